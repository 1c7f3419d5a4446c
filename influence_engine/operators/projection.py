"""Projections of layer gradients (rows by columns) to few numbers."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from ..functions.randoms import gauss_matrix


@dataclass(frozen=True)
class TwoSided:
    """A Gaussian matrix on either side of each layer gradient; d is k_out times k_in per layer.

    A sub-grid of both factors is itself a projection, so indexes of smaller dimension are
    cut from larger ones.
    """

    seed: int
    k_out: int
    k_in: int

    def size(self, rows: int, cols: int) -> int:
        return self.k_out * self.k_in

    def factors(self, layer: str, rows: int, cols: int) -> tuple[np.ndarray, np.ndarray]:
        return (
            gauss_matrix(self.seed, f"{layer}:out", self.k_out, rows),
            gauss_matrix(self.seed, f"{layer}:in", self.k_in, cols),
        )

    def apply(self, layer: str, g: np.ndarray) -> np.ndarray:
        left, right = self.factors(layer, *g.shape[1:])
        return np.einsum("ar,nrc,bc->nab", left, g, right, optimize=True).reshape(len(g), -1)


@dataclass(frozen=True)
class OneSided:
    """A Gaussian matrix on the flattened layer gradient."""

    seed: int
    d: int

    def size(self, rows: int, cols: int) -> int:
        return self.d

    def apply(self, layer: str, g: np.ndarray) -> np.ndarray:
        flat = g.reshape(len(g), -1)
        return flat @ gauss_matrix(self.seed, f"{layer}:flat", self.d, flat.shape[1]).T


@dataclass(frozen=True)
class Identity:
    """No projection; the index holds every parameter."""

    def size(self, rows: int, cols: int) -> int:
        return rows * cols

    def apply(self, layer: str, g: np.ndarray) -> np.ndarray:
        return g.reshape(len(g), -1)


class QueryBasis:
    """The leading singular directions of the query gradients of each layer.

    It ties the index to one set of queries: other queries need all candidates anew.
    """

    def __init__(self, query_gradients: dict[str, np.ndarray], rank: int):
        self.basis = {}
        for layer, g in query_gradients.items():
            _, _, vt = np.linalg.svd(g.reshape(len(g), -1), full_matrices=False)
            self.basis[layer] = vt[:rank]

    def size(self, rows: int, cols: int) -> int:
        return max(len(b) for b in self.basis.values())

    def apply(self, layer: str, g: np.ndarray) -> np.ndarray:
        return g.reshape(len(g), -1) @ self.basis[layer].T
