"""Named combinations of output, moment, curvature and norm."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import curvature, gradients, scoring
from .gradients import ID, TIMES


@dataclass(frozen=True)
class Preset:
    moment: bool
    hessian: str
    unit_norm: bool
    output: str = "loss"


PRESETS = {
    "mixed_cosine": Preset(True, "mixed", True),
    "exp1_plain_dot": Preset(False, "none", False),
    "exp2_plain_cosine": Preset(False, "none", True),
    "exp3_train_curvature_cosine": Preset(False, "train", True),
    "exp4_moment_cosine": Preset(True, "none", True),
    "exp5_moment_train_cosine": Preset(True, "train", True),
    "gradient_dot": Preset(True, "none", False),
    "margin_influence": Preset(False, "train", False, "margin_example"),
    "x_no_norm_train": Preset(False, "train", False),
    "x_no_norm_moment_train": Preset(True, "train", False),
    "x_no_norm_mixed": Preset(True, "mixed", False),
    "x_eval_cosine": Preset(True, "eval", True),
}
#: Every cell of output correction, curvature and norm; cells that have a name keep it.
GRID = {
    (moment, hessian, norm): next(
        (n for n, p in PRESETS.items() if p == Preset(moment, hessian, norm)),
        f"x_{'moment' if moment else 'plain'}_{hessian}_{'cosine' if norm else 'dot'}",
    )
    for moment in (False, True)
    for hessian in ("none", "train", "eval", "mixed")
    for norm in (False, True)
}
PRESETS.update({name: Preset(*cell) for cell, name in GRID.items()})
PRESETS["gradient_cosine"] = PRESETS["exp4_moment_cosine"]

CLOSED_SET_LAMBDA, OPEN_SET_LAMBDA = 0.90, 0.99


class Study:
    """Candidates, queries and a model, with indexes shared among presets."""

    def __init__(
        self,
        candidates: DataFrame,
        queries: DataFrame,
        model,
        spec: gradients.IndexSpec,
        moment: dict,
        lam: float | None = CLOSED_SET_LAMBDA,
        block_size: int = 2,
        damping: float = 1e-6,
        keep=None,
        k_copies: int = 10,
        keep_index: bool = True,
    ):
        self.candidates, self.queries, self.model = candidates, queries, model
        self.spec, self.moment, self.lam, self.block_size, self.damping = spec, moment, lam, block_size, damping
        self.keep, self.keep_index = keep or (lambda df: df), keep_index
        # candidates that stand for several examples carry `times` and `copies`
        self.copies = candidates.select(ID, "copies") if "copies" in candidates.columns else None
        self.k_copies = k_copies
        self._indexes: dict = {}
        self._curvatures: dict = {}

    def indexes(self, moment: bool, output: str = "loss") -> tuple[DataFrame, DataFrame]:
        """Candidate and query index; a preset that shares both flags shares them."""
        key = (moment, output)
        if key not in self._indexes:
            spec = self.spec.with_(moment=self.moment if moment else None, output=output)
            sides = [(self.candidates, spec.with_(extra=[TIMES] if self.copies is not None else [])), (self.queries, spec)]
            index, queries = (gradients.build_index(side, self.model, own) for side, own in sides)
            self._indexes[key] = (self.keep(index) if self.keep_index else index, self.keep(queries))
        return self._indexes[key]

    def use(self, moment: bool, index: DataFrame, queries: DataFrame, output: str = "loss") -> None:
        """Take ready indexes instead of building them."""
        self._indexes[moment, output] = (index, queries)

    def curvature(self, hessian: str, moment: bool, output: str = "loss") -> DataFrame | None:
        if hessian == "none":
            return None
        if (hessian, moment, output) in self._curvatures:
            return self._curvatures[hessian, moment, output]
        index, queries = self.indexes(moment, output)
        train = lambda: curvature.autocorrelation(index, self.block_size)
        own = lambda: curvature.autocorrelation(queries, self.block_size)
        if hessian == "mixed":
            r_eval, r_train = self.keep(own()), self.keep(train())
            lam = curvature.choose_lambda(r_eval, r_train) if self.lam is None else self.lam
            r = curvature.mix(r_eval, r_train, lam)
        else:
            r = train() if hessian == "train" else own()
        self._curvatures[hessian, moment, output] = self.keep(r)
        return self._curvatures[hessian, moment, output]

    def run(self, name: str, k: int = 10, ascending: bool = False, method: str = "eigh") -> DataFrame:
        p = PRESETS[name]
        index, queries = self.indexes(p.moment, p.output)
        r = self.curvature(p.hessian, p.moment, p.output)
        inverse = curvature.invert(r, self.damping, method=method) if r is not None else None
        return self.top_k(index, queries, k, inverse, p.unit_norm, ascending)

    def top_k(self, index: DataFrame, queries: DataFrame, k: int = 10, inverse: DataFrame | None = None, unit_norm: bool = True, ascending: bool = False) -> DataFrame:
        """Rankings of examples, each copy of a candidate counted."""
        if self.copies is not None and k > self.k_copies:
            raise ValueError(f"candidates carry {self.k_copies} copies, too few for rankings of {k}")
        return scoring.score_top_k(index, queries, k, inverse, unit_norm, ascending, copies=self.copies)

    def run_all(self, names: list[str], k: int = 10) -> DataFrame:
        """Rankings of several presets, with a `preset` column."""
        out = None
        for name in names:
            part = self.run(name, k).withColumn("preset", F.lit(name))
            out = part if out is None else out.unionByName(part)
        return out
