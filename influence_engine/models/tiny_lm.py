"""A small next-word model with exact gradients, trained by averaged local steps.

Three previous words are embedded, two tanh layers follow, then a softmax over the vocabulary.
The gradient of each indexed layer (the embedding is left out) is a sum over tokens of an
outer product, so projections and factored moments are applied to the two factors and no
layer gradient is ever built. The network is run once for each distinct context of a batch:
tokens with the same three words before them differ in the target alone, and all errors are
linear in the softmax's error.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import words
from ..functions.textops import tokenise
from ..functions.words import plain as _plain
from ..operators.gradients import ID, IndexSpec
from ..operators.projection import TwoSided
from ..operators.work import materialise

CONTEXT, EMBED, PAD, UNKNOWN = 3, 16, 0, 1
#: Share of the old second moments that a training step keeps.
DECAY = 0.9
WIDTHS = {"s": 16, "m": 32, "l": 64}
#: Contexts that are held against the whole vocabulary at once; sums over tokens are taken piece by piece.
PIECE = 256
#: Target tokens an example on average, from which examples count as long, and tokens of such a piece.
LONG, HELD_LONG = 16, 4096
#: Tokens whose contexts a task holds at once.
HELD_TOKENS = 1 << 18
#: Bytes of text that a task splits at once.
HELD_BYTES = words.HELD_BYTES
#: Batches whose counts a task hands on at once.
HELD_BATCHES = 64
BLOCKS = {"w1": ["w1"], "w2": ["w2"], "w3": ["w3"]}


def vocabulary(corpus: DataFrame, size: int = 1024) -> dict[str, int]:
    """Most frequent words, ties by word; ids 0 and 1 are padding and unknown."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for _, found in words.spelled(b.column(0), HELD_BYTES):
                yield pa.RecordBatch.from_arrays(found.value_counts().flatten(), names=["word", "n"])

    counts = corpus.select(_plain(F.col("text"))).mapInArrow(count, "word string, n long").groupBy("word").agg(F.sum("n").alias("n"))
    top = counts.orderBy(F.desc("n"), "word").limit(size - 2).collect()
    return {r["word"]: i + 2 for i, r in enumerate(top)}


def encode(df: DataFrame, vocab: dict[str, int], prompt: str | None = None, text: str = "text") -> DataFrame:
    """Add `tokens` (all words of the text) and `target_from`, the count of prompt words."""
    shared = df.sparkSession.sparkContext.broadcast((list(vocab), list(vocab.values())))

    @F.arrow_udf("array<int>")
    def ids(text: pa.Array) -> pa.Array:
        known, numbers = shared.value
        known, numbers = pa.array(known, pa.string()), np.array([*numbers, UNKNOWN], dtype=np.int32)
        found, sizes = [np.empty(0, np.int32)], [np.zeros(1, np.int64)]
        for counts, here in words.spelled(text, HELD_BYTES):
            at = pc.fill_null(pc.index_in(here, value_set=known), len(known)).to_numpy(zero_copy_only=False)
            found.append(numbers[at])
            sizes.append(counts)
        return pa.ListArray.from_arrays(pa.array(np.cumsum(np.concatenate(sizes)).astype(np.int32)), pa.array(np.concatenate(found)))

    start = F.size(tokenise(F.col(prompt))) if prompt else F.lit(0)
    return df.withColumn("tokens", ids(_plain(F.col(text)))).withColumn("target_from", start.cast("int"))


@dataclass
class TinyLM:
    """Weights by layer name; `moment` has (row, column) factors of each layer's second moment.

    `rate` is the one of the last training step.
    """

    weights: dict[str, np.ndarray]
    moment: dict[str, tuple[np.ndarray, np.ndarray]]
    rate: float = 0.0

    columns = ["tokens", "target_from"]

    @classmethod
    def start(cls, vocab_size: int, width: int, seed: int = 3) -> TinyLM:
        rng = np.random.default_rng(seed)
        shapes = {"emb": (vocab_size, EMBED), "w1": (width, CONTEXT * EMBED), "w2": (width, width), "w3": (vocab_size, width)}
        weights = {k: rng.normal(size=s) / np.sqrt(s[1] if k != "emb" else 4) for k, s in shapes.items()}
        return cls(weights, {k: (np.full(s[0], 1e-4), np.full(s[1], 1e-4)) for k, s in shapes.items()})

    @property
    def layers(self) -> dict[str, tuple[int, int]]:
        return {k: self.weights[k].shape for k in ("w1", "w2", "w3")}

    def forward(self, context: np.ndarray):
        x = self.weights["emb"][context].reshape(len(context), -1)
        h1 = np.tanh(x @ self.weights["w1"].T)
        h2 = np.tanh(h1 @ self.weights["w2"].T)
        z = h2 @ self.weights["w3"].T
        z -= z.max(axis=1, keepdims=True)
        p = np.exp(z, out=z)
        p *= 1 / p.sum(axis=1, keepdims=True)
        return x, h1, h2, p

    def factors(self, context: np.ndarray, target: np.ndarray, weight=None):
        """Per token and layer: (error, input), so the layer's gradient is error outer input; and the target's probability."""
        x, h1, h2, p = self.forward(context)
        at = np.arange(len(target))
        own = p[at, target].copy()
        e3 = p
        e3[at, target] -= 1
        if weight is not None:
            e3 = e3 * weight(own)[:, None]
        e2 = (e3 @ self.weights["w3"]) * (1 - h2 * h2)
        e1 = (e2 @ self.weights["w2"]) * (1 - h1 * h1)
        return {"w3": (e3, h2), "w2": (e2, h1), "w1": (e1, x)}, own

    def step(self, context: np.ndarray, target: np.ndarray, rate: float, decay: float | None = None) -> TinyLM:
        """One update by the mean gradient over its factored root second moment.

        With a decay the moments move too, as in training; without, they stay.
        """
        return self.step_counted(counted(context, target, len(self.weights["emb"])), rate, decay)

    def step_counted(self, given: Counted, rate: float, decay: float | None = None, kind: type = np.float64) -> TinyLM:
        """The same update from the counts of a batch, which do not depend on the weights.

        The pass forward and back is in the given precision; sums, moments and weights are in double.
        """
        steps = Steps(self, kind)
        steps.take(given, rate, decay)
        return steps.model()

    # --- kernels over Arrow batches

    def _targets(self, batch: pa.RecordBatch):
        """Contexts and targets of all target tokens, with the example of each."""
        return _laid(*_lists(batch.column("tokens")), batch.column("target_from").to_numpy())

    def _weight(self, output: str, owner: np.ndarray, n: int):
        if output == "loss":
            return None
        if output == "margin_token":
            return lambda p: -1 / np.maximum(1 - p, 1e-6)

        def per_example(p: np.ndarray) -> np.ndarray:
            mean = np.bincount(owner, p, n) / np.maximum(np.bincount(owner, minlength=n), 1)
            return -1 / np.maximum(1 - mean, 1e-6)[owner]

        return per_example

    def gradients(self, batch: pa.RecordBatch, output: str = "loss") -> dict[str, np.ndarray]:
        """Layer gradients in full, summed over target tokens; for tests and small layers."""
        context, target, owner = self._targets(batch)
        f, _ = self.factors(context, target, self._weight(output, owner, batch.num_rows))
        out = {k: np.zeros((batch.num_rows, *self.layers[k])) for k in f}
        for k, (e, i) in f.items():
            np.add.at(out[k], owner, e[:, :, None] * i[:, None, :])
        return out

    def projected(self, batch: pa.RecordBatch, spec: IndexSpec) -> dict[str, np.ndarray]:
        """Fused path: both factors are corrected and projected before they meet."""
        assert isinstance(spec.projection, TwoSided)
        layers = [k for names in spec.blocks.values() for k in names]
        sides = {k: spec.projection.factors(k, *self.layers[k]) for k in layers}
        if spec.moment is not None:
            for k, (left, right) in sides.items():
                r, c = spec.moment[k]
                sides[k] = left / np.sqrt(r + spec.eps), right * (np.sqrt(r.mean()) / np.sqrt(c + spec.eps))
        sums = {k: np.zeros((batch.num_rows, len(left) * len(right))) for k, (left, right) in sides.items()}
        for rows in stretches(pc.list_value_length(batch.column("tokens")).to_numpy()):
            self._project(batch.slice(rows.start, rows.stop - rows.start), spec.output, sides, {k: v[rows] for k, v in sums.items()})
        return {block: np.concatenate([sums[k] for k in names], axis=1) for block, names in spec.blocks.items()}

    def _project(self, batch: pa.RecordBatch, output: str, sides: dict, sums: dict[str, np.ndarray]) -> None:
        """Add the projected gradients of few examples to their rows of `sums`."""
        context, target, owner = self._targets(batch)
        seen, which, order = distinct(context, len(self.weights["emb"]))
        w2, w3 = self.weights["w2"], self.weights["w3"]
        own = np.zeros(len(target))
        ends = np.cumsum(np.bincount(which, minlength=len(seen)))
        error = np.empty((len(seen), len(sides["w3"][0]) if "w3" in sides else 0))
        back, d2, d1 = np.empty((len(seen), w3.shape[1])), np.empty((len(seen), w2.shape[0])), np.empty((len(seen), w2.shape[1]))
        inputs = {k: np.empty((len(seen), len(right))) for k, (_, right) in sides.items()}
        for some in pieces(len(seen)):
            x, h1, h2, p = self.forward(seen[some])
            at = order[ends[some.start - 1] if some.start else 0 : ends[min(some.stop, len(seen)) - 1]]
            own[at] = p[which[at] - some.start, target[at]]
            if "w3" in sides:
                np.matmul(p, sides["w3"][0].T, out=error[some])
            np.matmul(p, w3, out=back[some])
            d2[some], d1[some] = 1 - h2 * h2, 1 - h1 * h1
            for k, i in (("w1", x), ("w2", h1), ("w3", h2)):
                if k in sides:
                    np.matmul(i, sides[k][1].T, out=inputs[k][some])
        if not len(target):
            return
        weight = self._weight(output, owner, batch.num_rows)
        # a weight may depend on all tokens of an example, so it is settled before the pieces
        scale = None if weight is None else weight(own)
        # the outer products of a long example are summed by one product of matrices, those of short ones side by side
        long = len(target) >= LONG * batch.num_rows
        for some in pieces(len(target), HELD_LONG if long else PIECE):
            c, t, o = which[some], target[some], owner[some]
            e2 = (back[c] - w3[t]) * d2[c]
            e = {"w2": e2, "w1": (e2 @ w2) * d1[c]}
            firsts = np.flatnonzero(np.r_[True, o[1:] != o[:-1]])
            for k, (left, _) in sides.items():
                a = error[c] - left.T[t] if k == "w3" else e[k] @ left.T
                if scale is not None:
                    a = a * scale[some, None]
                i = inputs[k][c]
                if long:
                    for at, end in zip(firsts, [*firsts[1:], len(a)]):
                        sums[k][o[at]] += (a[at:end].T @ i[at:end]).ravel()
                else:
                    sums[k][o[firsts]] += np.add.reduceat((a[:, :, None] * i[:, None, :]).reshape(len(a), -1), firsts, axis=0)

    def _own(self, context: np.ndarray, target: np.ndarray) -> np.ndarray:
        """Probability of each target token."""
        own = np.zeros(len(target))
        for some in pieces(len(target)):
            t = target[some]
            own[some] = self.forward(context[some])[3][np.arange(len(t)), t]
        return own

    def log_probability(self, tokens: list[list[int]], target_from: list[int]) -> np.ndarray:
        """Log probability of each target sequence after its prompt."""
        context, target, owner = contexts(tokens, target_from)
        if not len(target):
            return np.zeros(len(tokens))
        p = self._own(context, target)
        return np.bincount(owner, np.log(np.maximum(p, 1e-300)), len(tokens))

    def complete(self, tokens: list[int], most: int = 3) -> list[int]:
        """Greedy continuation."""
        out = list(tokens)
        for _ in range(most):
            context = np.array([([PAD] * CONTEXT + out)[-CONTEXT:]])
            out.append(int(self.forward(context)[3][0].argmax()))
        return out[len(tokens) :]


class Steps:
    """Updates of a model in arrays of its own: many steps in a row allocate none of the layers' size anew.

    The embedding's gradient is zero but in the rows of words that a batch's contexts hold, so
    only these are moved. The pass forward and back is in the given precision.
    """

    def __init__(self, model: TinyLM, kind: type = np.float64):
        self.weights = {k: w.copy() for k, w in model.weights.items()}
        self.moment = dict(model.moment)
        self.rate, self.kind = model.rate, kind
        self._own = TinyLM({k: w.astype(kind, copy=False) for k, w in self.weights.items()}, self.moment)
        self._grads = {k: np.empty(shape) for k, shape in model.layers.items()}
        self._roots = {k: np.empty(shape) for k, shape in model.layers.items()}

    def model(self) -> TinyLM:
        return TinyLM(self.weights, dict(self.moment), self.rate)

    def take(self, given: Counted, rate: float, decay: float | None = None) -> None:
        """One step on the counts of a batch."""
        n = max(1, int(given.times.sum()))
        own, grads, seen, at = self._own, self._grads, given.seen, given.at
        words, which = np.unique(seen, return_inverse=True)
        which = which.reshape(-1, 1) * EMBED + np.arange(EMBED)
        emb = np.zeros(len(words) * EMBED)
        times = np.bincount(at, given.times, len(seen)).astype(self.kind)
        for g in grads.values():
            g.fill(0)
        for some in pieces(len(seen)):
            x, h1, h2, e3 = own.forward(seen[some])
            # the errors of all tokens with one context are summed before they go back
            e3 *= times[some, None]
            pairs = slice(*np.searchsorted(at, (some.start, some.stop)))
            e3[at[pairs] - some.start, given.target[pairs]] -= given.times[pairs].astype(self.kind)
            e2 = (e3 @ own.weights["w3"]) * (1 - h2 * h2)
            e1 = (e2 @ own.weights["w2"]) * (1 - h1 * h1)
            for k, e, i in (("w3", e3, h2), ("w2", e2, h1), ("w1", e1, x)):
                grads[k] += e.T @ i
            held = which[some.start * CONTEXT : some.stop * CONTEXT].ravel()
            emb += np.bincount(held, (e1 @ own.weights["w1"]).ravel(), len(emb))
        for k, g in grads.items():
            self._move(k, g, self._roots[k], slice(None), n, rate, decay)
        rows = emb.reshape(len(words), EMBED)
        self._move("emb", rows, np.empty_like(rows), words, n, rate, decay)
        self.rate = rate

    def _move(self, k: str, g: np.ndarray, root: np.ndarray, rows, n: int, rate: float, decay: float | None) -> None:
        """Move some rows of a layer by their gradient, which is zero in all others."""
        g *= 1 / n
        r, c = self.moment[k]
        if decay is not None:
            sq = np.multiply(g, g, out=root)
            # means by products with ones, which are quicker than reductions
            mean = np.zeros(len(r))
            mean[rows] = sq @ np.full(len(c), 1 / len(c))
            r, c = decay * r + (1 - decay) * (mean + 1e-12), decay * c + (1 - decay) * (np.full(len(g), 1 / len(r)) @ sq + 1e-12)
            self.moment[k] = r, c
        np.multiply.outer((r / r.mean())[rows], c, out=root)
        root += 1e-12
        np.divide(g, np.sqrt(root, out=root), out=g)
        # updates are clipped to unit root mean square, as factored optimisers do
        weights = self.weights[k]
        g *= -rate / max(1.0, float(np.sqrt(np.vdot(g, g) / weights.size)))
        weights[rows] += g
        own = self._own.weights[k]
        if own is not weights:
            own[rows] = weights[rows]


def pieces(n: int, size: int | None = None) -> list[slice]:
    size = size or PIECE
    return [slice(a, a + size) for a in range(0, n, size)]


def stretches(sizes: np.ndarray, most: int | None = None) -> list[slice]:
    """Runs of rows of about HELD_TOKENS tokens, or of another sum of sizes."""
    return words.stretches(sizes, most or HELD_TOKENS)


def distinct(context: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The distinct contexts, which of them each token has, and the tokens ordered by that."""
    key = context[:, 0]
    for i in range(1, CONTEXT):
        key = key * size + context[:, i]
    order = np.argsort(key, kind="stable")
    ranked = key[order]
    new = np.ones(len(key), dtype=bool)
    np.not_equal(ranked[1:], ranked[:-1], out=new[1:])
    which = np.empty(len(key), dtype=np.int64)
    which[order] = np.cumsum(new) - 1
    return context[order[new]], which, order


@dataclass
class Counted:
    """A batch's distinct contexts, and how often each (context `at`, target) occurs, in that order."""

    seen: np.ndarray
    at: np.ndarray
    target: np.ndarray
    times: np.ndarray


def counted(context: np.ndarray, target: np.ndarray, size: int) -> Counted:
    seen, which, _ = distinct(context, size)
    pair, times = np.unique(which * size + target, return_counts=True)
    return Counted(seen, pair // size, pair % size, times)


def contexts(tokens: list[list[int]], target_from: list[int]):
    """(contexts, targets, example numbers) of the tokens from target_from on."""
    sizes = np.array([len(t) for t in tokens], dtype=np.int64)
    flat = np.concatenate([np.asarray(t, dtype=np.int64) for t in tokens]) if tokens else np.empty(0, np.int64)
    return _laid(flat, sizes, np.asarray(target_from, dtype=np.int64))


def _lists(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """All tokens of a column of lists, and the number of each row."""
    return column.flatten().to_numpy().astype(np.int64), pc.list_value_length(column).to_numpy().astype(np.int64)


def _laid(flat: np.ndarray, sizes: np.ndarray, target_from: np.ndarray):
    owner = np.repeat(np.arange(len(sizes)), sizes)
    nth = np.arange(len(flat)) - (np.cumsum(sizes) - sizes)[owner]
    padded = np.full(len(flat) + CONTEXT * len(sizes), PAD, dtype=np.int64)
    padded[np.arange(len(flat)) + CONTEXT * (owner + 1)] = flat
    keep = np.flatnonzero(nth >= target_from[owner])
    owner = owner[keep]
    place = keep + CONTEXT * owner
    return np.stack([padded[place + i] for i in range(CONTEXT)], axis=1), padded[place + CONTEXT], owner


def batches_of(tokens: DataFrame, vocab_size: int, turns: int = 4, workers: int = 4, batch: int = 256) -> DataFrame:
    """What training reads: a row of counts for each batch, (turn, worker, nth, seen, at, target, times).

    Examples are dealt to turns and workers by hashes of their ids and ordered by id; `turns` rounds
    are an epoch. Neither order nor counts depend on the weights, so all rounds and models share them.
    """
    turn, worker = F.pmod(F.xxhash64(F.lit(5), ID), F.lit(turns)), F.pmod(F.hash(ID), F.lit(workers))
    dealt = tokens.select(ID, "tokens", (turn * workers + worker).cast("int").alias("share"))

    def count(found: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        nth = 0
        for b in found:
            rows, share, out = b.column("tokens"), b.column("share")[0].as_py() if b.num_rows else 0, []
            for at in range(0, len(rows), batch):
                flat, sizes = _lists(rows.slice(at, batch))
                context, target, _ = _laid(flat, sizes, np.zeros(len(sizes), dtype=np.int64))
                if len(target):
                    c = counted(context, target, vocab_size)
                    out.append((share // workers, share % workers, nth, c.seen.ravel(), c.at, c.target, c.times))
                    nth += 1
                if len(out) == HELD_BATCHES or out and at + batch >= len(rows):
                    yield pa.RecordBatch.from_arrays([pa.array([x[i] for x in out], t) for i, t in enumerate(kinds)], names=names)
                    out = []

    ints = pa.list_(pa.int32())
    names, kinds = ["turn", "worker", "nth", "seen", "at", "target", "times"], [pa.int32(), pa.int32(), pa.int64(), ints, ints, ints, ints]
    ddl = "turn int, worker int, nth long, seen array<int>, at array<int>, target array<int>, times array<int>"
    return dealt.repartitionById(turns * workers, "share").sortWithinPartitions(ID).mapInArrow(count, ddl)


def fit(
    tokens: DataFrame,
    vocab_size: int,
    size: str = "m",
    epochs: int = 2,
    rounds: int = 8,
    workers: int = 4,
    rate: float = 0.02,
    batch: int = 256,
    given: DataFrame | None = None,
) -> list[TinyLM]:
    """Train and return a checkpoint after each round.

    Each round takes its share of the examples (by hash of the id, all of them once an epoch);
    workers start from the broadcast model, make local steps, and their weights are averaged.
    What reaches the driver has the size of the model times the workers. `given` are the
    batches of these tokens, where they are written already. Passes are in single precision.
    """
    spark = tokens.sparkSession
    model = TinyLM.start(vocab_size, WIDTHS[size])
    names = list(model.weights)
    per_epoch = max(1, rounds // epochs)
    if given is None:
        given = materialise(batches_of(tokens, vocab_size, per_epoch, workers, batch), "batches")
    out = []
    for r in range(rounds):
        shared = spark.sparkContext.broadcast(model)
        pace = rate * (1 - 0.9 * r / rounds)

        def train(batches: Iterator[pa.RecordBatch], shared=shared, pace=pace) -> Iterator[pa.RecordBatch]:
            own, n = Steps(shared.value, np.float32), 0
            for b in batches:
                columns = [b.column(b.schema.get_field_index(k)) for k in ("seen", "at", "target", "times")]
                for i in range(b.num_rows):
                    # only one row's counts are widened at a time
                    seen, *pairs = (_lists(column.slice(i, 1))[0] for column in columns)
                    own.take(Counted(seen.reshape(-1, CONTEXT), *pairs), pace, DECAY)
                    n += int(pairs[-1].sum())
            if n:
                w = [own.weights[k].astype(np.float64).tobytes() for k in names]
                m = [own.moment[k][i].tobytes() for k in names for i in (0, 1)]
                yield pa.RecordBatch.from_pydict({"n": [n], "w": [w], "m": [m]})

        part = given.filter(F.col("turn") == r % per_epoch).repartitionById(workers, "worker").sortWithinPartitions("nth")
        got = sorted((x["n"], [bytes(y) for y in x["w"]], [bytes(y) for y in x["m"]]) for x in part.mapInArrow(train, "n long, w array<binary>, m array<binary>").collect())
        total = sum(n for n, _, _ in got)
        if total:
            weights = {k: sum(n * np.frombuffer(w[i]).reshape(model.weights[k].shape) for n, w, _ in got) / total for i, k in enumerate(names)}
            moment = {
                k: tuple(sum(n * np.frombuffer(m[2 * i + j]) for n, _, m in got) / total for j in (0, 1)) for i, k in enumerate(names)
            }
            model = TinyLM(weights, moment, pace)
        shared.unpersist()
        out.append(model)
    return out


def complete(queries: DataFrame, model: TinyLM, vocab: dict[str, int], most: int = 3) -> DataFrame:
    """(query_id, fact_id, prediction): greedy words after each prompt."""
    shared = queries.sparkSession.sparkContext.broadcast((model, {i: w for w, i in vocab.items()}))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m, words = shared.value
        for b in batches:
            said = []
            for tokens, start in zip(b.column("tokens").to_pylist(), b.column("target_from").to_pylist()):
                said.append(" ".join(words.get(i, "?") for i in m.complete(tokens[:start], most)))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(said, pa.string())], names=["query_id", "fact_id", "prediction"])

    return queries.select("query_id", "fact_id", "tokens", "target_from").mapInArrow(run, "query_id long, fact_id long, prediction string")


def tail_patch(ranked: DataFrame, candidates: DataFrame, queries: DataFrame, model: TinyLM) -> DataFrame:
    """Change of the target's probability by one training step on one candidate.

    The step is the one that training would take next: its last rate, and moments that move.
    Pairs are sorted by the candidate's tokens, so candidates of the same tokens share a step and
    its answers; patched weights stay in the task.
    Columns of `ranked`, then p_before, p_after, delta.
    """
    shared = ranked.sparkSession.sparkContext.broadcast(model)
    keep = ranked.columns
    pairs = ranked.join(candidates.select(ID, F.col("tokens").alias("m_tokens")), ID).join(
        queries.select("query_id", F.col("tokens").alias("q_tokens"), "target_from"), "query_id"
    )

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m, last, patched = shared.value, None, None
        at_first, since = {}, {}
        for b in batches:
            before, after = [], []
            for own, q, start in zip(*(b.column(b.schema.get_field_index(c)).to_pylist() for c in ("m_tokens", "q_tokens", "target_from"))):
                if own != last:
                    context, target, _ = contexts([own], [0])
                    last, patched, since = own, m.step(context, target, m.rate, DECAY) if len(target) else m, {}
                asked = (*q, start)
                for said, by in ((at_first, m), (since, patched)):
                    if asked not in said:
                        said[asked] = float(np.exp(by.log_probability([q], [start])[0]))
                before.append(at_first[asked])
                after.append(since[asked])
            p, a = np.array(before), np.array(after)
            cols = [b.column(b.schema.get_field_index(c)) for c in keep]
            yield pa.RecordBatch.from_arrays([*cols, pa.array(p), pa.array(a), pa.array(a - p)], names=[*keep, "p_before", "p_after", "delta"])

    ddl = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in ranked.schema) + ", p_before double, p_after double, delta double"
    return pairs.repartition("m_tokens").sortWithinPartitions("m_tokens").mapInArrow(run, ddl)
