"""Queries on the softmax probe over `embeddings`, each with DuckDB SQL of the same values."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..models.probe import SoftmaxProbe, matrix
from ..operators import curvature, gradients, measures, scoring
from ..operators.gradients import ID, IndexSpec
from ..operators.presets import GRID, PRESETS, Study
from ..operators.projection import Identity, OneSided, QueryBasis, TwoSided
from ..sources import catalog

SCALE, EPS, DAMPING, LAM, SEED = 8.0, 1e-8, 1e-6, 0.9, 7
K_OUT, K_IN, EVERY, TOP = 4, 4, 100, 10
BETA, SAMPLED = 0.9, 25


def _candidates(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = catalog.load(spark, sf_dir, "embeddings")
    return vectors.select(F.col("vec_id").alias(ID), F.col("embedding").cast("array<double>").alias("embedding"), "label")


def _queries(candidates: DataFrame) -> DataFrame:
    """Every row whose id is divisible by 100."""
    return candidates.filter(F.col(ID) % EVERY == 0)


def _probe(candidates: DataFrame) -> SoftmaxProbe:
    return SoftmaxProbe.from_means(candidates, SCALE)


def _spec(projection=None, **more) -> IndexSpec:
    return IndexSpec({"b0": ["w"]}, projection or TwoSided(SEED, K_OUT, K_IN), eps=EPS, **more)


def study(spark: SparkSession, sf_dir: str, block_size: int = 2) -> Study:
    """Mixed-cosine study of the probe: every embedding a candidate, ids divisible by 100 as queries."""
    candidates = _candidates(spark, sf_dir)
    probe = _probe(candidates)
    moment = gradients.diagonal_moment(candidates, probe)
    return Study(candidates, _queries(candidates), probe, _spec(), moment, LAM, block_size, DAMPING)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _ranking("mixed_cosine")(spark, sf_dir)


def _rounded(df: DataFrame) -> DataFrame:
    return df.select("query_id", "rank", ID, F.round("score", 6).alias("score"))


def _ranking(preset: str, ascending: bool = False, block_size: int = 2):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return _rounded(study(spark, sf_dir, block_size).run(preset, TOP, ascending))

    return run


# --- the same steps in DuckDB: one chain of views, cut where a query ends


def _gauss(tag: str, row: str, col: str, rows: int) -> str:
    key = f"md5('{SEED}:{tag}:' || {row} || ':' || {col})"
    u = f"((('0x' || substr({key}, 1, 8))::UBIGINT + 1)::DOUBLE / 4294967297.0)"
    v = f"(('0x' || substr({key}, 9, 8))::UBIGINT::DOUBLE / 4294967296.0)"
    return f"sqrt(-2.0 * ln({u})) * cos(2.0 * pi() * {v}) / sqrt({float(rows)})"


def _chain(output: str = "loss", moment: bool = True, one_sided: int | None = None, k_out: int = K_OUT, k_in: int = K_IN) -> str:
    residual = {
        "loss": "p - hit",
        "margin_example": "-(p - hit) / (1 - pt)",
        "logit": "hit::DOUBLE",
    }[output]
    corrected = f"g / sqrt(m + {EPS})" if moment else "g"
    if one_sided:
        project = f"""
            rb AS (SELECT i.range AS i, q.range AS q, {_gauss('w:flat', 'i.range', 'q.range', one_sided)} AS u
                   FROM range({one_sided}) i, (SELECT range FROM range((SELECT count(DISTINCT c) * count(DISTINCT j) FROM wt))) q),
            ix AS (SELECT vec_id, i, sum(u * g) AS w FROM h JOIN rb ON q = c * (SELECT count(DISTINCT j) FROM wt) + j GROUP BY 1, 2)"""
    else:
        project = f"""
            la AS (SELECT a.range AS a, c, {_gauss('w:out', 'a.range', 'c', K_OUT)} AS l FROM range({K_OUT}) a, (SELECT DISTINCT c FROM wt)),
            rb AS (SELECT b.range AS b, j, {_gauss('w:in', 'b.range', 'j', K_IN)} AS u FROM range({K_IN}) b, (SELECT DISTINCT j FROM wt)),
            half AS (SELECT vec_id, a, j, sum(l * g) AS t FROM h JOIN la USING (c) WHERE a < {k_out} GROUP BY 1, 2, 3),
            ix AS (SELECT vec_id, a * {k_in} + b AS i, sum(u * t) AS w FROM half JOIN rb USING (j) WHERE b < {k_in} GROUP BY 1, 2)"""
    return f"""
        WITH e AS (SELECT vec_id, label, embedding::DOUBLE[] AS v FROM embeddings),
        x AS (SELECT vec_id, label, unnest(v) AS x, generate_subscripts(v, 1) - 1 AS j FROM e),
        wt AS (SELECT label AS c, j, avg(x) AS w FROM x GROUP BY 1, 2),
        z AS (SELECT vec_id, label, c, {SCALE} * sum(x * w) AS z FROM x JOIN wt USING (j) GROUP BY 1, 2, 3),
        ez AS (SELECT vec_id, label, c, exp(z - max(z) OVER (PARTITION BY vec_id)) AS ez FROM z),
        p AS (SELECT vec_id, label, c, (label = c)::INT AS hit, ez / sum(ez) OVER (PARTITION BY vec_id) AS p FROM ez),
        pt AS (SELECT *, max(p * hit) OVER (PARTITION BY vec_id) AS pt FROM p),
        r AS (SELECT vec_id, c, {residual} AS r, p - hit AS r0 FROM pt),
        g AS (SELECT vec_id, c, j, {SCALE} * r * x AS g, {SCALE} * r0 * x AS g0 FROM r JOIN x USING (vec_id)),
        m AS (SELECT c, j, avg(g0 * g0) AS m FROM g GROUP BY 1, 2),
        h AS (SELECT vec_id, c, j, {corrected} AS g FROM g JOIN m USING (c, j)),
        {project}"""


def _curvature_sql(hessian: str, size: int) -> str:
    """Views rt, re and rm(s, i, j, r): autocorrelation of training, evaluation, and the one used."""
    pick = {"train": "SELECT * FROM rt", "eval": "SELECT * FROM re"}.get(
        hessian, f"SELECT s, i, j, {LAM} * re.r + (1 - {LAM}) * rt.r AS r FROM re JOIN rt USING (s, i, j)"
    )
    pair = f"""SELECT a.i // {size} AS s, a.i % {size} AS i, b.i % {size} AS j, avg(a.w * b.w) AS r FROM {{0}} a JOIN {{0}} b
               ON a.vec_id = b.vec_id AND a.i // {size} = b.i // {size} GROUP BY 1, 2, 3"""
    return f""",
        rt AS ({pair.format('ix')}),
        qx AS (SELECT * FROM ix WHERE vec_id % {EVERY} = 0),
        re AS ({pair.format('qx')}),
        rm AS ({pick})"""


def _inverse_sql(size: int) -> str:
    if size == 1:
        return f""",
        iv AS (SELECT s, 0 AS i, 0 AS j, 1 / (r * (1 + {DAMPING})) AS v FROM rm)"""
    return f""",
        rd AS (SELECT s, max(CASE WHEN i = 0 AND j = 0 THEN r END) AS a, max(CASE WHEN i = 0 AND j = 1 THEN r END) AS b,
                      max(CASE WHEN i = 1 AND j = 1 THEN r END) AS d FROM rm GROUP BY 1),
        rc AS (SELECT s, a + {DAMPING} * (a + d) / 2 AS a, b, d + {DAMPING} * (a + d) / 2 AS d FROM rd),
        iv AS (SELECT s, 0 AS i, 0 AS j, d / (a * d - b * b) AS v FROM rc UNION ALL
               SELECT s, 1, 1, a / (a * d - b * b) FROM rc UNION ALL
               SELECT s, 0, 1, -b / (a * d - b * b) FROM rc UNION ALL
               SELECT s, 1, 0, -b / (a * d - b * b) FROM rc)"""


def _scores_sql(hessian: str, unit_norm: bool, size: int, sign: str = "") -> str:
    """Views y (folded side), nm (norms) and sc(query_id, example_id, score)."""
    fold = (
        "y AS (SELECT vec_id, i, w AS y FROM ix)"
        if hessian == "none"
        else f"y AS (SELECT vec_id, s * {size} + iv.i AS i, sum(v * w) AS y FROM ix JOIN iv ON i // {size} = s AND ix.i % {size} = iv.j GROUP BY 1, 2)"
    )
    if hessian != "none":
        fold = fold.replace("ON i //", "ON ix.i //")
    score = "sum(y.y * ix.w)" if not unit_norm else "sum(y.y * ix.w) / (any_value(nq.n) * any_value(nm.n))"
    return f""",
        {fold},
        nm AS (SELECT vec_id, sqrt(sum(y * w)) AS n FROM ix JOIN y USING (vec_id, i) GROUP BY 1),
        sc AS (SELECT y.vec_id AS query_id, ix.vec_id AS example_id, {sign}round({score}, 8) AS score
               FROM y JOIN ix USING (i) JOIN nm nq ON nq.vec_id = y.vec_id JOIN nm ON nm.vec_id = ix.vec_id
               WHERE y.vec_id % {EVERY} = 0 GROUP BY 1, 2)"""


def _top_sql(order: str = "DESC", k: int = TOP) -> str:
    return f"""
        SELECT query_id, rank::INT AS rank, example_id, round(score, 6) AS score FROM
        (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score {order}, example_id) AS rank FROM sc) WHERE rank <= {k}"""


def _ranking_sql(preset: str, order: str = "DESC", size: int = 2) -> str:
    p = PRESETS[preset]
    out = _chain(p.output, p.moment)
    if p.hessian != "none":
        out += _curvature_sql(p.hessian, size) + _inverse_sql(size)
    return out + _scores_sql(p.hessian, p.unit_norm, size) + _top_sql(order)


# --- single steps


def _rows(spark: SparkSession, sf_dir: str, fn, ddl: str) -> DataFrame:
    candidates = _candidates(spark, sf_dir)
    shared = spark.sparkContext.broadcast(_probe(candidates))

    def run(batches):
        for b in batches:
            if b.num_rows:
                yield pa.RecordBatch.from_pydict(fn(shared.value, b))

    return candidates.mapInArrow(run, ddl)


def probe_probabilities(spark: SparkSession, sf_dir: str) -> DataFrame:
    def fn(probe, b):
        p = probe.probabilities(matrix(b.column("embedding")))
        n, c = p.shape
        return {ID: np.repeat(b.column(0).to_numpy(), c), "class": np.tile(np.arange(c), n), "p": p.ravel()}

    return _rows(spark, sf_dir, fn, f"{ID} long, class long, p double").withColumn("p", F.round("p", 6))


def _gradient_query(output: str):
    def fn(probe, b):
        g = probe.gradients(b, output)["w"]
        n, c, d = g.shape
        return {
            ID: np.repeat(b.column(0).to_numpy(), c * d),
            "class": np.tile(np.repeat(np.arange(c), d), n),
            "dim": np.tile(np.arange(d), n * c),
            "g": g.ravel(),
        }

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return _rows(spark, sf_dir, fn, f"{ID} long, class long, dim long, g double").withColumn("g", F.round("g", 6))

    return run


def _moment_table(spark: SparkSession, moment: dict) -> DataFrame:
    v = moment["w"]
    rows = [(int(c), int(j), float(v[c, j])) for c in range(v.shape[0]) for j in range(v.shape[1])]
    return spark.createDataFrame(rows, "class long, dim long, v double")


def moment_diagonal(spark: SparkSession, sf_dir: str) -> DataFrame:
    candidates = _candidates(spark, sf_dir)
    return _moment_table(spark, gradients.diagonal_moment(candidates, _probe(candidates))).withColumn("v", F.round("v", 8))


def moment_factored(spark: SparkSession, sf_dir: str) -> DataFrame:
    candidates = _candidates(spark, sf_dir)
    rows, cols = gradients.factored(gradients.diagonal_moment(candidates, _probe(candidates)))["w"]
    v = rows[:, None] * cols[None, :] / rows.mean()
    return _moment_table(spark, {"w": v}).withColumn("v", F.round("v", 8))


def _index(spark: SparkSession, sf_dir: str, projection=None, moment: bool = True) -> DataFrame:
    candidates = _candidates(spark, sf_dir)
    probe = _probe(candidates)
    own = gradients.diagonal_moment(candidates, probe) if moment else None
    return gradients.build_index(candidates, probe, _spec(projection, moment=own))


def _long(index: DataFrame) -> DataFrame:
    return index.select(ID, F.posexplode("b0").alias("i", "w")).select(ID, F.col("i").cast("long").alias("i"), F.round("w", 6).alias("w"))


def moment_corrected_gradient(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _long(_index(spark, sf_dir, Identity()))


def project_identity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _long(_index(spark, sf_dir, Identity(), moment=False))


def project_two_sided(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _long(_index(spark, sf_dir))


def project_one_sided(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _long(_index(spark, sf_dir, OneSided(SEED, 8)))


def project_prefix_dims(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A two by two sub-grid of the four by four projection, cut from the index."""
    wide = _index(spark, sf_dir)
    keep = [a * K_IN + b for a in range(2) for b in range(2)]
    return _long(wide.select(ID, F.array(*[F.get("b0", F.lit(i)) for i in keep]).alias("b0")))


def _curvature_query(kind: str, size: int):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        s = study(spark, sf_dir, size)
        r = s.curvature(kind, True)
        flat = r.select(F.col("sub").cast("long").alias("s"), F.posexplode("vals").alias("at", "r"))
        return flat.select(
            "s", F.floor(F.col("at") / size).cast("long").alias("i"), (F.col("at") % size).cast("long").alias("j"), F.round("r", 6).alias("r")
        )

    return run


def moment_equals_autocorr_diag(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Dividing by the root moment equals a diagonal curvature: both sides, per parameter."""
    candidates = _candidates(spark, sf_dir)
    probe = _probe(candidates)
    v = gradients.diagonal_moment(candidates, probe)["w"].ravel()
    raw = gradients.build_index(candidates, probe, _spec(Identity()))
    r = curvature.autocorrelation(raw, 1).select(F.col("sub").cast("long").alias("i"), F.col("vals")[0].alias("autocorrelation"))
    own = spark.createDataFrame([(i, float(x)) for i, x in enumerate(v)], "i long, moment double")
    return r.join(own, "i").select("i", F.round("moment", 8).alias("moment"), F.round("autocorrelation", 8).alias("autocorrelation"))


def _whiten_query(size: int):
    """Inverse curvature applied to every candidate: the folded side."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        s = study(spark, sf_dir, size)
        inverse = curvature.invert(s.curvature("mixed", True), DAMPING)
        return _long(curvature.whiten(s.indexes(True)[0], inverse))

    return run


def unit_norms(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Length of every candidate after whitening by the root of the mixed curvature."""
    from ..functions.vectors import vec_norm

    s = study(spark, sf_dir)
    root = curvature.invert(s.curvature("mixed", True), DAMPING, power=-0.5)
    return curvature.whiten(s.indexes(True)[0], root).select(ID, F.round(vec_norm(F.col("b0")), 6).alias("norm"))


def score_bilinear_diag(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Change of the query's loss: minus the curvature-corrected inner product."""
    s = study(spark, sf_dir, 1)
    index, queries = s.indexes(True)
    inverse = curvature.invert(s.curvature("train", True), DAMPING)
    return _rounded(scoring.score_top_k(index, queries, TOP, inverse, unit_norm=False, ascending=True, sign=-1.0))


def score_prob_factor(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Margin influence with scores times one minus the candidate's probability."""
    candidates = _candidates(spark, sf_dir)
    probe = _probe(candidates)
    shared = spark.sparkContext.broadcast(probe)

    def add(batches):
        for b in batches:
            if b.num_rows:
                yield b.append_column("q", pa.array(1 - shared.value.target_probability(b)))

    with_q = candidates.mapInArrow(add, f"{ID} long, embedding array<double>, label int, q double")
    spec = _spec(output="margin_example", extra=["q"])
    index = gradients.build_index(with_q, probe, spec)
    queries = gradients.build_index(_queries(with_q), probe, spec.with_(extra=[]))
    inverse = curvature.invert(curvature.autocorrelation(index, 2, blocks=["b0"]), DAMPING)
    return _rounded(scoring.score_top_k(index, queries, TOP, inverse, unit_norm=False, factor="q"))


SETTINGS = ((2.0, 1.0), (4.0, 0.5), (8.0, 0.25))


def _over_settings(spark: SparkSession, sf_dir: str, unit_norm: bool) -> DataFrame:
    candidates = _candidates(spark, sf_dir)
    parts = []
    for scale, _ in SETTINGS:
        probe = SoftmaxProbe.from_means(candidates, scale)
        index = gradients.build_index(candidates, probe, _spec())
        parts.append(scoring.all_scores(index, _queries(index), unit_norm))
    return _rounded(scoring.top_k(scoring.over_checkpoints(parts, [w for _, w in SETTINGS]), TOP))


def score_over_checkpoints(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Weighted sum of gradient products over three softness settings of the probe, which is never trained.

    Checkpoints of a trained model are summed by `lm_checkpoint_sum`.
    """
    return _over_settings(spark, sf_dir, False)


def score_over_checkpoints_normalised(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same over gradients of unit length."""
    return _over_settings(spark, sf_dir, True)


def moment_moving_average(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Exponential average of second moments along the three settings, corrected for its start."""
    candidates = _candidates(spark, sf_dir)
    moments = [gradients.diagonal_moment(candidates, SoftmaxProbe.from_means(candidates, scale)) for scale, _ in SETTINGS]
    return _moment_table(spark, gradients.moving_average(moments, BETA)).withColumn("v", F.round("v", 8))


def score_subsampled(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cosine over a hashed quarter of the candidates: the practice of scoring a sample."""
    index = _index(spark, sf_dir)
    place = F.conv(F.substring(F.md5(F.concat(F.lit("sample:"), F.col(ID).cast("string"))), 1, 8), 16, 10).cast("long") % 100
    return _rounded(scoring.score_top_k(index.filter(place < SAMPLED), _queries(index), TOP))


def score_layer_subset(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cosine on the first half of the projected block alone; whole layers are left out by `lm_index_reuse`."""
    index = _index(spark, sf_dir).select(ID, F.slice("b0", 1, 8).alias("b0"))
    return _rounded(scoring.score_top_k(index, _queries(index), TOP))


def lambda_choice_diag(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mixing weight for diagonal curvature when the two leading components are to be damped."""
    s = study(spark, sf_dir, 1)
    lam = curvature.choose_lambda(s.curvature("eval", True), s.curvature("train", True), top=2)
    return spark.createDataFrame([(lam,)], "lam double").withColumn("lam", F.round("lam", 6))


def _patch_pairs(spark: SparkSession, sf_dir: str, rate: float = 0.5) -> DataFrame:
    """One step on each of the top candidates: target probability of the query before and after."""
    top = _ranking("gradient_dot")(spark, sf_dir).select("query_id", "rank", ID)
    candidates = _candidates(spark, sf_dir)
    probe = _probe(candidates)
    shared = spark.sparkContext.broadcast(probe)
    sides = top.join(candidates.select(ID, F.col("embedding").alias("mx"), F.col("label").alias("my")), ID).join(
        candidates.select(F.col(ID).alias("query_id"), F.col("embedding").alias("qx"), F.col("label").alias("qy")), "query_id"
    )

    def patch(batches):
        for b in batches:
            if b.num_rows:
                pr = shared.value
                mx, qx = matrix(b.column("mx")), matrix(b.column("qx"))
                my, qy = b.column("my").to_numpy(), b.column("qy").to_numpy()
                r = pr.residuals(mx, my)
                at = np.arange(len(qy))
                before = pr.probabilities(qx)[at, qy]
                # the step moves logits by -rate * scale^2 * residual * (candidate . query)
                z = pr.scale * qx @ pr.weights.T - rate * pr.scale**2 * r * (mx * qx).sum(axis=1)[:, None]
                z = np.exp(z - z.max(axis=1, keepdims=True))
                after = (z / z.sum(axis=1, keepdims=True))[at, qy]
                names = ["query_id", "rank", ID]
                yield pa.RecordBatch.from_arrays(
                    [b.column(b.schema.get_field_index(n)) for n in names] + [pa.array(after - before)], names=[*names, "delta"]
                )

    return sides.mapInArrow(patch, f"query_id long, rank int, {ID} long, delta double")


def probe_tail_patch(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _patch_pairs(spark, sf_dir).withColumn("delta", F.round("delta", 6))


def probe_tail_patch_by_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ..operators.measures import tail_patch_by_k

    return tail_patch_by_k(_patch_pairs(spark, sf_dir)).withColumn("tail_patch", F.round("tail_patch", 6))


def probe_leave_one_out(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Exact change of each query's loss when a candidate is left out of its class mean; ten largest.

    A brute-force check of influence that only a closed-form model affords.
    """
    candidates = _candidates(spark, sf_dir)
    probe = _probe(candidates)
    asked = _queries(candidates).toArrow()
    q_id, qy = np.array(asked[ID].to_pylist()), np.array(asked["label"].to_pylist())
    qx = np.array(asked["embedding"].to_pylist(), dtype=np.float64)
    sizes = np.zeros(len(probe.weights))
    for r in candidates.groupBy("label").count().collect():
        sizes[r["label"]] = r["count"]
    shared = spark.sparkContext.broadcast((probe, q_id, qx, qy, sizes))

    def run(batches):
        pr, ids, x, y, n = shared.value
        at = np.arange(len(ids))
        base = pr.scale * x @ pr.weights.T
        before = np.log(np.exp(base - base.max(axis=1, keepdims=True)).sum(axis=1)) + base.max(axis=1) - base[at, y]
        for b in batches:
            if b.num_rows:
                m, c = matrix(b.column("embedding")), b.column("label").to_numpy()
                out = []
                for v, label in zip(m, c):
                    z = base.copy()
                    z[:, label] = (n[label] * base[:, label] - pr.scale * x @ v) / (n[label] - 1)
                    top = z.max(axis=1)
                    out.append(np.log(np.exp(z - top[:, None]).sum(axis=1)) + top - z[at, y] - before)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(np.tile(ids, len(m))), pa.array(np.repeat(b.column(0).to_numpy(), len(ids))), pa.array(np.round(np.concatenate(out), 8))],
                    names=["query_id", ID, "score"],
                )

    return _rounded(scoring.top_k(candidates.mapInArrow(run, f"query_id long, {ID} long, score double"), TOP))


def index_footprint(spark: SparkSession, sf_dir: str) -> DataFrame:
    return gradients.footprint(_index(spark, sf_dir), K_OUT * K_IN)


def projection_fidelity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Correlation of projected with exact cosines, by kind of projection."""
    candidates = _candidates(spark, sf_dir)
    probe = _probe(candidates)
    own = gradients.diagonal_moment(candidates, probe)
    shared = spark.sparkContext.broadcast((probe, own["w"]))

    def outer(batch: pa.RecordBatch) -> dict[str, np.ndarray]:
        model, v = shared.value
        g = gradients.correct(model.gradients(batch)["w"], v, EPS).reshape(batch.num_rows, -1)
        return {"w": g.T @ g}

    square = gradients.sum_arrays(_queries(candidates), probe.columns, _sliced(outer)).get("w", np.zeros(own["w"].size**2))
    # any root of the sum has the singular directions of the query gradients
    size, turn = np.linalg.eigh(square.reshape(own["w"].size, -1))
    held = size > 1e-12 * max(float(size.max()), 1e-300)
    basis = QueryBasis({"w": np.sqrt(size[held])[:, None] * turn.T[held]}, 16)
    projections = {"exact": Identity(), "two_sided_16": TwoSided(SEED, 4, 4), "two_sided_64": TwoSided(SEED, 8, 8), "one_sided_16": OneSided(SEED, 16), "query_basis_16": basis}
    specs = spark.sparkContext.broadcast((probe, {name: _spec(p, moment=own) for name, p in projections.items()}))

    def sums(batch: pa.RecordBatch) -> dict[str, np.ndarray]:
        model, by_name = specs.value
        vectors = {name: gradients.project_batch(model, batch, spec)["b0"] for name, spec in by_name.items()}
        return measures.cosine_sums(vectors, batch.column(0).to_numpy() % EVERY == 0, "exact")

    found = gradients.sum_arrays(candidates, probe.columns, _sliced(sums))
    rows = [(*measures.fidelity_of_sums(found, name), name) for name in list(projections)[1:]]
    return spark.createDataFrame(rows, "correlation double, n_pairs long, projection string")


def _sliced(parts, rows: int = 2000):
    """The sums of `parts` over slices of a batch, as whole gradients are wide."""

    def run(batch: pa.RecordBatch) -> dict[str, np.ndarray]:
        total: dict[str, np.ndarray] = {}
        for at in range(0, batch.num_rows, rows):
            for name, x in parts(batch.slice(at, rows)).items():
                total[name] = total.get(name, 0) + x
        return total

    return run


_PATCH_SQL = (
    _ranking_sql("gradient_dot").replace("SELECT query_id, rank::INT", ", top AS (SELECT query_id, rank::INT", 1)
    + f"""),
        dot AS (SELECT t.query_id, t.rank, t.example_id, sum(a.x * b.x) AS d FROM top t JOIN x a ON a.vec_id = t.query_id
                JOIN x b ON b.vec_id = t.example_id AND b.j = a.j GROUP BY 1, 2, 3),
        nz AS (SELECT dot.query_id, dot.rank, dot.example_id, z.c, (z.label = z.c)::INT AS hit,
                      z.z - 0.5 * {SCALE * SCALE} * r.r0 * d AS z FROM dot JOIN z ON z.vec_id = dot.query_id
               JOIN r ON r.vec_id = dot.example_id AND r.c = z.c),
        ne AS (SELECT *, exp(z - max(z) OVER (PARTITION BY query_id, example_id)) AS ez FROM nz),
        dl AS (SELECT ne.query_id, ne.rank, ne.example_id, sum(ez * ne.hit) / sum(ez) - any_value(pt.pt) AS delta FROM ne
               JOIN (SELECT DISTINCT vec_id, pt FROM pt) pt ON pt.vec_id = ne.query_id GROUP BY 1, 2, 3)"""
)

_CHECKPOINTS_SQL = """
    WITH e AS (SELECT vec_id, label, embedding::DOUBLE[] AS v FROM embeddings),
    x AS (SELECT vec_id, label, unnest(v) AS x, generate_subscripts(v, 1) - 1 AS j FROM e),
    wt AS (SELECT label AS c, j, avg(x) AS w FROM x GROUP BY 1, 2),
    ck AS (SELECT * FROM (VALUES (2.0::DOUBLE, 1.0::DOUBLE), (4.0, 0.5), (8.0, 0.25)) t(s, k)),
    z AS (SELECT s, vec_id, label, c, s * sum(x * w) AS z FROM x JOIN wt USING (j), ck GROUP BY 1, 2, 3, 4),
    ez AS (SELECT s, vec_id, label, c, exp(z - max(z) OVER (PARTITION BY s, vec_id)) AS ez FROM z),
    r AS (SELECT s, vec_id, c, s * (ez / sum(ez) OVER (PARTITION BY s, vec_id) - (label = c)::INT) AS r FROM ez),
    la AS (SELECT a.range AS a, c, %s AS l FROM range(%d) a, (SELECT DISTINCT c FROM wt)),
    rb AS (SELECT b.range AS b, j, %s AS u FROM range(%d) b, (SELECT DISTINCT j FROM wt)),
    lr AS (SELECT s, vec_id, a, sum(l * r) AS l FROM r JOIN la USING (c) GROUP BY 1, 2, 3),
    rx AS (SELECT vec_id, b, sum(u * x) AS u FROM x JOIN rb USING (j) GROUP BY 1, 2),
    ix AS (SELECT s, vec_id, a, b, l * u AS w FROM lr JOIN rx USING (vec_id)),
    one AS (SELECT q.s, q.vec_id AS query_id, m.vec_id AS example_id, round(sum(q.w * m.w), 8) AS v
            FROM ix q JOIN ix m USING (s, a, b) WHERE q.vec_id %% 100 = 0 GROUP BY 1, 2, 3),
    sc AS (SELECT query_id, example_id, round(sum(k * v), 8) AS score FROM one JOIN ck USING (s) GROUP BY 1, 2)
""" % (_gauss("w:out", "a.range", "c", K_OUT), K_OUT, _gauss("w:in", "b.range", "j", K_IN), K_IN)

_NORMALISED_SQL = _CHECKPOINTS_SQL.replace(
    "one AS (SELECT", "ln AS (SELECT s, vec_id, sqrt(sum(w * w)) AS n FROM ix GROUP BY 1, 2),\n    one AS (SELECT"
).replace("round(sum(q.w * m.w), 8) AS v", "round(sum(q.w * m.w) / (any_value(a.n) * any_value(b.n)), 8) AS v").replace(
    "FROM ix q JOIN ix m USING (s, a, b) WHERE q.vec_id",
    "FROM ix q JOIN ix m USING (s, a, b) JOIN ln a ON a.s = q.s AND a.vec_id = q.vec_id JOIN ln b ON b.s = q.s AND b.vec_id = m.vec_id WHERE q.vec_id",
).replace("USING (s, a, b) JOIN", "ON m.s = q.s AND m.a = q.a AND m.b = q.b JOIN")

_AVERAGE_SQL = (
    _CHECKPOINTS_SQL.split("la AS (")[0]
    + f"""ms AS (SELECT s, c, j, avg(r * x * r * x) AS m FROM r JOIN x USING (vec_id) GROUP BY 1, 2, 3)
    SELECT c::BIGINT AS "class", j AS dim, round(sum(m * (1 - {BETA}) * CASE s WHEN 2.0 THEN {BETA} * {BETA} WHEN 4.0 THEN {BETA} ELSE 1 END)
           / (1 - {BETA} * {BETA} * {BETA}), 8) AS v FROM ms GROUP BY 1, 2"""
)

_INDEX_SQL = " SELECT vec_id AS example_id, i, round(w, 6) AS w FROM ix"
_FLAT_SQL = " SELECT vec_id AS example_id, c * (SELECT count(DISTINCT j) FROM wt) + j AS i, round(g, 6) AS w FROM h"
_GRAD_SQL = ' SELECT vec_id AS example_id, c::BIGINT AS "class", j AS dim, round(g, 6) AS g FROM g'


def _curvature_only_sql(kind: str, size: int) -> str:
    return _chain() + _curvature_sql(kind, size) + " SELECT s::BIGINT AS s, i::BIGINT AS i, j::BIGINT AS j, round(r, 6) AS r FROM rm"


def _folded_sql(size: int) -> str:
    return _chain() + _curvature_sql("mixed", size) + _inverse_sql(size) + _scores_sql("mixed", True, size)


QUERIES = {
    "probe_probabilities": probe_probabilities,
    "probe_loss_gradient": _gradient_query("loss"),
    "probe_margin_example": _gradient_query("margin_example"),
    "probe_margin_token": _gradient_query("margin_token"),
    "probe_logit_gradient": _gradient_query("logit"),
    "moment_diagonal": moment_diagonal,
    "moment_factored": moment_factored,
    "moment_corrected_gradient": moment_corrected_gradient,
    "moment_equals_autocorr_diag": moment_equals_autocorr_diag,
    "project_one_sided": project_one_sided,
    "project_two_sided": project_two_sided,
    "project_identity": project_identity,
    "project_prefix_dims": project_prefix_dims,
    "autocorr_train": _curvature_query("train", 4),
    "autocorr_eval": _curvature_query("eval", 4),
    "autocorr_mixed": _curvature_query("mixed", 4),
    "autocorr_block2": _curvature_query("mixed", 2),
    "autocorr_diag": _curvature_query("mixed", 1),
    "whiten_diag": _whiten_query(1),
    "whiten_block2": _whiten_query(2),
    "unit_norms": unit_norms,
    "score_mixed_cosine_top10": flagship,
    "score_mixed_cosine_diag": _ranking("mixed_cosine", block_size=1),
    "score_exp1": _ranking("exp1_plain_dot"),
    "score_exp2": _ranking("exp2_plain_cosine"),
    "score_exp3_block2": _ranking("exp3_train_curvature_cosine"),
    "score_exp4": _ranking("exp4_moment_cosine"),
    "score_exp5_block2": _ranking("exp5_moment_train_cosine"),
    "score_eval_curvature": _ranking("x_eval_cosine"),
    "score_gradient_dot": _ranking("gradient_dot"),
    "score_no_norm_mixed": _ranking("x_no_norm_mixed"),
    "score_no_norm_train": _ranking("x_no_norm_train"),
    "score_no_norm_moment_train": _ranking("x_no_norm_moment_train"),
    "score_margin_influence_block2": _ranking("margin_influence"),
    "score_bottom10": _ranking("mixed_cosine", ascending=True),
    "score_prob_factor": score_prob_factor,
    "score_bilinear_diag": score_bilinear_diag,
    "score_over_checkpoints": score_over_checkpoints,
    "score_layer_subset": score_layer_subset,
    "score_over_checkpoints_normalised": score_over_checkpoints_normalised,
    "moment_moving_average": moment_moving_average,
    "score_subsampled": score_subsampled,
    **{f"score_{name}": _ranking(name) for name in GRID.values() if name.startswith(("x_plain", "x_moment"))},
    "lambda_choice_diag": lambda_choice_diag,
    "probe_leave_one_out": probe_leave_one_out,
    "index_footprint": index_footprint,
    "projection_fidelity": projection_fidelity,
    "probe_tail_patch": probe_tail_patch,
    "probe_tail_patch_by_k": probe_tail_patch_by_k,
}

ORACLE_SQL = {
    "probe_probabilities": _chain() + ' SELECT vec_id AS example_id, c::BIGINT AS "class", round(p, 6) AS p FROM p',
    "probe_loss_gradient": _chain() + _GRAD_SQL,
    "probe_margin_example": _chain("margin_example") + _GRAD_SQL,
    "probe_margin_token": _chain("margin_example") + _GRAD_SQL,
    "probe_logit_gradient": _chain("logit") + _GRAD_SQL,
    "moment_diagonal": _chain() + ' SELECT c::BIGINT AS "class", j AS dim, round(m, 8) AS v FROM m',
    "moment_factored": _chain()
    + """, fr AS (SELECT c, avg(m) AS r FROM m GROUP BY 1), fc AS (SELECT j, avg(m) AS k FROM m GROUP BY 1)
        SELECT c::BIGINT AS "class", j AS dim, round(r * k / (SELECT avg(m) FROM m), 8) AS v FROM fr, fc""",
    "moment_corrected_gradient": _chain() + _FLAT_SQL,
    "moment_equals_autocorr_diag": _chain()
    + " SELECT c * (SELECT count(DISTINCT j) FROM wt) + j AS i, round(m, 8) AS moment, round(m, 8) AS autocorrelation FROM m",
    "project_one_sided": _chain(one_sided=8) + _INDEX_SQL,
    "project_two_sided": _chain() + _INDEX_SQL,
    "project_identity": _chain(moment=False) + _FLAT_SQL,
    "project_prefix_dims": _chain(k_out=2, k_in=2) + _INDEX_SQL,
    "autocorr_train": _curvature_only_sql("train", 4),
    "autocorr_eval": _curvature_only_sql("eval", 4),
    "autocorr_mixed": _curvature_only_sql("mixed", 4),
    "autocorr_block2": _curvature_only_sql("mixed", 2),
    "autocorr_diag": _curvature_only_sql("mixed", 1),
    "whiten_diag": _folded_sql(1) + " SELECT vec_id AS example_id, i::BIGINT AS i, round(y, 6) AS w FROM y",
    "whiten_block2": _folded_sql(2) + " SELECT vec_id AS example_id, i::BIGINT AS i, round(y, 6) AS w FROM y",
    "unit_norms": _folded_sql(2) + " SELECT vec_id AS example_id, round(n, 6) AS norm FROM nm",
    "score_mixed_cosine_top10": _ranking_sql("mixed_cosine"),
    "score_mixed_cosine_diag": _ranking_sql("mixed_cosine", size=1),
    "score_exp1": _ranking_sql("exp1_plain_dot"),
    "score_exp2": _ranking_sql("exp2_plain_cosine"),
    "score_exp3_block2": _ranking_sql("exp3_train_curvature_cosine"),
    "score_exp4": _ranking_sql("exp4_moment_cosine"),
    "score_exp5_block2": _ranking_sql("exp5_moment_train_cosine"),
    "score_eval_curvature": _ranking_sql("x_eval_cosine"),
    "score_gradient_dot": _ranking_sql("gradient_dot"),
    "score_no_norm_mixed": _ranking_sql("x_no_norm_mixed"),
    "score_no_norm_train": _ranking_sql("x_no_norm_train"),
    "score_no_norm_moment_train": _ranking_sql("x_no_norm_moment_train"),
    "score_margin_influence_block2": _ranking_sql("margin_influence"),
    "score_bottom10": _ranking_sql("mixed_cosine", "ASC"),
    "score_prob_factor": _chain("margin_example", False)
    + _curvature_sql("train", 2)
    + _inverse_sql(2)
    + _scores_sql("train", False, 2).replace("round(sum(y.y * ix.w), 8)", "round(sum(y.y * ix.w) * (1 - any_value(pq.pt)), 8)").replace(
        "JOIN nm ON nm.vec_id = ix.vec_id", "JOIN nm ON nm.vec_id = ix.vec_id JOIN (SELECT DISTINCT vec_id, pt FROM pt) pq ON pq.vec_id = ix.vec_id"
    )
    + _top_sql(),
    "score_bilinear_diag": _chain() + _curvature_sql("train", 1) + _inverse_sql(1) + _scores_sql("train", False, 1, "-") + _top_sql("ASC"),
    "score_over_checkpoints": _CHECKPOINTS_SQL + _top_sql(),
    "score_over_checkpoints_normalised": _NORMALISED_SQL + _top_sql(),
    "moment_moving_average": _AVERAGE_SQL,
    "score_subsampled": _chain()
    + _scores_sql("none", True, 2)
    + _top_sql().replace("FROM sc)", f"FROM sc WHERE ('0x' || substr(md5('sample:' || example_id), 1, 8))::BIGINT % 100 < {SAMPLED})"),
    **{f"score_{name}": _ranking_sql(name) for name in GRID.values() if name.startswith(("x_plain", "x_moment"))},
    "score_layer_subset": _chain().replace("GROUP BY 1, 2)", "GROUP BY 1, 2)") .replace("WHERE b < 4 GROUP", "WHERE b < 4 AND a * 4 + b < 8 GROUP")
    + _scores_sql("none", True, 2)
    + _top_sql(),
    "lambda_choice_diag": _chain()
    + _curvature_sql("mixed", 1)
    + " SELECT round(t / (t + e), 6) AS lam FROM (SELECT re.r AS e, rt.r AS t FROM re JOIN rt USING (s, i, j) ORDER BY e DESC LIMIT 1 OFFSET 1)",
    "index_footprint": f"SELECT count(*) AS n_examples, {K_OUT * K_IN}::BIGINT AS dim, (count(*) * {K_OUT * K_IN * 4})::BIGINT AS index_bytes FROM embeddings",
    "probe_leave_one_out": _chain()
    + f""", nc AS (SELECT label AS c, count(*) AS n FROM e GROUP BY 1),
        qd AS (SELECT q.vec_id AS query_id, m.vec_id AS example_id, m.label AS mc, sum(q.x * m.x) AS d FROM x q JOIN x m USING (j) WHERE q.vec_id % {EVERY} = 0 GROUP BY 1, 2, 3),
        lz AS (SELECT query_id, example_id, z.c, (z.label = z.c)::INT AS hit, z.z AS z0, CASE WHEN z.c = mc THEN (n * z.z - {SCALE} * d) / (n - 1) ELSE z.z END AS z
               FROM qd JOIN z ON z.vec_id = query_id JOIN nc ON nc.c = mc),
        sc AS (SELECT query_id, example_id, round(ln(sum(exp(z))) - sum(z * hit) - ln(sum(exp(z0))) + sum(z0 * hit), 8) AS score FROM lz GROUP BY 1, 2)"""
    + _top_sql(),
    "probe_tail_patch": _PATCH_SQL + " SELECT query_id, rank, example_id, round(delta, 6) AS delta FROM dl",
    "probe_tail_patch_by_k": _PATCH_SQL
    + """, run AS (SELECT query_id, rank, avg(delta) OVER (PARTITION BY query_id ORDER BY rank) AS v FROM dl)
        SELECT rank AS k, round(avg(v), 6) AS tail_patch FROM run GROUP BY 1""",
}
