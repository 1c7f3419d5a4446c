"""Language identification: family first, then one-versus-one linear SVMs within it."""

from __future__ import annotations

import re
from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ._runtime import bounded_broadcast, documents, release_memory

#: Width of the hashed feature vector.
WIDTH = 4096
#: Labelled documents of each language that the classifier is fitted on, and of all languages.
PER_LANGUAGE = 400
SAMPLE = 8_000
UNDETERMINED = "und"

# fixed values: ISO 639-1 codes by language family
FAMILIES = {
    "germanic": "en de nl sv da no nb nn is af fy lb yi",
    "romance": "fr es it pt ro ca gl oc",
    "slavic": "ru uk be pl cs sk sl hr sr bs mk bg",
    "baltic": "lt lv",
    "celtic": "ga cy gd br",
    "uralic": "fi et hu",
    "turkic": "tr az kk uz ky tk",
    "indic": "hi ur bn mr gu pa ne si",
    "semitic": "ar he mt am",
    "dravidian": "ta te kn ml",
    "austronesian": "id ms tl jv su mg",
    "sinitic": "zh",
    "japonic": "ja",
    "koreanic": "ko",
}
_FAMILY_OF = {code: family for family, codes in FAMILIES.items() for code in codes.split()}

#: Word characters that are no decimal digits: letters, and some numerals that are none.
_NEARLY = re.compile(r"[^\W\d_]")
_BLANK = np.arange(256, dtype=np.uint8)
_BLANK[[i for i in range(128) if not chr(i).isalpha()]] = 32


def _has_letter(text: str | None) -> bool:
    """Whether a character of Unicode category L occurs."""
    return text is not None and any(m.group().isalpha() for m in _NEARLY.finditer(text))


def features(text: str) -> np.ndarray:
    """Square roots of hashed byte n-gram counts (1 to 3) of the whole text, at unit length."""
    raw = _BLANK[np.frombuffer((" " + text.lower() + " ").encode(), np.uint8)].astype(np.uint32)
    grams = [raw, raw[:-1] << 8 | raw[1:] | 1 << 24, raw[:-2] << 16 | raw[1:-1] << 8 | raw[2:] | 2 << 24]
    out = np.zeros(WIDTH)
    for g in grams:
        out += np.bincount((g * np.uint32(2654435761)) >> np.uint32(20), minlength=WIDTH)
    out = np.sqrt(out)
    return (out / np.sqrt((out * out).sum())).astype(np.float32)


def fit_svm(x: np.ndarray, y: np.ndarray, penalty: float = 1e-3, steps: int = 80) -> np.ndarray:
    """Linear SVM with squared hinge loss, by accelerated gradient steps; the last weight is the bias."""
    x = np.hstack([x, np.ones((len(x), 1), dtype=x.dtype)])
    share = np.where(y > 0, 0.5 / max(1, (y > 0).sum()), 0.5 / max(1, (y < 0).sum()))
    w = ahead = np.zeros(x.shape[1])
    for k in range(steps):
        slack = np.maximum(0, 1 - y * (x @ ahead))
        new = ahead - (penalty * ahead - 2 * x.T @ (share * y * slack)) / (4 + penalty)
        ahead, w = new + k / (k + 3) * (new - w), new
    return w.astype(np.float32)


class Discriminator:
    """One-versus-one SVMs among groups; the winner has most won duels, then the largest margins."""

    def __init__(self, x: np.ndarray, labels: np.ndarray):
        self.names = sorted(set(labels))
        self.pairs = list(combinations(range(len(self.names)), 2))
        self.weights = np.array(
            [
                fit_svm(x[(keep := np.isin(labels, [self.names[a], self.names[b]]))], np.where(labels[keep] == self.names[a], 1.0, -1.0))
                for a, b in self.pairs
            ]
        ).reshape(len(self.pairs), x.shape[1] + 1)

    def decide(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Index of the winner, and its weakest duel as a number between 0 and 1."""
        if len(self.names) == 1:
            return np.zeros(len(x), dtype=int), np.ones(len(x))
        margins = x @ self.weights[:, :-1].T + self.weights[:, -1]
        wins, weakest = np.zeros((len(x), len(self.names))), np.full((len(x), len(self.names)), np.inf)
        for (a, b), m in zip(self.pairs, margins.T):
            for group, own in ((a, m), (b, -m)):
                wins[:, group] += (own > 0) + 0.25 * np.tanh(own) / len(self.names)
                weakest[:, group] = np.minimum(weakest[:, group], own)
        best = wins.argmax(axis=1)
        return best, 1 / (1 + np.exp(-4 * weakest[np.arange(len(x)), best]))


class HierarchicalModel:
    """Families, then languages within the family."""

    def __init__(self, x: np.ndarray, langs: np.ndarray):
        families = np.array([_FAMILY_OF.get(lang, "other") for lang in langs], dtype=object)
        self.top = Discriminator(x, families)
        self.within = {f: Discriminator(x[families == f], langs[families == f]) for f in self.top.names}

    def predict(self, x: np.ndarray) -> tuple[list[str], np.ndarray]:
        family, sure = self.top.decide(x)
        names: list[str] = [""] * len(x)
        score = np.zeros(len(x))
        for i, f in enumerate(self.top.names):
            rows = np.flatnonzero(family == i)
            if len(rows):
                lang, own = self.within[f].decide(x[rows])
                for r, k in zip(rows, lang):
                    names[r] = self.within[f].names[k]
                score[rows] = sure[rows] * own
        return names, score


def held_out(id_col: str) -> Column:
    return F.coalesce(F.crc32(F.col(id_col).cast("string")) % 3 == 1, F.lit(False))


def fit(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> HierarchicalModel | None:
    """Fit on at most PER_LANGUAGE labelled documents of each language and SAMPLE in all.

    Documents are drawn by a hash of their id among those that are not held out; null ids,
    texts and labels are left out. None if nothing can be learned.
    """
    labelled = (
        docs.select(
            F.col(id_col).cast("long").alias("i"),
            F.col(lang_col).cast("string").alias("lang"),
            F.col(text_col).cast("string").alias("t"),
            held_out(id_col).alias("held"),
        )
        .filter("i IS NOT NULL AND t IS NOT NULL AND lang IS NOT NULL AND NOT held")
        .drop("held")
    )
    ids = labelled.select(F.col("i").alias("fit_id"), F.col("lang").alias("fit_lang"))
    # a hash first cuts each language to about four times the wanted rows, so that ranking stays small
    sizes = ids.groupBy(F.col("fit_lang").alias("size_lang")).agg(F.count(F.lit(1)).alias("n"))
    small = bounded_broadcast(sizes)
    place = F.pmod(F.xxhash64(F.lit(9), "fit_id"), F.lit(1 << 20)) / F.lit(float(1 << 20))
    few = ids.join(small, F.col("fit_lang") == F.col("size_lang")).filter(place * F.col("n") < 4 * PER_LANGUAGE)
    nth = F.row_number().over(Window.partitionBy("fit_lang").orderBy(F.xxhash64("fit_id"), "fit_id"))
    drawn = few.select("fit_id", "fit_lang").withColumn("nth", nth).filter(F.col("nth") <= PER_LANGUAGE).orderBy("nth", "fit_lang").limit(SAMPLE)
    chosen = sorted({r["fit_id"] for r in drawn.select("fit_id").collect()})
    if not chosen:
        return None

    def measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = [(i, lang, features(t)) for i, lang, t in zip(*(b.column(k).to_pylist() for k in ("i", "lang", "t"))) if _has_letter(t)]
            yield pa.RecordBatch.from_pydict(
                {"i": [r[0] for r in rows], "lang": [r[1] for r in rows], "x": [r[2].astype(np.float16).tobytes() for r in rows]},
                schema=pa.schema([("i", pa.int64()), ("lang", pa.string()), ("x", pa.binary())]),
            )

    own = docs.sparkSession.createDataFrame([(i,) for i in chosen], "fit_id long")
    texts = labelled.join(F.broadcast(own), F.col("i") == F.col("fit_id"), "left_semi")
    got = sorted((r["i"], r["lang"], bytes(r["x"])) for r in texts.mapInArrow(measure, "i long, lang string, x binary").collect())
    if not got:
        return None
    x = np.stack([np.frombuffer(r[2], np.float16) for r in got]).astype(np.float32)
    return HierarchicalModel(x, np.array([r[1] for r in got], dtype=object))


def identify(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> DataFrame:
    """Predict the language of every whole text.

    Null text, text without a letter, and any text where no label could be learned get `und`
    with score 0. Every input row gives one row; a null id is not held out. An empty table gives
    no rows. The prediction sees the text alone.
    Returns doc_id, held_out, lang_pred, score.
    """
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), held_out(id_col).alias("held_out"), F.col(text_col).cast("string").alias("t"))
    predict = _predictor(docs.sparkSession, fit(docs, id_col, text_col, lang_col))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            names, score = predict(b.column("t").to_pylist())
            yield pa.RecordBatch.from_arrays(
                [b.column("doc_id"), b.column("held_out"), pa.array(names, pa.string()), pa.array(score)],
                names=["doc_id", "held_out", "lang_pred", "score"],
            )

    return rows.mapInArrow(run, "doc_id long, held_out boolean, lang_pred string, score double")


def _predictor(spark: SparkSession, model: HierarchicalModel | None):
    shared = spark.sparkContext.broadcast(model)

    def predict(texts: list[str | None]) -> tuple[list[str], np.ndarray]:
        names, scores = [UNDETERMINED] * len(texts), np.zeros(len(texts))
        able = [i for i, t in enumerate(texts) if _has_letter(t)] if shared.value is not None else []
        for at in range(0, len(able), 256):
            some = able[at : at + 256]
            found, score = shared.value.predict(np.stack([features(texts[i]) for i in some]))
            for i, name in zip(some, found):
                names[i] = name
            scores[some] = score
        release_memory()
        return names, scores

    return predict


def keep_identified(docs: DataFrame) -> DataFrame:
    """Documents whose language can be told; where `lang` is null it becomes the prediction.

    Columns stay as they are. Where no label could be learned, every text with a letter stays
    and `lang` is left alone.
    """
    model = fit(docs)
    predict, learned = _predictor(docs.sparkSession, model), model is not None

    @F.pandas_udf("string")
    def told(texts: pd.Series) -> pd.Series:
        if not learned:
            return pd.Series(["" if _has_letter(t) else UNDETERMINED for t in texts.tolist()], dtype=object)
        return pd.Series(predict(texts.tolist())[0], dtype=object)

    # texts go to Python one way, once; rows stay in the JVM
    found = docs.select(*[F.col(f"`{c}`") for c in docs.columns], told.asNondeterministic()(F.col("text").cast("string")).alias("op9 told"))
    lang = F.coalesce(F.col("lang"), F.nullif(F.col("op9 told"), F.lit(""))).alias("lang")
    return found.filter(F.col("op9 told") != UNDETERMINED).select(*[lang if c == "lang" else F.col(f"`{c}`") for c in docs.columns])


def op9_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return identify(documents(spark, sf_dir))
