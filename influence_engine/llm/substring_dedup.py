"""Substring de-duplication by level-wise doubling.

A window of 50 words can repeat only if what it holds at a shorter length repeats. Levels
double up to the window: 13, 25, 50 words. At each level every window that is still a
candidate stands for the smallest hash among its pieces of that length, so equal windows
stand for equal keys and most windows of a text share a few. Keys of a block of documents go
to hash-range owners, Golomb-Rice coded; owners answer with a bitmap of the keys that other
blocks hold too. Windows whose key is held by one document alone are no candidates at the
next level, and texts without candidates are finished. At the last level the key is the
window's own hash and the bitmap tells whether a smaller document id holds it.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import exchange, spans
from ._runtime import discard, documents, release_memory, work_path

WINDOW = 50
SHORTEST = 13
#: Bytes of text in a block of documents.
BLOCK_BYTES = 4 << 20
#: Bits of keys that only prune.
PRUNE_BITS = 44
#: Keys that an owner holds, about.
PER_OWNER = 250_000
#: Owners of keys, as a power of two, at least.
LEAST_OWNER_BITS = 6
_NO_ID = np.iinfo(np.int64).max

_ROWS = pa.schema(
    [
        ("kind", pa.string()),
        ("part", pa.int64()),
        ("doc_id", pa.int64()),
        ("text", pa.binary()),
        ("alive", pa.binary()),
        ("owner", pa.int32()),
        ("code", pa.binary()),
        ("mins", pa.binary()),
        ("rests", pa.binary()),
        ("n_words", pa.int64()),
        ("n_removed", pa.int64()),
        ("kept_sha256", pa.string()),
    ]
)
_DDL = (
    "kind string, part long, doc_id long, text binary, alive binary, owner int, code binary, mins binary, rests binary, "
    "n_words long, n_removed long, kept_sha256 string"
)


def levels_for(window: int, shortest: int) -> list[int]:
    """Lengths from about the shortest to the window, each half of the next, rounded up."""
    out = [window]
    while out[0] > shortest:
        out.insert(0, -(-out[0] // 2))
    return out


def gram_hashes(words: np.ndarray, length: int) -> np.ndarray:
    """Hash of every run of that many words, built by doubling from hashes of its two halves."""
    if length == 1:
        return words
    half = -(-length // 2)
    part = gram_hashes(words, half)
    n = len(words) - length + 1
    return spans.mix(part[:n] * np.uint64(0x9E3779B97F4A7C15) + part[length - half : length - half + n])


def _least(values: np.ndarray, width: int) -> np.ndarray:
    """Minimum of every run of that width."""
    step = 1
    while step * 2 <= width:
        values = np.minimum(values[:-step], values[step:])
        step *= 2
    if step < width:
        rest = width - step
        values = np.minimum(values[:-rest], values[rest:])
    return values


class Block:
    """Documents of one block: words, window keys and candidates."""

    def __init__(self, ids: list, texts: list[bytes], alive: list[bytes | None], window: int):
        self.ids, self.texts, self.window = ids, texts, window
        raw = b"\n".join(texts)
        starts, ends = spans.words(raw)
        hashed = spans.hashes(raw, starts, ends)
        sizes = np.fromiter(map(len, texts), dtype=np.int64, count=len(texts))
        edges = np.searchsorted(starts, np.cumsum(np.r_[0, sizes + 1])).tolist()
        self.words = [hashed[a:b] for a, b in zip(edges, edges[1:])]
        self.alive = []
        for w, bits in zip(self.words, alive):
            n = max(0, len(w) - window + 1)
            self.alive.append(np.ones(n, dtype=bool) if bits is None else exchange.read_bits(bits, n))

    def _digests(self, i: int) -> np.ndarray:
        """128 bits of each candidate window's words, as two numbers."""
        words = self.texts[i].split()
        plain = b" ".join(words)
        place = np.cumsum([0, *(len(w) + 1 for w in words)]).tolist()
        first = np.flatnonzero(self.alive[i]).tolist()
        raw = b"".join([hashlib.blake2b(plain[place[p] : place[p + self.window] - 1], digest_size=16).digest() for p in first])
        return np.frombuffer(raw, ">u8").reshape(-1, 2).astype(np.uint64)

    def keys(self, length: int, key_bits: int, last: bool) -> None:
        """Keys of the candidate windows at that length, with the documents that hold them."""
        own, doc = [np.empty((0, 2), np.uint64)], [np.empty(0, np.int64)]
        for i, (w, alive) in enumerate(zip(self.words, self.alive)):
            if alive.any():
                if last:
                    key = self._digests(i)
                else:
                    key = _least(gram_hashes(w, length), self.window - length + 1)[alive] >> np.uint64(64 - key_bits)
                    key = np.stack([key, np.zeros_like(key)], axis=1)
                own.append(key)
                doc.append(np.full(len(key), _NO_ID if self.ids[i] is None else self.ids[i], dtype=np.int64))
        key, self.doc = np.concatenate(own), np.concatenate(doc)
        order = np.lexsort((key[:, 1], key[:, 0])) if last else np.argsort(key[:, 0], kind="stable")
        ranked = key[order]
        new = np.ones(len(key), dtype=bool)
        new[1:] = (ranked[1:] != ranked[:-1]).any(axis=1)
        self.distinct, self.rest = ranked[new, 0], ranked[new, 1]
        self.back = np.empty(len(key), dtype=np.int64)
        self.back[order] = np.cumsum(new) - 1
        self.low = np.full(len(self.distinct), _NO_ID, dtype=np.int64)
        high = np.full(len(self.distinct), np.iinfo(np.int64).min, dtype=np.int64)
        np.minimum.at(self.low, self.back, self.doc)
        np.maximum.at(high, self.back, self.doc)
        self.shared = self.low != high

    def packets(self, part: int, owner_bits: int, key_bits: int, last: bool) -> list[dict]:
        return [
            {
                "kind": "packet",
                "part": part,
                "owner": owner,
                "code": exchange.rice_encode(self.distinct[a:b] - exchange.owner_base(owner, owner_bits, key_bits)),
                "mins": self.low[a:b].tobytes() if last else None,
                "rests": self.rest[a:b].tobytes() if last else None,
            }
            for owner, a, b in exchange.owner_slices(self.distinct, owner_bits, key_bits)
        ]

    def answered(self, bitmaps: dict[int, bytes], owner_bits: int, key_bits: int, last: bool) -> None:
        """Keep as candidates what the owners and the block itself know to repeat."""
        hit = np.zeros(len(self.distinct), dtype=bool)
        for owner, a, b in exchange.owner_slices(self.distinct, owner_bits, key_bits):
            hit[a:b] = exchange.read_bits(bitmaps[owner], b - a)
        if last:
            found = (hit[self.back] | (self.doc > self.low[self.back])) & (self.doc != _NO_ID)
        else:
            found = (hit | self.shared)[self.back]
        at = 0
        for alive in self.alive:
            n = int(alive.sum())
            alive[alive] = found[at : at + n]
            at += n

    def result(self, i: int, remove: bool) -> dict:
        """The finished row of a document; its candidates are the windows to remove."""
        words = self.texts[i].split()
        gone = np.zeros(len(words), dtype=bool)
        if remove and self.alive[i].any():
            first = np.flatnonzero(self.alive[i])
            turns = np.zeros(len(words) + 1, dtype=np.int64)
            np.add.at(turns, first, 1)
            np.add.at(turns, first + self.window, -1)
            gone = np.cumsum(turns[:-1]) > 0
            words = [w for w, g in zip(words, gone.tolist()) if not g]
        return {
            "kind": "done",
            "doc_id": self.ids[i],
            "n_words": len(gone),
            "n_removed": int(gone.sum()),
            "kept_sha256": hashlib.sha256(b" ".join(words)).hexdigest(),
        }

    def rows(self, part: int, length: int, owner_bits: int, key_bits: int, last: bool) -> list[dict]:
        """Finished documents, and for the next level the candidates' texts and packets."""
        out = []
        for i, alive in enumerate(self.alive):
            if alive.any():
                bits = np.packbits(alive).tobytes()
                out.append({"kind": "text", "part": part, "doc_id": self.ids[i], "text": self.texts[i], "alive": bits})
            else:
                out.append(self.result(i, False))
        self.keys(length, key_bits, last)
        return out + self.packets(part, owner_bits, key_bits, last)


def _open_blocks(window: int, length: int, owner_bits: int, key_bits: int, last: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task, seq, ids, texts, size = TaskContext.get().partitionId(), 0, [], [], 0

        def flush() -> pa.RecordBatch:
            block = Block(ids, texts, [None] * len(ids), window)
            return pa.RecordBatch.from_pylist(block.rows(task << 24 | seq, length, owner_bits, key_bits, last), schema=_ROWS)

        for b in batches:
            for i, t in zip(b.column("doc_id").to_pylist(), b.column("t").to_pylist()):
                ids.append(i)
                texts.append(t)
                size += len(t)
                if size >= BLOCK_BYTES:
                    yield flush()
                    seq, ids, texts, size = seq + 1, [], [], 0
        if ids:
            yield flush()
        release_memory()

    return run


def _own(last: bool):
    def run(packets: pd.DataFrame) -> pd.DataFrame:
        mins = [np.frombuffer(m, np.int64) for m in packets["mins"]] if last else None
        rests = [np.frombuffer(m, np.uint64) for m in packets["rests"]] if last else None
        return pd.DataFrame(
            {"part": packets["part"], "owner": packets["owner"], "bitmap": exchange.answer(list(packets["code"]), mins, rests)}
        )

    return run


def _bitmaps(table: DataFrame, last: bool) -> DataFrame:
    packets = table.filter("kind = 'packet'").select("part", "owner", "code", *(["mins", "rests"] if last else []))
    return packets.groupBy("owner").applyInPandas(_own(last), "part long, owner int, bitmap binary")


def _advance(window: int, now: tuple, then: tuple | None):
    """One level: take the owners' answers for `now`, open `then`. Each is (length, owner bits, key bits, last)."""

    def run(texts: pa.Table, bitmaps: pa.Table) -> pa.Table:
        part = texts["part"][0].as_py() if texts.num_rows else -1
        block = Block(texts["doc_id"].to_pylist(), texts["text"].to_pylist(), texts["alive"].to_pylist(), window)
        block.keys(now[0], now[2], now[3])
        answers = dict(zip(bitmaps["owner"].to_pylist(), bitmaps["bitmap"].to_pylist()))
        block.answered(answers, *now[1:])
        rows = [block.result(i, True) for i in range(len(block.ids))] if then is None else block.rows(part, *then)
        return pa.Table.from_pylist(rows, schema=_ROWS)

    return run


def _written(table: DataFrame, level: int) -> tuple[str, DataFrame]:
    """A level's rows in folders by kind, so that what is spent can go."""
    path = work_path(table.sparkSession, f"op4-level{level}")
    table.write.partitionBy("kind").parquet(path)
    return path, table.sparkSession.read.schema(table.schema).parquet(path)


def remove_repeats(
    docs: DataFrame,
    window: int = WINDOW,
    shortest: int = SHORTEST,
    id_col: str = "doc_id",
    text_col: str = "text",
    prune_bits: int = PRUNE_BITS,
) -> DataFrame:
    """Remove every word that a window covers whose words also start in a document of smaller id.

    Windows are judged on the input. Null or empty text has no words. Texts shorter than the
    window keep all. Rows of equal id do not remove each other's words; a null id neither
    removes nor loses words. An empty table gives no rows; other columns are ignored. Keys of
    prune_bits only prune; what is removed is decided by 128-bit digests of the words.
    Returns doc_id, n_words, n_removed, kept_sha256.
    """
    rows = docs.select(
        F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).cast("binary").alias("t")
    )
    size = rows.agg(F.sum(F.octet_length("t").cast("long"))).first()[0] or 0
    owner_bits = exchange.owner_bits_for(size // 16, PER_OWNER, least=min(prune_bits, LEAST_OWNER_BITS))
    lengths = levels_for(window, shortest)
    steps = [(n, owner_bits, 64 if n == window else prune_bits, n == window) for n in lengths]
    path, table = _written(rows.mapInArrow(_open_blocks(window, *steps[0]), _DDL), 0)
    done = table.filter("kind = 'done'")
    for at, now in enumerate(steps):
        then = steps[at + 1] if at + 1 < len(steps) else None
        spent = path
        texts = table.filter("kind = 'text'").select("part", "doc_id", "text", "alive")
        table = (
            texts.groupBy("part")
            .cogroup(_bitmaps(table, now[3]).groupBy("part"))
            .applyInArrow(_advance(window, now, then), _DDL)
        )
        path, table = _written(table, at + 1)
        # the next level holds the texts that are still open, and finished rows are kept apart
        for kind in ("text", "packet"):
            discard(docs.sparkSession, f"{spent}/kind={kind}")
        done = done.unionByName(table.filter("kind = 'done'"))
    return done.select("doc_id", "n_words", "n_removed", "kept_sha256")


def op4_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_repeats(documents(spark, sf_dir))


ORACLE_SQL = {
    "op4_substring_dedup": r"""
        WITH texts AS (
            SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS words FROM documents
        ), windows AS (
            SELECT doc_id, unnest(range(1, len(words) - 48)) AS pos, words FROM texts WHERE len(words) >= 50
        ), spelled AS (
            SELECT doc_id, pos, sha256(array_to_string(list_slice(words, pos, pos + 49), ' ')) AS run FROM windows
        ), late AS (
            SELECT doc_id, pos FROM (SELECT doc_id, pos, min(doc_id) OVER (PARTITION BY run) AS least FROM spelled) WHERE least < doc_id
        ), gone AS (
            SELECT DISTINCT doc_id, pos + k AS pos FROM late, unnest(range(50)) AS t(k)
        ), placed AS (
            SELECT doc_id, unnest(words) AS word, unnest(range(1, len(words) + 1)) AS pos FROM texts
        ), kept AS (
            SELECT p.doc_id, count(*) AS n, string_agg(p.word, ' ' ORDER BY p.pos) AS rest
            FROM placed p ANTI JOIN gone g ON p.doc_id = g.doc_id AND p.pos = g.pos GROUP BY p.doc_id
        )
        SELECT doc_id, len(words)::BIGINT AS n_words, (len(words) - coalesce(n, 0))::BIGINT AS n_removed,
               sha256(coalesce(rest, '')) AS kept_sha256
        FROM texts LEFT JOIN kept USING (doc_id)
    """
}
