"""The pipeline's stages against plain Python, each on its own input, and the whole run."""

import hashlib
import re
import unicodedata
import zlib
from collections import Counter, defaultdict

import corpus_pipeline
import numpy as np
import pytest
import xxhash

from influence_engine.llm import mixing
from influence_engine.llm.tokens import public_path

WORD = re.compile(r"[^\x20\x09-\x0D]+")
COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


@pytest.fixture(scope="module")
def folder(spark, odd_docs, sample_docs, tmp_path_factory):
    more = [
        (900, "²½Ⅷ① 12", None, "a", 7),
        (901, "alpha beta gamma delta " * 12, None, "a", 7),
        (902, "alpha beta gamma delta " * 12 + "end", None, "b", 7),
        (None, "a text without an id that is not repeated at all", "en", None, 1),
    ]
    docs = odd_docs.select(COLUMNS).unionByName(sample_docs.select(COLUMNS).withColumn("doc_id", sample_docs["doc_id"] + 1000))
    out = str(tmp_path_factory.mktemp("pipeline"))
    docs.unionByName(spark.createDataFrame(more, odd_docs.select(COLUMNS).schema)).write.parquet(f"{out}/documents.parquet")
    return out


@pytest.fixture(scope="module")
def steps(spark, folder):
    """Rows after each stage, by name; `documents` is the input."""
    out, docs = {"documents": spark.read.parquet(f"{folder}/documents.parquet")}, None
    docs = out["documents"]
    for name, stage in corpus_pipeline.STAGES:
        path = f"{folder}/{name}"
        stage(spark, docs, folder).write.parquet(path)
        docs = out[name] = spark.read.parquet(path)
    return {name: [tuple(r) for r in df.collect()] for name, df in out.items()}


def fingerprint(text):
    words = WORD.findall(re.sub("[A-Z]", lambda m: m.group().lower(), text or ""))
    shingles = [" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))] if words else []
    votes = [0] * 64
    for s in shingles:
        h = xxhash.xxh64_intdigest(s.encode(), 42)
        for b in range(64):
            votes[b] += h >> b & 1
    return sum(1 << b for b in range(64) if 2 * votes[b] > len(shingles))


def key(row):
    return tuple(str(x) for x in row)


def test_language_stage(steps):
    keep = [r for r in steps["documents"] if r[1] and any(unicodedata.category(c)[0] == "L" for c in r[1])]
    got = steps["language_id"]
    assert sorted((r[:2] + r[3:] for r in got), key=key) == sorted((r[:2] + r[3:] for r in keep), key=key)
    labels = {r[2] for r in steps["documents"] if r[2]}
    told = defaultdict(set)
    for r in got:
        told[r[0]].add(r[2])
    assert all(told[r[0]] == {r[2]} for r in keep if r[2] and r[0] is not None)
    assert all(x in labels for found in told.values() for x in found)


def test_exact_stage(steps):
    best = {}
    for r in steps["language_id"]:
        old = best.get(r[1])
        if old is None or (r[0] is not None and (old[0] is None or r[0] > old[0])):
            best[r[1]] = r
    assert sorted((r[:2] for r in steps["exact_dedup"]), key=key) == sorted((r[:2] for r in best.values()), key=key)


def test_near_stage(steps):
    rows = [(r[0], r[1], fingerprint(r[1])) for r in steps["exact_dedup"]]
    fps = np.array([f for _, _, f in rows], dtype=np.uint64)
    label = list(range(len(rows)))

    def root(x):
        while label[x] != x:
            x = label[x]
        return x

    for a, b in zip(*np.nonzero(np.bitwise_count(fps[:, None] ^ fps[None, :]) <= 2)):
        label[max(root(a), root(b))] = min(root(a), root(b))
    least = {}
    for i, r in enumerate(rows):
        if r[0] is not None:
            least[root(i)] = min(least.get(root(i), r[0]), r[0])
    keep = [r[:2] for i, r in enumerate(rows) if r[0] is None or r[0] == least[root(i)]]
    assert len(keep) < len(rows)
    assert sorted((r[:2] for r in steps["simhash_dedup"]), key=key) == sorted(keep, key=key)


def test_mix_stage(spark, folder, steps):
    docs = spark.read.parquet(f"{folder}/simhash_dedup")
    copies = Counter({(r["doc_id"], r["source"]): r["copies"] for r in mixing.mix(docs).collect() if r["copies"]})
    assert Counter((r[0], r[3]) for r in steps["mix_sources"]) == copies
    assert {r[:2] for r in steps["mix_sources"]} <= {r[:2] for r in steps["simhash_dedup"]}


def test_packing_stage(steps):
    from tokenizers import Tokenizer

    model = Tokenizer.from_file(public_path("word_bpe_49k.json"))
    want = Counter()
    for r in steps["mix_sources"]:
        ids = model.encode(r[1], add_special_tokens=False).ids + [1]
        for piece, at in enumerate(range(0, len(ids), 4096)):
            part = ids[at : at + 4096]
            want[r[0], piece, at, len(part), zlib.crc32(np.array(part, dtype="<u4").tobytes())] += 1
    got = steps["best_fit_packing"]
    assert Counter(r[:5] for r in got) == want
    sequences = defaultdict(list)
    for r in got:
        sequences[r[5]].append((r[6], r[3]))
    for parts in sequences.values():
        end = 0
        for offset, length in sorted(parts):
            assert offset == end
            end += length
        assert end <= 4096


def test_run_is_the_chain_of_stages(spark, folder, steps):
    got = [tuple(r) for r in corpus_pipeline.run(spark, folder).collect()]
    assert Counter(r[:5] for r in got) == Counter(r[:5] for r in steps["best_fit_packing"])
    digest = hashlib.sha256(repr(sorted(got, key=key)).encode()).hexdigest()
    assert digest == hashlib.sha256(repr(sorted(steps["best_fit_packing"], key=key)).encode()).hexdigest()
