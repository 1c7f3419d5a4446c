"""Every operator against brute force, on odd rows and on a small table."""

import hashlib
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
import xxhash
from conftest_texts import texts_of

from influence_engine.llm import (
    components,
    exact_dedup,
    exchange,
    language_id,
    mixing,
    multi_index,
    packing,
    sharding,
    simhash,
    substring_dedup,
    token_counts,
    token_output,
)
from influence_engine.llm._runtime import work_path
from influence_engine.llm.tokens import public_path

WORD = re.compile(r"[^\x20\x09-\x0D]+")
BPE = public_path("word_bpe_49k.json")
PIECES = public_path("piece_bpe_32k.model")


@pytest.fixture(params=["odd_docs", "sample_docs"])
def docs(request):
    return request.getfixturevalue(request.param)


def library_ids(text):
    from tokenizers import Tokenizer

    if not hasattr(library_ids, "model"):
        library_ids.model = Tokenizer.from_file(BPE)
    return library_ids.model.encode(text or "", add_special_tokens=False).ids


def crc(ids):
    return zlib.crc32(np.array(ids, dtype="<u4").tobytes())


def test_rice_round_trip():
    rng = np.random.default_rng(0)
    for n in (0, 1, 2, 1000, 70_000):
        keys = np.unique(rng.integers(0, 1 << 40, n, dtype=np.uint64))
        assert (exchange.rice_decode(exchange.rice_encode(keys)) == keys).all()
    tight = np.arange(5, dtype=np.uint64)
    assert (exchange.rice_decode(exchange.rice_encode(tight)) == tight).all()


def test_exact_dedup(docs):
    rows = texts_of(docs)
    got = exact_dedup.exact_dedup(docs).collect()
    assert len(got) == len(rows)
    groups = defaultdict(list)
    for i, t in rows:
        groups[t or ""].append(i)
    by_sha = {hashlib.sha256(t.encode()).hexdigest(): ids for t, ids in groups.items()}
    kept = Counter(r["text_sha256"] for r in got if r["kept"])
    assert kept == Counter(by_sha.keys())
    for r in got:
        ids = by_sha[r["text_sha256"]]
        assert r["group_size"] == len(ids)
        assert r["keep_id"] == max((i for i in ids if i is not None), default=None)
        assert not r["kept"] or r["doc_id"] == r["keep_id"]
    assert exact_dedup.keep_distinct(docs).count() == len(groups)


def test_ids_with_kept_and_dropped_rows_lose_no_distinct_text(spark):
    x, y, z = ("alpha beta gamma " * 5, "seven other words stand in this line", "and here are quite different ones again")
    rows = [(7, x), (9, x), (7, y), (7, y), (None, x), (None, z), (None, "z z"), (None, "z z"), (None, None), (3, "")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = Counter(texts_of(exact_dedup.keep_distinct(docs)))
    assert got == Counter([(9, x), (7, y), (None, z), (None, "z z"), (3, "")])
    near = spark.createDataFrame([(3, x), (7, x), (7, y), (7, z), (8, z)], "doc_id long, text string")
    assert Counter(texts_of(simhash.keep_one(near))) == Counter([(3, x), (7, y), (7, z)])


def test_token_counts(docs):
    from sentencepiece import SentencePieceProcessor

    model = SentencePieceProcessor(model_file=PIECES)
    got = sorted(map(tuple, token_counts.token_counts(docs, PIECES).select("doc_id", "n_bytes", "n_tokens", "over_limit").collect()), key=str)
    want = [(i, len((t or "").encode()), n := len(model.encode(t or "")), n > 4096) for i, t in texts_of(docs)]
    assert got == sorted(want, key=str)


def test_prefix_store(spark):
    from sentencepiece import SentencePieceProcessor

    model = SentencePieceProcessor(model_file=PIECES)
    texts = ["", " a", "two  spaces\n\nand ▁ marks", "Ünï", None, "end "]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    store = token_counts.prefix_store(df, PIECES)
    for r in store.collect():
        t = texts[r["doc_id"]] or ""
        assert r["prefix_tokens"] == [len(model.encode(t[:i])) for i in range(len(t) + 1)]
    fits = {r["doc_id"]: r["fit_chars"] for r in token_counts.longest_within(store, 3).collect()}
    cut = {r["doc_id"]: r["n_tokens"] for r in token_counts.tokens_of_prefix(store, 4).collect()}
    for i, t in enumerate(texts):
        t = t or ""
        assert fits[i] == max(j for j in range(len(t) + 1) if len(model.encode(t[:j])) <= 3)
        assert cut[i] == len(model.encode(t[:4]))
    limited = {r["doc_id"]: r["fit_chars"] for r in token_counts.token_counts(df, PIECES, 3).collect()}
    assert limited == fits


def simhash_of(text):
    words = WORD.findall("".join(c.lower() if "A" <= c <= "Z" else c for c in text or ""))
    if not words:
        return 0
    shingles = [" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))]
    h = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if sum(x >> b & 1 for x in h) * 2 > len(h))


def test_near_duplicates(docs):
    rows = [(i, simhash_of(t)) for i, t in texts_of(docs)]
    fps = sorted({f for _, f in rows})
    parent = {f: f for f in fps}

    def root(f):
        while parent[f] != f:
            f = parent[f]
        return f

    for a in fps:
        for b in fps:
            if bin(a ^ b).count("1") <= 2:
                parent[root(b)] = root(a)
    least = defaultdict(list)
    for i, f in rows:
        least[root(f)].append(i)
    want = [(i, f"{f:016x}", min((x for x in least[root(f)] if x is not None), default=None)) for i, f in rows]
    got = [tuple(r) for r in simhash.near_duplicates(docs).collect()]
    assert sorted(got, key=str) == sorted(want, key=str)


def test_links_in_large_and_crowded_leaves(spark):
    rng = np.random.default_rng(1)
    base = rng.integers(0, 2**63, 400, dtype=np.uint64)
    near = base[:200] ^ (np.uint64(1) << rng.integers(0, 64, 200).astype(np.uint64))
    crowd = np.uint64(977) ^ rng.integers(0, 2**16, 900, dtype=np.uint64)
    fps = np.unique(np.r_[base, near, crowd])
    want = simhash.Forest(len(fps))
    a, b = np.nonzero(np.bitwise_count(fps[:, None] ^ fps[None, :]) <= 2)
    want.join(a, b)
    df = spark.createDataFrame([(int(x),) for x in fps.view(np.int64)], "fp long")
    for large in (10**9, 50):
        got = simhash.Forest(len(fps))
        links = simhash.near_pairs(df, 2, large).collect()
        place = lambda k: np.searchsorted(fps, np.array([r[k] for r in links], dtype=np.int64).view(np.uint64))  # noqa: E731, B023
        got.join(place("a"), place("b"))
        assert (got.label == want.label).all()


@pytest.mark.parametrize("window", [50, 3])
def test_substring_dedup(docs, window):
    rows = [(i, (t or "").encode().split()) for i, t in texts_of(docs)]
    first = {}
    for i, w in rows:
        for p in range(len(w) - window + 1):
            key = tuple(w[p : p + window])
            if i is not None:
                first[key] = min(first.get(key, i), i)
    want = []
    for i, w in rows:
        gone = [False] * len(w)
        for p in range(len(w) - window + 1):
            if i is not None and first[tuple(w[p : p + window])] < i:
                gone[p : p + window] = [True] * window
        kept = b" ".join(x for x, g in zip(w, gone) if not g)
        want.append((i, len(w), sum(gone), hashlib.sha256(kept).hexdigest()))
    got = [tuple(r) for r in substring_dedup.remove_repeats(docs, window).collect()]
    assert sorted(got, key=str) == sorted(want, key=str)


def test_wavelet_output(spark, docs):
    rows = sorted(((i, t or "") for i, t in texts_of(docs)), key=lambda r: (r[0] is not None, r[0] or 0, r[1]))
    manifest = token_output.write_shards(docs, BPE, work_path(spark, "test-shards"), shards=3)
    got = sorted((tuple(r) for r in token_output.read_shards(manifest).collect()), key=lambda r: r[1])
    want, start = [], 0
    for i, t in rows:
        ids = [*library_ids(t), 2]
        want.append((i, start, len(ids), crc(ids)))
        start += len(ids)
    assert got == want


def test_sharding(docs):
    rows = texts_of(docs)
    got = sharding.assign_shards(docs).collect()
    assert Counter((r["doc_id"], r["size"], r["text_crc32"]) for r in got) == Counter(
        (i, len((t or "").encode()) + 1, zlib.crc32((t or "").encode())) for i, t in rows
    )
    slots = defaultdict(list)
    for r in got:
        slots[r["shard"]].append(r["slot"])
        assert r["law"] == "key" and r["grown_shard"] in (r["shard"], 8) and 0 <= r["shard"] < 8
    assert all(sorted(s) == list(range(len(s))) for s in slots.values())


def test_jump_is_even_and_consistent():
    keys = np.arange(100_000)
    eight, nine = sharding.jump_shard(keys, 8), sharding.jump_shard(keys, 9)
    assert (nine[nine != eight] == 8).all()
    assert abs((nine != eight).mean() - 1 / 9) < 0.01
    assert np.abs(np.bincount(eight) / 12_500 - 1).max() < 0.05


@pytest.mark.parametrize("capacity", [4096, 37])
def test_packing(docs, capacity):
    got = packing.pack(docs, BPE, capacity).collect()
    want = []
    for i, t in texts_of(docs):
        ids = [*library_ids(t), 1]
        want += [(i, k, at, len(p := ids[at : at + capacity]), crc(p)) for k, at in enumerate(range(0, len(ids), capacity))]
    assert sorted((tuple(r)[:5] for r in got), key=str) == sorted(want, key=str)
    bins = defaultdict(list)
    for r in got:
        bins[r["sequence_id"]].append((r["offset"], r["length"]))
    for places in bins.values():
        end = 0
        for offset, length in sorted(places):
            assert offset == end
            end += length
        assert end <= capacity
    assert len(bins) <= 1.1 * -(-sum(w[3] for w in want) // capacity) + 1


def test_components_of_links_that_differ_each_time_they_are_read(spark):
    import os

    import pyarrow as pa

    def star(batches):
        for b in batches:
            for g in b.column("id").to_pylist():
                nodes = np.random.default_rng(int.from_bytes(os.urandom(8), "little")).permutation(40) + 100 * g
                yield pa.RecordBatch.from_arrays([pa.array(nodes[1:]), pa.array(np.repeat(nodes[0], 39))], names=["a", "b"])

    links = spark.range(20).mapInArrow(star, "a long, b long")
    got = {(r["node"], r["root"]) for r in components.connected_components(links).collect()}
    assert got == {(100 * g + i, 100 * g) for g in range(20) for i in range(40)}


def test_plan_equals_best_fit_over_items():
    rng = np.random.default_rng(2)
    for _ in range(30):
        lengths = sorted(rng.integers(1, 40, 80).tolist(), reverse=True)
        rooms = []
        for n in lengths:
            fits = [r for r in rooms if r >= n]
            if fits:
                rooms.remove(best := min(fits))
                rooms.append(best - n)
            else:
                rooms.append(40 - n)
        slots = packing.plan_slots(Counter(lengths), 40)
        assert len({int(s[2]) + i for s in slots for i in range(1)}) <= len(rooms)
        used = 1 + max(
            int(s[2]) + (-(-n // int(s[3]))) - 1
            for s, n in zip(slots, [_taken(slots, k, Counter(lengths)) for k in range(len(slots))])
        )
        assert used == len(rooms)


def _taken(slots, k, histogram):
    """Pieces that the k-th row of a plan places."""
    length, rank = int(slots[k][0]), int(slots[k][1])
    later = [int(s[1]) for s in slots if int(s[0]) == length and int(s[1]) > rank]
    return (min(later) if later else histogram[length]) - rank


def test_language_id(sample_docs):
    got = {r["doc_id"]: r for r in language_id.identify(sample_docs).collect()}
    rows = sample_docs.collect()
    held = [r for r in rows if zlib.crc32(str(r["doc_id"]).encode()) % 3 == 1]
    assert all(got[r["doc_id"]]["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 3 == 1) for r in rows)
    assert np.mean([got[r["doc_id"]]["lang_pred"] == r["lang"] for r in held]) > 0.95
    assert all(0 <= r["score"] <= 1 for r in got.values())


def test_language_id_of_odd_rows(odd_docs):
    got = language_id.identify(odd_docs).collect()
    assert len(got) == odd_docs.count()
    und = {r["doc_id"] for r in got if r["lang_pred"] == "und"}
    assert und == {3, 4, 6, 8, None}
    assert sum(r["doc_id"] is None and r["lang_pred"] != "und" for r in got) == 1
    assert language_id.keep_identified(odd_docs).columns == odd_docs.columns


def test_texts_stay_where_no_language_can_be_learned(spark):
    rows = [(1, "a text with letters", None), (2, "noch ein Text", None), (3, "12 345 !!", None), (4, "", None), (5, None, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    assert sorted(r["doc_id"] for r in language_id.keep_identified(docs).collect()) == [1, 2]
    held = next(i for i in range(99) if zlib.crc32(str(i).encode()) % 3 == 1)
    alone = spark.createDataFrame([(held, "only this text", "en")], "doc_id long, text string, lang string")
    assert language_id.keep_identified(alone).count() == 1


def fill(sizes):
    order = sorted(sizes, key=lambda s: (s is None, s or ""))
    weight = {s: (3, 1, 2)[i % 3] for i, s in enumerate(order)}
    total, out = 1.5 * sum(sizes.values()), {}
    while True:
        free = [s for s in order if s not in out]
        rest, w = total - sum(out.values()), sum(weight[s] for s in free)
        over = [s for s in free if rest * weight[s] / w > 2 * sizes[s] or 2 * sizes[s] == 0]
        if not over:
            return out | {s: rest * weight[s] / w for s in free}
        out |= {s: 2.0 * sizes[s] for s in over}


def test_mixing(docs):
    rows = [(r["doc_id"], r["source"], len(WORD.findall(r["text"] or ""))) for r in docs.select("doc_id", "source", "text").collect()]
    sizes = defaultdict(int)
    for _, s, n in rows:
        sizes[s] += n
    target = fill(sizes)
    got = mixing.mix(docs).collect()
    source = {i: s for i, s, _ in rows}
    assert sorted(((r["doc_id"], r["size"]) for r in got), key=str) == sorted(((i, n) for i, _, n in rows), key=str)
    taken, most = defaultdict(int), defaultdict(int)
    for r in got:
        assert 0 <= r["taken"] <= 2 * r["size"]
        if r["doc_id"] is not None:
            assert r["source_size"] == sizes[source[r["doc_id"]]]
            assert r["target"] == pytest.approx(target[source[r["doc_id"]]])
    if None not in source:
        for r in got:
            taken[source[r["doc_id"]]] += r["taken"]
            most[source[r["doc_id"]]] = max(most[source[r["doc_id"]]], r["size"])
        assert all(abs(taken[s] - target[s]) <= most[s] / 2 + 1e-6 for s in sizes)
    again = mixing.mix(docs.repartition(3)).collect()
    assert sorted(((r["doc_id"], r["taken"]) for r in got), key=str) == sorted(((r["doc_id"], r["taken"]) for r in again), key=str)
    assert mixing.take_mix(docs).columns == docs.columns


def test_search(spark):
    rng = np.random.default_rng(3)
    x = rng.normal(size=(1500, 16))
    x[700:760] = x[5]
    rows = [(i, v.tolist()) for i, v in enumerate(x)]
    rows += [(2000, None), (2020, [0.0] * 16), (2040, [float("nan")] * 16), (2060, [None] * 16), (None, x[0].tolist()), (2080, [1.0]), (20, x[20].tolist())]
    df = spark.createDataFrame([(*r, "z") for r in rows], "vec_id long, embedding array<double>, v string")
    got = defaultdict(list)
    for r in multi_index.search(df, k=10).orderBy("query_id", "rank").collect():
        got[r["query_id"]].append((r["vec_id"], r["score"]))
        assert r["rank"] == len(got[r["query_id"]])
    assert set(got) == set(range(0, 1500, 20))
    found = total = 0
    for q, hits in got.items():
        s = x @ x[q]
        s[q] = -np.inf
        want = np.lexsort((np.arange(1500), -s))[:10]
        found += len({v for v, _ in hits} & set(want.tolist()))
        total += 10
        assert all(abs(sc - x[v] @ x[q]) < 1e-9 for v, sc in hits)
        assert hits == sorted(hits, key=lambda h: (-h[1], h[0]))
    assert found / total >= 0.9


def test_empty_tables(spark, no_docs):
    assert exact_dedup.exact_dedup(no_docs).count() == 0
    assert token_counts.token_counts(no_docs, PIECES).count() == 0
    assert simhash.near_duplicates(no_docs).count() == 0
    assert substring_dedup.remove_repeats(no_docs).count() == 0
    assert token_output.read_shards(token_output.write_shards(no_docs, BPE, work_path(spark, "none"))).count() == 0
    assert sharding.assign_shards(no_docs).count() == 0
    assert packing.pack(no_docs, BPE).count() == 0
    assert language_id.identify(no_docs).count() == 0
    assert mixing.mix(no_docs).count() == 0
    assert multi_index.search(spark.createDataFrame([], "vec_id long, embedding array<float>")).count() == 0


def test_mixing_of_many_equal_rows(spark):
    """Repeated ids and sizes round among themselves; sources without number limit are ordered in ranges."""
    rows = [(None, "a b c", "s")] * 700 + [(5, "a b", "s")] * 301 + [(i, "w " * (i % 7), f"t{i % 40:02d}") for i in range(400)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    sizes, most = defaultdict(int), defaultdict(int)
    for _, t, s in rows:
        sizes[s] += len(t.split())
        most[s] = max(most[s], len(t.split()))
    target, taken = fill(sizes), defaultdict(int)
    got = mixing.mix(docs).collect()
    assert Counter((r["doc_id"], r["source"], r["size"]) for r in got) == Counter((i, s, len(t.split())) for i, t, s in rows)
    for r in got:
        taken[r["source"]] += r["taken"]
        assert r["target"] == pytest.approx(target[r["source"]])
    assert all(abs(taken[s] - target[s]) <= most[s] / 2 + 1e-6 for s in sizes)


def test_prefix_counts_of_long_text_without_spaces():
    counter = token_counts.piece_counter(PIECES)
    for text in ("qzxv" * 50_000, "日本語のテキスト" * 10_000, "\n" * 3000 + "ab　" * 2000):
        (n, fits), ids = counter.count_many([text], 4096)[0], counter.model.encode(text)
        assert n == len(ids)
        table = counter.every_prefix(text)
        assert table[-1] == n and len(table) == len(text) + 1
        assert fits == (np.flatnonzero(table <= 4096)[-1])
        assert all(table[i] == len(counter.model.encode(text[:i])) for i in range(0, 3000, 61))


def test_equal_hashes_are_not_equal_cuts():
    from influence_engine.llm import spans, tokens

    learn = lambda cuts: [np.frombuffer(c, np.uint8).astype("<u4") for c in cuts]
    store = tokens._Store(learn, "<u4", lambda raw, a, b: spans.hashes(raw, a, b) & np.uint64(3))
    text = " ".join(f"w{i % 40}" for i in range(500)).encode() + b" " + b"x" * 200
    for _ in range(3):
        starts, ends = spans.words(text)
        flat, first, size = store.look_up(text, starts, ends)
        assert [bytes(flat[a : a + n].astype(np.uint8)) for a, n in zip(first, size)] == text.split()


def test_windows_whose_keys_collide_are_told_apart(docs):
    want = [tuple(r) for r in substring_dedup.remove_repeats(docs).collect()]
    got = [tuple(r) for r in substring_dedup.remove_repeats(docs, prune_bits=3).collect()]
    assert sorted(got, key=str) == sorted(want, key=str)


def test_numerals_are_no_letters(spark):
    rows = [(1, "²½Ⅷ①", "en"), (5, "١٢ _ !", None)]
    rows += [(i, "plain words of a text", "en") if i % 2 else (i, "noch ein kurzer Satz", "de") for i in range(10, 40)]
    got = {r["doc_id"]: r["lang_pred"] for r in language_id.identify(spark.createDataFrame(rows, "doc_id long, text string, lang string")).collect()}
    assert got.pop(1) == got.pop(5) == "und" and set(got.values()) == {"en", "de"}


def test_slots_of_repeated_and_null_ids(spark):
    rows = [(7, f"text {i}") for i in range(300)] + [(None, f"null {i}") for i in range(300)] + [(i, f"own {i}") for i in range(400)]
    got = sharding.assign_shards(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert len(got) == len(rows)
    by_shard = defaultdict(list)
    for r in got:
        by_shard[r["shard"]].append((r["slot"], -1 if r["doc_id"] is None else r["doc_id"], r["doc_id"] is not None))
    for found in by_shard.values():
        found.sort()
        assert [x[0] for x in found] == list(range(len(found)))
        order = [(known, i) for _, i, known in found]
        assert order == sorted(order)
