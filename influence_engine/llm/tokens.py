"""Exact encoders over public vocabulary files that remember what they have encoded.

Both models cut a text at places no token can cross. Many texts are cut at once, each
distinct cut is encoded once by the library, and the results are joined, so the ids equal
those of the whole text. Cuts are found by a 64-bit hash and compared byte by byte. Where
the file does not prove that cuts are safe, whole texts are encoded.
"""

from __future__ import annotations

import json
import os
import re
from collections.abc import Callable, Iterable
from functools import lru_cache

import numpy as np

from . import spans

#: Cuts remembered in each worker; beyond, memory starts anew.
REMEMBERED = 1_500_000
#: Longer cuts (bytes) are encoded anew instead of remembered.
LONGEST_REMEMBERED = 64
#: Cuts that the library gets in one call.
TOGETHER = 1_000
#: Letters with marks behind them that belong to no special string or contraction: two words for the file.
_MARKED = re.compile("([a-zÀ-ÖØ-öø-ÿ]+)([!-&(-/:;=-@\\[-`{-~]+)")


class _Table:
    """Open addressing over arrays: 64-bit keys to row numbers, many at a time."""

    def __init__(self, bits: int = 16):
        self.mask, self.used = (1 << bits) - 1, 0
        self.keys = np.zeros(1 << bits, dtype=np.uint64)
        self.rows = np.zeros(1 << bits, dtype=np.int32)

    def find(self, keys: np.ndarray) -> np.ndarray:
        """Row of each key, -1 where it is not held."""
        place = (keys & np.uint64(self.mask)).astype(np.int64)
        held = self.keys[place]
        out = np.where(held == keys, self.rows[place], -1)
        live = np.flatnonzero((held != keys) & (held != 0))
        while len(live):
            place[live] = (place[live] + 1) & self.mask
            held = self.keys[place[live]]
            hit = held == keys[live]
            out[live[hit]] = self.rows[place[live[hit]]]
            live = live[~hit & (held != 0)]
        return out

    def add(self, keys: np.ndarray, rows: np.ndarray) -> None:
        """Distinct keys that are not held yet."""
        if 2 * (self.used + len(keys)) > self.mask:
            full = self.keys != 0
            keys, rows = np.r_[self.keys[full], keys], np.r_[self.rows[full], rows]
            self.__init__((3 * len(keys)).bit_length())
        self.used += len(keys)
        place = (keys & np.uint64(self.mask)).astype(np.int64)
        live = np.arange(len(keys))
        while len(live):
            free = live[self.keys[place[live]] == 0]
            self.keys[place[free]] = keys[free]
            won = self.keys[place[live]] == keys[live]
            self.rows[place[live[won]]] = rows[live[won]]
            live = live[~won]
            place[live] = (place[live] + 1) & self.mask


class _Grown:
    """An array that grows by doubling, with eight spare items behind."""

    def __init__(self, kind: str):
        self.room, self.n = np.zeros(1024, dtype=kind), 0

    def add(self, values: np.ndarray) -> None:
        need = self.n + len(values)
        if need + 8 > len(self.room):
            wide = np.zeros(2 * need + 8, dtype=self.room.dtype)
            wide[: self.n] = self.room[: self.n]
            self.room = wide
        self.room[self.n : need] = values
        self.n = need

    @property
    def held(self) -> np.ndarray:
        return self.room[: self.n]


class _Store:
    """What has been learnt of cuts: for each one an array of numbers, all in a flat one.

    Cuts are found by a 64-bit hash and then compared byte by byte, so cuts whose hashes are
    equal are never taken for each other; the second one is learnt anew each time.
    """

    def __init__(self, learn: Callable[[list[bytes]], list[np.ndarray]], kind: str, hashes=spans.hashes):
        self.learn, self.kind, self.hashes = learn, kind, hashes
        self.reset()

    def reset(self) -> None:
        self.table = _Table()
        self.first, self.size, self.flat = _Grown("<i8"), _Grown("<i4"), _Grown(self.kind)
        self.raw, self.raw_first, self.raw_size = _Grown("u1"), _Grown("<i8"), _Grown("u1")

    def _same(self, raw: bytes, starts: np.ndarray, ends: np.ndarray, row: np.ndarray) -> np.ndarray:
        """Rows whose cut has the bytes of the span; others become -1."""
        hit = np.flatnonzero(row >= 0)
        hit = hit[(ends - starts)[hit] == self.raw_size.held[row[hit]]]
        own = np.ndarray((len(self.raw.room) - 7,), dtype="<u8", buffer=self.raw.room, strides=(1,))
        same = hit[spans.equal(spans.lanes(raw), starts[hit], own, self.raw_first.held[row[hit]], (ends - starts)[hit])]
        out = np.full(len(row), -1, dtype=row.dtype)
        out[same] = row[same]
        return out

    def look_up(self, raw: bytes, starts: np.ndarray, ends: np.ndarray):
        """(flat numbers, first and size of each span's numbers in them)."""
        if self.table.used > REMEMBERED:
            self.reset()
        keys = np.maximum(self.hashes(raw, starts, ends), np.uint64(1))
        row = self._same(raw, starts, ends, self.table.find(keys))
        unseen = np.flatnonzero(row < 0)
        if not len(unseen):
            return self.flat.held, self.first.held[row], self.size.held[row].astype(np.int64)
        numbers: dict[bytes, int] = {}
        own = [numbers.setdefault(raw[a:b], len(numbers)) for a, b in zip(starts[unseen].tolist(), ends[unseen].tolist())]
        own = np.array(own, dtype=np.int64)
        cuts, at = list(numbers), unseen[np.unique(own, return_index=True)[1]]
        learnt = self.learn(cuts)
        length = np.fromiter(map(len, cuts), dtype=np.int64, count=len(cuts))
        short = np.flatnonzero(length <= LONGEST_REMEMBERED)
        # of cuts with equal hashes one is remembered
        short = short[np.unique(keys[at[short]], return_index=True)[1]]
        short = short[self.table.find(keys[at[short]]) < 0]
        where = np.full(len(cuts), -1, dtype=np.int64)
        where[short] = self._remember(keys[at[short]], [cuts[i] for i in short], [learnt[i] for i in short])
        row[unseen] = where[own]
        out_first, out_size = np.zeros(len(row), dtype=np.int64), np.zeros(len(row), dtype=np.int64)
        known = row >= 0
        out_first[known], out_size[known] = self.first.held[row[known]], self.size.held[row[known]]
        loose = np.flatnonzero(where < 0)
        if not len(loose):
            return self.flat.held, out_first, out_size
        size = np.array([len(learnt[i]) for i in loose], dtype=np.int64)
        firsts, sizes = np.zeros(len(cuts), dtype=np.int64), np.zeros(len(cuts), dtype=np.int64)
        firsts[loose], sizes[loose] = self.flat.n + np.cumsum(size) - size, size
        lost = where[own] < 0
        out_first[unseen[lost]], out_size[unseen[lost]] = firsts[own[lost]], sizes[own[lost]]
        return np.concatenate([self.flat.held, *(learnt[i] for i in loose)]), out_first, out_size

    def _remember(self, keys: np.ndarray, cuts: list[bytes], learnt: list[np.ndarray]) -> np.ndarray:
        rows = np.arange(self.first.n, self.first.n + len(cuts), dtype=np.int32)
        if len(cuts):
            self.table.add(keys, rows)
            size = np.fromiter(map(len, learnt), dtype=np.int64, count=len(learnt))
            length = np.fromiter(map(len, cuts), dtype=np.int64, count=len(cuts))
            self.first.add(self.flat.n + np.cumsum(size) - size)
            self.size.add(size)
            self.flat.add(np.concatenate(learnt))
            self.raw_first.add(self.raw.n + np.cumsum(length) - length)
            self.raw_size.add(length)
            self.raw.add(np.frombuffer(b"".join(cuts), np.uint8))
        return rows


class WordEncoder:
    """Ids of a tokenizers file; texts are cut at white space when the file drops it."""

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.model = Tokenizer.from_file(path)
        self.model.no_truncation()
        self.model.no_padding()
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        self.marks = [t["content"][:2].encode() for t in spec["added_tokens"]]
        self.cuttable = self._drops_white_space(spec)
        suffix = spec["model"].get("end_of_word_suffix")
        self.ends = None
        if self.cuttable and suffix:
            self.ends = np.zeros(self.model.get_vocab_size() + 1, dtype=bool)
            self.ends[[i for t, i in spec["model"]["vocab"].items() if t.endswith(suffix)]] = True
        self.store = _Store(self._learn, "<u4")
        self.marked: dict[str, np.ndarray] = {}

    @staticmethod
    def _drops_white_space(spec: dict) -> bool:
        norm, pre = spec.get("normalizer") or {}, spec.get("pre_tokenizer") or {}
        norms = norm.get("normalizers", [norm])
        pres = pre.get("pretokenizers", [pre])
        first = pres[0]
        return (
            [n.get("type") for n in norms] == ["NFC", "Replace", "Lowercase"]
            and norms[1].get("pattern") == {"Regex": "\\s+"}
            and first.get("type") == "Split"
            and first.get("behavior") == "Removed"
            and first.get("invert") is True
            and first.get("pattern", {}).get("Regex", "").endswith("|[\\p{L}]+|[\\p{N}]|[^\\s\\p{L}\\p{N}]+")
            and all(not p.get("add_prefix_space") and not p.get("use_regex") for p in pres[1:])
            and not any(re.search(r"\s", t["content"]) for t in spec["added_tokens"])
        )

    def _library(self, text: str) -> np.ndarray:
        return np.asarray(self.model.encode_batch_fast([text], add_special_tokens=False)[0].ids, dtype="<u4")

    def _learn(self, cuts: list[bytes]) -> list[np.ndarray]:
        """Words of letters go to the library many at once: each ends with an id that ends a word."""
        out: list[np.ndarray | None] = [None] * len(cuts)
        letters, words, odd = [], [], []
        tails: dict[int, str] = {}
        for i, cut in enumerate(cuts):
            word = cut.decode()
            if self.ends is not None and word.isalpha():
                letters.append(i)
                words.append(word)
            elif self.ends is not None and (parts := _MARKED.fullmatch(word)):
                letters.append(i)
                words.append(parts[1])
                tails[i] = parts[2]
            else:
                odd.append(i)
        for at in range(0, len(letters), TOGETHER):
            some = letters[at : at + TOGETHER]
            ids = self._library(" ".join(words[at : at + TOGETHER]))
            last = (np.flatnonzero(self.ends[ids]) + 1).tolist()
            if len(last) == len(some):
                for i, a, b in zip(some, [0, *last], last):
                    out[i] = ids[a:b] if i not in tails else np.concatenate([ids[a:b], self._tail(tails[i])])
            else:
                odd += some
        for at in range(0, len(odd), TOGETHER):
            some = odd[at : at + TOGETHER]
            for i, e in zip(some, self.model.encode_batch_fast([cuts[i].decode() for i in some], add_special_tokens=False)):
                out[i] = np.asarray(e.ids, dtype="<u4")
        return out

    def _tail(self, marks: str) -> np.ndarray:
        known = self.marked.get(marks)
        if known is None:
            if len(self.marked) > REMEMBERED:
                self.marked.clear()
            known = self.marked[marks] = self._library(marks)
        return known

    @staticmethod
    def _split_stops(raw: bytes, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """A last full stop or comma after a letter a-z is always a word of its own."""
        data = np.frombuffer(raw, np.uint8)
        last, prior = data[ends - 1], data[np.maximum(ends - 2, 0)]
        stop = (ends - starts > 1) & ((last == 46) | (last == 44)) & (prior >= 97) & (prior <= 122)
        place = np.arange(len(starts)) + np.cumsum(stop) - stop
        out = np.empty((2, len(starts) + int(stop.sum())), dtype=np.int64)
        out[0, place], out[1, place] = starts, ends - stop
        out[0, place[stop] + 1], out[1, place[stop] + 1] = ends[stop] - 1, ends[stop]
        return out[0], out[1]

    def encode_many(self, texts: list[bytes]) -> list[np.ndarray]:
        """Little-endian unsigned 32-bit ids of whole UTF-8 texts, without added special tokens."""
        if not self.cuttable:
            return [self._library(t.decode()) for t in texts]
        # the file lowers case, so A-Z can be lowered first where that makes no special string
        whole = {i: self._library(t.decode()) for i, t in enumerate(texts) if any(m in t for m in self.marks)}
        raw = b"\n".join(b"" if i in whole else t for i, t in enumerate(texts)).lower()
        starts, ends = self._split_stops(raw, *spans.words(raw))
        flat, first, size = self.store.look_up(raw, starts, ends)
        upto = np.r_[0, np.cumsum(size)]
        ids = flat[np.repeat(first - upto[:-1], size) + np.arange(upto[-1])]
        sizes = np.array([0 if i in whole else len(t) for i, t in enumerate(texts)], dtype=np.int64)
        begins = np.cumsum(np.r_[0, sizes + 1])
        edges = upto[np.searchsorted(starts, begins)].tolist()
        return [whole[i] if i in whole else ids[a:b] for i, (a, b) in enumerate(zip(edges, edges[1:]))]


class PrefixTable:
    """Token counts of every prefix of a string under byte-pair merges, in one pass.

    The last token of a prefix is the one piece that ends it and that merges would leave beside
    the last token of what comes before, so the count at a place is the count at the start of
    that piece plus one. Pieces that end at a place are found along a tree of reversed pieces.
    """

    def __init__(self, pieces: dict[str, float]):
        self.score = pieces
        self.tree: dict = {}
        for piece in pieces:
            node = self.tree
            for c in reversed(piece):
                node = node.setdefault(c, {})
            node[""] = piece
        self.beside: dict[tuple[str, str], bool] = {}

    def merged(self, text: str) -> list[str]:
        """Merge neighbours, the best score first, then the leftmost."""
        parts, score = list(text), self.score
        while len(parts) > 1:
            found = [(-score[a + b], i) for i, (a, b) in enumerate(zip(parts, parts[1:])) if a + b in score]
            if not found:
                break
            i = min(found)[1]
            parts[i : i + 2] = [parts[i] + parts[i + 1]]
        return parts

    def stay(self, left: str, right: str) -> bool:
        """Whether merges leave these two tokens beside each other; nothing on the left is allowed."""
        if len(self.beside) > REMEMBERED:
            self.beside.clear()
        known = self.beside[left, right] = self.merged(left + right) == ([left, right] if left else [right])
        return known

    def counts(self, texts: list[str]) -> list[np.ndarray | None]:
        """Of each text, tokens of text[:i] for i from 1; a character without a piece counts its bytes.

        Texts are taken in sorted order, and each one goes on from where it leaves the one
        before. None where a place has no last token.
        """
        out: list[np.ndarray | None] = [None] * len(texts)
        tree, beside, score, stay = self.tree, self.beside, self.score, self.stay
        prior, last, n = "", [""], [0]
        for number in sorted(range(len(texts)), key=texts.__getitem__):
            text, same = texts[number], 0
            most = min(len(prior), len(text), len(last) - 1)
            while same < most and prior[same] == text[same]:
                same += 1
            del last[same + 1 :], n[same + 1 :]
            prior = text
            for i in range(same, len(text)):
                node, at = tree.get(text[i]), i
                while node is not None:
                    piece = node.get("")
                    if piece is not None:
                        left = last[at]
                        known = beside.get((left, piece))
                        if stay(left, piece) if known is None else known:
                            last.append(piece)
                            n.append(n[at] + 1)
                            break
                    at -= 1
                    node = node.get(text[at]) if at >= 0 else None
                else:
                    if text[i] in score:
                        break
                    last.append(text[i])
                    n.append(n[i] + len(text[i].encode()))
            if len(n) > len(text):
                out[number] = np.array(n[1:], dtype="<i4")
        return out


class PieceCounter:
    """Token counts of a sentencepiece BPE file at every prefix of a text.

    Prefix counts follow a recurrence over cuts: the count at a place inside a cut is the
    count at the cut's start plus the prefix count within the cut, which is kept for each
    distinct cut. A cut is a line end with what follows it, or a run of spaces with what
    follows it; the library puts a space before every text, so the first cut has one more
    than the text. The last entry of each cut is held against the library's own count.
    """

    def __init__(self, path: str):
        from sentencepiece import SentencePieceProcessor

        self.model = SentencePieceProcessor(model_file=path)
        n = self.model.get_piece_size()
        pieces = [self.model.id_to_piece(i) for i in range(n)]
        probe = self.model.encode("a\nb  c", out_type=str)
        plain = [i for i in range(n) if not (self.model.is_unknown(i) or self.model.is_control(i) or self.model.is_byte(i))]
        self.cuttable = (
            not any("▁" in p.lstrip("▁") or "\n" in p for p in pieces)
            and not any(self.model.is_unused(i) for i in range(n))
            and any(self.model.is_byte(i) for i in range(n))
            and "".join(probe).replace("<0x0A>", "\n") == "▁a\nb▁▁c"
        )
        self.prefixes = PrefixTable({pieces[i]: self.model.get_score(i) for i in plain})
        self.store = _Store(self._learn, "<i4")

    def _learn(self, cuts: list[bytes]) -> list[np.ndarray]:
        # the library adds the first space itself, before a line end too, and none to nothing
        texts = [c.decode() for c in cuts]
        keys = [t if t[:1] == "\n" else t[1:] for t in texts]
        coded = self.model.encode(keys, num_threads=1)
        out = []
        tables = self.prefixes.counts([t.replace(" ", "▁") for t in texts])
        for text, key, ids, counts in zip(texts, keys, coded, tables):
            if counts is None or counts[-1] != (len(ids) - (key[:1] == "\n") if key else 1):
                counts = np.array([self._part(text[:j]) for j in range(1, len(text) + 1)], dtype="<i4")
            out.append(counts)
        return out

    def _part(self, cut: str) -> int:
        """Tokens of a cut by the library: only where the file has pieces that merges do not explain."""
        if cut[0] == "\n":
            return len(self.model.encode(cut)) - 1
        return len(self.model.encode(cut[1:])) if len(cut) > 1 else 1

    def _tables(self, texts: list[str]):
        """Over all texts: flat prefix counts, each cut's first entry and characters, each text's first cut."""
        parts = [b" " + t.encode().replace("▁".encode(), b" ") if t else b"" for t in texts]
        raw = b"".join(parts)
        begins = np.cumsum(np.r_[0, np.fromiter(map(len, parts), np.int64, len(parts))])
        data = np.frombuffer(raw, np.uint8)
        space = data == 32
        opens = data == 10
        opens[space] = True
        opens[1:] &= ~(space[1:] & space[:-1])
        opens[begins[:-1][begins[:-1] < begins[1:]]] = True
        starts = np.flatnonzero(opens)
        flat, first, size = self.store.look_up(raw, starts, np.r_[starts[1:], len(raw)] if len(starts) else starts)
        return flat, first, size, np.searchsorted(starts, begins)

    def count_many(self, texts: list[str], budget: int | None = None) -> list[tuple[int, int]]:
        """Tokens of each text, and the characters of its longest prefix within the budget."""
        if not self.cuttable:
            tables = [self.every_prefix(t) for t in texts]
            return [(int(t[-1]), len(t) - 1 if budget is None else int(np.flatnonzero(t <= budget)[-1])) for t in tables]
        flat, first, size, edges = self._tables(texts)
        upto = np.r_[0, np.cumsum(flat[first + size - 1], dtype=np.int64)]
        chars = np.r_[0, np.cumsum(size)]
        totals = upto[edges[1:]] - upto[edges[:-1]]
        fits = [len(t) for t in texts]
        if budget is not None:
            for i in np.flatnonzero(totals > budget).tolist():
                a, b = edges[i], edges[i + 1]
                # whole cuts only add tokens, so beside those that fit only a part of the next one does
                cut = int(np.searchsorted(upto[a + 1 : b + 1] - upto[a], budget, side="right")) + a
                inside = np.flatnonzero(flat[first[cut] : first[cut] + size[cut]] <= budget - (upto[cut] - upto[a]))
                part = int(inside[-1]) + 1 if len(inside) else 0
                fits[i] = max(0, int(chars[cut] - chars[a]) + part - 1)
        return list(zip(totals.tolist(), fits))

    def every_prefix(self, text: str) -> np.ndarray:
        """Exact tokens of text[:i] for every i from 0 to len(text)."""
        if not self.cuttable:
            return np.array([len(self.model.encode(text[:i])) for i in range(len(text) + 1)], dtype=np.int64)
        if not text:
            return np.zeros(1, dtype=np.int64)
        flat, first, size, _ = self._tables([text])
        chars = np.r_[0, np.cumsum(size)]
        inside = flat[np.repeat(first - chars[:-1], size) + np.arange(chars[-1])].astype(np.int64)
        ends = flat[first + size - 1].astype(np.int64)
        out = inside + np.repeat(np.cumsum(ends) - ends, size)
        out[0] = 0
        return out


@lru_cache(maxsize=4)
def word_encoder(path: str) -> WordEncoder:
    """One for each worker process and file."""
    return WordEncoder(path)


@lru_cache(maxsize=4)
def piece_counter(path: str) -> PieceCounter:
    return PieceCounter(path)


def public_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def runs_of(sizes: Iterable[int], most: int = 1 << 20) -> Iterable[tuple[int, int]]:
    """Neighbouring items of about `most` in all, as (first, end)."""
    first = held = end = 0
    for end, size in enumerate(sizes, 1):
        held += size
        if held >= most:
            yield first, end
            first, held = end, 0
    if end > first:
        yield first, end
