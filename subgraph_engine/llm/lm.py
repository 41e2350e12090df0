"""Interpolated modified Kneser-Ney trigram model, counted in Spark and mapped by workers.

Counting goes over the training texts twice. The first pass counts words: tasks sum their own, and
shards by the top bits of the words' hashes write sorted hash arrays. Words are numbered by how often
they occur (in powers of two), then by shard and hash, so that frequent ones have small numbers. The
second pass counts trigrams of numbers, in shards by the hash of their first two words: a shard keeps
its pairs as a sorted hash array, and under each pair the words that follow it and their counts. Each
distinct trigram then counts once for its last two words (how many different words come before a
pair), and each distinct pair once for its last word, summed up in the pairs' and the words' shards.

Nothing is pruned and no word is left out. Shards follow the input in number, so that one task's
share is bounded; only sums of counts and shard sizes come to the driver. Word numbers have 32 bits:
a corpus of more than 2^32 - 2 different words raises an error.

Scoring maps the arrays from the shared folder and looks up the distinct words and pairs of a block
of texts by binary search in sorted order, and each token among its pair's followers:

    p(w | u v) = max(c(u v w) - D(c(u v w)), 0) / c(u v .) + g(u v) p(w | v)
    p(w | v) = max(a(v w) - D2(a(v w)), 0) / a(v .) + g(v) p(w)
    p(w) = max(b(w) - D1(b(w)), 0) / B + g1 / (V + 1)

with a(v w) the number of different words before the pair, b(w) that of different words before w in
distinct pairs, and V the training words beside one unknown word. An order whose context was never
seen leaves the token to the next. A text is its words and one end token, after two starts.

Null text counts as empty: the end alone. An empty training set gives the uniform model. Rows
without an id count as id '' for the held-out rule.
"""

from __future__ import annotations

import os
import uuid
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import pairwise

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from subgraph_engine.llm.common import fresh_path, local, mapped
from subgraph_engine.llm.hashing import blocks, mix, word_hashes

#: Tokens that a task counts before it hands them over, bytes of text scored at once.
TOKENS, SCORED = 1 << 21, 6 << 20
#: Tokens of a shard of pairs, about; followers from which a pair's sums are stored.
SHARD_TOKENS, CROWDED = 1 << 22, 32
#: What every count gives up at least, so that nothing is impossible.
LEAST_DISCOUNT = 0.1
#: Fixed value: the hash that stands for the end of a text.
END = np.uint64(0x0E0D_0E0D_0E0D_0E0D)
_LOW, _HALF = np.uint64(0xFFFFFFFF), np.uint64(32)


# packed columns ----------------------------------------------------------------------------------
def _squeezed(values: np.ndarray) -> bytes:
    """Numbers with equal bytes together, compressed."""
    width = values.dtype.itemsize
    return pa.compress(np.ascontiguousarray(values.view("u1").reshape(-1, width).T).tobytes(), codec="zstd", asbytes=True)


def _spread(data: bytes, n: int, kind: str) -> np.ndarray:
    width = np.dtype(kind).itemsize
    raw = pa.decompress(data, decompressed_size=width * n, codec="zstd", asbytes=True)
    return np.ascontiguousarray(np.frombuffer(raw, "u1").reshape(width, n).T).reshape(-1).view(kind)


def _pack(sorted_keys: np.ndarray) -> bytes:
    """Sorted numbers by their differences."""
    return _squeezed(np.diff(sorted_keys, prepend=np.zeros(1, "<u8")))


def _unpack(data: bytes, n: int) -> np.ndarray:
    return np.cumsum(_spread(data, n, "<u8"), dtype="<u8")


def _firsts(*keys: np.ndarray) -> np.ndarray:
    """Where runs of equal rows begin in sorted columns."""
    new = np.zeros(len(keys[0]), bool)
    new[:1] = True
    for k in keys:
        new[1:] |= k[1:] != k[:-1]
    return np.flatnonzero(new)


def _sum_by(keys: np.ndarray, *counts: np.ndarray) -> tuple[np.ndarray, ...]:
    """Distinct keys in order, and each one's sums."""
    if not len(keys):
        return keys, *counts
    order = np.argsort(keys, kind="stable")
    keys = keys[order]
    at = _firsts(keys)
    return keys[at], *(np.add.reduceat(c[order], at) for c in counts)


def _sum_grams(pairs: np.ndarray, words: np.ndarray, counts: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct (pair, word) in order and their sums."""
    order = np.lexsort((words, pairs))
    pairs, words = pairs[order], words[order]
    at = _firsts(pairs, words)
    if counts is None:
        return pairs[at], words[at], np.diff(at, append=len(pairs)).astype("<u8")
    return pairs[at], words[at], np.add.reduceat(counts[order], at) if len(at) else counts


# stored columns ----------------------------------------------------------------------------------
def _save(base: str, name: str, values: np.ndarray) -> None:
    """Written beside and renamed, so that a task that runs again does no harm."""
    draft = f"{local(base)}/{name}.{uuid.uuid4().hex}"
    values.tofile(draft)
    os.replace(draft, f"{local(base)}/{name}")


def _save_small(base: str, name: str, values: np.ndarray) -> None:
    """Counts, most of them small: one byte each; 255 refers to a sorted list of places and values."""
    large = np.flatnonzero(values >= 255)
    _save(base, name, np.minimum(values, 255).astype("u1"))
    _save(base, f"{name}.at", large.astype("<u8"))
    _save(base, f"{name}.value", values[large].astype("<u8"))


def _small(base: str, name: str, at: np.ndarray) -> np.ndarray:
    """The counts at some places."""
    out = mapped(f"{local(base)}/{name}", "u1")[at].astype("<i8")
    large = np.flatnonzero(out == 255)
    if len(large):
        there = np.searchsorted(mapped(f"{local(base)}/{name}.at", "<u8"), at[large].astype("<u8"))
        out[large] = mapped(f"{local(base)}/{name}.value", "<u8")[there]
    return out


def _cuts(keys: np.ndarray, bits: int) -> Iterator[tuple[int, int, int]]:
    """(shard, first, last) of sorted keys, shard by shard."""
    tops = (np.arange(1, 1 << bits, dtype="<u8") << np.uint64(64 - bits)) if bits else np.zeros(0, "<u8")
    ends = [0, *np.searchsorted(keys, tops).tolist(), len(keys)]
    return ((k, a, b) for k, (a, b) in enumerate(pairwise(ends)) if a < b)


def _power(counts: np.ndarray) -> np.ndarray:
    """The power of two of each count, 0 to 63."""
    return np.frexp(counts.astype("f8"))[1].astype("<i8") - 1


#: Columns of a word: as a context its followers' sum and how many have one, two or more words before
#: the pair; and the different words before it.
WORD_COLUMNS = ("follow", "once", "twice", "more", "before")


@dataclass(frozen=True)
class Words:
    """Words by sorted hashes, in shards by their top ``bits``; ``bases[power, shard]`` begins their numbers."""

    base: str
    bits: int
    sizes: tuple[int, ...]
    bases: np.ndarray

    def find(self, keys: np.ndarray) -> tuple[np.ndarray, ...]:
        """Of each of the sorted keys: shard, place in it (or -1), number (or -1) and count."""
        shard, place, number, count = (np.full(len(keys), x, "<i8") for x in (0, -1, -1, 0))
        for k, a, b in _cuts(keys, self.bits):
            shard[a:b] = k
            if own := self.sizes[k]:
                there = mapped(f"{local(self.base)}/{k}.keys", "<u8")
                at = np.minimum(np.searchsorted(there, keys[a:b]), own - 1)
                hit = np.flatnonzero(there[at] == keys[a:b])
                at = at[hit]
                place[a:b][hit] = at
                count[a:b][hit] = counts = _small(self.base, f"{k}.count", at)
                number[a:b][hit] = self.bases[_power(counts), k] + mapped(f"{local(self.base)}/{k}.rank", "<u4")[at]
        return shard, place, number, count

    def columns(self, shard: np.ndarray, place: np.ndarray) -> list[np.ndarray]:
        """WORD_COLUMNS at places of ascending shards; 0 where a place is -1."""
        out = [np.zeros(len(place), "<i8") for _ in WORD_COLUMNS]
        ends = np.searchsorted(shard, np.arange(len(self.sizes) + 1))
        for k, (a, b) in enumerate(pairwise(ends.tolist())):
            known = np.flatnonzero(place[a:b] >= 0)
            if len(known):
                for values, name in zip(out, WORD_COLUMNS, strict=True):
                    values[a:b][known] = _small(self.base, f"{k}.{name}", place[a:b][known])
        return out


@dataclass(frozen=True)
class Pairs:
    """Pairs by sorted hashes of their numbers, in shards by their top ``bits``.

    Each has the count of different words before it, and its followers: ``offsets`` into ``word``
    (ascending numbers) and ``count``. Pairs with the end have no followers and stand apart.
    """

    base: str
    bits: int
    sizes: tuple[int, ...]  # pairs with followers
    ends: tuple[int, ...]  # pairs with the end

    def look(self, keys: np.ndarray, asked: np.ndarray, words: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Of the sorted keys: ``before``, and the followers' sum and how many have counts of one, two
        and more; and the count of each of ``words`` after the key at ``asked``."""
        before, sums, counts = np.zeros(len(keys), "<i8"), np.zeros((4, len(keys)), "<i8"), np.zeros(len(asked), "<i8")
        order = np.argsort(asked, kind="stable")
        asked, words = asked[order], words[order]
        for k, a, b in _cuts(keys, self.bits):
            base = f"{local(self.base)}/{k}"
            rest = np.arange(a, b)
            if own := self.sizes[k]:
                there = mapped(f"{base}.keys", "<u8")
                at = np.minimum(np.searchsorted(there, keys[a:b]), own - 1)
                found = there[at] == keys[a:b]
                hit = np.flatnonzero(found)
                rest = rest[~found]
                if len(hit):
                    at = at[hit]
                    before[a + hit] = _small(self.base, f"{k}.before", at)
                    offsets = mapped(f"{base}.offsets", "<u4")
                    low, high = offsets[at].astype("<i8"), offsets[at + 1].astype("<i8")
                    sums[:, a + hit] = self._sums(k, at, low, high)
                    x, y = np.searchsorted(asked, [a, b])
                    span = np.full((2, b - a), 0, "<i8")
                    span[:, hit] = low, high
                    counts[order[x:y]] = self._counts(k, *span[:, asked[x:y] - a], words[x:y])
            if (own := self.ends[k]) and len(rest):
                there = mapped(f"{base}.end_keys", "<u8")
                at = np.minimum(np.searchsorted(there, keys[rest]), own - 1)
                hit = np.flatnonzero(there[at] == keys[rest])
                before[rest[hit]] = _small(self.base, f"{k}.end_before", at[hit])
        return before, sums, counts

    def _sums(self, shard: int, at: np.ndarray, low: np.ndarray, high: np.ndarray) -> np.ndarray:
        out = np.zeros((4, len(at)), "<i8")
        n = high - low
        few, many = np.flatnonzero(n < CROWDED), np.flatnonzero(n >= CROWDED)
        if len(few):
            starts = np.cumsum(n[few]) - n[few]
            own = _small(self.base, f"{shard}.count", np.repeat(low[few] - starts, n[few]) + np.arange(n[few].sum()))
            out[:, few] = [np.add.reduceat(x.astype("<i8"), starts) for x in (own, own == 1, own == 2, own > 2)]
        if len(many):
            there = np.searchsorted(mapped(f"{local(self.base)}/{shard}.crowded", "<u8"), at[many].astype("<u8"))
            out[:, many] = mapped(f"{local(self.base)}/{shard}.crowded_sums", "<u8").reshape(-1, 4)[there].T
        return out

    def _counts(self, shard: int, low: np.ndarray, high: np.ndarray, words: np.ndarray) -> np.ndarray:
        """Binary search of each word among its own stretch of followers."""
        every, stop = mapped(f"{local(self.base)}/{shard}.word", "<u4"), high
        low, high = low.copy(), high.copy()
        while len(open_ := np.flatnonzero(low < high)):
            middle = (low[open_] + high[open_]) >> 1
            less = every[middle] < words[open_]
            low[open_] = np.where(less, middle + 1, low[open_])
            high[open_] = np.where(less, high[open_], middle)
        out = np.zeros(len(words), "<i8")
        inside = np.flatnonzero(low < stop)
        hit = inside[every[low[inside]] == words[inside]]
        out[hit] = _small(self.base, f"{shard}.count", low[hit])
        return out


# the model ---------------------------------------------------------------------------------------
def _discounts(n: list[int]) -> tuple[float, float, float]:
    """For counts of one, two and more, from how many have counts of one to four."""
    n1, n2, n3, n4 = n
    if not all(n):  # too few to tell
        return 0.5, 1.0, 1.5
    y = n1 / (n1 + 2 * n2)
    d = 1 - 2 * y * n2 / n1, 2 - 3 * y * n3 / n2, 3 - 4 * y * n4 / n3
    return tuple(min(max(x, LEAST_DISCOUNT), k) for k, x in enumerate(d, 1))


def _less(counts: np.ndarray, d: tuple[float, float, float]) -> np.ndarray:
    """The counts after their discounts."""
    return np.maximum(counts - np.array([0.0, *d])[np.minimum(counts, 3).astype("<i8")], 0.0)


def _mixed(own: np.ndarray, d: tuple[float, float, float], sums: np.ndarray, below: np.ndarray) -> np.ndarray:
    """One order's probability: the discounted count's share, and what the discounts leave to the order below."""
    whole = np.maximum(sums[0], 1)
    left = sum(x * n for x, n in zip(d, sums[1:], strict=True)) / whole
    return np.where(sums[0] > 0, _less(own, d) / whole + left * below, below)


def _tokens(texts: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hashes of all words with an end after each text; where texts begin, and their tokens."""
    hashes, at = word_hashes(texts)
    rows, n = len(texts), np.diff(at) + 1
    ends = np.cumsum(n) - 1
    out = np.empty(len(hashes) + rows, "<u8")
    is_end = np.zeros(len(out), bool)
    is_end[ends] = True
    out[is_end], out[~is_end] = END, hashes
    return out, ends - n + 1, n


def _before(values: np.ndarray, begins: np.ndarray, start: int) -> np.ndarray:
    """What stands before each token: another, or the start."""
    out = np.empty_like(values)
    out[1:] = values[:-1]
    out[begins] = start
    return out


@dataclass(frozen=True)
class Model:
    words: Words
    pairs: Pairs
    tokens: int  # of training
    types: int  # also the number of the start
    discounts: tuple[tuple[float, float, float], ...]  # of words, pairs and trigrams
    befores: int  # distinct pairs
    before_counts: tuple[int, int, int]  # words with one, two, more different words before them
    start: tuple[int, int, int, int]  # the start as a context: as WORD_COLUMNS

    def unknown(self) -> float:
        """An unknown word's probability without context, and what each word gets beside its own."""
        if not self.befores:
            return 1 / (self.types + 1)
        return sum(d * n for d, n in zip(self.discounts[0], self.before_counts, strict=True)) / self.befores / (self.types + 1)

    def score(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Of each text: tokens, known ones, base score and score (log10)."""
        tokens, begins, n = _tokens(texts)
        distinct, back = np.unique(tokens, return_inverse=True)
        shard, place, number, count = self.words.find(distinct)
        *follow, before = self.words.columns(shard, place)
        lone = _less(before, self.discounts[0]) / max(self.befores, 1) + self.unknown()
        base = np.log10((count + 1) / (self.tokens + self.types + 1))[back]

        of = number[back]
        last = _before(of, begins, self.types)
        known = np.flatnonzero((of >= 0) & (last >= 0))
        first = np.uint64(self.types) << _HALF | np.uint64(self.types)
        names = mix(np.append((last[known].astype("<u8") << _HALF) | of[known].astype("<u8"), first))
        keys, at = np.unique(names, return_inverse=True)
        pair = np.full(len(of), -1, "<i8")  # of each token with the one before it
        pair[known] = at[:-1]
        context = _before(pair, begins, int(at[-1]))
        asks = np.flatnonzero((context >= 0) & (of >= 0))
        ahead, sums, counts = self.pairs.look(keys, context[asks], of[asks].astype("<u4"))

        slot = _before(back.astype("<i8"), begins, len(distinct))
        of_word = np.stack([np.append(x, s) for x, s in zip(follow, self.start, strict=True)])[:, slot]
        p = _mixed(np.where(pair >= 0, ahead[pair], 0), self.discounts[1], of_word, lone[back])
        own = np.zeros(len(of), "<i8")
        own[asks] = counts
        p = _mixed(own, self.discounts[2], np.where(context >= 0, sums[:, context], 0), p)
        return n, *(np.add.reduceat(x, begins) for x in ((count > 0)[back].astype("<i8"), base, np.log10(p)))


# training ----------------------------------------------------------------------------------------
_PARTS = "shard int, n long, keys binary, words binary, counts binary"


def _rows(parts: list[tuple[int, int, bytes, bytes, bytes]]) -> pa.RecordBatch:
    kinds = (pa.int32(), pa.int64(), pa.binary(), pa.binary(), pa.binary())
    columns = list(zip(*parts, strict=True)) or [()] * 5
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names=["shard", "n", "keys", "words", "counts"])


def _sharded(keys: np.ndarray, by: np.ndarray, bits: int, words: np.ndarray | None, counts: np.ndarray) -> list[tuple[int, int, bytes, bytes, bytes]]:
    """Sorted keys with their columns, by the shard of ``by``, packed."""
    shard = (by >> np.uint64(64 - bits)).astype("<i8") if bits else np.zeros(len(by), "<i8")
    order, out = np.argsort(shard, kind="stable"), []
    for k, (a, b) in enumerate(pairwise(np.searchsorted(shard[order], np.arange((1 << bits) + 1)).tolist())):
        if a < b:
            own = order[a:b]
            out.append((k, b - a, _pack(keys[own]), b"" if words is None else _squeezed(words[own]), _squeezed(counts[own])))
    return out


def _joined(table: pa.Table) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """All parts of a shard, unpacked: keys, words (none, if parts have none) and counts."""
    parts = [x for x in zip(*(table[c].to_pylist() for c in ("n", "keys", "words", "counts")), strict=True) if x[0]]
    keys = [_unpack(keys, n) for n, keys, _, _ in parts]
    words = [_spread(words, n, "<u4") for n, _, words, _ in parts if words]
    counts = [_spread(counts, n, "<u8") for n, _, _, counts in parts]
    return tuple(np.concatenate(x or [np.zeros(0, kind)]) for x, kind in ((keys, "<u8"), (words, "<u4"), (counts, "<u8")))


def _fours(counts: np.ndarray) -> list[int]:
    """How many counts are one to four."""
    return [int((counts == k).sum()) for k in range(1, 5)]


def _count_words(texts: DataFrame, base: str, bits: int) -> tuple[Words, int]:
    """The words' shards and the number of tokens."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        waiting, n = [], 0

        def total() -> pa.RecordBatch:
            keys, counts = np.unique(np.concatenate(waiting), return_counts=True)
            return _rows(_sharded(keys, keys, bits, None, counts.astype("<u8")))

        for batch in batches:
            for part in blocks(batch, 0):
                waiting.append(_tokens(part.column(0))[0])
                n += len(waiting[-1])
                if n >= TOKENS:
                    yield total()
                    waiting, n = [], 0
        if waiting:
            yield total()

    def merge(table: pa.Table) -> pa.Table:
        keys, _, counts = _joined(table)
        keys, counts = _sum_by(keys, counts)
        shard, power = table["shard"][0].as_py(), _power(counts)
        order = np.argsort(power, kind="stable")
        sizes = np.bincount(power, minlength=64)
        rank = np.empty(len(keys), "<u4")
        rank[order] = np.arange(len(keys)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
        _save(base, f"{shard}.keys", keys)
        _save(base, f"{shard}.rank", rank)
        _save_small(base, f"{shard}.count", counts)
        return pa.table({"shard": pa.array([shard], pa.int32()), "sizes": pa.array([sizes.tolist()], pa.list_(pa.int64())), "tokens": pa.array([int(counts.sum())], pa.int64())})

    got = texts.mapInArrow(count, _PARTS).groupBy("shard").applyInArrow(merge, "shard int, sizes array<long>, tokens long").collect()
    sizes = np.zeros((64, 1 << bits), "<i8")
    for r in got:
        sizes[:, r["shard"]] = r["sizes"]
    falling = sizes[::-1].reshape(-1)  # frequent words first
    bases = (np.cumsum(falling) - falling).reshape(64, -1)[::-1]
    return Words(base, bits, tuple(sizes.sum(0).tolist()), np.ascontiguousarray(bases)), sum(r["tokens"] for r in got)


def train(texts: DataFrame) -> Model:
    """The model of a frame's ``text`` column."""
    spark, texts = texts.sparkSession, texts.select("text")
    least = max(2, int(spark.conf.get("spark.sql.shuffle.partitions")), texts.rdd.getNumPartitions())
    base = fresh_path(spark, "language_model")
    word_base, pair_base = f"{base}/words", f"{base}/pairs"
    for d in (word_base, pair_base):
        os.makedirs(local(d), exist_ok=True)
    words, tokens = _count_words(texts, word_base, (least - 1).bit_length())
    types, shards = sum(words.sizes), len(words.sizes)
    if types >= (1 << 32) - 1:
        raise ValueError(f"{types} different words have no numbers of 32 bits")
    bits = max(least - 1, tokens // SHARD_TOKENS).bit_length()
    end = int(words.find(np.array([END]))[2][0]) if tokens else -1
    # all numbers begin in some (power, shard); the start's is the first past them
    flat = words.bases[::-1].reshape(-1)

    def owners(numbers: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The powers and the shards of numbers."""
        at = np.searchsorted(flat, numbers, "right") - 1
        return 63 - at // shards, at % shards

    def count_grams(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pairs, last, n = [], [], 0
        for batch in batches:
            for part in blocks(batch, 0, SCORED):
                own, begins, _ = _tokens(part.column(0))
                distinct, back = np.unique(own, return_inverse=True)
                of = words.find(distinct)[2].astype("<u8")[back]
                one = _before(of, begins, types)
                pairs.append((_before(one, begins, types) << _HALF) | one)
                last.append(of.astype("<u4"))
                n += len(of)
                if n >= TOKENS:
                    keys, ends, counts = _sum_grams(np.concatenate(pairs), np.concatenate(last))
                    yield _rows(_sharded(keys, mix(keys), bits, ends, counts))
                    pairs, last, n = [], [], 0
        if n:
            keys, ends, counts = _sum_grams(np.concatenate(pairs), np.concatenate(last))
            yield _rows(_sharded(keys, mix(keys), bits, ends, counts))

    def stats(shard: int, values: list[int]) -> tuple[int, int, bytes, bytes, bytes]:
        return -1 - shard, len(values), b"", b"", np.array(values, "<u8").tobytes()

    def merge_grams(table: pa.Table) -> pa.Table:
        shard = table["shard"][0].as_py()
        keys, last, counts = _sum_grams(*_joined(table))
        at = _firsts(keys)
        n, own = np.diff(at, append=len(keys)), mix(keys[at])
        order = np.argsort(own)
        sizes = n[order]
        starts = np.cumsum(sizes) - sizes
        into = np.repeat(at[order] - starts, sizes) + np.arange(len(keys))
        followers = counts[into]
        _save(pair_base, f"{shard}.keys", own[order])
        _save(pair_base, f"{shard}.offsets", np.append(starts, len(keys)).astype("<u4"))
        _save(pair_base, f"{shard}.word", last[into])
        _save_small(pair_base, f"{shard}.count", followers)
        crowded = np.flatnonzero(sizes >= CROWDED)
        sums = np.array([np.add.reduceat(x.astype("<u8"), starts)[crowded] for x in (followers, followers == 1, followers == 2, followers > 2)])
        _save(pair_base, f"{shard}.crowded", crowded.astype("<u8"))
        _save(pair_base, f"{shard}.crowded_sums", np.ascontiguousarray(sums.T))
        # each distinct trigram has one more word before its last two; the shard itself hears of it even if nothing comes
        ahead, befores = _sum_by((keys << _HALF) | last.astype("<u8"), np.ones(len(keys), "<u8"))
        out = _sharded(ahead, mix(ahead), bits, None, befores)
        return pa.Table.from_batches([_rows([*out, (shard, 0, b"", b"", b""), stats(shard, [len(own), *_fours(counts)])])])

    def merge_pairs(table: pa.Table) -> pa.Table:
        shard = table["shard"][0].as_py()
        if shard < 0:
            return pa.Table.from_batches([_rows([tuple(table[c][0].as_py() for c in ("shard", "n", "keys", "words", "counts"))])])
        pairs, _, befores = _joined(table)
        pairs, befores = _sum_by(pairs, befores)
        path, is_end = f"{local(pair_base)}/{shard}.keys", (pairs & _LOW) == np.uint64(end)
        there = np.fromfile(path, "<u8") if os.path.exists(path) else np.zeros(0, "<u8")
        column = np.zeros(len(there), "<u8")
        column[np.searchsorted(there, mix(pairs[~is_end]))] = befores[~is_end]
        _save_small(pair_base, f"{shard}.before", column)
        own = mix(pairs[is_end])
        order = np.argsort(own)
        _save(pair_base, f"{shard}.end_keys", own[order])
        _save_small(pair_base, f"{shard}.end_before", befores[is_end][order])
        out = []

        def hand_over(kind: int, numbers: np.ndarray, *columns: np.ndarray) -> None:
            numbers, *sums = _sum_by(numbers, *columns)
            owner = np.where(numbers == np.uint64(types), shards, owners(numbers)[1])
            order = np.argsort(owner, kind="stable")
            for k, (a, b) in enumerate(pairwise(np.searchsorted(owner[order], np.arange(shards + 2)).tolist())):
                if a < b:
                    at = order[a:b]
                    out.append((k, b - a, _pack(numbers[at]), bytes([kind]), _squeezed(np.concatenate([x[at] for x in sums]))))

        hand_over(0, pairs >> _HALF, befores, *((befores == k).astype("<u8") for k in (1, 2)), (befores > 2).astype("<u8"))
        hand_over(1, pairs & _LOW, np.ones(len(pairs), "<u8"))
        # shards of words and of pairs have numbers of their own: pairs' sums go by, below zero
        return pa.Table.from_batches([_rows([*out, stats((1 << bits) + shard, [int(is_end.sum()), len(pairs), *_fours(befores)])])])

    def merge_sums(table: pa.Table) -> pa.Table:
        shard, sums = table["shard"][0].as_py(), []
        if shard < 0:
            sums = np.frombuffer(table["counts"][0].as_py(), "<u8").tolist()
        else:
            size = words.sizes[shard] if shard < shards else 1
            dense = {name: np.zeros(size, "<u8") for name in WORD_COLUMNS}
            if shard < shards:
                power = _power(_small(word_base, f"{shard}.count", np.arange(size)))
                order, firsts = np.argsort(power, kind="stable"), np.searchsorted(np.sort(power), np.arange(64))
            for n, keys, kind, data in zip(*(table[c].to_pylist() for c in ("n", "keys", "words", "counts")), strict=True):
                numbers = _unpack(keys, n).astype("<i8")
                at = np.zeros(n, "<i8")
                if shard < shards:
                    own = owners(numbers)[0]
                    at = order[firsts[own] + numbers - words.bases[own, shard]]
                names = WORD_COLUMNS[4:] if kind[0] else WORD_COLUMNS[:4]
                for name, values in zip(names, _spread(data, n * len(names), "<u8").reshape(len(names), n), strict=True):
                    dense[name][at] += values
            if shard < shards:
                for name, values in dense.items():
                    _save_small(word_base, f"{shard}.{name}", values)
                b = dense["before"]
                sums = [int(b.sum()), *_fours(b), int((b > 2).sum())]
            else:
                sums = [int(dense[x][0]) for x in WORD_COLUMNS[:4]]
        return pa.table({"shard": pa.array([shard], pa.int32()), "sums": pa.array([sums], pa.list_(pa.int64()))})

    pairs_of = texts.mapInArrow(count_grams, _PARTS).groupBy("shard").applyInArrow(merge_grams, _PARTS)
    summed = pairs_of.groupBy("shard").applyInArrow(merge_pairs, _PARTS).groupBy("shard").applyInArrow(merge_sums, "shard int, sums array<long>")
    sizes, ends, grams, ahead, of_words, start, pairs_n = [0] * (1 << bits), [0] * (1 << bits), np.zeros(4, "<i8"), np.zeros(4, "<i8"), np.zeros(6, "<i8"), (0, 0, 0, 0), 0
    for r in summed.collect():
        if r["shard"] < -(1 << bits):
            ends[-1 - r["shard"] - (1 << bits)] = r["sums"][0]
            pairs_n += r["sums"][1]
            ahead += r["sums"][2:]
        elif r["shard"] < 0:
            sizes[-1 - r["shard"]] = r["sums"][0]
            grams += r["sums"][1:]
        elif r["shard"] == shards:
            start = tuple(r["sums"])
        else:
            of_words += r["sums"]
    discounts = tuple(_discounts(x.tolist()) for x in (of_words[1:5], ahead, grams))
    return Model(words, Pairs(pair_base, bits, tuple(sizes), tuple(ends)), tokens, types, discounts, pairs_n, (int(of_words[1]), int(of_words[2]), int(of_words[5])), start)


def score_documents(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, n_tokens, n_known, train_tokens, base_score, score``, a row for each row of ``docs``."""

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in blocks(batch, 1, SCORED):
                n, known, base, score = model.score(part.column(1))
                columns = [part.column(0), pa.array(n, pa.int64()), pa.array(known, pa.int64()), pa.array(np.full(len(n), model.tokens), pa.int64()), pa.array(base, pa.float64()), pa.array(score, pa.float64())]
                yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "n_tokens", "n_known", "train_tokens", "base_score", "score"])

    picked = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return picked.mapInArrow(rows, "doc_id long, n_tokens long, n_known long, train_tokens long, base_score double, score double")


def held_out(id_col: str, mod: int = 7, rest: int = 2) -> F.Column:
    """Whether a row is kept from training."""
    return (F.crc32(F.coalesce(F.col(id_col).cast("long").cast("string"), F.lit("")).cast("binary")) % mod) == rest


def train_and_score(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """All documents scored by the model of those not held out, with ``held_out``."""
    model = train(docs.where(~held_out(id_col)).select(F.col(text_col).cast("string").alias("text")))
    return score_documents(docs, model, id_col, text_col).withColumn("held_out", held_out("doc_id"))
