"""Byte-pair encoding over the corpus's table of distinct words, and decoding by id.

A text is cut into words, each word with the blank before it. No token of a byte-level
vocabulary reaches from a visible character into the white space after it, so words can be
encoded apart.

1. ``build_table``: each task makes its texts' words distinct, and only these are shuffled, to
   shards by the top bits of their 64-bit hashes. A shard sorts its words, encodes each once
   and writes hashes, a 32-bit check beside each, and ids as sorted arrays to the shared folder, as a
   stream.
2. ``encode_partitions`` maps the table and puts the words' ids back by their positions. Texts are
   never shuffled. A worker looks each word up once, in blocks, and keeps up to ``TABLE_WORDS``.
3. Decoding looks up each id's piece in the vocabulary's table, which each worker holds;
   ``decode_global`` does it as a join for ids that lie in a frame.

Without a table, ``encode_partitions`` encodes words as they turn up. Null and empty texts have no
ids. Repeated rows give repeated results. Any length works.
"""

from __future__ import annotations

import hashlib
import json
import os
import re
import uuid
from array import array
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import chain, pairwise
from zlib import crc32

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from xxhash import xxh64_intdigest

from subgraph_engine.llm.common import fresh_path, local, mapped, slices

#: Words that a worker keeps before it starts anew: of the table, and of those that it has handed over.
TABLE_WORDS, SEEN_WORDS = 400_000, 1_000_000
#: Longer words are not kept beyond a block.
KEPT_CHARS = 48
#: Longer words, and words with characters from here on, go to the reference tokenizer.
FAST_CHARS, FAST_BELOW = 1000, "ɐ"
#: White space as byte-level tokenizers see it, and their splitting pattern.
WHITE = r"\t-\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000"
SPLIT = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"

# A blank inside a longer run of white space isn't a place to cut at.
_INSIDE = re.compile(rf"[{WHITE}] (?![^{WHITE}])")
_LONG = re.compile(rf"[^{WHITE}]{{{2 * FAST_CHARS}}}|[{WHITE}]{{{FAST_CHARS}}}")
_RUNS = re.compile(rf"[{WHITE}]*[^{WHITE}]+|[{WHITE}]+")


def words_of(text: str) -> list[str]:
    """The text's words with the white space before each; joined they are the text."""
    if _INSIDE.search(text):
        return _RUNS.findall(text)
    first, *rest = text.split(" ")
    return ([first] if first else []) + [" " + x for x in rest]


def _plain(text: str) -> bool:
    """Whether all characters lie below U+0100 and no word is very long."""
    try:
        text.encode("latin-1")
    except UnicodeEncodeError:
        return False
    # a word of twice a block's length fills a block; few texts have a block without a blank
    return all(" " in text[k : k + FAST_CHARS] for k in range(0, len(text) - FAST_CHARS, FAST_CHARS)) or not _LONG.search(text)


def _bytes_of_symbols() -> dict[str, int]:
    """The printable symbol that stands for each byte in the vocabulary file, reversed."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    moved = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + k): b for k, b in enumerate(moved)}


class Codec(dict):
    """Word -> (ids as little-endian unsigned 32-bit bytes, ids as decimals each with a comma)."""

    def __init__(self, path: str) -> None:
        from tokenizers import Tokenizer

        super().__init__()
        self.exact = Tokenizer.from_file(path)
        self.exact.no_truncation()
        self.exact.no_padding()
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        symbols = _bytes_of_symbols()
        vocabulary = {k: v for k, v in spec["model"]["vocab"].items()}
        self.special = {x["content"]: x["id"] for x in spec.get("added_tokens", [])}
        ranks = {bytes(map(symbols.__getitem__, k)): v for k, v in vocabulary.items() if k not in self.special}
        self.pieces: list[bytes] = [b""] * (1 + max([*ranks.values(), *self.special.values()]))
        for piece, i in ranks.items():
            self.pieces[i] = piece
        for content, i in self.special.items():
            self.pieces[i] = content.encode()
        self.decimals = [b"%d," % i for i in range(len(self.pieces))]
        self._apart = re.compile("|".join(f"({re.escape(x)})" for x in sorted(self.special, key=len, reverse=True))) if self.special else None
        from tiktoken import Encoding

        self._fast = Encoding("words", pat_str=SPLIT, mergeable_ranks=ranks, special_tokens={}).encode_ordinary

    def ids_of(self, word: str) -> list[int]:
        if len(word) > FAST_CHARS or max(word) >= FAST_BELOW:
            return self.exact.encode(word, add_special_tokens=False).ids
        return self._fast(word)

    def entry(self, ids: list[int]) -> tuple[bytes, bytes]:
        return array("I", ids).tobytes(), b"".join(map(self.decimals.__getitem__, ids))

    def words(self, text: str | None) -> list[str]:
        """The text's words; special tokens stand alone."""
        if not text:
            return []
        if self._apart and self._apart.search(text):
            return [w for part in filter(None, self._apart.split(text)) for w in ([part] if part in self.special else words_of(part))]
        return words_of(text)

    def know(self, words: set[str], table: WordTable | None = None) -> None:
        """Makes entries of these words, by the table where it has them."""
        new = words.difference(self)
        if len(self) + len(new) > TABLE_WORDS:
            self.clear()
            new = words
        new = list(new)
        found = table.entries(new, self.decimals) if table else [None] * len(new)
        for w, entry in zip(new, found, strict=True):
            self[w] = entry or self.entry([self.special[w]] if w in self.special else self.ids_of(w))

    def forget_long(self, words: set[str]) -> None:
        for w in words:
            if len(w) > KEPT_CHARS:
                self.pop(w, None)

    def entries(self, text: str | None) -> list[tuple[bytes, bytes]]:
        words = self.words(text)
        distinct = set(words)
        self.know(distinct)
        out = [self[w] for w in words]
        self.forget_long(distinct)
        return out

    def encode(self, text: str | None) -> bytes:
        """The text's ids, four bytes each, past the table where a text is plain enough to go whole."""
        if not text:
            return b""
        if not (self._apart and self._apart.search(text)) and _plain(text):
            return array("I", self._fast(text)).tobytes()
        return b"".join([a for a, _ in self.entries(text)])

    def decode(self, ids: bytes) -> str:
        return b"".join(map(self.pieces.__getitem__, array("I", ids))).decode("utf-8", "replace")


_CODECS: dict[str, Codec] = {}


def codec(path: str) -> Codec:
    """This process's codec of a vocabulary file."""
    if path not in _CODECS:
        _CODECS[path] = Codec(path)
    return _CODECS[path]


#: Fixed value: the seed of Spark's xxhash64.
SEED = 42


@dataclass(frozen=True)
class WordTable:
    """The ids of distinct words, by sorted 64-bit hashes in shards by their top ``bits``.

    A shard has its words' hashes, checks of 32 more bits, where each word's ids end, and the ids.
    """

    base: str
    bits: int
    sizes: tuple[int, ...]  # words of each shard
    kind: str  # of ids as stored

    def entries(self, words: list[str], decimals: list[bytes]) -> list[tuple[bytes, bytes] | None]:
        """Each word's ids as unsigned 32-bit bytes and as decimals, None if it isn't in the table."""
        out: list[tuple[bytes, bytes] | None] = [None] * len(words)
        raw = [w.encode() for w in words]
        keys, checks = np.fromiter((xxh64_intdigest(w, SEED) for w in raw), "<u8", len(raw)), np.fromiter(map(crc32, raw), "<u4", len(raw))
        order = np.argsort(keys, kind="stable")
        keys, checks = keys[order], checks[order]
        tops = np.arange(1, 1 << self.bits, dtype="<u8") << np.uint64(64 - self.bits)
        for shard, (a, b) in enumerate(pairwise([0, *np.searchsorted(keys, tops).tolist(), len(keys)])):
            if a == b or not self.sizes[shard]:
                continue
            there, marks, ends, every = (mapped(f"{local(self.base)}/{shard}.{name}", kind) for name, kind in (("hashes", "<u8"), ("checks", "<u4"), ("ends", "<u4"), ("ids", self.kind)))
            own = np.minimum(np.searchsorted(there, keys[a:b]), len(there) - 1)
            while len(off := np.flatnonzero((there[own] == keys[a:b]) & (marks[own] != checks[a:b]) & (own < len(there) - 1))):
                own[off] += 1  # different words of one hash stand side by side
            hit = np.flatnonzero((there[own] == keys[a:b]) & (marks[own] == checks[a:b]))
            if not len(hit):
                continue
            own = own[hit]
            n = ends[own].astype("<i8")
            starts = np.where(own > 0, ends[np.maximum(own, 1) - 1].astype("<i8"), 0)
            n -= starts
            stops = np.cumsum(n)
            ids = every[np.repeat(starts - stops + n, n) + np.arange(stops[-1])].astype("<u4")
            data, numbers, x = ids.tobytes(), ids.tolist(), 0
            for k, y in zip(order[a:b][hit].tolist(), stops.tolist(), strict=True):
                out[k] = data[4 * x : 4 * y], b"".join([decimals[i] for i in numbers[x:y]])
                x = y
        return out


class _ShardFiles:
    """A shard's arrays as they grow; written beside and renamed, so that a task that runs again does no harm."""

    NAMES = ("hashes", "checks", "ends", "ids")

    def __init__(self, base: str, shard: int, kind: str) -> None:
        self.base, self.shard, self.kind, self.words, self.n = f"{local(base)}/{shard}", shard, kind, 0, 0
        self.draft = f"{self.base}.{uuid.uuid4().hex}"
        self.files = [open(f"{self.draft}.{name}", "wb") for name in self.NAMES]  # noqa: SIM115

    def add(self, hashes: np.ndarray, words: list[str], ids: list[list[int]]) -> None:
        ends = self.n + np.cumsum([len(x) for x in ids])
        if ends[-1] >= 1 << 32:
            raise ValueError("a shard of words has more than 2^32 ids; take more shuffle partitions")
        checks = np.fromiter((crc32(w.encode()) for w in words), "<u4", len(words))
        for f, values in zip(self.files, (hashes.astype("<u8"), checks, ends.astype("<u4"), np.fromiter(chain.from_iterable(ids), self.kind)), strict=True):
            f.write(values.tobytes())
        self.words, self.n = self.words + len(words), int(ends[-1])

    def close(self) -> tuple[int, int]:
        for f, name in zip(self.files, self.NAMES, strict=True):
            f.close()
            os.replace(f"{self.draft}.{name}", f"{self.base}.{name}")
        return self.shard, self.words


def build_table(docs: DataFrame, path: str, text_col: str = "text") -> WordTable:
    """The table of all distinct words of a column; only the shards' sizes come to the driver."""
    spark = docs.sparkSession
    bits = max(1, (int(spark.conf.get("spark.sql.shuffle.partitions")) - 1).bit_length())
    kind = "<u2" if len(codec(path).pieces) <= 1 << 16 else "<u4"
    base = fresh_path(spark, "words")
    os.makedirs(local(base), exist_ok=True)

    def split(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, seen = codec(path), set()
        for batch in slices(batches):
            new: set[str] = set()
            for text in batch.column(0).to_pylist():
                new.update(own.words(text))
            new = new.difference(seen, own.special)
            if len(seen) > SEEN_WORDS:
                seen.clear()
            seen.update(w for w in new if len(w) <= KEPT_CHARS)
            yield pa.RecordBatch.from_arrays([pa.array(list(new), pa.string())], names=["word"])

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, files, done, last = codec(path), None, [], None
        for batch in batches:
            if not batch.num_rows:
                continue
            hashes, words = batch.column(0).to_numpy().view("<u8"), batch.column(1)
            new = np.ones(batch.num_rows, bool)
            new[1:] = (hashes[1:] != hashes[:-1]) | pc.not_equal(words[1:], words[:-1]).to_numpy(zero_copy_only=False)
            new[0] = last != (hashes[0], words[0].as_py())
            last = hashes[-1], words[-1].as_py()
            hashes, words = hashes[new], words.filter(pa.array(new)).to_pylist()
            shards = (hashes >> np.uint64(64 - bits)).astype("<i8")
            for a, b in pairwise([0, *(np.flatnonzero(np.diff(shards)) + 1).tolist(), len(shards)] if len(shards) else []):
                if files is None or shards[a] != files.shard:
                    if files is not None:
                        done.append(files.close())
                    files = _ShardFiles(base, int(shards[a]), kind)
                files.add(hashes[a:b], words[a:b], list(map(own.ids_of, words[a:b])))
        if files is not None:
            done.append(files.close())
        if done:
            shards, sizes = zip(*done, strict=True)
            yield pa.RecordBatch.from_arrays([pa.array(shards, pa.int32()), pa.array(sizes, pa.int64())], names=["shard", "words"])

    words = docs.select(F.col(text_col).cast("string").alias("text")).mapInArrow(split, "word string")
    hashed = F.xxhash64("word")
    dealt = words.repartitionById(1 << bits, F.shiftrightunsigned(hashed, 64 - bits).cast("int")).select(hashed.alias("hash"), "word").sortWithinPartitions(F.shiftrightunsigned("hash", 64 - bits), "hash", "word")
    sizes = [0] * (1 << bits)
    for r in dealt.mapInArrow(encode, "shard int, words long").collect():
        sizes[r["shard"]] = r["words"]
    return WordTable(base, bits, tuple(sizes), kind)


def encode_partitions(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text", digests: bool = False, table: WordTable | None = None) -> DataFrame:
    """``doc_id, n_tokens`` and ``ids`` (binary, unsigned 32-bit little-endian), a row for each row of ``docs``.

    With ``digests``, the hex SHA-256 of the decimal ids joined by commas and of the decoded
    text (UTF-8) instead of ``ids``. With a ``table``, words' ids come from it.
    """

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = codec(path)
        for batch in slices(batches):
            n, first, second = [], [], []
            texts = list(map(own.words, batch.column(1).to_pylist()))
            distinct = set(chain.from_iterable(texts))
            own.know(distinct, table)
            for words in texts:
                entries = list(map(own.__getitem__, words))
                ids = b"".join([a for a, _ in entries])
                n.append(len(ids) // 4)
                if digests:
                    first.append(hashlib.sha256(b"".join([b for _, b in entries])[:-1]).hexdigest())
                    second.append(hashlib.sha256(own.decode(ids).encode()).hexdigest())
                else:
                    first.append(ids)
            own.forget_long(distinct)
            out = [batch.column(0), pa.array(n, pa.int64()), pa.array(first, pa.string() if digests else pa.binary())]
            names = ["doc_id", "n_tokens", "ids"]
            if digests:
                out.append(pa.array(second, pa.string()))
                names[2:] = ["ids_sha256", "decoded_sha256"]
            yield pa.RecordBatch.from_arrays(out, names=names)

    picked = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return picked.mapInArrow(rows, "doc_id long, n_tokens long, " + ("ids_sha256 string, decoded_sha256 string" if digests else "ids binary"))


def decode_partitions(encoded: DataFrame, path: str, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """``doc_id, text``: the text of binary ids as ``encode_partitions`` makes them (null: empty)."""

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = codec(path)
        for batch in slices(batches):
            texts = [own.decode(x or b"") for x in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, pa.string())], names=["doc_id", "text"])

    return encoded.select(F.col(id_col).cast("long").alias("doc_id"), F.col(ids_col).alias("ids")).mapInArrow(rows, "doc_id long, text string")


def encode_global(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``row, doc_id, ids array<int>`` by the table of all words; ``row`` keeps rows with equal or null ids apart."""
    table = build_table(docs, path, text_col)
    picked = docs.select(F.monotonically_increasing_id().alias("row"), F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = codec(path)
        for batch in slices(batches):
            texts = list(map(own.words, batch.column(2).to_pylist()))
            distinct = set(chain.from_iterable(texts))
            own.know(distinct, table)
            ids = [array("I", b"".join([own[w][0] for w in words])).tolist() for words in texts]
            own.forget_long(distinct)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(ids, pa.list_(pa.int32()))], names=["row", "doc_id", "ids"])

    return picked.mapInArrow(rows, "row long, doc_id long, ids array<int>")


def decode_global(encoded: DataFrame, path: str) -> DataFrame:
    """``row, doc_id, text``: each id joined with its piece by position; the vocabulary's size bounds the table.

    ``encoded`` has the columns of ``encode_global``; without ``row``, each row gets a key of its own.
    """
    pieces = encoded.sparkSession.createDataFrame([(i, bytearray(p)) for i, p in enumerate(codec(path).pieces)], "id int, piece binary")
    keyed = encoded if "row" in encoded.columns else encoded.withColumn("row", F.monotonically_increasing_id())
    at = keyed.select("row", "doc_id", F.posexplode_outer("ids").alias("pos", "id")).join(F.broadcast(pieces), "id", "left")
    gathered = at.groupBy("row").agg(F.first("doc_id").alias("doc_id"), F.sort_array(F.collect_list(F.struct("pos", F.hex("piece").alias("piece")))).alias("got"))
    joined = F.array_join(F.transform("got", lambda x: F.coalesce(x["piece"], F.lit(""))), "")
    return gathered.select("row", "doc_id", F.make_valid_utf8(F.unhex(joined).cast("string")).alias("text"))


def global_digests(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, n_tokens, ids_sha256, decoded_sha256`` by the corpus's table of words and the table of pieces."""
    return encode_partitions(docs, path, id_col, text_col, True, build_table(docs, path, text_col))
