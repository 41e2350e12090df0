"""URL rules and block lists as a sorted array of digests that workers map into memory.

An entry is a host followed by the start of a path (``example.org/en/1``); one without a path
(``example.org``) covers the whole host. An entry fits a url if the url's host is the entry's
or lies below it, and the url's path starts with the entry's; the longest fitting entry decides.

``DigestArray.build`` gives each entry its 64-bit xxhash, sorts by it over the cluster and
writes range shards (digests, offsets, strings) to the shared folder. ``judge`` makes all
strings of a url that could be entries (each suffix of the host with each start of the path
that is as long as some entry's path), finds their digests by binary search, and confirms each
hit against the stored string, so equal digests of different strings do no harm.

Null urls and urls without ``://`` have an empty host and path; no entry fits them, and they are
allowed. Entries that are repeated count once (a rule before a listing, then block before allow);
null entries are ignored.
"""

from __future__ import annotations

import os
import uuid
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from subgraph_engine.llm.common import fresh_path, local, slices

#: Kinds of entries, as stored.
RULE_BLOCK, RULE_ALLOW, LIST_BLOCK, LIST_ALLOW = 0, 1, 2, 3
VERDICTS = ("block", "allow", "block", "allow")


def digest(text: str) -> int:
    return xxhash.xxh64_intdigest(text.encode("utf-8", "surrogatepass"))


def split_url(url: str | None) -> tuple[str, str]:
    """Host in lower case (A-Z only) and path."""
    _, found, rest = (url or "").partition("://")
    if not found:
        return "", ""
    end = min((k for k in map(rest.find, "/?#") if k >= 0), default=len(rest))
    path = rest[end:]
    stop = min((k for k in map(path.find, "?#") if k >= 0), default=len(path))
    host = rest[:end]
    return (host.lower() if host.isascii() else "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in host)), path[:stop]


@lru_cache(maxsize=256)
def _mapped(base: str) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    at = local(base)

    def of(name: str, kind: str) -> np.ndarray:
        path = f"{at}.{name}"
        return np.memmap(path, kind, "r") if os.path.getsize(path) else np.zeros(0, kind)

    return of("digests", "<u8"), of("offsets", "<i8"), of("strings", "u1"), of("kinds", "u1")


@dataclass(frozen=True)
class DigestArray:
    """Shards in order of their digests; lowest[k] is shard k's first digest."""

    bases: tuple[str, ...]
    lowest: tuple[int, ...]
    path_lengths: tuple[int, ...]

    @staticmethod
    def build(entries: DataFrame, shards: int = 1) -> DigestArray:
        """From ``entry string, kind int``; only shard names and path lengths come to the driver."""
        spark = entries.sparkSession
        base = fresh_path(spark, "digests")
        os.makedirs(local(base), exist_ok=True)

        def keyed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                keys = [digest(x) - (1 << 63) for x in batch.column(0).to_pylist()]
                yield pa.RecordBatch.from_arrays([pa.array(keys, pa.int64()), batch.column(0), batch.column(1)], names=["key", "entry", "kind"])

        def shard(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            got = [b for b in batches if b.num_rows]
            if not got:
                return
            table = pa.Table.from_batches(got)
            strings = [x.encode("utf-8", "surrogatepass") for x in table.column("entry").to_pylist()]
            keys = (table.column("key").to_numpy().astype("<i8").view("<u8") + np.uint64(1 << 63)).astype("<u8")
            name = f"{base}/{keys[0]:016x}"
            parts = {"digests": keys, "offsets": np.cumsum([0, *map(len, strings)], dtype="<i8"), "strings": np.frombuffer(b"".join(strings), "u1"), "kinds": table.column("kind").to_numpy().astype("u1")}
            for part, values in parts.items():
                draft = f"{local(name)}.{uuid.uuid4().hex}"
                values.tofile(draft)
                os.replace(draft, f"{local(name)}.{part}")
            yield pa.RecordBatch.from_arrays([pa.array([name]), pa.array([str(int(keys[0]))])], names=["base", "lowest"])

        cleaned = entries.where("entry is not null and entry <> ''").groupBy("entry").agg(F.min("kind").alias("kind"))
        lengths = cleaned.select(F.expr("case when instr(entry, '/') = 0 then 0 else length(entry) - instr(entry, '/') + 1 end").alias("n")).distinct().collect()
        sorted_keys = cleaned.mapInArrow(keyed, "key long, entry string, kind int").repartitionByRange(shards, "key").sortWithinPartitions("key", "entry")
        found = sorted((int(r["lowest"]), r["base"]) for r in sorted_keys.mapInArrow(shard, "base string, lowest string").collect())
        return DigestArray(tuple(b for _, b in found), tuple(k for k, _ in found), tuple(sorted(r["n"] for r in lengths)))

    def find(self, strings: list[str]) -> np.ndarray:
        """The kind of each string's entry, or -1."""
        kinds = np.full(len(strings), -1)
        if not self.bases or not strings:
            return kinds
        keys = np.fromiter(map(digest, strings), "<u8", len(strings))
        shards = np.searchsorted(np.array(self.lowest, "<u8"), keys, "right") - 1
        for k in np.unique(shards[shards >= 0]):
            digests, offsets, stored, own = _mapped(self.bases[k])
            asked = np.flatnonzero(shards == k)
            at = np.searchsorted(digests, keys[asked])
            hit = at < len(digests)
            hit[hit] = digests[at[hit]] == keys[asked][hit]
            for i, j in zip(asked[hit], at[hit], strict=True):
                text = strings[i].encode("utf-8", "surrogatepass")
                while j < len(digests) and digests[j] == keys[i]:
                    if stored[offsets[j] : offsets[j + 1]].tobytes() == text:
                        kinds[i] = own[j]
                        break
                    j += 1
        return kinds

    def could_be(self, host: str, path: str) -> list[str]:
        suffixes, rest = [host], host
        while "." in rest:
            rest = rest.partition(".")[2]
            suffixes.append(rest)
        starts = [path[:n] for n in self.path_lengths if n <= len(path)]
        return [s + p for s in suffixes if s for p in starts]

    def judge(self, urls: list[str | None]) -> list[tuple[str, str, str | None, str]]:
        """(host, path, rule or None, verdict) of each url."""
        parts = [split_url(u) for u in urls]
        options = [self.could_be(*p) for p in parts]
        distinct = {s: k for k, s in enumerate(dict.fromkeys(s for o in options for s in o))}
        kinds = self.find(list(distinct))
        out = []
        for (host, path), own in zip(parts, options, strict=True):
            fits = sorted(((len(s), kinds[distinct[s]], s) for s in own if kinds[distinct[s]] >= 0), key=lambda x: (x[1] >= LIST_BLOCK, -x[0], -len(x[2].partition("/")[0])))
            _, kind, entry = fits[0] if fits else (0, LIST_ALLOW, "")
            out.append((host, path, entry if kind < LIST_BLOCK else None, VERDICTS[kind]))
        return out


def entries_frame(spark: SparkSession, allow: list[str], block: list[str], listed: list[str]) -> DataFrame:
    """Entries from short lists; long lists come as a frame of ``entry, kind``."""
    rows = [(x, RULE_ALLOW) for x in allow] + [(x, RULE_BLOCK) for x in block] + [(x, LIST_BLOCK) for x in listed]
    return spark.createDataFrame(rows, "entry string, kind int")


def judge_urls(pages: DataFrame, entries: DataFrame, shards: int = 1, id_col: str = "page_id", url_col: str = "url") -> DataFrame:
    """``page_id, host, path, rule, verdict``, a row for each row of ``pages``; rules come before listings."""
    array = DigestArray.build(entries, shards)

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, 4096):
            judged = list(zip(*array.judge(batch.column(1).to_pylist()), strict=True)) or [(), (), (), ()]
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(x, pa.string()) for x in judged)], names=["page_id", "host", "path", "rule", "verdict"])

    return pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).cast("string").alias("url")).mapInArrow(rows, "page_id long, host string, path string, rule string, verdict string")
