"""Language by fusion of evidence: text, declared markup, address suffix and host.

* Text: byte trigrams under a model of each language, learned from a bounded sample of labelled
  documents, and under a uniform one for text of no known language (``und``). Long texts count as
  ``TRUSTED`` trigrams at most, as trigrams of one text are not independent.
* Markup: the ``lang`` of an ``html`` tag, right with a known probability.
* Address suffix: country suffixes of a host, right with a known probability; others say nothing.
* Host: shares of languages among a host's documents by their text, smoothed towards those of its
  domain, and those towards all documents'; computed by grouped aggregation.

A document is kept if its most probable language is wanted and certain enough. Nulls and empty
texts leave the host's prior to decide; they are kept. Null hosts share no host and get the prior
of all documents. Ties go to the first language in alphabetical order. Hot hosts meet as sums of
each task, and join by a shuffle that splits skewed keys, or by broadcast where few.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from subgraph_engine.llm.common import column, written
from subgraph_engine.llm.hashing import NOT_LETTERS, blocks

#: Labelled documents with different texts of each language that the text models learn from at most.
SAMPLE = 1000
SLOTS, PRIOR, TRUSTED = 1 << 16, 0.5, 60
#: How often a declared language or a country suffix is right, and prior documents of a host and a domain.
MARKUP_RIGHT, SUFFIX_RIGHT, HOST_PRIOR, DOMAIN_PRIOR = 0.9, 0.8, 20.0, 50.0
CERTAIN, BROADCAST_HOSTS = 0.5, 200_000
UNKNOWN = "und"
#: Country suffixes and the language that each speaks for.
SUFFIXES = {"at": "de", "ca": "en", "cl": "es", "co": "es", "de": "de", "es": "es", "fr": "fr", "ie": "en", "it": "it", "jp": "ja", "mx": "es", "nl": "nl", "pl": "pl", "pt": "pt", "ru": "ru", "uk": "en", "us": "en"}
_OPENS = re.compile(r"<!--|<html(?=[\s/>])", re.I)
_DECLARED = re.compile(r"[\s\"'/]lang\s*=\s*[\"']?\s*([A-Za-z]{2,3})", re.I)


_LETTER = ~NOT_LETTERS
_LETTER[32] = True


def trigrams(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Slots of all byte trigrams of letters and blanks (A to Z as a to z), and where each row's begin.

    Digits and signs are of no language; bytes of characters beyond ASCII count as letters.
    """
    texts = texts.fill_null("").cast(pa.large_string())
    rows = len(texts)
    offsets = np.frombuffer(texts.buffers()[1], "<i8")[texts.offset : texts.offset + rows + 1]
    first, last = int(offsets[0]), int(offsets[-1])
    if first == last:
        return np.zeros(0, "<u4"), np.zeros(rows + 1, "<i8")
    raw = np.frombuffer(texts.buffers()[2], "u1")[first:last]
    lower = np.arange(256, dtype="<u4")
    lower[65:91] += 32
    x = lower[raw]
    slots = ((x[:-2] * np.uint32(0x9E3779B1) + x[1:-1] * np.uint32(0x85EBCA77) + x[2:] * np.uint32(0xC2B2AE3D)) >> np.uint32(16)).astype("<u4")
    cuts = offsets - first
    letter = _LETTER[raw]
    inside = letter[:-2] & letter[1:-1] & letter[2:]
    # and not across the border of two rows
    for back in (1, 2):
        at = cuts[1:-1] - back
        inside[at[(at >= 0) & (at < len(slots))]] = False
    kept = np.concatenate([[0], np.cumsum(inside)])
    return slots[inside], kept[np.minimum(cuts, len(slots))]


@dataclass(frozen=True)
class TextModel:
    languages: tuple[str, ...]  # in alphabetical order; UNKNOWN is the last
    logs: np.ndarray  # languages x SLOTS

    def likelihoods(self, texts: pa.Array) -> np.ndarray:
        """Log-likelihood of each row's text under each language, relative to the best."""
        slots, at = trigrams(texts)
        n = np.diff(at)
        out = np.zeros((len(texts), len(self.languages)))
        full = np.flatnonzero(n)
        if len(full):
            for k, own in enumerate(self.logs):
                out[full, k] = np.add.reduceat(own[slots], at[:-1][full])
            out[full] *= (np.minimum(n[full], TRUSTED) / n[full])[:, None]
        return out - out.max(1, keepdims=True)


def train_text(docs: DataFrame, sample: int = SAMPLE, text_col: str = "text", lang_col: str = "lang") -> TextModel:
    """The text models of all languages in ``lang_col``, of at most ``sample`` different texts each.

    Which texts is settled by their hashes, wherever they are stored and however often.
    """
    text, lang = F.coalesce(F.col(text_col).cast("string"), F.lit("")), F.lower(F.trim(F.col(lang_col).cast("string")))
    rows = docs.select(lang.alias("lang"), F.xxhash64(text).alias("h"), text.alias("text")).where("lang is not null and lang <> ''")
    # twice the sample passes by hash, so what meets in a language's group is bounded however many texts it has
    sizes = rows.select("lang", "h").distinct().groupBy("lang").agg(F.count("*").alias("n"))
    share = F.pmod("h", F.lit(1 << 30)) / float(1 << 30)
    picked = rows.join(F.broadcast(sizes), "lang").where(share * F.col("n") < 2 * sample).select("lang", "h", "text").dropDuplicates(["lang", "h"])

    def count(table: pa.Table) -> pa.Table:
        table = table.sort_by("h").slice(0, sample).combine_chunks()
        own = np.zeros(SLOTS, "<i8")
        for batch in table.to_batches():
            for part in blocks(batch, 2):
                own += np.bincount(trigrams(part.column(2))[0], minlength=SLOTS)
        return pa.table({"lang": table["lang"][:1], "counts": pa.array([own.tolist()], pa.list_(pa.int64()))})

    got = sorted((r["lang"], r["counts"]) for r in picked.groupBy("lang").applyInArrow(count, "lang string, counts array<long>").collect())
    logs = np.array([np.log((np.array(c) + PRIOR) / (sum(c) + PRIOR * SLOTS)) for _, c in got] + [np.full(SLOTS, -np.log(SLOTS))], dtype="<f4")
    return TextModel((*(k for k, _ in got), UNKNOWN), logs)


def declared(text: str | None) -> str | None:
    """The language that the first ``html`` tag outside of comments declares, wherever it stands."""
    if not text or "<" not in text:
        return None
    at = 0
    while opens := _OPENS.search(text, at):
        if opens[0] != "<!--":
            end = text.find(">", opens.end())
            found = _DECLARED.search(text, opens.end(), end if end >= 0 else len(text))
            return found[1].lower()[:2] if found else None
        at = text.find("-->", opens.end() - 2) + 3
        if at < 3:
            return None
    return None


def suffix_language(host: Column) -> Column:
    """The language of a host's country suffix."""
    table = F.create_map(*[F.lit(x) for pair in SUFFIXES.items() for x in pair])
    return F.element_at(table, F.substring_index(host, ".", -1))


def _domain(host: Column) -> Column:
    """The last two labels of a host."""
    return F.substring_index(host, ".", -2)


def _said(languages: tuple[str, ...], says: Column, right: float) -> Column:
    """Log-likelihood of a declaration under each language; nothing said or an unknown one says nothing."""
    rest = (1 - right) / max(len(languages) - 1, 1)
    out = F.array(*[F.when(says == k, float(np.log(right))).otherwise(float(np.log(rest))) for k in languages])
    return F.when(says.isin(list(languages)), out).otherwise(F.array(*[F.lit(0.0)] * len(languages)))


def identify(docs: DataFrame, model: TextModel, wanted: list[str] | None = None, certain: float = CERTAIN, id_col: str = "doc_id", text_col: str = "text", host_col: str = "source", markup_col: str | None = None) -> DataFrame:
    """``doc_id, language, confidence, kept``, a row for each row of ``docs``.

    ``markup_col`` holds the page whose ``html`` tag declares a language; by default the text itself.
    """
    names = model.languages
    n = len(names)
    page = 3 if markup_col else 1

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in blocks(batch, 1):
                logs = model.likelihoods(part.column(1))
                says = [declared(x) for x in part.column(page).to_pylist()]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(list(logs), pa.list_(pa.float64())), part.column(2), pa.array(says, pa.string())], names=["doc_id", "logs", "host", "says"])

    text = F.col(text_col).cast("string")
    picked = docs.select(F.col(id_col).cast("long").alias("doc_id"), text.alias("text"), F.lower(column(docs, host_col, "string")).alias("host"), *([F.col(markup_col).cast("string").alias("markup")] if markup_col else []))
    seen = written(picked.mapInArrow(rows, "doc_id long, logs array<double>, host string, says string"), "languages")

    def normal(logs: Column) -> Column:
        top = F.array_max(logs)
        parts = F.transform(logs, lambda x: F.exp(x - top))
        return F.transform(parts, lambda x: x / F.aggregate(parts, F.lit(0.0), lambda a, b: a + b))

    shares = seen.select("host", normal(F.col("logs")).alias("p"))
    sums = [F.sum(F.get("p", k)).alias(f"n{k}") for k in range(n)]
    hosts = written(shares.groupBy("host").agg(*sums), "hosts").withColumn("domain", _domain(F.col("host")))
    domains = hosts.groupBy("domain").agg(*[F.sum(f"n{k}").alias(f"d{k}") for k in range(n)])
    every = hosts.agg(*[F.sum(f"n{k}").alias(f"n{k}") for k in range(n)]).first()
    total = [(every[k] or 0.0) + 1.0 for k in range(n)]
    overall = [x / sum(total) for x in total]
    size_d, size_h = sum((F.col(f"d{k}") for k in range(n)), F.lit(0.0)), sum((F.col(f"n{k}") for k in range(n)), F.lit(0.0))
    of_domain = [(F.col(f"d{k}") + DOMAIN_PRIOR * overall[k]) / (size_d + DOMAIN_PRIOR) for k in range(n)]
    priors = hosts.where("host is not null").join(domains, "domain").select("host", F.array(*[F.log((F.col(f"n{k}") + HOST_PRIOR * of_domain[k]) / (size_h + HOST_PRIOR)) for k in range(n)]).alias("prior"))
    priors = written(priors, "host_priors")
    if priors.count() <= BROADCAST_HOSTS:
        priors = F.broadcast(priors)
    joined = seen.join(priors, "host", "left")
    prior = F.coalesce("prior", F.array(*[F.lit(float(np.log(x))) for x in overall]))
    evidence = [F.col("logs"), prior, _said(names, F.col("says"), MARKUP_RIGHT), _said(names, suffix_language(F.col("host")), SUFFIX_RIGHT)]
    fused = F.array(*[sum((F.get(e, k) for e in evidence[1:]), F.get(evidence[0], k)) for k in range(n)])
    judged = joined.select("doc_id", normal(fused).alias("p"))
    best = F.array_max("p")
    language = F.get(F.array(*[F.lit(x) for x in names]), (F.array_position("p", best) - 1).cast("int"))
    out = judged.select("doc_id", language.alias("language"), best.alias("confidence"))
    fits = F.col("language").isin(wanted) if wanted is not None else F.col("language") != UNKNOWN
    return out.select("doc_id", "language", "confidence", (fits & (F.col("confidence") >= certain)).alias("kept"))
