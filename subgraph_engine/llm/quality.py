"""Quality rules, line first, in DataFrame functions only.

Each line with a word is judged by itself: it goes if it looks like navigation (several bars or
arrows between short items), boilerplate (phrases of page furniture), symbols (a tenth of its
characters or more), or a fragment (few words and no closing punctuation). The document's cleaned
text is what remains; a document that keeps less than half of its characters is rejected.

Before that, a document fails for too few words or too many words in repeated three-word windows.

Null text counts as empty, which has no words and fails. Texts of any length, repeated rows and an
empty table are fine. Windows are compared by 64-bit hashes of their three words.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: White space between words, and the characters that count as symbols.
WHITE, SYMBOLS = r"\x20\x09-\x0D", r"#*$%&|<>"
#: Limits: words of a document, share of words in repeated windows, share of a line's characters
#: that are symbols, words of a fragment, share of characters that a document keeps.
LEAST_WORDS, REPEATED, SYMBOL_SHARE, FRAGMENT_WORDS, KEPT_SHARE = 50, 0.5, 0.1, 3, 0.5
NAVIGATION = r"(?:[|»›>].*){3}"
BOILERPLATE = r"(?i)cookies?\b|all rights reserved|copyright|privacy policy|terms of (?:use|service)|javascript|sign (?:in|up)|log ?in\b|subscribe|click here|read more|lorem ipsum"
CLOSED = "[.!?…:;。！？][\"'”’»)\\]]*$"


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body`` of a value that is computed once."""
    return F.element_at(F.transform(F.array(value), body), 1)


def repeated_words(words: Column) -> Column:
    """How many words lie in three-word windows that occur twice or more."""

    def covered(windows: Column) -> Column:
        def twice(x: Column, i: Column) -> Column:
            return (x["h"] == F.get(windows, i - 1)["h"]) | (x["h"] == F.get(windows, i + 1)["h"])

        starts = F.array_sort(F.transform(F.filter(windows, lambda x, i: F.coalesce(twice(x, i), F.lit(False))), lambda x: x["i"]))
        none = F.struct(F.lit(-3).alias("at"), F.lit(0).alias("n"))
        return F.aggregate(starts, none, lambda a, i: F.struct(i.alias("at"), (a["n"] + F.least(F.lit(3), i - a["at"])).alias("n")), lambda a: a["n"])

    def hashed(own: Column) -> Column:
        return F.transform(F.sequence(F.lit(0), F.size(own) - 3), lambda i: F.xxhash64(F.get(own, i), F.get(own, i + 1), F.get(own, i + 2)))

    def sorted_windows(hashes: Column) -> Column:
        return F.sort_array(F.transform(hashes, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))

    def count(hashes: Column) -> Column:
        return F.when(F.size(F.array_distinct(hashes)) == F.size(hashes), 0).otherwise(let(sorted_windows(hashes), covered))

    return F.when(F.size(words) < 4, 0).otherwise(let(hashed(words), count)).cast("long")


def bad_line(line: Column) -> Column:
    """Whether a line goes."""
    symbols = F.length(F.regexp_replace(line, f"[^{SYMBOLS}]+", ""))
    bare = F.rtrim(line)
    few = F.size(F.split(F.trim(line), f"[{WHITE}]+")) <= FRAGMENT_WORDS
    return (symbols >= SYMBOL_SHARE * F.length(line)) | line.rlike(NAVIGATION) | line.rlike(BOILERPLATE) | (few & ~bare.rlike(CLOSED))


def clean_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The counts, the verdict and ``cleaned`` text of each row of ``docs``.

    doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, kept, cleaned.
    """
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    parts = docs.select(
        F.col(id_col).cast("long").alias("doc_id"), text.alias("text"),
        F.array_remove(F.split(text, f"[{WHITE}]+"), "").alias("words"),
        F.filter(F.split(text, "\n"), lambda x: x.rlike(f"[^{WHITE}]")).alias("lines"),
    )
    counted = parts.select(
        "doc_id", "lines",
        F.size("words").cast("long").alias("n_words"),
        F.length(F.array_join("words", "")).cast("long").alias("word_chars"),
        F.length(F.regexp_replace("text", f"[^{SYMBOLS}]+", "")).cast("long").alias("n_symbols"),
        (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines"),
        repeated_words(F.col("words")).alias("n_repeat_words"),
    )
    cleaned = F.array_join(F.filter("lines", lambda x: ~bad_line(x)), "\n")
    judged = counted.withColumn("cleaned", cleaned)
    failed = (F.col("n_words") < LEAST_WORDS) | (F.col("n_repeat_words") > REPEATED * F.col("n_words"))
    enough = F.length("cleaned") >= KEPT_SHARE * F.length(F.array_join("lines", "\n"))
    return judged.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", failed.alias("base_failed"), (~failed & enough).alias("kept"), "cleaned")
