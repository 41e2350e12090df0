"""Document fingerprints: a Merkle tree over sections, paragraphs and pieces of them.

Sections end at empty lines, paragraphs at line ends; a paragraph's leaves are runs of words cut
after words whose last letter says so, so an edit moves no cut beyond its neighbours. Each inner
node is the digest of its children's digests; the root tests equality of texts. ``differing`` goes
down where two trees' digests differ and gives the edited spans.

A fingerprint is a string with the digest of every node: the root's, then each section's with the
paragraphs and leaves below it, and their lengths. Where leaves are large beside the text, finer ones
come after the tree: short texts have their words too, and tiny ones their bytes. All texts have the
tree, so any two are compared, by the finest pieces that both have. ``likeness`` and ``edited_spans``
of two fingerprints descend where branches differ, without the texts.

``likeness`` is 1 for equal roots only, else the code points in shared leaves (with repeats, line
breaks counted with the leaf before them) over all code points of the longer text; if all are shared
but stand elsewhere, half a code point is taken off. A text that keeps two thirds of its code points
as its beginning keeps a likeness of 0.4 at least, whatever its length.

Null text counts as empty. Texts of any length, repeated rows and an empty table are fine.
"""

from __future__ import annotations

import hashlib
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from xxhash import xxh3_128_hexdigest

from subgraph_engine.llm.common import slices

#: Hex digits in a fingerprint of the root's digest, of another's, of a branch's length in bytes, and
#: of a leaf's length in bytes and then in code points.
ROOT, DIGEST, BRANCH_BYTES, LEAF_BYTES, LEAF_CHARS = 32, 16, 8, 2, 2
#: Before a section, a paragraph, all words and all bytes; no hex digits.
SECTION, PARAGRAPH, WORDS, BYTES = "s", "p", "w", "y"
#: A leaf has MOST bytes at most. It ends after the first word with LEAST to USUAL bytes before it whose last
#: byte is one of ENDS (a quarter of all); else after the last word that fits.
LEAST, USUAL, MOST, ENDS = 11, 39, 56, bytes(range(1, 256, 4))
#: Texts of fewer code points have their words as well, those of fewer than TINY their bytes.
SHORT, TINY = 240, 40
_LEAVES = re.compile(rb"(?s).{%d,%d}?[%s] |.{1,%d}\Z|.{1,%d} |.{1,%d}" % (LEAST - 1, USUAL - 1, re.escape(ENDS), MOST, MOST - 1, MOST))
_WORDS = re.compile(rb"[^ \n]{1,8}[ \n]?|[ \n]")
_HEX = [f"{k:02x}" for k in range(256)]
#: Bytes that don't begin a character.
_INSIDE = bytes(range(0x80, 0xC0))


def _leaves(line: bytes) -> list[bytes]:
    """The paragraph's leaves; joined they are the paragraph."""
    return _LEAVES.findall(line) or [b""]


def _inner(children: list[str]) -> str:
    return hashlib.blake2b("".join(children).encode(), digest_size=16).hexdigest()


def _chars(data: bytes) -> int:
    return len(data) if data.isascii() else len(data.translate(None, _INSIDE))


def _paragraph(line: bytes, breaks: bytes) -> tuple[str, str]:
    """A paragraph's digest and its part of a fingerprint; line breaks after it count with its last leaf."""
    leaves = _leaves(line)
    size = _HEX[len(leaves[-1])]
    leaves[-1] += breaks
    own = list(map(xxh3_128_hexdigest, leaves))
    sizes = list(map(_HEX.__getitem__, map(len, leaves)))
    chars = sizes if line.isascii() else [_HEX[_chars(x)] for x in leaves]
    sizes = [*sizes[:-1], size]
    digest = _inner(own)
    below = "".join([d[:DIGEST] + x + y for d, x, y in zip(own, sizes, chars, strict=True)])
    return digest, f"{PARAGRAPH}{digest[:DIGEST]}{len(line):08x}{below}"


def fingerprint(text: str | None, known: dict[tuple[bytes, bytes], tuple[str, str]] | None = None) -> str:
    """Root, sections, paragraphs and leaves in the text's order, as hex digits; then finer leaves.

    ``known`` keeps paragraphs that another text may have too.
    """
    data = (text or "").encode("utf-8", "surrogatepass")
    known = {} if known is None else known
    out, sections = [], []
    parts = data.split(b"\n\n")
    for k, section in enumerate(parts, 1):
        below, paragraphs = [], []
        lines = section.split(b"\n")
        for j, line in enumerate(lines, 1):
            key = line, b"\n" if j < len(lines) else b"\n\n" if k < len(parts) else b""
            if (found := known.get(key)) is None:
                found = known[key] = _paragraph(*key)
            paragraphs.append(found[0])
            below.append(found[1])
        sections.append(_inner(paragraphs))
        out.append(f"{SECTION}{sections[-1][:DIGEST]}{len(section):08x}{''.join(below)}")
    n = len(text or "")
    if n < SHORT:
        out.append(WORDS + "".join(xxh3_128_hexdigest(x)[:DIGEST] + _HEX[len(x)] + _HEX[_chars(x)] for x in _WORDS.findall(data)))
    if n < TINY:  # each byte with the one before it, so that letters alone say little
        out.append(BYTES + "".join(xxh3_128_hexdigest(data[max(j - 1, 0) : j + 1])[:DIGEST] + "01" + _HEX[_chars(data[j : j + 1])] for j in range(len(data))))
    return _inner(sections) + "".join(out)


#: A node read from a fingerprint: digest, start and end in bytes, code points, what is below it.
Read = tuple[str, int, int, int, str]


def _levels(print_: str) -> tuple[str, str | None, str | None]:
    """The tree without its root, the words, and the bytes."""
    tree, has_words, rest = print_[ROOT:].partition(WORDS)
    words, has_bytes, singles = rest.partition(BYTES)
    return tree, words if has_words else None, singles if has_bytes else None


def _branches(below: str, mark: str, at: int) -> list[Read]:
    """The sections or paragraphs of a stretch of a fingerprint that begins at byte ``at`` of the text."""
    out, gap = [], 2 if mark == SECTION else 1
    for x in below.split(mark)[1:]:
        end = at + int(x[DIGEST : DIGEST + BRANCH_BYTES], 16)
        out.append((x[:DIGEST], at, end, 0, x[DIGEST + BRANCH_BYTES :]))
        at = end + gap
    return out


def _leaf_nodes(below: str, at: int) -> list[Read]:
    out, size, step = [], DIGEST + LEAF_BYTES, DIGEST + LEAF_BYTES + LEAF_CHARS
    for k in range(0, len(below), step):
        end = at + int(below[k + DIGEST : k + size], 16)
        out.append((below[k : k + DIGEST], at, end, int(below[k + size : k + step], 16), ""))
        at = end
    return out


def _without(nodes: list[Read], others: list[Read]) -> list[Read]:
    """Nodes that have no counterpart among the others, repeats counted."""
    left = Counter(x[0] for x in others)
    out = []
    for x in nodes:
        if left[x[0]]:
            left[x[0]] -= 1
        else:
            out.append(x)
    return out


def _apart(a: str, b: str) -> list[Read]:
    """Leaves of one tree without a counterpart in another; equal branches are not entered."""
    one, two = _branches(a, SECTION, 0), _branches(b, SECTION, 0)
    one, two = _without(one, two), _without(two, one)
    one, two = ([p for x in side for p in _branches(x[4], PARAGRAPH, x[1])] for side in (one, two))
    one, two = _without(one, two), _without(two, one)
    one, two = ([leaf for x in side for leaf in _leaf_nodes(x[4], x[1])] for side in (one, two))
    return _without(one, two)


def _size(tree: str) -> int:
    """Code points of the leaves of a tree."""
    step, head = DIGEST + LEAF_BYTES + LEAF_CHARS, DIGEST + BRANCH_BYTES
    total = 0
    for x in tree.replace(SECTION, PARAGRAPH).split(PARAGRAPH)[1:]:
        for k in range(head + DIGEST + LEAF_BYTES, len(x), step):
            total += int(x[k : k + LEAF_CHARS], 16)
    return total


def likeness(a: str, b: str, chars: tuple[int, int] | None = None) -> float:
    """0 to 1, from two fingerprints alone; 1 for equal roots only. ``chars`` are the texts' code points, if known."""
    if a[:ROOT] == b[:ROOT]:
        return 1.0
    own, other = _levels(a), _levels(b)
    for x, y in ((own[2], other[2]), (own[1], other[1])):
        if x is not None and y is not None:
            one, two = _leaf_nodes(x, 0), _leaf_nodes(y, 0)
            gone = _without(one, two)
            break
    else:
        gone = _apart(own[0], other[0])
    n, m = chars or (_size(own[0]), _size(other[0]))
    return min(n - sum(x[3] for x in gone), max(n, m) - 0.5) / max(n, m)


@dataclass(frozen=True)
class Node:
    """kind: document, section, paragraph or leaf; start and end are byte positions in the text's UTF-8."""

    kind: str
    digest: bytes
    start: int
    end: int
    children: tuple[Node, ...] = ()


def read_tree(print_: str) -> Node:
    """The tree that a fingerprint holds."""
    def of(kind: str, x: Read, below: list[Node]) -> Node:
        return Node(kind, bytes.fromhex(x[0]), x[1], x[2], tuple(below))

    sections = []
    for x in _branches(_levels(print_)[0], SECTION, 0):
        paragraphs = [of("paragraph", p, [of("leaf", leaf, []) for leaf in _leaf_nodes(p[4], p[1])]) for p in _branches(x[4], PARAGRAPH, x[1])]
        sections.append(of("section", x, paragraphs))
    return Node("document", bytes.fromhex(print_[:ROOT]), 0, sections[-1].end, tuple(sections))


def tree(text: str | None) -> Node:
    return read_tree(fingerprint(text))


def differing(a: Node, b: Node) -> list[tuple[int, int]]:
    """Byte spans of ``a`` that have no counterpart in ``b``, found by descending into differing branches."""
    if a.digest == b.digest:
        return []
    if not a.children or not b.children:
        return [(a.start, a.end)]
    left = Counter(x.digest for x in b.children)
    gone, free = [], []
    for x in a.children:
        if left[x.digest]:
            left[x.digest] -= 1
        else:
            gone.append(x)
    matched = Counter(x.digest for x in a.children)
    for x in b.children:
        if matched[x.digest]:
            matched[x.digest] -= 1
        else:
            free.append(x)
    out: list[tuple[int, int]] = []
    for k, x in enumerate(gone):
        out += differing(x, free[k]) if k < len(free) and x.children else [(x.start, x.end)]
    return out


def _in_line(tree: str) -> list[tuple[str, int, int]]:
    """All leaves and the beginnings of branches in the text's order."""
    out = []
    for x in _branches(tree, SECTION, 0):
        out.append((SECTION, x[1], x[1]))
        for p in _branches(x[4], PARAGRAPH, x[1]):
            out.append((PARAGRAPH, p[1], p[1]))
            out += [leaf[:3] for leaf in _leaf_nodes(p[4], p[1])]
    return out


def edited_spans(a: str, b: str) -> list[tuple[int, int]]:
    """Byte spans of ``a``'s text that have no counterpart in ``b``'s, from the fingerprints.

    If all of its leaves have one, they have moved or others are missing between them: the span
    from the first place that differs to the last, empty where something was only taken out.
    """
    if a[:ROOT] == b[:ROOT]:
        return []
    a, b = _levels(a)[0], _levels(b)[0]
    out: list[tuple[int, int]] = []
    for _, start, end, _, _ in _apart(a, b):
        if out and out[-1][1] == start:
            out[-1] = out[-1][0], end
        else:
            out.append((start, end))
    if out:
        return out
    one, two = _in_line(a), _in_line(b)
    short, k, j = min(len(one), len(two)), 0, 0
    while k < short and one[k][0] == two[k][0]:
        k += 1
    while j < short - k and one[-1 - j][0] == two[-1 - j][0]:
        j += 1
    if k + j == len(one):
        at = one[k][1] if k < len(one) else one[-1][2]
        return [(at, at)]
    return [(one[k][1], one[-1 - j][2])]


def edited(text: str, other: str) -> str:
    """The last third of the text's code points replaced by the first as many of the other's."""
    k = len(text) // 3
    return text[: len(text) - k] + other[:k]


def in_order(docs: DataFrame, buckets: int) -> DataFrame:
    """``bucket, own, doc_id, text``: documents by descending id, each bucket a stretch of them.

    After a bucket's own rows comes a copy of the row that follows them (``own`` false): the next
    bucket's first, or the first of all after the last. Ids sort by value, null ids last, equal ids
    by text. Only the buckets' bounds and first ids come to the driver.
    """
    lowest = -(1 << 63)
    keyed = docs.withColumn("key", F.coalesce("doc_id", F.lit(lowest)))
    bounds = keyed.approxQuantile("key", [k / buckets for k in range(1, buckets)], 0.2 / buckets) if buckets > 1 else []
    bounds = sorted({int(x) for x in bounds})
    at = F.lit(0)
    if bounds:
        # descending: bucket 0 holds what lies above the highest bound
        ends = F.array(*[F.lit(x) for x in bounds])
        at = F.size(F.filter(ends, lambda x: x >= F.col("key")))
    keyed = keyed.withColumn("bucket", at)
    firsts = dict(keyed.groupBy("bucket").agg(F.max("key").alias("key")).collect())
    order = sorted(firsts)
    before = {firsts[b]: order[k - 1] for k, b in enumerate(order)}  # order[-1] for the first of all
    targets = F.array(F.struct(F.col("bucket").alias("bucket"), F.lit(True).alias("own")))
    if before:
        copied = F.element_at(F.create_map(*[F.lit(x) for pair in before.items() for x in pair]), F.col("key"))
        targets = F.when(F.col("key").isin(list(before)), F.concat(targets, F.array(F.struct(copied.alias("bucket"), F.lit(False).alias("own"))))).otherwise(targets)
    spread = keyed.select("doc_id", "text", "key", F.explode(targets).alias("at")).select("at.bucket", "at.own", "doc_id", "text", "key")
    parts = max(1, buckets // 4)  # dealt in turn, not by hash, so that all have as many buckets
    return spread.repartitionById(parts, F.pmod("bucket", F.lit(parts))).sortWithinPartitions("bucket", F.desc("own"), F.desc("key"), "text").drop("key")


def fingerprint_edits(docs: DataFrame, buckets: int | None = None, id_col: str = "doc_id", text_col: str = "text", spans: bool = False) -> DataFrame:
    """Fingerprints of each text and of its edited text, and their likeness; a row for each row of ``docs``.

    doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next; with
    ``spans`` also edited_spans, the byte spans of the edited text that the text doesn't have.
    """
    if buckets is None:
        buckets = 4 * int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    names = ["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"]
    kinds = (pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64())
    schema = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"
    if spans:
        names.append("edited_spans")
        kinds += (pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())])),)
        schema += ", edited_spans array<struct<start: long, end: long>>"

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        waiting = None  # bucket, id, text, fingerprint and paragraphs of the row whose next is still to come
        for batch in slices(batches):
            out = []
            for bucket, own, doc, text in zip(*(batch.column(k).to_pylist() for k in range(4)), strict=True):
                if waiting is None and not own:
                    continue
                paragraphs: dict = {}
                mark = fingerprint(text, paragraphs)
                if waiting is not None and waiting[0] == bucket:
                    _, i, before, print_, known = waiting
                    changed = edited(before, text)
                    changed_print = fingerprint(changed, known | paragraphs)
                    sha = hashlib.sha256(changed.encode("utf-8", "surrogatepass")).hexdigest()
                    near = likeness(print_, changed_print, (len(before), len(changed))), likeness(print_, mark, (len(before), len(text)))
                    row = (i, len(before), sha, print_, changed_print, *near)
                    out.append((*row, [{"start": a, "end": b} for a, b in edited_spans(changed_print, print_)]) if spans else row)
                waiting = (bucket, doc, text, mark, paragraphs) if own else None
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out, strict=True), kinds, strict=True)], names=names)

    picked = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    return in_order(picked, buckets).mapInArrow(rows, schema)
