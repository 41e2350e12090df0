"""64-bit hashes of the words of whole Arrow columns, in a few numpy passes over the bytes.

Words are runs of bytes other than blank, tab, line feed, vertical tab, form feed and carriage
return; A to Z count as a to z. A word's hash is a polynomial in random values of its bytes,
mixed; it depends on the word alone.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

#: Bytes of text that are hashed together.
BLOCK = 1 << 20
_BASE = np.uint64(0x9E3779B97F4A7C15 | 1)
_INVERSE = np.uint64(pow(int(_BASE), -1, 1 << 64))
_WHITE = np.zeros(256, bool)
_WHITE[[9, 10, 11, 12, 13, 32]] = True


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit numbers that spreads each bit over all."""
    x = (x ^ (x >> np.uint64(33))) * np.uint64(0xFF51AFD7ED558CCD)
    x = (x ^ (x >> np.uint64(33))) * np.uint64(0xC4CEB9FE1A85EC53)
    return x ^ (x >> np.uint64(33))


def _values() -> np.ndarray:
    values = mix(np.arange(1, 257, dtype="<u8"))
    values[65:91] = values[97:123]
    return values


_VALUES = _values()
_POWERS: list[np.ndarray] = [np.zeros(0, "<u8"), np.zeros(0, "<u8")]


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_POWERS[0]) < n:
        up, down = np.full(n, _BASE), np.full(n, _INVERSE)
        up[0] = down[0] = 1
        up, down = np.multiply.accumulate(up), np.multiply.accumulate(down)
        if n > 4 * BLOCK:
            return up, down
        _POWERS[:] = up, down
    return _POWERS[0], _POWERS[1]


#: What lies between runs of letters: all of ASCII but letters; bytes of other characters count as letters.
NOT_LETTERS = np.ones(256, bool)
NOT_LETTERS[[*range(65, 91), *range(97, 123), *range(128, 256)]] = False


def word_hashes(texts: pa.Array, white: np.ndarray = _WHITE) -> tuple[np.ndarray, np.ndarray]:
    """The hashes of all words in order, and where each row's words begin (one more entry than rows).

    ``white`` says of each byte whether it lies between words.
    """
    rows = len(texts)
    if texts.null_count:
        texts = texts.fill_null("")
    texts = texts.cast(pa.large_string())
    _, offsets, data = texts.buffers()
    offsets = np.frombuffer(offsets, "<i8")[texts.offset : texts.offset + rows + 1]
    first, last = int(offsets[0]), int(offsets[-1])
    if first == last:
        return np.zeros(0, "<u8"), np.zeros(rows + 1, "<i8")
    raw = np.frombuffer(data, "u1")[first:last]
    cuts = offsets - first
    inside = ~white[raw]
    start = inside.copy()
    start[1:] &= ~inside[:-1]
    begins = cuts[:-1][cuts[:-1] < len(raw)]
    start[begins] = inside[begins]  # a row's first byte begins a word whatever came before
    end = inside.copy()
    end[:-1] &= ~inside[1:] | start[1:]
    starts, ends = np.flatnonzero(start), np.flatnonzero(end) + 1
    up, down = _powers(len(raw))
    sums = np.zeros(len(raw) + 1, "<u8")
    np.cumsum(_VALUES[raw] * up[: len(raw)], out=sums[1:])
    hashes = mix((sums[ends] - sums[starts]) * down[starts] + (ends - starts).astype("<u8"))
    return hashes, np.searchsorted(starts, cuts).astype("<i8")


def blocks(batch: pa.RecordBatch, column: int, block: int = BLOCK) -> Iterator[pa.RecordBatch]:
    """The batch in stretches of rows with about ``block`` bytes of text, or a single row."""
    texts = batch.column(column)
    if texts.null_count:
        texts = texts.fill_null("")
    if not len(texts):
        return
    texts = texts.cast(pa.large_string())
    offsets = np.frombuffer(texts.buffers()[1], "<i8")[texts.offset : texts.offset + batch.num_rows + 1]
    at = 0
    while at < batch.num_rows:
        end = int(np.searchsorted(offsets, offsets[at] + block, "right")) - 1
        end = min(max(end, at + 1), batch.num_rows)
        yield batch.slice(at, end - at)
        at = end
