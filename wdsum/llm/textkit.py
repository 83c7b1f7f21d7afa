"""Array kernels over UTF-8 text shared by the corpus operators.

Everything here works on one Arrow batch at a time, in blocks of whole texts
whose size is bounded by ``BLOCK_BYTES`` (one text longer than that is a block
of its own), so memory follows the block and never the partition.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa

BLOCK_BYTES = 1 << 20
#: symbols of a text that are hashed at once; positions in a piece fit 24 bits
PIECE = 1 << 20

_BASE = 0x9E3779B97F4A7C15 - 0x9E3779B97F4A7C15 % 8 + 5  # odd, 5 modulo 8
_MASK = (1 << 64) - 1
U64 = np.uint64


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: every input bit reaches every output bit."""
    x = x ^ (x >> U64(30))
    x *= U64(0xBF58476D1CE4E5B9)
    x ^= x >> U64(27)
    x *= U64(0x94D049BB133111EB)
    x ^= x >> U64(31)
    return x


BYTE_CODES = mix(np.arange(1, 257, dtype=U64) * U64(0x9E3779B97F4A7C15))

_powers = [np.ones(1, U64), np.ones(1, U64)]


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the rolling base and of its inverse modulo 2**64, 0..n-1."""
    if len(_powers[0]) < n:
        size = 1 << max(16, (n - 1).bit_length())
        for slot, base in enumerate((_BASE, pow(_BASE, -1, 1 << 64))):
            steps = np.full(size, base, U64)
            steps[0] = 1
            _powers[slot] = np.cumprod(steps, dtype=U64)
    return _powers[0][:n], _powers[1][:n]


class Rolling:
    """Rabin-Karp hashes of any slices of one symbol array, from one prefix sum."""

    def __init__(self, codes: np.ndarray):
        up, self._down = powers(len(codes) + 1)
        self.prefix = np.empty(len(codes) + 1, U64)
        self.prefix[0] = 0
        np.cumsum(codes * up[: len(codes)], dtype=U64, out=self.prefix[1:])

    def slices(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        return (self.prefix[end] - self.prefix[start]) * self._down[start]

    def grams(self, k: int) -> np.ndarray:
        n = len(self.prefix) - k
        return (self.prefix[k:] - self.prefix[:n]) * self._down[:n] if n > 0 else np.zeros(0, U64)


def utf8(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string column without copying; null is empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("" if not pa.types.is_binary(column.type) else b"")
    kind = np.int64 if pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type) else np.int32
    _, offs, data = column.buffers()
    if len(column) == 0 or offs is None:
        return np.zeros(0, np.uint8), np.zeros(len(column) + 1, np.int64)
    at = np.frombuffer(offs, kind)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[at[0] : at[-1]], at - at[0]


def blocks(offsets: np.ndarray, limit: int = BLOCK_BYTES) -> Iterator[tuple[int, int]]:
    """Ranges of texts of at most ``limit`` bytes together, one text at least."""
    i, n = 0, len(offsets) - 1
    while i < n:
        j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + limit, "right")) - 1)
        yield i, min(j, n)
        i = min(j, n)


_SPACE = np.zeros(256, bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True


def words(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Maximal runs of bytes other than space and tab..carriage return.

    Gives word starts, word ends, and for each text the number of words before it.
    Words never cross a text's end.
    """
    if len(data) == 0:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(len(offsets), np.int64)
    inside = ~_SPACE[data]
    first = inside.copy()
    first[1:] &= ~inside[:-1]
    edges = offsets[:-1][offsets[:-1] < len(data)]
    first[edges] = inside[edges]
    last = inside.copy()
    last[:-1] &= ~inside[1:]
    ends = offsets[1:][offsets[1:] > 0] - 1
    last[ends] = inside[ends]
    start = np.flatnonzero(first)
    return start, np.flatnonzero(last) + 1, np.searchsorted(start, offsets)


def lower_ascii(data: np.ndarray) -> np.ndarray:
    return np.where((data >= 65) & (data <= 90), data + np.uint8(32), data)


def word_codes(data: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each word's bytes, some ``PIECE`` bytes at a time."""
    out = np.empty(len(start), U64)
    for i, j in blocks(np.r_[start, end[-1:]], PIECE) if len(start) else ():
        lo = start[i]
        out[i:j] = Rolling(BYTE_CODES[data[lo : end[j - 1]]]).slices(start[i:j] - lo, end[i:j] - lo)
    return mix(out + (end - start).astype(U64) * U64(0x9E3779B97F4A7C15))


def sliding_min(x: np.ndarray, w: int) -> np.ndarray:
    """Minimum of each run of ``w`` neighbours, by doubling."""
    size, out = 1, x
    while size * 2 <= w:
        out = np.minimum(out[:-size], out[size:])
        size *= 2
    return np.minimum(out[: len(x) - w + 1], out[w - size :][: len(x) - w + 1]) if size < w else out


def anchored_cells(codes: np.ndarray, offsets: np.ndarray, n: int, k: int, far: int | None = None) -> dict[str, np.ndarray]:
    """Groups the windows of ``n`` symbols of every text by their anchor.

    A window's anchor is its k-gram of smallest hash, the leftmost of equals, so
    it depends on the window's content alone: equal windows have equal anchor
    keys. Neighbouring windows with the same anchor make one *cell*; every
    window lies in exactly one. Gives, per cell: text, first and last window
    start and where its context ends (all within the text), the anchor's 64-bit
    key, and a 64-bit print of the context together with the anchor's place. The
    context is what windows of ``far`` symbols (``n`` if not given) from the same
    starts cover, up to the text's end.

    More than ``PIECE`` symbols are done piece by piece, with the same cells:
    the next piece starts at the first cell whose context may go on.
    """
    far = far or n
    size = max(PIECE, 2 * (n + far))  # a cell has n - k + 1 windows at most: some cells of a piece are whole
    if len(codes) <= size:
        return _cells(codes, offsets, n, k, far)
    parts = []
    for t, (start, end) in enumerate(zip(offsets[:-1].tolist(), offsets[1:].tolist(), strict=True)):
        at = start
        while True:
            stop = min(at + size, end)
            part = _cells(codes[at:stop], np.array([0, stop - at]), n, k, far)
            more = stop < end
            whole = int(np.searchsorted(part["s1"], stop - at - far)) if more else len(part["s1"])
            last = int(part["s0"][whole]) if more else 0
            part = {x: v[:whole] for x, v in part.items()}
            parts.append(part | {"text": part["text"] + t} | {x: part[x] + (at - start) for x in ("s0", "s1", "s2")})
            if not more:
                break
            at += last
    return {x: np.concatenate([p[x] for p in parts]) for x in parts[0]}


def _cells(codes: np.ndarray, offsets: np.ndarray, n: int, k: int, far: int) -> dict[str, np.ndarray]:
    """``anchored_cells`` of one piece."""
    empty = {x: np.zeros(0, np.int64) for x in ("text", "s0", "s1", "s2")} | {x: np.zeros(0, U64) for x in ("key", "print")}
    if len(codes) < n:
        return empty
    rolling = Rolling(codes)
    gram = mix(rolling.grams(k))
    place = (gram & U64(_MASK ^ 0xFFFFFF)) | np.arange(len(gram), dtype=U64)
    at = (sliding_min(place, n - k + 1) & U64(0xFFFFFF)).astype(np.int64)  # by window start
    length = np.diff(offsets)
    text = np.repeat(np.arange(len(length)), length)[: len(at)]
    ok = np.arange(len(at)) + n <= offsets[1:][text]
    fresh = ok.copy()
    fresh[1:] &= (at[1:] != at[:-1]) | ~ok[:-1]
    stop = ok.copy()
    stop[:-1] &= (at[1:] != at[:-1]) | ~ok[1:]
    s0, s1 = np.flatnonzero(fresh), np.flatnonzero(stop)
    if len(s0) == 0:
        return empty
    a, doc = at[s0], text[s0]
    s2 = np.minimum(s1 + far, offsets[1:][doc])
    shape = ((a - s0) << 40 | (s1 - s0) << 20 | (s2 - s1)).astype(U64)
    base = offsets[doc]
    return {"text": doc, "s0": s0 - base, "s1": s1 - base, "s2": s2 - base, "key": gram[a], "print": mix(rolling.slices(s0, s2) ^ mix(shape))}


def crc_of_id(doc_id) -> int:
    """crc32 of an id written as decimal text."""
    return zlib.crc32(str(doc_id).encode())


def merge_spans(start: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Maximal runs covered by half-open spans; touching spans join."""
    if len(start) == 0:
        return start, end
    order = np.argsort(start, kind="stable")
    start, reach = start[order], np.maximum.accumulate(end[order])
    fresh = np.ones(len(start), bool)
    fresh[1:] = start[1:] > reach[:-1]
    first = np.flatnonzero(fresh)
    return start[first], reach[np.r_[first[1:] - 1, len(start) - 1]]
