"""Invertible Bloom lookup sketches of texts' paragraphs.

A text is cut into paragraphs at line ends, and long ones into pieces where a
word's hash says so; each piece, with its number among equal ones of its text,
has a 64-bit digest. A sketch adds every digest to one cell in each of three
tables; a cell holds how many, their sum and the sum of their checks. Subtract
the sketches of two versions and only the digests in which they differ are left;
cells with a single one give it up, which frees others (peeling).

A text's fingerprint is the smallest sketch, of 2, 4, 8 .. cells a table, that
peels alone. A digest's cell in a small sketch is its cell in a larger one
modulo the small one's cells, so a fingerprint can be folded to any smaller
size: two are compared folded to few cells first, and where some digests remain,
with more. At the smaller one's full size each peels alone at the latest, so the
fingerprints always tell how alike they are.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .textkit import U64, Rolling, mix, word_codes, words
from .windows import NULL_ID

TABLES = 3
PIECE_BITS = 4  # a word in sixteen ends a piece
#: cells of all sketches that are worked on at once, and rows and characters compared at once
CELLS_AT_ONCE, ROWS_AT_ONCE, CHARS_AT_ONCE = 1 << 18, 2048, 1 << 18
#: bytes of a cell in a fingerprint: count, sum, check
_FIELDS = ("<u2", "<u8", "<u4")


def digests(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(text, digest) of every piece of every text, in text order."""
    start, end, at = words(data, offsets)
    if not len(start):
        return np.zeros(0, np.int64), np.zeros(0, U64)
    code = word_codes(data, start, end)
    text = np.repeat(np.arange(len(offsets) - 1), np.diff(at))
    stop = (code & U64((1 << PIECE_BITS) - 1)) == 0
    lines = np.flatnonzero(data == 10)
    stop[:-1] |= (np.searchsorted(lines, start[1:]) > np.searchsorted(lines, end[:-1])) | (text[1:] != text[:-1])
    stop[-1] = True
    last = np.flatnonzero(stop)
    first = np.r_[0, last[:-1] + 1]
    piece = mix(Rolling(code).slices(first, last + 1) + U64(0x632BE59BD9B4E019))
    owner = text[first]
    order = np.lexsort((piece, owner))
    fresh = np.ones(len(order), bool)
    fresh[1:] = (piece[order[1:]] != piece[order[:-1]]) | (owner[order[1:]] != owner[order[:-1]])
    place = np.arange(len(order))
    copy = place - np.maximum.accumulate(np.where(fresh, place, 0))
    again = np.empty(len(order), np.int64)
    again[order] = copy
    return owner, mix(piece + again.astype(U64) * U64(0x9E3779B97F4A7C15))


def _check(d: np.ndarray) -> np.ndarray:
    return mix(d ^ U64(0xD6E8FEB86659FD93)) & U64(0xFFFFFFFF)


_SALTS = np.arange(1, TABLES + 1, dtype=U64) * U64(0xA0761D6478BD642F)


def _cell(d: np.ndarray, table: int | np.ndarray, cells: int) -> np.ndarray:
    """A digest's cell in a table of ``cells``, a power of two."""
    return (mix(d + _SALTS[table]) & U64(cells - 1)).astype(np.int64) + table * cells


class Sketches:
    """Sketches of many texts at once, of one size: ``cells`` in each table."""

    def __init__(self, texts: int, cells: int):
        self.cells = cells
        self.count = np.zeros((texts, TABLES * cells), np.int64)
        self.total = np.zeros((texts, TABLES * cells), U64)
        self.check = np.zeros((texts, TABLES * cells), U64)

    def add(self, text: np.ndarray, d: np.ndarray, sign: np.ndarray | int = 1) -> Sketches:
        sign = np.broadcast_to(np.asarray(sign, np.int64), d.shape)
        wide = sign.astype(U64)  # two's complement: -1 subtracts
        for t in range(TABLES):
            place = text * self.count.shape[1] + _cell(d, t, self.cells)
            np.add.at(self.count.ravel(), place, sign)
            np.add.at(self.total.ravel(), place, d * wide)
            np.add.at(self.check.ravel(), place, _check(d) * wide)
        return self

    def minus(self, other: Sketches) -> Sketches:
        out = Sketches(0, self.cells)
        out.count, out.total, out.check = self.count - other.count, self.total - other.total, self.check - other.check
        return out

    def folded(self, cells: int) -> Sketches:
        """What the same digests make with fewer cells."""
        out = Sketches(0, cells)
        out.count, out.total, out.check = (x.reshape(len(x), TABLES, -1, cells).sum(axis=2, dtype=x.dtype).reshape(len(x), -1) for x in (self.count, self.total, self.check))
        return out

    def peel(self) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Empties the sketches: (text, digest, sign) found, and which texts are all found."""
        found: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        low = U64(0xFFFFFFFF)
        # every round but the last frees a cell in some sketch, or a false digest goes back and forth
        for _ in range(self.count.shape[1] + 1):
            text, at = np.nonzero(np.abs(self.count) == 1)
            sign = self.count[text, at]
            d = self.total[text, at] * sign.astype(U64)
            pure = (_check(d) == (self.check[text, at] * sign.astype(U64) & low)) & (_cell(d, at // self.cells, self.cells) == at)
            text, d, sign = text[pure], d[pure], sign[pure]
            if not len(text):
                break
            _, first = np.unique(mix(text.astype(U64)) ^ d, return_index=True)
            text, d, sign = text[first], d[first], sign[first]
            self.add(text, d, -sign)
            found.append((text, d, sign))
        done = ~(self.count.any(axis=1) | self.total.any(axis=1) | (self.check & low).any(axis=1))
        parts = [np.concatenate(x) for x in zip(*found, strict=True)] if found else [np.zeros(0, np.int64), np.zeros(0, U64), np.zeros(0, np.int64)]
        return parts[0], parts[1], parts[2], done

    def strings(self, sizes: np.ndarray) -> list[str]:
        """Each sketch with its number of digests, as text."""
        planes = (x.astype(kind).view(np.uint8) for x, kind in zip((self.count, self.total, self.check), _FIELDS, strict=True))
        raw = np.concatenate([np.asarray(sizes, "<u4")[:, None].view(np.uint8), *planes], axis=1)
        return [base64.b64encode(r.tobytes()).decode() for r in raw]

    @staticmethod
    def parse(fingerprint: str) -> tuple[Sketches, int]:
        """A sketch and its number of digests from text."""
        raw = base64.b64decode(fingerprint)
        n = (len(raw) - 4) // 14
        out, at = Sketches(1, n // TABLES), 4
        for name, kind in zip(("count", "total", "check"), _FIELDS, strict=True):
            size = n * np.dtype(kind).itemsize
            value = np.frombuffer(raw, kind, n, at)
            setattr(out, name, (value.astype(np.int16).astype(np.int64) if name == "count" else value.astype(U64))[None, :])
            at += size
        return out, int(np.frombuffer(raw, "<u4", 1)[0])


def enough(n: np.ndarray) -> np.ndarray:
    """The fewest cells a table, by powers of two from 2, whose tables have as many cells as there are digests."""
    return 2 ** np.maximum(1, np.ceil(np.log2(np.maximum(n, 1) / TABLES)).astype(np.int64))


class Corpus:
    """Digests of many texts: ``d[begin[i] : begin[i + 1]]`` are those of text i."""

    def __init__(self, owner: np.ndarray, d: np.ndarray, texts: int):
        self.d, self.size = d, np.bincount(owner, minlength=texts)
        self.begin = np.r_[0, np.cumsum(self.size)]

    def of(self, texts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(place in ``texts``, digest) of all of their digests."""
        n = self.size[texts]
        row = np.repeat(np.arange(len(texts)), n)
        return row, self.d[np.repeat(self.begin[texts] - (np.cumsum(n) - n), n) + np.arange(n.sum())]

    def parts(self, which: np.ndarray, cells: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
        """(cells, some of ``which``): those with the same number of cells, a bounded number at once."""
        for c in np.unique(cells).tolist():
            same = which[cells == c]
            step = max(1, CELLS_AT_ONCE // (TABLES * c))
            for k in range(0, len(same), step):
                yield c, same[k : k + step]

    def own(self) -> tuple[np.ndarray, list[str]]:
        """(cells, fingerprint) of every text: the smallest sketch that peels alone."""
        cells = enough(self.size)
        prints = [""] * len(self.size)
        todo = np.arange(len(self.size))
        while len(todo):
            failed = [todo[:0]]
            for c, part in self.parts(todo, cells[todo]):
                row, d = self.of(part)
                text = Sketches(len(part), c).add(row, d)
                said = text.strings(self.size[part])
                done = text.peel()[3]
                for i in np.flatnonzero(done).tolist():
                    prints[part[i]] = said[i]
                failed.append(part[~done])
            todo = np.concatenate(failed)
            cells[todo] *= 2
        return cells, prints

    def differences(self, left: np.ndarray, right: np.ndarray, most: np.ndarray) -> np.ndarray:
        """How many digests differ between texts ``left[i]`` and ``right[i]``: peeled from sketches folded to few cells, then more, up to ``most[i]``."""
        out = np.zeros(len(left), np.int64)
        todo = np.arange(len(left))
        # no sketch gives up more digests than it has cells
        cells = enough(np.abs(self.size[left] - self.size[right]))
        while True:
            late = cells[todo] > most[todo]
            for i in todo[late].tolist():  # both peel alone
                a, b = (self.d[self.begin[x[i]] : self.begin[x[i] + 1]] for x in (left, right))
                out[i] = len(a) + len(b) - 2 * len(np.intersect1d(a, b, assume_unique=True))
            todo = todo[~late]
            if not len(todo):
                return out
            failed = [todo[:0]]
            for c, part in self.parts(todo, cells[todo]):
                text = Sketches(len(part), c)
                for side, sign in ((left, 1), (right, -1)):
                    text.add(*self.of(side[part]), sign)
                found, _, _, done = text.peel()
                out[part[done]] = np.bincount(found, minlength=len(part))[done]
                failed.append(part[~done])
            todo = np.concatenate(failed)
            cells[todo] *= 4

    def likeness(self, left: np.ndarray, right: np.ndarray, cells: np.ndarray) -> np.ndarray:
        """Shared digests as a part of all digests of two texts; 1 if neither has any. ``cells``: of the texts' fingerprints."""
        both = self.size[left] + self.size[right]
        differ = self.differences(left, right, np.minimum(cells[left], cells[right]))
        return np.where(both == 0, 1.0, (both - differ) / np.maximum(both + differ, 1))


def likeness(one: str, other: str) -> float:
    """How alike two fingerprints are, from themselves alone: shared digests as a part of all."""
    (a, n), (b, k) = Sketches.parse(one), Sketches.parse(other)
    if n + k == 0:
        return 1.0
    most = min(a.cells, b.cells)
    cells = int(enough(np.array(abs(n - k))))
    while cells <= most:
        found, _, _, done = a.folded(cells).minus(b.folded(cells)).peel()
        if done[0]:
            return (n + k - len(found)) / (n + k + len(found))
        cells *= 2
    left, right = (set(x.peel()[1].tolist()) for x in (a, b))
    return len(left & right) / len(left | right)


# over a table ----------------------------------------------------------------

_COLUMNS = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"


def _compare(ids: list[int], texts: list[str], nexts: list[str]) -> pa.RecordBatch:
    """One result row for each text, from it and the next one's text."""
    edited = [t[: len(t) - len(t) // 2] + x[: len(t) // 2] for t, x in zip(texts, nexts, strict=True)]
    raw = [t.encode() for t in (*texts, *edited, *nexts)]
    offsets = np.cumsum([0, *map(len, raw)])
    n = len(texts)
    pieces = Corpus(*digests(np.frombuffer(b"".join(raw), np.uint8), offsets), 3 * n)
    cells, prints = pieces.own()
    row = np.arange(n)
    near = pieces.likeness(np.r_[row, row], np.r_[row + n, row + 2 * n], cells)
    return pa.record_batch(
        [pa.array([None if i == NULL_ID else i for i in ids], pa.int64()), pa.array([len(t) for t in texts], pa.int64()), pa.array([hashlib.sha256(r).hexdigest() for r in raw[n : 2 * n]]), pa.array(prints[:n]), pa.array(prints[n : 2 * n]), pa.array(near[:n]), pa.array(near[n:])],
        names=[c.split()[0] for c in _COLUMNS.split(", ")],
    )


def fingerprint_versions(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", buckets: int | None = None) -> DataFrame:
    """Fingerprints of every text and of an edit of it, and how alike they are.

    The edit replaces the last half of the text's code points by the first of
    the next text, in descending order of id (equal ids by text, null ids last;
    after the last comes the first; a single text is its own next). Null texts
    are empty. Equal texts have equal fingerprints; ``near_edited`` and
    ``near_next`` are what ``likeness`` gives for the fingerprints. Texts without
    words are alike. Other columns are ignored; an empty table has no rows.

    Rows are dealt out by ranges of ids; the greatest text of each range is sent
    along to the range above, so that neighbours always meet.
    """
    spark = docs.sparkSession
    rows = docs.select(F.coalesce(F.col(id_col).cast("long"), F.lit(NULL_ID)).alias("doc"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    buckets = buckets or 4 * parts
    # one number for each range, whatever the table's size
    cuts = np.unique(np.array(rows.stat.approxQuantile("doc", [k / buckets for k in range(1, buckets)], 0.25 / buckets), np.float64)).astype(np.int64) if buckets > 1 else np.zeros(0, np.int64)

    def tops(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        best: dict[int, int] = {}
        for b in batches:
            doc = b.column(0).to_numpy()
            at = np.searchsorted(cuts, doc, "right")
            for k in np.unique(at).tolist():
                best[k] = max(best.get(k, NULL_ID), int(doc[at == k].max()))
        yield pa.record_batch([pa.array(list(best), pa.int64()), pa.array(list(best.values()), pa.int64())], names=["bucket", "doc"])

    top = {r.bucket: r.top for r in rows.select("doc").mapInArrow(tops, "bucket long, doc long").groupBy("bucket").agg(F.max("doc").alias("top")).collect()}
    filled = sorted(top)
    #: the id that a range sends along, and to which range
    sends = {top[k]: filled[i + 1 if i + 1 < len(filled) else 0] for i, k in enumerate(filled)}

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        heads = np.array(sorted(sends), np.int64)
        for b in batches:
            doc = b.column(0).to_numpy()
            yield pa.record_batch([pa.array(np.searchsorted(cuts, doc, "right")), pa.array(np.zeros(len(doc), bool)), b.column(0), b.column(1)], names=["bucket", "sent", "doc", "text"])
            along = np.flatnonzero(np.isin(doc, heads))
            if len(along):
                to = np.array([sends[x] for x in doc[along].tolist()], np.int64)
                which = pa.array(along)
                yield pa.record_batch([pa.array(to), pa.array(np.ones(len(along), bool)), b.column(0).take(which), b.column(1).take(which)], names=["bucket", "sent", "doc", "text"])

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[int, bool, int, str]] = []
        size = 0
        for part in (b.slice(at, ROWS_AT_ONCE) for b in batches for at in range(0, b.num_rows, ROWS_AT_ONCE)):
            for r in zip(*(c.to_pylist() for c in part.columns), strict=True):
                held.append(r)
                size += len(r[3])
                if size >= CHARS_AT_ONCE or len(held) > ROWS_AT_ONCE:
                    yield from flush(held)
                    held, size = held[-1:], len(r[3])
        yield from flush(held)

    def flush(held: list[tuple[int, bool, int, str]]) -> Iterator[pa.RecordBatch]:
        pairs = [(x, y) for x, y in zip(held[:-1], held[1:], strict=True) if not x[1]]
        if pairs:
            yield _compare([x[2] for x, _ in pairs], [x[3] for x, _ in pairs], [y[3] for _, y in pairs])

    dealt = rows.mapInArrow(deal, "bucket long, sent boolean, doc long, text string").repartition(parts, "bucket")
    return dealt.sortWithinPartitions("bucket", "sent", F.desc("doc"), "text").mapInArrow(meet, _COLUMNS)
