"""Enhanced suffix arrays and their common-prefix interval trees; repeated byte strings of a corpus.

``SuffixArray`` sorts the suffixes of a bounded set of texts by prefix doubling
and has the common prefix of neighbours. ``maximal_repeats`` scans it with a
stack: each interval of suffixes that share a prefix is one node of the tree,
and a node whose suffixes are preceded by different symbols can't be extended to
the left, so it is a maximal repeat with all its occurrences.

Over a corpus, ``repeat_spans`` first lets Spark find the windows' cells whose
anchor occurs elsewhere (``windows``): cells with equal prints repeat whole.
One representative of each different cell that shares its key with another goes
to a suffix array, in tasks that hold a bounded number of bytes; there the
interval tree tells how long each window's longest repeat is, and with it which
bytes lie in repeats of one length and which in longer ones. Keys with more
representatives than ``GROUP`` are first split by the bytes that all windows of
a sub-cell share, ever narrower, down to single windows, so that no group has to
fit one task and none is cut short.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .stored import stored
from .textkit import BYTE_CODES, U64, Rolling, anchored_cells, merge_spans, mix
from .windows import NULL_ID, by_document, by_print, cells, free_names, identified, list_parts, packed, removal, shared_cells, symbols, unpack
from .workers import kernel

#: bytes of context in one suffix array, and representatives of one key
BATCH_BYTES, GROUP = 1 << 19, 2048


class SuffixArray:
    """Suffixes of several byte strings, each ending with its own string.

    ``order`` has their places in the concatenation; ``lcp[i]`` is the length of
    the prefix that suffixes ``order[i - 1]`` and ``order[i]`` share.
    """

    def __init__(self, data: np.ndarray, offsets: np.ndarray):
        self.data, self.offsets = data, offsets
        n = len(data)
        self.end = np.repeat(offsets[1:], np.diff(offsets))
        place = np.arange(n)
        if n == 0:
            self.order, self.lcp = place, place
            return
        code = np.zeros(n, U64)
        for j in range(7):  # seven symbols of 257 values fit 64 bits
            at = place + j
            code = code * U64(257) + np.where(at < self.end, data[np.minimum(at, n - 1)].astype(U64) + U64(1), U64(0))
        order = np.argsort(code, kind="stable")
        rank = self._ranks(order, code[order])
        levels, span, longest = [(7, rank)], 7, int(np.diff(offsets).max())
        while span < longest:
            single = np.ones(n, bool)  # by slot: alone with its rank
            held = rank[order]
            single[1:] &= held[1:] != held[:-1]
            single[:-1] &= held[1:] != held[:-1]
            slots = np.flatnonzero(~single)
            if not len(slots):
                break
            who = order[slots]
            nxt = who + span
            code = rank[who].astype(U64) * U64(n + 1) + np.where(nxt < self.end[who], rank[np.minimum(nxt, n - 1)].astype(U64) + U64(1), U64(0))
            by = np.argsort(code, kind="stable")
            order[slots] = who[by]
            fresh = np.ones(len(slots), bool)
            code = code[by]
            fresh[1:] = code[1:] != code[:-1]
            rank = rank.copy()
            rank[who[by]] = slots[np.maximum.accumulate(np.where(fresh, np.arange(len(slots)), 0))]
            span *= 2
            levels.append((span, rank))
        self.order = order
        self.lcp = np.zeros(n, np.int64)
        a, b = order[:-1].copy(), order[1:].copy()
        rest = np.minimum(self.end[a] - a, self.end[b] - b)
        length = np.zeros(n - 1, np.int64)
        for span, rank in reversed(levels):
            live = length < rest
            x, y = np.minimum(a + length, n - 1), np.minimum(b + length, n - 1)
            length += np.where(live & (rank[x] == rank[y]), span, 0)
        # fewer than seven symbols are left to compare
        for _ in range(7):
            live = length < rest
            x, y = np.minimum(a + length, n - 1), np.minimum(b + length, n - 1)
            length += live & (data[x] == data[y])
        self.lcp[1:] = np.minimum(length, rest)

    @staticmethod
    def _ranks(order: np.ndarray, code: np.ndarray) -> np.ndarray:
        fresh = np.ones(len(order), bool)
        fresh[1:] = code[1:] != code[:-1]
        rank = np.empty(len(order), np.int32)
        rank[order] = np.maximum.accumulate(np.where(fresh, np.arange(len(order)), 0))
        return rank


def maximal_repeats(array: SuffixArray, least: int) -> Iterator[tuple[int, int, int]]:
    """(length, first, last): slots first..last of ``array.order`` are all occurrences of a maximal repeat.

    Maximal: it can be made longer on neither side without losing an occurrence.
    """
    if len(array.order) < 2:
        return
    at = array.order
    begins = np.zeros(len(array.data) + 1, bool)
    begins[array.offsets[:-1]] = True
    # symbols before neighbours differ; a text's beginning differs from all
    differ = np.zeros(len(at), np.int64)
    before = array.data[np.maximum(at - 1, 0)]
    differ[1:] = (before[1:] != before[:-1]) | begins[at[1:]] | begins[at[:-1]]
    diverse = np.cumsum(differ)
    long = array.lcp >= least
    edge = np.flatnonzero(np.diff(np.r_[False, long, False]))
    lcp = array.lcp
    for first, past in edge.reshape(-1, 2).tolist():
        # slots first - 1 .. past - 1 share ``least`` symbols at least
        if diverse[past - 1] == diverse[first - 1]:
            continue  # all are preceded by one symbol, and so is every node below
        stack: list[tuple[int, int]] = []
        for i, h in enumerate(lcp[first:past].tolist() + [0], first):
            left = i - 1
            while stack and stack[-1][0] > h:
                size, left = stack.pop()
                if diverse[i - 1] > diverse[left]:
                    yield size, left, i - 1
            if h and (not stack or stack[-1][0] < h):
                stack.append((h, left))


def repeats_in(texts: list[bytes], least: int) -> list[tuple[bytes, list[tuple[int, int]]]]:
    """Maximal repeats of a bounded list of texts: (string, all (text, place))."""
    offsets = np.cumsum([0, *map(len, texts)])
    data = np.frombuffer(b"".join(texts), np.uint8)
    array = SuffixArray(data, offsets)
    out = []
    for size, first, last in maximal_repeats(array, least):
        places = np.sort(array.order[first : last + 1])
        text = np.searchsorted(offsets, places, "right") - 1
        out.append((data[places[0] : places[0] + size].tobytes(), list(zip(text.tolist(), (places - offsets[text]).tolist(), strict=True))))
    return out


def longest(data: np.ndarray, offsets: np.ndarray, last: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """(place, length) of maximal repeats of ``n`` bytes or more, the longest at each place that begins one.

    Only places up to ``last`` in each string begin one, and only they count as
    others' occurrences; a repeat may reach on behind them.
    """
    array = SuffixArray(data, offsets)
    text = np.repeat(np.arange(len(last)), np.diff(offsets))
    slots = np.flatnonzero((array.order - offsets[text[array.order]]) <= last[text[array.order]])
    if len(slots) < 2:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    # neighbours share what all between them share
    array.lcp = np.r_[0, np.minimum.reduceat(array.lcp[: slots[-1] + 1], slots[:-1] + 1)]
    array.order = array.order[slots]
    reach = np.zeros(len(slots), np.int64)
    for size, first, end in maximal_repeats(array, n):
        part = reach[first : end + 1]
        np.maximum(part, size, out=part)
    hit = np.flatnonzero(reach)
    return array.order[hit], reach[hit]


# over a corpus ---------------------------------------------------------------


#: the mark of a span that lies in repeats of ``far`` bytes
FAR = 1 << 31
_CONTEXT = "grp long, doc long, tag int, s0 int, windows int, part binary"
_TYPES = (pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.binary())
_NAMES = [x.split()[0] for x in _CONTEXT.split(", ")]


def _contexts(texts: DataFrame) -> DataFrame:
    """(grp, doc, tag, s0, windows, part): the context of each asked cell, and its windows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            lo, hi, values = list_parts(b.column(3))
            key, s0, s1, s2 = (values.field(x).to_numpy(zero_copy_only=False) for x in range(4))
            for at in range(0, b.num_rows, 256):
                rows = range(at, min(at + 256, b.num_rows))
                raws = _raws(b.column(2).slice(at, len(rows)))
                row = np.repeat(np.array(rows), hi[at : at + len(rows)] - lo[at : at + len(rows)])
                cell = slice(lo[at], hi[rows[-1]])
                found = [raws[r - at][x:z] for r, x, z in zip(row.tolist(), s0[cell].tolist(), s2[cell].tolist(), strict=True)]
                yield pa.record_batch([pa.array(key[cell]), b.column(0).take(pa.array(row)), b.column(1).take(pa.array(row)), pa.array(s0[cell]), pa.array(s1[cell] - s0[cell] + 1), pa.array(found, pa.binary())], names=_NAMES)

    return texts.mapInArrow(kernel(run), _CONTEXT)


def _narrower(contexts: DataFrame, n: int, far: int, width: int) -> DataFrame:
    """Contexts cut into sub-cells of ``width`` windows at places that their group's anchor fixes.

    Two windows that are equal lie in sub-cells with equal cores (the bytes that
    all of a sub-cell's windows have), so the core's hash is the new group.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out: list[tuple] = []
            for g, doc, tag, s0, windows, part in zip(*(c.to_pylist() for c in b.columns), strict=True):
                codes = BYTE_CODES[np.frombuffer(part, np.uint8, windows + n - 1)]
                if width == 1:
                    a = e = np.arange(windows)
                    core = mix(Rolling(codes).slices(a, e + n))
                else:  # sub-cells by the anchor of a window's first bytes' gram: content alone decides
                    c = anchored_cells(codes, np.array([0, len(codes)]), n, n - width + 1)
                    a, e, core = c["s0"], c["s1"], c["key"]
                for x, y, h in zip(a.tolist(), e.tolist(), mix(core ^ mix(np.full(len(a), g, np.int64).view(U64))).view(np.int64).tolist(), strict=True):
                    out.append((h, doc, tag, s0 + x, y - x + 1, part[x : y + far]))
            columns = list(zip(*out, strict=True)) or [[]] * len(_TYPES)
            yield pa.record_batch([pa.array(x, t) for x, t in zip(columns, _TYPES, strict=True)], names=_NAMES)

    return contexts.mapInArrow(kernel(run), _CONTEXT)


def _spans(start: np.ndarray, end: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(string, start, end) of maximal spans within each string of a concatenation."""
    string = np.searchsorted(offsets, start, "right") - 1
    start, end = merge_spans(start + string, end + string)  # a gap between strings, so that none meet
    string = np.searchsorted(offsets[:-1] + np.arange(len(offsets) - 1), start, "right") - 1
    return string, start - string - offsets[string], end - string - offsets[string]


def _array_spans(contexts: DataFrame, n: int, far: int) -> DataFrame:
    """(doc, tag, span): bytes that repeat within a group, by suffix arrays over whole groups."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        size = 0

        def solve() -> pa.RecordBatch:
            doc, tag, s0, windows = (np.array([x[k] for x in held]) for k in range(1, 5))
            data = np.frombuffer(b"".join(x[5] for x in held), np.uint8)
            offsets = np.cumsum([0, *(len(x[5]) for x in held)])
            # a context none of whose windows occurs twice here needs no sorting
            window = mix(Rolling(BYTE_CODES[data]).grams(n))
            text = np.repeat(np.arange(len(held)), np.diff(offsets))[: len(window)]
            ok = np.flatnonzero(np.arange(len(window)) - offsets[text] < windows[text])
            _, back, count = np.unique(window[ok], return_inverse=True, return_counts=True)
            twice = ok[count[back] > 1]
            who, first, times = np.unique(text[twice], return_index=True, return_counts=True)
            if not len(who):
                return pa.record_batch([pa.array([], pa.int64()), pa.array([], pa.int32()), pa.array([], pa.int64())], names=["doc", "tag", "span"])
            # what the repeated windows of a context cover, from the first to the last
            lo, hi = twice[first], twice[first + times - 1]
            end = np.minimum(hi + far, offsets[who + 1])
            at = np.r_[0, np.cumsum(end - lo)]
            place, length = longest(np.concatenate([data[x:y] for x, y in zip(lo, end, strict=True)]), at, hi - lo, n)
            base = s0[who] + lo - offsets[who]
            rows, spans = [], []
            for mark, some in ((0, length >= n), (FAR, length >= far)) if far > n else ((0, length >= n),):
                c, a, e = _spans(place[some], place[some] + length[some], at)
                rows.append(who[c])
                spans.append((a + base[c]) << 32 | e + base[c] | mark)
            row = np.concatenate(rows)
            return pa.record_batch([pa.array(doc[row]), pa.array(tag[row].astype(np.int32)), pa.array(np.concatenate(spans))], names=["doc", "tag", "span"])

        last = None
        for b in batches:
            for r in zip(*(c.to_pylist() for c in b.columns), strict=True):
                if r[0] != last and size >= BATCH_BYTES:
                    yield solve()
                    held, size = [], 0
                last = r[0]
                held.append(r)
                size += len(r[5])
        if held:
            yield solve()

    # by a hash of its own: dealing by the join's key again would be optimised away, and the join may split a key's rows
    return contexts.repartition(F.xxhash64("grp")).sortWithinPartitions("grp", "doc", "s0").mapInArrow(kernel(run), "doc long, tag int, span long")


def _whole(cells: DataFrame, n: int, far: int) -> DataFrame:
    """(doc, tag, span) of cells (s0, s1, s2) that repeat whole."""
    near = packed("s0", F.col("s1").cast("long") + n)
    long = F.when(F.col("s2") - F.col("s0") >= far, packed("s0", F.col("s2").cast("long").bitwiseOR(F.lit(FAR))))
    return cells.select("doc", "tag", F.explode(F.array_compact(F.array(near, long)) if far > n else F.array(near)).alias("span"))


def partial_repeats(contexts: DataFrame, n: int, far: int, widths: tuple[int, ...] = (32, 1), group: int = GROUP) -> DataFrame:
    """(doc, tag, span) of the bytes in windows that occur in two contexts of one group."""
    found: DataFrame | None = None
    for width in widths:
        big = contexts.groupBy("grp").agg(F.count(F.lit(1)).alias("size")).where(F.col("size") > group).select("grp")
        large = bool(big.take(1))
        spans = _array_spans(contexts.join(big, "grp", "left_anti") if large else contexts, n, far)
        found = spans if found is None else found.unionByName(spans)
        if not large:
            return found
        # near copies have most of these in common, so each different one goes on once
        cut = stored(_narrower(contexts.join(big, "grp", "left_semi"), n, far, width).withColumn("print", F.xxhash64("windows", "part")))
        each = cut.groupBy("grp", "print").agg(F.count(F.lit(1)).alias("size"), F.min(F.struct("doc", "tag", "s0", "windows", "part")).alias("first"))
        # only places of sub-cells that do recur meet their count, without the bytes
        places = cut.select("grp", "print", "doc", "tag", "s0", (F.col("s0") + F.col("windows") - 1).alias("s1"), (F.col("s0") + F.octet_length("part")).alias("s2"))
        found = found.unionByName(_whole(places.join(each.where("size > 1").select("grp", "print"), ["grp", "print"], "left_semi"), n, far))
        contexts = each.select("grp", "first.*").select(*_NAMES)
    # groups are single windows now: all of one with two members repeat, and those of ``far`` bytes if two of these are equal
    twice = lambda rows: rows.groupBy("grp").agg(F.count(F.lit(1)).alias("size")).where("size > 1").select("grp")
    found = found.unionByName(contexts.join(twice(contexts), "grp", "left_semi").select("doc", "tag", packed("s0", F.col("s0").cast("long") + n).alias("span")))
    if far > n:
        whole = contexts.where(F.octet_length("part") == far).select("doc", "tag", "s0", F.xxhash64("grp", "part").alias("grp"))
        found = found.unionByName(whole.join(twice(whole), "grp", "left_semi").select("doc", "tag", packed("s0", (F.col("s0").cast("long") + far).bitwiseOR(F.lit(FAR))).alias("span")))
    return found


def remove_repeats(docs: DataFrame, n: int = 400, passage: int = 240, k: int = 80, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Removes every byte covered by an ``n``-byte string that starts at another place too.

    Gives for each row of ``docs``: doc_id, n_bytes, n_removed, n_spans and
    kept_sha256, and what repeats of ``passage`` bytes (no more than ``n``) cover:
    passage_bytes, and n_passages, their maximal runs. See ``repeat_spans`` for
    what counts.
    """

    def finish(column: pa.Array, spans: list[np.ndarray]) -> dict[str, list]:
        out: dict[str, list] = {"n_bytes": [], "n_removed": [], "n_spans": [], "kept_sha256": [], "passage_bytes": [], "n_passages": []}
        for raw, ((x, y), (a, e)) in zip(_raws(column), merged_spans(column, spans, passage, k, n), strict=True):
            edges = [0, *np.column_stack([a, e]).ravel().tolist(), len(raw)]
            kept = hashlib.sha256()
            for i, j in zip(edges[::2], edges[1::2], strict=True):
                kept.update(raw[i:j])
            for c, v in zip(out.values(), (len(raw), int((e - a).sum()), len(a), kept.hexdigest(), int((y - x).sum()), len(x)), strict=True):
                c.append(v)
        return out

    texts = identified(docs, id_col, text_col)
    return removal(texts, repeat_spans(texts, passage, k, n), finish, "n_bytes long, n_removed long, n_spans long, kept_sha256 string, passage_bytes long, n_passages long")


def repeat_spans(texts: DataFrame, n: int, k: int, far: int | None = None) -> DataFrame:
    """(doc, tag, span) of bytes repeated between texts, or partly within one.

    Spans lie in strings of ``n`` bytes that start at another place too, those
    marked ``FAR`` in strings of ``far`` bytes (at least ``n``). Windows are judged
    on the input; overlaps count; no window crosses a text's end; a null text is
    empty. Repeated rows are texts of their own, so each of them repeats the
    other. Cells that recur whole within one text are left to ``merged_spans``.
    """
    far = far or n
    shared = shared_cells(cells(texts, "byte", n, k, far))
    mixed = by_print(shared)
    whole = [_whole(x, n, far) for x in (shared.where("not mixed"), mixed.where("n > 1"))]
    asked = mixed.where("doc = first_doc").groupBy("doc", "tag").agg(F.collect_list(F.struct("key", "s0", "s1", "s2")).alias("cells"))
    contexts = stored(_contexts(texts.join(asked, ["doc", "tag"]).select("doc", "tag", "text", "cells")))
    return whole[0].unionByName(whole[1]).unionByName(partial_repeats(contexts, n, far))


def _raws(column: pa.Array) -> list[bytes]:
    return [x.encode() for x in column.to_pylist()]


def merged_spans(column: pa.Array, spans: list[np.ndarray], n: int, k: int, far: int | None = None) -> Iterator[list[tuple[np.ndarray, np.ndarray]]]:
    """Maximal spans of each text, those of repeats of ``n`` bytes and of ``far``: spans found, and cells that recur within the text."""
    far = far or n
    for i, j, codes, at, _ in symbols(column, "byte"):
        c = anchored_cells(codes, at, n, k, far)
        _, back, count = np.unique(mix(c["key"] + mix(c["text"].astype(U64) + U64(1))) ^ c["print"], return_inverse=True, return_counts=True)
        again = np.flatnonzero(count[back] > 1)
        s0, s1, s2, text = (c[x][again] for x in ("s0", "s1", "s2", "text"))
        long = (s2 - s0 >= far) & (far > n)
        own = np.concatenate([s0 << 32 | s1 + n, s0[long] << 32 | s2[long] | FAR])
        text = np.concatenate([text, text[long]])
        own = own[np.argsort(text, kind="stable")]
        cut = np.searchsorted(np.sort(text), np.arange(j - i + 1))
        for t in range(j - i):
            every = np.concatenate([spans[i + t], own[cut[t] : cut[t + 1]]]) if cut[t] < cut[t + 1] else spans[i + t]
            marked = every & FAR != 0
            near = unpack(every[~marked])
            yield [near, unpack(every[marked] ^ FAR) if far > n else near]


def cut_repeats(docs: DataFrame, n: int = 400, k: int = 128, id_col: str = "doc_id", text_col: str = "text", chars_col: str = "n_chars") -> DataFrame:
    """``docs``, all rows and columns, without the characters that lie wholly in a repeat of ``n`` bytes.

    A character that is only partly in a repeat stays; ``chars_col``, if there,
    is the new number of characters; null texts stay null. Repeated rows are
    texts of their own, so each repeats the other; a null id counts as the
    smallest; an empty table stays empty.
    """
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    key = identified(docs, id_col, text_col)
    doc_, tag_, spans_ = free_names(docs, "doc", "tag", "spans")
    tagged = docs.withColumns({doc_: F.coalesce(F.col(id_col).cast("long"), F.lit(NULL_ID)), tag_: F.hash(text)})
    spans = by_document(repeat_spans(key, n, k)).select(F.col("doc").alias(doc_), F.col("tag").alias(tag_), F.col("spans").alias(spans_))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            names = b.schema.names
            at = names.index(text_col)
            column = b.column(at)
            lo, hi, values = list_parts(b.column(len(names) - 1))
            values = values.to_numpy(zero_copy_only=False)
            filled = column.fill_null("")
            texts: list[str | None] = []
            for raw, there, ((a, e), _) in zip(_raws(filled), column.is_valid().to_pylist(), merged_spans(filled, [values[x:y] for x, y in zip(lo, hi, strict=True)], n, k), strict=True):
                out, last = [], 0
                for x, y in zip(a.tolist(), e.tolist(), strict=True):
                    while x < y and raw[x] & 0xC0 == 0x80:  # inside a character
                        x += 1
                    while y > x and y < len(raw) and raw[y] & 0xC0 == 0x80:
                        y -= 1
                    out.append(raw[last:x])
                    last = y
                texts.append((b"".join(out) + raw[last:]).decode() if there else None)
            columns = dict(zip(names[:-1], b.columns, strict=False))
            columns[text_col] = pa.array(texts, column.type)
            if chars_col in columns:
                columns[chars_col] = pa.array([None if t is None else len(t) for t in texts], pa.int64()).cast(columns[chars_col].type)
            yield pa.record_batch(list(columns.values()), names=list(columns))

    return tagged.join(spans, [doc_, tag_], "left").select(*docs.columns, spans_).mapInArrow(kernel(run), docs.schema)
