"""Repeated fixed-length windows over a whole corpus, without shuffling them all.

A window's *anchor* is its k-gram of smallest hash; neighbouring windows with
one anchor make a cell (``textkit.anchored_cells``). Equal windows have equal
anchor keys, so a window whose anchor key occurs once cannot repeat, and cells
that agree in key and print hold the same windows throughout. So Spark counts
about one row for each (n - k) / 2 windows; single windows are looked at only
in one representative of each different cell that shares its key with another.
Counts are partial before they are shuffled, and occurrences meet them in
sort-merge joins whose hot partitions can be split.

A document is known by (id, tag): ``tag`` is a hash of its text, so that rows
that share an id but not a text stay apart. A null id counts as the smallest.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .stored import stored
from .textkit import BYTE_CODES, U64, Rolling, anchored_cells, blocks, merge_spans, mix, utf8, word_codes, words
from .workers import kernel

NULL_ID = -(1 << 63)


def identified(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(doc, tag, text), with neither null."""
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    return docs.select(F.coalesce(F.col(id_col).cast("long"), F.lit(NULL_ID)).alias("doc"), F.hash(text).alias("tag"), text.alias("text"))


def free_names(df: DataFrame, *wanted: str) -> list[str]:
    """``wanted`` with as many underscores before them as it takes not to be the name of a column, in any case."""
    taken = {c.lower() for c in df.columns}
    out = []
    for name in wanted:
        while name.lower() in taken:
            name = f"_{name}"
        taken.add(name.lower())
        out.append(name)
    return out


def symbols(batch_text: pa.Array, unit: str) -> Iterator[tuple[int, int, np.ndarray, np.ndarray, tuple]]:
    """Blocks of a text column: (first text, past the last, codes, offsets, places)."""
    data, offsets = utf8(batch_text)
    for i, j in blocks(offsets):
        part, at = data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i]
        if unit == "byte":
            yield i, j, BYTE_CODES[part], at, (part, at, None, None)
        else:
            start, end, at_word = words(part, at)
            yield i, j, word_codes(part, start, end), at_word, (part, at, start, end)


def cells(identified_docs: DataFrame, unit: str, n: int, k: int, far: int | None = None) -> DataFrame:
    """(doc, tag, key, print, s0, s1), and s2 if ``far`` is given: each different cell of each text, at its first place."""
    places = ["s0", "s1", "s2"] if far else ["s0", "s1"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            doc, tag = b.column(0).to_numpy(), b.column(1).to_numpy()
            for i, _, codes, at, _ in symbols(b.column(2), unit):
                c = anchored_cells(codes, at, n, k, far)
                row = c["text"] + i
                # rows are in text order: the first of equal ones has the smallest start
                _, first = np.unique(mix(c["key"] + mix(row.astype(U64) + U64(1))) ^ c["print"], return_index=True)
                first.sort()
                yield pa.record_batch(
                    [pa.array(doc[row[first]]), pa.array(tag[row[first]]), pa.array(c["key"][first].view(np.int64)), pa.array(c["print"][first].view(np.int64)), *(pa.array(c[x][first].astype(np.int32)) for x in places)],
                    names=["doc", "tag", "key", "print", *places],
                )

    return identified_docs.mapInArrow(kernel(run), "doc long, tag int, key long, print long, " + ", ".join(f"{x} int" for x in places))


def shared_cells(found: DataFrame) -> DataFrame:
    """Cells whose key occurs in others too, stored: found's columns and

    ``mixed`` (cells of different print have the key) and ``first_doc``, the
    smallest document with the key.
    """
    by_key = found.groupBy("key").agg(F.count(F.lit(1)).alias("n"), F.min("print").alias("lo"), F.max("print").alias("hi"), F.min("doc").alias("first_doc"))
    return stored(found.join(by_key.where("n > 1").select("key", (F.col("lo") != F.col("hi")).alias("mixed"), "first_doc"), "key"))


def by_print(shared: DataFrame) -> DataFrame:
    """Mixed cells with ``first_doc`` now the smallest document with the same key and print, and ``n`` such cells."""
    mixed = shared.where("mixed").drop("first_doc", "mixed")
    return mixed.join(mixed.groupBy("key", "print").agg(F.min("doc").alias("first_doc"), F.count(F.lit(1)).alias("n")), ["key", "print"])


def packed(start, end):
    """A span as one long."""
    return F.shiftleft(F.col(start).cast("long") if isinstance(start, str) else start, 32).bitwiseOR(end)


def by_document(spans: DataFrame) -> DataFrame:
    return spans.groupBy("doc", "tag").agg(F.collect_list("span").alias("spans"))


def list_parts(column: pa.ListArray) -> tuple[np.ndarray, np.ndarray, pa.Array]:
    """(starts, ends, values) of a list column; null is empty."""
    offsets = column.offsets.to_numpy().astype(np.int64)
    base = int(offsets[0]) if len(offsets) else 0
    offsets = offsets - base
    start, end = offsets[:-1].copy(), offsets[1:].copy()
    if column.null_count:
        end = np.where(column.is_null().to_numpy(zero_copy_only=False), start, end)
    return start, end, column.values.slice(base, int(offsets[-1]) if len(offsets) else 0)


def removal(texts: DataFrame, spans: DataFrame, finish: Callable[[pa.Array, list[np.ndarray]], dict[str, list]], schema: str) -> DataFrame:
    """Gives ``finish`` each text with its packed spans; columns as it returns them, after doc_id."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            start, end, values = list_parts(b.column(2))
            values = values.to_numpy(zero_copy_only=False)
            doc = b.column(0).to_numpy()
            out = finish(b.column(1), [values[x:y] for x, y in zip(start, end, strict=True)])
            yield pa.record_batch([pa.array(doc, mask=doc == NULL_ID), *map(pa.array, out.values())], names=["doc_id", *out])

    return texts.join(by_document(spans), ["doc", "tag"], "left").select("doc", "text", "spans").mapInArrow(kernel(run), f"doc_id long, {schema}")


def unpack(spans: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    return merge_spans(spans >> 32, spans & 0xFFFFFFFF)


# word windows ---------------------------------------------------------------


def _window_rows(texts: DataFrame, n: int) -> DataFrame:
    """(key, window, doc, tag, s) of the windows in each text's listed cells, the first of equals in a text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            doc, tag = b.column(0).to_numpy(), b.column(1).to_numpy()
            lo, hi, values = list_parts(b.column(3))
            key, s0, s1 = (values.field(x).to_numpy(zero_copy_only=False) for x in range(3))
            for i, j, codes, at, _ in symbols(b.column(2), "word"):
                row = np.repeat(np.arange(i, j), hi[i:j] - lo[i:j])
                cell = slice(lo[i], hi[j - 1]) if len(row) else slice(0, 0)
                width = (s1[cell] - s0[cell] + 1).astype(np.int64)
                at_row = np.repeat(row, width)
                s = np.repeat(s0[cell].astype(np.int64), width) + np.arange(width.sum()) - np.repeat(np.cumsum(width) - width, width)
                if not len(s):
                    continue
                g = s + at[at_row - i]
                window = mix(Rolling(codes).slices(g, g + n))
                k = np.repeat(key[cell], width)
                order = np.lexsort((s, window, k, at_row))
                same = np.zeros(len(s), bool)
                o = order
                same[o[1:]] = (window[o[1:]] == window[o[:-1]]) & (k[o[1:]] == k[o[:-1]]) & (at_row[o[1:]] == at_row[o[:-1]])
                f = np.flatnonzero(~same)
                yield pa.record_batch([pa.array(k[f]), pa.array(window[f].view(np.int64)), pa.array(doc[at_row[f]]), pa.array(tag[at_row[f]]), pa.array(s[f].astype(np.int32))], names=["key", "window", "doc", "tag", "s"])

    return texts.mapInArrow(kernel(run), "key long, window long, doc long, tag int, s int")


def repeated_word_windows(docs: DataFrame, n: int = 20, k: int = 6, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Removes every word in a window of ``n`` words that starts earlier too.

    Earlier is a smaller id, or the same text further left. Gives for each row
    of ``docs``: doc_id, n_words, n_removed, n_spans, kept_sha256 (kept words
    joined by one space). A null text has no words; rows that share an id are
    versions of one document, so repeats between them stay; a null id counts as
    the smallest and is returned as null; a text under ``n`` words loses none.
    """
    texts = identified(docs, id_col, text_col)
    found = cells(texts, "word", n, k)
    shared = shared_cells(found)
    mixed = by_print(shared)
    span = packed("s0", F.col("s1").cast("long") + n).alias("span")
    whole = [x.where("doc != first_doc").select("doc", "tag", span) for x in (shared.where("not mixed"), mixed)]
    # a first occurrence may hold windows that a different, earlier cell holds too
    asked = mixed.where("doc = first_doc").groupBy("doc", "tag").agg(F.collect_list(F.struct("key", "s0", "s1")).alias("cells"))
    rows = _window_rows(texts.join(asked, ["doc", "tag"]).select("doc", "tag", "text", "cells"), n)
    first = rows.groupBy("key", "window").agg(F.min("doc").alias("first_doc"), F.max("doc").alias("last_doc")).where("first_doc != last_doc").drop("last_doc")
    single = rows.join(first, ["key", "window"]).where("doc != first_doc").select("doc", "tag", packed("s", F.col("s").cast("long") + n).alias("span"))

    def finish(column: pa.Array, spans: list[np.ndarray]) -> dict[str, list]:
        out: dict[str, list] = {"n_words": [], "n_removed": [], "n_spans": [], "kept_sha256": []}
        for i, j, codes, at, (part, _, start, end) in symbols(column, "word"):
            raw = part.tobytes()
            window = Rolling(codes).grams(n)
            text = np.repeat(np.arange(j - i), np.diff(at))[: len(window)]
            inside = np.flatnonzero(np.arange(len(window)) + n <= at[1:][text])
            _, seen, back = np.unique(mix(window[inside] ^ mix(text[inside].astype(U64))), return_index=True, return_inverse=True)
            again = inside[np.arange(len(inside)) != seen[back]]
            cut = np.searchsorted(again, at)
            for t in range(j - i):
                own = again[cut[t] : cut[t + 1]] - at[t]
                a, e = unpack(np.concatenate([spans[i + t], own << 32 | own + n]) if len(own) else spans[i + t])
                m = int(at[t + 1] - at[t])
                keep = np.ones(m, bool)
                for x, y in zip(a, e, strict=True):
                    keep[x:y] = False
                w = at[t] + np.flatnonzero(keep)
                kept = b" ".join([raw[x:y] for x, y in zip(start[w].tolist(), end[w].tolist(), strict=True)])
                for column_, value in zip(out.values(), (m, m - len(w), len(a), hashlib.sha256(kept).hexdigest()), strict=True):
                    column_.append(value)
        return out

    return removal(texts, whole[0].unionByName(whole[1]).unionByName(single), finish, "n_words long, n_removed long, n_spans long, kept_sha256 string")
