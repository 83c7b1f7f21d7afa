"""Near-duplicate texts: a Jaccard self-join of shingle sets by chosen paths.

A text's set holds its runs of five words. Sets are split over and over: a run
starts with all sets in one bucket, and in each step a bucket's sets go apart by
sampled tokens, the one that a random order puts first in each (in the first
step those of two orders); two sets stay together with the probability of their
Jaccard similarity for each. In some steps (``FORKS``) a set follows the tokens
of two orders apart from each other, so that its path branches and what one
branch loses the other may keep. Buckets of ``BUCKET`` sets or fewer are compared
pair by pair by their sketches; larger ones are split further. Sets that still
share a large bucket after all steps have all those sampled tokens in common and
are one candidate group. Every split of every run has orders of its own, so runs
are independent, and they are repeated (``RUNS``) until a pair at the threshold
is found with a probability of ``RECALL``, even if its buckets stay large through
all steps.

Pairs that met, however many there are, only join sets into candidate groups;
within these every pair is compared exactly, blocks of sets against blocks, so
a large group is spread over tasks and no list of pairs exists. Copies (equal
sets) are one set with a count.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .graph import components
from .stored import stored
from .textkit import U64, Rolling, blocks, lower_ascii, mix, utf8, word_codes, words
from .windows import NULL_ID, free_names, identified
from .workers import kernel

SHINGLE, THRESHOLD = 5, (4, 5)
#: what a pair at the threshold is found with at least, and sets compared pair by pair
RECALL, BUCKET = 0.9999, 512
#: for each split: branches that a path goes on by, and orders whose tokens a branch looks at
FORKS, LOOKS = (1, 2, 1, 2), (2, 1, 1, 1)


def meet(similarity: float, steps: int = len(FORKS)) -> float:
    """Probability that one run brings a pair together, if its buckets take ``steps`` splits."""
    p = 1.0
    for fork, looks in reversed(list(zip(FORKS, LOOKS, strict=True))[:steps]):
        p = 1 - (1 - similarity**looks * p) ** fork
    return p


def runs_for(recall: float, similarity: float) -> int:
    """Runs after which a pair is found with a probability of ``recall``, whatever splits it takes."""
    return math.ceil(math.log(1 - recall) / math.log(1 - meet(similarity)))


RUNS = runs_for(RECALL, THRESHOLD[0] / THRESHOLD[1])
#: orders of a run, and of them those before each step's
_ENDS = np.cumsum(np.cumprod(FORKS) * LOOKS).tolist()
RUN_ORDERS, BEFORE = _ENDS[-1], [0, *_ENDS[:-1]]
#: orders, one for each look of each branch of each split of each run, and bytes kept of a token
ORDERS, TOKEN_BYTES = RUNS * RUN_ORDERS, 3
#: bytes of a sketch; sketches that agree in fewer than ``ALIKE`` can't be at the threshold (five standard errors)
SLOTS = 60
ALIKE = math.floor(SLOTS * 0.8 - 5 * math.sqrt(SLOTS * 0.8 * 0.2))
#: sets, and shingles of all sets, in one block of the exact comparison, and blocks that a task holds
BLOCK_SETS, BLOCK_SHINGLES, HELD_BLOCKS = 1024, 1 << 19, 4
#: sets of several small groups compared at once
TOGETHER = 256


_ORDERS = mix(np.arange(1, ORDERS + 1, dtype=U64) * U64(0xD1342543DE82EF95)) | U64(1)


def order_of(run, step: int, branch, look: int = 0):
    """The order that a branch looks at in a split; no other has it."""
    return run * RUN_ORDERS + BEFORE[step] + branch * LOOKS[step] + look


def shingles(data: np.ndarray, offsets: np.ndarray, n: int = SHINGLE) -> tuple[np.ndarray, np.ndarray]:
    """(hashes, bounds): each text's different runs of ``n`` words, sorted; a shorter text is one run.

    Words are runs of bytes other than white space, A-Z in lower case.
    """
    data = lower_ascii(data)
    start, end, at = words(data, offsets)
    count = np.diff(at)
    rolling = Rolling(word_codes(data, start, end))
    gram = rolling.grams(n)
    text = np.repeat(np.arange(len(count)), count)
    ok = np.flatnonzero(np.arange(len(gram)) + n <= at[1:][text[: len(gram)]])
    short = np.flatnonzero((count > 0) & (count < n))
    value = np.concatenate([mix(gram[ok]), mix(rolling.slices(at[short], at[short + 1]) + count[short].astype(U64))])
    owner = np.concatenate([text[ok], short])
    order = np.lexsort((value, owner))
    value, owner = value[order], owner[order]
    fresh = np.r_[True, (value[1:] != value[:-1]) | (owner[1:] != owner[:-1])] if len(value) else np.zeros(0, bool)
    value, owner = value[fresh], owner[fresh]
    return value, np.searchsorted(owner, np.arange(len(count) + 1))


def _sets_of(column: pa.Array) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    data, at = utf8(column)
    for i, j in blocks(at):
        yield i, j, *shingles(data[at[i] : at[j]], at[i : j + 1] - at[i])


def shingle_sets(texts: DataFrame) -> DataFrame:
    """(doc, tag, node, size, tokens, sketch) of every text.

    ``node`` is a 64-bit hash of the set, ``tokens`` the low bytes of the least
    hash in each of ``ORDERS`` orders, ``sketch`` a byte of the first ``SLOTS``. A
    text without words has a null node.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i, j, value, bounds in _sets_of(b.column(2)):
                size = np.diff(bounds)
                full = np.flatnonzero(size)
                first = bounds[:-1][full]
                node, token = np.zeros(len(size), np.int64), np.zeros((len(size), ORDERS), "<u4")
                if len(full):
                    node[full] = mix(np.add.reduceat(mix(value ^ U64(0x2545F4914F6CDD1D)), first) + size[full].astype(U64)).view(np.int64)
                    for s in range(ORDERS):
                        token[full, s] = np.minimum.reduceat((value * _ORDERS[s]) >> U64(32), first)
                sketch = (mix(token[:, :SLOTS].astype(U64)) & U64(255)).astype(np.uint8)
                low = token.view(np.uint8).reshape(len(size), ORDERS, 4)[:, :, :TOKEN_BYTES]
                part = slice(i, j)
                yield pa.record_batch(
                    [b.column(0)[part], b.column(1)[part], pa.array(node, mask=size == 0), pa.array(size.astype(np.int32)), pa.array([r.tobytes() for r in low], pa.binary()), pa.array([r.tobytes() for r in sketch], pa.binary())],
                    names=["doc", "tag", "node", "size", "tokens", "sketch"],
                )

    return texts.mapInArrow(kernel(run), "doc long, tag int, node long, size int, tokens binary, sketch binary")


def _split(rows: DataFrame, step: int) -> DataFrame:
    """(key, run, branch, node): rows with run, branch, key and tokens, by the tokens that their branches look at next."""
    fork = FORKS[step]
    rows = rows.withColumn("branch", F.explode(F.sequence(F.col("branch") * fork, F.col("branch") * fork + (fork - 1)))) if fork > 1 else rows
    order = [order_of(F.col("run"), step, F.col("branch"), look) for look in range(LOOKS[step])]
    tokens = [F.substring("tokens", o * TOKEN_BYTES + 1, F.lit(TOKEN_BYTES)) for o in order]
    return rows.select(F.xxhash64("key", order[0], *tokens).alias("key"), "run", "branch", "node")


def labels(alike: np.ndarray) -> np.ndarray:
    """For each member of a symmetric matrix the least one of its connected component."""
    label = np.full(len(alike), -1)
    for k in range(len(alike)):
        if label[k] < 0:
            new = np.zeros(len(alike), bool)
            new[k] = True
            while new.any():
                label[new] = k
                new = alike[new].any(axis=0) & (label < 0)
    return label


def side_labels(linked: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For each row and column of a matrix the first row of its connected component; -1 without any link."""
    left, right = (np.full(n, -1) for n in linked.shape)
    for k in np.flatnonzero(linked.any(axis=1)).tolist():
        if left[k] < 0:
            new = np.zeros(len(left), bool)
            new[k] = True
            while new.any():
                left[new] = k
                reached = linked[new].any(axis=0) & (right < 0)
                right[reached] = k
                new = linked[:, reached].any(axis=1) & (left < 0)
    return left, right


def _bucket_links(members: DataFrame) -> DataFrame:
    """(a, b): links that join the alike sets of each small bucket; from (key, node, sketch)."""

    def solve(node: list[int], sketch: list[bytes]) -> Iterator[tuple[int, int]]:
        rows = np.frombuffer(b"".join(sketch), np.uint8).reshape(len(node), -1)
        alike = [(rows[k : k + 64, None, :] == rows[None, :, :]).sum(axis=2, dtype=np.uint8) >= ALIKE for k in range(0, len(rows), 64)]
        label = labels(np.concatenate(alike))
        return ((node[i], node[k]) for i, k in enumerate(label.tolist()) if i != k)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        node: list[int] = []
        sketch: list[bytes] = []
        last = None
        for b in (*batches, None):
            out: list[tuple[int, int]] = []
            for key, n, s in zip(*(c.to_pylist() for c in b.columns), strict=True) if b is not None else [(None, 0, b"")]:
                if key != last or b is None:
                    if len(node) > 1:
                        out += solve(node, sketch)
                    node, sketch, last = [], [], key
                node.append(n)
                sketch.append(s)
            a, c = zip(*out, strict=True) if out else ((), ())
            yield pa.record_batch([pa.array(a, pa.int64()), pa.array(c, pa.int64())], names=["a", "b"])

    return members.repartition("key").sortWithinPartitions("key", "node").mapInArrow(kernel(run), "a long, b long")


def candidates(nodes: DataFrame) -> DataFrame:
    """(a, b): links that join all sets that met in some run and look alike; from (node, tokens, sketch)."""
    whole = nodes.select("node", "tokens", F.explode(F.sequence(F.lit(0), F.lit(RUNS - 1))).alias("run"), F.lit(0).alias("branch"), F.lit(0).cast("long").alias("key"))
    rows, many = _split(whole, 0), RUNS * nodes.count()
    found: list[DataFrame] = []
    for step in range(1, len(FORKS) + 1):
        met = stored(rows.join(rows.groupBy("key").agg(F.count(F.lit(1)).alias("n"), F.min("node").alias("least")).where("n > 1"), "key"), many)
        small = met.where(F.col("n") <= BUCKET).select("key", "node")
        found.append(_bucket_links(small.join(nodes.select("node", "sketch"), "node").select("key", "node", "sketch")))
        large = met.where(F.col("n") > BUCKET)
        if not large.take(1):
            break
        if step == len(FORKS):
            # all those sampled tokens in common: one candidate group, which is compared exactly later on
            found.append(large.where("node != least").select(F.col("node").alias("a"), F.col("least").alias("b")))
        else:
            rows = _split(large.select("key", "run", "branch", "node").join(nodes.select("node", "tokens"), "node"), step)
    out = found[0]
    for more in found[1:]:
        out = out.unionByName(more)
    return out


def intersections(value: np.ndarray, bounds: np.ndarray, left: np.ndarray, right: np.ndarray) -> np.ndarray:
    """Sizes of the intersections of sets ``left`` with sets ``right`` (both sorted places)."""
    n = len(bounds) - 1
    owner = np.repeat(np.arange(n), np.diff(bounds))
    order = np.argsort(value, kind="stable")
    token, owner = value[order], owner[order]
    first = np.flatnonzero(np.r_[True, token[1:] != token[:-1]]) if len(token) else np.zeros(0, np.int64)
    size = np.diff(np.r_[first, len(token)])
    row, col = np.full(n, -1), np.full(n, -1)
    row[left], col[right] = np.arange(len(left)), np.arange(len(right))
    out = np.zeros((len(left), len(right)))
    # tokens of few sets: their pairs, by distance in the sorted list
    few = np.repeat((size > 1) & (size <= 8), size)
    end = np.repeat(first + size, size)
    place = np.arange(len(token))
    for d in range(1, 8):
        at = np.flatnonzero(few & (place + d < end))
        for x, y in ((owner[at], owner[at + d]), (owner[at + d], owner[at])):
            ok = (row[x] >= 0) & (col[y] >= 0)
            out += np.bincount(row[x[ok]] * len(right) + col[y[ok]], minlength=out.size).reshape(out.shape)
        if not len(at):
            break
    # tokens of many: products of 0/1 matrices, some columns at a time
    many = np.flatnonzero(size > 8)
    width = max(64, (1 << 22) // max(n, 1))
    for k in range(0, len(many), width):
        part = many[k : k + width]
        at = np.repeat(first[part], size[part]) + np.arange(size[part].sum()) - np.repeat(np.cumsum(size[part]) - size[part], size[part])
        table = np.zeros((n, len(part)), np.float32)
        table[owner[at], np.repeat(np.arange(len(part)), size[part])] = 1
        out += table[left] @ table[right].T
    return out


def compared(value: np.ndarray, size: np.ndarray, left: np.ndarray, right: np.ndarray) -> np.ndarray:
    """Which sets ``left`` reach the threshold with which sets ``right``, themselves left out."""
    num, den = THRESHOLD
    shared = intersections(value, np.r_[0, np.cumsum(size)], left, right)
    # shared / (a + b - shared) >= num / den
    return ((num + den) * shared >= num * (size[left][:, None] + size[right][None, :])) & (left[:, None] != right[None, :])


class Block:
    """Sets of a candidate group, each known by its node."""

    def __init__(self, rows: list[tuple[int, int, bytes]], apart: list[int] | None = None):
        # shingles of other groups never meet: ``apart`` has each set's group
        parts = [np.frombuffer(r[2], U64) for r in rows]
        self.node, self.mult = (np.array([r[k] for r in rows], np.int64) for k in range(2))
        self.size = np.array([len(x) for x in parts])
        self.value = np.concatenate(parts)
        if apart is not None:
            self.value = self.value ^ np.repeat(mix(np.array(apart, np.int64).view(U64)), self.size)

    def links(self, other: Block) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """(node, documents at the threshold in the other block, a node of the same class) of the sets that have any, of both blocks."""
        n = len(self.node)
        if other is self:
            linked = compared(self.value, self.size, np.arange(n), np.arange(n))
            label = labels(linked)
            yield from self._found(linked, other.mult, self.node[label])
            return
        linked = compared(np.concatenate([self.value, other.value]), np.r_[self.size, other.size], np.arange(n), n + np.arange(len(other.node)))
        left, right = side_labels(linked)
        yield from self._found(linked, other.mult, self.node[left])
        yield from other._found(linked.T, self.mult, self.node[right])

    def _found(self, linked: np.ndarray, mult: np.ndarray, to: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        some = np.flatnonzero(linked.any(axis=1))
        if len(some):
            yield self.node[some], np.concatenate([np.where(linked[some[k : k + 64]], mult, 0).sum(axis=1) for k in range(0, len(some), 64)]), to[some]


def _verified(members: DataFrame) -> DataFrame:
    """(node, links, to): documents at the threshold, and a set of the same class; from (root, stripe, block, node, mult, shingles).

    A stripe has ``HELD_BLOCKS`` blocks, which a task holds, and meets them and
    all later ones of its group one after another.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[Block] = []
        rows: list[tuple[int, int, bytes]] = []
        groups: list[int] = []
        last: tuple | None = None
        shingles = 0

        def close() -> Iterator[tuple]:
            """The open block is complete."""
            nonlocal rows, groups, shingles
            if rows:
                alone = last[1] is None
                block = Block(rows, groups if alone else None)
                rows, groups, shingles = [], [], 0
                for other in held:
                    yield from other.links(block)
                yield from block.links(block) if alone or last[2] // HELD_BLOCKS == last[1] else ()
                if not alone and last[2] // HELD_BLOCKS == last[1]:
                    held.append(block)

        for b in (*batches, None):
            out: list[tuple] = [(np.zeros(0, np.int64),) * 3]
            for root, stripe, block, node, mult, raw in zip(*(c.to_pylist() for c in b.columns), strict=True) if b is not None else [(None, 0, 0, 0, 0, b"")]:
                here = (root, stripe, block)
                # groups of a single block share one, each whole
                if here != last and (b is None or stripe is not None or last is not None and last[1] is not None or len(rows) >= TOGETHER or shingles >= BLOCK_SHINGLES):
                    out += close()
                    if last is None or last[:2] != here[:2]:
                        held.clear()
                if here == last and rows and rows[-1][0] == node:
                    continue  # rows that share id and text
                last = here
                rows.append((node, mult, raw))
                groups.append(root)
                shingles += len(raw) // 8
            node_, links, to = (np.concatenate(x) for x in zip(*out, strict=True))
            yield pa.record_batch([pa.array(node_), pa.array(links), pa.array(to)], names=["node", "links", "to"])

    dealt = members.repartition("root", "stripe").sortWithinPartitions("root", "stripe", "block", "node")
    return dealt.mapInArrow(kernel(run), "node long, links long, to long")


def _shingled(texts: DataFrame) -> DataFrame:
    """(doc, tag, shingles): each text's set as sorted 64-bit hashes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i, j, value, bounds in _sets_of(b.column(2)):
                raw = value.tobytes()
                at = (8 * bounds).tolist()
                yield pa.record_batch([b.column(0)[i:j], b.column(1)[i:j], pa.array([raw[x:y] for x, y in zip(at[:-1], at[1:], strict=True)], pa.binary())], names=["doc", "tag", "shingles"])

    return texts.select("doc", "tag", "text").mapInArrow(kernel(run), "doc long, tag int, shingles binary")


def classes(texts: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Every text's class: ((doc, tag, node) of all texts, (node, root, links, mult, copy) of all sets).

    Sets of one class are linked by steps of similarity at or above the threshold;
    ``links`` counts the documents whose sets differ and reach it, ``mult`` those
    with the set itself.
    """
    all_sets = stored(shingle_sets(texts))
    worded = all_sets.where("node is not null")
    own = stored(worded.groupBy("node").agg(F.count(F.lit(1)).alias("mult"), F.min(F.struct("doc", "tag")).alias("first"), F.first("size").alias("size")))
    nodes = stored(worded.select("node", "tokens", "sketch").dropDuplicates(["node"]))
    group = components(candidates(nodes))
    sized = group.join(own, "node")
    shape = sized.groupBy("root").agg(F.greatest(F.ceil(F.count(F.lit(1)) / BLOCK_SETS), F.ceil(F.sum("size") / BLOCK_SHINGLES)).cast("int").alias("blocks"), F.count(F.lit(1)).alias("n")).where("n > 1")
    placed = sized.join(shape, "root").select("node", "root", "blocks", "mult", F.col("first.doc").alias("doc"), F.col("first.tag").alias("tag"), F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int").alias("block"))
    shingled = stored(_shingled(texts.join(placed.select("doc", "tag"), ["doc", "tag"], "left_semi")))
    stripes = F.when(F.col("blocks") > 1, F.sequence(F.lit(0), F.floor(F.col("block") / HELD_BLOCKS).cast("int"))).otherwise(F.array(F.lit(None).cast("int")))
    members = placed.join(shingled, ["doc", "tag"]).select("root", F.explode(stripes).alias("stripe"), "block", "node", "mult", "shingles")
    found = stored(_verified(members))
    linked = components(found.where("node != to").select(F.col("node").alias("a"), F.col("to").alias("b")))
    links = found.groupBy("node").agg(F.sum("links").alias("links"))
    sets = own.join(linked, "node", "left").join(links, "node", "left").select("node", F.coalesce("root", "node").alias("root"), F.coalesce("links", F.lit(0)).alias("links"), "mult", "first")
    return all_sets.select("doc", "tag", "node"), stored(sets)


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, class_id, copy_id, n_links) of every row of ``docs``.

    Two texts are linked if the Jaccard similarity of their sets of runs of five
    words (A-Z in lower case; a shorter text is one run) is 0.8 or more.
    ``n_links`` counts the other rows linked to the row, copies included;
    ``class_id`` is the least id of all that links lead to, ``copy_id`` of those
    with the same set. Texts without words, null ones too, have no links and
    their own id. Repeated rows are copies; a null id counts as the smallest
    and is returned as null; other columns are ignored.
    """
    rows, sets = classes(identified(docs, id_col, text_col))
    least = sets.groupBy("root").agg(F.min("first.doc").alias("class_id"))
    known = sets.join(least, "root").select("node", "class_id", F.col("first.doc").alias("copy_id"), (F.col("links") + F.col("mult") - 1).alias("n_links"))
    out = rows.join(known, "node", "left")
    shown = lambda c: F.when(F.col(c) != NULL_ID, F.col(c)).alias(c)
    return out.select(F.col("doc").alias("doc_id"), F.coalesce("class_id", "doc").alias("class_id"), F.coalesce("copy_id", "doc").alias("copy_id"), F.coalesce("n_links", F.lit(0)).alias("n_links")).select(shown("doc_id"), shown("class_id"), shown("copy_id"), "n_links")


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows of ``docs``, all columns: of each class the text of least id, once; all texts without words.

    Classes as in ``near_duplicates``. Null texts and texts without words have no
    class and all stay, repeated rows too; a null id counts as the smallest; an
    empty table stays empty.
    """
    key = identified(docs, id_col, text_col)
    _, sets = classes(key)
    doc, tag, some = free_names(docs, "doc", "tag", "some")
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    first = sets.groupBy("root").agg(F.min("first").alias("f")).select(F.col("f.doc").alias(doc), F.col("f.tag").alias(tag))
    tagged = docs.withColumns({doc: F.coalesce(F.col(id_col).cast("long"), F.lit(NULL_ID)), tag: F.hash(text), some: F.length(F.regexp_replace(text, r"[\x09-\x0D ]+", "")) > 0})
    kept = tagged.where(some).join(first, [doc, tag], "left_semi").dropDuplicates([doc, tag])
    return kept.unionByName(tagged.where(~F.col(some))).select(*docs.columns)
