"""Context-tree weighting over bytes: code lengths of texts under a corpus.

A byte is eight binary choices, each a node of a decision tree of its own. For
every choice and every context (the last 0, 1, .. ``DEPTH`` bytes) the corpus
has counts of zeros and ones, and the Krichevsky-Trofimov estimate tells how
well that context alone predicts them. A context's weighted probability is the
mean of its own estimate and the product of its one-byte-longer contexts'; the
weights that follow mix the estimates of all depths for the next bit.

Counts are the corpus's (context, byte) strings, summed by Spark. Strings that
share their last two context bytes form whole subtrees, which tasks weigh apart
from each other; only the two shallowest levels, of at most 256 contexts of 255
choices, pass the driver. Where two such bytes are so common that their subtree
would outgrow a task (at most ``SPLIT`` pairs, by a sample), it is dealt out by
the third byte, and the pair's own 255 choices pass the driver too. Texts are scored in chunks: a chunk asks for the
strings and words that it has and no more, so no table is sent everywhere.
"""

from __future__ import annotations

import itertools
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .stored import stored
from .textkit import U64, blocks, lower_ascii, mix, utf8, word_codes, words

DEPTH = 6
#: bytes of text scored together
CHUNK_BYTES = 24 << 20
#: pairs of bytes whose subtrees are dealt out at most, and bytes of text that show how common pairs are
SPLIT, SAMPLE_BYTES = 1024, 32 << 20
END, SPACE = 0x0A, 0x20
GRAM, WORD = 0, 1
#: what travels as the answer for a key: a byte's log10 probability, a word's count
KIND = {GRAM: np.float32, WORD: np.int64}
#: the key of the end token among words
END_WORD = 0


def log_gamma(x: np.ndarray) -> np.ndarray:
    """log of gamma for x > 0, to about 1e-12."""
    x = np.asarray(x, float)
    shift = np.ones_like(x)
    y = x.copy()
    for _ in range(8):
        low = y < 8
        shift = np.where(low, shift * y, shift)
        y = np.where(low, y + 1, y)
    z = 1 / (y * y)
    tail = (1 / 12 - z * (1 / 360 - z * (1 / 1260 - z * (1 / 1680 - z / 1188)))) / y
    return (y - 0.5) * np.log(y) - y + 0.5 * np.log(2 * np.pi) + tail - np.log(shift)


def log_estimate(zeros: np.ndarray, ones: np.ndarray) -> np.ndarray:
    """log of the Krichevsky-Trofimov probability of a sequence with these counts."""
    return log_gamma(zeros + 0.5) + log_gamma(ones + 0.5) - log_gamma(zeros + ones + 1) - np.log(np.pi)


def weigh(zeros: np.ndarray, ones: np.ndarray, deeper: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(log weighted probability, weight of the own estimate) given the log product of the longer contexts'."""
    own = log_estimate(zeros, ones)
    return np.logaddexp(own, deeper) - np.log(2), 1 / (1 + np.exp(np.clip(deeper - own, -700, 700)))


def next_bit(zeros: np.ndarray, ones: np.ndarray, bit: np.ndarray) -> np.ndarray:
    return (np.where(bit == 1, ones, zeros) + 0.5) / (zeros + ones + 1)


class Subtree:
    """All contexts of ``least`` bytes and more of some keys.

    A key is a context, nearest byte first, and the next byte last, as one
    number of ``depth`` + 1 bytes. ``counts`` may be 0 for keys only asked for.
    """

    def __init__(self, keys: np.ndarray, counts: np.ndarray, depth: int = DEPTH, least: int = 2):
        byte = (keys & U64(255)).astype(np.int64)
        # probability of each key's eight bits under contexts of ``least`` bytes and more
        self.chance = np.full((8, len(keys)), 0.5)
        self.top: list[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]] = []
        for level in range(8):
            bit = (byte >> (7 - level)) & 1
            node = U64(1 << level) | (keys & U64(255)) >> U64(8 - level)
            one = np.where(bit == 1, counts, 0).astype(float)
            zero = np.where(bit == 0, counts, 0).astype(float)
            lower: tuple[np.ndarray, np.ndarray] | None = None
            for d in range(depth, least - 1, -1):
                code = (keys >> U64(8 * (depth + 1 - d))) << U64(8) | node
                codes, first, at = np.unique(code, return_index=True, return_inverse=True)
                zeros, ones = np.bincount(at, zero), np.bincount(at, one)
                if lower is None:
                    weighted = log_estimate(zeros, ones)
                    self.chance[level] = next_bit(zeros[at], ones[at], bit)
                else:
                    deeper = np.bincount(at[lower[0]], lower[1], minlength=len(codes))
                    weighted, share = weigh(zeros, ones, deeper)
                    self.chance[level] = share[at] * next_bit(zeros[at], ones[at], bit) + (1 - share[at]) * self.chance[level]
                lower = first, weighted
            self.top.append((codes, zeros, ones, weighted))

    def shallow(self, least: int = 2) -> tuple[np.ndarray, np.ndarray]:
        """(nodes, sums): the counts and log probabilities of contexts one byte shorter than ``least``, added up."""
        code = np.concatenate([t[0] for t in self.top])
        up = (code >> U64(16)) << U64(8) | (code & U64(255)) if least > 1 else code & U64(255)
        nodes, at = np.unique(up, return_inverse=True)
        return nodes, np.column_stack([np.bincount(at, np.concatenate([t[k] for t in self.top]), minlength=len(nodes)) for k in (1, 2, 3)])


class Shallow:
    """The two shallowest levels, from sums over contexts of two bytes; and these contexts themselves, where they are split.

    ``middle``: (nodes, sums) over contexts of three bytes of the split pairs.
    """

    def __init__(self, nodes: np.ndarray, sums: np.ndarray, middle: tuple[np.ndarray, np.ndarray] | None = None):
        self.count = np.zeros((2, 256 * 256))
        deeper = np.zeros(256 * 256)
        self.count[:, nodes], deeper[nodes] = sums[:, :2].T, sums[:, 2]
        self.nodes, found = middle or (np.zeros(0, U64), np.zeros((0, 3)))
        self.middle = found[:, :2].T
        weighted, self.middle_share = weigh(*self.middle, found[:, 2])
        up = ((self.nodes >> U64(16)) << U64(8) | self.nodes & U64(255)).astype(np.int64)
        for total, part in ((self.count[0], self.middle[0]), (self.count[1], self.middle[1]), (deeper, weighted)):
            np.add.at(total, up, part)
        weighted, self.share = weigh(*self.count, deeper)
        self.count0 = self.count.reshape(2, 256, 256).sum(axis=1)
        weighted0, self.share0 = weigh(*self.count0, weighted.reshape(256, 256).sum(axis=0))
        #: log probability of the whole training text under the weighted tree
        self.log_weighted = float(weighted0[1:].sum())

    def mixed(self, keys: np.ndarray, chance: np.ndarray, depth: int = DEPTH) -> np.ndarray:
        """Probabilities of each key's bits with those of its context of two bytes mixed in."""
        byte, pair = keys & U64(255), keys >> U64(8 * (depth - 1))
        out = np.empty_like(chance)
        for level in range(8):
            node = pair << U64(8) | U64(1 << level) | byte >> U64(8 - level)
            at = np.minimum(np.searchsorted(self.nodes, node), max(len(self.nodes) - 1, 0))
            known = self.nodes[at] == node if len(self.nodes) else np.zeros(len(keys), bool)
            zeros, ones, share = (np.where(known, x[at] if len(x) else 0.0, none) for x, none in ((self.middle[0], 0.0), (self.middle[1], 0.0), (self.middle_share, 0.5)))
            out[level] = share * next_bit(zeros, ones, (byte >> U64(7 - level) & U64(1)).astype(np.int64)) + (1 - share) * chance[level]
        return out

    def log10(self, keys: np.ndarray, chance: np.ndarray, depth: int = DEPTH) -> np.ndarray:
        """log10 of the probability of each key's byte in its context."""
        byte, near = (keys & U64(255)).astype(np.int64), (keys >> U64(8 * depth)).astype(np.int64)
        out = np.zeros(len(keys))
        for level in range(8):
            bit = (byte >> (7 - level)) & 1
            node = (1 << level) | byte >> (8 - level)
            at = near << 8 | node
            p = self.share[at] * next_bit(self.count[0][at], self.count[1][at], bit) + (1 - self.share[at]) * chance[level]
            p = self.share0[node] * next_bit(self.count0[0][node], self.count0[1][node], bit) + (1 - self.share0[node]) * p
            out += np.log10(p)
        return out


def spelled(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Texts as their tokens: words in lower case, each with a space after it, and an end.

    Gives (bytes, offsets, word hashes, words before each text).
    """
    data = lower_ascii(data)
    start, end, at = words(data, offsets)
    count = np.diff(at)
    size = end - start
    text = np.repeat(np.arange(len(count)), count)
    before = np.cumsum(size) - size  # word bytes before each word
    to = before + np.arange(len(size)) + text
    total = int(size.sum())
    out = np.full(total + len(size) + len(count), SPACE, np.uint8)
    shift = np.repeat(to - before, size)
    source = np.repeat(start - before, size) + np.arange(total)
    out[shift + np.arange(total)] = data[source]
    bounds = np.r_[0, np.cumsum(np.bincount(text, size, minlength=len(count)).astype(np.int64) + count + 1)]
    out[bounds[1:] - 1] = END
    return out, bounds, word_codes(data, start, end), at


def keys_of(data: np.ndarray, offsets: np.ndarray, depth: int = DEPTH) -> np.ndarray:
    """The key of every byte; a text's first ones have ends before them."""
    n = len(data)
    key = data.astype(U64)
    for back in range(1, depth + 1):  # the nearest byte is the highest
        key[back:] |= data[: n - back].astype(U64) << U64(8 * (depth + 1 - back))
    early = (offsets[:-1, None] + np.arange(depth)).ravel()
    early = early[early < np.repeat(offsets[1:], depth)]
    begin = offsets[np.searchsorted(offsets, early, "right") - 1]
    fixed = data[early].astype(U64)
    for back in range(1, depth + 1):
        at = early - back
        fixed |= np.where(at >= begin, data[np.maximum(at, 0)], END).astype(U64) << U64(8 * (depth + 1 - back))
    key[early] = fixed
    return key


def word_keys(codes: np.ndarray) -> np.ndarray:
    """Word hashes apart from the end token's key."""
    return np.where(codes == U64(END_WORD), U64(1), codes)


class Tally:
    """Sums of counts by key, compacted now and then."""

    def __init__(self, limit: int = 1 << 19):
        self.parts: list[tuple[np.ndarray, np.ndarray]] = []
        self.size, self.limit = 0, limit

    def add(self, keys: np.ndarray, counts: np.ndarray | None = None) -> None:
        if counts is None:
            keys, counts = np.unique(keys, return_counts=True)
        self.parts.append((keys, counts.astype(np.int64)))
        self.size += len(keys)
        if self.size > self.limit:
            self.parts = [self.all()]
            self.size = len(self.parts[0][0])
            self.limit = max(self.limit, self.size + self.size // 2)

    def all(self) -> tuple[np.ndarray, np.ndarray]:
        """Different keys in order, and their counts."""
        if not self.parts:
            return np.zeros(0, U64), np.zeros(0, np.int64)
        if len(self.parts) == 1:
            return self.parts[0]
        keys, counts = (np.concatenate(x) for x in zip(*self.parts, strict=True))
        order = np.argsort(keys, kind="stable")
        keys = keys[order]
        first = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1]])
        return keys[first], np.add.reduceat(counts[order], first)


class Keys:
    """Different keys of many, without counts: half the memory of a ``Tally``, and sorted in place."""

    def __init__(self, limit: int = 1 << 19):
        self.parts: list[np.ndarray] = []
        self.size, self.limit = 0, limit

    def add(self, keys: np.ndarray) -> None:
        keys = np.sort(keys)
        self.parts.append(keys[np.r_[True, keys[1:] != keys[:-1]]] if len(keys) else keys)
        self.size += len(self.parts[-1])
        if self.size > self.limit:
            self.size = len(self.all())
            self.limit = max(self.limit, self.size + self.size // 2)

    def all(self) -> np.ndarray:
        """Different keys in order."""
        if len(self.parts) != 1:
            keys = np.concatenate([np.zeros(0, U64), *self.parts])
            self.parts = []
            keys.sort(kind="stable")  # merges the parts, which are sorted
            new = np.ones(len(keys), bool)
            np.not_equal(keys[1:], keys[:-1], out=new[1:])
            self.parts = [keys[new]]
        return self.parts[0]


class Lookup:
    """Places of many keys in a sorted array of different ones, by open addressing."""

    def __init__(self, keys: np.ndarray):
        self.keys = keys
        self.mask = (1 << max(4, int(2 * len(keys)).bit_length())) - 1
        self.slots = np.full(self.mask + 1, -1, np.int32)
        left = np.arange(len(keys), dtype=np.int32)
        at = self._home(keys)
        while len(left):
            free = self.slots[at] < 0
            self.slots[at[free]] = left[free]
            lost = self.slots[at] != left
            left, at = left[lost], (at[lost] + 1) & self.mask

    def _home(self, keys: np.ndarray) -> np.ndarray:
        return (mix(keys) & U64(self.mask)).astype(np.int64)

    def __call__(self, keys: np.ndarray) -> np.ndarray:
        """Each key's place; all of them must be there."""
        at = self._home(keys)
        out = self.slots[at]
        wrong = np.flatnonzero(self.keys[out] != keys)
        while len(wrong):
            at[wrong] = (at[wrong] + 1) & self.mask
            out[wrong] = self.slots[at[wrong]]
            wrong = wrong[self.keys[out[wrong]] != keys[wrong]]
        return out


# packed rows: sorted keys of one bucket as differences ------------------------


def pack(values: np.ndarray) -> bytes:
    return zstandard.ZstdCompressor(level=1).compress(values.tobytes())


def unpack(raw: bytes, kind: type) -> np.ndarray:
    return np.frombuffer(zstandard.ZstdDecompressor().decompress(raw), kind)


def pack_keys(keys: np.ndarray) -> bytes:
    """Sorted keys, the bytes of their differences by significance."""
    step = np.diff(keys, prepend=U64(0))
    return pack(np.ascontiguousarray(step.view(np.uint8).reshape(-1, 8).T))


def unpack_keys(raw: bytes) -> np.ndarray:
    planes = unpack(raw, np.uint8).reshape(8, -1)
    return np.cumsum(np.ascontiguousarray(planes.T).view(U64).ravel(), dtype=U64)


def bucket_of(kind: int, keys: np.ndarray, buckets: int, depth: int, parts: np.ndarray) -> np.ndarray:
    """Keys of one bucket are met in one task; contexts with the same two nearest bytes share one, or ``parts`` of them by the third byte."""
    place = keys
    if kind == GRAM:
        pair = keys >> U64(8 * (depth - 1))
        third = mix((keys >> U64(8 * (depth - 2)) & U64(255)) + U64(1)) % parts[pair.astype(np.int64)].astype(U64) if depth > 2 else U64(0)
        place = pair << U64(8) | third
    return (mix(place + U64(kind)) % U64(buckets)).astype(np.int64) * 2 + kind


#: keys whose buckets are worked out at once
PLACED = 1 << 18


def _by_bucket(keys: np.ndarray, kind: int, buckets: int, depth: int, parts: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
    """(bucket, places in ``keys``) of every bucket that has any; places ascend."""
    at = np.empty(len(keys), np.int32 if buckets < 1 << 30 else np.int64)
    for x in range(0, len(keys), PLACED):
        at[x : x + PLACED] = bucket_of(kind, keys[x : x + PLACED], buckets, depth, parts)
    order = np.argsort(at, kind="stable")
    at = at[order]
    edge = np.flatnonzero(np.r_[True, at[1:] != at[:-1], True]) if len(at) else []
    for x, y in zip(edge[:-1], edge[1:], strict=True):
        yield int(at[x]), order[x:y]


def packed_rows(tally: Tally, kind: int, buckets: int, depth: int, parts: np.ndarray) -> Iterator[tuple[int, bytes, bytes]]:
    """(bucket, keys, counts) of a tally."""
    keys, counts = tally.all()
    for bucket, rows in _by_bucket(keys, kind, buckets, depth, parts):
        yield bucket, pack_keys(keys[rows]), pack(counts[rows])


def packed_keys(held: Keys, kind: int, buckets: int, depth: int, parts: np.ndarray) -> Iterator[tuple[int, bytes]]:
    """(bucket, keys) of different keys."""
    keys = held.all()
    for bucket, rows in _by_bucket(keys, kind, buckets, depth, parts):
        yield bucket, pack_keys(keys[rows])


def whole(keys: np.ndarray, depth: int, parts: np.ndarray) -> np.ndarray:
    """Which keys have the whole subtree of their two nearest bytes beside them."""
    return parts[(keys >> U64(8 * (depth - 1))).astype(np.int64)] == 1


# over a table ------------------------------------------------------------------


def held_out(doc_id: Column, parts: int = 7, which: int = 2) -> Column:
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % parts == which


def add_texts(grams: Tally | Keys, tokens: Tally | Keys, column: pa.Array, depth: int) -> None:
    data, at = utf8(column)
    for i, j in blocks(at):
        out, bounds, code, _ = spelled(data[at[i] : at[j]], at[i : j + 1] - at[i])
        grams.add(keys_of(out, bounds, depth))
        tokens.add(word_keys(code))
        tokens.add(np.full(j - i, END_WORD, U64))


def parts_of(rows: DataFrame, size: int, buckets: int, depth: int) -> np.ndarray:
    """For each pair of nearest bytes the parts that its subtree is dealt to: one, unless it has more than two buckets' share of a sample.

    However it turns out, only the deal depends on it, not the scores.
    """
    parts = np.ones(1 << 16, np.int64)
    if depth < 3 or buckets < 16:
        return parts

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n = np.zeros(1 << 16, np.int64)
        for b in batches:
            data, at = utf8(b.column(0))
            for i, j in blocks(at):
                out, bounds, _, _ = spelled(data[at[i] : at[j]], at[i : j + 1] - at[i])
                n += np.bincount((keys_of(out, bounds, 2) >> U64(8)).astype(np.int64), minlength=1 << 16)
        pair = np.flatnonzero(n)
        yield pa.record_batch([pa.array(pair), pa.array(n[pair])], names=["pair", "n"])

    some = rows.where(F.rand(1) < min(1.0, SAMPLE_BYTES / max(size, 1))).select("text").mapInArrow(count, "pair long, n long")
    found = some.groupBy("pair").agg(F.sum("n").alias("n")).collect()  # at most 65,536 pairs
    total = sum(r.n for r in found)
    for r in sorted(found, key=lambda r: -r.n)[:SPLIT]:
        parts[r.pair] = min(256, max(1, int(r.n / total * buckets / 2)))
    return parts


def _counts(texts: DataFrame, buckets: int, depth: int, deal: np.ndarray) -> DataFrame:
    """(bucket, keys, counts) of all of ``texts``, one row for each bucket."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tallies = Tally(), Tally()
        for b in batches:
            add_texts(*tallies, b.column(0), depth)
        yield from _record(((k, *row) for k in (GRAM, WORD) for row in packed_rows(tallies[k], k, buckets, depth, deal)), ["_", "bucket", "keys", "counts"])

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, tally = None, Tally()
        for b in batches:
            for bucket, keys, counts in zip(*(c.to_pylist() for c in b.columns), strict=True):
                if bucket != held:
                    if held is not None:
                        yield from _merged(held, tally)
                    held, tally = bucket, Tally()
                tally.add(unpack_keys(keys), unpack(counts, np.int64))
        if held is not None:
            yield from _merged(held, tally)

    parts = texts.select("text").mapInArrow(count, "bucket long, keys binary, counts binary")
    return parts.repartition("bucket").sortWithinPartitions("bucket").mapInArrow(merge, "bucket long, keys binary, counts binary, n_keys long, total long")


_TYPES = {"bucket": pa.int64(), "chunk": pa.int64(), "keys": pa.binary(), "counts": pa.binary(), "values": pa.binary(), "n_keys": pa.int64(), "total": pa.int64()}


def _record(rows: Iterator[tuple], names: list[str], size: int = 64) -> Iterator[pa.RecordBatch]:
    """Rows as batches; a column named _ is left out."""
    rows = iter(rows)
    keep = [k for k, x in enumerate(names) if x != "_"]
    while True:
        part = list(itertools.islice(rows, size))
        if not part:
            return
        yield pa.record_batch([pa.array([r[k] for r in part], _TYPES[names[k]]) for k in keep], names=[names[k] for k in keep])


def _merged(bucket: int, tally: Tally) -> Iterator[pa.RecordBatch]:
    keys, counts = tally.all()
    yield from _record(iter([(bucket, pack_keys(keys), pack(counts), len(keys), int(counts.sum()))]), ["bucket", "keys", "counts", "n_keys", "total"])


def _shallow(model: DataFrame, depth: int, deal: np.ndarray) -> Shallow:
    """At most 256 times 255 rows of sums pass the driver, and ``SPLIT`` times 255 of split pairs."""

    def sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, split = np.zeros((256 * 256, 3)), []
        for b in batches:
            for raw, n in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                keys, counts = unpack_keys(raw), unpack(n, np.int64)
                own = whole(keys, depth, deal)
                nodes, part = Subtree(keys[own], counts[own], depth).shallow()
                total[nodes.astype(np.int64)] += part
                if not own.all():
                    split.append(Subtree(keys[~own], counts[~own], depth, 3).shallow())
        nodes = np.flatnonzero(total.any(axis=1))
        yield pa.record_batch([pa.array(np.zeros(len(nodes), np.int32)), pa.array(nodes), *(pa.array(total[nodes, k]) for k in range(3))], names=["middle", "node", "zeros", "ones", "deeper"])
        for found, part in split:
            yield pa.record_batch([pa.array(np.ones(len(found), np.int32)), pa.array(found.astype(np.int64)), *(pa.array(part[:, k]) for k in range(3))], names=["middle", "node", "zeros", "ones", "deeper"])

    found = model.where(f"bucket % 2 = {GRAM}").select("keys", "counts").mapInArrow(sums, "middle int, node long, zeros double, ones double, deeper double")
    rows = found.groupBy("middle", "node").agg(F.sum("zeros"), F.sum("ones"), F.sum("deeper")).orderBy("node").collect()
    table = lambda kind, middle: (np.array([r[1] for r in rows if r[0] == middle], kind), np.array([r[2:] for r in rows if r[0] == middle], float).reshape(-1, 3))
    return Shallow(*table(np.int64, 0), table(U64, 1))


def score_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", depth: int = DEPTH, chunk_bytes: int = CHUNK_BYTES) -> DataFrame:
    """log10 probabilities of every text under its corpus.

    Learns from texts whose crc32(id as text) mod 7 isn't 2 (a null id counts as
    empty). A text is its tokens: runs of bytes other than space and
    tab..carriage return, A-Z in lower case, and one end. Gives doc_id,
    held_out, n_tokens, n_known, train_tokens, base_score (words apart from each
    other, counts plus one), score (the context tree's, of the words' bytes, a
    space after each, and the end), n_bytes (of those) and bits_per_byte. Null and
    empty texts are the end alone; repeated rows count and are scored each;
    other columns are ignored.
    """
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), held_out(F.col(id_col)).alias("held_out"), text.alias("text"))
    size = rows.agg(F.sum(F.octet_length("text") + 1)).first()[0] or 0
    chunks, buckets = max(1, -(-size // chunk_bytes)), max(8, -(-size // (chunk_bytes // 4)))
    deal = parts_of(rows, size, buckets, depth)
    model = stored(_counts(rows.where("not held_out"), buckets, depth, deal))
    totals = {r[0]: r[1:] for r in model.groupBy((F.col("bucket") % 2).alias("kind")).agg(F.sum("n_keys"), F.sum("total")).collect()}
    different, train_tokens = totals.get(WORD, (0, 0))
    shallow = _shallow(model, depth, deal)

    def ask(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        # a partition may have several chunks, which come one after the other: one is held at a time
        held, asked = None, (Keys(), Keys())

        def told() -> Iterator[pa.RecordBatch]:
            for kind in (GRAM, WORD):
                yield from _record(((r[0], held, r[1]) for r in packed_keys(asked[kind], kind, buckets, depth, deal)), ["bucket", "chunk", "keys"])

        for b in batches:
            chunk = b.column(0).to_numpy()
            for c in np.unique(chunk).tolist():
                if c != held:
                    yield from told()
                    held, asked = c, (Keys(), Keys())
                add_texts(*asked, b.column(1).filter(pa.array(chunk == c)), depth)
        yield from told()

    def answer(key: tuple, known: pa.Table, asked: pa.Table) -> pa.Table:
        kind = key[0].as_py() % 2
        wanted = [unpack_keys(x) for x in asked.column("keys").to_pylist()]
        keys, counts = (unpack_keys(known.column("keys")[0].as_py()), unpack(known.column("counts")[0].as_py(), np.int64)) if len(known) else (np.zeros(0, U64), np.zeros(0, np.int64))
        tally = Tally()
        tally.add(keys, counts)
        for w in wanted:
            tally.add(w, np.zeros(len(w), np.int64))
        every, counts = tally.all()
        if not wanted:
            values = np.zeros(len(every))
        elif kind == GRAM:  # seven digits of each byte's share
            own = whole(every, depth, deal)
            chance = np.empty((8, len(every)))
            chance[:, own] = Subtree(every[own], counts[own], depth).chance
            if not own.all():
                chance[:, ~own] = shallow.mixed(every[~own], Subtree(every[~own], counts[~own], depth, 3).chance, depth)
            values = shallow.log10(every, chance, depth).astype(np.float32)
        else:
            values = counts
        found = [pack(values[np.searchsorted(every, w)]) for w in wanted]
        return pa.table([asked.column("chunk").combine_chunks(), pa.array([kind] * len(wanted), pa.int64()), asked.column("keys").combine_chunks().cast(pa.binary()), pa.array(found, pa.binary())], names=["chunk", "kind", "keys", "values"])

    def score(key: tuple, texts: pa.Table, answers: pa.Table) -> pa.Table:
        tables = []
        for kind in (GRAM, WORD):
            part = answers.filter(pc.equal(answers.column("kind"), kind))
            keys = np.concatenate([np.zeros(0, U64), *(unpack_keys(x) for x in part.column("keys").to_pylist())])
            values = np.concatenate([np.zeros(0, KIND[kind]), *(unpack(x, KIND[kind]) for x in part.column("values").to_pylist())])
            tables.append((Lookup(keys), values))
        data, at = utf8(texts.column("text"))
        columns: list[list[np.ndarray]] = [[] for _ in range(5)]
        for i, j in blocks(at):
            out, bounds, code, at_word = spelled(data[at[i] : at[j]], at[i : j + 1] - at[i])
            find, values = tables[GRAM]
            bits = np.add.reduceat(values[find(keys_of(out, bounds, depth))], bounds[:-1], dtype=float)
            find, values = tables[WORD]
            count = np.diff(at_word)
            own = values[find(word_keys(code))]
            end = int(values[find(np.full(1, END_WORD, U64))][0])
            share = lambda c: np.log10((c + 1) / (train_tokens + different + 1))
            owner = np.repeat(np.arange(j - i), count)
            base = np.bincount(owner, share(own), minlength=j - i) + share(end)
            known = np.bincount(owner, own > 0, minlength=j - i).astype(np.int64) + int(end > 0)
            for c, v in zip(columns, (count + 1, known, base, bits, np.diff(bounds)), strict=True):
                c.append(v)
        n, known, base, bits, size = (np.concatenate(c) for c in columns)
        return pa.table(
            [texts.column("doc_id"), texts.column("held_out"), pa.array(n), pa.array(known), pa.array(np.full(len(n), train_tokens)), pa.array(base), pa.array(bits), pa.array(size), pa.array(-bits / np.log10(2) / size)],
            names=["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score", "n_bytes", "bits_per_byte"],
        )

    dealt = rows.withColumn("chunk", F.pmod(F.xxhash64("doc_id", "text"), F.lit(chunks))).repartition("chunk")
    asked = dealt.sortWithinPartitions("chunk").select("chunk", "text").mapInArrow(ask, "bucket long, chunk long, keys binary")
    answers = model.select("bucket", "keys", "counts").groupBy("bucket").cogroup(asked.groupBy("bucket")).applyInArrow(answer, "chunk long, kind long, keys binary, values binary")
    return dealt.groupBy("chunk").cogroup(answers.groupBy("chunk")).applyInArrow(score, "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double, n_bytes long, bits_per_byte double")
