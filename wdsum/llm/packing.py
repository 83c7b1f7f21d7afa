"""Vector bin packing of token sequences by the dot-product heuristic.

An example needs three resources at once: tokens, segments (one a piece) and
loss-bearing tokens. A sequence offers a fixed amount of each. Sequences are
filled one after another: of all waiting pieces that fit, the one whose needs
have the largest dot product with what the open sequence has left goes in, each
resource weighted by its share of all needs. Where pieces may be cut and none
fits whole, the best one is cut to fill the gap.

Tasks pack their own rows as these stream by, so there is no shuffle and no
collect. The pool of waiting pieces is bounded by ``POOL_TOKENS``; what is left
of it under one sequence's capacity waits for the next rows. At a task's end the
rest is laid out in sequences whose lengths are powers of two, which need no
padding.
"""

from __future__ import annotations

import os
import zlib
from array import array
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .textkit import blocks, utf8
from .workers import kernel, kept

TOKENIZER = "word_bpe_49k.json"
END_ID = 1
POOL_TOKENS = 1 << 20
CACHED_WORDS = 250_000
CACHED_STEMS = 400_000


@dataclass(frozen=True)
class Limits:
    """What one sequence offers."""

    tokens: int = 2048
    segments: int = 256
    loss: int = 2048


@dataclass
class Piece:
    """A run of one example's ids: ``start`` ids come before it in the example."""

    key: object
    start: int
    length: int
    loss: int


@dataclass
class Packer:
    """Places pieces; ``full`` holds finished sequences as lists of pieces."""

    limits: Limits = field(default_factory=Limits)
    cut: bool = True

    def __post_init__(self):
        self.pool: dict[tuple[int, int], list[Piece]] = {}
        self.tokens = 0
        self.need = np.zeros(3)
        self._row: dict[tuple[int, int], int] = {}  # of each shape seen
        self._shapes = np.zeros((64, 3))
        self._held = np.zeros(64, bool)

    def add(self, key, length: int, loss: int | None = None) -> Iterator[list[Piece]]:
        """Takes an example; yields the sequences it fills alone."""
        loss = length if loss is None else loss
        cap, start = self.limits.tokens, 0
        if self.cut and loss == length and cap <= self.limits.loss:
            while length - start >= cap:
                yield [Piece(key, start, cap, cap)]
                start += cap
        if length > start or length == 0:
            self._put(Piece(key, start, length - start, loss - start if loss == length else loss))

    def _put(self, piece: Piece) -> None:
        if not self.cut and (piece.length > self.limits.tokens or piece.loss > self.limits.loss):
            raise ValueError(f"{piece} exceeds a sequence and may not be cut")
        shape = (piece.length, piece.loss)
        row = self._row.setdefault(shape, len(self._row))
        if row == len(self._held):
            self._shapes = np.vstack([self._shapes, np.zeros_like(self._shapes)])
            self._held = np.r_[self._held, np.zeros_like(self._held)]
        self._shapes[row] = piece.length, 1, piece.loss
        self._held[row] = True
        self.pool.setdefault(shape, []).append(piece)
        self.tokens += piece.length
        self.need += (piece.length, 1, piece.loss)

    def _take(self, shape: tuple[int, int]) -> Piece:
        held = self.pool[shape]
        piece = held.pop()
        if not held:
            del self.pool[shape]
            self._held[self._row[shape]] = False
        self.tokens -= piece.length
        return piece

    def _next(self, left: np.ndarray) -> tuple[tuple[int, int], bool] | None:
        """The shape to place and whether it fits whole."""
        rows = np.flatnonzero(self._held)
        if not len(rows):
            return None
        shapes = self._shapes[rows]
        cap = np.array([self.limits.tokens, self.limits.segments, self.limits.loss], float)
        score = shapes @ (self.need / cap * left / cap**2)
        fits = (shapes[:, 0] <= left[0]) & (shapes[:, 2] <= left[2]) & (left[1] >= 1)
        whole = fits.any()
        if not whole:
            if not self.cut or left[0] < 1 or left[1] < 1:
                return None
            # only pieces that bear loss throughout, or nowhere, have a known loss after a cut
            fits = (shapes[:, 2] == 0) | ((shapes[:, 2] == shapes[:, 0]) & (left[2] >= 1))
            if not fits.any():
                return None
        t, _, x = shapes[np.argmax(np.where(fits, score, -1.0))]
        return (int(t), int(x)), bool(whole)

    def fill(self) -> list[Piece]:
        """One sequence of waiting pieces."""
        left = np.array([self.limits.tokens, self.limits.segments, self.limits.loss], float)
        out: list[Piece] = []
        while (found := self._next(left)) is not None:
            piece = self._take(found[0])
            if not found[1]:
                n = int(min(left[0], left[2]) if piece.loss else left[0])
                rest = Piece(piece.key, piece.start + n, piece.length - n, piece.loss - n if piece.loss else 0)
                piece = Piece(piece.key, piece.start, n, n if piece.loss else 0)
                self._put(rest)
            out.append(piece)
            left -= (piece.length, 1, piece.loss)
        return out

    def drain(self, final: bool = False) -> Iterator[list[Piece]]:
        while self.pool and (final or self.tokens >= self.limits.tokens):
            yield self.fill()


def power_lengths(n: int) -> list[int]:
    """n as a sum of distinct powers of two, largest first."""
    return [1 << b for b in range(n.bit_length() - 1, -1, -1) if n >> b & 1]


def split_to_powers(sequence: list[Piece]) -> Iterator[list[Piece]]:
    """The same pieces in sequences of power-of-two lengths."""
    todo = sequence[::-1]
    for want in power_lengths(sum(p.length for p in sequence)):
        out = []
        while want:
            piece = todo.pop()
            n = min(want, piece.length)
            out.append(Piece(piece.key, piece.start, n, min(n, piece.loss)))
            if n < piece.length:
                todo.append(Piece(piece.key, piece.start + n, piece.length - n, max(0, piece.loss - n)))
            want -= n
        yield out


def tokenizer_path(name: str = TOKENIZER) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


# byte-level vocabularies show bytes that are no printable Latin-1 characters by those from U+0100 on, in order
_HIDDEN = [*range(0x00, 0x21), *range(0x7F, 0xA1), 0xAD]
_SHOWN = {b: chr(0x100 + k) for k, b in enumerate(_HIDDEN)}
#: marks without the apostrophe, which may begin a suffix, and "<", which begins special tokens
_MARKS = '!"#$%&()*+,-./:;=>?@[\\]^_`{|}~'


class Kept(dict):
    """A map that fills itself and forgets: entries not asked for during a whole generation go."""

    def __init__(self, make: Callable[[str], bytes], size: int, old: dict[str, bytes] | None = None):
        self.make, self.size, self.old = make, size, old or {}

    def __missing__(self, key: str) -> bytes:
        found = self.old.pop(key, None)
        if found is None:
            found = self.make(key)
        if len(key) <= 100:
            self[key] = found
        return found

    def renewed(self) -> Kept:
        """Itself, or an empty generation before which this one is."""
        if len(self) <= self.size:
            return self
        self.old = {}
        return Kept(self.make, self.size, self)


class WordEncoder:
    """Ids of whole texts, one space-delimited word at a time.

    The vocabulary's own rules drop white space, fold case code point by code
    point and never join across white space, nor letters with marks other than
    an apostrophe, so a text's ids are its words' ids in order. Words repeat, so their
    ids are kept, within a bound. Special tokens are found before case is folded,
    so a text that may hold one keeps its capitals until the vocabulary's rules.
    """

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.merge = self.tokenizer.model.tokenize
        added = [t.content for t in self.tokenizer.get_added_tokens_decoder().values()]
        if any(" " in t or "\n" in t for t in added):
            raise ValueError("a special token with white space would be cut")
        #: what every special token begins with; empty if they have nothing in common, none if there are none
        self.special = os.path.commonprefix(added) if added else None
        self.marks = Kept(self._any, 10_000)
        self.stems = Kept(self._letters, CACHED_STEMS)
        self.words = Kept(self._word, CACHED_WORDS)

    def _any(self, text: str) -> bytes:
        return array("I", self.tokenizer.encode(text, add_special_tokens=False).ids).tobytes()

    def _letters(self, stem: str) -> bytes:
        """Ids of letters below U+0100 in lower case, which the rules before the merges leave as they are."""
        return array("I", [t.id for t in self.merge(stem if stem.isascii() else stem.encode().decode("latin-1").translate(_SHOWN))]).tobytes()

    def _word(self, word: str) -> bytes:
        stem = word.rstrip(_MARKS)
        mark = word[len(stem) :]
        if stem.isalpha() and (stem.isascii() or max(stem) < "\u0100") and stem == stem.lower():
            return self.stems[stem] + self.marks[mark] if mark else self.stems[stem]
        return self._any(word)

    def __call__(self, texts: list[str]) -> list[bytes]:
        get = self.words.__getitem__
        special = self.special
        # capital sigma folds by its neighbours in Python, not in the vocabulary's rules
        raw = lambda t: "\u03a3" in t or special is not None and special in t
        out = [b"".join(map(get, (t if raw(t) else t.lower()).replace("\n", " ").split(" "))) for t in texts]
        self.words, self.stems = self.words.renewed(), self.stems.renewed()
        return out


def encoder(path: str) -> WordEncoder:
    if path not in kept:
        kept[path] = WordEncoder(path)
    return kept[path]


SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


def pack_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", path: str | None = None, limits: Limits = Limits()) -> DataFrame:
    """Packs every text of ``docs``; one row for each piece (``SCHEMA``).

    A text's ids are the tokenizer's and then ``END_ID``; all bear loss. A null
    or empty text is that one id. Repeated rows are packed each; a null id stays
    null; other columns are ignored; an empty table gives no rows.
    """
    path = path or tokenizer_path()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, packer = encoder(path), Packer(limits)
        ids: dict[int, tuple[object, bytes, int]] = {}  # by row: id, ids, ids not yet placed
        at = TaskContext.get().partitionId() << 40
        rows: list[list] = [[] for _ in range(7)]
        row = 0

        def lay(sequence: list[Piece]) -> None:
            nonlocal at
            total = sum(p.length for p in sequence)
            for part in [sequence] if total == limits.tokens else split_to_powers(sequence):
                offset = 0
                for p in part:
                    doc, raw, left = ids[p.key]
                    for column, value in zip(rows, (doc, p.start, p.length, zlib.crc32(raw[4 * p.start : 4 * (p.start + p.length)]), len(raw) // 4, at, offset), strict=True):
                        column.append(value)
                    offset += p.length
                    if left == p.length:
                        del ids[p.key]
                    else:
                        ids[p.key] = doc, raw, left - p.length
                at += 1

        def take() -> pa.RecordBatch:
            nonlocal rows
            out = pa.record_batch([pa.array(x, pa.int64()) for x in rows], names=[x.split()[0] for x in SCHEMA.split(", ")])
            rows = [[] for _ in range(7)]
            return out

        end = np.array([END_ID], "<u4").tobytes()
        for batch in batches:
            _, offsets = utf8(batch.column(1))
            for i, j in blocks(offsets):
                raw = encode([x or "" for x in batch.column(1).slice(i, j - i).to_pylist()])
                for doc, r in zip(batch.column(0).slice(i, j - i).to_pylist(), raw, strict=True):
                    ids[row] = doc, r + end, len(r) // 4 + 1
                    for sequence in packer.add(row, len(r) // 4 + 1):
                        lay(sequence)
                    row += 1
                if packer.tokens >= POOL_TOKENS:
                    for sequence in packer.drain():
                        lay(sequence)
                if len(rows[0]) >= 50_000:
                    yield take()
        for sequence in packer.drain(final=True):
            lay(sequence)
        yield take()

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(kernel(run, keeps=True), SCHEMA)


def pack_lengths(lengths: list[tuple[object, int, int]], limits: Limits = Limits()) -> list[list[object]]:
    """Whole examples (key, tokens, loss-bearing tokens) in sequences, uncut.

    For instruction data whose examples must stay together; longer ones raise.
    """
    packer = Packer(limits, cut=False)
    for key, tokens, loss in lengths:
        list(packer.add(key, tokens, loss))
    return [[p.key for p in sequence] for sequence in packer.drain(final=True)]


def pack_examples(examples: DataFrame, id_col: str, tokens_col: str, loss_col: str, limits: Limits = Limits()) -> DataFrame:
    """Packs whole examples of known sizes, uncut: (id, sequence_id, position).

    Null sizes count as 0. An example over a limit is an error.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        packer, at = Packer(limits, cut=False), TaskContext.get().partitionId() << 40
        for last in (*(b for b in batches), None):
            if last is not None:
                for key, tokens, loss in zip(*(last.column(k).to_pylist() for k in range(3)), strict=True):
                    list(packer.add(key, tokens, loss))
                if packer.tokens < POOL_TOKENS:
                    continue
            out: list[tuple] = []
            for sequence in packer.drain(final=last is None):
                out += [(p.key, at, i) for i, p in enumerate(sequence)]
                at += 1
            columns = list(zip(*out, strict=True)) or [[], [], []]
            yield pa.record_batch([pa.array(c, t) for c, t in zip(columns, (pa.string(), pa.int64(), pa.int64()), strict=True)], names=["id", "sequence_id", "position"])

    whole = lambda c: F.coalesce(F.col(c).cast("long"), F.lit(0))
    return examples.select(F.col(id_col).cast("string").alias("id"), whole(tokens_col).alias("t"), whole(loss_col).alias("l")).mapInArrow(kernel(run, keeps=True), "id string, sequence_id long, position long")


def conversation_sizes(conversations: DataFrame, path: str | None = None, max_tokens: int = 2048) -> DataFrame:
    """Sizes of each conversation's examples for ``pack_examples``: (id, tokens, loss_tokens).

    Assistant turns bear loss, other turns don't. Turns are summed by
    conversation and cut into examples of ``max_tokens`` at most: a turn is cut
    at half of it, and example k has the pieces that end where the running sum is
    in the k-th half.
    """
    half = max(1, max_tokens // 2)
    path = path or tokenizer_path()

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = encoder(path)
        for b in batches:
            sizes = [len(x) // 4 + 1 for x in encode([t or "" for t in b.column(3).to_pylist()])]
            out = [(c, t, r, min(half, n - at)) for c, t, r, n in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).to_pylist(), sizes, strict=True) for at in range(0, n, half)]
            columns = list(zip(*out, strict=True)) or [[]] * 4
            yield pa.record_batch([pa.array(x, k) for x, k in zip(columns, (pa.int64(), pa.int64(), pa.string(), pa.int64()), strict=True)], names=["conv_id", "turn", "role", "n"])

    turns = conversations.select(F.col("conv_id").cast("long"), F.col("turn").cast("long"), F.col("role").cast("string"), F.col("text").cast("string")).mapInArrow(kernel(count, keeps=True), "conv_id long, turn long, role string, n long")
    from pyspark.sql import Window as W

    run = F.sum("n").over(W.partitionBy("conv_id").orderBy("turn", "n").rowsBetween(W.unboundedPreceding, 0))
    # pieces that end in one half start less than a half before it
    cut = turns.withColumn("k", F.floor((run - 1) / half))
    return (
        cut.groupBy("conv_id", "k")
        .agg(F.sum("n").alias("tokens"), F.sum(F.when(F.col("role") == "assistant", F.col("n")).otherwise(0)).alias("loss_tokens"))
        .select(F.concat_ws(":", "conv_id", "k").alias("id"), "tokens", "loss_tokens")
    )
