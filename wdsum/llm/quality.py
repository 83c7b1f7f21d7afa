"""Compression classifier: which labelled class's dictionary makes a text smaller?

Two zstandard dictionaries are trained, one on texts labelled good and one on
texts labelled bad. A text compressed with each has two sizes; their difference
by the text's bytes says which class it resembles. A logistic curve over that
difference, and over the smaller size by byte (repetitive text has neither
dictionary's help), fitted on labelled texts that the dictionaries haven't
seen, makes it a probability.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .textkit import blocks, utf8
from .workers import kernel

#: bounds of what is fitted on: labelled texts by class, bytes of one of them, bytes of a dictionary
FIT_ROWS, FIT_BYTES, DICTIONARY_BYTES, LEVEL = 4000, 1 << 16, 112_640, 3


def held_out(doc_id: Column, parts: int = 3, which: int = 1) -> Column:
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % parts == which


@dataclass
class Model:
    good: bytes
    bad: bytes
    weights: list[float]
    prior: float
    _tools: list = field(default_factory=list, repr=False)

    def __getstate__(self):
        return self.__dict__ | {"_tools": []}

    def sizes(self, texts: list[bytes]) -> np.ndarray:
        """(text, [good, bad]) compressed bytes, without what an empty frame takes."""
        if not self._tools:
            for raw in (self.good, self.bad):
                d = zstandard.ZstdCompressionDict(raw, dict_type=zstandard.DICT_TYPE_AUTO if raw else zstandard.DICT_TYPE_RAWCONTENT)
                d.precompute_compress(level=LEVEL)
                self._tools.append(zstandard.ZstdCompressor(dict_data=d, level=LEVEL, write_content_size=False, write_checksum=False, write_dict_id=False))
            self._empty = [len(c.compress(b"")) for c in self._tools]
        return np.array([[len(c.compress(t)) - e for c, e in zip(self._tools, self._empty, strict=True)] for t in texts], float).reshape(-1, 2)

    @staticmethod
    def inputs(sizes: np.ndarray, n: np.ndarray) -> np.ndarray:
        n = np.maximum(n, 1)
        x, r = (sizes[:, 1] - sizes[:, 0]) / n, sizes.min(axis=1) / n
        return np.column_stack([np.ones(len(n)), x, r, x * r, x * x, r * r])

    def score(self, texts: list[bytes]) -> np.ndarray:
        """Probability of the good class; an empty text has the labelled share of good ones."""
        n = np.array([len(t) for t in texts], float)
        z = self.inputs(self.sizes(texts), n) @ np.array(self.weights)
        return np.where(n == 0, self.prior, 1 / (1 + np.exp(-np.clip(z, -30, 30))))


def logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1e-3, rounds: int = 50) -> np.ndarray:
    """Newton's method for a ridge logistic regression on scaled inputs."""
    scale = np.maximum(np.abs(x).max(axis=0), 1e-12)
    x = x / scale
    w = np.zeros(x.shape[1])
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        g = x.T @ (y - p) - ridge * w
        step = np.linalg.solve((x.T * (p * (1 - p))) @ x + ridge * np.eye(len(w)), g)
        w = w + step
        if np.abs(step).max() < 1e-8:
            break
    return w / scale


def train(texts: list[bytes], good: list[bool]) -> Model:
    """Fits on labelled texts: every other one, by class, makes the dictionaries and the rest the curve."""
    parts: dict[bool, list[bytes]] = {True: [], False: []}
    for t, q in zip(texts, good, strict=True):
        parts[q].append(t)
    prior = len(parts[True]) / len(texts) if texts else 0.5

    def dictionary(samples: list[bytes]) -> bytes:
        samples = [s for s in samples if s]
        try:
            return zstandard.train_dictionary(DICTIONARY_BYTES, samples).as_bytes()
        except zstandard.ZstdError:  # too little text to train on: the text itself
            return b"".join(samples)[:DICTIONARY_BYTES]

    model = Model(dictionary(parts[True][::2]), dictionary(parts[False][::2]), [], prior)
    held = [(t, q) for q in (True, False) for t in parts[q][1::2] if t]
    if len({q for _, q in held}) < 2:
        model.weights = [float(np.log((prior + 1e-3) / (1 - prior + 1e-3))), 20.0, 0, 0, 0, 0]
        return model
    raw = [t for t, _ in held]
    x = model.inputs(model.sizes(raw), np.array([len(t) for t in raw], float))
    model.weights = logistic(x, np.array([q for _, q in held], float)).tolist()
    return model


def labelled(docs: DataFrame, labels: DataFrame, keep: Column, rows: int = FIT_ROWS) -> tuple[list[bytes], list[bool]]:
    """At most ``rows`` labelled texts and whether they are good, those of smallest hash; none longer than ``FIT_BYTES``.

    An id that is labelled both ways has no label; of texts that share an id
    only the least counts, so that no more than ``rows`` of them are collected.
    """
    known = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("quality").cast("int").alias("quality")).where(F.col("quality").isin(0, 1) & F.col("doc_id").isNotNull()).where(keep)
    agreed = known.groupBy("doc_id").agg(F.min("quality").alias("quality"), F.max("quality").alias("most")).where("quality = most").drop("most")
    chosen = agreed.orderBy(F.xxhash64("doc_id"), "doc_id").limit(rows)
    # at most ``rows`` pairs of numbers
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).where(F.octet_length("text") <= FIT_BYTES)
    found = texts.join(F.broadcast(chosen), "doc_id").withColumn("_nth", F.row_number().over(Window.partitionBy("doc_id").orderBy("text"))).where("_nth = 1")
    got = found.orderBy(F.xxhash64("doc_id"), "doc_id").select("text", "quality").collect()
    return [r.text.encode() for r in got], [r.quality == 1 for r in got]


def score_documents(docs: DataFrame, labels: DataFrame, fit_rows: int = FIT_ROWS, everything: bool = False) -> DataFrame:
    """(doc_id, held_out, score, predicted) of every row of ``docs``.

    Learns from labels whose crc32(doc_id as text) mod 3 isn't 1, or from all of
    them if ``everything``. Null and empty texts get the labelled share of good
    ones. Repeated rows are scored each; other columns are ignored; without
    labels every score is 0.5.
    """
    model = train(*labelled(docs, labels, F.lit(True) if everything else ~held_out(F.col("doc_id")), fit_rows))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            data, at = utf8(b.column(2))
            scores = []
            for i, j in blocks(at):
                raw = data[at[i] : at[j]].tobytes()
                scores.append(model.score([raw[x - at[i] : y - at[i]] for x, y in zip(at[i:j].tolist(), at[i + 1 : j + 1].tolist(), strict=True)]))
            s = np.concatenate(scores) if scores else np.zeros(0)
            yield pa.record_batch([b.column(0), b.column(1), pa.array(s), pa.array((s >= 0.5).astype(np.int32))], names=["doc_id", "held_out", "score", "predicted"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), held_out(F.col("doc_id")).alias("held_out"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(kernel(run), "doc_id long, held_out boolean, score double, predicted int")


def reject_bad(docs: DataFrame, labels: DataFrame, fit_rows: int = FIT_ROWS, threshold: float = 0.5) -> DataFrame:
    """Rows of ``docs``, all columns, whose score reaches ``threshold``; learns from all labels.

    Null and empty texts have the labelled share of good ones as their score;
    repeated rows stay or go together; without labels all rows stay; an empty
    table stays empty. Columns of ``labels`` are never columns of the result.
    """
    model = train(*labelled(docs, labels, F.lit(True), fit_rows))

    def good(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            column = b.column(b.schema.get_field_index("text"))
            data, at = utf8(column)
            keep = []
            for i, j in blocks(at):
                raw = data[at[i] : at[j]].tobytes()
                keep.append(model.score([raw[x - at[i] : y - at[i]] for x, y in zip(at[i:j].tolist(), at[i + 1 : j + 1].tolist(), strict=True)]) >= threshold)
            yield b.filter(pa.array(np.concatenate(keep) if keep else np.zeros(0, bool)))

    return docs.mapInArrow(kernel(good), docs.schema)
