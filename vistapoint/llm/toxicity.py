"""Toxicity: logistic regression over hashed word n-grams and skip-grams, fitted by FTRL-proximal.

Words are runs of letters, digits and bytes above 0x7F with A-Z lower-cased. Features are the distinct words, the stems of
longer words (their first bytes, since inflection spreads one insult over many forms), pairs of neighbours and pairs with
one word between, hashed to ``slots``. Each coordinate has its own learning rate; the L1 term
keeps most weights at exactly zero, so the model is a short list of (slot, weight) that is broadcast with the scoring task.
It is fitted on a bounded sample of labelled rows; scoring covers all rows and whole texts.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import wordhash as wh
from .storage import frugal

#: Labelled rows that a model is fitted on at most: those with the smallest hashes of their ids.
MAX_TRAINING_ROWS = 12_000
#: Bytes of features that the learner holds at most; labelled rows beyond, in the order of their ids' hashes, are not learnt from.
MAX_TRAINING_BYTES = 256_000_000
SLOTS = 1 << 20
STEM_BYTES = 4

SEPARATORS = np.ones(256, bool)
SEPARATORS[48:58] = SEPARATORS[65:91] = SEPARATORS[97:123] = SEPARATORS[128:] = False


@dataclass(frozen=True)
class Settings:
    """FTRL-proximal: alpha and beta set the per-coordinate rates, l1 and l2 the penalties."""

    alpha: float = 2.0
    beta: float = 1.0
    l1: float = 4.0
    l2: float = 0.0
    epochs: int = 5
    slots: int = SLOTS


@dataclass
class Model:
    """Non-zero weights by slot; without training rows it has none and scores 0.5."""

    slots: int = SLOTS
    bias: float = 0.0
    at: np.ndarray = field(default_factory=lambda: np.zeros(0, np.int32))
    weight: np.ndarray = field(default_factory=lambda: np.zeros(0, np.float32))

    def dense(self) -> np.ndarray:
        out = np.zeros(self.slots, np.float32)
        out[self.at] = self.weight
        return out


def feature_slots(data: np.ndarray, offsets: np.ndarray, slots: int) -> tuple[np.ndarray, np.ndarray]:
    """The distinct feature slots of each row, and where each row's begin."""
    words, bounds = wh.word_hashes(data, offsets, separators=SEPARATORS)
    row = np.repeat(np.arange(len(bounds) - 1, dtype=np.int64), np.diff(bounds))
    parts = [(row, words)]
    for gap, odd in ((1, 0x9E3779B97F4A7C15), (2, 0xC2B2AE3D27D4EB4F)):
        if len(words) > gap:
            same = row[gap:] == row[:-gap]
            parts.append((row[gap:][same], wh.mix(words[:-gap][same] * wh.U64(odd) + words[gap:][same])))
    stems, stem_bounds = wh.stem_hashes(data, offsets, STEM_BYTES, SEPARATORS)
    parts.append((np.repeat(np.arange(len(bounds) - 1, dtype=np.int64), np.diff(stem_bounds)), stems))
    keys = np.concatenate([(r << 32) | (h % wh.U64(slots)).astype(np.int64) for r, h in parts])
    keys.sort()
    if len(keys):
        keys = keys[np.concatenate([[True], keys[1:] != keys[:-1]])]
    return (keys & 0xFFFFFFFF).astype(np.int32), np.searchsorted(keys, np.arange(len(bounds), dtype=np.int64) << 32)


class Ftrl:
    """The learner's state: one z and n for each slot, and for the bias, which has no L1 term."""

    def __init__(self, settings: Settings) -> None:
        self.s = settings
        self.z, self.n = np.zeros(settings.slots + 1), np.zeros(settings.slots + 1)

    def weights(self, at: np.ndarray) -> np.ndarray:
        s, z = self.s, self.z[at]
        free = np.where(at == s.slots, z, np.sign(z) * np.maximum(np.abs(z) - s.l1, 0))
        return -free / ((s.beta + np.sqrt(self.n[at])) / s.alpha + s.l2)

    def learn(self, slots: np.ndarray, label: int) -> None:
        at = np.append(slots, self.s.slots)
        w = self.weights(at)
        slope = 1 / (1 + np.exp(-np.clip(w.sum(), -35, 35))) - label
        n = self.n[at]
        self.z[at] += slope - (np.sqrt(n + slope * slope) - np.sqrt(n)) / self.s.alpha * w
        self.n[at] = n + slope * slope


def fit(docs: DataFrame, labels: DataFrame, settings: Settings = Settings(), max_rows: int = MAX_TRAINING_ROWS, max_bytes: int = MAX_TRAINING_BYTES) -> Model:  # noqa: B008
    """Fit on the texts of ``docs`` (doc_id, text) that ``labels`` (doc_id, toxic) covers.

    Of the labelled ids, the ``max_rows`` with the smallest hashes are used, so the model is the same for every order and
    partitioning. Null ids and labels are left out; an id with both labels counts as toxic; of several texts of one id one
    counts. The bounded id list is broadcast to one pass over ``docs``; one task runs the sequential learner, on at most
    ``max_bytes`` of features, so that very long texts cannot fill it either.
    """
    chosen = labels.where(F.col("doc_id").isNotNull() & F.col("toxic").isNotNull()).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    chosen = chosen.select("doc_id", F.col("toxic").cast("int").alias("toxic"), F.xxhash64("doc_id").alias("turn")).orderBy("turn", "doc_id").limit(max_rows)

    def features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = []
            for _, data, offsets in wh.byte_rows(batch.column(2)):
                at, bounds = feature_slots(data, offsets, settings.slots)
                found += [at[a:b].tobytes() for a, b in zip(bounds[:-1], bounds[1:], strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(found, pa.binary())], ["turn", "toxic", "at"])

    def learn(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows, held = [], 0
        for batch in batches:
            for x, y in zip(batch.column(2).to_pylist(), batch.column(1).to_pylist(), strict=True):
                held += len(x)
                if held <= max_bytes:
                    rows.append((np.frombuffer(x, np.int32), y))
        learner = Ftrl(settings)
        for _ in range(settings.epochs if rows else 0):
            for at, label in rows:
                learner.learn(at, label)
        w = learner.weights(np.arange(settings.slots + 1))
        at = np.flatnonzero(w)
        yield pa.RecordBatch.from_arrays([pa.array(at, pa.int64()), pa.array(w[at], pa.float64())], ["slot", "weight"])

    texts = docs.select("doc_id", docs["text"].cast("string").alias("text")).join(F.broadcast(chosen), "doc_id").select("turn", "toxic", "text")
    rows = texts.mapInArrow(frugal(features), "turn long, toxic int, at binary").groupBy("turn", "toxic").agg(F.min("at").alias("at"))
    seen = rows.select("turn", "toxic", "at").repartition(1).sortWithinPartitions("turn", "at")
    rows = seen.mapInArrow(frugal(learn), "slot long, weight double").toPandas()
    own = rows[rows["slot"] < settings.slots]
    return Model(settings.slots, float(rows.loc[rows["slot"] == settings.slots, "weight"].sum()), own["slot"].to_numpy(np.int32), own["weight"].to_numpy(np.float32))


def score(docs: DataFrame, model: Model) -> DataFrame:
    """``docs`` with a column score (0 to 1, double) from each whole text; null and empty texts have the bias alone.

    Other columns pass through untouched; a column named score is replaced.
    """
    names = [c for c in docs.columns if c != "score"]
    schema = docs.select([docs[c] for c in names]).schema
    at = names.index("text")
    is_string = dict(docs.dtypes)["text"] == "string"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        weights = model.dense()
        for batch in batches:
            column = batch.column(at) if is_string else batch.column(at).cast(pa.string())
            out = np.zeros(len(column))
            for first, data, offsets in wh.byte_rows(column):
                slots, bounds = feature_slots(data, offsets, model.slots)
                logits = wh.row_reduce(np.add, weights[slots].astype(np.float64), bounds, 0)
                out[first : first + len(logits)] = 1 / (1 + np.exp(-np.clip(logits + model.bias, -35, 35)))
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(out, pa.float64())], [*batch.schema.names, "score"])

    return docs.select([docs[c] for c in names]).mapInArrow(frugal(run), schema.add("score", "double"))


def remainder(doc_id: str = "doc_id") -> Column:
    """crc32 of the id as text, modulo 3: rows with 1 are held out of training. Null ids give null."""
    return F.crc32(F.col(doc_id).cast("string").cast("binary")) % 3
