"""Toxicity scores: FTRL-proximal logistic regression over hashed word n-grams and skip-grams.

Features of a text are its words (letters and digits, ASCII lower case), neighbouring pairs and pairs with one
word between, each hashed to one of 2**BITS coordinates and counted once. Every coordinate has its own
learning rate, and the L1 term leaves most weights at zero, so the model is a short list of (coordinate,
weight) pairs that is broadcast. It is trained in one task on at most about ``most`` labelled
rows, chosen by a hash of their id; scoring covers all rows.

Null and empty texts have the features of no word, so their score is the bias's; repeated rows have equal
scores; where one id has several labels, the greatest counts; texts of any length are scored whole; labels without a document and null labels are left out; without any labels every score is 0.5; other
columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from doccurate.llm.common import docs_of, slices, table
from doccurate.llm.decontaminate import words_of
from doccurate.llm.token_store import mix

BITS, MOST_ROWS = 18, 16_000
_SALTS = (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9)


class _Hashes(dict):
    def __missing__(self, word: bytes) -> int:
        if len(self) >= 500_000:
            self.clear()
        self[word] = h = xxhash.xxh64_intdigest(word)
        return h


_hashes = _Hashes()


@dataclass(frozen=True)
class Model:
    """Non-zero weights; coordinate 2**BITS is the bias."""

    at: np.ndarray
    weights: np.ndarray

    def dense(self) -> np.ndarray:
        out = np.zeros((1 << BITS) + 1)
        out[self.at] = self.weights
        return out


def features(texts: list[bytes | None]) -> tuple[np.ndarray, np.ndarray]:
    """Coordinates of all texts, with repeats, and the text number of each."""
    words = [words_of(t) for t in texts]
    lengths = np.array([len(w) for w in words], np.int64)
    n = int(lengths.sum())
    h = np.fromiter((_hashes[x] for w in words for x in w), np.uint64, n)
    doc = np.repeat(np.arange(len(texts)), lengths)
    parts, docs = [h], [doc]
    with np.errstate(over="ignore"):
        for gap, salt in ((1, _SALTS[0]), (2, _SALTS[1])):
            if n > gap:
                same = doc[gap:] == doc[:-gap]
                parts.append((h[:-gap] * np.uint64(salt) + h[gap:])[same])
                docs.append(doc[gap:][same])
    return (mix(np.concatenate(parts), 3) >> np.uint64(64 - BITS)).astype(np.int64), np.concatenate(docs)


def ftrl(rows: list[tuple[np.ndarray, int]], epochs: int = 3, alpha: float = 1.0, beta: float = 1.0, l1: float = 4.0, l2: float = 0.1) -> Model:
    """Weights after ``epochs`` passes over (distinct coordinates, label) rows, one update a row."""
    size = (1 << BITS) + 1
    z, n = np.zeros(size), np.zeros(size)
    strength = np.full(size, l1)
    strength[-1] = 0  # the bias is not driven to zero
    for _ in range(epochs):
        for at, label in rows:
            at = np.append(at, size - 1)
            zi, ni = z[at], n[at]
            w = np.where(np.abs(zi) > strength[at], (np.sign(zi) * strength[at] - zi) / ((beta + np.sqrt(ni)) / alpha + l2), 0.0)
            g = 1 / (1 + np.exp(-min(max(w.sum(), -35.0), 35.0))) - label
            grown = ni + g * g
            z[at] = zi + g - (np.sqrt(grown) - np.sqrt(ni)) / alpha * w
            n[at] = grown
    at = np.flatnonzero(np.abs(z) > strength)
    return Model(at, (np.sign(z[at]) * strength[at] - z[at]) / ((beta + np.sqrt(n[at])) / alpha + l2))


def train(spark: SparkSession, docs: DataFrame, labels: DataFrame, label: str = "toxic", most: int = MOST_ROWS, **options) -> Model:
    """Learn from labels(doc_id, label); most: bound on the labelled rows that are used, about."""
    known = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(label).cast("int").alias("label")).dropna()
    total = known.count()
    if total > most:
        known = known.filter(F.shiftrightunsigned(F.xxhash64("doc_id"), 2) < (most << 62) // total)
    known = known.groupBy("doc_id").agg(F.max("label").alias("label"))
    marked = docs_of(docs).join(F.broadcast(known), "doc_id").select("doc_id", "text", "label")  # ``most`` small rows

    def hashed(batches):
        for batch in batches:
            for part in slices(batch, "text", 1 << 20):
                at, doc = features(part.column(1).cast(pa.binary()).to_pylist())
                pairs = np.unique(doc << 32 | at)
                cut = np.searchsorted(pairs >> 32, np.arange(part.num_rows + 1))
                blobs = [(pairs[a:b] & 0xFFFFFFFF).astype("<u4").tobytes() for a, b in zip(cut[:-1], cut[1:], strict=True)]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(2), pa.array(blobs, pa.binary())], ["doc_id", "label", "at"])

    def fit(batches):
        rows = [(np.frombuffer(at, "<u4").astype(np.int64), int(y)) for b in batches for y, at in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True)]
        if rows:
            model = ftrl(rows, **options)
            yield pa.RecordBatch.from_arrays([pa.array([model.at.astype("<i8").tobytes()]), pa.array([model.weights.astype("<f8").tobytes()])], ["at", "weights"])

    sample = marked.mapInArrow(hashed, "doc_id long, label int, at binary").repartition(1)
    found = sample.sortWithinPartitions(F.xxhash64("doc_id", F.lit(1)), "doc_id", "at").select("label", "at").mapInArrow(fit, "at binary, weights binary").collect()
    if not found:
        return Model(np.zeros(0, np.int64), np.zeros(0))
    return Model(np.frombuffer(found[0].at, "<i8"), np.frombuffer(found[0].weights, "<f8"))


def scored(docs: DataFrame, model: Model, into: str = "score") -> DataFrame:
    """docs with the chance of label 1, from its ``text``, as a last column ``into``, which replaces one of that name."""
    docs = docs.select(*(F.col(f"`{c}`") for c in docs.columns if c.lower() != into.lower()))
    spark, schema, where = docs.sparkSession, docs.schema, docs.columns.index("text")
    sent = spark.sparkContext.broadcast(model)

    def run(batches):
        w = sent.value.dense()
        for batch in batches:
            for part in slices(batch, "text", 2 << 20):
                at, doc = features(part.column(where).cast(pa.binary()).to_pylist())
                live = w[at] != 0
                pairs = np.unique(doc[live] << 32 | at[live])
                total = np.bincount(pairs >> 32, weights=w[pairs & 0xFFFFFFFF], minlength=part.num_rows) + w[-1]
                score = 1 / (1 + np.exp(-np.clip(total, -35, 35)))
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(score)], [*part.schema.names, into])

    from pyspark.sql.types import DoubleType, StructType

    return docs.mapInArrow(run, StructType([*schema.fields]).add(into, DoubleType()))


def held_out(doc_id="doc_id"):
    """Rows that are kept from training: crc32 of the id as text is 2 modulo 4."""
    return F.coalesce(F.crc32(F.col(doc_id).cast("string").cast("binary")) % 4 == 2, F.lit(False))


def op2_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    model = train(spark, docs, labels.filter(~held_out()))
    rows = scored(docs_of(docs), model)
    return rows.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"))
