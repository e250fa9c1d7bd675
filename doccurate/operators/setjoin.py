"""Exact similarity join of texts on their word n-gram sets, by hashed prefixes; whole sets are compared for pairs only."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Rows whose grams are counted at least, the share of all rows, the count and number of frequent grams.
SAMPLE, SHARE, FREQUENT, MOST = 20_000, 16, 3, 500_000
#: Rows of a gram compared at once; words of 64 bits, one for as many row numbers, that are broadcast at most.
BLOCK, WORDS = 1024, 1 << 20

Keep = Callable[[DataFrame], DataFrame]


def among(rows: DataFrame, some: DataFrame, keep: Keep) -> DataFrame:
    """The rows whose number ``row`` is some's only column, picked by a bit a row, so that texts are not dealt out for it."""
    (own,) = some.columns
    words = keep(some.groupBy(F.shiftright(own, 6).alias("at")).agg(F.bit_or(F.expr(f"shiftleft(1L, cast({own} & 63L as int))")).alias("bits")))
    if words.count() > WORDS:
        return rows.join(some.select(F.col(own).alias("row")).distinct(), "row", "left_semi")
    told = rows.join(F.broadcast(words), F.shiftright("row", 6) == F.col("at"))
    return told.filter("shiftright(bits, cast(row & 63L as int)) & 1L = 1L").select(*rows.columns)


def gram_set(words: bytes, n: int) -> set[bytes]:
    """Windows of n words of a normal form; none if it is shorter."""
    found = [w for w in words.split(b" ") if w]
    joined, ends = b" ".join(found), np.cumsum([0, *(len(w) + 1 for w in found)]).tolist()
    return {joined[ends[k] : ends[k + n] - 1] for k in range(len(found) - n + 1)}


def hashed(grams: set[bytes]) -> np.ndarray:
    return np.fromiter((xxhash.xxh64_intdigest(g) for g in grams), np.uint64, len(grams)).view(np.int64)


def _open(size: np.ndarray, place: np.ndarray, i: np.ndarray, j: np.ndarray, least: float) -> np.ndarray:
    """Which pairs sizes and places leave open: the common grams are the first common one, where an alike pair is open, and later ones."""
    a, b = size[i], size[j]
    left = np.minimum(a - place[i], b - place[j])
    return (left >= np.ceil(least / (1 + least) * (a + b) - 1e-9)) & (np.minimum(a, b) >= least * np.maximum(a, b) - 1e-9)


def _of_grams(gram: np.ndarray, row: np.ndarray, size: np.ndarray, place: np.ndarray, least: float) -> Iterator[pa.RecordBatch]:
    """a < b: open pairs of rows that share a gram (grams are sorted and whole); grams of equally many rows go at once."""

    def told(i, j):
        may = (row[i] != row[j]) & _open(size, place, i, j, least)
        i, j = row[i[may]], row[j[may]]
        return pa.RecordBatch.from_arrays([pa.array(np.minimum(i, j)), pa.array(np.maximum(i, j))], ["a", "b"])

    heads = np.concatenate([[0], np.flatnonzero(gram[1:] != gram[:-1]) + 1, [len(gram)]])
    times = np.diff(heads)
    for m in np.unique(times[times > 1]).tolist():
        starts = heads[:-1][times == m]
        if m <= 16:
            for i in range(m):
                for j in range(i + 1, m):
                    yield told(starts + i, starts + j)
            continue
        for start in starts.tolist():
            for p in range(0, m, BLOCK):
                for q in range(p, m, BLOCK):
                    i, j = np.meshgrid(np.arange(p, min(p + BLOCK, m)), np.arange(q, min(q + BLOCK, m)), indexing="ij")
                    once = i < j
                    yield told(start + i[once], start + j[once])


def _candidates(spread: DataFrame, least: float) -> DataFrame:
    """a < b: distinct pairs that spread(gram, row, size, place) leaves open."""

    def run(batches):
        rest = [np.zeros(0, np.int64) for _ in range(4)]
        for batch in batches:
            got = [np.concatenate([r, c.to_numpy()]) for r, c in zip(rest, batch.columns, strict=True)]
            if not len(got[0]):
                continue
            cut = int(np.searchsorted(got[0], got[0][-1]))  # the last gram can go on in the next batch
            rest = [c[cut:] for c in got]
            if cut:
                yield from _of_grams(*(c[:cut] for c in got), least)
        if len(rest[0]):
            yield from _of_grams(*rest, least)

    return spread.repartition("gram").sortWithinPartitions("gram").mapInArrow(run, "a long, b long").distinct()


def _prefixes(rows: DataFrame, count: int, n: int, least: float) -> DataFrame:
    """gram, row, size, place of each row's first grams, in an order that puts those last that are frequent in a sample."""
    share = min(1.0, max(SAMPLE / max(count, 1), 1 / SHARE))

    def grams(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([np.zeros(0, np.int64), *(hashed(gram_set(w, n)) for w in b.column(0).cast(pa.binary()).to_pylist())]))], ["gram"])

    some = rows.filter(F.pmod(F.xxhash64("row"), F.lit(1 << 20)) < int(share * (1 << 20))).select("words")
    often = some.mapInArrow(grams, "gram long").groupBy("gram").count().filter(F.col("count") >= FREQUENT).orderBy(F.desc("count"), "gram").limit(MOST).toPandas().sort_values("gram")
    sent = rows.sparkSession.sparkContext.broadcast((often["gram"].to_numpy(np.int64), often["count"].to_numpy(np.int64)))

    def run(batches):
        frequent, times = sent.value
        for b in batches:
            for part in range(0, b.num_rows, 256):
                out = []
                for row, words in zip(b.column(0)[part : part + 256].to_pylist(), b.column(1)[part : part + 256].cast(pa.binary()).to_pylist(), strict=True):
                    own = np.sort(hashed(gram_set(words, n)))
                    rank = np.zeros(len(own), np.int64)
                    if len(frequent) and len(own):
                        at = np.minimum(np.searchsorted(frequent, own), len(frequent) - 1)
                        rank = np.where(frequent[at] == own, times[at], 0)
                    first = own[np.lexsort((own, rank))][: len(own) - int(np.ceil(len(own) * least - 1e-9)) + 1 if len(own) else 0]
                    out.append((first, np.full(len(first), row), np.full(len(first), len(own)), np.arange(len(first))))
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([np.zeros(0, np.int64), *c])) for c in zip(*out, strict=True)], ["gram", "row", "size", "place"])

    return rows.select("row", "words").mapInArrow(run, "gram long, row long, size long, place long")


def alike(rows: DataFrame, count: int, n: int, threshold: float, keep: Keep) -> DataFrame:
    """id, other, similarity of the rows(row, id, words) whose n-gram sets have this Jaccard at least (to six places), exactly.

    Equal grams have equal hashes, so prefixes of hashes lose no pair; sets are compared as they are. A pair moves one text.
    """
    least = threshold - 1e-6
    pairs = keep(_candidates(_prefixes(rows, count, n, least), least))
    right = pairs.join(among(rows, pairs.select("b"), keep).withColumnRenamed("row", "b"), "b").select("a", "b", "id", "words")
    left = among(rows, pairs.select("a"), keep).select(F.col("row").alias("a"), F.lit(None).cast("long").alias("b"), "id", "words")
    # By now no event of the writing refers to the prefixes any more: executors delete their shuffle files before texts move.
    rows.sparkSession.sparkContext._jvm.System.gc()
    kind = rows.schema["id"].dataType.simpleString()

    def run(batches):
        own, mine = set(), None
        for batch in batches:
            out = []
            for b, one, words in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), batch.column(3).cast(pa.binary()).to_pylist(), strict=True):
                found = gram_set(words, n)
                if b is None:
                    own, mine = found, one
                else:
                    out.append((mine, one, len(own & found), len(own) + len(found)))
            ids = [pa.array([x[k] for x in out], batch.schema.field(2).type) for k in (0, 1)]
            yield pa.RecordBatch.from_arrays([*ids, *(pa.array([x[k] for x in out], pa.int64()) for k in (2, 3))], ["x", "y", "common", "total"])

    told = right.union(left).repartition("a").sortWithinPartitions("a", F.col("b").asc_nulls_first()).mapInArrow(run, f"x {kind}, y {kind}, common long, total long")
    measured = told.select(F.least("x", "y").alias("id"), F.greatest("x", "y").alias("other"), F.round(F.col("common") / (F.col("total") - F.col("common")), 6).alias("similarity"))
    return measured.filter((F.col("similarity") >= threshold) & (F.col("id") < F.col("other")))
