"""Packing of token pieces into sequences through a configuration linear program.

Only the histogram of piece lengths (at most ``capacity`` numbers) reaches the driver. There a
fractional solution is built by multiplicative weights: lengths that lag behind in coverage get
dearer, a bounded knapsack over the prices (dynamic programming on the capacity) names the next
configuration, and it enters with the largest amount that covers no length twice. Amounts are
rounded down; what they leave is filled by best fit over the histogram, after several shares of the
solution, and the fewest sequences win. Prices are a solution of the dual program when they are divided by what the dearest
configuration of all lengths costs, so they also give a lower bound on the sequences that any packing needs. All steps cost
the same for thousand pieces or a trillion. Pieces then find their place by their rank among equally long ones.

Null and empty texts become a document of the end id alone; repeated rows each are packed; rows
with a null id keep it; which of equally long pieces takes which place is open; longer documents are cut, however
long; an empty table gives no rows.
"""

from __future__ import annotations

import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from doccurate.llm.common import docs_of, materialise, table
from doccurate.llm.tokens import rank_encoder


@dataclass(frozen=True)
class Plan:
    """Configurations: ``parts[i]`` maps length to copies, used ``times[i]`` times; bound: no packing has fewer sequences."""

    parts: list[dict[int, int]]
    times: list[int]
    bound: int = 0

    @property
    def sequences(self) -> int:
        return sum(self.times)


def _knapsack(lengths: np.ndarray, prices: np.ndarray, most: np.ndarray, capacity: int) -> dict[int, int]:
    """The dearest multiset of lengths within capacity; copies of each up to ``most`` (binary split)."""
    best = np.zeros(capacity + 1)
    items, taken = [], []
    for length, price, limit in zip(lengths.tolist(), prices.tolist(), most.tolist(), strict=True):
        k, left = 1, min(limit, capacity // length)
        while left > 0:
            k = min(k, left)
            size = k * length
            other = best[:-size] + k * price
            took = other > best[size:]
            best[size:][took] = other[took]
            items.append((length, k))
            taken.append(took)
            left, k = left - k, 2 * k
    out: dict[int, int] = {}
    room = int(best.argmax())
    for (length, k), took in zip(reversed(items), reversed(taken), strict=True):
        size = k * length
        if room >= size and took[room - size]:
            out[length] = out.get(length, 0) + k
            room -= size
    return out


def _best_fit(counts: dict[int, int], capacity: int) -> list[tuple[dict[int, int], int]]:
    """Best fit decreasing over a histogram: groups of equal bins are filled together."""
    free: dict[int, list[tuple[dict[int, int], int]]] = {}
    for length in sorted((x for x in counts if counts[x] > 0), reverse=True):
        left = counts[length]
        for room in sorted(r for r in free if r >= length):
            if not left:
                break
            groups, fits, stay = free.pop(room), room // length, []
            for parts, times in groups:
                whole = min(times, left // fits)
                if whole:
                    free.setdefault(room - fits * length, []).append((parts | {length: fits}, whole))
                    left, times = left - whole * fits, times - whole
                if times and 0 < left < fits:
                    free.setdefault(room - left * length, []).append((parts | {length: left}, 1))
                    left, times = 0, times - 1
                if times:
                    stay.append((parts, times))
            if stay:
                free.setdefault(room, []).extend(stay)
        fits = capacity // length
        if left >= fits:
            free.setdefault(capacity - fits * length, []).append(({length: fits}, left // fits))
        if left % fits:
            free.setdefault(capacity - left % fits * length, []).append(({length: left % fits}, 1))
    return [g for groups in free.values() for g in groups]


def _dual_bound(lengths: np.ndarray, total: np.ndarray, prices: np.ndarray, capacity: int) -> float:
    """Sequences that the linear program needs at least: the worth of all pieces over that of the dearest configuration of all lengths."""
    dearest = _knapsack(lengths, prices, np.minimum(total, capacity).astype(np.int64), capacity)
    worth = dict(zip(lengths.tolist(), prices.tolist(), strict=True))
    return float((prices * total).sum()) / sum(worth[x] * k for x, k in dearest.items())


def plan(counts: dict[int, int], capacity: int, rounds: int = 3000, offered: int = 160, rate: float = 0.1, rests: tuple[float, ...] = (0.95, 0.8, 0.5, 0.2, 0.02), bounds: int = 8) -> Plan:
    """Configurations that hold every counted length, at nearly as few sequences as the linear program needs.

    rounds: most pricing rounds; offered: lengths in a round's knapsack (those of the highest weight
    and a seeded draw); rate: how strongly lagging coverage raises a price (prices start above proportion for
    long pieces, which have fewer partners); rests: shares of tokens left to rounding that are tried; bounds: how many
    of the rounds' prices are tried as dual solutions, beside fixed ones.
    """
    counts = {int(k): int(n) for k, n in counts.items() if n > 0}
    whole = counts.pop(capacity, 0)
    lengths = np.array(sorted(counts), np.int64)
    total = np.array([counts[x] for x in lengths.tolist()], float)
    missing, rng = total.copy(), np.random.default_rng(7)
    tokens = float((lengths * total).sum())
    entered: list[tuple[tuple, float]] = []
    cuts, prices = {}, []  # how many entries reach each share of rests; some rounds' prices
    for k in range(rounds if len(lengths) else 0):
        live = np.flatnonzero(missing >= 1)
        left = (lengths * missing).sum()
        for rest in rests:
            if left <= rest * tokens:
                cuts.setdefault(rest, len(entered))
        if not len(live) or left <= min(rests) * tokens:
            break
        lag = missing[live] / total[live]
        size = lengths[live] / capacity
        weights = size * (1 + size) * np.exp(rate * (lag - lag.max()))
        if k % max(rounds // (10 * bounds), 1) == 0 and len(prices) < bounds and len(live) == len(lengths):
            prices.append(weights)
        if len(live) > offered:
            first = np.argpartition(-weights, offered // 4)[: offered // 4]
            drawn = rng.permutation(len(live))[: offered - offered // 4]
            some = np.unique(np.concatenate([first, drawn]))
        else:
            some = np.arange(len(live))
        at = live[some]
        chosen = _knapsack(lengths[at], weights[some], np.minimum(missing[at], capacity).astype(np.int64), capacity)
        spots = np.searchsorted(lengths, list(chosen))
        copies = np.array(list(chosen.values()), float)
        amount = float((missing[spots] / copies).min())
        missing[spots] -= amount * copies
        entered.append((tuple(sorted(chosen.items())), amount))
    # Prices in proportion to length, and step functions that count pieces above a half, a third, ... of the capacity.
    prices += [lengths / capacity, *(np.where(k * lengths % capacity, k * lengths // capacity / (k - 1), lengths / capacity) for k in range(2, 7))] if len(lengths) else []
    least = max((_dual_bound(lengths, total, w, capacity) for w in prices if w.any()), default=0.0)
    bound, best = int(np.ceil(least - 1e-6)), None
    for cut in sorted({*cuts.values(), len(entered)}, reverse=True):
        if best is None or sum(n for _, n in best) > bound:
            tried = _rounded(entered[:cut], counts, capacity)
            best = tried if best is None or sum(n for _, n in tried) < sum(n for _, n in best) else best
    found = [*([({capacity: 1}, whole)] if whole else []), *best]
    return Plan([p for p, _ in found], [n for _, n in found], bound + whole)


def _rounded(entered: list[tuple[tuple, float]], counts: dict[int, int], capacity: int) -> list[tuple[dict[int, int], int]]:
    """Whole amounts of the configurations, and best fit for the pieces that they leave."""
    amounts: dict[tuple, float] = {}
    for key, amount in entered:
        amounts[key] = amounts.get(key, 0.0) + amount
    left, out = dict(counts), []
    for key, amount in amounts.items():
        if n := int(amount + 1e-9):
            out.append((dict(key), n))
            for length, k in key:
                left[length] -= n * k
    return out + _best_fit(left, capacity)


def pieces(docs: DataFrame, vocabulary: str, capacity: int = 2048, end_id: int = 0) -> DataFrame:
    """Token pieces of each document (its ids and the end id), with the writing task and the rank in it among equal lengths."""
    columns = ["doc_id", "piece", "start", "length", "ids_crc32", "part", "rank"]
    kinds = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int64()]

    def run(batches):
        ids_of, part = rank_encoder(vocabulary), TaskContext.get().partitionId()
        end, seen = np.array([end_id], ids_of.dtype).tobytes(), np.zeros(capacity + 1, np.int64)
        for b in batches:
            rows = []
            for key, text in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                ids = np.frombuffer(ids_of.one(text.as_py()) + end, ids_of.dtype).astype("<u4")
                for k, start in enumerate(range(0, len(ids), capacity)):
                    piece = ids[start : start + capacity]
                    rows.append((key, k, start, len(piece), zlib.crc32(piece), part, int(seen[len(piece)])))
                    seen[len(piece)] += 1
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*rows, strict=True), kinds, strict=True)], columns)

    return docs_of(docs).mapInArrow(run, "doc_id long, piece int, start long, length long, ids_crc32 long, part int, rank long")


def pack(spark: SparkSession, docs: DataFrame, vocabulary: str, capacity: int = 2048, end_id: int = 0) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id and offset of every piece."""
    cut = materialise(spark, pieces(docs, vocabulary, capacity, end_id), "pieces")
    by_part = cut.groupBy("part", "length").agg(F.count("*").alias("n"))
    counts = dict(by_part.groupBy("length").agg(F.sum("n")).collect())  # capacity rows at most
    solved = plan(counts, capacity)

    # Slots of a length, in order: from ``first`` on, ``copies`` a sequence, sequences from ``base``, at ``offset``.
    slots: dict[int, list[tuple[int, int, int, int]]] = {}
    reached: dict[int, int] = {}
    base = 0
    for parts, n in zip(solved.parts, solved.times, strict=True):
        offset = 0
        for length, copies in sorted(parts.items(), reverse=True):
            slots.setdefault(length, []).append((reached.get(length, 0), copies, base, offset))
            reached[length] = reached.get(length, 0) + n * copies
            offset += length * copies
        base += n
    tables = {k: np.array(v, np.int64) for k, v in slots.items()}

    def place(batches):
        for b in batches:
            length, rank = b.column(3).to_numpy(), b.column(5).to_numpy()
            sequence, offset = np.zeros(len(length), np.int64), np.zeros(len(length), np.int64)
            for value in np.unique(length).tolist():
                rows, t = np.flatnonzero(length == value), tables[value]
                found = t[np.searchsorted(t[:, 0], rank[rows], side="right") - 1]
                within = rank[rows] - found[:, 0]
                sequence[rows] = found[:, 2] + within // found[:, 1]
                offset[rows] = found[:, 3] + within % found[:, 1] * value
            yield pa.RecordBatch.from_arrays([*b.columns[:5], pa.array(sequence), pa.array(offset)], [*b.schema.names[:5], "sequence_id", "offset"])

    before = W.partitionBy("length").orderBy("part").rowsBetween(W.unboundedPreceding, -1)
    starts = by_part.select("part", "length", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("before"))
    ranked = cut.join(starts, ["part", "length"]).select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("before") + F.col("rank")).alias("rank"))
    return ranked.mapInArrow(place, "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")


def op3_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return pack(spark, table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"))
