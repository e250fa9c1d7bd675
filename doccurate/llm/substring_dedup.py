"""Removal of long word sequences that repeat anywhere in the corpus, found by recompression.

Every document is parsed in rounds. A round names runs of equal symbols, then pairs whose left
symbol falls on one side of a seeded partition of the names and whose right symbol falls on the other. A name is a
hash of what it stands for, so the same run or pair gets the same name in every task of every machine
with nothing exchanged. After ROUNDS rounds a symbol covers 8 words at most and its ends depend on
8 words to the right and 4 to the left, hence equal word windows hold equal interior symbols at equal places.

Each window of ``width`` words picks the interior symbol whose name comes first in a hashed order
(leftmost of equals). That symbol with LEFT words before its start and RIGHT after it is a phrase
that every equal window has too. So phrases that occur once rule all their windows out, and only
windows of repeated phrases are counted, by 128-bit names, so that no two different windows meet. Windows that touch a run of RUN or more equal
symbols, whose parse may reach further, go to that count directly; an equal window whose neighbours don't extend the run
touches none, so phrases at all places that it could choose are sent for them too.

Documents are gathered into units of a few MB, written once. What is exchanged is sorted arrays of
distinct names by unit, a name once a unit, so frequent passages and large groups of copies weigh no more than
one entry a unit. Answers come back as bits.

Null, empty and short texts have nothing removed; a repeated row makes all its windows repeats; equal
words inside one text count as well; other columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from doccurate.llm.common import docs_of, materialise, slices, table
from doccurate.llm.token_store import mix

ROUNDS, RUN, LEFT, RIGHT = 3, 4, 5, 13
UNIT_BYTES, PART_BYTES = 4 << 20, 16 << 20
_BASE = np.uint64(0x5851F42D4C957F2D)
_CHECK = np.uint64(0x2545F4914F6CDD1D)


class _Names(dict):
    """Word to 64-bit name; emptied when it grows beyond a bound."""

    def __missing__(self, word: bytes) -> int:
        if len(self) >= 500_000:
            self.clear()
        self[word] = name = xxhash.xxh64_intdigest(word)
        return name


_names = _Names()


def _lane(names: np.ndarray, base: np.uint64) -> tuple[np.ndarray, np.ndarray]:
    """Powers of an odd base, and running sums of the names by the powers of its inverse."""
    with np.errstate(over="ignore"):
        powers, back = np.full(len(names) + 1, base), np.full(len(names), np.uint64(pow(int(base), -1, 1 << 64)))
        powers[:1] = back[:1] = 1
        sums = np.add.accumulate(names * np.multiply.accumulate(back))
        return np.multiply.accumulate(powers), np.concatenate([np.zeros(1, np.uint64), sums])


def _of_lane(powers: np.ndarray, sums: np.ndarray, at: np.ndarray, length: int) -> np.ndarray:
    with np.errstate(over="ignore"):
        return mix((sums[at + length] - sums[at]) * powers[at], length)


class Unit:
    """The words of some documents as names, with the parse and the windows over them."""

    def __init__(self, texts: list[bytes | None], width: int):
        self.width = width
        self.words = [t.split() if t else [] for t in texts]
        self.lengths = np.array([len(w) for w in self.words], np.int64)
        self.starts = np.concatenate([[0], np.cumsum(self.lengths)])
        n = int(self.starts[-1])
        self.names = np.fromiter((_names[x] for w in self.words for x in w), np.uint64, n)
        self.lane = _lane(self.names, _BASE)
        room = np.repeat(self.starts[1:], self.lengths) - np.arange(n)
        self.valid = np.flatnonzero(room >= width)

    def hashes(self, at: np.ndarray, length: int) -> np.ndarray:
        """A name for the ``length`` words from each position."""
        return _of_lane(*self.lane, at, length)

    def windows(self, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """128-bit names of the windows from these positions, as two halves; the second is of words named anew to another base."""
        return self.hashes(at, self.width), _of_lane(*_lane(mix(self.names, 7), _CHECK), at, self.width)

    def parse(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Names and starts of the last round's symbols, and a flag for each word inside a long run."""
        names, starts = self.names, np.arange(len(self.names))
        opens = np.zeros(len(names), bool)
        opens[self.starts[:-1][self.lengths > 0]] = True
        in_run = np.zeros(len(names), bool)
        ends = np.concatenate([starts[1:], [len(names)]])
        for k in range(ROUNDS):
            if len(names) < 2:
                break
            same = (names[1:] == names[:-1]) & ~opens[1:]
            if len(at := np.flatnonzero(same[2:] & same[1:-1] & same[:-2])):  # RUN equal symbols in a row
                heads = np.flatnonzero(np.concatenate([[True], ~same]))
                sizes = np.diff(np.concatenate([heads, [len(names)]]))
                heads, sizes = heads[sizes >= RUN], sizes[sizes >= RUN]
                keep = np.ones(len(names), bool)
                inner = np.repeat(heads, sizes) + np.arange(int(sizes.sum())) - np.repeat(np.cumsum(sizes) - sizes, sizes)
                keep[inner] = False
                keep[heads] = True
                for a, b in zip(starts[heads].tolist(), ends[heads + sizes - 1].tolist(), strict=True):
                    in_run[a:b] = True
                names = names.copy()
                with np.errstate(over="ignore"):
                    names[heads] = mix(names[heads] + sizes.astype(np.uint64) * _BASE, 70 + k)
                names, starts, opens = names[keep], starts[keep], opens[keep]
            side = (mix(names, 10 + k) >> np.uint64(40)) & np.uint64(1) == 1
            pair = np.flatnonzero(~side[:-1] & side[1:] & ~opens[1:])
            keep = np.ones(len(names), bool)
            keep[pair + 1] = False
            joined = names.copy()
            with np.errstate(over="ignore"):
                joined[pair] = mix(names[pair] * _BASE + names[pair + 1], 40 + k)
            names, starts, opens = joined[keep], starts[keep], opens[keep]
            ends = np.concatenate([starts[1:], [len(self.names)]])
        return names, starts, in_run

    def anchors(self) -> tuple[np.ndarray, np.ndarray]:
        """Of each valid window: where its chosen symbol starts (-1: it touches a run), and distinct starts, with all that such windows could choose."""
        n, reach = len(self.names), self.width - LEFT - RIGHT + 1
        names, starts, in_run = self.parse()
        order = np.full(n, np.iinfo(np.uint64).max, np.uint64)
        order[starts] = ((mix(names, 5) >> np.uint64(32)) << np.uint64(32)) | starts.astype(np.uint64)
        low, size = order, 1
        while 2 * size <= reach:
            low, size = np.minimum(low[:-size], low[size:]), 2 * size
        if size < reach:
            low = np.minimum(low[: len(low) - (reach - size)], low[reach - size :])
        chosen = (low[self.valid + LEFT] & np.uint64(0xFFFFFFFF)).astype(np.int64)
        if in_run.any():
            before = np.concatenate([[0], np.cumsum(in_run)])
            touched = before[self.valid + self.width] > before[self.valid]
            chosen[touched] = -1
            edge = np.zeros(n + 1, np.int64)
            np.add.at(edge, self.valid[touched] + LEFT, 1)
            np.add.at(edge, self.valid[touched] + LEFT + reach, -1)
            return chosen, np.union1d(chosen[~touched], np.flatnonzero(np.cumsum(edge[:-1])))
        return chosen, np.unique(chosen)

    def phrases(self, starts: np.ndarray) -> np.ndarray:
        return self.hashes(starts - LEFT, LEFT + RIGHT)


def _sorted(names: np.ndarray, checks: np.ndarray | None) -> tuple[np.ndarray, np.ndarray]:
    """The order of names (of equal names, of checks), and a flag for the first of each distinct one in that order."""
    order = np.argsort(names, kind="stable")
    step = np.concatenate([[True], np.diff(names[order]) != 0])[: len(names)]
    if checks is not None:
        other = np.concatenate([[True], np.diff(checks[order]) != 0])[: len(names)]
        if (other & ~step).any():  # a name that stands for two windows: rare
            order = np.lexsort((checks, names))
            step = np.concatenate([[True], (np.diff(names[order]) != 0) | (np.diff(checks[order]) != 0)])
    return order, step


def _numbers(names: np.ndarray, checks: np.ndarray | None = None) -> np.ndarray:
    """For each name its number among the sorted distinct ones."""
    order, step = _sorted(names, checks)
    out = np.empty(len(names), np.int64)
    out[order] = np.cumsum(step) - 1
    return out


def _pack(unit: int, edges: np.ndarray, names: np.ndarray, checks: np.ndarray | None = None) -> Iterator[dict]:
    """Sorted distinct names by range of names, with a bit for those that this unit has more than once."""
    order, step = _sorted(names, checks)
    first = np.flatnonzero(step)
    times, found = np.diff(np.append(first, len(names))), names[order[first]]
    part = np.searchsorted(edges, found, side="right") - 1
    cut = np.append(np.flatnonzero(np.diff(part, prepend=-1)), len(found)).tolist()
    for a, b in zip(cut[:-1], cut[1:], strict=True):
        told = None if checks is None else checks[order[first[a:b]]].tobytes()
        yield {"part": int(part[a]), "unit": unit, "names": found[a:b].tobytes(), "checks": told, "more": np.packbits(times[a:b] > 1).tobytes()}


def _edges(parts: int) -> np.ndarray:
    """First value of each of ``parts`` equal ranges of 64-bit names."""
    return np.array([k * (1 << 64) // parts for k in range(parts)], np.uint64)


_SENT = pa.schema([("part", pa.int32()), ("unit", pa.int64()), ("names", pa.binary()), ("checks", pa.binary()), ("more", pa.binary())])
_SENT_SQL = "part int, unit long, names binary, checks binary, more binary"


def _repeated(sent: DataFrame, parts: int) -> DataFrame:
    """unit, bits: for each name a unit sent, in order, whether the corpus has it twice or more."""

    def run(batches):
        rows = [r for b in batches for r in zip(*(c.to_pylist() for c in b.columns), strict=True)]
        if not rows:
            return
        values = [np.frombuffer(r[2], np.uint64) for r in rows]
        checks = None if rows[0][3] is None else np.concatenate([np.frombuffer(r[3], np.uint64) for r in rows])
        more = [np.unpackbits(np.frombuffer(r[4], np.uint8), count=len(v)) for r, v in zip(rows, values, strict=True)]
        back = _numbers(np.concatenate(values), checks)
        twice = np.bincount(back) + np.bincount(back, weights=np.concatenate(more)) >= 2
        flags, at, out = twice[back], 0, []
        for (part, unit, *_), v in zip(rows, values, strict=True):
            out.append({"unit": unit, "part": part, "n": len(v), "bits": np.packbits(flags[at : at + len(v)]).tobytes()})
            at += len(v)
        yield pa.RecordBatch.from_pylist(out, schema=pa.schema([("unit", pa.int64()), ("part", pa.int32()), ("n", pa.int64()), ("bits", pa.binary())]))

    told = sent.repartition(parts, "part").mapInArrow(run, "unit long, part int, n long, bits binary")
    return told.groupBy("unit").agg(F.array_sort(F.collect_list(F.struct("part", "n", "bits"))).alias("told"))


def _flags(told: list[dict] | None) -> np.ndarray:
    return np.concatenate([np.zeros(0, bool), *(np.unpackbits(np.frombuffer(x["bits"], np.uint8), count=x["n"]).astype(bool) for x in told or [])])


def _read(blob: bytes) -> pa.RecordBatch:
    with pa.ipc.open_stream(blob) as f:
        return f.read_next_batch()


def units_of(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """unit, docs: compressed batches of documents, written once."""

    def run(batches):
        first, k = TaskContext.get().partitionId() << 32, 0
        for batch in batches:
            for part in slices(batch, "text", UNIT_BYTES):
                sink = pa.BufferOutputStream()
                with pa.ipc.new_stream(sink, part.schema, options=pa.ipc.IpcWriteOptions(compression=pa.Codec("zstd", compression_level=3))) as f:
                    f.write_batch(pa.RecordBatch.from_struct_array(pa.concat_arrays([part.to_struct_array()])))
                yield pa.RecordBatch.from_arrays([pa.array([first + k], pa.int64()), pa.array([sink.getvalue().to_pybytes()], pa.binary())], ["unit", "docs"])
                k += 1

    return materialise(spark, docs_of(docs).mapInArrow(run, "unit long, docs binary"), "units")


def repeated_words(spark: SparkSession, docs: DataFrame, width: int = 35, keep_text: bool = False) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256, runs of removed words ([from, to)) and, if asked for, the kept text."""
    if width - LEFT - RIGHT + 1 < 1 << ROUNDS:
        raise ValueError(f"width must be {LEFT + RIGHT - 1 + (1 << ROUNDS)} at least")
    units = units_of(spark, docs)
    size = units.agg(F.sum(F.octet_length("docs"))).first()[0] or 0
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), size // PART_BYTES, 1)

    def texts(blob: bytes) -> list[bytes | None]:
        return _read(blob).column(1).cast(pa.binary()).to_pylist()

    def send_phrases(batches):
        edges = _edges(parts)
        for b in batches:
            for number, blob in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                unit = Unit(texts(blob), width)
                if len(unit.valid):
                    if out := list(_pack(number, edges, unit.phrases(unit.anchors()[1]))):
                        yield pa.RecordBatch.from_pylist(out, schema=_SENT)

    def candidates(batches):
        """Windows whose phrase repeats: a bit a valid window, and the sorted names by range."""
        schema = pa.schema([("unit", pa.int64()), ("windows", pa.binary()), ("sent", pa.list_(pa.struct([f for f in _SENT if f.name != "unit"])))])
        edges = _edges(parts)
        for b in batches:
            for number, blob, told in zip(*(c.to_pylist() for c in b.columns), strict=True):
                unit = Unit(texts(blob), width)
                if not len(unit.valid):
                    continue
                chosen, some = unit.anchors()
                names = unit.phrases(some)
                again = _flags(told)[_numbers(names)] if len(some) else np.zeros(0, bool)
                hot = chosen < 0
                if len(some):
                    hot |= again[np.minimum(np.searchsorted(some, chosen), len(some) - 1)] & (chosen >= 0)
                if hot.any():
                    out = [{k: v for k, v in x.items() if k != "unit"} for x in _pack(number, edges, *unit.windows(unit.valid[hot]))]
                    yield pa.RecordBatch.from_pylist([{"unit": number, "windows": zlib.compress(np.packbits(hot).tobytes(), 1), "sent": out}], schema=schema)

    def finish(batches):
        fields = [("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_removed", pa.int64()), ("kept_sha256", pa.string()), ("runs", pa.list_(pa.list_(pa.int32())))]
        schema = pa.schema(fields + [("kept_text", pa.string())] * keep_text)
        for b in batches:
            for blob, windows, told in zip(*(c.to_pylist() for c in b.columns), strict=True):
                batch = _read(blob)
                unit = Unit(texts(blob), width)
                edge = np.zeros(len(unit.names) + 1, np.int64)
                if windows:
                    hot = unit.valid[np.unpackbits(np.frombuffer(zlib.decompress(windows), np.uint8), count=len(unit.valid)).astype(bool)]
                    at = hot[_flags(told)[_numbers(*unit.windows(hot))]]
                    np.add.at(edge, at, 1)
                    np.add.at(edge, at + width, -1)
                gone, rows = np.cumsum(edge[:-1]) > 0, []
                for key, words, start in zip(batch.column(0).to_pylist(), unit.words, unit.starts.tolist(), strict=False):
                    flags = gone[start : start + len(words)]
                    if flags.any():
                        kept = b" ".join([w for w, g in zip(words, flags.tolist(), strict=True) if not g])
                        step = np.diff(np.concatenate([[0], flags.astype(np.int8), [0]]))
                        runs = np.stack([np.flatnonzero(step == 1), np.flatnonzero(step == -1)], 1).tolist()
                    else:
                        kept, runs = b" ".join(words), []
                    rows.append({"doc_id": key, "n_words": len(words), "n_removed": int(flags.sum()), "kept_sha256": hashlib.sha256(kept).hexdigest(), "runs": runs} | ({"kept_text": kept.decode()} if keep_text else {}))
                yield pa.RecordBatch.from_pylist(rows, schema=schema)

    told = _repeated(units.mapInArrow(send_phrases, _SENT_SQL), parts)
    found = units.join(told, "unit", "left").select("unit", "docs", "told")
    found = materialise(spark, found.mapInArrow(candidates, "unit long, windows binary, sent array<struct<part: int, names: binary, checks: binary, more: binary>>"), "windows")
    sent = found.select("unit", F.inline("sent")).select("part", "unit", "names", "checks", "more")
    told = found.select("unit", "windows").join(_repeated(sent, parts), "unit")
    kept = ", kept_text string" if keep_text else ""
    return units.join(told, "unit", "left").select("docs", "windows", "told").mapInArrow(finish, f"doc_id long, n_words long, n_removed long, kept_sha256 string, runs array<array<int>>{kept}")


def op1_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repeated_words(spark, table(spark, sf_dir, "documents")).drop("runs")
