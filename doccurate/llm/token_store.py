"""Token ids in binary shards with a minimal perfect hash index.

A shard is two files. ``ids-N.bin`` holds raw little-endian ids, documents one after another
in ascending key order. ``idx-N.npz`` holds the documents' keys and offsets, the levels of a minimal
perfect hash over the distinct keys, and per slot the entry number and a 32-bit fingerprint of the key,
so that a lookup takes constant time and unknown keys are turned away. ``manifest.json`` holds shard totals.

Null and empty texts are documents of the end id alone. Rows with a null key come first and
aren't indexed; equal keys stand together and a lookup gives all of them. An empty table gives empty shards.
"""

from __future__ import annotations

import io
import json
import uuid
import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyarrow import fs
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from doccurate.llm.common import docs_of, shared_dir, table
from doccurate.llm.tokens import rank_encoder

#: Bytes of text to a shard, and bytes of ids that are read back at once.
SHARD_BYTES, READ_BYTES = 256 << 20, 8 << 20
_GOLDEN = np.uint64(0x9E3779B97F4A7C15)


def mix(keys: np.ndarray, salt: int) -> np.ndarray:
    """A 64-bit finaliser (xor-shift and multiply) of each key under a salt."""
    with np.errstate(over="ignore"):
        x = keys.astype(np.uint64) + np.uint64(salt + 1) * _GOLDEN
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        return x ^ (x >> np.uint64(31))


class PerfectHash:
    """Minimal perfect hash by levels of bit arrays; collided keys go one level down."""

    GAMMA, LEVELS = 2.0, 40

    def __init__(self, sizes: np.ndarray, bits: np.ndarray, rest: np.ndarray):
        self.sizes, self.bits, self.rest = sizes, bits, rest
        self.offsets = np.concatenate([[0], np.cumsum(sizes)])
        words = np.zeros(-(-len(bits) // 8) * 8, np.uint8)
        words[: len(bits)] = bits
        self.words = words.view("<u8")
        self.ranks = np.concatenate([[0], np.cumsum(np.bitwise_count(self.words))]).astype(np.int64)

    @classmethod
    def build(cls, keys: np.ndarray) -> PerfectHash:
        sizes, flags = [], []
        while len(keys) and len(sizes) < cls.LEVELS:
            m = max(64, int(cls.GAMMA * len(keys)))
            at = mix(keys, len(sizes)) % np.uint64(m)
            alone = np.bincount(at.astype(np.int64), minlength=m) == 1
            sizes.append(m)
            flags.append(alone)
            keys = keys[~alone[at.astype(np.int64)]]
        bits = np.packbits(np.concatenate(flags), bitorder="little") if flags else np.zeros(0, np.uint8)
        return cls(np.array(sizes, np.int64), bits, np.sort(keys))

    def slots(self, keys: np.ndarray) -> np.ndarray:
        """Slot of each key; a key that was not indexed gets any slot, or -1."""
        out, open_ = np.full(len(keys), -1, np.int64), np.arange(len(keys))
        for level, m in enumerate(self.sizes.tolist()):
            at = (mix(keys[open_], level) % np.uint64(m)).astype(np.int64) + self.offsets[level]
            word, bit = self.words[at >> 6], (at & 63).astype(np.uint64)
            hit = (word >> bit) & np.uint64(1) == 1
            below = np.bitwise_count(word & ((np.uint64(1) << bit) - np.uint64(1))).astype(np.int64)
            out[open_[hit]] = (self.ranks[at >> 6] + below)[hit]
            open_ = open_[~hit]
        if len(open_) and len(self.rest):
            at = np.minimum(np.searchsorted(self.rest, keys[open_]), len(self.rest) - 1)
            hit = self.rest[at] == keys[open_]
            out[open_[hit]] = self.ranks[-1] + at[hit]
        return out


def _files(folder: str) -> tuple[fs.FileSystem, str]:
    return fs.FileSystem.from_uri(folder) if "://" in folder else (fs.LocalFileSystem(), folder)


class _Put:
    """A file written under a name of this attempt and moved to its own when it is whole."""

    def __init__(self, folder: str, name: str):
        self.system, root = _files(folder)
        self.final, self.now = f"{root}/{name}", f"{root}/.{name}-{uuid.uuid4().hex}"
        self.stream = self.system.open_output_stream(self.now)

    def close(self):
        self.stream.close()
        self.system.move(self.now, self.final)


def write_store(spark: SparkSession, docs: DataFrame, vocabulary: str, folder: str, end_id: int, shards: int | None = None) -> dict:
    """Encode docs(doc_id, text) into shards of folder, ascending by doc_id over all shards; gives the manifest."""
    rows = docs_of(docs)
    n = shards or max(int(spark.conf.get("spark.sql.shuffle.partitions")), (rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0) // SHARD_BYTES)
    system, root = _files(folder)
    system.create_dir(root, recursive=True)

    def run(batches):
        number, enc = TaskContext.get().partitionId(), rank_encoder(vocabulary)
        end, width = np.array([end_id], enc.dtype).tobytes(), enc.dtype.itemsize
        put = _Put(folder, f"ids-{number}.bin")
        keys, lengths = [], []
        for b in batches:
            keys += b.column(0).to_pylist()
            for text in b.column(1):
                payload = enc.one(text.as_py()) + end
                put.stream.write(payload)
                lengths.append(len(payload) // width)
        put.close()
        known = np.array([k is not None for k in keys], bool)
        values = np.array([k or 0 for k in keys], np.int64)
        at = np.flatnonzero(known)
        distinct, first = np.unique(values[at], return_index=True)
        hash_ = PerfectHash.build(distinct.view(np.uint64))
        slot = hash_.slots(distinct.view(np.uint64))
        entry, mark = np.zeros(len(distinct), np.uint32), np.zeros(len(distinct), np.uint32)
        entry[slot], mark[slot] = at[first] if len(at) else 0, mix(distinct, 99) >> np.uint64(32)
        blob = io.BytesIO()
        starts = np.concatenate([[0], np.cumsum(np.array(lengths, np.int64))]).astype(np.int64)
        np.savez(blob, keys=values, known=known, starts=starts, sizes=hash_.sizes, bits=hash_.bits, rest=hash_.rest, entry=entry, mark=mark)
        put = _Put(folder, f"idx-{number}.npz")
        put.stream.write(blob.getvalue())
        put.close()
        low, high = (min(k for k in keys if k is not None), max(k for k in keys if k is not None)) if known.any() else (None, None)
        yield pa.RecordBatch.from_pylist([{"shard": number, "docs": len(keys), "tokens": int(starts[-1]), "low": low, "high": high, "width": width}], schema=found)

    found = pa.schema([("shard", pa.int32()), ("docs", pa.int64()), ("tokens", pa.int64()), ("low", pa.int64()), ("high", pa.int64()), ("width", pa.int32())])
    # Rows of one key are split over shards by the start of their text, and equal ones by where they come from.
    split = rows.select("doc_id", "text", F.substring("text", 1, 32).alias("head"), F.monotonically_increasing_id().alias("place"))
    ordered = split.repartitionByRange(n, "doc_id", "head", "place").select("doc_id", "text").sortWithinPartitions("doc_id", "text")
    rows = ordered.mapInArrow(run, "shard int, docs long, tokens long, low long, high long, width int").collect()  # one row a shard
    made = sorted((r.asDict() for r in rows), key=lambda r: r["shard"])
    total = 0
    for r in made:
        r["before"], total = total, total + r["tokens"]
    put = _Put(folder, "manifest.json")
    put.stream.write(json.dumps({"shards": made, "tokens": total}).encode())
    put.close()
    return {"shards": made, "tokens": total}


class Shard:
    """One opened shard: scan in order, or look keys up."""

    def __init__(self, folder: str, number: int, width: int):
        system, root = _files(folder)
        with system.open_input_stream(f"{root}/idx-{number}.npz") as f:
            self.index = dict(np.load(io.BytesIO(f.read())))
        self.hash = PerfectHash(self.index["sizes"], self.index["bits"], self.index["rest"])
        self.dtype, self.starts = np.dtype(f"<u{width}"), self.index["starts"]
        self.file = system.open_input_file(f"{root}/ids-{number}.bin")

    def ids(self, entry: int) -> np.ndarray:
        start, end = int(self.starts[entry]), int(self.starts[entry + 1])
        width = self.dtype.itemsize
        return np.frombuffer(self.file.read_at((end - start) * width, start * width), self.dtype).astype("<u4")

    def ids_of(self, entries: np.ndarray) -> list[np.ndarray]:
        """Ids of each of these entries, read at one go from the least to the greatest."""
        low, high, width = int(self.starts[entries.min()]), int(self.starts[entries.max() + 1]), self.dtype.itemsize
        whole = np.frombuffer(self.file.read_at((high - low) * width, low * width), self.dtype).astype("<u4")
        return [whole[self.starts[e] - low : self.starts[e + 1] - low] for e in entries.tolist()]

    def entries(self, keys: np.ndarray) -> np.ndarray:
        """First entry of each key, -1 where the shard doesn't hold it."""
        slots, out = self.hash.slots(keys.view(np.uint64)), np.full(len(keys), -1, np.int64)
        at = np.flatnonzero((slots >= 0) & (slots < len(self.index["mark"])))
        good = at[self.index["mark"][slots[at]] == mix(keys[at], 99) >> np.uint64(32)]
        good = good[self.index["keys"][self.index["entry"][slots[good]]] == keys[good]]
        out[good] = self.index["entry"][slots[good]]
        return out

    def get(self, key: int) -> list[np.ndarray]:
        """Ids of every document with this key."""
        first = int(self.entries(np.array([key], np.int64))[0])
        keys, known, out = self.index["keys"], self.index["known"], []
        while 0 <= first < len(keys) and keys[first] == key and known[first]:
            out.append(self.ids(first))
            first += 1
        return out


@lru_cache(maxsize=8)
def _opened(folder: str, number: int, width: int) -> Shard:
    return Shard(folder, number, width)


def lookup(folder: str, manifest: dict, key: int) -> list[np.ndarray]:
    """Ids of every document with this key, over the shards whose range has it."""
    return [x for s in manifest["shards"] if s["low"] is not None and s["low"] <= key <= s["high"] for x in _opened(folder, s["shard"], s["width"]).get(key)]


def _blocks(entries: np.ndarray, starts: np.ndarray, ids: int) -> Iterator[np.ndarray]:
    """Consecutive entries in blocks of about ``ids`` ids and 4,096 entries at most, one entry at least."""
    first = 0
    while first < len(entries):
        end = int(np.searchsorted(starts, starts[entries[first]] + ids, side="right")) - 1
        end = min(max(end, first + 1), first + 4096, len(entries))
        yield entries[first:end]
        first = end


def read_store(spark: SparkSession, folder: str, manifest: dict) -> DataFrame:
    """doc_id, start, n_tokens and ids_crc32 of every document, read back from the files through their index."""
    shards = {s["shard"]: (s["before"], s["width"]) for s in manifest["shards"]}
    schema = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("n_tokens", pa.int64()), ("ids_crc32", pa.int64())])

    def run(batches):
        for b in batches:
            for number in b.column(0).to_pylist():
                if number not in shards:
                    continue
                before, width = shards[number]
                shard = Shard(folder, number, width)
                keys, known, starts = shard.index["keys"], shard.index["known"], shard.starts
                entry = np.arange(len(keys))
                if len(keys):
                    fresh = known & np.concatenate([[True], (keys[1:] != keys[:-1]) | ~known[:-1]])  # the first of equal keys
                    entry[fresh] = shard.entries(keys[fresh])
                    entry = np.where(known & ~fresh, np.arange(len(keys)), entry)
                for part in _blocks(entry, starts, READ_BYTES // width):
                    payloads = shard.ids_of(part)
                    rows = [(int(keys[e]) if known[e] else None, before + int(starts[e]), int(starts[e + 1] - starts[e]), zlib.crc32(x)) for e, x in zip(part.tolist(), payloads, strict=True)]
                    yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*rows, strict=True), schema.types, strict=True)], schema=schema)

    n = max(1, len(shards))
    return spark.range(0, n, 1, n).mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")


def op5_token_store(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    folder = f"{shared_dir(spark)}/token-store-{uuid.uuid4().hex}"
    manifest = write_store(spark, table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"), folder, end_id=2)
    return read_store(spark, folder, manifest)
