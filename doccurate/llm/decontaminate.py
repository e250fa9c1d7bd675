"""Benchmark decontamination: an FM-index over each shard of training texts, searched for test phrases.

Words are runs of digits, ASCII letters (lower-cased) and characters beyond ASCII. A phrase is a
window of ``width`` consecutive words of a test item; an item with fewer words, but some, is one phrase.
Phrases are searched backwards through the wavelet matrix of the shard, occurrences are located by
sampled suffix positions, and words inside any occurrence are merged into removal spans.

Null and empty texts have no words and no hits; repeated rows each are judged; items without words
never match; with an empty item table every document is clean; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
import uuid
from collections import defaultdict
from collections.abc import Iterator
from itertools import count

import numpy as np
import pyarrow as pa
import pyarrow.compute
import pyarrow.dataset as ds
from pyarrow import fs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from doccurate.llm.common import docs_of, shared_dir, slices, table
from doccurate.llm.fm_index import FMIndex
from doccurate.llm.token_store import _files

#: Bytes to bytes: A-Z to lower case, and what isn't part of a word to a space.
_FOLD = bytes(b + 32 if 65 <= b <= 90 else b if b >= 128 or 48 <= b <= 57 or 97 <= b <= 122 else 32 for b in range(256))
_WORD = re.compile(r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+")
SHARD_BYTES, BLOCK_BYTES = 4 << 20, 8 << 20
#: Shards of a task that are searched together for each block, where items fill several.
GROUP = 8

Phrases = dict[tuple[bytes, ...], list]


def words_of(text: bytes | None) -> list[bytes]:
    return text.translate(_FOLD).split() if text else []


def phrases_of(items: list[tuple], width: int) -> Phrases:
    """Distinct phrases of (item_id, text) rows, each with the ids of its items."""
    found: Phrases = {}
    for item, text in items:
        words = words_of((text or "").encode())
        for k in range(max(len(words) - width, 0) + 1 if words else 0):
            at = found.setdefault(tuple(words[k : k + width]), [])
            if not at or at[-1] != item:
                at.append(item)
    return found


class Shard:
    """The words of some documents behind an index; a separator ends each document."""

    def __init__(self, texts: list[bytes | None]):
        self.ids: dict[bytes, int] = defaultdict(count(2).__next__)
        parts, self.lengths = [], []
        for text in texts:
            words = words_of(text)
            parts.append(np.fromiter(map(self.ids.__getitem__, words), np.int64, len(words)))
            parts.append(np.ones(1, np.int64))
            self.lengths.append(len(words))
        self.ids.default_factory = None
        self.starts = np.concatenate([[0], np.cumsum(np.array(self.lengths, np.int64) + 1)])
        self.index = FMIndex(np.concatenate(parts)) if any(self.lengths) else None

    def hits(self, phrases: Phrases) -> tuple[list[np.ndarray], list[set]]:
        """Per document: a flag a word, and the items that occur."""
        size, found = int(self.starts[-1]), [set() for _ in self.lengths]
        edge = np.zeros(size + 1, np.int64)
        by_width = defaultdict(list)
        for phrase, items in phrases.items():
            if self.index and all(w in self.ids for w in phrase):
                by_width[len(phrase)].append((phrase, items))
        for width, some in by_width.items():
            which, low, high = self.index.search(np.array([[self.ids[w] for w in p] for p, _ in some], np.int64))
            if not len(which):
                continue
            times = high - low
            owner = np.repeat(which, times)
            rows = np.repeat(low, times) + np.arange(int(times.sum())) - np.repeat(np.cumsum(times) - times, times)
            at = self.index.locate(rows)
            np.add.at(edge, at, 1)
            np.add.at(edge, at + width, -1)
            doc = np.searchsorted(self.starts, at, side="right") - 1
            for d, p in np.unique(np.stack([doc, owner], 1), axis=0).tolist():
                found[d].update(some[p][1])
        flags = np.cumsum(edge[:-1]) > 0
        return [flags[a : a + n] for a, n in zip(self.starts[:-1].tolist(), self.lengths, strict=True)], found


def _runs(flags: np.ndarray) -> list[list[int]]:
    step = np.diff(np.concatenate([[0], flags.astype(np.int8), [0]]))
    return np.stack([np.flatnonzero(step == 1), np.flatnonzero(step == -1)], 1).tolist()


class Items:
    """The phrases of the test items in blocks of about ``block_bytes`` of text: one is broadcast, several lie in the shared folder."""

    def __init__(self, spark: SparkSession, items: DataFrame, width: int, block_bytes: int):
        bench = items.select("item_id", F.col("text").cast("string").alias("text"))
        total = bench.agg(F.sum(F.octet_length("text"))).first()[0] or 0
        self.width, self.blocks, self.sent = width, max(1, -(-total // block_bytes)), None
        if self.blocks == 1:
            self.sent = spark.sparkContext.broadcast(phrases_of([tuple(r) for r in bench.collect()], width))
            return
        self.folder = f"{shared_dir(spark)}/items-{uuid.uuid4().hex}"
        block = F.pmod(F.xxhash64(F.col("item_id").cast("string"), "text"), F.lit(self.blocks))
        bench.withColumn("block", block).repartition(self.blocks, "block").write.partitionBy("block").parquet(self.folder)

    def __iter__(self) -> Iterator[Phrases]:
        """One block after another, read anew on each pass."""
        if self.sent:
            yield self.sent.value
            return
        system, root = _files(self.folder)
        for k in range(self.blocks):
            at = f"{root}/block={k}"
            if system.get_file_info(at).type == fs.FileType.Directory:
                rows = ds.dataset(at, filesystem=system, format="parquet").to_table(["item_id", "text"])
                yield phrases_of(list(zip(*(c.to_pylist() for c in rows.columns), strict=True)), self.width)


def _judged(batches: Iterator[pa.RecordBatch], items: Items) -> Iterator[tuple[pa.RecordBatch, list[int], list[np.ndarray], list[set]]]:
    """Parts of the batches with the word count, the flags of hit words and the items of each document.

    A part is indexed once, whatever the number of blocks; of several blocks each is read for GROUP parts together.
    """
    waiting, size = [], 1 if items.blocks == 1 else GROUP

    def search():
        shards = [Shard(part.column(part.schema.get_field_index("text")).cast(pa.binary()).to_pylist()) for part in waiting]
        found = [([np.zeros(n, bool) for n in x.lengths], [set() for _ in x.lengths]) for x in shards]
        for phrases in items:
            for shard, (flags, some) in zip(shards, found, strict=True):
                for k, (f, i) in enumerate(zip(*shard.hits(phrases), strict=True)):
                    flags[k] |= f
                    some[k] |= i
        for part, shard, (flags, some) in zip(waiting, shards, found, strict=True):
            yield part, shard.lengths, flags, some

    for batch in batches:
        for part in slices(batch, "text", SHARD_BYTES):
            waiting.append(part)
            if len(waiting) >= size:
                yield from search()
                waiting.clear()
    yield from search()


def find_contamination(spark: SparkSession, docs: DataFrame, items: DataFrame, width: int = 10, block_bytes: int = BLOCK_BYTES, keep_text: bool = False) -> DataFrame:
    """doc_id (and text), n_words, runs of hit words ([from, to) word numbers) and the items of each document."""
    phrases, names = Items(spark, items, width, block_bytes), ["doc_id", "text"] if keep_text else ["doc_id"]

    def run(batches):
        for part, lengths, flags, found in _judged(batches, phrases):
            out = [pa.array(lengths, pa.int64()), pa.array([_runs(f) if f.any() else [] for f in flags], pa.list_(pa.list_(pa.int32()))), pa.array([sorted(map(str, x)) for x in found], pa.list_(pa.string()))]
            yield pa.RecordBatch.from_arrays([*part.columns[: len(names)], *out], [*names, "n_words", "runs", "items"])

    kinds = ["doc_id long", "text string"][: len(names)]
    return docs_of(docs).mapInArrow(run, ", ".join([*kinds, "n_words long, runs array<array<int>>, items array<string>"]))


def remove_spans(text: str | None, runs: list[list[int]]) -> str | None:
    """The text without the words of these runs and what stands between them."""
    if not text or not runs:
        return text
    spans = [m.span() for m in _WORD.finditer(text)]
    out, at = [], 0
    for first, end in runs:
        out.append(text[at : spans[first][0]])
        at = spans[end - 1][1]
    return "".join([*out, text[at:]])


def op8_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = find_contamination(spark, table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    n_hit = F.aggregate("runs", F.lit(0).cast("long"), lambda n, x: n + (F.get(x, F.lit(1)) - F.get(x, F.lit(0))).cast("long"))
    return found.select(
        "doc_id", "n_words", n_hit.alias("n_hit"), F.size("items").cast("long").alias("n_items"),
        F.sha2(F.array_join("items", ",").cast("binary"), 256).alias("items_sha256"), (F.size("runs") > 0).alias("contaminated"),
    )


def cleaned(spark: SparkSession, docs: DataFrame, items: DataFrame, width: int = 10, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """docs with the removal spans cut out of ``text`` and ``n_chars``, where there is one, counted anew; all rows stay.

    All items are judged on the text as it came, in however many blocks, and it is cut once.
    """
    phrases, schema, at = Items(spark, items, width, block_bytes), docs.schema, docs.columns.index("text")
    counted = docs.columns.index("n_chars") if "n_chars" in docs.columns else None

    def run(batches):
        for part, _, flags, _ in _judged(batches, phrases):
            columns = list(part.columns)
            if any(f.any() for f in flags):
                columns[at] = pa.array([remove_spans(t.as_py(), _runs(f)) if f.any() else t.as_py() for t, f in zip(part.column(at), flags, strict=True)], pa.string())
                if counted is not None:
                    hit = pa.array([bool(f.any()) for f in flags])
                    fresh = pa.compute.utf8_length(columns[at]).cast(columns[counted].type)
                    columns[counted] = pa.compute.if_else(hit, fresh, columns[counted])
            yield pa.RecordBatch.from_arrays(columns, part.schema.names)

    return docs.mapInArrow(run, schema)
