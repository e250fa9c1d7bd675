"""Shared plumbing: input tables, shared storage and Arrow helpers of the llm operators."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
import pyarrow.compute
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Table names of this project's input folders.
TABLES = ("documents", "benchmark", "pages", "labels")

_own_dir: list[str] = []


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir`` of the session.

    Where a session of local mode has none (tests), a temporary folder is made once and set; on a cluster that is an error.
    """
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
        if not _own_dir:
            _own_dir.append(tempfile.mkdtemp(prefix="doccurate-"))
            atexit.register(shutil.rmtree, _own_dir[0], ignore_errors=True)
        found = f"file://{_own_dir[0]}"
    if spark.sparkContext.getCheckpointDir() is None:
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


def materialise(spark: SparkSession, df: DataFrame, name: str) -> DataFrame:
    """Write df as Parquet to the shared folder and read it back: lineage ends here.

    A lost executor later costs a re-read, not a recomputation, and identifiers that were
    assigned while writing stay what they are.
    """
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


class Scratch:
    """Tables of ``materialise`` that are deleted together, once what was worked out from them is written itself."""

    def __init__(self, spark: SparkSession):
        self.spark, self.paths = spark, []

    def __call__(self, df: DataFrame, name: str) -> DataFrame:
        self.paths.append(path := f"{shared_dir(self.spark)}/{name}-{uuid.uuid4().hex}")
        df.write.parquet(path)
        return self.spark.read.schema(df.schema).parquet(path)

    def drop(self) -> None:
        jvm, conf = self.spark.sparkContext._jvm, self.spark.sparkContext._jsc.hadoopConfiguration()
        for path in self.paths:
            where = jvm.org.apache.hadoop.fs.Path(path)
            where.getFileSystem(conf).delete(where, True)
        self.paths = []

    def sweep(self) -> None:
        """Have the driver collect garbage now: executors then delete the shuffle files of plans that nothing refers to."""
        self.spark.sparkContext._jvm.System.gc()


def fresh(names: list[str], *wanted: str) -> list[str]:
    """The wanted column names, with underscores before those that names has already (in any case)."""
    taken, out = {n.lower() for n in names}, []
    for w in wanted:
        while w.lower() in taken:
            w = f"_{w}"
        taken.add(w.lower())
        out.append(w)
    return out


def arrow_rows(
    make: Callable[[], Callable[[pa.RecordBatch], Iterator[dict] | list[dict]]], schema: pa.Schema, block: int = 4096
) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """A mapInArrow function from a factory of batch-to-rows functions (built once per task)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        work, rows = make(), []
        for batch in batches:
            for row in work(batch):
                rows.append(row)
                if len(rows) >= block:
                    yield pa.RecordBatch.from_pylist(rows, schema=schema)
                    rows = []
        if rows:
            yield pa.RecordBatch.from_pylist(rows, schema=schema)

    return run


def slices(batch: pa.RecordBatch, text: str, limit: int = 4 << 20) -> Iterator[pa.RecordBatch]:
    """Cut a batch so that each part holds about ``limit`` bytes of the text column at most (one row at least)."""
    if batch.num_rows == 0:
        return
    column = batch.column(batch.schema.get_field_index(text))
    lengths = pa.compute.fill_null(pa.compute.binary_length(column), 0).to_pylist()
    start = used = 0
    for i, n in enumerate(lengths):
        if i > start and used + n > limit:
            yield batch.slice(start, i - start)
            start, used = i, 0
        used += n
    yield batch.slice(start)


def docs_of(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, text) of a table, whatever else it has."""
    return df.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
