"""Given tables with declared schemas."""

from __future__ import annotations

import atexit
import shutil
import tempfile

from pyspark.sql import DataFrame, SparkSession

#: Columns that the methods use, by table; the Parquet footer is checked against them.
SCHEMAS: dict[str, dict[str, str]] = {
    "documents": {"doc_id": "bigint", "text": "string", "lang": "string", "source": "string", "n_chars": "bigint"},
    "pages": {"page_id": "bigint", "url": "string", "html": "string"},
    "benchmark": {"item_id": "bigint", "text": "string"},
    "labels": {"doc_id": "bigint", "quality": "int", "toxic": "int"},
    "conversations": {"conv_id": "bigint", "turn": "bigint", "role": "string", "text": "string"},
}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    found = dict(df.dtypes)
    if wrong := {c: (t, found.get(c)) for c, t in SCHEMAS.get(name, {}).items() if found.get(c) != t}:
        raise TypeError(f"{name} has other columns than declared: {wrong}")
    return df


_own_folder: list[str] = []


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share (``spark.checkpoint.dir``); in local mode a temporary one where that is unset."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
        if not _own_folder:
            _own_folder.append(tempfile.mkdtemp(prefix="doccurate-"))
            atexit.register(shutil.rmtree, _own_folder[0], ignore_errors=True)
        found = f"file://{_own_folder[0]}"
    return found.rstrip("/")
