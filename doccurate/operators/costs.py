"""Cost measures of a run: seconds, rows, shuffled and spilled bytes."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

SCHEMA = "name string, out_rows long, seconds double, rows_per_second double, shuffle_bytes long, spill_bytes long"


def _stages(spark: SparkSession, after: int) -> list:
    """The session's finished stages with larger ids, once all listeners have seen them."""
    sc, gateway = spark.sparkContext._jsc.sc(), spark.sparkContext._gateway
    sc.listenerBus().waitUntilEmpty()
    found = sc.statusStore().stageList(None, False, False, gateway.new_array(gateway.jvm.double, 0), gateway.jvm.java.util.ArrayList())
    return [s for s in (found.apply(i) for i in range(found.size())) if s.stageId() > after]


def measured(spark: SparkSession, name: str, build: Callable[[], DataFrame], rows: int | None = None) -> tuple:
    """A row of SCHEMA: build() is run to its end without being kept; the rows per second are of its output, or of the stated input rows.

    Shuffle and spill are those of all stages of the session meanwhile, so nothing else must run in it. Jobs that build() itself starts count.
    """
    last = max((s.stageId() for s in _stages(spark, -1)), default=-1)
    seen, start = Observation(), time.time()
    build().observe(seen, F.count(F.lit(1)).alias("n")).write.format("noop").mode("overwrite").save()
    took, stages, n = time.time() - start, _stages(spark, last), seen.get["n"]
    shuffled, spilled = sum(s.shuffleWriteBytes() for s in stages), sum(s.diskBytesSpilled() for s in stages)
    return name, n, round(took, 3), round((n if rows is None else rows) / max(took, 1e-3), 3), shuffled, spilled


def as_table(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame(rows, SCHEMA)
