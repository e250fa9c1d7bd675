"""Token counts of whole texts through the whole-token shortcut.

Strings that are proven to encode alone as one token count one; only other pre-tokens are merged.
Null and empty texts have 0 tokens and 0 bytes; repeated rows each give a row; other columns are ignored.
"""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from doccurate.llm.common import docs_of, table
from doccurate.llm.tokens import encoder, in_steps


def count_tokens(docs: DataFrame, vocabulary: str, limit: int = 2048) -> DataFrame:
    """doc_id, n_bytes, n_tokens and over_limit (more than ``limit`` tokens) of each row of docs(doc_id, text)."""

    def run(batches):
        counts = encoder(vocabulary).counts
        for b in batches:
            numbers = pa.array([n for some in in_steps(b.column(2)) for n in counts(some)], pa.int64())
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), numbers], ["doc_id", "n_bytes", "n_tokens"])

    rows = docs_of(docs).select("doc_id", F.coalesce(F.octet_length("text"), F.lit(0)).cast("long").alias("n_bytes"), "text")
    return rows.mapInArrow(run, "doc_id long, n_bytes long, n_tokens long").withColumn("over_limit", F.col("n_tokens") > limit)


def op7_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return count_tokens(table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"))
