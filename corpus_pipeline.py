"""A training corpus from ``documents``: five stages, each over all that the one before kept.

toxicity drops rejected documents; near duplicates keeps one document of each group; decontamination cuts
benchmark passages out; personal data masks spans; packing places the tokens of what is left.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from doccurate.llm.common import Scratch, fresh, table
from doccurate.llm.decontaminate import cleaned
from doccurate.llm.packing import pack
from doccurate.llm.pii import redacted
from doccurate.llm.simhash import one_of_each
from doccurate.llm.toxicity import held_out, scored, train

#: Score from which a document is rejected as toxic.
TOXIC = 0.3


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """docs whose score is below TOXIC. Null and empty texts have the bias's score; without labels all stay."""
    model, (score,) = train(spark, docs, table(spark, sf_dir, "labels").filter(~held_out())), fresh(docs.columns, "_toxic")
    return scored(docs, model, score).filter(F.col(score) < (TOXIC if len(model.at) else 1.0)).drop(score)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group of near copies, that of least doc_id. Null and empty texts are one group."""
    return one_of_each(spark, docs)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All docs, without the words of benchmark passages. Null and empty texts stay as they are."""
    return cleaned(spark, docs, table(spark, sf_dir, "benchmark"))


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All docs, personal data replaced by its kind in brackets. Null and empty texts stay as they are."""
    return redacted(docs)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of all docs and their places. Null and empty texts are the end id alone."""
    import public_tokenizers

    return pack(spark, docs, public_tokenizers.path("word_bpe_49k.json"))


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("toxicity", toxicity),
    ("near_duplicates", near_duplicates),
    ("decontamination", decontamination),
    ("personal_data", personal_data),
    ("packing", packing),
]

#: The stages use models and hashes that SQL doesn't express.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each stage's result is written to the shared folder and read again as the next one's documents, then deleted."""
    docs, before = table(spark, sf_dir, "documents"), Scratch(spark)
    for name, stage in STAGES:
        after = Scratch(spark)
        docs = after(stage(spark, docs, sf_dir), f"pipeline-{name}")
        before.drop()
        before = after
    return docs
