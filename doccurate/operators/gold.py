"""The hand-made set: choice of pages, annotation tasks, translators, verification."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from doccurate.functions.keys import hash_order, uniform
from doccurate.functions.text import dice
from doccurate.operators.qa import sentences

#: A translator maps a text column to a text column.
Translator = Callable[[Column], Column]


def identity_translator() -> Translator:
    return lambda text: text


def dictionary_translator(salt: str, share: float = 0.1) -> Translator:
    """Stand-in of a service: a keyed share of words is upper-cased, so that two services differ."""

    def translate(text: Column) -> Column:
        return F.array_join(F.transform(F.split(text, " "), lambda w: F.when(uniform(w, salt) < share, F.concat(F.upper(w), F.lit("'"))).otherwise(w)), " ")

    return translate


def coded_translator(salt: str = "english", share: float = 0.3) -> tuple[Translator, Translator]:
    """Stand-in of a service in both directions: a keyed share of the words of letters only is written backwards with a sign before, and back.

    Words that carry other characters stay, so sentences end where they did.
    """
    each = lambda use: lambda text: F.array_join(F.transform(F.split(text, " "), use), " ")
    there = each(lambda w: F.when(w.rlike(r"^\p{L}+$") & (uniform(w, salt) < share), F.concat(F.lit("~"), F.reverse(w))).otherwise(w))
    back = each(lambda w: F.when(w.rlike(r"^~\p{L}+$"), F.reverse(F.substr(w, F.lit(2)))).otherwise(w))
    return there, back


def translated_pairs(items: DataFrame, there: Translator, back: Translator) -> DataFrame:
    """item_id, the pair in the annotator's language, written from the translated page, and the pair translated back; null without a sentence."""
    first = F.split(F.get(sentences(there(F.col("text"))), F.lit(0)), " +")
    half = F.ceil(F.size("ws") / 2).cast("int")
    rows = items.select("item_id", first.alias("ws"))
    rows = rows.select("item_id", F.concat(F.array_join(F.slice("ws", 1, half), " "), F.lit(" ?")).alias("question_read"), F.array_join(F.slice("ws", half + 1, F.size("ws")), " ").alias("answer_read"))
    return rows.select("*", back(F.col("question_read")).alias("question"), back(F.col("answer_read")).alias("answer"))


def gold_sample(items: DataFrame, n: int = 54, salt: str = "gold") -> DataFrame:
    """n pages in hash order; all, if there are no more."""
    return items.orderBy(hash_order("item_id", salt), "item_id").limit(n)


def annotation_tasks(items: DataFrame, one: Translator, two: Translator) -> DataFrame:
    """A task a page: the text as two translators give it, their agreement (low first to check), and a draft pair from the first sentence."""
    first = F.split(F.get(sentences(F.col("text")), F.lit(0)), " +")
    half = F.ceil(F.size(first) / 2).cast("int")
    return items.select(
        "item_id", "text", one(F.col("text")).alias("reading_one"), two(F.col("text")).alias("reading_two"),
        F.round(dice(one(F.col("text")), two(F.col("text"))), 6).alias("agreement"),
        F.concat(F.array_join(F.slice(first, 1, half), " "), F.lit(" ?")).alias("question"), F.array_join(F.slice(first, half + 1, F.size(first)), " ").alias("answer"), F.lit("drafted").alias("state"),
    )


def verify(tasks: DataFrame, verdicts: DataFrame) -> DataFrame:
    """Pairs that a native speaker has approved; pairs without a verdict never pass."""
    return tasks.join(verdicts.filter("approved").select("item_id").distinct(), "item_id", "left_semi").withColumn("state", F.lit("verified")).withColumn("split", F.lit("test"))
