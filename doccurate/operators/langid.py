"""Language detection: naive Bayes over word or character grams with integer scores, and a stop-word vote."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from doccurate.functions.text import grams, words

#: Frequent function words (fixed values) of the stop-word vote.
STOP_WORDS = {
    "de": ["der", "die", "das", "und", "ist", "nicht", "von", "zu"],
    "en": ["the", "and", "of", "to", "is", "in", "that", "it"],
    "es": ["el", "los", "las", "que", "y", "en", "por", "con"],
    "fr": ["le", "les", "des", "et", "est", "que", "un", "une"],
}


def units(text: Column, unit: str = "word") -> Column:
    """Grams of a text that are counted: words, or character grams of 1 to 3."""
    return words(text) if unit == "word" else F.concat(*(grams(text, n, "char", distinct=False) for n in (1, 2, 3)))


def profile(docs: DataFrame, langs: list[str], unit: str = "word", least: int = 3) -> DataFrame:
    """gram and, for each language, round(10**4 ln((count + 1) / (total + grams))).

    docs: (lang, text). Grams of fewer than ``least`` occurrences in a language count as absent from it.
    """
    grams_ = docs.select("lang", F.explode(units(F.col("text"), unit)).alias("gram"))
    kept = grams_.groupBy("lang", "gram").agg(F.count("*").alias("n")).filter(F.col("n") >= least)
    wide = kept.groupBy("gram").pivot("lang", langs).agg(F.sum("n"))
    sizes = kept.groupBy(F.lit(1).alias("one")).agg(F.countDistinct("gram").alias("v"), *(F.coalesce(F.sum(F.when(F.col("lang") == x, F.col("n"))), F.lit(0)).alias(f"t_{x}") for x in langs))
    scored = wide.crossJoin(sizes)  # one row of totals
    score = lambda x: F.round(10000 * F.ln((F.coalesce(F.col(x), F.lit(0)) + 1) / (F.col(f"t_{x}") + F.col("v")))).cast("long")
    return scored.select("gram", *(score(x).alias(f"s_{x}") for x in langs))


def detect(df: DataFrame, keys: list[str], text: str, profiles: DataFrame, langs: list[str], unit: str = "word", min_margin: int = 0) -> DataFrame:
    """keys and ``detected``: the language of highest total score (ties by code); null without a known gram."""
    grams_ = df.select(*keys, F.explode_outer(units(F.col(text), unit)).alias("gram"))
    counted = grams_.groupBy(*keys, "gram").agg(F.count("gram").alias("times"))
    joined = counted.join(profiles, "gram", "left")
    sums = joined.groupBy(*keys).agg(*(F.sum(F.col(f"s_{x}") * F.col("times")).alias(f"s_{x}") for x in langs))
    ranked = F.array_sort(F.array(*(F.struct((-F.col(f"s_{x}")).alias("cost"), F.lit(x).alias("lang")) for x in langs)))
    best, second = F.get(ranked, F.lit(0)), F.get(ranked, F.lit(1))
    clear = F.coalesce(second.cost - best.cost >= min_margin, F.lit(True)) if len(langs) > 1 else F.lit(True)
    return sums.select(*keys, F.when(best.cost.isNotNull() & clear, best.lang).alias("detected"))


def detect_crossed(docs: DataFrame, key: str, fold: Column, folds: list[int], langs: list[str], unit: str = "word") -> DataFrame:
    """key, detected for all rows of docs(key, lang, text): each fold is judged by profiles of the rows of the other folds."""
    out = None
    for k in folds:
        own = profile(docs.filter(fold != k).select("lang", "text"), langs, unit)
        one = detect(docs.filter(fold == k), [key], "text", own, langs, unit)
        out = one if out is None else out.unionByName(one)
    return out


def stop_word_vote(text: Column) -> Column:
    """The language with most distinct stop words in the text (ties by code), null if there are none."""
    own = F.array_distinct(words(text))
    votes = [F.struct((-F.size(F.array_intersect(own, F.array(*map(F.lit, ws))))).alias("cost"), F.lit(x).alias("lang")) for x, ws in sorted(STOP_WORDS.items())]
    best = F.array_min(F.array(*votes))
    return F.when(best.cost < 0, best.lang)


def keep_language(docs: DataFrame, target: str, profiles: DataFrame, langs: list[str], key: str = "doc_id", text: str = "text") -> DataFrame:
    found = detect(docs, [key], text, profiles, langs).filter(F.col("detected") == target)
    return docs.join(found.select(key), key, "left_semi")
