"""Answers, scores, gaps and correlations."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from doccurate.functions.keys import uniform
from doccurate.functions.metrics import anls, exact_match, lexical_judge
from doccurate.functions.text import bound, grams, overlap
from doccurate.operators.qa import sentences

#: Published accuracies by neutral model names: strongest closed model first (fixed values).
PUBLISHED = {
    "closed_a": {"english": 0.815, "gold": 0.667, "synthetic": 0.694},
    "closed_b": {"english": 0.938, "gold": 0.630, "synthetic": 0.655},
    "open_72b": {"english": 0.961, "gold": 0.611, "synthetic": 0.613},
    "open_90b": {"english": 0.954, "gold": 0.481, "synthetic": 0.498},
}
#: Published human level on the English benchmark (fixed values).
HUMAN = {"exact": 0.9436, "anls": 0.981}
#: Published accuracies after fine-tuning, by training data (fixed values).
TUNED = {"base": 0.332, "synthetic_only": 0.285, "mixture": 0.303, "mixture_21k": 0.374, "mixture_105k": 0.404}


def published_scores(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([(m, d, v) for m, some in PUBLISHED.items() for d, v in some.items()], "model string, dataset string, accuracy double")


def tuned_scores(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([(k, m, v) for k, (m, v) in enumerate(TUNED.items())], "step int, model string, accuracy double")


def quality_rows(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """model, dataset, quality: labelled documents, their source as the model and their language as the test set; of repeated labels the least counts."""
    own = labels.groupBy("doc_id").agg(F.min("quality").alias("quality")).filter("quality is not null")
    return docs.select("doc_id", F.col("source").alias("model"), F.col("lang").alias("dataset")).join(own, "doc_id").select("model", "dataset", "quality")


def quality_scores(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """model, dataset, accuracy: share of good documents by source and language."""
    return quality_rows(docs, labels).groupBy("model", "dataset").agg(F.avg("quality").alias("accuracy"))


def added_scores(docs: DataFrame, labels: DataFrame, sets: dict[str, str]) -> DataFrame:
    """step, model, accuracy: share of good documents as one language after another is added (sets: name of the step, language)."""
    names, langs = (F.array(*map(F.lit, x)) for x in (sets.keys(), sets.values()))
    own = quality_rows(docs, labels).select("quality", F.array_position(langs, F.col("dataset")).cast("int").alias("at")).filter("at > 0")
    each = own.select("quality", F.explode(F.sequence(F.col("at") - 1, F.lit(len(sets) - 1))).alias("step"))
    return each.groupBy("step").agg(F.avg("quality").alias("accuracy")).select("step", F.get(names, F.col("step")).alias("model"), "accuracy")


def answerers(question: Column, text: Column, key: Column) -> dict[str, Column]:
    """Four deterministic answerers of rising strength: first sentence, a hash-drawn one, best overlap, its second half."""
    some = sentences(text)
    cost = lambda own, s: -F.coalesce(overlap(own, grams(s, 4)), F.lit(0.0))
    scored = bound(grams(question, 4), lambda own: F.transform(some, lambda s, i: F.struct(cost(own, s).alias("cost"), i.alias("i"), s.alias("s"))))
    best = F.array_min(scored).s
    ws = F.split(best, " +")
    return {
        "first_sentence": F.get(some, F.lit(0)),
        "drawn_sentence": F.get(some, F.floor(uniform(key, "answer") * F.size(some)).cast("int")),
        "best_sentence": best,
        "best_clause": F.array_join(F.slice(ws, F.ceil(F.size(ws) / 2).cast("int") + 1, F.size(ws)), " "),
    }


def answers(pairs: DataFrame) -> DataFrame:
    """model, dataset, qa_id, prediction, reference of pairs(dataset, qa_id, text, question, answer)."""
    found = answerers(F.col("question"), F.col("text"), F.col("qa_id"))
    rows = F.array(*(F.struct(F.lit(m).alias("model"), F.coalesce(p, F.lit("")).alias("prediction")) for m, p in found.items()))
    return pairs.select("dataset", "qa_id", F.col("answer").alias("reference"), F.inline(rows))


def with_scores(df: DataFrame) -> DataFrame:
    p, r = F.col("prediction"), F.col("reference")
    return df.withColumns({"exact": exact_match(p, F.array(r)).cast("int"), "right": lexical_judge(p, r).cast("int"), "anls": anls(p, F.array(r))})


def score_matrix(scored: DataFrame, measure: str = "right") -> DataFrame:
    """model, dataset, n, accuracy and whether it is the best of its dataset."""
    means = scored.groupBy("model", "dataset").agg(F.count("*").alias("n"), F.round(F.avg(measure), 6).alias("accuracy"))
    return means.withColumn("best", F.rank().over(W.partitionBy("dataset").orderBy(F.desc("accuracy"))) == 1)  # a row a model and dataset


def metric_agreement(scored: DataFrame, tau: float = 0.5) -> DataFrame:
    """How often the judgement and the edit measure (at tau) agree, by model."""
    near = F.col("anls") >= tau
    return scored.groupBy("model").agg(
        F.count("*").alias("n"), F.count_if((F.col("right") == 1) & near).alias("both"), F.count_if((F.col("right") == 1) & ~near).alias("judge_only"),
        F.count_if((F.col("right") == 0) & near).alias("edit_only"), F.count_if((F.col("right") == 0) & ~near).alias("neither"),
    )


def human_gap(scores: DataFrame, dataset: str = "english", level: float = HUMAN["exact"]) -> DataFrame:
    """model, accuracy and distance to the human level on a dataset, and whether it is near or above (within a tenth)."""
    some = scores.filter(F.col("dataset") == dataset)
    return some.select("model", "accuracy", F.round(F.col("accuracy") - level, 6).alias("to_human"), (F.col("accuracy") >= level - 0.1).alias("near_or_above"))


def language_gap(scores: DataFrame, reference: str = "english") -> DataFrame:
    """model, dataset, absolute and relative gap to the reference dataset."""
    ref = scores.filter(F.col("dataset") == reference).select("model", F.col("accuracy").alias("ref"))
    rows = scores.filter(F.col("dataset") != reference).join(ref, "model")
    return rows.select("model", "dataset", F.round(F.col("ref") - F.col("accuracy"), 6).alias("gap"), F.round((F.col("ref") - F.col("accuracy")) / F.nullif("ref", F.lit(0.0)), 6).alias("relative_gap"))


def two_sided_p(r: float | None, n: int) -> float | None:
    """p of a Pearson r under Student's t with n - 2 degrees of freedom; null for n < 3 or an undefined r."""
    if r is None or math.isnan(r) or n < 3:
        return None
    if abs(r) >= 1:
        return 0.0
    dof, x = n - 2, 1 - r * r  # p = I_x(dof / 2, 1 / 2) with x = dof / (dof + t**2)
    return _incomplete_beta(dof / 2, 0.5, x)


def _incomplete_beta(a: float, b: float, x: float) -> float:
    if x <= 0 or x >= 1:
        return float(x >= 1)
    if x > (a + 1) / (a + b + 2):
        return 1 - _incomplete_beta(b, a, 1 - x)
    front = math.exp(a * math.log(x) + b * math.log(1 - x) + math.lgamma(a + b) - math.lgamma(a) - math.lgamma(b)) / a
    total = term = 1.0  # series in x, which converges fast on this side
    k = 0
    while abs(term) > 1e-16 * abs(total) and k < 100_000:
        term *= (a + b + k) * x / (a + 1 + k)
        total += term
        k += 1
    return front * total


def _r(x: str, y: str) -> Column:
    """Correlation; null where a side is constant."""
    return F.try_divide(F.covar_pop(x, y), F.stddev_pop(x) * F.stddev_pop(y))


def pearson(spark: SparkSession, wide: DataFrame, x: str, y: str) -> DataFrame:
    """One row: n, r and p; the p-value is a function of the two aggregated numbers."""
    row = wide.select(x, y).dropna().agg(F.count("*").alias("n"), F.try_divide(F.covar_pop(x, y), F.stddev_pop(x) * F.stddev_pop(y)).alias("r")).first()
    p = two_sided_p(row.r, row.n)
    return spark.createDataFrame([(row.n, None if row.r is None else round(row.r, 6), None if p is None else round(p, 6))], "n long, r double, p double")


def spearman(wide: DataFrame, x: str, y: str) -> DataFrame:
    """Pearson of mean ranks."""
    mean_rank = lambda c: F.rank().over(W.orderBy(c)) + (F.count("*").over(W.partitionBy(c)) - 1) / 2  # noqa: E731  a row a model
    ranked = wide.select(mean_rank(x).alias("rx"), mean_rank(y).alias("ry"))
    return ranked.agg(F.count("*").alias("n"), F.round(_r("rx", "ry"), 6).alias("rho"))


def leave_one_out(wide: DataFrame, key: str, x: str, y: str) -> DataFrame:
    """r without each row in turn."""
    left = wide.select(F.col(key).alias("without"))
    rest = left.join(wide, F.col("without") != F.col(key))  # rows are models: a handful
    return rest.groupBy("without").agg(F.round(_r(x, y), 6).alias("r"))


def bootstrap(wide: DataFrame, key: str, x: str, y: str, times: int = 200) -> DataFrame:
    """Quartiles and the 5th percentile of r over keyed resamples with replacement."""
    n = F.count("*").over(W.partitionBy(F.lit(1)))
    numbered = wide.select(x, y, (F.row_number().over(W.orderBy(key)) - 1).alias("k"), n.alias("n"))  # a row a model
    draws = numbered.select("n", "k", F.explode(F.sequence(F.lit(1), F.lit(times))).alias("sample"))
    drawn = draws.select("sample", F.floor(uniform(F.concat_ws("|", F.col("sample").cast("string"), F.col("k").cast("string")), "boot") * F.col("n")).cast("int").alias("k"))
    each = drawn.join(numbered.drop("n"), "k").groupBy("sample").agg(F.try_divide(F.covar_pop(x, y), F.stddev_pop(x) * F.stddev_pop(y)).alias("r")).filter("r is not null and not isnan(r)")
    return each.agg(F.count("*").alias("samples"), F.round(F.percentile("r", F.lit(0.05)), 4).alias("low"), F.round(F.percentile("r", F.lit(0.5)), 4).alias("median"))


def proxy_ok(r: float | None, p: float | None, r_min: float = 0.9, p_max: float = 0.05) -> bool:
    """Whether the synthetic test set may stand alone."""
    return r is not None and p is not None and r >= r_min and p <= p_max


def deltas(scores: DataFrame, base: str = "base") -> DataFrame:
    ref = scores.filter(F.col("model") == base).select(F.col("accuracy").alias("ref"))
    return scores.crossJoin(ref).select("step", "model", "accuracy", F.round(F.col("accuracy") - F.col("ref"), 6).alias("delta"))  # one reference row
