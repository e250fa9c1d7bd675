"""Judges side by side, cost measures, students on hashed words, and scaling."""

from __future__ import annotations

from pyspark.sql import functions as F

from doccurate.operators import costs, filters, training
from doccurate.plans import sql
from doccurate.plans.registry import QUERIES, query
from doccurate.plans.workloads import TARGET, judged, keeper, parsed
from doccurate.sources.tables import table

#: Workloads whose cost is measured, from the crawl to the filtered pairs.
SCALED = ["w02_links", "w03_page_views", "w04_doc_language", "w05_corpus_pages", "w07_exact_copies", "w11_overlap", "w13_attrition"]


def lower_case_judge(a: list[str], b: list[str]) -> list[bool]:
    """A stand-in of an outside judge."""
    return [x.lower() == y.lower() for x, y in zip(a, b)]


_DIMS = 64
_PLACES = f"list_transform(list_transform(range(1, length({{0}}) - 1), lambda i: {{0}}[i:i + 2]), lambda g: ('0x' || md5(g)[:8])::BIGINT % {_DIMS})"
_VECTOR = f"list_transform(range({_DIMS}), lambda i: len(list_filter({{0}}, lambda p: p = i))::DOUBLE)"


@query("w12_judges", f"""WITH q AS (SELECT DISTINCT conv_id, text AS t FROM conversations WHERE role = 'user' AND text IS NOT NULL), b AS (SELECT DISTINCT a.t AS a, b.t AS b FROM q a JOIN q b ON a.conv_id = b.conv_id AND a.t < b.t),
n AS (SELECT a, b, {sql.norm('a')} AS na, {sql.norm('b')} AS nb, list_distinct({sql.words('a')}) AS wa, list_distinct({sql.words('b')}) AS wb FROM b),
p AS (SELECT *, {_PLACES.format('na')} AS pa, {_PLACES.format('nb')} AS pb FROM n), v AS (SELECT *, {_VECTOR.format('pa')} AS va, {_VECTOR.format('pb')} AS vb FROM p),
j AS (SELECT unnest(['norm', 'words', 'cosine', 'external']) AS judge, unnest([na = nb, na = nb OR coalesce(len(list_intersect(wa, wb)) / nullif(len(list_distinct(list_concat(wa, wb))), 0)::DOUBLE >= 0.8, false),
  coalesce(list_dot_product(va, vb) / nullif(sqrt(list_dot_product(va, va) * list_dot_product(vb, vb)), 0) >= 0.8, false), lower(a) = lower(b)]) AS same FROM v)
SELECT judge, count(*) AS comparisons, count(*) FILTER (same) AS same FROM j GROUP BY judge""")
def w12_judges(spark, sf_dir):
    """Pairs of different questions of one conversation, and how many of them each judge calls the same."""
    user = table(spark, sf_dir, "conversations").filter("role = 'user'").select("conv_id", F.col("text").alias("question"))
    both = keeper(spark)(filters.external_verdicts(user, lower_case_judge, page="conv_id"))
    a, b = F.col("a"), F.col("b")
    judges = {"norm": filters.equal_norm(), "words": filters.same_words(), "cosine": filters.close_vectors(0.8, _DIMS)}
    said = [F.struct(F.lit(k).alias("judge"), j(a, b).alias("same")) for k, j in judges.items()] + [F.struct(F.lit("external").alias("judge"), F.col("same"))]
    return both.select(F.inline(F.array(*said))).groupBy("judge").agg(F.count("*").alias("comparisons"), F.count_if("same").alias("same"))


@query("w13_cost", f"""WITH {sql.cascade(TARGET)}, s AS (SELECT image_id, count(*) AS n FROM judged WHERE reasons = [] OR reasons = ['paraphrase'] GROUP BY image_id)
SELECT 'calls' AS step, count(DISTINCT call) AS amount FROM parsed UNION ALL SELECT 'pairs', count(*) FROM parsed UNION ALL SELECT 'well_formed', count(*) FROM pairs
UNION ALL SELECT 'judged_pairs', coalesce(sum(n), 0)::BIGINT FROM s UNION ALL SELECT 'comparisons', coalesce(sum(n * (n - 1) // 2), 0)::BIGINT FROM s UNION ALL SELECT 'comparisons_unfiltered', coalesce(sum(n * (n - 1) // 2), 0)::BIGINT FROM (SELECT image_id, count(*) AS n FROM judged GROUP BY image_id)""")
def w13_cost(spark, sf_dir):
    """What the cascade asks for: model calls, pairs, and comparisons of the judge after the cheap filters and without them."""
    made = parsed(spark, sf_dir).agg(F.countDistinct("call").alias("calls"), F.count("*").alias("pairs"), F.count_if("well_formed").alias("well_formed"))
    rows = keeper(spark)(judged(spark, sf_dir).select("image_id", "reasons"))
    late = filters.judge_calls(rows.filter("size(reasons) = 0 or reasons = array('paraphrase')")).select(F.col("pairs").alias("judged_pairs"), "comparisons")
    every = filters.judge_calls(rows).select(F.col("comparisons").alias("comparisons_unfiltered"))
    steps = lambda df: df.select(F.inline(F.array(*(F.struct(F.lit(c).alias("step"), F.col(c).alias("amount")) for c in df.columns))))
    return steps(made).unionByName(steps(late)).unionByName(steps(every))


@query("w21_quality_students")
def w21_quality(spark, sf_dir):
    """Held-out accuracy on labels.quality of students of four seeds, and of the one with their averaged parameters."""
    labels = table(spark, sf_dir, "labels").groupBy("doc_id").agg(F.min("quality").alias("label"))
    rows = table(spark, sf_dir, "documents").select("doc_id", "text").join(labels, "doc_id").select(F.col("doc_id").cast("string").alias("key"), "text", "label")
    return training.hashed_students(keeper(spark)(rows))


@query("w25_scale")
def w25(spark, sf_dir):
    """Seconds, documents a second, shuffled and spilled bytes of the main workloads; run it at each size to see them grow."""
    documents = table(spark, sf_dir, "documents").count()
    return costs.as_table(spark, [costs.measured(spark, name, lambda name=name: QUERIES[name](spark, sf_dir), documents) for name in SCALED])
