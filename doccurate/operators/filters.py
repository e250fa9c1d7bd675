"""The filter cascade over question-answer pairs, its attrition, and rounds of it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from doccurate.functions.text import bound, computed, edit_ratio, gram_cosine, grams, jaccard, norm, overlap
from doccurate.operators.langid import detect

#: Reasons in the order of the cascade, cheap ones first; the paraphrase test sees survivors only.
REASONS = ["length", "overlap", "language", "paraphrase"]


def f_length(text: Column, min_exclusive: int = 60) -> Column:
    return F.coalesce(F.length(F.trim(text)) > min_exclusive, F.lit(False))


def overlap_of(question: Column, text: Column, n: int = 4, unit: str = "char", denom: str = "question") -> Column:
    return overlap(grams(question, n, unit), grams(text, n, unit), denom)


def f_overlap(value: Column, threshold: float = 0.12, on_short: str = "drop") -> Column:
    return F.coalesce(value >= threshold, F.lit(on_short == "keep"))


def with_language(pairs: DataFrame, profiles: DataFrame, langs: list[str], key: str = "qa_id", question: str = "question") -> DataFrame:
    return pairs.join(detect(pairs, [key], question, profiles, langs), key, "left")


Judge = Callable[[Column, Column], Column]


def same_words(tau: float = 0.8) -> Judge:
    """Paraphrase stand-in: equal normal form, or a Jaccard of words of at least tau."""
    return lambda a, b: (norm(a) == norm(b)) | (F.coalesce(jaccard(a, b), F.lit(0.0)) >= tau)


def equal_norm() -> Judge:
    return lambda a, b: norm(a) == norm(b)


def close_edit(tau: float = 0.8) -> Judge:
    return lambda a, b: edit_ratio(norm(a), norm(b)) >= tau


def close_vectors(tau: float = 0.8, dims: int = 64) -> Judge:
    """Cosine of hashed gram vectors, a stand-in of a trained embedding; false where a text has no gram."""
    return lambda a, b: F.coalesce(gram_cosine(a, b, dims) >= tau, F.lit(False))


Ask = Callable[[list[str], list[str]], list[bool]]


def external_verdicts(pairs: DataFrame, ask: Ask, cache: DataFrame | None = None, page: str = "image_id") -> DataFrame:
    """a, b, same: verdicts of an outside judge over the pairs a < b of different questions of one page.

    A distinct pair is asked once, and not at all where cache(a, b, same) has it; the result can be the next call's cache once it is
    written. Null questions aren't asked. A page has at most as many questions as it had calls.
    """
    q = pairs.filter("question is not null").select(page, "question").distinct()
    both = q.withColumnRenamed("question", "a").join(q.withColumnRenamed("question", "b"), page).filter("a < b").select("a", "b").distinct()

    def run(batches):
        for some in batches:
            yield some.assign(same=[bool(x) for x in ask(some["a"].tolist(), some["b"].tolist())])

    schema = "a string, b string, same boolean"
    if cache is None:
        return both.mapInPandas(run, schema)
    known = cache.groupBy("a", "b").agg(F.max("same").alias("same"))
    return both.join(known, ["a", "b"], "left_anti").mapInPandas(run, schema).unionByName(both.join(known, ["a", "b"]))


def by_verdicts() -> Judge:
    """Judge by the verdicts given to f_paraphrase; equal questions are the same."""
    link = lambda a, b: F.struct(F.least(a, b).alias("a"), F.greatest(a, b).alias("b"))
    return lambda a, b: (a == b) | F.coalesce(F.array_contains("links", link(a, b)), F.lit(False))


def _page_links(pairs: DataFrame, verdicts: DataFrame, page: str) -> DataFrame:
    """page, links: the pairs of each page's questions that verdicts(a, b, same) call the same."""
    q = pairs.select(page, "question").distinct()
    both = q.withColumnRenamed("question", "a").join(q.withColumnRenamed("question", "b"), page).filter("a < b")
    return both.join(verdicts.filter("same").select("a", "b").distinct(), ["a", "b"]).groupBy(page).agg(F.collect_set(F.struct("a", "b")).alias("links"))


def judge_calls(pairs: DataFrame, page: str = "image_id") -> DataFrame:
    """One row: pages, pairs, and comparisons that a paraphrase judge is asked for (pairs of pairs of one page)."""
    each = pairs.groupBy(page).agg(F.count("*").alias("n"))
    zero = lambda c: F.coalesce(c, F.lit(0)).cast("long")
    return each.agg(F.count("*").alias("pages"), zero(F.sum("n")).alias("pairs"), zero(F.sum(F.expr("n * (n - 1) div 2"))).alias("comparisons"))


def f_paraphrase(pairs: DataFrame, judge: Judge, keep: str = "first", closure: str = "transitive", page: str = "image_id", verdicts: DataFrame | None = None) -> DataFrame:
    """pairs with ``duplicate``: whether an other question of the page that paraphrases this one is kept instead.

    A page has at most as many pairs as it had calls, so its questions are compared inside one array.
    keep: first (by view and slot, ``parse`` before ``ocr``), longest (question), or none of a group; closure: transitive, or greedy (against kept ones).
    A null question paraphrases none. verdicts: of external_verdicts, for the judge by_verdicts.
    """
    rank = F.when(F.col("view") == "parse", 0).otherwise(1) * 1000 + F.col("slot")
    rank = rank if keep != "longest" else F.struct(-F.length("question"), rank)
    groups = pairs.groupBy(page).agg(F.array_sort(F.collect_list(F.struct(rank.alias("rank"), "qa_id", "question"))).alias("qs"))
    if verdicts is not None:
        groups = groups.join(_page_links(pairs, verdicts, page), page, "left")
    qs = F.col("qs")
    if closure == "greedy":
        kept = F.aggregate(qs, F.slice(qs, 1, 0), lambda done, q: F.when(F.exists(done, lambda d: F.coalesce(judge(d.question, q.question), F.lit(False))), done).otherwise(F.concat(done, F.array(q))))
        groups = groups.withColumn("kept", F.transform(kept, lambda q: q.qa_id))
    else:
        # Each question's least linked position, followed down to a root. Groups are tiny, the judge's matrix is made once.
        linked = F.transform(qs, lambda q, i: F.transform(qs, lambda p, j: (i == j) | F.coalesce(judge(p.question, q.question), F.lit(False))))
        least = lambda m, ls: F.transform(m, lambda row: F.array_min(F.filter(ls, lambda _, j: F.get(row, j))))
        labels = bound(linked, lambda m: bound(least(m, F.transform(m, lambda _, i: i)), lambda one: bound(least(m, one), lambda two: least(m, two))))
        alone = lambda ls, i: F.size(F.filter(ls, lambda x: x == i)) == 1
        root = lambda ls, i: (F.get(ls, i) == i) & (alone(ls, i) if keep == "none" else F.lit(True))
        groups = groups.withColumn("kept", bound(labels, lambda ls: F.transform(F.filter(qs, lambda q, i: root(ls, i)), lambda q: q.qa_id)))
    marked = groups.select(F.explode(F.transform(qs, lambda q: F.struct(q.qa_id.alias("qa_id"), (~F.array_contains("kept", q.qa_id)).alias("duplicate")))).alias("m"))
    return pairs.join(marked.select("m.qa_id", "m.duplicate"), "qa_id")


def judged_alone(pairs: DataFrame, target: str | Column, n: int = 4, threshold: float = 0.12, min_exclusive: int = 60) -> DataFrame:
    """pairs with measures and ``reasons`` of the filters that judge each pair by itself: all but the paraphrase test."""
    target = F.lit(target) if isinstance(target, str) else target
    value = F.coalesce(overlap_of(F.col("question"), F.col("text"), n), F.lit(-1.0))
    rows = computed(pairs, measures=F.create_map(F.lit("length"), F.length(F.trim("text")).cast("double"), F.lit("overlap"), value))
    fails = {
        "length": ~f_length(F.col("text"), min_exclusive),
        "overlap": ~f_overlap(F.nullif(F.col("measures")["overlap"], F.lit(-1.0)), threshold),
        "language": ~F.coalesce(F.col("detected") == target, F.lit(False)),
    }
    return computed(rows, reasons=F.array_compact(F.array(*(F.when(c, F.lit(k)) for k, c in fails.items()))))


def run_cascade(pairs: DataFrame, target: str | Column, judge: Judge | None = None, mode: str = "sequential", n: int = 4, threshold: float = 0.12, min_exclusive: int = 60, keep: Callable[[DataFrame], DataFrame] = lambda df: df) -> DataFrame:
    """pairs(qa_id, image_id, view, slot, text, question, detected) with measures, ``reasons`` and ``kept``.

    sequential: the paraphrase test sees pairs that the other filters keep; independent: it sees all.
    keep can write the pairs with the first three verdicts, which are read twice from there.
    """
    judge = judge or same_words()
    rows = keep(judged_alone(pairs, target, n, threshold, min_exclusive))
    seen = rows if mode == "independent" else rows.filter(F.size("reasons") == 0)
    judged = f_paraphrase(seen.select("qa_id", "image_id", "view", "slot", "question"), judge).filter("duplicate").select("qa_id", "duplicate")
    rows = rows.join(judged, "qa_id", "left")
    rows = rows.withColumn("reasons", F.when(F.col("duplicate"), F.concat("reasons", F.array(F.lit("paraphrase")))).otherwise(F.col("reasons"))).drop("duplicate")
    return rows.withColumn("kept", F.size("reasons") == 0)


def attrition(judged: DataFrame) -> DataFrame:
    """reason, sequential (pairs whose first failing filter it is) and independent (pairs that fail it) removals, and the kept ones."""
    first = judged.groupBy(F.coalesce(F.get("reasons", F.lit(0)), F.lit("kept")).alias("reason")).agg(F.count("*").alias("sequential"))
    every = judged.select(F.explode(F.when(F.col("kept"), F.array(F.lit("kept"))).otherwise(F.col("reasons"))).alias("reason")).groupBy("reason").agg(F.count("*").alias("independent"))
    return every.join(first, "reason", "left").select("reason", F.coalesce("sequential", F.lit(0)).alias("sequential"), "independent")


def image_survival(before: DataFrame, after: DataFrame) -> DataFrame:
    a = before.agg(F.countDistinct("image_id").alias("images"))
    return a.crossJoin(after.agg(F.countDistinct("image_id").alias("surviving")))  # two single rows


def filter_quality(judged: DataFrame) -> DataFrame:
    """Per injected fault: pairs, removed ones and recall; and for sound pairs (fault ``none``) what is removed wrongly."""
    rows = judged.groupBy(F.coalesce("fault", F.lit("none")).alias("fault")).agg(F.count("*").alias("pairs"), F.count_if(~F.col("kept")).alias("removed"))
    return rows.withColumn("share", F.round(F.col("removed") / F.col("pairs"), 6))


def filter_scores(judged: DataFrame, truth: Column) -> DataFrame:
    """One row: the filters as a detector of pairs that truth marks as bad (null: unknown, left out): tp, fp, fn, precision, recall, f1."""
    bad, gone = F.col("bad"), ~F.col("kept")
    row = judged.select(truth.alias("bad"), "kept").filter("bad is not null").agg(F.count_if(bad & gone).alias("tp"), F.count_if(~bad & gone).alias("fp"), F.count_if(bad & ~gone).alias("fn"))
    share = lambda a, b: F.round(F.try_divide(a, b), 6)
    tp, fp, fn = F.col("tp"), F.col("fp"), F.col("fn")
    return row.select("tp", "fp", "fn", share(tp, tp + fp).alias("precision"), share(tp, tp + fn).alias("recall"), share(2 * tp, 2 * tp + fp + fn).alias("f1"))


def rounds(df: DataFrame, step: Callable[[DataFrame], DataFrame], keep: Callable[[DataFrame, int], DataFrame], most: int = 5) -> DataFrame:
    """Filter again until nothing goes. keep(df, round) must cut lineage (checkpoint or a written table)."""
    now, size = df, df.count()
    for k in range(most):
        now = keep(step(now), k)
        size, before = now.count(), size
        if size == before:
            break
    return now
