"""URL filters: rules first, then a character language-model ratio.

Two smoothed variable-order Markov models are trained on the URLs that rules accept and reject. Their n-gram counts are
tables over all such URLs and all contexts, and grow with the input. The chance of a character interpolates from the order
below (Witten-Bell), down to a uniform one; it is worked out once for each distinct n-gram of all URLs, order by order. An
n-gram's log ratio then reaches the places where it occurs: those of frequent n-grams, of which there can
be at most FREQUENT, by a broadcast, all others by a join, in which none has more than a FREQUENT-th of the rows. A URL's score is
the difference of the models' log-likelihoods over its length. A fifth of the rule-labelled URLs, by a hash,
is kept from the models; the threshold is calibrated on these (on all, if they lack a kind), where the two error rates
are closest, on exact scores.

Null URLs and those without ``://`` have empty host and path, no rule, and the score 0; repeated rows have
equal results; without any accepted or rejected URLs every score is 0 and the verdict is allow. Log ratios are summed as
whole billionths, so that scores don't depend on the order of rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from doccurate.llm.common import materialise, table

ORDER, FREQUENT = 5, 20_000
#: (host, path, verdict): a rule fits its host and all subdomains, and paths that start with its own.
Rule = tuple[str, str, str]
# Fixed values of the production rules.
RULES: list[Rule] = [("org", "/", "allow"), ("example.org", "/es/", "block"), ("example.org", "/en/1", "block"), ("com", "/fr/", "allow"), ("com", "/de/", "block")]
_UP, _LOW = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def host_of(url: Column) -> Column:
    rest = F.regexp_extract(url, r"(?s)^.*?://(.*)$", 1)
    return F.coalesce(F.translate(F.regexp_extract(rest, r"(?s)^([^/?#]*)", 1), _UP, _LOW), F.lit(""))


def path_of(url: Column) -> Column:
    rest = F.regexp_extract(url, r"(?s)^.*?://(.*)$", 1)
    return F.coalesce(F.regexp_extract(rest, r"(?s)^[^/?#]*([^?#]*)", 1), F.lit(""))


def rule_of(host: Column, path: Column, rules: list[Rule]) -> Column:
    """(name, verdict) of the longest rule that fits, else null."""
    out = None
    for h, p, verdict in sorted(rules, key=lambda r: -len(r[0] + r[1])):
        fits = ((host == h) | host.endswith(f".{h}")) & path.startswith(p)
        found = F.struct(F.lit(h + p).alias("name"), F.lit(verdict).alias("verdict"))
        out = F.when(fits, found) if out is None else out.when(fits, found)
    return out if out is not None else F.lit(None).cast("struct<name: string, verdict: string>")


def ngrams(urls: DataFrame, order: int = ORDER) -> DataFrame:
    """u, accepted, rejected, context (``order`` characters), char: one row for each place of urls(u, url, accepted, rejected) and for its end."""
    chars = F.array(F.split(F.concat(F.lit("\x02" * order), "url", F.lit("\x03")), ""))
    before = lambda t, i: F.concat(*(F.get(t, i - k) for k in range(order, 0, -1))) if order else F.lit("")
    places = lambda t: F.transform(F.sequence(F.lit(order), F.size(t) - 1), lambda i: F.struct(before(t, i).alias("context"), F.get(t, i).alias("char")))
    return urls.select("u", "accepted", "rejected", F.inline(F.get(F.transform(chars, places), F.lit(0))))


def counts(grams: DataFrame, order: int = ORDER) -> DataFrame:
    """k, context, char, and how often accepted and rejected URLs and (of the full order) all distinct URLs have it, for contexts of k = 0 to ``order`` characters."""
    full = grams.groupBy("context", "char").agg(F.sum("accepted").alias("a"), F.sum("rejected").alias("b"), F.count("*").alias("n"))
    ends = F.array(*(F.struct(F.lit(k).alias("k"), F.substring("context", order - k + 1, k).alias("context")) for k in range(order + 1)))
    every = full.select(F.inline(ends), "char", "a", "b", "n")
    return every.groupBy("k", "context", "char").agg(F.sum("a").alias("a"), F.sum("b").alias("b"), F.sum("n").alias("n"))


def log_ratios(found: DataFrame, order: int = ORDER) -> DataFrame:
    """context, char, n and ``ratio`` (billionths) of each n-gram of the full order in found, a table of ``counts``.

    A context has at most as many rows as there are characters.
    """
    alphabet = found.filter((F.col("k") == 0) & (F.col("a") + F.col("b") > 0)).count() + 1
    same, below = W.partitionBy("context"), None
    for k in range(order + 1):
        now = found.filter(F.col("k") == k).select("context", "char", "n", *(f(x).alias(f"{name}_{x}") for x in "ab" for f, name in ((F.col, "seen"), (lambda x: F.sum(x).over(same), "total"), (lambda x: F.count_if(F.col(x) > 0).over(same), "kinds"))))
        if below is None:
            now = now.select("*", *(F.lit(1 / alphabet).alias(f"below_{x}") for x in "ab"))
        else:
            now = now.withColumn("short", F.substring("context", 2, k - 1)).join(below, ["short", "char"])
        chance = lambda x: F.when(F.col(f"total_{x}") > 0, (F.col(f"seen_{x}") + F.col(f"kinds_{x}") * F.col(f"below_{x}")) / (F.col(f"total_{x}") + F.col(f"kinds_{x}"))).otherwise(F.col(f"below_{x}"))
        now = now.select("context", "char", "n", *(chance(x).alias(f"below_{x}") for x in "ab"))
        below = now.select(F.col("context").alias("short"), "char", "below_a", "below_b")
    return now.select("context", "char", "n", F.round(F.log(F.col("below_a") / F.col("below_b")) * 1e9).cast("long").alias("ratio"))


def scored(spark: SparkSession, urls: DataFrame, order: int = ORDER, frequent: int = FREQUENT) -> DataFrame:
    """urls(url, accepted, rejected: rows with it that rules accept and reject; distinct URLs) with ``score``: the accepted model's log-likelihood less the rejected one's, over the length with the end sign."""
    urls = materialise(spark, urls.withColumn("u", F.monotonically_increasing_id()), "urls")
    good, bad = urls.agg(F.coalesce(F.sum("accepted"), F.lit(0)), F.coalesce(F.sum("rejected"), F.lit(0))).first()
    if not good or not bad:
        return urls.select("url", "accepted", "rejected", F.lit(0.0).alias("score"))
    grams = ngrams(urls, order)
    ratios = materialise(spark, log_ratios(materialise(spark, counts(grams, order), "counts"), order), "ratios")
    places = ratios.agg(F.sum("n")).first()[0]
    often = F.col("n") * frequent >= places  # at most ``frequent`` n-grams can have so large a share
    at = grams.select("u", "context", "char").join(F.broadcast(ratios.filter(often).select("context", "char", "ratio")), ["context", "char"], "left")
    seldom = at.filter("ratio is null").drop("ratio").join(ratios.filter(~often).select("context", "char", "ratio"), ["context", "char"])
    sums = at.filter("ratio is not null").select("u", "ratio").union(seldom.select("u", "ratio")).groupBy("u").agg(F.sum("ratio").alias("ratio"))
    return urls.join(sums, "u").select("url", "accepted", "rejected", (F.col("ratio") / 1e9 / (F.length("url") + 1)).alias("score"))


def held_out(url: str = "url") -> Column:
    """URLs that calibrate the threshold and train no model: a fifth, by a hash."""
    return F.pmod(F.xxhash64(url, F.lit(10)), F.lit(5)) == 0


def calibrate(rows: DataFrame, bins: int = 1000) -> float:
    """Threshold on ``score`` of rows(accepted, rejected, score) where the shares of wrongly judged of both kinds are closest.

    As the threshold grows, the share of accepted URLs below it grows and the share of rejected ones from it on falls. The
    score where they cross is found by histograms, each within the one bin of the one before, until a bin has one score.
    """
    some = rows.filter("accepted + rejected > 0")
    total = some.agg(F.sum("accepted").alias("good"), F.sum("rejected").alias("bad"), F.min("score").alias("low"), F.max("score").alias("high")).first()
    if not total.good or not total.bad:
        return 0.0
    low, high, good, bad = total.low, total.high, 0, 0  # counts below ``low``

    def gap(good: int, bad: int) -> float:
        return good / total.good - (1 - bad / total.bad)

    while low < high:
        width = (high - low) / bins
        at = F.least(F.lit(bins - 1), F.floor((F.col("score") - low) / width)) if width > 0 else F.lit(0)
        within = some.filter((F.col("score") >= low) & (F.col("score") <= high)).groupBy(at.alias("bin"))
        found = sorted(within.agg(F.sum("accepted").alias("good"), F.sum("rejected").alias("bad"), F.min("score").alias("low"), F.max("score").alias("high")).collect())
        for r in found:  # ``bins`` rows at most
            if gap(good + r.good, bad + r.bad) >= 0 or r is found[-1]:
                break
            good, bad = good + r.good, bad + r.bad
        if (r.low, r.high) == (low, high):  # neighbouring numbers that no bin divides
            break
        low, high = r.low, r.high
    own = some.filter(F.col("score") == low).agg(F.sum("accepted").alias("good"), F.sum("rejected").alias("bad")).first()
    above = some.filter(F.col("score") > low).agg(F.min("score")).first()[0]
    return float(low if above is None or -gap(good, bad) <= gap(good + own.good, bad + own.bad) else above)


def judge(spark: SparkSession, pages: DataFrame, rules: list[Rule] = RULES) -> DataFrame:
    """page_id, host, path, rule, verdict and score of every row of pages(page_id, url)."""
    rows = pages.select("page_id", F.col("url").cast("string").alias("url"))
    rows = rows.select("page_id", "url", host_of(F.col("url")).alias("host"), path_of(F.col("url")).alias("path"))
    rows = rows.withColumn("fit", rule_of(F.col("host"), F.col("path"), rules))
    ruled = lambda verdict: F.count_if(F.col("fit.verdict") == verdict)
    distinct = rows.filter(F.contains("url", F.lit("://"))).groupBy("url").agg(ruled("allow").alias("accepted"), ruled("block").alias("rejected"))
    seen = lambda c: F.when(held_out(), 0).otherwise(F.col(c))
    scores = scored(spark, distinct.select("url", seen("accepted").alias("accepted"), seen("rejected").alias("rejected")))
    scores = materialise(spark, scores.select("url", "score").join(distinct, "url"), "scores")
    ours = scores.filter(held_out())
    kinds = ours.agg(F.coalesce(F.sum("accepted"), F.lit(0)), F.coalesce(F.sum("rejected"), F.lit(0))).first()
    threshold = calibrate(ours if all(kinds) else scores)
    done = rows.join(scores.select("url", "score"), "url", "left").withColumn("score", F.coalesce("score", F.lit(0.0)))
    verdict = F.coalesce("fit.verdict", F.when(F.col("score") >= threshold, "allow").otherwise("block"))
    return done.select("page_id", "host", "path", F.col("fit.name").alias("rule"), verdict.alias("verdict"), "score")


def op10_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(spark, table(spark, sf_dir, "pages"))
