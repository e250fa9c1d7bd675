"""From crawl records to pages of text: sampling, links, fetching, extraction, pages, yield."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from doccurate.functions.keys import hash_order, uniform
from doccurate.functions.text import bound, dice, edit_ratio, jaccard, strip_markup, words
from doccurate.functions.web import absolute, article_of, canonical_url, hrefs, to_markdown, to_plain


def sample_archives(df: DataFrame, key: str, fraction: float = 0.0625, salt: str = "archive", exact: int | None = None) -> DataFrame:
    """Rows of a keyed share of the archives; exact: of that many archives, in hash order."""
    if exact is None:
        return df.filter(uniform(key, salt) < fraction)
    chosen = df.select(key).distinct().orderBy(hash_order(key, salt), key).limit(exact)
    return df.join(F.broadcast(chosen), key, "left_semi")  # ``exact`` keys


def harvest_links(pages: DataFrame, url_col: str = "url", html_col: str = "html", suffix: str = "") -> DataFrame:
    """Distinct canonical targets that end in suffix, with the number of records that name each."""
    links = pages.select(F.col(url_col).alias("base"), F.explode(hrefs(F.col(html_col))).alias("href"))
    target = canonical_url(absolute(F.col("base"), F.col("href")))
    found = links.select("base", target.alias("target")).filter(F.col("target").endswith(suffix))
    return found.groupBy("target").agg(F.countDistinct("base").alias("records"))


def fetch(links: DataFrame, fetcher: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """Targets with what the fetcher gives for them (status, content); the fetcher is a DataFrame function."""
    return fetcher(links)


def table_fetcher(pages: DataFrame) -> Callable[[DataFrame], DataFrame]:
    """Offline stand-in of a downloader: a target is found if a record has its canonical URL."""
    known = pages.select(canonical_url(F.col("url")).alias("target"), "html").groupBy("target").agg(F.min("html").alias("content"))

    def get(links: DataFrame) -> DataFrame:
        return links.join(known, "target", "left").withColumn("status", F.when(F.col("content").isNull(), 404).otherwise(200))

    return get


def page_views(pages: DataFrame) -> DataFrame:
    """Crawl records as pages: article text (parse), all visible text (ocr), plain and Markdown of the article."""
    html = F.col("html")
    return pages.select(
        F.concat(F.lit("pages:"), F.col("page_id").cast("string"), F.lit(":0")).alias("image_id"), "page_id",
        F.regexp_extract(html, r'<html[^>]*lang="([a-z]+)"', 1).alias("lang"),
        to_plain(article_of(html)).alias("view_parse"), to_plain(html).alias("view_ocr"),
        to_plain(article_of(html)).alias("plain"), to_markdown(article_of(html)).alias("markdown"),
    )


def folded(text: Column, block_chars: int) -> Column:
    """Lines gathered into pages: a page closes when its next line would take it beyond block_chars."""
    first = F.struct(F.array().cast("array<string>").alias("done"), F.lit("").alias("open"))
    lines = F.split(text, "\n", -1)

    def step(state: Column, line: Column) -> Column:
        fits = F.length(state.open) + 1 + F.length(line) <= block_chars
        return (
            F.when(state.open == "", F.struct(state.done.alias("done"), line.alias("open")))
            .when(fits, F.struct(state.done.alias("done"), F.concat(state.open, F.lit("\n"), line).alias("open")))
            .otherwise(F.struct(F.concat(state.done, F.array(state.open)).alias("done"), line.alias("open")))
        )

    return F.aggregate(lines, first, step, lambda s: F.concat(s.done, F.array(s.open)))


def paginate(docs: DataFrame, block_chars: int = 800, by: str = "fold") -> DataFrame:
    """doc columns with page_no and page_text; by: fold (blocks of lines), lines, or form_feed."""
    text = F.coalesce("text", F.lit(""))
    parts = {"fold": lambda: folded(text, block_chars), "lines": lambda: F.split(text, "\n"), "form_feed": lambda: F.split(text, "\f")}[by]()
    keep = [c for c in docs.columns if c != "text"]
    return docs.select(*keep, F.posexplode(parts).alias("page_no", "page_text"))


def noisy(text: Column, key: Column) -> Column:
    """Stand-in of optical recognition: every 50th word, from a keyed one on, has look-alike characters."""
    start = F.floor(uniform(key, "noise") * 50).cast("int")
    look_alike = lambda w: F.translate(w, "olieas", "011345")
    changed = lambda first: F.transform(F.split(text, " "), lambda w, i: F.when((i + first) % 50 == 0, look_alike(w)).otherwise(w))
    return F.array_join(bound(start, changed), " ")


def document_views(docs: DataFrame, block_chars: int = 800, use: tuple[str, ...] = ("parse", "ocr")) -> DataFrame:
    """Pages of documents with both text views; a view that is not in use is null."""
    key = F.concat(F.lit("documents:"), F.col("doc_id").cast("string"), F.lit(":"), F.col("page_no").cast("string"))
    paged = paginate(docs, block_chars).select("doc_id", "page_no", "lang", key.alias("image_id"), "page_text")
    views = {"parse": F.col("page_text"), "ocr": noisy(F.col("page_text"), F.col("image_id"))}
    return paged.select("image_id", "doc_id", "page_no", "lang", *(v.alias(f"view_{k}") if k in use else F.lit(None).cast("string").alias(f"view_{k}") for k, v in views.items()))


def min_chars(df: DataFrame, col: str, least: int = 100, strict: bool = False) -> DataFrame:
    return df.filter(F.length(col) > least if strict else F.length(col) >= least)


def multiset_dice(df: DataFrame, key: str, a: Column, b: Column) -> DataFrame:
    """key, agreement: Dice coefficient of the word multisets of two texts of a row; rows without any word are missing."""
    sides = F.array(F.struct(F.lit(1).alias("a"), F.lit(0).alias("b"), words(a).alias("ws")), F.struct(F.lit(0).alias("a"), F.lit(1).alias("b"), words(b).alias("ws")))
    each = df.select(key, F.inline(sides)).select(key, "a", "b", F.explode("ws").alias("w"))
    counts = each.groupBy(key, "w").agg(F.sum("a").alias("a"), F.sum("b").alias("b"))
    return counts.groupBy(key).agg((2 * F.sum(F.least("a", "b")) / F.sum(F.col("a") + F.col("b"))).alias("agreement"))


def with_agreement(df: DataFrame, key: str = "image_id", plain: str = "plain", markdown: str = "markdown", measure: str = "dice", max_diff: float = 0.2) -> DataFrame:
    """df with ``agreement`` of the two renderings and ``agrees``; rows without words have a null agreement and don't agree."""
    a, b = F.col(plain), strip_markup(F.col(markdown))
    if measure == "dice":
        rows = df.join(multiset_dice(df, key, a, b), key, "left")
    else:
        rows = df.withColumn("agreement", {"set_dice": dice, "jaccard": jaccard, "edit": edit_ratio}[measure](a, b))
    return rows.withColumn("agrees", F.coalesce(F.col("agreement") >= 1 - max_diff, F.lit(False)))


def language_share(df: DataFrame, lang: str = "lang") -> DataFrame:
    counted = df.groupBy(lang).agg(F.count("*").alias("n"))
    return counted.withColumn("share", F.col("n") / F.sum("n").over(W.partitionBy(F.lit(1))))  # a row a language


def corpus_report(pages: DataFrame, target: str, least: int = 100, max_diff: float = 0.2) -> DataFrame:
    """One row: records, those in the target language, pages kept by each filter, pages a record, share."""
    views = with_agreement(page_views(pages), max_diff=max_diff)
    ours, long = F.col("lang") == target, F.length("plain") >= least
    row = views.agg(
        F.count("*").alias("collected"), F.count_if(ours).alias("in_language"), F.count_if(ours & long).alias("long_enough"),
        F.count_if(ours & long & F.col("agrees")).alias("kept"), F.countDistinct(F.when(ours & long & F.col("agrees"), F.col("page_id"))).alias("records_kept"),
    )
    return row.withColumn("share", F.round(F.col("in_language") / F.col("collected"), 6)).withColumn("pages_per_record", F.round(F.col("kept") / F.nullif("records_kept", F.lit(0)), 6))
