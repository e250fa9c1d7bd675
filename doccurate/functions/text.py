"""Text measures: normal form, grams, overlap, agreement, edit similarity."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def computed(df: DataFrame, **columns: Column) -> DataFrame:
    """df with columns that are computed once: later filters and projections can't copy their expressions below this step."""
    return df.select("*", F.inline(F.array(F.struct(*(c.alias(k) for k, c in columns.items())))))


def bound(value: Column, use: Callable[[Column], Column]) -> Column:
    """use(value) with value computed once: inside a lambda a free expression would be computed for every element."""
    return F.get(F.transform(F.array(value), use), F.lit(0))


def norm(text: Column) -> Column:
    """Lower case; runs of characters other than letters and digits become one space; trimmed."""
    return F.trim(F.regexp_replace(F.lower(text), r"[^\p{L}\p{N}]+", " "))


def words(text: Column) -> Column:
    """Words of the normal form; none for blank text."""
    return F.filter(F.split(norm(text), " "), lambda w: w != "")


def grams(text: Column, n: int = 4, unit: str = "char", distinct: bool = True) -> Column:
    """Windows of n code points or words of the normal form; none if it is shorter."""
    glue = "" if unit == "char" else " "
    starts = lambda u: F.when(F.size(u) >= n, F.sequence(F.lit(0), F.size(u) - n)).otherwise(F.array().cast("array<int>"))
    windows = lambda u: F.transform(starts(u), lambda i: F.concat_ws(glue, *(F.get(u, i + k) for k in range(n))))
    found = bound(F.split(norm(text), "") if unit == "char" else words(text), windows)
    return F.array_distinct(found) if distinct else found


def overlap(question: Column, text: Column, denom: str = "question") -> Column:
    """Share of common grams of two gram arrays; null where the denominator is empty.

    denom: question, text, union (Jaccard) or min.
    """

    def measure(q: Column, t: Column) -> Column:
        size = {
            "question": F.size(q),
            "text": F.size(t),
            "union": F.size(F.array_union(q, t)),
            "min": F.least(F.size(q), F.size(t)),
        }[denom]
        return F.when(size > 0, F.size(F.array_intersect(q, t)) / size)

    return bound(question, lambda q: bound(text, lambda t: measure(q, t)))


def strip_markup(markdown: Column) -> Column:
    """Markdown without heading, emphasis, list and link signs."""
    return F.regexp_replace(F.regexp_replace(markdown, r"\[([^\]]*)\]\([^)]*\)", "$1"), r"[#*_`>]+|(?m)^- ", "")


def dice(a: Column, b: Column) -> Column:
    """Dice coefficient of the word sets of two short texts; null if neither has words."""
    x, y = F.array_distinct(words(a)), F.array_distinct(words(b))
    total = F.size(x) + F.size(y)
    return F.when(total > 0, 2 * F.size(F.array_intersect(x, y)) / total)


def edit_ratio(a: Column, b: Column) -> Column:
    """1 - edit distance over the longer length; 1 for two empty strings."""
    longest = F.greatest(F.length(a), F.length(b))
    return F.when(longest == 0, 1.0).otherwise(1 - F.levenshtein(a, b) / longest)


def jaccard(a: Column, b: Column) -> Column:
    """Jaccard of the distinct words of two texts; null if neither has words."""
    return overlap(F.array_distinct(words(a)), F.array_distinct(words(b)), "union")


def gram_cosine(a: Column, b: Column, dims: int = 64, n: int = 3) -> Column:
    """Cosine of two short texts' vectors of character gram counts, hashed by md5 to so many places; null if either has no gram."""
    place = lambda g: F.conv(F.substring(F.md5(g.cast("binary")), 1, 8), 16, 10).cast("long") % dims
    counts = lambda ps: F.transform(F.sequence(F.lit(0), F.lit(dims - 1)), lambda i: F.size(F.filter(ps, lambda p: p == i)).cast("double"))
    vector = lambda t: bound(F.transform(grams(t, n, distinct=False), place), counts)
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p * q), F.lit(0.0), lambda s, v: s + v)
    return bound(vector(a), lambda x: bound(vector(b), lambda y: F.try_divide(dot(x, y), F.sqrt(dot(x, x) * dot(y, y)))))


def token_f1(prediction: Column, reference: Column) -> Column:
    """Harmonic mean of precision and recall of distinct words."""
    p, r = F.array_distinct(words(prediction)), F.array_distinct(words(reference))
    return F.when(F.size(p) + F.size(r) > 0, 2 * F.size(F.array_intersect(p, r)) / (F.size(p) + F.size(r))).otherwise(1.0)
