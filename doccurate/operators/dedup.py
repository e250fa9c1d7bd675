"""Deduplication of pages: exact, SimHash, MinHash bands, containment, vectors; clusters; repeated lines; disjoint sets."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from doccurate.functions.text import bound, grams, norm
from doccurate.operators import setjoin


def fp_exact(text: Column) -> Column:
    """Fingerprint of the normal form."""
    return F.md5(norm(text).cast("binary"))


def exact_groups(df: DataFrame, key: str, text: str = "text") -> DataFrame:
    """key, fp and ``keeper``: the least key of the rows with the same fingerprint."""
    own = df.select(key, fp_exact(F.col(text)).alias("fp"))
    first = own.groupBy("fp").agg(F.min(key).alias("keeper"), F.count("*").alias("copies"))
    return own.join(first, "fp")


def fp_simhash(text: Column, n: int = 3) -> Column:
    """64-bit SimHash of word n-grams: per bit, whether most gram hashes have it."""
    hashes = F.transform(grams(text, n, "word", distinct=False), lambda g: F.xxhash64(g))
    hashes = bound(hashes, lambda h: F.when(F.size(h) > 0, h).otherwise(F.array(F.xxhash64(norm(text)))))
    # Four counters of 16 bits a word would overflow on long texts: two of 32 bits, so 32 words hold the 64 counts.
    zero = F.array(*(F.lit(0).cast("long") for _ in range(32)))
    lanes = lambda h: F.array(*(F.shiftrightunsigned(h, k).bitwiseAND(F.lit(0x100000001)) for k in range(32)))
    counts = F.aggregate(hashes, zero, lambda s, h: F.zip_with(s, lanes(h), lambda x, y: x + y))

    def bits(c: Column, total: Column) -> Column:
        out = F.lit(0).cast("long")
        for b in range(64):
            count = F.get(c, F.lit(b % 32))
            count = F.shiftrightunsigned(count, 32) if b >= 32 else count.bitwiseAND(F.lit(0xFFFFFFFF))
            out = out.bitwiseOR(F.when(count * 2 > total, F.lit((1 << b) - (1 << 64 if b == 63 else 0))).otherwise(F.lit(0).cast("long")))
        return out

    return bound(counts, lambda c: bound(F.size(hashes), lambda total: bits(c, total)))


def simhash_pairs(df: DataFrame, key: str, text: str = "text", radius: int = 3) -> DataFrame:
    """Pairs of distinct fingerprints' least keys within the radius: radius + 1 blocks, one of which agrees."""
    nodes = df.select(key, fp_simhash(F.col(text)).alias("fp")).groupBy("fp").agg(F.min(key).alias("id"))
    size = -(-64 // (radius + 1))
    parts = F.array(*(F.struct(F.lit(k).alias("block"), F.shiftrightunsigned("fp", k * size).bitwiseAND(F.lit((1 << size) - 1)).alias("bits")) for k in range(radius + 1)))
    a = nodes.select("id", "fp", F.inline(parts))
    b = a.withColumnsRenamed({"id": "other", "fp": "other_fp"})
    near = a.join(b, ["block", "bits"]).filter("id < other").withColumn("distance", F.bit_count(F.col("fp").bitwiseXOR(F.col("other_fp"))))
    return near.filter(F.col("distance") <= radius).select("id", "other", "distance").distinct()


def minhash(sets: Column, perms: int, seed: int = 5) -> Column:
    """Least hashed element under ``perms`` hash functions, one pass of linear maps over 32-bit hashes."""
    rng = np.random.default_rng(seed)
    prime = (1 << 31) - 1
    base = F.transform(sets, lambda g: F.pmod(F.xxhash64(g), F.lit(prime)))
    a, b = rng.integers(1, prime, perms).tolist(), rng.integers(0, prime, perms).tolist()
    return bound(base, lambda hs: F.array(*(F.array_min(F.transform(hs, lambda h: (h * x + y) % prime)) for x, y in zip(a, b, strict=True))))


def gram_nodes(df: DataFrame, key: str, text: str = "text", n: int = 5) -> DataFrame:
    """id, set: distinct texts, each by its least key, with their word n-grams; texts without grams have no node."""
    texts = df.select(key, F.col(text).alias("t")).groupBy("t").agg(F.min(key).alias("id"))
    return texts.select("id", grams(F.col("t"), n, "word").alias("set")).filter(F.size("set") > 0)


def _linked(spread: DataFrame, on: list[str], nodes: DataFrame, threshold: float) -> DataFrame:
    """id, other, similarity of the nodes that share a row of spread(id, size, *on) and have at least this Jaccard.

    Sizes too far apart for the threshold are not compared; each candidate is verified once, on whole sets.
    """
    other = spread.withColumnsRenamed({"id": "other", "size": "other_size"})
    fits = F.least("size", "other_size") >= F.greatest("size", "other_size") * (threshold - 1e-6)
    found = spread.join(other, on).filter((F.col("id") < F.col("other")) & fits).select("id", "other").distinct()
    both = found.join(nodes.withColumnRenamed("set", "a"), "id").join(nodes.select(F.col("id").alias("other"), F.col("set").alias("b")), "other")
    common = F.size(F.array_intersect("a", "b"))
    return both.select("id", "other", F.round(common / (F.size("a") + F.size("b") - common), 6).alias("similarity")).filter(F.col("similarity") >= threshold)


def near_pairs(df: DataFrame, key: str, text: str = "text", n: int = 5, perms: int = 64, bands: int = 16, threshold: float = 0.7, keep: Callable[[DataFrame], DataFrame] = lambda x: x) -> DataFrame:
    """id, other, similarity: pairs of distinct texts whose word n-gram sets have at least this Jaccard.

    Equal texts are one node (its least key). All nodes of a band's bucket are candidates, gram sets verify them;
    what no band proposes is missed, ``gram_join_pairs`` finds that too. keep may write the node table.
    """
    nodes = keep(gram_nodes(df, key, text, n))
    rows = perms // bands
    signed = nodes.select("id", F.size("set").alias("size"), minhash(F.col("set"), perms).alias("sig"))
    banded = signed.select("id", "size", F.posexplode(F.array(*(F.xxhash64(F.slice("sig", k * rows + 1, rows)) for k in range(bands)))).alias("band", "bucket"))
    return _linked(banded, ["band", "bucket"], nodes, threshold)


def gram_join_pairs(df: DataFrame, key: str, text: str = "text", n: int = 5, threshold: float = 0.7, keep: Callable[[DataFrame], DataFrame] = lambda x: x, copies: bool = False) -> DataFrame:
    """All such pairs, exactly, by prefixes: in any common order of grams, two sets that are alike enough share one of
    their first grams, so only these are joined, as hashes; an order by frequency in a sample keeps what many texts share out of them.
    copies: each other key of an equal text that has grams is paired with the least one, at 1, so the components are those of all rows.
    keep may write the rows, so that their numbers stay (without it df must give its rows in one order).
    """
    given = df.select(F.monotonically_increasing_id().alias("row"), F.col(key).alias("id"), F.md5(F.col(text).cast("binary")).alias("fp"), norm(F.col(text)).alias("words"))
    whole = given.filter("words is not null").withColumn("has_grams", F.size(F.filter(F.split("words", " "), lambda w: w != "")) >= n)
    rows = keep(whole if copies else whole.drop("has_grams"))
    first = rows.groupBy("fp").agg(F.min(F.struct(F.col("id").isNull().alias("lost"), "id", "row")).alias("first"), F.count("*").alias("n"))
    nodes = keep(first.select("first.row", "first.id", F.when(F.col("n") > 1, F.col("fp")).alias("fp")) if copies else first.select("first.row"))
    pairs = setjoin.alike(setjoin.among(rows.select("row", "id", "words"), nodes.select("row"), keep), nodes.count(), n, threshold, keep)
    if not copies:
        return pairs
    others = rows.filter("has_grams").select("fp", F.col("id").alias("other"))
    return pairs.union(nodes.join(others, "fp").filter("id < other").select("id", "other", F.lit(1.0).alias("similarity")).distinct())


def contained_in(small: DataFrame, small_key: str, big: DataFrame, big_key: str, n: int = 5, min_share: float = 0.8) -> DataFrame:
    """small_key, big_key, share of the small text's word n-grams that the big text has."""
    s = small.select(small_key, grams(F.col("text"), n, "word").alias("set")).select(small_key, F.size("set").alias("size"), F.explode("set").alias("gram"))
    b = big.select(big_key, F.explode(grams(F.col("text"), n, "word")).alias("gram"))
    shared = b.join(s, "gram").groupBy(small_key, big_key, "size").agg(F.count("*").alias("common"))
    return shared.select(small_key, big_key, F.round(F.col("common") / F.col("size"), 6).alias("share")).filter(F.col("share") >= min_share)


def near_vectors(df: DataFrame, key: str, vector: str, tau: float = 0.9, tables: int = 30, bits: int = 8, seed: int = 3) -> DataFrame:
    """id, other, cosine: pairs that share a random-hyperplane bucket in a table and have at least this cosine.

    A pair at the cosine 0.9 shares none with a chance of about 4 in 100,000, one above with less. Vectors have the length of the
    longest; null, shorter and zero ones have no pair.
    """
    dims = df.agg(F.max(F.size(vector))).first()[0] or 0
    df = df.filter(F.size(vector) == dims)
    planes = np.random.default_rng(seed).normal(size=(tables * bits, dims)).round(4)
    length = lambda v: F.sqrt(F.aggregate(v, F.lit(0.0), lambda s, y: s + y * y))
    unit = bound(F.transform(vector, lambda x: x.cast("double")), lambda v: bound(length(v), lambda n: F.transform(v, lambda x: F.try_divide(x, n))))
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
    rows = df.select(F.col(key).alias("id"), unit.alias("u")).filter("not exists(u, x -> x is null or isnan(x))")
    sides = lambda t: sum((F.when(dot(F.col("u"), F.array(*map(F.lit, planes[t * bits + k].tolist()))) > 0, 1 << k).otherwise(0) for k in range(bits)), F.lit(0))
    dealt = rows.select("id", "u", F.posexplode(F.array(*(sides(t) for t in range(tables)))).alias("table", "bucket"))
    other = dealt.withColumnsRenamed({"id": "other", "u": "w"})
    near = dealt.join(other, ["table", "bucket"]).filter("id < other").select("id", "other", F.round(dot(F.col("u"), F.col("w")), 6).alias("cosine"))
    return near.filter(F.col("cosine") >= tau).distinct()


def clusters(pairs: DataFrame, keep: Callable[[DataFrame], DataFrame], most: int = 50) -> DataFrame:
    """node, root (least reachable node) of the linked nodes of pairs(id, other). keep must cut lineage (checkpoint or a written table)."""
    both = keep(pairs.select("id", "other").union(pairs.select(F.col("other").alias("id"), F.col("id").alias("other"))).distinct())
    labels = keep(both.groupBy("id").agg(F.least(F.min("other"), F.first("id")).alias("root")))
    for _ in range(most):
        around = both.join(labels.select(F.col("id").alias("other"), F.col("root").alias("r")), "other").groupBy("id").agg(F.min("r").alias("r"))
        stepped = labels.join(around, "id").select("id", F.least("root", "r").alias("root"))
        jumped = stepped.join(labels.select(F.col("id").alias("root"), F.col("root").alias("up")), "root", "left").select("id", F.least("root", F.coalesce("up", "root")).alias("new"))
        after = keep(jumped.join(labels, "id").select("id", "root", "new"))
        labels = after.select("id", F.col("new").alias("root"))
        if after.filter("root <> new").isEmpty():
            return labels.withColumnRenamed("id", "node")
    raise RuntimeError("clusters did not settle")


def boilerplate_lines(docs: DataFrame, min_docs: int = 10) -> DataFrame:
    """Lines that occur in at least so many documents, with occurrences and documents."""
    lines = docs.select("doc_id", F.explode(F.split("text", "\n")).alias("line")).filter(F.trim("line") != "")
    per_doc = lines.groupBy("line", "doc_id").agg(F.count("*").alias("n"))
    return per_doc.groupBy("line").agg(F.sum("n").alias("occurrences"), F.count("*").alias("documents")).filter(F.col("documents") >= min_docs)


def drop_boilerplate(docs: DataFrame, min_docs: int = 10) -> DataFrame:
    """doc_id, text without such lines, lines dropped."""
    lines = docs.select("doc_id", F.posexplode(F.split("text", "\n")).alias("at", "line"))
    marked = lines.join(boilerplate_lines(docs, min_docs).select("line", F.lit(True).alias("hot")), "line", "left")
    kept = F.array_sort(F.collect_list(F.when(F.col("hot").isNull(), F.struct("at", "line"))))
    return marked.groupBy("doc_id").agg(F.array_join(F.transform(kept, lambda x: x.line), "\n").alias("text"), F.count("hot").alias("dropped"))


def disjoint_sets(sets: list[tuple[str, int, DataFrame]]) -> DataFrame:
    """dataset, key, fp of rows that stay when each text is kept once, in the set of least priority number, at its least key.

    sets: (name, priority, rows(key, text)).
    """
    tagged = None
    for name, priority, rows in sets:
        one = rows.select(F.lit(name).alias("dataset"), F.lit(priority).alias("priority"), F.col("key").cast("string").alias("key"), fp_exact(F.col("text")).alias("fp"))
        tagged = one if tagged is None else tagged.unionByName(one)
    best = tagged.groupBy("fp").agg(F.min(F.struct("priority", "key", "dataset")).alias("best"))
    return best.select("best.dataset", "best.key", "fp")


def disjoint_near(sets: list[tuple[str, int, DataFrame]], protected: int = 0, n: int = 5, min_share: float = 0.8) -> DataFrame:
    """As disjoint_sets, and without rows beyond the protected priority that hold a near or whole copy of a protected text within.

    A text of fewer than n words is only found where it is equal. The protected sets are test sets: small beside the others.
    """
    kept = disjoint_sets(sets)
    tagged = [(priority, rows.select(F.lit(name).alias("dataset"), F.col("key").cast("string").alias("key"), "text")) for name, priority, rows in sets]
    guarded, others = ([rows for priority, rows in tagged if (priority <= protected) == side] for side in (True, False))
    if not guarded or not others:
        return kept
    small, big = (_all(some).withColumn("both", F.struct("dataset", "key")) for some in (guarded, others))
    inside = contained_in(small.select(F.col("both").alias("own"), "text"), "own", big.select("both", "text"), "both", n, min_share)
    return kept.join(inside.select("both.dataset", "both.key").distinct(), ["dataset", "key"], "left_anti")


def _all(some: list[DataFrame]) -> DataFrame:
    out = some[0]
    for rows in some[1:]:
        out = out.unionByName(rows)
    return out


def without_leaks(train: DataFrame, test: DataFrame, train_key: str, test_key: str) -> DataFrame:
    """train without rows that equal a test text or hold one within."""
    equal = test.select(fp_exact(F.col("text")).alias("fp")).distinct()
    inside = contained_in(test, test_key, train, train_key).select(train_key).distinct()
    return train.join(inside, train_key, "left_anti").join(equal, fp_exact(train["text"]) == equal["fp"], "left_anti")


def assert_disjoint(train: DataFrame, test: DataFrame, train_key: str, test_key: str) -> None:
    """Raise if a test text equals, or lies within, a training text."""
    found = leaks(train, test, train_key, test_key).count()
    if found:
        raise ValueError(f"{found} test texts leak into the training set")


def leaks(train: DataFrame, test: DataFrame, train_key: str, test_key: str) -> DataFrame:
    """Test keys whose text equals a training text, or whose 5-grams lie within one; empty if the sets are disjoint."""
    same = test.select(test_key, fp_exact(F.col("text")).alias("fp")).join(train.select(fp_exact(F.col("text")).alias("fp")).distinct(), "fp", "left_semi").select(test_key, F.lit("equal").alias("how"))
    inside = contained_in(test, test_key, train, train_key).select(test_key, F.lit("contained").alias("how"))
    return same.union(inside).distinct()
