"""Document fingerprints: a homomorphic multiset hash of paragraphs, with DataFrame functions only.

A text is the multiset of its lines. Each line has a wide vector: EXACT lanes of 32 bits from salted hashes of
the whole line, and LANES lanes of 16 bits, the sum over the line's phrases of +1 or -1 for each bit of
the phrase's hash. A fingerprint is the sum of the vectors, lane by lane modulo 2**32 and 2**16. So it
does not depend on the order of lines, equal multisets have equal fingerprints, and a line is added or taken away by
adding or subtracting its vector (``combine``). Phrases end after words whose last letter is in a fixed
class, hence an edit moves only the phrases that it touches. The cosine of the centred narrow lanes estimates the
share of common phrases (``likeness``).

Null texts count as empty; an empty text is one empty line; repeated rows have equal fingerprints; rows with a
null id come last in descending order; with a single row, it is its own next; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from doccurate.llm.common import table

EXACT, LANES = 8, 128
#: A phrase ends after a line, or at white space after one of these characters.
_PHRASE_END = r"\n|(?<=[adegimorsty.,;:!?])[ \t]+"
_LOW32 = 0xFFFFFFFF


def _elements(text: Column) -> Column:
    """Lines, then phrases, of a text as one array."""
    return F.concat(F.split(text, "\n", -1), F.split(text, _PHRASE_END, -1))


def _sums(element: Column, is_line: Column, is_phrase: Column) -> list[Column]:
    """Sums over elements: EXACT of line lanes, the number of phrases, LANES / 2 of two bit counts each."""
    exact = [F.sum(F.when(is_line, F.xxhash64(element, F.lit(k)).bitwiseAND(F.lit(_LOW32))).otherwise(0)) for k in range(EXACT)]
    out = [x.alias(f"e{k}") for k, x in enumerate(exact)]
    out.append(F.sum(F.when(is_phrase, 1).otherwise(0)).cast("long").alias("n"))
    for w in range(LANES // 64):
        h = F.when(is_phrase, F.xxhash64(element, F.lit(100 + w))).otherwise(0)
        for k in range(32):
            out.append(F.sum(F.shiftrightunsigned(h, k).bitwiseAND(F.lit(0x100000001))).alias(f"b{w * 32 + k}"))
    return out


def _wide() -> Column:
    """The exact lanes modulo 2**32, as one array."""
    return F.array(*(F.col(f"e{k}").bitwiseAND(F.lit(_LOW32)) for k in range(EXACT)))


def _narrow() -> Column:
    """The narrow lanes, twice the bit count less the number of phrases, modulo 2**16."""
    lanes = []
    for k in range(LANES // 2):
        for count in (F.col(f"b{k}").bitwiseAND(F.lit(_LOW32)), F.shiftrightunsigned(F.col(f"b{k}"), 32)):
            lanes.append((count * 2 - F.col("n")).bitwiseAND(F.lit(0xFFFF)).cast("int"))
    return F.array(*lanes)


def as_text(wide: Column, narrow: Column) -> Column:
    """Hex digits of a fingerprint: 8 an exact lane, 4 a narrow lane."""
    digits = [F.lpad(F.hex(F.get(wide, F.lit(k))), 8, "0") for k in range(EXACT)]
    return F.lower(F.concat(*digits, F.array_join(F.transform(narrow, lambda x: F.lpad(F.hex(x), 4, "0")), "")))


def combine(a: Column, b: Column, bits: int, sign: int = 1) -> Column:
    """Lanes of the union of two multisets (sign 1), or of a without b (sign -1), modulo 2**bits."""
    return F.zip_with(a, b, lambda x, y: (x.cast("long") + y.cast("long") * sign).bitwiseAND(F.lit((1 << bits) - 1)))


def _centred(lane: Column) -> Column:
    return (F.pmod(lane + 32768, F.lit(65536)) - 32768).cast("double")


def likeness(a: Column, b: Column) -> Column:
    """Cosine of two fingerprints' centred narrow lanes, 0 where it is negative; equal ones, empty too, have 1."""
    zero = F.struct(F.lit(0.0).alias("ab"), F.lit(0.0).alias("aa"), F.lit(0.0).alias("bb"))
    pairs = F.zip_with(a, b, lambda x, y: F.struct(_centred(x).alias("x"), _centred(y).alias("y")))
    done = F.aggregate(
        pairs,
        zero,
        lambda s, p: F.struct((s.ab + p.x * p.y).alias("ab"), (s.aa + p.x * p.x).alias("aa"), (s.bb + p.y * p.y).alias("bb")),
        lambda s: F.when((s.aa == 0) | (s.bb == 0), 0.0).otherwise(F.greatest(F.lit(0.0), F.least(F.lit(1.0), s.ab / F.sqrt(s.aa * s.bb)))),
    )
    return F.when(a == b, 1.0).otherwise(done)


def fingerprints(docs: DataFrame, *keys: str) -> DataFrame:
    """keys, wide, narrow: the fingerprint of all lines of ``text`` of the rows with these keys.

    Rows of a key add up, so a document can be given as many rows as it has parts, if they are cut at line ends
    and each part but the last has lost its newline.
    """
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    lines = F.size(F.split(text, "\n", -1)).alias("lines")
    each = docs.select(*keys, lines, F.posexplode(_elements(text)))
    line = F.col("pos") < F.col("lines")
    return each.groupBy(*keys).agg(*_sums(F.col("col"), line, ~line & (F.col("col") != ""))).select(*keys, _wide().alias("wide"), _narrow().alias("narrow"))


def _with_ghosts(spark: SparkSession, docs: DataFrame, buckets: int) -> DataFrame:
    """Rows dealt into ranges of descending doc_id; the first row of a range comes again, as a ghost, at the end of the range before.

    Then each row's next one is in its range. What reaches the driver are ``buckets`` range limits and least row marks.
    """
    rows = docs.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"),
        F.coalesce(F.bitwise_not(F.col("doc_id").cast("long")), F.lit((1 << 63) - 1)).alias("low"),
    )
    shares = [k / buckets for k in range(1, buckets)] or [0.5]
    limits = sorted(set(rows.agg(F.percentile_approx("low", shares, 20 * buckets)).first()[0] or [0]))
    size = max(1, int(len(limits) ** 0.5))
    groups = [limits[k : k + size] for k in range(0, len(limits), size)]
    # The range of a row is the number of limits below it: first by groups of limits, then in the group.
    group = F.greatest(F.size(F.filter(F.lit([g[0] for g in groups]), lambda x: x < F.col("low"))) - 1, F.lit(0))
    inner = F.size(F.filter(F.get(F.array(*(F.lit(g) for g in groups)), group), lambda x: x < F.col("low")))
    rows = rows.withColumn("bucket", group * size + inner)
    first = sorted(tuple(r) for r in rows.groupBy("bucket").agg(F.min("low")).collect())  # a row a range
    least, before = [(1 << 63) - 1] * (len(limits) + 1), [0] * (len(limits) + 1)
    for k, (bucket, low) in enumerate(first):
        least[bucket], before[bucket] = low, first[k - 1][0]  # the first range follows the last
    own, ghost = F.struct("bucket", F.lit(False).alias("ghost")), F.struct(F.get(F.lit(before), F.col("bucket")).alias("bucket"), F.lit(True).alias("ghost"))
    is_first = F.get(F.lit(least), F.col("bucket")) == F.col("low")
    return rows.select("doc_id", "text", "low", F.inline(F.when(is_first, F.array(own, ghost)).otherwise(F.array(own))))


def op4_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return with_edits(spark, table(spark, sf_dir, "documents"))


def with_edits(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """Fingerprints of docs(doc_id, text) and of each text whose second half is the start of the next one's, with their likeness."""
    buckets = 4 * int(spark.conf.get("spark.sql.shuffle.partitions"))
    dealt = _with_ghosts(spark, docs, max(1, min(buckets, 4000)))
    order = W.partitionBy("bucket").orderBy("ghost", "low", "text")
    n_chars = F.length("text")
    half = (n_chars / 2).cast("int")
    edited = F.concat(F.substring("text", F.lit(1), n_chars - half), F.substring(F.col("next"), F.lit(1), half))
    paired = dealt.select("bucket", "doc_id", "ghost", "text", F.row_number().over(order).alias("spot"), F.lead("text").over(order).alias("next"))
    paired = paired.withColumn("edited", F.when(F.col("ghost"), F.lit("")).otherwise(edited))
    # Elements of the text, then of the edited text, in one pass; sums of both in one row.
    text_lines, edited_lines = F.size(F.split("text", "\n", -1)), F.size(F.split("edited", "\n", -1))
    both = F.array(F.struct(F.lit(0).alias("which"), F.col("text").alias("t"), text_lines.alias("lines")), F.struct(F.lit(1).alias("which"), F.col("edited").alias("t"), edited_lines.alias("lines")))
    each = paired.select("bucket", "spot", "doc_id", "ghost", n_chars.cast("long").alias("n_chars"), F.sha2(F.col("edited").cast("binary"), 256).alias("edited_sha256"), F.inline(both))
    each = each.select("bucket", "spot", "doc_id", "ghost", "n_chars", "edited_sha256", "which", "lines", F.posexplode(_elements(F.col("t"))))
    line = F.col("pos") < F.col("lines")
    keys = ["bucket", "spot", "doc_id", "ghost", "n_chars", "edited_sha256", "which"]
    summed = each.groupBy(*keys).agg(*_sums(F.col("col"), line, ~line & (F.col("col") != ""))).select(*keys, _wide().alias("wide"), _narrow().alias("narrow"))
    at = W.partitionBy("bucket").orderBy("spot", "which")
    wide = summed.select(*keys, "wide", "narrow", *(F.lead(c, k).over(at).alias(f"{c}{k}") for c, k in (("wide", 1), ("narrow", 1), ("narrow", 2))))
    return wide.filter("which = 0 AND NOT ghost").select(
        "doc_id", "n_chars", "edited_sha256",
        as_text(F.col("wide"), F.col("narrow")).alias("fingerprint"),
        as_text(F.col("wide1"), F.col("narrow1")).alias("edited_fingerprint"),
        likeness(F.col("narrow"), F.col("narrow1")).alias("near_edited"),
        likeness(F.col("narrow"), F.col("narrow2")).alias("near_next"),
    )
