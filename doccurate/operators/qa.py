"""Question-answer generation: calls, prompts, generators, format check, splits, sizes."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from doccurate.functions.keys import uniform
from doccurate.functions.text import computed

#: Three hand-written exemplars a language (fixed values): question and answer.
EXEMPLARS: dict[str, list[tuple[str, str]]] = {
    "de": [("Wer hat den Brief geschrieben?", "Die Leiterin"), ("Wann beginnt das Treffen?", "Am Montag"), ("Was kostet die Karte?", "Zehn Euro")],
    "en": [("Who signed the letter?", "The director"), ("When does the meeting start?", "On Monday"), ("What does the ticket cost?", "Ten pounds")],
    "es": [("¿Quién firmó la carta?", "La directora"), ("¿Cuándo empieza la reunión?", "El lunes"), ("¿Cuánto cuesta la entrada?", "Diez euros")],
    "fr": [("Qui a signé la lettre ?", "La directrice"), ("Quand commence la réunion ?", "Le lundi"), ("Combien coûte le billet ?", "Dix euros")],
}
#: Train, validation and test shares, from the published image counts.
RATIOS = {"train": 0.8956, "validation": 0.0527, "test": 0.0517}
#: Rates of the stand-in generator's faults.
FAULTS = {"malformed": 0.035, "off_topic": 0.05, "wrong_language": 0.05, "paraphrase": 0.05, "empty": 0.005}
SENTENCE_END = r"[.!?]+[ \n]+|\n+"


def qa_pool(views: DataFrame, target: str) -> DataFrame:
    return views.filter(F.col("lang") == target)


def plan_calls(views: DataFrame, per_view: int = 2) -> DataFrame:
    """One row a model call: image_id, lang, view, slot, text, call key."""
    both = F.array(*(F.struct(F.lit(v).alias("view"), F.col(f"view_{v}").alias("text")) for v in ("parse", "ocr")))
    rows = views.select("image_id", "lang", F.inline(both)).filter("text is not null")
    rows = rows.select("image_id", "lang", "view", F.explode(F.sequence(F.lit(1), F.lit(per_view))).alias("slot"), "text")
    return rows.withColumn("call", F.concat_ws("|", "image_id", "view", F.col("slot").cast("string")))


def exemplar_table(spark: SparkSession) -> DataFrame:
    rows = [(lang, k, q, a) for lang, some in sorted(EXEMPLARS.items()) for k, (q, a) in enumerate(some)]
    return spark.createDataFrame(rows, "lang string, ex_no int, ex_question string, ex_answer string")


def one_shot(calls: DataFrame, exemplars: DataFrame, per: str = "call", shots: int = 1) -> DataFrame:
    """Calls with a drawn exemplar and the prompt; per: a draw a call or a page; shots: 0, 1 (drawn), or the first k exemplars of the language."""
    key = F.col("call") if per == "call" else F.col("image_id")
    rows = calls.withColumn("ex_no", F.floor(uniform(key, "ex") * 3).cast("int"))
    rows = rows.join(F.broadcast(exemplars), ["lang", "ex_no"], "left")  # three constant rows a language
    one = F.concat(F.lit("Q: "), F.col("ex_question"), F.lit("\nA: "), F.col("ex_answer"), F.lit("\n\n"))
    if shots > 1:
        several = exemplars.groupBy("lang").agg(F.array_join(F.slice(F.array_sort(F.collect_list(F.concat(F.lit("Q: "), "ex_question", F.lit("\nA: "), "ex_answer"))), 1, shots), "\n\n").alias("shots"))
        rows, one = rows.join(F.broadcast(several), "lang", "left"), F.concat("shots", F.lit("\n\n"))
    head = F.lit("") if shots == 0 else F.coalesce(one, F.lit(""))
    return rows.withColumn("prompt", F.concat(head, F.lit("Text:\n"), "text"))


Generator = Callable[[DataFrame], DataFrame]


def sentences(text: Column, least: int = 5) -> Column:
    return F.filter(F.transform(F.split(text, SENTENCE_END), lambda s: F.trim(s)), lambda s: F.size(F.split(s, " +")) >= least)


def extractive_generator(faults: dict[str, float] | None = None) -> Generator:
    """Deterministic stand-in of a language model, with faults at given rates; ``fault`` tells which, else null.

    The slot-th sentence of the view in hash order is cut in halves: the exemplar's first two words and the
    first half are the question, the rest is the answer. Without such a sentence the completion is malformed.
    """
    rates = FAULTS if faults is None else faults

    def complete(calls: DataFrame) -> DataFrame:
        seed = F.concat_ws("|", "image_id", "view")
        ranked = F.array_sort(F.transform(sentences(F.col("text")), lambda s, i: F.struct(F.md5(F.concat(seed, F.lit("|"), i.cast("string")).cast("binary")).alias("h"), s.alias("s"))))
        lead = lambda q: F.array_join(F.slice(F.split(q, " "), 1, 2), " ")
        draw, low, fault = F.col("_draw"), 0.0, None
        for name, rate in rates.items():
            found = (draw >= low) & (draw < low + rate)
            fault = F.when(found, F.lit(name)) if fault is None else fault.when(found, F.lit(name))
            low += rate
        rows = computed(calls, _ranked=ranked, _draw=uniform("call", "fault"))
        rows = computed(rows, _fault=fault if fault is not None else F.lit(None).cast("string"))
        slot = F.when((F.col("slot") > 1) & (F.col("_fault") == "paraphrase"), F.lit(1)).otherwise(F.col("slot"))
        rows = computed(rows, _ws=F.split(F.get("_ranked", (slot - 1).cast("int")).s, " +"))
        rows = computed(rows, _half=F.ceil(F.size("_ws") / 2).cast("int"))
        first, rest = F.slice("_ws", 1, F.col("_half")), F.slice(F.col("_ws"), F.col("_half") + 1, F.greatest(F.size("_ws") - F.col("_half"), F.lit(0)))
        swapped = F.concat(F.slice(first, 2, 1), F.slice(first, 1, 1), F.slice(first, 3, F.greatest(F.size(first) - 2, F.lit(0))))
        question = F.concat(lead(F.col("ex_question")), F.lit(" "), F.array_join(F.when(F.col("_fault") == "paraphrase", swapped).otherwise(first), " "), F.lit(" ?"))
        other = F.when(F.col("lang") == "en", EXEMPLARS["de"][0][0]).otherwise(EXEMPLARS["en"][0][0])
        question = F.when(F.col("_fault") == "off_topic", F.col("ex_question")).when(F.col("_fault") == "wrong_language", other).otherwise(question)
        answer = F.array_join(rest, " ")
        rows = computed(rows, _q=question, _a=answer)
        completion = (
            F.when(F.col("_ws").isNull() | (F.col("_fault") == "malformed"), F.concat(F.lit("Q: "), F.coalesce("_q", F.lit(""))))
            .when(F.col("_fault") == "empty", F.lit("Q: \nA: "))
            .otherwise(F.concat(F.lit("Q: "), "_q", F.lit("\nA: "), "_a"))
        )
        done = computed(rows, completion=completion, fault=F.when(F.col("_ws").isNull(), F.lit("malformed")).otherwise(F.col("_fault")))
        return done.select(*calls.columns, "completion", "fault")

    return complete


def parse_qa(completions: DataFrame) -> DataFrame:
    """Completions with question and answer where they follow the exemplars' format, else null, and ``well_formed``."""
    form = r"^Q: ([^\n]*[^\s][^\n]*)\nA: ([^\n]*[^\s][^\n]*)$"
    ok = F.col("completion").rlike(form) & (F.regexp_count("completion", F.lit(r"(^|\n)[QA]: ")) == 2)
    part = lambda k: F.when(F.col("well_formed"), F.trim(F.regexp_extract("completion", form, k)))
    rows = computed(completions, well_formed=F.coalesce(ok, F.lit(False)))
    return computed(rows, question=part(1), answer=part(2), qa_id=F.concat(F.col("image_id"), F.lit("#"), F.col("view"), F.col("slot").cast("string")))


def split_of(key: Column, ratios: dict[str, float] = RATIOS, salt: str = "split") -> Column:
    """The split of a key (the image, so that a page is never in two splits)."""
    u, low, out = uniform(key, salt), 0.0, None
    for name, share in list(ratios.items())[:-1]:
        low += share
        out = F.when(u < low, name) if out is None else out.when(u < low, name)
    return out.otherwise(list(ratios)[-1]) if out is not None else F.lit(next(iter(ratios)))


def split_by_image(df: DataFrame, ratios: dict[str, float] = RATIOS, salt: str = "split", group: str = "image_id") -> DataFrame:
    """df with ``split``; group: image_id, or the column of documents or near-copy clusters that must not be divided."""
    return df.withColumn("split", split_of(F.col(group), ratios, salt))


def split_exact(df: DataFrame, ratios: dict[str, float] = RATIOS, salt: str = "split", group: str = "image_id", bits: int = 16) -> DataFrame:
    """df with ``split`` of exact sizes: the groups in the order of their draws are cut at the rounded cumulative shares.

    The draws are whole numbers below 2**32; histograms, each of 2**bits bins at most, find where a cut falls, so no
    sort of all groups is needed. Groups of equal draws go by their key.
    """
    draw = F.floor(uniform(F.col(group), salt) * (1 << 32)).cast("long")
    groups = df.select(F.col(group).alias("g")).filter("g is not null").distinct().select("g", F.floor(uniform("g", salt) * (1 << 32)).cast("long").alias("h"))
    n, low, cuts = groups.count(), 0.0, []
    for share in list(ratios.values())[:-1]:
        low += share
        cuts.append(_cut_of(groups, round(n * low), bits))
    out = None
    for name, (h, key) in zip(ratios, cuts, strict=False):
        below = (draw < h) | ((draw == h) & (F.col(group) <= key)) if key is not None else draw < h
        out = F.when(below, name) if out is None else out.when(below, name)
    return df.withColumn("split", out.otherwise(list(ratios)[-1]) if out is not None else F.lit(next(iter(ratios))))


def _cut_of(groups: DataFrame, first: int, bits: int) -> tuple[int, str | None]:
    """(draw, key): ``first`` groups have a lower draw, or this draw and at most this key."""
    start, size, left = 0, 1 << 32, first
    while size > 1:
        step = max(size >> bits, 1)
        some = groups.filter((F.col("h") >= start) & (F.col("h") < start + size))
        for b, k in sorted(tuple(r) for r in some.groupBy(F.floor((F.col("h") - start) / step).alias("b")).agg(F.count("*")).collect()):  # 2**bits rows at most
            if k > left:
                start, size = start + int(b) * step, step
                break
            left -= k
        else:
            return start + size, None  # all of them
    ties = [r.g for r in groups.filter(F.col("h") == start).orderBy("g").limit(left).collect()] if left else []  # groups of one draw in 2**32
    return start, ties[-1] if ties else None


def qa_stats(before: DataFrame, after: DataFrame) -> DataFrame:
    """Images and pairs by split, before and after filtering, with a total row each (split ``all``)."""
    tagged = before.select(F.lit("generated").alias("dataset"), "split", "image_id").unionByName(after.select(F.lit("filtered").alias("dataset"), "split", "image_id"))
    sizes = tagged.rollup("dataset", "split").agg(F.countDistinct("image_id").alias("images"), F.count("*").alias("pairs"))
    return sizes.filter("dataset is not null").withColumn("split", F.coalesce("split", F.lit("all")))


def yield_rates(parsed: DataFrame) -> DataFrame:
    """One row: calls, well-formed pairs, images, pairs an image, share lost to the format."""
    row = parsed.agg(F.count("*").alias("calls"), F.count_if("well_formed").alias("pairs"), F.countDistinct("image_id").alias("images"))
    return row.withColumn("pairs_per_image", F.round(F.col("pairs") / F.col("images"), 6)).withColumn("format_loss", F.round(1 - F.col("pairs") / F.col("calls"), 6))
