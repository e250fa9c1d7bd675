"""Training mixtures, budgets, checkpoint averaging, proxy students and ablations."""

from __future__ import annotations

from pyspark.ml.classification import LogisticRegression
from pyspark.ml.feature import HashingTF
from pyspark.ml.functions import vector_to_array
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from doccurate.functions.keys import uniform
from doccurate.functions.text import words

TASK = "Write down the text of this page."


def as_ocr_task(pages: DataFrame) -> DataFrame:
    """Transcription examples: a constant instruction, the page's text as target."""
    return pages.select(F.lit("transcription").alias("task"), "image_id", F.lit(TASK).alias("prompt"), F.col("plain").alias("target"))


def as_qa_task(pairs: DataFrame) -> DataFrame:
    return pairs.select(F.lit("qa").alias("task"), "image_id", F.col("question").alias("prompt"), F.col("answer").alias("target"))


def conversation_pairs(conversations: DataFrame) -> DataFrame:
    """A user's turn with the assistant's next one."""
    user = conversations.filter("role = 'user'").select("conv_id", "turn", F.col("text").alias("question"))
    reply = conversations.filter("role = 'assistant'").select("conv_id", (F.col("turn") - 1).alias("turn"), F.col("text").alias("answer"))
    return user.join(reply, ["conv_id", "turn"])


def mixture(parts: list[tuple[str, DataFrame, float]], salt: str = "mix") -> DataFrame:
    """source, image_id, task, prompt, target: a keyed share of each part (name, rows, share)."""
    out = None
    for name, rows, share in parts:
        some = rows.filter(uniform("image_id", f"{salt}/{name}") < share).select(F.lit(name).alias("source"), F.col("image_id").cast("string").alias("image_id"), "task", "prompt", "target")
        out = some if out is None else out.unionByName(some)
    return out


def with_budget(base: DataFrame, ocr: DataFrame, share: float, salt: str = "budget") -> DataFrame:
    """The base with a keyed share of transcription examples; a smaller share lies inside a larger one."""
    return base.unionByName(ocr.filter(uniform("image_id", salt) < share).select(F.lit("ocr").alias("source"), "image_id", "task", "prompt", "target"))


def average_checkpoints(ckpts: DataFrame, weights: dict[int, float] | None = None, last: int | None = None, decay: float | None = None) -> DataFrame:
    """param, idx, value over ckpts(ckpt, param, idx, value): uniform, weighted, of the last k, or exponentially decayed.

    A cell that some checkpoint lacks has ``complete`` false.
    """
    names = ckpts.agg(F.collect_set("ckpt")).first()[0]  # one number a checkpoint
    chosen = sorted(names)[-last:] if last else sorted(names)
    if decay is not None:
        weights = {c: decay**k for k, c in enumerate(reversed(chosen))}
    weight = F.lit(1.0) if weights is None else F.element_at(F.create_map(*(F.lit(x) for c in chosen for x in (c, float(weights.get(c, 0.0))))), F.col("ckpt"))
    some = ckpts.filter(F.col("ckpt").isin(chosen)).withColumn("w", weight)
    return some.groupBy("param", "idx").agg(F.try_divide(F.sum(F.col("value") * F.col("w")), F.sum("w")).alias("value"), (F.count("*") == len(chosen)).alias("complete"))


def checkpoints_of(embeddings: DataFrame, k: int = 4) -> DataFrame:
    """Vectors as parameter rows: vec_id mod k is the checkpoint, its quotient the parameter."""
    return embeddings.select((F.col("vec_id") % k).cast("int").alias("ckpt"), F.floor(F.col("vec_id") / k).cast("string").alias("param"), F.posexplode("embedding").alias("idx", "value")).withColumn("value", F.col("value").cast("double"))


def unigram_bits(train: DataFrame, test: DataFrame) -> DataFrame:
    """Proxy student: an add-one unigram model; one row with its integer cost (10**4 nats) over test words, and their number.

    A stand-in: it shows the trend with more text of the language, not a model's accuracy.
    """
    counts = train.select(F.explode(words(F.col("text"))).alias("w")).groupBy("w").agg(F.count("*").alias("n"))
    size = counts.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("total"), F.count("*").alias("v"))
    asked = test.select(F.explode(words(F.col("text"))).alias("w")).groupBy("w").agg(F.count("*").alias("times"))
    rows = asked.join(counts, "w", "left").crossJoin(size)  # one row of totals
    cost = F.round(-10000 * F.ln((F.coalesce("n", F.lit(0)) + 1) / (F.col("total") + F.col("v") + 1))).cast("long")
    return rows.agg(F.sum(cost * F.col("times")).alias("cost"), F.sum("times").alias("n_words"))


def part_counts(rows: DataFrame, checkpoints: int = 1) -> DataFrame:
    """part, ckpt, w, n: words of rows(part, key, text); a keyed draw deals the rows to checkpoints. Null and blank texts have none."""
    ckpt = F.floor(uniform("key", "ckpt") * checkpoints).cast("int") if checkpoints > 1 else F.lit(0)
    return rows.select("part", ckpt.alias("ckpt"), F.explode(words(F.col("text"))).alias("w")).groupBy("part", "ckpt", "w").agg(F.count("*").alias("n"))


def fitted(counts: DataFrame, members: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(cell, ckpt, w, n) and (cell, ckpt, total, v) of unigram students, each of the parts that members(cell, part), a small table, names for it."""
    own = counts.join(F.broadcast(members), "part").groupBy("cell", "ckpt", "w").agg(F.sum("n").alias("n"))
    return own, own.groupBy("cell", "ckpt").agg(F.sum("n").alias("total"), F.count("*").alias("v"))


def student_costs(counts: DataFrame, members: DataFrame, test: DataFrame) -> DataFrame:
    """cell, single, averaged (10**4 nats), n_words: cost of the words of test(text) to add-one unigram students.

    single: the mean cost over the students of a cell's checkpoints; averaged: the cost to the one student whose parameters
    are the means of theirs. Stand-ins of a trained model: they show trends, not its accuracy. A cell without training rows is missing.
    """
    own, sizes = fitted(counts, members)
    asked = test.select(F.explode(words(F.col("text"))).alias("w")).groupBy("w").agg(F.count("*").alias("times"))
    rows = asked.crossJoin(F.broadcast(sizes)).join(own, ["cell", "ckpt", "w"], "left")  # a row a cell and checkpoint
    chance = (F.coalesce("n", F.lit(0)) + 1) / (F.col("total") + F.col("v") + 1)
    cost = lambda p: F.round(-10000 * F.ln(p)).cast("long")
    each = rows.select("cell", "ckpt", "w", "times", chance.alias("p"))
    means = average_checkpoints(each.select("ckpt", F.col("cell").alias("param"), F.col("w").alias("idx"), F.col("p").alias("value")))
    averaged = means.select(F.col("param").alias("cell"), F.col("idx").alias("w"), F.col("value").alias("p")).join(asked, "w")
    one = each.groupBy("cell", "ckpt").agg(F.sum(cost(F.col("p")) * F.col("times")).alias("cost")).groupBy("cell").agg(F.round(F.avg("cost")).cast("long").alias("single"))
    return one.join(averaged.groupBy("cell").agg(F.sum(cost(F.col("p")) * F.col("times")).alias("averaged"), F.sum("times").alias("n_words")), "cell")


def hashed_students(rows: DataFrame, seeds: int = 4, features: int = 1024, test_share: float = 0.2, steps: int = 20) -> DataFrame:
    """student, n, right, majority, accuracy on held-out rows(key, text, label) of logistic regressions on hashed words, and of their mean.

    majority: how many of the held-out rows have their commoner label, which a student without knowledge gets right at most.
    Each seed's student learns from its own keyed draw of 80 % of the training rows; ``mean`` has the averaged parameters
    (average_checkpoints). Rows without a text or label are left out; no rows without two labels to learn from. A stand-in of a trained model.
    """
    known = rows.filter("text is not null and label is not null").select("key", F.col("label").cast("double").alias("label"), words(F.col("text")).alias("words"))
    hashed = HashingTF(numFeatures=features, inputCol="words", outputCol="features").transform(known).select("key", "label", "features")
    train, test = (hashed.filter((uniform("key", "held") < test_share) == held) for held in (False, True))
    spark, found = rows.sparkSession, []
    for seed in range(seeds):  # a student a seed; its parameters are one bounded vector
        some = train.filter(uniform("key", f"seed{seed}") < 0.8)
        if some.agg(F.countDistinct("label")).first()[0] < 2:
            continue
        model = LogisticRegression(maxIter=steps, regParam=0.01).fit(some)
        found += [(seed, "w", -1, float(model.intercept)), *((seed, "w", i, float(v)) for i, v in enumerate(model.coefficients.toArray()))]
    weights = spark.createDataFrame(found, "ckpt int, param string, idx int, value double")
    names = sorted({f[0] for f in found})
    students = weights.select(F.concat(F.lit("seed"), "ckpt").alias("student"), "idx", "value")
    if names:
        students = students.unionByName(average_checkpoints(weights).select(F.lit("mean").alias("student"), "idx", "value"))
    cells = test.select("key", "label", F.posexplode(F.concat(F.array(F.lit(1.0)), vector_to_array("features"))).alias("at", "times")).filter("times <> 0")
    margins = cells.withColumn("idx", F.col("at") - 1).join(F.broadcast(students), "idx").groupBy("student", "key", "label").agg(F.sum(F.col("times") * F.col("value")).alias("margin"))
    out = margins.groupBy("student").agg(F.count("*").alias("n"), F.count_if((F.col("margin") > 0) == (F.col("label") > 0.5)).alias("right"), F.greatest(F.count_if(F.col("label") > 0.5), F.count_if(F.col("label") <= 0.5)).alias("majority"))
    return out.withColumn("accuracy", F.round(F.col("right") / F.col("n"), 6))
