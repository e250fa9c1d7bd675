"""Training experiments with proxy students, near-disjoint sets, leak guards and further measures."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from doccurate.functions.keys import uniform
from doccurate.operators import collect, compare, dedup, filters, gold, qa, training
from doccurate.plans import sql
from doccurate.plans.registry import query
from doccurate.plans.workloads import _VIEWS, SCORES, TARGET, _grams5, judged, keeper, parsed, quality_scores
from doccurate.sources.tables import table

#: Parts of each student's training set: the base text is in all, as a model is tuned from a trained one.
STUDENTS = {
    "base": ["english"],
    "synthetic_only": ["english", "kept"],
    "mixture": ["english", "kept", "talk"],
    "mixture_20": ["english", "kept", "talk", "ocr_20"],
    "mixture_100": ["english", "kept", "talk", "ocr_20", "ocr_100"],
}
GRID = {
    (filtered, share): ["english", "talk", "kept", *(["removed"] if filtered == "off" else []), *[p for p, least in (("ocr_20", 0.2), ("ocr_100", 1.0)) if share >= least]]
    for filtered in ("off", "on")
    for share in (0.0, 0.2, 1.0)
}
CHECKPOINTS = 4


def student_texts(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """rows(part, key, text) of all training parts, and the test rows(text): pairs of the synthetic test split that the filters keep."""
    pairs = keeper(spark)(qa.split_by_image(judged(spark, sf_dir)).select("image_id", "qa_id", "split", "kept", F.concat_ws(" ", "question", "answer").alias("text")))
    own = pairs.filter("split = 'train'").select(F.when(F.col("kept"), "kept").otherwise("removed").alias("part"), F.col("qa_id").alias("key"), "text")
    base = table(spark, sf_dir, "documents").filter("lang = 'en'").select(F.lit("english").alias("part"), F.col("doc_id").cast("string").alias("key"), "text")
    talk = training.conversation_pairs(table(spark, sf_dir, "conversations")).select(F.lit("talk").alias("part"), F.concat_ws(":", F.col("conv_id").cast("string"), F.col("turn").cast("string")).alias("key"), F.concat_ws(" ", "question", "answer").alias("text"))
    pages = collect.page_views(table(spark, sf_dir, "pages")).filter(F.col("lang") == TARGET)
    ocr = pages.select(F.when(uniform("image_id", "budget") < 0.2, "ocr_20").otherwise("ocr_100").alias("part"), F.col("image_id").alias("key"), F.col("plain").alias("text"))
    return own.unionByName(base).unionByName(talk).unionByName(ocr), pairs.filter("kept AND split = 'test'").select("text")


def _members(spark: SparkSession, cells: dict) -> DataFrame:
    return spark.createDataFrame([(k, p) for k, some in enumerate(cells.values()) for p in some], "cell int, part string")


_TEXTS = f"""WITH {sql.cascade(TARGET)}, {_VIEWS},
parts AS (SELECT CASE WHEN kept THEN 'kept' ELSE 'removed' END AS part, qa_id AS key, question || ' ' || answer AS text FROM judged WHERE split = 'train'
  UNION ALL SELECT 'english', doc_id::VARCHAR, text FROM documents WHERE lang = 'en'
  UNION ALL SELECT 'talk', u.conv_id || ':' || u.turn, u.text || ' ' || r.text FROM conversations u JOIN conversations r ON r.conv_id = u.conv_id AND r.turn = u.turn + 1 AND u.role = 'user' AND r.role = 'assistant'
  UNION ALL SELECT CASE WHEN {sql.u('image_id', 'budget')} < 0.2 THEN 'ocr_20' ELSE 'ocr_100' END, image_id, plain FROM crawl WHERE lang = '{TARGET}'),
wanted AS (SELECT w, count(*) AS times FROM (SELECT unnest({sql.words("question || ' ' || answer")}) AS w FROM judged WHERE kept AND split = 'test') GROUP BY w)"""


def _cells(cells: dict) -> str:
    return ", ".join(f"({k}, '{p}')" for k, some in enumerate(cells.values()) for p in some)


def _students(cells: dict, ckpt: str) -> str:
    return f"""{_TEXTS}, m(cell, part) AS (VALUES {_cells(cells)}),
c AS (SELECT cell, ckpt, w, count(*) AS n FROM (SELECT cell, {ckpt} AS ckpt, unnest({sql.words('text')}) AS w FROM parts JOIN m USING (part)) GROUP BY ALL),
z AS (SELECT cell, ckpt, sum(n) AS total, count(*) AS v FROM c GROUP BY ALL),
p AS (SELECT z.cell, z.ckpt, a.w, a.times, (coalesce(n, 0) + 1)::DOUBLE / (total + v + 1) AS p FROM z CROSS JOIN wanted a LEFT JOIN c ON c.cell = z.cell AND c.ckpt = z.ckpt AND c.w = a.w),
one AS (SELECT cell, round(avg(cost))::BIGINT AS single FROM (SELECT cell, ckpt, sum(round(-10000 * ln(p))::BIGINT * times) AS cost FROM p GROUP BY ALL) GROUP BY cell),
mean AS (SELECT cell, sum(round(-10000 * ln(q))::BIGINT * times)::BIGINT AS averaged, sum(times)::BIGINT AS n_words FROM (SELECT cell, w, any_value(times) AS times, avg(p) AS q FROM p GROUP BY cell, w) GROUP BY cell)"""


@query("w19_students", f"""{_students(STUDENTS, '0')}, s AS (SELECT cell AS step, [{', '.join(f"'{x}'" for x in STUDENTS)}][cell + 1] AS model, single AS cost, n_words FROM one JOIN mean USING (cell))
SELECT step, model, cost, n_words, round((cost - (SELECT cost FROM s WHERE step = 0)) / n_words::DOUBLE, 6) AS delta FROM s""")
def w19_students(spark, sf_dir):
    """The five training sets as students: cost of the synthetic test pairs, and its change a word against the base (lower is better)."""
    rows, test = student_texts(spark, sf_dir)
    found = training.student_costs(training.part_counts(rows), _members(spark, STUDENTS), test)
    names = F.array(*map(F.lit, STUDENTS))
    named = keeper(spark)(found.select(F.col("cell").alias("step"), F.get(names, F.col("cell")).alias("model"), F.col("single").alias("cost"), "n_words"))
    base = named.filter("step = 0").select(F.col("cost").alias("base"))
    return named.crossJoin(base).select("step", "model", "cost", "n_words", F.round((F.col("cost") - F.col("base")) / F.col("n_words"), 6).alias("delta"))  # one base row


def grid_costs(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows, test = student_texts(spark, sf_dir)
    return training.student_costs(training.part_counts(rows, CHECKPOINTS), _members(spark, GRID), test)


_GRID = _students(GRID, f"floor({sql.u('key', 'ckpt')} * {CHECKPOINTS})::INT")
_PLACE = f"[{', '.join(repr(f) for f, _ in GRID)}][cell + 1] AS filters, [{', '.join(str(s) for _, s in GRID)}][cell + 1]::DOUBLE AS budget"


def _placed(df: DataFrame) -> DataFrame:
    return df.withColumns({"filters": F.get(F.array(*(F.lit(f) for f, _ in GRID)), F.col("cell")), "budget": F.get(F.array(*(F.lit(s) for _, s in GRID)), F.col("cell"))})


@query("w20_grid", f"{_GRID}, g AS (SELECT {_PLACE}, single, averaged, n_words FROM one JOIN mean USING (cell)) SELECT filters, budget, 'off' AS averaging, single AS cost, n_words FROM g UNION ALL SELECT filters, budget, 'on', averaged, n_words FROM g")
def w20_grid(spark, sf_dir):
    """Quality filters off and on, transcription budgets, averaging off and on: cost of the synthetic test pairs, a row a cell."""
    both = F.array(*(F.struct(F.lit(k).alias("averaging"), F.col(c).alias("cost")) for k, c in (("off", "single"), ("on", "averaged"))))
    return _placed(grid_costs(spark, sf_dir)).select("filters", "budget", F.inline(both), "n_words").select("filters", "budget", "averaging", "cost", "n_words")


@query("w21_onoff", f"{_GRID} SELECT {_PLACE}, single AS off, averaged AS on_, round((averaged - single) / n_words::DOUBLE, 6) AS change FROM one JOIN mean USING (cell)")
def w21_onoff(spark, sf_dir):
    """Averaging off and on side by side (the grid as a pivot), with the change a word."""
    rows = _placed(grid_costs(spark, sf_dir))
    return rows.select("filters", "budget", F.col("single").alias("off"), F.col("averaged").alias("on_"), F.round((F.col("averaged") - F.col("single")) / F.col("n_words"), 6).alias("change"))


_SETS = f"""t AS (SELECT 'gold' AS dataset, 0 AS p, item_id::VARCHAR AS key, text FROM benchmark
  UNION ALL SELECT 'synthetic', CASE {sql.split_case('image_id')} WHEN 'test' THEN 1 WHEN 'validation' THEN 2 ELSE 3 END, image_id, view_parse FROM doc_views WHERE lang = '{TARGET}'
  UNION ALL SELECT 'corpus', 4, image_id, plain FROM crawl WHERE lang = '{TARGET}')"""


@query("w07_disjoint_near", f"""WITH {sql.DOC_PAGES}, {_VIEWS}, {_SETS},
r AS (SELECT dataset, key, md5({sql.norm('text')}) AS fp, row_number() OVER (PARTITION BY md5({sql.norm('text')}) ORDER BY p, key) AS k FROM t),
o AS (SELECT dataset || '/' || key AS both_, text FROM t WHERE p > 0), s AS ({_grams5('benchmark', 'item_id')}), b AS ({_grams5('o', 'both_')}), n AS (SELECT item_id, count(*) AS size FROM s GROUP BY item_id),
i AS (SELECT both_ FROM s JOIN b USING (g) JOIN n USING (item_id) GROUP BY item_id, both_ HAVING count(*) / any_value(size)::DOUBLE >= 0.8)
SELECT dataset, key, fp FROM r WHERE k = 1 AND (dataset || '/' || key) NOT IN (SELECT both_ FROM i)""")
def w07_disjoint_near(spark, sf_dir):
    """The three sets made disjoint, pages that hold a near or whole copy of a gold page left out too."""
    own = qa.split_by_image(qa.qa_pool(collect.document_views(table(spark, sf_dir, "documents")), TARGET)).select("split", F.col("image_id").alias("key"), F.col("view_parse").alias("text"))
    corpus = collect.page_views(table(spark, sf_dir, "pages")).filter(F.col("lang") == TARGET).select(F.col("image_id").alias("key"), F.col("plain").alias("text"))
    sets = [("gold", 0, table(spark, sf_dir, "benchmark").select(F.col("item_id").alias("key"), "text"))]
    sets += [("synthetic", k + 1, own.filter(F.col("split") == s)) for k, s in enumerate(("test", "validation", "train"))]
    return dedup.disjoint_near([*sets, ("corpus", 4, corpus)])


@query("w22_guarded_pool", f"""WITH {sql.DOC_PAGES}, s AS ({_grams5('benchmark', 'item_id')}), tr AS (SELECT image_id, view_parse AS text FROM doc_pages WHERE lang = '{TARGET}'), b AS ({_grams5('tr', 'image_id')}), n AS (SELECT item_id, count(*) AS size FROM s GROUP BY item_id),
i AS (SELECT image_id FROM s JOIN b USING (g) JOIN n USING (item_id) GROUP BY item_id, image_id HAVING count(*) / any_value(size)::DOUBLE >= 0.8)
SELECT image_id FROM tr WHERE image_id NOT IN (SELECT image_id FROM i) AND md5({sql.norm('text')}) NOT IN (SELECT md5({sql.norm('text')}) FROM benchmark)""")
def w22_guarded(spark, sf_dir):
    """The pool's pages that training may use: none equals a gold page or holds one."""
    pool = qa.qa_pool(collect.document_views(table(spark, sf_dir, "documents")), TARGET).select("image_id", F.col("view_parse").alias("text"))
    return dedup.without_leaks(pool, table(spark, sf_dir, "benchmark"), "image_id", "item_id").select("image_id")


_LABELS = "SELECT doc_id, min(quality) AS quality FROM labels GROUP BY doc_id"
_F1 = "round(tp / nullif(tp + fp, 0)::DOUBLE, 6) AS precision, round(tp / nullif(tp + fn, 0)::DOUBLE, 6) AS recall, round(2 * tp / nullif(2 * tp + fp + fn, 0)::DOUBLE, 6) AS f1"


@query("w22_filter_f1", f"""WITH {sql.cascade(TARGET)}, l AS ({_LABELS}), b AS (SELECT 'fault' AS truth, fault IS NOT NULL AS bad, kept FROM judged UNION ALL SELECT 'quality', quality = 0, kept FROM judged JOIN l USING (doc_id) WHERE quality IS NOT NULL),
c AS (SELECT truth, count(*) FILTER (bad AND NOT kept) AS tp, count(*) FILTER (NOT bad AND NOT kept) AS fp, count(*) FILTER (bad AND kept) AS fn FROM b GROUP BY truth) SELECT truth, tp, fp, fn, {_F1} FROM c""")
def w22_f1(spark, sf_dir):
    """The cascade as a detector of injected faults, and of pages of documents labelled as of low quality."""
    rows = judged(spark, sf_dir).select(F.split("image_id", ":")[1].cast("long").alias("doc_id"), "fault", "kept")
    labels = table(spark, sf_dir, "labels").groupBy("doc_id").agg(F.min("quality").alias("quality"))
    rows = keeper(spark)(rows.join(labels, "doc_id", "left"))
    one = filters.filter_scores(rows, F.col("fault").isNotNull()).withColumn("truth", F.lit("fault"))
    return one.unionByName(filters.filter_scores(rows, F.col("quality") == 0).withColumn("truth", F.lit("quality")))


@query("w16_human_gap", f"{SCORES} SELECT model, accuracy, round(accuracy - {compare.HUMAN['exact']}, 6) AS to_human, accuracy >= {compare.HUMAN['exact']} - 0.1 AS near_or_above FROM s WHERE dataset = 'en'")
def w16_human(spark, sf_dir):
    """Shares of good English documents by source against the human level."""
    return compare.human_gap(quality_scores(spark, sf_dir), "en")


@query("w08_shots", f"""WITH {sql.calls(TARGET)}, e AS (SELECT lang, list_sort(list('Q: ' || ex_question || chr(10) || 'A: ' || ex_answer)) AS xs FROM exemplars GROUP BY lang)
SELECT call, md5(array_to_string(xs[1:2], chr(10) || chr(10)) || chr(10) || chr(10) || 'Text:' || chr(10) || text) AS two, md5(array_to_string(xs, chr(10) || chr(10)) || chr(10) || chr(10) || 'Text:' || chr(10) || text) AS three FROM shown JOIN e USING (lang)""")
def w08_shots(spark, sf_dir):
    """Prompts with two and with all three exemplars."""
    calls, shown = qa.plan_calls(qa.qa_pool(collect.document_views(table(spark, sf_dir, "documents")), TARGET)), qa.exemplar_table(spark)
    digest = lambda k, name: qa.one_shot(calls, shown, shots=k).select("call", F.md5(F.col("prompt").cast("binary")).alias(name))
    return digest(2, "two").join(digest(3, "three"), "call")


def _exact_sql(key: str) -> str:
    cuts = "CASE WHEN k <= round(n * 0.8956) THEN 'train' WHEN k <= round(n * (0.8956 + 0.0527)) THEN 'validation' ELSE 'test' END"
    return f"SELECT {key}, {cuts} AS split FROM (SELECT {key}, row_number() OVER (ORDER BY {sql.u(key, 'split')}, {key}) AS k, count(*) OVER () AS n FROM g)"


@query("w10_split_exact", f"WITH {sql.DOC_PAGES}, g AS (SELECT DISTINCT image_id FROM doc_pages WHERE lang = '{TARGET}') {_exact_sql('image_id')}")
def w10_exact(spark, sf_dir):
    """Pages split at exact shares."""
    pool = qa.qa_pool(collect.document_views(table(spark, sf_dir, "documents")), TARGET)
    return qa.split_exact(pool.select("image_id"))


@query("w10_split_grouped", f"WITH {sql.DOC_PAGES} SELECT image_id, {sql.split_case('doc_id')} AS split FROM doc_pages WHERE lang = '{TARGET}'")
def w10_grouped(spark, sf_dir):
    """Pages split by document, so that no document is in two splits."""
    pool = qa.qa_pool(collect.document_views(table(spark, sf_dir, "documents")), TARGET)
    return qa.split_by_image(pool.withColumn("document", F.col("doc_id").cast("string")), group="document").select("image_id", "split")


@query("w14_back_translation", f"""WITH r AS (SELECT item_id, string_split(text, ' ') AS raw, array_to_string(list_transform(string_split(text, ' '), lambda w: CASE WHEN regexp_full_match(w, '\\p{{L}}+') AND {sql.u('w', 'english')} < 0.3 THEN '~' || reverse(w) ELSE w END), ' ') AS there FROM benchmark),
s AS (SELECT item_id, regexp_split_to_array(list_filter(list_transform(regexp_split_to_array(there, '[.!?]+[ \\n]+|\\n+'), lambda s: trim(s)), lambda s: len(regexp_split_to_array(s, ' +')) >= 5)[1], ' +') AS ws FROM r),
h AS (SELECT item_id, array_to_string(ws[1:ceil(len(ws) / 2.0)::INT], ' ') || ' ?' AS q, array_to_string(ws[ceil(len(ws) / 2.0)::INT + 1:], ' ') AS a FROM s),
b AS (SELECT *, array_to_string(list_transform(string_split(q, ' '), lambda w: CASE WHEN regexp_full_match(w, '~\\p{{L}}+') THEN reverse(w[2:]) ELSE w END), ' ') AS qb,
  array_to_string(list_transform(string_split(a, ' '), lambda w: CASE WHEN regexp_full_match(w, '~\\p{{L}}+') THEN reverse(w[2:]) ELSE w END), ' ') AS ab FROM h)
SELECT item_id, md5(q) AS question_read, md5(a) AS answer_read, md5(qb) AS question, md5(ab) AS answer FROM b""")
def w14_back(spark, sf_dir):
    """Gold pairs written from the translated page and translated back."""
    rows = gold.translated_pairs(table(spark, sf_dir, "benchmark"), *gold.coded_translator())
    return rows.select("item_id", *(F.md5(F.col(c).cast("binary")).alias(c) for c in ("question_read", "answer_read", "question", "answer")))


@query("w20_translated", f"""WITH {sql.cascade(TARGET)}, t AS (SELECT question, text, array_to_string(list_transform(string_split(question, ' '), lambda w: CASE WHEN regexp_full_match(w, '\\p{{L}}+') AND {sql.u('w', 'english')} < 0.3 THEN '~' || reverse(w) ELSE w END), ' ') AS moved FROM pairs),
m AS (SELECT 'native' AS source, {sql.norm('question')} AS q, {sql.norm('text')} AS t FROM t UNION ALL SELECT 'translated', {sql.norm('moved')}, {sql.norm('text')} FROM t),
g AS (SELECT source, {sql.char_grams('q')} AS x, {sql.char_grams('t')} AS y FROM m)
SELECT source, count(*) AS pairs, count(*) FILTER (len(x) > 0 AND len(list_intersect(x, y)) / len(x)::DOUBLE >= 0.12) AS kept, round(avg(len(list_intersect(x, y)) / nullif(len(x), 0)::DOUBLE), 6) AS overlap FROM g GROUP BY source""")
def w20_translated(spark, sf_dir):
    """A translated mixture member beside the native one: what the overlap filter makes of each (a stand-in of machine translation)."""
    there, _ = gold.coded_translator()
    pairs = parsed(spark, sf_dir).filter("well_formed").select("text", F.inline(F.array(F.struct(F.lit("native").alias("source"), F.col("question").alias("q")), F.struct(F.lit("translated").alias("source"), there(F.col("question")).alias("q")))))
    rows = pairs.select("source", filters.overlap_of(F.col("q"), F.col("text")).alias("v"))
    return rows.groupBy("source").agg(F.count("*").alias("pairs"), F.count_if(filters.f_overlap(F.col("v"))).alias("kept"), F.round(F.avg("v"), 6).alias("overlap"))
