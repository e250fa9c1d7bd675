"""The experiment workloads on the given tables, each with its checking SQL where SQL expresses it."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from doccurate.functions.text import norm
from doccurate.functions.web import canonical_url
from doccurate.operators import collect, compare, dedup, filters, gold, langid, qa, training
from doccurate.plans import sql
from doccurate.plans.registry import query
from doccurate.sources.tables import shared_folder, table

LANGS, TARGET = sql.LANGS, "fr"


def keeper(spark: SparkSession):
    """Cuts lineage through the shared folder of the session."""
    folder = shared_folder(spark)

    def keep(df: DataFrame, _: int = 0) -> DataFrame:
        path = f"{folder.rstrip('/')}/kept-{uuid.uuid4().hex}"
        df.write.parquet(path)
        return spark.read.schema(df.schema).parquet(path)

    return keep


def profiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Word profiles from documents of even id, for questions (of which none is a document)."""
    return langid.profile(table(spark, sf_dir, "documents").filter("doc_id % 2 = 0").select("lang", "text"), LANGS)


def parsed(spark: SparkSession, sf_dir: str, target: str | None = TARGET) -> DataFrame:
    views = collect.document_views(table(spark, sf_dir, "documents"))
    pool = qa.qa_pool(views, target) if target else views
    calls = qa.one_shot(qa.plan_calls(pool), qa.exemplar_table(spark))
    return qa.parse_qa(qa.extractive_generator()(calls))


def judged(spark: SparkSession, sf_dir: str, target: str = TARGET, mode: str = "sequential") -> DataFrame:
    pairs = parsed(spark, sf_dir, target).filter("well_formed")
    return filters.run_cascade(filters.with_language(pairs, profiles(spark, sf_dir), LANGS), target, mode=mode, keep=keeper(spark))


def synthetic(spark: SparkSession, sf_dir: str, target: str = TARGET) -> DataFrame:
    return qa.split_by_image(judged(spark, sf_dir, target)).filter("kept")


@query("w01_archive_sample", f"SELECT source, count(*) AS documents FROM documents WHERE {sql.u('source', 'archive')} < 0.3 GROUP BY source")
def w01(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").select("source")
    return collect.sample_archives(docs, "source", 0.3).groupBy("source").agg(F.count("*").alias("documents"))


@query("w01_archive_sample_exact", "SELECT source, count(*) AS documents FROM documents WHERE source IN (SELECT source FROM (SELECT DISTINCT source FROM documents) ORDER BY md5('archive|' || source), source LIMIT 5) GROUP BY source")
def w01_exact(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").select("source")
    return collect.sample_archives(docs, "source", exact=5).groupBy("source").agg(F.count("*").alias("documents"))


@query("w02_links", r"""
WITH l AS (SELECT regexp_extract(url, '^([a-z]+://[^/?#]*)', 1) AS root, url, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS h FROM pages),
t AS (SELECT url, regexp_replace(CASE WHEN regexp_matches(h, '^[a-z]+://') THEN h WHEN starts_with(h, '/') THEN root || h ELSE root || '/' || h END, '#.*$', '') AS a FROM l),
p AS (SELECT url, a, lower(regexp_extract(a, '^([A-Za-z]+://[^/?]*)', 1)) AS head, regexp_extract(a, '^[A-Za-z]+://[^/?]*([^?]*)', 1) AS path,
  list_sort(list_filter(string_split(regexp_extract(a, '\?(.*)$', 1), '&'), lambda k: k <> '' AND NOT regexp_matches(k, '^(utm_[^=]*|ref)(=|$)'))) AS ks FROM t),
c AS (SELECT url, CASE WHEN head = '' THEN a ELSE head || CASE WHEN path = '' THEN '/' ELSE path END || CASE WHEN len(ks) > 0 THEN '?' || array_to_string(ks, '&') ELSE '' END END AS target FROM p)
SELECT target, count(DISTINCT url) AS records FROM c GROUP BY target""")
def w02(spark, sf_dir):
    return collect.harvest_links(table(spark, sf_dir, "pages"))


@query("w02_fetch", r"""
WITH p AS (SELECT page_id, regexp_replace(url, '#.*$', '') AS a FROM pages),
q AS (SELECT page_id, a, lower(regexp_extract(a, '^([A-Za-z]+://[^/?]*)', 1)) AS head, regexp_extract(a, '^[A-Za-z]+://[^/?]*([^?]*)', 1) AS path,
  list_sort(list_filter(string_split(regexp_extract(a, '\?(.*)$', 1), '&'), lambda k: k <> '' AND NOT regexp_matches(k, '^(utm_[^=]*|ref)(=|$)'))) AS ks FROM p)
SELECT count(DISTINCT CASE WHEN head = '' THEN a ELSE head || CASE WHEN path = '' THEN '/' ELSE path END || CASE WHEN len(ks) > 0 THEN '?' || array_to_string(ks, '&') ELSE '' END END) AS n, 200 AS status FROM q""")
def w02_fetch(spark, sf_dir):
    pages = table(spark, sf_dir, "pages")
    targets = pages.select(canonical_url(F.col("url")).alias("target")).distinct()
    return collect.fetch(targets, collect.table_fetcher(pages)).groupBy("status").agg(F.count("*").alias("n"))


_BLOCK = "p|div|article|section|nav|footer|header|ul|ol|li|tr|table|br|h[1-6]|title|body|html|head"


def _plain(x: str, markdown: bool = False) -> str:
    x = f"regexp_replace({x}, '(?is)<script.*?</script>|<style.*?</style>|<!--.*?-->', ' ', 'g')"
    if markdown:
        for pattern, to in (("(?i)<h1\\b[^>]*>", "\n# "), ("(?i)</?(?:b|strong)\\b[^>]*>", "**"), ("(?i)<li\\b[^>]*>", "\n- "), ('(?is)<a\\b[^>]*href="([^"]*)"[^>]*>(.*?)</a>', "[\\2](\\1)")):
            x = f"regexp_replace({x}, '{pattern}', '{to}', 'g')"
    x = f"regexp_replace(regexp_replace({x}, '(?i)</?(?:{_BLOCK})\\b[^>]*>', chr(10), 'g'), '<[^>]*>', ' ', 'g')"
    for entity, char in (("&nbsp;", " "), ("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "''"), ("&amp;", "&")):
        x = f"replace({x}, '{entity}', '{char}')"
    return f"regexp_replace(regexp_replace(regexp_replace(regexp_replace({x}, '[ \\t]+', ' ', 'g'), ' ?\\n ?', chr(10), 'g'), '\\n+', chr(10), 'g'), '^[ \\n]+|[ \\n]+\\z', '', 'g')"


_ARTICLE = "CASE WHEN regexp_extract(html, '(?is)<article[^>]*>(.*?)</article>', 1) <> '' THEN regexp_extract(html, '(?is)<article[^>]*>(.*?)</article>', 1) ELSE html END"
_VIEWS = f"""crawl AS (SELECT page_id, 'pages:' || page_id || ':0' AS image_id, regexp_extract(html, '<html[^>]*lang="([a-z]+)"', 1) AS lang,
  {_plain(_ARTICLE)} AS plain, {_plain('html')} AS view_ocr, {_plain(_ARTICLE, True)} AS markdown FROM pages)"""
_BARE = r"regexp_replace(regexp_replace(markdown, '\[([^\]]*)\]\([^)]*\)', '\1', 'g'), '[#*_`>]+|(?m)^- ', '', 'g')"
_AGREE = f"""{_VIEWS}, sides AS (SELECT page_id, unnest({sql.words('plain')}) AS w, 1 AS a, 0 AS b FROM crawl
  UNION ALL SELECT page_id, unnest({sql.words(_BARE)}), 0, 1 FROM crawl),
agreed AS (SELECT page_id, 2 * sum(least(a, b)) / sum(a + b)::DOUBLE AS agreement FROM (SELECT page_id, w, sum(a) AS a, sum(b) AS b FROM sides GROUP BY ALL) GROUP BY page_id)"""


@query("w03_page_views", f"WITH {_VIEWS} SELECT page_id, lang, length(plain) AS n_plain, length(view_ocr) AS n_ocr, md5(plain) AS plain, md5(view_ocr) AS ocr, md5(markdown) AS markdown FROM crawl")
def w03(spark, sf_dir):
    v = collect.page_views(table(spark, sf_dir, "pages"))
    digest = lambda c: F.md5(F.col(c).cast("binary"))
    return v.select("page_id", "lang", F.length("plain").cast("long").alias("n_plain"), F.length("view_ocr").cast("long").alias("n_ocr"), digest("plain").alias("plain"), digest("view_ocr").alias("ocr"), digest("markdown").alias("markdown"))


def _fold(k: int) -> str:
    """The documents of one parity, judged by profiles of the other."""
    return f"(WITH train_docs AS (SELECT lang, text FROM documents WHERE doc_id % 2 <> {k}), own AS (SELECT * FROM documents WHERE doc_id % 2 = {k}), {sql.profile('train_docs')} {sql.detected('own', 'doc_id', 'text')})"


_FOUND = f"WITH found AS (SELECT * FROM {_fold(0)} UNION ALL SELECT * FROM {_fold(1)})"


@query("w04_doc_language", f"{_FOUND} SELECT lang, detected, count(*) AS n FROM documents JOIN found USING (doc_id) GROUP BY ALL")
def w04(spark, sf_dir):
    """All documents by true and detected language, each judged by profiles of the documents of the other parity."""
    docs = table(spark, sf_dir, "documents")
    found = langid.detect_crossed(docs, "doc_id", F.col("doc_id") % 2, [0, 1], LANGS)
    return docs.select("doc_id", "lang").join(found, "doc_id").groupBy("lang", "detected").agg(F.count("*").alias("n"))


@query("w04_keep_language", f"{_FOUND} SELECT doc_id FROM found WHERE detected = '{TARGET}'")
def w04_keep(spark, sf_dir):
    found = langid.detect_crossed(table(spark, sf_dir, "documents"), "doc_id", F.col("doc_id") % 2, [0, 1], LANGS)
    return found.filter(F.col("detected") == TARGET).select("doc_id")


@query("w04_language_chars")
def w04_chars(spark, sf_dir):
    """Character grams of 1 to 3 instead of words: documents by true and detected language."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "lang", "text")
    found = langid.detect_crossed(docs, "doc_id", F.col("doc_id") % 2, [0, 1], LANGS, "char")
    return docs.select("doc_id", "lang").join(found, "doc_id").groupBy("lang", "detected").agg(F.count("*").alias("n"))


def _vote_sql() -> str:
    n = {x: f"len(list_intersect(w, [{', '.join(map(sql.quoted, ws))}]))" for x, ws in langid.STOP_WORDS.items()}
    top = f"greatest({', '.join(n.values())})"
    pick = f"CASE WHEN {top} = 0 THEN NULL " + " ".join(f"WHEN {n[x]} = {top} THEN '{x}'" for x in sorted(n)) + " END"
    return f"SELECT lang, detected, count(*) AS n FROM (SELECT lang, {pick} AS detected FROM (SELECT lang, list_distinct({sql.words('text')}) AS w FROM documents)) GROUP BY ALL"


@query("w04_stop_words", _vote_sql())
def w04_stop(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").select("lang", langid.stop_word_vote(F.col("text")).alias("detected"))
    return docs.groupBy("lang", "detected").agg(F.count("*").alias("n"))


@query("w05_corpus_pages", f"WITH {_AGREE} SELECT page_id, lang, length(plain) AS n_plain, round(agreement, 6) AS agreement, coalesce(agreement >= 0.8, false) AS agrees FROM crawl LEFT JOIN agreed USING (page_id) WHERE length(plain) >= 100")
def w05(spark, sf_dir):
    views = collect.min_chars(collect.page_views(table(spark, sf_dir, "pages")), "plain", 100)
    return collect.with_agreement(views).select("page_id", "lang", F.length("plain").cast("long").alias("n_plain"), F.round("agreement", 6).alias("agreement"), "agrees")


@query("w05_document_pages", f"WITH {sql.DOC_PAGES} SELECT image_id, lang, length(view_parse) AS n_chars, md5(view_parse) AS parse, md5(view_ocr) AS ocr FROM doc_views WHERE length(view_parse) >= 100")
def w05_documents(spark, sf_dir):
    views = collect.min_chars(collect.document_views(table(spark, sf_dir, "documents")), "view_parse", 100)
    return views.select("image_id", "lang", F.length("view_parse").cast("long").alias("n_chars"), F.md5(F.col("view_parse").cast("binary")).alias("parse"), F.md5(F.col("view_ocr").cast("binary")).alias("ocr"))


@query("w06_corpus_report", f"""WITH {_AGREE}, r AS (SELECT *, lang = '{TARGET}' AS ours, length(plain) >= 100 AS long, coalesce(agreement >= 0.8, false) AS ok FROM crawl LEFT JOIN agreed USING (page_id))
SELECT count(*) AS collected, count(*) FILTER (ours) AS in_language, count(*) FILTER (ours AND long) AS long_enough, count(*) FILTER (ours AND long AND ok) AS kept,
  count(DISTINCT page_id) FILTER (ours AND long AND ok) AS records_kept, round(count(*) FILTER (ours) / count(*)::DOUBLE, 6) AS share,
  round(count(*) FILTER (ours AND long AND ok) / nullif(count(DISTINCT page_id) FILTER (ours AND long AND ok), 0)::DOUBLE, 6) AS pages_per_record FROM r""")
def w06(spark, sf_dir):
    return collect.corpus_report(table(spark, sf_dir, "pages"), TARGET)


@query("w06_language_share", "SELECT lang, count(*) AS n, round(count(*) / (SELECT count(*) FROM documents)::DOUBLE, 6) AS share FROM documents GROUP BY lang")
def w06_share(spark, sf_dir):
    return collect.language_share(table(spark, sf_dir, "documents")).withColumn("share", F.round("share", 6))


@query("w07_exact_copies", f"SELECT doc_id, min(doc_id) OVER (PARTITION BY f) AS keeper, count(*) OVER (PARTITION BY f) AS copies FROM (SELECT doc_id, md5({sql.norm('text')}) AS f FROM documents)")
def w07_exact(spark, sf_dir):
    return dedup.exact_groups(table(spark, sf_dir, "documents"), "doc_id").select("doc_id", "keeper", "copies")


@query("w07_disjoint_sets", f"""WITH {sql.DOC_PAGES}, {_VIEWS},
t AS (SELECT 'gold' AS dataset, 0 AS p, item_id::VARCHAR AS key, text FROM benchmark
  UNION ALL SELECT 'synthetic', CASE {sql.split_case('image_id')} WHEN 'test' THEN 1 WHEN 'validation' THEN 2 ELSE 3 END, image_id, view_parse FROM doc_views WHERE lang = '{TARGET}'
  UNION ALL SELECT 'corpus', 4, image_id, plain FROM crawl WHERE lang = '{TARGET}'),
r AS (SELECT dataset, key, md5({sql.norm('text')}) AS fp, row_number() OVER (PARTITION BY md5({sql.norm('text')}) ORDER BY p, key) AS k FROM t)
SELECT dataset, key, fp FROM r WHERE k = 1""")
def w07(spark, sf_dir):
    own = qa.split_by_image(qa.qa_pool(collect.document_views(table(spark, sf_dir, "documents")), TARGET)).select("split", F.col("image_id").alias("key"), F.col("view_parse").alias("text"))
    corpus = collect.page_views(table(spark, sf_dir, "pages")).filter(F.col("lang") == TARGET).select(F.col("image_id").alias("key"), F.col("plain").alias("text"))
    sets = [("gold", 0, table(spark, sf_dir, "benchmark").select(F.col("item_id").alias("key"), "text"))]
    sets += [("synthetic", k + 1, own.filter(F.col("split") == s)) for k, s in enumerate(("test", "validation", "train"))]
    return dedup.disjoint_sets([*sets, ("corpus", 4, corpus)])


def _grams5(source: str, key: str) -> str:
    w = f"string_split({sql.norm('text')}, ' ')"
    return f"SELECT DISTINCT {key}, unnest(list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' '))) AS g FROM (SELECT {key}, {w} AS w FROM {source})"


@query("w07_containment", f"""WITH s AS ({_grams5('benchmark', 'item_id')}), b AS ({_grams5('documents', 'doc_id')}), n AS (SELECT item_id, count(*) AS size FROM s GROUP BY item_id)
SELECT item_id, doc_id, round(count(*) / any_value(size)::DOUBLE, 6) AS share FROM s JOIN b USING (g) JOIN n USING (item_id) GROUP BY item_id, doc_id HAVING count(*) / any_value(size)::DOUBLE >= 0.8""")
def w07_contained(spark, sf_dir):
    return dedup.contained_in(table(spark, sf_dir, "benchmark"), "item_id", table(spark, sf_dir, "documents"), "doc_id")


@query("w07_near_exact", f"""WITH d AS (SELECT min(doc_id) AS doc_id, text FROM documents GROUP BY text), g AS ({_grams5('d', 'doc_id')}), n AS (SELECT doc_id, count(*) AS size FROM g GROUP BY doc_id),
c AS (SELECT a.doc_id AS id, b.doc_id AS other, count(*) AS k FROM g a JOIN g b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY ALL)
SELECT id, other, round(k / (x.size + y.size - k)::DOUBLE, 6) AS similarity FROM c JOIN n x ON x.doc_id = id JOIN n y ON y.doc_id = other WHERE round(k / (x.size + y.size - k)::DOUBLE, 6) >= 0.7""")
def w07_near_exact(spark, sf_dir):
    return dedup.gram_join_pairs(table(spark, sf_dir, "documents"), "doc_id", keep=keeper(spark))


@query("w07_near_minhash")
def w07_minhash(spark, sf_dir):
    return dedup.near_pairs(table(spark, sf_dir, "documents"), "doc_id", keep=keeper(spark))


@query("w07_near_simhash")
def w07_simhash(spark, sf_dir):
    return dedup.simhash_pairs(table(spark, sf_dir, "documents"), "doc_id")


@query("w07_near_vectors", "SELECT a.vec_id AS id, b.vec_id AS other, round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 6) AS cosine FROM embeddings a JOIN embeddings b ON a.vec_id < b.vec_id WHERE round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 6) >= 0.9")
def w07_vectors(spark, sf_dir):
    return dedup.near_vectors(table(spark, sf_dir, "embeddings"), "vec_id", "embedding")


@query("w07_clusters")
def w07_clusters(spark, sf_dir):
    """Components of all pairs at 0.7 or more, equal texts with them: the exact pairs, since a link that bands miss can split a cluster."""
    pairs = dedup.gram_join_pairs(table(spark, sf_dir, "documents"), "doc_id", keep=keeper(spark), copies=True)
    return dedup.clusters(keeper(spark)(pairs.select("id", "other")), keeper(spark))


@query("w07_boilerplate", """WITH l AS (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents)
SELECT line, count(*) AS occurrences, count(DISTINCT doc_id) AS documents FROM l WHERE trim(line) <> '' GROUP BY line HAVING count(DISTINCT doc_id) >= 10""")
def w07_boilerplate(spark, sf_dir):
    return dedup.boilerplate_lines(table(spark, sf_dir, "documents"))


@query("w07_drop_boilerplate", """WITH l AS (SELECT doc_id, unnest(string_split(text, chr(10))) AS line, generate_subscripts(string_split(text, chr(10)), 1) AS k FROM documents),
h AS (SELECT line FROM l WHERE trim(line) <> '' GROUP BY line HAVING count(DISTINCT doc_id) >= 10)
SELECT doc_id, md5(coalesce(string_agg(line, chr(10) ORDER BY k) FILTER (line NOT IN (SELECT line FROM h)), '')) AS text, count(*) FILTER (line IN (SELECT line FROM h)) AS dropped FROM l GROUP BY doc_id""")
def w07_drop(spark, sf_dir):
    return dedup.drop_boilerplate(table(spark, sf_dir, "documents")).withColumn("text", F.md5(F.col("text").cast("binary")))


@query("w08_qa_generate", f"WITH {sql.calls(TARGET)} SELECT call, lang, md5(completion) AS completion, fault FROM completed")
def w08(spark, sf_dir):
    views = qa.qa_pool(collect.document_views(table(spark, sf_dir, "documents")), TARGET)
    done = qa.extractive_generator()(qa.one_shot(qa.plan_calls(views), qa.exemplar_table(spark)))
    return done.select("call", "lang", F.md5(F.col("completion").cast("binary")).alias("completion"), "fault")


@query("w08_prompts", f"""WITH {sql.calls(TARGET)} SELECT call, md5('Q: ' || ex_question || chr(10) || 'A: ' || ex_answer || chr(10) || chr(10) || 'Text:' || chr(10) || text) AS one,
md5('Text:' || chr(10) || text) AS zero FROM shown""")
def w08_prompts(spark, sf_dir):
    calls, shown = qa.plan_calls(qa.qa_pool(collect.document_views(table(spark, sf_dir, "documents")), TARGET)), qa.exemplar_table(spark)
    digest = lambda k, name: qa.one_shot(calls, shown, shots=k).select("call", F.md5(F.col("prompt").cast("binary")).alias(name))
    return digest(1, "one").join(digest(0, "zero"), "call")


@query("w08_single_view", f"""WITH {sql.calls(TARGET)} SELECT view, count(*) AS calls, count(*) FILTER (well_formed) AS pairs, count(DISTINCT question) AS questions FROM parsed GROUP BY view""")
def w08_views(spark, sf_dir):
    return parsed(spark, sf_dir).groupBy("view").agg(F.count("*").alias("calls"), F.count_if("well_formed").alias("pairs"), F.countDistinct("question").alias("questions"))


@query("w09_format_check", f"WITH {sql.calls(TARGET)} SELECT qa_id, well_formed, md5(question) AS question, md5(answer) AS answer FROM parsed")
def w09(spark, sf_dir):
    return parsed(spark, sf_dir).select("qa_id", "well_formed", F.md5(F.col("question").cast("binary")).alias("question"), F.md5(F.col("answer").cast("binary")).alias("answer"))


@query("w09_yield", f"""WITH {sql.calls(TARGET)} SELECT count(*) AS calls, count(*) FILTER (well_formed) AS pairs, count(DISTINCT image_id) AS images,
round(count(*) FILTER (well_formed) / count(DISTINCT image_id)::DOUBLE, 6) AS pairs_per_image, round(1 - count(*) FILTER (well_formed) / count(*)::DOUBLE, 6) AS format_loss FROM parsed""")
def w09_yield(spark, sf_dir):
    return qa.yield_rates(parsed(spark, sf_dir))


@query("w10_split_stats", f"""WITH {sql.cascade(TARGET)}, t AS (SELECT 'generated' AS dataset, split, image_id FROM judged UNION ALL SELECT 'filtered', split, image_id FROM judged WHERE kept)
SELECT dataset, coalesce(split, 'all') AS split, count(DISTINCT image_id) AS images, count(*) AS pairs FROM t GROUP BY GROUPING SETS ((dataset, split), (dataset))""")
def w10(spark, sf_dir):
    rows = qa.split_by_image(judged(spark, sf_dir))
    return qa.qa_stats(rows, rows.filter("kept"))


@query("w11_overlap", f"""WITH q AS (SELECT u.conv_id, u.turn, {sql.norm('u.text')} AS a, {sql.norm('r.text')} AS b FROM conversations u JOIN conversations r
  ON r.conv_id = u.conv_id AND r.turn = u.turn + 1 AND u.role = 'user' AND r.role = 'assistant'),
g AS (SELECT conv_id, turn, {sql.char_grams('a')} AS x, {sql.char_grams('b')} AS y FROM q)
SELECT conv_id, turn, round(len(list_intersect(x, y)) / len(x)::DOUBLE, 6) AS overlap, len(list_intersect(x, y)) / len(x)::DOUBLE >= 0.12 AS keep FROM g""")
def w11(spark, sf_dir):
    pairs = training.conversation_pairs(table(spark, sf_dir, "conversations"))
    value = filters.overlap_of(F.col("question"), F.col("answer"))
    return pairs.select("conv_id", "turn", value.alias("v")).select("conv_id", "turn", F.round("v", 6).alias("overlap"), filters.f_overlap(F.col("v")).alias("keep"))


_VARIANTS = {"question": "len(x)", "text": "len(y)", "union": "len(list_distinct(list_concat(x, y)))", "min": "least(len(x), len(y))"}


@query("w11_overlap_variants", f"""WITH q AS (SELECT {sql.norm('u.text')} AS a, {sql.norm('r.text')} AS b, {sql.words('u.text')} AS wa, {sql.words('r.text')} AS wb FROM conversations u JOIN conversations r
  ON r.conv_id = u.conv_id AND r.turn = u.turn + 1 AND u.role = 'user' AND r.role = 'assistant'),
g AS (SELECT 'char' AS unit, {sql.char_grams('a')} AS x, {sql.char_grams('b')} AS y FROM q UNION ALL SELECT 'word',
  list_distinct(list_transform(range(1, len(wa) - 2), lambda i: array_to_string(wa[i:i + 3], ' '))), list_distinct(list_transform(range(1, len(wb) - 2), lambda i: array_to_string(wb[i:i + 3], ' '))) FROM q),
v AS ({' UNION ALL '.join(f"SELECT unit, '{d}' AS denom, len(list_intersect(x, y)) / nullif({e}, 0)::DOUBLE AS v FROM g" for d, e in _VARIANTS.items())})
SELECT unit, denom, t::DOUBLE AS threshold, count(*) AS pairs, count(*) FILTER (v >= t::DOUBLE) AS kept FROM v, (VALUES (0.06), (0.12), (0.24)) AS h(t) GROUP BY ALL""")
def w11_variants(spark, sf_dir):
    """Pairs kept by unit, denominator and threshold: how the unstated choices move the filter."""
    pairs = training.conversation_pairs(table(spark, sf_dir, "conversations"))
    values = [F.struct(F.lit(unit).alias("unit"), F.lit(d).alias("denom"), filters.overlap_of(F.col("question"), F.col("answer"), 4, unit, d).alias("v")) for unit in ("char", "word") for d in ("question", "text", "union", "min")]
    grid = pairs.select(F.inline(F.array(*values))).select("unit", "denom", "v", F.explode(F.array(*map(F.lit, (0.06, 0.12, 0.24)))).alias("threshold"))
    return grid.groupBy("unit", "denom", "threshold").agg(F.count("*").alias("pairs"), F.count_if(filters.f_overlap(F.col("v"), F.col("threshold"))).alias("kept"))


@query("w12_paraphrase", f"""WITH q AS (SELECT conv_id, turn, {sql.norm('text')} AS n, list_distinct({sql.words('text')}) AS w FROM conversations WHERE role = 'user'),
l AS (SELECT a.conv_id, a.turn AS a, b.turn AS b FROM q a JOIN q b ON a.conv_id = b.conv_id AND (a.n = b.n OR (len(list_distinct(list_concat(a.w, b.w))) > 0
  AND len(list_intersect(a.w, b.w)) / len(list_distinct(list_concat(a.w, b.w)))::DOUBLE >= 0.8)))
SELECT conv_id, a AS turn, min(b) < a AS duplicate FROM l GROUP BY conv_id, a""")
def w12(spark, sf_dir):
    user = table(spark, sf_dir, "conversations").filter("role = 'user'")
    key = F.concat_ws("#", F.col("conv_id").cast("string"), F.col("turn").cast("string"))
    rows = user.select("conv_id", F.col("turn"), F.lit("parse").alias("view"), F.col("turn").cast("int").alias("slot"), key.alias("qa_id"), F.col("text").alias("question"))
    return filters.f_paraphrase(rows, filters.same_words(), page="conv_id").select("conv_id", "turn", "duplicate")


@query("w13_attrition", f"""WITH {sql.cascade(TARGET)}, f AS (SELECT coalesce(reasons[1], 'kept') AS reason, count(*) AS sequential FROM judged GROUP BY 1),
i AS (SELECT unnest(CASE WHEN kept THEN ['kept'] ELSE reasons END) AS reason FROM judged)
SELECT i.reason, coalesce(any_value(sequential), 0) AS sequential, count(*) AS independent FROM i LEFT JOIN f USING (reason) GROUP BY i.reason""")
def w13(spark, sf_dir):
    return filters.attrition(judged(spark, sf_dir))


@query("w13_independent", f"""WITH {sql.cascade(TARGET, 'independent')}, f AS (SELECT coalesce(reasons[1], 'kept') AS reason, count(*) AS sequential FROM judged GROUP BY 1),
i AS (SELECT unnest(CASE WHEN kept THEN ['kept'] ELSE reasons END) AS reason FROM judged)
SELECT i.reason, coalesce(any_value(sequential), 0) AS sequential, count(*) AS independent FROM i LEFT JOIN f USING (reason) GROUP BY i.reason""")
def w13_independent(spark, sf_dir):
    """Attrition when each filter sees all pairs."""
    return filters.attrition(judged(spark, sf_dir, mode="independent"))


@query("w13_survival", f"WITH {sql.cascade(TARGET)} SELECT count(DISTINCT image_id) AS images, count(DISTINCT image_id) FILTER (kept) AS surviving FROM judged")
def w13_survival(spark, sf_dir):
    rows = judged(spark, sf_dir)
    return filters.image_survival(rows, rows.filter("kept"))


@query("w13_rounds")
def w13_rounds(spark, sf_dir):
    """Rounds of filtering and page deduplication until nothing goes: pairs left by split.

    Filters that judge a pair by itself say the same in each round, so they run in the first one only."""
    keep = keeper(spark)
    pairs = keep(parsed(spark, sf_dir).filter("well_formed").select("qa_id", "image_id", "view", "slot", "lang", "text", "question", "answer"))
    alone = filters.judged_alone(filters.with_language(pairs, keep(profiles(spark, sf_dir)), LANGS), TARGET)
    passing = keep(alone.filter(F.size("reasons") == 0).select(*pairs.columns))

    def step(df: DataFrame) -> DataFrame:
        again = filters.f_paraphrase(df.select("qa_id", "image_id", "view", "slot", "question"), filters.same_words()).filter("duplicate")
        kept = df.join(again.select("qa_id"), "qa_id", "left_anti")
        own = kept.groupBy("image_id").agg(F.min("text").alias("page"))
        stay = own.groupBy(dedup.fp_exact(F.col("page"))).agg(F.min("image_id").alias("image_id")).select("image_id")
        return kept.join(stay, "image_id", "left_semi")

    return qa.split_by_image(filters.rounds(passing, step, keep)).groupBy("split").agg(F.count("*").alias("pairs"))


@query("w14_gold", "SELECT item_id, true AS verified, 'test' AS split FROM (SELECT * FROM benchmark ORDER BY md5('gold|' || item_id), item_id LIMIT 54) WHERE item_id % 3 <> 0")
def w14(spark, sf_dir):
    """Chosen pages whose draft a stand-in verdict (id not a multiple of three) approves; others never enter."""
    chosen = gold.gold_sample(table(spark, sf_dir, "benchmark"))
    tasks = gold.annotation_tasks(chosen, gold.identity_translator(), gold.dictionary_translator("second"))
    done = gold.verify(tasks, chosen.select("item_id", (F.col("item_id") % 3 != 0).alias("approved")))
    return done.select("item_id", (F.col("state") == "verified").alias("verified"), "split")


@query("w14_translator_agreement")
def w14_agreement(spark, sf_dir):
    tasks = gold.annotation_tasks(table(spark, sf_dir, "benchmark"), gold.dictionary_translator("first"), gold.dictionary_translator("second"))
    return tasks.select("item_id", "agreement")


def test_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """dataset, qa_id, text, question, answer: gold, the synthetic test split, and English pages."""
    tasks = gold.annotation_tasks(gold.gold_sample(table(spark, sf_dir, "benchmark")), gold.identity_translator(), gold.identity_translator())
    hand = tasks.filter("answer is not null").select(F.lit("gold").alias("dataset"), F.col("item_id").cast("string").alias("qa_id"), "text", "question", "answer")
    made = synthetic(spark, sf_dir).filter("split = 'test'").select(F.lit("synthetic").alias("dataset"), "qa_id", "text", "question", "answer")
    english = qa.split_by_image(parsed(spark, sf_dir, "en").filter("well_formed")).filter("split = 'test'").select(F.lit("english").alias("dataset"), "qa_id", "text", "question", "answer")
    return hand.unionByName(made).unionByName(english)


@query("w15_model_matrix")
def w15(spark, sf_dir):
    return compare.score_matrix(compare.with_scores(compare.answers(test_sets(spark, sf_dir))))


_FIRST = f"""WITH {sql.cascade(TARGET)}, s AS (SELECT qa_id, answer, list_filter(list_transform(regexp_split_to_array(text, '[.!?]+[ \\n]+|\\n+'), lambda s: trim(s)), lambda s: len(regexp_split_to_array(s, ' +')) >= 5)[1] AS p
  FROM judged WHERE kept AND split = 'test'), n AS (SELECT {sql.norm("coalesce(p, '')")} AS p, {sql.norm('answer')} AS r FROM s)"""


@query("w15_first_sentence", f"{_FIRST} SELECT count(*) AS n, count(*) FILTER (p = r) AS exact, count(*) FILTER (contains(' ' || p || ' ', ' ' || r || ' ')) AS contained FROM n")
def w15_first(spark, sf_dir):
    rows = compare.answers(synthetic(spark, sf_dir).filter("split = 'test'").select(F.lit("synthetic").alias("dataset"), "qa_id", "text", "question", "answer")).filter("model = 'first_sentence'")
    p, r = norm(F.col("prediction")), norm(F.col("reference"))
    space = F.lit(" ")
    return rows.agg(F.count("*").alias("n"), F.count_if(p == r).alias("exact"), F.count_if(F.concat(space, p, space).contains(F.concat(space, r, space))).alias("contained"))


@query("w15_metric_agreement")
def w15_agreement(spark, sf_dir):
    return compare.metric_agreement(compare.with_scores(compare.answers(test_sets(spark, sf_dir))))


#: Shares of good documents by source (as the model) and language (as the test set).
SCORES = """WITH l AS (SELECT doc_id, min(quality) AS quality FROM labels GROUP BY doc_id HAVING min(quality) IS NOT NULL), d AS (SELECT source AS model, lang AS dataset, quality FROM documents JOIN l USING (doc_id)),
s AS (SELECT model, dataset, avg(quality) AS accuracy FROM d GROUP BY ALL)"""
_BOTH = f"{SCORES}, w AS (SELECT a.model, a.accuracy AS x, b.accuracy AS y FROM s a JOIN s b ON a.model = b.model AND a.dataset = '{TARGET}' AND b.dataset = 'de')"
#: Integral of cos(t) ** (n - 3) by Simpson's rule; the two-sided p of r is its part above asin(|r|).
_AREA = "list_sum(list_transform(range(2001), lambda i: (CASE WHEN i IN (0, 2000) THEN 1 WHEN i % 2 = 1 THEN 4 ELSE 2 END) * pow(cos({0} + i * (pi() / 2 - {0}) / 2000), n - 3))) * (pi() / 2 - {0})"


def quality_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    return compare.quality_scores(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


@query("w16_gap", f"{SCORES} SELECT a.model, a.dataset, round(b.accuracy - a.accuracy, 6) AS gap, round((b.accuracy - a.accuracy) / nullif(b.accuracy, 0), 6) AS relative_gap FROM s a JOIN s b ON a.model = b.model AND b.dataset = 'en' AND a.dataset <> 'en'")
def w16(spark, sf_dir):
    return compare.language_gap(quality_scores(spark, sf_dir), "en")


def _wide(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A row a source that has labelled documents of both languages."""
    return quality_scores(spark, sf_dir).groupBy("model").pivot("dataset", [TARGET, "de"]).agg(F.first("accuracy")).dropna(subset=[TARGET, "de"])


@query("w17_pearson", f"{_BOTH}, c AS (SELECT count(*) AS n, corr(x, y) AS r FROM w) SELECT n, round(r, 6) AS r, CASE WHEN n >= 3 THEN round({_AREA.format('asin(least(abs(r), 1))')} / ({_AREA.format('0')}), 6) END AS p FROM c")
def w17(spark, sf_dir):
    return compare.pearson(spark, _wide(spark, sf_dir), TARGET, "de")


@query("w17_spearman", f"{_BOTH}, k AS (SELECT rank() OVER (ORDER BY x) + (count(*) OVER (PARTITION BY x) - 1) / 2 AS x, rank() OVER (ORDER BY y) + (count(*) OVER (PARTITION BY y) - 1) / 2 AS y FROM w) SELECT count(*) AS n, round(corr(x, y), 6) AS rho FROM k")
def w17_spearman(spark, sf_dir):
    return compare.spearman(_wide(spark, sf_dir), TARGET, "de")


@query("w17_leave_one_out", f"{_BOTH} SELECT o.model AS without, round(corr(w.x, w.y), 6) AS r FROM w o JOIN w ON w.model <> o.model GROUP BY o.model")
def w17_loo(spark, sf_dir):
    return compare.leave_one_out(keeper(spark)(_wide(spark, sf_dir)), "model", TARGET, "de")


@query("w17_bootstrap")
def w17_bootstrap(spark, sf_dir):
    return compare.bootstrap(keeper(spark)(_wide(spark, sf_dir)), "model", TARGET, "de")


@query("w17_answerers")
def w17_answerers(spark, sf_dir):
    """The same correlation between the two test sets for this repository's own answerers."""
    scores = compare.score_matrix(compare.with_scores(compare.answers(test_sets(spark, sf_dir))), "anls")
    wide = scores.groupBy("model").pivot("dataset", ["gold", "synthetic"]).agg(F.first("accuracy"))
    return compare.pearson(spark, wide, "gold", "synthetic")


def mixtures(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The base mixture: synthetic training pairs and three conversation sources (conv_id modulo 3)."""
    own = training.as_qa_task(synthetic(spark, sf_dir).filter("split = 'train'"))
    talk = training.conversation_pairs(table(spark, sf_dir, "conversations")).withColumn("image_id", F.concat_ws(":", F.lit("conv"), F.col("conv_id").cast("string"), F.col("turn").cast("string")))
    parts = [("synthetic", own, 1.0)] + [(f"talk_{k}", training.as_qa_task(talk.filter(F.col("conv_id") % 3 == k)), share) for k, share in enumerate((1.0, 0.5, 0.25))]
    return training.mixture(parts)


@query("w18_mixtures", f"""WITH {sql.cascade(TARGET)}, {_VIEWS}, talk AS (SELECT u.conv_id % 3 AS k, 'conv:' || u.conv_id || ':' || u.turn AS image_id FROM conversations u JOIN conversations r
  ON r.conv_id = u.conv_id AND r.turn = u.turn + 1 AND u.role = 'user' AND r.role = 'assistant'),
base AS (SELECT 'synthetic' AS source FROM judged WHERE kept AND split = 'train' UNION ALL SELECT 'talk_' || k FROM talk
  WHERE CASE k WHEN 0 THEN {sql.u('image_id', 'mix/talk_0')} < 1 WHEN 1 THEN {sql.u('image_id', 'mix/talk_1')} < 0.5 ELSE {sql.u('image_id', 'mix/talk_2')} < 0.25 END),
ocr AS (SELECT image_id FROM crawl WHERE lang = '{TARGET}')
SELECT b.share::DOUBLE AS budget, source, count(*) AS n FROM (VALUES (0.0), (0.2), (1.0)) AS b(share), (SELECT source, -1.0 AS v FROM base UNION ALL SELECT 'ocr', {sql.u('image_id', 'budget')} FROM ocr) x WHERE x.v < b.share GROUP BY ALL""")
def w18(spark, sf_dir):
    base = mixtures(spark, sf_dir)
    ocr = training.as_ocr_task(collect.page_views(table(spark, sf_dir, "pages")).filter(F.col("lang") == TARGET))
    out = None
    for share in (0.0, 0.2, 1.0):
        one = training.with_budget(base, ocr, share).groupBy("source").agg(F.count("*").alias("n")).select(F.lit(share).alias("budget"), "source", "n")
        out = one if out is None else out.unionByName(one)
    return out


@query("w19_budget_curve", f"""WITH {_VIEWS}, o AS (SELECT image_id, plain AS text, {sql.u('image_id', 'budget')} AS v FROM crawl WHERE lang = '{TARGET}'),
test AS (SELECT w, count(*) AS times FROM (SELECT unnest({sql.words('text')}) AS w FROM documents WHERE lang = '{TARGET}') GROUP BY w),
tr AS (SELECT s AS budget, unnest({sql.words('text')}) AS w FROM o, (VALUES (0.0), (0.2), (1.0)) AS b(s) WHERE v < s),
c AS (SELECT budget, w, count(*) AS n FROM tr GROUP BY ALL),
z AS (SELECT s AS budget, coalesce(sum(n), 0) AS total, count(n) AS size FROM (VALUES (0.0), (0.2), (1.0)) AS b(s) LEFT JOIN c ON budget = s GROUP BY s)
SELECT z.budget::DOUBLE AS budget, sum(round(-10000 * ln((coalesce(n, 0) + 1)::DOUBLE / (total + size + 1)))::BIGINT * times)::BIGINT AS cost, sum(times)::BIGINT AS n_words FROM z CROSS JOIN test LEFT JOIN c ON c.budget = z.budget AND c.w = test.w GROUP BY z.budget""")
def w19(spark, sf_dir):
    """Cost of all documents of the target language to the proxy student of pages by transcription budget."""
    pages = collect.page_views(table(spark, sf_dir, "pages")).filter(F.col("lang") == TARGET).select("image_id", F.col("plain").alias("text"))
    test = table(spark, sf_dir, "documents").filter(F.col("lang") == TARGET).select("text")
    from doccurate.functions.keys import uniform

    out = None
    for share in (0.0, 0.2, 1.0):
        one = training.unigram_bits(pages.filter(uniform("image_id", "budget") < share), test).select(F.lit(share).alias("budget"), "cost", "n_words")
        out = one if out is None else out.unionByName(one)
    return out


@query("w20_filter_ablation")
def w20(spark, sf_dir):
    """Filters on and off: mean label quality of documents whose pairs stay, and cost of pages of the test split to a student of the training questions."""
    labels = table(spark, sf_dir, "labels").groupBy("doc_id").agg(F.min("quality").alias("quality"))
    rows = keeper(spark)(qa.split_by_image(judged(spark, sf_dir)).select("image_id", "question", "answer", "kept", "split"))
    pool = qa.split_by_image(qa.qa_pool(collect.document_views(table(spark, sf_dir, "documents")), TARGET))
    test = pool.filter("split = 'test'").select(F.col("view_parse").alias("text"))
    out = None
    for name, some in (("off", rows), ("on", rows.filter("kept"))):
        source = some.withColumn("doc_id", F.split("image_id", ":")[1].cast("long")).join(labels, "doc_id")
        one = source.agg(F.count("*").alias("labelled_pairs"), F.round(F.avg("quality"), 6).alias("quality")).crossJoin(training.unigram_bits(some.filter("split = 'train'").select(F.concat_ws(" ", "question", "answer").alias("text")), test))
        one = one.select(F.lit(name).alias("filters"), "labelled_pairs", "quality", "cost", "n_words")
        out = one if out is None else out.unionByName(one)
    return out


@query("w21_averaging", "SELECT floor(vec_id / 4)::BIGINT::VARCHAR AS param, i AS idx, round(avg(v), 6) AS value, count(*) = 4 AS complete FROM (SELECT vec_id, unnest(embedding)::DOUBLE AS v, generate_subscripts(embedding, 1) - 1 AS i FROM embeddings) GROUP BY ALL")
def w21(spark, sf_dir):
    rows = training.average_checkpoints(training.checkpoints_of(table(spark, sf_dir, "embeddings")))
    return rows.withColumn("value", F.round("value", 6)).withColumn("idx", F.col("idx").cast("long"))


@query("w21_averaging_variants")
def w21_variants(spark, sf_dir):
    """Distance of each averaging variant from the uniform mean."""
    ckpts = training.checkpoints_of(table(spark, sf_dir, "embeddings"))
    mean = training.average_checkpoints(ckpts).select("param", "idx", F.col("value").alias("mean"))
    out = None
    for name, kw in (("last_2", {"last": 2}), ("weighted", {"weights": {0: 1, 1: 2, 2: 3, 3: 4}}), ("decayed", {"decay": 0.5}), ("equal_weights", {"weights": dict.fromkeys(range(4), 2.0)})):
        one = training.average_checkpoints(ckpts, **kw).join(mean, ["param", "idx"]).agg(F.round(F.sqrt(F.avg((F.col("value") - F.col("mean")) ** 2)), 6).alias("distance")).select(F.lit(name).alias("variant"), "distance")
        out = one if out is None else out.unionByName(one)
    return out


#: Steps of added data: name, language.
ADDED = {"base": "en", "add_de": "de", "add_es": "es", "add_fr": "fr"}


@query("w21_tuned_deltas", SCORES + ", t(place, step, model) AS (SELECT a.k, b.k, b.m FROM (VALUES " + ", ".join(f"({k}, '{x}')" for k, x in enumerate(ADDED.values())) + ") a(k, x), (VALUES " + ", ".join(f"({k}, '{m}')" for k, m in enumerate(ADDED)) + ") b(k, m) WHERE a.k <= b.k), i(place, dataset) AS (VALUES " + ", ".join(f"({k}, '{x}')" for k, x in enumerate(ADDED.values())) + "), z AS (SELECT step, t.model, avg(quality) AS accuracy FROM d JOIN i USING (dataset) JOIN t USING (place) GROUP BY ALL) SELECT step, model, accuracy, round(accuracy - (SELECT accuracy FROM z WHERE model = 'base'), 6) AS delta FROM z")
def w21_deltas(spark, sf_dir):
    """Share of good documents as languages are added to the English ones, and its change against these."""
    return compare.deltas(keeper(spark)(compare.added_scores(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"), ADDED)))


@query("w22_filter_quality", f"WITH {sql.cascade(TARGET)} SELECT coalesce(fault, 'none') AS fault, count(*) AS pairs, count(*) FILTER (NOT kept) AS removed, round(count(*) FILTER (NOT kept) / count(*)::DOUBLE, 6) AS share FROM judged GROUP BY 1")
def w22(spark, sf_dir):
    return filters.filter_quality(judged(spark, sf_dir))


@query("w22_leaks", f"""WITH {sql.DOC_PAGES}, s AS ({_grams5('benchmark', 'item_id')}), tr AS (SELECT image_id, view_parse AS text FROM doc_pages WHERE lang = '{TARGET}'), b AS ({_grams5('tr', 'image_id')}), n AS (SELECT item_id, count(*) AS size FROM s GROUP BY item_id)
SELECT item_id, 'equal' AS how FROM benchmark WHERE md5({sql.norm('text')}) IN (SELECT md5({sql.norm('text')}) FROM tr)
UNION SELECT item_id, 'contained' FROM (SELECT item_id FROM s JOIN b USING (g) JOIN n USING (item_id) GROUP BY item_id, image_id HAVING count(*) / any_value(size)::DOUBLE >= 0.8)""")
def w22_leaks(spark, sf_dir):
    """Gold pages that equal, or lie inside, a page of the synthetic pool: what the disjointness guard must report."""
    pool = qa.qa_pool(collect.document_views(table(spark, sf_dir, "documents")), TARGET).select("image_id", F.col("view_parse").alias("text"))
    return dedup.leaks(pool, table(spark, sf_dir, "benchmark"), "image_id", "item_id")


for _lang in ("de", "es", "en"):

    @query(f"w24_attrition_{_lang}", f"""WITH {sql.cascade(_lang)}, f AS (SELECT coalesce(reasons[1], 'kept') AS reason, count(*) AS sequential FROM judged GROUP BY 1),
i AS (SELECT unnest(CASE WHEN kept THEN ['kept'] ELSE reasons END) AS reason FROM judged)
SELECT i.reason, coalesce(any_value(sequential), 0) AS sequential, count(*) AS independent FROM i LEFT JOIN f USING (reason) GROUP BY i.reason""")
    def _w24(spark, sf_dir, lang=_lang):
        return filters.attrition(judged(spark, sf_dir, lang))


@query("op_sql_functions", f"SELECT u.conv_id, u.turn, {sql.norm('u.text')} AS n, round({sql.u('u.conv_id', 's')}, 9) AS draw FROM conversations u WHERE role = 'user'")
def sql_functions(spark, sf_dir):
    """The methods through SQL: registered functions in a statement."""
    from doccurate.functions.sql import register

    register(spark)
    rows = table(spark, sf_dir, "conversations")
    return spark.sql("SELECT conv_id, turn, norm_text(text) AS n, round(keyed_uniform(CAST(conv_id AS STRING), 's'), 9) AS draw FROM {rows} WHERE role = 'user'", rows=rows)
