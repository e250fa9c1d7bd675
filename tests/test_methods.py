"""Methods of the library: published anchors, boundaries, properties, brute force."""

import itertools
import math
import random

import pytest
from pyspark.sql import functions as F

from doccurate.functions import metrics, text, web
from doccurate.functions.keys import uniform
from doccurate.operators import collect, compare, dedup, filters, gold, langid, qa, training


def one(spark, column):
    return spark.range(1).select(column.alias("x")).first().x


def test_norm_and_grams(spark):
    assert one(spark, text.norm(F.lit("  Él-Niño, 3%!"))) == "él niño 3"
    assert one(spark, text.grams(F.lit("abcde"), 4)) == ["abcd", "bcde"]
    assert one(spark, text.grams(F.lit("abc"), 4)) == []
    assert one(spark, text.grams(F.lit("a b c"), 2, "word")) == ["a b", "b c"]
    assert one(spark, text.grams(F.lit("😀😀😀a😀"), 4)) == []  # signs are not part of the normal form


@pytest.mark.parametrize("denom, value", [("question", 2 / 3), ("text", 0.5), ("union", 0.4), ("min", 2 / 3)])
def test_overlap_denominators(spark, denom, value):
    q, t = F.array(*map(F.lit, "abc")), F.array(*map(F.lit, "bcde"))
    assert one(spark, text.overlap(q, t, denom)) == pytest.approx(value)


def test_boundaries(spark):
    rows = spark.createDataFrame([("x" * n,) for n in (60, 61, 99, 100)] + [(None,)], "t string")
    assert [r.k for r in rows.select(filters.f_length(F.col("t")).alias("k")).collect()] == [False, True, True, True, False]
    assert collect.min_chars(rows, "t", 100).count() == 1 and collect.min_chars(rows, "t", 99, strict=True).count() == 1
    assert one(spark, filters.f_overlap(F.lit(0.12))) and not one(spark, filters.f_overlap(F.lit(0.1199)))
    assert not one(spark, filters.f_overlap(F.lit(None).cast("double"))) and one(spark, filters.f_overlap(F.lit(None).cast("double"), on_short="keep"))


def test_answer_measures(spark):
    refs = F.array(F.lit("The red house"), F.lit("house"))
    assert one(spark, metrics.exact_match(F.lit("the RED house!"), refs))
    assert one(spark, metrics.anls(F.lit("the red mouse"), F.array(F.lit("the red house")))) == pytest.approx(12 / 13)
    assert one(spark, metrics.anls(F.lit("zzz"), refs)) == 0 and one(spark, metrics.anls(F.lit(""), F.array(F.lit("")))) == 1
    assert one(spark, metrics.lexical_judge(F.lit("in the red house there"), F.lit("red house")))
    assert not one(spark, metrics.lexical_judge(F.lit("unhoused"), F.lit("house")))


def test_web(spark):
    html = '<html lang="fr"><script>var t="</p>";</script><nav>N</nav><article><h1>T&amp;u</h1><p><b>x</b> <a href="/k">y</a><p>z</article></html>'
    assert one(spark, web.to_plain(web.article_of(F.lit(html)))) == "T&u\nx y\nz"
    assert one(spark, web.to_markdown(web.article_of(F.lit(html)))) == "# T&u\n**x** [y](/k)\nz"
    assert one(spark, web.canonical_url(F.lit("HTTP://A.org/x?b=2&utm_source=q&a=1&ref=z#f"))) == "http://a.org/x?a=1&b=2"


def test_pages_keep_the_text(spark):
    rng = random.Random(1)
    texts = ["\n".join("x" * rng.randint(1, 900) for _ in range(rng.randint(1, 9))) for _ in range(20)]
    docs = spark.createDataFrame([(k, t) for k, t in enumerate(texts)], "doc_id long, text string")
    pages = {}
    for r in collect.paginate(docs).orderBy("doc_id", "page_no").collect():
        pages.setdefault(r.doc_id, []).append(r.page_text)
    assert ["\n".join(pages[k]) for k in range(20)] == texts
    assert all(len(p) <= 800 or "\n" not in p for ps in pages.values() for p in ps)


@pytest.fixture(scope="module")
def pairs(spark):
    rng = random.Random(2)
    vocabulary = [f"mot{k}" for k in range(300)]
    say = lambda n: " ".join(rng.choice(vocabulary) for _ in range(n))
    docs = spark.createDataFrame([(k, ". \n".join(say(12) for _ in range(6)) if k else "court", "fr") for k in range(120)], "doc_id long, text string, lang string")
    calls = qa.one_shot(qa.plan_calls(collect.document_views(docs)), qa.exemplar_table(spark))
    return qa.parse_qa(qa.extractive_generator()(calls)).cache()


def test_faults_and_format(pairs):
    rows = pairs.collect()
    assert all(r.well_formed != (r.fault in ("malformed", "empty")) for r in rows)
    assert {r.fault for r in rows} >= {None, "malformed", "off_topic", "wrong_language", "paraphrase"}
    assert len({r.qa_id for r in rows}) == len(rows)


def test_format_check(spark):
    given = ["Q: a\nA: b", "Q: a\nA: ", "Q: a", "Q: a\nQ: b\nA: c", "A: b\nQ: a", "Q: a\nA: b\nmore", " Q: a\nA: b"]
    rows = spark.createDataFrame([(x, "i", "parse", k) for k, x in enumerate(given)], "completion string, image_id string, view string, slot int")
    assert [r.well_formed for r in qa.parse_qa(rows).orderBy("slot").collect()] == [True] + [False] * 6


def test_split_is_by_page(pairs):
    split = qa.split_by_image(pairs)
    assert split.groupBy("image_id").agg(F.countDistinct("split").alias("n")).filter("n > 1").count() == 0
    again = {r.image_id: r.split for r in qa.split_by_image(pairs.repartition(7)).collect()}
    assert again == {r.image_id: r.split for r in split.collect()}


def test_cascade(spark, pairs):
    prof = langid.profile(spark.createDataFrame([("fr", "mot1 mot2 qui quand combien a signé la lettre " * 3), ("en", "who signed the letter " * 3)], "lang string, text string"), ["en", "fr"])
    good = pairs.filter("well_formed")
    judged = filters.run_cascade(filters.with_language(good, prof, ["en", "fr"]), "fr").cache()
    counts = {r.reason: r.sequential for r in filters.attrition(judged).collect()}
    assert sum(counts.values()) == good.count()
    removed = {r.fault for r in judged.filter("not kept").select("fault").distinct().collect()}
    assert "wrong_language" in removed and "paraphrase" in removed
    kept = judged.filter("kept").select(*good.columns)
    twice = filters.run_cascade(filters.with_language(kept, prof, ["en", "fr"]), "fr")
    assert twice.filter("not kept").count() == 0  # a fixed point
    every = filters.attrition(filters.run_cascade(filters.with_language(good, prof, ["en", "fr"]), "fr", mode="independent"))
    assert all(r.independent >= counts.get(r.reason, 0) for r in every.collect() if r.reason != "kept")


@pytest.mark.parametrize("questions", [["a b c d e", "a b c d e", "x", "A  b C d e!"], ["p", "q", "r", "s"], ["one two three four five", "one two three four", "two three four", "x y"]])
def test_paraphrase_closure(spark, questions):
    rows = spark.createDataFrame([("p", f"{k}", "parse" if k < 2 else "ocr", k % 2 + 1, q) for k, q in enumerate(questions)], "image_id string, qa_id string, view string, slot int, question string")
    sets = [set("".join(c if c.isalnum() else " " for c in q.lower()).split()) for q in questions]
    linked = {(i, j) for i, j in itertools.product(range(4), repeat=2) if len(sets[i] & sets[j]) / len(sets[i] | sets[j]) >= 0.8}
    for _ in range(4):
        linked |= {(a, d) for a, b in linked for c, d in linked if b == c}
    found = {int(r.qa_id): r.duplicate for r in filters.f_paraphrase(rows, filters.same_words()).collect()}
    assert found == {i: min(j for j in range(4) if (i, j) in linked) < i for i in range(4)}
    none = {int(r.qa_id): r.duplicate for r in filters.f_paraphrase(rows, filters.same_words(), keep="none").collect()}
    assert none == {i: sum((i, j) in linked for j in range(4)) > 1 for i in range(4)}
    assert filters.f_paraphrase(rows, filters.equal_norm(), closure="greedy").filter("not duplicate").count() == len({frozenset(s) if questions[0][0] == "a" else i for i, s in enumerate(sets)})


def test_published_counts():
    images, pairs_, filtered = (21800, 1283, 1258), (84192, 4930, 4811), (55325, 3382, 3315)
    assert (sum(images), sum(pairs_), sum(filtered), sum(pairs_) - sum(filtered)) == (24341, 93933, 62022, 31911)
    assert [round(a / sum(images), 4) for a in images] == list(qa.RATIOS.values())


def test_published_scores(spark):
    wide = compare.published_scores(spark).groupBy("model").pivot("dataset").agg(F.first("accuracy"))
    r = compare.pearson(spark, wide, "gold", "synthetic").first()
    assert r.n == 4 and r.r == pytest.approx(0.99166, abs=1e-5) and r.p == pytest.approx(0.00834, abs=1e-5)
    assert compare.spearman(wide, "gold", "synthetic").first().rho == 1
    assert compare.proxy_ok(r.r, r.p)
    d = {x.model: x.delta for x in compare.deltas(compare.tuned_scores(spark)).collect()}
    assert (d["synthetic_only"], d["mixture_21k"], d["mixture_105k"]) == (-0.047, 0.042, 0.072)


def test_p_values():
    for r in (0.1, 0.5, 0.9, -0.7):
        assert compare.two_sided_p(r, 4) == pytest.approx(1 - abs(r), abs=1e-9)
    assert compare.two_sided_p(0.5, 12) == pytest.approx(0.0978, abs=1e-3)
    assert compare.two_sided_p(0.5, 2) is None and compare.two_sided_p(None, 9) is None and compare.two_sided_p(1.0, 5) == 0
    assert not math.isnan(compare.two_sided_p(1e-12, 40))


def test_constant_scores_have_no_correlation(spark):
    wide = spark.createDataFrame([("a", 0.5, 0.1), ("b", 0.5, 0.2), ("c", 0.5, 0.3)], "model string, x double, y double")
    assert compare.pearson(spark, wide, "x", "y").first().r is None


def test_dedup(spark, tmp_path):
    rng = random.Random(3)
    say = lambda n: [f"w{rng.randint(0, 999)}" for _ in range(n)]
    base = [say(80) for _ in range(12)]
    edited = [b[:40] + ["changed"] + b[41:] for b in base[:6]]
    docs = spark.createDataFrame([(k, " ".join(t)) for k, t in enumerate([*base, *edited, base[0]])], "doc_id long, text string")
    exact = {(r.id, r.other) for r in dedup.gram_join_pairs(docs, "doc_id", threshold=0.7).collect()}
    assert exact == {(k, 12 + k) for k in range(6)}
    n = itertools.count()

    def keep(df):
        path = f"{tmp_path}/{next(n)}"
        df.write.parquet(path)
        return spark.read.parquet(path)

    found = dedup.near_pairs(docs, "doc_id", keep=keep)
    assert {(r.id, r.other) for r in found.collect()} <= exact and found.count() >= 5
    chain = spark.createDataFrame([(k, k + 1) for k in range(20)] + [(50, 51)], "id long, other long")
    assert {r.node: r.root for r in dedup.clusters(chain, keep).collect()} == {**dict.fromkeys(range(21), 0), 50: 50, 51: 50}
    copies = {r.doc_id: r.keeper for r in dedup.exact_groups(docs, "doc_id").collect()}
    assert copies[18] == 0 and copies[5] == 5
    near = dedup.simhash_pairs(spark.createDataFrame([(1, "a b c d e f"), (2, "A b c, d e f"), (3, "q r s t u v")], "doc_id long, text string"), "doc_id")
    assert near.count() == 0  # equal normal forms are one fingerprint
    sets = dedup.disjoint_sets([("gold", 0, docs.limit(1).select(F.col("doc_id").alias("key"), "text")), ("corpus", 1, docs.select(F.col("doc_id").alias("key"), "text"))])
    assert sets.count() == 18 and sets.filter("dataset = 'gold'").count() == 1


@pytest.mark.parametrize("threshold", [0.5, 0.7, 0.8])
def test_gram_join_finds_all_pairs(spark, threshold):
    rng = random.Random(int(threshold * 10))
    common = [f"c{k}" for k in range(30)]  # a passage that all texts share
    texts = []
    for _ in range(12):
        base = [f"w{rng.randint(0, 60)}" for _ in range(rng.randint(30, 120))]
        for _ in range(6):
            own = list(base)
            for _ in range(rng.randint(0, 2)):
                own.insert(rng.randint(0, len(own)), f"n{rng.randint(0, 9)}")
            texts.append(" ".join(own + common * rng.randint(0, 1)))
    rows = [*enumerate(texts), (900, None), (901, ""), (902, "one two"), (903, texts[0])]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    sets, first = {}, {}
    for k, t in rows:
        w = (t or "").split()
        if len(w) > 4 and first.setdefault(t, k) == k:
            sets[k] = {tuple(w[i : i + 5]) for i in range(len(w) - 4)}
    want = {(a, b) for a, b in itertools.combinations(sets, 2) if round(len(sets[a] & sets[b]) / len(sets[a] | sets[b]), 6) >= threshold}
    assert len(want) > 20  # or the fixture shows nothing
    assert {(r.id, r.other) for r in dedup.gram_join_pairs(docs, "doc_id", threshold=threshold).collect()} == want
    found = {(r.id, r.other) for r in dedup.near_pairs(docs, "doc_id", threshold=threshold).collect()}
    assert found <= want and len(found) > 0.7 * len(want)


def test_gold_needs_a_verdict(spark):
    items = spark.createDataFrame([(k, "one two three four five six. more words are in here too.") for k in range(5)], "item_id long, text string")
    tasks = gold.annotation_tasks(items, gold.identity_translator(), gold.identity_translator())
    assert gold.verify(tasks, spark.createDataFrame([(1, True), (2, False)], "item_id long, approved boolean")).select("item_id").collect() == [(1,)]


def test_averaging_and_budgets(spark):
    ckpts = spark.createDataFrame([(c, "p", i, float(c * i)) for c in range(4) for i in range(3)], "ckpt int, param string, idx int, value double")
    mean = {r.idx: r.value for r in training.average_checkpoints(ckpts).collect()}
    assert mean == {0: 0.0, 1: 1.5, 2: 3.0}
    assert {r.idx: r.value for r in training.average_checkpoints(ckpts, weights=dict.fromkeys(range(4), 5.0)).collect()} == mean
    assert {r.idx: r.value for r in training.average_checkpoints(ckpts, last=1).collect()} == {0: 0.0, 1: 3.0, 2: 6.0}
    assert not training.average_checkpoints(ckpts.filter("not (ckpt = 2 and idx = 1)")).filter("idx = 1").first().complete
    ocr = spark.createDataFrame([(f"i{k}", "t", "p", "x") for k in range(200)], "image_id string, task string, prompt string, target string")
    base = ocr.limit(0).select(F.lit("s").alias("source"), "image_id", "task", "prompt", "target")
    small, large = ({r.image_id for r in training.with_budget(base, ocr, s).collect()} for s in (0.2, 0.7))
    assert small < large and 20 < len(small) < 60


def test_uniform_matches_its_definition(spark):
    import hashlib

    assert one(spark, uniform(F.lit("k1"), "s")) == int(hashlib.md5(b"s|k1").hexdigest()[:8], 16) / 2**32


def test_language_detection(spark):
    docs = spark.createDataFrame([("en", "the cat and the dog " * 4), ("fr", "le chat et le chien " * 4)], "lang string, text string")
    asked = spark.createDataFrame([(1, "the dog"), (2, "le chien"), (3, "zzz"), (4, None)], "doc_id long, text string")
    for unit in ("word", "char"):
        found = {r.doc_id: r.detected for r in langid.detect(asked, ["doc_id"], "text", langid.profile(docs, ["en", "fr"], unit), ["en", "fr"], unit).collect()}
        assert (found[1], found[2], found[4]) == ("en", "fr", None)


def test_plans_stay_native(spark, pairs):
    from doccurate.plans.workloads import parsed

    for df in (parsed(spark, "/root/testdata/sf0.001"), filters.f_paraphrase(pairs, filters.same_words())):
        plan = df._jdf.queryExecution().executedPlan().toString()
        assert not any(x in plan for x in ("ArrowEvalPython", "BatchEvalPython", "MapInArrow"))


def test_pushed_filters(spark):
    from doccurate.plans.registry import QUERIES

    plan = QUERIES["op_scan_prune"](spark, "/root/testdata/sf0.001")._jdf.queryExecution().executedPlan().toString()
    assert "EqualTo(lang,fr)" in plan and "text" not in plan.split("ReadSchema")[1]


def test_clusters_use_links_that_no_band_proposes(spark, tmp_path):
    import random

    import __spark_entry__

    rng, rows = random.Random(4), []
    for k in range(600):  # 46 five-grams; a changed last 8 words leave 38 of 54: similarity 0.7037
        one = [f"w{rng.randint(0, 10**9)}" for _ in range(50)]
        rows += [(2 * k, " ".join(one)), (2 * k + 1, " ".join(one[:42] + [f"x{rng.randint(0, 10**9)}" for _ in range(8)]))]
    spark.createDataFrame([(k, t, "en", "s", len(t)) for k, t in rows], "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{tmp_path}/documents.parquet")
    found = {(r.node, r.root) for r in __spark_entry__.queries()["w07_clusters"](spark, str(tmp_path)).collect()}
    assert found == {(x, 2 * k) for k in range(600) for x in (2 * k, 2 * k + 1)}


def test_clusters_hold_all_copies(spark, tmp_path):
    """Every row of an equal text is in its cluster, also where the text has no other near copy; texts without grams and nulls are in none."""
    import __spark_entry__

    say = lambda k: " ".join(f"w{k}x{i}" for i in range(40))
    near = say(1) + " end"
    docs = [(1, say(1)), (7, say(1)), (9, near), (3, near), (4, say(4)), (5, say(4)), (6, say(4)), (8, say(8)), (20, "too short"), (21, "too short"), (22, ""), (23, ""), (24, None), (25, None), (None, say(8)), (30, "a b c d e"), (31, "a b c d e")]
    docs += [(40 + k, say(40)) for k in range(50)] + [(40, say(40))]
    spark.createDataFrame(docs, "doc_id long, text string").selectExpr("doc_id", "text", "'en' as lang", "'s' as source", "0L as n_chars").repartition(5).write.parquet(f"{tmp_path}/documents.parquet")
    found = sorted((r.node, r.root) for r in __spark_entry__.queries()["w07_clusters"](spark, str(tmp_path)).collect())
    assert found == [(1, 1), (3, 1), (4, 4), (5, 4), (6, 4), (7, 1), (9, 1), (30, 30), (31, 30), *((40 + k, 40) for k in range(50))]
    pairs = dedup.gram_join_pairs(spark.read.parquet(f"{tmp_path}/documents.parquet"), "doc_id", copies=True)
    links = sorted((r.id, r.other) for r in pairs.filter("id < 40").collect())
    assert links == [(1, 3), (1, 7), (3, 9), (4, 5), (4, 6), (30, 31)]
    assert pairs.filter("id >= 40").count() == 49 and pairs.filter("similarity < 1").count() == 1


def test_vectors_against_all_pairs(spark):
    rng = random.Random(1)
    base = [[rng.gauss(0, 1) for _ in range(24)] for _ in range(30)]
    rows = [(k, [x + rng.gauss(0, 0.25) for x in base[k % 30]]) for k in range(150)] + [(200, None), (201, [0.0] * 24), (202, [1.0] * 3)]
    cosine = lambda a, b: sum(x * y for x, y in zip(a, b, strict=True)) / math.sqrt(sum(x * x for x in a) * sum(y * y for y in b))
    expected = {(a, b) for (a, x), (b, y) in itertools.combinations(rows[:150], 2) if round(cosine(x, y), 6) >= 0.9}
    found = dedup.near_vectors(spark.createDataFrame(rows, "vec_id long, embedding array<double>"), "vec_id", "embedding")
    assert {(r.id, r.other) for r in found.collect()} == expected and len(expected) > 100


def test_simhash_pairs_against_all_pairs(spark):
    rng = random.Random(2)
    say = lambda n: [f"w{rng.randint(0, 400)}" for _ in range(n)]
    texts = []
    for _ in range(25):
        own = say(150)
        for _ in range(4):
            own = [*own[: (k := rng.randrange(150))], f"x{rng.random()}", *own[k + 1 :]]
            texts.append(" ".join(own))
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    fps = {r.doc_id: r.fp for r in df.select("doc_id", dedup.fp_simhash(F.col("text")).alias("fp")).collect()}
    first = sorted({fp: k for k, fp in sorted(fps.items(), reverse=True)}.values())  # the least key of each fingerprint
    expected = {(a, b) for a, b in itertools.combinations(first, 2) if ((fps[a] ^ fps[b]) & ((1 << 64) - 1)).bit_count() <= 3}
    assert {(r.id, r.other) for r in dedup.simhash_pairs(df, "doc_id").collect()} == expected and len(expected) >= 5


def test_leak_guard(spark):
    say = lambda k, n: " ".join(f"w{(k * 37 + i * i) % 1000}" for i in range(n))
    gold = spark.createDataFrame([(1, say(1, 30)), (2, say(2, 30)), (3, None), (4, "too short")], "item_id long, text string")
    train = spark.createDataFrame([("a", say(3, 80)), ("b", f"{say(4, 40)} {say(1, 30)} {say(5, 9)}"), ("c", say(2, 30).upper()), ("d", None), ("e", "")], "image_id string, text string")
    with pytest.raises(ValueError, match="2 test texts|3 test texts"):
        dedup.assert_disjoint(train, gold, "image_id", "item_id")
    clean = dedup.without_leaks(train, gold, "image_id", "item_id")
    assert clean.columns == train.columns and {"a"} <= {r.image_id for r in clean.collect()} <= {"a", "d", "e"}
    dedup.assert_disjoint(clean.filter("text <> ''"), gold, "image_id", "item_id")


def test_near_disjoint_sets(spark):
    say = lambda k, n: " ".join(f"w{(k * 37 + i * i) % 1000}" for i in range(n))
    rows = lambda *texts: spark.createDataFrame([(k, t) for k, t in enumerate(texts)], "key long, text string")
    near = say(1, 40).split()
    near[20] = "changed"
    sets = [("gold", 0, rows(say(1, 40))), ("own", 1, rows(" ".join(near[:33]) + " " + say(9, 20), say(7, 40))), ("corpus", 2, rows(f"{say(8, 30)} {say(1, 40)}", say(7, 40), say(6, 30)))]
    kept = {(r.dataset, r.key) for r in dedup.disjoint_near(sets).collect()}
    assert kept == {("gold", "0"), ("own", "0"), ("own", "1"), ("corpus", "2")}  # own 0 has fewer than four fifths of the gold page
    assert dedup.disjoint_near(sets[:1]).count() == 1


def test_exact_split(spark):
    for n in (0, 1, 7, 500):
        df = spark.createDataFrame([(f"i{k}",) for k in range(n) for _ in range(2)], "image_id string")
        for bits in (3, 16):
            rows = qa.split_exact(df, bits=bits).collect()
            assert len(rows) == 2 * n
            sizes = {s: len({r.image_id for r in rows if r.split == s}) for s in qa.RATIOS}
            first, second = round(n * 0.8956), round(n * (0.8956 + 0.0527))
            assert list(sizes.values()) == [first, second - first, n - second]


def test_paging_by_lines_and_form_feeds(spark):
    df = spark.createDataFrame([(1, "a\nb\fc", "en"), (2, None, "en"), (3, "", None)], "doc_id long, text string, lang string")
    pages = lambda by: sorted((r.doc_id, r.page_no, r.page_text) for r in collect.paginate(df, by=by).collect())
    assert pages("lines") == [(1, 0, "a"), (1, 1, "b\fc"), (2, 0, ""), (3, 0, "")]
    assert pages("form_feed") == [(1, 0, "a\nb"), (1, 1, "c"), (2, 0, ""), (3, 0, "")]


def test_translation_there_and_back(spark):
    text = "Nous avons signé la lettre hier. Le chat dort, dit-elle ~!"
    there, back = gold.coded_translator(share=0.6)
    moved = one(spark, there(F.lit(text)))
    assert moved != text and one(spark, back(F.lit(moved))) == text
    items = spark.createDataFrame([(1, text), (2, None), (3, "")], "item_id long, text string")
    rows = {r.item_id: r for r in gold.translated_pairs(items, there, back).collect()}
    assert rows[1].question == "Nous avons signé ?" and rows[1].answer == "la lettre hier" and (rows[1].question_read, rows[1].answer_read) != (rows[1].question, rows[1].answer)
    assert rows[2].question is None and rows[3].question is None


def test_students(spark):
    rows = spark.createDataFrame([("base", str(k), "a b c") for k in range(8)] + [("more", str(k), "d e") for k in range(8)] + [("more", "n", None)], "part string, key string, text string")
    members = spark.createDataFrame([(0, "base"), (1, "base"), (1, "more")], "cell int, part string")
    test = spark.createDataFrame([("d d",), ("",), (None,)], "text string")
    cost = {r.cell: r for r in training.student_costs(training.part_counts(rows), members, test).collect()}
    assert [cost[c].single for c in (0, 1)] == [2 * round(-10000 * math.log(1 / (24 + 3 + 1))), 2 * round(-10000 * math.log(9 / (40 + 5 + 1)))]
    assert all(r.single == r.averaged and r.n_words == 2 for r in cost.values())  # one checkpoint is its own mean
    dealt = {r.cell: r for r in training.student_costs(training.part_counts(rows, 4), members, test).collect()}
    assert all(r.averaged <= r.single for r in dealt.values())  # a mean of chances costs no more than the mean cost


def test_filter_scores(spark):
    rows = spark.createDataFrame([(1, False), (1, True), (0, False), (0, True), (None, False), (1, False)], "bad int, kept boolean")
    r = filters.filter_scores(rows, F.col("bad") == 1).first()
    assert (r.tp, r.fp, r.fn, r.precision, r.recall, r.f1) == (2, 1, 1, 0.666667, 0.666667, 0.666667)
    empty = filters.filter_scores(rows.limit(0), F.col("bad") == 1).first()
    assert empty.tp == 0 and empty.f1 is None


def test_gram_cosine(spark):
    from collections import Counter
    from hashlib import md5

    def vector(t):
        return Counter(int(md5(t[i : i + 3].encode()).hexdigest()[:8], 16) % 64 for i in range(len(t) - 2))

    a, b = "where is the port", "where was the old port"
    x, y = vector(a), vector(b)
    want = sum(x[k] * y[k] for k in x) / math.sqrt(sum(v * v for v in x.values()) * sum(v * v for v in y.values()))
    assert one(spark, text.gram_cosine(F.lit(a), F.lit(b))) == pytest.approx(want)
    assert one(spark, text.gram_cosine(F.lit("ab"), F.lit(b))) is None
    assert one(spark, filters.close_vectors()(F.lit(a), F.lit(a.upper()))) and not one(spark, filters.close_vectors()(F.lit(""), F.lit("")))
    assert not one(spark, filters.close_edit()(F.lit("abc"), F.lit("abd"))) and one(spark, filters.close_edit(0.6)(F.lit("abc"), F.lit("abd")))


def test_external_judge(spark):
    """Distinct pairs are asked once, known ones not at all; verdicts rule as a judge in columns does."""
    asked = spark.sparkContext.accumulator(0)

    def ask(a, b):
        asked.add(len(a))
        return [x.lower() == y.lower() for x, y in zip(a, b)]

    qs = [("p", "parse", 0, "Who?"), ("p", "parse", 1, "who?"), ("p", "ocr", 0, "WHO?"), ("p", "ocr", 1, "Where?"), ("r", "parse", 0, "Who?"), ("r", "ocr", 0, "who?"), ("r", "ocr", 1, None)]
    rows = spark.createDataFrame([(f"{i}{v}{s}", i, v, s, q) for i, v, s, q in qs], "qa_id string, image_id string, view string, slot int, question string")
    told = [tuple(r) for r in filters.external_verdicts(rows, ask).collect()]
    assert asked.value == len(told) == 6 and sum(t[2] for t in told) == 3
    cache = spark.createDataFrame(told, "a string, b string, same boolean")
    assert sorted(map(tuple, filters.external_verdicts(rows, ask, cache).collect())) == sorted(told) and asked.value == 6
    by_ask = filters.f_paraphrase(rows, filters.by_verdicts(), verdicts=cache)
    assert {r.qa_id for r in by_ask.filter("duplicate").collect()} == {"pparse1", "pocr0", "rocr0"}
    assert tuple(filters.judge_calls(rows).first()) == (2, 7, 9) and tuple(filters.judge_calls(rows.limit(0)).first()) == (0, 0, 0)
    assert filters.external_verdicts(rows.limit(0), ask).count() == 0


def test_hashed_students(spark):
    data = [(str(i), "good fine words here" if i % 2 else "bad poor words there", i % 2) for i in range(300)] + [("n", None, 1), ("m", "x", None)]
    rows = spark.createDataFrame(data, "key string, text string, label int")
    found = {r.student: r for r in training.hashed_students(rows, seeds=2).collect()}
    assert set(found) == {"seed0", "seed1", "mean"} and all(r.accuracy == 1.0 and r.majority < r.n for r in found.values())
    assert training.hashed_students(rows.filter("label = 1"), seeds=2).count() == 0 and training.hashed_students(rows.limit(0), seeds=1).count() == 0


def test_costs(spark):
    from doccurate.operators import costs

    build = lambda: spark.range(1000).groupBy((F.col("id") % 10).alias("k")).count()
    name, n, took, speed, shuffled, spilled = costs.measured(spark, "x", build, 1000)
    assert (name, n, spilled) == ("x", 10, 0) and took > 0 and speed > 10 and shuffled > 0
    assert costs.as_table(spark, [costs.measured(spark, "none", lambda: spark.range(0))]).first().out_rows == 0


def test_gram_join_writes_no_gram_texts(spark):
    """What is written grows as the texts, not as their grams' texts; prefixes of hashes give the pairs, a null id yields to one."""
    rng = random.Random(8)
    base = [" ".join(f"w{rng.randint(0, 10**6)}" for _ in range(300)) for _ in range(20)]
    near = [b.rsplit(" ", 20)[0] + " end" for b in base]
    docs = spark.createDataFrame([(k, t) for k, t in enumerate(base + near)] + [(None, base[0]), (90, near[1]), (91, None), (92, "too short")], "doc_id long, text string").repartition(3)
    written = []

    def keep(df):
        rows = spark.createDataFrame(df.collect(), df.schema)
        written.append(sum(len(str(x)) for r in rows.collect() for c, x in r.asDict().items() if c not in ("row", "id", "fp")))
        return rows

    found = {(r.id, r.other): r.similarity for r in dedup.gram_join_pairs(docs, "doc_id", keep=keep).collect()}
    assert set(found) == {(k, k + 20) for k in range(20)} and set(found.values()) == {round(276 / 297, 6)}
    assert sum(written) < 2 * sum(len(t) for t in base + near)


def test_clusters_read_written_pairs(spark, tmp_path, monkeypatch):
    """Pairs are worked out once: clusters reads them in both directions from what is written."""
    import __spark_entry__

    docs = [(k, " ".join(f"w{i}" for i in range(k, k + 40))) for k in (0, 1, 100)]
    spark.createDataFrame(docs, "doc_id long, text string").selectExpr("doc_id", "text", "'en' as lang", "'s' as source", "0L as n_chars").write.parquet(f"{tmp_path}/documents.parquet")
    plans, clusters = [], dedup.clusters
    monkeypatch.setattr(dedup, "clusters", lambda pairs, keep: plans.append(pairs._jdf.queryExecution().optimizedPlan().toString()) or clusters(pairs, keep))
    assert {(r.node, r.root) for r in __spark_entry__.queries()["w07_clusters"](spark, str(tmp_path)).collect()} == {(0, 0), (1, 0)}
    assert "Relation" in plans[0] and "Join" not in plans[0] and "MapInArrow" not in plans[0]


def test_rounds_judge_each_pair_alone_once(spark, monkeypatch):
    """Language, overlap and length are judged in the first round only; the pairs left are those of whole cascades in each round."""
    from doccurate.plans import workloads

    folder, calls, detected = "/root/testdata/sf0.001", [], filters.with_language
    monkeypatch.setattr(filters, "with_language", lambda *a: calls.append(1) or detected(*a))
    found = {r.split: r.pairs for r in workloads.w13_rounds(spark, folder).collect()}
    assert len(calls) == 1
    keep = workloads.keeper(spark)
    pairs = keep(workloads.parsed(spark, folder).filter("well_formed").select("qa_id", "image_id", "view", "slot", "lang", "text", "question", "answer"))
    prof = keep(workloads.profiles(spark, folder))

    def step(df):
        kept = keep(filters.run_cascade(filters.with_language(df, prof, workloads.LANGS), workloads.TARGET).filter("kept").select(*df.columns))
        own = kept.groupBy("image_id").agg(F.min("text").alias("page"))
        return kept.join(own.groupBy(dedup.fp_exact(F.col("page"))).agg(F.min("image_id").alias("image_id")), "image_id", "left_semi").select(*df.columns)

    whole = qa.split_by_image(filters.rounds(pairs, step, keep)).groupBy("split").agg(F.count("*").alias("pairs"))
    assert found and found == {r.split: r.pairs for r in whole.collect()}
