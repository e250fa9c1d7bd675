"""The pipeline's stages keep clean documents, take decisions, and survive hard rows."""

import random
import uuid

import pytest

pytest.importorskip("public_tokenizers")
import corpus_pipeline  # noqa: E402


def test_stages(spark, tmp_path):
    rng = random.Random(6)
    say = lambda n: " ".join(f"w{rng.randint(0, 5000)}" for _ in range(n))
    passage = say(30)
    rows = [(k, say(120) + (" idiot moron" if k % 4 == 0 else ""), "en", "s", 0) for k in range(400)]
    rows += [(900, rows[1][1], "en", "s", 0), (901, rows[2][1].replace("w1", "w2", 1), "en", "s", 0), (902, f"{say(50)} {passage} {say(50)}", "en", "s", 0), (903, f"{say(60)} write to a.b@c.de", "en", "s", 0), (904, None, None, None, None), (905, "", "en", "s", 0)]
    folder = f"{tmp_path}/{uuid.uuid4().hex}"
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{folder}/documents.parquet")
    spark.createDataFrame([(k, int(k % 4 == 0)) for k in range(400)], "doc_id long, toxic int").write.parquet(f"{folder}/labels.parquet")
    spark.createDataFrame([(1, passage)], "item_id long, text string").write.parquet(f"{folder}/benchmark.parquet")
    docs, after = spark.read.parquet(f"{folder}/documents.parquet"), {}
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, docs, folder)
        if name != "packing":
            assert out.columns == docs.columns
        out.write.parquet(f"{folder}/{name}")
        docs = spark.read.parquet(f"{folder}/{name}")
        after[name] = {r.doc_id: r for r in docs.collect()}
    assert set(after["toxicity"]) == {k for k, *_ in rows} - set(range(0, 400, 4))
    assert 900 not in after["near_duplicates"] and 901 not in after["near_duplicates"] and len(after["near_duplicates"]) == len(after["toxicity"]) - 3
    assert passage[:50] not in after["decontamination"][902].text and after["decontamination"][902].n_chars == len(after["decontamination"][902].text)
    assert "[EMAIL]" in after["personal_data"][903].text
    assert set(after["packing"]) == set(after["personal_data"])


HARD = [
    [],
    [(None, None, None, None, None, 1.0, 2, "a")],
    [(1, None, "en", "s", 0, 1.0, 2, "a"), (1, None, "en", "s", 0, 1.0, 2, "a"), (None, "", "en", "s", 0, None, None, None), (2, "word " * 30_000, None, None, None, 0.5, 3, "b"), (3, "a tie of words here", "en", "s", 0, 0.0, 0, ""), (4, "a tie of words here", "en", "s", 0, 0.0, 0, "")],
]


@pytest.mark.parametrize("which", range(len(HARD)))
def test_stages_on_hard_tables(spark, tmp_path, which):
    folder = str(tmp_path)
    spark.createDataFrame(HARD[which], "doc_id long, text string, lang string, source string, n_chars long, score double, _row int, _toxic string").write.parquet(f"{folder}/documents.parquet")
    spark.createDataFrame([], "doc_id long, quality int, toxic int").write.parquet(f"{folder}/labels.parquet")
    spark.createDataFrame([(1, None), (2, "")], "item_id long, text string").write.parquet(f"{folder}/benchmark.parquet")
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, docs, folder)
        assert name == "packing" or out.columns == docs.columns
        out.write.parquet(f"{folder}/{name}")
        docs = spark.read.parquet(f"{folder}/{name}")
    pieces = sorted((-1 if r.doc_id is None else r.doc_id, r.piece) for r in docs.collect())
    if which < 2:
        assert pieces == [(-1, 0)][: len(HARD[which])]
    else:  # of null and empty texts the least id stays, of the tie too
        assert {k for k, _ in pieces} == {1, 2, 3} and len(pieces) > 10
