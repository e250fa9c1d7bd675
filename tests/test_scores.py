"""Queries on scores read the given tables."""

import pytest

from doccurate.plans import catalogue

ROWS = [(1, "a", "en", 1), (2, "a", "en", 1), (3, "a", "fr", 0), (4, "a", "fr", 1), (5, "a", "de", 1), (6, "b", "en", 1), (7, "b", "fr", 1), (8, "b", "de", 0), (9, "c", "en", 0), (10, "c", "fr", 0), (11, "c", "de", 0), (12, "d", "es", 1)]


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    out = str(tmp_path_factory.mktemp("scores"))
    spark.createDataFrame([(k, f"text {k}", x, s, 6) for k, s, x, _ in ROWS], "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{out}/documents.parquet")
    spark.createDataFrame([(k, q, 0) for k, *_, q in ROWS] + [(1, 1, 0), (99, 1, 0)], "doc_id long, quality int, toxic int").write.parquet(f"{out}/labels.parquet")
    return out


@pytest.mark.parametrize("name", ["w16_gap", "w16_human_gap", "w17_bootstrap", "w17_leave_one_out", "w17_pearson", "w17_spearman", "w21_tuned_deltas"])
def test_scores(spark, folder, name):
    rows = sorted(tuple(r) for r in catalogue.QUERIES[name](spark, folder).collect())
    expected = {
        "w16_gap": [("a", "de", 0.0, 0.0), ("a", "fr", 0.5, 0.5), ("b", "de", 1.0, 1.0), ("b", "fr", 0.0, 0.0), ("c", "de", 0.0, None), ("c", "fr", 0.0, None)],
        "w16_human_gap": [("a", 1.0, 0.0564, True), ("b", 1.0, 0.0564, True), ("c", 0.0, -0.9436, False)],
        "w17_leave_one_out": [("a", None), ("b", 1.0), ("c", -1.0)], "w17_pearson": [(3, 0.0, 1.0)], "w17_spearman": [(3, 0.0)],
        "w21_tuned_deltas": [(0, "base", 0.75, 0.0), (1, "add_de", 4 / 7, -0.178571), (2, "add_es", 0.625, -0.125), (3, "add_fr", 7 / 12, -0.166667)],
    }
    assert len(rows) == 1 if name == "w17_bootstrap" else rows[1:] == expected[name][1:] if name == "w17_leave_one_out" else rows == expected[name]
