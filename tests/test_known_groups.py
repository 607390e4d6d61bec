"""The matrix of known groups comes from documents, and trade-off weights from line items."""

import pytest

from partnet import catalog
from partnet.queries import text_queries as tq


def small(spark, path):
    texts = [("en", "s0", "apple apple pear dog"), ("en", "s1", "apple pear haus"), ("de", "s0", "haus haus baum apple"), (None, "s0", "apple"), ("fr", None, "chien")]
    rows = [(i, t, lang, source, len(t)) for i, (lang, source, t) in enumerate(texts)]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{path}/documents.parquet")
    return str(path)


def test_known_groups_are_counted_from_documents(spark, tmp_path):
    d = small(spark, tmp_path)
    got = {(r.a, r.b): (r.home, r.n) for r in tq.known(spark, d).collect()}
    assert got["en/s0", "apple"] == ("en", 2) and got["de/s0", "apple"] == ("en", 1) and got["en/s1", "haus"] == ("de", 1) and len(got) == 9
    assert {(r.a, r.b) for r in catalog.queries()["planted_matrix"](spark, d).collect()} == set(got)
    blocks = {(r.ta, r.tb): r.p for r in catalog.queries()["block_joint_planted"](spark, d).collect()}
    assert blocks == {(0, 0): pytest.approx(3 / 11), (0, 1): pytest.approx(1 / 11), (1, 0): pytest.approx(1 / 11), (1, 1): pytest.approx(6 / 11)}


@pytest.mark.parametrize("name", ["permuted_planted", "permuted_found", "anneal_planted_tree", "anneal_planted_curve", "anneal_planted_single", "ablation_grid"])
def test_queries_follow_the_documents(spark, tmp_path, name):
    d = small(spark, tmp_path)
    rows = lambda at: sorted(map(tuple, catalog.queries()[name](spark, at).collect()), key=str)
    assert rows(d) != rows("/root/testdata/sf0.001")


def test_weights_come_from_line_items(spark, tmp_path):
    spark.createDataFrame([(0.0,), (3.0,), (3.0,), (99.0,), (None,)], "l_quantity double").write.parquet(f"{tmp_path}/lineitem.parquet")
    assert {tuple(r) for r in catalog.queries()["beta_gamma_grid"](spark, str(tmp_path)).collect()} == {(0.0, 0.0, 0.0), (3.0, 0.75, 3.0), (99.0, 0.99, 99.0)}
