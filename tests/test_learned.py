"""Learned results of the experiments, the distributed solver against the array one, restarts, ranks, measures."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from partnet import catalog, workloads
from partnet.operators import anneal, apply, compact, info
from partnet.operators.joint import build_joint, ranked
from partnet.operators.model import log_partition, marginal_of
from partnet.operators.solve import StopRule, run_sweeps, start_table
from partnet.plans import presets
from partnet.plans.graph import TradeOff
from partnet.queries import text_queries as tq
from partnet.sources import tables
from partnet.streaming import joint_stream as streams

SF = "/root/testdata/sf0.01"


@pytest.fixture(scope="module")
def text_joint(spark):
    return tables.cut_lineage(tq.text_cells(spark, SF).select("w", "c", "p"))


def dense(rows, x, y):
    found = rows.select(x, y, "p").collect()
    xs, ys = sorted({r[x] for r in found}), sorted({r[y] for r in found})
    p = np.zeros((len(xs), len(ys)))
    for r in found:
        p[xs.index(r[x]), ys.index(r[y])] = r["p"]
    return xs, ys, p


def test_split_sequence_of_the_known_groups(spark):
    rows = {(r.step, r["var"]): (r.k, r.relevance_frac, r.split) for r in catalog.queries()["anneal_planted_curve"](spark, SF).collect()}
    assert [(rows[s, "TA"][0], rows[s, "TB"][0]) for s in range(2)] == [(2, 2), (4, 4)]
    assert rows[1, "TA"][1] > 0.95 and rows[1, "TB"][1] > 0.85 and rows[3, "TA"][1] - rows[1, "TA"][1] < 0.02


def test_clusters_found_order_the_matrix_like_the_known_ones(spark):
    found, known = (catalog.queries()[x](spark, SF) for x in ("permuted_found", "permuted_planted"))
    assert sorted(r.p for r in found.collect()) == sorted(r.p for r in known.collect())
    cells = tq.known(spark, SF)
    model = tq.model_of(workloads.anneal_tables(cells.select("a", "b", "p"), tq.PAIR, {"fixed": tq.PLANTED_FIXED}), cells, tq.PAIR)
    labels = apply.assign(model.parts["TA"], ["a"]).withColumn("lang", F.split("a", "/")[0])
    assert apply.agreement(labels, "lang").first()["purity"] >= 0.95


def test_text_hierarchy(spark, text_joint):
    model = tq.model_of(workloads.anneal_tables(text_joint, tq.WORDS, {"fixed": tq.TEXT_FIXED}), text_joint, tq.WORDS)
    labels = apply.assign(model.parts["TB"], ["c"]).withColumn("lang", F.split("c", "/")[0])
    assert apply.agreement(labels, "lang").first()["purity"] >= 0.95
    link = apply.cluster_link(model, "TB", "TA").where("is_best").collect()
    assert len(link) == 8 and np.mean([r.p_cond for r in link]) > 0.5
    assert apply.profile(model, "TA", "c").groupBy("TA").agg(F.sum("p_cond").alias("s")).agg(F.min("s")).first()[0] == pytest.approx(1)
    assert apply.hardness(model.parts["TB"]).first()["effective"] < 1.2
    curve = workloads.anneal_curves(text_joint, tq.WORDS, {"fixed": tq.TEXT_FIXED}).where("var = 'TA'").orderBy("step").collect()
    assert [r.k for r in curve] == [1, 2, 4, 8] and curve[-1].relevance_frac > 0.8
    assert all(a.relevance <= b.relevance + 1e-9 and b.relevance <= b.compression + 1e-9 for a, b in zip(curve, curve[1:]))


def test_parallel_curves(spark, text_joint):
    """Together the two systems keep far more than either; no curve passes the joint's information or its own compression."""
    rows = workloads.anneal_curves(text_joint, tq.PARALLEL, {"fixed": tq.PARALLEL_FIXED}).orderBy("step").collect()
    both = [r for r in rows if r["var"] == "T1,T2"]
    assert [r.k for r in both] == [4, 16, 16] and both[1].relevance_frac > 0.8
    for r in both:
        one, two = (x for x in rows if x.step == r.step and x["var"] in ("T1", "T2"))
        assert max(one.relevance, two.relevance) < r.relevance <= min(r.compression, r.relevance / r.relevance_frac) + 1e-9
        assert r.relevance > 1.2 * max(one.relevance, two.relevance)
    assert all(a.relevance_frac <= b.relevance_frac + 1e-3 for a, b in zip(both, both[1:]))


def test_distributed_sweeps_equal_the_array_ones_on_the_text_joint(spark, text_joint):
    trade, spec = TradeOff.gamma(60.0), presets.symmetric("w", "c")
    model = run_sweeps(text_joint, spec, {"TA": 5, "TB": 4}, trade, 1, kind="lcg")
    ws, cs, p = dense(text_joint, "w", "c")
    m = compact.Dense(spec, p, {})
    for j, (t, k) in enumerate((("TA", 5), ("TB", 4))):
        raw = 0.6 + compact.lcg(np.arange(p.shape[j])[:, None], np.arange(k)[None, :], j)
        m.q[t] = raw / raw.sum(axis=1, keepdims=True)
    for t in ("TA", "TB"):
        m.q[t] = compact.update(m, t, trade)
    for t, v, values in (("TA", "w", ws), ("TB", "c", cs)):
        got = {r[v]: r["q"] for r in model.parts[t].collect()}
        assert np.abs(np.array([got[x] for x in values]) - m.q[t]).max() < 1e-8
    logs = {r["w"]: r["log_z"] for r in log_partition(model, "TA", trade).collect()}
    assert np.abs(np.array([logs[x] for x in ws]) - compact.log_partition(m, "TA", trade)).max() < 1e-7
    exponent_free = log_partition(model, "TA", TradeOff.gamma(0.0)).agg(F.max(F.abs("log_z"))).first()[0]
    assert exponent_free < 1e-9


def test_anneal_goes_on_from_its_folder_and_stops_at_the_floor(spark, tmp_path):
    p = np.array([[0.2, 0.01, 0.01], [0.2, 0.01, 0.01], [0.01, 0.2, 0.02], [0.01, 0.02, 0.2], [0.02, 0.04, 0.04]])
    cells = spark.createDataFrame([(i, j, float(p[i, j] / p.sum())) for i in range(5) for j in range(3)], "A int, B int, p double")
    spec, weights, stop = presets.single("A", "B"), [2.0, 6.0, 9.0], StopRule(0.0, 6)
    whole = anneal.anneal(cells, spec, weights, max_k=4, stop=stop)
    folder = str(tmp_path / "state")
    anneal.anneal(cells, spec, weights[:2], max_k=4, stop=stop, folder=folder)
    resumed = anneal.anneal(cells, spec, weights, max_k=4, stop=stop, folder=folder)
    assert [r[:4] for r in resumed.curve] == [r[:4] for r in whole.curve] and [x[1] for x in resumed.tree] == [x[1] for x in whole.tree]
    assert np.allclose([r[5] for r in resumed.curve], [r[5] for r in whole.curve])
    again = anneal.anneal(cells, spec, weights, max_k=4, stop=stop, folder=folder)
    assert again.curve == resumed.curve
    floor = anneal.anneal(cells, spec, [6.0, 6.6, 7.2, 8.0], max_k=8, stop=stop, stop_gain=10.0)
    assert len(floor.curve) < 4


def test_schedules(spark):
    s = compact.Schedule.geometric(1.0, 2.0, 8.0)
    assert s.values == (1.0, 2.0, 4.0, 8.0)
    assert len(s.refined([3.0], 4).values) == 7 and s.refined([3.0], 4).values[:2] == (1.0, 2.0)
    p = dense(workloads.planted_joint(spark), "a", "b")[2]
    coarse = compact.Schedule((2.0, 4.0))
    first = lambda schedule: next(r[1] for r in compact.anneal(presets.single("a", "b"), p, schedule, noise="spectral", max_k=2).curve if r[3] > 1)
    assert first(coarse) == 4.0 and 2.85 < first(coarse.refined([first(coarse)], 32)) < 3.0


def test_ranks_without_one_task(spark):
    rng = np.random.default_rng(0)
    values = rng.permutation(500).tolist()
    rows = spark.createDataFrame([(v, float(v % 7)) for v in values], "v long, x double").repartition(7)
    got = {r.v: (r.i, r.reached) for r in ranked(rows, [F.desc("v")], "i", "x").collect()}
    total = np.cumsum([v % 7 for v in range(499, -1, -1)])
    assert all(got[v] == (499 - v, pytest.approx(total[499 - v])) for v in range(500))
    assert ranked(rows.limit(0), ["v"]).count() == 0
    k3 = start_table(spark.createDataFrame([(v, 1.0) for v in range(9)], "u int, p double"), ["u"], 3)
    assert all(r.q[r.u % 3] == 0.7 for r in k3.collect())


def test_measures_on_the_target_network():
    """Under the projection, hard clusters give the same information whichever pair is measured; under the source model they differ."""
    p = np.random.default_rng(6).dirichlet(np.ones(24)).reshape(6, 4)
    m = compact.Dense(presets.symmetric("A", "B"), p, {"TA": np.eye(3)[np.arange(6) % 3], "TB": np.eye(2)[np.arange(4) % 2]})
    between = compact.info(m, ("TA",), ("TB",))
    assert compact.target_info(m, "TA", "TB") == pytest.approx(between)
    assert compact.target_info(m, "TA", "B") == pytest.approx(between) and compact.target_info(m, "TB", "A") == pytest.approx(between)
    assert compact.info(m, ("TA",), ("B",)) > between + 1e-6


def test_bounds_of_one_task(spark, monkeypatch):
    cells = spark.createDataFrame([(i, i, 0.01) for i in range(100)], "a int, b int, p double")
    monkeypatch.setattr(workloads, "MOST_CELLS", 9_999)
    with pytest.raises(ValueError, match="10000 cells"):
        workloads.anneal_curves(cells, presets.single("a", "b"), {"x": {}})


def test_observed_gap(spark):
    x, y, z = np.array([0.3, 0.7]), np.array([[0.5, 0.5], [0.1, 0.9]]), np.array([[0.2, 0.8], [0.6, 0.4]])
    p = x[:, None, None] * y[:, :, None] * z[None, :, :]
    rows = spark.createDataFrame([(*map(int, at), float(p[at])) for at in np.ndindex(p.shape)], "X int, Y int, Z int, p double")
    chain = presets.custom(("X", "Y", "Z"), "X->Y; Y->Z; Z->T", "T->X")
    assert info.observed_gap(rows, chain).first()["consistent"]
    wrong = presets.custom(("X", "Y", "Z"), "X->Z; Y->T", "T->X")
    assert not info.observed_gap(rows, wrong).first()["consistent"]
    assert info.observed_gap(rows, presets.custom(("X", "Y", "Z"), "Y->T", "T->X")).first()["gap"] == 0


def test_k_means_against_plain_rounds(spark):
    cells = workloads.planted_joint(spark).select("a", "b", "p")
    xs, _, p = dense(cells, "a", "b")
    x = p / p.sum(axis=1, keepdims=True)
    labels = np.arange(len(xs)) % 5
    for _ in range(8):
        held = [t for t in range(5) if (labels == t).any()]
        means = np.stack([x[labels == t].mean(axis=0) for t in held])
        labels = np.array(held)[np.round((means**2).sum(axis=1)[None, :] - 2 * x @ means.T, 12).argmin(axis=1)]
    assert {r.a: r.t for r in workloads.kmeans_profiles(cells, "a", "b", 5).collect()} == dict(zip(xs, labels.tolist(), strict=True))


@pytest.mark.parametrize("fmt", ["json", "orc", "parquet", "csv"])
def test_cells_in_every_format(spark, tmp_path, fmt):
    cells = spark.createDataFrame([("a", "x", 1.0), ("b", "y", 3.0), ("a", "y", 2.0)], "a string, b string, n double")
    writer = cells.write.format(fmt)
    (writer.option("header", "true") if fmt == "csv" else writer).save(str(tmp_path / "cells"))
    assert sorted(map(tuple, tables.read_cells(spark, str(tmp_path / "cells"), ["a", "b"], fmt).collect())) == sorted(map(tuple, cells.collect()))


def test_written_tables_go_when_dropped(spark):
    import os

    store = tables.Written(spark, "loop")
    one, two = store.keep(spark.range(3)), store.keep(spark.range(4))
    store.drop(one)
    left = os.listdir(store.folder.removeprefix("file:"))
    assert left == ["1"] and two.count() == 4
    store.drop(spark.range(3))


def test_rate_stream_and_stream_that_is_stopped(spark, sf, tmp_path):
    events = streams.event_stream(spark, sf)
    cells = streams.windowed_joint(events, ["event_type"], "1 day")
    folder = str(tmp_path / "drain")
    first = {tuple(r) for r in streams.drain(cells, folder=folder).collect()}
    assert first == {tuple(r) for r in streams.drain(streams.windowed_joint(streams.event_stream(spark, sf), ["event_type"], "1 day"), folder=folder).collect()}
    assert spark.readStream.format("rate").load().isStreaming


def test_joint_with_mass_kept_by_marginals(spark):
    cells = build_joint(spark.createDataFrame([("a", "x"), ("b", "y"), ("a", "y")], "a string, b string"), ["a", "b"])
    model = run_sweeps(cells, presets.symmetric("a", "b"), {"TA": 2, "TB": 2}, TradeOff.gamma(2.0), 1)
    assert marginal_of(model, ("TA", "TB")).agg(F.sum("p")).first()[0] == pytest.approx(1)
