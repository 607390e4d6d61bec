import json

import numpy as np
import pandas as pd
import pytest
from hypothesis import HealthCheck, given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from partnet import workloads
from partnet.functions import sql as sql_functions
from partnet.functions.udaf import array_sum_agg, entropy_agg
from partnet.ml import BottleneckEstimator, BottleneckModel
from partnet.operators import agglomerate, anneal, apply, compact, info, text
from partnet.operators.joint import build_joint, encode
from partnet.operators.model import lagrangian, marginal_of, update_step
from partnet.operators.solve import StopRule, bind, run_sweeps, solve
from partnet.plans import presets
from partnet.plans.graph import Dag, TradeOff
from partnet.sources import tables
from partnet.streaming import joint_stream as streams


def dense_joint(spark, p: np.ndarray, names):
    rows = [(*[int(x) for x in at], float(p[at])) for at in np.ndindex(p.shape) if p[at] > 0]
    return spark.createDataFrame(rows, ", ".join(f"{n} int" for n in names) + ", n double").withColumn("p", F.col("n"))


def table_of(part, source, k, n):
    out = np.zeros((n, k))
    for r in part.collect():
        out[r[source]] = r["q"]
    return out


@pytest.mark.parametrize("spec,form", [(presets.parallel("A", "B", objective="gamma"), "literal"), (presets.symmetric("A", "B"), "collapsed"), (presets.symmetric("A", "B", "b"), "literal"), (presets.parallel("A", "B"), None)], ids=["p6", "p8", "p9", "p5"])
def test_distributed_equals_compact(spark, spec, form):
    p = np.random.default_rng(3).dirichlet(np.ones(20)).reshape(5, 4)
    sizes = {t: 2 + i for i, t in enumerate(spec.clusters)}
    trade = TradeOff(spec.objective, 3.0)
    model = run_sweeps(dense_joint(spark, p, ["A", "B"]), spec, sizes, trade, 2, form=form)
    axis = {"A": 5, "B": 4}
    m = compact.Dense(spec, p, {})
    for t in spec.clusters:
        n, k = axis[spec.sources(t)[0]], sizes[t]
        m.q[t] = np.where(np.arange(n)[:, None] % k == np.arange(k)[None, :], 0.7, 0.3 / (k - 1))
    for _ in range(2):
        for t in spec.clusters:
            m.q[t] = compact.update(m, t, trade, form)
    for t in spec.clusters:
        source = spec.sources(t)[0]
        assert np.abs(table_of(model.parts[t], source, sizes[t], axis[source]) - m.q[t]).max() < 1e-8
    row = lagrangian(model, trade).first()
    assert row["objective"] == pytest.approx(compact.objective(m, trade), abs=1e-8)


@settings(max_examples=5, deadline=None, suppress_health_check=[HealthCheck.function_scoped_fixture])
@given(st.lists(st.floats(0.01, 1), min_size=12, max_size=12))
def test_identities_on_random_joints(spark, weights):
    p = np.array(weights).reshape(3, 2, 2)
    cells = dense_joint(spark, p / p.sum(), ["X", "Y", "Z"])
    dag = Dag.parse("X->Y; Y->Z")
    gaps = [info.projection_gap(cells, dag, f).first()["gap"] for f in ("difference", "markov", "direct")]
    assert max(gaps) - min(gaps) < 1e-9 and gaps[0] > -1e-12


def test_factored_joint_is_consistent(spark):
    x, y = np.array([0.2, 0.8]), np.array([[0.5, 0.5], [0.1, 0.9]])
    z = np.array([[0.3, 0.7], [0.6, 0.4]])
    p = x[:, None, None] * y[:, :, None] * z[None, :, :]
    row = info.is_consistent(dense_joint(spark, p, ["X", "Y", "Z"]), Dag.parse("X->Y; Y->Z")).first()
    assert row["consistent"] and abs(row["gap"]) < 1e-12


def test_joint_null_policies_weights_and_edge_cases(spark):
    rows = spark.createDataFrame([("a", "x", 1.0), ("a", None, 2.0), (None, "y", 4.0), ("b", "x", 0.0)], "a string, b string, w double")
    assert {(r.a, r.b): r.n for r in build_joint(rows, ["a", "b"]).collect()} == {("a", "x"): 1.0, ("b", "x"): 1.0}
    levelled = {(r.a, r.b): r.p for r in build_joint(rows, ["a", "b"], "w", "level").collect()}
    assert levelled == pytest.approx({("a", "x"): 1 / 7, ("a", "(null)"): 2 / 7, ("(null)", "y"): 4 / 7})
    scaled = {(r.a, r.b): r.p for r in build_joint(rows, ["a", "b"], F.col("w") * 9, "level").collect()}
    assert scaled == pytest.approx(levelled)
    empty = build_joint(rows.limit(0), ["a", "b"])
    assert empty.count() == 0
    coded, names = encode(build_joint(rows, ["a", "b"]), ["a", "b"])
    assert {r.a for r in coded.collect()} == {0, 1} and names.count() == 3
    with pytest.raises(ValueError):
        build_joint(rows, ["a"], nulls="keep")


def test_kl_is_infinite_without_support(spark):
    p = spark.createDataFrame([("x", 0.5), ("y", 0.5)], "v string, p double")
    q = spark.createDataFrame([("x", 1.0)], "v string, p double")
    assert info.kl_divergence(p, q, ["v"]).first()["kl"] == float("inf")
    assert info.kl_divergence(q, p, ["v"]).first()["kl"] == pytest.approx(1.0)


def test_rows_sum_to_one_and_empty_clusters(spark):
    cells = dense_joint(spark, np.array([[0.5, 0.0], [0.0, 0.5]]), ["A", "B"])
    model = run_sweeps(cells, presets.single("A", "B"), {"T": 4}, TradeOff.beta(50.0), 3)
    for r in model.parts["T"].collect():
        assert sum(r["q"]) == pytest.approx(1) and not any(np.isnan(r["q"]))


def test_stop_rule_sync_guard_and_hard_limit(spark):
    p = np.random.default_rng(0).dirichlet(np.ones(12) * 0.5).reshape(4, 3)
    for schedule in ("async", "sync"):
        found = solve(bind(dense_joint(spark, p, ["A", "B"]), presets.parallel("A", "B"), {"T1": 2, "T2": 2}), TradeOff.beta(3.0), schedule, StopRule(1e-2, 8), final_hard=schedule == "async")
        assert found.sweeps <= 8 and found.trace
        if schedule == "async":
            assert all(sorted(r["q"]) == [0.0, 1.0] for r in found.model.parts["T1"].collect())


def test_distributed_anneal_splits(spark):
    p = np.array([[0.24, 0.01], [0.24, 0.01], [0.01, 0.24], [0.01, 0.24]])
    result = anneal.anneal(dense_joint(spark, p, ["A", "B"]), presets.single("A", "B"), [0.5, 4.0], max_k=2, stop=StopRule(1e-4, 10))
    assert [r[3] for r in result.curve] == [1, 2]
    assert [x[1] for x in result.tree] == ["0", "0.0", "0.1"]


def test_agglomerate_matches_brute_force(spark):
    p = np.random.default_rng(8).dirichlet(np.ones(15)).reshape(5, 3)
    steps = agglomerate.agglomerate(dense_joint(spark, p, ["A", "B"]), "A", "B", 2)
    groups = {str(i): p[i] for i in range(5)}
    mi = lambda g: sum((x * np.log2(x / x.sum() / sum(g.values()) * 1)).sum() for x in g.values())
    for _, kept, merged, loss in steps:
        costs = {}
        for i in groups:
            for j in groups:
                if i < j:
                    trial = {k: v for k, v in groups.items() if k not in (i, j)} | {i: groups[i] + groups[j]}
                    costs[i, j] = mi(groups) - mi(trial)
        assert (kept, merged) == min(costs, key=costs.get) and loss == pytest.approx(costs[kept, merged], abs=1e-9)
        groups[kept] = groups[kept] + groups.pop(merged)


def test_apply_operators(spark):
    part = spark.createDataFrame([("u", [0.5, 0.5]), ("v", [0.05, 0.95])], "a string, q array<double>")
    assert {r.a: r.t for r in apply.assign(part, ["a"]).collect()} == {"u": 0, "v": 1}
    assert {r.a: [x.t for x in r.clusters] for r in apply.memberships(part, ["a"], 0.1).collect()} == {"u": [0, 1], "v": [1]}
    assert {r.a: dict(r.clusters) for r in apply.membership_map(part, ["a"], 0.1).collect()}["v"] == {1: 0.95}
    hard = apply.hardness(part).first()
    assert hard["mean_max"] == pytest.approx(0.725)
    labels = spark.createDataFrame([(0, "x"), (0, "x"), (1, "y"), (1, "y")], "t int, g string")
    assert apply.agreement(labels, "g").first().asDict() == pytest.approx({"purity": 1, "nmi": 1, "adjusted_rand": 1})
    facts = spark.createDataFrame([("u", 1), ("w", 2)], "a string, x int")
    assert {r.a: r.t for r in apply.label_rows(facts, part, ["a"]).collect()} == {"u": 0, "w": None}


def test_score_new_reproduces_a_fitted_row(spark):
    p = np.array([[0.2, 0.05], [0.05, 0.2], [0.2, 0.3]])
    cells = dense_joint(spark, p, ["A", "B"])
    model = run_sweeps(cells, presets.single("A", "B"), {"T": 2}, TradeOff.beta(5.0), 3)
    again = apply.score_new(model, "T", "B", cells.select("A", "B", "p"), 5.0)
    assert np.abs(table_of(again, "A", 2, 3) - table_of(update_step(model, "T", TradeOff.beta(5.0)), "A", 2, 3)).max() < 1e-9


def test_permuted_order_is_smoother(spark):
    cells = workloads.planted_joint(spark).select("a", "b", "p")
    rows = cells.select("a").distinct().withColumn("t", (F.col("a") % 6).cast("int"))
    cols = cells.select("b").distinct().withColumn("t", (F.col("b") % 3).cast("int"))
    flat = lambda df, v: df.select(v, F.lit(0).alias("t"))
    given_order = apply.neighbour_variation(apply.permuted(cells, flat(rows, "a"), flat(cols, "b"), "a", "b")).first()["variation"]
    assert apply.neighbour_variation(apply.permuted(cells, rows, cols, "a", "b")).first()["variation"] < 0.5 * given_order


def test_text_rules(spark):
    df = spark.createDataFrame([(1, "The (Cat) sat.\nShared line"), (2, "x1 cat!\nShared line"), (3, None), (4, "")], "doc_id long, text string")
    found = sorted((r.doc_id, r.w) for r in text.tokens(df, "doc_id", "text").collect())
    assert found == [(1, "cat"), (1, "line"), (1, "sat"), (1, "shared"), (2, "cat"), (2, "line"), (2, "shared")]
    assert [r.line for r in text.boilerplate_lines(df, "doc_id", "text", 2).collect()] == ["Shared line"]
    assert {r.w for r in text.tokens(df, "doc_id", "text", boilerplate_min_docs=2).collect()} == {"cat", "sat"}


def test_marginal_of_never_loses_mass(spark):
    p = np.random.default_rng(4).dirichlet(np.ones(24)).reshape(4, 3, 2)
    model = bind(dense_joint(spark, p, ["A", "B", "C"]), presets.custom(("A", "B", "C"), "A->T1; B->T1; C->T2", "T1->C; T2->A"), {"T1": 2, "T2": 2})
    for keep in (("T1",), ("T1", "T2"), ("A", "T2"), ("C", "T1", "T2")):
        assert marginal_of(model, keep).agg(F.sum("p")).first()[0] == pytest.approx(1)


def test_sources_and_models_round_trip(spark, tmp_path):
    cells = spark.createDataFrame([("a", "x", 1.0), ("b", "y", 3.0)], "a string, b string, n double")
    cells.coalesce(1).write.option("header", "true").csv(str(tmp_path / "cells"))
    assert tables.read_cells(spark, str(tmp_path / "cells"), ["a", "b"]).count() == 2
    rows = spark.createDataFrame([("a", "x")] * 4 + [("b", "y")] * 4 + [("c", "x")], "a string, b string")
    spec = presets.single("a", "b")
    fitted = BottleneckEstimator.of(spec, {"T": 2}, trade=20.0, maxIter=6).fit(rows)
    labels = {r["a"]: r["T_label"] for r in fitted.transform(rows.unionByName(spark.createDataFrame([("z", "x")], "a string, b string"))).collect()}
    assert labels["a"] == labels["c"] != labels["b"] and labels["z"] is None
    fitted.save(str(tmp_path / "model"))
    again = BottleneckModel.load(spark, str(tmp_path / "model"))
    assert {r["a"]: r["T_label"] for r in again.transform(rows).collect()} == {k: v for k, v in labels.items() if k != "z"}
    copies = tables.bucketed_copies(cells, ["a", "b"], "partnet_test_cells", 2)
    assert copies["a"].count() == 2


def test_sql_functions_and_aggregates(spark):
    sql_functions.register(spark)
    row = spark.sql("SELECT xlogx(0D) AS z, kl_term(0.5D, 0D) AS inf, js_term(0.5D, 0.5D) AS same").first()
    assert row["z"] == 0 and row["inf"] == float("inf") and row["same"] == 0
    assert [r.token for r in spark.sql("SELECT * FROM tokenize('The cat, 9 (sat)')").collect()] == ["the", "cat", "sat"]
    curve = spark.sql(f"SELECT * FROM bottleneck_curve('{json.dumps([[4, 1], [1, 4], [4, 1]])}', 20)").collect()
    assert curve[0]["k"] == 1 and curve[-1]["k"] >= 2
    df = spark.createDataFrame([("g", 1.0, [1.0, 2.0]), ("g", 1.0, [3.0, 4.0])], "k string, n double, v array<double>")
    assert df.groupBy("k").agg(entropy_agg("n").alias("h")).first()["h"] == pytest.approx(1.0)
    assert df.groupBy("k").agg(array_sum_agg("v").alias("s")).first()["s"] == [4.0, 6.0]


def test_stream_equals_batch(spark, sf):
    cells = streams.drain(streams.windowed_joint(streams.event_stream(spark, sf), ["event_type"], "1 day"))
    batch = spark.read.parquet(f"{sf}/events.parquet").groupBy(F.to_date("ts").alias("d"), "event_type").count()
    assert sorted((str(r.start.date()), r.event_type, r.n) for r in cells.collect()) == sorted((str(r.d), r.event_type, r["count"]) for r in batch.collect())


def test_resolve_each_batch_counts_once(spark):
    state: dict = {}
    step = streams.resolve_each_batch(lambda cells, previous: (previous or 0) + 1, state)
    batch = spark.createDataFrame([("a", 1), ("b", 2)], "v string, n long")
    step(batch, 0)
    step(batch, 0)
    step(batch, 1)
    assert state["model"] == 2 and {r.v: r.n for r in state["cells"].collect()} == {"a": 2, "b": 4}


def test_kmeans_baseline_and_null_panel(spark):
    cells = workloads.planted_joint(spark).select("a", "b", "p", "n")
    labels = workloads.kmeans_profiles(cells, "a", "b", 6)
    assert workloads.hard_relevance(cells, labels, "a", "b").first()["relevance_frac"] > 0.9
    flat = dense_joint(spark, np.full((4, 3), 1 / 12), ["A", "B"])
    curve = workloads.anneal_curves(flat, presets.single("A", "B"), {"null": {"first": 1.0, "rate": 2.0, "last": 64.0, "max_k": 4}}).toPandas()
    assert isinstance(curve, pd.DataFrame) and (curve.k == 1).all()


def test_entry_imports_without_the_corpus_part(monkeypatch):
    import builtins
    import importlib
    import sys

    import __spark_entry__

    real = builtins.__import__

    def gone(name, *a, **b):
        return real(name, *a, **b)

    monkeypatch.setitem(sys.modules, "partnet.llm", None)
    monkeypatch.setitem(sys.modules, "partnet.llm.queries", None)
    monkeypatch.setattr(builtins, "__import__", gone)
    assert importlib.reload(__spark_entry__)
    assert not [q for q in __spark_entry__.queries() if q.startswith("op")]
    monkeypatch.undo()
    importlib.reload(__spark_entry__)
