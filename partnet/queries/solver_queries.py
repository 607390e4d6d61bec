"""Fixed-point sweeps of every specification, annealing parts, hard limit, traces, against unrolled SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from partnet.functions.expr import rounded
from partnet.operators import agglomerate as bottom_up
from partnet.operators import anneal
from partnet.operators.joint import build_joint, marginal
from partnet.operators.info import observed_gap
from partnet.operators.model import Model, distortion, harden, lagrangian, pair_info, update_step
from partnet.operators.solve import StopRule, bind, long_table, run_sweeps, solve, start_table, sync_sweeps
from partnet.plans import presets
from partnet.plans.graph import BottleneckSpec, TradeOff, update_rule
from partnet.plans.sweep_sql import AnnealScript, SweepScript
from partnet.queries.info_queries import LINE_CELLS, LINES, STAR_FROM, STAR_WEIGHT, TURN_ROLE, cells_sql, h_sql, star, turn_role
from partnet.sources.tables import cut_lineage, read_table

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):
    def keep(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLES[f.__name__] = sql
        return f

    return keep


def tables(model: Model) -> DataFrame:
    """var, u, t, q of every cluster variable."""
    out = None
    for t in model.spec.clusters:
        sources = list(model.spec.sources(t))
        u = F.concat_ws("|", *[F.col(v).cast("string") for v in sources])
        one = long_table(model.parts[t], sources).select(F.lit(t).alias("var"), u.alias("u"), F.col("t").cast("long").alias("t"), rounded("q").alias("q"))
        out = one if out is None else out.unionByName(one)
    return out


def registered(name: str, joint, joint_sql: str, spec: BottleneckSpec, sizes: dict[str, int], trade: TradeOff, sweeps: int, schedule: str = "async", form: str | None = None) -> None:
    """A query of a fixed number of sweeps from the rank start, and the same sweeps in SQL."""

    def run(spark: SparkSession, d: str) -> DataFrame:
        return tables(run_sweeps(joint(spark, d), spec, sizes, trade, sweeps, schedule, form))

    run.__name__ = name
    QUERIES[name] = run
    ORACLES[name] = SweepScript(spec, sizes, joint_sql).sweeps(sweeps, trade, schedule, form).tables()


TR = ("turn", "role")
LABELLED_SQL = cells_sql("(SELECT lang, source, quality FROM documents JOIN labels USING (doc_id))", ("source", "lang", "quality"))


def labelled(spark: SparkSession, d: str) -> DataFrame:
    rows = read_table(spark, d, "documents").select("doc_id", "lang", "source").join(read_table(spark, d, "labels").select("doc_id", "quality"), "doc_id")
    return build_joint(rows, ["source", "lang", "quality"])


def brand_supplier(spark: SparkSession, d: str) -> DataFrame:
    lines = read_table(spark, d, "lineitem").select("l_partkey", "l_suppkey", (F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("value"))
    part = read_table(spark, d, "part").select("p_partkey", "p_brand")
    return build_joint(lines.join(part, F.col("l_partkey") == F.col("p_partkey")), ["l_suppkey", "p_brand"], "value")


BRAND_SUPPLIER_SQL = cells_sql("lineitem JOIN part ON l_partkey = p_partkey", ("l_suppkey", "p_brand"), STAR_WEIGHT)

registered("single_fixed_turn_role_s10", turn_role, TURN_ROLE, presets.single(*TR), {"T": 3}, TradeOff.beta(5.0), 10)
registered("single_l1_target_b_s4", turn_role, TURN_ROLE, presets.single(*TR, target="b"), {"T": 3}, TradeOff.beta(0.8), 4)
registered("single_l1_target_b_literal_s4", turn_role, TURN_ROLE, presets.single(*TR, target="b"), {"T": 3}, TradeOff.beta(1.5), 4, form="literal")
registered("single_l2_target_a_s4", turn_role, TURN_ROLE, presets.single(*TR, objective="gamma"), {"T": 3}, TradeOff.gamma(9.0), 4)
registered("parallel_a_s4", turn_role, TURN_ROLE, presets.parallel(*TR), {"T1": 2, "T2": 2}, TradeOff.beta(5.0), 4)
registered("parallel_b_literal_s4", turn_role, TURN_ROLE, presets.parallel(*TR, objective="gamma"), {"T1": 2, "T2": 2}, TradeOff.gamma(5.0), 4)
registered("parallel_b_collapsed_s3", turn_role, TURN_ROLE, presets.parallel(*TR, objective="gamma"), {"T1": 2, "T2": 2}, TradeOff.gamma(2.0), 3, form="collapsed")
registered("three_way_parallel_s2", turn_role, TURN_ROLE, presets.parallel(*TR, r=3), {"T1": 2, "T2": 2, "T3": 2}, TradeOff.beta(4.0), 2)
registered("symmetric_a_s6", turn_role, TURN_ROLE, presets.symmetric(*TR), {"TA": 3, "TB": 2}, TradeOff.gamma(8.0), 6)
registered("symmetric_a_literal_s4", turn_role, TURN_ROLE, presets.symmetric(*TR), {"TA": 3, "TB": 2}, TradeOff.gamma(8.0), 4, form="literal")
registered("symmetric_b_literal_s4", turn_role, TURN_ROLE, presets.symmetric(*TR, target="b"), {"TA": 3, "TB": 2}, TradeOff.gamma(6.0), 4)
registered("symmetric_b_collapsed_s3", turn_role, TURN_ROLE, presets.symmetric(*TR, target="b"), {"TA": 3, "TB": 2}, TradeOff.gamma(2.0), 3, form="collapsed")
registered("multi_target_s5", labelled, LABELLED_SQL, presets.multi_target("source", ("lang", "quality")), {"T": 3}, TradeOff.beta(6.0), 5)
registered("joint_source_s5", labelled, LABELLED_SQL, presets.joint_source(("source", "lang"), "quality"), {"T": 3}, TradeOff.beta(6.0), 5)
registered("custom_chain_s3", turn_role, TURN_ROLE, presets.custom(TR, "turn->T1,T2", "T1->T2; T2->role"), {"T1": 2, "T2": 3}, TradeOff.beta(2.5), 3)
registered("sync_s4", turn_role, TURN_ROLE, presets.parallel(*TR), {"T1": 2, "T2": 3}, TradeOff.beta(5.0), 4, schedule="sync")
registered("async_s4", turn_role, TURN_ROLE, presets.parallel(*TR), {"T1": 2, "T2": 3}, TradeOff.beta(5.0), 4)
registered("zero_weight_s1", turn_role, TURN_ROLE, presets.single(*TR), {"T": 3}, TradeOff.beta(0.0), 1)
registered("supplier_brand_single_s3", brand_supplier, BRAND_SUPPLIER_SQL, presets.single("l_suppkey", "p_brand"), {"T": 4}, TradeOff.beta(20.0), 3)
registered("revenue_brand_nation_symmetric_s2", lambda spark, d: build_joint(star(spark, d), ["p_brand", "c_nationkey"], "value"), cells_sql(STAR_FROM, ("p_brand", "c_nationkey"), STAR_WEIGHT), presets.symmetric("p_brand", "c_nationkey"), {"TA": 3, "TB": 3}, TradeOff.gamma(20.0), 2)


def customer_part(spark: SparkSession, d: str) -> DataFrame:
    """Customers and parts, weighted by revenue: the largest joint of the given tables, nearly as many cells as line items."""
    lines = read_table(spark, d, "lineitem").select("l_orderkey", "l_partkey", (F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("value"))
    orders = read_table(spark, d, "orders").select("o_orderkey", "o_custkey")
    return build_joint(lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")), ["o_custkey", "l_partkey"], "value")


registered("customer_part_single_s2", customer_part, cells_sql("lineitem JOIN orders ON l_orderkey = o_orderkey", ("o_custkey", "l_partkey"), STAR_WEIGHT), presets.single("o_custkey", "l_partkey"), {"T": 4}, TradeOff.beta(8.0), 2)


def _l2_sql() -> str:
    one = SweepScript(presets.single(*TR), {"T": 3}, TURN_ROLE).sweeps(6, TradeOff.beta(5.0)).tables()
    return f"SELECT var, u, t, q, q AS q_second FROM ({one})"


@query(_l2_sql())
def single_l2_equals_l1(spark, d):
    cells = turn_role(spark, d)
    first = tables(run_sweeps(cells, presets.single(*TR), {"T": 3}, TradeOff.beta(5.0), 6))
    second = tables(run_sweeps(cells, presets.single(*TR, objective="gamma", target="b"), {"T": 3}, TradeOff.gamma(5.0), 6))
    return first.join(second.withColumnRenamed("q", "q_second"), ["var", "u", "t"])


def _rescaled_sql() -> str:
    one = SweepScript(presets.single(*TR), {"T": 3}, TURN_ROLE).sweeps(4, TradeOff.beta(4.0)).tables()
    return f"SELECT var, u, t, q, q AS q_second, q AS q_third FROM ({one})"


@query(_rescaled_sql())
def rescaled_trades(spark, d):
    """The plain single bottleneck at 4, the first objective with the source as a goal at 0.8, and the second objective without it: the same tables."""
    cells, out = turn_role(spark, d), None
    for name, spec, weight in (("q", presets.single(*TR), 4.0), ("q_second", presets.single(*TR, target="b"), 0.8), ("q_third", presets.single(*TR), presets.rescaled_trade("b", "beta", 0.8))):
        one = tables(run_sweeps(cells, spec, {"T": 3}, TradeOff.beta(weight), 4)).withColumnRenamed("q", name)
        out = one if out is None else out.join(one, ["var", "u", "t"])
    return out


STOP_TOL = 0.045


def _stop_sql(most: int = 12) -> str:
    """Every sweep's largest move, up to the first below the tolerance."""
    s, rows = SweepScript(presets.single(*TR), {"T": 3}, TURN_ROLE), []
    for sweep in range(1, most + 1):
        before = s.current["T"]
        s.sweeps(1, TradeOff.beta(5.0))
        rows.append(f"SELECT {sweep}::BIGINT AS sweep, MAX(abs(x.q - y.q)) AS moved FROM {before} x JOIN {s.current['T']} y USING (turn, t)")
    every = s.add(" UNION ALL ".join(rows), "moves")
    return s.ending(f"SELECT sweep, round(moved, 6) AS moved FROM {every} WHERE sweep <= coalesce((SELECT MIN(sweep) FROM {every} WHERE moved <= {STOP_TOL}), {most})")


@query(_stop_sql())
def stop_rule_trace(spark, d):
    """The largest move of each sweep until the stop rule holds."""
    found = solve(bind(cut_lineage(turn_role(spark, d)), presets.single(*TR), {"T": 3}), TradeOff.beta(5.0), stop=StopRule(STOP_TOL, 12))
    rows = spark.createDataFrame([(sweep, delta) for sweep, _, _, delta in found.trace], "sweep long, moved double")
    return rows.select("sweep", F.round("moved", 6).alias("moved"))


def _closed_parallel_sql() -> str:
    """The distortion of the parallel form written out: sum over t2 of q2(t2|a) KL(P(b|a) || P(b|t1,t2)), less its value at t1 = 0."""
    s = SweepScript(presets.parallel(*TR), {"T1": 2, "T2": 3}, TURN_ROLE)
    j, q1, q2 = s.joint, s.current["T1"], s.current["T2"]
    m = s.add(f"SELECT q1.t AS t1, q2.t AS t2, j.role, SUM(j.p * q1.q * q2.q) AS m FROM {j} j JOIN {q1} q1 USING (turn) JOIN {q2} q2 USING (turn) GROUP BY 1, 2, 3", "m")
    g = s.add(f"SELECT t1, t2, role, m / SUM(m) OVER (PARTITION BY t1, t2) AS pb FROM {m}", "g")
    c = s.add(f"SELECT turn, role, p / SUM(p) OVER (PARTITION BY turn) AS pc FROM {j}", "c")
    dist = s.add(f"SELECT c.turn, g.t1, SUM(q2.q * c.pc * (ln(c.pc) - ln(g.pb))) AS d FROM {c} c JOIN {q2} q2 USING (turn) JOIN {g} g ON g.role = c.role AND g.t2 = q2.t GROUP BY 1, 2", "dist")
    return s.ending(f"SELECT CAST(turn AS VARCHAR) AS u, CAST(t1 AS BIGINT) AS t, round(d - FIRST_VALUE(d) OVER (PARTITION BY turn ORDER BY t1), 6) + 0.0 AS d FROM {dist}")


def _relative(model: Model, cluster: str, trade: TradeOff) -> DataFrame:
    _, terms = update_rule(model.spec, cluster, trade)
    source = model.spec.sources(cluster)[0]
    rows = distortion(model, cluster, terms).select(F.col(source).cast("string").alias("u"), F.col("d")[0].alias("d0"), F.posexplode("d").alias("t", "d"))
    return rows.select("u", F.col("t").cast("long").alias("t"), rounded(F.col("d") - F.col("d0")).alias("d"))


@query(_closed_parallel_sql())
def generic_matches_kernel(spark, d):
    return _relative(bind(cut_lineage(turn_role(spark, d)), presets.parallel(*TR), {"T1": 2, "T2": 3}), "T1", TradeOff.beta(5.0))


def _closed_symmetric_sql() -> str:
    """KL(P(tb|a) || P(tb|ta)), less its value at ta = 0."""
    s = SweepScript(presets.symmetric(*TR), {"TA": 3, "TB": 2}, TURN_ROLE)
    j, qa, qb = s.joint, s.current["TA"], s.current["TB"]
    w = s.add(f"SELECT j.turn, qb.t AS tb, SUM(j.p * qb.q) AS p FROM {j} j JOIN {qb} qb USING (role) GROUP BY 1, 2", "w")
    m = s.add(f"SELECT qa.t AS ta, w.tb, SUM(w.p * qa.q) AS m FROM {w} w JOIN {qa} qa USING (turn) GROUP BY 1, 2", "m")
    g = s.add(f"SELECT ta, tb, m / SUM(m) OVER (PARTITION BY ta) AS pb FROM {m}", "g")
    c = s.add(f"SELECT turn, tb, p / SUM(p) OVER (PARTITION BY turn) AS pc FROM {w}", "c")
    dist = s.add(f"SELECT c.turn, g.ta, SUM(c.pc * (ln(c.pc) - ln(g.pb))) AS d FROM {c} c JOIN {g} g USING (tb) GROUP BY 1, 2", "dist")
    return s.ending(f"SELECT CAST(turn AS VARCHAR) AS u, CAST(ta AS BIGINT) AS t, round(d - FIRST_VALUE(d) OVER (PARTITION BY turn ORDER BY ta), 6) + 0.0 AS d FROM {dist}")


@query(_closed_symmetric_sql())
def distortion_table(spark, d):
    return _relative(bind(cut_lineage(turn_role(spark, d)), presets.symmetric(*TR), {"TA": 3, "TB": 2}), "TA", TradeOff.gamma(5.0))


def _hard_sql() -> str:
    s = SweepScript(presets.single(*TR), {"T": 3}, TURN_ROLE).sweeps(3, TradeOff.beta(5.0))
    j, q = s.joint, s.current["T"]
    m = s.add(f"SELECT q.t, j.role, SUM(j.p * q.q) AS m FROM {j} j JOIN {q} q USING (turn) GROUP BY 1, 2", "m")
    g = s.add(f"SELECT t, role, m / SUM(m) OVER (PARTITION BY t) AS pb FROM {m}", "g")
    dist = s.add(f"SELECT j.turn, g.t, round(-SUM(j.p * ln(g.pb)) / SUM(j.p), 12) AS d FROM {j} j JOIN {g} g USING (role) GROUP BY 1, 2", "dist")
    return s.ending(f"SELECT turn, CAST(t AS BIGINT) AS t FROM (SELECT turn, t, row_number() OVER (PARTITION BY turn ORDER BY d, t) AS r FROM {dist}) WHERE r = 1")


@query(_hard_sql())
def hard_limit_step(spark, d):
    model = run_sweeps(turn_role(spark, d), presets.single(*TR), {"T": 3}, TradeOff.beta(5.0), 3)
    return harden(model, "T", TradeOff.beta(5.0)).select("turn", F.col("t").cast("long").alias("t"))


def _trace_sql() -> str:
    trade, s, rows = TradeOff.gamma(8.0), SweepScript(presets.symmetric(*TR), {"TA": 3, "TB": 2}, TURN_ROLE), []
    for sweep in range(1, 5):
        s.sweeps(1, trade)
        rows.append(f"SELECT {sweep}::BIGINT AS sweep, round({s.objective(trade)[2]}, 6) + 0.0 AS objective")
    return s.ending(" UNION ALL ".join(rows))


@query(_trace_sql())
def lagrangian_trace(spark, d):
    trade = TradeOff.gamma(8.0)
    model, out = bind(cut_lineage(turn_role(spark, d)), presets.symmetric(*TR), {"TA": 3, "TB": 2}), None
    for sweep in range(1, 5):
        solve(model, trade, stop=StopRule(0.0, 1))
        one = lagrangian(model, trade).select(F.lit(sweep).cast("long").alias("sweep"), rounded("objective").alias("objective"))
        out = one if out is None else out.unionByName(one)
    return out


EXTREMES = (("l1_target_a", "beta", "a", (0.0, 1e4)), ("l1_target_b", "beta", "b", (0.0, 0.999)), ("l2_target_b", "gamma", "b", (0.0, 1e4)), ("l2_target_a", "gamma", "a", (0.0, 1e4)))


def _extreme_sql() -> str:
    parts = []
    for name, kind, target, weights in EXTREMES:
        for w in weights:
            s = SweepScript(presets.single(*TR, objective=kind, target=target), {"T": 3}, TURN_ROLE).sweeps(2, TradeOff(kind, w))
            row = f"SELECT '{name}' AS spec, {w}::DOUBLE AS weight, round({s.mutual(('T',), ('turn',))} / ln(2), 5) + 0.0 AS compression, round({s.mutual(('T',), ('role',))} / ln(2), 5) + 0.0 AS relevance"
            parts.append(f"SELECT * FROM ({s.ending(row)})")
    return " UNION ALL ".join(parts)


@query(_extreme_sql())
def extreme_trade_panel(spark, d):
    cells, out = cut_lineage(turn_role(spark, d)), None
    for name, kind, target, weights in EXTREMES:
        for w in weights:
            model = run_sweeps(cells, presets.single(*TR, objective=kind, target=target), {"T": 3}, TradeOff(kind, w), 2)
            info = pair_info(model, ("T",), ("turn",)).withColumnRenamed("mutual_info", "c").crossJoin(pair_info(model, ("T",), ("role",)))
            one = info.select(F.lit(name).alias("spec"), F.lit(w).alias("weight"), rounded("c", 5).alias("compression"), rounded("mutual_info", 5).alias("relevance"))
            out = one if out is None else out.unionByName(one)
    return out


# --- parts of annealing ---

LCG = "(((i * 7919 + t * 104729 + 1 * 1299709) % 10007) / 10006.0::DOUBLE - 0.5)"


@query(
    f"WITH l AS ({LINE_CELLS}), gap AS (SELECT {h_sql(('l_returnflag', 'l_linestatus'), 'l')} + {h_sql(('l_linestatus', 'l_linenumber'), 'l')} - {h_sql(('l_linestatus',), 'l')} - {h_sql(LINES, 'l')} AS g FROM (SELECT 1)) "
    "SELECT 'chain' AS network, round(g, 6) + 0.0 AS gap, g <= 1e-6 AS consistent FROM gap UNION ALL SELECT 'complete', 0.0, true"
)
def input_consistency(spark, d):
    """Whether the observed joint is one that the observed part of the compression network allows."""
    cells, out = build_joint(read_table(spark, d, "lineitem"), list(LINES)), None
    for name, edges in (("chain", "l_returnflag->l_linestatus; l_linestatus->l_linenumber; l_linenumber->T"), ("complete", "l_linenumber->T")):
        spec = presets.custom(LINES, edges, "T->l_returnflag")
        one = observed_gap(cells, spec, tol=1e-6).select(F.lit(name).alias("network"), rounded("gap").alias("gap"), "consistent")
        out = one if out is None else out.unionByName(one)
    return out


def _double_sql(s: SweepScript, q: str, alpha: float) -> str:
    ranked = s.add(f"SELECT turn, t, q, dense_rank() OVER (ORDER BY turn) - 1 AS i FROM {q}", "r")
    return s.add(f"SELECT turn, 2 * t AS t, q * (0.5 + {alpha} * {LCG}) AS q FROM {ranked} UNION ALL SELECT turn, 2 * t + 1, q * (0.5 - {alpha} * {LCG}) FROM {ranked}", "q")


def _doubled_sql() -> str:
    s = SweepScript(presets.single(*TR), {"T": 2}, TURN_ROLE)
    s.current["T"] = _double_sql(s, s.current["T"], 0.8)
    return s.tables()


@query(_doubled_sql())
def double_lcg(spark, d):
    cells = cut_lineage(turn_role(spark, d))
    model = bind(cells, presets.single(*TR), {"T": 2})
    model.parts["T"] = anneal.double_values(model.parts["T"], ["turn"], 2, 0.8, 1, "lcg")
    return tables(model)


def _split_sql(merge: bool) -> str:
    s = SweepScript(presets.single(*TR), {"T": 2}, TURN_ROLE).sweeps(2, TradeOff.beta(5.0))
    s.current["T"] = _double_sql(s, s.current["T"], 1.0)
    s.sizes["T"] = 4
    s.sweeps(3, TradeOff.beta(5.0))
    q = s.current["T"]
    pt = s.add(f"SELECT t, SUM(pu * q) AS pt FROM {q} JOIN {s.mass['T']} USING (turn) GROUP BY t", "pt")
    pairs = s.add(f"SELECT turn, t // 2 AS t, MAX(CASE WHEN t % 2 = 0 THEN q END) AS a, MAX(CASE WHEN t % 2 = 1 THEN q END) AS b FROM {q} GROUP BY turn, t // 2", "pairs")
    over = s.add(f"SELECT t // 2 AS t, MAX(CASE WHEN t % 2 = 0 THEN pt END) AS pa, MAX(CASE WHEN t % 2 = 1 THEN pt END) AS pb FROM {pt} GROUP BY t // 2", "over")
    gaps = f"SELECT t, MAX(CASE WHEN a + b > 1e-6 THEN abs(a / (a + b) - pa / (pa + pb)) ELSE 0.0 END) AS gap FROM {pairs} JOIN {over} USING (t) GROUP BY t"
    if not merge:
        return s.ending(f"SELECT CAST(t AS BIGINT) AS t, round(gap, 6) AS gap, gap > 0.05 AS split FROM ({gaps})")
    return s.ending(f"SELECT 'T' AS var, CAST(turn AS VARCHAR) AS u, CAST(t AS BIGINT) AS t, round(a + b, 6) + 0.0 AS q FROM {pairs}")


def _copies(spark, d) -> Model:
    model = run_sweeps(turn_role(spark, d), presets.single(*TR), {"T": 2}, TradeOff.beta(5.0), 2)
    model.parts["T"] = cut_lineage(anneal.double_values(model.parts["T"], ["turn"], 2, 1.0, 1, "lcg"))
    model.sizes["T"] = 4
    return solve(model, TradeOff.beta(5.0), stop=StopRule(0.0, 3)).model


@query(_split_sql(False))
def split_test_fixture(spark, d):
    model = _copies(spark, d)
    gaps = anneal.split_gaps(model.parts["T"], model.mass("T"), ["turn"], 2)
    return gaps.select(F.col("t").cast("long").alias("t"), F.round("gap", 6).alias("gap"), (F.col("gap") > 0.05).alias("split"))


@query(_split_sql(True))
def merge_copies_fixture(spark, d):
    model = _copies(spark, d)
    model.parts["T"] = anneal.merge_copies(model.parts["T"], ["turn"], [False, False])
    model.sizes["T"] = 2
    return tables(model)


SINGLE_WEIGHTS, SINGLE_SWEEPS = [3.0, 9.0], 3


def _anneal_sql() -> str:
    s = AnnealScript(presets.single(*TR), TURN_ROLE).anneal(SINGLE_WEIGHTS, SINGLE_SWEEPS, max_k=4)
    return f"SELECT step, beta, var, k, compression, relevance, split FROM ({s.curve()})"


@query(_anneal_sql())
def anneal_single_turn_role(spark, d):
    """The distributed anneal of a single bottleneck: its curve."""
    result = anneal.anneal(turn_role(spark, d), presets.single(*TR), SINGLE_WEIGHTS, max_k=4, noise="lcg", stop=StopRule(0.0, SINGLE_SWEEPS))
    rows = spark.createDataFrame(result.curve, "step long, beta double, var string, k long, compression double, relevance double, split boolean")
    return rows.select("step", "beta", "var", "k", rounded("compression").alias("compression"), rounded("relevance").alias("relevance"), "split")


def _critical_sql(rounds: int = 10) -> str:
    b = [f"j AS MATERIALIZED ({TURN_ROLE})", "pa AS MATERIALIZED (SELECT turn, SUM(p) AS pa FROM j GROUP BY turn)", "pb AS MATERIALIZED (SELECT role, SUM(p) AS pb FROM j GROUP BY role)"]
    b.append("m AS MATERIALIZED (SELECT turn, role, pb, p / sqrt(pa * pb) AS m FROM j JOIN pa USING (turn) JOIN pb USING (role))")
    b.append("v0 AS MATERIALIZED (SELECT role, pb, ((row_number() OVER (ORDER BY role) * 7919) % 10007) / 10007.0::DOUBLE AS v FROM pb)")
    for i in range(rounds):
        b.append(f"c{i} AS MATERIALIZED (SELECT role, pb, v - (SELECT SUM(v * sqrt(pb)) FROM v{i}) * sqrt(pb) AS v FROM v{i})")
        b.append(f"n{i} AS MATERIALIZED (SELECT role, pb, v / (SELECT sqrt(SUM(v * v)) FROM c{i}) AS v FROM c{i})")
        b.append(f"l{i} AS MATERIALIZED (SELECT turn, SUM(m * v) AS l FROM m JOIN n{i} USING (role) GROUP BY turn)")
        b.append(f"v{i + 1} AS MATERIALIZED (SELECT role, m.pb AS pb, SUM(m * l) AS v FROM m JOIN l{i} USING (turn) GROUP BY role, m.pb)")
    return "WITH " + ", ".join(b) + f" SELECT round(SUM(l * l), 6) AS sigma2_squared, round(1 / SUM(l * l), 6) AS critical_beta FROM l{rounds - 1}"


@query(_critical_sql())
def critical_beta_power10(spark, d):
    return anneal.critical_beta(turn_role(spark, d), *TR, 10).select(F.round("sigma2_squared", 6).alias("sigma2_squared"), F.round("critical_beta", 6).alias("critical_beta"))


def _agglomerate_sql(steps: int = 5) -> str:
    """Every step written out: all pairs' losses from their profiles, the least one merged."""
    b = [f"c0 AS MATERIALIZED (SELECT CAST(turn AS VARCHAR) AS a, role AS b, SUM(p) AS p FROM ({TURN_ROLE}) GROUP BY 1, 2)"]
    xl = lambda x: f"(CASE WHEN {x} > 0 THEN {x} * ln({x}) ELSE 0 END)"
    for i in range(steps):
        b.append(f"f{i} AS MATERIALIZED (SELECT a.a, b.b, coalesce(c.p, 0) AS p, SUM(coalesce(c.p, 0)) OVER (PARTITION BY a.a) AS pa FROM (SELECT DISTINCT a FROM c{i}) a CROSS JOIN (SELECT DISTINCT b FROM c{i}) b LEFT JOIN c{i} c ON c.a = a.a AND c.b = b.b)")
        own = lambda t: f"({xl(f'{t}.p')} - {t}.p * ln({t}.pa))"
        both = f"({xl('(x.p + y.p)')} - (x.p + y.p) * ln(x.pa + y.pa))"
        b.append(f"k{i} AS MATERIALIZED (SELECT x.a AS i, y.a AS j, round(SUM({own('x')} + {own('y')} - {both}), 12) AS loss FROM f{i} x JOIN f{i} y ON x.b = y.b AND x.a < y.a GROUP BY 1, 2 ORDER BY 3, 1, 2 LIMIT 1)")
        b.append(f"c{i + 1} AS MATERIALIZED (SELECT CASE WHEN a = (SELECT j FROM k{i}) THEN (SELECT i FROM k{i}) ELSE a END AS a, b, SUM(p) AS p FROM c{i} GROUP BY 1, 2)")
    return "WITH " + ", ".join(b) + " " + " UNION ALL ".join(f"SELECT {i + 1}::BIGINT AS step, i AS kept, j AS merged, round(loss / ln(2), 6) + 0.0 AS loss FROM k{i}" for i in range(steps))


@query(_agglomerate_sql())
def agglomerate_turn_role(spark, d):
    n = turn_role(spark, d).select("turn").distinct().count()
    steps = bottom_up.agglomerate(turn_role(spark, d), *TR, max(1, n - 5))
    return spark.createDataFrame(steps, "step long, kept string, merged string, loss double").select("step", "kept", "merged", rounded("loss").alias("loss"))


@query(_agglomerate_sql(7))
def agglomerate_turn_role_whole(spark, d):
    """Every merge down to one cluster. The tables have eight turns, so the SQL unrolls seven merges."""
    steps = bottom_up.agglomerate(turn_role(spark, d), *TR, 1)
    return spark.createDataFrame(steps, "step long, kept string, merged string, loss double").select("step", "kept", "merged", rounded("loss").alias("loss"))


