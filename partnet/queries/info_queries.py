"""Joints, measures, networks and specification checks on the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from partnet.functions.expr import rounded
from partnet.operators import info
from partnet.operators.joint import build_joint, conditional, marginal, width_bins
from partnet.operators.model import lagrangian, pair_info
from partnet.operators.solve import bind
from partnet.operators.text import word_category_joint
from partnet.plans import presets
from partnet.plans.graph import Dag, TradeOff
from partnet.plans.sweep_sql import SweepScript
from partnet.sources.tables import read_table, ship_value

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):
    def keep(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLES[f.__name__] = sql
        return f

    return keep


def cells_sql(source: str, variables: tuple[str, ...], weight: str = "1.0::DOUBLE") -> str:
    """SELECT variables, n, p of a joint over a FROM clause (nulls dropped)."""
    v = ", ".join(variables)
    some = " AND ".join(f"{x} IS NOT NULL" for x in variables)
    return f"SELECT {v}, n, n / SUM(n) OVER () AS p FROM (SELECT {v}, SUM({weight}) AS n FROM {source} WHERE {some} GROUP BY {v})"


def h_sql(variables: tuple[str, ...], table: str = "j") -> str:
    return f"(SELECT -SUM(p * ln(p)) / ln(2) FROM (SELECT SUM(p) AS p FROM {table} GROUP BY {', '.join(variables)}))"


def mi_sql(x: tuple[str, ...], y: tuple[str, ...], table: str = "j") -> str:
    return f"({h_sql(x, table)} + {h_sql(y, table)} - {h_sql((*x, *y), table)})"


TURN_ROLE = cells_sql("conversations", ("turn", "role"))
LINES = ("l_returnflag", "l_linestatus", "l_linenumber")
LINE_CELLS = cells_sql("lineitem", LINES)
CHAIN = Dag.parse("l_returnflag -> l_linestatus; l_linestatus -> l_linenumber")
STAR_WEIGHT = "l_extendedprice * (1 - l_discount)"


def turn_role(spark: SparkSession, d: str) -> DataFrame:
    return build_joint(read_table(spark, d, "conversations"), ["turn", "role"])


def line_joint(spark: SparkSession, d: str) -> DataFrame:
    return build_joint(read_table(spark, d, "lineitem"), list(LINES))


@query(f"SELECT turn, role, n, round(p, 9) AS p FROM ({TURN_ROLE})")
def joint_turn_role(spark, d):
    return turn_role(spark, d).select("turn", "role", "n", F.round("p", 9).alias("p"))


@query(f"SELECT lang, source, n, round(p, 9) AS p FROM ({cells_sql('documents', ('lang', 'source'))})")
def joint_lang_source(spark, d):
    return build_joint(read_table(spark, d, "documents"), ["lang", "source"]).select("lang", "source", "n", F.round("p", 9).alias("p"))


def star(spark: SparkSession, d: str) -> DataFrame:
    """lineitem with brand and nation. Dimensions join unhinted: the engine broadcasts those it finds small."""
    lines = read_table(spark, d, "lineitem").select("l_orderkey", "l_partkey", ship_value().alias("value"))
    orders = read_table(spark, d, "orders").select("o_orderkey", "o_custkey")
    customer = read_table(spark, d, "customer").select("c_custkey", "c_nationkey")
    part = read_table(spark, d, "part").select("p_partkey", "p_brand")
    return lines.join(part, F.col("l_partkey") == F.col("p_partkey")).join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(customer, F.col("o_custkey") == F.col("c_custkey"))


STAR_FROM = "lineitem JOIN part ON l_partkey = p_partkey JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey"


@query(f"SELECT p_brand, c_nationkey, round(n, 1) AS n, round(p, 9) AS p FROM ({cells_sql(STAR_FROM, ('p_brand', 'c_nationkey'), STAR_WEIGHT)})")
def joint_revenue_brand_nation(spark, d):
    cells = build_joint(star(spark, d), ["p_brand", "c_nationkey"], "value")
    return cells.select("p_brand", "c_nationkey", F.round("n", 1).alias("n"), F.round("p", 9).alias("p"))


NULL_FROM = "(SELECT lang, quality FROM documents LEFT JOIN labels USING (doc_id))"
LEVELLED = "(SELECT coalesce(lang, '(null)') AS lang, coalesce(CAST(quality AS VARCHAR), '(null)') AS quality FROM documents LEFT JOIN labels USING (doc_id))"


@query(
    f"SELECT 'drop' AS policy, lang, CAST(quality AS VARCHAR) AS quality, n, round(p, 9) AS p FROM ({cells_sql(NULL_FROM, ('lang', 'quality'))}) "
    f"UNION ALL SELECT 'level', lang, quality, n, round(p, 9) FROM ({cells_sql(LEVELLED, ('lang', 'quality'))})"
)
def joint_null_policy(spark, d):
    rows = read_table(spark, d, "documents").select("doc_id", "lang").join(read_table(spark, d, "labels").select("doc_id", "quality"), "doc_id", "left")
    out = [build_joint(rows, ["lang", "quality"], nulls=x).select(F.lit(x).alias("policy"), "lang", F.col("quality").cast("string").alias("quality"), "n", F.round("p", 9).alias("p")) for x in ("drop", "level")]
    return out[0].unionByName(out[1])


@query(
    "WITH b AS (SELECT p_type, CAST(CASE WHEN p_retailprice < 900 THEN 0 WHEN p_retailprice >= 1000 THEN 13 ELSE floor(12 * (p_retailprice - 900) / 100) + 1 END AS BIGINT) AS price_bin FROM part) "
    f"SELECT price_bin, p_type, n, round(p, 9) AS p FROM ({cells_sql('b', ('price_bin', 'p_type'))})"
)
def joint_binned_price_type(spark, d):
    binned = read_table(spark, d, "part").select("p_type", width_bins(F.col("p_retailprice"), 900.0, 1000.0, 12).cast("long").alias("price_bin"))
    return build_joint(binned, ["price_bin", "p_type"]).select("price_bin", "p_type", "n", F.round("p", 9).alias("p"))


@query(f"WITH j AS ({LINE_CELLS}) " + " UNION ALL ".join(f"SELECT '{'+'.join(s)}' AS variables, round({h_sql(s)}, 6) + 0.0 AS entropy" for s in (*((v,) for v in LINES), LINES[:2], LINES)))
def entropy_panel(spark, d):
    sets = [*((v,) for v in LINES), LINES[:2], LINES]
    row = info.entropies(line_joint(spark, d), sets)
    return row.select(F.inline(F.array(*[F.struct(F.lit("+".join(s)).alias("variables"), rounded(f"h{i}").alias("entropy")) for i, s in enumerate(sets)])))


@query(f"WITH j AS ({cells_sql('nation', ('n_nationkey', 'n_regionkey'))}) SELECT round({mi_sql(('n_nationkey',), ('n_regionkey',))}, 6) + 0.0 AS mutual_info, round(ln(5) / ln(2), 6) AS log2_5")
def mi_anchor_nation_region(spark, d):
    cells = build_joint(read_table(spark, d, "nation"), ["n_nationkey", "n_regionkey"])
    return info.mutual_info(cells, ["n_nationkey"], ["n_regionkey"]).select(rounded("mutual_info").alias("mutual_info"), F.round(F.log2(F.lit(5.0)), 6).alias("log2_5"))


WORDS_SQL = "SELECT doc_id, lang, source, w FROM (SELECT doc_id, lang, source, trim(w, '.,;:!?()\"') AS w FROM (SELECT doc_id, lang, source, unnest(regexp_split_to_array(lower(text), '\\s+')) AS w FROM documents)) WHERE regexp_matches(w, '^\\p{L}+$')"


@query(f"WITH t AS ({WORDS_SQL}), j AS ({cells_sql('t', ('w', 'lang'))}) SELECT round({mi_sql(('w',), ('lang',))}, 6) + 0.0 AS mutual_info, round({h_sql(('lang',))}, 6) AS lang_entropy")
def mi_word_lang(spark, d):
    cells = word_category_joint(read_table(spark, d, "documents"), F.col("lang"), stop=())
    row = info.combined(cells, {"mutual_info": info.mi_terms(("w",), ("c",)), "lang_entropy": [(1, ("c",))]}, "bits")
    return row.select(rounded("mutual_info").alias("mutual_info"), F.round("lang_entropy", 6).alias("lang_entropy"))


#: (name, table, x, y as Spark SQL, the same in the oracle's SQL)
NULL_PAIRS = (
    ("returnflag_linestatus", "lineitem", "l_returnflag", "l_linestatus"),
    ("shipmonth_returnflag", "lineitem", "month(l_shipdate)", "l_returnflag"),
    ("linenumber_returnflag", "lineitem", "l_linenumber", "l_returnflag"),
    ("brand_type", "part", "p_brand", "p_type"),
    ("name_brand", "part", "p_name", "p_brand"),
    ("status_priority", "orders", "o_orderstatus", "o_orderpriority"),
    ("user_eventtype", "events", "user_id", "event_type"),
    ("hour_eventtype", "events", "hour(ts)", "event_type"),
    ("segment_nation", "customer", "c_mktsegment", "c_nationkey"),
)


def _null_sql() -> str:
    ctes, rows = [], []
    for name, table, x, y in NULL_PAIRS:
        ctes.append(f"{name} AS ({cells_sql(f'(SELECT {x} AS x, {y} AS y FROM {table})', ('x', 'y'))})")
        mi = mi_sql(("x",), ("y",), name)
        bias = f"(SELECT (count(DISTINCT x) - 1) * (count(DISTINCT y) - 1) / (2 * SUM(n) * ln(2)) FROM {name})"
        rows.append(f"SELECT '{name}' AS pair, round({mi}, 6) + 0.0 AS mutual_info, round({bias}, 6) AS bias, round(2 * (SELECT SUM(n) FROM {name}) * {mi} * ln(2), 3) + 0.0 AS g_statistic")
    return "WITH " + ", ".join(ctes) + " " + " UNION ALL ".join(rows)


@query(_null_sql())
def mi_null_panel(spark, d):
    out = None
    for name, table, x, y in NULL_PAIRS:
        cells = build_joint(read_table(spark, d, table).select(F.expr(x).alias("x"), F.expr(y).alias("y")), ["x", "y"])
        row = info.mi_panel_row(cells, "x", "y", name)
        out = row if out is None else out.unionByName(row)
    return out.select("pair", rounded("mutual_info").alias("mutual_info"), F.round("bias", 6).alias("bias"), rounded("g_statistic", 3).alias("g_statistic"))


ORDERS_FROM = "orders JOIN customer ON o_custkey = c_custkey"


@query(
    f"WITH j AS ({cells_sql(ORDERS_FROM, ('o_orderstatus', 'o_orderpriority', 'c_mktsegment'))}) "
    f"SELECT round({h_sql(('o_orderstatus', 'c_mktsegment'))} + {h_sql(('o_orderpriority', 'c_mktsegment'))} - {h_sql(('o_orderstatus', 'o_orderpriority', 'c_mktsegment'))} - {h_sql(('c_mktsegment',))}, 6) + 0.0 AS cond_mutual_info"
)
def cmi_status_priority_by_segment(spark, d):
    orders, customer = read_table(spark, d, "orders"), read_table(spark, d, "customer")
    cells = build_joint(orders.join(customer, F.col("o_custkey") == F.col("c_custkey")), ["o_orderstatus", "o_orderpriority", "c_mktsegment"])
    return info.cond_mutual_info(cells, ["o_orderstatus"], ["o_orderpriority"], ["c_mktsegment"]).select(rounded("cond_mutual_info").alias("cond_mutual_info"))


MULTI_SQL = " + ".join(h_sql((v,)) for v in LINES) + " - " + h_sql(LINES)
CHAIN_SQL = mi_sql(("l_linestatus",), ("l_returnflag",)) + " + " + mi_sql(("l_linenumber",), ("l_linestatus",))


@query(f"WITH j AS ({LINE_CELLS}) SELECT round({MULTI_SQL}, 6) + 0.0 AS multi_info")
def multi_info_lineitem(spark, d):
    return info.multi_info(line_joint(spark, d), list(LINES)).select(rounded("multi_info").alias("multi_info"))


@query(
    f"WITH j AS ({LINE_CELLS}) SELECT 'l_linestatus' AS variable, 'l_returnflag' AS parents, round({mi_sql(('l_linestatus',), ('l_returnflag',))}, 6) + 0.0 AS information "
    f"UNION ALL SELECT 'l_linenumber', 'l_linestatus', round({mi_sql(('l_linenumber',), ('l_linestatus',))}, 6) + 0.0"
)
def network_info_chain(spark, d):
    return info.network_info_by_variable(line_joint(spark, d), CHAIN).select("variable", "parents", rounded("information").alias("information"))


@query(
    f"WITH j AS ({LINE_CELLS}) SELECT 'l_returnflag' AS variable, '' AS parent, l_returnflag AS value, round(SUM(p), 9) AS p_cond FROM j GROUP BY l_returnflag "
    "UNION ALL SELECT 'l_linestatus', l_returnflag, l_linestatus, round(SUM(p) / SUM(SUM(p)) OVER (PARTITION BY l_returnflag), 9) FROM j GROUP BY l_returnflag, l_linestatus "
    "UNION ALL SELECT 'l_linenumber', l_linestatus, CAST(l_linenumber AS VARCHAR), round(SUM(p) / SUM(SUM(p)) OVER (PARTITION BY l_linestatus), 9) FROM j GROUP BY l_linestatus, l_linenumber"
)
def projection_factors(spark, d):
    out = None
    for v, factor in info.projection_factors(line_joint(spark, d), CHAIN).items():
        parent = F.concat_ws("|", *CHAIN.parents[v]) if CHAIN.parents[v] else F.lit("")
        one = factor.select(F.lit(v).alias("variable"), parent.alias("parent"), F.col(v).cast("string").alias("value"), F.round("p_cond", 9).alias("p_cond"))
        out = one if out is None else out.unionByName(one)
    return out


DIRECT_SQL = (
    "(SELECT SUM(c.p * ln(c.p / (a.p * b.p / a.p * d.p / s.p))) / ln(2) FROM (SELECT l_returnflag, l_linestatus, l_linenumber, SUM(p) AS p FROM j GROUP BY ALL) c "
    "JOIN (SELECT l_returnflag, SUM(p) AS p FROM j GROUP BY ALL) a USING (l_returnflag) JOIN (SELECT l_returnflag, l_linestatus, SUM(p) AS p FROM j GROUP BY ALL) b USING (l_returnflag, l_linestatus) "
    "JOIN (SELECT l_linestatus, SUM(p) AS p FROM j GROUP BY ALL) s USING (l_linestatus) JOIN (SELECT l_linestatus, l_linenumber, SUM(p) AS p FROM j GROUP BY ALL) d USING (l_linestatus, l_linenumber))"
)
MARKOV_SQL = f"({h_sql(('l_linenumber', 'l_linestatus'))} + {h_sql(('l_returnflag', 'l_linestatus'))} - {h_sql(LINES)} - {h_sql(('l_linestatus',))})"


@query(f"WITH j AS ({LINE_CELLS}) SELECT 'difference' AS form, round(({MULTI_SQL}) - ({CHAIN_SQL}), 6) + 0.0 AS gap UNION ALL SELECT 'markov', round({MARKOV_SQL}, 6) + 0.0 UNION ALL SELECT 'direct', round({DIRECT_SQL}, 6) + 0.0")
def gap_three_forms(spark, d):
    out = None
    for form in ("difference", "markov", "direct"):
        one = info.projection_gap(line_joint(spark, d), CHAIN, form).select(F.lit(form).alias("form"), rounded("gap").alias("gap"))
        out = one if out is None else out.unionByName(one)
    return out


def nation_region(spark, d):
    return build_joint(read_table(spark, d, "nation"), ["n_nationkey", "n_regionkey"])


@query(
    f"WITH j AS ({cells_sql('nation', ('n_nationkey', 'n_regionkey'))}) SELECT 'edge' AS network, round({mi_sql(('n_nationkey',), ('n_regionkey',))} - {mi_sql(('n_nationkey',), ('n_regionkey',))}, 6) + 0.0 AS gap, true AS consistent "
    f"UNION ALL SELECT 'empty', round({mi_sql(('n_nationkey',), ('n_regionkey',))}, 6) + 0.0, false"
)
def consistency_flags(spark, d):
    cells, out = nation_region(spark, d), None
    for name, dag in (("edge", Dag.parse("n_nationkey -> n_regionkey")), ("empty", Dag.parse("n_nationkey; n_regionkey"))):
        one = info.is_consistent(cells, dag).select(F.lit(name).alias("network"), rounded("gap").alias("gap"), "consistent")
        out = one if out is None else out.unionByName(one)
    return out


@query(
    f"WITH j AS ({TURN_ROLE}), r AS (SELECT role, SUM(p) AS q FROM j GROUP BY role), c AS (SELECT turn, role, p / SUM(p) OVER (PARTITION BY turn) AS p FROM j) "
    "SELECT turn, round(SUM(p * ln(p / q)) / ln(2), 6) + 0.0 AS kl FROM c JOIN r USING (role) GROUP BY turn"
)
def kl_role_profiles(spark, d):
    cells = turn_role(spark, d)
    given = conditional(cells, ["role"], ["turn"]).withColumnRenamed("p_cond", "p")
    return info.kl_divergence(given, marginal(cells, ["role"]), ["role"], by=["turn"]).select("turn", rounded("kl").alias("kl"))


@query("SELECT " + ", ".join(f"coalesce(CAST({v} AS VARCHAR), 'all') AS {v}" for v in LINES) + ", count(*) AS n FROM lineitem GROUP BY CUBE (lineitem.l_returnflag, lineitem.l_linestatus, lineitem.l_linenumber)")
def marginals_cube(spark, d):
    return read_table(spark, d, "lineitem").cube(*LINES).agg(F.count(F.lit(1)).alias("n")).select(*[F.coalesce(F.col(v).cast("string"), F.lit("all")).alias(v) for v in LINES], "n")


@query(
    f"WITH j AS ({TURN_ROLE}), a AS (SELECT turn, SUM(p) AS pv FROM j GROUP BY turn), b AS (SELECT role, SUM(p) AS pc FROM j GROUP BY role) "
    "SELECT turn, round(pv, 9) AS p, round(SUM(p * ln(p / (pv * pc))) / ln(2), 6) + 0.0 AS contribution FROM j JOIN a USING (turn) JOIN b USING (role) GROUP BY turn, pv"
)
def value_contribution_turns(spark, d):
    return info.value_contribution(turn_role(spark, d), "turn", "role").select("turn", F.round("p", 9).alias("p"), rounded("contribution").alias("contribution"))


def start_script(spec, sizes) -> SweepScript:
    return SweepScript(spec, sizes, TURN_ROLE)


def _lagrangian_sql(spec, sizes, trade) -> str:
    s = start_script(spec, sizes)
    i_in, i_out, value = s.objective(trade)
    return s.ending(f"SELECT round({i_in}, 6) + 0.0 AS i_in, round({i_out}, 6) + 0.0 AS i_out, round({value}, 6) + 0.0 AS objective")


def _lagrangian(spark, d, spec, sizes, trade) -> DataFrame:
    model = bind(turn_role(spark, d), spec, sizes)
    return lagrangian(model, trade).select(*[rounded(c).alias(c) for c in ("i_in", "i_out", "objective")])


@query(_lagrangian_sql(presets.parallel("turn", "role"), {"T1": 2, "T2": 3}, TradeOff.beta(4.0)))
def lagrangian_l1_fixed_part(spark, d):
    return _lagrangian(spark, d, presets.parallel("turn", "role"), {"T1": 2, "T2": 3}, TradeOff.beta(4.0))


@query(_lagrangian_sql(presets.symmetric("turn", "role"), {"TA": 3, "TB": 2}, TradeOff.gamma(4.0)))
def lagrangian_l2_fixed_part(spark, d):
    return _lagrangian(spark, d, presets.symmetric("turn", "role"), {"TA": 3, "TB": 2}, TradeOff.gamma(4.0))


@query("SELECT gamma, round(gamma / (1 + gamma), 9) AS beta, round((gamma / (1 + gamma)) / (1 - gamma / (1 + gamma)), 6) AS back FROM (SELECT DISTINCT l_quantity AS gamma FROM lineitem WHERE l_quantity >= 0)")
def beta_gamma_grid(spark, d):
    """Line items' quantities as weights of the second objective, as weights of the first, and back."""

    @F.udf("struct<beta: double, back: double>")
    def both(g: float) -> tuple[float, float]:
        beta = TradeOff.gamma(g).to_beta()
        return beta, TradeOff.beta(beta).to_gamma()

    grid = read_table(spark, d, "lineitem").select(F.col("l_quantity").alias("gamma")).where("gamma >= 0").distinct()
    return grid.withColumn("x", both("gamma")).select("gamma", F.round("x.beta", 9).alias("beta"), F.round("x.back", 6).alias("back"))


def _overlap_sql() -> str:
    s = start_script(presets.parallel("turn", "role"), {"T1": 2, "T2": 3})
    both, one, two, lap = s.mutual(("T1", "T2"), ("turn",)), s.mutual(("T1",), ("turn",)), s.mutual(("T2",), ("turn",)), s.mutual(("T1",), ("T2",))
    bit = "/ ln(2)"
    return s.ending(f"SELECT round({both} {bit}, 6) + 0.0 AS joint_side, round(({one} + {two} - {lap}) {bit}, 6) + 0.0 AS sum_side, round({lap} {bit}, 6) + 0.0 AS overlap")


@query(_overlap_sql())
def overlap_identity(spark, d):
    from partnet.operators.model import marginal_of

    model = bind(turn_role(spark, d), presets.parallel("turn", "role"), {"T1": 2, "T2": 3})
    extended = marginal_of(model, ("turn", "T1", "T2"))
    return info.overlap_identity(extended, "turn", "T1", "T2").select(*[rounded(c).alias(c) for c in ("joint_side", "sum_side", "overlap")])


def _combined_sql() -> str:
    s = start_script(presets.parallel("turn", "role"), {"T1": 2, "T2": 3})
    whole = s.mutual(("turn",), ("role",))
    cols = {"first": s.mutual(("T1",), ("role",)), "second": s.mutual(("T2",), ("role",)), "together": s.mutual(("T1", "T2"), ("role",))}
    return s.ending("SELECT " + ", ".join(f"round({v} / {whole}, 6) + 0.0 AS {k}" for k, v in cols.items()))


@query(_combined_sql())
def combined_relevance(spark, d):
    model = bind(turn_role(spark, d), presets.parallel("turn", "role"), {"T1": 2, "T2": 3})
    row = None
    for name, x in (("first", ("T1",)), ("second", ("T2",)), ("together", ("T1", "T2")), ("whole", ("turn",))):
        one = pair_info(model, x, ("role",)).select(F.col("mutual_info").alias(name))
        row = one if row is None else row.crossJoin(one)
    return row.select(*[rounded(F.col(n) / F.col("whole")).alias(n) for n in ("first", "second", "together")])
