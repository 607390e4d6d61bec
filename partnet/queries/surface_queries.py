"""Streams, SQL functions, array, map and JSON forms, joins of every kind, sources and sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from partnet.functions import sql as sql_functions
from partnet.functions.expr import rounded, softmax
from partnet.operators.apply import membership_map as shares
from partnet.operators.apply import memberships
from partnet.operators.info import mi_panel_row, mutual_info
from partnet.operators.joint import build_joint, encode, normalise
from partnet.operators.solve import bind, start_table
from partnet.plans import presets
from partnet.plans.sweep_sql import SweepScript
from partnet.queries.info_queries import TURN_ROLE, cells_sql, mi_sql, turn_role
from partnet.sources.tables import read_table, scratch_path
from partnet.streaming import joint_stream as streams

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):
    def keep(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLES[f.__name__] = sql
        return f

    return keep


def epoch(c: str):
    return F.unix_timestamp(c)


@query("SELECT CAST(epoch(date_trunc('day', ts)) AS BIGINT) AS start, user_id, event_type, count(*) AS n FROM events GROUP BY ALL")
def events_tumbling_joint(spark, d):
    cells = streams.windowed_joint(streams.event_stream(spark, d), ["user_id", "event_type"], "1 day")
    return streams.drain(cells).select(epoch("start").alias("start"), "user_id", "event_type", "n")


@query("SELECT CAST(epoch(time_bucket(INTERVAL 6 HOUR, ts) - INTERVAL (6 * k) HOUR) AS BIGINT) AS start, event_type, count(*) AS n FROM events, (SELECT range AS k FROM range(4)) GROUP BY ALL")
def events_sliding_joint(spark, d):
    cells = streams.windowed_joint(streams.event_stream(spark, d), ["event_type"], "1 day", "6 hours")
    return streams.drain(cells).select(epoch("start").alias("start"), "event_type", "n")


@query(
    "WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 12 HOUR THEN 0 ELSE 1 END AS fresh FROM events), "
    "s AS (SELECT user_id, ts, SUM(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) "
    "SELECT user_id, CAST(epoch(date_trunc('second', MIN(ts))) AS BIGINT) AS start, count(*) AS n FROM s GROUP BY user_id, k"
)
def events_session_counts(spark, d):
    sessions = streams.drain(streams.session_counts(streams.event_stream(spark, d), ["user_id"], "12 hours"))
    return sessions.select("user_id", epoch("start").alias("start"), "n")


@query("SELECT event_type, count(DISTINCT event_id) AS n FROM events GROUP BY event_type")
def events_dedup_late(spark, d):
    """Every event sent twice, counted once. Ids stay in the state for a day of event time."""
    once = streams.event_stream(spark, d)
    kept = streams.deduplicated(once.unionByName(once), "event_id", "1 day")
    return streams.drain(kept.select("event_id", "event_type"), "append").groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))


@query(
    "WITH r AS (SELECT event_type, count(*) / (SELECT count(*) FROM events) AS q FROM events GROUP BY event_type), c AS (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY ALL), "
    "u AS (SELECT user_id, event_type, n, SUM(n) OVER (PARTITION BY user_id) AS m FROM c) SELECT user_id, CAST(SUM(n) AS BIGINT) AS n, round(SUM(n / m * ln(n / m / q)) / ln(2), 6) + 0.0 AS kl FROM u JOIN r USING (event_type) GROUP BY user_id"
)
def events_drift(spark, d):
    events = read_table(spark, d, "events")
    total = events.count()
    reference = {r["event_type"]: r["n"] / total for r in events.groupBy("event_type").agg(F.count(F.lit(1)).alias("n")).collect()}
    scores = streams.drain(streams.drift(streams.event_stream(spark, d), "user_id", "event_type", reference), "update")
    last = scores.groupBy("user_id").agg(F.max_by("kl", "n").alias("kl"), F.max("n").alias("n"))
    return last.select("user_id", "n", rounded("kl").alias("kl"))


@query(
    "WITH e AS (SELECT turn, role, p, exp(ln(p) - MAX(ln(p)) OVER (PARTITION BY turn)) AS e FROM (" + TURN_ROLE + ")) "
    "SELECT turn, list(round(e / s, 6) ORDER BY role)[1] AS first_share, round(SUM(e / s), 6) AS whole FROM (SELECT *, SUM(e) OVER (PARTITION BY turn) AS s FROM e) GROUP BY turn"
)
def array_softmax_panel(spark, d):
    rows = turn_role(spark, d).groupBy("turn").agg(F.array_sort(F.collect_list(F.struct("role", F.ln("p").alias("lp")))).alias("s"))
    shares = rows.select("turn", softmax(F.transform("s", lambda x: x["lp"])).alias("q"))
    return shares.select("turn", F.round(F.col("q")[0], 6).alias("first_share"), F.round(F.aggregate("q", F.lit(0.0), lambda a, x: a + x), 6).alias("whole"))


def _start_sql() -> tuple[SweepScript, str]:
    s = SweepScript(presets.single("turn", "role"), {"T": 3}, TURN_ROLE)
    return s, s.current["T"]


def _map_sql() -> str:
    s, q = _start_sql()
    return s.ending(f"SELECT turn, string_agg(t || ':' || round(q, 3), ' ' ORDER BY t) AS clusters, count(*) AS k FROM {q} WHERE q >= 0.2 GROUP BY turn")


@query(_map_sql())
def membership_map(spark, d):
    part = bind(turn_role(spark, d), presets.single("turn", "role"), {"T": 3}).parts["T"]
    pairs = F.array_sort(F.map_entries("clusters"))
    text = F.array_join(F.transform(pairs, lambda e: F.concat(e["key"].cast("string"), F.lit(":"), F.round(e["value"], 3).cast("string"))), " ")
    return shares(part, ["turn"], 0.2).select("turn", text.alias("clusters"), F.size("clusters").cast("long").alias("k"))


def _member_sql() -> str:
    s, q = _start_sql()
    return s.ending(f"SELECT turn, string_agg(CAST(t AS VARCHAR), ' ' ORDER BY q DESC, t) AS clusters FROM {q} WHERE q >= 0.1 GROUP BY turn")


@query(_member_sql())
def membership_lists(spark, d):
    part = bind(turn_role(spark, d), presets.single("turn", "role"), {"T": 3}).parts["T"]
    return memberships(part, ["turn"], 0.1).select("turn", F.array_join(F.transform("clusters", lambda x: x["t"].cast("string")), " ").alias("clusters"))


@query("SELECT event_type, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events GROUP BY ALL")
def json_k_by_type(spark, d):
    rows = read_table(spark, d, "events").select("event_type", F.from_json("props", "k long")["k"].alias("k"))
    return rows.groupBy("event_type", "k").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT count(*) AS sent, count(*) FILTER (WHERE day >= d) AS kept, count(*) FILTER (WHERE day < d) AS late FROM (SELECT date_trunc('day', ts) AS day, (SELECT date_trunc('day', MIN(ts) + (MAX(ts) - MIN(ts)) / 2) FROM events) AS d FROM events)")
def events_late_rows(spark, d):
    """The later days' events are sent first; when the earlier days arrive, the watermark has passed their windows.

    The engine drops rows by the watermark of the batch before the last, so the latest event comes in a batch of its own between.
    """
    events = read_table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    middle = events.agg(F.expr("date_trunc('day', timestamp_micros((unix_micros(min(ts)) + unix_micros(max(ts))) div 2))").alias("m")).first()["m"]
    folder = scratch_path(spark, "late-events")
    last_event = F.col("event_id") == events.agg(F.max_by("event_id", F.struct("ts", "event_id")).alias("m")).first()["m"]
    later = F.col("ts") >= F.lit(middle)
    for part in (later & ~last_event, last_event, ~later):  # files are read in the order they were written
        events.where(part).select("event_type", "ts").coalesce(1).write.mode("append").parquet(folder)
    stream = spark.readStream.schema("event_type string, ts timestamp").option("maxFilesPerTrigger", 1).parquet(folder)
    cells = streams.windowed_joint(stream, ["event_type"], "1 day", watermark="1 second")
    out = streams.drain(cells.withColumn("at", F.unix_timestamp("start")), "update")
    last = out.groupBy("at", "event_type").agg(F.max("n").alias("n"))
    return streams.late_rows(events, last)


@query("WITH l AS (SELECT turn, row_number() OVER (ORDER BY turn) - 1 AS i FROM (SELECT DISTINCT turn FROM conversations)) SELECT c.turn, c.role, i % 3 AS t, count(*) AS n FROM conversations c JOIN l USING (turn) GROUP BY ALL")
def stream_labels(spark, d):
    """Arriving rows get the label of a stored table, which has every turn, also one whose roles are all null. Rows without a turn have no label and stay out."""
    part = start_table(build_joint(read_table(spark, d, "conversations"), ["turn"]), ["turn"], 3)
    rows = streams.event_stream(spark, d, "conversations", None).select("turn", "role").where("turn IS NOT NULL")
    counted = streams.label_stream(rows, part, ["turn"]).groupBy("turn", "role", F.col("t").cast("long").alias("t")).agg(F.count(F.lit(1)).alias("n"))
    return streams.drain(counted)


EDGES = ((0, 10), (10, 20), (20, 30), (30, 40), (40, 51))


@query("WITH e(bin, lo, hi) AS (VALUES " + ", ".join(f"({i}::BIGINT, {a}, {b})" for i, (a, b) in enumerate(EDGES)) + ") SELECT bin, l_returnflag, count(*) AS n FROM lineitem JOIN e ON l_quantity >= lo AND l_quantity < hi GROUP BY ALL")
def bins_range_join(spark, d):
    """Numeric values to bins by a range join; the edges are a short list."""
    edges = spark.range(1).select(F.inline(F.array(*[F.struct(F.lit(i).cast("long").alias("bin"), F.lit(float(a)).alias("lo"), F.lit(float(b)).alias("hi")) for i, (a, b) in enumerate(EDGES)])))
    rows = read_table(spark, d, "lineitem").select("l_quantity", "l_returnflag")
    joined = rows.join(F.broadcast(edges), (F.col("l_quantity") >= F.col("lo")) & (F.col("l_quantity") < F.col("hi")))
    return joined.groupBy("bin", "l_returnflag").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT o_orderpriority, CAST(r AS BIGINT) AS rank, c_mktsegment, n FROM (SELECT o_orderpriority, c_mktsegment, count(*) AS n, row_number() OVER (PARTITION BY o_orderpriority ORDER BY count(*) DESC, c_mktsegment) AS r FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1, 2) WHERE r <= 2")
def top_by_group(spark, d):
    pairs = read_table(spark, d, "orders").join(read_table(spark, d, "customer"), F.col("o_custkey") == F.col("c_custkey"))
    counts = pairs.groupBy("o_orderpriority", "c_mktsegment").agg(F.count(F.lit(1)).alias("n"))
    order = Window.partitionBy("o_orderpriority").orderBy(F.desc("n"), "c_mktsegment")
    return counts.withColumn("rank", F.row_number().over(order).cast("long")).where("rank <= 2").select("o_orderpriority", "rank", "c_mktsegment", "n")


@query(
    "SELECT 'with orders' AS kind, count(*) AS n FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders) UNION ALL SELECT 'without orders', count(*) FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders) "
    "UNION ALL SELECT 'unlabelled documents', count(*) FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)"
)
def semi_anti_panel(spark, d):
    customer, orders = read_table(spark, d, "customer"), read_table(spark, d, "orders").select(F.col("o_custkey").alias("c_custkey"))
    kinds = [("with orders", customer.join(orders, "c_custkey", "left_semi")), ("without orders", customer.join(orders, "c_custkey", "left_anti"))]
    kinds.append(("unlabelled documents", read_table(spark, d, "documents").join(read_table(spark, d, "labels"), "doc_id", "left_anti")))
    out = None
    for name, rows in kinds:
        one = rows.agg(F.count(F.lit(1)).alias("n")).select(F.lit(name).alias("kind"), "n")
        out = one if out is None else out.unionByName(one)
    return out


@query(f"WITH j AS ({TURN_ROLE}) SELECT round(-SUM(CASE WHEN p > 0 THEN p * ln(p) ELSE 0 END), 6) AS h, round(SUM(p * ln(p / 0.5)), 6) AS kl_half FROM j")
def sql_functions_panel(spark, d):
    sql_functions.register(spark)
    turn_role(spark, d).createOrReplaceTempView("partnet_cells")
    return spark.sql("SELECT round(-sum(xlogx(p)), 6) AS h, round(sum(kl_term(p, 0.5D)), 6) AS kl_half FROM partnet_cells")


NATIONS_FROM = "lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey"


@query(f"WITH j AS ({cells_sql(NATIONS_FROM, ('c_nationkey', 's_nationkey'))}) SELECT round({mi_sql(('c_nationkey',), ('s_nationkey',))}, 6) + 0.0 AS mutual_info, round((SELECT (count(DISTINCT c_nationkey) - 1) * (count(DISTINCT s_nationkey) - 1) / (2 * SUM(n) * ln(2)) FROM j), 6) AS bias")
def custnation_suppnation_mi(spark, d):
    lines = read_table(spark, d, "lineitem").select("l_orderkey", "l_suppkey")
    orders = read_table(spark, d, "orders").select("o_orderkey", "o_custkey")
    rows = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    rows = rows.join(read_table(spark, d, "customer").select("c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey"))
    rows = rows.join(read_table(spark, d, "supplier").select("s_suppkey", "s_nationkey"), F.col("l_suppkey") == F.col("s_suppkey"))
    cells = build_joint(rows, ["c_nationkey", "s_nationkey"])
    return mi_panel_row(cells, "c_nationkey", "s_nationkey", "nations").select(rounded("mutual_info").alias("mutual_info"), F.round("bias", 6).alias("bias"))


@query(
    "WITH x AS (SELECT label, unnest(range(1, 65)) AS dim, unnest(embedding) AS v FROM embeddings), "
    f"j AS ({cells_sql('(SELECT label, dim * 2 + CASE WHEN v >= 0 THEN 1 ELSE 0 END AS cell FROM x)', ('label', 'cell'))}) SELECT round({mi_sql(('label',), ('cell',))}, 6) + 0.0 AS mutual_info"
)
def embedding_sign_mi(spark, d):
    rows = read_table(spark, d, "embeddings").select("label", F.posexplode("embedding").alias("i", "v"))
    cells = build_joint(rows.select("label", ((F.col("i") + 1) * 2 + F.when(F.col("v") >= 0, 1).otherwise(0)).alias("cell")), ["label", "cell"])
    return mutual_info(cells, ["label"], ["cell"]).select(rounded("mutual_info").alias("mutual_info"))




@query(
    "WITH n AS (SELECT event_type, user_id, count(*) AS n FROM events GROUP BY ALL) SELECT event_type, user_id, n, CAST(ntile(4) OVER o AS BIGINT) AS quarter, round(percent_rank() OVER (PARTITION BY event_type ORDER BY n), 6) AS share_below, coalesce(n - lag(n) OVER o, 0) AS step "
    "FROM n WINDOW o AS (PARTITION BY event_type ORDER BY n, user_id)"
)
def window_panel(spark, d):
    """Users in quarters by their events of a type, with the share of users below and the step from the one before."""
    counts = read_table(spark, d, "events").groupBy("event_type", "user_id").agg(F.count(F.lit(1)).alias("n"))
    order = Window.partitionBy("event_type").orderBy("n", "user_id")
    below = F.percent_rank().over(Window.partitionBy("event_type").orderBy("n"))
    return counts.select("event_type", "user_id", "n", F.ntile(4).over(order).cast("long").alias("quarter"), F.round(below, 6).alias("share_below"), F.coalesce(F.col("n") - F.lag("n").over(order), F.lit(0)).alias("step"))


@query("WITH j AS (" + TURN_ROLE + ") SELECT dense_rank() OVER (ORDER BY turn) - 1 AS turn, dense_rank() OVER (ORDER BY role) - 1 AS role, round(p, 9) AS p FROM j")
def encoded_joint(spark, d):
    """A joint of whole-number codes in the order of the values."""
    coded, _ = encode(turn_role(spark, d), ["turn", "role"])
    return coded.select(F.col("turn").cast("long").alias("turn"), F.col("role").cast("long").alias("role"), F.round("p", 9).alias("p"))


@query(f"WITH j AS ({cells_sql('events', ('event_type', 'user_id'))}) SELECT 3::BIGINT AS batches, CAST((SELECT SUM(n) FROM j) AS BIGINT) AS n, round({mi_sql(('event_type',), ('user_id',))}, 6) + 0.0 AS mutual_info")
def events_incremental(spark, d):
    """Counts added up batch by batch, with the measure taken anew after each."""
    events, folder = read_table(spark, d, "events").select("event_type", "user_id", "event_id"), scratch_path(spark, "event-parts")
    for k in range(3):
        events.where(F.pmod("event_id", F.lit(3)) == k).select("event_type", "user_id").coalesce(1).write.mode("append").parquet(folder)
    state: dict = {}

    def refit(cells, previous):
        one = mutual_info(normalise(cells), ["event_type"], ["user_id"]).first()["mutual_info"]
        return {"batches": (previous or {"batches": 0})["batches"] + 1, "mutual_info": one}

    step = streams.resolve_each_batch(refit, state)
    kinds = ", ".join(f"{c} {t}" for c, t in events.select("event_type", "user_id").dtypes)
    rows = spark.readStream.schema(kinds).option("maxFilesPerTrigger", 1).parquet(folder)
    counted = lambda batch, i: step(batch.groupBy("event_type", "user_id").agg(F.count(F.lit(1)).alias("n")), i)
    rows.writeStream.foreachBatch(counted).option("checkpointLocation", scratch_path(spark, "event-state")).trigger(availableNow=True).start().awaitTermination()
    total = state["cells"].agg(F.sum("n").alias("n"))
    return total.select(F.lit(state["model"]["batches"]).cast("long").alias("batches"), "n", rounded(F.lit(state["model"]["mutual_info"])).alias("mutual_info"))
