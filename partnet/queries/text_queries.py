"""Text preparation, selection of words, and the text workloads."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from partnet import workloads
from partnet.functions.expr import rounded
from partnet.operators import apply, text
from partnet.operators.info import mutual_info
from partnet.operators.joint import build_joint, normalise, ranked
from partnet.operators.model import Model, log_partition
from partnet.operators.solve import labelled_table, run_sweeps
from partnet.plans import presets
from partnet.plans.graph import BottleneckSpec, TradeOff
from partnet.plans.sweep_sql import AnnealScript, LcgScript, SweepScript
from partnet.queries.info_queries import TURN_ROLE, WORDS_SQL, cells_sql, mi_sql, turn_role
from partnet.sources.tables import cut_lineage, read_table, scratch_path

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):
    def keep(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLES[f.__name__] = sql
        return f

    return keep


STOPS = ", ".join(f"'{w}'" for w in text.STOP_WORDS)
KEPT_SQL = f"SELECT * FROM ({WORDS_SQL}) WHERE w NOT IN ({STOPS})"
LINES_SQL = "SELECT doc_id, unnest(list_distinct(string_split(text, chr(10)))) AS line FROM documents"


HEADERLESS_SQL = (
    f"SELECT doc_id, lang, source, w FROM (WITH shared AS (SELECT line FROM ({LINES_SQL}) WHERE trim(line) <> '' GROUP BY line HAVING count(DISTINCT doc_id) >= 5), "
    "l AS (SELECT doc_id, lang, source, unnest(string_split(text, chr(10))) AS line FROM documents), kept AS (SELECT * FROM l WHERE line NOT IN (SELECT line FROM shared)) "
    "SELECT doc_id, lang, source, trim(w, '.,;:!?()\"') AS w FROM (SELECT doc_id, lang, source, unnest(regexp_split_to_array(lower(line), '\\s+')) AS w FROM kept)) "
    f"WHERE regexp_matches(w, '^\\p{{L}}+$') AND w NOT IN ({STOPS})"
)


def ranked_sql(category: str, kept: str = KEPT_SQL) -> str:
    """j, a, b, r: joint of words and a category, and words ranked by contribution."""
    return (
        f"j AS MATERIALIZED ({cells_sql(f'(SELECT w, {category} AS c FROM ({kept}))', ('w', 'c'))}), a AS (SELECT w, SUM(p) AS pv FROM j GROUP BY w), b AS (SELECT c, SUM(p) AS pc FROM j GROUP BY c), "
        "r AS MATERIALIZED (SELECT w, pv, contribution, row_number() OVER (ORDER BY contribution DESC, w) AS rank FROM (SELECT w, pv, round(SUM(p * ln(p / (pv * pc))) / ln(2), 12) AS contribution FROM j JOIN a USING (w) JOIN b USING (c) GROUP BY w, pv))"
    )


CATEGORIES = {"lang": "lang", "source": "source", "langsource": "concat_ws('/', lang, source)"}


def category(name: str):
    return {"lang": F.col("lang"), "source": F.col("source"), "langsource": F.concat_ws("/", "lang", "source")}[name]


def words(spark: SparkSession, d: str, name: str) -> DataFrame:
    return text.word_category_joint(read_table(spark, d, "documents"), category(name))


@query(f"SELECT w, count(*) AS n, count(DISTINCT doc_id) AS docs FROM ({KEPT_SQL}) GROUP BY w")
def tokens_clean(spark, d):
    rows = text.tokens(read_table(spark, d, "documents"), "doc_id", "text")
    return rows.groupBy("w").agg(F.count(F.lit(1)).alias("n"), F.count_distinct("doc_id").alias("docs"))


@query(
    f"WITH shared AS (SELECT line FROM ({LINES_SQL}) WHERE trim(line) <> '' GROUP BY line HAVING count(DISTINCT doc_id) >= 5), "
    "l AS (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents), kept AS (SELECT * FROM l WHERE line NOT IN (SELECT line FROM shared)), "
    "w AS (SELECT trim(w, '.,;:!?()\"') AS w FROM (SELECT unnest(regexp_split_to_array(lower(line), '\\s+')) AS w FROM kept)) "
    f"SELECT w, count(*) AS n FROM w WHERE regexp_matches(w, '^\\p{{L}}+$') AND w NOT IN ({STOPS}) GROUP BY w"
)
def tokens_without_boilerplate(spark, d):
    return text.tokens(read_table(spark, d, "documents"), "doc_id", "text", boilerplate_min_docs=5).groupBy("w").agg(F.count(F.lit(1)).alias("n"))


@query(f"SELECT line, count(DISTINCT doc_id) AS docs FROM ({LINES_SQL}) WHERE trim(line) <> '' GROUP BY line HAVING count(DISTINCT doc_id) >= 5")
def boilerplate_lines(spark, d):
    return text.boilerplate_lines(read_table(spark, d, "documents"), "doc_id", "text", 5)


@query(f"SELECT w, c, n FROM ({cells_sql(f'(SELECT w, lang AS c FROM ({KEPT_SQL}))', ('w', 'c'))})")
def word_category_joint(spark, d):
    return words(spark, d, "lang").select("w", "c", "n")


def _top(name: str) -> None:
    def run(spark, d):
        top = text.informative_values(words(spark, d, name), "w", "c", 300)
        return top.select("w", F.round("p", 9).alias("p"), rounded("contribution", 8).alias("contribution"))

    run.__name__ = f"informative_top300_{name}"
    QUERIES[run.__name__] = run
    ORACLES[run.__name__] = f"WITH {ranked_sql(CATEGORIES[name])} SELECT w, round(pv, 9) AS p, round(contribution, 8) + 0.0 AS contribution FROM r WHERE rank <= 300"


for _name in CATEGORIES:
    _top(_name)


@query(
    f"WITH {ranked_sql('lang')}, s AS (SELECT rank, SUM(contribution) OVER (ORDER BY rank) AS reached, SUM(contribution) OVER () AS whole FROM r) "
    "SELECT MIN(rank) FILTER (WHERE reached >= 0.9 * whole) AS values_needed, count(*) AS values FROM s"
)
def coverage_90(spark, d):
    return text.coverage(words(spark, d, "lang"), "w", "c", 0.9)


@query(
    f"WITH {ranked_sql(CATEGORIES['langsource'])}, s AS (SELECT w, c, n / SUM(n) OVER () AS p FROM j JOIN r USING (w) WHERE rank <= 300) "
    f"SELECT round({mi_sql(('w',), ('c',), 's')}, 6) + 0.0 AS mutual_info, (SELECT count(DISTINCT c) FROM s) AS categories"
)
def renormalised_mi(spark, d):
    cells = workloads.text_joint(read_table(spark, d, "documents"))
    return mutual_info(cells, ["w"], ["c"]).crossJoin(cells.agg(F.count_distinct("c").alias("categories"))).select(rounded("mutual_info").alias("mutual_info"), "categories")


def _two_tops(how: str) -> str:
    one, two = (f"SELECT w FROM (WITH {ranked_sql(CATEGORIES[n])} SELECT w FROM r WHERE rank <= 300)" for n in ("lang", "source"))
    return f"{one} {how} {two}"


def tops(spark, d) -> tuple[DataFrame, DataFrame]:
    """The words that say most about the language and about the source, from one counting of the texts."""
    rows = text.tokens(read_table(spark, d, "documents"), "doc_id", "text", ["lang", "source"])
    counted = cut_lineage(rows.groupBy("w", "lang", "source").agg(F.count(F.lit(1)).alias("k")))
    return tuple(text.informative_values(build_joint(counted, ["w", c], "k"), "w", c, 300).select("w") for c in ("lang", "source"))


@query(_two_tops("INTERSECT"))
def word_set_intersection(spark, d):
    one, two = tops(spark, d)
    return one.intersect(two)


@query(_two_tops("EXCEPT"))
def word_set_difference(spark, d):
    one, two = tops(spark, d)
    return one.exceptAll(two)


@query(
    "WITH b AS (SELECT page_id, regexp_replace(regexp_replace(regexp_replace(html, '<script[^>]*>.*?</script>|<style[^>]*>.*?</style>', ' ', 'gs'), '<[^>]*>', ' ', 'g'), '&[#a-zA-Z0-9]+;', ' ', 'g') AS t FROM pages), "
    "w AS (SELECT page_id, trim(w, '.,;:!?()\"') AS w FROM (SELECT page_id, unnest(regexp_split_to_array(lower(t), '\\s+')) AS w FROM b)) "
    "SELECT page_id, count(*) AS n, count(DISTINCT w) AS distinct_words FROM w WHERE regexp_matches(w, '^\\p{L}+$') GROUP BY page_id"
)
def pages_text_tokens(spark, d):
    pages = read_table(spark, d, "pages").select("page_id", text.strip_tags(F.col("html")).alias("text"))
    return text.tokens(pages, "page_id", "text", stop=()).groupBy("page_id").agg(F.count(F.lit(1)).alias("n"), F.count_distinct("w").alias("distinct_words"))


def _rollup_sql() -> str:
    rows = [f"SELECT '{n}' AS category, round({mi_sql(('w',), ('c',), t)}, 6) + 0.0 AS mutual_info FROM (SELECT 1)" for n, t in (("lang", "jl"), ("lang+source", "js"))]
    return f"WITH jl AS ({cells_sql(f'(SELECT w, lang AS c FROM ({KEPT_SQL}))', ('w', 'c'))}), js AS ({cells_sql(f'(SELECT w, lang || chr(47) || source AS c FROM ({KEPT_SQL}))', ('w', 'c'))}) " + " UNION ALL ".join(rows)


@query(_rollup_sql())
def rollup_lang_source_info(spark, d):
    """Information of words about each level of the category hierarchy."""
    out = None
    for label, name in (("lang", "lang"), ("lang+source", "langsource")):
        one = mutual_info(words(spark, d, name), ["w"], ["c"]).select(F.lit(label).alias("category"), rounded("mutual_info").alias("mutual_info"))
        out = one if out is None else out.unionByName(one)
    return out


# --- planted matrix ---

PLANTED_SQL = (
    "SELECT a, b, n, n / SUM(n) OVER () AS p FROM (SELECT i // 20 AS a, i % 20 AS b, "
    f"[{', '.join(str(list(map(float, r))) for r in workloads.LEVELS)}][(i // 20) % 6 + 1][(i % 20) % 3 + 1] * (1 + 0.05 * ((7 * (i // 20) + 13 * (i % 20)) % 5 - 2)) AS n FROM (SELECT range AS i FROM range(1600)))"
)


def planted(spark: SparkSession) -> DataFrame:
    return workloads.planted_joint(spark)


# --- known groups: languages and sources by the words that are commonest in each language ---

HOME_WORDS = 5
KNOWN_SQL = (
    f"WITH k AS MATERIALIZED (SELECT lang, source, w, count(*)::DOUBLE AS n FROM ({KEPT_SQL}) WHERE lang IS NOT NULL AND source IS NOT NULL GROUP BY lang, source, w), "
    "h AS (SELECT w, lang AS home, n FROM (SELECT w, lang, SUM(n) AS n, row_number() OVER (PARTITION BY w ORDER BY SUM(n) DESC, lang) AS r FROM k GROUP BY w, lang) WHERE r = 1), "
    f"top AS (SELECT w, home FROM (SELECT w, home, row_number() OVER (PARTITION BY home ORDER BY n DESC, w) AS r FROM h) WHERE r <= {HOME_WORDS}) "
    "SELECT concat_ws('/', lang, source) AS a, w AS b, lang, home, n, n / SUM(n) OVER () AS p FROM k JOIN top USING (w)"
)


def known(spark: SparkSession, d: str) -> DataFrame:
    """(a, b, lang, home, n, p): categories lang/source by words, with the group that each is known to belong to.

    A word's home is the language that has most of it; of each home the commonest words are taken.
    """
    counted = cut_lineage(build_joint(text.tokens(read_table(spark, d, "documents"), "doc_id", "text", ["lang", "source"]), ["w", "lang", "source"]))
    homes = counted.groupBy("w", "lang").agg(F.sum("n").alias("n")).groupBy("w").agg(F.min(F.struct((-F.col("n")).alias("less"), "lang")).alias("h"))
    order = Window.partitionBy("home").orderBy("less", "w")
    top = homes.select("w", F.col("h.lang").alias("home"), F.col("h.less").alias("less")).withColumn("r", F.row_number().over(order)).where(F.col("r") <= HOME_WORDS)
    cells = counted.join(F.broadcast(top.select("w", "home")), "w").select(F.concat_ws("/", "lang", "source").alias("a"), F.col("w").alias("b"), "lang", "home", "n")
    return cut_lineage(normalise(cells))


@query(f"SELECT a, b, round(p, 12) AS p FROM ({KNOWN_SQL})")
def planted_matrix(spark, d):
    return known(spark, d).select("a", "b", F.round("p", 12).alias("p"))


#: the same with the places of both languages in their order
GROUPED_SQL = f"WITH j AS MATERIALIZED ({KNOWN_SQL}), l AS (SELECT lang, row_number() OVER (ORDER BY lang) - 1 AS i FROM (SELECT DISTINCT lang FROM j)) SELECT a, b, x.i AS ta, y.i AS tb, p FROM j JOIN l x ON j.lang = x.lang JOIN l y ON j.home = y.lang"


def hard_known(cells: DataFrame) -> Model:
    """The known groups as tables: languages in their order."""
    langs = cut_lineage(ranked(cells.select("lang").distinct(), ["lang"]).select("lang", F.col("i").cast("int").alias("t")))
    k = langs.count()
    of = lambda v, lang: labelled_table(cells.select(v, F.col(lang).alias("lang")).distinct().join(langs, "lang"), [v], k)
    return Model(presets.symmetric("a", "b"), cells.select("a", "b", "p"), {"TA": of("a", "lang"), "TB": of("b", "home")}, {"TA": k, "TB": k})


@query(f"SELECT ta, tb, round(SUM(p), 9) AS p FROM ({GROUPED_SQL}) GROUP BY 1, 2")
def block_joint_planted(spark, d):
    return apply.block_joint(hard_known(known(spark, d)), "TA", "TB").where("p > 0").select(F.col("TA").cast("long").alias("ta"), F.col("TB").cast("long").alias("tb"), F.round("p", 9).alias("p"))


@query(
    f"WITH g AS MATERIALIZED ({GROUPED_SQL}), r AS (SELECT a, row_number() OVER (ORDER BY ta, a) - 1 AS row_pos FROM (SELECT DISTINCT a, ta FROM g)), c AS (SELECT b, row_number() OVER (ORDER BY tb, b) - 1 AS col_pos FROM (SELECT DISTINCT b, tb FROM g)) "
    "SELECT row_pos, col_pos, ta AS row_cluster, tb AS col_cluster, round(p, 12) AS p FROM g JOIN r USING (a) JOIN c USING (b)"
)
def permuted_planted(spark, d):
    """The matrix of known groups with languages side by side."""
    model = hard_known(known(spark, d))
    rows, cols = apply.assign(model.parts["TA"], ["a"]), apply.assign(model.parts["TB"], ["b"])
    cells = apply.permuted(model.joint, rows, cols, "a", "b")
    return cells.select(*[F.col(c).cast("long").alias(c) for c in ("row_pos", "col_pos", "row_cluster", "col_cluster")], F.round("p", 12).alias("p"))


#: full anneals until the tables rest, with seeded noise or noise along the leading direction; other engines can't repeat them
PLANTED_RUNS = {f"uniform_{s}": {"seed": s, "noise": "uniform", "last": 500.0} for s in range(3)} | {"aligned": {"noise": "spectral", "last": 500.0}}
#: a short anneal that any engine can repeat: noise of whole numbers, a fixed number of sweeps at each weight
PLANTED_FIXED = {"weights": [600.0, 660.0, 720.0, 790.0], "sweeps": 6}
PAIR, CURVE_COLUMNS, TREE_COLUMNS = presets.symmetric("a", "b"), ("compression", "relevance", "compression_frac", "relevance_frac"), ("mass",)


def script(spec, joint_sql: str, fixed: dict) -> AnnealScript:
    return AnnealScript(spec, joint_sql).anneal(fixed["weights"], fixed["sweeps"], max_k=fixed.get("max_k", 32))


def as_curve(rows: DataFrame) -> DataFrame:
    return rows.select(F.col("step").cast("long").alias("step"), "beta", "var", F.col("k").cast("long").alias("k"), *[rounded(c).alias(c) for c in CURVE_COLUMNS], "split")


def as_tree(rows: DataFrame) -> DataFrame:
    return rows.select("var", "node_id", "parent_id", F.col("level").cast("long").alias("level"), "beta", F.round("mass", 6).alias("mass"), "split")


@query(script(PAIR, KNOWN_SQL, PLANTED_FIXED).tree())
def anneal_planted_tree(spark, d):
    return as_tree(workloads.anneal_trees(known(spark, d), PAIR, {"fixed": PLANTED_FIXED}))


@query(script(PAIR, KNOWN_SQL, PLANTED_FIXED).curve())
def anneal_planted_curve(spark, d):
    """Cluster counts 2 x 2, then 4 x 4 as there are languages, then splits that add little."""
    return as_curve(workloads.anneal_curves(known(spark, d), PAIR, {"fixed": PLANTED_FIXED}))


@query(f"SELECT var, count(*) AS nodes, round(SUM(mass), 6) AS mass FROM ({script(PAIR, PLANTED_SQL, PLANTED_FIXED).tree()}) WHERE level = 1 GROUP BY var")
def tree_by_level(spark, d):
    """The tree written in folders by level; reading one level opens one folder."""
    path = scratch_path(spark, "tree")
    workloads.anneal_trees(planted(spark), PAIR, {"fixed": PLANTED_FIXED}).write.partitionBy("level").parquet(path)
    level = spark.read.parquet(path).where("level = 1")
    return level.groupBy("var").agg(F.count(F.lit(1)).alias("nodes"), F.round(F.sum(F.round("mass", 6)), 6).alias("mass"))


@query()
def anneal_planted_runs(spark, d):
    return workloads.anneal_curves(known(spark, d), PAIR, PLANTED_RUNS)


SINGLE_FIXED = {"weights": [0.95, 1.2], "sweeps": 20, "max_k": 2}


@query(script(presets.single("a", "b"), KNOWN_SQL, SINGLE_FIXED).curve())
def anneal_planted_single(spark, d):
    """First split of a single bottleneck next to the predicted weight: 1.0035 on sf0.01's matrix of known groups."""
    return as_curve(workloads.anneal_curves(known(spark, d), presets.single("a", "b"), {"fixed": SINGLE_FIXED}))


def model_of(rows: DataFrame, cells: DataFrame, spec: BottleneckSpec) -> Model:
    """A model from long tables (var, value, t, q) of one-source clusters; values get the joint's type back."""
    rows, cells, kinds = cut_lineage(rows), cut_lineage(cells.select(*spec.observed, "p")), dict(cells.dtypes)
    sizes = {r["var"]: r["k"] for r in rows.groupBy("var").agg((F.max("t") + 1).alias("k")).collect()}
    parts = {}
    for t in spec.clusters:
        v = spec.sources(t)[0]
        ordered = rows.where(F.col("var") == t).groupBy("value").agg(F.array_sort(F.collect_list(F.struct("t", "q"))).alias("s"))
        parts[t] = ordered.select(F.col("value").cast(kinds[v]).alias(v), F.transform("s", lambda x: x["q"]).alias("q"))
    return Model(spec, cells, parts, sizes)


def _found_sql() -> str:
    """The matrix of known groups in the order of the clusters that the anneal finds."""
    s = script(PAIR, KNOWN_SQL, PLANTED_FIXED)
    hard = lambda v, t: s.add(f"SELECT {v}, t, row_number() OVER (ORDER BY t, {v}) - 1 AS pos FROM (SELECT {v}, t, row_number() OVER (PARTITION BY {v} ORDER BY round(q, 9) DESC, t) AS r FROM {s.current[t]}) WHERE r = 1", "hard")
    rows, cols = hard("a", "TA"), hard("b", "TB")
    return s.ending(f"SELECT r.pos AS row_pos, c.pos AS col_pos, CAST(r.t AS BIGINT) AS row_cluster, CAST(c.t AS BIGINT) AS col_cluster, round(j.p, 12) AS p FROM {s.joint} j JOIN {rows} r USING (a) JOIN {cols} c USING (b)")


@query(_found_sql())
def permuted_found(spark, d):
    """The matrix of known groups in the order of the clusters found, not of those known."""
    cells = known(spark, d).select("a", "b", "p")
    model = model_of(workloads.anneal_tables(cells, PAIR, {"fixed": PLANTED_FIXED}), cells, PAIR)
    rows, cols = apply.assign(model.parts["TA"], ["a"]), apply.assign(model.parts["TB"], ["b"])
    ordered = apply.permuted(cells, rows, cols, "a", "b")
    return ordered.select(*[F.col(c).cast("long").alias(c) for c in ("row_pos", "col_pos", "row_cluster", "col_cluster")], F.round("p", 12).alias("p"))


# --- text workloads: fits run on the selected joint, without the header lines that texts share ---

WORDS = presets.symmetric("w", "c")
HEADER_DOCS = 5
#: full anneal, with noise along the leading direction
TEXT_RUN = {"first": 5.0, "rate": 1.15, "last": 130.0, "max_k": 16, "noise": "spectral", "max_iter": 80}
TEXT_FIXED = {"weights": [200.0, 220.0, 242.0, 266.0], "sweeps": 6, "max_k": 8}
#: the same, then back to a weight at which words are shared
SOFT_FIXED = {"weights": [200.0, 220.0, 242.0, 5.0], "sweeps": 6, "max_k": 4}
TEXT_SQL = f"WITH {ranked_sql(CATEGORIES['langsource'], HEADERLESS_SQL)} SELECT w, c, n / SUM(n) OVER () AS p FROM j JOIN r USING (w) WHERE rank <= 300"


def text_cells(spark: SparkSession, d: str) -> DataFrame:
    return workloads.text_joint(read_table(spark, d, "documents"), boilerplate_min_docs=HEADER_DOCS)


@query(f"WITH s AS ({TEXT_SQL}) SELECT round({mi_sql(('w',), ('c',), 's')}, 6) + 0.0 AS mutual_info, count(DISTINCT w) AS words, count(DISTINCT c) AS categories, count(*) AS cells FROM s")
def text_joint_without_headers(spark, d):
    cells = cut_lineage(text_cells(spark, d))
    sizes = cells.agg(F.count_distinct("w").alias("words"), F.count_distinct("c").alias("categories"), F.count(F.lit(1)).alias("cells"))
    return mutual_info(cells, ["w"], ["c"]).crossJoin(sizes).select(rounded("mutual_info").alias("mutual_info"), "words", "categories", "cells")


@query(script(WORDS, TEXT_SQL, TEXT_FIXED).tree())
def symmetric_text_tree(spark, d):
    return as_tree(workloads.anneal_trees(text_cells(spark, d), WORDS, {"fixed": TEXT_FIXED}))


@query(script(WORDS, TEXT_SQL, TEXT_FIXED).curve())
def text_curve(spark, d):
    return as_curve(workloads.anneal_curves(text_cells(spark, d), WORDS, {"fixed": TEXT_FIXED}))


@query()
def symmetric_text_runs(spark, d):
    """The full anneal of words and categories, to 16 clusters of words."""
    return workloads.anneal_curves(text_cells(spark, d), WORDS, {"text": TEXT_RUN})


def fitted(spark: SparkSession, d: str, settings: dict[str, dict]) -> tuple[DataFrame, DataFrame]:
    """(cells, long tables of the settings' runs) from one reading of the texts."""
    cells = cut_lineage(text_cells(spark, d).select("w", "c", "p"))
    return cells, workloads.anneal_tables(cells, WORDS, settings)


def text_model(spark: SparkSession, d: str) -> Model:
    cells, rows = fitted(spark, d, {"fixed": TEXT_FIXED})
    return model_of(rows, cells, WORDS)


def _link(s: AnnealScript) -> str:
    """(ta, tb, p_cond, is_best) block."""
    both = s.add(s.marginal(("TA", "TB")), "both")
    return s.add(f"SELECT ta, tb, p_cond, row_number() OVER (PARTITION BY ta ORDER BY round(p_cond, 9) DESC, tb) = 1 AS is_best FROM (SELECT TA AS ta, TB AS tb, p / SUM(p) OVER (PARTITION BY TA) AS p_cond FROM {both})", "link")


def _top5_sql() -> str:
    s = script(WORDS, TEXT_SQL, TEXT_FIXED)
    link = _link(s)
    top = s.add(f"SELECT q.t, row_number() OVER (PARTITION BY q.t ORDER BY round(q.q, 9) DESC, round(m.pu, 12) DESC, q.w) AS rank, q.w, q.q, m.pu FROM {s.current['TA']} q JOIN {s.mass['TA']} m USING (w)", "top")
    return s.ending(f"SELECT CAST(t AS BIGINT) AS t, rank, w, round(q, 6) + 0.0 AS q, round(pu, 9) AS pu, CAST(tb AS BIGINT) AS t_c, round(p_cond, 6) + 0.0 AS p_c FROM {top} JOIN {link} ON t = ta AND is_best WHERE rank <= 5")


@query(_top5_sql())
def text_top5_words(spark, d):
    """The five surest words of each word cluster, with the category cluster it predicts."""
    model = text_model(spark, d)
    best = apply.cluster_link(model, "TB", "TA").where("is_best").select(F.col("TA").alias("t"), F.col("TB").cast("long").alias("t_c"), rounded("p_cond").alias("p_c"))
    rows = apply.top_members(model, "TA", 5).join(best, "t")
    return rows.select(F.col("t").cast("long").alias("t"), F.col("rank").cast("long").alias("rank"), "w", rounded("q").alias("q"), F.round("pu", 9).alias("pu"), "t_c", "p_c")


def _link_sql() -> str:
    s = script(WORDS, TEXT_SQL, TEXT_FIXED)
    return s.ending(f"SELECT CAST(ta AS BIGINT) AS ta, CAST(tb AS BIGINT) AS tb, round(p_cond, 6) + 0.0 AS p_cond, is_best FROM {_link(s)}")


@query(_link_sql())
def cluster_link(spark, d):
    rows = apply.cluster_link(text_model(spark, d), "TB", "TA")
    return rows.select(F.col("TA").cast("long").alias("ta"), F.col("TB").cast("long").alias("tb"), rounded("p_cond").alias("p_cond"), "is_best")


def _profile_sql() -> str:
    s = script(WORDS, TEXT_SQL, TEXT_FIXED)
    both = s.add(s.marginal(("TA", "c")), "both")
    return s.ending(f"SELECT CAST(TA AS BIGINT) AS t, c, round(p / SUM(p) OVER (PARTITION BY TA), 6) + 0.0 AS p_cond FROM {both}")


@query(_profile_sql())
def cluster_profiles(spark, d):
    """What each cluster of words says about the categories."""
    return apply.profile(text_model(spark, d), "TA", "c").select(F.col("TA").cast("long").alias("t"), "c", rounded("p_cond").alias("p_cond"))


def _soft_sql() -> str:
    s = script(WORDS, TEXT_SQL, SOFT_FIXED)
    return s.ending(f"SELECT w, count(*) AS k, string_agg(CAST(t AS VARCHAR), ' ' ORDER BY t) AS t FROM {s.current['TA']} WHERE q >= 0.1 GROUP BY w HAVING count(*) > 1")


@query(_soft_sql())
def soft_words(spark, d):
    """Words with a share of a tenth or more in several clusters."""
    _, rows = fitted(spark, d, {"soft": SOFT_FIXED})
    shared = rows.where("var = 'TA' AND q >= 0.1").groupBy(F.col("value").alias("w")).agg(F.count(F.lit(1)).alias("k"), F.array_sort(F.collect_list("t")).alias("t"))
    return shared.where("k > 1").select("w", "k", F.array_join(F.transform("t", lambda x: x.cast("string")), " ").alias("t"))


def _hardness_sql() -> str:
    parts = []
    for run, fixed in (("early", SOFT_FIXED), ("late", TEXT_FIXED)):
        s = script(WORDS, TEXT_SQL, fixed)
        one = [f"SELECT '{run}' AS run, '{t}' AS var, AVG(top) AS mean_max, MIN(top) AS least_max, AVG(exp(h)) AS effective FROM (SELECT MAX(q) AS top, -SUM(CASE WHEN q > 0 THEN q * ln(q) ELSE 0 END) AS h FROM {s.current[t]} GROUP BY {v})" for t, v in (("TA", "w"), ("TB", "c"))]
        parts.append(f"SELECT * FROM ({s.ending(' UNION ALL '.join(one))})")
    return "SELECT run, var, round(mean_max, 6) AS mean_max, round(least_max, 6) AS least_max, round(effective, 6) AS effective FROM (" + " UNION ALL ".join(parts) + ")"


@query(_hardness_sql())
def hardness_text(spark, d):
    """How hard the clusters of words and of categories are, while words are shared and at the end, and over how many clusters a value spreads."""
    cells, rows = fitted(spark, d, {"early": SOFT_FIXED, "late": TEXT_FIXED})
    rows, out = cut_lineage(rows), None
    for run in ("early", "late"):
        model = model_of(rows.where(F.col("run") == run).drop("run"), cells, WORDS)
        for t in WORDS.clusters:
            one = apply.hardness(model.parts[t]).select(F.lit(run).alias("run"), F.lit(t).alias("var"), *[F.round(c, 6).alias(c) for c in ("mean_max", "least_max", "effective")])
            out = one if out is None else out.unionByName(one)
    return out


def _purity_sql() -> str:
    s = script(WORDS, TEXT_SQL, TEXT_FIXED)
    hard = s.add(f"SELECT c, split_part(c, '/', 1) AS g, t FROM (SELECT c, t, row_number() OVER (PARTITION BY c ORDER BY round(q, 9) DESC, t) AS r FROM {s.current['TB']}) WHERE r = 1", "hard")
    s.blocks.append(f"n AS MATERIALIZED (SELECT t, g, count(*)::DOUBLE AS n FROM {hard} GROUP BY t, g), x AS MATERIALIZED (SELECT t, SUM(n) AS m FROM n GROUP BY t), y AS MATERIALIZED (SELECT g, SUM(n) AS m FROM n GROUP BY g)")
    s.blocks.append(
        "z AS MATERIALIZED (SELECT (SELECT SUM(n) FROM n) AS total, (SELECT SUM(m) FROM (SELECT MAX(n) AS m FROM n GROUP BY t)) AS hit, (SELECT SUM(n * (n - 1) / 2) FROM n) AS together, (SELECT SUM(m * (m - 1) / 2) FROM x) AS px, (SELECT SUM(m * (m - 1) / 2) FROM y) AS py, "
        "(SELECT SUM(n * ln(n)) FROM n) AS lij, (SELECT SUM(m * ln(m)) FROM x) AS lx, (SELECT SUM(m * ln(m)) FROM y) AS ly)"
    )
    h = lambda c: f"(ln(total) - {c} / total)"
    expected = "px * py / greatest(total * (total - 1) / 2, 1.0)"
    return s.ending(
        f"SELECT round(hit / total, 6) AS purity, round(CASE WHEN {h('lx')} + {h('ly')} > 0 THEN 2 * ({h('lx')} + {h('ly')} - {h('lij')}) / ({h('lx')} + {h('ly')}) ELSE 1.0 END, 6) AS nmi, "
        f"round(CASE WHEN (px + py) / 2 <> {expected} THEN (together - {expected}) / ((px + py) / 2 - {expected}) ELSE 1.0 END, 6) AS adjusted_rand FROM z"
    )


@query(_purity_sql())
def purity_lang(spark, d):
    """Category clusters against the language in the category's name."""
    labels = apply.assign(text_model(spark, d).parts["TB"], ["c"]).withColumn("lang", F.split("c", "/")[0])
    return apply.agreement(labels, "lang").select(*[F.round(c, 6).alias(c) for c in ("purity", "nmi", "adjusted_rand")])


# --- parallel systems, equal budgets, ablations: fixed sweeps from starts of whole numbers ---


def measures_sql(s: LcgScript) -> list[tuple[str, str]]:
    """The names and scalar expressions of workloads.solve_panel's measures."""
    out, spec = [], s.spec
    for v in spec.observed:
        by = [t for t in spec.clusters if v not in spec.sources(t)]
        for t in by:
            out.append((f"I({t};{v})/I({','.join(spec.sources(t))};{v})", f"{s.mutual((t,), (v,))} / {s.mutual(spec.sources(t), (v,))}"))
        same = [t for t in by if spec.sources(t) == spec.sources(by[0])]
        if len(same) > 1:
            u = spec.sources(same[0])
            out.append((f"I({','.join(same)};{v})/I({','.join(u)};{v})", f"{s.mutual(tuple(same), (v,))} / {s.mutual(u, (v,))}"))
            out.append((f"I({';'.join(same[:2])})", f"{s.mutual((same[0],), (same[1],))} / ln(2)"))
    return out


def panel_sql(spec: BottleneckSpec, joint_sql: str, settings: dict[str, dict]) -> str:
    """run, objective, measure, value: of a setting's starts the one with the least objective."""
    rows, s = [], None
    for run, x in settings.items():
        trade, sizes = TradeOff(spec.objective, x["trade"]), {t: x["k"][i] for i, t in enumerate(spec.clusters)}
        for level in range(x["starts"]):
            s = s.restart(sizes, level) if s else LcgScript(spec, sizes, joint_sql, level)
            s.sweeps(x["sweeps"], trade, x.get("schedule", "async"), x.get("form"))
            own = s.add(f"SELECT {s.objective(trade)[2]} AS objective", "own")
            if x.get("hard"):
                for t in spec.clusters:
                    u = s.cols(spec.sources(t))
                    s.current[t] = s.add(f"SELECT {u}, t, CASE WHEN row_number() OVER (PARTITION BY {u} ORDER BY round(q, 12) DESC, t) = 1 THEN 1.0 ELSE 0.0 END AS q FROM {s.current[t]}", "q")
            rows += [f"SELECT '{run}' AS run, {level} AS start, objective, '{name}' AS measure, {value} AS value FROM {own}" for name, value in measures_sql(s)]
    whole = " UNION ALL ".join(rows)
    return s.ending(f"SELECT run, round(objective, 6) + 0.0 AS objective, measure, round(value, 6) + 0.0 AS value FROM (SELECT *, rank() OVER (PARTITION BY run ORDER BY objective, start) AS r FROM ({whole})) WHERE r = 1")


def as_panel(rows: DataFrame) -> DataFrame:
    return rows.select("run", rounded("objective").alias("objective"), "measure", rounded("value").alias("value"))


PARALLEL = presets.parallel("w", "c")
PANELS = {"k2_b5": {"k": [2, 2], "trade": 5.0, "sweeps": 8, "starts": 2}, "k4_b10": {"k": [4, 4], "trade": 10.0, "sweeps": 8, "starts": 2}, "k4_b10_hard": {"k": [4, 4], "trade": 10.0, "sweeps": 8, "starts": 1, "hard": True}}
PARALLEL_FIXED = {"weights": [5.0, 10.0, 20.0], "sweeps": 8, "max_k": 4}


@query(panel_sql(PARALLEL, TEXT_SQL, PANELS))
def parallel_text_panel(spark, d):
    """Two systems of clusters of words, each apart and together."""
    return as_panel(workloads.solve_panel(text_cells(spark, d), PARALLEL, PANELS))


@query(script(PARALLEL, TEXT_SQL, PARALLEL_FIXED).curve())
def parallel_text_curve(spark, d):
    """Information curves of the parallel form up to the second split: each system about the categories, and both together."""
    return as_curve(workloads.anneal_curves(text_cells(spark, d), PARALLEL, {"fixed": PARALLEL_FIXED}))


#: full parallel anneals on the joints with 80 and with 20 categories
PARALLEL_RUNS = {f"uniform_{s}": {"first": 1.5, "rate": 1.2, "last": 20.0, "max_k": 4, "seed": s, "noise": "uniform", "max_iter": 60} for s in range(2)}


@query()
def parallel_text_runs(spark, d):
    out = None
    for name in ("lang_source", "source"):
        cells = workloads.text_joint(read_table(spark, d, "documents"), name, boilerplate_min_docs=HEADER_DOCS)
        one = workloads.anneal_curves(cells, PARALLEL, PARALLEL_RUNS).withColumn("category", F.lit(name))
        out = one if out is None else out.unionByName(one)
    return out


BUDGETS = {"k8": {"k": [8], "trade": 10.0, "sweeps": 8, "starts": 1}, "k16": {"k": [16], "trade": 10.0, "sweeps": 8, "starts": 1}}


@query(panel_sql(presets.single("w", "c"), TEXT_SQL, BUDGETS))
def equal_budget(spark, d):
    """A single system with as many clusters as the pair has values in sum, and in product."""
    return as_panel(workloads.solve_panel(text_cells(spark, d), presets.single("w", "c"), BUDGETS))


#: order of updates, form of the update, target network, objective and hardness, on the planted matrix and that of known groups
ABLATIONS = {
    "parallel": (presets.parallel("a", "b"), {f"{s}_{w}": {"k": [3, 3], "trade": float(w), "schedule": s, "sweeps": 6, "starts": 1} for s in ("async", "sync") for w in (5, 20)}),
    "symmetric_a": (PAIR, {f"{f}": {"k": [6, 3], "trade": 80.0, "form": f, "sweeps": 6, "starts": 1} for f in ("collapsed", "literal")} | {"hard": {"k": [6, 3], "trade": 80.0, "sweeps": 6, "starts": 1, "hard": True}}),
    "symmetric_b": (presets.symmetric("a", "b", "b"), {"literal": {"k": [6, 3], "trade": 10.0, "sweeps": 6, "starts": 1}}),
    "l1_target_a": (presets.single("a", "b"), {"soft": {"k": [4], "trade": 20.0, "sweeps": 6, "starts": 2}, "hard": {"k": [4], "trade": 20.0, "sweeps": 6, "starts": 2, "hard": True}}),
    "l1_target_b": (presets.single("a", "b", target="b"), {"soft": {"k": [4], "trade": 0.95, "sweeps": 6, "starts": 2}}),
    "l2_target_a": (presets.single("a", "b", objective="gamma"), {"soft": {"k": [4], "trade": 20.0, "sweeps": 6, "starts": 2}}),
    "l2_target_b": (presets.single("a", "b", objective="gamma", target="b"), {"soft": {"k": [4], "trade": 20.0, "sweeps": 6, "starts": 2}}),
}


def _ablation_sql() -> str:
    return " UNION ALL ".join(f"SELECT '{name}' AS spec, * FROM ({panel_sql(spec, KNOWN_SQL, runs)})" for name, (spec, runs) in ABLATIONS.items())


def ablations(cells: DataFrame, runs: dict) -> DataFrame:
    out = None
    for name, (spec, settings) in runs.items():
        one = workloads.solve_panel(cells, spec, settings).withColumn("spec", F.lit(name))
        out = one if out is None else out.unionByName(one)
    return out


@query(_ablation_sql())
def ablation_grid(spark, d):
    rows = ablations(known(spark, d), ABLATIONS)
    return rows.select("spec", "run", rounded("objective").alias("objective"), "measure", rounded("value").alias("value"))


def to_rest(settings: dict) -> dict:
    """The same settings until the tables rest, from random starts; the converged flag tells which cycle."""
    return {run: {k: v for k, v in x.items() if k not in ("sweeps", "starts")} | {"max_iter": 400, "starts": 3, "seed": 4} for run, x in settings.items()}


@query()
def ablation_runs(spark, d):
    """The ablations to convergence, with the number of sweeps, on the planted matrix, on turns and roles and on the text joint."""
    every = {name: (spec, to_rest(runs)) for name, (spec, runs) in ABLATIONS.items()}
    orders = {f"{s}_{w}": {"trade": w, "schedule": s, "max_iter": 200, "starts": 2} for s in ("async", "sync") for w in (5.0, 20.0)}
    out = ablations(cut_lineage(planted(spark)), every).withColumn("joint", F.lit("planted"))
    small = {"parallel": (presets.parallel("turn", "role"), {k: x | {"k": [2, 2]} for k, x in orders.items()}), "symmetric_a": (presets.symmetric("turn", "role"), {k: x | {"k": [3, 2]} for k, x in orders.items()})}
    out = out.unionByName(ablations(cut_lineage(turn_role(spark, d)), small).withColumn("joint", F.lit("turn x role")))
    words = {"symmetric_a": (WORDS, {k: x | {"k": [4, 4], "starts": 1, "trade": 4 * x["trade"]} for k, x in orders.items()})}
    return out.unionByName(ablations(cut_lineage(text_cells(spark, d)), words).withColumn("joint", F.lit("text")))


def _log_z_sql() -> str:
    """ln Z of each value's update after two sweeps: the normaliser that the softmax divides by."""
    s = SweepScript(presets.single("turn", "role"), {"T": 3}, TURN_ROLE).sweeps(2, TradeOff.beta(5.0))
    s.update("T", TradeOff.beta(5.0))
    return s.ending(f"SELECT turn, round(MAX(s) + ln(SUM(exp(s - top))), 6) + 0.0 AS log_z FROM (SELECT *, MAX(s) OVER (PARTITION BY turn) AS top FROM {s.last_score}) GROUP BY turn")


@query(_log_z_sql())
def partition_function(spark, d):
    spec, trade = presets.single("turn", "role"), TradeOff.beta(5.0)
    model = run_sweeps(cut_lineage(turn_role(spark, d)), spec, {"T": 3}, trade, 2)
    return log_partition(model, "T", trade).select("turn", rounded("log_z").alias("log_z"))


@query(f"WITH j AS ({cells_sql('conversations', ('turn', 'role'))}) SELECT 'one cluster' AS \"end\", 0.0::DOUBLE AS information, 0.0::DOUBLE AS fraction UNION ALL SELECT 'uncompressed', round({mi_sql(('turn',), ('role',))}, 6), 1.0")
def endpoints(spark, d):
    return workloads.endpoints(turn_role(spark, d), "turn", "role").select("end", F.round("information", 6).alias("information"), "fraction")


def _kmeans_sql(k: int = 4, rounds: int = 8) -> str:
    b = [f"j AS MATERIALIZED ({TEXT_SQL})", "x AS MATERIALIZED (SELECT w, c, p / SUM(p) OVER (PARTITION BY w) AS x FROM j)", f"l0 AS MATERIALIZED (SELECT w, (row_number() OVER (ORDER BY w) - 1) % {k} AS t FROM (SELECT DISTINCT w FROM x))"]
    for i in range(rounds):
        b.append(f"m{i} AS MATERIALIZED (SELECT t, c, SUM(x) / (SELECT count(*) FROM l{i} l WHERE l.t = z.t) AS m FROM (SELECT * FROM x JOIN l{i} USING (w)) z GROUP BY t, c)")
        b.append(f"n{i} AS MATERIALIZED (SELECT t, SUM(m * m) AS norm FROM m{i} GROUP BY t)")
        b.append(f"e{i} AS MATERIALIZED (SELECT w, t, SUM(x * m) AS dot FROM x JOIN m{i} USING (c) GROUP BY w, t)")
        b.append(
            f"l{i + 1} AS MATERIALIZED (SELECT w, t FROM (SELECT w, t, row_number() OVER (PARTITION BY w ORDER BY round(norm - 2 * coalesce(dot, 0), 12), t) AS r FROM (SELECT DISTINCT w FROM x) CROSS JOIN n{i} LEFT JOIN e{i} USING (w, t)) WHERE r = 1)"
        )
    b.append(f"k AS MATERIALIZED (SELECT t, c, SUM(p) AS p FROM j JOIN l{rounds} USING (w) GROUP BY t, c)")
    kept, whole = mi_sql(("t",), ("c",), "k"), mi_sql(("w",), ("c",), "j")
    return "WITH " + ", ".join(b) + f" SELECT round({kept}, 6) + 0.0 AS mutual_info, round({kept} / {whole}, 6) + 0.0 AS relevance_frac"


@query(_kmeans_sql())
def kmeans_profiles(spark, d):
    """k-means labels of words by their category profiles, and what they keep."""
    cells = cut_lineage(text_cells(spark, d))
    rows = workloads.hard_relevance(cells, workloads.kmeans_profiles(cells, "w", "c", 4), "w", "c")
    return rows.select(rounded("mutual_info").alias("mutual_info"), rounded("relevance_frac").alias("relevance_frac"))


MULTI, MULTI_RUNS = presets.multi_target("w", ("lang", "quality")), {"k6": {"k": [6], "trade": 20.0, "sweeps": 6, "starts": 1}}
MULTI_SQL = (
    f"WITH rows AS MATERIALIZED (SELECT w, lang, quality FROM ({KEPT_SQL}) JOIN labels USING (doc_id)), j AS MATERIALIZED ({cells_sql('rows', ('w', 'lang'))}), a AS (SELECT w, SUM(p) AS pv FROM j GROUP BY w), b AS (SELECT lang, SUM(p) AS pc FROM j GROUP BY lang), "
    "r AS (SELECT w, row_number() OVER (ORDER BY round(SUM(p * ln(p / (pv * pc))) / ln(2), 12) DESC, w) AS rank FROM j JOIN a USING (w) JOIN b USING (lang) GROUP BY w) "
    f"SELECT w, lang, quality, p FROM ({cells_sql('(SELECT * FROM rows JOIN r USING (w) WHERE rank <= 200)', ('w', 'lang', 'quality'))})"
)


@query(panel_sql(MULTI, MULTI_SQL, MULTI_RUNS))
def text_multi_target(spark, d):
    """Words relevant to both language and quality label."""
    documents = read_table(spark, d, "documents").join(read_table(spark, d, "labels").select("doc_id", "quality"), "doc_id")
    counted = cut_lineage(build_joint(text.tokens(documents, "doc_id", "text", ["lang", "quality"]), ["w", "lang", "quality"]))
    top = text.informative_values(counted, "w", "lang", 200).select("w")
    return as_panel(workloads.solve_panel(normalise(counted.join(F.broadcast(top), "w", "left_semi").select("w", "lang", "quality", "n")), MULTI, MULTI_RUNS))
