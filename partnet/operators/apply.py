"""Using a solution: labels, memberships, descriptions, ordered matrices, scores for new values."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from partnet.functions.expr import safe_ln, softmax
from partnet.operators.joint import conditional, ranked
from partnet.operators.model import Model, marginal_of


def assign(part: DataFrame, sources: list[str]) -> DataFrame:
    """(sources, t, confidence): the likeliest cluster, the smallest of equals."""
    top = F.array_max("q")
    return part.select(*sources, (F.array_position("q", top) - 1).cast("int").alias("t"), top.alias("confidence"))


def memberships(part: DataFrame, sources: list[str], threshold: float = 0.1) -> DataFrame:
    """(sources, clusters): every cluster with a share of at least the threshold, likeliest first."""
    pairs = F.transform("q", lambda x, i: F.struct((-x).alias("minus"), i.alias("t")))
    kept = F.array_sort(F.filter(pairs, lambda s: -s["minus"] >= threshold))
    return part.select(*sources, F.transform(kept, lambda s: F.struct(s["t"].alias("t"), (-s["minus"]).alias("q"))).alias("clusters"))


def membership_map(part: DataFrame, sources: list[str], threshold: float = 0.1) -> DataFrame:
    whole = F.map_from_arrays(F.transform(F.col("q"), lambda x, i: i), F.col("q"))
    return part.select(*sources, F.map_filter(whole, lambda k, v: v >= threshold).alias("clusters"))


def top_members(model: Model, cluster: str, n: int = 5, by: str = "q") -> DataFrame:
    """(t, rank, sources, q, pu): values with the largest share (or joint mass), ties by mass, then by value."""
    sources = list(model.spec.sources(cluster))
    rows = model.parts[cluster].join(model.mass(cluster), sources).select(*sources, "pu", F.posexplode("q").alias("t", "q"))
    score = F.round("q", 9) if by == "q" else F.round(F.col("q") * F.col("pu"), 12)
    order = Window.partitionBy("t").orderBy(score.desc(), F.round("pu", 12).desc(), *sources)
    return rows.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= n).select("t", "rank", *sources, "q", "pu")


def cluster_link(model: Model, of: str, given: str) -> DataFrame:
    """(given, of, p_cond, is_best): how one system's clusters predict the other's."""
    rows = conditional(marginal_of(model, (given, of)), [of], [given])
    best = Window.partitionBy(given).orderBy(F.round("p_cond", 9).desc(), of)
    return rows.withColumn("is_best", F.row_number().over(best) == 1)


def block_joint(model: Model, x: str, y: str) -> DataFrame:
    """Cluster by cluster cells."""
    return marginal_of(model, (x, y))


def profile(model: Model, cluster: str, about: str) -> DataFrame:
    """(cluster, about, p_cond)."""
    return conditional(marginal_of(model, (cluster, about)), [about], [cluster])


def permuted(joint: DataFrame, rows: DataFrame, cols: DataFrame, a: str, b: str) -> DataFrame:
    """Cells with positions that put clusters side by side: (row_pos, col_pos, row_cluster, col_cluster, p)."""

    def places(labels: DataFrame, v: str, prefix: str) -> DataFrame:
        return ranked(labels.select(v, "t"), ["t", v], f"{prefix}_pos").withColumnRenamed("t", f"{prefix}_cluster")

    return joint.join(places(rows, a, "row"), a).join(places(cols, b, "col"), b).select("row_pos", "col_pos", "row_cluster", "col_cluster", "p")


def neighbour_variation(cells: DataFrame) -> DataFrame:
    """Sum over rows of the jumps between neighbouring columns; small when the order gathers like values."""
    step = F.lag("p", 1).over(Window.partitionBy("row_pos").orderBy("col_pos"))
    return cells.withColumn("jump", F.abs(F.col("p") - step)).agg(F.sum("jump").alias("variation"))


def hardness(part: DataFrame) -> DataFrame:
    """One row: mean and least largest share, mean effective number of clusters (the exponential of a row's entropy)."""
    h = F.aggregate("q", F.lit(0.0), lambda acc, x: acc - F.when(x > 0, x * F.ln(x)).otherwise(0.0))
    return part.agg(F.avg(F.array_max("q")).alias("mean_max"), F.min(F.array_max("q")).alias("least_max"), F.avg(F.exp(h)).alias("effective"))


def agreement(labels: DataFrame, truth: str, label: str = "t") -> DataFrame:
    """Purity, normalised information and adjusted Rand index of hard labels against a known grouping."""
    cells = labels.groupBy(label, truth).agg(F.count(F.lit(1)).cast("double").alias("n"))
    by = lambda v: cells.groupBy(v).agg(F.sum("n").alias("m"))
    pairs = lambda x: x * (x - 1) / 2
    total = F.col("total")
    purity = cells.groupBy(label).agg(F.max("n").alias("m")).agg(F.sum("m").alias("hit"))
    shape = cells.agg(F.sum("n").alias("total"), F.sum(pairs(F.col("n"))).alias("both"), F.sum(F.col("n") * F.ln("n")).alias("lij"))
    side = lambda v, n: by(v).agg(F.sum(pairs(F.col("m"))).alias(f"pairs_{n}"), F.sum(F.col("m") * F.ln("m")).alias(f"l_{n}"))
    row = shape.crossJoin(purity).crossJoin(side(label, "x")).crossJoin(side(truth, "y"))
    hx, hy, hxy = (F.ln("total") - F.col(c) / total for c in ("l_x", "l_y", "lij"))
    expected = F.col("pairs_x") * F.col("pairs_y") / F.greatest(pairs(total), F.lit(1.0))
    top = (F.col("pairs_x") + F.col("pairs_y")) / 2
    return row.select(
        (F.col("hit") / total).alias("purity"),
        F.when(hx + hy > 0, 2 * (hx + hy - hxy) / (hx + hy)).otherwise(1.0).alias("nmi"),
        F.when(top != expected, (F.col("both") - expected) / (top - expected)).otherwise(1.0).alias("adjusted_rand"),
    )


def score_new(model: Model, cluster: str, about: str, cells: DataFrame, exponent: float) -> DataFrame:
    """One update with fixed profiles for values that were not in the fit: (sources, q) from their cells (sources, about, p)."""
    sources, k = list(model.spec.sources(cluster)), model.sizes[cluster]
    given = conditional(cells, [about], sources)
    joint = marginal_of(model, (cluster, about))
    mass = joint.groupBy(cluster).agg(F.sum("p").alias("pt"))
    logs = joint.join(F.broadcast(mass), cluster).select(cluster, about, (safe_ln(F.col("p")) - safe_ln(F.col("pt"))).alias("lp"))
    floor = F.lit(-690.0)
    wide = logs.groupBy(about).agg(*[F.coalesce(F.max(F.when(F.col(cluster) == i, F.col("lp"))), floor).alias(f"l{i}") for i in range(k)])
    costs = given.join(wide, about).groupBy(*sources).agg(*[(-F.sum(F.col("p_cond") * F.col(f"l{i}"))).alias(f"d{i}") for i in range(k)])
    pt = mass.agg(*[F.coalesce(F.max(F.when(F.col(cluster) == i, F.col("pt"))), F.lit(0.0)).alias(f"p{i}") for i in range(k)])
    scores = F.array(*[safe_ln(F.col(f"p{i}")) - exponent * F.col(f"d{i}") for i in range(k)])
    return costs.crossJoin(F.broadcast(pt)).select(*sources, softmax(scores).alias("q"))


def label_rows(facts: DataFrame, part: DataFrame, sources: list[str]) -> DataFrame:
    """A fact table with t and confidence; rows with unseen values stay, unlabelled."""
    return facts.join(assign(part, sources), sources, "left")
