"""Information measures over joints, sets of variables and networks. Each returns one row, or keyed rows.

Measures come from entropies of marginals: an entropy needs one aggregation, no
join, and the sets that a network needs share one pass (grouping sets).
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from partnet.functions.expr import kl_term, unit_scale, xlogx
from partnet.operators.joint import conditional, marginal
from partnet.plans.graph import BottleneckSpec, Dag


def entropies(joint: DataFrame, sets: list[tuple[str, ...]], unit: str = "bits") -> DataFrame:
    """One row: h0, h1, ... for the sets in order, from one pass over the joint.

    The joint is aggregated once to the variables that occur; grouping sets then give every marginal together.
    """
    names = list(dict.fromkeys(v for s in sets for v in s))
    scale = unit_scale(unit)
    wanted = list(dict.fromkeys(tuple(sorted(set(s))) for s in sets if s))
    base = marginal(joint, names) if names else joint
    if not wanted:
        return joint.agg(*[F.lit(0.0).alias(f"h{i}") for i in range(len(sets))])
    masks = {s: sum(1 << (len(names) - 1 - names.index(v)) for v in names if v not in s) for s in wanted}
    grouped = base.groupingSets([[F.col(v) for v in s] for s in wanted], *names).agg(F.sum("p").alias("p"), F.grouping_id(*names).alias("gid"))
    by_set = grouped.groupBy("gid").agg((-F.sum(xlogx(F.col("p"))) * scale).alias("h"))
    pick = lambda s: F.coalesce(F.max(F.when(F.col("gid") == masks[tuple(sorted(set(s)))], F.col("h"))), F.lit(0.0)) if s else F.lit(0.0)
    return by_set.agg(*[pick(s).alias(f"h{i}") for i, s in enumerate(sets)])


def combined(joint: DataFrame, parts: dict[str, list[tuple[float, tuple[str, ...]]]], unit: str) -> DataFrame:
    """One row with a column per part: a weighted sum of entropies."""
    sets = list(dict.fromkeys(tuple(sorted(set(s))) for terms in parts.values() for _, s in terms))
    h = entropies(joint, sets, unit)
    total = lambda terms: reduce(lambda a, b: a + b, [F.lit(float(w)) * F.col(f"h{sets.index(tuple(sorted(set(s))))}") for w, s in terms], F.lit(0.0))
    return h.select(*[total(terms).alias(name) for name, terms in parts.items()])


def mi_terms(x: tuple[str, ...], y: tuple[str, ...]) -> list[tuple[float, tuple[str, ...]]]:
    return [(1, tuple(x)), (1, tuple(y)), (-1, (*x, *y))]


def cmi_terms(x: tuple[str, ...], y: tuple[str, ...], z: tuple[str, ...]) -> list[tuple[float, tuple[str, ...]]]:
    return [(1, (*x, *z)), (1, (*y, *z)), (-1, (*x, *y, *z)), (-1, tuple(z))]


def entropy(joint: DataFrame, variables: list[str], unit: str = "bits") -> DataFrame:
    return combined(joint, {"entropy": [(1, tuple(variables))]}, unit)


def mutual_info(joint: DataFrame, x: list[str], y: list[str], unit: str = "bits") -> DataFrame:
    """Between sets of variables."""
    return combined(joint, {"mutual_info": mi_terms(tuple(x), tuple(y))}, unit)


def cond_mutual_info(joint: DataFrame, x: list[str], y: list[str], z: list[str], unit: str = "bits") -> DataFrame:
    return combined(joint, {"cond_mutual_info": cmi_terms(tuple(x), tuple(y), tuple(z))}, unit)


def multi_info_terms(variables: tuple[str, ...]) -> list[tuple[float, tuple[str, ...]]]:
    return [*((1, (v,)) for v in variables), (-1, variables)]


def multi_info(joint: DataFrame, variables: list[str], unit: str = "bits") -> DataFrame:
    """Divergence of the joint from the product of its single marginals."""
    return combined(joint, {"multi_info": multi_info_terms(tuple(variables))}, unit)


def network_terms(dag: Dag) -> list[tuple[float, tuple[str, ...]]]:
    return [t for v, parents in dag.parents.items() if parents for t in mi_terms((v,), parents)]


def network_info(joint: DataFrame, dag: Dag, unit: str = "bits") -> DataFrame:
    """Sum over the variables of the information with their parents; the n-way product is never built."""
    return combined(joint, {"network_info": network_terms(dag)}, unit)


def network_info_by_variable(joint: DataFrame, dag: Dag, unit: str = "bits") -> DataFrame:
    """(variable, parents, information)."""
    held = {v: p for v, p in dag.parents.items() if p}
    row = combined(joint, {v: mi_terms((v,), p) for v, p in held.items()}, unit)
    pairs = [F.struct(F.lit(v).alias("variable"), F.lit(",".join(p)).alias("parents"), F.col(v).alias("information")) for v, p in held.items()]
    return row.select(F.inline(F.array(*pairs)))


def projection_factors(joint: DataFrame, dag: Dag) -> dict[str, DataFrame]:
    """The nearest distribution that factors along the network: its own conditionals, one table per variable."""
    return {v: conditional(joint, [v], list(p)) if p else marginal(joint, [v]).withColumnRenamed("p", "p_cond") for v, p in dag.parents.items()}


def projected_cells(joint: DataFrame, dag: Dag) -> DataFrame:
    """The joint's cells with pg, the projection's probability there. Factors join the cells, not each other."""
    cells = marginal(joint, list(dag.parents))
    out = cells.withColumn("pg", F.lit(1.0))
    for v, factor in projection_factors(joint, dag).items():
        out = out.join(factor, [*dag.parents[v], v]).withColumn("pg", F.col("pg") * F.col("p_cond")).drop("p_cond")
    return out


def projection_gap(joint: DataFrame, dag: Dag, form: str = "difference", unit: str = "bits", order: list[str] | None = None) -> DataFrame:
    """Divergence of the joint from its projection on a network, in one of three equal forms."""
    variables = tuple(dag.parents)
    if form == "difference":
        return combined(joint, {"gap": [*multi_info_terms(variables), *((-w, s) for w, s in network_terms(dag))]}, unit)
    if form == "markov":
        order, terms = order or dag.order(), []
        for i, v in enumerate(order):
            rest = tuple(u for u in order[:i] if u not in dag.parents[v])
            if rest:
                terms += cmi_terms((v,), rest, dag.parents[v])
        return combined(joint, {"gap": terms}, unit)
    if form == "direct":
        return projected_cells(joint, dag).agg((F.sum(kl_term(F.col("p"), F.col("pg"))) * unit_scale(unit)).alias("gap"))
    raise ValueError(f"no such form: {form!r}")


def is_consistent(joint: DataFrame, dag: Dag, tol: float = 1e-9) -> DataFrame:
    return projection_gap(joint, dag).select("gap", (F.col("gap") <= tol).alias("consistent"))


def observed_gap(joint: DataFrame, spec: BottleneckSpec, tol: float = 1e-9) -> DataFrame:
    """One row (gap, consistent): how far the joint is from those that the compression network's observed part allows.

    Without edges between observed variables the network is taken as complete there, which allows every joint.
    """
    edges = {v: tuple(p for p in spec.g_in.parents.get(v, ()) if p in spec.observed) for v in spec.observed}
    if not any(edges.values()):
        return joint.agg(F.lit(0.0).alias("gap"), F.lit(True).alias("consistent"))
    return is_consistent(marginal(joint, list(spec.observed)), Dag(edges), tol)


def kl_divergence(p: DataFrame, q: DataFrame, keys: list[str], unit: str = "bits", by: list[str] | None = None) -> DataFrame:
    """Between tables (keys, p); rows that q lacks make it infinite. by: a divergence for each of these columns of p."""
    by = by or []
    joined = p.join(q.withColumnRenamed("p", "q"), keys, "left")
    value = (F.sum(kl_term(F.col("p"), F.col("q"))) * unit_scale(unit)).alias("kl")
    return joined.groupBy(*by).agg(value) if by else joined.agg(value)


def value_contribution(joint: DataFrame, variable: str, about: str, unit: str = "bits") -> DataFrame:
    """(value, p, contribution): each value's share of the information about another variable; they add up to it."""
    scale = unit_scale(unit)
    own = marginal(joint, [variable]).withColumnRenamed("p", "pv")
    other = marginal(joint, [about]).withColumnRenamed("p", "pc")
    cells = marginal(joint, [variable, about]).join(own, variable).join(other, about)
    return cells.groupBy(variable).agg(F.first("pv").alias("p"), (F.sum(F.col("p") * (F.ln("p") - F.ln("pv") - F.ln("pc"))) * scale).alias("contribution"))


def mi_bias(sizes: tuple[int, int], n: float) -> float:
    """First-order estimate, in bits, of the information that n draws of independent variables show."""
    import math

    return (sizes[0] - 1) * (sizes[1] - 1) / (2 * n * math.log(2))


def mi_panel_row(joint: DataFrame, x: str, y: str, name: str) -> DataFrame:
    """pair, mutual_info, bias, and the G statistic 2 n I."""
    facts = joint.agg(F.countDistinct(x).alias("kx"), F.countDistinct(y).alias("ky"), F.sum("n").alias("draws"))
    info = mutual_info(joint, [x], [y])
    bias: Column = (F.col("kx") - 1) * (F.col("ky") - 1) / (2 * F.col("draws") * F.lit(0.6931471805599453))
    return info.crossJoin(F.broadcast(facts)).select(F.lit(name).alias("pair"), "mutual_info", bias.alias("bias"), (2 * F.col("draws") * F.col("mutual_info") * F.lit(0.6931471805599453)).alias("g_statistic"))


def overlap_identity(extended: DataFrame, a: str, t1: str, t2: str, unit: str = "bits") -> DataFrame:
    """Both sides of I(T1,T2;A) = I(T1;A) + I(T2;A) - I(T1;T2), which holds when the systems are independent given A."""
    both = combined(
        extended,
        {"joint_side": mi_terms((t1, t2), (a,)), "overlap": mi_terms((t1,), (t2,)), "first": mi_terms((t1,), (a,)), "second": mi_terms((t2,), (a,))},
        unit,
    )
    return both.select("joint_side", (F.col("first") + F.col("second") - F.col("overlap")).alias("sum_side"), "overlap")
