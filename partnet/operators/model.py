"""A bottleneck bound to data: marginals by variable elimination, update steps, objectives.

The extended joint over observed and cluster variables is never built. Every
need is a marginal over a few variables: the observed joint is summed down to
what the marginal and its cluster variables' sources require, tables join it one
by one, and a source that is not kept is summed out at once, over vectors.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from partnet.functions.expr import gathered, safe_ln, softmax, vector_sum
from partnet.operators.joint import marginal
from partnet.plans.graph import BottleneckSpec, Term, TradeOff, update_rule


@dataclass
class Model:
    """spec, the observed joint (values, p), and for each cluster variable a table (sources, q array) of k places."""

    spec: BottleneckSpec
    joint: DataFrame
    parts: dict[str, DataFrame]
    sizes: dict[str, int]
    sources_mass: dict[str, DataFrame] = field(default_factory=dict)
    #: marginals that an update reads twice, held until it is written
    held: list[DataFrame] = field(default_factory=list)

    def release(self) -> None:
        for x in self.held:
            x.unpersist()
        self.held = []

    def mass(self, cluster: str) -> DataFrame:
        """(sources, pu)."""
        if cluster not in self.sources_mass:
            self.sources_mass[cluster] = marginal(self.joint, list(self.spec.sources(cluster))).withColumnRenamed("p", "pu")
        return self.sources_mass[cluster]


def marginal_of(model: Model, keep: tuple[str, ...]) -> DataFrame:
    """(keep..., p) in the long form."""
    spec = model.spec
    clusters = [t for t in spec.clusters if t in keep]
    wanted = [v for v in spec.observed if v in keep or any(v in spec.sources(t) for t in clusters)]
    now = model.joint.select(*wanted, "p") if set(wanted) == set(spec.observed) else marginal(model.joint, wanted)
    for i, t in enumerate(clusters):
        later = {v for u in clusters[i + 1 :] for v in spec.sources(u)}
        stay = [v for v in wanted if v in keep or v in later] + clusters[:i]
        k = model.sizes[t]
        now = now.join(model.parts[t], list(spec.sources(t)))
        if set(stay) != set(now.columns) - {"p", "q"}:
            sums = vector_sum(k, lambda j: F.col("p") * F.col("q")[j])
            now = now.groupBy(*stay).agg(*sums).select(*stay, gathered(k).alias("pq__"))
        else:
            now = now.select(*stay, F.transform("q", lambda x: x * F.col("p")).alias("pq__"))
        now = now.select(*stay, F.posexplode("pq__").alias(t, "p"))
        wanted = [v for v in wanted if v in stay]
    return now.groupBy(*keep).agg(F.sum("p").alias("p")) if set(now.columns) - {"p"} != set(keep) else now.select(*keep, "p")


def cluster_mass(model: Model, cluster: str) -> DataFrame:
    """One row: pt, the clusters' probabilities as an array."""
    k = model.sizes[cluster]
    rows = model.parts[cluster].join(model.mass(cluster), list(model.spec.sources(cluster)))
    return rows.agg(*vector_sum(k, lambda i: F.col("pu") * F.col("q")[i])).select(gathered(k).alias("pt"))


def term_cost(model: Model, cluster: str, term: Term) -> DataFrame:
    """(sources, d array): the part of the term's expected divergence that depends on t.

    W is the marginal without the cluster variable; its sums over the clusters give the profiles, and the profiles,
    joined back, the cost. Profiles have one row per (y, z), so they are broadcast when the engine finds them small.
    """
    sources, k = list(model.spec.sources(cluster)), model.sizes[cluster]
    yz = list(dict.fromkeys((*term.y, *term.z)))
    # a source that recurs in y or z keeps one column: only agreeing values weigh
    w = marginal_of(model, tuple(dict.fromkeys((*sources, *yz)))).withColumnRenamed("p", "w__")
    if any(v in model.spec.clusters for v in yz):  # else the joint itself, or a sum of it
        w = w.persist(StorageLevel.MEMORY_AND_DISK)
        model.held.append(w)
    profile = w.join(model.parts[cluster], sources).groupBy(*yz).agg(*vector_sum(k, lambda i: F.col("w__") * F.col("q")[i])).select(*yz, gathered(k).alias("m__"))
    if term.z:
        base = profile.groupBy(*term.z).agg(*vector_sum(k, lambda i: F.col("m__")[i])).select(*term.z, gathered(k).alias("base__"))
        profile = profile.join(base, list(term.z))
    else:
        base = profile.agg(*vector_sum(k, lambda i: F.col("m__")[i])).select(gathered(k).alias("base__"))
        profile = profile.crossJoin(F.broadcast(base))
    logs = profile.select(*yz, F.zip_with("m__", "base__", lambda m, n: safe_ln(m) - safe_ln(n)).alias("lp__"))
    costs = w.join(logs, yz).groupBy(*sources).agg(*vector_sum(k, lambda i: -F.col("w__") * F.col("lp__")[i]))
    scaled = costs.select(*sources, gathered(k).alias("d")).join(model.mass(cluster), sources)
    return scaled.select(*sources, F.transform("d", lambda x: x / F.col("pu") * F.lit(term.weight)).alias("d"))


def distortion(model: Model, cluster: str, terms: list[Term]) -> DataFrame:
    """(sources, d array), up to a constant for each source combination."""
    sources = list(model.spec.sources(cluster))
    total = None
    for term in terms:
        one = term_cost(model, cluster, term)
        total = one if total is None else total.join(one.withColumnRenamed("d", "e__"), sources).select(*sources, F.zip_with("d", "e__", lambda a, b: a + b).alias("d"))
    return total


def update_step(model: Model, cluster: str, trade: TradeOff, form: str | None = None) -> DataFrame:
    """The cluster variable's next table: q' proportional to P(t) exp(-exponent * d), in logarithms."""
    exponent, terms = update_rule(model.spec, cluster, trade, form)
    sources = list(model.spec.sources(cluster))
    pt = F.broadcast(cluster_mass(model, cluster))
    if exponent == 0:
        return model.parts[cluster].crossJoin(pt).select(*sources, F.col("pt").alias("q"))
    scores = distortion(model, cluster, terms).crossJoin(pt).select(*sources, F.zip_with("pt", "d", lambda p, d: safe_ln(p) - F.lit(exponent) * d).alias("s__"))
    return scores.select(*sources, softmax(F.col("s__")).alias("q"))


def log_partition(model: Model, cluster: str, trade: TradeOff, form: str | None = None) -> DataFrame:
    """(sources, log_z): the logarithm of what normalises the update, the sum over t of P(t) exp(-exponent * d)."""
    exponent, terms = update_rule(model.spec, cluster, trade, form)
    sources, pt = list(model.spec.sources(cluster)), F.broadcast(cluster_mass(model, cluster))
    if exponent == 0:
        return model.parts[cluster].select(*sources, F.lit(0.0).alias("log_z"))
    scores = distortion(model, cluster, terms).crossJoin(pt).select(*sources, F.zip_with("pt", "d", lambda p, d: safe_ln(p) - F.lit(exponent) * d).alias("s__"))
    top = F.array_max("s__")
    return scores.select(*sources, (top + F.ln(F.aggregate("s__", F.lit(0.0), lambda acc, x: acc + F.exp(x - top)))).alias("log_z"))


def harden(model: Model, cluster: str, trade: TradeOff) -> DataFrame:
    """The limit of an infinite weight: every source combination goes to its least distortion, the smallest t of equals."""
    _, terms = update_rule(model.spec, cluster, trade)
    k, sources = model.sizes[cluster], list(model.spec.sources(cluster))
    best = F.array_position(F.col("r__"), F.array_min("r__")).cast("int") - 1
    rows = distortion(model, cluster, terms).select(*sources, F.transform("d", lambda x: F.round(x, 12)).alias("r__")).select(*sources, best.alias("t"))
    return rows.select(*sources, "t", F.transform(F.sequence(F.lit(0), F.lit(k - 1)), lambda i: F.when(i == F.col("t"), 1.0).otherwise(0.0)).alias("q"))


def pair_info(model: Model, x: tuple[str, ...], y: tuple[str, ...], unit: str = "bits") -> DataFrame:
    """One row: the information between two sets of observed or cluster variables."""
    from partnet.operators.info import mutual_info

    return mutual_info(marginal_of(model, tuple(dict.fromkeys((*x, *y)))), list(x), list(y), unit)


def compression_terms(spec: BottleneckSpec) -> list[tuple[tuple[str, ...], tuple[str, ...]]]:
    return [((t,), spec.sources(t)) for t in spec.clusters]


def relevance_terms(spec: BottleneckSpec) -> list[tuple[tuple[str, ...], tuple[str, ...]]]:
    return [((v,), p) for v, p in spec.g_out.parents.items() if p]


def objective_parts(model: Model, unit: str = "nats") -> DataFrame:
    """(side, x, y, information): every pair whose information the two networks count."""
    rows = None
    for side, pairs in (("in", compression_terms(model.spec)), ("out", relevance_terms(model.spec))):
        for x, y in pairs:
            one = pair_info(model, x, y, unit).select(F.lit(side).alias("side"), F.lit(",".join(x)).alias("x"), F.lit(",".join(y)).alias("y"), F.col("mutual_info").alias("information"))
            rows = one if rows is None else rows.unionByName(one)
    return rows


def lagrangian(model: Model, trade: TradeOff, unit: str = "nats") -> DataFrame:
    """One row: i_in, i_out and the objective, without the observed networks' constants.

    First objective: i_in - beta i_out. Second: (1 + gamma) i_in - gamma i_out.
    """
    sums = objective_parts(model, unit).agg(*[F.sum(F.when(F.col("side") == s, F.col("information")).otherwise(0.0)).alias(f"i_{s}") for s in ("in", "out")])
    value = F.col("i_in") - trade.value * F.col("i_out") if trade.kind == "beta" else (1 + trade.value) * F.col("i_in") - trade.value * F.col("i_out")
    return sums.select("i_in", "i_out", value.alias("objective"))
