"""Annealing on tables of any size: doubling, split test, merging, and the driver that raises the weight.

The driver reads a handful of numbers for each step (how far the copies of each
cluster have parted, masses, three informations); tables stay distributed.
"""

from __future__ import annotations

import json
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from partnet.functions.expr import gathered, vector_sum
from partnet.operators.compact import Schedule
from partnet.operators.joint import marginal, ranked
from partnet.operators.model import Model, cluster_mass, pair_info
from partnet.operators.solve import StopRule, lcg_noise, solve
from partnet.plans.graph import BottleneckSpec, TradeOff
from partnet.sources.tables import cut_lineage


def double_values(part: DataFrame, sources: list[str], k: int, alpha: float = 1.0, level: int = 0, noise: str = "uniform", seed: int = 0) -> DataFrame:
    """Two copies of every cluster, at places 2t and 2t+1, that add up to it: q (1/2 +- alpha e)."""
    if noise == "lcg":
        rows = ranked(part, sources)
        e = lambda t: lcg_noise(F.col("i"), t, level)
    elif noise == "uniform":
        rows = part
        e = lambda t: F.pmod(F.xxhash64(F.lit(seed), F.lit(level), t, *sources), F.lit(1 << 30)).cast("double") / float(1 << 30) - 0.5
    else:
        raise ValueError(f"no such noise: {noise!r}")
    pair = lambda x, t: F.array(x * (0.5 + alpha * e(t)), x * (0.5 - alpha * e(t)))
    return rows.select(*sources, F.flatten(F.transform("q", pair)).alias("q"))


def split_gaps(part: DataFrame, mass: DataFrame, sources: list[str], k: int, floor: float = 1e-6) -> DataFrame:
    """(t, gap) for k pairs of copies: the largest difference over u between a copy's share there and its share overall."""
    rows = part.join(mass, sources)
    pt = rows.agg(*vector_sum(2 * k, lambda i: F.col("pu") * F.col("q")[i])).select(gathered(2 * k).alias("pt"))
    both = lambda a, i: a[2 * i] + a[2 * i + 1]
    gap = lambda i: F.when(both(F.col("q"), i) > floor, F.abs(F.col("q")[2 * i] / both(F.col("q"), i) - F.col("pt")[2 * i] / both(F.col("pt"), i))).otherwise(0.0)
    alive = lambda i: (F.col("pt")[2 * i] > floor) & (F.col("pt")[2 * i + 1] > floor)
    one = rows.crossJoin(F.broadcast(pt)).agg(*[F.max(F.when(alive(i), gap(i)).otherwise(0.0)).alias(f"v{i}") for i in range(k)])
    return one.select(F.posexplode(gathered(k)).alias("t", "gap"))


def merge_copies(part: DataFrame, sources: list[str], split: list[bool]) -> DataFrame:
    """Pairs that did not split are added up again; the others stay apart."""
    cells = []
    for i, apart in enumerate(split):
        a, b = F.col("q")[2 * i], F.col("q")[2 * i + 1]
        cells += [a, b] if apart else [a + b]
    return part.select(*sources, F.array(*cells).alias("q"))


@dataclass
class AnnealResult:
    model: Model
    tree: list[tuple[str, str, str | None, int, float, float, bool]]
    curve: list[tuple[int, float, str, int, float, float, bool]]


class State:
    """An anneal's progress in a folder: after each step the tables, the cluster names, tree and curve. A stopped run goes on from the last whole step."""

    def __init__(self, spark: SparkSession, folder: str):
        self.spark, self.folder = spark, folder.rstrip("/")

    def steps(self) -> list[int]:
        jvm = self.spark.sparkContext._jvm
        path = jvm.org.apache.hadoop.fs.Path(self.folder)
        system = path.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration())
        names = [x.getPath().getName() for x in system.listStatus(path)] if system.exists(path) else []
        # notes are written last, so a step without them is not whole
        return sorted(int(n[5:]) for n in names if n.startswith("step=") and system.exists(jvm.org.apache.hadoop.fs.Path(f"{self.folder}/{n}/notes/_SUCCESS")))

    def save(self, step: int, parts: dict[str, DataFrame], notes: dict) -> None:
        at = f"{self.folder}/step={step}"
        for t, part in parts.items():
            part.write.mode("overwrite").parquet(f"{at}/part={t}")
        self.spark.createDataFrame([(json.dumps(notes),)], "notes string").coalesce(1).write.mode("overwrite").json(f"{at}/notes")

    def load(self, step: int, clusters: tuple[str, ...]) -> tuple[dict[str, DataFrame], dict]:
        at = f"{self.folder}/step={step}"
        return {t: self.spark.read.parquet(f"{at}/part={t}") for t in clusters}, json.loads(self.spark.read.schema("notes string").json(f"{at}/notes").first()["notes"])


def anneal(
    joint: DataFrame, spec: BottleneckSpec, weights: list[float] | Schedule, alpha: float = 1.0, threshold: float = 0.05, max_k: int = 16, noise: str = "uniform", seed: int = 0,
    stop: StopRule = StopRule(1e-5, 40), stop_gain: float | None = None, folder: str | None = None,
) -> AnnealResult:
    """Starts with one value for each cluster variable and raises the weight through the schedule.

    noise: uniform (a hash of the values) or lcg (whole numbers by rank). stop_gain ends the run once a split adds less relevance, in bits;
    mi_bias() of the joint is a fitting floor. folder: where each step's state is written, and from where a stopped run goes on.
    """
    weights = list(weights.values) if isinstance(weights, Schedule) else list(weights)
    cells = cut_lineage(marginal(joint, list(spec.observed)))
    one = F.array(F.lit(1.0)).alias("q")
    model = Model(spec, cells, {t: marginal(cells, list(spec.sources(t))).select(*spec.sources(t), one) for t in spec.clusters}, dict.fromkeys(spec.clusters, 1))
    notes: dict = {"paths": {t: ["0"] for t in spec.clusters}, "tree": [(t, "0", None, 0, 0.0, 1.0, False) for t in spec.clusters], "curve": [], "done": False}
    state, begin = State(joint.sparkSession, folder) if folder else None, 0
    if state and (found := state.steps()):
        begin = found[-1] + 1
        model.parts, notes = state.load(found[-1], spec.clusters)
        model.sizes = {t: len(names) for t, names in notes["paths"].items()}
    for step, value in list(enumerate(weights))[begin:]:
        if notes["done"]:
            break
        trade, before, gained = TradeOff(spec.objective, value), dict(model.sizes), []
        for t in spec.clusters:
            beside = [u for u in spec.clusters if spec.sources(u) == spec.sources(t)].index(t)
            model.parts[t] = cut_lineage(double_values(model.parts[t], list(spec.sources(t)), before[t], alpha, step + 31 * beside, noise, seed))
            model.sizes[t] = 2 * before[t]
        solve(model, trade, "async", stop)
        apart = {}
        for t in spec.clusters:
            sources = list(spec.sources(t))
            gaps = {r["t"]: r["gap"] for r in split_gaps(model.parts[t], model.mass(t), sources, before[t]).collect()}
            widest = sorted(gaps, key=lambda i: (-gaps[i], i))[: max(0, max_k - before[t])]
            apart[t] = [gaps[i] > threshold and i in widest for i in range(before[t])]
            masses, names = cluster_mass(model, t).first()["pt"], []
            for i, (path, yes) in enumerate(zip(notes["paths"][t], apart[t], strict=True)):
                names += [f"{path}.{j}" for j in range(2)] if yes else [path]
                if yes:
                    notes["tree"] += [(t, f"{path}.{j}", path, path.count(".") + 1, value, float(masses[2 * i + j]), True) for j in range(2)]
            model.parts[t] = cut_lineage(merge_copies(model.parts[t], sources, apart[t]))
            model.sizes[t], notes["paths"][t] = len(names), names
        for t in spec.clusters:
            rest = tuple(v for v in spec.observed if v not in spec.sources(t))
            info = [float(pair_info(model, (t,), about).first()["mutual_info"]) for about in (spec.sources(t), rest)]
            past = [r[5] for r in notes["curve"] if r[2] == t]
            gained.append(info[1] - past[-1] if past else info[1])
            notes["curve"].append((step, value, t, model.sizes[t], *info, any(apart[t])))
        notes["done"] = stop_gain is not None and step > 0 and any(map(any, apart.values())) and max(gained) < stop_gain
        if state:
            state.save(step, model.parts, notes)
    return AnnealResult(model, [tuple(x) for x in notes["tree"]], [tuple(x) for x in notes["curve"]])


def critical_beta(joint: DataFrame, a: str, b: str, iterations: int = 20) -> DataFrame:
    """One row: sigma2 squared and its inverse, the weight of the first split of a single bottleneck.

    Power iteration on the scaled joint, without its first singular vector; two joins and sums for each round.
    """
    cells = marginal(joint, [a, b])
    pa, pb = marginal(cells, [a]).withColumnRenamed("p", "pa"), marginal(cells, [b]).withColumnRenamed("p", "pb")
    scaled = cut_lineage(cells.join(pa, a).join(pb, b).select(a, b, "pb", (F.col("p") / F.sqrt(F.col("pa") * F.col("pb"))).alias("m")))
    vector = ranked(pb, [b]).select(b, "pb", (F.pmod((F.col("i") + 1) * 7919, F.lit(10007)) / 10007.0).alias("v"))
    ratio = None
    for _ in range(iterations):
        first = vector.agg(F.sum(F.col("v") * F.sqrt("pb")).alias("dot"))
        vector = vector.crossJoin(F.broadcast(first)).select(b, "pb", (F.col("v") - F.col("dot") * F.sqrt("pb")).alias("v"))
        norm = vector.agg(F.sqrt(F.sum(F.col("v") * F.col("v"))).alias("norm"))
        vector = vector.crossJoin(F.broadcast(norm)).select(b, "pb", (F.col("v") / F.col("norm")).alias("v"))
        left = scaled.join(vector.select(b, "v"), b).groupBy(a).agg(F.sum(F.col("m") * F.col("v")).alias("l"))
        ratio = left.agg(F.sum(F.col("l") * F.col("l")).alias("sigma2_squared"))
        vector = cut_lineage(scaled.join(left, a).groupBy(b, "pb").agg(F.sum(F.col("m") * F.col("l")).alias("v")))
    return ratio.select("sigma2_squared", (1 / F.col("sigma2_squared")).alias("critical_beta"))
