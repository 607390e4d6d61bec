"""Fixed-point sweeps over cluster tables: start, asynchronous and synchronous order, stop rule."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from partnet.operators.joint import marginal, ranked
from partnet.operators.model import Model, harden, lagrangian, update_step
from partnet.plans.graph import BottleneckSpec, TradeOff
from partnet.sources.tables import Written, cut_lineage


@dataclass(frozen=True)
class StopRule:
    """Stops when no table moved by more than tol (on "q"), or the objective by less than tol ("lagrangian")."""

    tol: float = 1e-6
    max_iter: int = 200
    on: str = "q"


@dataclass
class Solution:
    model: Model
    sweeps: int
    converged: bool
    #: (sweep, cluster, objective or None, max_delta or None)
    trace: list[tuple[int, str, float | None, float | None]]


def lcg_noise(i, t, level: int):
    """Noise in [-1/2, 1/2] from whole numbers, the same in every engine."""
    return F.pmod(i * 7919 + t * 104729 + F.lit(level * 1299709), F.lit(10007)).cast("double") / 10006 - 0.5


def start_table(joint: DataFrame, sources: list[str], k: int, kind: str = "rank", seed: int = 0, noise: float = 1.0) -> DataFrame:
    """(sources, q). rank: .7 at the rank modulo k, the rest even; random: an even simplex draw from a hash of the values;
    lcg: proportional to 0.6 and noise of whole numbers by rank.

    The draw depends on values and seed alone, so it is the same however the table is dealt out.
    """
    rows = marginal(joint, sources).select(*sources)
    places = F.sequence(F.lit(0), F.lit(k - 1))
    if k == 1:
        return rows.withColumn("q", F.array(F.lit(1.0)))
    if kind == "rank":
        return ranked(rows, sources).select(*sources, F.transform(places, lambda t: F.when(t == F.col("i") % k, F.lit(0.7)).otherwise(F.lit(0.3 / (k - 1)))).alias("q"))
    if kind == "lcg":
        rows = ranked(rows, sources).withColumn("e", F.transform(places, lambda t: 0.6 + lcg_noise(F.col("i"), t, seed)))
        return rows.select(*sources, F.transform("e", lambda x: x / F.aggregate("e", F.lit(0.0), lambda acc, y: acc + y)).alias("q"))
    if kind == "random":
        drawn = F.transform(places, lambda t: -F.ln((F.pmod(F.xxhash64(F.lit(seed), t, *sources), F.lit(1 << 40)).cast("double") + 1) / F.lit(float((1 << 40) + 1))) * noise)
        whole = rows.withColumn("e", drawn)
        return whole.select(*sources, F.transform("e", lambda x: x / F.aggregate("e", F.lit(0.0), lambda acc, y: acc + y)).alias("q"))
    raise ValueError(f"no such start: {kind!r}")


def labelled_table(labels: DataFrame, sources: list[str], k: int, label: str = "t") -> DataFrame:
    """Hard labels as a table."""
    return labels.select(*sources, F.transform(F.sequence(F.lit(0), F.lit(k - 1)), lambda i: F.when(i == F.col(label), 1.0).otherwise(0.0)).alias("q"))


#: columns of the engine's own tables
RESERVED = frozenset(("p", "q", "pu", "pt", "d", "t", "i"))


def bind(joint: DataFrame, spec: BottleneckSpec, sizes: dict[str, int], kind: str = "rank", seed: int = 0) -> Model:
    missing = [v for v in spec.observed if v not in joint.columns]
    if missing:
        raise ValueError(f"the joint lacks {missing}")
    if clash := RESERVED.intersection((*spec.observed, *spec.clusters)):
        raise ValueError(f"rename {sorted(clash)}: the engine's tables have columns of these names")
    cells = marginal(joint, list(spec.observed))
    return Model(spec, cells, {t: start_table(cells, list(spec.sources(t)), sizes[t], kind, seed + i) for i, t in enumerate(spec.clusters)}, dict(sizes))


def largest_move(before: DataFrame, after: DataFrame, sources: list[str]) -> float:
    gap: Column = F.array_max(F.zip_with("q", "r__", lambda a, b: F.abs(a - b)))
    found = before.join(after.withColumnRenamed("q", "r__"), sources).agg(F.max(gap).alias("m")).first()["m"]
    return float(found or 0.0)


def hold_masses(model: Model) -> None:
    """The source masses don't change: they are summed once for all sweeps."""
    for t in model.spec.clusters:
        if t not in model.sources_mass:
            model.sources_mass[t] = cut_lineage(model.mass(t))


def solve(
    model: Model, trade: TradeOff, schedule: str = "async", stop: StopRule = StopRule(), form: str | None = None, order: list[str] | None = None, watch: bool = False, final_hard: bool = False
) -> Solution:
    """Sweeps until the stop rule holds.

    async: one table at a time with the newest of the others. sync: all from the previous sweep; if the objective then
    rises, sweeps go on asynchronously, since synchronous ones may cycle. Each sweep ends in a checkpoint, because plans
    that refer to themselves twice double with every sweep; the tables of the sweep before the last are removed as it goes on.
    """
    if schedule not in ("async", "sync"):
        raise ValueError(f"schedule is async or sync, not {schedule!r}")
    order, trace, last, done = order or list(model.spec.clusters), [], None, False
    hold_masses(model)
    store = Written(model.joint.sparkSession, "sweeps")
    sweep = 0
    for sweep in range(1, stop.max_iter + 1):
        old, moved = dict(model.parts), 0.0
        fresh: dict[str, DataFrame] = {}
        for t in order:
            part = store.keep(update_step(model, t, trade, form))
            model.release()
            delta = largest_move(old[t], part, list(model.spec.sources(t))) if stop.tol > 0 else None
            moved = max(moved, delta or 0.0)
            fresh[t] = part
            if schedule == "async":
                model.parts[t] = part
            trace.append((sweep, t, None, delta))
        model.parts.update(fresh)
        for table in old.values():
            store.drop(table)
        if watch or stop.on == "lagrangian" or schedule == "sync":
            value = float(lagrangian(model, trade).first()["objective"])
            trace[-1] = (*trace[-1][:2], value, trace[-1][3])
            if schedule == "sync" and last is not None and value > last + 1e-9:
                schedule = "async"  # may be a cycle
            done = stop.on == "lagrangian" and last is not None and abs(last - value) <= stop.tol * max(1.0, abs(value))
            last = value
        if done or (stop.on == "q" and stop.tol > 0 and moved <= stop.tol):
            done = True
            break
    if final_hard:
        for t in order:
            model.parts[t] = cut_lineage(harden(model, t, trade).drop("t"))
            model.release()
    return Solution(model, sweep, done, trace)


def run_sweeps(joint: DataFrame, spec: BottleneckSpec, sizes: dict[str, int], trade: TradeOff, sweeps: int, schedule: str = "async", form: str | None = None, kind: str = "rank", seed: int = 0) -> Model:
    """A fixed number of sweeps without any stop test."""
    model = bind(cut_lineage(marginal(joint, list(spec.observed))), spec, sizes, kind, seed)
    return solve(model, trade, "async", StopRule(0.0, sweeps), form).model if schedule == "async" else sync_sweeps(model, trade, sweeps, form)


def sync_sweeps(model: Model, trade: TradeOff, sweeps: int, form: str | None = None) -> Model:
    """Plain synchronous sweeps, without the guard."""
    hold_masses(model)
    store = Written(model.joint.sparkSession, "sweeps")
    for _ in range(sweeps):
        old = model.parts
        model.parts = {t: store.keep(update_step(model, t, trade, form)) for t in model.spec.clusters}
        model.release()
        for table in old.values():
            store.drop(table)
    return model


def long_table(part: DataFrame, sources: list[str], name: str = "t") -> DataFrame:
    return part.select(*sources, F.posexplode("q").alias(name, "q"))
