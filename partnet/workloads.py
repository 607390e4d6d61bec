"""The experiments: planted matrix, text hierarchy, parallel systems, extremes, ablations, baselines.

Fits run on the selected joint, which is small whatever it was counted from.
Each (seed, setting) is a row, and tasks solve their rows side by side.
"""

from __future__ import annotations

import json
import math
from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from partnet.operators import compact
from partnet.operators.joint import ranked
from partnet.operators.info import mutual_info
from partnet.operators.text import select_informative, word_category_joint
from partnet.plans.graph import BottleneckSpec, TradeOff
from partnet.sources.tables import cut_lineage

#: most cells of the full product of the variables' values that one task may hold as an array
MOST_CELLS = 5_000_000
CURVE_SCHEMA = "run string, step int, beta double, var string, k int, compression double, relevance double, compression_frac double, relevance_frac double, split boolean"
TREE_SCHEMA = "run string, var string, node_id string, parent_id string, level int, beta double, mass double, split boolean"
LABEL_SCHEMA = "run string, var string, value string, t int, q double"
PANEL_SCHEMA = "run string, sweeps int, converged boolean, objective double, max_rise double, measure string, value double"

#: fixed values: the planted level of each row group in each column group
LEVELS = ((9, 1, 1), (1, 9, 1), (1, 1, 9), (6, 5, 1), (1, 6, 5), (5, 1, 6))


def planted_joint(spark: SparkSession, na: int = 80, nb: int = 20) -> DataFrame:
    """(a, b, n, p): row groups a mod 6, column groups b mod 3, a small deterministic ripple."""
    levels = F.array(*[F.array(*[F.lit(float(x)) for x in row]) for row in LEVELS])
    grid = spark.range(na * nb).select(F.floor(F.col("id") / nb).alias("a"), (F.col("id") % nb).alias("b"))
    ripple = 1 + 0.05 * (F.pmod(7 * F.col("a") + 13 * F.col("b"), F.lit(5)) - 2)
    cells = grid.withColumn("n", levels[(F.col("a") % 6).cast("int")][(F.col("b") % 3).cast("int")] * ripple)
    total = cells.agg(F.sum("n").alias("total"))
    return cells.crossJoin(F.broadcast(total)).select("a", "b", "n", (F.col("n") / F.col("total")).alias("p"))


def text_joint(documents: DataFrame, category: str = "lang_source", m: int = 300, boilerplate_min_docs: int | None = None) -> DataFrame:
    """(w, c, n, p): the m words that say most about the category, over word positions.

    Texts are read for the word and category counts alone; these are written, and the selection starts from them.
    """
    named = {"lang": F.col("lang"), "source": F.col("source"), "lang_source": F.concat_ws("/", "lang", "source")}[category]
    counted = cut_lineage(word_category_joint(documents, named, boilerplate_min_docs=boilerplate_min_docs))
    return select_informative(counted, "w", "c", m)


def on_grid(joint: DataFrame, spec: BottleneckSpec, settings: dict[str, dict], solve: Callable[[BottleneckSpec, np.ndarray, dict, dict[str, list]], list[tuple]], schema: str) -> DataFrame:
    """Runs solve(spec, dense joint, setting, values by variable) for each named setting, one group each.

    The product of the numbers of values is checked against a bound before any task holds the array.
    """
    variables = list(spec.observed)
    cells = cut_lineage(joint.select(*[F.col(v).cast("string").alias(v) for v in variables], "p"))
    levels = cells.agg(*[F.count_distinct(v).alias(v) for v in variables]).first()
    if (n := math.prod(levels)) > MOST_CELLS:
        raise ValueError(f"{n} cells: too many for one task; use the distributed solver")
    names = [x.split()[0] for x in schema.split(", ")]
    numbers = {v: dict(joint.dtypes)[v] in ("int", "bigint") for v in variables}

    def one(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        values, codes = {}, []
        for v in variables:
            found = sorted(rows[v].unique(), key=int if numbers[v] else None)
            values[v] = found
            codes.append(rows[v].map({x: i for i, x in enumerate(found)}).to_numpy())
        p = np.zeros([len(values[v]) for v in variables])
        np.add.at(p, tuple(codes), rows["p"].to_numpy())
        return pd.DataFrame(solve(spec, p / p.sum(), json.loads(key[1]), values), columns=names[1:]).assign(run=key[0])[names]

    grid = joint.sparkSession.createDataFrame([(k, json.dumps(v)) for k, v in settings.items()], "run string, setting string")
    return grid.crossJoin(F.broadcast(cells)).groupBy("run", "setting").applyInPandas(one, schema)


def _annealed(spec: BottleneckSpec, p: np.ndarray, s: dict) -> compact.Annealed:
    """A setting with weights and sweeps runs that many sweeps at each weight, with noise of whole numbers, so that other engines can repeat it."""
    if "weights" in s:
        return compact.anneal(spec, p, compact.Schedule(tuple(s["weights"])), max_k=s.get("max_k", 32), noise="lcg", max_iter=s["sweeps"], tol=-1.0)
    schedule = compact.Schedule.geometric(s.get("first", 5.0), s.get("rate", 1.1), s.get("last", 330.0))
    return compact.anneal(spec, p, schedule, alpha=s.get("alpha", 1.0), max_k=s.get("max_k", 32), seed=s.get("seed", 0), noise=s.get("noise", "uniform"), max_iter=s.get("max_iter", 150), stop_gain=s.get("stop_gain"))


def anneal_curves(joint: DataFrame, spec: BottleneckSpec, settings: dict[str, dict]) -> DataFrame:
    return on_grid(joint, spec, settings, lambda spec, p, s, _: _annealed(spec, p, s).curve, CURVE_SCHEMA)


def anneal_trees(joint: DataFrame, spec: BottleneckSpec, settings: dict[str, dict]) -> DataFrame:
    return on_grid(joint, spec, settings, lambda spec, p, s, _: _annealed(spec, p, s).tree, TREE_SCHEMA)


def anneal_tables(joint: DataFrame, spec: BottleneckSpec, settings: dict[str, dict]) -> DataFrame:
    """The cluster tables at the end of the schedule, long: one-source clusters only."""

    def solve(spec, p, s, values):
        m = _annealed(spec, p, s).model
        return [(t, str(values[spec.sources(t)[0]][i]), j, float(x)) for t in spec.clusters for i, row in enumerate(m.q[t]) for j, x in enumerate(row)]

    return on_grid(joint, spec, settings, solve, LABEL_SCHEMA)


def _measures(m: compact.Dense) -> list[tuple[str, float]]:
    """Relevance fractions of each system about each other observed variable, of all systems together, and overlaps."""
    out, spec = [], m.spec
    for v in spec.observed:
        by = [t for t in spec.clusters if v not in spec.sources(t)]
        for t in by:
            out.append((f"I({t};{v})/I({','.join(spec.sources(t))};{v})", compact.info(m, (t,), (v,)) / compact.info(m, spec.sources(t), (v,))))
        same = [t for t in by if spec.sources(t) == spec.sources(by[0])]
        if len(same) > 1:
            out.append((f"I({','.join(same)};{v})/I({','.join(spec.sources(same[0]))};{v})", compact.info(m, tuple(same), (v,)) / compact.info(m, spec.sources(same[0]), (v,))))
            out.append((f"I({';'.join(same[:2])})", compact.info(m, (same[0],), (same[1],)) / np.log(2)))
    return out


def solve_panel(joint: DataFrame, spec: BottleneckSpec, settings: dict[str, dict]) -> DataFrame:
    """Fixed sizes and weight: best of the starts by objective, with its measures. settings: k, trade, starts, schedule, form.

    With sweeps, that many are run from starts of whole numbers, so that other engines can repeat it. hard: harden the tables at the end.
    """

    def solve(spec, p, s, _):
        trade = TradeOff(spec.objective, s["trade"])
        best = None
        for seed in range(s.get("starts", 3)):
            sizes, fixed = {t: s["k"][i] for i, t in enumerate(spec.clusters)}, s.get("sweeps")
            m = compact.lcg_tables(spec, p, sizes, seed) if fixed else compact.random_tables(spec, p, sizes, seed + s.get("seed", 0))
            run = compact.solve(m, trade, s.get("schedule", "async"), tol=-1.0 if fixed else 1e-7, max_iter=fixed or s.get("max_iter", 150), form=s.get("form"))
            if s.get("hard"):
                m.q = {t: np.eye(q.shape[-1])[q.argmax(axis=-1)] for t, q in m.q.items()}
            if best is None or run.objective < best[0].objective:
                best = (run, m)
        run, m = best
        return [(run.sweeps, run.converged, run.objective, run.max_rise, name, float(value)) for name, value in _measures(m)]

    return on_grid(joint, spec, settings, solve, PANEL_SCHEMA)


def endpoints(joint: DataFrame, a: str, b: str) -> DataFrame:
    """The ends of every curve: one cluster keeps nothing, no compression keeps all."""
    whole = mutual_info(joint, [a], [b])
    return whole.select(F.inline(F.array(F.struct(F.lit("one cluster").alias("end"), F.lit(0.0).alias("information"), F.lit(0.0).alias("fraction")), F.struct(F.lit("uncompressed").alias("end"), F.col("mutual_info").alias("information"), F.lit(1.0).alias("fraction")))))


def kmeans_profiles(joint: DataFrame, a: str, b: str, k: int, rounds: int = 8) -> DataFrame:
    """(a, t): k-means on the rows P(b|a), a geometric baseline, from labels of rank modulo k of a hash-free order; ties go to the smaller cluster.

    Distances come from |x|^2 - 2 x.m + |m|^2 over cells, so profiles stay sparse whatever the number of values of b.
    Centres are kept in the same long form; an emptied cluster stays empty.
    """
    from partnet.operators.joint import conditional

    x = cut_lineage(conditional(joint, [b], [a]).withColumnRenamed("p_cond", "x"))
    labels = cut_lineage(ranked(x.select(a).distinct(), [a]).select(a, (F.col("i") % k).cast("int").alias("t")))
    for _ in range(rounds):
        held = x.join(labels, a)
        sizes = labels.groupBy("t").agg(F.count(F.lit(1)).alias("n"))
        centre = held.groupBy("t", b).agg(F.sum("x").alias("s")).join(sizes, "t").select("t", b, (F.col("s") / F.col("n")).alias("m"))
        norm = centre.groupBy("t").agg(F.sum(F.col("m") * F.col("m")).alias("norm"))
        dots = x.join(centre, b).groupBy(a, "t").agg(F.sum(F.col("x") * F.col("m")).alias("dot"))
        apart = x.select(a).distinct().crossJoin(F.broadcast(norm)).join(dots, [a, "t"], "left").select(a, "t", F.round(F.col("norm") - 2 * F.coalesce("dot", F.lit(0.0)), 12).alias("d"))
        labels = cut_lineage(apart.groupBy(a).agg(F.min(F.struct("d", "t")).alias("best")).select(a, F.col("best.t").alias("t")))
    return labels


def hard_relevance(joint: DataFrame, labels: DataFrame, a: str, b: str) -> DataFrame:
    """One row: the share of I(a;b) that hard labels of a keep."""
    kept = mutual_info(joint.join(labels, a).groupBy("t", b).agg(F.sum("p").alias("p")), ["t"], [b])
    return kept.crossJoin(mutual_info(joint, [a], [b]).withColumnRenamed("mutual_info", "whole")).select("mutual_info", (F.col("mutual_info") / F.col("whole")).alias("relevance_frac"))
