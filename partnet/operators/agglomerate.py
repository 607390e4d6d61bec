"""Bottom-up merging: the pair whose merger loses the least information goes first.

All pairs are costed once. A merger changes the costs of the merged value's
pairs only, so a step computes one row of pairs anew and keeps the others.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from partnet.functions.expr import xlogx
from partnet.operators.joint import marginal
from partnet.sources.tables import Written

#: steps between rewrites of the pair table; in between, merged values are filtered out of it
REWRITE = 8


def singles(cells: DataFrame, a: str) -> DataFrame:
    return cells.groupBy(a).agg(F.sum("p").alias("pa"), F.sum(xlogx(F.col("p"))).alias("s"))


def pair_costs(cells: DataFrame, a: str, b: str, only: str | None = None) -> DataFrame:
    """(i, j, loss) for all pairs i < j, in nats: (p_i + p_j) times the divergence of their profiles from their mixture. only: the pairs of one value.

    Only cells that both have add more than single sums, so pairs meet on b, not in a product of all cells.
    """
    single = singles(cells, a)
    x, y = (single.select(F.col(a).alias(k), F.col("pa").alias(f"p{k}"), F.col("s").alias(f"s{k}")) for k in "ij")
    left, right = cells.select(F.col(a).alias("i"), b, F.col("p").alias("u")), cells.select(F.col(a).alias("j"), b, F.col("p").alias("v"))
    ordered = F.col("i") < F.col("j")
    if only is not None:
        # the other value is on either side; one side of the join is one value
        x, left, ordered = x.where(F.col("i") == only), left.where(F.col("i") == only), F.col("i") != F.col("j")
    pairs = x.join(y, ordered)
    shared = left.join(right, [b]).where(ordered).groupBy("i", "j").agg(F.sum(xlogx(F.col("u") + F.col("v")) - xlogx(F.col("u")) - xlogx(F.col("v"))).alias("extra"))
    mixed = F.col("si") + F.col("sj") + F.coalesce(F.col("extra"), F.lit(0.0))
    loss = (F.col("si") - xlogx(F.col("pi"))) + (F.col("sj") - xlogx(F.col("pj"))) - (mixed - xlogx(F.col("pi") + F.col("pj")))
    return pairs.join(shared, ["i", "j"], "left").select(F.least("i", "j").alias("i"), F.greatest("i", "j").alias("j"), loss.alias("loss"))


def agglomerate(joint: DataFrame, a: str, b: str, k_min: int = 1) -> list[tuple[int, str, str, float]]:
    """(step, kept, merged, loss in bits). The merged value takes the smaller name; ties go to the smaller pair.

    The pair table has one row for each two values, written every REWRITE steps; there is no bound on the number of values.
    """
    store = Written(joint.sparkSession, "agglomerate")
    cells = store.keep(marginal(joint.withColumn(a, F.col(a).cast("string")), [a, b]))
    costs = store.keep(pair_costs(cells, a, b))
    n, steps, stale, fresh = cells.select(a).distinct().count(), [], [], []
    for step in range(1, n - k_min + 1):
        now = without(costs, stale)
        for _, rows, later in fresh:
            now = now.unionAll(without(rows, later))
        if len(fresh) >= REWRITE:
            old = [costs, *(rows for _, rows, _ in fresh)]
            costs = store.keep(now)
            for table in old:
                store.drop(table)
            now, stale, fresh = costs, [], []
        best = now.select(F.round("loss", 12).alias("loss"), "i", "j").orderBy("loss", "i", "j").first()
        steps.append((step, best["i"], best["j"], best["loss"] / 0.6931471805599453))
        if step == n - k_min:
            break
        merged = store.keep(cells.withColumn(a, F.when(F.col(a) == best["j"], best["i"]).otherwise(F.col(a))).groupBy(a, b).agg(F.sum("p").alias("p")))
        store.drop(cells)
        cells = merged
        for changed in (stale, *(later for _, _, later in fresh)):
            changed += [best["i"], best["j"]]
        for _, rows, _ in [x for x in fresh if x[0] in (best["i"], best["j"])]:
            store.drop(rows)
        # (value, its pairs, values that changed since)
        fresh = [x for x in fresh if x[0] not in (best["i"], best["j"])] + [(best["i"], store.keep(pair_costs(cells, a, b, best["i"])), [])]
    return steps


def without(pairs: DataFrame, values: list[str]) -> DataFrame:
    return pairs.where(~F.col("i").isin(values) & ~F.col("j").isin(values)) if values else pairs
