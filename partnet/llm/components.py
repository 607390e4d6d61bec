"""Connected components of a distributed edge table.

Edges first shrink to a spanning forest within each task. Then two star
operations alternate: every vertex hangs its larger neighbours on its smallest
neighbour, then its smaller ones. Both keep connectivity; they end when the
edges are stars, each of which is a component around its smallest vertex. Every
round is written to the shared folder.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from partnet.llm.common import materialize, tidy

CHUNK = 200_000


def find(parent: dict[int, int], x: int) -> int:
    root = x
    while (up := parent.get(root, root)) != root:
        root = up
    while x != root:
        parent[x], x = root, parent.get(x, x)
    return root


def local_forest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Edges to stars, over chunks of bounded size."""

    def stars(u: np.ndarray, v: np.ndarray) -> pa.RecordBatch | None:
        parent: dict[int, int] = {}
        for a, b in zip(u.tolist(), v.tolist(), strict=True):
            a, b = find(parent, a), find(parent, b)
            if a != b:
                parent[max(a, b)] = min(a, b)
        out = [(x, find(parent, x)) for x in list(parent)]
        out = [x for x in out if x[0] != x[1]]
        return pa.RecordBatch.from_arrays([pa.array([x[0] for x in out], pa.int64()), pa.array([x[1] for x in out], pa.int64())], ["u", "v"]) if out else None

    held: list[tuple[np.ndarray, np.ndarray]] = []
    n = 0
    for batch in batches:
        held.append((batch["u"].to_numpy(), batch["v"].to_numpy()))
        n += batch.num_rows
        if n >= CHUNK:
            if (out := stars(*(np.concatenate(x) for x in zip(*held, strict=True)))) is not None:
                yield out
            held, n = [], 0
    if held and (out := stars(*(np.concatenate(x) for x in zip(*held, strict=True)))) is not None:
        yield out


def hang(edges: DataFrame, larger: bool) -> DataFrame:
    """One star operation on edges (u above v)."""
    if larger:
        both = edges.select("u", "v").unionAll(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        moved = both.join(least, "u").where(F.col("v") > F.col("u")).select(F.col("v").alias("u"), F.col("m").alias("v"))
    else:
        least = edges.groupBy("u").agg(F.min("v").alias("m"))
        moved = edges.join(least, "u").where(F.col("v") > F.col("m")).select(F.col("v").alias("u"), F.col("m").alias("v")).unionAll(least.select("u", F.col("m").alias("v")))
    return moved.where(F.col("u") > F.col("v")).distinct()


def components(edges: DataFrame, label: str = "components", most_rounds: int = 60) -> DataFrame:
    """(u, v) pairs of longs, in either order, to (node, root): root is the component's smallest node; roots themselves have no row."""
    forest = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).where(F.col("u") > F.col("v"))
    now = materialize(forest.mapInArrow(tidy(local_forest), "u long, v long").distinct(), label)
    for _ in range(most_rounds):
        tops = now.groupBy("u").agg(F.count(F.lit(1)).alias("n"))
        open_ends = tops.where("n > 1").select("u").unionAll(now.join(tops.select(F.col("u").alias("v")), "v", "left_semi").select("v")).limit(1)
        if not open_ends.take(1):
            return now.select(F.col("u").alias("node"), F.col("v").alias("root"))
        now = materialize(hang(hang(now, True), False).mapInArrow(tidy(local_forest), "u long, v long").distinct(), label)
    raise RuntimeError(f"components did not settle in {most_rounds} rounds")
