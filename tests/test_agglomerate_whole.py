"""All merges of turns by role against brute force in numpy."""

import numpy as np
import pytest

from partnet.queries.solver_queries import QUERIES


def test_merges_end_in_one_cluster(spark, sf):
    counts = spark.read.parquet(f"{sf}/conversations.parquet").groupBy("turn", "role").count().collect()
    roles = sorted({r.role for r in counts})
    rows: dict = {}
    for r in counts:
        rows.setdefault(str(r.turn), np.zeros(len(roles)))[roles.index(r.role)] += r["count"]
    total, want = sum(x.sum() for x in rows.values()), []

    def h(x):
        x = x[x > 0]
        return -(x * np.log2(x / x.sum())).sum() / total

    first = len(rows)
    while len(rows) > 1:
        names = sorted(rows)
        loss, i, j = min((round((h(rows[i] + rows[j]) - h(rows[i]) - h(rows[j])) * np.log(2), 12), i, j) for i in names for j in names if i < j)
        want.append((i, j, loss / np.log(2)))
        rows[i] = rows[i] + rows.pop(j)
    got = sorted(QUERIES["agglomerate_turn_role_whole"](spark, sf).collect(), key=lambda r: r.step)
    assert [(r.kept, r.merged) for r in got] == [x[:2] for x in want] and len(got) == first - 1
    assert [r.loss for r in got] == pytest.approx([x[2] for x in want], abs=2e-6)
