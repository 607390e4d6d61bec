"""SQL access: temporary functions for information terms and table functions for curves and tokens."""

from __future__ import annotations

import json

from pyspark.sql import SparkSession
from pyspark.sql import types as T
from pyspark.sql.functions import udtf

#: name, parameters, body
SQL_FUNCTIONS = (
    ("xlogx", "p DOUBLE", "CASE WHEN p > 0 THEN p * ln(p) ELSE 0D END"),
    ("kl_term", "p DOUBLE, q DOUBLE", "CASE WHEN p <= 0 THEN 0D WHEN q IS NULL OR q <= 0 THEN double('Infinity') ELSE p * (ln(p) - ln(q)) END"),
    ("js_term", "p DOUBLE, q DOUBLE", "CASE WHEN p > 0 THEN p * (ln(p) - ln((p + q) / 2)) / 2 ELSE 0D END + CASE WHEN q > 0 THEN q * (ln(q) - ln((p + q) / 2)) / 2 ELSE 0D END"),
)


@udtf(returnType=T.StructType().add("position", T.IntegerType()).add("token", T.StringType()))
class TokenRows:
    """tokenize(text): words of letters with their positions."""

    def eval(self, text: str):
        for i, word in enumerate((text or "").lower().split()):
            bare = word.strip('.,;:!?()"')
            if bare.isalpha():
                yield i, bare


@udtf(returnType=T.StructType().add("beta", T.DoubleType()).add("k", T.IntegerType()).add("compression", T.DoubleType()).add("relevance", T.DoubleType()))
class BottleneckCurve:
    """bottleneck_curve(rows, last): the annealed curve of a single bottleneck over a joint given as JSON rows of numbers."""

    def eval(self, rows: str, last: float):
        import numpy as np

        from partnet.operators import compact
        from partnet.plans import presets

        p = np.array(json.loads(rows), dtype=float)
        for r in compact.anneal(presets.single("a", "b"), p / p.sum(), compact.Schedule.geometric(1.0, 1.25, float(last)), max_k=8, max_iter=60).curve:
            yield float(r[1]), int(r[3]), float(r[4]), float(r[5])


def register(spark: SparkSession) -> None:
    for name, parameters, body in SQL_FUNCTIONS:
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({parameters}) RETURNS DOUBLE RETURN {body}")
    spark.udtf.register("tokenize", TokenRows)
    spark.udtf.register("bottleneck_curve", BottleneckCurve)
