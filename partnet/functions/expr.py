"""Column builders for information terms: plain expressions, kept inside code generation."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

TINY = 1e-300
LN2 = 0.6931471805599453


def safe_ln(x: Column) -> Column:
    """ln with a floor: Spark's ln(0) is null, and a null would silently leave a sum."""
    return F.ln(F.greatest(x, F.lit(TINY)))


def xlogx(p: Column) -> Column:
    """p ln p, 0 at 0."""
    return F.when(p > 0, p * F.ln(p)).otherwise(F.lit(0.0))


def kl_term(p: Column, q: Column) -> Column:
    """p ln(p / q); infinite where q lacks support that p has."""
    return F.when(p <= 0, F.lit(0.0)).when(q.isNull() | (q <= 0), F.lit(float("inf"))).otherwise(p * (F.ln(p) - safe_ln(q)))


def unit_scale(unit: str) -> float:
    if unit not in ("bits", "nats"):
        raise ValueError(f"unit is bits or nats, not {unit!r}")
    return 1 / LN2 if unit == "bits" else 1.0


def vector_sum(k: int, term) -> list[Column]:
    """One sum per place of a vector of length k; term(i) is the i-th summand."""
    return [F.sum(term(i)).alias(f"v{i}") for i in range(k)]


def gathered(k: int) -> Column:
    """The sums of vector_sum as one array."""
    return F.array(*[F.col(f"v{i}") for i in range(k)])


def softmax(scores: Column) -> Column:
    """exp of the scores less their largest, divided by their sum."""
    shifted = F.transform(scores, lambda x: F.exp(x - F.array_max(scores)))
    total = F.aggregate(shifted, F.lit(0.0), lambda acc, x: acc + x)
    return F.transform(shifted, lambda x: x / total)


def rounded(x: Column | str, places: int = 6) -> Column:
    """For comparison across engines: rounded, without minus zero."""
    return F.round(F.col(x) if isinstance(x, str) else x, places) + F.lit(0.0)
