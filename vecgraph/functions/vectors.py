"""Vector functions as column expressions and as SQL functions.

Elements are cast to double before any arithmetic, so results do not depend on
the engine that sums them beyond the last bits.
"""

from __future__ import annotations

from pyspark.sql import Column, SparkSession, functions as F


def _c(x) -> Column:
    return F.col(x) if isinstance(x, str) else x


def _sum(values: Column) -> Column:
    return F.aggregate(values, F.lit(0.0), lambda s, v: s + v)


def _pairwise(a, b, f) -> Column:
    return F.zip_with(_c(a), _c(b), lambda u, v: f(u.cast("double"), v.cast("double")))


def dot(a, b) -> Column:
    return _sum(_pairwise(a, b, lambda u, v: u * v))


def sq_l2(a, b) -> Column:
    return _sum(_pairwise(a, b, lambda u, v: (u - v) * (u - v)))


def l2(a, b) -> Column:
    return F.sqrt(sq_l2(a, b))


def l1(a, b) -> Column:
    return _sum(_pairwise(a, b, lambda u, v: F.abs(u - v)))


def linf(a, b) -> Column:
    return F.array_max(_pairwise(a, b, lambda u, v: F.abs(u - v)))


def norm(a) -> Column:
    return F.sqrt(_sum(F.transform(_c(a), lambda u: u.cast("double") * u.cast("double"))))


def cosine_similarity(a, b) -> Column:
    """Null for a zero vector."""
    return F.try_divide(dot(a, b), norm(a) * norm(b))


def cosine_distance(a, b) -> Column:
    return 1 - cosine_similarity(a, b)


def angle(a, b) -> Column:
    return F.acos(F.least(F.lit(1.0), F.greatest(F.lit(-1.0), cosine_similarity(a, b))))


def normalise(a) -> Column:
    n = norm(a)
    return F.when(n > 0, F.transform(_c(a), lambda u: u.cast("double") / n)).otherwise(_c(a).cast("array<double>"))


def add(a, b) -> Column:
    return _pairwise(a, b, lambda u, v: u + v)


def subtract(a, b) -> Column:
    return _pairwise(a, b, lambda u, v: u - v)


def scale(a, k) -> Column:
    return F.transform(_c(a), lambda u: u.cast("double") * k)


def hamming(a, b) -> Column:
    """Differing bits of two longs."""
    return F.bit_count(_c(a).bitwiseXOR(_c(b)))


def distance(a, b, metric: str = "l2") -> Column:
    return {"l2": l2, "cosine": cosine_distance, "l1": l1, "linf": linf, "dot": lambda x, y: -dot(x, y)}[metric](a, b)


def recall_nines(c) -> Column:
    """Recall on a logarithmic axis: -log10(1 - recall); an exact recall is infinite."""
    return F.when(_c(c) >= 1, F.lit(float("inf"))).otherwise(-F.log10(1 - _c(c)))


_FOLD = "aggregate(zip_with(a, b, (u, v) -> {}), 0D, (s, x) -> s + x)"
#: The body of ``vec_l2``, for lambdas, where functions are not inlined.
SQL_L2 = "sqrt(" + _FOLD.format("(CAST(u AS DOUBLE) - v) * (CAST(u AS DOUBLE) - v)") + ")"
_SQL = {
    "vec_dot": ("a ARRAY<FLOAT>, b ARRAY<FLOAT>", _FOLD.format("CAST(u AS DOUBLE) * v")),
    "vec_l2": ("a ARRAY<FLOAT>, b ARRAY<FLOAT>", SQL_L2),
    "vec_l1": ("a ARRAY<FLOAT>, b ARRAY<FLOAT>", _FOLD.format("abs(CAST(u AS DOUBLE) - v)")),
    "vec_norm": ("a ARRAY<FLOAT>", "sqrt(aggregate(a, 0D, (s, u) -> s + CAST(u AS DOUBLE) * u))"),
    "gate_stat": ("a DOUBLE, b DOUBLE, r DOUBLE, cos_target DOUBLE, cos_own DOUBLE", "cos_target / cos_own - (a * a + b * b - r * r) / (2 * a * b)"),
    "screen_stat": ("a DOUBLE, b DOUBLE, cos_target DOUBLE, cos_own DOUBLE", "cos_target / cos_own - a / (2 * b)"),
}


def register(spark: SparkSession) -> list[str]:
    """Register the SQL functions; their bodies are inlined into the plan."""
    for name, (arguments, body) in _SQL.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({arguments}) RETURNS DOUBLE RETURN {body}")
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION vec_cos(a ARRAY<FLOAT>, b ARRAY<FLOAT>) RETURNS DOUBLE RETURN try_divide(" + _SQL["vec_dot"][1] + ", "
        "sqrt(aggregate(a, 0D, (s, u) -> s + CAST(u AS DOUBLE) * u)) * sqrt(aggregate(b, 0D, (s, u) -> s + CAST(u AS DOUBLE) * u)))"
    )
    return [*_SQL, "vec_cos"]
