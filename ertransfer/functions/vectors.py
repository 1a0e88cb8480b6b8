"""Vectors as arrays of longs in millionths: expression builders, and the same as SQL functions of a session."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

MICRO = 1_000_000


def _total(x: Column) -> Column:
    return F.aggregate(x, F.lit(0.0), lambda acc, v: acc + v)


def absdiff(a: Column | str, b: Column | str) -> Column:
    return F.zip_with(a, b, lambda u, v: F.abs(u - v))


def product(a: Column | str, b: Column | str) -> Column:
    return F.zip_with(a, b, lambda u, v: F.abs(F.round(u * v / MICRO).cast("long")))


def scale(a: Column | str, by: float) -> Column:
    return F.transform(a, lambda u: F.round(u * by).cast("long"))


def add(a: Column | str, b: Column | str) -> Column:
    return F.zip_with(a, b, lambda u, v: u + v)


def l1(a: Column | str, b: Column | str) -> Column:
    """Sum of the absolute differences, a long in millionths."""
    return F.aggregate(absdiff(a, b), F.lit(0).cast("long"), lambda acc, v: acc + v)


def dot(a: Column | str, b: Column | str) -> Column:
    return _total(F.zip_with(a, b, lambda u, v: u.cast("double") * v))


def norm(a: Column | str) -> Column:
    return F.sqrt(_total(F.transform(a, lambda u: u.cast("double") * u)))


def cosine(a: Column | str, b: Column | str) -> Column:
    """0 where a vector is zero."""
    return F.coalesce(F.try_divide(dot(a, b), norm(a) * norm(b)), F.lit(0.0))


def as_text(x: Column | str) -> Column:
    return F.array_join(F.transform(x, lambda v: v.cast("string")), ",")


def zeros(n: int) -> Column:
    return F.array_repeat(F.lit(0).cast("long"), n)


def sif_weight(p: Column, a: float = 1e-4) -> Column:
    """a / (a + p) in millionths."""
    return F.round(MICRO * a / (a + p)).cast("long")


def origin_weight(p: Column, clip: float | None = None) -> Column:
    """1 / p - 1, at most ``clip`` if given."""
    w = 1 / p - 1
    return F.least(w, F.lit(float(clip))) if clip else w


def phi_source(x: Column, width: int, i: int = 1, n: int = 1) -> Column:
    """Common block, then the block of source ``i`` of ``n``; the target's block comes last."""
    return F.concat(x, zeros((i - 1) * width), x, zeros((n - i + 1) * width))


def phi_target(x: Column, width: int, n: int = 1) -> Column:
    return F.concat(x, zeros(n * width), x)


def phi_unlabeled(x: Column, width: int, n: int = 1, i: int | None = None) -> Column:
    """Nothing in common; the block of source ``i`` (default: the last) and the target's block oppose each other."""
    i = i or n
    return F.concat(zeros(i * width), x, zeros((n - i) * width), F.transform(x, lambda v: -v))


#: SQL bodies of the functions that :func:`register` creates, by signature.
SQL_FUNCTIONS = {
    "vec_absdiff(a ARRAY<BIGINT>, b ARRAY<BIGINT>) RETURNS ARRAY<BIGINT>": "zip_with(a, b, (u, v) -> abs(u - v))",
    "vec_add(a ARRAY<BIGINT>, b ARRAY<BIGINT>) RETURNS ARRAY<BIGINT>": "zip_with(a, b, (u, v) -> u + v)",
    "vec_product(a ARRAY<BIGINT>, b ARRAY<BIGINT>) RETURNS ARRAY<BIGINT>": "zip_with(a, b, (u, v) -> abs(cast(round(u * v / 1000000) as bigint)))",
    "vec_dot(a ARRAY<BIGINT>, b ARRAY<BIGINT>) RETURNS DOUBLE": "aggregate(zip_with(a, b, (u, v) -> cast(u as double) * v), 0.0D, (acc, v) -> acc + v)",
    "vec_norm(a ARRAY<BIGINT>) RETURNS DOUBLE": "sqrt(aggregate(transform(a, u -> cast(u as double) * u), 0.0D, (acc, v) -> acc + v))",
    "vec_l1(a ARRAY<BIGINT>, b ARRAY<BIGINT>) RETURNS BIGINT": "aggregate(zip_with(a, b, (u, v) -> abs(u - v)), 0L, (acc, v) -> acc + v)",
    "phi_s(x ARRAY<BIGINT>) RETURNS ARRAY<BIGINT>": "concat(x, x, array_repeat(0L, size(x)))",
    "phi_t(x ARRAY<BIGINT>) RETURNS ARRAY<BIGINT>": "concat(x, array_repeat(0L, size(x)), x)",
    "phi_u(x ARRAY<BIGINT>) RETURNS ARRAY<BIGINT>": "concat(array_repeat(0L, size(x)), x, transform(x, v -> -v))",
    "iw_weight(p DOUBLE) RETURNS DOUBLE": "1 / p - 1",
}


def register(spark: SparkSession) -> list[str]:
    """Creates the vector functions in ``spark`` as temporary SQL functions and returns their names."""
    for head, body in SQL_FUNCTIONS.items():
        name, rest = head.split("(", 1)
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({rest} RETURN {body}")
    return [h.split("(", 1)[0] for h in SQL_FUNCTIONS]
