"""Vector and hash expressions that stay in generated code."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession, functions as F

#: Modulus and multipliers of the portable hash: fixed values, equal in every SQL engine.
M = 2147483647
MULTIPLIERS = (1000003, 48271, 69621, 12345, 16807)


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def norm(a: Column) -> Column:
    return F.sqrt(F.aggregate(a, F.lit(0.0), lambda s, x: s + x * x))


def add(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x + y)


def scale(a: Column, c: Column) -> Column:
    return F.transform(a, lambda x: x * c)


def unit(a: Column) -> Column:
    """``a`` over its norm. Both are bound by one-element arrays, so that the norm is taken once and not once a component."""
    one = lambda v: F.transform(F.array(norm(v)), lambda n: F.when(n > 0, scale(v, 1.0 / n)).otherwise(v))[0]
    return F.transform(F.array(a), one)[0]


def cosine(a: Column, b: Column) -> Column:
    n = norm(a) * norm(b)
    return F.when(n > 0, dot(a, b) / n).otherwise(F.lit(0.0))


def signed_sqrt(a: Column) -> Column:
    """Sign times root of the magnitude, which tames bursty descriptor values."""
    return F.transform(a, lambda x: F.signum(x) * F.sqrt(F.abs(x)))


def portable_hash(a: Column, b: Column, seed: int) -> Column:
    """Three rounds of modular multiplication; the same number in Spark and any other SQL engine."""
    m, (p, q, r, s, t) = F.lit(M).cast("long"), MULTIPLIERS
    x = (F.pmod(a.cast("long"), m) * p + F.pmod(b.cast("long"), m)) % m
    x = (x * q + F.lit(seed * r + s).cast("long")) % m
    x = (x * t + 1) % m
    return (x * q) % m


def portable_hash_line(seed: int) -> tuple[int, int, int]:
    """(p, k, c): the hash of (a, b) is (k (a p + b) + c) mod M, as every round is linear in what the one before gives."""
    p, q, r, s, t = MULTIPLIERS
    return p, q * t * q % M, (q * t * (seed * r + s) + q) % M


def portable_hash_sql(a: str, b: str, seed: int) -> str:
    """The same hash as SQL text."""
    p, q, r, s, t = MULTIPLIERS
    x = f"((CAST({a} AS BIGINT) % {M}) * {p} + (CAST({b} AS BIGINT) % {M})) % {M}"
    x = f"(({x}) * {q} + {seed * r + s}) % {M}"
    x = f"(({x}) * {t} + 1) % {M}"
    return f"((({x}) * {q}) % {M})"


def register(spark: SparkSession) -> None:
    """Make the expressions callable from SQL text."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION vec_dot(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION vec_norm(a ARRAY<DOUBLE>) RETURNS DOUBLE RETURN sqrt(aggregate(a, 0D, (s, x) -> s + x * x))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION signed_sqrt(a ARRAY<DOUBLE>) RETURNS ARRAY<DOUBLE> RETURN transform(a, x -> signum(x) * sqrt(abs(x)))")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION portable_hash(a BIGINT, b BIGINT, seed BIGINT) RETURNS BIGINT RETURN {portable_hash_sql('a', 'b', 0).replace(f'+ {MULTIPLIERS[3]}', f'+ seed * {MULTIPLIERS[2]} + {MULTIPLIERS[3]}')}")
