"""Vector functions as columns, and their registration for SQL."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def _total(x: Column) -> Column:
    return F.aggregate(x, F.lit(0.0), lambda a, v: a + v)


def dot(a: Column, b: Column) -> Column:
    return _total(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")))


def l2(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a: Column, b: Column) -> Column:
    """0 where either vector is zero."""
    n = l2(a) * l2(b)
    return F.when(n > 0, dot(a, b) / n).otherwise(0.0)


def delta(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x - y)


def mse(a: Column, b: Column) -> Column:
    d = delta(a, b)
    return dot(d, d) / F.size(a)


def add(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x + y)


def scale(a: Column, k: Column | float) -> Column:
    return F.transform(a, lambda x: x * k)


def softmax(a: Column) -> Column:
    e = F.transform(a, lambda x: F.exp(x - F.array_max(a)))
    return F.transform(e, lambda x: x / _total(e))


def token(tokens: Column, no: Column | int, dim: int) -> Column:
    """One token of a packed frame."""
    return F.slice(tokens, (F.lit(no) if isinstance(no, int) else no) * dim + 1, dim)


def rolled(a: Column, shift: int) -> Column:
    """A ring moved on by `shift` places."""
    n = F.size(a)
    k = F.pmod(F.lit(shift), n)
    return F.concat(F.slice(a, n - k + 1, k), F.slice(a, F.lit(1), n - k)) if shift else a


def codec_hints(a: Column, ref: Column) -> tuple[Column, Column]:
    """(motion, residual): half the ring shift in -2..2 of least L1 distance to the reference, the least shift of equal ones; mean absolute change."""
    dist = F.array(*[_total(F.zip_with(a, rolled(ref, s), lambda x, y: F.abs(x - y))) for s in (0, 1, -1, 2, -2)])

    def moved(d):
        far = F.least(F.get(d, F.lit(3)), F.get(d, F.lit(4)))
        near = F.least(F.get(d, F.lit(1)), F.get(d, F.lit(2)))
        return F.when(F.get(d, F.lit(0)) <= F.least(near, far) + 1e-9, F.lit(0.0)).when(near <= far + 1e-9, F.lit(0.5)).otherwise(1.0)

    return F.transform(F.array(dist), moved)[0], F.get(dist, F.lit(0)) / F.size(a)


def linear(vec: Column, weights, bias) -> Column:
    """vec times a literal matrix (rows, columns) plus a bias."""
    columns = F.array(*[F.struct(F.array(*[F.lit(float(x)) for x in c]).alias("c"), F.lit(float(b)).alias("b")) for c, b in zip(weights.T, bias, strict=True)])
    return F.transform(columns, lambda s: dot(vec, s["c"]) + s["b"])


def mlp(vec: Column, m: dict, w1: str, b1: str, w2: str, b2: str) -> Column:
    """Two layers with a rectifier between them, with literal weights."""
    return linear(F.transform(linear(vec, m[w1], m[b1]), lambda x: F.greatest(x, F.lit(0.0))), m[w2], m[b2])


def mean_pool(df: DataFrame, by: list[str], vec: str = "emb") -> DataFrame:
    """Mean vector of each group, by an explode and partial sums."""
    x = df.select(*by, F.posexplode(vec).alias("_i", "_v")).groupBy(*by, "_i").agg(F.avg("_v").alias("_v"))
    x = x.groupBy(*by).agg(F.sort_array(F.collect_list(F.struct("_i", "_v"))).alias("_x"))
    return x.select(*by, F.transform("_x", lambda s: s["_v"]).alias(vec))


def register(spark: SparkSession) -> None:
    """fd_dot, fd_cosine, fd_mse, fd_delta for SQL text, as JVM-side SQL functions."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION fd_dot(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> x * y), CAST(0 AS DOUBLE), (s, v) -> s + v)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION fd_cosine(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN CASE WHEN fd_dot(a, a) > 0 AND fd_dot(b, b) > 0 THEN fd_dot(a, b) / sqrt(fd_dot(a, a)) / sqrt(fd_dot(b, b)) ELSE 0D END")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION fd_delta(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS ARRAY<DOUBLE> RETURN zip_with(a, b, (x, y) -> x - y)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION fd_mse(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN fd_dot(fd_delta(a, b), fd_delta(a, b)) / size(a)")
