"""Column functions: binomials, reproducible draws, sample bounds; and their SQL names."""

from __future__ import annotations

import math
from decimal import Decimal

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

#: Draws are whole numbers below 2^52, from 13 hexadecimal digits of a digest.
DRAW_BITS = 52
EXACT = "decimal(38,0)"


def binomial(n: Column, k: int, kind: str = "double") -> Column:
    """n over k as a product of k factors, each division exact; 0 where n < k. kind: a numeric SQL type."""
    n = n.cast("long")
    out = F.lit(1).cast(kind)
    for i in range(k):
        out = (out * (n - i).cast(kind) / F.lit(i + 1).cast(kind)) if kind == "double" else F.floor(out * (n - i).cast("decimal(18,0)") / F.lit(i + 1)).cast(kind)
    return F.when(n >= k, out).otherwise(F.lit(0).cast(kind))


def draw(*parts: Column | int | str) -> Column:
    """A whole number below 2^52 from a digest of the parts; the same in any engine with md5."""
    text = F.concat_ws(":", *[(x if isinstance(x, Column) else F.lit(x)).cast("string") for x in parts])
    return F.conv(F.substring(F.md5(text), 1, 13), 16, 10).cast("long")


def draw_sql(*parts: str) -> str:
    """draw() in DuckDB's SQL."""
    return f"('0x' || substr(md5({" || ':' || ".join(f'({x})::varchar' for x in parts)}), 1, 13))::bigint"


def required_samples(b: Column, c: Column, eps: Column | float, alpha: Column | float) -> Column:
    """The samples after which the estimate is off by more than eps times C with probability alpha at most. Large numbers
    are rounded up from a double, so the order of operations is that of the SQL, and 2 eps^2 of a literal is exact."""
    twice = 2 * eps * eps if isinstance(eps, Column) else F.lit(float(2 * Decimal(str(eps)) ** 2))
    alpha = alpha if isinstance(alpha, Column) else F.lit(alpha)
    b, c = b.cast("double"), c.cast("double")
    return F.ceil(b * b / (c * c) / twice * F.ln(2 / alpha))


def failure_bound(b: Column, c: Column, eps: float, t: Column) -> Column:
    ratio = b.cast("double") / c.cast("double")
    return F.least(F.lit(1.0), 2 * F.exp(-2 * eps * eps * t / (ratio * ratio)))


def error_at(b: Column, c: Column, t: Column, alpha: float) -> Column:
    """The error that t samples keep to but for a probability alpha."""
    return b.cast("double") / c.cast("double") * F.sqrt(F.lit(math.log(2 / alpha)) / (2 * t))


def relative_error(estimate: Column, exact: Column) -> Column:
    return F.abs(estimate.cast("double") - exact.cast("double")) / exact.cast("double")


def register(spark: SparkSession) -> None:
    """SQL functions relative_error, hoeffding_samples, binomial and the table function broom_steps(p, q)."""
    spark.sql("create or replace temporary function relative_error(e double, c double) returns double return abs(e - c) / c")
    spark.sql(
        "create or replace temporary function hoeffding_samples(b double, c double, eps double, alpha double) returns bigint "
        "return ceil(b * b / (c * c) / (2 * eps * eps) * ln(2 / alpha))"
    )
    spark.sql(
        "create or replace temporary function binomial(n bigint, k int) returns double "
        "return if(k < 0 or n < k, 0D, round(aggregate(if(k = 0, array(), sequence(1, k)), 1D, (a, i) -> a * (n - k + i) / i)))"
    )
    from pyspark.sql.functions import udtf

    from biclique_spark.functions import pattern

    class Steps:
        def eval(self, p: int, q: int):
            edges, steps = pattern.broom_edges(p, q), pattern.broom_steps(p, q) + " "
            for t, ((i, j), s) in enumerate(zip(edges, steps, strict=True), 1):
                yield t, i, j, s.strip() or None

    spark.udtf.register("broom_steps", udtf(Steps, returnType="t int, i int, j int, step string"))
