"""Vectors in plans: one double column per dimension (wide) or one ARRAY<DOUBLE> column.

Wide columns keep sums inside whole-stage code generation with partial aggregation; arrays are the form
for storage, joins on many layers and the SQL surface. Blocks of at most 64 columns stay below the limit
of fields for generated code.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

MAX_WIDE = 64


def names(prefix: str, d: int) -> list[str]:
    return [f"{prefix}{i}" for i in range(d)]


def tidy(x: Column) -> Column:
    """Zero without a sign: -0.0 prints and hashes unlike 0.0."""
    return F.when(x == 0, F.lit(0.0)).otherwise(x)


def to_array(df: DataFrame, prefix: str, d: int, name: str) -> DataFrame:
    return df.withColumn(name, F.array(*names(prefix, d))).drop(*names(prefix, d))


def to_wide(df: DataFrame, name: str, d: int, prefix: str) -> DataFrame:
    return df.select(*[c for c in df.columns if c != name], *[F.col(name)[i].alias(f"{prefix}{i}") for i in range(d)])


def rounded(x: str, digits: int) -> str:
    """SQL text: half away from zero as scaled doubles, like the SQL engines that results are held against.

    ``round`` goes through decimal texts (a microsecond for each value); it is left for values whose scaled form has no fraction."""
    z = f"({x}) * {10.0**digits!r}D"
    return f"CASE WHEN abs({z}) < {2.0**52!r}D THEN (CASE WHEN {z} < 0 THEN -floor(0.5D - {z}) ELSE floor({z} + 0.5D) END) / {10.0**digits!r}D ELSE round({x}, {digits}) END"


def to_long(df: DataFrame, prefix: str, d: int, digits: int | None = None, key: str = "vid") -> DataFrame:
    """(key, k, x): the comparable form of results."""
    value = F.expr(f"posexplode(array({', '.join(names(prefix, d))})) AS (k, x)")
    out = df.select(F.col(key).alias(key), value)
    # the shift moves exact halves away from the border, where the order of sums would decide
    x = F.col("x") if digits is None else F.expr(rounded("x + 3.0E-8D", digits))
    return out.select(key, F.col("k").cast("long").alias("k"), tidy(x).alias("x"))


def dense_columns(xs: Sequence[Column], matrix: Sequence[Sequence[float]], bias: Sequence[float] | None = None) -> list[Column]:
    """x*W (+ b) as literal arithmetic; zero weights vanish from the plan."""
    out = []
    for j in range(len(matrix[0])):
        terms = [x * F.lit(float(row[j])) for x, row in zip(xs, matrix, strict=True) if row[j] != 0]
        total = F.lit(float(bias[j])) if bias is not None else None
        for t in terms:
            total = t if total is None else total + t
        out.append(total if total is not None else F.lit(0.0))
    return out


def relu(x: Column) -> Column:
    return F.when(x > 0, x).otherwise(F.lit(0.0))


def argmax(xs: Sequence[Column]) -> Column:
    """Index of the largest entry, the smallest index on ties."""
    array = F.array(*xs)
    return (F.array_position(array, F.array_max(array)) - 1).cast("long")


# --- on ARRAY<DOUBLE> columns -------------------------------------------------------------------

def vec_add(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x + y)


def vec_sub(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x - y)


def vec_scale(a: Column, s: Column) -> Column:
    return F.transform(a, lambda x: x * s)


def vec_dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def vec_norm(a: Column, order: int = 2) -> Column:
    if order == 1:
        return F.aggregate(a, F.lit(0.0), lambda s, x: s + F.abs(x))
    return F.sqrt(vec_dot(a, a))


def vec_relu(a: Column) -> Column:
    return F.transform(a, relu)


def vec_argmax(a: Column) -> Column:
    return (F.array_position(a, F.array_max(a)) - 1).cast("long")


def vec_softmax(a: Column) -> Column:
    top = F.array_max(a)
    total = F.aggregate(a, F.lit(0.0), lambda s, x: s + F.exp(x - top))
    return F.transform(a, lambda x: F.exp(x - top) / total)


def vec_concat(a: Column, b: Column) -> Column:
    return F.concat(a, b)


def vec_round(a: Column, digits: int) -> Column:
    return F.transform(a, lambda x: F.round(x, digits))


def vec_is_zero(a: Column) -> Column:
    return ~F.exists(a, lambda x: x != 0)


def vec_matmul(a: Column, matrix: Sequence[Sequence[float]]) -> Column:
    columns = [F.array(*[F.lit(float(row[j])) for row in matrix]) for j in range(len(matrix[0]))]
    return F.array(*[vec_dot(a, c) for c in columns])


def vec_quantise(a: Column, steps: int = 64) -> Column:
    return F.transform(a, lambda x: F.floor(x.cast("double") * steps + 0.5) / F.lit(float(steps)))


def register_sql(spark: SparkSession) -> list[str]:
    """The vector functions as temporary SQL functions, for text queries."""
    vec = "ARRAY<DOUBLE>"
    bodies = {
        f"vec_add(a {vec}, b {vec}) RETURNS {vec}": "zip_with(a, b, (x, y) -> x + y)",
        f"vec_sub(a {vec}, b {vec}) RETURNS {vec}": "zip_with(a, b, (x, y) -> x - y)",
        f"vec_scale(a {vec}, s DOUBLE) RETURNS {vec}": "transform(a, x -> x * s)",
        f"vec_dot(a {vec}, b {vec}) RETURNS DOUBLE": "aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)",
        f"vec_norm(a {vec}) RETURNS DOUBLE": "sqrt(aggregate(a, 0D, (s, x) -> s + x * x))",
        f"vec_relu(a {vec}) RETURNS {vec}": "transform(a, x -> CASE WHEN x > 0 THEN x ELSE 0D END)",
        f"vec_argmax(a {vec}) RETURNS BIGINT": "array_position(a, array_max(a)) - 1",
        f"vec_is_zero(a {vec}) RETURNS BOOLEAN": "NOT exists(a, x -> x <> 0)",
    }
    for head, body in bodies.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
    return [h.split("(")[0] for h in bodies]
