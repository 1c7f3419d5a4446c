"""Array functions on vectors, for the DataFrame API and as SQL functions."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def vec_dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def vec_norm(a: Column) -> Column:
    return F.sqrt(vec_dot(a, a))


def vec_cosine(a: Column, b: Column) -> Column:
    """Null when either side is zero."""
    return vec_dot(a, b) / F.nullif(vec_norm(a) * vec_norm(b), F.lit(0.0))


def vec_add(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x + y)


def vec_hadamard(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: x * y)


def vec_scale(a: Column, by: Column) -> Column:
    return F.transform(a, lambda x: x * by)


def vec_outer(a: Column, b: Column) -> Column:
    """Row-major outer product."""
    return F.flatten(F.transform(a, lambda x: F.transform(b, lambda y: x * y)))


# bodies in Spark SQL, inlined by the analyser so that code generation sees them
SQL_FUNCTIONS = {
    "vec_dot(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE": "aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)",
    "vec_norm(a ARRAY<DOUBLE>) RETURNS DOUBLE": "sqrt(aggregate(a, 0D, (s, x) -> s + x * x))",
    "vec_scale(a ARRAY<DOUBLE>, k DOUBLE) RETURNS ARRAY<DOUBLE>": "transform(a, x -> x * k)",
    "vec_add(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS ARRAY<DOUBLE>": "zip_with(a, b, (x, y) -> x + y)",
    "vec_hadamard(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS ARRAY<DOUBLE>": "zip_with(a, b, (x, y) -> x * y)",
}


def register(spark: SparkSession) -> None:
    """Make the vector functions known to SQL in this session."""
    for head, body in SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
