"""SQL functions on vectors, registered in a session."""

from __future__ import annotations

from pyspark.sql import SparkSession

#: Name, parameters and body. They are SQL functions: Catalyst inlines them.
SQL_FUNCTIONS = (
    ("vec_dot", "a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "DOUBLE", "aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)"),
    ("vec_add", "a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "ARRAY<DOUBLE>", "zip_with(a, b, (x, y) -> x + y)"),
    ("vec_norm", "a ARRAY<DOUBLE>", "DOUBLE", "sqrt(aggregate(a, 0D, (s, x) -> s + x * x))"),
    ("vec_softmax", "a ARRAY<DOUBLE>", "ARRAY<DOUBLE>", "transform(a, x -> exp(x - array_max(a)) / aggregate(a, 0D, (s, y) -> s + exp(y - array_max(a))))"),
    ("cosine", "a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "DOUBLE", "try_divide(vec_dot(a, b), vec_norm(a) * vec_norm(b))"),
)


def register(spark: SparkSession) -> None:
    for name, params, returns, body in SQL_FUNCTIONS:
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({params}) RETURNS {returns} RETURN {body}")
