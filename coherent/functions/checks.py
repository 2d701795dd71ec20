"""Schema and value checks at the entry of the engine."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

OP = {"sys": "string", "row": "int", "col": "int", "re": "double", "im": "double"}
VEC = {"sys": "string", "op": "int", "idx": "bigint", "re": "double", "im": "double"}
RATES = {"sys": "string", "j": "bigint", "k": "bigint", "re": "double", "im": "double"}
SYSMAT = {"sys": "string", "s": "bigint", "n": "bigint", "x": "double"}


def require_schema(df: DataFrame, schema: dict[str, str]) -> DataFrame:
    """`df` with the columns of `schema` in order and cast; missing columns are an error."""
    missing = [c for c in schema if c not in df.columns]
    if missing:
        raise ValueError(f"columns missing: {', '.join(missing)}")
    return df.select(*[F.col(c).cast(t).alias(c) for c, t in schema.items()])


def summed(op: DataFrame) -> DataFrame:
    """Duplicate cells added up."""
    return op.groupBy("sys", "row", "col").agg(F.sum("re").alias("re"), F.sum("im").alias("im"))


def assert_finite(df: DataFrame, *columns: str) -> DataFrame:
    """Raise when evaluated if a value is null, NaN or infinite."""
    for c in columns:
        bad = F.col(c).isNull() | F.isnan(c) | (F.abs(F.col(c)) == float("inf"))
        df = df.withColumn(c, F.when(bad, F.raise_error(F.lit(f"{c} is null, NaN or infinite")).cast("double")).otherwise(F.col(c)))
    return df


def assert_hermitian(op: DataFrame, tol: float = 1e-9) -> DataFrame:
    """`op`, after one pass that raises if it differs from its adjoint."""
    swapped = op.select("sys", F.col("row").alias("col"), F.col("col").alias("row"), (-F.col("re")).alias("re"), F.col("im"))
    off = summed(op.unionByName(swapped)).where((F.abs("re") > tol) | (F.abs("im") > tol))
    if not off.isEmpty():
        raise ValueError("the operator is not Hermitian")
    return op


def levels(n: int) -> int:
    if n < 2:
        raise ValueError("at least two levels are needed")
    return n
