"""Matrix algebra on coordinate frames (sys, row, col, re, im): joins and sums."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

TOL = 1e-12


def _nonzero(df: DataFrame) -> DataFrame:
    return df.where((F.abs("re") > TOL) | (F.abs("im") > TOL))


def matmul(a: DataFrame, b: DataFrame) -> DataFrame:
    x = a.select("sys", "row", F.col("col").alias("mid"), F.col("re").alias("x"), F.col("im").alias("y"))
    y = b.select("sys", F.col("row").alias("mid"), "col", "re", "im")
    return _nonzero(x.join(y, ["sys", "mid"]).groupBy("sys", "row", "col").agg(F.sum(F.expr("x*re-y*im")).alias("re"), F.sum(F.expr("x*im+y*re")).alias("im")))


def adjoint(a: DataFrame) -> DataFrame:
    return a.select("sys", F.col("col").alias("row"), F.col("row").alias("col"), "re", (-F.col("im")).alias("im"))


def combine(a: DataFrame, b: DataFrame, x: float = 1.0, y: float = 1.0) -> DataFrame:
    s = lambda d, w: d.select("sys", "row", "col", (F.col("re") * w).alias("re"), (F.col("im") * w).alias("im"))
    return _nonzero(s(a, x).unionByName(s(b, y)).groupBy("sys", "row", "col").agg(F.sum("re").alias("re"), F.sum("im").alias("im")))


def commutator(a: DataFrame, b: DataFrame) -> DataFrame:
    return combine(matmul(a, b), matmul(b, a), 1.0, -1.0)


def kron(a: DataFrame, b: DataFrame, size_b: int) -> DataFrame:
    x = a.select("sys", F.col("row").alias("r"), F.col("col").alias("c"), F.col("re").alias("x"), F.col("im").alias("y"))
    return x.join(b, "sys").select("sys", ((F.col("r") - 1) * size_b + F.col("row")).cast("int").alias("row"), ((F.col("c") - 1) * size_b + F.col("col")).cast("int").alias("col"), F.expr("x*re-y*im").alias("re"), F.expr("x*im+y*re").alias("im"))


def matvec(mat: DataFrame, vec: DataFrame) -> DataFrame:
    """sys, s, x of a real matrix (sys, s, n, x) and vector (sys, idx, x)."""
    v = vec.select("sys", F.col("idx").alias("n"), F.col("x").alias("v"))
    return mat.join(v, ["sys", "n"]).groupBy("sys", "s").agg(F.sum(F.col("x") * F.col("v")).alias("x"))


def trace(a: DataFrame) -> DataFrame:
    return a.where("row = col").groupBy("sys").agg(F.sum("re").alias("re"), F.sum("im").alias("im"))


def dense_rows(mat: DataFrame, m: int) -> DataFrame:
    """sys, s, cells: rows packed as arrays of m doubles; worth it from a density of about a third."""
    packed = mat.groupBy("sys", "s").agg(F.map_from_entries(F.collect_list(F.struct("n", "x"))).alias("e"))  # at most m a row
    return packed.select("sys", "s", F.transform(F.sequence(F.lit(1), F.lit(m)), lambda n: F.coalesce(F.col("e")[n.cast("long")], F.lit(0.0))).alias("cells"))


def array_matvec(rows: DataFrame, vector: DataFrame) -> DataFrame:
    """sys, s, x of packed rows and one packed vector a system (sys, v)."""
    dot = F.aggregate(F.zip_with("cells", "v", lambda a, b: a * b), F.lit(0.0), lambda s, x: s + x)
    return rows.join(F.broadcast(vector), "sys").select("sys", "s", dot.alias("x"))


def frobenius(a: DataFrame, b: DataFrame) -> DataFrame:
    return combine(a, b, 1.0, -1.0).groupBy("sys").agg(F.sqrt(F.sum(F.expr("re*re+im*im"))).alias("distance"))


def top_cells(mat: DataFrame, k: int) -> DataFrame:
    """The k cells of largest size of each system."""
    w = Window.partitionBy("sys").orderBy(F.abs(F.round("x", 9)).desc(), "s", "n")
    return mat.withColumn("place", F.row_number().over(w)).where(F.col("place") <= k)
