"""Spectra of generators: eigenvalues per system, density on a grid, and moments that need no eigenvalues."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: One non-symmetric dense matrix doesn't distribute: a task holds it. Beyond this size use `moments`.
MOST = 4000


def eigenvalues(mat: DataFrame, m: int) -> DataFrame:
    """sys, i, re, im, ordered by real then imaginary part."""
    if m > MOST:
        raise ValueError(f"{m} rows are more than one task should hold; use moments()")

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        a = np.zeros((m, m))
        np.add.at(a, (pdf["s"].to_numpy(int) - 1, pdf["n"].to_numpy(int) - 1), pdf["x"].to_numpy(float))
        e = np.sort_complex(np.linalg.eigvals(a))
        return pd.DataFrame({"sys": pdf["sys"].iloc[0], "i": np.arange(m), "re": e.real, "im": e.imag})

    return mat.groupBy("sys").applyInPandas(run, "sys string, i int, re double, im double")


def moments(mat: DataFrame) -> DataFrame:
    """sys, trace, trace2: sums of the eigenvalues and of their squares."""
    t = mat.where("s = n").groupBy("sys").agg(F.sum("x").alias("trace"))
    other = mat.select("sys", F.col("s").alias("n"), F.col("n").alias("s"), F.col("x").alias("y"))
    t2 = mat.join(other, ["sys", "s", "n"]).groupBy("sys").agg(F.sum(F.col("x") * F.col("y")).alias("trace2"))
    return t.join(t2, "sys")


def _cells(eig: DataFrame, nx: int, ny: int, bounds: tuple[float, float, float, float] | None) -> DataFrame:
    """sys, re, im, x0, dx, y0, dy, bx, by: each point's cell; an upper edge belongs to the last cell, points outside have none."""
    if bounds is None:
        edges = eig.groupBy("sys").agg(F.min("re").alias("x0"), F.max("re").alias("x1"), F.min("im").alias("y0"), F.max("im").alias("y1"))
        d = eig.select("sys", "re", "im").join(edges, "sys")
    else:
        d = eig.select("sys", "re", "im", *[F.lit(float(v)).alias(c) for c, v in zip(("x0", "x1", "y0", "y1"), bounds, strict=True)])
    width = lambda lo, hi, k: F.when(F.col(hi) > F.col(lo), (F.col(hi) - F.col(lo)) / k).otherwise(1.0)
    d = d.withColumn("dx", width("x0", "x1", nx)).withColumn("dy", width("y0", "y1", ny))
    cell = lambda v, lo, hi, step, k: F.when(F.col(v).between(F.col(lo), F.col(hi)), F.least(F.floor((F.col(v) - F.col(lo)) / F.col(step)), F.lit(k - 1))).cast("int")
    return d.withColumn("bx", cell("re", "x0", "x1", "dx", nx)).withColumn("by", cell("im", "y0", "y1", "dy", ny))


def density(eig: DataFrame, nx: int = 100, ny: int = 100, bounds: tuple[float, float, float, float] | None = None, empty: bool = False) -> DataFrame:
    """sys, bx, by, n, density: points per cell, divided by points and cell area. The trivial eigenvalue 0 isn't among them.

    Without `bounds` each system's own extent is the area. Points outside given bounds are one row with null bx and by and no
    density, so that no mass is lost unseen. With `empty`, cells without points are rows too.
    """
    d = _cells(eig, nx, ny, bounds)
    inside = F.col("bx").isNotNull() & F.col("by").isNotNull()
    grid = d.groupBy("sys", F.when(inside, F.col("bx")).alias("bx"), F.when(inside, F.col("by")).alias("by")).agg(F.count(F.lit(1)).alias("n"))
    area = d.groupBy("sys").agg(F.count(F.lit(1)).alias("_all"), F.first(F.col("dx") * F.col("dy")).alias("_area"))
    if empty:
        every = area.select("sys", F.explode(F.sequence(F.lit(0), F.lit(nx - 1))).alias("bx")).select("sys", "bx", F.explode(F.sequence(F.lit(0), F.lit(ny - 1))).alias("by"), F.lit(0).cast("long").alias("n"))
        grid = grid.unionByName(every).groupBy("sys", "bx", "by").agg(F.sum("n").alias("n"))
    return grid.join(area, "sys").select("sys", "bx", "by", "n", F.when(F.col("bx").isNotNull(), F.col("n") / F.col("_all") / F.col("_area")).alias("density"))


def power_trace(order: int, m: int):
    """A grouped aggregate (s, n, x) -> Tr(A^order) of the matrix whose cells are a group's rows; at most `MOST` rows."""
    if m > MOST:
        raise ValueError(f"{m} rows are more than one task should hold; use moments()")

    @F.pandas_udf("double")
    def run(s: pd.Series, n: pd.Series, x: pd.Series) -> float:
        a = np.zeros((m, m))
        np.add.at(a, (s.to_numpy(int) - 1, n.to_numpy(int) - 1), x.to_numpy(float))
        return float(np.trace(np.linalg.matrix_power(a, order)))

    return run


def load_boundary(spark: SparkSession, path: str) -> DataFrame:
    """Points (re, im) of a boundary curve that the user supplies as CSV."""
    return spark.read.schema("re double, im double").option("mode", "FAILFAST").csv(path)


def slowest(eig: DataFrame, k: int) -> DataFrame:
    """The k eigenvalues nearest to zero in real part, of each system."""
    from pyspark.sql.window import Window

    return eig.withColumn("place", F.row_number().over(Window.partitionBy("sys").orderBy(F.col("re").desc(), "im"))).where(F.col("place") <= k)
