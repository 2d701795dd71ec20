"""Invariants and comparisons."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T


def compare(a: DataFrame, b: DataFrame, keys: list[str], value: str = "x") -> DataFrame:
    """rows, only_a, only_b, largest: a full outer join on `keys`, absent cells counting as 0."""
    x = a.select(*keys, F.col(value).alias("_a"))
    y = b.select(*keys, F.col(value).alias("_b"))
    d = x.join(y, keys, "full")
    gap = F.abs(F.coalesce("_a", F.lit(0.0)) - F.coalesce("_b", F.lit(0.0)))
    return d.agg(F.count(F.lit(1)).alias("rows"), F.count(F.when(F.col("_b").isNull(), 1)).alias("only_a"), F.count(F.when(F.col("_a").isNull(), 1)).alias("only_b"), F.max(gap).alias("largest"))


def basis_gram(elem: DataFrame) -> DataFrame:
    """i, j, re, im of Tr(F_i F_j), nonzeros only: the unit matrix."""
    a = elem.select(F.col("idx").alias("i"), "row", "col", F.col("re").alias("x"), F.col("im").alias("y"))
    b = elem.select(F.col("idx").alias("j"), F.col("col").alias("row"), F.col("row").alias("col"), "re", "im")
    g = a.join(b, ["row", "col"]).groupBy("i", "j").agg(F.sum(F.expr("x*re-y*im")).alias("re"), F.sum(F.expr("x*im+y*re")).alias("im"))
    return g.where("abs(re) > 1e-9 OR abs(im) > 1e-9")


def rates_trace(relaxation: DataFrame, rates: DataFrame, n: int) -> DataFrame:
    """sys, trace_r, expected: Tr R and -n Tr(rates), which agree."""
    r = relaxation.where("s = n").groupBy("sys").agg(F.sum("x").alias("trace_r"))
    e = rates.where("j = k").groupBy("sys").agg((-n * F.sum("re")).alias("expected"))
    return r.join(e, "sys")


def antisymmetric_gap(mat: DataFrame) -> DataFrame:
    """sys, gap: largest |x_sn + x_ns|; 0 for the drift of a Hamiltonian."""
    other = mat.select("sys", F.col("n").alias("s"), F.col("s").alias("n"), "x")
    return mat.unionByName(other).groupBy("sys", "s", "n").agg(F.sum("x").alias("g")).groupBy("sys").agg(F.max(F.abs("g")).alias("gap"))


@F.pandas_udf(T.DoubleType())
def smallest_eigenvalue(cells: pd.Series) -> pd.Series:
    """Of Hermitian matrices packed row by row as re, im, re, im, ...; at least -tol for a density operator."""
    import numpy as np

    out = []
    for c in cells:
        a = np.asarray(c, float).reshape(-1, 2)
        n = round(len(a) ** 0.5)
        out.append(float(np.linalg.eigvalsh((a[:, 0] + 1j * a[:, 1]).reshape(n, n))[0]))
    return pd.Series(out)


def residual(system_matrix: DataFrame, k: DataFrame, v: DataFrame) -> DataFrame:
    """sys, s, x of A v + k; 0 for a steady state."""
    av = system_matrix.join(v.select("sys", F.col("idx").alias("n"), F.col("x").alias("v")), ["sys", "n"]).select("sys", "s", (F.col("x") * F.col("v")).alias("x"))
    return av.unionByName(k.select("sys", "s", "x")).groupBy("sys", "s").agg(F.sum("x").alias("x"))


def state_facts(rho: DataFrame, n: int) -> DataFrame:
    """sys, trace, hermitian_gap, smallest: Tr(rho), the largest |rho - rho^+| and the smallest eigenvalue of a density operator."""
    d = rho.select("sys", "row", "col", "re", "im")
    mirror = d.select("sys", F.col("col").alias("row"), F.col("row").alias("col"), (-F.col("re")).alias("re"), F.col("im"))
    gap = d.unionByName(mirror).groupBy("sys", "row", "col").agg(F.sum("re").alias("x"), F.sum("im").alias("y"))
    gap = gap.groupBy("sys").agg(F.max(F.sqrt(F.expr("x*x+y*y"))).alias("hermitian_gap"))
    trace = d.groupBy("sys").agg(F.sum(F.when(F.col("row") == F.col("col"), F.col("re")).otherwise(0.0)).alias("trace"))
    # Cells in order, with zeros for those that are absent: at most n^2 a system.
    every = d.select("sys").distinct().select("sys", F.explode(F.sequence(F.lit(1), F.lit(n))).alias("row")).select("sys", "row", F.explode(F.sequence(F.lit(1), F.lit(n))).alias("col"))
    cells = every.join(d, ["sys", "row", "col"], "left").na.fill(0.0, ["re", "im"]).groupBy("sys").agg(F.array_sort(F.collect_list(F.struct("row", "col", "re", "im"))).alias("c"))
    packed = cells.select("sys", smallest_eigenvalue(F.flatten(F.transform("c", lambda c: F.array(c["re"], c["im"])))).alias("smallest"))
    return trace.join(gap, "sys").join(packed, "sys")


def conjugate_gap(eig: DataFrame, digits: int = 6) -> DataFrame:
    """sys, unmatched: eigenvalues of a real matrix whose conjugate isn't one, in so many digits; 0."""
    at = lambda im: (F.round("re", digits) + 0.0, F.round(im, digits) + 0.0)
    own = eig.select("sys", *[c.alias(a) for c, a in zip(at(F.col("im")), "xy", strict=True)], F.lit(1).alias("w"))
    other = eig.select("sys", *[c.alias(a) for c, a in zip(at(-F.col("im")), "xy", strict=True)], F.lit(-1).alias("w"))
    return own.unionByName(other).groupBy("sys", "x", "y").agg(F.sum("w").alias("w")).groupBy("sys").agg((F.sum(F.abs("w")) / 2).cast("long").alias("unmatched"))
