"""What the methods are compared with."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from coherent.operators import assemble, basis, structure


def dense_tensors(spark: SparkSession, n: int) -> DataFrame:
    """m, n, s, alpha, beta of all M^3 entries, zeros too: the unrestricted evaluation, for n of 4 at most."""
    if n > 4:
        raise ValueError("the dense evaluation is for at most four levels")
    i = lambda c: spark.range(1, basis.size(n) + 1).withColumnRenamed("id", c)
    every = i("m").crossJoin(i("n")).crossJoin(i("s"))
    return every.join(structure.by_trace(basis.elements(spark, n)), ["m", "n", "s"], "left").na.fill(0.0, ["alpha", "beta"])


def sequential(l: DataFrame, weights: DataFrame, n: int) -> DataFrame:  # noqa: E741
    """R in one partition with stored tensors: the one-process variant, in numpy."""
    m = basis.size(n)
    spark = l.sparkSession
    t = structure.tensor(spark, n).coalesce(1)
    rows = t.select(F.lit("t").alias("kind"), F.lit("").alias("sys"), F.lit(0).alias("op"), "m", "n", "s", F.col("alpha").alias("a"), F.col("beta").alias("b"))
    vec = l.join(weights, ["sys", "op"]).select(F.lit("l").alias("kind"), "sys", "op", F.col("idx").alias("m"), F.lit(0).cast("long").alias("n"), F.lit(0).cast("long").alias("s"), (F.col("re") * F.sqrt("gamma")).alias("a"), (F.col("im") * F.sqrt("gamma")).alias("b"))

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        t, v = pdf[pdf["kind"] == "t"], pdf[pdf["kind"] == "l"]
        alpha, zeta = np.zeros((m, m, m)), np.zeros((m, m, m), complex)
        at = (t["m"] - 1, t["n"] - 1, t["s"] - 1)
        alpha[at], zeta[at] = t["a"], t["a"] + 1j * t["b"]
        out = []
        for sys, g in v.groupby("sys"):
            r = np.zeros((m, m))
            for _, o in g.groupby("op"):
                c = np.zeros(m, complex)
                c[o["m"] - 1] = o["a"] + 1j * o["b"]
                r += -0.5 * np.einsum("ln,ls->sn", np.einsum("j,jln->ln", c, zeta), np.einsum("k,kls->ls", c.conj(), alpha)).real
            s, k = np.nonzero(np.abs(r) > 1e-12)
            out.append(pd.DataFrame({"sys": sys, "s": s + 1, "n": k + 1, "x": r[s, k]}))
        return pd.concat(out) if out else pd.DataFrame({"sys": [], "s": [], "n": [], "x": []})

    return rows.unionByName(vec).groupBy(F.lit(0).alias("_one")).applyInPandas(run, "sys string, s long, n long, x double")


def superoperator(jumps: DataFrame, weights: DataFrame, n: int, hamiltonian: DataFrame | None = None) -> DataFrame:
    """The complex N^2 x N^2 generator that the real form replaces."""
    return assemble.superoperator(assemble.jump_cells(jumps, weights), n, hamiltonian)


def rk4_density(hamiltonian: DataFrame, jumps: DataFrame, weights: DataFrame, rho: DataFrame, n: int, steps: int, period: float) -> DataFrame:
    """sys, row, col, re, im: the density matrix propagated as a matrix, apart from the expansion."""
    tag = lambda d, kind: d.withColumn("kind", F.lit(kind))
    j = jumps.join(weights, ["sys", "op"]).select("sys", "op", "row", "col", (F.col("re") * F.sqrt("gamma")).alias("re"), (F.col("im") * F.sqrt("gamma")).alias("im"))
    plain = lambda d: d.select("sys", F.lit(0).alias("op"), "row", "col", "re", "im")
    every = tag(plain(hamiltonian), "h").unionByName(tag(j, "l")).unionByName(tag(plain(rho), "r"))
    h = period / steps

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        def matrix(g: pd.DataFrame) -> np.ndarray:
            a = np.zeros((n, n), complex)
            np.add.at(a, (g["row"] - 1, g["col"] - 1), g["re"] + 1j * g["im"])
            return a

        ham, state = matrix(pdf[pdf["kind"] == "h"]), matrix(pdf[pdf["kind"] == "r"])
        ls = [matrix(g) for _, g in pdf[pdf["kind"] == "l"].groupby("op")]
        sink = sum((l.conj().T @ l for l in ls), np.zeros((n, n), complex))  # noqa: E741

        def f(r: np.ndarray) -> np.ndarray:
            return -1j * (ham @ r - r @ ham) + sum((l @ r @ l.conj().T for l in ls), 0 * r) - (sink @ r + r @ sink) / 2  # noqa: E741

        for _ in range(steps):
            a = f(state)
            b = f(state + h / 2 * a)
            c = f(state + h / 2 * b)
            state = state + h / 6 * (a + 2 * b + 2 * c + f(state + h * c))
        r, c = np.indices((n, n)) + 1
        return pd.DataFrame({"sys": pdf["sys"].iloc[0], "row": r.ravel(), "col": c.ravel(), "re": state.real.ravel(), "im": state.imag.ravel()})

    return every.groupBy("sys").applyInPandas(run, "sys string, row int, col int, re double, im double")
