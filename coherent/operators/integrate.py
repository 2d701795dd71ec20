"""Propagation of dv/dt = (Q0 + eps(t) Q1 + R) v + k by fourth-order Runge-Kutta, in four strategies.

The drive is constant on intervals, and steps end on its switches; a step uses the value inside it, also at its end, so
that the strategies agree. `grouped` steps one system in one task; `collapsed` applies the affine map of a constant step
by repeated squaring; `panel` splits rows over tasks and exchanges the vector; `step` is one plan a stage, for few steps;
`auto` chooses by size.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coherent.operators import linalg, partition
from coherent.sources.store import keep

STRATEGIES = ("grouped", "collapsed", "panel", "step")  # and "auto"


def bundle(q0: DataFrame, r: DataFrame, k: DataFrame, v0: DataFrame, q1: DataFrame | None = None) -> DataFrame:
    """All parts of the systems in one frame (sys, part, s, n, x), keyed for a grouped map."""
    part = lambda d, name: d.select("sys", F.lit(name).alias("part"), "s", "n", "x")
    col = lambda d, name, i: d.select("sys", F.lit(name).alias("part"), F.col(i).alias("s"), F.lit(0).cast("long").alias("n"), "x")
    out = part(q0, "Q0").unionByName(part(r, "R")).unionByName(col(k, "k", "s")).unionByName(col(v0, "v", "idx"))
    return out if q1 is None else out.unionByName(part(q1, "Q1"))


#: One system in one task: dense up to so many rows, sparse up to so many nonzeros; larger ones go by panels.
DENSE, SPARSE = 4000, 1 << 26


class Csr:
    """A sparse square matrix for products with a vector, in numpy alone."""

    def __init__(self, s: np.ndarray, n: np.ndarray, x: np.ndarray, m: int) -> None:
        order = np.lexsort((n, s))
        s, self.n, self.x, self.m = s[order], n[order], x[order], m
        self.rows, self.begin = np.unique(s, return_index=True)

    def __matmul__(self, v: np.ndarray) -> np.ndarray:
        out = np.zeros(self.m)
        if len(self.x):
            out[self.rows] = np.add.reduceat(self.x * v[self.n], self.begin)
        return out


def matrices(pdf: pd.DataFrame, m: int, dense: bool = True) -> tuple:
    """(Q0 + R, Q1, k, v0) of one system; matrices as arrays, or sparse."""
    if dense and m > DENSE:
        raise ValueError(f"{m} rows are more than one task should hold as a dense matrix")
    s, n, x, part = pdf["s"].to_numpy(int) - 1, pdf["n"].to_numpy(int) - 1, pdf["x"].to_numpy(float), pdf["part"].to_numpy()
    vec = {}
    for p in ("k", "v"):
        vec[p] = np.zeros(m)
        np.add.at(vec[p], s[part == p], x[part == p])
    out = []
    for names in (("Q0", "R"), ("Q1",)):
        on = np.isin(part, names)
        if dense:
            a = np.zeros((m, m))
            np.add.at(a, (s[on], n[on]), x[on])
        else:
            a = Csr(s[on], n[on], x[on], m)
        out.append(a)
    return (*out, vec["k"], vec["v"])


def step(a: np.ndarray, k: np.ndarray, v: np.ndarray, h: float) -> np.ndarray:
    f = lambda u: a @ u + k
    s1 = f(v)
    s2 = f(v + h / 2 * s1)
    s3 = f(v + h / 2 * s2)
    return v + h / 6 * (s1 + 2 * s2 + 2 * s3 + f(v + h * s3))


def step_map(a: np.ndarray, k: np.ndarray, h: float) -> np.ndarray:
    """The affine map of one step on (v, 1): the exponential's series to fourth order."""
    m = len(a)
    b = np.zeros((m + 1, m + 1))
    b[:m, :m], b[:m, m] = h * a, h * k
    out = term = np.eye(m + 1)
    for i in range(1, 5):
        term = term @ b / i
        out = out + term
    return out


def _together(pdf: pd.DataFrame, eps: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Cells of Q0 + R + eps Q1."""
    d = pdf[pdf["part"].isin(("Q0", "Q1", "R"))]
    x = d["x"].to_numpy(float) * np.where(d["part"] == "Q1", eps, 1.0)
    return d["s"].to_numpy(int) - 1, d["n"].to_numpy(int) - 1, x


def segments(steps: int, period: float, drive: tuple[tuple[float, float], ...]) -> list[tuple[int, float]]:
    """(steps, eps) of the intervals (fraction of the period, eps); fractions must hold whole steps."""
    out = []
    for share, eps in drive:
        count = round(share * steps)
        if abs(count - share * steps) > 1e-9:
            raise ValueError("steps must end where the drive switches")
        out.append((count, eps))
    return out


def rk4(system: DataFrame, m: int, steps: int, period: float, drive: tuple[tuple[float, float], ...] = ((1.0, 0.0),), strategy: str = "grouped", every: int | None = None) -> DataFrame:
    """sys, step, t, idx, x after one period of `steps` steps (and, if asked, after each `every` of them)."""
    h, parts = period / steps, segments(steps, period, drive)
    if strategy == "auto":
        systems, nnz = system.groupBy("sys").agg(F.count(F.lit(1)).alias("of")).agg(F.count(F.lit(1)), F.max("of")).first()
        strategy = choose_strategy(m, nnz or 0, steps, systems)
    if strategy == "step":
        return _by_plans(system, m, steps, h, parts)

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        if len(pdf) > SPARSE:
            raise ValueError(f"{len(pdf)} nonzeros are more than one task should hold; use panels")
        sparse = strategy == "grouped" and len(pdf) * 8 < m * m
        a0, q1, k, v = matrices(pdf, m, not sparse)
        rows, done = [], 0

        def note(v: np.ndarray) -> None:
            rows.append(pd.DataFrame({"sys": pdf["sys"].iloc[0], "step": done, "t": done * h, "idx": np.arange(1, m + 1), "x": v}))

        for count, eps in parts:
            a = Csr(*_together(pdf, eps), m) if sparse else a0 + eps * q1
            if strategy == "collapsed":
                v = (np.linalg.matrix_power(step_map(a, k, h), count) @ np.append(v, 1.0))[:m]
                done += count
                continue
            for _ in range(count):
                v = step(a, k, v, h)
                done += 1
                if every and done % every == 0 and done < steps:
                    note(v)
        note(v)
        return pd.concat(rows)

    if strategy == "panel":
        return _by_panels(system, m, h, parts)
    return system.groupBy("sys").applyInPandas(run, "sys string, step int, t double, idx long, x double")


def panel_rows(system: DataFrame, m: int, panels: int) -> DataFrame:
    """panel, s, part, n, x: rows packed as arrays of columns and values, in panels of about equal nonzeros, one panel a task."""
    mat = system.where("part IN ('Q0','Q1','R')")
    where = partition.balanced(partition.row_counts(mat, m), panels).select("sys", "s", "panel")
    packed = mat.groupBy("sys", "s", "part").agg(F.collect_list(F.struct("n", "x")).alias("c"))  # at most m cells a row
    packed = packed.select("sys", "s", "part", F.transform("c", lambda c: c["n"]).alias("n"), F.transform("c", lambda c: c["x"]).alias("x"))
    return packed.join(where, ["sys", "s"]).repartitionById(panels, F.col("panel"))


def _by_panels(system: DataFrame, m: int, h: float, parts: list[tuple[int, float]], panels: int | None = None) -> DataFrame:
    """Balanced panels of rows, each a task that computes its rows of every stage in numpy; vectors of m doubles go round.

    One system at a time: the vector (m doubles, bounded by the model) is what tasks and driver exchange.
    """
    spark, out = system.sparkSession, []
    panels = panels or spark.sparkContext.defaultParallelism
    system = keep(system, "system")
    for (name,) in system.select("sys").distinct().collect():
        own = system.where(F.col("sys") == name)
        rows = panel_rows(own, m, panels).persist()  # read four times a step; given back below
        vec = {p: np.zeros(m) for p in ("k", "v")}
        for p, s, x in own.where("part IN ('k','v')").select("part", "s", "x").toArrow().to_pandas().itertuples(index=False):
            vec[p][int(s) - 1] += x
        v, done = vec["v"], 0

        def product(eps: float, u: np.ndarray, rows: DataFrame = rows) -> np.ndarray:
            shared = spark.sparkContext.broadcast((eps, u))

            def part(batches):
                eps, u = shared.value
                for b in batches:
                    n, x = b.column("n"), b.column("x")
                    begin = n.offsets.to_numpy()[:-1].astype(np.int64) - n.offsets[0].as_py()
                    flat = x.flatten().to_numpy() * u[n.flatten().to_numpy() - 1]
                    own = np.add.reduceat(flat, begin) if len(flat) else np.zeros(0)
                    driven = np.fromiter((p == "Q1" for p in b.column("part").to_pylist()), bool, b.num_rows)
                    yield pa.RecordBatch.from_arrays([b.column("s"), pa.array(own * np.where(driven, eps, 1.0))], names=["s", "x"])

            got, y = rows.select("s", "part", "n", "x").mapInArrow(part, "s long, x double").toArrow(), np.zeros(m)
            np.add.at(y, got["s"].to_numpy() - 1, got["x"].to_numpy())
            shared.destroy()
            return y

        for count, eps in parts:
            for _ in range(count):
                f = lambda u, eps=eps: product(eps, u) + vec["k"]  # noqa: B023, E731
                s1 = f(v)
                s2 = f(v + h / 2 * s1)
                s3 = f(v + h / 2 * s2)
                v = v + h / 6 * (s1 + 2 * s2 + 2 * s3 + f(v + h * s3))
                done += 1
        rows.unpersist()
        out.append(pd.DataFrame({"sys": name, "step": done, "t": done * h, "idx": np.arange(1, m + 1), "x": v}))
    schema = "sys string, step int, t double, idx long, x double"
    return spark.createDataFrame(pd.concat(out), schema) if out else spark.createDataFrame([], schema)


def _by_plans(system: DataFrame, m: int, steps: int, h: float, parts: list[tuple[int, float]]) -> DataFrame:
    """Joins and sums only, four products a step: for teaching and a few tens of steps.

    Each stage's vector (m values a system) goes through the driver, so plans stay one product deep.
    """
    system = system.persist()
    fixed = lambda d: d.sparkSession.createDataFrame(d.select("sys", "idx", "x").collect(), "sys string, idx long, x double")
    v = fixed(system.where("part = 'v'").select("sys", F.col("s").alias("idx"), "x"))
    k = fixed(system.where("part = 'k'").select("sys", F.col("s").alias("idx"), "x"))
    add = lambda *terms: _sum([d.select("sys", "idx", (F.col("x") * w).alias("x")) for d, w in terms])
    for count, eps in parts:
        a = system.where("part IN ('Q0','Q1','R')").select("sys", "s", "n", F.when(F.col("part") == "Q1", F.col("x") * eps).otherwise(F.col("x")).alias("x"))
        f = lambda u, a=a: fixed(add((linalg.matvec(a, u).withColumnRenamed("s", "idx"), 1.0), (k, 1.0)))
        for _ in range(count):
            s1 = f(v)
            s2 = f(add((v, 1.0), (s1, h / 2)))
            s3 = f(add((v, 1.0), (s2, h / 2)))
            s4 = f(add((v, 1.0), (s3, h)))
            v = fixed(add((v, 1.0), (s1, h / 6), (s2, h / 3), (s3, h / 3), (s4, h / 6)))
    system.unpersist()
    return v.select("sys", F.lit(steps).alias("step"), F.lit(steps * h).alias("t"), "idx", "x")


def _sum(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out.groupBy("sys", "idx").agg(F.sum("x").alias("x"))


def choose_strategy(m: int, nnz: int, steps: int, systems: int) -> str:
    """Collapsed where matrix powers cost less than the steps; grouped while a system fits a task; else panels."""
    if m <= DENSE and 36 * m**3 < 4 * steps * nnz:
        return "collapsed"
    return "grouped" if nnz <= SPARSE // 4 else "panel"


def steady_state(system: DataFrame, m: int, method: str = "auto", rounds: int = 10_000, tol: float = 1e-12) -> DataFrame:
    """sys, idx, x with (Q0 + R) v + k = 0.

    `direct`: least squares in one task a system, for up to `DENSE` rows. `iterative`: conjugate gradients on the normal
    equations over the sparse rows, which keeps a few vectors beside the nonzeros; `auto` takes it beyond a tenth of `DENSE` rows.
    """
    if method == "auto":
        method = "direct" if m <= DENSE // 10 else "iterative"

    def direct(pdf: pd.DataFrame) -> np.ndarray:
        a, _, k, _ = matrices(pdf, m)
        return np.linalg.lstsq(a, -k, rcond=None)[0]

    def iterative(pdf: pd.DataFrame) -> np.ndarray:
        if len(pdf) > SPARSE:
            raise ValueError(f"{len(pdf)} nonzeros are more than one task should hold")
        s, n, x = _together(pdf[pdf["part"] != "Q1"], 0.0)
        a, back = Csr(s, n, x, m), Csr(n, s, x, m)
        k = matrices(pdf, m, False)[2]
        v = np.zeros(m)
        r = -k - a @ v
        z = back @ r
        p, size = z.copy(), z @ z
        for _ in range(rounds):
            if size <= tol * tol:
                break
            w = a @ p
            step = size / (w @ w)
            v += step * p
            r -= step * w
            z = back @ r
            p, size = z + (z @ z) / size * p, z @ z
        return v

    solve = {"direct": direct, "iterative": iterative}[method]

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"sys": pdf["sys"].iloc[0], "idx": np.arange(1, m + 1), "x": solve(pdf)})

    return system.groupBy("sys").applyInPandas(run, "sys string, idx long, x double")


def ensemble(systems: list[DataFrame], work, pools: int = 2) -> list:
    """`work(system)` for every sample: `pools` at a time, each in a scheduler pool of its own, and each over all its tasks.

    The outer level of a two-level scheme: samples run side by side as jobs, and a job deals one sample's rows over tasks.
    """
    from concurrent.futures import ThreadPoolExecutor

    def one(i: int):
        sc = systems[i].sparkSession.sparkContext
        sc.setLocalProperty("spark.scheduler.pool", f"sample-{i % pools}")
        try:
            return work(systems[i])
        finally:
            sc.setLocalProperty("spark.scheduler.pool", None)

    with ThreadPoolExecutor(pools) as pool:
        return list(pool.map(one, range(len(systems))))
