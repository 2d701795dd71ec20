"""Assembly of the real linear system dv/dt = (Q(t) + R) v + k.

Contractions generate the planes of a vector's own nonzeros and sum by output index. R contracts each factor with its
coefficients before the join on the middle index (route `tensor`), or goes through matrix cells (route `cell`), which has the
output's own order of work. Symmetry: the second term of R is the conjugate of the first, so twice a real part is taken.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from coherent.operators import basis, expand, partition, structure
from coherent.sources.store import fresh_path, keep

TOL = 1e-12
KEY, PARTS = ["sys", "op"], 16


def _kept(df: DataFrame) -> DataFrame:
    return df.where(F.abs("x") > TOL)


def drift(h: DataFrame, n: int) -> DataFrame:
    """sys, s, n, x: Q of a Hamiltonian's real coefficients `h` (sys, idx, re)."""
    p = structure.planes(h.select("sys", "idx", "re"), n)
    return _kept(p.where("abs(alpha) > 1e-12").groupBy("sys", "s", "n").agg(F.sum(F.col("re") * F.col("alpha")).alias("x")))


def drift_at(q0: DataFrame, q1: DataFrame, drive: DataFrame, times: DataFrame) -> DataFrame:
    """sys, t, s, n, x: Q0 + eps(t) Q1 at `times` (sys, t), with eps from the intervals `drive` (sys, t0, t1, eps)."""
    at = times.join(drive, (times["sys"] == drive["sys"]) & (times["t"] >= drive["t0"]) & (times["t"] < drive["t1"])).select(times["sys"], "t", "eps")
    parts = q0.withColumn("w", F.lit(False)).unionByName(q1.withColumn("w", F.lit(True)))
    both = parts.join(at, "sys").groupBy("sys", "t", "s", "n").agg(F.sum(F.col("x") * F.when(F.col("w"), F.col("eps")).otherwise(1.0)).alias("x"))
    return _kept(both)


def inhomogeneity(l: DataFrame, weights: DataFrame, n: int) -> DataFrame:  # noqa: E741
    """sys, s, x: k of jump operators' coefficients `l` (sys, op, idx, re, im) and `weights` (sys, op, gamma)."""
    w = l.join(weights, KEY)
    p = structure.planes(w.select(*KEY, "gamma", "idx", F.col("re").alias("m_re"), F.col("im").alias("m_im")), n).where("abs(alpha) > 1e-12")
    other = l.select(*KEY, F.col("idx").alias("n"), "re", "im")
    x = -F.col("gamma") / n * F.expr("(m_im*re-m_re*im)*alpha")
    return _kept(p.join(other, [*KEY, "n"]).groupBy("sys", "s").agg(F.sum(x).alias("x")))


def inhomogeneity_from_rates(rates: DataFrame, n: int) -> DataFrame:
    """sys, s, x: k of a full rate matrix (sys, j, k, re, im)."""
    r = rates.select("sys", F.col("j").alias("m"), F.col("k").alias("n"), "im")
    p = structure.alpha(rates.sparkSession, n)
    return _kept(r.join(p, ["m", "n"]).groupBy("sys", "s").agg((-F.sum(F.col("im") * F.col("alpha")) / n).alias("x")))


def _factors(l: DataFrame, n: int) -> tuple[DataFrame, DataFrame]:  # noqa: E741
    """sum_j l_j zeta(j, mid, n) and sum_k conj(l_k) alpha(k, mid, s)."""
    p = structure.planes(l.select(*KEY, "idx", "re", "im"), n)
    a = p.groupBy(*KEY, F.col("n").alias("mid"), F.col("s").alias("n")).agg(F.sum(F.expr("re*alpha-im*beta")).alias("a_re"), F.sum(F.expr("im*alpha+re*beta")).alias("a_im"))
    b = p.where("abs(alpha) > 1e-12").groupBy(*KEY, F.col("n").alias("mid"), F.col("s")).agg(F.sum(F.expr("re*alpha")).alias("b_re"), F.sum(F.expr("-im*alpha")).alias("b_im"))
    some = lambda d, x, y: d.where((F.abs(x) > TOL) | (F.abs(y) > TOL))
    return some(a, "a_re", "a_im"), some(b, "b_re", "b_im")


def relaxation(l: DataFrame, weights: DataFrame, n: int, stages: int = 1, path: str | None = None, route: str = "tensor") -> DataFrame:  # noqa: E741
    """sys, s, n, x: R of jump operators.

    Route `tensor` contracts the structure constants with the coefficients, `cell` goes through matrix cells, `auto` counts the
    coefficients and takes the one with less work. With `stages` > 1 the tensor route is staged (`staged`).
    """
    if route == "auto":
        most = l.groupBy(*KEY).agg(F.count(F.lit(1)).alias("of")).agg(F.max("of")).first()[0]
        route = choose_route(most or 0, n)
    if route == "cell":
        none = l.select(*KEY).distinct().select(*KEY, F.lit(0.0).alias("re"), F.lit(0.0).alias("im"))
        return relaxation_by_cells(expand.rebuild(l, none, n), weights, n)
    if stages > 1:
        return staged(l, weights, n, stages, path or fresh_path(l.sparkSession, "stages"))
    a, b = _factors(l, n)
    return _product(a, b.join(weights, KEY))


def _product(a: DataFrame, b: DataFrame) -> DataFrame:
    x = F.expr("-0.5*gamma*(a_re*b_re-a_im*b_im)")
    return _kept(a.join(b, [*KEY, "mid"]).groupBy("sys", "s", "n").agg(F.sum(x).alias("x")))


def column_panels(a: DataFrame, m: int, stages: int) -> DataFrame:
    """n, stage: the columns of R in ranges of about equal nonzeros of the first factor, counted first and then dealt."""
    counts = a.groupBy(F.lit("").alias("sys"), F.col("n").alias("s")).agg(F.count(F.lit(1)).alias("nnz"))
    return partition.balanced(counts, stages).select(F.col("s").alias("n"), F.col("panel").alias("stage"))


def staged(l: DataFrame, weights: DataFrame, n: int, stages: int, path: str) -> DataFrame:  # noqa: E741
    """R in `stages` blocks of columns under `path`, one after the other.

    Both factors are written once, the first in one folder a block; a block reads its own part of the first factor only, so what is
    joined and shuffled at once is bounded by a block. A block that was finished before (its folder has the mark of a
    committed write) is not computed again, so an interrupted run goes on where it stopped.
    """
    spark = l.sparkSession
    hadoop = spark._jvm.org.apache.hadoop.fs.Path

    def done(folder: str) -> bool:
        at = hadoop(f"{folder}/_SUCCESS")
        return at.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()).exists(at)

    first, second = f"{path}/factors/a", f"{path}/factors/b"
    if not (done(first) and done(second)):
        a, b = _factors(l, n)
        a = keep(a, "factor")
        a.join(column_panels(a, basis.size(n), stages), "n").write.mode("overwrite").partitionBy("stage").parquet(first)
        b.join(weights, KEY).write.mode("overwrite").parquet(second)
    a, b = spark.read.parquet(first), spark.read.parquet(second)
    for i in range(stages):
        if not done(f"{path}/blocks/stage={i}"):
            _product(a.where(F.col("stage") == i).drop("stage"), b).write.mode("overwrite").parquet(f"{path}/blocks/stage={i}")
    return spark.read.schema("sys string, s long, n long, x double").parquet(*[f"{path}/blocks/stage={i}" for i in range(stages)])


def relaxation_from_rates(rates: DataFrame, n: int, route: str = "tensor") -> DataFrame:
    """sys, s, n, x: R of a full rate matrix, without diagonalising it."""
    spark = rates.sparkSession
    if route == "cell":
        return cell_to_basis(rate_cells(rates, n), n)
    t = structure.tensor(spark, n)
    left = rates.select("sys", F.col("j").alias("m"), "k", "re", "im").join(t, "m").groupBy("sys", "k", F.col("n").alias("mid"), F.col("s").alias("n")).agg(F.sum(F.expr("re*alpha-im*beta")).alias("a_re"))
    right = t.where("abs(alpha) > 1e-12").select(F.col("m").alias("k"), F.col("n").alias("mid"), "s", "alpha")
    return _kept(left.join(right, ["k", "mid"]).groupBy("sys", "s", "n").agg((-0.5 * F.sum(F.expr("a_re*alpha"))).alias("x")))


# -- the cell route: C[(a,c),(b,d)] = sum over jump operators of weight L_ac conj(L_bd)


def jump_cells(jumps: DataFrame, weights: DataFrame) -> DataFrame:
    """sys, a, b, c, d, re, im of C for jump operators (sys, op, row, col, re, im).

    Every cell of an operator meets every other one, and there may be one operator: the left cells are dealt in `PARTS` groups, and
    the right ones are copied to each, so that no operator is one task.
    """
    part = F.pmod(F.xxhash64("row", "col"), F.lit(PARTS)).cast("int")
    x = jumps.join(weights, KEY).select(*KEY, part.alias("part"), "gamma", F.col("row").alias("a"), F.col("col").alias("c"), F.col("re").alias("x"), F.col("im").alias("y"))
    y = jumps.select(*KEY, F.explode(F.sequence(F.lit(0), F.lit(PARTS - 1))).alias("part"), F.col("row").alias("b"), F.col("col").alias("d"), "re", "im")
    return x.join(y, [*KEY, "part"]).groupBy("sys", "a", "b", "c", "d").agg(F.sum(F.expr("gamma*(x*re+y*im)")).alias("re"), F.sum(F.expr("gamma*(y*re-x*im)")).alias("im"))


def rate_cells(rates: DataFrame, n: int) -> DataFrame:
    """C for a rate matrix: transformed on one side after the other, each join at most doubling the rows but for D."""
    e = basis.elements(rates.sparkSession, n)
    left = e.select(F.col("idx").alias("j"), F.col("row").alias("a"), F.col("col").alias("c"), F.col("re").alias("x"), F.col("im").alias("y"))
    half = rates.join(left, "j").groupBy("sys", "k", "a", "c").agg(F.sum(F.expr("re*x-im*y")).alias("re"), F.sum(F.expr("re*y+im*x")).alias("im"))
    right = e.select(F.col("idx").alias("k"), F.col("row").alias("b"), F.col("col").alias("d"), F.col("re").alias("x"), F.col("im").alias("y"))
    return half.join(right, "k").groupBy("sys", "a", "b", "c", "d").agg(F.sum(F.expr("re*x+im*y")).alias("re"), F.sum(F.expr("im*x-re*y")).alias("im"))


def superoperator(cells: DataFrame, n: int, hamiltonian: DataFrame | None = None) -> DataFrame:
    """sys, a, b, c, d, re, im of the generator on matrix cells: d rho_ab = sum X_abcd rho_cd."""
    g = cells.where("a = b").groupBy("sys", F.col("d").alias("p"), F.col("c").alias("q")).agg(F.sum("re").alias("re"), F.sum("im").alias("im"))  # sum of weight L^+ L
    spread = lambda df: df.select("*", F.explode(F.sequence(F.lit(1), F.lit(n))).alias("z"))
    s = spread(g)
    left = s.select("sys", F.col("p").alias("a"), F.col("z").alias("b"), F.col("q").alias("c"), F.col("z").alias("d"), (-F.col("re") / 2).alias("re"), (-F.col("im") / 2).alias("im"))
    right = s.select("sys", F.col("z").alias("a"), F.col("q").alias("b"), F.col("z").alias("c"), F.col("p").alias("d"), (-F.col("re") / 2).alias("re"), (-F.col("im") / 2).alias("im"))
    out = cells.unionByName(left).unionByName(right)
    if hamiltonian is not None:
        h = spread(hamiltonian.select("sys", "row", "col", "re", "im"))
        out = out.unionByName(h.select("sys", F.col("row").alias("a"), F.col("z").alias("b"), F.col("col").alias("c"), F.col("z").alias("d"), F.col("im").alias("re"), (-F.col("re")).alias("im")))
        out = out.unionByName(h.select("sys", F.col("z").alias("a"), F.col("col").alias("b"), F.col("z").alias("c"), F.col("row").alias("d"), (-F.col("im")).alias("re"), F.col("re").alias("im")))
    x = out.groupBy("sys", "a", "b", "c", "d").agg(F.sum("re").alias("re"), F.sum("im").alias("im"))
    return x.where((F.abs("re") > TOL) | (F.abs("im") > TOL))


def cell_to_basis(cells: DataFrame, n: int) -> DataFrame:
    """sys, s, n, x of R from C, by two joins with the basis elements."""
    e = basis.elements(cells.sparkSession, n)
    x = superoperator(cells, n)
    right = e.select(F.col("idx").alias("n"), F.col("row").alias("c"), F.col("col").alias("d"), F.col("re").alias("x"), F.col("im").alias("y"))
    half = x.join(right, ["c", "d"]).groupBy("sys", "n", "a", "b").agg(F.sum(F.expr("re*x-im*y")).alias("re"), F.sum(F.expr("re*y+im*x")).alias("im"))
    left = e.select(F.col("idx").alias("s"), F.col("row").alias("b"), F.col("col").alias("a"), F.col("re").alias("x"), F.col("im").alias("y"))
    return _kept(half.join(left, ["a", "b"]).groupBy("sys", "s", "n").agg(F.sum(F.expr("re*x-im*y")).alias("x")))


def relaxation_by_cells(jumps: DataFrame, weights: DataFrame, n: int) -> DataFrame:
    """sys, s, n, x: R of jump operators by the cell route."""
    return cell_to_basis(jump_cells(jumps, weights), n)


def choose_route(l_nonzeros: int, n: int) -> str:
    """The tensor route for sparse coefficients, else the cell route, whose work is that of its output."""
    return "tensor" if l_nonzeros <= 8 * n else "cell"


def transposed(spark: SparkSession, rates: DataFrame) -> DataFrame:
    """A rate matrix given in the other orientation."""
    return rates.select("sys", F.col("k").alias("j"), F.col("j").alias("k"), "re", "im")
