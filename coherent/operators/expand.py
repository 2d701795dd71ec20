"""Expansion of operators over the basis in one pass over their nonzeros, and the way back."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from coherent.functions.checks import levels
from coherent.operators import basis

TOL = 1e-12


def expand(op: DataFrame, n: int) -> DataFrame:
    """sys, op, idx, re, im: coefficients of each operator (sys, op if present, row, col, re, im); the trace is left out.

    At most n^2 rows an operator, which every branch of the planes reads: callers keep them (sources.store.keep).
    """
    levels(n)
    d = op if "op" in op.columns else op.withColumn("op", F.lit(0))
    key = ["sys", "op"]
    upper = F.col("row") < F.col("col")
    off = d.where("row <> col").groupBy(*key, F.least("row", "col").alias("j"), F.greatest("row", "col").alias("k")).agg(
        F.sum("re").alias("sum_re"), F.sum("im").alias("sum_im"),
        F.sum(F.when(upper, F.col("re")).otherwise(-F.col("re"))).alias("dif_re"), F.sum(F.when(upper, F.col("im")).otherwise(-F.col("im"))).alias("dif_im"),
    )
    h, j, k = F.lit(basis.ROOT_HALF), F.col("j"), F.col("k")
    entry = lambda i, re, im: F.struct(i.alias("idx"), re.alias("re"), im.alias("im"))
    pairs = off.select(*key, F.explode(F.array(entry(basis.index_of("S", j, k, n), h * F.col("sum_re"), h * F.col("sum_im")), entry(basis.index_of("J", j, k, n), -h * F.col("dif_im"), h * F.col("dif_re")))).alias("x")).select(*key, "x.*")
    cells = d.where("row = col").groupBy(*key, F.col("row").alias("a")).agg(F.sum("re").alias("re"), F.sum("im").alias("im"))
    # Every level after the first nonzero one matters to a prefix sum, so the diagonal is filled up.
    whole = cells.select(*key).distinct().select(*key, F.explode(F.sequence(F.lit(1), F.lit(n))).alias("a")).join(cells, [*key, "a"], "left").na.fill(0.0, ["re", "im"])
    before = Window.partitionBy(*key).orderBy("a").rowsBetween(Window.unboundedPreceding, -1)
    l = F.col("a") - 1  # noqa: E741
    norm = F.sqrt(l * (l + 1.0))
    diag = whole.select(*key, "a", *[((F.sum(c).over(before) - l * F.col(c)) / norm).alias(c) for c in ("re", "im")]).where("a > 1")
    diag = diag.select(*key, basis.index_of("D", l, l, n).alias("idx"), "re", "im")
    return pairs.unionByName(diag).where((F.abs("re") > TOL) | (F.abs("im") > TOL))


def traces(op: DataFrame) -> DataFrame:
    d = op if "op" in op.columns else op.withColumn("op", F.lit(0))
    return d.where("row = col").groupBy("sys", "op").agg(F.sum("re").alias("re"), F.sum("im").alias("im"))


def rebuild(vec: DataFrame, trace: DataFrame, n: int) -> DataFrame:
    """The operators of `vec` with the traces in `trace` (sys, op, re, im): trace / n on the diagonal plus the expansion."""
    key = ["sys", "op"]
    v = basis.elements_of(basis.located(vec.withColumnRenamed("re", "c_re").withColumnRenamed("im", "c_im"), "idx", n))
    v = v.select(*key, "row", "col", F.expr("c_re*re-c_im*im").alias("re"), F.expr("c_re*im+c_im*re").alias("im"))
    t = trace.select(*key, F.explode(F.sequence(F.lit(1), F.lit(n))).alias("row"), (F.col("re") / n).alias("re"), (F.col("im") / n).alias("im"))
    t = t.select(*key, "row", F.col("row").alias("col"), "re", "im")
    whole = v.unionByName(t).groupBy(*key, "row", "col").agg(F.sum("re").alias("re"), F.sum("im").alias("im"))
    return whole.where((F.abs("re") > TOL) | (F.abs("im") > TOL))


def density_from_vector(vec: DataFrame, n: int) -> DataFrame:
    """The density operator of a coherence vector (sys, idx, x): unit trace."""
    v = vec.select("sys", F.lit(0).alias("op"), "idx", F.col("x").alias("re"), F.lit(0.0).alias("im"))
    return rebuild(v, v.select("sys", "op").distinct().select("sys", "op", F.lit(1.0).alias("re"), F.lit(0.0).alias("im")), n).drop("op")


def pure(spark: SparkSession, sys: str, level: int) -> DataFrame:
    return spark.createDataFrame([(sys, level, level, 1.0, 0.0)], "sys string, row int, col int, re double, im double")


def mixed(spark: SparkSession, sys: str, n: int) -> DataFrame:
    return spark.range(1, n + 1).select(F.lit(sys).alias("sys"), F.col("id").cast("int").alias("row"), F.col("id").cast("int").alias("col"), F.lit(1.0 / n).alias("re"), F.lit(0.0).alias("im"))


def initial_vector(rho: DataFrame, n: int) -> DataFrame:
    """sys, idx, x: the coherence vector of a density operator; the empty vector is the mixed state."""
    return expand(rho, n).select("sys", "idx", F.col("re").alias("x"))


def recentre_jump(jump: DataFrame, hamiltonian: DataFrame | None, gamma: float, n: int) -> tuple[DataFrame, DataFrame]:
    """(traceless jump operator, Hamiltonian with the compensating term), which generate the same dynamics.

    With c = Tr(L) / n and L0 = L - c I, the term is gamma i/2 (conj(c) L0 - c L0^+).
    """
    c = jump.where("row = col").groupBy("sys").agg((F.sum("re") / n).alias("c_re"), (F.sum("im") / n).alias("c_im"))
    shift = c.select("sys", F.explode(F.sequence(F.lit(1), F.lit(n))).alias("row"), (-F.col("c_re")).alias("re"), (-F.col("c_im")).alias("im")).select("sys", "row", F.col("row").alias("col"), "re", "im")
    cols = ["sys", "row", "col", "re", "im"]
    l0 = jump.select(*cols).unionByName(shift).groupBy("sys", "row", "col").agg(F.sum("re").alias("re"), F.sum("im").alias("im")).where((F.abs("re") > TOL) | (F.abs("im") > TOL))
    # i z has parts (-im, re); conj(c) L0 and c L0^+ are formed cell by cell.
    with_c = l0.join(c, "sys")
    first = with_c.select("sys", "row", "col", F.expr("c_re*re+c_im*im").alias("x"), F.expr("c_re*im-c_im*re").alias("y"))
    second = with_c.select("sys", F.col("col").alias("row"), F.col("row").alias("col"), F.expr("-(c_re*re+c_im*im)").alias("x"), F.expr("-(c_im*re-c_re*im)").alias("y"))
    extra = first.unionByName(second).select("sys", "row", "col", (-F.col("y") * gamma / 2).alias("re"), (F.col("x") * gamma / 2).alias("im"))
    h = extra if hamiltonian is None else hamiltonian.select(*cols).unionByName(extra)
    h = h.groupBy("sys", "row", "col").agg(F.sum("re").alias("re"), F.sum("im").alias("im")).where((F.abs("re") > TOL) | (F.abs("im") > TOL))
    return l0, h
