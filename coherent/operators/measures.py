"""Observables of states, and the costs of the methods: nonzeros, tuples, bytes, balance, cut, density, time."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from coherent.operators import structure


def populations(rho: DataFrame) -> DataFrame:
    return rho.where("row = col").select("sys", F.col("row").alias("level"), F.col("re").alias("p"))


def purity(rho: DataFrame) -> DataFrame:
    """sys, purity, entropy: sum of squared cells, and the linear entropy 1 - purity."""
    p = F.sum(F.expr("re*re+im*im"))
    return rho.groupBy("sys").agg(p.alias("purity"), (1.0 - p).alias("entropy"))


def expectation(rho: DataFrame, op: DataFrame) -> DataFrame:
    """sys, re, im of Tr(rho A)."""
    a = op.select("sys", F.col("row").alias("col"), F.col("col").alias("row"), F.col("re").alias("x"), F.col("im").alias("y"))
    return rho.join(a, ["sys", "row", "col"]).groupBy("sys").agg(F.sum(F.expr("re*x-im*y")).alias("re"), F.sum(F.expr("re*y+im*x")).alias("im"))


def imbalance_of(rho: DataFrame, n: int) -> DataFrame:
    """sys, x: mean of n2 - n1 per boson in the two-site model."""
    return populations(rho).groupBy("sys").agg((F.sum(F.col("p") * (2 * (F.col("level") - 1) - (n - 1))) / (n - 1)).alias("x"))


def observables(rho: DataFrame) -> DataFrame:
    """sys, values: a map of named observables."""
    own = rho.groupBy("sys").agg(F.sum(F.when(F.col("row") == F.col("col"), F.col("re")).otherwise(0.0)).alias("trace"), F.sum(F.expr("re*re+im*im")).alias("purity"))
    return own.select("sys", F.map_from_entries(F.array(*[F.struct(F.lit(c).alias("k"), F.col(c).alias("v")) for c in ("trace", "purity")])).alias("values"))


def nnz(mat: DataFrame) -> DataFrame:
    return mat.groupBy("sys").agg(F.count(F.lit(1)).alias("nnz"))


def density(mat: DataFrame, m: int) -> DataFrame:
    return mat.groupBy("sys").agg((F.count(F.lit(1)) / F.lit(float(m) * m)).alias("density"))


def plane_counts(spark: SparkSession, n: int) -> DataFrame:
    """m, alpha, beta: nonzeros of each plane."""
    return structure.tensor(spark, n).groupBy("m").agg(F.count(F.when(F.abs("alpha") > 1e-12, 1)).alias("alpha"), F.count(F.when(F.abs("beta") > 1e-12, 1)).alias("beta"))


def contraction_tuples(spark: SparkSession, n: int, vec: DataFrame | None = None) -> DataFrame:
    """tuples: index tuples that a term of R touches, sum over the middle index of nnz(zeta) nnz(alpha).

    With coefficients `vec` (sys, op, idx), sys, op, tuples: those that the operators' own coefficients touch.
    """
    if vec is not None:
        some = lambda c: F.count(F.when(F.abs(c) > 1e-12, 1))
        c = structure.planes(vec.select("sys", "op", "idx"), n).groupBy("sys", "op", F.col("n").alias("mid")).agg(some("alpha").alias("alpha"), some("beta").alias("beta"))
        return c.groupBy("sys", "op").agg(F.sum((F.col("alpha") + F.col("beta")) * F.col("alpha")).alias("tuples"))
    c = plane_counts(spark, n)
    return c.agg(F.sum((F.col("alpha") + F.col("beta")) * F.col("alpha")).alias("tuples"))


def imbalance(panels: DataFrame) -> DataFrame:
    """sys, panels, largest, mean, ratio of nonzeros a panel."""
    p = panels.groupBy("sys", "panel").agg(F.sum("nnz").alias("nnz"))
    return p.groupBy("sys").agg(F.count(F.lit(1)).alias("panels"), F.max("nnz").alias("largest"), F.avg("nnz").alias("mean")).withColumn("ratio", F.col("largest") / F.col("mean"))


def edge_cut(mat: DataFrame, panels: DataFrame) -> DataFrame:
    """sys, cut, remote: nonzeros between panels, and distinct (panel, column) pairs a panel must receive."""
    p = panels.select("sys", "s", F.col("panel").alias("ps"))
    q = panels.select("sys", F.col("s").alias("n"), F.col("panel").alias("pn"))
    d = mat.join(p, ["sys", "s"]).join(q, ["sys", "n"]).where("ps <> pn")
    return d.groupBy("sys").agg(F.count(F.lit(1)).alias("cut"), F.countDistinct("ps", "n").alias("remote"))


def scaling_efficiency(runs: DataFrame) -> DataFrame:
    """nodes, memory, efficiency: (memory x nodes) of the run before over that of this one, in order of nodes."""
    w = Window.orderBy("nodes")
    cost = F.col("memory") * F.col("nodes")
    return runs.select("nodes", "memory", (F.lag(cost).over(w) / cost).alias("efficiency"))


def partition_bytes(df: DataFrame) -> DataFrame:
    """part, rows, bytes: what each partition holds, in Arrow's layout as a worker receives it."""

    def run(batches):
        import pyarrow as pa
        from pyspark import TaskContext

        rows = size = 0
        for b in batches:
            rows, size = rows + b.num_rows, size + b.nbytes
        yield pa.RecordBatch.from_pydict({"part": [TaskContext.get().partitionId()], "rows": [rows], "bytes": [size]}, pa.schema([("part", pa.int32()), ("rows", pa.int64()), ("bytes", pa.int64())]))

    return df.mapInArrow(run, "part int, rows long, bytes long")


def peak_memory(spark: SparkSession) -> DataFrame:
    """stage, tasks, execution, spilled, written: of each stage the engine still knows, the largest execution memory of its tasks
    together (bytes), what they spilled and what they wrote to shuffles. From the status store, which the driver keeps anyway."""
    store, rows = spark.sparkContext._jsc.sc().statusStore(), []
    none = spark._jvm.java.util.ArrayList()
    stages = store.stageList(none, False, False, spark.sparkContext._gateway.new_array(spark._jvm.double, 0), none)
    for i in range(stages.size()):
        s = stages.apply(i)
        rows.append((s.stageId(), s.numCompleteTasks(), s.peakExecutionMemory(), s.memoryBytesSpilled(), s.shuffleWriteBytes()))
    return spark.createDataFrame(rows, "stage int, tasks int, execution long, spilled long, written long")


def timed(df: DataFrame) -> float:
    """Seconds to compute every row, without a result."""
    began = time.time()
    df.write.format("noop").mode("overwrite").save()
    return time.time() - began
