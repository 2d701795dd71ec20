"""Panels: rows of the system grouped for workers, uniformly, by nonzeros, or by the sparsity graph."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from coherent.sources.store import keep


def row_counts(mat: DataFrame, m: int | None = None) -> DataFrame:
    """sys, s, nnz of each row; with `m`, empty rows too."""
    c = mat.groupBy("sys", "s").agg(F.count(F.lit(1)).alias("nnz"))
    if m is None:
        return c
    every = mat.select("sys").distinct().select("sys", F.explode(F.sequence(F.lit(1).cast("long"), F.lit(m).cast("long"))).alias("s"))
    return every.join(c, ["sys", "s"], "left").na.fill(0, ["nnz"])


def uniform(counts: DataFrame, m: int, panels: int) -> DataFrame:
    """Equal index ranges, the imbalanced way."""
    return counts.withColumn("panel", F.floor((F.col("s") - 1) * panels / m).cast("int"))


def balanced(counts: DataFrame, panels: int, blocks: int = 256) -> DataFrame:
    """Contiguous ranges of about equal nonzeros. Prefix sums in two levels: within blocks of rows, then over the blocks."""
    b = counts.withColumn("_b", F.floor(F.col("s") / blocks))
    inside = Window.partitionBy("sys", "_b").orderBy("s").rowsBetween(Window.unboundedPreceding, -1)
    before = Window.partitionBy("sys").orderBy("_b").rowsBetween(Window.unboundedPreceding, -1)
    tops = b.groupBy("sys", "_b").agg(F.sum("nnz").alias("_n")).withColumn("_before", F.coalesce(F.sum("_n").over(before), F.lit(0))).withColumn("_total", F.sum("_n").over(Window.partitionBy("sys"))).drop("_n")
    joined = b.withColumn("_in", F.coalesce(F.sum("nnz").over(inside), F.lit(0))).join(tops, ["sys", "_b"])
    panel = F.least(F.lit(panels - 1), F.floor((F.col("_before") + F.col("_in")) * panels / F.greatest("_total", F.lit(1))))
    return joined.select("sys", "s", "nnz", panel.cast("int").alias("panel"))


def ranked(rows: DataFrame, order: list[str], coarse: str, out: str, blocks: int = 256) -> DataFrame:
    """`rows` with their rank from 1 in `order` within each system, in two levels: inside the values of `coarse`, then over these.

    `coarse` must be the first of `order`. Values with many rows are ranked in one task; there are as many tasks as values.
    """
    inside = F.row_number().over(Window.partitionBy("sys", coarse).orderBy(*order))
    before = Window.partitionBy("sys").orderBy(coarse).rowsBetween(Window.unboundedPreceding, -1)
    tops = rows.groupBy("sys", coarse).agg(F.count(F.lit(1)).alias("_n"))
    tops = tops.select("sys", F.col(coarse).alias("_c"), F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_before"))
    d = rows.withColumn("_in", inside).join(tops.withColumnRenamed("sys", "_sys"), (F.col("sys") == F.col("_sys")) & (F.col(coarse) == F.col("_c")))
    return d.withColumn(out, (F.col("_before") + F.col("_in")).cast("long")).drop("_in", "_before", "_sys", "_c")


def largest_first(counts: DataFrame, panels: int) -> DataFrame:
    """Rows dealt by falling size in alternating direction: close to equal loads, not contiguous."""
    r = ranked(counts.withColumn("_less", -F.col("nnz")), ["_less", "s"], "_less", "_rank")
    place, lap = (F.col("_rank") - 1) % panels, F.floor((F.col("_rank") - 1) / panels)
    return r.withColumn("panel", F.when(lap % 2 == 0, place).otherwise(panels - 1 - place).cast("int")).drop("_rank", "_less")


def by_graph(mat: DataFrame, m: int, panels: int, method: str = "bfs") -> DataFrame:
    """Rows ordered by the sparsity graph and cut into panels of about equal nonzeros.

    `bfs`: by distance from the smallest row of each component; `label`: by the component alone. A step is one
    join and a minimum; four steps are a round, kept in the shared folder. Rounds go on until no label changes.
    """
    edges = mat.where("s <> n").select("sys", F.col("s").alias("a"), F.col("n").alias("b"))
    edges = keep(edges.unionByName(edges.select("sys", F.col("b").alias("a"), F.col("a").alias("b"))).distinct(), "edges")
    rows = keep(row_counts(mat, m), "rows")
    label, mark = rows.select("sys", "s", F.col("s").alias("label"), F.lit(0).alias("far")), None
    while True:
        for _ in range(4):
            step = edges.join(label.select("sys", F.col("s").alias("a"), "label", "far"), ["sys", "a"]).select("sys", F.col("b").alias("s"), "label", (F.col("far") + 1).alias("far"))
            label = label.unionByName(step).groupBy("sys", "s").agg(F.min(F.struct("label", "far")).alias("x")).select("sys", "s", "x.label", "x.far")
        label = keep(label, "labels")
        now = label.agg(F.sum("label"), F.sum("far")).first()  # labels only fall, and distances under one label too
        if now == mark:
            break
        mark = now
    # Far components come after near ones; a value of `_coarse` is one ring around its component's smallest row.
    far = F.col("far") if method == "bfs" else F.lit(0)
    d = rows.join(label, ["sys", "s"]).withColumn("_coarse", F.struct("label", far.alias("far")))
    d = keep(ranked(d, ["_coarse", "s"], "_coarse", "_at").drop("_coarse", "label", "far"), "ordered")
    placed = balanced(d.select("sys", F.col("_at").alias("s"), "nnz"), panels)
    return d.join(placed.select("sys", F.col("s").alias("_at"), "panel"), ["sys", "_at"]).select("sys", "s", "nnz", "panel")


def dealt(mat: DataFrame, panels: DataFrame, parts: int) -> DataFrame:
    """The matrix with its panel, one panel a task."""
    return mat.join(panels.select("sys", "s", "panel"), ["sys", "s"]).repartitionById(parts, F.col("panel"))


def loads(mat: DataFrame) -> DataFrame:
    """task, rows: nonzeros that each task of `mat` holds, and `largest over mean` for all of them."""
    c = mat.groupBy(F.spark_partition_id().alias("task")).agg(F.count(F.lit(1)).alias("rows"))
    every = Window.partitionBy(F.lit(0))
    return c.withColumn("ratio", F.max("rows").over(every) / F.avg("rows").over(every))
