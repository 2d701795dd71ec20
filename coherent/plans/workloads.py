"""The experiments' operators re-expressed on the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from coherent.operators import expand, linalg, models
from coherent.sources.io import table
from coherent.sources.store import keep

OP = ["sys", "row", "col", "re", "im"]


def flow(spark: SparkSession, d: str, level: str = "region") -> DataFrame:
    """sys, row, col, re, im: discounted price from the customers' to the suppliers' level, over the largest cell."""
    li = table(spark, d, "lineitem").select("l_orderkey", "l_suppkey", (F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("v"))
    o = table(spark, d, "orders").select("o_orderkey", "o_custkey")
    c, s, n = table(spark, d, "customer").select("c_custkey", "c_nationkey"), table(spark, d, "supplier").select("s_suppkey", "s_nationkey"), table(spark, d, "nation").select("n_nationkey", "n_regionkey")
    x = li.join(o, F.col("l_orderkey") == F.col("o_orderkey")).join(c, F.col("o_custkey") == F.col("c_custkey")).join(s, F.col("l_suppkey") == F.col("s_suppkey"))
    x = x.groupBy("c_nationkey", "s_nationkey").agg(F.sum("v").alias("v"))  # at most 625 cells go on
    if level == "region":
        a, b = n.select(F.col("n_nationkey").alias("c_nationkey"), F.col("n_regionkey").alias("row")), n.select(F.col("n_nationkey").alias("s_nationkey"), F.col("n_regionkey").alias("col"))
        x = x.join(F.broadcast(a), "c_nationkey").join(F.broadcast(b), "s_nationkey").groupBy("row", "col").agg(F.sum("v").alias("v"))
    else:
        x = x.select(F.col("c_nationkey").alias("row"), F.col("s_nationkey").alias("col"), "v")
    top = x.agg(F.max("v").alias("top"))
    name = "flow5" if level == "region" else "flow25"
    return x.crossJoin(F.broadcast(top)).select(F.lit(name).alias("sys"), (F.col("row") + 1).cast("int").alias("row"), (F.col("col") + 1).cast("int").alias("col"), (F.col("v") / F.col("top")).alias("re"), F.lit(0.0).alias("im"))


def flow_hamiltonian(x: DataFrame) -> DataFrame:
    return linalg.combine(x, linalg.adjoint(x), 0.5, 0.5)


def flow_system(spark: SparkSession, d: str, level: str = "region", gamma: float = 1.0) -> tuple[DataFrame, DataFrame, DataFrame, int]:
    """(H, jump operators, weights, levels) with the traceless part of the flow as the one jump operator."""
    n = 5 if level == "region" else 25
    x = keep(flow(spark, d, level), "flow")
    l0, h = expand.recentre_jump(x, flow_hamiltonian(x), gamma, n)
    return h, l0.withColumn("op", F.lit(0)), x.select("sys").distinct().select("sys", F.lit(0).alias("op"), F.lit(gamma).alias("gamma")), n


def transitions(pairs: DataFrame, names: list[str], sys: str) -> tuple[DataFrame, DataFrame]:
    """(jump operators |to><from|, weights = shares of the pairs) from rows (a, b); op numbers follow the names' order."""
    level = lambda c: F.array_position(F.array(*[F.lit(x) for x in names]), F.col(c)).cast("int")
    c = pairs.groupBy("a", "b").agg(F.count(F.lit(1)).alias("n")).select(level("a").alias("f"), level("b").alias("t"), "n").where("f > 0 AND t > 0")
    total = c.agg(F.sum("n").alias("total"))
    c = keep(c.crossJoin(F.broadcast(total)), "pairs").select(F.lit(sys).alias("sys"), ((F.col("f") - 1) * len(names) + F.col("t") - 1).cast("int").alias("op"), "f", "t", (F.col("n") / F.col("total")).alias("gamma"))
    jumps = c.select("sys", "op", F.col("t").alias("row"), F.col("f").alias("col"), F.lit(1.0).alias("re"), F.lit(0.0).alias("im"))
    return jumps, c.select("sys", "op", "gamma")


EVENT_TYPES = ["click", "error", "purchase", "signup", "view"]
ROLES = ["assistant", "system", "user"]
LANGS = ["de", "en", "es", "fr"]


def event_pairs(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return table(spark, d, "events").select(F.lag("event_type").over(w).alias("a"), F.col("event_type").alias("b")).where("a IS NOT NULL")


def hops(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    return transitions(event_pairs(spark, d), EVENT_TYPES, "hop5")


def turn_pairs(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("conv_id").orderBy("turn")
    return table(spark, d, "conversations").select(F.col("role").alias("a"), F.lead("role").over(w).alias("b")).where("b IS NOT NULL")


def turns(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    return transitions(turn_pairs(spark, d), ROLES, "turn3")


def traceless(jumps: DataFrame, n: int) -> DataFrame:
    """Jump operators without their trace; for operators whose compensating Hamiltonian vanishes (Hermitian, real trace)."""
    c = jumps.where("row = col").groupBy("sys", "op").agg((F.sum("re") / n).alias("c"))
    i = c.select("sys", "op", F.explode(F.sequence(F.lit(1), F.lit(n))).alias("row"), (-F.col("c")).alias("re")).select("sys", "op", "row", F.col("row").alias("col"), "re", F.lit(0.0).alias("im"))
    return jumps.select("sys", "op", "row", "col", "re", "im").unionByName(i).groupBy("sys", "op", "row", "col").agg(F.sum("re").alias("re"), F.sum("im").alias("im")).where("abs(re) > 1e-12 OR abs(im) > 1e-12")


def gram(cells: DataFrame) -> DataFrame:
    """The density operator X X^T / Tr of real cells (sys, row, col, v)."""
    a = cells.select("sys", "row", F.col("col").alias("mid"), F.col("v").alias("x"))
    b = cells.select("sys", F.col("row").alias("col"), F.col("col").alias("mid"), F.col("v").alias("y"))
    g = a.join(b, ["sys", "mid"]).groupBy("sys", "row", "col").agg(F.sum(F.col("x") * F.col("y")).alias("g"))
    t = cells.groupBy("sys").agg(F.sum(F.col("v") * F.col("v")).alias("t"))
    return g.join(F.broadcast(t), "sys").select("sys", F.col("row").cast("int").alias("row"), F.col("col").cast("int").alias("col"), (F.col("g") / F.col("t")).alias("re"), F.lit(0.0).alias("im"))


def label_cells(spark: SparkSession, d: str) -> DataFrame:
    x = table(spark, d, "labels").join(table(spark, d, "documents").select("doc_id"), "doc_id")
    return x.groupBy("quality", "toxic").agg(F.count(F.lit(1)).alias("n")).select(F.lit("label2").alias("sys"), (F.col("quality") + 1).alias("row"), (F.col("toxic") + 1).alias("col"), F.col("n").cast("double").alias("v"))


def lang_cells(spark: SparkSession, d: str) -> DataFrame:
    level = F.array_position(F.array(*[F.lit(x) for x in LANGS]), F.col("lang")).cast("int")
    x = table(spark, d, "documents").select("lang", "source").groupBy("lang", "source").agg(F.count(F.lit(1)).alias("n"))
    return x.select(F.lit("lang4").alias("sys"), level.alias("row"), F.col("source").alias("col"), F.col("n").cast("double").alias("v")).where("row > 0")


def embedding_cells(spark: SparkSession, d: str) -> DataFrame:
    """row = dimension, col = vector, one system a label."""
    x = table(spark, d, "embeddings").select(F.col("label").cast("string").alias("sys"), F.col("vec_id").alias("col"), F.posexplode("embedding").alias("p", "v"))
    return x.select("sys", (F.col("p") + 1).alias("row"), "col", F.col("v").cast("double").alias("v"))


def levels_of(spark: SparkSession, d: str, name: str) -> DataFrame:
    """sys, level from 1, of a dimension table: the levels of the two-site model."""
    key, sys = {"region": ("r_regionkey", "dimer5"), "nation": ("n_nationkey", "dimer25")}[name]
    return table(spark, d, name).select(F.lit(sys).alias("sys"), (F.col(key) + 1).cast("int").alias("level"))


def part_levels(spark: SparkSession, d: str) -> tuple[DataFrame, int]:
    """(sys, level of every part, the number of levels): a two-site model as large as the table."""
    p = table(spark, d, "part")
    return p.select(F.lit("parts").alias("sys"), F.col("p_partkey").cast("int").alias("level")), p.count()


def dimer(spark: SparkSession, d: str, name: str = "region", **options) -> tuple[DataFrame, DataFrame, DataFrame, DataFrame, int]:
    """(H0, H1, jump operators, weights, levels)."""
    n = 5 if name == "region" else 25
    h0, h1, jump = models.dimer(levels_of(spark, d, name), n, **options)
    w = levels_of(spark, d, name).select("sys").distinct().select("sys", F.lit(0).alias("op"), F.lit(models.dimer_weight(n)).alias("gamma"))
    return h0, h1, traceless(jump.withColumn("op", F.lit(0)), n), w, n


def samples(spark: SparkSession, d: str, count: int) -> DataFrame:
    """Sample names from the line items' suppliers."""
    return table(spark, d, "lineitem").select(F.concat(F.lit("s"), (F.col("l_suppkey") % count).cast("string")).alias("sys")).distinct()


def sites(spark: SparkSession, d: str) -> DataFrame:
    """sys, site, gamma: the regions as sites, weighed by their customers' mean balance."""
    c = table(spark, d, "customer").select("c_nationkey", "c_acctbal").join(table(spark, d, "nation").select("n_nationkey", "n_regionkey"), F.col("c_nationkey") == F.col("n_nationkey"))
    g = c.groupBy(F.col("n_regionkey").alias("site")).agg((F.avg("c_acctbal") / 10000).alias("gamma"))
    return g.select(F.lit("chain").alias("sys"), "site", F.abs("gamma").alias("gamma"))
