"""Shards by proportional stratified interleaving.

Rows of each source are shuffled by a seeded hash and ranked; the fractional rank (rank + 1/2) / rows of the source
spreads every source evenly over [0, 1), so sorting by it interleaves the sources in proportion and any contiguous cut
has the mixture of the whole. Cuts fall at equal row counts (law `rows`).

Both rankings go through `common.ranked`: hash buckets are numbered on their own and offset by running sums over bucket
counts, so a source with a third of the rows is never in one task.

Edge cases: a null text has size 1 and crc32 0; a null source is a stratum of its own; equal doc_ids are ordered by
crc32 and size (rows equal in all of these are interchangeable); an empty table gives an empty result; other columns
are ignored.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

SHARDS, SEED, HASH_BUCKETS, RANK_BUCKETS = 16, "shard-1", 4096, 8192


def interleave(docs: DataFrame, shards: int = SHARDS, seed: str = SEED) -> DataFrame:
    """doc_id, source, size, text_crc32, shard, slot for each row of `docs` (doc_id, text, source)."""
    text = F.coalesce(F.col("text"), F.lit(""))
    rows = common.durable(
        docs.select(
            "doc_id", "source", (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(text).alias("text_crc32"),
            F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(F.col("doc_id").cast("string"), F.lit("")))).alias("_h"),
        ),
        "shard-rows",
    )
    order = [F.col("_h"), F.col("doc_id"), F.col("text_crc32"), F.col("size")]
    bucket = F.conv(F.substring("_h", 1, 3), 16, 10).cast("int")  # 3 hex digits: HASH_BUCKETS values
    local = common.ranked(rows, ["source"], order, bucket, "_rank")
    counts = rows.groupBy(F.col("source").alias("_s")).agg(F.count(F.lit(1)).alias("_of"))
    part = local.join(counts, F.col("source").eqNullSafe(F.col("_s"))).drop("_s")
    part = part.withColumn("_f", (2 * F.col("_rank") + 1).cast("double") / (2 * F.col("_of")).cast("double")).withColumn("_all", F.lit(0))
    part = common.durable(part, "shard-parts")
    total = rows.count()
    mixed = common.ranked(part, ["_all"], [F.col("_f"), F.col("source").asc_nulls_last(), *order], F.floor(F.col("_f") * RANK_BUCKETS).cast("int"), "_g")
    shard = F.expr(f"(_g * {shards}) div {max(1, total)}").cast("int")
    first = F.expr(f"(shard * {max(1, total)}L + {shards - 1}) div {shards}")
    return mixed.withColumn("shard", shard).withColumn("slot", F.col("_g") - first).select("doc_id", "source", "size", "text_crc32", "shard", "slot")


def op8(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = interleave(common.table(spark, sf_dir, "documents"))
    return got.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", F.col("slot").cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"), "source")


