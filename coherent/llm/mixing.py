"""Mixing sources to target weights by cube-method balanced sampling.

A source with size S and target t takes every document floor(t / S) times and once more with probability
p = frac(t / S). Which documents get the extra copy is decided by the cube method: inclusion probabilities move along
the null space of the balancing constraints (number of documents, number of words) until all but a few are 0 or 1.

The flight phase runs on blocks of about `BLOCK` documents of one source, each leaving at most three undecided
documents; those meet in blocks again, round after round, until one block a source is left, where the landing phase
drops the word constraint first and the count constraint last. Every task holds one block, whatever a source's share.

Edge cases: a null or blank text has size 0 and is taken 0 words; a null source is a source of its own, last in order;
rows of equal doc_id are decided each on its own; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import math
import random

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

WEIGHTS, SHARE, CAP, SEED, BLOCK = (5.0, 2.0, 1.0), 1.5, 2.0, "mix-1", 3000


def targets(sizes: list[tuple[str | None, int]]) -> dict[str | None, float]:
    """Target of each source from (source, size): weights in code-point order, null last, capped and reshared.

    The catalogue of sources (not of documents) is all that this needs; it is the only thing the driver holds.
    """
    order = sorted(sizes, key=lambda x: (x[0] is None, (x[0] or "").encode("utf-32-be")))
    weight = {s: WEIGHTS[i % len(WEIGHTS)] for i, (s, _) in enumerate(order)}
    size = dict(order)
    left, open_, out = SHARE * sum(size.values()), dict(weight), {}
    while open_:
        unit = left / sum(open_.values())
        over = [s for s, w in open_.items() if w * unit > CAP * size[s]]
        if not over:
            return out | {s: w * unit for s, w in open_.items()}
        for s in over:
            out[s] = CAP * size[s]
            left -= out[s]
            del open_[s]
    return out


def flight(p: list[float], x: list[float], rng: random.Random, landing: bool) -> list[float]:
    """Move `p` into {0, 1} keeping sum(p) and sum(p x); at most three stay between, none if `landing`."""
    eps, p = 1e-9, [min(1.0, max(0.0, v)) for v in p]
    p = [0.0 if v < eps else 1.0 if v > 1 - eps else v for v in p]
    waiting = [i for i, v in enumerate(p) if 0 < v < 1]
    rng.shuffle(waiting)
    active: list[int] = []

    def move(u: list[float]) -> None:
        up = min((((1 - p[i]) / d) if d > 0 else (p[i] / -d)) for i, d in zip(active, u, strict=True) if d)
        down = min(((p[i] / d) if d > 0 else ((1 - p[i]) / -d)) for i, d in zip(active, u, strict=True) if d)
        step = up if rng.random() * (up + down) < down else -down
        for i, d in zip(active, u, strict=True):
            v = p[i] + step * d
            p[i] = 0.0 if v < eps else 1.0 if v > 1 - eps else v
        active[:] = [i for i in active if 0 < p[i] < 1]

    while True:
        while waiting and len(active) < 3:
            active.append(waiting.pop())
        if len(active) == 3:
            a, b, c = (x[i] for i in active)
            u = [c - b, a - c, b - a]
            scale = max(map(abs, u))
            move([v / scale for v in u] if scale > 1e-12 else [1.0, -1.0, 0.0])
        elif landing and len(active) == 2:
            move([1.0, -1.0])
        elif landing and active:
            p[active[0]] = float(rng.random() < p[active[0]])
            active.clear()
        else:
            return p


def _settle(landing_blocks: bool):
    def run(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["_h", "doc_id", "size"], kind="stable", na_position="last")
        rng = random.Random(f"{SEED}:{key}")
        one = landing_blocks or bool((pdf["_blocks"] == 1).all())
        return pdf.assign(_p=flight(pdf["_p"].tolist(), pdf["size"].astype(float).tolist(), rng, one))

    return run


def mix(docs: DataFrame) -> DataFrame:
    """doc_id, source, size, source_size, target, copies, taken for each row of `docs` (doc_id, text, source)."""
    spark = docs.sparkSession
    size = F.regexp_count(F.coalesce(F.col("text"), F.lit("")), F.lit(common.WORD)).cast("long")
    rows = common.durable(
        docs.select("doc_id", "source", size.alias("size"), F.md5(F.concat_ws(":", F.lit(SEED), F.col("doc_id").cast("string"), F.crc32(F.coalesce(F.col("text"), F.lit(""))).cast("string"))).alias("_h")),
        "mix-rows",
    )
    per = [(r[0], r[1], r[2]) for r in rows.groupBy("source").agg(F.sum("size"), F.count(F.lit(1))).collect()]
    goal = targets([(s, n) for s, n, _ in per])
    catalogue = spark.createDataFrame(
        [(s, n, float(goal[s]), goal[s] / n if n else 0.0, max(1, math.ceil(k / BLOCK))) for s, n, k in per],
        "_s string, source_size long, target double, _ratio double, _blocks int",
    )
    d = rows.join(F.broadcast(catalogue) if len(per) <= 10_000 else catalogue, F.col("source").eqNullSafe(F.col("_s"))).drop("_s")
    d = d.withColumn("_whole", F.floor(F.col("_ratio") + 1e-12).cast("int")).withColumn("_p", F.greatest(F.lit(0.0), F.col("_ratio") - F.col("_whole")))
    d = d.withColumn("_p", F.when(F.col("size") == 0, 0.0).otherwise(F.col("_p")))
    hashed = F.conv(F.substring("_h", 1, 8), 16, 10).cast("long")
    decided, open_, rounds = [], d, 0
    while True:
        grouped = open_.withColumn("_block", F.pmod(hashed, F.col("_blocks")).cast("int"))
        got = common.durable(grouped.groupBy("source", "_block").applyInPandas(_settle(False), grouped.schema), f"mix-{rounds}").drop("_block")
        between = (F.col("_p") > 0) & (F.col("_p") < 1)
        decided.append(got.where(~between))
        if got.where(between).isEmpty():
            break
        # What is left is three documents a block: blocks shrink by BLOCK / 6 each round, and the last one of a source lands.
        open_, rounds = got.where(between).withColumn("_blocks", F.ceil(F.col("_blocks") * 6 / BLOCK).cast("int")), rounds + 1
        hashed = F.conv(F.substring("_h", 1 + 4 * min(rounds, 6), 8), 16, 10).cast("long")
    out = decided[0]
    for more in decided[1:]:
        out = out.unionByName(more)
    copies = (F.col("_whole") + F.col("_p").cast("int")).cast("int")
    return out.select("doc_id", "source", "size", "source_size", "target", copies.alias("copies"), (copies * F.col("size")).cast("long").alias("taken"))


def op3(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix(common.table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken", "source", "copies")


def mixture(docs: DataFrame) -> DataFrame:
    """The rows of `docs` as often as the mix takes them, with all columns; rows of equal doc_id are taken alike."""
    copies = mix(docs).groupBy(F.col("doc_id").alias("_id")).agg(F.max("copies").alias("_copies")).where("_copies > 0")
    # The side of the copies grows with the documents: joined by a merge at every size, never broadcast.
    taken = docs.join(copies.hint("merge"), docs["doc_id"].eqNullSafe(copies["_id"]))
    own = [docs[f"`{c}`"] for c in docs.columns]
    return taken.select(*own, F.explode(F.sequence(F.lit(1), copies["_copies"])).alias("_copy")).select(*own)
