"""Near-duplicate documents by bottom-k sketches.

1. Each text becomes its set of 5-word shingles under one hash function; the `K` smallest values are its sketch. Texts of
   equal sets form a class, and one representative a class goes on.
2. Inverted lists of retained values generate overlaps. Values are ordered by how many sketches hold them (those of more than
   `HOT` last); a pair whose sketches share the `OVERLAP` that a similarity of 0.75 gives with near certainty
   (over five standard deviations) shares at least `SHARED` values, or a hot one, among the first
   `K - OVERLAP + SHARED` of both. Lists of up to `HOT` give pairs; longer ones only tie their members to the smallest.
3. Pairs and ties form clusters (connected components, by star contraction). The members' full sets meet in blocks of
   bounded bytes, where an overlap of the union's sketch filters pairs and the exact similarity confirms links.
4. Components of the links give component_id, the smallest doc_id reachable.

Classes have numbers of their own, and rows are told apart by doc_id and text, so null and repeated doc_ids are no special case.

Nothing is dropped or capped: a family of any size is compared block by block, and pairs already connected are skipped.

Edge cases: null, empty and blank texts have no shingles and link with nothing; texts of one to four words have their whole
sequence as one shingle; a null doc_id counts as the largest (a component of nulls alone has a null component_id, and the row of the
smallest text hash is kept); rows of equal doc_id and different texts are separate documents; equal rows get equal results, and `keep_one`
keeps one of them; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

K, OVERLAP, SHARED, HOT, WORDS = 48, 20, 5, 24, 5
BLOCK_DOCS, BLOCK_VALUES, FILTER = 400, 1 << 20, 32
LAST = (1 << 63) - 1
_ODD = [np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xFF51AFD7ED558CCD)]


def shingle_sets(texts: pa.Array) -> list[np.ndarray]:
    """The sorted distinct 64-bit shingle values (signed) of each text."""
    lists = pc.ascii_split_whitespace(pc.ascii_lower(common.whole(texts)))
    flat = lists.flatten()
    keep = pc.greater(pc.binary_length(flat), 0).to_numpy(zero_copy_only=False)
    coded = flat.dictionary_encode()
    digest = xxhash.xxh3_64_intdigest
    word = np.fromiter((digest(w) for w in coded.dictionary.to_numpy(zero_copy_only=False)), np.uint64, len(coded.dictionary))
    hashed = word[coded.indices.to_numpy(zero_copy_only=False)][keep] if len(flat) else np.zeros(0, np.uint64)
    before = np.concatenate([[0], np.cumsum(keep)])
    starts = before[np.concatenate([[0], np.cumsum(pc.list_value_length(lists).to_numpy(zero_copy_only=False))]).astype(np.int64)]
    n = max(0, len(hashed) - WORDS + 1)
    h = np.zeros(n, np.uint64)
    for i in range(WORDS):
        h = (h ^ (h >> np.uint64(31))) * _ODD[i] + hashed[i : i + n]
    h ^= h >> np.uint64(29)
    h *= _ODD[1]
    h ^= h >> np.uint64(32)
    out = []
    for a, b in zip(starts[:-1].tolist(), starts[1:].tolist(), strict=True):
        if b - a >= WORDS:
            out.append(np.unique(h[a : b - WORDS + 1].view(np.int64)))
        elif b > a:
            out.append(np.array([digest(hashed[a:b].tobytes(), b - a)], np.uint64).view(np.int64))
        else:
            out.append(np.zeros(0, np.int64))
    return out


def _slices(batches: Iterator[pa.RecordBatch], size: int) -> Iterator[pa.RecordBatch]:
    for whole in batches:
        for at in range(0, whole.num_rows, size):
            yield whole.slice(at, size)


def _sketch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for part in _slices(batches, 512):
        sets = shingle_sets(part.column("text"))
        keys = np.array([np.frombuffer(xxhash.xxh3_128_digest(s.tobytes()), np.int64) for s in sets], np.int64).reshape(-1, 2)
        sketches = [s[:K] for s in sets]
        values = pa.ListArray.from_arrays(np.concatenate([[0], np.cumsum([len(s) for s in sketches])]).astype(np.int32), pa.array(np.concatenate(sketches), pa.int64()))
        yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("h"), pa.array([len(s) for s in sets], pa.int64()), pa.array(keys[:, 0]), pa.array(keys[:, 1]), values], names=["doc_id", "h", "n", "k1", "k2", "sketch"])


def _sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for part in _slices(batches, 256):
        sets = [s.tobytes() for s in shingle_sets(part.column("text"))]
        # A row whose text hash agrees with its class by chance only is left out.
        own = np.array([np.frombuffer(xxhash.xxh3_128_digest(s), np.int64) for s in sets], np.int64).reshape(-1, 2)
        same = (own[:, 0] == part.column("k1").to_numpy()) & (own[:, 1] == part.column("k2").to_numpy())
        got = pa.RecordBatch.from_arrays([part.column(c) for c in ("cluster", "blocks", "block", "node")] + [pa.array(sets, pa.binary())], names=["cluster", "blocks", "block", "node", "values"])
        yield got.filter(pa.array(same))


def similar(a: np.ndarray, b: np.ndarray) -> bool:
    both = len(np.intersect1d(a, b, assume_unique=True))
    return 100 * both >= 75 * (len(a) + len(b) - both)


def _links(left: list[tuple[int, np.ndarray]], right: list[tuple[int, np.ndarray]] | None) -> list[tuple[int, int]]:
    """A spanning forest of the links within `left`, or between `left` and `right`."""
    both = left + (right or [])
    size = [len(v) for _, v in both]
    low = [frozenset(v[:FILTER].tolist()) for _, v in both]
    root = list(range(len(both)))

    def find(x: int) -> int:
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    out = []
    for j in range(len(both)):
        if right is not None and j < len(left):
            continue
        rj, nj, lj = find(j), size[j], low[j]
        for i in range(len(left) if right is not None else j):
            ni = size[i]
            if 4 * ni < 3 * nj or 4 * nj < 3 * ni:
                continue
            ri = find(i)
            if ri != rj and len(low[i] & lj) * 4 >= min(FILTER, ni, nj) and similar(both[i][1], both[j][1]):
                root[ri] = rj
                out.append((both[i][0], both[j][0]))
    return out


def _verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """From members sorted by (cluster, left, right): the confirmed links of each pair of blocks."""
    key, sides = None, ([], [])
    out: list[tuple[int, int]] = []

    def done() -> None:
        if key:
            out.extend(_links(sides[0], sides[1] if key[1] != key[2] else None))

    def flush() -> pa.RecordBatch:
        got = pa.RecordBatch.from_arrays([pa.array([x[i] for x in out], pa.int64()) for i in (0, 1)], names=["a", "b"])
        out.clear()
        return got

    for part in _slices(batches, 1024):
        for cluster, left, right, block, node, values in zip(*(part.column(c).to_pylist() for c in ("cluster", "left", "right", "block", "node", "values")), strict=True):
            if key != (cluster, left, right):
                done()
                key, sides = (cluster, left, right), ([], [])
            side = sides[int(block != left)]
            if not side or side[-1][0] != node:  # equal rows of a table bring a class more than once
                side.append((node, np.frombuffer(values, np.int64)))
        if out:
            yield flush()
    done()
    if out:
        yield flush()


def components(edges: DataFrame, tag: str) -> DataFrame:
    """(node, root) of every node of `edges` (a, b) but the roots; root is the smallest node reachable.

    Alternates large and small stars, which ends after a logarithmic number of rounds; each round is written, and only
    its row count and checksum come to the driver.
    """
    a, b = F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")
    e = common.durable(edges.select(a, b).where("a <> b").distinct(), tag)
    mark = None
    while True:
        now = e.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if now == mark:
            return e.select(F.col("a").alias("node"), F.col("b").alias("root"))
        mark = now
        both = e.unionByName(e.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy(F.col("a").alias("u")).agg(F.least(F.min("b"), F.first("a")).alias("m"))
        large = both.where("b > a").join(least, F.col("a") == F.col("u")).select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        least = large.groupBy(F.col("a").alias("u")).agg(F.min("b").alias("m"))
        small = large.join(least, F.col("a") == F.col("u")).select(F.explode(F.array(F.struct(F.col("b").alias("a"), F.col("m").alias("b")), F.struct(F.col("a"), F.col("m").alias("b")))).alias("x")).select("x.*")
        e = common.durable(small.where("a <> b").distinct(), tag)


def _candidates(classes: DataFrame) -> DataFrame:
    """(a, b): pairs and ties of representatives that may be similar, from `classes` (doc_id, n, sketch)."""
    size = F.size("sketch")
    t = F.ceil(size * OVERLAP / K)
    shared = F.least(F.lit(SHARED), t)
    posts = classes.select("doc_id", F.explode("sketch").alias("v"))
    hot = common.durable(posts.groupBy("v").agg(F.count(F.lit(1)).alias("df")).where(F.col("df") > HOT), "hot-values")
    hot_of = posts.join(hot, "v").groupBy(F.col("doc_id").alias("_d")).agg(F.array_sort(F.collect_list(F.struct("df", "v"))).alias("hot"))  # at most K each
    c = classes.join(hot_of, F.col("doc_id") == F.col("_d"), "left").drop("_d")
    hot_values = F.coalesce(F.transform("hot", lambda x: x["v"]), F.array().cast("array<long>"))
    cold_values = F.array_except("sketch", hot_values)
    first = (size - t + shared).cast("int")
    lists = c.select(
        "doc_id", "n", shared.cast("int").alias("need"),
        F.slice(cold_values, F.lit(1), first).alias("cold"),
        F.slice(hot_values, F.lit(1), F.greatest(F.lit(0), first - F.size(cold_values))).alias("ties"),
    )
    cold = lists.select("doc_id", "n", "need", F.explode("cold").alias("v"))
    left, right = cold.select("v", *[F.col(x).alias(f"{x}_l") for x in ("doc_id", "n", "need")]), cold.select("v", *[F.col(x).alias(f"{x}_r") for x in ("doc_id", "n", "need")])
    near = (F.col("doc_id_l") < F.col("doc_id_r")) & (4 * F.col("n_l") >= 3 * F.col("n_r")) & (4 * F.col("n_r") >= 3 * F.col("n_l"))
    pairs = left.join(right, "v").where(near).groupBy(F.col("doc_id_l").alias("a"), F.col("doc_id_r").alias("b")).agg(F.count(F.lit(1)).alias("got"), F.first(F.least("need_l", "need_r")).alias("need"))
    pairs = pairs.where(F.col("got") >= F.col("need")).select("a", "b")
    tied = lists.select("doc_id", F.explode("ties").alias("v"))
    centre = tied.groupBy("v").agg(F.min("doc_id").alias("b"))
    ties = tied.join(centre, "v").select(F.col("doc_id").alias("a"), "b")
    return pairs.unionByName(ties)


def _groups(docs: DataFrame) -> DataFrame:
    """doc_id (null: LAST), h (hash of the text), n, k1, k2, first (least doc_id and h of its component) of each row of `docs`."""
    spark = docs.sparkSession
    n = common.partitions(spark)
    d = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(LAST)).alias("doc_id"), F.xxhash64(F.coalesce(F.col("text"), F.lit(""))).alias("h"), "text")
    every = common.durable(d.mapInArrow(_sketch, "doc_id long, h long, n long, k1 long, k2 long, sketch array<long>"), "sketches")
    row = F.struct("doc_id", "h")
    classes = every.where("n > 0").groupBy("k1", "k2").agg(F.min(row).alias("first"), F.first("n").alias("n"), F.first("sketch").alias("sketch"))
    classes = common.durable(classes.withColumn("node", F.monotonically_increasing_id()), "classes")  # written once, so the numbers stay
    cluster = components(_candidates(classes.select(F.col("node").alias("doc_id"), "n", "sketch")), "clusters")
    members = cluster.unionByName(cluster.select(F.col("root").alias("node"), "root").distinct())
    sizes = members.join(classes.select("node", "n", "k1", "k2", "first"), "node")
    total = sizes.groupBy(F.col("root").alias("cluster")).agg(F.greatest(F.ceil(F.count(F.lit(1)) / BLOCK_DOCS), F.ceil(F.sum("n") / BLOCK_VALUES)).cast("int").alias("blocks"))
    placed = sizes.join(total, F.col("root") == F.col("cluster"))
    placed = placed.select("node", "cluster", "blocks", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int").alias("block"), "k1", "k2", F.col("first.doc_id").alias("_doc"), F.col("first.h").alias("_h"))
    placed = common.durable(placed, "members")
    # The members grow with the documents: joined by a merge at every size, never broadcast.
    texts = d.join(placed.hint("merge"), (F.col("doc_id") == F.col("_doc")) & (F.col("h") == F.col("_h")))
    sets = texts.select("cluster", "blocks", "block", "node", "k1", "k2", "text").mapInArrow(_sets, "cluster long, blocks int, block int, node long, values binary")
    # A block meets every block of its cluster, itself included.
    meets = sets.select("*", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("other")).select(
        "cluster", F.least("block", "other").alias("left"), F.greatest("block", "other").alias("right"), "block", "node", "values"
    )
    links = meets.repartition(n, "cluster", "left", "right").sortWithinPartitions("cluster", "left", "right", "block", "node").mapInArrow(_verify, "a long, b long")
    joined = components(links, "links")
    linked = joined.unionByName(joined.select(F.col("root").alias("node"), "root").distinct()).join(classes.select("node", "k1", "k2", "first"), "node")
    least = linked.groupBy(F.col("root").alias("_root")).agg(F.min("first").alias("least"))
    of_class = linked.join(least, F.col("root") == F.col("_root")).select(F.col("k1").alias("_1"), F.col("k2").alias("_2"), "least")
    alone = classes.join(linked.select("node"), "node", "left_anti").select(F.col("k1").alias("_1"), F.col("k2").alias("_2"), F.col("first").alias("least"))
    of_class = common.durable(of_class.unionByName(alone), "components")
    flat = every.select("doc_id", "h", "n", "k1", "k2").join(of_class, (F.col("k1") == F.col("_1")) & (F.col("k2") == F.col("_2")) & (F.col("n") > 0), "left")
    return flat.select("doc_id", "h", "n", F.coalesce("least", row).alias("first"))


def group(docs: DataFrame) -> DataFrame:
    """doc_id, n_shingles, component_id, kept for each row of `docs` (doc_id, text)."""
    null = lambda c: F.when(c != LAST, c)
    component = F.col("first.doc_id")
    kept = F.when(F.col("doc_id") == LAST, (component == LAST) & (F.col("h") == F.col("first.h"))).otherwise(F.col("doc_id") == component)
    return _groups(docs).select(null(F.col("doc_id")).alias("doc_id"), F.col("n").alias("n_shingles"), null(component).alias("component_id"), kept.alias("kept"))


def op4(spark: SparkSession, sf_dir: str) -> DataFrame:
    return group(common.table(spark, sf_dir, "documents"))


def keep_one(docs: DataFrame) -> DataFrame:
    """One row of `docs` of each group of similar documents, with all columns: that of the least doc_id and text hash.

    Rows without shingles stay. Of rows equal in doc_id and text, the one whose other columns have the least hash stays.
    """
    spark = docs.sparkSession
    seen = _groups(docs).groupBy("doc_id", "h").agg(F.count(F.lit(1)).alias("rows"), F.max("n").alias("n"), F.first("first").alias("first"))
    seen = seen.select(F.col("doc_id").alias("_doc"), F.col("h").alias("_h"), ((F.col("first.doc_id") == F.col("doc_id")) & (F.col("first.h") == F.col("h"))).alias("_stays"), ((F.col("rows") > 1) & (F.col("n") > 0)).alias("_often"))
    marks = common.durable(seen.where("not _stays or _often"), "near-duplicates")
    # By position: a table may have any column names.
    plain = docs.toDF(*[f"c{i}" for i in range(len(docs.columns))])
    doc, text = (F.col(f"c{docs.columns.index(c)}") for c in ("doc_id", "text"))
    on = (F.coalesce(doc.cast("long"), F.lit(LAST)) == F.col("_doc")) & (F.xxhash64(F.coalesce(text, F.lit(""))) == F.col("_h"))
    # The marks grow with the documents: joined by a merge at every size, never broadcast.
    out = plain.join(marks.hint("merge"), on, "left_anti")
    often = marks.where("_stays and _often")
    if not often.isEmpty():
        whole = F.struct(*plain.columns)
        one = plain.join(often, on).groupBy("_doc", "_h").agg(F.min_by(whole, F.xxhash64(F.to_json(whole))).alias("x"))
        out = out.unionByName(one.select("x.*"))
    return out.toDF(*docs.columns)
