"""Document fingerprints: a Merkle tree over sections, paragraphs and phrases of the text.

Sections end at blank lines, paragraphs at line ends, and leaves (phrases) after sentence marks or after a word that ends
in one of `CUT`: these cuts depend on the content alone, so an edit changes the leaves it touches and no others. A node's digest
covers its children's digests in order; roots of equal texts are equal, and of different texts they differ.

Two trees are compared from the roots down (`compare`): branches of equal digests are matched in order and left out, the
stretches between them are descended into, and what no branch of the other tree matches locates the edits, as stretches of the
text. The likeness is 1 for equal roots, and else the code points of matched branches over those of both texts together, matched
ones counted once; so order, repeats and single edits of long texts count, exactly.

The printed fingerprint has the root, the number of distinct leaves and the `SKETCH` smallest leaf digests. Two stored fingerprints
can be compared without their texts by `estimate`, whose standard error is at most 0.0625; the likenesses of the result don't use it.

The neighbour of each document is found with one exchange of the texts: documents are dealt to many small ranges of
doc_id, the first document of each range is sent to the range before it as well (one more row a range), and a task
walks its ranges in order, one document at a time.

Edge cases: a null text is the empty text, whose tree is a root without leaves (two of them have likeness 1); null doc_ids come last,
in the order of their texts' sha256 and in ranges of their own; rows of equal doc_id are ordered by the text's sha256; a table of one
row has itself as its next document; texts of any length are held one tree at a time; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
from bisect import bisect_left
from collections import defaultdict, deque
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from . import common

SKETCH, RANGES = 64, 16
#: Phrases end behind these letters at a word's end; about a fifth of all words.
CUT = "dhr"
LEAF = re.compile(rf"(?:[^\n]{{1,255}}?(?:(?<=[.!?;:{CUT}])[ \t]+|(?=\n)|\Z)|[^\n]{{1,255}}|)\n?")
SCHEMA = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double, n_leaves long, edited_places string"


def _digest(data: bytes) -> bytes:
    return hashlib.blake2b(data, digest_size=16).digest()


def leaves(text: str) -> list[str]:
    return [x for x in LEAF.findall(text) if x]


class Node:
    """A branch or leaf: its digest, the code points it covers, its children."""

    __slots__ = ("children", "digest", "end", "start")

    def __init__(self, mark: bytes, children: list[Node]) -> None:
        self.digest, self.children = _digest(mark + b"".join([c.digest for c in children])), children
        self.start, self.end = (children[0].start, children[-1].end) if children else (0, 0)

    @classmethod
    def leaf(cls, phrase: str, start: int) -> Node:
        node = cls.__new__(cls)
        node.digest, node.children, node.start, node.end = _digest(phrase.encode("utf-8", "surrogatepass")), [], start, start + len(phrase)
        return node


def tree(text: str) -> Node:
    """The root; its children are sections, theirs paragraphs, theirs leaves."""
    sections: list[Node] = []
    section: list[Node] = []
    paragraph: list[Node] = []
    at = 0
    for phrase in leaves(text):
        paragraph.append(Node.leaf(phrase, at))
        at += len(phrase)
        if phrase[-1] == "\n":
            section.append(Node(b"p", paragraph))
            paragraph = []
            if phrase == "\n":
                sections.append(Node(b"s", section))
                section = []
    if paragraph:
        section.append(Node(b"p", paragraph))
    if section:
        sections.append(Node(b"s", section))
    return Node(b"r", sections)


def leaf_digests(root: Node) -> set[bytes]:
    return {leaf.digest for s in root.children for p in s.children for leaf in p.children}


def fingerprint(text: str) -> tuple[str, Node, int]:
    """(printed form, tree, number of distinct leaves)."""
    root = tree(text)
    distinct = leaf_digests(root)
    sketch = sorted({d[:4] for d in distinct})[:SKETCH]
    return f"{root.digest.hex()}:{len(distinct)}:{b''.join(sketch).hex()}", root, len(distinct)


def estimate(a: str, b: str) -> float:
    """Jaccard estimate of the leaf sets of two printed fingerprints; 1 for equal roots."""
    (ra, _, sa), (rb, _, sb) = a.split(":"), b.split(":")
    if ra == rb:
        return 1.0
    x, y = ({s[i : i + 8] for i in range(0, len(s), 8)} for s in (sa, sb))
    union = sorted(x | y)[:SKETCH]
    return sum(v in x and v in y for v in union) / len(union) if union else 0.0


def in_order(a: list[bytes], b: list[bytes]) -> list[tuple[int, int]]:
    """Pairs of places of equal digests, rising on both sides: common ends, and the longest rising run of matches between them."""
    head, tail, most = 0, 0, min(len(a), len(b))
    while head < most and a[head] == b[head]:
        head += 1
    while tail < most - head and a[-1 - tail] == b[-1 - tail]:
        tail += 1
    where: dict[bytes, deque[int]] = defaultdict(deque)
    for j in range(head, len(b) - tail):
        where[b[j]].append(j)
    found = [(i, where[a[i]].popleft()) for i in range(head, len(a) - tail) if where.get(a[i])]
    lasts: list[int] = []  # smallest last place of a rising run, by length
    ends: list[int] = []
    before = [-1] * len(found)
    for n, (_, j) in enumerate(found):
        k = bisect_left(lasts, j)
        before[n] = ends[k - 1] if k else -1
        if k == len(lasts):
            lasts.append(j)
            ends.append(n)
        else:
            lasts[k], ends[k] = j, n
    run, n = [], ends[-1] if ends else -1
    while n >= 0:
        run.append(found[n])
        n = before[n]
    return [(i, i) for i in range(head)] + run[::-1] + [(len(a) - t, len(b) - t) for t in range(tail, 0, -1)]


def compare(a: Node, b: Node) -> tuple[float, list[tuple[int, int]]]:
    """(likeness, the stretches of the first text that the second lacks), descending only where branches differ."""
    if a.digest == b.digest:
        return 1.0, []
    places: list[tuple[int, int]] = []
    todo = [(a.children, b.children)]
    while todo:
        own, other = todo.pop()
        if not other or not own or not (own[0].children and other[0].children):
            matched = in_order([x.digest for x in own], [x.digest for x in other]) if own and other else []
            kept = {i for i, _ in matched}
            places += [(x.start, x.end) for i, x in enumerate(own) if i not in kept]
            continue
        i = j = 0
        for p, q in [*in_order([x.digest for x in own], [x.digest for x in other]), (len(own), len(other))]:
            if p > i or q > j:  # a stretch between two matches: the children on both sides
                todo.append(([c for x in own[i:p] for c in x.children], [c for x in other[j:q] for c in x.children]))
            i, j = p + 1, q + 1
    merged: list[tuple[int, int]] = []
    for s, e in sorted(places):
        if merged and merged[-1][1] == s:
            merged[-1] = (merged[-1][0], e)
        else:
            merged.append((s, e))
    shared = a.end - sum(e - s for s, e in merged)
    return shared / (a.end + b.end - shared), merged


def _walk(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    held = None  # (range, doc_id, text, fingerprint)
    types = {"long": pa.int64(), "string": pa.string(), "double": pa.float64()}
    schema = pa.schema([(x.split()[0], types[x.split()[1]]) for x in SCHEMA.split(", ")])
    for whole in batches:
        for at in range(0, whole.num_rows, 512):
            batch, out = whole.slice(at, 512), []
            for bucket, doc_id, text, edge in zip(*(batch.column(c).to_pylist() for c in ("_bucket", "doc_id", "text", "_edge")), strict=True):
                own = fingerprint(text)
                if held and held[0] == bucket:
                    half = len(held[2]) // 2
                    edited = held[2][: len(held[2]) - half] + text[:half]
                    changed = fingerprint(edited)
                    near, places = compare(held[3][1], changed[1])
                    shown = ",".join(f"{s}:{e}" for s, e in places)
                    out.append((held[1], len(held[2]), hashlib.sha256(edited.encode()).hexdigest(), held[3][0], changed[0], near, compare(held[3][1], own[1])[0], held[3][2], shown))
                held = None if edge else (bucket, doc_id, text, own)
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, schema.field(i).type) for i, c in enumerate(zip(*out, strict=True))], schema=schema)


def compare_with_next(docs: DataFrame) -> DataFrame:
    """Fingerprints of each document and of its edit by the next one, with their likenesses and the edit's places (see SCHEMA)."""
    spark = docs.sparkSession
    ranges = RANGES * common.partitions(spark)
    d = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text"), F.lit("")).alias("text"))
    d = d.withColumn("_sha", F.sha2("text", 256))
    d = common.range_bucketed(d, "doc_id", ranges, "_bucket")
    # Documents without a number come last, in as many ranges of their texts' sha256.
    of_sha = F.conv(F.substring("_sha", 1, 4), 16, 10).cast("int") * ranges / 65536
    d = d.withColumn("_bucket", F.col("_bucket") + F.when(F.col("doc_id").isNull(), of_sha.cast("int")).otherwise(0))
    # The first document of each range: one row a range.
    place = F.struct(F.col("doc_id").isNull().alias("n"), "doc_id", "_sha")
    firsts = d.groupBy("_bucket").agg(F.min(place).alias("_f")).select("_bucket", F.col("_f.doc_id").alias("_first"), F.col("_f._sha").alias("_first_sha"))
    firsts = common.durable(firsts, "fingerprint-ranges")
    turn = Window.orderBy("_bucket")  # as many rows as there are ranges, whatever the table's size
    before = firsts.select(F.col("_bucket").alias("_b"), "_first", "_first_sha", F.coalesce(F.lag("_bucket").over(turn), F.max("_bucket").over(Window.partitionBy(F.lit(0)))).alias("_to"))
    edge = d.join(F.broadcast(before), (F.col("_bucket") == F.col("_b")) & F.col("doc_id").eqNullSafe(F.col("_first")) & (F.col("_sha") == F.col("_first_sha")))
    edge = edge.groupBy(F.col("_to").alias("_bucket"), "doc_id", "_sha").agg(F.first("text").alias("text"))
    every = d.select("_bucket", "doc_id", "text", "_sha", F.lit(0).alias("_edge")).unionByName(edge.select("_bucket", "doc_id", "text", "_sha", F.lit(1).alias("_edge")))
    dealt = every.repartition(common.partitions(spark), "_bucket")
    return dealt.sortWithinPartitions("_bucket", "_edge", F.col("doc_id").asc_nulls_last(), "_sha").drop("_sha").mapInArrow(_walk, SCHEMA)


def op2(spark: SparkSession, sf_dir: str) -> DataFrame:
    return compare_with_next(common.table(spark, sf_dir, "documents"))
