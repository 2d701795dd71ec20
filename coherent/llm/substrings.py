"""Removal of repeated 100-byte strings, as a depth-limited radix sort of the suffixes.

Only windows of `DEPTH` bytes matter, so suffixes are ordered only that deep, and those that stand alone leave early:

1. The first pass deals windows by content: each is filed under the smallest hash among its inner `GRAM`-byte strings (its anchor).
   Equal windows have equal anchors, and neighbouring windows mostly share one, so a run of windows with one anchor is one row.
2. Rows are range-sorted by (anchor, hash of the slice of text, document, position), so that any anchor or slice, however common, is
   spread over tasks. A slice that came before is covered whole; an anchor with one slice repeats nothing; the first rows
   of the different slices of one anchor stay.
3. The windows of those slices alone are sorted by their bytes, `DIGIT` of them a pass from the most significant on: each pass splits the
   groups of the pass before, and windows that are alone in their group leave. Groups left after the last pass are
   exactly the repeated windows; all but a group's first cover their bytes. Anchors are sorted whole, many in one array. One of
   over `LARGE` slices is dealt over tasks by window instead, and its equal windows meet in a sorted stream.

Texts travel compressed; what is filed is about one row in 36 bytes of text. No task holds more than an anchor of `LARGE` slices.

Edge cases: a null or empty text has 0 bytes and the sha256 of nothing; texts under 100 bytes stay whole; equal texts of at least
100 bytes are removed but the first; a null doc_id counts as the largest; rows of equal doc_id are documents of their own, in the order
of their texts' hash, and of wholly equal ones one comes first; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

DEPTH, GRAM, CHUNK, DIGIT, LARGE, BATCH = 100, 28, 1 << 19, 8, 4096, 4096
INNER = DEPTH - GRAM + 1
LAST = (1 << 63) - 1
SCHEMA = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, spans array<struct<start:int,end:int>>"
_BYTES = np.random.default_rng(1).integers(0, 1 << 63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_MUL = [np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xFF51AFD7ED558CCD, 0xA0761D6478BD642F)]


def anchors(buf: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Runs of windows with one anchor in the texts laid end to end in `buf`: (text, first window, last window, anchor hash).

    `ends` has each text's end. Positions are in `buf`, which must be shorter than 2^20.
    """
    n = len(buf)
    if n < DEPTH:
        return tuple(np.zeros(0, np.int64) for _ in range(4))
    h1 = _BYTES[buf]
    h2 = h1[:-1] * _MUL[0] + h1[1:]
    h4 = h2[:-2] * _MUL[1] + h2[2:]
    h8 = h4[:-4] * _MUL[2] + h4[4:]
    h16 = h8[:-8] * _MUL[3] + h8[8:]
    m = n - GRAM + 1
    h = (h16[:m] * _MUL[4] + h8[16 : 16 + m]) * _MUL[5] + h4[24 : 24 + m]
    h ^= h >> np.uint64(29)
    h *= _MUL[4]
    h ^= h >> np.uint64(32)
    low = np.uint64((1 << 20) - 1)
    key = (h & ~low) | np.arange(m, dtype=np.uint64)
    for d in (1, 2, 4, 8, 16, 32):
        key = np.minimum(key[:-d], key[d:])
    key = np.minimum(key[: n - DEPTH + 1], key[INNER - 64 : INNER - 64 + n - DEPTH + 1])
    at = (key & low).astype(np.int64)
    starts = np.concatenate([[0], ends[:-1]])
    text = np.repeat(np.arange(len(ends)), ends - starts)[: n - DEPTH + 1]
    ok = np.arange(n - DEPTH + 1) + DEPTH <= ends[text]
    where = np.flatnonzero(ok)
    if not len(where):
        return tuple(np.zeros(0, np.int64) for _ in range(4))
    a, t = at[where], text[where]
    new = np.concatenate([[True], (a[1:] != a[:-1]) | (t[1:] != t[:-1])])
    first = np.flatnonzero(new)
    last = np.concatenate([first[1:], [len(where)]]) - 1
    return t[first], where[first], where[last], h[a[first]].astype(np.int64)


def _file(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    def flush(ids: list[tuple[int, int]], texts: list[bytes], offsets: list[int]) -> pa.RecordBatch:
        raw = b"".join(texts)
        ends = np.cumsum([len(t) for t in texts])
        doc, first, last, anchor = anchors(np.frombuffer(raw, np.uint8), ends)
        digest = xxhash.xxh3_64_intdigest
        slices = np.fromiter((digest(raw[a:b]) for a, b in zip(first.tolist(), (last + DEPTH).tolist(), strict=True)), np.uint64, len(first)).view(np.int64)
        shift = np.array(offsets, np.int64) - np.concatenate([[0], ends[:-1]])
        place = ((first + shift[doc]) << 8) | (last - first)
        keys = np.array(ids, np.int64)[doc]
        return pa.RecordBatch.from_arrays([pa.array(x) for x in (anchor, slices, keys[:, 0], keys[:, 1], place)], names=["anchor", "slice", "doc_id", "h", "place"])

    ids, texts, offsets, size = [], [], [], 0
    for whole in batches:
        for at in range(0, whole.num_rows, 256):
            part = whole.slice(at, 256)
            for doc_id, h, text in zip(*(part.column(c).to_pylist() for c in ("doc_id", "h", "text")), strict=True):
                data = (text or "").encode()
                if len(data) < DEPTH:
                    continue
                for cut in range(0, len(data) - DEPTH + 1, CHUNK):  # pieces of a long text overlap by all but one byte of a window
                    piece = data[cut : cut + CHUNK + DEPTH - 1]
                    ids.append((doc_id, h))
                    texts.append(piece)
                    offsets.append(cut)
                    size += len(piece)
                    if size > CHUNK // 2:
                        yield flush(ids, texts, offsets)
                        ids, texts, offsets, size = [], [], [], 0
    if texts:
        yield flush(ids, texts, offsets)


KEYS = ("anchor", "slice", "doc_id", "h", "place")


def _repeats(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """From rows sorted by `KEYS`: whole = 1 for slices that came before, 0 for those to compare.

    The task's first and last anchor and slice may go on in its neighbours, so the first of each of their slices is compared.
    """
    before = pending = None  # the row before; the one slice so far of the anchor that the last batch ended with
    names = ["doc_id", "h", "anchor", "place", "whole"]

    def marks(rows: np.ndarray, whole: int) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([*(pa.array(rows[KEYS.index(c)]) for c in names[:4]), pa.array(np.full(rows.shape[1], whole, np.int8))], names=names)

    for b in batches:
        if not b.num_rows:
            continue
        rows = np.stack([b.column(c).to_numpy() for c in KEYS])
        prior = np.concatenate([rows[:, :1] if before is None else before, rows[:, :-1]], axis=1)
        new_k, new_s = rows[0] != prior[0], (rows[:2] != prior[:2]).any(axis=0)
        again = (rows == prior).all(axis=0)  # an equal row of the table
        if before is None:
            new_s[0], again[0] = True, False
        run = np.cumsum(new_k)  # 0: the anchor of the batch before, or the task's first
        several = np.bincount(run, weights=new_s) >= 2
        several[0] = True
        if pending is not None:
            if (new_s & (run == 0)).any():
                yield marks(pending, 0)
                pending = None
            elif run[-1] > 0:
                pending = None
        yield marks(rows[:, ~new_s & ~again], 1)
        yield marks(rows[:, new_s & several[run]], 0)
        if not several[run[-1]]:
            at = int(np.flatnonzero(new_s)[-1])
            pending = rows[:, at : at + 1]
        before = rows[:, -1:]
    if pending is not None:
        yield marks(pending, 0)


def _pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    press = zstandard.ZstdCompressor(level=3)
    for whole in batches:
        for at in range(0, whole.num_rows, 512):
            part = whole.slice(at, 512)
            packed = [press.compress((t or "").encode()) for t in part.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("h"), pa.array(packed, pa.binary())], names=["doc_id", "h", "packed"])


def _unpack(data: bytes) -> bytes:
    return zstandard.ZstdDecompressor().decompress(data) if data else b""


def _cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The bytes of the wanted slices; of a large anchor, the windows' digests, each in a part of its own."""
    kinds = [(c, pa.int64()) for c in ("anchor", "part", "doc_id", "h", "start")] + [("digest", pa.binary()), ("bytes", pa.binary())]
    digest = xxhash.xxh3_128_digest
    for whole in batches:
        for at in range(0, whole.num_rows, 128):
            rows: list[tuple] = []
            for doc_id, h, packed, wanted in zip(*(whole.slice(at, 128).column(c).to_pylist() for c in ("doc_id", "h", "packed", "wanted")), strict=True):
                text = _unpack(packed)
                for w in wanted:
                    start = w["place"] >> 8
                    end = start + (w["place"] & 255) + 1
                    if not w["large"]:
                        rows.append((w["anchor"], 0, doc_id, h, start, b"", text[start : end - 1 + DEPTH]))
                        continue
                    for i in range(start, end):
                        d = digest(text[i : i + DEPTH])
                        rows.append((w["anchor"], int.from_bytes(d[:8], "big", signed=True) or 1, doc_id, h, i, d, b""))
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, (_, t) in zip(zip(*rows, strict=True), kinds, strict=True)], names=[c for c, _ in kinds])


def equal_windows(group: np.ndarray, data: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """(row, place in it) of every window that equals an earlier one of its group; `group` numbers the rows, in order.

    Digits are `DIGIT` bytes as a number, the most significant first; what is alone after a pass leaves.
    """
    size = np.fromiter(map(len, data), np.int64, len(data))
    begin = np.cumsum(size) - size
    raw = np.frombuffer(b"".join(data) + b"\0" * DIGIT, np.uint8)
    number = np.ascontiguousarray(np.lib.stride_tricks.sliding_window_view(raw, DIGIT)).view(">u8").ravel().astype(np.uint64)
    count = np.maximum(size - DEPTH + 1, 0)
    row = np.repeat(np.arange(len(data)), count)
    at = np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count) + begin[row]
    key = group[row].astype(np.int64)
    item = np.arange(len(row))
    for offset in [*range(0, DEPTH - DIGIT, DIGIT), DEPTH - DIGIT]:
        digit = number[at[item] + offset]
        order = np.lexsort((digit, key))  # stable: a group's windows stay in the order of the documents
        item, key, digit = item[order], key[order], digit[order]
        new = np.concatenate([[True], (key[1:] != key[:-1]) | (digit[1:] != digit[:-1])]) if len(item) else np.zeros(0, bool)
        key = np.cumsum(new)
        shared = np.bincount(key)[key] > 1 if len(key) else new
        item, key = item[shared], key[shared]
        if not len(item):
            break
    later = np.concatenate([[False], key[1:] == key[:-1]]) if len(item) else np.zeros(0, bool)
    item = np.sort(item[later])
    return row[item], at[item] - begin[row[item]]


COVER, ORDER = ["doc_id", "h", "start", "end"], ["anchor", "part", "digest", "doc_id", "h", "start"]


def _compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """From rows sorted by `ORDER`: the bytes covered by windows seen before under the same anchor.

    Slices of whole anchors are gathered and sorted together; a large anchor's windows come one a row, equal ones next to each other.
    """
    keys: list[tuple[int, int, int, int]] = []
    data: list[bytes] = []
    window = first = None

    def covers() -> pa.RecordBatch | None:
        k = np.array(keys, np.int64)
        row, place = equal_windows(np.cumsum(np.concatenate([[0], k[1:, 0] != k[:-1, 0]])), data)
        if not len(row):
            return None
        start = k[row, 3] + place
        head = np.concatenate([[True], (row[1:] != row[:-1]) | (start[1:] > start[:-1] + DEPTH)])
        last = np.concatenate([head[1:], [True]])
        return pa.RecordBatch.from_arrays([pa.array(c) for c in (k[row[head], 1], k[row[head], 2], start[head], start[last] + DEPTH)], names=COVER)

    for b in batches:
        singles: list[tuple] = []
        for anchor, part, digest, *key, text in zip(*(b.column(c).to_pylist() for c in (*ORDER, "bytes")), strict=True):
            if part:
                if (anchor, digest) != window:
                    window, first = (anchor, digest), key
                elif key != first:
                    singles.append((*key, key[2] + DEPTH))
                continue
            if keys and (anchor, *key) == keys[-1]:  # from an equal row of the table
                continue
            if len(keys) >= BATCH and anchor != keys[-1][0]:
                if (got := covers()) is not None:
                    yield got
                keys.clear()
                data.clear()
            keys.append((anchor, *key))
            data.append(text)
        if singles:
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*singles, strict=True)], names=COVER)
    if keys and (got := covers()) is not None:
        yield got


def merged(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for s, e in sorted(spans):
        if out and s <= out[-1][1]:
            out[-1] = (out[-1][0], max(out[-1][1], e))
        else:
            out.append((s, e))
    return out


def _apply(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32())])))
    names = ("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "spans")
    for whole in batches:
        for at in range(0, whole.num_rows, 256):
            part, rows = whole.slice(at, 256), []
            for doc_id, packed, covers, gone in zip(*(part.column(c).to_pylist() for c in ("doc_id", "packed", "covers", "gone")), strict=True):
                text = _unpack(packed)
                spans = [(0, len(text))] if gone and len(text) >= DEPTH else merged([(c["start"], c["end"]) for c in covers or ()])
                sha, done = hashlib.sha256(), 0
                for s, e in spans:
                    sha.update(text[done:s])
                    done = e
                sha.update(text[done:])
                rows.append((None if doc_id == LAST else doc_id, len(text), sum(e - s for s, e in spans), len(spans), sha.hexdigest(), [{"start": s, "end": e} for s, e in spans]))
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], names=names)


def deduplicate(docs: DataFrame) -> DataFrame:
    """What is removed from each row of `docs` (doc_id, text); see SCHEMA."""
    n, key = common.partitions(docs.sparkSession), ["doc_id", "h"]
    d = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(LAST)).alias("doc_id"), F.xxhash64(F.coalesce(F.col("text"), F.lit(""))).alias("h"), "text")
    filed = d.mapInArrow(_file, "anchor long, slice long, doc_id long, h long, place long")
    marks = filed.repartitionByRange(2 * n, *KEYS).sortWithinPartitions(*KEYS).mapInArrow(_repeats, "doc_id long, h long, anchor long, place long, whole byte")
    marks = common.durable(marks, "repeats")
    open_ = marks.where("whole = 0")
    large = common.durable(open_.groupBy("anchor").agg(F.count(F.lit(1)).alias("_of")).where(F.col("_of") > LARGE).select(F.col("anchor").alias("_large")), "large-anchors")
    open_ = open_.join(large, F.col("anchor") == F.col("_large"), "left")
    packed = d.mapInArrow(_pack, "doc_id long, h long, packed binary")
    wanted = open_.groupBy(*key).agg(F.collect_list(F.struct("anchor", "place", F.col("_large").isNotNull().alias("large"))).alias("wanted"))  # at most one a byte of the text
    slices = packed.join(wanted, key).select(*key, "packed", "wanted").mapInArrow(_cut, "anchor long, part long, doc_id long, h long, start long, digest binary, bytes binary")
    partly = slices.repartition(n, "anchor", "part").sortWithinPartitions(*ORDER).mapInArrow(_compare, "doc_id long, h long, start long, end long")
    start = F.shiftright("place", 8)
    fully = marks.where("whole = 1").select(*key, start.alias("start"), (start + F.col("place").bitwiseAND(255) + DEPTH).alias("end"))
    covers = fully.unionByName(partly).groupBy(*key).agg(F.collect_list(F.struct("start", "end")).alias("covers"))
    often = common.durable(d.groupBy(*key).agg(F.count(F.lit(1)).alias("_rows")).where("_rows > 1"), "equal-rows")
    once, none = packed, F.lit(None).cast("array<struct<start:bigint,end:bigint>>")
    later = None
    if not often.isEmpty():  # of equal rows, one is judged like any other, and the others are copies of it
        once = packed.join(often, key, "left_anti")
        same = packed.join(often, key).groupBy(*key, "_rows").agg(F.first("packed").alias("packed"))
        once = once.unionByName(same.drop("_rows"))
        later = same.select("doc_id", "packed", none.alias("covers"), F.lit(True).alias("gone"), "_rows")
    out = once.join(covers, key, "left").select("doc_id", "packed", "covers", F.lit(False).alias("gone")).mapInArrow(_apply, SCHEMA)
    if later is not None:
        copies = later.select("doc_id", "packed", "covers", "gone", F.explode(F.sequence(F.lit(2).cast("long"), F.col("_rows"))).alias("_copy")).repartition(n)
        out = out.unionByName(copies.drop("_copy").mapInArrow(_apply, SCHEMA))
    return out


def op6(spark: SparkSession, sf_dir: str) -> DataFrame:
    return deduplicate(common.table(spark, sf_dir, "documents")).drop("spans")
