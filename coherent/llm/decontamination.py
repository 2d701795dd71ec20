"""Benchmark decontamination by template canonicalisation, with DataFrame functions only.

Texts become tokens; numbers, units and names inside sentences become typed placeholders, so that a question with other numbers
or names has the template of the original. Windows of `WINDOW` tokens of the benchmark are looked up in every window of every
document, by two keys: their template, if it has `PLAIN` plain tokens, and their words as they are (in lower case). Whether a
capital is a name depends on what stands before it, which an item's first token lacks: the first window is also looked up with
that token as a name, and counts if the document has the item's own word there. Windows of one document and item on one diagonal
(document position - item position) belong to one copy; a copy counts if the windows of either key, or of both together, are
`LEAST` (or all of a shorter item's) and their slots are consistent: on the diagonal each value of the item maps to one value of
the document. The figures of a pair are those of its templates as they stand where these suffice (a first window found as a name is not
counted then), and else the largest of the others.

The benchmark's window hashes are a set of checked size: up to `INLINE` they are one literal, a table of buckets that the scan of
the documents tests in place, so texts are never exchanged; a larger benchmark is joined by hash instead.

Edge cases: null or empty texts match nothing; items of fewer than `SHORTEST` tokens, and windows with fewer than four
plain tokens, have templates too general to match and are found word for word only (an item of one word in every document that
has the word); items shorter than `WINDOW` are one window of their own length; rows are told
apart by doc_id (null or not) and text, so each text is judged on its own, and equal rows give one result; ties cannot arise; an empty table on either side gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import json

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

WINDOW, SHORTEST, LEAST, PLAIN, INLINE = 8, 4, 3, 4, 100_000
MARK = "\x01"
NAME = r"([\p{Ll}0-9,;] )(\p{Lu})"
TOKEN = MARK + r"?(?:[0-9]+(?:[.,][0-9]+)*|\p{L}[\p{L}\p{N}]*)"
UNITS = ("km", "cm", "mm", "kg", "mg", "ml", "hz", "khz", "mhz", "kb", "mb", "gb", "usd", "eur", "gbp", "percent", "meters", "metres", "miles", "feet", "inches", "liters", "litres", "grams", "pounds", "dollars", "euros", "seconds", "minutes", "hours", "days", "weeks", "months", "years")
SLOTS = ("<number>", "<name>", "<unit>")


def tokens(text: Column) -> Column:
    marked = F.regexp_replace(F.coalesce(text, F.lit("")), F.lit(NAME), F.lit("$1" + MARK + "$2"))
    return F.regexp_extract_all(marked, F.lit(TOKEN), F.lit(0))


def template(raw: Column) -> Column:
    def one(t: Column) -> Column:
        low = F.lower(t)
        return F.when(t < ":", F.when(F.substring(t, 1, 1) == MARK, "<name>").otherwise("<number>")).when(low.isin(*UNITS), "<unit>").otherwise(low)

    return F.transform(raw, one)


def words(raw: Column) -> Column:
    """The tokens as they are, in lower case and without marks."""
    return F.transform(raw, lambda t: F.lower(F.ltrim(t, F.lit(MARK))))


def _text_key(text: Column) -> Column:
    return F.xxhash64(F.coalesce(text, F.lit("")))


def _word_key(w: Column) -> Column:
    return F.xxhash64(w, F.lit("words"))  # apart from the templates' keys


def item_windows(benchmark: DataFrame) -> DataFrame:
    """_hash, _kind, item_id, _at, _first, _values (raw tokens), _n (windows of the item and kind) of every usable window of the benchmark."""
    t = benchmark.select(F.col("item_id").cast("long").alias("item_id"), tokens(F.col("text")).alias("_raw")).where(F.size("_raw") > 0)
    t = t.withColumn("_t", template(F.col("_raw"))).withColumn("_w", F.least(F.lit(WINDOW), F.size("_t")))
    starts = F.expr("sequence(1, size(_t) - _w + 1)")
    w = t.select("item_id", "_raw", "_t", "_w", F.explode(starts).alias("_at"))
    w = w.select("item_id", "_at", "_w", *[F.slice(c, F.col("_at"), F.col("_w")).alias(n) for c, n in (("_raw", "_values"), ("_t", "_slots"))])
    plain = (F.size(F.filter("_slots", lambda x: ~x.isin(*SLOTS))) >= PLAIN) & (F.col("_w") >= SHORTEST)
    renamed = F.concat(F.array(F.lit("<name>")), F.slice("_slots", 2, WINDOW))
    capital = (F.col("_at") == 1) & F.col("_values")[0].rlike(r"^\p{Lu}")
    key = lambda kind, first, h: F.struct(F.lit(kind).alias("_kind"), F.lit(first).alias("_first"), h.alias("_hash"))
    keys = F.array(
        key("words", False, _word_key(words(F.col("_values")))), F.when(plain, key("template", False, F.xxhash64("_slots"))), F.when(plain & capital, key("template", True, F.xxhash64(renamed)))
    )
    w = w.withColumn("_key", F.explode(F.array_compact(keys))).select("*", "_key.*").drop("_key")
    n = w.groupBy(F.col("item_id").alias("_i"), F.col("_kind").alias("_k")).agg(F.countDistinct("_at").alias("_n"))
    return w.join(n, (F.col("item_id") == F.col("_i")) & (F.col("_kind") == F.col("_k"))).drop("_i", "_k").dropDuplicates(["item_id", "_at", "_hash"])


def _buckets(known: list[int]) -> list[list[int]]:
    """`known` dealt by remainder, about one number a bucket."""
    out: list[list[int]] = [[] for _ in range(max(1, len(known)))]
    for h in known:
        out[h % len(out)].append(h)
    return out


def _found(w: int, known: list[int] | None) -> Column:
    """The windows of `w` tokens of `text` with a key in `known` (all where it is None): position, key, raw tokens.

    Tokens, template and words are bound as variables, so each is computed once a document. The keys are one literal, which the
    optimizer folds, bound as well: tens of thousands of literals by one call each take the driver seconds and its memory.
    """
    told = _buckets(known or [])
    table = F.from_json(F.lit(json.dumps(told)), "array<array<bigint>>")
    is_known = lambda table, h: F.array_contains(F.element_at(table, (F.pmod(h, F.lit(len(told)).cast("long")) + 1).cast("int")), h)

    def windows(table: Column | None, raw: Column, t: Column, low: Column) -> Column:
        starts = F.when(F.size(t) >= w, F.sequence(F.lit(1), F.size(t) - w + 1)).otherwise(F.array().cast("array<int>"))
        keyed = [
            F.transform(starts, lambda i: F.struct(i.alias("p"), F.xxhash64(F.slice(t, i, w)).alias("h"))),
            F.transform(starts, lambda i: F.struct(i.alias("p"), _word_key(F.slice(low, i, w)).alias("h"))),
        ]
        kept = keyed if table is None else [F.filter(k, lambda x: is_known(table, x["h"])) for k in keyed]
        return F.transform(F.concat(*kept), lambda x: F.struct(x["p"].alias("p"), x["h"].alias("h"), F.slice(raw, x["p"], w).alias("v")))

    every = lambda table: common.let(tokens(F.col("text")), lambda raw: common.let(template(raw), lambda t: common.let(words(raw), lambda low: windows(table, raw, t, low))))
    return every(None) if known is None else common.let(table, every)


def _copies(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """One row for each (doc_id, _text, item_id) with a copy, where _text is the hash of the document's text."""
    items = common.durable(item_windows(benchmark), "benchmark-windows")
    widths = sorted(r[0] for r in items.select("_w").distinct().collect())  # at most WINDOW numbers
    known = items.select("_hash").distinct()
    inline = known.limit(INLINE + 1).count() <= INLINE
    hits = None
    for w in widths:
        found = _found(w, [r[0] for r in items.where(F.col("_w") == w).select("_hash").distinct().collect()] if inline else None)
        rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), _text_key(F.col("text")).alias("_text"), F.explode(F.array(found)).alias("_found"))
        each = rows.select("doc_id", "_text", F.explode("_found").alias("_x"))
        each = each.select("doc_id", "_text", F.col("_x.p").alias("_p"), F.col("_x.h").alias("_h"), F.col("_x.v").alias("_v"), F.lit(w).alias("_width"))
        hits = each if hits is None else hits.unionByName(each)
    schema = "doc_id long, _text long, item_id long, n_windows long, coverage double, n_slots long"
    if hits is None:
        return docs.sparkSession.createDataFrame([], schema)
    right = F.broadcast(items) if inline else items
    m = hits.join(right, (F.col("_h") == F.col("_hash")) & (F.col("_width") == F.col("_w")))
    own_word = words(F.slice("_v", 1, 1)) == words(F.slice("_values", 1, 1))
    m = m.where(~F.col("_first") | own_word)
    slot_pairs = F.filter(F.arrays_zip(F.col("_slots").alias("s"), F.col("_values").alias("a"), F.col("_v").alias("b")), lambda x: x["s"].isin(*SLOTS))
    m = m.select("doc_id", "_text", "item_id", "_kind", "_first", "_n", "_at", (F.col("_p") - F.col("_at")).alias("_diagonal"), F.transform(slot_pairs, lambda x: F.struct(F.lower(x["a"]).alias("a"), F.lower(x["b"]).alias("b"))).alias("_pairs"))
    # Words cover every window of an item, so their number of windows is that of both keys together.
    n = right.where("_kind = 'words'").groupBy(F.col("item_id").alias("_i")).agg(F.max("_n").alias("_every"))
    m = m.join(F.broadcast(n) if inline else n, F.col("item_id") == F.col("_i"))
    # A first window with a name belongs to "named" and "both" only, so that "template" counts windows as they stand.
    m = m.withColumn("_kind", F.explode(F.array_compact(F.array(F.when(~F.col("_first"), F.col("_kind")), F.when(F.col("_kind") == "template", "named"), F.lit("both"))))).withColumn("_n", F.when(F.col("_kind") == "both", F.col("_every")).otherwise(F.col("_n")))
    # A diagonal has at most the item's windows, so its sets are bounded by the item's length.
    copy = m.groupBy("doc_id", "_text", "item_id", "_kind", "_n", "_diagonal").agg(F.countDistinct("_at").alias("_m"), F.array_distinct(F.flatten(F.collect_set("_pairs"))).alias("_pairs"))
    consistent = F.size(F.array_distinct(F.transform("_pairs", lambda x: x["a"]))) == F.size("_pairs")
    copy = copy.where((F.col("_m") >= F.least(F.lit(LEAST), F.col("_n"))) & consistent)
    most = lambda c: F.coalesce(F.max(F.when(F.col("_kind") == "template", c)), F.max(c))
    best = copy.groupBy("doc_id", "_text", "item_id").agg(most(F.col("_m")).alias("n_windows"), most(F.col("_m") / F.col("_n")).alias("coverage"), most(F.size("_pairs")).cast("long").alias("n_slots"))
    return best.select("doc_id", "_text", "item_id", "n_windows", F.round("coverage", 6).alias("coverage"), "n_slots")


def find(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """One row for each document and item with a copy: windows, share of the item's windows, slots of the best copy."""
    return _copies(docs, benchmark).drop("_text")


def clean(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """The rows of `docs` without a copy of a benchmark item, with all columns."""
    bad = common.durable(_copies(docs, benchmark).select(F.col("doc_id").alias("_bad"), "_text").distinct(), "contaminated")
    return docs.join(bad, docs["doc_id"].cast("long").eqNullSafe(bad["_bad"]) & (_text_key(docs["text"]) == bad["_text"]), "left_anti")


def op9(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find(common.table(spark, sf_dir, "documents"), common.table(spark, sf_dir, "benchmark"))


_SQL_TOKENS = "regexp_extract_all(regexp_replace(coalesce(text, ''), '([\\p{Ll}0-9,;] )(\\p{Lu})', '\\1' || chr(1) || '\\2', 'g'), chr(1) || '?(?:[0-9]+(?:[.,][0-9]+)*|\\p{L}[\\p{L}\\p{N}]*)')"
_SQL_UNITS = ", ".join(f"'{u}'" for u in UNITS)


def _token_rows(key: str, table: str) -> str:
    return f"SELECT {key}, unnest({_SQL_TOKENS}) AS r, generate_subscripts({_SQL_TOKENS}, 1) AS p FROM {table}"


_SQL_ONE = f"CASE WHEN r[1] = chr(1) THEN '<name>' WHEN r[1] BETWEEN '0' AND '9' THEN '<number>' WHEN lower(r) IN ({_SQL_UNITS}) THEN '<unit>' ELSE lower(r) END"


def _windows(key: str, rows: str) -> str:
    return f"""SELECT *, list(t) OVER e AS win, list(r) OVER e AS vals FROM (SELECT *, {_SQL_ONE} AS t, count(*) OVER (PARTITION BY {key}) AS len FROM {rows})
               WINDOW e AS (PARTITION BY {key} ORDER BY p ROWS BETWEEN CURRENT ROW AND {WINDOW - 1} FOLLOWING)"""


ORACLE = f"""
WITH br AS ({_token_rows("item_id", "benchmark")}), dr AS ({_token_rows("doc_id", "documents")}),
b0 AS ({_windows("item_id", "br")}), d0 AS ({_windows("doc_id", "dr")}),
bw AS (SELECT item_id, p AS q, least({WINDOW}, len) AS w, win, vals FROM b0 WHERE len >= {SHORTEST} AND p + least({WINDOW}, len) - 1 <= len
       AND len(list_filter(win, lambda y: y NOT IN ('<number>', '<name>', '<unit>'))) >= {PLAIN}),
bn AS (SELECT *, count(*) OVER (PARTITION BY item_id) AS n FROM bw),
dw AS (SELECT doc_id, p, w, win[1:w] AS win, vals[1:w] AS vals FROM d0, (SELECT DISTINCT w FROM bw) WHERE p + w - 1 <= len),
m AS (SELECT dw.doc_id, bn.item_id, bn.n, bn.q, dw.p - bn.q AS diagonal, bn.win, bn.vals AS a, dw.vals AS b FROM dw JOIN bn ON array_to_string(dw.win, ' ') = array_to_string(bn.win, ' ')),
pairs AS (SELECT DISTINCT doc_id, item_id, diagonal, lower(a[i]) AS a, lower(b[i]) AS b
          FROM (SELECT *, unnest(range(1, len(win)::BIGINT + 1)) AS i FROM m) WHERE win[i] IN ('<number>', '<name>', '<unit>')),
slots AS (SELECT doc_id, item_id, diagonal, count(*) AS pairs, count(DISTINCT a) AS items FROM pairs GROUP BY ALL),
copies AS (SELECT doc_id, item_id, n, diagonal, count(DISTINCT q) AS m FROM m GROUP BY ALL)
SELECT doc_id, item_id, max(m)::BIGINT AS n_windows, round(max(m::DOUBLE / n), 6) AS coverage, max(coalesce(pairs, 0))::BIGINT AS n_slots
FROM copies LEFT JOIN slots USING (doc_id, item_id, diagonal)
WHERE m >= least({LEAST}, n) AND coalesce(pairs, 0) = coalesce(items, 0) GROUP BY ALL
"""
