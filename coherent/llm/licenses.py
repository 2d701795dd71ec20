"""License scans by ordered signature rules, with DataFrame functions only.

A text is lower-cased (A-Z) and normalised to its words with single spaces. The signatures, in order of priority: passages of the
licenses themselves (4), file headers and notices (3; both in `license_texts`), tags and field values of a license's name (3), prose
that grants under a name (2), a plain mention (1). A rule is tried only where its keyword, a run of words that every match of it
holds, occurs in the normalised text, and all of them only where one of `STEMS` does, of which every rule needs one.
Detections are intervals; one that lies within another of at least its priority is suppressed.

The base phrases are counted on the words themselves: every place where a phrase's words stand one after the other.

Edge cases: a null or empty text has no words, no labels and score 0; rows of equal doc_id are scanned each on their own; an empty
table gives an empty result; other columns are ignored. Positions are word numbers from 0.
"""

from __future__ import annotations

import json

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common
from .license_texts import BODIES, NOTICES, literal

TOKEN = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"
GAP = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
BASE = (("apache", ("apache", "license")), ("gpl", ("general", "public", "license")), ("mit", ("mit", "license")))
#: A text without any of these has no signature: a tag and a mention hold "licen" or "version", a grant one of its verbs, and
#: each of `OTHERS` a word of its own. Single words, as the text has other gaps than the normalised one.
STEMS = ("licen", "version", "released", "distribut", "available", "published", "covered", "provided", "governed", "domain", "reserved", "proprietary", "copyright", "copyleft",
         "permi", "freedom", "waive", "warrant", "liab", "clause", "attribution", "software", "dealings", "executable", "stuff", "fuck", "endorse",
         "prominent", "forming", "verbatim", "derivative", "statically", "png", "commercial", "restrictions", "invariant", "gcc", "mozilla",
         "ofl", "lppl", "charityware", "prohibited", "reproduced", "agreement", "oracle")
#: label: names as they read after normalising; the first words of each name are its keyword.
FAMILIES: dict[str, tuple[str, ...]] = {
    "mit": ("mit", "expat", "x11"), "mit-0": ("mit 0", "mit no attribution"), "isc": ("isc", "internet systems consortium"),
    "apache": ("apache", "apache software"), "apache-1.1": ("apache 1 1", "apache software 1 1"), "apache-2.0": ("apache 2 0", "apache license version 2 0", "apache version 2 0"),
    "bsd": ("bsd", "berkeley software distribution"), "bsd-2-clause": ("bsd 2 clause", "simplified bsd", "freebsd"), "bsd-3-clause": ("bsd 3 clause", "new bsd", "revised bsd", "modified bsd"), "bsd-4-clause": ("bsd 4 clause", "original bsd"), "0bsd": ("0bsd", "bsd zero clause"),
    "gpl": ("gnu general public", "gpl", "gnu gpl"), "gpl-1.0": ("gpl 1 0", "gplv1"), "gpl-2.0": ("gpl 2 0", "gplv2", "gnu general public license version 2"), "gpl-3.0": ("gpl 3 0", "gplv3", "gnu general public license version 3"),
    "lgpl": ("gnu lesser general public", "lgpl", "gnu library general public"), "lgpl-2.1": ("lgpl 2 1", "lgplv2 1", "gnu lesser general public license version 2 1"), "lgpl-3.0": ("lgpl 3 0", "lgplv3", "gnu lesser general public license version 3"),
    "agpl": ("gnu affero general public", "agpl"), "agpl-3.0": ("agpl 3 0", "agplv3", "gnu affero general public license version 3"), "gfdl": ("gnu free documentation", "gfdl"),
    "mpl": ("mozilla public",), "mpl-1.1": ("mpl 1 1", "mozilla public license version 1 1"), "mpl-2.0": ("mpl 2 0", "mozilla public license version 2 0", "mozilla public license v 2 0"),
    "epl": ("eclipse public",), "epl-1.0": ("epl 1 0",), "epl-2.0": ("epl 2 0", "eclipse public license 2 0"), "edl": ("eclipse distribution",), "cddl": ("cddl", "common development and distribution"), "cpl": ("common public license", "cpl 1 0"),
    "eupl": ("eupl", "european union public"), "osl-3.0": ("osl 3 0", "open software license"), "afl-3.0": ("afl 3 0", "academic free"), "artistic-1.0": ("artistic 1 0", "artistic license 1 0"), "artistic-2.0": ("artistic 2 0", "artistic license 2 0"), "perl": ("same terms as perl itself",),
    "zlib": ("zlib", "zlib libpng", "libpng"), "bsl-1.0": ("bsl 1 0", "boost software"), "busl-1.1": ("busl 1 1", "business source"), "sspl": ("sspl", "server side public"), "elastic-2.0": ("elastic license", "elastic 2 0"), "unlicense": ("unlicense",), "wtfpl": ("wtfpl", "do what the fuck you want to public"),
    "python-2.0": ("python software foundation", "psf", "python 2 0"), "php-3.01": ("php license", "php 3 01"), "ruby": ("ruby license",), "ncsa": ("ncsa", "university of illinois"), "openssl": ("openssl",), "ofl-1.1": ("ofl 1 1", "sil open font"), "postgresql": ("postgresql license",), "ms-pl": ("ms pl", "microsoft public"), "ms-rl": ("ms rl", "microsoft reciprocal"), "nasa": ("nasa open source",), "intel": ("intel open source",), "ipl-1.0": ("ipl 1 0", "ibm public"), "lppl": ("lppl", "latex project public"), "qpl": ("qpl", "q public"), "sleepycat": ("sleepycat",), "vim": ("vim license",), "w3c": ("w3c software", "w3c license"), "zope": ("zope public", "zpl"), "upl-1.0": ("upl 1 0", "universal permissive"), "mulanpsl-2.0": ("mulan psl",), "cecill": ("cecill",), "odbl": ("odbl", "open database license"), "odc-by": ("odc by", "open data commons attribution"), "pddl": ("pddl", "public domain dedication and"), "blueoak": ("blue oak model",), "hippocratic": ("hippocratic license",), "openrail": ("openrail", "open rail"), "llama": ("llama community",),
    "cc0": ("cc0", "creative commons zero", "cc zero"), "cc-by": ("cc by", "creative commons attribution"), "cc-by-sa": ("cc by sa", "creative commons attribution sharealike", "creative commons attribution share alike"), "cc-by-nc": ("cc by nc", "creative commons attribution noncommercial", "creative commons attribution non commercial"), "cc-by-nd": ("cc by nd", "creative commons attribution noderivatives", "creative commons attribution no derivatives"), "cc-by-nc-sa": ("cc by nc sa", "creative commons attribution noncommercial sharealike"), "cc-by-nc-nd": ("cc by nc nd", "creative commons attribution noncommercial noderivatives"),
}
TOP = 4
OTHERS = (
    ("public-domain", "public domain", r"(?:in|into|to) the public domain", 2), ("public-domain", "public domain", r"dedicated to (?:\S+ ){0,3}public domain", 3),
    ("proprietary", "all rights reserved", r"all rights reserved", 1), ("proprietary", "proprietary", r"proprietary (?:and confidential|licen[sc]e|software)", 2),
    ("copyright", "copyright", r"copyright (?:c )?(?:19|20)[0-9]{2}", 1), ("copyleft", "copyleft", r"copyleft", 1),
)
GRANT = r"(?:licen[sc]ed|released|distributed|available|published|covered|provided|governed|made available|redistribute\w*)(?: \S+){0,6}? (?:under|by|with)(?: the| a| an| terms| of){0,5}"


def rules() -> list[tuple[str, str, str, int]]:
    """(label, keyword, regular expression on normalised text, priority), the ordered table of signatures."""
    out = []
    for label, names in FAMILIES.items():
        for name in names:
            out.append((label, f" {name}", rf" (?:spdx )?license identifier(?: \S+)?? {name}(?= )(?: only| or later)?", 3))
            out.append((label, f" {name}", rf" {GRANT} {name}(?= )(?:(?: software| public)? licen[sc]e)?", 2))
            out.append((label, f" {name}", rf" (?:the )?{name}(?:(?: software| public)? licen[sc]e| version [0-9](?: [0-9])?)", 1))
    out += [(label, literal(pattern), f" {pattern}(?= )", priority) for table, priority in ((BODIES, 4), (NOTICES, 3)) for label, pattern in table]
    return out + [(label, f" {key}", f" {pattern}(?= )", priority) for label, key, pattern, priority in OTHERS]


def _detections(norm: Column) -> Column:
    """All matches of the applicable rules: start and end (characters of `norm`), priority, label."""
    # One literal, which the optimizer folds: hundreds of literals by one call each take the driver many seconds.
    told = json.dumps([dict(zip(("label", "key", "re", "prio"), rule, strict=True)) for rule in rules()])
    table = F.from_json(F.lit(told), "array<struct<label:string,key:string,re:string,prio:int>>")
    usable = F.filter(table, lambda r: F.contains(norm, r["key"]))

    def places(r: Column) -> Column:
        lengths = F.transform(F.regexp_extract_all(norm, r["re"], F.lit(0)), F.length)
        before = F.transform(F.split(norm, r["re"], -1), F.length)
        fold = F.aggregate(
            F.arrays_zip(lengths.alias("m"), F.slice(before, 1, F.size(lengths)).alias("b")),
            F.struct(F.lit(0).alias("at"), F.array().cast("array<struct<s:int,e:int>>").alias("out")),
            lambda acc, x: F.struct((acc["at"] + x["b"] + x["m"]).alias("at"), F.concat(acc["out"], F.array(F.struct((acc["at"] + x["b"]).alias("s"), (acc["at"] + x["b"] + x["m"]).alias("e")))).alias("out")),
            lambda acc: acc["out"],
        )
        return F.transform(fold, lambda p: F.struct(p["s"].alias("s"), (-p["e"]).alias("ne"), (-r["prio"]).alias("np"), r["label"].alias("label")))

    return F.flatten(F.transform(usable, places))


def _resolved(found: Column) -> Column:
    """Suppress what lies within another detection of at least its priority. One pass in order of start, longest first."""
    none = F.lit(-1)
    acc = F.struct(*[none.alias(f"m{k}") for k in range(1, TOP + 1)], F.array().cast("array<struct<s:int,e:int,prio:int,label:string>>").alias("kept"))

    def step(a: Column, d: Column) -> Column:
        end, prio = -d["ne"], -d["np"]
        # m_k: the furthest end so far of a detection of priority k or more
        reach = F.element_at(F.array(*[a[f"m{k}"] for k in range(1, TOP + 1)]), prio)
        one = F.struct(d["s"].alias("s"), end.alias("e"), prio.alias("prio"), d["label"].alias("label"))
        keep = lambda k: F.when(prio >= k, F.greatest(a[f"m{k}"], end)).otherwise(a[f"m{k}"])
        return F.struct(*[keep(k).alias(f"m{k}") for k in range(1, TOP + 1)], F.when(end <= reach, a["kept"]).otherwise(F.concat(a["kept"], F.array(one))).alias("kept"))

    return F.aggregate(F.array_sort(F.array_distinct(found)), acc, step, lambda a: a["kept"])


def _places(words: Column, phrase: tuple[str, ...]) -> Column:
    n = len(phrase)
    same = lambda i: F.slice(words, i + 1, n) == F.array(*[F.lit(w) for w in phrase])
    return F.filter(F.sequence(F.lit(0), F.greatest(F.lit(0), F.size(words) - n)), same)


def scan(docs: DataFrame) -> DataFrame:
    """n_words, base places and labels, and the resolved detections of each row of `docs` (doc_id, text)."""
    low = common.ascii_lower(F.coalesce(F.col("text"), F.lit("")))
    none = F.array().cast("array<int>")
    starts = F.struct(*[F.lit(None).cast("array<int>").alias(label) for label, _ in BASE])

    def base(low: Column) -> Column:
        def on(words: Column) -> Column:
            return F.struct(*[F.when(F.array_contains(words, phrase[0]), _places(words, phrase)).otherwise(none).alias(label) for label, phrase in BASE])

        return F.when(low.contains("license"), common.let(F.regexp_extract_all(low, F.lit(TOKEN), F.lit(0)), on)).otherwise(starts)

    def detections(low: Column) -> Column:
        norm = F.concat(F.lit(" "), F.trim(F.regexp_replace(low, F.lit(GAP), F.lit(" "))), F.lit(" "))
        gate = common.any_of([low.contains(s) for s in STEMS])
        empty = F.array().cast("array<struct<s:int,e:int,prio:int,label:string>>")
        # Ends of matches become word numbers: as many words start before a character as there are blanks up to it.
        number = lambda norm, at: F.length(F.substring(norm, F.lit(1), at)) - F.length(F.replace(F.substring(norm, F.lit(1), at), F.lit(" "), F.lit("")))

        def spans(norm: Column) -> Column:
            kept = _resolved(_detections(norm))
            return F.transform(kept, lambda d: F.struct(number(norm, d["s"]).alias("s"), number(norm, d["e"]).alias("e"), d["prio"].alias("prio"), d["label"].alias("label")))

        return F.when(gate, common.let(norm, spans)).otherwise(empty)

    one = common.let(low, lambda t: F.struct(F.regexp_count(t, F.lit(TOKEN)).cast("long").alias("n"), base(t).alias("base"), detections(t).alias("found")))
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.explode(F.array(one)).alias("_x")).select(
        "doc_id", F.col("_x.n").alias("n_words"), *[F.coalesce(F.col(f"_x.base.{label}"), none).alias(f"_{label}") for label, _ in BASE], F.col("_x.found").alias("detections")
    )


def op1(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = scan(common.table(spark, sf_dir, "documents"))
    every = F.flatten(F.array(*[F.col(f"_{label}") for label, _ in BASE]))
    base = F.array_compact(F.array(*[F.when(F.size(f"_{label}") > 0, F.lit(label)) for label, _ in BASE]))
    own = F.transform("detections", lambda x: x["label"])
    top = F.array_max(F.transform("detections", lambda x: x["prio"]))
    return d.select(
        "doc_id", "n_words", F.size(every).cast("long").alias("n_base"), F.array_min(every).cast("long").alias("first_word"), F.array_max(every).cast("long").alias("last_word"),
        F.array_join(base, ",").alias("base_labels"), F.array_join(F.array_sort(F.array_union(base, own)), ",").alias("labels"),
        F.greatest(F.coalesce(F.lit(0.25) * top, F.lit(0.0)), F.when(F.size(base) > 0, 0.8).otherwise(0.0)).alias("score"), F.size("detections").cast("long").alias("n_detections"),
    )
