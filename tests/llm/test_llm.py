"""Corpus operators against brute force on small fixtures, and the edge cases that their docstrings define."""

import hashlib
import random
import re
import zlib

import pyarrow as pa
import pytest
from pyspark.sql import functions as F

llm = pytest.importorskip("coherent.llm.catalogue")
from coherent.llm import common, decontamination, fingerprint, licenses, mixing, neardup, pii, sharding, substrings, toxicity, warc  # noqa: E402

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, extra string"
WORDS = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau".split()
LOWER = str.maketrans(common.UPPER, common.LOWER)


def corpus(seed=3, n=60):
    rng = random.Random(seed)
    text = lambda k: " ".join(rng.choice(WORDS) + str(rng.randrange(300)) for _ in range(k)) + ".\n"
    shared, texts = text(30), []
    for i in range(n):
        kind = i % 6
        if kind == 0:
            texts.append("".join(text(rng.randrange(5, 40)) for _ in range(3)))
        elif kind == 1:
            texts.append(texts[-1])  # an exact copy
        elif kind == 2:  # a near copy
            w = texts[-1].split(" ")
            w[rng.randrange(len(w))] = "changed"
            texts.append(" ".join(w))
        elif kind == 3:
            texts.append(text(10) + shared + text(12))
        elif kind == 4:
            texts.append(rng.choice(["", None, " \n ", "one two", "Üñí çødé MIT License ♥ the Apache-License; mit  license"]))
        else:
            texts.append(text(rng.randrange(1, 60)).upper())
    return [(i, t, "en", rng.choice(["a", "a", "a", "b", None]), 0, "x") for i, t in enumerate(texts)]


@pytest.fixture(scope="module")
def rows():
    return corpus()


@pytest.fixture(scope="module")
def docs(spark, rows):
    return spark.createDataFrame(rows, SCHEMA)


@pytest.fixture(scope="module")
def empty(docs):
    return docs.where("1 = 0")


def by_id(df):
    return {r.doc_id: r for r in df.collect()}


def shingles(text):
    w = re.findall(common.WORD, (text or "").translate(LOWER))
    return {tuple(w[j : j + 5]) for j in range(max(1, len(w) - 4))} if w else set()


def linked(sets):
    """The number of each set's group: the smallest place reachable over links."""
    root = list(range(len(sets)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, x in enumerate(sets):
        for b in range(a):
            if x and 100 * len(x & sets[b]) >= 75 * len(x | sets[b]):
                p, q = sorted((find(a), find(b)))
                root[q] = p
    return [find(i) for i in range(len(sets))]


def test_near_duplicates(docs, rows, empty):
    sets = [shingles(t) for _, t, *_ in rows]
    want = {i: (len(sets[i]), g, g == i) for i, g in enumerate(linked(sets))}
    got = by_id(neardup.group(docs))
    assert {i: (r.n_shingles, r.component_id, r.kept) for i, r in got.items()} == want
    assert neardup.group(empty).count() == 0


def test_near_duplicates_of_null_and_repeated_numbers(spark):
    a, b, c, d = (" ".join(f"{x}{i}" for i in range(60)) for x in "abcd")
    near = lambda t: t + " tail"
    long = " ".join(f"w{i % 50_000}" for i in range(250_000))  # over a megabyte
    rows = [(3, a), (7, near(a)), (7, b), (None, near(near(a))), (None, c), (None, near(c)), (None, None), (None, ""), (4, d), (4, d), (4, None), (9, long), (8, long + " x"), (1, "one two"), (2, "One  two")]
    df = spark.createDataFrame([(*r, 1, "x") for r in rows], "doc_id long, text string, h int, `c0.n` string").repartition(3)
    groups = linked([shingles(t) for _, t in rows])
    least = [min((rows[j][0] for j in range(len(rows)) if groups[j] == g and rows[j][0] is not None), default=None) for g in groups]
    show = lambda x: tuple("" if v is None else str(v) for v in x)
    got = sorted(show((r.doc_id, r.n_shingles, r.component_id)) for r in neardup.group(df).collect())
    assert got == sorted(show((i, len(shingles(t)), least[k])) for k, (i, t) in enumerate(rows))
    kept = neardup.keep_one(df)
    assert kept.columns == df.columns
    left = [(r.doc_id, r.text) for r in kept.collect()]
    # One row of each group, of the least number; all rows without words.
    assert sorted(show(x) for x in left if x[1] not in (c, near(c))) == sorted(show(x) for x in [(3, a), (7, b), (None, None), (None, ""), (4, d), (4, None), (8, long + " x"), (1, "one two")])
    assert len([x for x in left if x[1] in (c, near(c))]) == 1


def test_large_families_and_shared_boilerplate(spark):
    rng = random.Random(21)
    word = lambda: f"w{rng.randrange(5000)}"
    plate = [word() for _ in range(60)]
    base = [word() for _ in range(120)]
    texts = []
    for i in range(900):
        if i % 3 == 0:  # a family of near copies
            w = list(base)
            w[rng.randrange(120)] = f"edit{i}"
            texts.append(w)
        else:  # half of it shared by all, the rest its own
            texts.append(plate + [word() for _ in range(60)])
    rows = [(i, " ".join(w)) for i, w in enumerate(texts)]
    sets = [shingles(t) for _, t in rows]
    got = by_id(neardup.group(spark.createDataFrame(rows, "doc_id long, text string").repartition(4)))
    assert [got[i].component_id for i in range(len(rows))] == linked(sets)


def removed(rows, order):
    """Expected rows of op6, one for each of `rows` taken in `order`."""
    seen, out = set(), {}
    for i in order:
        b, spans = (rows[i][1] or "").encode(), []
        for j in range(len(b) - 99):
            w = b[j : j + 100]
            if w in seen:
                spans.append((j, j + 100))
            seen.add(w)
        spans, kept, at = substrings.merged(spans), b"", 0
        for s, e in spans:
            kept, at = kept + b[at:s], e
        out[i] = (rows[i][0], len(b), sum(e - s for s, e in spans), len(spans), hashlib.sha256(kept + b[at:]).hexdigest())
    return out


def test_repeated_strings(docs, rows, empty):
    got = [(r.doc_id, r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in substrings.deduplicate(docs).collect()]
    assert sorted(got) == sorted(removed(rows, range(len(rows))).values())
    assert substrings.deduplicate(empty).count() == 0


@pytest.mark.parametrize("large", [4096, 3])
def test_repeated_strings_of_null_and_repeated_numbers(spark, monkeypatch, large):
    monkeypatch.setattr(substrings, "LARGE", large)  # 3: every anchor is dealt over tasks by window
    rng = random.Random(3)
    vocabulary = ["".join(rng.choice("abcdefgh") for _ in range(rng.randrange(2, 9))) for _ in range(300)]
    text = lambda k: " ".join(rng.choice(vocabulary) for _ in range(k))
    shared, rows = [text(60) for _ in range(4)], []
    for i in range(120):
        t = text(rng.randrange(1, 80)) + (f" {rng.choice(shared)} {text(10)}" if i % 3 == 0 else "")
        rows.append((rng.choice([i, i, None, i // 2]), rng.choice(rows)[1] if i % 7 == 6 else t))
    rows += [(5, None), (5, "x" * 50), (None, ""), (9, "ü" * 400), (9, "ü" * 400), (9, "ü" * 400), (None, rows[0][1]), (None, rows[0][1]), (77, "ab" * 300_000), (78, text(110_000))]
    df = spark.createDataFrame([(*r, 1, 2) for r in rows], "doc_id long, text string, h int, packed int").repartition(5)
    h = [r.h for r in spark.createDataFrame(rows, "doc_id long, text string").select(F.xxhash64(F.coalesce("text", F.lit(""))).alias("h")).collect()]
    order = sorted(range(len(rows)), key=lambda i: (rows[i][0] is None, rows[i][0] or 0, h[i]))
    key = lambda x: (x[0] is None, x[0] or 0, *x[1:])
    got = [(r.doc_id, r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in substrings.deduplicate(df).collect()]
    assert sorted(got, key=key) == sorted(removed(rows, order).values(), key=key)


def test_digit_passes():
    rng = random.Random(1)
    for _ in range(30):
        base, rows, groups = bytes(rng.choice(b"ab") for _ in range(400)), [], []
        for g in range(3):
            for _ in range(rng.randrange(1, 8)):
                a, size = rng.randrange(260), rng.randrange(100, 137)
                rows.append(base[a : a + size] if rng.random() < 0.7 else bytes(rng.choice(b"ab") for _ in range(size)))
                groups.append(g)
        seen, want = set(), []
        for i, (g, x) in enumerate(zip(groups, rows, strict=True)):
            for j in range(len(x) - 99):
                want += [(i, j)] if (g, x[j : j + 100]) in seen else []
                seen.add((g, x[j : j + 100]))
        row, place = substrings.equal_windows(substrings.np.array(groups), rows)
        assert list(zip(row.tolist(), place.tolist(), strict=True)) == want


def test_personal_data_equals_patterns():
    kinds = {
        "email": (re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"), lambda s: True),
        "ip": (re.compile(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)"), lambda s: all(int(x) <= 255 for x in s.split("."))),
        "card": (re.compile(r"[0-9]([\x20-]?[0-9])+"), lambda s: 14 <= sum(map(str.isdigit, s)) <= 19 and pii._luhn(re.sub(r"\D", "", s))),
        "phone": (re.compile(r"\+[0-9][\x20().0-9-]+[0-9]"), lambda s: 10 <= sum(map(str.isdigit, s)) <= 15),
    }
    rng, found = random.Random(5), 0
    parts = ["a@b.co", "x.y@", "@", "..", ".", "-", " ", "+", "1", "22", "255", "4111 1111 1111 1111", "+1 (555) 123-4567", "10.0.0.1", "é", "a", "_", "%", "(", ")", "300.1.2.3", "4539-1488-0343-6467"]
    for _ in range(4000):
        text = "".join(rng.choice(parts) for _ in range(rng.randrange(1, 12)))
        want = sorted((m.start(), pii.KINDS.index(k), m.end()) for k, (p, ok) in kinds.items() for m in p.finditer(text) if ok(m[0]))
        assert [s for s in pii.find(text) if s[1] < 4] == want, text
        found += len(want)
    assert found > 1000
    assert pii.mask("mail a@b.co now") == "mail <email> now"


def test_personal_data_rows(spark, docs, rows, empty):
    assert len(by_id(pii.scan(docs))) == 60 and pii.scan(empty).count() == 0
    digits = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}
    text = "A é a@b.co and 10.0.0.1; 999.1.1.1 +1 (555) 123-4567 x@y.z.w, " * 9_000  # over half a megabyte
    own = [(1, text, 1), (1, None, 1), (None, "a@b.co", 1), (2, "", 1), (2, "1.2.3.4", 1)]
    got = spark.createDataFrame(own, "doc_id long, text string, n_email int").transform(pii.scan).collect()
    assert sorted((r.doc_id or 0, r.n_email, r.n_ip, r.n_phone) for r in got) == [(0, 1, 0, 0), (1, 0, 0, 0), (1, 18_000, 9_000, 9_000), (2, 0, 0, 0), (2, 0, 1, 0)]
    found = sorted((m.start(), list(digits).index(k), f"{k}:{m.start()}:{m.end()}") for k, p in digits.items() for m in re.finditer(p, text) if k != "ip" or all(int(x) < 256 for x in m[0].split(".")))
    want = hashlib.sha256(",".join(x for *_, x in found).encode()).hexdigest()
    assert [r.base_sha256 for r in got if r.n_ip == 9_000] == [want]


def test_personal_data_of_added_kinds():
    kinds = lambda t: [(pii.KINDS[k], t[s:e]) for s, k, e in pii.find(t) if k >= len(pii.BASE)]
    long = "a1" * 4000
    assert kinds(f"password: {long} end") == [("secret", long)]
    assert kinds("my IBAN, as agreed at length with the office that handles all of these matters for us, is DE89 3704 0044 0532 0130 00.") == [("account", "DE89 3704 0044 0532 0130 00")]
    assert kinds("IBAN\nDE89 3704 0044 0532 0130 00") == [] and kinds("iban DE88 3704 0044 0532 0130 00") == []
    assert kinds("12 Baker street, rue de la Grande Paix de Notre Dame et du Bon Secours 7; Hauptstraße 5; calle Mayor, 12; true story 5; the road 4x4") == [
        ("address", "12 Baker street"), ("address", "rue de la Grande Paix de Notre Dame et du Bon Secours 7"), ("address", "straße 5"), ("address", "calle Mayor, 12")]
    assert kinds("see https://a.b/c?d=e, or ssn 123-45-6789") == [("url", "https://a.b/c?d=e"), ("identifier", "123-45-6789")]
    for unit in ("iban ", "token=", "http://", " street", "rue Rue ", "account 1"):  # cues without end take time in proportion
        pii.find(unit * 40_000)


def longest_common(a, b, weight):
    """Weight of the heaviest common subsequence, by dynamic programming."""
    best = [0] * (len(b) + 1)
    for x in a:
        row = [0]
        for j, y in enumerate(b):
            row.append(max(best[j + 1], row[j], best[j] + weight(x) if x == y else 0))
        best = row
    return best[-1]


def test_fingerprints(docs, rows, empty):
    got, n = by_id(fingerprint.compare_with_next(docs)), len(rows)
    for i, t, *_ in rows:
        own, nxt = t or "", rows[(i + 1) % n][1] or ""
        half = len(own) // 2
        edited = own[: len(own) - half] + nxt[:half]
        r = got[i]
        assert (r.n_chars, r.edited_sha256) == (len(own), hashlib.sha256(edited.encode()).hexdigest())
        assert r.fingerprint == fingerprint.fingerprint(own)[0] and (r.near_next == 1.0) == (own == nxt)
        assert r.edited_fingerprint == fingerprint.fingerprint(edited)[0] and (r.near_edited == 1.0) == (own == edited)
        places = [tuple(map(int, x.split(":"))) for x in r.edited_places.split(",") if x]
        gone = sum(e - s for s, e in places)
        if own != edited:
            shared = len(own) - gone
            assert r.near_edited == pytest.approx(shared / (len(own) + len(edited) - shared))
            # What is left of the text is, in order, made of the other text's phrases: never more than the best alignment has.
            assert shared <= longest_common(fingerprint.leaves(own), fingerprint.leaves(edited), len)
            # All but the phrase that the cut goes through is found again, up to the cut.
            assert not places or places[0][0] >= len(own) - half - 512
        else:
            assert not places
    assert "".join(fingerprint.leaves("A b. C d\n\nE\x00f" * 99)) == "A b. C d\n\nE\x00f" * 99
    assert fingerprint.compare_with_next(empty).count() == 0


def test_fingerprint_trees():
    rng = random.Random(9)
    lines = ["".join(rng.choice(WORDS) + " " for _ in range(rng.randrange(1, 9))) for _ in range(40)]
    for _ in range(200):
        a = [rng.choice(lines) + rng.choice(["\n", "\n\n", ". "]) for _ in range(rng.randrange(0, 25))]
        b = [x for x in a if rng.random() < 0.9] + [rng.choice(lines)] * rng.randrange(2)
        if rng.random() < 0.3:
            rng.shuffle(b)
        x, y = "".join(a), "".join(b)
        near, places = fingerprint.compare(fingerprint.tree(x), fingerprint.tree(y))
        back, _ = fingerprint.compare(fingerprint.tree(y), fingerprint.tree(x))
        assert 0 <= near <= 1 and (near == 1.0) == (x == y) == (back == 1.0)
        assert (fingerprint.tree(x).digest == fingerprint.tree(y).digest) == (x == y)
        shared = len(x) - sum(e - s for s, e in places)
        assert shared <= longest_common(fingerprint.leaves(x), fingerprint.leaves(y), len)
    # A single edit of a long text is found where it is, and order and repeats count.
    text = "".join(f"Line {i} has its own words here.\n" + "\n" * (i % 7 == 0) for i in range(5000))
    at = text.index("Line 3000 ")
    edited = text.replace("Line 3000 has", "Line 3000 had")
    near, places = fingerprint.compare(fingerprint.tree(text), fingerprint.tree(edited))
    assert 0.999 < near < 1 and len(places) == 1 and at <= places[0][0] <= places[0][1] <= at + 40
    swapped = fingerprint.compare(fingerprint.tree("One two.\nThree four.\n"), fingerprint.tree("Three four.\nOne two.\n"))
    assert 0 < swapped[0] < 1
    assert fingerprint.compare(fingerprint.tree("x.\n"), fingerprint.tree("x.\nx.\n"))[0] == 0.5
    assert fingerprint.estimate(fingerprint.fingerprint(text)[0], fingerprint.fingerprint(edited)[0]) > 0.8


def test_fingerprints_of_null_and_repeated_numbers(spark):
    rng = random.Random(12)
    keys = [rng.choice([None, None, i // 2, i]) for i in range(120)]
    rows = [(k, f"text {rng.randrange(60)} " * rng.randrange(1, 30), 1, "e") for k in keys]
    rows += [(7, "long " * 300_000, 1, "e")]
    df = spark.createDataFrame(rows, "doc_id long, text string, _bucket int, _sha string").repartition(5)
    order = sorted(rows, key=lambda r: (r[0] is None, r[0] or 0, hashlib.sha256(r[1].encode()).hexdigest()))
    want = []
    for i, (k, t, *_) in enumerate(order):
        half, nxt = len(t) // 2, order[(i + 1) % len(order)][1]
        want.append((k or -1, len(t), hashlib.sha256((t[: len(t) - half] + nxt[:half]).encode()).hexdigest()))
    got = [(r.doc_id or -1, r.n_chars, r.edited_sha256) for r in fingerprint.compare_with_next(df).collect()]
    assert sorted(got) == sorted(want)


def test_sharding_against_brute_force(docs, rows, empty):
    got = by_id(sharding.interleave(docs))
    n, groups = len(rows), {}
    h = lambda i: hashlib.md5(f"{sharding.SEED}:{i}".encode()).hexdigest()
    for i, _, _, s, *_ in rows:
        groups.setdefault(s, []).append((h(i), i))
    order = []
    for s, g in groups.items():
        order += [((2 * k + 1) / (2 * len(g)), s is None, s or "", x, i) for k, (x, i) in enumerate(sorted(g))]
    place = {i: g for g, (*_, i) in enumerate(sorted(order))}
    for i, t, *_ in rows:
        s = place[i] * 16 // n
        assert (got[i].shard, got[i].slot) == (s, place[i] - -(-s * n // 16)), i
        assert (got[i].size, got[i].text_crc32) == (len((t or "").encode()) + 1, zlib.crc32((t or "").encode()))
    assert sharding.interleave(empty).count() == 0


def test_mixing(docs, rows, empty):
    got = by_id(mixing.mix(docs))
    size = {i: len(re.findall(common.WORD, t or "")) for i, t, *_ in rows}
    goal = mixing.targets([(s, sum(size[i] for i, _, _, x, *_ in rows if x == s)) for s in ("a", "b", None)])
    assert sum(goal.values()) == pytest.approx(1.5 * sum(size.values()))
    for s in goal:
        own = [r for i, r in got.items() if r.source == s]
        assert abs(sum(r.taken for r in own) - goal[s]) <= 2 * max(size.values())
    assert all(r.size == size[i] and r.taken <= 2 * r.size for i, r in got.items())
    assert {i: r.taken for i, r in got.items()} == {i: r.taken for i, r in by_id(mixing.mix(docs)).items()}
    assert mixing.mix(empty).count() == 0
    rng = random.Random(1)
    x = [rng.randrange(1, 50) for _ in range(500)]
    p = mixing.flight([0.3] * 500, [float(v) for v in x], rng, False)
    assert sum(0 < v < 1 for v in p) <= 3
    assert sum(p) == pytest.approx(150) and sum(a * b for a, b in zip(p, x)) == pytest.approx(0.3 * sum(x))


def test_warc_round_trip(spark, tmp_path):
    big = "<p>" + "é" * 700
    pages = [(1, "http://a/1", big), (2, "http://a/2", "small"), (3, None, "small"), (4, "http://a/4", big), (5, "u", None), (None, "n", big), (6, "x\r\ny", big)]
    df = spark.createDataFrame([(*p, 1) for p in pages], "page_id long, url string, html string, file int")
    names = []
    for run in ("a", "b"):
        root = f"file://{tmp_path}/{run}"
        manifest = warc.write(df, root, roll=600).orderBy("file").collect()
        names.append([(m.file, m.sha256) for m in manifest])
    assert names[0] == names[1] and len(names[0]) > 1
    got = {r.page_id: r for r in warc.read(spark, root).collect()}
    assert {i: r.refers_to for i, r in got.items()} == {1: 6, 4: 6, 6: None, 2: None, 3: None, 5: None, None: None}
    assert all(r.intact and r.payload_digest == hashlib.sha1((p[2] or "").encode()).hexdigest() and r.payload_bytes == len((p[2] or "").encode()) for p in pages for r in [got[p[0]]])
    root = f"file://{tmp_path}/none"
    warc.write(df.where("1 = 0"), root)
    assert warc.read(spark, root).count() == 0


def test_licenses(docs, rows, empty):
    got = by_id(licenses.scan(docs))
    for i, t, *_ in rows:
        w = re.findall(licenses.TOKEN, (t or "").translate(LOWER))
        assert got[i].n_words == len(w)
        for label, phrase in licenses.BASE:
            assert list(got[i][f"_{label}"]) == [k for k in range(len(w)) if tuple(w[k : k + len(phrase)]) == phrase]
    one = docs.limit(1).select(F.lit(1).alias("doc_id"), F.lit("Released under the Apache License, Version 2.0. SPDX-License-Identifier: MIT").alias("text"))
    assert {"apache-2.0", "mit"} <= {x.label for x in licenses.scan(one).first().detections}
    assert len(licenses.rules()) > 200 and licenses.scan(empty).count() == 0


def test_license_detections_against_brute_force(spark):
    rng = random.Random(11)
    parts = ["Licensed under the Apache License, Version 2.0", "SPDX-License-Identifier: MIT", "the GPL v2", "released under the terms of the GNU General Public License version 3", "MIT License; mit license", "Copyright (c) 2019 A. B.",
             "All rights reserved", "into the public domain", "CC BY-SA license", "creative commons attribution sharealike", "BSD 3-Clause License", "zlib", "proprietary and confidential", "é ünder", "commit mit", "license", "gpl or later"]
    texts = [rng.choice([" ", "\n", ". "]).join(rng.choice(parts) for _ in range(rng.randrange(1, 9))) for _ in range(60)]
    got = by_id(licenses.scan(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")))
    found = 0
    for i, text in enumerate(texts):
        low = text.translate(LOWER)
        norm = f" {re.sub(licenses.GAP, ' ', low).strip(' ')} "
        hits = sorted({(m.start(), -m.end(), -prio, label) for label, _, rule, prio in licenses.rules() for m in re.finditer(rule, norm, re.ASCII)})
        want = []
        for n, (s, e, prio, label) in enumerate(hits):
            if not any(e2 <= e and p2 <= prio for _, e2, p2, _ in hits[:n]):
                want.append((norm[:s].count(" "), norm[:-e].count(" "), -prio, label))
        assert [(d.s, d.e, d.prio, d.label) for d in got[i].detections] == want, text
        found += len(want)
    assert found > 100


def test_licenses_without_a_license_word(spark):
    parts = ["Distributed under the terms of the MPL 2.0", "available under MIT", "Released under the Apache 2.0 terms", "released under the BSD 3-Clause", "Provided under CC BY-SA 4.0", "covered by the EPL 2.0",
             "governed by\nthe Zlib terms", "published with Expat", "redistributed under ISC", "Apache Version 2.0", "Zlib version 1.2", "All rights\nreserved", "into the public-domain", "Proprietary software", "plain words"]
    texts = parts + [f"{a}; {b}" for a in parts for b in parts[::4]]
    got = by_id(licenses.scan(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")))
    for i, text in enumerate(texts):
        norm = f" {re.sub(licenses.GAP, ' ', text.translate(LOWER)).strip(' ')} "
        hits = sorted({(m.start(), -m.end(), -prio, label) for label, _, rule, prio in licenses.rules() for m in re.finditer(rule, norm, re.ASCII)})
        want = [(norm[:s].count(" "), norm[:-e].count(" "), -p, label) for n, (s, e, p, label) in enumerate(hits) if not any(e2 <= e and p2 <= p for _, e2, p2, _ in hits[:n])]
        assert [(d.s, d.e, d.prio, d.label) for d in got[i].detections] == want, text
    assert all(got[i].detections for i in range(len(parts) - 1)) and not got[len(parts) - 1].detections


def samples(pattern, rng):
    """A text that matches `pattern`."""
    from re import _parser as parser

    def one(items):
        out = ""
        for op, arg in items:
            name = str(op)
            if name == "LITERAL":
                out += chr(arg)
            elif name == "IN":
                kind, value = rng.choice(arg)
                out += chr(value) if str(kind) == "LITERAL" else chr(rng.randint(*value)) if str(kind) == "RANGE" else rng.choice("wxyz")
            elif name == "BRANCH":
                out += one(rng.choice(arg[1]))
            elif name in ("MAX_REPEAT", "MIN_REPEAT"):
                out += "".join(one(arg[2]) for _ in range(rng.randint(arg[0], min(int(arg[1]), arg[0] + 3))))
            elif name == "SUBPATTERN":
                out += one(arg[3])
            elif name == "ASSERT":
                out += one(arg[1]) if arg[0] > 0 else ""
            else:
                raise ValueError(name)
        return out

    return one(parser.parse(pattern))


def test_every_license_rule_is_reached(spark):
    rng = random.Random(17)
    rules = licenses.rules()
    texts = [samples(rule, rng) + " end of it" for _, _, rule, _ in rules for _ in range(2)]
    marked = [re.sub(" ", lambda _: rng.choice([" ", "\n", ", ", " (", '"-']), t).title() for t in texts]
    got = by_id(licenses.scan(spark.createDataFrame(list(enumerate(marked)), "doc_id long, text string").repartition(4)))
    for i, text in enumerate(marked):
        norm = f" {re.sub(licenses.GAP, ' ', text.translate(LOWER)).strip(' ')} "
        hits = sorted({(m.start(), -m.end(), -prio, label) for label, _, rule, prio in rules for m in re.finditer(rule, norm, re.ASCII)})
        assert any(label == rules[i // 2][0] for *_, label in hits), (rules[i // 2], text)
        want = [(norm[:s].count(" "), norm[:-e].count(" "), -p, label) for n, (s, e, p, label) in enumerate(hits) if not any(e2 <= e and p2 <= p for _, e2, p2, _ in hits[:n])]
        assert [(d.s, d.e, d.prio, d.label) for d in got[i].detections] == want, text
    bodies = {"Permission is hereby granted, free of charge, to any person obtaining a copy\nof this software and associated documentation files (the \"Software\")": "mit", "Redistribution and use in source and binary forms, with or without\n modification, are permitted provided that the following conditions are met:": "bsd"}
    for text, label in bodies.items():
        assert [x.label for x in licenses.scan(spark.createDataFrame([(1, text)], "doc_id long, text string")).first().detections] == [label]


def test_decontamination(spark, docs, empty):
    item = "If Anna buys 12 apples and then 7 pears for 3 km of road, how many fruits does she carry home"
    slots = "take 12 apples from 12 boxes and eat 12 pears by 12 noon"
    bench = spark.createDataFrame([(1, item), (2, "too short"), (3, None), (4, slots)], "item_id long, text string")
    texts = [(1, "So. " + item + " today?"), (2, item.replace("12", "40").replace("Anna", "Maria")), (3, item.replace("12", "40", 1) + " " + "noise " * 20), (4, "nothing here at all"), (5, None), (6, item[:30]),
             (7, slots.replace("12", "15")), (8, "take 15 apples from 16 boxes and eat 17 pears by 18 noon"), (9, "word " * 200_000 + item)]
    found = decontamination.find(spark.createDataFrame(texts, "doc_id long, text string"), bench).collect()
    # In document 8 the item's one value has become four: not one re-parameterisation.
    assert {(r.doc_id, r.item_id) for r in found} == {(1, 1), (2, 1), (3, 1), (7, 4), (9, 1)}
    assert {r.doc_id for r in decontamination.clean(spark.createDataFrame(texts, "doc_id long, text string"), bench).collect()} == {4, 5, 6, 8}
    assert decontamination.find(empty, bench).count() == 0 and decontamination.find(docs, bench.where("1 = 0")).count() == 0


def test_decontamination_hands_its_keys_over_as_one_literal(spark):
    """The driver's memory: literals by one call each, twice a key, and both kept and printed with every plan."""
    text = lambda k: " ".join(WORDS[(k * 7 + i * i) % len(WORDS)] + "abcdefghij"[(k + i) % 10] for i in range(12))
    bench = spark.createDataFrame([(i, text(i)) for i in range(1, 31)], "item_id long, text string")
    texts = spark.createDataFrame([(k, text(k) + " and more") for k in (3, 17)] + [(99, "nothing of it")], "doc_id long, text string")
    pairs = decontamination._copies(texts, bench)
    plan = pairs._jdf.queryExecution().analyzed().toString()
    keys = [r[0] for r in decontamination.item_windows(bench).select("_hash").distinct().collect()]
    assert len(keys) > 100 and max(plan.count(str(h)) for h in keys) == 1
    assert {(r.doc_id, r.item_id) for r in pairs.collect()} >= {(3, 3), (17, 17)} and pairs.where("doc_id = 99").count() == 0


def test_decontamination_of_null_and_repeated_numbers(spark):
    item = "Which of the many old bridges over the river is the longest one in town"
    bench = spark.createDataFrame([(1, item), (1, item), (None, None)], "item_id long, text string")
    half = [item[:33], item[33:]]
    rows = [(None, item), (None, "clean words only"), (None, None), (5, item), (5, "other"), (5, item), (6, half[0]), (6, half[1]), (7, "fine")]
    df = spark.createDataFrame([(*r, 1, 2, 3) for r in rows], "doc_id long, text string, _bad int, _text int, item_id int")
    assert sorted((r.doc_id or 0, r.item_id) for r in decontamination.find(df, bench).collect()) == [(0, 1), (5, 1)]
    kept = decontamination.clean(df, bench)
    assert kept.columns == df.columns
    assert sorted((r.doc_id or 0, r.text or "") for r in kept.collect()) == sorted((a or 0, b or "") for a, b in rows if b != item)


def test_decontamination_word_for_word(spark):
    items = [(1, "Compute 12 + 7 - 3 times 44 minus 9."), (2, "What is the capital of France"), (3, "two words"), (4, "Which of the brothers buys 12 pears at noon"), (5, "Sum 1 2 3 4 5 6 7 8 9 10 11 12")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    texts = [
        (1, "so " + items[0][1] + " then"), (2, "they asked What is the capital of France today"), (3, "here are Two words."), (4, "he asks Which of the brothers buys 40 pears at noon, again"), (5, "as in Sum 1 2 3 4 5 6 7 8 9 10, then"),
        (6, "Compute 13 + 7 - 3 times 44 minus 9."), (7, "they asked Where is the capital of France today"), (8, "two other words"), (9, "Sum 1 2 3 4 5 6 7 8"), (10, None), (11, "He asks Whose of the brothers buys 40 pears at noon"),
    ]
    found = decontamination.find(spark.createDataFrame(texts, "doc_id long, text string"), bench).collect()
    # Document 11 has one of item 4's two windows, 9 two of item 5's six.
    assert {(r.doc_id, r.item_id) for r in found} == {(i, i) for i in range(1, 6)}


def test_toxicity_learns_words(spark, empty):
    rng = random.Random(2)
    texts, y = [], []
    for i in range(300):
        w = [rng.choice(WORDS) for _ in range(rng.randrange(5, 90))]
        if i % 4 == 0:
            w.insert(rng.randrange(len(w)), rng.choice(["vilewort", "badstuff"]))
        texts.append(" ".join(w))
        y.append(int(i % 4 == 0))
    net = toxicity.fit(texts[:220], y[:220], epochs=4)
    df = spark.createDataFrame([(i, t) for i, t in enumerate(texts[220:] + [None, "", " ", "w " * 50_000])], "doc_id long, text string")
    got = by_id(toxicity.score(df, net))
    assert sum((got[i].score >= 0.5) == bool(y[220 + i]) for i in range(80)) >= 76
    assert got[80].score == got[81].score == got[82].score and got[83].n_windows > 2000
    assert {r.doc_id for r in toxicity.keep_clean(df, net).collect()} == {i for i, r in got.items() if r.score < 0.5}
    assert toxicity.fit(["a", "b"], [0, 0]) is None and toxicity.score(empty, net).count() == 0


def plain_score(net, text):
    """The score of one text by loops over words, apart from the operator's arrays."""
    np, w, h = toxicity.np, net.w, toxicity.HIDDEN
    words = []
    for raw in re.findall(r"[^ \t-\r]+", (text or "").lower()):
        words += toxicity.pieces(raw.strip(toxicity.MARKS))

    def bins(word):
        data = f"<{word}>".encode().ljust(max(toxicity.GRAMS), b"\0")
        for n in toxicity.GRAMS:
            for i in range(len(data) - n + 1):
                x = n
                for c in data[i : i + n]:
                    x = ((x ^ c) * 16777619) % 2**32
                yield (x ^ (x >> 15)) % toxicity.BINS

    def row(word):
        b = list(bins(word))
        odds = [float(net.gram_odds[i]) for i in b]
        return np.concatenate([w["word"][zlib.crc32(word.encode()) % toxicity.BINS], np.mean([w["gram"][i] for i in b], axis=0), [net.word_odds.get(word, 0.0), max(odds), sum(odds) / len(odds)]])

    hard = lambda x: np.clip(0.25 * x + 0.5, 0, 1)

    def direction(k, xs):
        state, out = np.zeros(h), []
        for x in xs:
            own, rec = x @ w[f"in_{k}"] + w[f"in_b_{k}"], state @ w[f"rec_{k}"]
            update, reset = hard(own[:h] + rec[:h]), hard(own[h : 2 * h] + rec[h : 2 * h])
            state = state + (1 - update) * (np.tanh(own[2 * h :] + reset * rec[2 * h :]) - state)
            out.append(state)
        return out

    def logit(some):
        if not some:
            return float(w["out_b"][0])
        xs = [row(x) for x in some]
        states = [np.concatenate(s) for s in zip(direction("f", xs), direction("b", xs[::-1])[::-1], strict=True)]
        e = np.array([np.tanh(s @ w["att"] + w["att_b"]) @ w["att_v"] for s in states])
        a = np.exp(e - e.max())
        return float((a / a.sum()) @ np.array(states) @ w["out"] + w["out_b"][0])

    starts = range(0, max(1, len(words) - toxicity.WINDOW + toxicity.STRIDE), toxicity.STRIDE)
    return 1 / (1 + np.exp(-(max(logit(words[i : i + toxicity.WINDOW]) for i in starts) + net.shift)))


def toxic_corpus(n, seed):
    rng, texts, y = random.Random(seed), [], []
    for i in range(n):
        w = [rng.choice(WORDS) + rng.choice(["", ",", ".", "-x"]) for _ in range(rng.randrange(1, 90))]
        if i % 4 == 0:
            w.insert(rng.randrange(len(w)), rng.choice(["vilewort", "Badstuff!"]))
        texts.append(" ".join(w))
        y.append(int(i % 4 == 0))
    return texts, y


def test_toxicity_scores_by_hand():
    texts, y = toxic_corpus(120, 5)
    net = toxicity.fit(texts, y, epochs=1)
    own = texts[:25] + ["", None, "a", "Ünïcode vilewort " * 30, "x" * 300, "\u00a0 \t\n!!"]
    got, windows = net.score(pa.array(own))
    assert got.tolist() == pytest.approx([plain_score(net, t) for t in own], abs=2e-4)
    assert windows[-3] == 3 and windows[25] == 1


def test_toxicity_gradients():
    np = toxicity.np
    net = toxicity.Network(np.random.default_rng(3))
    net.w = {k: v.astype(np.float64) for k, v in net.w.items()}
    rng = np.random.default_rng(4)
    x = rng.standard_normal((7, 2 * toxicity.WORD_DIM + toxicity.STATS)) * 0.4
    at, on = rng.integers(0, 7, (3, 5)), np.array([[1, 1, 1, 1, 1], [1, 1, 1, 0, 0], [1, 0, 0, 0, 0]], float)
    weight = rng.standard_normal(3)
    loss = lambda rows: float(weight @ net.forward(net.projected(rows), at, on))
    keep = {}
    net.forward(net.projected(x), at, on, keep)
    grad, dx = net.backward(x, at, on, keep, weight)
    assert set(grad) == set(net.w) - {"word", "gram"}
    for target, exact in [(net.w[k], g) for k, g in grad.items()] + [(x, dx)]:
        for i in map(tuple, rng.integers(0, target.shape, (12, target.ndim))):
            was = target[i]
            target[i] = was + 1e-3
            up = loss(x)
            target[i] = was - 1e-3
            down = loss(x)
            target[i] = was
            # States travel in single precision.
            assert exact[i] == pytest.approx((up - down) / 2e-3, abs=1e-2 + 1e-2 * abs(float(exact[i])))


def test_toxicity_reads_whole_words():
    word = "".join(chr(97 + i * i % 23) for i in range(500)) + "ünïcode" * 9
    cut = toxicity.pieces(word)
    assert max(map(len, cut)) <= toxicity.PIECE and all(any(word[i : i + 6] in p for p in cut) for i in range(len(word) - 5))
    assert toxicity.pieces("x" * 30 + "-vile_word\u00a0end\u3000.") == ["x" * 30, "vile", "word", "end"]
    rng = random.Random(4)
    plain = [[rng.choice(WORDS) for _ in range(30)] for _ in range(240)]
    y = [int(i % 4 == 0) for i in range(240)]
    net = toxicity.fit([" ".join(w[:15] + ["vilewort"] * v + w[15:]) for w, v in zip(plain, y, strict=True)], y)
    for glue in ("-", "_", ".", "\u00a0", "\u3000"):
        scores, _ = net.score(pa.array([glue.join(w[:20] + ["vilewort"] * v + w[20:]) for w, v in zip(plain, y, strict=True)]))
        assert sum((s >= 0.5) == bool(v) for s, v in zip(scores, y, strict=True)) >= 228, glue


def test_toxicity_schedule_and_overlap(monkeypatch):
    count, steps = [], []
    back = toxicity.Network.backward
    monkeypatch.setattr(toxicity.Network, "backward", lambda *a: steps.append(1) or back(*a))
    for n in (90, 1500, 1501, 1600):
        steps.clear()
        toxicity.fit([f"alpha beta {'bad' if i % 3 else 'good'}" for i in range(n)], [int(i % 3 > 0) for i in range(n)])
        count.append(len(steps))
    least = toxicity.EPOCHS * toxicity.STEPS
    assert all(least <= c < least + 30 for c in count), count
    # A run of half a window, wherever it is, lies whole in some window.
    _, first, last = toxicity.windows(toxicity.np.array([0, 1000]))
    assert all(any(a <= p and p + toxicity.WINDOW // 2 <= b for a, b in zip(first, last, strict=True)) for p in range(1000 - toxicity.WINDOW // 2 + 1))


CLASHES = "_h h n k1 k2 node first slice anchor place packed covers wanted part gone _bucket _edge _sha _x base found _raw _t _w _text _hash _s _blocks _p _whole size target copies shard slot _f _rank _all _of score n_words c0 _doc _stays a.b".split()


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls in every column, repeated and null numbers, ties, empty and very long texts, with and without clashing columns."""
    rng = random.Random(31)
    long = " ".join(rng.choice(WORDS) + str(rng.randrange(999)) for _ in range(150_000))
    rows = [(rng.choice([i, None, i // 2]), rng.choice([None, "", " ", "mit license a@b.co " * 3, f"text number {i} " * 9]), rng.choice([None, "en"]), rng.choice([None, "a", "b"]), rng.choice([None, 3])) for i in range(30)]
    rows += [(3, "same row", "en", "a", 1)] * 3 + [(None, "no number", None, None, None)] * 2 + [(50, long, "en", "a", len(long))]
    plain = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").repartition(3)
    return plain.select("*", *[F.lit(i).alias(c) for i, c in enumerate(CLASHES)]), plain


RUNS = {
    "licenses": licenses.scan, "fingerprints": fingerprint.compare_with_next, "mixing": mixing.mix, "near_duplicates": neardup.group, "personal_data": pii.scan,
    "repeats": substrings.deduplicate, "sharding": sharding.interleave, "toxicity": lambda d: toxicity.score(d, toxicity.fit(["a bad one", "a good one"] * 9, [1, 0] * 9, epochs=1)),
}


@pytest.mark.parametrize("name", RUNS)
def test_odd_tables(odd, name):
    wide, plain = odd
    got, want = (sorted(map(str, RUNS[name](d).collect())) for d in (wide, plain))
    assert got == want and len(got) == plain.count()


def test_odd_pages(spark):
    big = "<p>" + "word " * 300_000
    rows = [(1, None, big), (1, "u", big), (None, "u", big), (None, None, None), (2, "u", "x"), (2, "u", "x"), (None, "n", "y" * 2000), (7, "v", big)]
    df = spark.createDataFrame([(*r, 1, 2, 3, 4) for r in rows], "page_id long, url string, html string, _bucket int, _digest int, _size int, file int")
    root = common.fresh_path(spark, "odd-pages")
    warc.write(df, root)
    got = sorted((r.page_id or 0, r.payload_bytes, r.record_type, r.refers_to or 0, r.intact) for r in warc.read(spark, root).collect())
    size = len(big)
    assert got == sorted([(1, size, "revisit", 7, True), (1, size, "revisit", 7, True), (0, size, "response", 0, True), (0, 0, "response", 0, True), (2, 1, "response", 0, True), (2, 1, "response", 0, True), (0, 2000, "response", 0, True), (7, size, "response", 0, True)])


def test_pipeline_stages(spark, tmp_path, docs):
    import corpus_pipeline

    spark.createDataFrame([(i, 1, int(i % 7 == 0)) for i in range(60)], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    spark.createDataFrame([(1, "no such passage in any of these documents at all")], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    d = docs.drop("extra")
    for name, stage in corpus_pipeline.STAGES:
        before, d = d, common.durable(stage(spark, d, str(tmp_path)), name)
        if name != "sharding":
            assert d.columns == before.columns
    assert d.count() == before.count() and set(r.shard for r in d.select("shard").collect()) <= set(range(16))


def test_pipeline_against_brute_force(spark, tmp_path):
    """Planted toxic documents, copies and benchmark passages: each stage's decisions on its own input, one row at a time."""
    import corpus_pipeline

    texts, y = toxic_corpus(240, 6)
    item = "Which of the seven old bridges over the wide river was built first by the monks"
    rng = random.Random(7)
    rows = [(i, t) for i, t in enumerate(texts)]
    base = [" ".join(rng.choice(WORDS) + str(rng.randrange(90)) for _ in range(60)) for _ in range(6)]
    for k, b in enumerate(base):
        rows += [(300 + 10 * k, b), (301 + 10 * k, b), (302 + 10 * k, b + " tail"), (303 + 10 * k, base[k][:200] + " " + item + ".")]
    rows += [(None, base[0]), (900, None), (901, ""), (301, base[0])]
    docs = spark.createDataFrame([(i, t, "en", rng.choice(["a", "b", None]), len(t or "")) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    spark.createDataFrame([(i, 1, v) for i, v in enumerate(y)], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    spark.createDataFrame([(1, item)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    show = lambda rows: sorted((str(r.doc_id), r.text or "") for r in rows)
    d, states = docs, {}
    for name, stage in corpus_pipeline.STAGES:
        d = common.durable(stage(spark, d, str(tmp_path)), name)
        states[name] = d.collect()
    before = docs.collect()
    net = toxicity.learn(docs, common.table(spark, str(tmp_path), "labels"))
    clear = [r for r in before if plain_score(net, r.text) < 0.5]
    assert show(states["toxicity"]) == show(clear)
    assert not any("vilewort" in (r.text or "") or "badstuff" in (r.text or "").lower() for r in clear) and len(clear) > 190
    groups = linked([shingles(r.text) for r in clear])
    key = lambda r: (r.doc_id is None, r.doc_id or 0)
    least = {}
    for g, r in zip(groups, clear, strict=True):
        if g not in least or key(r) < key(least[g]):
            least[g] = r
    assert show(states["near_duplicates"]) == show(least.values())
    assert show(states["decontamination"]) == show(r for r in least.values() if item not in (r.text or ""))
    mixed = states["mixing"]
    own = {(r.doc_id, r.text): r for r in states["decontamination"]}
    times = {k: sum((r.doc_id, r.text) == k for r in mixed) for k in own}
    assert all((r.doc_id, r.text) in own for r in mixed) and max(times.values()) <= 2
    words = lambda t: len(re.findall(common.WORD, t or ""))
    goal = mixing.targets([(s, sum(words(t) for (_, t), r in own.items() if r.source == s)) for s in {r.source for r in own.values()}])
    for s, g in goal.items():
        assert abs(sum(words(r.text) for r in mixed if r.source == s) - g) <= 2 * 90
    assert len(states["sharding"]) == len(mixed)
    counts = [sum(r.shard == k for r in states["sharding"]) for k in range(16)]
    assert max(counts) - min(counts) <= 1
    assert sorted((r.shard, r.slot) for r in states["sharding"]) == [(k, i) for k in range(16) for i in range(counts[k])]


def test_stages_with_clashing_columns_and_repeated_rows(spark, tmp_path):
    import corpus_pipeline

    names = ("_copies", "_copy", "_id", "_gone", "_bad", "_l", "_h", "toxic", "node", "root", "a.b")
    rng = random.Random(8)
    texts = [" ".join(rng.choice(WORDS) for _ in range(rng.randrange(1, 80))) for _ in range(40)]
    rows = [(i, t, "en", None, len(t)) for i, t in enumerate(texts)] + [(3, texts[3], "en", "s", 1)] * 3 + [(None, None, None, None, None)] * 2
    rows.append((7, "another text of the same number", "en", "s", 1))
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    docs = docs.select("*", *[F.lit(1).alias(c) for c in names])
    labels = [(i, 1, int(i % 3 == 0)) for i in range(40)]
    for n, (folder, own) in enumerate({"a": labels, "b": labels[::-1]}.items()):
        own = own + [(4, 0, 1), (None, 1, 1), (5, 1, None), (999, 1, 1)] if n else [(4, 0, 1), (None, 1, 1), (5, 1, None), (999, 1, 1)] + own
        spark.createDataFrame(own, "doc_id long, quality int, toxic int").coalesce(1).write.parquet(f"{tmp_path}/{folder}/labels.parquet")
        spark.createDataFrame([(1, "no such passage in any of these documents at all")], "item_id long, text string").write.parquet(f"{tmp_path}/{folder}/benchmark.parquet")
    for name, stage in corpus_pipeline.STAGES:
        got = stage(spark, docs, f"{tmp_path}/a")
        assert name == "sharding" or got.columns == docs.columns, name
        assert got.count() > 0
        none = stage(spark, docs.where("1 = 0"), f"{tmp_path}/a")
        assert none.count() == 0 and none.columns == got.columns
    scores = [toxicity.score(docs, toxicity.learn(docs, common.table(spark, f"{tmp_path}/{f}", "labels"))).orderBy("doc_id", "score").collect() for f in "ab"]
    assert scores[0] == scores[1]
