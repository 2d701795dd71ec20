"""Personal data by anchor expansion.

An Aho-Corasick automaton walks each whole text once and reports anchors: at-signs, plus signs, digits, URL schemes and
identifier cues. A deterministic parser of each kind then expands from the anchor in both directions and validates the
boundaries. The four base kinds give exactly the leftmost non-overlapping matches of their patterns (failing matches are
dropped and not retried); the method adds URLs, account numbers (IBAN by check digits), national identifiers, secrets
behind a cue, and street addresses. An account number by check digits counts on the line of its cue, a house number at the end of the
words behind a street; values are taken whole, however long. What a parser reads ahead is remembered, so that many cues on one
long line don't read it again and again.

Edge cases: a null text is the empty text, without spans; rows of equal doc_id are each scanned on their own; an empty table
gives an empty result; other columns are ignored. Offsets are code points, ends exclusive.
"""

from __future__ import annotations

import hashlib
import re
from bisect import bisect_left
from collections.abc import Iterator
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

BASE = ("email", "ip", "card", "phone")
KINDS = (*BASE, "url", "account", "identifier", "secret", "address")
LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
DOMAIN = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789-")
DIGITS = frozenset("0123456789")
SCHEMES = ("http://", "https://", "ftp://")
CUES = {
    "account": ("iban", "account", "konto", "cuenta", "compte"),
    "identifier": ("ssn", "passport", "tax id", "national id", "social security"),
    "secret": ("password", "passwd", "api_key", "api key", "apikey", "secret", "token", "akia", "ghp_", "sk-"),
    "address": (" street", " avenue", " road", " lane", " boulevard", "straße", "strasse", "rue ", "calle "),
}
IBAN = re.compile(r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?(?![A-Za-z0-9])")
ACCOUNT = re.compile(r"[\s:#=.no]{0,8}([0-9]{6,18})(?![0-9])", re.I)
NATIONAL = re.compile(r"[\s:#=.no]{0,8}([0-9]{3}-[0-9]{2}-[0-9]{4}|[A-Z]{1,2}[0-9]{6,9})(?![A-Za-z0-9])")
SECRET = re.compile(r"[\s:=\"']{1,4}([A-Za-z0-9_\-/+=]{8,})")
KEY = re.compile(r"(?:AKIA[0-9A-Z]{16}|ghp_[A-Za-z0-9]{36}|sk-[A-Za-z0-9_-]{20,})(?![A-Za-z0-9])")
NAMES = re.compile(r"(?:(?:de|del|la|las|le|les|los|du|des|el|et|y|[A-ZÀ-Ý][A-Za-zÀ-ÿ'’]*)(?: (?=[A-Za-zÀ-Ý])|(?![A-Za-zÀ-ÿ])))*")
HOUSE = re.compile(r"([0-9]{1,5}[a-z]?)(?![0-9A-Za-z])")
HOUSE_BEFORE = re.compile(r"(?<![0-9A-Za-z])[0-9]{1,5}[a-z]?\Z")
SCHEMA = "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string, n_spans long"


@lru_cache(1)
def _automaton():
    import ahocorasick

    a = ahocorasick.Automaton()
    for word in ("@", "+", *"0123456789"):
        a.add_word(word, word)
    for kind, words in (("url", SCHEMES), *CUES.items()):
        for word in words:
            for form in {word, word.upper(), word.title(), word.capitalize()}:
                a.add_word(form, (kind, len(form)))
    a.make_automaton()
    return a


def _luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        v = int(c) * (1 + i % 2)
        total += v - 9 * (v > 9)
    return total % 10 == 0


def _email(text: str, at: int, floor: int) -> tuple[int, int] | None:
    start, n = at, len(text)
    while start > floor and text[start - 1] in LOCAL:
        start -= 1
    end = dot = at + 1
    while dot < n and text[dot] in DOMAIN:
        dot += 1
    if start == at or dot == end:
        return None
    labels, end = 0, dot
    while end + 1 < n and text[end] == "." and text[end + 1] in DOMAIN:
        end += 1
        while end < n and text[end] in DOMAIN:
            end += 1
        labels += 1
    return (start, end) if labels else None


def _digit_run(text: str, start: int) -> tuple[int, list[str]]:
    """End of the chain of digit groups joined by single dots from `start`, and the groups."""
    n, end, groups = len(text), start, []
    while True:
        first = end
        while end < n and text[end] in DIGITS:
            end += 1
        groups.append(text[first:end])
        if end + 1 < n and text[end] == "." and text[end + 1] in DIGITS:
            end += 1
        else:
            return end, groups


def _phone(text: str, plus: int) -> tuple[int, int] | None:
    n, end = len(text), plus + 1
    if end >= n or text[end] not in DIGITS:
        return None
    end += 1
    while end < n and (text[end] in DIGITS or text[end] in " ().-"):
        end += 1
    while end > plus + 3 and text[end - 1] not in DIGITS:
        end -= 1
    if end < plus + 4 or text[end - 1] not in DIGITS:
        return None
    return plus, end


def _iban_ok(s: str) -> bool:
    s = s.replace(" ", "")
    return 15 <= len(s) <= 34 and int("".join(str(int(c, 36)) for c in s[4:] + s[:4])) % 97 == 1


def find(text: str) -> list[tuple[int, int, int]]:
    """(start, index in KINDS, end) of every span of `text`, in order."""
    spans: list[tuple[int, int, int]] = []
    free_email = free_ip = free_card = free_phone = -1
    free_email = 0
    ahead = _Ahead(text)
    for last, what in _automaton().iter(text):
        if what == "@":
            if got := _email(text, last, free_email):
                free_email = got[1]
                spans.append((got[0], 0, got[1]))
        elif what == "+":
            if last >= free_phone and (got := _phone(text, last)):
                free_phone = got[1]
                if 10 <= sum(c in DIGITS for c in text[got[0] : got[1]]) <= 15:
                    spans.append((got[0], 3, got[1]))
        elif isinstance(what, str):
            if last >= free_ip:
                free_ip, groups = _digit_run(text, last)
                at = last
                for i in range(0, len(groups) - 3, 4):
                    four = groups[i : i + 4]
                    width = sum(map(len, four)) + 3
                    if all(len(g.lstrip("0")) <= 3 and int(g.lstrip("0") or "0") <= 255 for g in four):
                        spans.append((at, 1, at + width))
                    at += width + 1
            if last >= free_card:
                end, n = last + 1, len(text)
                while True:
                    if end < n and text[end] in DIGITS:
                        end += 1
                    elif end + 1 < n and text[end] in " -" and text[end + 1] in DIGITS:
                        end += 2
                    else:
                        break
                free_card = end
                if 14 <= end - last and 14 <= len(digits := text[last:end].replace(" ", "").replace("-", "")) <= 19 and _luhn(digits):
                    spans.append((last, 2, end))
        else:
            spans += _cued(text, what[0], last + 1 - what[1], last + 1, ahead)
    return sorted(set(spans))


class _Ahead:
    """What lies ahead of the cues of one text, read once."""

    def __init__(self, text: str) -> None:
        self.text, self.run, self.numbers, self.link, self.value = text, (0, 0), None, 0, 0

    def names_end(self, at: int) -> int:
        """Where the names from `at` end."""
        if not self.run[0] <= at < self.run[1]:
            self.run = (at, NAMES.match(self.text, at).end())
        return self.run[1]

    def iban(self, at: int) -> tuple[int, int] | None:
        """The first valid account number from `at` on the same line."""
        if self.numbers is None:
            self.numbers = [m.span() for m in IBAN.finditer(self.text) if _iban_ok(m[0])]
        k = bisect_left(self.numbers, (at, 0))
        if k == len(self.numbers) or self.text.find("\n", at, self.numbers[k][0]) >= 0:
            return None
        return self.numbers[k]


def _house_before(text: str, start: int) -> int | None:
    """Start of the house number of up to three capitalised words that end at the blank at `start`."""
    end = start
    for _ in range(3):
        word = end
        while word > 0 and "A" <= text[word - 1] <= "z" and text[word - 1].isalpha():
            word -= 1
        if word == end or not text[word].isupper() or word == 0 or text[word - 1] != " ":
            return None
        end = word - 1
        if m := HOUSE_BEFORE.search(text, max(0, end - 7), end):
            return m.start()
    return None


def _cued(text: str, kind: str, start: int, end: int, ahead: _Ahead) -> list[tuple[int, int, int]]:
    k = KINDS.index(kind)
    if kind == "url":
        if start < ahead.link:  # within another address
            return []
        stop = end
        while stop < len(text) and not text[stop].isspace() and text[stop] not in "<>\"'`{}|\\^[]":
            stop += 1
        ahead.link = stop
        while stop > end and text[stop - 1] in ".,;:!?)":
            stop -= 1
        return [(start, k, stop)] if stop > end else []
    if kind == "account":
        if found := ahead.iban(end):
            return [(found[0], k, found[1])]
        return [(m.start(1), k, m.end(1)) for m in [ACCOUNT.match(text, end)] if m]
    if kind == "identifier":
        return [(m.start(1), k, m.end(1)) for m in [NATIONAL.match(text, end)] if m]
    if kind == "secret":
        if m := KEY.match(text, start):
            return [(m.start(), k, m.end())]
        if start < ahead.value or not (m := SECRET.match(text, end)):
            return []
        ahead.value = m.end()
        return [(m.start(1), k, m.end(1))] if re.search(r"[0-9]", m[1]) and re.search(r"[A-Za-z]", m[1]) else []
    if text[start] == " " and (number := _house_before(text, start)) is not None:
        return [(number, k, end)]
    stop = end
    if text[end - 1] == " ":  # the street's name follows
        stop = ahead.names_end(end)
        if stop == end or (start and text[start - 1].isalnum()):
            return []
    gap = 2 if text.startswith(", ", stop) else 1 if text.startswith(" ", stop) else 0
    return [(start, k, m.end(1)) for m in [HOUSE.match(text, stop + gap)] if m and gap]


def _scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for whole in batches:
        for at in range(0, whole.num_rows, 1024):
            batch, rows = whole.slice(at, 1024), []
            for doc_id, text in zip(batch.column("doc_id").to_pylist(), batch.column("text").to_pylist(), strict=True):
                spans = find(text or "")
                count = [0] * len(KINDS)
                for _, k, _ in spans:
                    count[k] += 1
                show = lambda some: ",".join(f"{KINDS[k]}:{s}:{e}" for s, k, e in some)
                base = show(x for x in spans if x[1] < len(BASE))
                rows.append((doc_id, *count[:4], hashlib.sha256(base.encode()).hexdigest(), show(spans), len(spans)))
            kinds = [pa.int64()] * 5 + [pa.string()] * 2 + [pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], names=[x.split()[0] for x in SCHEMA.split(", ")])


def scan(docs: DataFrame) -> DataFrame:
    """Spans of personal data of each row of `docs` (doc_id, text); see SCHEMA."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(_scan, SCHEMA)


def mask(text: str) -> str:
    """`text` with every span replaced by its kind in angle brackets; overlapping spans merge into the first one's kind."""
    out, at = [], 0
    for start, k, end in find(text):
        if end <= at:
            continue
        if start >= at:
            out += [text[at:start], f"<{KINDS[k]}>"]
        at = end
    return "".join([*out, text[at:]])


def op5(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(common.table(spark, sf_dir, "documents"))
