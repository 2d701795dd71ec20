"""Toxicity scores from a small bidirectional gated recurrent network, trained and run in numpy.

Input of each word: a learned word vector, the mean of learned vectors of its character n-grams, and label statistics of
the word and of its n-grams (smoothed log odds, fitted across folds so that no document meets its own label). Words of over
`PIECE` characters, as in glued text, are read whole as several words (`pieces`). A
gated recurrent unit reads each window in both directions, attention pools its states, and a logistic unit scores the
window. Windows of `WINDOW` words overlap by half and cover the whole text; a document's score is that of its
highest window, in training (the loss goes to that window) as in scoring.

Training takes `EPOCHS * STEPS` gradient steps of up to `BATCH` documents at every size of the sample, rounded up to whole passes
over it; before each pass every document's highest window is chosen anew. Fitting uses a bounded sample of labelled rows: at most `SAMPLE` documents of at most `LONGEST` characters, those of the
smallest hash of doc_id, none held out (crc32 of doc_id mod 5 = 0). Everything else covers all rows and whole texts.
Only texts are inputs of a score.

Edge cases: null, empty and blank texts have one window without words and get the score of the bias alone; a null
doc_id counts as the empty string for the split; without labels of both classes every score is 0; labels of unknown
documents and null labels are ignored; of a document's differing labels the larger counts, of its differing texts the
first in code-point order; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

SAMPLE, LONGEST, WINDOW, STRIDE, HIDDEN, WORD_DIM, BINS, EPOCHS, SEED = 3000, 20_000, 32, 16, 8, 4, 1 << 15, 6, 7
STATS, GRAMS, PIECE, BATCH, STEPS = 3, (4, 6), 40, 64, 72
MARKS = " \t\n!\"#$%&'()*+,-./:;<=>?@[\\]^_`{|}~«»„“”‘’…–—¿¡|"
SCHEMA = "doc_id long, score double, n_windows long"


def pieces(word: str) -> list[str]:
    """The word; one of over `PIECE` characters is split at marks and blanks of any kind, and what is still longer into overlapping pieces.

    Neighbours share `max(GRAMS)` characters, so every n-gram of the word's parts lies whole in a piece.
    """
    if len(word) <= PIECE:
        return [word] if word else []
    return [p[i : i + PIECE] for p in re.findall(r"[^\W_]+", word) or [word] for i in range(0, max(1, len(p) - max(GRAMS)), PIECE - max(GRAMS))]


def tokens(texts: pa.Array) -> tuple[list[str], np.ndarray, np.ndarray]:
    """Distinct words (lower case, trimmed of marks), the word number of each token, and each text's first token."""
    lists = pc.ascii_split_whitespace(pc.utf8_lower(common.whole(texts)))
    flat = lists.flatten().dictionary_encode()
    codes, raw = flat.indices.to_numpy(zero_copy_only=False), flat.dictionary.to_numpy(zero_copy_only=False).tolist()
    number: dict[str, int] = {"": 0}
    cut = [[number.setdefault(x, len(number)) for x in pieces(w.strip(MARKS))] for w in raw]
    count = np.fromiter(map(len, cut), np.int64, len(cut))
    of = np.fromiter((x for xs in cut for x in xs), np.int32, count.sum())
    begin = np.cumsum(count) - count
    width = count[codes] if len(codes) else np.zeros(0, np.int64)
    at = np.concatenate([[0], np.cumsum(width)])
    word = of[np.repeat(begin[codes] - at[:-1], width) + np.arange(at[-1])] if at[-1] else np.zeros(0, np.int32)
    starts = np.concatenate([[0], np.cumsum(pc.list_value_length(lists).to_numpy(zero_copy_only=False))]).astype(np.int64)
    return list(number), word, at[starts]


def windows(starts: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(document, first token, last token + 1) of every window."""
    n = np.diff(starts)
    count = np.maximum(1, -(-(n - WINDOW) // STRIDE) + 1)
    doc = np.repeat(np.arange(len(n)), count)
    within = np.arange(len(doc)) - np.repeat(np.cumsum(count) - count, count)
    first = starts[:-1][doc] + within * STRIDE
    return doc, first, np.minimum(first + WINDOW, starts[1:][doc])


def grams(words: list[str]) -> list[tuple[np.ndarray, np.ndarray]]:
    """For each size in GRAMS: bins of the n-grams (bytes, words marked at both ends) and where each word's begin."""
    marked = [f"<{w}>".encode().ljust(max(GRAMS), b"\0") for w in words]
    buf = np.frombuffer(b"".join(marked) + b"\0" * max(GRAMS), np.uint8).astype(np.uint32)
    length = np.fromiter(map(len, marked), np.int64, len(marked))
    begin = np.concatenate([[0], np.cumsum(length)])
    out = []
    for n in GRAMS:
        h = np.full(int(begin[-1]), n, np.uint32)
        for i in range(n):
            h = (h ^ buf[i : i + len(h)]) * np.uint32(16777619)
        h ^= h >> np.uint32(15)
        count = length - n + 1
        spans = np.concatenate([[0], np.cumsum(count)])
        at = np.arange(spans[-1]) + np.repeat(begin[:-1] - spans[:-1], count)
        out.append(((h[at] % np.uint32(BINS)).astype(np.int32), spans))
    return out


def _of(lists: list[tuple[np.ndarray, np.ndarray]], used: np.ndarray) -> list[tuple[np.ndarray, np.ndarray]]:
    """The n-grams of the words `used` only."""
    out = []
    for bins, spans in lists:
        width = np.diff(spans)[used]
        new = np.concatenate([[0], np.cumsum(width)])
        out.append((bins[np.repeat(spans[used] - new[:-1], width) + np.arange(new[-1])], new))
    return out


def word_bins(words: list[str]) -> np.ndarray:
    return np.array([zlib.crc32(w.encode()) for w in words], np.int64) % BINS


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 0.5 * np.tanh(0.5 * x) + 0.5


class Network:
    """Weights by name in `w`; `words` and `stats` hold the label statistics."""

    def __init__(self, rng: np.random.Generator) -> None:
        d, h = 2 * WORD_DIM + STATS, HIDDEN
        g = lambda *s: (rng.standard_normal(s) * 0.3).astype(np.float32)
        self.w = {"word": g(BINS, WORD_DIM) * 0.1, "gram": g(BINS, WORD_DIM) * 0.1, "att": g(2 * h, h), "att_b": np.zeros(h, np.float32), "att_v": g(h), "out": g(2 * h), "out_b": np.full(1, -1.0, np.float32)}
        for k in "fb":
            self.w |= {f"in_{k}": g(d, 3 * h), f"in_b_{k}": np.zeros(3 * h, np.float32), f"rec_{k}": g(h, 3 * h)}
        self.word_odds: dict[str, float] = {}
        self.gram_odds = np.zeros(BINS, np.float32)
        self.shift = 0.0

    # -- inputs

    def inputs(self, lists: list[tuple[np.ndarray, np.ndarray]], ids: np.ndarray, odds: np.ndarray, gram_odds: np.ndarray) -> np.ndarray:
        """One row a distinct word; `lists` has its n-grams, `ids` its word bin, `odds` its log odds."""
        most = 20_000  # words at a time, for memory
        if len(ids) > most:
            cut = [np.arange(i, min(i + most, len(ids))) for i in range(0, len(ids), most)]
            return np.concatenate([self.inputs([(b[s[c[0]] : s[c[-1] + 1]], s[c[0] : c[-1] + 2] - s[c[0]]) for b, s in lists], ids[c], odds[c], gram_odds) for c in cut])
        x = np.empty((len(ids), 2 * WORD_DIM + STATS), np.float32)
        width = sum(np.diff(spans) for _, spans in lists).astype(np.float32)
        x[:, :WORD_DIM] = self.w["word"][ids]
        x[:, WORD_DIM : 2 * WORD_DIM] = sum(np.add.reduceat(self.w["gram"][bins], spans[:-1]) for bins, spans in lists) / width[:, None]
        x[:, 2 * WORD_DIM] = odds
        z = [(gram_odds[bins], spans[:-1]) for bins, spans in lists]
        x[:, 2 * WORD_DIM + 1] = np.max([np.maximum.reduceat(v, at) for v, at in z], axis=0)
        x[:, 2 * WORD_DIM + 2] = sum(np.add.reduceat(v, at) for v, at in z) / width
        return x

    # -- one direction over (windows, WINDOW) word rows

    def _run(self, k: str, proj: np.ndarray, at: np.ndarray, on: np.ndarray, keep: list | None) -> np.ndarray:
        h, rec = HIDDEN, self.w[f"rec_{k}"]
        state = np.zeros((len(at), h), np.float32)
        out = np.zeros((at.shape[1], len(at), h), np.float32)
        steps = range(at.shape[1]) if k == "f" else range(at.shape[1] - 1, -1, -1)
        for t in steps:
            x, m = proj[at[:, t]], on[:, t, None]
            r = state @ rec
            gates = np.clip(0.25 * (x[:, : 2 * h] + r[:, : 2 * h]) + 0.5, 0, 1)  # a piecewise linear sigmoid
            z, g = gates[:, :h], gates[:, h:]
            new = np.tanh(x[:, 2 * h :] + g * r[:, 2 * h :])
            nxt = state + m * (1 - z) * (new - state)
            if keep is not None:
                keep.append((t, state, z, g, new, r[:, 2 * h :], m))
            state = nxt
            out[t] = state
        return out

    def projected(self, x: np.ndarray) -> dict[str, np.ndarray]:
        """What each word adds to the gates of either direction."""
        return {k: x @ self.w[f"in_{k}"] + self.w[f"in_b_{k}"] for k in "fb"}

    def forward(self, proj: dict[str, np.ndarray], at: np.ndarray, on: np.ndarray, keep: dict | None = None) -> np.ndarray:
        """Logits of windows; `at` has words (rows of `proj`), `on` is 1 where there is a word and else 0."""
        states = [self._run(k, proj[k], at, on, keep.setdefault(k, []) if keep is not None else None) for k in "fb"]
        hs = np.concatenate(states, axis=2)  # (time, window, 2 hidden)
        u = np.tanh(hs @ self.w["att"] + self.w["att_b"])
        e = u @ self.w["att_v"] + (on.T - 1) * 1e4
        e -= e.max(axis=0)
        a = np.exp(e)
        a /= a.sum(axis=0)
        a *= on.T.max(axis=0)
        pooled = (a[:, :, None] * hs).sum(axis=0)
        if keep is not None:
            keep |= {"hs": hs, "u": u, "a": a, "pooled": pooled}
        return pooled @ self.w["out"] + self.w["out_b"][0]

    def backward(self, x: np.ndarray, at: np.ndarray, on: np.ndarray, keep: dict, dlogit: np.ndarray) -> tuple[dict, np.ndarray]:
        """Gradients of the weights, and of the rows of `x`."""
        h, g = HIDDEN, {}
        g["out"], g["out_b"] = keep["pooled"].T @ dlogit, dlogit.sum(keepdims=True)
        dp = dlogit[:, None] * self.w["out"]
        hs, a, u = keep["hs"], keep["a"], keep["u"]
        da = (dp[None] * hs).sum(axis=2)
        de = a * (da - (a * da).sum(axis=0))
        g["att_v"] = np.tensordot(de, u, ([0, 1], [0, 1]))
        du = de[:, :, None] * self.w["att_v"] * (1 - u * u)
        g["att"], g["att_b"] = np.tensordot(hs, du, ([0, 1], [0, 1])), du.sum(axis=(0, 1))
        dhs = a[:, :, None] * dp[None] + du @ self.w["att"].T
        dx = np.zeros_like(x)
        for i, k in enumerate("fb"):
            rec, dproj = self.w[f"rec_{k}"], np.zeros((len(x), 3 * h), np.float32)
            drec, dstate, each, rows = np.zeros_like(rec), np.zeros((len(at), h), np.float32), [], []
            for t, state, z, r, new, rn, m in reversed(keep[k]):
                dn = dstate + dhs[t, :, i * h : (i + 1) * h]
                dnew = dn * m * (1 - z) * (1 - new * new)
                dz = dn * m * (state - new) * (0.25 * ((z > 0) & (z < 1)))
                dr = dnew * rn * (0.25 * ((r > 0) & (r < 1)))
                dgate = np.concatenate([dz, dr, dnew * r], axis=1)
                drec += state.T @ dgate
                dstate = dn * (1 - m * (1 - z)) + dgate @ rec.T
                each.append(np.concatenate([dz, dr, dnew], axis=1))
                rows.append(at[:, t])
            np.add.at(dproj, np.concatenate(rows), np.concatenate(each))
            g[f"rec_{k}"], g[f"in_{k}"], g[f"in_b_{k}"] = drec, x.T @ dproj, dproj.sum(axis=0)
            dx += dproj @ self.w[f"in_{k}"].T
        return g, dx

    # -- scoring

    def score(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """(score, number of windows) of each text."""
        words, word, starts = tokens(texts)
        x = self.inputs(grams(words), word_bins(words), np.array([self.word_odds.get(w, 0.0) for w in words], np.float32), self.gram_odds)
        doc, first, last = windows(starts)
        best, proj = np.full(len(texts), -np.inf, np.float32), self.projected(x)
        for i in range(0, len(doc), 1024):
            at, on = _laid(word, first[i : i + 1024], last[i : i + 1024])
            np.maximum.at(best, doc[i : i + 1024], self.forward(proj, at, on))
        return 1 / (1 + np.exp(-(best.astype(np.float64) + self.shift))), np.bincount(doc, minlength=len(texts))


def _laid(word: np.ndarray, first: np.ndarray, last: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    pos = first[:, None] + np.arange(WINDOW)
    on = pos < last[:, None]
    at = np.where(on, word[np.minimum(pos, max(0, len(word) - 1))] if len(word) else 0, 0)
    return at, on.astype(np.float32)


def _odds(pos: np.ndarray, neg: np.ndarray, n_pos: int, n_neg: int) -> np.ndarray:
    """Smoothed log odds ratio, drawn to 0 where a word is rare."""
    ratio = np.log((pos + 0.5) / (n_pos + 1)) - np.log((neg + 0.5) / (n_neg + 1))
    seen = pos + neg
    return (np.clip(ratio, -4, 4) * seen / (seen + 3) / 2).astype(np.float32)


def passes(folds: np.ndarray, epochs: int = EPOCHS) -> int:
    """Passes over folds of these sizes until `epochs * STEPS` gradient steps are made."""
    return -(-epochs * STEPS // int(np.sum(-(-folds // BATCH))))


def fit(texts: list[str], y: np.ndarray, epochs: int = EPOCHS) -> Network | None:
    """Train on whole texts and labels 0 / 1, in `passes` of the sample; None without both classes."""
    y = np.asarray(y, np.int64)
    if not 0 < y.sum() < len(y):
        return None
    rng = np.random.default_rng(SEED)
    net = Network(rng)
    words, word, starts = tokens(pa.array(texts))
    lists, ids = grams(words), word_bins(words)
    fold = rng.permutation(len(y)) % 3
    # Documents of each fold and class that hold a word, or an n-gram bin; a few hundred documents at a time.
    has_word, has_gram = np.zeros((3, 2, len(words)), np.int32), np.zeros((3, 2, BINS), np.int32)
    for i in range(0, len(y), 256):
        group = np.arange(i, min(i + 256, len(y)))
        doc_of = np.repeat(group, np.diff(starts)[group])
        pair = np.unique(doc_of * len(words) + word[starts[group[0]] : starts[group[-1] + 1]])
        p_doc, p_word = pair // len(words), pair % len(words)
        np.add.at(has_word, (fold[p_doc], y[p_doc], p_word), 1)
        found = []
        for bins, spans in lists:
            width = np.diff(spans)[p_word]
            inner = np.arange(width.sum()) - np.repeat(np.cumsum(width) - width, width)
            found.append(np.unique(np.repeat(p_doc, width) * BINS + bins[np.repeat(spans[p_word], width) + inner]))
        both = np.unique(np.concatenate(found))
        np.add.at(has_gram, (fold[both // BINS], y[both // BINS], both % BINS), 1)

    def stats(folds: list[int]) -> tuple[np.ndarray, np.ndarray]:
        inside = np.isin(fold, folds)
        n = int(y[inside].sum()), int((1 - y[inside]).sum())
        return tuple(_odds(h[folds, 1].sum(axis=0), h[folds, 0].sum(axis=0), *n) for h in (has_word, has_gram))

    crossed = [stats([g for g in range(3) if g != f]) for f in range(3)]
    odds, net.gram_odds = stats([0, 1, 2])
    net.word_odds = {w: float(v) for w, v in zip(words, odds, strict=True) if abs(v) > 0.05}
    doc, first, last = windows(starts)
    lead = np.concatenate([[0], np.cumsum(np.bincount(doc, minlength=len(y)))])
    mean = {k: [np.zeros_like(v), np.zeros_like(v)] for k, v in net.w.items()}
    step, best_at = 0, lead[:-1].copy()
    weight = np.where(y == 1, min(4.0, (1 - y).sum() / y.sum()), 1.0).astype(np.float32)
    logits = np.zeros(len(doc), np.float32)
    epochs = passes(np.bincount(fold), epochs)
    for epoch in range(epochs + 1):
        for f in range(3):  # the highest window of each document, under statistics that don't know its label
            x = net.inputs(lists, ids, *crossed[f])
            own = np.flatnonzero(fold[doc] == f)
            if epoch == 0:  # no weights yet: the window with the largest statistics
                strength = np.maximum(x[:, 2 * WORD_DIM], 0) + np.maximum(x[:, 2 * WORD_DIM + 1], 0)
                total = np.concatenate([[0], np.cumsum(strength[word])])
                logits[own] = total[last[own]] - total[first[own]]
            else:
                proj = net.projected(x)
                for i in range(0, len(own), 1024):
                    o = own[i : i + 1024]
                    logits[o] = net.forward(proj, *_laid(word, first[o], last[o]))
        order = np.lexsort((-logits, doc))
        best_at = order[lead[:-1]]
        if epoch == epochs:
            break
        rate = 0.02 * (1 - epoch / epochs) + 0.002
        for f in rng.permutation(3):
            docs = rng.permutation(np.flatnonzero(fold == f))
            for i in range(0, len(docs), BATCH):
                some = docs[i : i + BATCH]
                at, on = _laid(word, first[best_at[some]], last[best_at[some]])
                used, local = np.unique(at, return_inverse=True)
                local = local.reshape(at.shape)
                own_lists = _of(lists, used)
                x = net.inputs(own_lists, ids[used], crossed[f][0][used], crossed[f][1])
                keep: dict = {}
                p = _sigmoid(net.forward(net.projected(x), local, on, keep))
                g, dx = net.backward(x, local, on, keep, ((p - y[some]) * weight[some] / len(some)).astype(np.float32))
                g = {k: v + 1e-4 * net.w[k] for k, v in g.items()}
                step += 1
                for k, v in g.items():
                    m, s = mean[k]
                    m += 0.1 * (v - m)
                    s += 0.01 * (v * v - s)
                    net.w[k] -= rate * (m / (1 - 0.9**step)) / (np.sqrt(s / (1 - 0.99**step)) + 1e-6)
                # the tables get plain steps, only in the rows that were used
                np.add.at(net.w["word"], ids[used], -5 * rate * dx[:, :WORD_DIM])
                share = dx[:, WORD_DIM : 2 * WORD_DIM] / sum(np.diff(v) for _, v in own_lists)[:, None]
                for b2, s2 in own_lists:
                    np.add.at(net.w["gram"], b2, -5 * rate * share[np.repeat(np.arange(len(used)), np.diff(s2))])
    top = logits[best_at].astype(np.float64)
    cut = np.sort(top)
    mids = np.concatenate([(cut[1:] + cut[:-1]) / 2, [0.0]])[:: max(1, len(cut) // 400)]
    f1 = [2 * (y[top >= c]).sum() / max(1, (top >= c).sum() + y.sum()) for c in mids]
    best = max(f1)
    good = [c for c, v in zip(mids, f1, strict=True) if v >= best - 1e-9]
    net.shift = -float(np.median(good))
    return net


def learn(docs: DataFrame, labels: DataFrame) -> Network | None:
    """Fit on the bounded sample of labelled rows (see the module's text)."""
    key = F.coalesce(F.col("doc_id").cast("string"), F.lit(""))
    own = labels.where((F.crc32(key) % 5 != 0) & F.col("toxic").isin(0, 1)).groupBy(F.col("doc_id").alias("_l"), F.xxhash64(key).alias("_h")).agg(F.max("toxic").alias("toxic"))
    own = own.orderBy("_h", "_l").limit(SAMPLE)
    got = docs.where(F.length("text") <= LONGEST).select("doc_id", "text").join(F.broadcast(own), F.col("doc_id") == F.col("_l")).select("_h", "doc_id", "text", "toxic").toArrow().to_pandas()
    got = got.sort_values(["_h", "doc_id", "text"], kind="stable").drop_duplicates("doc_id")
    return fit(got["text"].tolist(), got["toxic"].to_numpy())


def _slices(batch: pa.RecordBatch, text: str | int) -> Iterator[pa.RecordBatch]:
    """The rows of `batch`, about 4 MB of text at a time."""
    sizes = np.concatenate([[0], np.cumsum(pc.fill_null(pc.binary_length(batch.column(text)), 0).to_numpy(zero_copy_only=False), dtype=np.int64)])
    at = 0
    while at < batch.num_rows:
        end = max(at + 1, int(np.searchsorted(sizes, sizes[at] + 4_000_000, "right")) - 1)
        yield batch.slice(at, end - at)
        at = end


def score(docs: DataFrame, net: Network | None) -> DataFrame:
    """Score and number of windows of each row of `docs` (doc_id, text)."""
    spark = docs.sparkSession
    d = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    if net is None:
        return d.select("doc_id", F.lit(0.0).alias("score"), F.lit(0).cast("long").alias("n_windows"))
    shared = spark.sparkContext.broadcast(net)  # two tables of BINS rows and the word statistics of a bounded sample

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for part in _slices(whole, "text"):
                s, n = shared.value.score(part.column("text"))
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(s, pa.float64()), pa.array(n, pa.int64())], names=["doc_id", "score", "n_windows"])

    return d.mapInArrow(run, SCHEMA)


def op10(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents")
    got = score(docs, learn(docs, common.table(spark, sf_dir, "labels")))
    held = F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit(""))) % 5 == 0
    return got.select("doc_id", held.alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"), "n_windows")


def keep_clean(docs: DataFrame, net: Network | None) -> DataFrame:
    """The rows of `docs` that score under 0.5, with all columns; texts travel to the scorer and back in one pass."""
    if net is None:
        return docs
    shared = docs.sparkSession.sparkContext.broadcast(net)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for part in _slices(whole, text):
                s, _ = shared.value.score(part.column(text))
                yield part.filter(pa.array(s < 0.5))

    # By position: Spark's Arrow mapping does not take every column name.
    text, plain = docs.columns.index("text"), docs.toDF(*[f"c{i}" for i in range(len(docs.columns))])
    return plain.mapInArrow(run, plain.schema).toDF(*docs.columns)
