"""Toxicity by a support vector machine over a subsequence string kernel with Nyström landmarks.

The kernel of two words counts their common subsequences of P characters; each costs DECAY to the power of the lengths that
it spans in both words, so that gaps and inserted characters lower the value but do not end it. A word's share of a landmark is its kernel with it over the
landmark's own, at most 1: how much of the landmark the word holds. Runs of single characters ("i d i o t", "i+d+i+o+t") with any separators count as one word too.
A text has two values for each landmark: the largest share over its words, and the mean share over all its words.
Landmarks are words and parts of words of the labelled training texts that are most telling of the label, chosen one after another so that none holds most of
an earlier one, then words of middling frequency. The landmarks' own kernel matrix maps the values to the features of
a linear machine, trained by squared hinge loss and calibrated by a logistic fit.

Training takes at most MAX_LABELLED labelled texts, of least hash; all texts are scored, and as a whole.

Null and empty texts have no word: all kernels are 0, and they are scored like any other. Null labels are not used. Without labels of both kinds
the score is the share of toxic labels (0 if none). Repeated rows are scored each on its own.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import pick, table

MAX_LABELLED = 5000
LANDMARKS = 48
P, DECAY = 3, 0.7
#: Characters of a word that the kernel sees; longer words are seen in overlapping parts.
SEEN = 24
#: Shares under this are noise of unrelated words and count as 0; a landmark with a character between all its letters has more.
LEAST = 0.3
ALERT = 0.7
CACHED_WORDS = 300_000
#: Words added to a text's length in the mean, so that one word of a short text does not count as a habit.
CALM = 100
PART_SIZES = (4, 5, 6, 7)
_SPACED = re.compile(r"(?<!\w)(?:[^\W\d_][\W_]+){3,23}[^\W\d_](?!\w)")
_CORE = re.compile(r"^\W+|\W+$")


def codes(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """A row of SEEN character codes for each word (0: none), and lengths."""
    out = np.zeros((len(words), SEEN), np.int32)
    raw = np.asarray([w[:SEEN] for w in words], f"U{SEEN}")
    if len(words):
        out[:] = raw.view(np.uint32).reshape(len(words), SEEN).astype(np.int32)
    return out, (out > 0).sum(axis=1)


def raw_kernel(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Gap-weighted common subsequences of P characters of each word in a with the one word b (codes without zeros).

    A column for each character of b, all words of a at once: m holds the weight of the subsequences of the current
    length that end before a position, aged by DECAY for each step in either word.
    """
    n, la, lb = len(a), a.shape[1], len(b)
    same = (a.T[:, None, :] == b[None, :, None]).astype(np.float32)  # la x lb x n
    ends = same * np.float32(DECAY * DECAY)
    for _ in range(P - 1):
        # aged[i, j]: weight of all that ends at (i', j') <= (i, j), times DECAY for each step since
        aged = ends.copy()
        for i in range(1, la):
            aged[i] += DECAY * aged[i - 1]
        for j in range(1, lb):
            aged[:, j] += DECAY * aged[:, j - 1]
        ends = np.zeros_like(ends)
        ends[1:, 1:] = same[1:, 1:] * aged[:-1, :-1] * np.float32(DECAY * DECAY)
    return ends.sum(axis=(0, 1)) if n else np.zeros(0, np.float32)


class Kernel:
    """Shares of fixed landmarks in words."""

    def __init__(self, landmarks: list[str]):
        self.landmarks = landmarks
        c, n = codes(landmarks)
        self.codes = [c[k, : n[k]] for k in range(len(landmarks))]
        self.own = np.asarray([float(raw_kernel(x[None, :], x)[0]) for x in self.codes])
        self.letters = [set(x) for x in landmarks]

    def __call__(self, words: list[str]) -> np.ndarray:
        """words x landmarks; values under LEAST are 0.

        Only words that share two thirds of a landmark's pairs of near characters can come near it: others are not computed.
        """
        out = np.zeros((len(words), len(self.landmarks)), np.float32)
        if not words:
            return out
        c, n = codes(words)
        near = _near_pairs(c)
        for k, b in enumerate(self.codes):
            want = _near_pairs(b[None, :])[0]
            bits = np.bitwise_count(near & want[None, :]).sum(axis=1)
            could = np.flatnonzero(bits >= max(1, math.ceil(0.34 * np.bitwise_count(want).sum())))
            for lo in range(0, len(could), 2048):
                at = could[lo : lo + 2048]
                width = max(1, int(n[at].max()))
                w = c[at, :width]
                v = np.minimum(raw_kernel(w, b) / max(self.own[k], 1e-12), 1)
                out[at, k] = np.where(v >= LEAST, v, 0)
        return out

    def gram(self) -> np.ndarray:
        """The landmarks' shares in each other, as texts have them: the mean of both directions, 1 for equal ones."""
        share = self(self.landmarks).astype(np.float64)
        return (share + share.T) / 2


def _near_pairs(c: np.ndarray) -> np.ndarray:
    """256 bits for each word: hashed pairs of characters at most two apart."""
    bits = np.zeros((len(c), 4), np.uint64)
    rows = np.arange(len(c))
    for gap in (1, 2):
        for i in range(c.shape[1] - gap):
            x, y = c[:, i].astype(np.uint32), c[:, i + gap].astype(np.uint32)
            h = ((x * np.uint32(0x9E3779B1)) ^ (y * np.uint32(0x85EBCA77))) >> np.uint32(24)
            bits[rows, h >> np.uint32(6)] |= np.where((x > 0) & (y > 0), np.uint64(1) << (h & np.uint32(63)).astype(np.uint64), np.uint64(0))
    return bits


def words_of(text: str) -> Counter:
    """How often a text has each lower-case word without punctuation at its ends, joined run of single characters, and part of a long word."""
    low = text.lower()
    out: Counter = Counter()
    for w, n in Counter(low.split()).items():
        if not w.isalnum():
            w = _CORE.sub("", w)
        if len(w) <= SEEN:
            out[w] += n
        else:
            for i in range(0, len(w) - SEEN // 2, SEEN // 2):
                out[w[i : i + SEEN]] += n
    for run in _SPACED.findall(low):
        out[re.sub(r"[\W_]", "", run)] += 1
    return out


class ToxicModel:
    def __init__(self, kernel: Kernel | None, weights: np.ndarray, bias: float, base: float):
        self.kernel, self.weights, self.bias, self.base = kernel, weights, bias, base
        self.cache: dict[str, int] = {}
        self.rows = np.zeros((0, 0), np.float32)

    def __getstate__(self):
        return (self.kernel, self.weights, self.bias, self.base)

    def __setstate__(self, s):
        self.__init__(*s)

    def values(self, bags: list[Counter]) -> np.ndarray:
        """bags x (2 * landmarks): largest and mean shares. Words seen before are remembered, within a bound."""
        cache, many = self.cache, len(self.kernel.landmarks)
        new = set().union(*bags).difference(cache) if bags else set()
        if new:
            if len(cache) + len(new) > CACHED_WORDS:
                cache.clear()
                self.rows = np.zeros((0, 0), np.float32)
                new = set().union(*bags)
            order = sorted(new)
            got = self.kernel(order)
            hit = got.any(axis=1)
            if not self.rows.size:
                self.rows = np.zeros((1, many), np.float32)  # row 0: no share of any
            at = np.where(hit, len(self.rows) + np.cumsum(hit) - 1, 0)
            self.rows = np.vstack([self.rows, got[hit]])
            cache.update(zip(order, at.tolist(), strict=True))
        out = np.zeros((len(bags), 2 * many))
        for i, bag in enumerate(bags):
            rows = [(r, n) for r, n in ((cache[w], n) for w, n in bag.items()) if r]
            if rows:
                r, n = np.asarray(rows).T
                share = self.rows[r]
                out[i, :many] = share.max(axis=0)
                out[i, many:] = np.sqrt(n @ share / (bag.total() + CALM)) * 4
        return out

    def scores(self, texts: list[str]) -> np.ndarray:
        if self.kernel is None:
            return np.full(len(texts), self.base)
        z = self.values([words_of(t) for t in texts]) @ self.weights + self.bias
        return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def choose_landmarks(bags: list[Counter], toxic: np.ndarray, many: int = LANDMARKS) -> list[str]:
    """Words and parts of words, by how far their rate in toxic texts is from that in the others, skipping those that hold most of an earlier one or are mostly held by one.

    A text counts a part three times at most. The last eighth are words of middling frequency.
    """
    seen = [Counter(), Counter()]
    for bag, y in zip(bags, toxic, strict=True):
        own: Counter = Counter()
        for w, n in bag.items():
            n = min(n, 3)
            parts = {w} if P < len(w) <= 12 else set()
            parts.update(w[i : i + k] for k in PART_SIZES for i in range(len(w) - k + 1))
            for x in parts:
                own[x] += n
        for x, n in own.items():
            seen[y][x] += min(n, 3)
    n = [max(1, int((toxic == y).sum())) for y in (0, 1)]
    worth = {}
    for w, c in seen[1].items():
        d = seen[0][w]
        if c >= 4 and c / n[1] > 2 * d / n[0]:
            mean = (c + d) / (n[0] + n[1])
            worth[w] = c * math.log(c / (mean * n[1])) + (d * math.log(d / (mean * n[0])) if d else 0)
    ranked = sorted(worth, key=lambda w: (-round(worth[w], 6), -len(w), w))[:1500]
    out: list[str] = []
    for w in ranked:
        if len(out) >= many * 7 // 8 or worth[w] < 8:
            break
        if not out or (Kernel(out)([w]).max() < 0.7 and Kernel([w])(out).max() < 0.7):
            out.append(w)
    common = sorted((w for w in seen[0] if len(w) > P), key=lambda w: (-seen[0][w], w))[20:2000:60]
    return out + [w for w in common if w not in out][: many - len(out)]


def fit(bags: list[Counter], toxic: np.ndarray, many: int = LANDMARKS) -> ToxicModel:
    if len(set(toxic.tolist())) < 2:
        return ToxicModel(None, np.zeros(0), 0.0, float(toxic.mean()) if len(toxic) else 0.0)
    landmarks = choose_landmarks(bags, toxic, many)
    if not landmarks:
        return ToxicModel(None, np.zeros(0), 0.0, float(toxic.mean()))
    kernel = Kernel(landmarks)
    x = ToxicModel(kernel, np.zeros(0), 0.0, 0.0).values(bags)
    gram = kernel.gram()
    val, vec = np.linalg.eigh((gram + gram.T) / 2 + 5e-2 * np.eye(len(gram)))
    half = vec / np.sqrt(np.maximum(val, 5e-2))  # Nyström: features whose products give back the kernel
    mapping = np.kron(np.eye(2), half)
    f = x @ mapping
    y = np.where(toxic == 1, 1.0, -1.0)
    cost = np.where(y > 0, len(y) / 2 / (y > 0).sum(), len(y) / 2 / (y < 0).sum())
    w, b = np.zeros(f.shape[1]), 0.0
    for _ in range(60):  # Newton steps on the squared hinge loss
        inside = y * (f @ w + b) < 1
        if not inside.any():
            break
        a = np.hstack([f[inside], np.ones((inside.sum(), 1))])
        c = cost[inside][:, None]
        h = a.T @ (c * a) + np.diag([1.0] * len(w) + [1e-6])
        new = np.linalg.solve(h, a.T @ (c[:, 0] * y[inside]))
        step = np.abs(new - np.append(w, b)).max()
        w, b = new[:-1], float(new[-1])
        if step < 1e-8:
            break
    z = f @ w + b
    s, o = 1.0, 0.0
    for _ in range(50):  # logistic calibration
        p = 1 / (1 + np.exp(-np.clip(s * z + o, -30, 30)))
        g = np.asarray([((p - (y > 0)) * z).sum() + 1e-3 * s, (p - (y > 0)).sum()])
        r = p * (1 - p) + 1e-9
        h = np.asarray([[(r * z * z).sum() + 1e-3, (r * z).sum()], [(r * z).sum(), r.sum() + 1e-6]])
        d = np.linalg.solve(h, g)
        s, o = s - d[0], o - d[1]
        if np.abs(d).max() < 1e-9:
            break
    return ToxicModel(kernel, s * (mapping @ w), float(s * b + o), 0.0)


#: The third of the documents whose labels are never learnt from.
HELD_OUT = "pmod(crc32(cast(doc_id AS string)), 3) = 1"


def train(docs: DataFrame, labels: DataFrame, max_labelled: int = MAX_LABELLED) -> ToxicModel:
    """labels: doc_id, toxic. At most max_labelled sentences' texts come to the driver, each cut into words there by the same rule as when scored."""
    sample = pick(labels, "doc_id", "toxic").where(f"doc_id is not null and toxic is not null and not ({HELD_OUT})")
    toxic = F.col("toxic").cast("int")
    half = max_labelled // 2
    order = (F.xxhash64("doc_id"), F.col("doc_id"))
    some = sample.where(toxic == 1).orderBy(*order).limit(half).unionByName(sample.where(toxic == 0).orderBy(*order).limit(half))
    rows = pick(docs, "doc_id", "text").join(F.broadcast(some), "doc_id")  # max_labelled rows

    def run(batches):
        for b in batches:
            for k, y, t in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True):
                bag = words_of(t or "")
                order = sorted(bag)
                yield pa.RecordBatch.from_arrays([pa.array([k], pa.int64()), pa.array([y], pa.int64()), pa.array([order], pa.list_(pa.string())), pa.array([[bag[w] for w in order]], pa.list_(pa.int64()))], names=["k", "y", "words", "n"])

    bags = rows.select(F.xxhash64("doc_id").alias("k"), F.expr("cast(toxic as long) y"), F.expr("cast(text as string) t")).mapInArrow(run, "k long, y long, words array<string>, n array<long>")
    got = bags.orderBy("k", "y", "words", "n").limit(max_labelled).toArrow()  # a labelled row may be repeated
    rows = sorted(zip(got["y"].to_pylist(), got["words"].to_pylist(), got["n"].to_pylist(), strict=True))
    return fit([Counter(dict(zip(w, n, strict=True))) for _, w, n in rows], np.asarray([y for y, _, _ in rows], np.int64))


def score(docs: DataFrame, model: ToxicModel, alert: float = ALERT) -> DataFrame:
    shared = docs.sparkSession.sparkContext.broadcast(model)  # LANDMARKS words and weights

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for b in batches:
            for lo in range(0, b.num_rows, 256):
                part = b.slice(lo, 256)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(m.scores([t.as_py() or "" for t in part.column(1)]))], names=["doc_id", "score"])

    out = pick(docs, "doc_id", "text").selectExpr("cast(doc_id as long) doc_id", "cast(text as string) text").mapInArrow(run, "doc_id long, score double")
    return out.select("doc_id", F.expr(f"coalesce({HELD_OUT}, false)").alias("held_out"), "score", (F.col("score") >= alert).cast("int").alias("predicted"))


def op4_toxicity(spark, sf_dir) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return score(docs, train(docs, table(spark, sf_dir, "labels")))


