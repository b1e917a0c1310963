"""Ordinal cumulative-link regression on graded ratings, over hashed text.

P(grade > j) = sigmoid(w.x - t_j): one weight vector for all grades, and ordered thresholds t_0 < t_1 < ... The vector x holds
square roots of the shares of hashed features of a document's words: the word, its shape (letter case, digits, punctuation at its ends), and
whether it equals the word before. A document gets its expected grade and, for each j, the tail probability; it is selected
by the tail probability of MIN_GRADE.

Training takes at most MAX_RATED rated rows, those of least hash; all else covers all documents.

A null or empty text has no features: x = 0. Ratings that are null are not used: a label without a quality gives none, nor does a good one without
its other label. Several labels of one document are each a rating, and so is each row of a repeated document. If there are no
ratings, or ratings of one grade only, all documents are selected with tail probability 1. Repeated rows are scored each on its own.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import pick, table

MAX_RATED = 6000
DIMS = 4096
#: Selected if P(grade >= MIN_GRADE) is at least this.
MIN_GRADE, MIN_TAIL = 1, 0.5
STEPS, RATE, L2 = 250, 0.05, 1e-4
CACHED_WORDS = 400_000
_FIRST, _LAST = re.compile(r"\w"), re.compile(r"\w\W*\Z")
_cache: dict[str, bytes] = {}


def _slot(kind: str, value: str) -> int:
    return zlib.crc32(f"{kind}{value}".encode("utf-8", "replace")) % (DIMS - 2)


def _word(w: str) -> bytes:
    first, last = _FIRST.search(w), _LAST.search(w)
    before, core, after = (w[: first.start()], w[first.start() : last.start() + 1], w[last.start() + 1 :]) if first else (w, "", "")
    case = "u" if core.isupper() and len(core) > 1 else "t" if core[:1].isupper() else "l" if core.islower() else "d" if core.isdigit() else "x" if core else ""
    shape = f"{before[:3]}{case}{after[:3]}"
    return np.asarray([_slot("w", w.lower()), _slot("s", shape), _slot("e", after[:3])], "<u2").tobytes()


def features(text: str) -> np.ndarray:
    """Square roots of shares, DIMS long; the last place but one is for words equal to the one before, the last for texts with words."""
    words = text.split()
    x = np.zeros(DIMS, np.float32)
    if not words:
        return x
    if len(_cache) > CACHED_WORDS:
        _cache.clear()
    try:
        ids = b"".join(map(_cache.__getitem__, words))
    except KeyError:
        out = []
        for w in words:
            got = _cache.get(w)
            if got is None:
                got = _word(w)
                if len(w) < 64:
                    _cache[w] = got
            out.append(got)
        ids = b"".join(out)
    at = np.frombuffer(ids, "<u2")
    x += np.bincount(at, minlength=DIMS)
    own = at.reshape(-1, 3)
    x[DIMS - 2] = (own[1:] == own[:-1]).all(axis=1).sum()
    x = np.sqrt(x / len(words))
    x[DIMS - 1] = 1
    return x


def _sparse(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        for k, grade, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2), strict=True):
            x = features(text.as_py() or "")
            at = np.flatnonzero(x)
            yield pa.RecordBatch.from_arrays([pa.array([k], pa.int64()), pa.array([grade], pa.int64()), pa.array([at.astype("<u2").tobytes()]), pa.array([x[at].astype("<f4").tobytes()])], names=["k", "grade", "at", "x"])


class OrdinalModel:
    """Weights and ordered thresholds; grades is how many thresholds there are, plus one."""

    def __init__(self, w: np.ndarray, thresholds: np.ndarray):
        self.w, self.thresholds = w, thresholds

    def tails(self, z: np.ndarray) -> np.ndarray:
        """P(grade > j) for each j, a row for each z."""
        return 1 / (1 + np.exp(-np.clip(z[:, None] - self.thresholds[None, :], -30, 30)))


def fit(x: np.ndarray, grade: np.ndarray, steps: int = STEPS) -> OrdinalModel | None:
    """Maximum likelihood by Adam; thresholds are t_0 and positive steps after it. None if fewer than two grades occur."""
    kinds = int(grade.max()) + 1 if len(grade) else 0
    if kinds < 2 or len(np.unique(grade)) < 2:
        return None
    n, j = len(grade), np.arange(kinds - 1)
    # each threshold is a yes-or-no question about every rating; cumulative-link likelihood from their sigmoids
    w, t0, gaps = np.zeros(x.shape[1]), 0.0, np.zeros(kinds - 2)
    state = [np.zeros(len(w) + kinds - 1) for _ in range(2)]
    above, below = np.clip(grade - 1, 0, None), np.clip(grade, None, kinds - 2)
    rows = np.arange(n)
    weight = (n / len(np.unique(grade)) / np.bincount(grade, minlength=kinds).clip(1))[grade]
    weight = np.sqrt(weight)
    for step in range(1, steps + 1):
        t = t0 + np.concatenate([[0], np.cumsum(np.exp(gaps))])
        s = 1 / (1 + np.exp(-np.clip((x @ w.astype(x.dtype)).astype(float)[:, None] - t[None, :], -30, 30)))
        high = np.where(grade > 0, s[rows, above], 1.0)  # P(grade >= own)
        low = np.where(grade < kinds - 1, s[rows, below], 0.0)  # P(grade > own)
        p = np.maximum(high - low, 1e-12)
        dh, dl = np.where(grade > 0, high * (1 - high), 0), np.where(grade < kinds - 1, low * (1 - low), 0)
        dz = -weight * (dh - dl) / p / n
        dt = np.zeros(kinds - 1)
        np.add.at(dt, above, weight * np.where(grade > 0, dh / p, 0) / n)
        np.add.at(dt, below, -weight * np.where(grade < kinds - 1, dl / p, 0) / n)
        dgap = np.asarray([dt[j > k].sum() * np.exp(gaps[k]) for k in range(kinds - 2)])
        g = np.concatenate([x.T @ dz.astype(x.dtype) + L2 * w, [dt.sum()], dgap])
        state[0] = 0.9 * state[0] + 0.1 * g
        state[1] = 0.999 * state[1] + 0.001 * g * g
        move = RATE * (state[0] / (1 - 0.9**step)) / (np.sqrt(state[1] / (1 - 0.999**step)) + 1e-8)
        w, t0, gaps = w - move[: len(w)], t0 - move[len(w)], gaps - move[len(w) + 1 :]
    return OrdinalModel(w, t0 + np.concatenate([[0], np.cumsum(np.exp(gaps))]))


def train(docs: DataFrame, ratings: DataFrame, max_rated: int = MAX_RATED) -> OrdinalModel | None:
    """ratings: doc_id, grade. Features of at most max_rated rows come to the driver, whatever repeats: DIMS * 6 bytes for each at most."""
    sample = ratings.where("doc_id is not null and grade is not null").orderBy(F.xxhash64("doc_id"), "doc_id", "grade").limit(max_rated)
    rows = pick(docs, "doc_id", "text").join(F.broadcast(sample), "doc_id").select(F.xxhash64("doc_id").alias("k"), F.expr("cast(grade as long) grade"), F.expr("cast(text as string) text"))  # max_rated rows
    sparse = rows.mapInArrow(_sparse, "k long, grade long, at binary, x binary")
    got = (sparse.orderBy("k", "grade", "at", "x").limit(max_rated) if rows.count() > max_rated else sparse).toArrow()  # more only where labelled rows are repeated
    grade = np.asarray(got["grade"].to_pylist(), np.int64)
    at, values = ([np.frombuffer(v.as_py(), kind) for v in got[c]] for c, kind in (("at", "<u2"), ("x", "<f4")))
    order = np.lexsort(([float(v @ (a + np.float32(1))) for a, v in zip(at, values, strict=True)], grade))  # the same model whatever the rows' order
    x = np.zeros((len(grade), DIMS), np.float32)
    for i, k in enumerate(order.tolist()):
        x[i, at[k]] = values[k]
    return fit(x, grade[order])


def score(docs: DataFrame, model: OrdinalModel | None, min_grade: int = MIN_GRADE, min_tail: float = MIN_TAIL) -> DataFrame:
    """docs' columns as they are, then expected_grade, tail_probability and selected; columns of these names in docs are replaced."""
    names = ["expected_grade", "tail_probability", "selected"]
    docs = docs.drop(*names)
    fields = docs.schema.fields
    at = docs.columns.index("text")
    shared = docs.sparkSession.sparkContext.broadcast(model)  # DIMS weights

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for b in batches:
            if m is None:
                expected, tail = np.zeros(b.num_rows), np.ones(b.num_rows)
            else:
                z = np.asarray([features(str(t.as_py() or "")) @ m.w for t in b.column(at)], np.float64)
                tails = m.tails(z) if len(z) else np.zeros((0, 1))
                expected = tails.sum(axis=1)
                tail = tails[:, min_grade - 1] if 1 <= min_grade <= tails.shape[1] else np.full(len(z), float(min_grade < 1))
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(expected), pa.array(tail), pa.array(tail >= min_tail)], names=[f"c{k}" for k in range(len(fields) + 3)])

    kept = docs.toDF(*(f"c{k}" for k in range(len(fields))))
    kinds = [*(f.dataType for f in fields), T.DoubleType(), T.DoubleType(), T.BooleanType()]
    schema = T.StructType([T.StructField(f"c{k}", kind) for k, kind in enumerate(kinds)])
    return kept.mapInArrow(run, schema).toDF(*docs.columns, *names)


def graded(labels: DataFrame) -> DataFrame:
    """Three grades from the two labels: 0 poor, 1 good but toxic, 2 good; null where the labels do not say."""
    return pick(labels, "doc_id", "quality", "toxic").selectExpr("doc_id", "CASE WHEN quality = 0 THEN 0 WHEN quality IS NOT NULL THEN 2 - toxic END AS grade")


def op9_quality_classifier(spark, sf_dir) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = train(docs, graded(table(spark, sf_dir, "labels")))
    return score(pick(docs, "doc_id", "text"), model).drop("text")
