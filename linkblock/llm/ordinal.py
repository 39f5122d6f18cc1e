"""Quality classifier: ordinal cumulative-link regression on graded ratings.

P(grade <= j) = logistic(theta_j - w.x): one weight vector over hashed words
and shape marks of the text, shared by all grades, and ordered thresholds.
Weights are trained by follow-the-regularised-leader steps with an L1 term, so
that only telling features keep a weight. The model gives the expected grade
and the probability of a grade at least TAIL, which selects.

Training uses at most SAMPLE labelled documents (those with the least hash of
their id); all documents are scored, over their whole text.
"""

from __future__ import annotations

import zlib
from collections import Counter
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linkblock.llm.common import as_bytes, narrow, per_document

BUCKETS = 1 << 18
SAMPLE = 10_000
GRADES = 3
TAIL, AT_LEAST = 2, 0.5
EPOCHS = 16
#: Bytes of a word's start that count as a feature of their own, and occurrences told apart.
START, TIMES = 6, 4
_LETTERS = bytes(b + 32 if 65 <= b <= 90 else b if b >= 128 or 97 <= b <= 122 else 32 for b in range(256))
_SYMBOLS, _CAPITALS, _DIGITS = b"#*$%&|<>!", bytes(range(65, 91)), b"0123456789"


def _mark(name: str, value: float) -> int:
    """A shape mark: one feature for each eighth of a ratio, finer near 0."""
    return zlib.crc32(f"\0{name}{min(16, int(16 * value**0.5))}".encode()) & (BUCKETS - 1)


def features(raw: bytes) -> np.ndarray:
    """Sorted distinct feature ids: words of letters (A-Z lower-cased), starts of words and how often they occur (1 to TIMES), marks of shape."""
    words = raw.translate(_LETTERS).split()
    tokens = raw.split()
    n, lines = max(1, len(raw)), [x for x in raw.split(b"\n") if x.strip()]
    share = lambda table: (n - len(raw.translate(None, table)) - (n - len(raw))) / n
    marks = [
        _mark("symbols", share(_SYMBOLS)), _mark("capitals", share(_CAPITALS)), _mark("digits", share(_DIGITS)),
        _mark("repeats", 1 - len(set(tokens)) / max(1, len(tokens))), _mark("lines", 1 - len(set(lines)) / max(1, len(lines))),
        _mark("length", min(1.0, len(tokens) / 2000)),
    ]
    starts = Counter([w[:START] for w in words])
    counted = (zlib.crc32(b"\1%d" % i + w) & (BUCKETS - 1) for w, n in starts.items() for i in range(min(n, TIMES)))
    return np.unique(np.fromiter([*(zlib.crc32(w) & (BUCKETS - 1) for w in set(words)), *counted, *marks], np.int32))


def _logistic(x):
    return 1 / (1 + np.exp(-np.clip(x, -35, 35)))


class OrdinalModel:
    """Shared weights and ordered thresholds."""

    def __init__(self, weights: np.ndarray, thresholds: np.ndarray):
        self.weights, self.thresholds = weights, thresholds

    def below(self, latent: float) -> np.ndarray:
        """P(grade <= j) for j under the top grade."""
        return _logistic(self.thresholds - latent)

    def judge(self, raw: bytes, tail: int = TAIL) -> tuple[float, float]:
        """Expected grade and P(grade >= tail)."""
        over = 1 - self.below(float(self.weights[features(raw)].sum()))
        return float(over.sum()), float(over[tail - 1])


def train(rows: list[tuple[np.ndarray, int]], grades: int = GRADES, epochs: int = EPOCHS, rate: float = 1.0, l1: float = 5.0, l2: float = 0.1, pace: float = 0.02) -> OrdinalModel:
    """Fit on (feature ids, grade). Without rows every document gets the top grade's probability 1/2 or more."""
    seen = np.bincount([g for _, g in rows], minlength=grades) + 1.0
    below = np.cumsum(seen)[:-1] / seen.sum()
    theta = np.log(below / (1 - below)) if rows else -np.arange(grades - 1, 0, -1).astype(float)
    z, n, w = np.zeros(BUCKETS), np.zeros(BUCKETS), np.zeros(BUCKETS)
    for epoch in range(epochs):
        for at in np.random.default_rng(epoch).permutation(len(rows)):
            ids, grade = rows[at]
            latent = w[ids].sum()
            f = np.r_[0.0, _logistic(theta - latent), 1.0]
            slope = 1 - f[grade + 1] - f[grade]
            here = max(1e-9, f[grade + 1] - f[grade])
            if grade < grades - 1:
                theta[grade] += pace * f[grade + 1] * (1 - f[grade + 1]) / here
            if grade:
                theta[grade - 1] -= pace * f[grade] * (1 - f[grade]) / here
            theta = np.maximum.accumulate(theta)
            root = np.sqrt(n[ids])
            n[ids] += slope * slope
            grown = np.sqrt(n[ids])
            z[ids] += slope - (grown - root) / rate * w[ids]
            zi = z[ids]
            w[ids] = np.where(np.abs(zi) > l1, (np.sign(zi) * l1 - zi) / ((1 + grown) / rate + l2), 0.0)
    return OrdinalModel(w.astype(np.float32), theta)


def graded(labels: DataFrame, id_col: str = "doc_id", quality: str = "quality", toxic: str = "toxic") -> DataFrame:
    """(doc_id, grade): 0 not of quality, 1 of quality but toxic, 2 both well. Rows without either label are left out."""
    grade = F.when(F.col(quality) == 0, 0).when(F.col(toxic) == 1, 1).otherwise(2)
    return labels.where(F.col(quality).isNotNull() & F.col(toxic).isNotNull()).select(F.col(id_col).cast("bigint").alias("doc_id"), grade.alias("grade")).groupBy("doc_id").agg(F.min("grade").alias("grade"))


def fit(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", sample: int = SAMPLE) -> OrdinalModel:
    """Train on the `sample` labelled ids with the least hash; their features, not their texts, meet the driver.

    Of an id with several texts the one of the least hash is taken, so neither
    repeated rows nor their order matter.
    """
    chosen = graded(labels).orderBy(F.xxhash64(F.col("doc_id").cast("string")), "doc_id").limit(sample)
    mine = narrow(docs, id_col, text_col).join(F.broadcast(chosen), "doc_id")
    text = F.coalesce("text", F.lit(""))
    once = mine.groupBy("doc_id", "grade").agg(F.min_by(text, F.struct(F.xxhash64(text), text)).alias("text"))  # at most `sample` rows
    found = per_document(once, lambda raw: (features(raw).tolist(),), "doc_id bigint, grade int, ids array<int>", "grade")
    rows = found.toArrow().combine_chunks()
    if not rows.num_rows:
        return train([])
    lists = rows.column("ids").chunk(0)
    starts, values = lists.offsets.to_numpy(), lists.values.to_numpy()
    grades = rows.column("grade").to_pylist()
    order = np.argsort(rows.column("doc_id").to_numpy())
    return train([(values[starts[i] : starts[i + 1]], grades[i]) for i in order])


def judge_documents(docs: DataFrame, model: OrdinalModel, id_col: str = "doc_id", text_col: str = "text", tail: int = TAIL) -> DataFrame:
    """(doc_id, expected_grade, tail_prob, kept) for every row; null text is judged as empty, repeated rows alike."""
    return per_document(
        narrow(docs, id_col, text_col), lambda raw: (e := model.judge(raw, tail)) + (e[1] >= AT_LEAST,),
        "doc_id bigint, expected_grade double, tail_prob double, kept boolean",
    )


def select_documents(docs: DataFrame, model: OrdinalModel, text_col: str = "text", tail: int = TAIL) -> DataFrame:
    """Rows of docs, with all their columns, whose tail probability is at least AT_LEAST."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, 512):
                part = whole.slice(at, 512)
                texts = part.column(text_col).cast(pa.string()).cast(pa.binary()).to_pylist()
                kept = [model.judge(x or b"", tail)[1] >= AT_LEAST for x in texts]
                yield part.filter(pa.array(kept, pa.bool_()))

    return docs.mapInArrow(run, docs.schema)


def by_hand(model: OrdinalModel, raw: bytes) -> float:
    """The latent score by plain sums, for tests."""
    return reduce(lambda a, i: a + float(model.weights[i]), features(raw), 0.0)
