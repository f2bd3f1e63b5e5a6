"""Quality classifier: naive-Bayes support vectors over n-gram indicators.

A text becomes the set of its n-grams, hashed to 2^18 places: single words, and runs of one to three word shapes (cases,
digits, letters beyond ASCII, punctuation at either end, length, and whether the word repeats the one before). Each place is scaled by the log ratio of its
smoothed counts in the two classes; a linear hinge-loss model over the scaled indicators is fitted by dual coordinate
descent, each class weighing the same, and interpolated with the mean weight. A sigmoid over margins of held-out thirds
turns margins into probabilities.

Only the fit uses a bounded sample: at most ``MOST_ROWS`` labelled rows (those whose doc_id hashes lowest). Every document is
scored, whole. Rows of the held-out fold (crc32 of the doc_id as text, mod 5 = 0) are never learned from; labels, lang, source and doc_id are
no features.

Null and empty texts have one feature, emptiness, and a score. With labels of one class or none, every score is the share of ones
(0.5 without labels). Conflicting labels of a doc_id each count; rows that repeat are each scored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from bipercolate.llm.common import text_blocks

PLACES = 1 << 18
MOST_ROWS = 6000
THRESHOLD = 0.3
MOST_WORDS = 300_000
_U64 = np.uint64
_M = _U64(0x9E3779B97F4A7C15)
SCORES = "doc_id long, score double"


class Words(dict):
    """A 64-bit number of a word: its hash, with its shape in the low 16 bits."""

    def __missing__(self, word: bytes) -> int:
        import xxhash

        if len(self) >= MOST_WORDS:
            self.clear()
        text = word.decode("utf-8", "replace")
        ends = [0 if x.isalnum() else 1 + ord(x) % 31 for x in (text[0], text[-1])]
        core = text.strip("".join({x for x in (text[0], text[-1]) if not x.isalnum()}))
        case = 3 if not core else 2 if core.isupper() and len(core) > 1 else 1 if core[0].isupper() else 0
        kinds = (any(x.isdigit() for x in core) << 1) | any(not x.isalnum() for x in core)
        shape = ends[0] << 11 | ends[1] << 6 | case << 4 | kinds << 2 | min(len(core) // 8, 3)
        self[word] = found = xxhash.xxh3_64_intdigest(word) & ~0xFFFF | shape
        return found


_words = Words()


def features(text: bytes) -> np.ndarray:
    """The sorted distinct places of a text's n-grams."""
    words = text.split()
    if not words:
        return np.zeros(1, np.int64)
    codes = np.fromiter(map(_words.__getitem__, words), _U64, len(words))
    shape = codes & _U64(0xFFFF)
    shape[1:] |= (codes[1:] == codes[:-1]).astype(_U64) << _U64(16)
    found = [(codes >> _U64(16)) * _M]
    total = np.zeros(len(shape), _U64)
    for n in range(min(3, len(shape))):
        total = (total[: len(shape) - n] + shape[n:] + _U64(n + 1)) * _M
        total ^= total >> _U64(29)
        found.append(total * _M)
    seen = np.zeros(PLACES, bool)
    for x in found:
        seen[(x >> _U64(46)).astype(np.int64)] = True
    return np.flatnonzero(seen)


@dataclass
class Model:
    weights: np.ndarray  # of the unscaled indicators
    bias: float
    slope: float
    offset: float

    def score(self, places: np.ndarray) -> float:
        """Probability of label 1. Indicators are divided by the root of their number."""
        margin = float(self.weights[places].sum()) / math.sqrt(len(places)) + self.bias
        return 1 / (1 + math.exp(-max(-60.0, min(60.0, self.slope * margin + self.offset))))


def _descent(rows: list[np.ndarray], labels: np.ndarray, cost: float = 0.1, rounds: int = 12, smooth: float = 1.0, blend: float = 0.25) -> tuple[np.ndarray, float]:
    """Weights and bias of the scaled hinge-loss model, by dual coordinate descent."""
    sums = np.full((2, PLACES), smooth)
    for places, y in zip(rows, labels, strict=True):
        sums[int(y)][places] += 1
    ratio = np.log(sums[1] / sums[1].sum()) - np.log(sums[0] / sums[0].sum())
    sign = np.where(labels == 1, 1.0, -1.0)
    most = cost * len(labels) / (2 * np.where(labels == 1, max((labels == 1).sum(), 1), max((labels == 0).sum(), 1)))
    values = [ratio[x] / math.sqrt(len(x)) for x in rows]
    norms = np.array([float(v @ v) + 1 for v in values])
    w, bias, dual = np.zeros(PLACES), 0.0, np.zeros(len(rows))
    order = np.random.default_rng(11)
    for _ in range(rounds):
        for k in order.permutation(len(rows)):
            gradient = sign[k] * (float(w[rows[k]] @ values[k]) + bias) - 1
            new = min(max(dual[k] - gradient / norms[k], 0.0), most[k])
            if new != dual[k]:
                step = (new - dual[k]) * sign[k]
                w[rows[k]] += step * values[k]
                bias += step
                dual[k] = new
    w = (1 - blend) * np.abs(w).mean() + blend * w if blend < 1 else w
    return w * ratio, bias


def _sigmoid(margins: np.ndarray, labels: np.ndarray) -> tuple[float, float]:
    """Slope and offset of the logistic curve of labels over margins, by Newton steps with a little ridge."""
    spread = float(margins.std()) or 1.0
    x = np.stack([margins / spread, np.ones(len(margins))], axis=1)
    beta = np.zeros(2)
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(x @ beta, -30, 30)))
        step = np.linalg.solve((x.T * (p * (1 - p))) @ x + 1e-3 * np.eye(2), x.T @ (labels - p) - 1e-3 * beta)
        beta += step
        if np.abs(step).max() < 1e-8:
            break
    return float(beta[0] / spread), float(beta[1])


def fit(rows: list[np.ndarray], labels: np.ndarray) -> Model:
    """A model of places lists and labels 0 or 1."""
    share = float(labels.mean()) if len(labels) else 0.5
    if len(labels) < 6 or share in (0.0, 1.0):
        share = min(max(share, 1e-3), 1 - 1e-3)
        return Model(np.zeros(PLACES, np.float32), 0.0, 0.0, math.log(share / (1 - share)))
    fold = np.arange(len(labels)) % 3
    margins = np.zeros(len(labels))
    for f in range(3):
        w, bias = _descent([x for x, g in zip(rows, fold, strict=True) if g != f], labels[fold != f])
        margins[fold == f] = [float(w[x].sum()) / math.sqrt(len(x)) + bias for x, g in zip(rows, fold, strict=True) if g == f]
    w, bias = _descent(rows, labels)
    return Model(w.astype(np.float32), bias, *_sigmoid(margins, labels.astype(float)))


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(5)) == 0, F.lit(False))


def _places(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for start, texts in text_blocks(batch):
            found = [features(x).astype(np.int32) for x in texts]
            lists = pa.ListArray.from_arrays(pa.array(np.cumsum([0, *map(len, found)]), pa.int32()), pa.array(np.concatenate(found)))
            yield pa.RecordBatch.from_arrays([batch.column("label").slice(start, len(texts)), batch.column("doc_id").slice(start, len(texts)), lists], ["label", "doc_id", "places"])


def train(docs: DataFrame, labels: DataFrame, label: str = "quality", most_rows: int = MOST_ROWS) -> Model:
    """Fit on at most ``most_rows`` labelled rows outside the held-out fold; the rest of ``docs`` is only skimmed for them."""
    known = labels.select(F.col("doc_id").cast("long"), F.col(label).cast("int").alias("label")).filter(F.col("label").isin(0, 1) & F.col("doc_id").isNotNull()).filter(~held_out(F.col("doc_id")))
    sample = known.orderBy(F.xxhash64("doc_id"), "doc_id", "label").limit(most_rows)  # bounded by most_rows
    rows = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).join(F.broadcast(sample), "doc_id")
    found = rows.mapInArrow(_places, "label int, doc_id long, places array<int>").toArrow().sort_by([("doc_id", "ascending"), ("label", "ascending")])
    places = found.column("places").combine_chunks()
    offsets, values = places.offsets.to_numpy(), places.values.to_numpy()
    lists = [values[a:b] for a, b in zip(offsets[:-1], offsets[1:], strict=True)]
    return fit(lists, found.column("label").to_numpy())


def _scorer(model: Model):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for start, texts in text_blocks(batch):
                scores = pa.array([model.score(features(x)) for x in texts], pa.float64())
                yield pa.RecordBatch.from_arrays([batch.column("doc_id").slice(start, len(texts)), scores], ["doc_id", "score"])

    return run


def scored(docs: DataFrame, model: Model, threshold: float = THRESHOLD) -> DataFrame:
    """Per document: doc_id, held_out, score, predicted."""
    rows = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(_scorer(model), SCORES)
    return rows.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))


def evaluate(scores: DataFrame, labels: DataFrame, label: str = "quality") -> DataFrame:
    """One row over held-out labelled documents: n, accuracy, and the recall of either class."""
    both = scores.filter("held_out").join(labels.select("doc_id", F.col(label).alias("label")), "doc_id")
    right = (F.col("predicted") == F.col("label")).cast("double")
    return both.agg(F.count("*").alias("n"), F.avg(right).alias("accuracy"), F.avg(F.when(F.col("label") == 1, right)).alias("recall_1"), F.avg(F.when(F.col("label") == 0, right)).alias("recall_0"))
