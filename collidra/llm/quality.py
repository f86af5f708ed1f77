"""Quality by a byte-level convolutional network, fitted and run in numpy.

A filter reads ``WIDTH`` bytes; as its input is one byte per place, it is a table of one weight per place and byte value.
The responses over a whole text are maxima over blocks, and two neighbouring blocks make a chunk, so chunks overlap by
half and cover the text to its last byte. What is left after a ramp at zero is pooled over the chunks of the whole text,
as their maximum and as their mean, and a logistic unit combines these into the probability of label 1. Only the places of the maxima carry gradients, so learning is
a few additions per chunk and filter.

Defined results: a null or empty text has no chunk and gets the score of all-zero pools; a text shorter than a
filter is padded with zero bytes; without labelled rows of both classes every score is the share of label 1 (0.5
without any); texts are read whole, in parts of bounded size.
"""

from __future__ import annotations

import math
import pickle
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import read_table
from .sampling import HELD_OUT_FOLD, fold, labelled_sample
from .toxicity import _logistic

THRESHOLD = 0.5
WIDTH, FILTERS, BLOCK = 5, 12, 256
#: Rows of each class that the filters are learned from; epochs over them; step of the optimiser.
ROWS_PER_CLASS, EPOCHS, RATE, BATCH = 1500, 5, 0.02, 16
_PART_BLOCKS = 1024


def _bytes(text: str | None) -> np.ndarray:
    raw = (text or "").encode("utf-8", "surrogatepass")
    return np.frombuffer(raw.ljust(WIDTH, b"\0") if raw else b"", dtype=np.uint8)


def _responses(table: np.ndarray, a: np.ndarray) -> np.ndarray:
    """(places, filters): the filters' sums at each place of ``a``."""
    m = len(a) - WIDTH + 1
    out = table[0][a[:m]]
    for k in range(1, WIDTH):
        out += table[k][a[k : k + m]]
    return out


def _chunks(blocks: np.ndarray) -> np.ndarray:
    return blocks if len(blocks) < 2 else np.maximum(blocks[:-1], blocks[1:])


def features(table: np.ndarray, text: str | None) -> np.ndarray:
    """Mean and maximum over the chunks of a whole text of what each filter found."""
    a = _bytes(text)
    if not len(a):
        return np.zeros(2 * table.shape[2], dtype=np.float32)
    places = len(a) - WIDTH + 1
    step, found = BLOCK * _PART_BLOCKS, []
    for lo in range(0, places, step):
        r = _responses(table, a[lo : min(lo + step, places) + WIDTH - 1])
        found.append(np.maximum.reduceat(r, np.arange(0, len(r), BLOCK), axis=0))
    chunks = np.maximum(_chunks(np.concatenate(found)), 0)
    return np.concatenate((chunks.mean(axis=0), chunks.max(axis=0)))


def _traced(table: np.ndarray, a: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Chunk maxima and the place of each, (chunks, filters)."""
    r = _responses(table, a)
    n = -(-len(r) // BLOCK)
    padded = np.full((n * BLOCK, r.shape[1]), -np.inf, dtype=r.dtype)
    padded[: len(r)] = r
    cube = padded.reshape(n, BLOCK, -1)
    at = cube.argmax(axis=1)
    top = np.take_along_axis(cube, at[:, None, :], axis=1)[:, 0, :]
    at = at + np.arange(n)[:, None] * BLOCK
    if n < 2:
        return top, at
    first = top[:-1] >= top[1:]
    return np.where(first, top[:-1], top[1:]), np.where(first, at[:-1], at[1:])


class _Adam:
    def __init__(self, shape: tuple):
        self.m, self.v, self.t = np.zeros(shape, np.float32), np.zeros(shape, np.float32), 0

    def step(self, g: np.ndarray, rate: float) -> np.ndarray:
        self.t += 1
        self.m += 0.1 * (g - self.m)
        self.v += 0.001 * (g * g - self.v)
        return rate * (self.m / (1 - 0.9**self.t)) / (np.sqrt(self.v / (1 - 0.999**self.t)) + 1e-8)


@dataclass
class QualityModel:
    table: np.ndarray
    weights: np.ndarray
    base: float | None = None

    def score(self, text: str | None) -> float:
        if self.base is not None:
            return self.base
        z = float(self.weights[0] + features(self.table, text) @ self.weights[1:])
        return 1 / (1 + math.exp(-max(-40.0, min(40.0, z))))


def fit(sample: list[tuple[int, int, str]], share: float | None = None, seed: int = 5) -> QualityModel:
    """A model from (fold, label, text); ``share`` is the share of label 1 among all labels, which the sample may not have."""
    y = np.array([v for _, v, _ in sample], dtype=np.float32)
    if len(set(y.tolist())) < 2:
        return QualityModel(np.zeros(0), np.zeros(0), float(y.mean()) if len(y) else 0.5)
    rng = np.random.default_rng(seed)
    texts = [_bytes(t) for _, _, t in sample]
    table = rng.normal(0, 0.15, (WIDTH, 256, FILTERS)).astype(np.float32)
    w, b = rng.normal(0, 0.3, FILTERS).astype(np.float32), np.float32(0)
    steps = [_Adam(table.shape), _Adam(w.shape), _Adam(())]
    balance = {v: len(y) / (2 * (y == v).sum()) for v in (0.0, 1.0)}
    for epoch in range(EPOCHS):
        order = rng.permutation(len(texts))
        rate = RATE * (1 - epoch / EPOCHS)
        for lo in range(0, len(order), BATCH):
            gt, gw, gb = np.zeros_like(table), np.zeros_like(w), 0.0
            for i in order[lo : lo + BATCH]:
                a = texts[i]
                if not len(a):
                    continue
                top, at = _traced(table, a)
                h = np.maximum(top, 0)
                mean = h.mean(axis=0)
                z = float(mean @ w + b)
                err = (1 / (1 + math.exp(-max(-40.0, min(40.0, z)))) - y[i]) * balance[float(y[i])] / BATCH
                gw += err * mean
                gb += err
                back = (err / len(top)) * w * (top > 0)
                for k in range(WIDTH):
                    np.add.at(gt[k], (a[at + k], np.arange(FILTERS)[None, :]), back)
            table -= steps[0].step(gt + 1e-5 * table, rate)
            w -= steps[1].step(gw + 1e-4 * w, rate)
            b -= steps[2].step(np.float32(gb), rate)
    x = np.array([features(table, t) for _, _, t in sample])
    final = _logistic(x, y.astype(float), ridge=0.1)
    if share is not None and 0 < share < 1:  # from the sample's odds to the labels' odds
        mean = float(y.mean())
        final[0] += math.log(share / (1 - share)) - math.log(mean / (1 - mean))
    return QualityModel(table, final.astype(np.float32))


def fit_documents(docs: DataFrame, labels: DataFrame, rows_per_class: int = ROWS_PER_CLASS) -> QualityModel:
    share = labels.where(fold("doc_id") != HELD_OUT_FOLD).where("quality IN (0, 1)").agg(F.avg("quality")).first()[0]
    return fit(labelled_sample(docs, labels, "quality", rows_per_class), share)


def score_documents(docs: DataFrame, model: QualityModel, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, held_out, score, predicted) for each row, by its text alone."""
    blob = pickle.dumps(model)

    @F.pandas_udf("double")
    def score(texts: pd.Series) -> pd.Series:
        m = pickle.loads(blob)
        return pd.Series([m.score(t) for t in texts], dtype=float)

    return docs.select(
        F.col(id_col).cast("long").alias("doc_id"), (fold(id_col) == HELD_OUT_FOLD).alias("held_out"), score(F.col(text_col)).alias("score")
    ).withColumn("predicted", (F.col("score") >= THRESHOLD).cast("int"))


def op8_quality(spark, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    return score_documents(docs, fit_documents(docs, read_table(spark, sf_dir, "labels")))
