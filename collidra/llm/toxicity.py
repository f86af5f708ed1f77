"""Toxicity by compression distance: two zstandard dictionaries, compared window by window.

The library's trainer makes the ordinary dictionary from windows of ordinary texts and, apart from it, the toxic one from
windows of toxic texts: first of all their windows, then of those that a dictionary trained on the other half of the toxic
texts finds telling, as most windows of a toxic text are ordinary. A window of words is compressed with the ordinary dictionary alone and with the toxic one put
before it; the bytes that the toxic dictionary saves are the window's gain. It lies farther from the window than the
ordinary one, so what both know saves nothing. A text's score is a logistic function of how many of its windows reach each
level of gain, calibrated on another fold than the dictionaries; the threshold of 0.7 is where that fold's F1 is best.

Defined results: null and empty texts have no windows and get the score of no gain (below the threshold); a class with
no labelled rows gives the score of the share of toxic labels (0 without any) for every text; long texts are
windowed whole; texts with invalid code points are scored on their UTF-8 bytes.
"""

from __future__ import annotations

import math
import pickle
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import read_table, spare, trim
from .sampling import HELD_OUT_FOLD, ROWS_PER_CLASS, fold, labelled_sample

THRESHOLD = 0.7
WINDOW_WORDS = 8
#: Bytes of either dictionary, the trainer's segment lengths, and the most windows that it is shown.
ORDINARY_BYTES, TOXIC_BYTES, FIRST_TOXIC_BYTES = 96 << 10, 4 << 10, 8 << 10
ORDINARY_SEGMENT, TOXIC_SEGMENT, SEGMENT_MATCH = 16, 12, 6
TRAINING_WINDOWS = 60_000
#: How often the trainer goes over the samples, and stretches of them that it may lose to its header.
TRAINER_PASSES, SPARE = 4, 16
#: How the compressor searches: a dictionary's whole chain of matches of five bytes or more.
LEVEL, SEARCH = 9, {"strategy": zstandard.STRATEGY_BTLAZY2, "search_log": 10, "min_match": 5}
#: Gains in bytes from which on windows are counted; the least one also tells a toxic text's telling windows.
GAINS = (2, 3, 4, 5)
#: How often the toxic windows are narrowed down to the telling ones, and fewer than which of them train no dictionary.
NARROWINGS, LEAST_WINDOWS = 2, 64


def _words(text: str | None) -> list[bytes]:
    return (text or "").lower().encode("utf-8", "surrogatepass").split()


def windows(words: list[bytes]) -> list[bytes]:
    return [b" " + b" ".join(words[i : i + WINDOW_WORDS]) + b" " for i in range(0, len(words), WINDOW_WORDS)]


def _trained(size: int, samples: list[bytes], segment: int) -> bytes:
    """A dictionary's bytes by the library's trainer; from too few windows these themselves, joined.

    The trainer takes the best segment of each stretch of the samples in turn and fills the dictionary from its end, and
    its header then pushes out the last of it: the segments taken first, which are the most frequent of all. So the first
    ``SPARE`` stretches hold nothing but one string each, and only those are lost.

    It also stops at the tenth stretch in a row that tells nothing new, wherever that is: a few texts of one line repeated
    would leave the rest unread and the dictionary all but empty. So it gets each window once, in the order of a hash.
    """
    samples = sorted(set(samples), key=lambda w: (zlib.crc32(w), w))
    samples = samples[:: max(1, -(-len(samples) // TRAINING_WINDOWS))]
    stretches = max(1, size // segment // TRAINER_PASSES)
    spare = min(SPARE, stretches // 2)
    stretch = sum(map(len, samples)) // (stretches - spare) + 1
    filler = []
    for i in range(spare):
        unit = bytes([1 + i]) * (segment - 1) + b"\0"
        filler += [unit * 8] * (stretch // (8 * segment) + 1)
    try:
        return zstandard.train_dictionary(size, filler + samples, k=segment, d=SEGMENT_MATCH).as_bytes()
    except zstandard.ZstdError:
        return b"".join(samples)[-size:]


def _compressor(content: bytes):
    kind = zstandard.ZstdCompressionDict(content, dict_type=zstandard.DICT_TYPE_RAWCONTENT)
    p = zstandard.ZstdCompressionParameters.from_level(
        LEVEL, source_size=64, dict_size=len(content), write_content_size=False, write_checksum=False, write_dict_id=False, **SEARCH
    )
    return zstandard.ZstdCompressor(dict_data=kind, compression_params=p).compress


def _toxic_dictionary(texts: list[list[bytes]], ordinary: bytes) -> bytes:
    plain = _compressor(ordinary)
    halves = [[(w, len(plain(w))) for words in texts[h::2] for w in windows(words)] for h in (0, 1)]
    telling = [[w for w, _ in half] for half in halves]
    for _ in range(NARROWINGS):
        marked = [_compressor(_trained(FIRST_TOXIC_BYTES, now, TOXIC_SEGMENT) + ordinary) for now in telling]
        found = [[w for w, n in half if n - len(marked[1 - h](w)) >= GAINS[0]] for h, half in enumerate(halves)]
        telling = [new if len(new) >= LEAST_WINDOWS else old for new, old in zip(found, telling, strict=True)]
    return _trained(TOXIC_BYTES, telling[0] + telling[1], TOXIC_SEGMENT)


@dataclass
class ToxicityModel:
    ordinary: bytes
    toxic: bytes
    weights: list[float]
    base: float | None = None  # a fixed score, where nothing could be learned

    def compressors(self) -> tuple:
        return _compressor(self.ordinary), _compressor(self.toxic + self.ordinary)

    def features(self, text: str | None, pair: tuple) -> list[float]:
        plain, marked = pair
        counts, best, excess, n = dict.fromkeys(GAINS, 0), 0, 0, 0
        for w in windows(_words(text)):
            n += 1
            gain = len(plain(w)) - len(marked(w))
            if gain > 1:
                excess += gain - 1
                best = max(best, gain)
                for g in GAINS:
                    counts[g] += gain >= g
        n = max(n, 8)
        out = [best / 4, 2.5 * excess / n]
        for g in GAINS:
            out += [math.log1p(counts[g]), 10 * counts[g] / n]
        return out

    def score(self, text: str | None, pair: tuple) -> float:
        if self.base is not None:
            return self.base
        z = self.weights[0] + sum(a * b for a, b in zip(self.weights[1:], self.features(text, pair), strict=True))
        return 1 / (1 + math.exp(-max(-40.0, min(40.0, z))))


def fit(sample: list[tuple[int, int, str]]) -> ToxicityModel:
    """Dictionaries from fold 0, calibration on fold 2 (on all if one is empty)."""
    learn = {y: list(dict.fromkeys(t for f, v, t in sample if v == y and f == 0)) for y in (0, 1)}
    check = [(v, t) for f, v, t in sample if f == 2]
    if not learn[0] or not learn[1] or len({v for v, _ in check}) < 2:
        learn = {y: list(dict.fromkeys(t for _, v, t in sample if v == y)) for y in (0, 1)}
        check = [(v, t) for _, v, t in sample]
    if not learn[0] or not learn[1]:
        share = sum(v for _, v, _ in sample) / len(sample) if sample else 0.0
        return ToxicityModel(b"", b"", [], share)
    plain, toxic = ([_words(t) for t in learn[y]] for y in (0, 1))
    ordinary = _trained(ORDINARY_BYTES, [w for words in plain for w in windows(words)], ORDINARY_SEGMENT)
    model = ToxicityModel(ordinary, _toxic_dictionary(toxic, ordinary), [])
    pair = model.compressors()
    x = np.array([model.features(t, pair) for _, t in check])
    y = np.array([v for v, _ in check], dtype=float)
    w = _logistic(x, y)
    p = 1 / (1 + np.exp(-np.clip(np.c_[np.ones(len(x)), x] @ w, -40, 40)))
    w[0] += math.log(THRESHOLD / (1 - THRESHOLD)) - _best_cut(p, y)
    model.weights = w.tolist()
    return model


def _logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1.0, steps: int = 50) -> np.ndarray:
    a = np.c_[np.ones(len(x)), x]
    w = np.zeros(a.shape[1])
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(a @ w, -40, 40)))
        penalty = ridge * np.r_[0.0, np.ones(a.shape[1] - 1)]
        h = a.T @ (a * (p * (1 - p))[:, None]) + np.diag(penalty + 1e-6)
        w += np.linalg.solve(h, a.T @ (y - p) - penalty * w)
    return w


def _best_cut(p: np.ndarray, y: np.ndarray) -> float:
    """The log odds at which F1 is best, midway between neighbours."""
    z = np.log(np.clip(p, 1e-12, 1 - 1e-12) / np.clip(1 - p, 1e-12, 1))
    order = np.argsort(-z, kind="stable")
    hits = np.cumsum(y[order])
    f1 = 2 * hits / (np.arange(1, len(y) + 1) + y.sum())
    last = np.r_[z[order][1:] != z[order][:-1], True]  # ties stay together
    k = int(np.argmax(np.where(last, f1, -1)))
    return float((z[order][k] + (z[order][k + 1] if k + 1 < len(z) else z[order][k] - 1)) / 2)


def score_documents(docs: DataFrame, model: ToxicityModel, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, held_out, score, predicted) for each row, by its text alone."""
    blob = pickle.dumps(model)

    @F.pandas_udf("double")
    def score(texts: pd.Series) -> pd.Series:
        m = pickle.loads(blob)
        pair = m.compressors() if m.base is None else ()
        return pd.Series([m.score(t, pair) for t in texts], dtype=float)

    return docs.select(
        F.col(id_col).cast("long").alias("doc_id"), (fold(id_col) == HELD_OUT_FOLD).alias("held_out"), score(F.col(text_col)).alias("score")
    ).withColumn("predicted", (F.col("score") >= THRESHOLD).cast("int"))


def fit_documents(docs: DataFrame, labels: DataFrame, rows_per_class: int = ROWS_PER_CLASS) -> ToxicityModel:
    return fit(labelled_sample(docs, labels, "toxic", rows_per_class))


def drop_toxic(docs: DataFrame, model: ToxicityModel, text_col: str = "text") -> DataFrame:
    """``docs`` without the rows that score at or above the threshold; columns unchanged."""
    blob = pickle.dumps(model)

    @F.pandas_udf("boolean")
    def clean(parts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        spare()
        m = pickle.loads(blob)
        pair = m.compressors() if m.base is None else ()
        for texts in parts:
            yield pd.Series([m.score(t, pair) < THRESHOLD for t in texts], dtype=bool)
            del texts
        trim()

    return docs.where(clean(F.col(text_col)))


def op2_toxicity(spark, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    return score_documents(docs, fit_documents(docs, read_table(spark, sf_dir, "labels")))
