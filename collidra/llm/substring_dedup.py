"""Repeated passages: paragraphs collide by MinHash bands, are verified by exact Jaccard, and clustered by components.

A paragraph is a line of at least ``LEAST_WORDS`` words. Words are lower-cased, shingles have five words. Equal
paragraphs are one unit from the first shuffle on. ``tuned`` takes the longest bands that find a pair at the least
similarity with the chance ``RECALL`` within ``MINIMA`` minima. Units that share a band meet in a bucket, where all pairs
are compared exactly, unless links found before join them. A bucket of more than ``CELL_WORDS`` words is dealt to several
tasks in pairs of groups. No link in a bucket is lost.

A passage may also be repeated inside lines that differ around it. For that, texts are cut into short chunks before the
words whose hash is smallest in any ``WINDOW`` words in a row; such cuts depend on the nearest words only, so a passage has
the same ones wherever it stands, the first and the last less than a window from its ends. Chunks found in two documents
are joined to runs, which are reported from ``LEAST_WORDS`` words on: a passage of ``LEAST_WORDS`` + 2 ``WINDOW`` - 2 words
is never missed.

Defined results: null and empty texts have no paragraphs; each row with a null id is a document of its own; rows that
repeat an id are one document, its texts are told apart by their hash, and rows that repeat both are reported each; of a
cluster the occurrence with the smallest id (null last), text hash and place is kept; an empty table gives an empty
result; other columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .common import KEPT, cells, components, crowds, read_table, spare, trim, written
from .set_join import DEN, NUM, by_cell

SHINGLE, SIMILARITY = 5, NUM / DEN


def tuned(recall: float, minima: int, similarity: float = SIMILARITY) -> tuple[int, int]:
    """(bands, rows): the longest bands that find a pair of ``similarity`` with the chance ``recall`` within ``minima`` minima."""
    fits = [(math.ceil(math.log(1 - recall) / math.log(1 - similarity**r)), r) for r in range(1, minima + 1)]
    return max(((b, r) for b, r in fits if b * r <= minima), key=lambda x: x[1])


RECALL, MINIMA = 0.996, 24
BANDS, ROWS = tuned(RECALL, MINIMA)
LEAST_WORDS = 12
#: Words of a bucket that a task holds twice of.
CELL_WORDS = 500_000
#: Any so many words in a row have a cut.
WINDOW = 18
_rng = np.random.default_rng(11)
_MUL = _rng.integers(1, 2**63, BANDS * ROWS, dtype=np.uint64) | np.uint64(1)
_ADD = _rng.integers(0, 2**63, BANDS * ROWS, dtype=np.uint64)
_STEP, _MIX = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xD6E8FEB86659FD93)
_PART_WORDS, _KNOWN_WORDS = 100_000, 200_000


class _Known(dict):
    """Hashes of words met so far."""

    def __missing__(self, word: bytes) -> int:
        self[word] = found = xxhash.xxh64_intdigest(word)
        return found


_known = _Known()
KEPT.append(_known)


def _word_hashes(words: list[bytes]) -> np.ndarray:
    if len(_known) > _KNOWN_WORDS:
        _known.clear()
    return np.fromiter(map(_known.__getitem__, words), dtype=np.uint64, count=len(words))


def _rolled(h: np.ndarray, n: int) -> np.ndarray:
    """Hash of each n words in a row."""
    out = np.zeros(max(0, len(h) - n + 1), dtype=np.uint64)
    for i in range(n):
        out = out * _STEP + h[i : len(h) - n + 1 + i]
    out *= _MIX
    return out ^ (out >> np.uint64(32))


def _words(text: str) -> list[bytes]:
    return text.lower().encode("utf-8", "surrogatepass").split()


class Text:
    """Words of a text with their places and hashes."""

    def __init__(self, text: str | None):
        text = text or ""
        code = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), dtype="<u4")
        space = (code == 32) | ((code >= 9) & (code <= 13))
        edge = np.flatnonzero(np.diff(np.concatenate(([True], space, [True])).astype(np.int8)))
        self.start, self.end = edge[::2], edge[1::2]
        self.hashes = _word_hashes(_words(text))
        self.line = np.searchsorted(np.flatnonzero(code == 10), self.start)

    def lines(self) -> np.ndarray:
        """(paragraphs, 2): first and one past the last word of each."""
        cut = np.flatnonzero(np.diff(self.line)) + 1
        spans = np.stack([np.concatenate(([0], cut)), np.concatenate((cut, [len(self.line)]))], axis=1)
        return spans[spans[:, 1] - spans[:, 0] >= LEAST_WORDS]

    def chunks(self) -> np.ndarray:
        """(chunks, 2): first and one past the last word of each chunk between two cuts.

        Where one word only repeats, every place is smallest around; of such cuts one in a window is left.
        """
        h = self.hashes
        if len(h) < WINDOW:
            return np.zeros((0, 2), dtype=np.int64)
        pair = np.concatenate((h[:1], _rolled(h, 2)))  # a word with the one before it
        low = np.lib.stride_tricks.sliding_window_view(pair, WINDOW).argmin(axis=1)
        cut = np.unique(low + np.arange(len(low)))
        same = (pair[cut[1:]] == pair[cut[:-1]]) & (np.diff(cut) < WINDOW)
        if same.any():
            start = np.concatenate(([0], np.flatnonzero(~same) + 1))
            group = np.repeat(np.arange(len(start)), np.diff(np.concatenate((start, [len(cut)]))))
            turn = (cut - cut[start][group]) // WINDOW
            cut = cut[np.concatenate(([True], (group[1:] != group[:-1]) | (turn[1:] != turn[:-1])))]
        return np.stack([cut[:-1], cut[1:]], axis=1)

    def span_hashes(self, spans: np.ndarray) -> np.ndarray:
        """A hash of the words of each span, from sums of word hashes times powers by place."""
        if not len(spans):
            return np.zeros(0, dtype=np.int64)
        size = spans[:, 1] - spans[:, 0]
        power = np.multiply.accumulate(np.full(int(size.max()), _STEP))
        at = np.concatenate([[0], np.cumsum(size)[:-1]])
        inside = np.arange(int(size.sum())) - np.repeat(at, size)
        sums = np.add.reduceat(self.hashes[np.repeat(spans[:, 0], size) + inside] * power[inside], at) * _MIX
        sums = (sums ^ (sums >> np.uint64(29))) * _STEP + size.astype(np.uint64)
        return (sums ^ (sums >> np.uint64(32))).view(np.int64)


def paragraphs(text: str | None) -> list[tuple[int, int, list[bytes]]]:
    """(start, end, words) of each paragraph of a text."""
    t, words = Text(text), _words(text or "")
    return [(int(t.start[a]), int(t.end[b - 1]), words[a:b]) for a, b in t.lines().tolist()]


def shingle_hashes(words: list[bytes]) -> list[int]:
    return _rolled(_word_hashes(words), min(SHINGLE, len(words))).tolist()


def band_keys(hashes: np.ndarray, spans: np.ndarray) -> np.ndarray:
    """(len(spans), BANDS) keys of the paragraphs that the spans of word hashes are."""
    rolled = np.append(_rolled(hashes, SHINGLE), np.uint64(2**64 - 1))
    at = (spans + np.array([0, 1 - SHINGLE])).ravel()
    keys = np.zeros((len(spans), BANDS), dtype=np.uint64)
    for k in range(BANDS * ROWS):
        low = np.minimum.reduceat((rolled * _MUL[k] + _ADD[k]) ^ (rolled >> np.uint64(29)), at)[::2]
        keys[:, k // ROWS] = (keys[:, k // ROWS] ^ low) * _STEP
    return keys.view(np.int64)


NAMES = ["owner", "no_id", "th", "kind", "place", "start", "chars", "n_words", "unit"]
SCHEMA = "owner long, no_id boolean, th long, kind byte, place int, start int, chars int, n_words int, unit long, bands array<long>"
LINE, CHUNK = 0, 1


def _passages(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """Paragraphs with their band keys, and chunks, of all texts; a text is read once."""
    for pdf in parts:
        held: list[tuple] = []
        size = 0

        def full() -> pd.DataFrame:
            columns, bands, offset = [[] for _ in NAMES], [], 0
            lines, hashes = [], []
            for owner, no_id, th, t, spans, chunks in held:
                both = np.concatenate((spans, chunks))
                n = len(both)
                kind = np.repeat(np.array([LINE, CHUNK], dtype=np.int8), [len(spans), len(chunks)])
                place = np.concatenate((np.arange(len(spans)), np.arange(len(chunks))))
                start = t.start[both[:, 0]]
                row = (np.full(n, owner), np.full(n, no_id), np.full(n, th), kind, place, start, t.end[both[:, 1] - 1] - start, both[:, 1] - both[:, 0], t.span_hashes(both))
                for c, v in zip(columns, row, strict=True):
                    c.append(v)
                lines.append(spans + offset)
                hashes.append(t.hashes)
                offset += len(t.hashes)
            out = pd.DataFrame({n: np.concatenate(c) for n, c in zip(NAMES, columns, strict=True)})
            bands = np.full(len(out), None, dtype=object)
            at = np.flatnonzero(out["kind"].to_numpy() == LINE)
            if len(at):
                for j, row in zip(at.tolist(), band_keys(np.concatenate(hashes), np.concatenate(lines)), strict=True):
                    bands[j] = row
            out["bands"] = bands
            return out

        for owner, no_id, th, text in zip(pdf["owner"], pdf["no_id"], pdf["th"], pdf["text"], strict=True):
            t = Text(text)
            spans, chunks = t.lines(), t.chunks()
            if len(spans) or len(chunks):
                held.append((owner, no_id, th, t, spans, chunks))
                size += len(t.hashes)
            if size > _PART_WORDS:
                yield full()
                held, size = [], 0
        if held:
            yield full()
        del pdf
    trim()


def _shingles(words: str) -> np.ndarray:
    return np.unique(np.array(shingle_hashes(words.encode("utf-8", "surrogatepass").split(b"\x1f")), dtype=np.uint64))


def _meeting(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """Rows sorted by bucket, without those alone in theirs."""
    spare()
    last, sent = None, False
    for pdf in parts:
        if not len(pdf):
            continue
        if last is not None:
            pdf = pd.concat([last, pdf], ignore_index=True)
        k = pdf["key"].to_numpy()
        same = k[1:] == k[:-1]
        keep = np.concatenate(([False], same)) | np.concatenate((same, [False]))
        # the last row waits for the next batch; if it has met others here, it goes out now and only marks its bucket then
        yield pdf[keep & (np.arange(len(pdf)) >= (1 if last is not None and sent else 0))]
        last, sent = pdf.iloc[-1:].copy(), bool(keep[-1])
        del pdf
    trim()


def passages(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> tuple[DataFrame, DataFrame]:
    """The documents as (owner, no_id, th, text), and their paragraphs and chunks as a table in the shared folder.

    The owner is the id, or a number of the row, counted down from the largest, where there is none; th is the text's hash.
    """
    own = F.coalesce(F.col(id_col).cast("long"), F.lit(2**63 - 1) - F.monotonically_increasing_id())
    base = docs.select(own.alias("owner"), F.col(id_col).isNull().alias("no_id"), F.xxhash64(F.col(text_col)).alias("th"), F.col(text_col).alias("text"))
    return base, written(base.mapInPandas(_passages, SCHEMA), "passages")


def _words_of(base: DataFrame, spots: DataFrame) -> DataFrame:
    """(unit, words) for units with one place (owner, no_id, th, start, chars) each; rows without an id by their text alone."""
    key = F.when(F.col("no_id"), F.lit(None)).otherwise(F.col("owner"))
    at = spots.select("unit", "start", "chars", F.col("th").alias("at_th"), key.alias("at_owner"))
    texts = base.join(at, (F.col("th") == F.col("at_th")) & key.eqNullSafe(F.col("at_owner")))
    cut = texts.select("unit", F.expr("lower(substring(text, start + 1, chars))").alias("w")).select("unit", F.regexp_replace("w", "[\\x20\\x09-\\x0D]+", "\x1f").alias("words"))
    return cut.groupBy("unit").agg(F.min("words").alias("words"))


def similar_units(base: DataFrame, units: DataFrame, cell_words: int = CELL_WORDS) -> DataFrame:
    """Links (a, b) whose components are those of all similar units that share a band."""
    rows = units.select("unit", "n_words", "bands").dropDuplicates(["unit"]).select("unit", "n_words", F.posexplode("bands").alias("band", "value"))
    rows = rows.select("unit", "n_words", F.xxhash64("band", "value").alias("key"))
    meet = written(rows.repartition("key").sortWithinPartitions("key", "unit").mapInPandas(_meeting, "unit long, n_words int, key long"), "bands")
    spot = units.groupBy("unit").agg(F.min(F.struct("no_id", "owner", "th", "start", "chars")).alias("s")).select("unit", "s.*")
    words = _words_of(base, spot.join(meet.select("unit").distinct(), "unit", "left_semi"))
    dealt = cells(meet.join(words, "unit"), crowds(meet, cell_words, F.col("n_words")), F.xxhash64("unit", F.lit(3))).select("cell", "unit", "words")
    return dealt.repartition("cell").sortWithinPartitions("cell", "unit").mapInPandas(by_cell(_shingles, ["unit", "words"]), "a long, b long")


def repeated_paragraphs(base: DataFrame, found: DataFrame, across_documents: bool = True, **options) -> DataFrame:
    """One row per occurrence of a paragraph that others equal or resemble.

    doc_id, place (number of the paragraph in its text), start, chars (code points), n_words, cluster_id, occurrences,
    removed (all but the first occurrence of a cluster). With ``across_documents`` only clusters of two or more documents.
    """
    units = found.where(F.col("kind") == LINE).drop("kind")
    linked = components(similar_units(base, units, **options))
    member = units.drop("bands").join(linked.select(F.col("node").alias("unit"), "component"), "unit", "left").withColumn("cluster_id", F.coalesce("component", "unit"))
    place = F.struct("owner", "th", "place")
    stats = member.groupBy("cluster_id").agg(
        F.count("*").alias("occurrences"), F.min(place).alias("first"), F.min("owner").alias("low"), F.max("owner").alias("high")
    ).where("occurrences > 1")
    if across_documents:
        stats = stats.where("low <> high")
    return member.join(stats.select("cluster_id", "occurrences", "first"), "cluster_id").select(
        F.when(~F.col("no_id"), F.col("owner")).alias("doc_id"), "place", "start", "chars", "n_words", "cluster_id", "occurrences", (place != F.col("first")).alias("removed")
    )


def repeated_runs(found: DataFrame) -> DataFrame:
    """One row per run of chunks that other documents have too; columns as for paragraphs, place counts chunks.

    A chunk stays in the document with the smallest id (null last) and is removed from all others; a run of
    ``LEAST_WORDS`` is split where that changes, and parts shorter than that stay. Its cluster is its first chunk, its occurrences those of its rarest chunk.
    Chunks are counted per task before the shuffle; the repeated ones are a table, so that AQE can split the rows of a
    very common one in the join.
    """
    chunks = found.where(F.col("kind") == CHUNK).drop("kind", "bands").withColumnRenamed("unit", "chunk")
    often = chunks.groupBy("chunk").agg(F.min("owner").alias("first"), F.max("owner").alias("last"), F.count("*").alias("n")).where("first <> last").drop("last")
    rows = chunks.join(written(often, "often"), "chunk").withColumn("removed", F.col("owner") != F.col("first"))
    text = ["owner", "th"]
    once = rows.repartition(*text).dropDuplicates([*text, "place"])
    whole = once.withColumn("run", F.col("place") - F.row_number().over(W.partitionBy(*text).orderBy("place")))
    whole = whole.withColumn("total", F.sum("n_words").over(W.partitionBy(*text, "run"))).where(F.col("total") >= LEAST_WORDS)
    part = F.col("place") - F.row_number().over(W.partitionBy(*text, "run", "removed").orderBy("place"))
    runs = whole.withColumn("part", part).groupBy(*text, "no_id", "run", "removed", "part").agg(
        F.min("place").alias("place"), F.min("start").alias("start"), F.max(F.col("start") + F.col("chars")).alias("end"), F.sum("n_words").cast("int").alias("n_words"),
        F.min_by("chunk", "place").alias("cluster_id"), F.min("n").alias("occurrences"),
    )
    return runs.select(
        F.when(~F.col("no_id"), F.col("owner")).alias("doc_id"), "place", "start", (F.col("end") - F.col("start")).alias("chars"), "n_words", "cluster_id", "occurrences", (F.col("removed") & (F.col("n_words") >= LEAST_WORDS)).alias("removed")
    )


def repeated_passages(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """Paragraphs (kind ``line``) and runs inside lines (kind ``run``) that occur in two or more documents."""
    base, found = passages(docs, id_col, text_col)
    lines = repeated_paragraphs(base, found, **options).withColumn("kind", F.lit("line"))
    return lines.unionByName(repeated_runs(found).withColumn("kind", F.lit("run")))


def op3_substring_dedup(spark, sf_dir: str) -> DataFrame:
    return repeated_passages(read_table(spark, sf_dir, "documents"))
