"""A corpus from documents to token ids, in stages.

Each stage takes all rows that the one before kept and is written as Parquet before the next reads it. All but the last
return the columns of ``documents``.

1. toxicity: documents whose compression-distance score reaches the threshold go.
2. exact dedup: of equal texts the row with the largest id stays.
3. near dedup: SimHash candidates, bit-sliced and verified by exact Jaccard similarity of 0.8 of five-word shingles; of
   each class the smallest id stays. The rule of ``op7_simhash`` (two bits of 64) is that query's own; it would keep
   nearly all such near copies.
4. mixing: a row is repeated as often as the mix to target weights takes it.
5. encoding: token counts and digests of ids and of the decoded text, a row per row.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from collidra.llm import bpe, exact_dedup, mixing, simhash, toxicity
from collidra.llm.common import read_table, remove, tables_made, written


_spent: list[str] = []


def stage(make):
    """A stage that first removes the tables which the one before left: its result has been written and read again."""

    def run_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        remove(spark, _spent)
        _spent.clear()
        before = len(tables_made())
        out = make(spark, docs, sf_dir)
        _spent.extend(tables_made()[before:])
        return out

    return run_stage


@stage
def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return toxicity.drop_toxic(docs, toxicity.fit_documents(docs, read_table(spark, sf_dir, "labels")))


@stage
def drop_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return exact_dedup.drop_duplicates(docs)


@stage
def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return simhash.drop_similar(docs)


@stage
def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.repeat_rows(docs)


@stage
def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return bpe.digest_documents(docs)


STAGES = [
    ("toxicity", drop_toxic),
    ("exact_dedup", drop_copies),
    ("simhash", drop_near_copies),
    ("mixing", mix_sources),
    ("bpe", encode),
]

#: Scores, fingerprints, random rounding and encoding are not SQL; tests hold each stage against a plain version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read_table(spark, sf_dir, "documents")
    for name, apply in STAGES:
        rows = apply(spark, rows, sf_dir)
        if name != STAGES[-1][0]:
            rows = written(rows, f"stage-{name}")
    return rows
