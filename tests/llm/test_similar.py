"""Similar texts and links of fingerprints against brute force over all pairs."""

from __future__ import annotations

import duckdb
import numpy as np
import pandas as pd
import pytest

from collidra.llm import bpe, common, sampling, set_join, simhash, substring_dedup
from tests.llm.test_operators import docs_of, odd


def plain_set(text):
    words = (text or "").encode().lower().split()
    k = min(5, len(words))
    return frozenset(tuple(words[i : i + k]) for i in range(len(words) - k + 1)) or frozenset([()])


def plain_classes(texts: dict) -> dict:
    """Smallest id reachable over pairs of Jaccard similarity 0.8 or more."""
    sets, root = {d: plain_set(t) for d, t in texts.items()}, {d: d for d in texts}

    def find(d):
        while root[d] != d:
            d = root[d]
        return d

    ids = sorted(texts)
    for i, a in enumerate(ids):
        for b in ids[:i]:
            both = len(sets[a] & sets[b])
            if 9 * both >= 4 * (len(sets[a]) + len(sets[b])):
                x, y = sorted((find(a), find(b)))
                root[y] = x
    return {d: find(d) for d in ids}


def test_pipeline_stage_equals_brute_force(spark, small):
    import corpus_pipeline

    table = duckdb.sql(f"SELECT max(doc_id), text FROM '{small}/documents.parquet' GROUP BY text").fetchall()
    want = set(plain_classes(dict(table)).values())
    assert len(want) < len(table)
    docs = common.read_table(spark, small, "documents")
    stage = dict(corpus_pipeline.STAGES)["simhash"]
    got = stage(spark, docs.where(docs.doc_id.isin([d for d, _ in table])), small).collect()
    assert {r["doc_id"] for r in got} == want and len(got) == len(want)


@pytest.mark.parametrize("options", [{}, {"bucket_rows": 20, "cell_shingles": 600}])
def test_pairs_around_the_limit_and_crowds(spark, options):
    rng = np.random.default_rng(3)
    say = lambda n: rng.choice([f"w{i}" for i in range(3000)], n).tolist()
    shared, texts = say(60), []
    for _ in range(8):
        base = say(int(rng.integers(6, 150)))
        for _ in range(6):
            words = list(base)
            for at in rng.choice(len(words), int(rng.integers(0, 1 + len(words) // 20)), replace=False):
                words[at] = f"x{rng.integers(10**6)}"
            texts.append(" ".join(words))
    chain = say(80)
    for i in range(40):  # each a word off the one before
        chain = [*chain[:i], f"y{i}", *chain[i + 1 :]]
        texts.append(" ".join(chain))
    texts += [" ".join(shared + say(int(rng.integers(2, 30)))) for _ in range(60)]
    texts += ["", " \n", "one two", "One  two", "one two three"]
    texts = dict(enumerate(texts))
    got = {r["doc_id"]: r["component_id"] for r in simhash.similar_documents(docs_of(spark, list(texts.values())), **options).collect()}
    want = plain_classes(texts)
    assert sum(got[d] == want[d] for d in texts) >= len(texts) - 1 and 20 < len(set(want.values())) < len(texts) - 50
    assert all(got[d] >= want[d] for d in texts)  # nothing joins that should not


def test_odd_rows(spark):
    df = odd(spark)
    got = simhash.drop_similar(df)
    assert got.columns == df.columns
    assert sorted((r["doc_id"] or 0, r["text"] or "") for r in got.collect()) == [(0, "no id at all"), (1, ""), (3, "same text here."), (7, "word " * 30_000 + "end.")]
    assert simhash.drop_similar(df.limit(0)).count() == 0


def test_an_id_with_two_texts_loses_only_the_copy(spark):
    df = docs_of(spark, ["a b c d e f g h", "other words are in this one", "a b c d e f g h"], [1, 5, 5])
    for drop in (simhash.drop_similar, simhash.drop_near_duplicates):
        assert sorted((r["doc_id"], r["text"]) for r in drop(df).collect()) == [(1, "a b c d e f g h"), (5, "other words are in this one")]


@pytest.mark.parametrize("radius", [0, 1, 2, 3, 5])
@pytest.mark.parametrize("bucket_rows", [4096, 8])
def test_no_link_is_lost_at_any_radius(spark, radius, bucket_rows):
    rng = np.random.default_rng(radius)
    base = int(rng.integers(0, 2**62))
    values = sorted({base ^ (1 << int(b)) for b in range(40)} | {base ^ (1 << int(a)) ^ (1 << int(b)) for a, b in rng.integers(0, 64, (60, 2))} | set(rng.integers(0, 2**62, 50).tolist()))
    root = {v: v for v in values}

    def find(v):
        while root[v] != v:
            v = root[v]
        return v

    for i, a in enumerate(values):
        for b in values[:i]:
            if (a ^ b).bit_count() <= radius:
                x, y = sorted((find(a), find(b)))
                root[y] = x
    signed = lambda v: v - 2**64 if v >= 2**63 else v
    edges = simhash.fingerprint_edges(spark.createDataFrame([(signed(v),) for v in values], "fp long"), radius, bucket_rows)
    linked = {r["node"]: r["component"] for r in common.components(edges).collect()}
    classes = lambda of: {frozenset(v for v in values if of(v) == c) for c in map(of, values)}
    assert classes(lambda v: linked.get(signed(v), signed(v))) == classes(find)


def test_counters_equal_counted_bits():
    rng = np.random.default_rng(2)
    for words, radius in ((1, 0), (1, 2), (1, 7), (4, 63), (4, 100)):
        base = rng.integers(0, 2**63, (1, words), dtype=np.uint64)
        noise = np.bitwise_and.reduce(rng.integers(0, 2**63, (3, 300, words), dtype=np.uint64), axis=0)
        values = np.concatenate((base ^ noise, rng.integers(0, 2**63, (50, words), dtype=np.uint64)))
        low, high = np.zeros(len(values), dtype=int), np.arange(len(values))
        got = {(int(a), int(b)) for r, p in simhash.reachable(values, low, high, radius) for a, b in zip(r, p, strict=True)}
        far = np.bitwise_count(values[:, None] ^ values[None]).sum(axis=2)
        assert got == {(i, j) for i in range(len(values)) for j in range(i) if far[i, j] <= radius}


def test_links_still_moving_are_an_error(spark):
    with pytest.raises(RuntimeError):
        common.components(spark.createDataFrame([(i, i + 1) for i in range(500)], "a long, b long"), 2)


def test_sample_is_bounded_in_bytes(spark):
    docs = spark.createDataFrame([(i % 7, f"text {i} " + "w " * 500) for i in range(200)], "doc_id long, text string")
    labels = spark.createDataFrame([(i, i % 2) for i in range(7)] + [(None, 1), (3, None)], "doc_id long, toxic int")
    got = sampling.labelled_sample(docs, labels, "toxic", sample_bytes=2500)
    assert 0 < sum(len(t) for _, _, t in got) <= 2500
    assert len(sampling.labelled_sample(docs, labels, "toxic")) == sum(1 for i in range(7) if sampling_fold(i) != 1)
    assert sampling.labelled_sample(docs, labels.limit(0), "toxic") == []


def sampling_fold(i: int) -> int:
    import zlib

    return zlib.crc32(str(i).encode()) % 3


def test_buckets_go_across_batches():
    rng = np.random.default_rng(0)
    cell = np.sort(rng.integers(0, 60, 300))
    whole = pd.DataFrame({"cell": cell, "unit": np.arange(300)})
    cuts = [0, *sorted(rng.choice(np.arange(1, 300), 40, replace=False).tolist()), 300]
    parts = list(simhash._whole_buckets((whole.iloc[a:b] for a, b in zip(cuts, cuts[1:], strict=False)), ["cell", "unit"]))
    assert np.array_equal(np.concatenate(parts), whole.to_numpy())
    ends = [set(p[:, 0].tolist()) for p in parts]
    assert sum(map(len, ends)) == len(set(cell.tolist()))


def test_workers_do_not_keep_what_another_stage_held():
    """A worker that has encoded texts is used again by the next run's stages; the encoder's tables do not stay beside their work."""
    rows = pd.DataFrame({"unit": [1, 2], "key": [1, 1], "text": ["a b c d e f", "a b c d e g"]})
    tasks = [simhash._printed, simhash._shingled, simhash._compare(2, "fp", ["fp"]), set_join.by_cell(np.asarray, ["unit", "s"])]
    for task, part in zip(tasks, [rows, rows, pd.DataFrame({"cell": [1], "fp": [3]}), pd.DataFrame({"cell": [1], "unit": [1], "s": [[1, 2]]})], strict=True):
        bpe._encoder(bpe.vocabulary_path())
        list(task(iter([part])))
        assert not bpe._OPEN


def test_workers_do_not_keep_words_of_passages():
    """A worker that has cut texts into passages is used again by the next stages; the words it met do not stay beside their work."""
    text = " ".join(f"word{i}" for i in range(40))
    cut = list(substring_dedup._passages(iter([pd.DataFrame({"owner": [1], "no_id": [False], "th": [1], "text": [text]})])))
    assert len(cut[0]) and substring_dedup._known
    met = list(substring_dedup._meeting(iter([pd.DataFrame({"unit": [1, 2], "n_words": [12, 12], "key": [1, 1]})])))
    assert len(met[0]) == 2 and not substring_dedup._known
    words = text.replace(" ", "\x1f")
    links = list(set_join.by_cell(substring_dedup._shingles, ["unit", "words"])(iter([pd.DataFrame({"cell": [1, 1], "unit": [1, 2], "words": [words, words]})])))
    assert len(links[0]) == 1 and not substring_dedup._known
