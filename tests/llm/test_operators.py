"""Corpus operators against plain versions, exact round trips and held-out labels; and their edge cases."""

from __future__ import annotations

import hashlib
import re
import zlib
from collections import Counter, defaultdict

import duckdb
import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from collidra.llm import bpe, common, exact_dedup, html_text, mixing, paragraph_sketch, quality, registry, sharding, simhash, substring_dedup, toxicity
from tests.conftest import same_rows

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
WORDS = re.compile(r"[^\x20\x09-\x0D]+")


@pytest.fixture(scope="module")
def documents(small):
    return duckdb.sql(f"SELECT doc_id, text, lang, source, n_chars FROM '{small}/documents.parquet'").fetchall()


def docs_of(spark, texts, ids=None, sources=None):
    rows = [(i if ids is None else ids[i], t, "en", None if sources is None else sources[i], len(t or "")) for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, DOCS)


def odd(spark):
    """Nulls, empties, a long text, ties, repeated rows, and columns with names that operators use inside."""
    long = "word " * 30_000 + "end."
    rows = [(1, None, None, None), (2, "", "s", 0), (3, "same text here.", "s", 5), (4, "same text here.", None, 5), (4, "same text here.", None, 5), (None, "no id at all", "t", 1), (7, long, "t", None), (8, "   \n ", "t", 2)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string, n_chars long")
    clash = {c: F.lit(1) for c in ("body", "key", "cell", "bucket", "shard", "slot", "size", "fp", "block", "unit", "h", "range", "tie", "p", "_k", "row", "digest", "component", "draw", "copies")}
    return df.withColumns(clash)


def empty(spark):
    return spark.createDataFrame([], DOCS)


# ---------------------------------------------------------------- all operators on odd input

CALLS = {
    "sketch": lambda d: paragraph_sketch.compare_with_edit_and_next(d),
    "passages": lambda d: substring_dedup.repeated_passages(d),
    "mix": lambda d: mixing.mix(d),
    "repeat": lambda d: mixing.repeat_rows(d),
    "shards": lambda d: sharding.shard_rows(d),
    "simhash": lambda d: simhash.near_duplicates(d),
    "drop_near": lambda d: simhash.drop_near_duplicates(d),
    "similar": lambda d: simhash.similar_documents(d),
    "drop_similar": lambda d: simhash.drop_similar(d),
    "exact": lambda d: exact_dedup.find_duplicates(d),
    "drop_exact": lambda d: exact_dedup.drop_duplicates(d),
    "bpe": lambda d: bpe.digest_documents(d),
    "ids": lambda d: bpe.encode_documents(d),
    "toxicity": lambda d: toxicity.score_documents(d, toxicity.fit([])),
    "quality": lambda d: quality.score_documents(d, quality.fit([])),
}
PER_ROW = {"sketch", "mix", "shards", "simhash", "similar", "exact", "bpe", "ids", "toxicity", "quality"}


@pytest.mark.parametrize("name", sorted(CALLS))
def test_odd_and_empty_tables(name, spark):
    got = CALLS[name](odd(spark)).collect()
    if name in PER_ROW:
        assert len(got) == 8
    assert CALLS[name](empty(spark)).count() == 0


def test_odd_rows_have_the_stated_results(spark):
    d = odd(spark)
    dup = {(r["doc_id"], r["keep_id"], r["group_size"], r["kept"]) for r in exact_dedup.find_duplicates(d).collect()}
    assert {(1, 2, 2, False), (2, 2, 2, True), (3, 4, 3, False), (4, 4, 3, True), (None, None, 1, True)} <= dup
    stay = exact_dedup.drop_duplicates(d)
    assert stay.count() == 5 and stay.columns == d.columns
    near = {r["doc_id"]: r["component_id"] for r in simhash.near_duplicates(d).collect()}
    assert near[1] == near[2] == near[8] == 1 and near[3] == near[4] == 3
    shards = sharding.shard_rows(d).collect()
    assert len({r["shard"] for r in shards if r["doc_id"] in (3, 4)}) == 1
    taken = {r["doc_id"]: (r["size"], r["taken"]) for r in mixing.mix(d).collect()}
    assert taken[1] == (0, 0) and taken[2] == (0, 0) and taken[8] == (0, 0) and taken[7][0] == 30_001
    assert {r["doc_id"]: r["n_tokens"] for r in bpe.digest_documents(d).collect()}[1] == 0


# ---------------------------------------------------------------- 1 sketches


def test_sketch_follows_the_edit_rule(spark, small, documents):
    got = {r["doc_id"]: r for r in registry.QUERIES["op1_paragraph_sketch"](spark, small).collect()}
    order = sorted(documents, key=lambda r: -r[0])
    near = []
    for i, (doc, text, *_) in enumerate(order):
        follow = order[(i + 1) % len(order)][1]
        n = len(text)
        edited = text[: n - n // 3] + follow[: n // 3]
        r = got[doc]
        assert r["n_chars"] == n and r["edited_sha256"] == hashlib.sha256(edited.encode()).hexdigest()
        assert 0 <= r["near_edited"] <= 1 and 0 <= r["near_next"] <= 1
        if text == edited:
            assert r["near_edited"] == 1 and r["fingerprint"] == r["edited_fingerprint"]
        if text == follow:
            assert r["near_next"] == 1
        elif n > 200:
            near.append((r["near_edited"], r["near_next"]))
    assert np.mean([a for a, _ in near]) > 0.5 > 0.1 > np.mean([b for _, b in near])
    by_text = defaultdict(set)
    for doc, text, *_ in documents:
        by_text[text].add(got[doc]["fingerprint"])
    assert all(len(v) == 1 for v in by_text.values())


def plain_digests(text):
    return {p.strip(" ") for p in re.split(r"[\r\n]+|(?<=[.!?])[ \t]+", text) if p.strip(" ")}


def test_likeness_equals_sets_of_paragraphs(spark, small, documents):
    got = {r["doc_id"]: r for r in registry.QUERIES["op1_paragraph_sketch"](spark, small).collect()}
    order = sorted(documents, key=lambda r: -r[0])
    like = lambda a, b: 1 - len(a ^ b) / (len(a) + len(b)) if a or b else 1.0
    for i, (doc, text, *_) in enumerate(order):
        follow = order[(i + 1) % len(order)][1]
        edited = text[: len(text) - len(text) // 3] + follow[: len(text) // 3]
        sets = [plain_digests(t) for t in (text, edited, follow)]
        if max(len(p) for s in sets for p in s | {""}) <= paragraph_sketch.MOST_CHARS:
            assert got[doc]["near_edited"] == pytest.approx(like(sets[0], sets[1])) and got[doc]["near_next"] == pytest.approx(like(sets[0], sets[2]))
            assert got[doc]["fingerprint"].startswith(f"{len(sets[0])}:")


def test_paragraphs_do_not_depend_on_how_they_are_set(spark):
    say = [f"Sentence number {i} says something." for i in range(60)]
    other = [*say[:7], "Another one.", *say[8:]]
    rows = [(3, " ".join(say)), (2, "\r\n".join(say)), (1, "  \n\n".join(other)), (0, " ".join(other * 500))]
    got = {r["doc_id"]: r["near_next"] for r in paragraph_sketch.compare_with_edit_and_next(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got[3] == 1 and got[2] == pytest.approx(1 - 2 / 120) and got[1] == 1


def test_long_texts_are_compared_in_linear_time(spark):
    text = lambda n, k: " ".join(f"Sentence {i} of {k if i % 3 == 0 else 'all'}." for i in range(n))
    rows = [(1, text(9000, "one")), (0, text(9000, "two")), (-1, "no end of a sentence " * 5000)]
    got = {r["doc_id"]: r["near_next"] for r in paragraph_sketch.compare_with_edit_and_next(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got[1] == pytest.approx(2 / 3, abs=1e-3) and got[0] == 0


@pytest.mark.parametrize("shared", [0, 3, 40, 900])
def test_peeling_recovers_the_difference(spark, shared):
    rng = np.random.default_rng(shared)
    rows = []
    for k in range(60):
        base = rng.integers(-(2**62), 2**62, shared + 30).tolist()
        cut = int(rng.integers(0, 15))
        a, b = base[: shared + cut], base[:shared] + base[shared + 15 : shared + 15 + cut]
        rows.append((k, a, b, sorted(set(a) ^ set(b))))
    df = spark.createDataFrame(rows, "k long, a array<long>, b array<long>, want array<long>")
    small_first = paragraph_sketch.differing("a", "b", paragraph_sketch.sketch("a", "24", 1), paragraph_sketch.sketch("b", "24", 1))
    got = df.select("want", F.expr(small_first).alias("d"), F.expr(paragraph_sketch.differing("a", "b")).alias("e"))
    assert all(sorted(r["d"]) == r["want"] == sorted(r["e"]) for r in got.collect())


# ---------------------------------------------------------------- 2 and 8 classifiers


def held_out(spark, folder, name, label):
    """(predicted, label, lang) of the labelled rows of the held-out fold."""
    got = {r["doc_id"]: r for r in registry.QUERIES[name](spark, folder).collect()}
    labels = duckdb.sql(f"SELECT doc_id, {label}, lang FROM '{folder}/labels.parquet' JOIN '{folder}/documents.parquet' USING (doc_id)").fetchall()
    assert all(r["held_out"] == (zlib.crc32(str(i).encode()) % 3 == 1) and 0 <= r["score"] <= 1 for i, r in got.items())
    return [(got[i]["predicted"], y, lang) for i, y, lang in labels if got[i]["held_out"]]


def test_quality_on_the_held_out_fold(spark):
    held = held_out(spark, "/root/testdata/sf0.01", "op8_quality", "quality")
    assert sum(p == y for p, y, _ in held) / len(held) >= 0.95


def test_toxicity_on_the_held_out_fold(spark):
    held = held_out(spark, "/root/testdata/sf0.1", "op2_toxicity", "toxic")
    found, missed, false, clean = (sum(p == a and y == b for p, y, _ in held) for a, b in ((1, 1), (0, 1), (1, 0), (0, 0)))
    english = [p for p, y, lang in held if y and lang == "en"]
    assert sum(english) / len(english) >= 0.8 and found / (found + false) >= 0.8 and clean / (clean + false) >= 0.98


def test_toxic_words_decide_and_not_the_id():
    rng = np.random.default_rng(0)
    words = ["".join(rng.choice(list("aeioudnrst"), 5)) for _ in range(400)]
    text = lambda bad: " ".join([*rng.choice(words, 60), *(["vilegrub"] * bad)])
    sample = [(f, y, text(3 * y)) for f in (0, 2) for y in (0, 1) for _ in range(60)]
    model = toxicity.fit(sample)
    pair = model.compressors()
    assert np.mean([model.score(text(3), pair) >= 0.7 for _ in range(50)]) > 0.9
    assert np.mean([model.score(text(0), pair) >= 0.7 for _ in range(50)]) < 0.1
    assert model.score(None, pair) == model.score("", pair) < 0.7


def test_repeated_lines_do_not_end_the_training_of_a_dictionary():
    rng = np.random.default_rng(2)
    words = ["".join(rng.choice(list("aeioudnrst"), 6)) for _ in range(3000)]
    texts = [["the", "same", "line", "again"] * 2000] + [list(rng.choice(words, 80)) for _ in range(800)]
    samples = [w for t in texts for w in toxicity.windows([x.encode() for x in t])]
    assert len(toxicity._trained(32 << 10, samples, toxicity.ORDINARY_SEGMENT)) > 24 << 10


def test_network_reads_to_the_last_byte():
    rng = np.random.default_rng(1)
    clean = lambda n: "".join(rng.choice(list("abcdefgh "), n))
    sample = [(0, 1, clean(900)) for _ in range(80)] + [(0, 0, clean(300) + "%%$#!! " * 90) for _ in range(80)]
    model = quality.fit(sample, 0.5)
    assert model.score(clean(5000)) > 0.5 > model.score(clean(100) + "%%$#!! " * 700)
    tail = quality.features(model.table, clean(70_000) + "%%$#!! " * 30)
    assert not np.allclose(tail, quality.features(model.table, clean(70_000)))


# ---------------------------------------------------------------- 3 passages


def test_passages_equal_a_plain_join(spark, small, documents):
    units = [(d, k, tuple(w)) for d, t, *_ in documents for k, (_, _, w) in enumerate(substring_dedup.paragraphs(t))]
    shingles = {u: frozenset(substring_dedup.shingle_hashes(list(u))) for _, _, u in units}
    different = sorted(shingles)
    parent = {u: u for u in different}

    def root(u):
        while parent[u] != u:
            u = parent[u]
        return u

    meet = defaultdict(set)
    for u in different:
        for s in shingles[u]:
            meet[s].add(u)
    for group in meet.values():
        for a in group:
            for b in group:
                if a < b and 9 * len(shingles[a] & shingles[b]) >= 4 * (len(shingles[a]) + len(shingles[b])):
                    parent[root(a)] = root(b)
    clusters = defaultdict(set)
    for d, k, u in units:
        clusters[root(u)].add((d, k))
    want = {frozenset(c) for c in clusters.values() if len({d for d, _ in c}) > 1}
    got = defaultdict(set)
    for r in registry.QUERIES["op3_substring_dedup"](spark, small).where("kind = 'line'").collect():
        got[r["cluster_id"]].add((r["doc_id"], r["place"]))
    found = {frozenset(c) for c in got.values()}
    assert want and len(found & want) / len(want) > 0.97 and len(found - want) <= 0.03 * len(want)


def test_passage_inside_different_lines_is_found(spark):
    rng = np.random.default_rng(4)
    say = lambda n: " ".join("".join(rng.choice(list("abcdefghij"), 6)) for _ in range(n)) + ". "
    shared = "".join(say(9) for _ in range(14))
    texts = [say(30) + say(35) + shared + say(40), say(90) + shared + say(20) + say(12), say(150), say(60) + "\n" + say(70)]
    got = substring_dedup.repeated_passages(docs_of(spark, texts)).collect()
    assert {r["doc_id"] for r in got} == {0, 1}
    assert all(r["kind"] == "run" and texts[r["doc_id"]][r["start"] : r["start"] + r["chars"]] in shared for r in got)
    assert {r["doc_id"] for r in got if r["removed"]} == {1} and sum(r["n_words"] for r in got if r["removed"]) > 90


def test_every_passage_of_46_words_inside_lines_is_found(spark):
    """LEAST_WORDS + 2 WINDOW - 2 words are a guarantee; runs tell their place to within a window at either end."""
    rng = np.random.default_rng(9)
    say = lambda n: " ".join(f"{x:x}" for x in rng.integers(0, 5000, n))
    least = substring_dedup.LEAST_WORDS + 2 * substring_dedup.WINDOW - 2
    shared = [say(least) for _ in range(300)]
    texts = [f"{say(int(rng.integers(30, 60)))} {p} {say(int(rng.integers(30, 60)))}" for _ in (0, 1) for p in shared]
    got = substring_dedup.repeated_passages(docs_of(spark, texts)).where("kind = 'run'").collect()
    assert {r["doc_id"] for r in got} == set(range(600)) and {r["doc_id"] for r in got if r["removed"]} == set(range(300, 600))
    assert all(texts[r["doc_id"]][r["start"] : r["start"] + r["chars"]] in shared[r["doc_id"] % 300] for r in got)
    words = Counter()
    for r in got:
        words[r["doc_id"]] += r["n_words"]
    assert min(words.values()) >= substring_dedup.LEAST_WORDS


def test_runs_are_measured_before_they_are_split(spark):
    rng = np.random.default_rng(3)
    say = lambda n: " ".join(f"{x:x}" for x in rng.integers(0, 5000, n))
    left, middle, right = say(30), say(8), say(30)
    texts = [f"{say(40)} {middle} {say(40)}", f"{say(30)} {left} {middle} {right} {say(30)}", f"{say(50)} {left} {middle} {right} {say(20)}"]
    got = [r for r in substring_dedup.repeated_passages(docs_of(spark, texts)).collect() if r["doc_id"] == 2]
    assert sum(r["n_words"] for r in got) >= 68 - 2 * substring_dedup.WINDOW and all(r["removed"] for r in got)


def test_low_entropy_text_makes_few_chunks():
    assert len(substring_dedup.Text("word " * 30_000).chunks()) <= 30_000 / substring_dedup.WINDOW + 1


def test_null_and_repeated_ids_keep_their_links(spark):
    rng = np.random.default_rng(1)
    say = lambda n: " ".join(f"{x:x}" for x in rng.integers(0, 10**6, n))
    one, two = say(30), say(30)
    near = " ".join([*two.split()[:-1], "other"])
    rows = [(None, one), (None, one), (None, f"{say(20)}\n{one}"), (1, say(20) + "\n" + one), (1, two), (2, near), (3, near), (3, near)]
    got = substring_dedup.repeated_passages(spark.createDataFrame(rows, "doc_id long, text string")).where("kind = 'line'").collect()
    by = defaultdict(list)
    for r in got:
        by[r["cluster_id"]].append((r["doc_id"], r["removed"]))
    first, second = sorted(by.values(), key=len)[::-1] if len(by) == 2 else (None, None)
    assert sorted(map(str, first)) == sorted(map(str, [(1, False), (2, True), (3, True), (3, True)])) or sorted(map(str, first)) == sorted(map(str, [(1, False), (None, True), (None, True), (None, True)]))
    assert len(first) == len(second) == 4 and sum(not x for _, x in first) == sum(not x for _, x in second) == 1
    runs = substring_dedup.repeated_passages(spark.createDataFrame([(None, f"{say(40)} {one} {two} {say(40)}") for _ in range(3)], "doc_id long, text string")).where("kind = 'run'").collect()
    assert sum(not r["removed"] for r in runs) == 1 and sum(r["removed"] for r in runs) == 2


def test_rows_alone_in_their_bucket_go_across_batches():
    import pandas as pd

    rng = np.random.default_rng(0)
    keys = np.sort(rng.integers(0, 400, 600))
    whole = pd.DataFrame({"unit": np.arange(600), "key": keys})
    cuts = [0, *sorted(rng.choice(np.arange(1, 600), 40, replace=False).tolist()), 600]
    got = pd.concat(substring_dedup._meeting(whole.iloc[a:b].reset_index(drop=True) for a, b in zip(cuts, cuts[1:], strict=False)))
    assert sorted(got["unit"]) == whole["unit"][whole.duplicated("key", keep=False)].tolist()


def versions(rng, groups: int, each: int) -> list[str]:
    """Lines of which each is some words off an earlier one of its group."""
    out = []
    for g in range(groups):
        lines = [[f"{g}w{x}" for x in rng.integers(0, 10**6, 60)]]
        while len(lines) < each:
            words = list(lines[int(rng.integers(len(lines)))])
            for _ in range(int(rng.integers(1, 3))):
                words[int(rng.integers(60))] = f"x{rng.integers(10**6)}"
            lines.append(words)
        out += [" ".join(w) for w in lines]
    return out


def test_crowded_buckets_lose_no_link(spark):
    """All pairs against the links of one task, and against the operator with buckets dealt to many tasks."""
    rng = np.random.default_rng(6)
    lines = versions(rng, 4, 150)
    sets = [frozenset(substring_dedup.shingle_hashes(x.encode().split())) for x in lines]
    parent = list(range(len(lines)))

    def root(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i in range(len(lines)):
        for j in range(i):
            if 9 * len(sets[i] & sets[j]) >= 4 * (len(sets[i]) + len(sets[j])):
                parent[root(i)] = root(j)
    want = {frozenset(i for i in range(len(lines)) if root(i) == r) for r in map(root, range(len(lines)))}
    for options in ({"cell_words": 3000}, {}):
        got = defaultdict(set)
        for r in substring_dedup.repeated_passages(docs_of(spark, lines), **options).where("kind = 'line'").collect():
            got[r["cluster_id"]].add(r["doc_id"])
        assert {x for x in want if len(x) > 1} == {frozenset(x) for x in got.values()}


@pytest.mark.parametrize("seed", range(6))
def test_links_within_a_task_equal_all_pairs(seed):
    from collidra.llm import set_join

    rng = np.random.default_rng(seed)
    sets = [np.zeros(0, dtype=np.uint64)] * 2 if seed == 5 else []
    while len(sets) < 400:
        base = rng.choice(4000 if seed % 2 else 120, int(rng.integers(1, 60)), replace=False)
        for _ in range(int(rng.integers(1, 90))):
            change = rng.random(len(base)) < rng.choice([0, 0.03, 0.1])
            sets.append(np.unique(np.where(change, rng.integers(0, 4000, len(base)), base)).astype(np.uint64))
    sets = [sets[i] for i in rng.permutation(len(sets))]
    links = set_join.links_within(sets)
    plain = [frozenset(s.tolist()) for s in sets]
    similar = lambda i, j: 9 * len(plain[i] & plain[j]) >= 4 * (len(plain[i]) + len(plain[j]))
    assert all(similar(i, j) for i, j in links) and len(links) < len(sets)

    def classes(pairs):
        parent = list(range(len(sets)))

        def root(i):
            while parent[i] != i:
                i = parent[i]
            return i

        for i, j in pairs:
            parent[max(root(i), root(j))] = min(root(i), root(j))
        return [root(i) for i in range(len(sets))]

    want = classes([(i, j) for i in range(len(sets)) for j in range(i) if similar(i, j)])
    got = classes(links)
    assert all((want[i] == want[j]) == (got[i] == got[j]) for i in range(len(sets)) for j in range(i))


def test_bands_are_tuned_for_recall():
    for recall in (0.9, 0.99, 0.999):
        bands, rows = substring_dedup.tuned(recall, 40)
        assert bands * rows <= 40 and 1 - (1 - 0.8**rows) ** bands >= recall
    assert (substring_dedup.BANDS, substring_dedup.ROWS) == (8, 3)


# ---------------------------------------------------------------- 4 pages

PAGE = """<!doctype html><html><head><title>T</title><style>p{{}}</style></head><body><header><div class="logo">Site</div></header>
<div id="cookie-notice">We use cookies</div><nav><ul><li><a href="/">Home</a></li></ul></nav><div class="w9">Follow our {0} channel</div>
<article><h1>Head &amp; line</h1><p>One   <b>two</b>
three&nbsp;&#52;<p>Next &lt;tag&gt; &am</p><div class="share-buttons">Share</div><ul><li>a<li>b</ul><div class="comments"><p>nice</p></div></article>
<aside>More</aside><form><input value="x"><label>Mail</label></form><script>var p="<p>no</p>";</script><footer>&copy; us</footer></body></html>"""


def test_article_without_the_rest():
    assert html_text.main_text(PAGE.format("x")) == "Head & line\n\nOne two three 4\n\nNext <tag> &am\n\na\n\nb"
    assert html_text.main_text(None) == html_text.main_text("") == ""
    assert html_text.main_text("plain text  only") == "plain text only"
    assert html_text.main_text("<p>cut <b>off") == "cut off"


def test_recurring_subtrees_of_a_host_go(spark):
    page = lambda i, host: (i, f"http://{host}/p{i}", f"<html><body><div class='w9'>Subscribe to all our channels</div><div><p>Story number {i} of {host}.</p><p>common words</p></div></body></html>")
    df = spark.createDataFrame([page(i, "a.example") for i in range(12)] + [page(20, "b.example"), (30, None, None), (31, "bad url", "<p>x</p>")], "page_id long, url string, html string")
    got = {r["page_id"]: r for r in html_text.extract(df).collect()}
    assert "Subscribe" not in got[3]["text"] and "Story number 3" in got[3]["text"]
    assert "Subscribe" in got[20]["text"]  # a single page tells nothing about its site
    assert got[30]["text"] == "" and got[30]["n_chars"] == 0 and got[31]["text"] == "x"


def test_given_pages(spark, small):
    import html

    rows = {r["page_id"]: r["text"] for r in registry.QUERIES["op4_html_text"](spark, small).collect()}
    for page, src in duckdb.sql(f"SELECT page_id, html FROM '{small}/pages.parquet'").fetchall():
        inner = re.search(r"<article>(.*?)(?:</article>|$)", src, re.S)[1]
        blocks = [re.sub(r"\s+", " ", html.unescape(re.sub(r"<[^>]*>", "", b))).strip() for b in re.split(r"</?(?:p|h1)>", inner)]
        assert rows[page] == "\n\n".join(b for b in blocks if b)


BROKEN = {
    '<article><div class="post-header"><h1>Title</h1></div><p class="side-by-side">A</p><p id="form-factor">B</p></article>': "Title\n\nA\n\nB",
    "<p data=it's>Text one</p><p>don't go</p><p>end</p>": "Text one\n\ndon't go\n\nend",
    'x <a title="unclosed>link': "x",
    "a &lt <b>c</i> d": "a < c d",
    "1 < 2 and </3> <p/>x<br/>y": "1 < 2 and\n\nx y",
    "<table><tr><td>a<td>b<tr><td>c</table>": "a\n\nb\n\nc",
    "<ul><li>a<ul><li>b</ul><li>c</ul>": "a\n\nb\n\nc",
    "<!-->x<!-- y --!>z<!-- q": "xz",
    "<div><p>one<div>two</p>three</div>": "one\n\ntwo\n\nthree",
}


@pytest.mark.parametrize("page", sorted(BROKEN))
def test_broken_pages(page):
    assert html_text.main_text(page) == BROKEN[page]


def test_deep_pages_take_linear_time():
    import time

    def seconds(make, n):
        began = time.process_time()
        html_text.main_text(make(n))
        return time.process_time() - began

    for make in (
        lambda n: "<div>" * n + "x" + "</span>" * n + "</div>" * n, lambda n: "<b>" * n + "<p>x" * n + "</b>" * n,
        lambda n: "<ul>" + "<div>" * n + "<td>x</td>" * n, lambda n: "<article>" * n + "x",
    ):
        seconds(make, 500)
        assert seconds(make, 16_000) < 12 * max(seconds(make, 4_000), 0.02)


def test_subtree_counts_equal_a_plain_recount(spark):
    """By site templates alone, without articles and tag rules, most given pages come out right."""
    folder = "/root/testdata/sf0.1"
    pages = common.read_table(spark, folder, "pages")
    got = {(r["host"], r["path"], r["content"]): r["pages"] for r in html_text.subtree_counts(pages).collect()}
    rows = [(r["host"], r["html"]) for r in pages.select(html_text.host_of("url").alias("host"), "html").distinct().collect()]
    counts, by_host = Counter(), Counter()
    for host, source in rows:
        page = html_text.Page(source)
        counts.update({(host, page.path[k], page.content[k]) for k in page.counted()} | {(host, 0, 0)})
        by_host[host] += 1
    assert got == dict(counts)
    hashes, slots = defaultdict(set), defaultdict(set)
    total, by_path, again = Counter(), Counter(), Counter()
    for (host, path, content), n in counts.items():
        if path:
            total[host, content] += n
            by_path[host, path] += n
            again[host, path] += n if n > 1 else 0
    for (host, content), n in total.items():
        if n >= 4 and n >= 0.01 * by_host[host]:
            hashes[host].add(content)
    for (host, path), n in by_path.items():
        if again[host, path] >= 4 and again[host, path] >= 0.2 * n and n >= 0.05 * by_host[host]:
            slots[host].add(path)
    sites = {r["host"]: (set(r["hashes"]), set(r["slots"])) for r in html_text.site_templates(pages).collect()}
    assert sites == {h: (hashes[h], slots[h]) for h in set(hashes) | set(slots)}
    full = {r["url"]: r["text"] for r in html_text.extract(pages).collect()}
    right = changed = 0
    for url, host, source in pages.select("url", html_text.host_of("url").alias("host"), "html").collect():
        page = html_text.Page(source)
        gone = page.template(frozenset(hashes[host]), frozenset(slots[host]))
        alone = page.text(gone, by_tags=False)
        changed += alone != page.text(by_tags=False)
        right += alone == full[url]
    assert changed > 0.9 * len(rows) and right > 0.9 * len(rows)


def test_copies_of_a_page_are_no_site(spark):
    story = "<div class='body'><p>The only story there is.</p></div><div class='x'>More</div>"
    df = spark.createDataFrame([(i, "http://a.example/", story) for i in range(50)], "page_id long, url string, html string")
    assert {r["text"] for r in html_text.extract(df).collect()} == {"The only story there is.\n\nMore"}


def test_slots_go_whole_and_long_text_stays(spark):
    """Adverts from a pool go, those seen once too; a slot that holds most of a page's text does not."""
    page = lambda i: f"<body><div class='slot'>Advert {min(i % 7, i % 5)}</div><div class='story'>{'Copied story with many words. ' * 4 if i % 2 else f'Story {i} of its own, with words. ' * 4}</div><i>{i}</i></body>"
    rows = [(i, f"http://a.example/{i}", page(i)) for i in range(20)] + [(20, "http://a.example/20", page(0).replace("Advert 0", "Advert seen once"))]
    got = {r["page_id"]: r["text"] for r in html_text.extract(spark.createDataFrame(rows, "page_id long, url string, html string"), content_share=2.0).collect()}
    assert all("Advert" not in t and "tory" in t for t in got.values())


def test_odd_pages(spark):
    rows = [(1, None, None), (2, "", ""), (3, "http://a/", "<p>x</p>"), (3, "http://a/", "<p>x</p>"), (None, "no url", "<p>" + "long " * 50_000 + "</p>"), (5, "http://a/", "  \n"), (6, "http://A:80/q", "\x00<p>\ud7ff&#0;&#xD800;</p>")]
    df = spark.createDataFrame(rows, "page_id long, url string, html string")
    df = df.withColumns({c: F.lit(1) for c in ("host", "text", "hashes", "slots", "n_chars", "page", "s", "path", "content", "pages", "template")})
    got = html_text.extract(df).collect()
    assert len(got) == 7 and [r["text"] for r in got if r["page_id"] == 3] == ["x", "x"] and [r["n_chars"] for r in got if r["page_id"] is None] == [249_999]
    assert {r["text"] for r in got if r["page_id"] in (1, 2, 5)} == {""}
    assert html_text.extract(df.limit(0)).count() == 0


# ---------------------------------------------------------------- 5 mixing


def plain_targets(sizes: dict) -> dict:
    order = sorted(sizes, key=lambda s: (s is None, s))
    weight = {s: (3, 1, 2)[i % 3] for i, s in enumerate(order)}
    left, held = 1.5 * sum(sizes.values()), set()
    while True:
        total = sum(weight[s] for s in order if s not in held)
        rate = (left - sum(2 * sizes[s] for s in held)) / total if total else 0
        over = {s for s in order if s not in held and rate * weight[s] > 2 * sizes[s]}
        if not over:
            return {s: 2 * sizes[s] if s in held else rate * weight[s] for s in order}
        held |= over


def test_mix_meets_its_targets(spark, documents):
    docs = spark.createDataFrame(documents, DOCS)
    got = mixing.mix(docs).collect()
    sizes = Counter()
    for _, text, _, source, _ in documents:
        sizes[source] += len(WORDS.findall(text))
    want = plain_targets(dict(sizes))
    taken, largest = Counter(), Counter()
    for r in got:
        assert r["size"] == len(WORDS.findall({d[0]: d[1] for d in documents}[r["doc_id"]])) and r["source_size"] == sizes[r["source"]]
        assert r["target"] == pytest.approx(want[r["source"]]) and r["taken"] in (0, r["size"], 2 * r["size"])
        taken[r["source"]] += r["taken"]
        largest[r["source"]] = max(largest[r["source"]], r["size"])
    assert all(abs(taken[s] - want[s]) <= largest[s] for s in want)
    again = mixing.mix(docs.repartition(5)).collect()
    assert sorted((r["doc_id"], r["taken"]) for r in got) == sorted((r["doc_id"], r["taken"]) for r in again)
    assert mixing.repeat_rows(docs).count() == sum(r["copies"] for r in got)


def test_rounding_keeps_means_and_mass():
    rng = np.random.default_rng(0)
    p, size = rng.random(30), rng.integers(1, 100, 30).astype(float)
    total = np.zeros(30)
    for _ in range(3000):
        out = mixing.duel(p, size, rng.random(30))
        open_ = (out > 0) & (out < 1)
        assert open_.sum() <= 1 and abs(out @ size - p @ size) < 1e-6
        total += out
    assert np.abs(total / 3000 - p).max() < 0.05


def test_many_blocks_meet_in_the_tree(spark, monkeypatch):
    monkeypatch.setattr(mixing, "BLOCK_ROWS", 8)
    monkeypatch.setattr(mixing, "FAN_IN", 3)
    docs = docs_of(spark, [f"{'w ' * (i % 9 + 1)}" for i in range(400)], sources=["abc"[i % 3] for i in range(400)])
    got = mixing.mix(docs).collect()
    taken = Counter()
    for r in got:
        taken[r["source"]] += r["taken"]
    assert all(abs(taken[r["source"]] - r["target"]) <= 9 for r in got)


# ---------------------------------------------------------------- 6 shards


def best_minimax(sizes: list[int], shards: int) -> int:
    low, high = max(sizes), sum(sizes)
    while low < high:
        mid, count, now = (low + high) // 2, 1, 0
        for s in sizes:
            count, now = (count + 1, s) if now + s > mid else (count, now + s)
        low, high = (low, mid) if count <= shards else (mid + 1, high)
    return low


@pytest.mark.parametrize("hot", [False, True])
def test_shards_are_minimax(spark, documents, hot):
    texts = [d[1] for d in documents] * 2 + ["hot " * 200] * (700 if hot else 0)
    docs = docs_of(spark, texts)
    got = sharding.shard_rows(docs).collect()
    groups, slots = Counter(), defaultdict(list)
    for t in texts:
        groups[hashlib.sha256(t.encode()).hexdigest()] += len(t.encode()) + 8
    load = Counter()
    where = defaultdict(set)
    for r in got:
        load[r["shard"]] += r["size"]
        slots[r["shard"]].append(r["slot"])
        where[r["text_crc32"]].add(r["shard"])
        assert r["text_crc32"] == zlib.crc32(texts[r["doc_id"]].encode()) and 0 <= r["shard"] < 24
    assert max(load.values()) == best_minimax([groups[k] for k in sorted(groups)], 24)
    assert all(sorted(s) == list(range(len(s))) for s in slots.values()) and all(len(v) == 1 for v in where.values())


# ---------------------------------------------------------------- 7 fingerprints


def plain_fingerprint(text: str) -> int:
    words = WORDS.findall("".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text))
    if not words:
        return 0
    shingles = [" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))]
    h = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def plain_classes(prints: dict[int, int]) -> dict[int, int]:
    parent = {d: d for d in prints}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    ids = sorted(prints)
    for i, a in enumerate(ids):
        for b in ids[:i]:
            if (prints[a] ^ prints[b]).bit_count() <= 2:
                x, y = sorted((root(a), root(b)))
                parent[y] = x
    return {d: root(d) for d in ids}


def test_fingerprints_and_classes(spark, small, documents):
    prints = {d[0]: plain_fingerprint(d[1]) for d in documents}
    got = {r["doc_id"]: (r["fingerprint"], r["component_id"]) for r in registry.QUERIES["op7_simhash"](spark, small).collect()}
    classes = plain_classes(prints)
    assert got == {d: (f"{prints[d]:016x}", classes[d]) for d in prints}


@pytest.mark.parametrize(("bucket_rows", "take"), [(1024, 1), (1024, 2), (4, 1)])
def test_links_of_crowded_values(spark, bucket_rows, take):
    rng = np.random.default_rng(7)
    seeds = rng.integers(0, 2**63, 12, dtype=np.uint64).tolist()
    values = {0}
    for s in seeds:
        for _ in range(25):
            v = s
            for b in rng.choice(64, int(rng.integers(0, 5)), replace=False):
                v ^= 1 << int(b)
            values.add(v)
    values |= set(rng.integers(0, 2**63, 300, dtype=np.uint64).tolist())
    prints = dict(enumerate(sorted(values)))
    signed = [(v - 2**64 if v >= 2**63 else v,) for v in prints.values()]
    edges = simhash.fingerprint_edges(spark.createDataFrame(signed, "fp long"), 2, bucket_rows, take)
    got = {r["node"] % 2**64: r["component"] for r in common.components(edges).collect()}
    by_class = defaultdict(set)
    for k, v in prints.items():
        by_class[got.get(v, ("alone", v))].add(k)
    want = defaultdict(set)
    for k, c in plain_classes(prints).items():
        want[c].add(k)
    assert {frozenset(c) for c in by_class.values()} == {frozenset(c) for c in want.values()}


def test_components_of_a_long_chain(spark):
    edges = spark.createDataFrame([(i, i + 1) for i in range(200)] + [(1000, 1001), (5, 5)], "a long, b long")
    got = {r["node"]: r["component"] for r in common.components(edges).collect()}
    assert all(got[i] == 0 for i in range(201)) and got[1001] == 1000 and len(got) == 203


# ---------------------------------------------------------------- 9 and 10


def test_exact_dedup_equals_sql(spark, small, duck):
    same_rows(registry.QUERIES["op9_exact_dedup"](spark, small), duck, registry.ORACLES["op9_exact_dedup"])


def test_directory_splits_overfull_buckets(spark):
    docs = docs_of(spark, [f"text {i % 900}" for i in range(1000)])
    cells, index = exact_dedup.build_index(docs, bucket_entries=40)
    sizes = [r["count"] for r in index.groupBy("bucket").count().collect()]
    assert len(sizes) > 900 / 40 and max(sizes) <= 40 and sum(sizes) == 900
    assert cells.select("bucket").distinct().count() == len(sizes)
    assert exact_dedup.find_duplicates(docs, bucket_entries=40).where("kept").count() == 900


@pytest.mark.parametrize("key_bits", [1, 6, 64])
def test_chains_tell_colliding_texts_apart(spark, duck, key_bits):
    """With few bits all keys collide; only the bytes differ. A hot group is among the texts."""
    texts = [None, "", "", "a", "A", "a "] + [f"text {i % 37}" for i in range(150)] + ["hot"] * 200
    got = {r["doc_id"]: (r["keep_id"], r["group_size"], r["kept"], r["text_sha256"]) for r in exact_dedup.find_duplicates(docs_of(spark, texts), key_bits=key_bits).collect()}
    plain = [t or "" for t in texts]
    last, count = {t: i for i, t in enumerate(plain)}, Counter(plain)
    assert got == {i: (last[t], count[t], last[t] == i, hashlib.sha256(t.encode()).hexdigest()) for i, t in enumerate(plain)}
    assert sorted(r["doc_id"] for r in exact_dedup.drop_duplicates(docs_of(spark, texts), key_bits=key_bits).collect()) == sorted(last.values())


def test_texts_alone_with_their_key_do_not_move(spark):
    """No exchange of the plan holds a text but that of the chains."""
    docs = docs_of(spark, [f"text {i % 90}" for i in range(100)])
    plan = exact_dedup.drop_duplicates(docs)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning(bucket") == 1 and "Python" not in plan and "Pandas" not in plan


def test_bpe_equals_the_library(spark, small, documents):
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(bpe.vocabulary_path())
    enc = bpe.WordEncoder(bpe.vocabulary_path())
    texts = [d[1] for d in documents[:80]] + [
        "", "a<|endoftext|>b <|startoftext|>  ", "ΣΑΣ ΟΔΟΣ İx", "x\x1cy\x85z　q w", "Don't I'LL 123 漢字😀!!", "a" * 3000, "é" * 90, "é ﬁ ǅ ẞ", "\n\t", "x" * 24 + " " + "y" * 25,
    ]
    for text, (n, ids, decoded) in zip(texts, enc.encode_many(texts), strict=True):
        want = tok.encode(text, add_special_tokens=False).ids
        assert ids.decode() == " ".join(map(str, want)) and n == len(want)
        assert decoded.decode() == tok.decode(want, skip_special_tokens=False)
    docs = docs_of(spark, texts)
    got = {r["doc_id"]: r["ids"] for r in bpe.encode_documents(docs).collect()}
    assert all(got[i] == tok.encode(t, add_special_tokens=False).ids for i, t in enumerate(texts))
    back = {r["doc_id"]: r["text"] for r in bpe.decode_documents(bpe.encode_documents(docs)).collect()}
    assert all(back[i] == tok.decode(got[i], skip_special_tokens=False) for i in back)
    word = "thtionheationing"
    assert enc.merge_long(word.encode()) == enc.merge_short([word.encode()])[0]


# ---------------------------------------------------------------- pipeline


def test_pipeline_stages(spark, small):
    import corpus_pipeline

    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "exact_dedup", "simhash", "mixing", "bpe"]
    docs = common.read_table(spark, small, "documents")
    columns, rows = docs.columns, common.written(docs, "test")
    for name, stage in corpus_pipeline.STAGES:
        before = rows.collect()
        after = common.written(stage(spark, rows, small), "test")
        got = after.collect()
        if name == "bpe":
            assert len(got) == len(before) and "n_tokens" in after.columns
            break
        assert after.columns == columns and set(got) <= set(before)
        texts = [r["text"] for r in got]
        if name == "toxicity":
            scores = {r["doc_id"]: r["predicted"] for r in registry.QUERIES["op2_toxicity"](spark, small).collect()}
            assert {r["doc_id"] for r in got} == {r["doc_id"] for r in before if not scores[r["doc_id"]]}
        if name == "exact_dedup":
            best = {}
            for r in before:
                best[r["text"]] = max(best.get(r["text"], -1), r["doc_id"])
            assert sorted(r["doc_id"] for r in got) == sorted(best.values()) and len(set(texts)) == len(texts)
        if name == "simhash":
            from tests.llm.test_similar import plain_classes as similar_classes

            assert {r["doc_id"] for r in got} == set(similar_classes({r["doc_id"]: r["text"] for r in before}).values())
        if name == "mixing":
            assert max(Counter(r["doc_id"] for r in got).values()) <= 2
        rows = after
    assert corpus_pipeline.run(spark, small).count() == len(got)


ODD_LABELS = "doc_id long, quality int, toxic int"


def saved(spark, folder, docs, labels):
    docs.write.mode("overwrite").parquet(f"{folder}/documents.parquet")
    labels.write.mode("overwrite").parquet(f"{folder}/labels.parquet")
    return str(folder)


def test_pipeline_and_classifiers_on_odd_and_empty_tables(spark, tmp_path):
    import corpus_pipeline

    labels = spark.createDataFrame([(1, 1, 0), (1, 0, 1), (None, 1, 1), (3, None, None), (4, 1, 0), (99, 0, 1), (7, 1, 7)], ODD_LABELS)
    folder = saved(spark, tmp_path / "odd", odd(spark), labels)
    got = corpus_pipeline.run(spark, folder).collect()
    assert {r["doc_id"] for r in got} <= {None, 1, 2, 3, 4, 7, 8} and len(got) >= 3
    for name in ("op2_toxicity", "op8_quality"):
        rows = registry.QUERIES[name](spark, folder).collect()
        assert len(rows) == 8 and all(0 <= r["score"] <= 1 for r in rows)
    nothing = saved(spark, tmp_path / "empty", empty(spark), labels.limit(0))
    assert corpus_pipeline.run(spark, nothing).count() == 0
    for name in ("op2_toxicity", "op8_quality"):
        assert registry.QUERIES[name](spark, nothing).count() == 0
    unlabelled = saved(spark, tmp_path / "unlabelled", odd(spark), labels.limit(0))
    assert {r["predicted"] for r in registry.QUERIES["op2_toxicity"](spark, unlabelled).collect()} == {0}


def test_toxic_documents_go_and_clean_ones_stay(spark):
    rng = np.random.default_rng(4)
    words = ["".join(rng.choice(list("aeioudnrst"), 5)) for _ in range(400)]
    text = lambda bad: " ".join([*rng.choice(words, 60), *(["vilegrub"] * bad)])
    model = toxicity.fit([(f, y, text(4 * y)) for f in (0, 2) for y in (0, 1) for _ in range(80)])
    docs = docs_of(spark, [text(6 * (i % 4 == 0)) for i in range(80)] + [None, ""])
    kept = {r["doc_id"] for r in toxicity.drop_toxic(docs, model).collect()}
    scored = {r["doc_id"]: r["predicted"] for r in toxicity.score_documents(docs, model).collect()}
    assert kept == {i for i, p in scored.items() if not p} and {80, 81} <= kept
    assert sum(i % 4 == 0 for i in kept if i < 80) <= 4 and sum(i % 4 != 0 for i in kept if i < 80) >= 54


def test_peeling_updates_only_the_cells_that_digests_go_to(spark):
    """Cells less placed digests equal the difference of two sketches, and one attempt sums cells once for both texts."""
    from collidra.llm import paragraph_sketch as p

    items = "transform(sequence(1, 20), i -> xxhash64(i))"
    some = f"slice({items}, 5, 9)"
    less = p._less(p.sketch(items, "57", 101), f"transform({some}, d -> {p._placed('d', '1L', '19', 101)})", "19")
    both = p.subtract(p.sketch(items, "57", 101), p.sketch(some, "57", 101))
    found = p._attempt(items, f"concat({some}, array(7L))", "19", 101)
    row = spark.sql(f"SELECT {less} AS a, {both} AS b, array_sort({found}) AS c, array_sort(concat(array_except({items}, {some}), array(7L))) AS d").first()
    assert row["a"] == row["b"] and row["c"] == row["d"]
    assert found.count("sequence(0, v.part - 1)") == 3
