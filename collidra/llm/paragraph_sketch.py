"""Document fingerprints that tell which paragraphs differ: invertible Bloom lookup sketches; DataFrame operations only.

A paragraph is what stands between the ends of lines and sentences, without the blanks around it, so that the same
sentences give the same paragraphs however they are set and however long the text is. Only one beyond ``MOST_CHARS`` is cut
into pieces of that size. Each different paragraph is a 64-bit digest.

A sketch has cells in three parts; a digest goes to one cell of each, where it adds to a count, an XOR of digests and an
XOR of check sums. The cells of two versions subtract; what they share cancels, and peeling takes digests out of cells
that hold exactly one until none is left. A fingerprint is the sketch of ``CELLS`` cells and the number of paragraphs. Two
texts are first compared by their fingerprints; if cells remain, there were more differences than these hold, and both
are sketched again with more cells, up to sixteen for each digest. For that, digests fall into groups of about ``GROUP`` by their
value, and each group has a sketch of its own, so the work stays linear in the text; a group whose peeling gets stuck is
sketched once more, larger and with other hashes.

Likeness is 1 - differing / all digests of both.

All of a document's work is done in its row, so the only shuffle is the one that brings each text beside the next.

Defined results: a null text counts as empty; an empty text has no paragraphs, and two empty texts are alike (1.0); rows
that repeat an id follow each other in the order of their texts' hashes; null ids come last; a single row is followed
by itself; digests that stay stuck through all sizes (less than one in 10**12) count as differing; an empty table gives
an empty result; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .common import read_table, shuffle_partitions, text_or_empty

#: Cells of a fingerprint, a multiple of 3, and most rounds of peeling.
CELLS, ROUNDS = 24, 24
#: Ranges of ids per shuffle partition when texts are brought beside their successors.
RANGES_PER_PARTITION = 4
#: Most characters of a paragraph, digests of both texts in a group, and cells per digest, try by try.
MOST_CHARS, GROUP, GROWTH = 4096, 24, (2, 4, 8, 16)
_CELL = "struct(0L AS n, 0L AS k, 0L AS x)"
_CHECK = "(xxhash64({0}, 7) & 4294967295L)"


def digests(text: str) -> str:
    """SQL for the different paragraph digests of a text."""
    parts = f"filter(transform(split({text}, '[\\\\r\\\\n]+|(?<=[.!?])[ \\\\t]+'), p -> trim(p)), p -> p <> '')"
    pieces = f"flatten(transform({parts}, p -> IF(char_length(p) <= {MOST_CHARS}, array(p), regexp_extract_all(p, '(?s).{{1,{MOST_CHARS}}}', 0))))"
    return f"array_distinct(transform({pieces}, p -> xxhash64(p)))"


def _summed(placed: str, part: str) -> str:
    """SQL for the cells, part by part, of an array of struct<n,k,x,p0,p1,p2>."""
    return "concat(" + ", ".join(
        f"transform(sequence(0, {part} - 1), c -> aggregate(filter({placed}, i -> i.p{j} = c), {_CELL}, (a, i) -> struct(a.n + i.n AS n, a.k ^ i.k AS k, a.x ^ i.x AS x)))"
        for j in range(3)
    ) + ")"


def _placed(digest: str, sign: str, part: str, seed: int) -> str:
    places = ", ".join(f"cast(pmod(xxhash64({digest}, {seed + j}), {part}) AS int) AS p{j}" for j in range(3))
    return f"struct({sign} AS n, {digest} AS k, {_CHECK.format(digest)} AS x, {places})"


def sketch(items: str, cells: str, seed: int) -> str:
    """SQL for the cells, array<struct<n,k,x>>, of an array of digests; ``cells`` is a multiple of 3."""
    part = f"cast({cells} / 3 AS int)"
    return f"transform(array(transform({items}, d -> {_placed('d', '1L', part, seed)})), its -> {_summed('its', part)})[0]"


def _less(cells: str, placed: str, part: str) -> str:
    """SQL for cells less an array of struct<n,k,x,p0,p1,p2>; a cell that none goes to stays as it is."""
    return "concat(" + ", ".join(
        f"transform(slice({cells}, 1 + {j} * {part}, {part}), (q, c) -> aggregate(filter({placed}, i -> i.p{j} = c), q, (a, i) -> struct(a.n - i.n AS n, a.k ^ i.k AS k, a.x ^ i.x AS x)))"
        for j in range(3)
    ) + ")"


def subtract(a: str, b: str) -> str:
    return f"zip_with({a}, {b}, (u, v) -> struct(u.n - v.n AS n, u.k ^ v.k AS k, u.x ^ v.x AS x))"


def peel(cells: str, seed: int) -> str:
    """SQL for the digests that subtracted cells hold, null if peeling gets stuck.

    A round takes the digests that are alone in a cell, by the sign of their count, and subtracts a sketch of them.
    """
    pure = f"filter(s.cells, q -> abs(q.n) = 1L AND {_CHECK.format('q.k')} = q.x)"
    signed = [f"transform(array_distinct(transform(filter(pure, q -> q.n = {n}), q -> q.k)), e -> {_placed('e', n, 's.part', seed)})" for n in ("1L", "-1L")]
    rest = f"struct({_less('s.cells', 't', 's.part')} AS cells, s.part AS part, concat(s.found, t.k) AS found)"
    step = f"IF(s.part < 0, s, transform(transform(array({pure}), pure -> concat({signed[0]}, {signed[1]})), t -> IF(size(t) = 0, struct(s.cells AS cells, -1 AS part, s.found AS found), {rest}))[0])"
    start = f"struct({cells} AS cells, cast(size({cells}) / 3 AS int) AS part, cast(array() AS array<bigint>) AS found)"
    end = "IF(exists(z.cells, c -> c.n <> 0L OR c.k <> 0L OR c.x <> 0L), NULL, z.found)"
    return f"aggregate(sequence(1, {ROUNDS}), {start}, (s, r) -> {step}, z -> {end})"


def _attempt(a: str, b: str, part: str, seed: int) -> str:
    """Peels the sketch of ``a`` less that of ``b``, of three parts of ``part`` cells.

    As sketches are sums, digests of ``b`` are added with the opposite sign, which gives the cells of the difference at
    once; the size is worked out once and not again for each digest.
    """
    placed = f"concat(transform({a}, d -> {_placed('d', '1L', 'part', seed)}), transform({b}, d -> {_placed('d', '-1L', 'part', seed)}))"
    cells = f"transform(transform(array({part}), part -> struct(part AS part, {placed} AS its)), v -> {_summed('v.its', 'v.part')})"
    return f"transform({cells}, w -> {peel('w', seed)})[0]"


def differing(a: str, b: str, sketch_a: str | None = None, sketch_b: str | None = None) -> str:
    """SQL for the digests in only one of two arrays, by sketches that grow while peeling fails.

    Given the sketches of two fingerprints, these are tried first.
    """
    whole = "(size(r.a) + size(r.b))"
    tries = [_attempt("r.a", "r.b", f"cast(3 + ceil({whole} * {f} / 3) AS int)", 101 + 100 * i) for i, f in enumerate(GROWTH)]
    group = f"transform(array(struct(filter({a}, d -> pmod(d, m) = g) AS a, filter({b}, d -> pmod(d, m) = g) AS b)), r -> coalesce({', '.join(tries)}, concat(r.a, r.b)))[0]"
    groups = f"flatten(transform(array(1 + cast((size({a}) + size({b})) / {GROUP} AS int)), m -> flatten(transform(sequence(0, m - 1), g -> {group}))))"
    if not sketch_a:
        return groups
    return f"coalesce(transform(array({subtract(sketch_a, sketch_b)}), w -> {peel('w', 1)})[0], {groups})"


def likeness(a: str, b: str, difference: str) -> str:
    return f"IF(size({a}) + size({b}) = 0, 1.0D, 1.0D - size({difference}) / cast(size({a}) + size({b}) AS double))"


def as_string(items: str, cells: str) -> str:
    """SQL for a fingerprint: the number of paragraphs and the cells' counts, digests and check sums in hex."""
    return f"lower(concat(size({items}), ':', array_join(transform({cells}, c -> concat(hex(c.n), '.', hex(c.k), '.', hex(c.x))), ',')))"


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_chars, fingerprint) of each row; needs no shuffle."""
    df = docs.select(F.col(id_col).cast("long").alias("doc_id"), text_or_empty(text_col).alias("body"))
    df = df.withColumn("n_chars", F.char_length("body").cast("long")).withColumn("a", F.expr(digests("body")))
    return df.withColumn("sa", F.expr(sketch("a", str(CELLS), 1))).select("doc_id", "n_chars", F.expr(as_string("a", "sa")).alias("fingerprint"))


# ---------------------------------------------------------------- texts beside the next one

def range_number(col: str, edges: list[int]) -> Column:
    """How many of the sorted ``edges`` are at or below a value (-1 for null), by way of every 64th edge."""
    if not edges:
        return F.when(F.col(col).isNull(), -1).otherwise(0)
    step = max(1, round(len(edges) ** 0.5))
    coarse = F.array(*[F.lit(e) for e in edges[::step]])
    groups = F.array(*[F.array(*[F.lit(e) for e in edges[i : i + step]]) for i in range(0, len(edges), step)])
    at = F.size(F.filter(coarse, lambda e: e <= F.col(col)))
    fine = F.size(F.filter(F.element_at(groups, F.greatest(at, F.lit(1))), lambda e: e <= F.col(col)))
    return F.when(F.col(col).isNull(), -1).otherwise(F.when(at == 0, 0).otherwise((at - 1) * step + fine))


def beside_next(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, body, next_body): each text beside that of the next smaller id; the last is followed by the first.

    Texts are shuffled once, into ranges of ids of about equal counts. Only the last row of each range looks beyond,
    to the first row of the next range that has any; those first rows, one per range, are joined by the range.
    """
    spark = docs.sparkSession
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), text_or_empty(text_col).alias("body"))
    n = shuffle_partitions(spark) * RANGES_PER_PARTITION
    found = rows.agg(F.percentile_approx("doc_id", [i / n for i in range(1, n)], 20 * n)).first()[0]
    placed = rows.withColumn("range", range_number("doc_id", sorted(set(found or [])))).withColumn("h", F.xxhash64("body"))
    # (first id, first hash) of each range, then what follows each range; a row per range
    heads = placed.groupBy("range").agg(F.max(F.struct(F.col("doc_id").alias("i"), "h")).alias("head"))
    down = W.orderBy(F.col("range").desc())
    after = heads.select(
        "range", F.coalesce(F.lead("head").over(down), F.first("head").over(down.rowsBetween(W.unboundedPreceding, W.unboundedFollowing))).alias("then")
    )
    after = after.select(F.col("range").alias("of_range"), F.col("then.i").alias("then_id"), F.col("then.h").alias("then_h"))
    follow = (
        placed.join(F.broadcast(after), F.col("doc_id").eqNullSafe(F.col("then_id")) & (F.col("h") == F.col("then_h")))
        .groupBy("of_range").agg(F.first("body").alias("follow"))
    )
    order = W.partitionBy("range").orderBy(F.col("doc_id").desc_nulls_last(), F.col("h").desc())
    within = placed.select("doc_id", "range", "body", F.lead("body").over(order).alias("next_body"))
    both = within.join(follow.hint("merge"), (F.col("range") == F.col("of_range")) & F.col("next_body").isNull(), "left")
    return both.select("doc_id", "body", F.coalesce("next_body", "follow").alias("next_body"))


def compare_with_edit_and_next(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Fingerprints of each text and of its edit, and their likenesses to each other and to the next text."""
    df = beside_next(docs, id_col, text_col).withColumn("n_chars", F.char_length("body").cast("long"))
    df = df.withColumn("cut", F.floor(F.col("n_chars") / 3).cast("int"))
    df = df.withColumn("edited", F.expr("concat(substring(body, 1, cast(n_chars AS int) - cut), substring(next_body, 1, cut))"))
    df = df.select(
        "doc_id", "n_chars", F.sha2("edited", 256).alias("edited_sha256"), F.expr(digests("body")).alias("a"), F.expr(digests("edited")).alias("e"), F.expr(digests("next_body")).alias("n"),
    )
    for items in "aen":
        df = df.withColumn(f"s{items}", F.expr(sketch(items, str(CELLS), 1)))
    df = df.withColumn("d_e", F.expr(differing("a", "e", "sa", "se"))).withColumn("d_n", F.expr(differing("a", "n", "sa", "sn")))
    return df.select(
        "doc_id", "n_chars", "edited_sha256", F.expr(as_string("a", "sa")).alias("fingerprint"), F.expr(as_string("e", "se")).alias("edited_fingerprint"),
        F.expr(likeness("a", "e", "d_e")).alias("near_edited"), F.expr(likeness("a", "n", "d_n")).alias("near_next"),
    )


def op1_paragraph_sketch(spark, sf_dir: str) -> DataFrame:
    return compare_with_edit_and_next(read_table(spark, sf_dir, "documents"))
