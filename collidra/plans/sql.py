"""The same questions in SQL for DuckDB: pieces of WITH clauses over the given tables.

Each function returns named sub-queries; ``query`` joins them. All take a prefix, so that one query can hold several
settings side by side.
"""

from __future__ import annotations

from ..functions.portable import P, HashNumbers, parameters
from ..operators.hashing import directions, offset, tries
from ..operators.index import IndexParams
from ..operators.reservoir import pool_size
from .workloads import LINE_KEY, LINE_TAGS, PART_COLUMNS, TABLE, grows


def fid(token: str) -> str:
    return f"('0x' || substr(md5({token}), 1, 7))::BIGINT"


def _tokens(table: str, key: str, tokens: str, more: str = "") -> str:
    return f"SELECT DISTINCT k::BIGINT AS item_id, {fid('w')} AS f FROM (SELECT {key} AS k, unnest({tokens}) AS w FROM {table} {more}) WHERE w IS NOT NULL AND w <> ''"


def _words(col: str) -> str:
    return f"string_split_regex(lower({col}), '\\s+')"


def _tagged(tag: str, parts: str) -> str:
    return f"list_transform(list_filter({parts}, lambda p: p <> ''), lambda p: '{tag}' || p)"


_URL = "list_concat(list_concat({}, {}), {})".format(
    _tagged("h:", "string_split(regexp_extract(url, '^[a-z]+://([^/?#]*)', 1), '.')"),
    _tagged("p:", "string_split(regexp_extract(url, '^[a-z]+://[^/?#]*([^?#]*)', 1), '/')"),
    _tagged("q:", "string_split(regexp_extract(url, '\\?([^#]*)', 1), '&')"),
)
_LINES = "lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey"
_TAGS = "[" + ", ".join(f"'{k}=' || {v.format(s='varchar')}" for k, v in LINE_TAGS.items()) + "]"
_EDGES = "lineitem JOIN orders ON l_orderkey = o_orderkey"

FEATURES = {
    "docs_words": _tokens("documents", "doc_id", _words("text")),
    "docs_char3": _tokens("documents", "doc_id", "list_transform(range(1, greatest(length(text) - 1, 1)), lambda i: substr(lower(text), i, 3))"),
    "pages_url": _tokens("pages", "page_id", _URL),
    "pages_full": _tokens("pages", "page_id", f"list_concat({_URL}, {_tagged('t:', _words('html'))})"),
    "part_cat": _tokens("part", "p_partkey", "[" + ", ".join(f"'{c}=' || {c}::VARCHAR" for c in PART_COLUMNS) + "]"),
    "lines_cat": _tokens(_LINES, f"('0x' || substr(md5({LINE_KEY}), 1, 12))::BIGINT", _TAGS),
    "cust_parts": f"SELECT DISTINCT o_custkey AS item_id, l_partkey AS f FROM {_EDGES}",
    "part_custs": f"SELECT DISTINCT l_partkey AS item_id, o_custkey AS f FROM {_EDGES}",
    "user_events": f"SELECT DISTINCT user_id AS item_id, {fid('w')} AS f FROM (SELECT user_id, event_type || ':' || json_extract_string(props, '$.k') AS w FROM events)",
    "turns_words": _tokens("conversations", "conv_id * 100 + turn", _words("text")),
    "bench_words": _tokens("benchmark", "item_id", _words("text")),
}


def query(parts: list[tuple[str, str]], last: str) -> str:
    return "WITH " + ",\n".join(f"{n} AS MATERIALIZED ({s})" for n, s in parts) + "\n" + last


def feats(name: str, x: str = "") -> list[tuple[str, str]]:
    return [(f"{x}feats", FEATURES[name])]


def bins(m: int, seed: int = 1, x: str = "", src: str | None = None) -> list[tuple[str, str]]:
    a, b = HashNumbers(seed).feature
    return [(f"{x}bins", f"SELECT item_id, h % {m} AS bin, min(h // {m}) AS v FROM (SELECT item_id, ({a} * f + {b}) % {P} AS h FROM {src or x + 'feats'}) GROUP BY 1, 2")]


def densified(m: int, scheme: str = "probe", seed: int = 1, x: str = "") -> list[tuple[str, str]]:
    a, b = HashNumbers(seed).probe
    t, c = tries(m), offset(m)
    out = [(f"{x}own", f"SELECT e.item_id, e.i, v FROM (SELECT item_id, i FROM (SELECT DISTINCT item_id FROM {x}bins), range({m}) r(i)) e LEFT JOIN {x}bins n ON n.item_id = e.item_id AND n.bin = e.i")]
    if scheme == "two_way":
        turns = ", ".join(f"({i}, {int(d)})" for i, d in enumerate(directions(m, seed)))
        dist = f"CASE WHEN turn = 1 THEN (n.bin - e.i + {m}) % {m} ELSE (e.i - n.bin + {m}) % {m} END"
        source = f"{x}own e JOIN (VALUES {turns}) d(di, turn) ON di = e.i JOIN {x}bins n USING (item_id)"
    else:
        dist, source = f"(n.bin - e.i + {m}) % {m}", f"{x}own e JOIN {x}bins n USING (item_id)"
    out.append((f"{x}rotated", f"SELECT e.item_id, e.i, arg_min(n.v + ({dist}) * {c}, {dist}) AS r FROM {source} WHERE e.v IS NULL GROUP BY 1, 2"))
    value, joins = "coalesce(o.v, r.r)", f"{x}own o LEFT JOIN {x}rotated r USING (item_id, i)"
    if scheme == "probe":
        out.append((f"{x}steps", f"SELECT i, t, ({a} * (i * {t} + t) + {b}) % {P} % {m} AS j FROM range({m}) p(i), range({t}) q(t)"))
        out.append((f"{x}probed", f"SELECT e.item_id, e.i, arg_min(n.v, s.t) AS p FROM {x}own e JOIN {x}steps s USING (i) JOIN {x}bins n ON n.item_id = e.item_id AND n.bin = s.j WHERE e.v IS NULL GROUP BY 1, 2"))
        value, joins = "coalesce(o.v, p.p, r.r)", joins + f" LEFT JOIN {x}probed p USING (item_id, i)"
    return [*out, (f"{x}sig", f"SELECT o.item_id, o.i, {value} AS v FROM {joins}")]


def room(p: IndexParams, features: str | None) -> str:
    """The number of addresses of a table, which grows with the workload's table."""
    if features is None or not grows(p):
        return str(1 << p.bits)
    return f"(1::BIGINT << greatest({p.bits}, least(30, (SELECT ceil(log2(greatest(2, count(*) / 16.0::DOUBLE))) FROM {TABLE[features]})))::INT)"


def fold(k: int, tables_from: str, size: str, seed: int = 1, x: str = "") -> list[tuple[str, str]]:
    a = HashNumbers(seed).fold
    acc = "(table_id::BIGINT + 1)"
    for i in range(k):
        acc = f"(({acc} * {a} + vs[{i + 1}] + 1) % {P})"
    return [(f"{x}addr", f"SELECT item_id, table_id, {acc} % {size} AS address FROM (SELECT item_id, i // {k} AS table_id, list(v ORDER BY i) AS vs FROM {tables_from} GROUP BY 1, 2)")]


def addresses(p: IndexParams, x: str = "", features: str | None = None, size: str | None = None) -> list[tuple[str, str]]:
    m = p.k * p.tables
    head = feats(features, x) if features else []
    return [*head, *bins(m, p.seed, x), *densified(m, p.densify, p.seed, x), *fold(p.k, f"{x}sig", size or room(p, features), p.seed, x)]


def priority(seed: int, first: str = "table_id", second: str = "address") -> str:
    a, b = HashNumbers(seed).priority
    x = f"((((item_id % {P}) * 31 + {first} * 1009 + {second} * 101) % {P} * {a} + {b}) % {P})"
    return f"({x} * {x} + {a}) % {P}"


def reservoirs(p: IndexParams, x: str = "", policy: str = "priority") -> list[tuple[str, str]]:
    """(table_id, address, seen, item_id) rows of the held items."""
    if policy == "priority":
        return [(f"{x}res", f"SELECT table_id, address, seen, item_id FROM (SELECT *, row_number() OVER (PARTITION BY table_id, address ORDER BY pr, item_id) AS rk, count(*) OVER (PARTITION BY table_id, address) AS seen FROM (SELECT *, {priority(p.seed)} AS pr FROM {x}addr)) WHERE rk <= {p.r}")]
    slot = f"({priority(p.seed + 77)} * (i + 1)) // {P}"
    if policy == "arrival":
        slot = f"CASE WHEN i < {p.r} THEN i ELSE {slot} END"
    ranked = f"SELECT *, row_number() OVER (PARTITION BY table_id, address ORDER BY item_id) - 1 AS i, count(*) OVER (PARTITION BY table_id, address) AS seen FROM {x}addr"
    return [(f"{x}res", f"SELECT table_id, address, seen, arg_max(item_id, i) AS item_id FROM (SELECT *, {slot} AS slot FROM ({ranked})) WHERE slot < {p.r} GROUP BY table_id, address, seen, slot")]


def pointers(p: IndexParams, x: str = "", local_fraction: float = 0.5) -> list[tuple[str, str]]:
    a, b = HashNumbers(p.seed).share
    pool = pool_size(p.tables, p.bits, p.share)
    spot = f"(((table_id * {1 << p.bits} + address) % {P}) * {a} + {b}) % {P} % {pool}"
    used = f"SELECT table_id, address, min(item_id) AS first_item FROM {x}addr GROUP BY 1, 2"
    if p.sharing == "global":
        return [(f"{x}ptr", f"SELECT table_id, address, {spot} AS reservoir_id FROM ({used})")]
    local = int(-(-(1 << p.bits) * local_fraction // 1))
    return [(f"{x}ptr", f"SELECT table_id, address, CASE WHEN rk <= {local} THEN {pool} + table_id * {local} + rk - 1 ELSE {spot} END AS reservoir_id FROM (SELECT *, row_number() OVER (PARTITION BY table_id ORDER BY first_item, address) AS rk FROM ({used}))")]


def shared(p: IndexParams, x: str = "") -> list[tuple[str, str]]:
    pr = priority(p.seed, "table_id", "reservoir_id")
    return [(f"{x}sres", f"SELECT reservoir_id, seen, item_id FROM (SELECT *, row_number() OVER (PARTITION BY reservoir_id ORDER BY pr, item_id, table_id) AS rk, count(*) OVER (PARTITION BY reservoir_id) AS seen FROM (SELECT *, {pr} AS pr FROM {x}addr JOIN {x}ptr USING (table_id, address))) WHERE rk <= {p.r}")]


def index(p: IndexParams, x: str = "", features: str | None = None) -> list[tuple[str, str]]:
    """Up to ``met``: (query_id, table_id, seen, neighbor_id) for the graph of all items."""
    out = addresses(p, x, features)
    if p.share < 1:
        return [*out, *pointers(p, x), *shared(p, x), (f"{x}met", f"SELECT a.item_id AS query_id, a.table_id, s.seen, s.item_id AS neighbor_id FROM {x}addr a JOIN {x}ptr USING (table_id, address) JOIN {x}sres s USING (reservoir_id)")]
    return [*out, *reservoirs(p, x), (f"{x}met", f"SELECT a.item_id AS query_id, a.table_id, s.seen, s.item_id AS neighbor_id FROM {x}addr a JOIN {x}res s USING (table_id, address)")]


def ranked(src: str, k: int, by: str = "collisions") -> str:
    return f"SELECT query_id, neighbor_id, rank, {by} FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY {by} DESC, neighbor_id) AS rank FROM ({src})) WHERE rank <= {k}"


def graph(p: IndexParams, k: int, x: str = "", features: str | None = None, self_too: bool = False) -> list[tuple[str, str]]:
    keep = "" if self_too else "WHERE query_id <> neighbor_id"
    return [*index(p, x, features), (f"{x}graph", ranked(f"SELECT query_id, neighbor_id, count(*) AS collisions FROM {x}met {keep} GROUP BY 1, 2", k))]


def overlaps(x: str = "", queries: str | None = None) -> list[tuple[str, str]]:
    """(query_id, neighbor_id, a, x, y) of pairs with common features; ``queries`` restricts the query ids."""
    where = f"AND q.item_id IN ({queries})" if queries else ""
    return [
        (f"{x}sizes", f"SELECT item_id, count(*) AS n FROM {x}feats GROUP BY 1"),
        (f"{x}over", f"SELECT query_id, neighbor_id, a, s.n AS x, t.n AS y FROM (SELECT q.item_id AS query_id, d.item_id AS neighbor_id, count(*) AS a FROM {x}feats q JOIN {x}feats d USING (f) WHERE q.item_id <> d.item_id {where} GROUP BY 1, 2) JOIN {x}sizes s ON s.item_id = query_id JOIN {x}sizes t ON t.item_id = neighbor_id"),
    ]


COSINE = "round(a / sqrt(x::DOUBLE * y), 6)"
JACCARD = "round(a / (x + y - a)::DOUBLE, 6)"


def gold(k: int, x: str = "", queries: str | None = None, score: str = COSINE) -> list[tuple[str, str]]:
    return [*overlaps(x, queries), (f"{x}gold", ranked(f"SELECT query_id, neighbor_id, {score} AS similarity FROM {x}over", k, "similarity"))]


def sampled(src: str, n: int, seed: int = 9, key: str = "item_id") -> str:
    a, b = parameters(seed, 2)
    return f"SELECT {key} FROM {src} ORDER BY (({key} % {2**31}) * {a} + {b}) % {P}, {key} LIMIT {n}"


def recall(ks: tuple, graph_name: str, gold_name: str) -> str:
    each = ", ".join(f"({k})" for k in ks)
    return (
        f"SELECT k, round(avg(coalesce((rank <= k)::INT, 0)), 6) AS recall, count(*) AS n_queries FROM (SELECT t.query_id, min(g.rank) AS rank FROM (SELECT query_id, neighbor_id FROM {gold_name} "
        f"JOIN (SELECT query_id, max(similarity) AS top FROM {gold_name} GROUP BY 1) USING (query_id) WHERE similarity = top) t LEFT JOIN {graph_name} g ON g.query_id = t.query_id AND g.neighbor_id = t.neighbor_id GROUP BY 1), (VALUES {each}) v(k) GROUP BY k"
    )
