"""Pieces of DuckDB SQL that the catalogue's checks are put together from."""

from __future__ import annotations

from .operators.products import half_bits, permutation_keys
from .sources.tables import EVENT_TYPES

ORDER_PART = "SELECT l_orderkey AS i, l_partkey AS j, CAST(sum(l_quantity) AS BIGINT) AS v FROM lineitem GROUP BY ALL"
SUPP_PART = "SELECT l_suppkey AS i, l_partkey AS j, CAST(sum(l_quantity) AS BIGINT) AS v FROM lineitem GROUP BY ALL"
CUST_SUPP = (
    "SELECT o_custkey AS i, l_suppkey AS j, count(*) AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY ALL"
)
NATION_TRADE = """SELECT CAST(c_nationkey AS BIGINT) AS i, CAST(s_nationkey AS BIGINT) AS j, CAST(sum(l_quantity) AS BIGINT) AS v
FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey
JOIN supplier ON l_suppkey = s_suppkey GROUP BY ALL"""
USER_FOLLOW = """SELECT i, j, count(*) AS v FROM (
SELECT user_id AS i, lead(user_id) OVER (ORDER BY ts, event_id) AS j FROM events) WHERE j IS NOT NULL GROUP BY ALL"""
_CODE = "CASE event_type " + " ".join(f"WHEN '{t}' THEN {n}" for n, t in enumerate(EVENT_TYPES)) + " END"
USER_EVENT = f"SELECT user_id AS i, CAST({_CODE} AS BIGINT) AS j, count(*) AS v FROM events GROUP BY ALL"
COPURCHASE = """SELECT x.l_partkey AS i, y.l_partkey AS j, count(*) AS v
FROM (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem) x
JOIN (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem) y
ON x.l_orderkey = y.l_orderkey AND x.l_partkey <> y.l_partkey GROUP BY ALL"""
BANDED = """SELECT l_orderkey AS i, least(l_orderkey + l_linenumber - 1, (SELECT max(o_orderkey) FROM orders)) AS j, count(*) AS v
FROM lineitem GROUP BY ALL"""
TOKENS = "SELECT doc_id, unnest(string_split(lower(text), ' ')) AS token FROM documents"
DOC_TERM = f"""SELECT doc_id AS i, r AS j, count(*) AS v FROM ({TOKENS}) t JOIN (
SELECT token, row_number() OVER (ORDER BY token) - 1 AS r FROM (SELECT DISTINCT token FROM ({TOKENS}) WHERE token <> '')) d
USING (token) GROUP BY ALL"""
TERM_NUMBERS = f"(SELECT row_number() OVER () - 1 AS r FROM (SELECT DISTINCT token FROM ({TOKENS}) WHERE token <> ''))"
TERMS = f"(SELECT count(DISTINCT token) FROM ({TOKENS}) WHERE token <> '')"
EMB_GRAPH = """SELECT i, j, CAST(1 AS BIGINT) AS v FROM (
SELECT x.vec_id AS i, y.vec_id AS j, sum(x.q * y.q) AS s, min(x.n) AS n1, min(y.n) AS n2
FROM (SELECT *, sum(q * q) OVER (PARTITION BY vec_id) AS n FROM (SELECT vec_id, generate_subscripts(embedding, 1) AS d,
  CAST(floor(1000 * CAST(unnest(embedding) AS DOUBLE) + 0.5) AS BIGINT) AS q FROM embeddings)) x
JOIN (SELECT *, sum(q * q) OVER (PARTITION BY vec_id) AS n FROM (SELECT vec_id, generate_subscripts(embedding, 1) AS d,
  CAST(floor(1000 * CAST(unnest(embedding) AS DOUBLE) + 0.5) AS BIGINT) AS q FROM embeddings)) y
ON x.d = y.d AND x.vec_id <> y.vec_id GROUP BY 1, 2) WHERE s > 0 AND 25 * s * s >= n1 * n2"""
HREF = """SELECT page_id, href, count(*) AS n FROM (
SELECT page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS href FROM pages) GROUP BY ALL"""


def rmat(scale: int, edge_factor: int = 8, seed: int = 42, merge: bool = True) -> str:
    levels = range(scale)
    digit = lambda level: (
        f"CAST('0x' || substr(md5('{seed}:' || e || ':{level // 8}'), {4 * (level % 8) + 1}, 4) AS BIGINT)"
    )
    weight = lambda level: 1 << (scale - 1 - level)
    row = " + ".join(f"CASE WHEN u{x} >= 48060 THEN {weight(x)} ELSE 0 END" for x in levels)
    col = " + ".join(f"CASE WHEN (u{x} >= 39322 AND u{x} < 48060) OR u{x} >= 56798 THEN {weight(x)} ELSE 0 END" for x in levels)
    edges = f"SELECT {', '.join(f'{digit(x)} AS u{x}' for x in levels)} FROM range({edge_factor << scale}) t(e)"
    cells = f"SELECT CAST({row} AS BIGINT) AS i, CAST({col} AS BIGINT) AS j FROM ({edges})"
    if merge:
        return f"SELECT i, j, count(*) AS v FROM ({cells}) GROUP BY ALL"
    return f"SELECT i, j, CAST(1 AS BIGINT) AS v FROM ({cells})"


def grid_b(keys: str, key: str, n: int) -> str:
    """A dense operand by rule over the dense keys of a table."""
    return f"SELECT {key} AS i, j, CAST((31 * {key} + 17 * j) % 97 - 48 AS BIGINT) AS v FROM {keys}, range({n}) g(j)"


def transpose(a: str) -> str:
    return f"SELECT j AS i, i AS j, v FROM ({a})"


def product(a: str, b: str, value: str = "CAST(sum(a.v * b.v) AS BIGINT)") -> str:
    return f"WITH a AS ({a}), b AS ({b}) SELECT a.i AS i, b.j AS j, {value} AS v FROM a JOIN b ON a.j = b.i GROUP BY a.i, b.j"


def units(a: str, b: str, hm: int, hk: int, hn: int) -> str:
    """(ti, tk, tj, mults) of units that have any, for tile extents."""
    return f"""SELECT CAST(ti AS INTEGER) AS ti, CAST(tk AS INTEGER) AS tk, CAST(tj AS INTEGER) AS tj, CAST(sum(ca * rb) AS BIGINT) AS mults
FROM (SELECT i // {hm} AS ti, j AS k, j // {hk} AS tk, count(*) AS ca FROM ({a}) GROUP BY ALL) x
JOIN (SELECT i AS k, j // {hn} AS tj, count(*) AS rb FROM ({b}) GROUP BY ALL) y USING (k) GROUP BY 1, 2, 3"""


def permutation(size: int, seed: int) -> str:
    """(id, x) of the keyed bijection of 0..size-1, walked until it is inside."""
    h = half_bits(size)
    shown = "id, n, x >> %d AS p0, x & %d AS q0 FROM walk WHERE n = 0 OR x >= %d" % (h, (1 << h) - 1, size)
    step = f"SELECT {shown}"
    for r, (k1, k2) in enumerate(permutation_keys(seed)):
        mixed = f"(((q{r} * q{r} + {k1} * q{r} + {k2}) % 2147483647) >> 3) & {(1 << h) - 1}"
        step = f"SELECT id, n, q{r} AS p{r + 1}, xor(p{r}, {mixed}) AS q{r + 1} FROM ({step})"
    return f"""(WITH RECURSIVE walk AS (SELECT r AS id, r AS x, 0 AS n FROM range({size}) t(r) UNION ALL
SELECT id, (p4 << {h}) | q4 AS x, n + 1 AS n FROM ({step})) SELECT id, x FROM walk WHERE n > 0 AND x < {size})"""


def permuted(a: str, size: int, seed_rows: int, seed_cols: int) -> str:
    return f"SELECT r.x AS i, c.x AS j, v FROM ({a}) JOIN {permutation(size, seed_rows)} r ON i = r.id JOIN {permutation(size, seed_cols)} c ON j = c.id"


def digest(c: str) -> str:
    """(j, entries, total, weighted) of a product's columns."""
    return f"SELECT j, count(*) AS entries, CAST(sum(v) AS BIGINT) AS total, CAST(sum(v * (i % 1009)) AS BIGINT) AS weighted FROM ({c}) GROUP BY j"


def part_loads(units: str, slots: int) -> str:
    """(part, pieces, mults) of the units' plan of partitions."""
    return f"""WITH u AS (SELECT ti, tk, tj, mults, sum(mults) OVER () AS total,
coalesce(sum(mults) OVER (ORDER BY ti, tk, tj ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before FROM ({units})),
n AS (SELECT *, greatest(1, CAST(ceil(CAST(mults * {4 * slots} AS DOUBLE) / CAST(total AS DOUBLE)) AS BIGINT)) AS pieces FROM u),
e AS (SELECT *, unnest(range(pieces)) AS piece FROM n)
SELECT CAST(least({slots - 1}, ((before + ((2 * piece + 1) * mults) // (2 * pieces)) * {slots}) // total) AS INTEGER) AS part, count(*) AS pieces,
CAST(sum(((piece + 1) * mults) // pieces - (piece * mults) // pieces) AS BIGINT) AS mults FROM e GROUP BY 1"""
