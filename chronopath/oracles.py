"""SQL twins of the engine's queries, built from shared common table expressions.

They compute each snapshot by itself from its edges with a recursive query keyed by
snapshot and vertex, and know nothing of bounds, reduction or masks' evaluation.
"""

from __future__ import annotations

from chronopath.functions.algebra import PathAlgebra

BASKET = """
g AS (
  SELECT src, dst, min(w)::DOUBLE AS w FROM (
    SELECT l_partkey AS src, l_quantity AS w,
           lead(l_partkey) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_quantity) AS dst
    FROM lineitem) WHERE dst IS NOT NULL AND src <> dst GROUP BY src, dst
)"""


def scripted(snapshots: int, batch: int, seed: int = 42) -> str:
    half, steps = batch // 2, snapshots - 1
    return f"""{BASKET}, ranked AS (
  SELECT *, row_number() OVER (ORDER BY ((src * 1000003 + dst * 7919 + {seed}) % 1000000007) * 48271 % 2147483647, src, dst) - 1 AS r FROM g
), lt AS (
  SELECT src, dst, w,
    CASE WHEN r < {half * steps} THEN 1 + (r // {half}) % {steps} ELSE 0 END::INTEGER AS born,
    CASE WHEN r >= {half * steps} AND r < {2 * half * steps} THEN 1 + (r // {half}) % {steps} ELSE {snapshots} END::INTEGER AS died
  FROM ranked
), snaps AS (SELECT range::INTEGER AS snap FROM range({snapshots}))"""


CORE = "core AS (SELECT src, dst, w FROM lt WHERE born = 0 AND died = (SELECT count(*) FROM snaps))"
HULL = "hull AS (SELECT src, dst, w FROM lt)"
ADDITIONS = "adds AS (SELECT src, dst, w, snap FROM lt, snaps WHERE born <= snap AND snap < died AND NOT (born = 0 AND died = (SELECT count(*) FROM snaps)))"


def mask(low: str = "born", high: str = "died") -> str:
    """Signed 64-bit word of up to 64 snapshots."""
    return f"(SELECT sum(CASE WHEN b = 63 THEN -9223372036854775808 ELSE (1::BIGINT << b::INTEGER)::HUGEINT END)::BIGINT FROM range({low}, {high}) AS t(b))"


def paths(name: str, edges: str, algebra: PathAlgebra, source: int, starts: str = "(SELECT 0 AS snap)") -> str:
    """``name(snap, v, val)``: best values over ``edges`` (a query of snap, src, dst, w)."""
    keep = "min" if algebra.direction == "min" else "max"
    better = "<" if algebra.direction == "min" else ">"
    start = "'infinity'::DOUBLE" if algebra.source_value == float("inf") else f"{algebra.source_value}::DOUBLE"
    extend = algebra.extend_sql.format(val="p.val", w="e.w")
    return f"""{name}_edges AS MATERIALIZED ({edges}),
{name}(snap, v, val) USING KEY (snap, v) AS (
  SELECT snap, {source}::BIGINT, {start} FROM {starts}
  UNION
  (SELECT c.snap, c.v, c.val FROM (
     SELECT e.snap AS snap, e.dst AS v, {keep}({extend}) AS val
     FROM {name} p JOIN {name}_edges e ON e.snap = p.snap AND e.src = p.v GROUP BY e.snap, e.dst) c
   LEFT JOIN recurring.{name} r ON r.snap = c.snap AND r.v = c.v
   WHERE r.val IS NULL OR c.val {better} r.val)
)"""


def per_snapshot(algebra: PathAlgebra, source: int) -> str:
    return paths("res", "SELECT snap, src, dst, w FROM lt, snaps WHERE born <= snap AND snap < died", algebra, source, "snaps")


def bounds(algebra: PathAlgebra, source: int) -> str:
    low, high = ("hull_val", "core_val") if algebra.direction == "min" else ("core_val", "hull_val")
    return f"""{CORE}, {HULL}, {ADDITIONS},
{paths("lo", "SELECT 0 AS snap, src, dst, w FROM core", algebra, source)},
{paths("hi", "SELECT 0 AS snap, src, dst, w FROM hull", algebra, source)},
bounds AS (
  SELECT coalesce(lo.v, hi.v) AS v, lo.val AS core_val, hi.val AS hull_val, {low.replace("hull_val", "hi.val").replace("core_val", "lo.val")} AS lower, {high.replace("hull_val", "hi.val").replace("core_val", "lo.val")} AS upper
  FROM lo FULL JOIN hi ON lo.v = hi.v
), unstable AS (SELECT v FROM bounds WHERE core_val IS DISTINCT FROM hull_val),
residual AS (SELECT c.* FROM core c WHERE dst IN (SELECT v FROM unstable)),
trimmed AS (SELECT a.* FROM adds a WHERE dst IN (SELECT v FROM unstable))"""


def recursive(*parts: str) -> str:
    return "WITH RECURSIVE " + ",\n".join(parts)


def _pairs(body: str) -> str:
    return f"SELECT src, dst, min(w)::DOUBLE AS w FROM ({body}) WHERE src <> dst AND dst IS NOT NULL GROUP BY src, dst"


def _text_id(salt: str, col: str) -> str:
    return f"('0x' || substr(md5('{salt}' || {col}), 1, 15))::BIGINT"


def _grams(table: str, key: str, n: int = 5) -> str:
    words = f"SELECT {key} AS id, regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^ \\t\\n\\x0B\\f\\r]+') AS words FROM {table}"
    return f"SELECT DISTINCT id, md5(array_to_string(words[i:i + {n - 1}], ' ')) AS h FROM (SELECT id, words, unnest(range(1, len(words) - {n - 2})) AS i FROM ({words}))"


_TRADE = "SELECT 2 * o_custkey AS a, 2 * l_suppkey + 1 AS b, l_quantity AS w FROM lineitem JOIN orders ON l_orderkey = o_orderkey"
_SUPPLY = "SELECT 2 * l_partkey AS a, 2 * l_suppkey + 1 AS b, floor(l_extendedprice / 1000) AS w FROM lineitem"


def _both_ways(body: str) -> str:
    return f"WITH m AS ({body}) " + _pairs("SELECT a AS src, b AS dst, w FROM m UNION ALL SELECT b, a, w FROM m")


GRAPH_SQL = {
    "basket": f"WITH {BASKET} SELECT * FROM g",
    "trade": _both_ways(_TRADE),
    "supply": _both_ways(_SUPPLY),
    "visit": _pairs("SELECT user_id AS src, lead(user_id) OVER (PARTITION BY event_type, ts::DATE ORDER BY ts, event_id) AS dst, greatest(1, ceil(value)) AS w FROM events"),
    "geo": "SELECT (-1 - n_regionkey)::BIGINT AS src, n_nationkey::BIGINT AS dst, 1.0::DOUBLE AS w FROM nation UNION ALL SELECT c_nationkey::BIGINT, 1000 + 2 * c_custkey, 1.0 FROM customer UNION ALL SELECT s_nationkey::BIGINT, 1001 + 2 * s_suppkey, 1.0 FROM supplier",
    "reply": _pairs("SELECT 1000 * conv_id + turn AS src, lead(1000 * conv_id + turn) OVER (PARTITION BY conv_id ORDER BY turn) AS dst, 1 + coalesce(length(text), 0) // 100 AS w FROM conversations"),
    "linkhost": f"SELECT DISTINCT {_text_id('h', 'host')} AS src, {_text_id('p', 'path')} AS dst, 1.0::DOUBLE AS w FROM (SELECT regexp_extract(url, '^https?://([^/]+)', 1) AS host, unnest(regexp_extract_all(html, 'href=\"(/[^\"]*)\"', 1)) AS path FROM pages)",
    "curated": f"SELECT DISTINCT -1 - {_text_id('s', 'source')} AS src, doc_id AS dst, 1.0::DOUBLE AS w FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 1 AND toxic = 0)",
    "lookalike": f"WITH l AS ({_grams('documents', 'doc_id')}), f AS (SELECT h, min(id) AS a FROM l GROUP BY h HAVING count(*) > 1), m AS (SELECT a, id AS b, (1 + count(*))::DOUBLE AS w FROM l JOIN f USING (h) WHERE id <> a GROUP BY a, id) SELECT a AS src, b AS dst, w FROM m UNION ALL SELECT b, a, w FROM m",
    "quiz": f"WITH l AS ({_grams('documents', 'doc_id')}), i AS ({_grams('benchmark', 'item_id')}) SELECT DISTINCT -1 - i.id AS src, l.id AS dst, 1.0::DOUBLE AS w FROM l JOIN i USING (h)",
    "knn": "SELECT src, dst, 1 + d AS w FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY d, dst) AS r FROM (SELECT a.vec_id AS src, b.vec_id AS dst, round(list_sum(list_transform(list_zip(a.embedding, b.embedding), lambda p: (p[1]::DOUBLE - p[2]::DOUBLE) * (p[1]::DOUBLE - p[2]::DOUBLE))), 6) AS d FROM embeddings a JOIN embeddings b ON a.label = b.label AND a.vec_id <> b.vec_id)) WHERE r <= 3",
}
