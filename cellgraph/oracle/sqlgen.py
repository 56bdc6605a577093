"""DuckDB SQL for graph queries: builders, ids, unrolled rounds, closures."""

from __future__ import annotations

from ..sources.builders import OFFSET

_SUCC = "SELECT {key} AS s, lead({key}) OVER (PARTITION BY {part} ORDER BY {order}) AS t FROM {table}"


def _clean(inner: str) -> str:
    return f"SELECT DISTINCT s AS src_key, t AS dst_key FROM ({inner}) WHERE s IS NOT NULL AND t IS NOT NULL AND s <> t"


def _custday(where: str = "true") -> str:
    return _clean(_SUCC.format(key="o_custkey", part="o_orderdate", order="o_orderkey", table=f"(SELECT * FROM orders WHERE {where})"))


_HALF = """SELECT p.p_partkey AS s, p.p_partkey + d.d AS t FROM part p,
  (SELECT CAST(ceil(sqrt(count(*))) AS BIGINT) AS w, max(p_partkey) AS top FROM part) z,
  LATERAL (VALUES (CAST(1 AS BIGINT), p.p_partkey % z.w < z.w - 1), (z.w, true), (z.w + 1, p.p_partkey % z.w < z.w - 1)) d(d, ok)
  WHERE d.ok AND p.p_partkey + d.d <= z.top"""

#: SELECT src_key, dst_key of each builder.
GRAPHS = {
    "copart": _clean(_SUCC.format(key="l_partkey", part="l_orderkey", order="l_linenumber, l_partkey, l_suppkey", table="lineitem")),
    "custday": _custday(),
    "custhigh": _custday("o_orderpriority IN ('1-URGENT', '2-HIGH')"),
    "custurg": _custday("o_orderpriority = '1-URGENT'"),
    "user": _clean("SELECT user_id AS s, lead(user_id) OVER (ORDER BY ts, event_id) AS t FROM events WHERE event_type = 'purchase'"),
    "trade": _clean(f"SELECT o_custkey AS s, l_suppkey + {OFFSET} AS t FROM orders JOIN lineitem ON o_orderkey = l_orderkey"),
    "web": _clean("SELECT 'page:' || page_id AS s, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS t FROM pages"),
    "talk": _clean("SELECT a.conv_id * 100 + a.turn AS s, b.conv_id * 100 + b.turn AS t FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1"),
    "lattice": _clean(f"SELECT s, t FROM ({_HALF}) UNION ALL SELECT t, s FROM ({_HALF})"),
    "knn": _clean(
        """SELECT x.s, x.t FROM (SELECT s, t FROM (
             SELECT a.vec_id AS s, b.vec_id AS t, row_number() OVER (PARTITION BY a.vec_id ORDER BY list_cosine_similarity(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])) DESC, b.vec_id) AS r
             FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id) WHERE r <= 6) x
           UNION ALL SELECT t, s FROM (
             SELECT a.vec_id AS s, b.vec_id AS t, row_number() OVER (PARTITION BY a.vec_id ORDER BY list_cosine_similarity(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])) DESC, b.vec_id) AS r
             FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id) WHERE r <= 6"""
    ),
    "userk": _clean(f"SELECT user_id AS s, CAST(props->>'k' AS BIGINT) + {OFFSET} AS t FROM events"),
}


def base(graph: str, bands: int = 4, symmetric: bool = False, recursive: bool = False) -> str:
    """WITH ... e(src, dst, sb, db), v(vid, raw_key, out_deg, in_deg, band), nn(n, m)."""
    edges = "SELECT s.vid AS src, d.vid AS dst FROM raw JOIN vm s ON s.raw_key = src_key JOIN vm d ON d.raw_key = dst_key"
    if symmetric:
        edges = f"SELECT DISTINCT src, dst FROM (SELECT src, dst FROM ({edges}) UNION ALL SELECT dst, src FROM ({edges}))"
    return f"""WITH {'RECURSIVE ' if recursive else ''}raw AS MATERIALIZED ({GRAPHS[graph]}),
vm AS MATERIALIZED (SELECT k AS raw_key, row_number() OVER (ORDER BY k) AS vid FROM (SELECT src_key AS k FROM raw UNION SELECT dst_key FROM raw)),
nn AS MATERIALIZED (SELECT count(*) AS n, greatest(1, CAST(ceil(count(*) / {bands}.0) AS BIGINT)) AS w FROM vm),
e AS MATERIALIZED (SELECT src, dst, CAST((src - 1) // w + 1 AS INTEGER) AS sb, CAST((dst - 1) // w + 1 AS INTEGER) AS db FROM ({edges}), nn),
v AS MATERIALIZED (SELECT vm.vid, raw_key, coalesce(o.c, 0) AS out_deg, coalesce(i.c, 0) AS in_deg, CAST((vm.vid - 1) // w + 1 AS INTEGER) AS band
  FROM vm CROSS JOIN nn LEFT JOIN (SELECT src, count(*) AS c FROM e GROUP BY src) o ON o.src = vm.vid LEFT JOIN (SELECT dst, count(*) AS c FROM e GROUP BY dst) i ON i.dst = vm.vid)"""


def pagerank(graph: str, rounds: int = 10, damping: float = 0.85, dangling: str = "drop", start: str = "1.0::DOUBLE", tail: str = "SELECT vid, round(rank, 8) AS rank FROM r{k}") -> str:
    parts = [base(graph), f"r0 AS MATERIALIZED (SELECT vid, {start} / n AS rank FROM v, nn)"]
    for k in range(1, rounds + 1):
        lost = f" + (SELECT coalesce(sum(rank), 0) FROM r{k - 1} JOIN v USING (vid) WHERE out_deg = 0) / n" if dangling == "spread" else ""
        parts.append(
            f"""r{k} AS MATERIALIZED (SELECT v.vid, (1 - {damping}::DOUBLE) / n + {damping}::DOUBLE * (coalesce(c.s, 0){lost}) AS rank
  FROM v CROSS JOIN nn LEFT JOIN (SELECT e.dst, sum(p.rank / s.out_deg) AS s FROM e JOIN r{k - 1} p ON p.vid = e.src JOIN v s ON s.vid = e.src GROUP BY e.dst) c ON c.dst = v.vid)"""
        )
    return ",\n".join(parts) + "\n" + tail.format(k=rounds)


def pagerank_units(graph: str, rounds: int = 10, units: int = 10**12) -> str:
    parts = [base(graph), f"r0 AS MATERIALIZED (SELECT vid, {units}::BIGINT // n AS rank FROM v, nn)"]
    for k in range(1, rounds + 1):
        parts.append(
            f"""r{k} AS MATERIALIZED (SELECT v.vid, {15 * units // 100}::BIGINT // n + (85 * coalesce(c.s, 0)) // 100 AS rank
  FROM v CROSS JOIN nn LEFT JOIN (SELECT e.dst, CAST(sum(p.rank // s.out_deg) AS BIGINT) AS s FROM e JOIN r{k - 1} p ON p.vid = e.src JOIN v s ON s.vid = e.src GROUP BY e.dst) c ON c.dst = v.vid)"""
        )
    return ",\n".join(parts) + f"\nSELECT vid, CAST(rank AS BIGINT) AS rank FROM r{rounds}"


def bfs(graph: str, tail: str = "SELECT v.vid, depth FROM v LEFT JOIN b USING (vid)", limit: int = 100, bands: int = 4) -> str:
    """Depth-capped recursion; b(vid, depth) holds what is reached from id 1."""
    return f"""{base(graph, bands, recursive=True)},
walk(vid, depth) AS (SELECT CAST(1 AS BIGINT), CAST(0 AS BIGINT) UNION SELECT e.dst, depth + 1 FROM walk JOIN e ON e.src = walk.vid WHERE depth < {limit}),
b AS MATERIALIZED (SELECT vid, min(depth) AS depth FROM walk GROUP BY vid)
{tail}"""


def wcc(graph: str, tail: str = "SELECT vid, attr FROM c") -> str:
    return f"""{base(graph, symmetric=True, recursive=True)},
reach(a, b) AS (SELECT vid, vid FROM v UNION SELECT reach.a, e.dst FROM reach JOIN e ON e.src = reach.b),
c AS MATERIALIZED (SELECT a AS vid, min(b) AS attr FROM reach GROUP BY a)
{tail}"""


def scc(graph: str, tail: str = "SELECT vid, attr FROM c") -> str:
    return f"""{base(graph, recursive=True)},
reach(a, b) AS (SELECT vid, vid FROM v UNION SELECT reach.a, e.dst FROM reach JOIN e ON e.src = reach.b),
c AS MATERIALIZED (SELECT x.a AS vid, min(x.b) AS attr FROM reach x JOIN reach y ON y.a = x.b AND y.b = x.a GROUP BY x.a)
{tail}"""
