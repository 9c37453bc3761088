"""SQL for another engine that computes the same answers: graph builders, fixpoints, level chains."""

from __future__ import annotations

from ..params import SketchParams, rate_schedule

_PIN = 1 << 40
_T = r"regexp_extract_all(lower(text), '\p{L}+')"


def _canon(src: str, dst: str, body: str) -> str:
    return f"SELECT DISTINCT least(a, b) AS src, greatest(a, b) AS dst FROM (SELECT {src} AS a, {dst} AS b {body}) WHERE a IS NOT NULL AND b IS NOT NULL AND a <> b"


def _within(group: str, member: str, table: str) -> str:
    one = f"SELECT DISTINCT {group} AS g, {member} AS m FROM {table}"
    return f"SELECT DISTINCT x.m AS src, y.m AS dst FROM ({one}) x JOIN ({one}) y ON x.g = y.g AND x.m < y.m"


_OL = "FROM orders JOIN lineitem ON o_orderkey = l_orderkey"
GRAPHS = {
    "part_supp": _canon("2 * l_partkey", "2 * l_suppkey + 1", "FROM lineitem"),
    "cust_supp": _canon("2 * o_custkey", "2 * l_suppkey + 1", _OL),
    "cust_part": _canon("2 * o_custkey", "2 * l_partkey + 1", _OL),
    "copart": _within("l_orderkey", "l_partkey", "lineitem"),
    "cosupp": _within("l_orderkey", "l_suppkey", "lineitem"),
    "part_day": _canon("2 * l_partkey", "2 * datediff('day', DATE '1970-01-01', CAST(l_shipdate AS DATE)) + 1", "FROM lineitem"),
    "word_adjacency": _canon("t[i]", "t[i + 1]", f"FROM (SELECT t, unnest(range(1, len(t))) AS i FROM (SELECT {_T} AS t FROM documents))"),
    "doc_word": _canon("'d' || doc_id", "'w' || w", f"FROM (SELECT doc_id, unnest(list_distinct({_T})) AS w FROM documents)"),
    "conv_word": _canon("'c' || conv_id", "'w' || w", f"FROM (SELECT conv_id, unnest(list_distinct({_T})) AS w FROM conversations)"),
    "page_link": _canon("'p' || page_id", "'h' || w", """FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href="([^"]+)"', 1)) AS w FROM pages)"""),
    "user_hour": _within("date_trunc('hour', ts)", "user_id", "events"),
    "user_hour_type": _within("(date_trunc('hour', ts), event_type)", "user_id", "events"),
    "user_minute": _within("date_trunc('minute', ts)", "user_id", "events"),
}


def fixpoint(name: str, edges: str, pinned: str | None = None) -> str:
    """CTEs ending in `name` (id, v): largest fixpoint of h-indices over the edges CTE, pinned ids never labelled."""
    pin = f"SELECT id FROM {pinned}" if pinned else "SELECT NULL AS id WHERE false"
    return f"""
{name}_pin AS ({pin}),
{name}_arcs AS (SELECT src AS a, dst AS b FROM {edges} UNION ALL SELECT dst, src FROM {edges}),
{name}_it(i, id, v, ch) AS (
  SELECT 0, a, CASE WHEN a IN (SELECT id FROM {name}_pin) THEN {_PIN} ELSE count(*) END::BIGINT, 1 FROM {name}_arcs GROUP BY a
  UNION ALL
  SELECT i + 1, id, nv, max(CASE WHEN nv < v THEN 1 ELSE 0 END) OVER () FROM (
    SELECT o.i, o.id, o.v, CASE WHEN o.v = {_PIN} THEN o.v ELSE max(least(n.v, n.rk)) END AS nv
    FROM {name}_it o JOIN (
      SELECT r.a, x.v, row_number() OVER (PARTITION BY r.a ORDER BY x.v DESC) AS rk FROM {name}_arcs r JOIN {name}_it x ON x.id = r.b) n ON n.a = o.id
    WHERE o.ch = 1 GROUP BY o.i, o.id, o.v)),
{name} AS (SELECT id, v FROM {name}_it WHERE i = (SELECT max(i) FROM {name}_it) AND v < {_PIN})"""


def coreness(graph: str) -> str:
    """`WITH RECURSIVE` head that defines e (src, dst) and c (id, v)."""
    return f"WITH RECURSIVE e AS ({GRAPHS[graph]}), {fixpoint('c', 'e')}"


#: Disjoint cliques of 2 to `most` vertices, as sources.clique_ladder makes them.
LADDER_EDGES = "SELECT 1000 * k + i AS src, 1000 * k + j AS dst FROM (SELECT unnest(range(2, {most} + 1)) AS k), (SELECT unnest(range({most})) AS i), (SELECT unnest(range({most})) AS j) WHERE i < j AND j < k"


def sketch_chain(graph: str, p: SketchParams, n: int | None = None) -> str:
    """graph: a name in GRAPHS, or a query for canonical edges. Head that defines e, c (exact), settled (id, label, level, raw), sizes (level, edges) for md5 samples.

    The schedule must not depend on n (p0 and accept given as numbers), so both engines use the same printed rates.
    """
    levels = rate_schedule(n or 1000, p)
    u = f"CAST('0x' || substr(md5('{p.seed}:' || src || ':' || dst), 1, 13) AS BIGINT)"
    parts = [f"e AS ({GRAPHS.get(graph, graph)})", fixpoint("c", "e"), f"ann AS (SELECT src, dst, {u} AS u FROM e)"]
    done = []
    for lv in levels:
        k = lv.level
        settled = " UNION ALL ".join(f"SELECT id FROM took{j}" for j in done) if done else "SELECT NULL AS id WHERE false"
        parts.append(f"set{k} AS ({settled})")
        drawn = u.replace(f"md5('{p.seed}:'", f"md5('{p.seed}/{k}:'") if p.sampler == "fresh" else "u"
        rate = f"{drawn} <= {int(lv.rate * (1 << 52))}" if lv.rate < 1 else "true"
        parts.append(f"h{k} AS (SELECT src, dst FROM ann WHERE {rate} AND NOT (src IN (SELECT id FROM set{k} WHERE id IS NOT NULL) AND dst IN (SELECT id FROM set{k} WHERE id IS NOT NULL)))")
        parts.append(fixpoint(f"r{k}", f"h{k}", f"set{k}"))
        factor = 1.0 if not p.deflate or (p.exact_last and lv.rate >= 1) else 1 - p.eps
        clip = "v" if lv.cap == float("inf") else f"least(v, {lv.cap})"
        cond = f"WHERE v >= {lv.accept}" if lv.rate < 1 else ""
        parts.append(f"took{k} AS (SELECT id, {factor} * {clip} / {lv.rate!r} AS label, {k} AS level, CAST(ceil({clip}) AS BIGINT) AS raw FROM r{k} {cond})")
        done.append(k)
    parts.append("settled AS (" + " UNION ALL ".join(f"SELECT * FROM took{k}" for k in done) + ")")
    parts.append("sizes AS (" + " UNION ALL ".join(f"SELECT {lv.level} AS level, {lv.rate!r} AS rate, (SELECT count(*) FROM h{lv.level}) AS edges" for lv in levels) + ")")
    return "WITH RECURSIVE " + ",\n".join(parts)
