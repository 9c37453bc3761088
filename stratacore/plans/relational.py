"""Relational operators around the methods: filters, joins by every strategy, windows, grouping sets, subqueries, text."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import core_histogram, edge_u52, first_level, peel_table
from ..operators import pairs, peel
from ..operators.sketch import sketch_coreness
from ..params import SketchParams, rate_schedule
from ..runtime import written
from ..sources import degrees, graph, load_table
from ..streaming import window_degrees
from .sqltext import GRAPHS, coreness, sketch_chain

BASE = SketchParams(accept=3, p0=2**-10, cap="scaled", hash="md5")
QUERIES: dict[str, tuple[Callable[[SparkSession, str], DataFrame], str | None]] = {}


def _query(name: str, sql: str | None = None):
    def put(f):
        QUERIES[name] = (f, sql)
        return f

    return put


def _core(s, d, g="part_supp"):
    return peel.exact_coreness(graph(s, d, g), "auto")


def _supplier_core(s, d):
    c = _core(s, d).where("id % 2 = 1").select(((F.col("id") - 1) / 2).cast("long").alias("s_suppkey"), "coreness")
    return load_table(s, d, "supplier").join(c, "s_suppkey").select("s_suppkey", "s_nationkey", "coreness")


_SC = coreness("part_supp") + ", sc AS (SELECT s_suppkey, s_nationkey, v AS coreness FROM supplier JOIN c ON c.id = 2 * s_suppkey + 1)"
_DEGREES = "SELECT id, count(*) AS degree FROM (SELECT src AS id FROM e UNION ALL SELECT dst FROM e) GROUP BY id"
_MD5 = "CAST('0x' || substr(md5('0:' || src || ':' || dst), 1, 13) AS BIGINT)"

# ---------------------------------------------------------------- filters

_RATE = rate_schedule(1000, BASE)[7].rate


@_query("op_level_filter", f"SELECT src, dst FROM ({GRAPHS['cust_supp']}) WHERE {_MD5} <= {int(_RATE * (1 << 52))}")
def _level_filter(s, d):
    rates = [x.rate for x in rate_schedule(1000, BASE)]
    return graph(s, d, "cust_supp").where(first_level(edge_u52(F.col("src"), F.col("dst"), 0, "md5"), rates) <= 7)


@_query("op_min_degree", f"WITH e AS ({GRAPHS['part_supp']}) SELECT id, degree FROM ({_DEGREES}) WHERE degree >= 30")
def _min_degree(s, d):
    return degrees(graph(s, d, "part_supp")).where("degree >= 30")


@_query("op_core_ge_k", coreness("cust_supp") + " SELECT id FROM c WHERE v >= 20")
def _core_ge_k(s, d):
    return _core(s, d, "cust_supp").where("coreness >= 20").select("id")


_FEW = "SELECT 2 * s_suppkey + 1 FROM supplier WHERE s_suppkey % 5 = 0"


@_query("op_in_settled", f"SELECT src, dst FROM ({GRAPHS['part_supp']}) WHERE dst IN ({_FEW}) OR src IN ({_FEW})")
def _in_settled(s, d):
    few = load_table(s, d, "supplier").where("s_suppkey % 5 = 0").select((2 * F.col("s_suppkey") + 1).alias("id"))
    return peel._flagged(graph(s, d, "part_supp"), few).where("su or sv").select("src", "dst")


# ---------------------------------------------------------------- joins

_LABELLED = coreness("part_supp") + " SELECT src, dst, v AS coreness FROM e JOIN c ON c.id = e.src"
for _name, _hint in (("broadcast_labels", "broadcast"), ("smj_labels", "merge"), ("shuffle_hash", "shuffle_hash")):

    @_query(f"op_join_{_name}", _LABELLED)
    def _hinted(s, d, hint=_hint):
        e = written(graph(s, d, "part_supp"), "edges")
        return e.join(peel.exact_coreness(e, "auto").hint(hint), F.col("id") == F.col("src")).select("src", "dst", "coreness")


@_query("op_left_degree", f"WITH e AS ({GRAPHS['cust_supp']}) SELECT c_custkey, coalesce(degree, 0) AS degree FROM customer LEFT JOIN ({_DEGREES}) g ON g.id = 2 * c_custkey")
def _left_degree(s, d):
    g = degrees(graph(s, d, "cust_supp"))
    return load_table(s, d, "customer").join(g, F.col("id") == 2 * F.col("c_custkey"), "left").select("c_custkey", F.coalesce("degree", F.lit(0)).alias("degree"))


_BOTH_WAYS = "SELECT src AS x, dst AS y FROM e UNION ALL SELECT dst, src FROM e"


@_query("op_two_hop", f"WITH e AS ({GRAPHS['page_link']}), a AS ({_BOTH_WAYS}) SELECT l.x AS id, count(DISTINCT r.y) AS reached FROM a l JOIN a r ON l.y = r.x AND r.y <> l.x GROUP BY l.x")
def _two_hop(s, d):
    from ..sources import arcs

    # Two vertices are two steps apart where they share a neighbour: vertices as members, their neighbours as groups.
    e, ids = peel.numbered(written(graph(s, d, "page_link"), "edges"))
    a = arcs(e.select(F.col("a").cast("long").alias("src"), F.col("b").cast("long").alias("dst")))
    sets = written(a.groupBy(F.col("src").alias("id")).agg(F.collect_list(F.col("dst").cast("int")).alias("slots")), "member-sets")
    reached = pairs.sharing_counts(sets).withColumnRenamed("id", "number")
    return ids.join(reached, ids["id"] == reached["number"]).select(F.col("key").alias("id"), F.col("n").alias("reached"))


_LISTS = {"accept": "l_linenumber + 1", "growth": "1 + CAST(l_suppkey % 4 + 1 AS DOUBLE) / 5", "seed": "l_partkey % 3"}


@_query("op_param_grid", "SELECT accept, growth, seed FROM " + " CROSS JOIN ".join(f"(SELECT DISTINCT {e} AS {c} FROM lineitem)" for c, e in _LISTS.items()))
def _param_grid(s, d):
    accept, growth, seed = (load_table(s, d, "lineitem").selectExpr(f"{e} AS {c}").distinct() for c, e in _LISTS.items())
    return accept.crossJoin(growth).crossJoin(seed)


@_query("op_asof_label", "SELECT event_id, (SELECT arg_max(n.value, n.event_id) FROM events n WHERE n.user_id = e.user_id AND n.event_id % 10 = 0 AND (n.ts < e.ts OR (n.ts = e.ts AND n.event_id <= e.event_id))) AS value FROM events e WHERE event_id % 10 <> 0")
def _asof_label(s, d):
    ev = load_table(s, d, "events").select("event_id", "ts", "user_id", "value")
    snapshots = ev.where("event_id % 10 = 0").select("event_id", "ts", "user_id", "value", F.lit(True).alias("snapshot"))
    both = snapshots.unionByName(ev.where("event_id % 10 != 0").withColumns({"value": F.lit(None).cast("double"), "snapshot": F.lit(False)}))
    line = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn("value", F.last("value", ignorenulls=True).over(line)).where("not snapshot").select("event_id", "value")


@_query("op_interval_edges", "SELECT DISTINCT a.user_id AS src, b.user_id AS dst FROM events a JOIN events b ON a.user_id < b.user_id AND abs(epoch(a.ts) - epoch(b.ts)) <= 60")
def _interval_edges(s, d):
    # A bucket as long as the interval: partners lie in the same bucket or a neighbouring one.
    at = F.unix_micros(F.col("ts").cast("timestamp"))
    ev = load_table(s, d, "events").select("user_id", at.alias("at"), F.floor(at / 60_000_000).alias("slot"))
    far = ev.select(F.col("user_id").alias("dst"), F.col("at").alias("at2"), F.explode(F.array(F.col("slot") - 1, F.col("slot"), F.col("slot") + 1)).alias("slot"))
    return ev.join(far, "slot").where((F.col("user_id") < F.col("dst")) & (F.abs(F.col("at") - F.col("at2")) <= 60_000_000)).select(F.col("user_id").alias("src"), "dst").distinct()


# ---------------------------------------------------------------- aggregation and windows


@_query("op_percentiles", f"WITH e AS ({GRAPHS['doc_word']}) SELECT quantile_cont(degree, 0.5) AS p50, quantile_cont(degree, 0.9) AS p90, quantile_cont(degree, 0.99) AS p99 FROM ({_DEGREES})")
def _percentiles(s, d):
    return degrees(graph(s, d, "doc_word")).agg(*[F.percentile("degree", F.lit(q)).alias(f"p{int(100 * q)}") for q in (0.5, 0.9, 0.99)])


def _spaces(s, d):
    out = None
    for name in ("cust_supp", "part_supp"):
        rows = s.createDataFrame([(name, x[0], x[2]) for x in sketch_coreness(graph(s, d, name), BASE).space], "graph string, level int, edges long")
        out = rows if out is None else out.unionByName(rows)
    return out


_SIZES = " UNION ALL ".join(f"SELECT '{g}' AS graph, level, edges FROM ({sketch_chain(g, BASE)} SELECT level, edges FROM sizes)" for g in ("cust_supp", "part_supp"))


@_query("op_space_rollup", f"SELECT graph, level, CAST(sum(edges) AS BIGINT) AS edges, CAST(grouping(graph, level) AS BIGINT) AS rolled FROM ({_SIZES}) GROUP BY ROLLUP(graph, level)")
def _space_rollup(s, d):
    return _spaces(s, d).rollup("graph", "level").agg(F.sum("edges").alias("edges"), F.grouping_id("graph", "level").cast("long").alias("rolled"))


@_query("op_lag_level", f"SELECT graph, level, edges, lag(edges) OVER w AS before, lead(edges) OVER w AS next FROM ({_SIZES}) WINDOW w AS (PARTITION BY graph ORDER BY level)")
def _lag_level(s, d):
    line = Window.partitionBy("graph").orderBy("level")
    return _spaces(s, d).select("graph", "level", "edges", F.lag("edges").over(line).alias("before"), F.lead("edges").over(line).alias("next"))


@_query("op_error_sets", sketch_chain("cust_supp", BASE) + " SELECT level, v // 10 AS band, count(*) AS vertices, round(avg(abs(label - v) / v), 6) AS error, CAST(grouping(level, v // 10) AS BIGINT) AS gid FROM settled JOIN c USING (id) GROUP BY GROUPING SETS ((level), (v // 10), ())")
def _error_sets(s, d):
    e = written(graph(s, d, "cust_supp"), "edges")
    both = sketch_coreness(e, BASE).labels.join(peel.exact_coreness(e, "auto"), "id").withColumn("band", F.floor(F.col("coreness") / 10))
    err = F.abs(F.col("label") - F.col("coreness")) / F.col("coreness")
    sets = both.groupingSets([["level"], ["band"], []], "level", "band")
    return sets.agg(F.count(F.lit(1)).alias("vertices"), F.round(F.avg(err), 6).alias("error"), F.grouping_id("level", "band").cast("long").alias("gid"))


@_query("op_range_frame", "SELECT l_suppkey, day, lines, CAST(sum(lines) OVER (PARTITION BY l_suppkey ORDER BY day RANGE BETWEEN 6 PRECEDING AND CURRENT ROW) AS BIGINT) AS week FROM (SELECT l_suppkey, datediff('day', DATE '1970-01-01', CAST(l_shipdate AS DATE)) AS day, count(*) AS lines FROM lineitem GROUP BY ALL)")
def _range_frame(s, d):
    day = F.datediff(F.col("l_shipdate").cast("date"), F.lit("1970-01-01").cast("date")).cast("long").alias("day")
    daily = load_table(s, d, "lineitem").groupBy("l_suppkey", day).agg(F.count(F.lit(1)).alias("lines"))
    return daily.withColumn("week", F.sum("lines").over(Window.partitionBy("l_suppkey").orderBy("day").rangeBetween(-6, 0)))


@_query("op_sorted_order", _SC + " SELECT s_suppkey, coreness FROM sc ORDER BY coreness DESC, s_suppkey")
def _sorted_order(s, d):
    return _supplier_core(s, d).select("s_suppkey", "coreness").orderBy(F.desc("coreness"), "s_suppkey")


# ---------------------------------------------------------------- subqueries


def _sql(s: SparkSession, text: str, **views: DataFrame) -> DataFrame:
    return s.sql(text, **views)


_CORRELATED = "SELECT s_suppkey, coreness FROM {sc} a WHERE coreness = (SELECT max(b.coreness) FROM {sc} b WHERE b.s_nationkey = a.s_nationkey)"


@_query("op_corr_max_core", _SC + " " + _CORRELATED.replace("{sc}", "sc"))
def _corr_max_core(s, d):
    return _sql(s, _CORRELATED, sc=written(_supplier_core(s, d), "supplier-core"))


_EXISTS = "SELECT c_custkey FROM {customer} c WHERE EXISTS (SELECT 1 FROM {orders} o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 300000)"
_IN = "SELECT p_partkey FROM {part} WHERE p_partkey IN (SELECT l_partkey FROM {lineitem} WHERE l_quantity >= 50)"


@_query("op_exists", _EXISTS.replace("{", "").replace("}", ""))
def _exists(s, d):
    return _sql(s, _EXISTS, customer=load_table(s, d, "customer"), orders=load_table(s, d, "orders"))


@_query("op_in", _IN.replace("{", "").replace("}", ""))
def _in(s, d):
    return _sql(s, _IN, part=load_table(s, d, "part"), lineitem=load_table(s, d, "lineitem"))


# ---------------------------------------------------------------- text and time

_T = r"regexp_extract_all(lower(text), '\p{L}+')"


def _tokens(df: DataFrame) -> DataFrame:
    return df.withColumn("token", F.explode(F.regexp_extract_all(F.lower("text"), F.lit(r"\p{L}+"), F.lit(0))))


@_query("op_tokens", f"SELECT token, count(*) AS n FROM (SELECT unnest({_T}) AS token FROM documents) GROUP BY token")
def _vocabulary(s, d):
    return _tokens(load_table(s, d, "documents").select("text")).groupBy("token").agg(F.count(F.lit(1)).alias("n"))


@_query("op_hrefs", """SELECT page_id, len(regexp_extract_all(html, 'href="([^"]+)"', 1))::BIGINT AS links FROM pages""")
def _hrefs(s, d):
    return load_table(s, d, "pages").select("page_id", F.size(F.regexp_extract_all("html", F.lit('href="([^"]+)"'), F.lit(1))).cast("long").alias("links"))


@_query("op_conv_words", f"SELECT conv_id, count(*) AS words, count(DISTINCT token) AS different FROM (SELECT conv_id, unnest({_T}) AS token FROM conversations) GROUP BY conv_id")
def _conv_words(s, d):
    per = _tokens(load_table(s, d, "conversations").select("conv_id", "text")).groupBy("conv_id", "token").agg(F.count(F.lit(1)).alias("n"))
    return per.groupBy("conv_id").agg(F.sum("n").alias("words"), F.count(F.lit(1)).alias("different"))


@_query("op_benchmark_overlap", f"SELECT lang, count(*) AS shared FROM (SELECT DISTINCT lang, unnest({_T}) AS token FROM documents) WHERE token IN (SELECT unnest({_T}) FROM benchmark) GROUP BY lang")
def _benchmark_overlap(s, d):
    words = _tokens(load_table(s, d, "benchmark").select("text")).select("token").distinct()
    mine = _tokens(load_table(s, d, "documents").select("lang", "text")).select("lang", "token").distinct()
    return mine.join(words, "token", "left_semi").groupBy("lang").agg(F.count(F.lit(1)).alias("shared"))


def timed_edges(s: SparkSession, d: str) -> DataFrame:
    """(edge_ts, src, dst): two users in one minute, at the time of the first one's event."""
    ev = load_table(s, d, "events").select("ts", "user_id")
    a = ev.select(F.date_trunc("minute", "ts").alias("slot"), F.col("user_id").alias("src"), F.col("ts").cast("timestamp").alias("edge_ts"))
    b = ev.select(F.date_trunc("minute", "ts").alias("slot"), F.col("user_id").alias("dst")).distinct()
    return a.join(b, "slot").where("src < dst").select("edge_ts", "src", "dst")


#: The same edges in SQL, with the wall clock of an edge.
TIMED = "SELECT a.ts AS edge_ts, a.user_id AS src, b.user_id AS dst FROM events a JOIN (SELECT DISTINCT date_trunc('minute', ts) AS slot, user_id FROM events) b ON date_trunc('minute', a.ts) = b.slot AND a.user_id < b.user_id"
_DAILY = f"SELECT strftime(date_trunc('day', edge_ts), '%Y-%m-%d') AS day, src, dst FROM ({TIMED}) GROUP BY ALL"
_ENDS = f"SELECT day, id, count(*) AS degree FROM (SELECT day, src AS id FROM ({_DAILY}) UNION ALL SELECT day, dst FROM ({_DAILY})) GROUP BY day, id"


def _daily(s, d):
    return window_degrees(timed_edges(s, d), "1 day").select(F.date_format("start", "yyyy-MM-dd").alias("day"), "id", "degree")


@_query("op_window_degrees", _ENDS)
def _window_degrees(s, d):
    return _daily(s, d)


@_query("op_window_edges", f"SELECT day, CAST(sum(degree) // 2 AS BIGINT) AS edges, count(*) AS vertices, max(degree) AS top FROM ({_ENDS}) GROUP BY day")
def _window_edges(s, d):
    return _daily(s, d).groupBy("day").agg((F.sum("degree") / 2).cast("long").alias("edges"), F.count(F.lit(1)).alias("vertices"), F.max("degree").alias("top"))


_UNIT = "(SELECT vec_id, [x / sqrt(list_dot_product(e, e)) for x in e] AS v FROM (SELECT vec_id, embedding::DOUBLE[] AS e FROM embeddings))"


@_query("op_vec_near", f"SELECT a.vec_id AS src, b.vec_id AS dst FROM {_UNIT} a JOIN {_UNIT} b ON a.vec_id < b.vec_id AND list_dot_product(a.v, b.v) >= 0.3")
def _vec_near(s, d):
    return graph(s, d, "vec_near")


# ---------------------------------------------------------------- user-defined aggregates and table functions


@_query("udaf_core_histogram", _SC + " SELECT s_nationkey, [" + ", ".join(f"count(*) FILTER (coreness >= {10 * k} AND (coreness < {10 * k + 10} OR {k} = 4))" for k in range(5)) + "] AS bins FROM sc GROUP BY s_nationkey")
def _histogram(s, d):
    return _supplier_core(s, d).groupBy("s_nationkey").agg(core_histogram("coreness").alias("bins"))


@_query("udtf_peel_order", coreness("page_link") + " SELECT id, v AS coreness FROM c")
def _peel_table(s, d):
    return peel_table(s, graph(s, d, "page_link")).select("id", "coreness")
