"""The registered queries of the core-decomposition engine, each with the SQL that checks it where SQL can."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import functions as fn
from .operators import cores, pairs, peel
from .operators.sketch import sketch_coreness
from .params import SketchParams, rate_schedule
from .plans import experiments, grid, measures, relational
from .plans.relational import TIMED, timed_edges
from .plans.sqltext import GRAPHS, LADDER_EDGES, coreness, fixpoint, sketch_chain
from .runtime import Rounds, new_path, written
from .sources import arcs, clique_ladder, degrees, edges_from, graph, load_table, user_slots
from .streaming import StreamingSketch, contact_counts, match_batches, multi_pass, run_windows, session_contacts, window_contacts, with_dimension

#: Rates are binary fractions here, so that both engines compare the same numbers.
BASE = SketchParams(accept=3, p0=2**-10, cap="scaled", hash="md5")
_QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
_SQL: dict[str, str] = {}


def _query(name: str, sql: str | None = None):
    def put(f):
        _QUERIES[name] = f
        if sql:
            _SQL[name] = sql
        return f

    return put


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(_QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(_SQL)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _labels(sketch_coreness(graph(spark, sf_dir, "cust_supp"), replace(BASE, hash="xxhash64", p0="scaled")))


def _labels(s) -> DataFrame:
    """The labels of a sketch, or a table of them, as both engines print them."""
    return (s if isinstance(s, DataFrame) else s.labels).select("id", F.round("label", 6).alias("label"), "level", "raw")


_LABELS_SQL = " SELECT id, round(label, 6) AS label, level, raw FROM settled"


# ---------------------------------------------------------------- graphs and scans

for _g in GRAPHS:
    _query(f"graph_{_g}", GRAPHS[_g])(lambda s, d, g=_g: graph(s, d, g))

for _t, _cols in {"lineitem": "l_orderkey, l_partkey, l_suppkey, l_linenumber", "orders": "o_orderkey, o_custkey, o_orderstatus", "customer": "c_custkey, c_mktsegment", "part": "p_partkey, p_size", "supplier": "s_suppkey, s_nationkey", "nation": "n_nationkey, n_name, n_regionkey", "region": "r_regionkey, r_name", "events": "event_id, user_id, event_type", "documents": "doc_id, lang, source", "pages": "page_id, url", "benchmark": "item_id, text", "labels": "doc_id, quality, toxic", "conversations": "conv_id, turn, role", "embeddings": "vec_id, label"}.items():
    _query(f"scan_{_t}", f"SELECT {_cols} FROM {_t}")(lambda s, d, t=_t, c=_cols: load_table(s, d, t).select(*c.split(", ")))


# ---------------------------------------------------------------- exact cores

_CORE = coreness("cust_supp") + " SELECT id, v AS coreness FROM c"
_query("core_exact", _CORE)(lambda s, d: peel.exact_coreness(graph(s, d, "cust_supp"), "auto"))
_query("core_exact_refine", _CORE)(lambda s, d: peel.exact_coreness(graph(s, d, "cust_supp"), "refine"))
_query("core_exact_waves", coreness("page_link") + " SELECT id, v AS coreness FROM c")(lambda s, d: peel.exact_coreness(graph(s, d, "page_link"), "waves"))
_query("core_exact_part_supp", coreness("part_supp") + " SELECT id, v AS coreness FROM c")(lambda s, d: peel.exact_coreness(graph(s, d, "part_supp"), "auto"))
_query("core_exact_doc_word", coreness("doc_word") + " SELECT id, v AS coreness FROM c")(lambda s, d: peel.exact_coreness(graph(s, d, "doc_word"), "auto"))
_query("vertex_refine", coreness("part_supp") + " SELECT id, v AS coreness FROM c")(lambda s, d: peel.exact_coreness(graph(s, d, "part_supp"), "refine"))


def _core_sql(g: str, k: int) -> str:
    return coreness(g) + f" SELECT src, dst FROM e WHERE src IN (SELECT id FROM c WHERE v >= {k}) AND dst IN (SELECT id FROM c WHERE v >= {k})"


_query("kcore_k3", _core_sql("page_link", 3))(lambda s, d: peel.k_core(graph(s, d, "page_link"), 3))
_query("kcore_k20", _core_sql("cust_supp", 20))(lambda s, d: peel.k_core(graph(s, d, "cust_supp"), 20))

_LEVELS_SQL = " , lv AS (SELECT e.src, e.dst, least(x.v, y.v) AS k FROM e JOIN c x ON x.id = src JOIN c y ON y.id = dst), ks AS (SELECT DISTINCT v AS k FROM c), hier AS (SELECT k, (SELECT count(*) FROM c WHERE v >= ks.k) AS vertices, (SELECT count(*) FROM lv WHERE lv.k >= ks.k) AS edges FROM ks)"


def _hier(s, d, g="cust_supp"):
    e = written(graph(s, d, g), "edges")
    return cores.core_hierarchy(e, peel.exact_coreness(e, "auto"))


_query("core_hierarchy", coreness("cust_supp") + _LEVELS_SQL + " SELECT k, vertices, edges, round(edges / vertices, 6) AS density FROM hier")(lambda s, d: _hier(s, d).withColumn("density", F.round("density", 6)))
_query("densest_from_core", coreness("cust_supp") + _LEVELS_SQL + " SELECT k, vertices, edges FROM hier ORDER BY edges / vertices DESC, k LIMIT 1")(lambda s, d: cores.densest_from_cores(_hier(s, d)).select("k", "vertices", "edges"))

_PINNED_SQL = f"WITH RECURSIVE e0 AS ({GRAPHS['cust_supp']}), pin AS (SELECT 2 * s_suppkey + 1 AS id FROM supplier WHERE s_suppkey % 10 = 0), e AS (SELECT * FROM e0 WHERE NOT (src IN (SELECT id FROM pin) AND dst IN (SELECT id FROM pin))), {fixpoint('c', 'e', 'pin')}"


def _pinned(s, d):
    return load_table(s, d, "supplier").where("s_suppkey % 10 = 0").select((2 * F.col("s_suppkey") + 1).alias("id"))


_query("excl_label", _PINNED_SQL + " SELECT id, v AS label FROM c")(lambda s, d: peel.exclusive_labels(graph(s, d, "cust_supp"), _pinned(s, d), method="auto"))
_query("excl_label_distributed", _PINNED_SQL + " SELECT id, v AS label FROM c")(lambda s, d: peel.exclusive_labels(graph(s, d, "cust_supp"), _pinned(s, d)))
_query("excl_label_capped", _PINNED_SQL + " SELECT id, least(v, 6) AS label FROM c")(lambda s, d: peel.exclusive_labels(graph(s, d, "cust_supp"), _pinned(s, d), cap=6))
_query("prepeel_labels", coreness("page_link") + " SELECT id, v AS label FROM c WHERE v < 3")(lambda s, d: peel.prepeel_labels(graph(s, d, "page_link"), 3)[1])


def _orient(s, d):
    e = written(graph(s, d, "part_supp"), "edges")
    order = written(cores.peel_order(e), "order")
    into = cores.orient_edges(e, order).groupBy(F.col("head").alias("id")).agg(F.count(F.lit(1)).alias("k"))
    return order.join(into, "id", "left").agg(F.count(F.lit(1)).alias("vertices"), F.count(F.when(F.col("k") > F.col("coreness"), 1)).alias("broken"))


_query("orient_bound", coreness("part_supp") + " SELECT count(*) AS vertices, CAST(0 AS BIGINT) AS broken FROM c")(_orient)


# ---------------------------------------------------------------- the sketch

for _t in (2, 3, 4, 5):
    _p = replace(BASE, accept=_t)
    _query(f"sketch_batch_T{_t}", sketch_chain("cust_supp", _p) + _LABELS_SQL)(lambda s, d, p=_p: _labels(sketch_coreness(graph(s, d, "cust_supp"), p)))
for _m in (1.2, 1.4, 1.6, 2.0):
    _p = replace(BASE, growth=_m, p0=2**-3)
    _query(f"sketch_batch_M{str(_m).replace('.', '')}", sketch_chain("part_supp", _p) + _LABELS_SQL)(lambda s, d, p=_p: _labels(sketch_coreness(graph(s, d, "part_supp"), p)))
_T3 = sketch_chain("cust_supp", BASE) + _LABELS_SQL
_query("sketch_mr", _T3)(lambda s, d: _labels(sketch_coreness(graph(s, d, "cust_supp"), replace(BASE, rounds="two", peeler="local"))))
_query("sketch_fused", _T3)(lambda s, d: _labels(sketch_coreness(graph(s, d, "cust_supp"), replace(BASE, rounds="fused", peeler="local"))))
_query("sketch_distributed", _T3)(lambda s, d: _labels(sketch_coreness(graph(s, d, "cust_supp"), replace(BASE, peeler="distributed", p0=2**-10))))
_PP = replace(BASE, p0=2**-5)
_query("sketch_prepeel", sketch_chain("part_supp", _PP) + _LABELS_SQL)(lambda s, d: _labels(sketch_coreness(graph(s, d, "part_supp"), replace(_PP, prepeel=3))))
_THEORY = SketchParams(hash="md5", p0=1.0)
_query("sketch_theory", coreness("cust_supp") + " SELECT id, round(CAST(0.75 AS DOUBLE) * v, 6) AS label, 0 AS level, v AS raw FROM c")(lambda s, d: _labels(sketch_coreness(graph(s, d, "cust_supp"), SketchParams(hash="md5"))))
_query("sketch_upper", coreness("cust_supp") + " SELECT id, round(CAST(1.5 AS DOUBLE) * v, 6) AS label, 0 AS level, v AS raw FROM c")(lambda s, d: _labels(sketch_coreness(graph(s, d, "cust_supp"), SketchParams(side="upper"))))
_query("sketch_exact_last", coreness("cust_supp") + " SELECT id, CAST(v AS DOUBLE) AS label, 0 AS level, v AS raw FROM c")(lambda s, d: _labels(sketch_coreness(graph(s, d, "cust_supp"), SketchParams(exact_last=True))))
_FRESH = replace(BASE, sampler="fresh", p0=2**-6)
_query("sketch_fresh", sketch_chain("cust_supp", _FRESH) + _LABELS_SQL)(lambda s, d: _labels(sketch_coreness(graph(s, d, "cust_supp"), _FRESH)))
_query("sketch_doc_word", sketch_chain("doc_word", replace(BASE, p0=2**-8)) + _LABELS_SQL)(lambda s, d: _labels(sketch_coreness(graph(s, d, "doc_word"), replace(BASE, p0=2**-8))))
_SCHED = rate_schedule(1000, BASE)
_SCHEDULE = "SELECT * FROM (VALUES " + ", ".join(f"({x.level}, CAST({x.rate!r} AS DOUBLE), CAST({x.accept!r} AS DOUBLE))" for x in _SCHED) + ") t(level, rate, accept)"
_REACHED = "CASE " + " ".join(f"WHEN u <= {int(x.rate * (1 << 52))} THEN {x.level}" for x in _SCHED[:-1]) + f" ELSE {_SCHED[-1].level} END"


def _levels(s, d):
    """The schedule with the number of edges of cust_supp that each level is the first to hold."""
    rows = s.createDataFrame([(x.level, float(x.rate), float(x.accept)) for x in _SCHED], "level int, rate double, accept double")
    e = graph(s, d, "cust_supp").select(fn.edge_u52(F.col("src"), F.col("dst"), 0, "md5").alias("u"))
    held = e.groupBy(fn.first_level(F.col("u"), [x.rate for x in _SCHED]).alias("level")).agg(F.count(F.lit(1)).alias("edges"))
    return rows.join(held, "level", "left").select("level", "rate", "accept", F.coalesce("edges", F.lit(0)).alias("edges"))


_query("sketch_levels", f"SELECT level, rate, accept, coalesce(edges, 0) AS edges FROM ({_SCHEDULE}) LEFT JOIN (SELECT {_REACHED} AS level, count(*) AS edges FROM (SELECT CAST('0x' || substr(md5('0:' || src || ':' || dst), 1, 13) AS BIGINT) AS u FROM ({GRAPHS['cust_supp']})) GROUP BY 1) USING (level)")(_levels)


def _space(s, d):
    return s.createDataFrame([(x[0], x[1], x[2]) for x in sketch_coreness(graph(s, d, "cust_supp"), BASE).space], "level int, rate double, edges long")


_CHAIN = sketch_chain("cust_supp", BASE)
_query("space_levels", _CHAIN + " SELECT level, CAST(rate AS DOUBLE) AS rate, edges FROM sizes")(_space)
_query("space_max", _CHAIN + " SELECT max(edges) AS edges FROM sizes")(lambda s, d: _space(s, d).agg(F.max("edges").alias("edges")))
_query("space_sum", _CHAIN + " SELECT CAST(sum(edges) AS BIGINT) AS edges FROM sizes")(lambda s, d: _space(s, d).agg(F.sum("edges").alias("edges")))


def _ratio(s, d):
    e = written(graph(s, d, "cust_supp"), "edges")
    x = measures.space_report(sketch_coreness(e, BASE), e.count())[0]
    return s.createDataFrame([(round(x[2], 6), round(x[3], 6))], "max_share double, sum_share double")


_query("space_ratio", _CHAIN + " SELECT round(max(edges) / (SELECT count(*) FROM e), 6) AS max_share, round(sum(edges) / (SELECT count(*) FROM e), 6) AS sum_share FROM sizes")(_ratio)


def _pair(s, d, p=BASE):
    e = written(graph(s, d, "cust_supp"), "edges")
    return e, sketch_coreness(e, p), written(peel.exact_coreness(e, "auto"), "exact")


def _errors_sql(cond: str) -> str:
    ps = ", ".join(f"round(quantile_cont(abs(label - v) / v, {q}), 6) AS p{int(100 * q)}" for q in measures.POINTS)
    return _CHAIN + f" SELECT count(*) AS vertices, {ps} FROM settled JOIN c USING (id) WHERE {cond}"


def _errors(s, d, **k):
    _, sk, ex = _pair(s, d)
    return measures.error_percentiles(sk.labels, ex, **k)


_query("error_pct", _errors_sql("v >= 5"))(lambda s, d: _errors(s, d))
_query("error_all", _errors_sql("v >= 1"))(lambda s, d: _errors(s, d, least=1))
_query("error_sparse", _errors_sql("v >= 1 AND v < 5"))(lambda s, d: _errors(s, d, least=1, most=4))


def _factor(s, d):
    _, sk, ex = _pair(s, d)
    x = measures.approximation_factor(sk.labels, ex, BASE.eps)
    return x.select(*[F.round(c, 6).alias(c) for c in ("least", "greatest", "within")])


_query("approx_factor", _CHAIN + " SELECT round(min(label / v), 6) AS least, round(max(label / v), 6) AS greatest, round(avg(CASE WHEN label / v >= 0.5 - 1e-9 AND label / v <= 1 + 1e-9 THEN 1.0 ELSE 0.0 END), 6) AS within FROM settled JOIN c USING (id) WHERE v > 0")(_factor)


def _validity(s, d):
    _, sk, ex = _pair(s, d)
    return cores.label_bounds(sk.labels, ex, BASE.eps).select("id", "coreness")


_query("label_validity", _CHAIN + " SELECT id, v AS coreness FROM settled JOIN c USING (id) WHERE NOT (label <= v + 1e-9 AND label >= 0.5 * v - 1e-9)")(_validity)


def _approx_core(s, d):
    e, sk, _ = _pair(s, d)
    return cores.approx_k_core(e, sk.labels, 20, 0.5)[0]


_APPROX = _CHAIN + ", picked AS (SELECT id FROM settled WHERE label >= 10), f AS (SELECT src, dst FROM e WHERE src IN (SELECT id FROM picked) AND dst IN (SELECT id FROM picked)), " + fixpoint("a", "f") + " SELECT id FROM a WHERE v >= 10"
_query("approx_kcore", _APPROX)(_approx_core)


_HALF = "CAST('0x' || substr(md5('0:' || src || ':' || dst), 1, 13) AS BIGINT) / 4503599627370496 <= 0.5"


def _conc_sql(ends: str) -> str:
    close, high = "abs(h - 0.5 * g) <= 0.5 * h", "2 * 0.5 * 100"
    parts = (("dense", "g >= 100", close), ("sparse", "g < 100", f"h < {high}"), ("seen_dense", f"h >= {high}", f"{close} AND g >= 2 * 0.5 * 100"), ("seen_sparse", f"h < {high}", "g <= 2 * 1.5 * 100"))
    counts = ", ".join(f"count(*) FILTER ({w}) AS {n}, count(*) FILTER (({w}) AND NOT ({ok})) AS {n}_broken" for n, w, ok in parts)
    return f"WITH e AS ({GRAPHS['user_hour']}), x AS ({ends}), d AS (SELECT id, count(*) AS g, count(*) FILTER (kept) AS h FROM x GROUP BY id) SELECT {counts} FROM d"


_BOTH_ENDS = f"SELECT src AS id, {_HALF} AS kept FROM e UNION ALL SELECT dst, {_HALF} FROM e"
_IN_ENDS = f"SELECT dst AS id, {_HALF} AS kept FROM (SELECT src, dst FROM e UNION ALL SELECT dst, src FROM e)"


def _concentration(s, d, direction):
    e = graph(s, d, "user_hour")
    if direction == "in":
        e = arcs(e)
    kept = e.select("src", "dst", fn.drawn(F.col("src"), F.col("dst"), 0.5, 0, "md5").alias("kept"))
    ends = kept.select(F.explode(F.array("src", "dst")).alias("id"), "kept") if direction == "both" else kept.select(F.col("dst").alias("id"), "kept")
    return measures.drawn_concentration(ends, 0.5, 100, 0.5)


_query("degree_conc", _conc_sql(_BOTH_ENDS))(lambda s, d: _concentration(s, d, "both"))
_query("degree_conc_in", _conc_sql(_IN_ENDS))(lambda s, d: _concentration(s, d, "in"))

# The sketch with log constants, on a ladder of cliques where several levels below rate 1 settle vertices.
_LADDER_N = sum(range(2, experiments.LADDER + 1))


def _ladder_chain(seed: int) -> str:
    return sketch_chain(LADDER_EDGES.format(most=experiments.LADDER), replace(experiments.SMALL, seed=seed), _LADDER_N)


def _bands_sql(seed: int) -> str:
    n, eps = _LADDER_N, repr(experiments.SMALL.eps)
    high, low = f"v >= 2 * (1 + {eps}) * {n} / 2.0 ** (level - 1)", f"level < (SELECT max(level) FROM sizes) AND v < 2 * (1 - {eps}) * {n} / 2.0 ** level"
    return f"SELECT {seed} AS seed, level, count(*) AS vertices, count(*) FILTER ({high}) AS too_dense, count(*) FILTER ({low}) AS too_sparse FROM ({_ladder_chain(seed)} SELECT level, v, (SELECT max(level) FROM sizes) AS top FROM settled JOIN c USING (id)) GROUP BY level".replace("(SELECT max(level) FROM sizes) AND v", "top AND v")


_query("band_check", _bands_sql(0))(lambda s, d: experiments.claims(s, seeds=(0,)))
_query("sketch_theory_levels", _ladder_chain(0) + _LABELS_SQL)(lambda s, d: _labels(sketch_coreness(clique_ladder(s, experiments.LADDER), experiments.SMALL)))
_query("success_rate")(experiments.success_rate)


def _rounds(s, d):
    e = written(graph(s, d, "page_link"), "edges")
    rows = []
    for name, p in (("fused", replace(BASE, rounds="fused", peeler="local")), ("two", replace(BASE, rounds="two", peeler="local")), ("distributed", replace(BASE, peeler="distributed"))):
        rows.append(sketch_coreness(e, replace(p, p0=2**-4)).rounds.row(name))
    r = Rounds()
    cores.threshold_waves(e, rounds=r)
    return s.createDataFrame([*rows, r.row("threshold_waves")], "method string, levels int, jobs int, sweeps int, waves int")


_query("rounds")(_rounds)
_query("machine_load")(lambda s, d: measures.machine_load(graph(s, d, "cust_supp")))


# ---------------------------------------------------------------- baselines

_WAVE = "CASE WHEN v < 4 THEN 4 WHEN v < 8 THEN 8 WHEN v < 16 THEN 16 WHEN v < 32 THEN 32 WHEN v < 64 THEN 64 WHEN v < 128 THEN 128 WHEN v < 256 THEN 256 ELSE 512 END"
_query("threshold_wave", coreness("cust_supp") + f" SELECT id, CAST({_WAVE} AS BIGINT) AS estimate FROM c")(lambda s, d: cores.threshold_waves(graph(s, d, "cust_supp")))
_query("threshold_wave_counts", coreness("part_supp") + f" SELECT CAST({_WAVE} AS BIGINT) AS estimate, count(*) AS vertices FROM c GROUP BY 1")(lambda s, d: cores.threshold_waves(graph(s, d, "part_supp")).groupBy("estimate").agg(F.count(F.lit(1)).alias("vertices")))
_U = f"WITH RECURSIVE e0 AS ({GRAPHS['cust_supp']}), e AS (SELECT src, dst FROM e0 WHERE CAST('0x' || substr(md5('0:' || src || ':' || dst), 1, 13) AS BIGINT) / 4503599627370496 <= 0.25), {fixpoint('c', 'e')} SELECT id, coalesce(v, 0) AS raw, coalesce(v, 0) / 0.25 AS label FROM (SELECT src AS id FROM e0 UNION SELECT dst FROM e0) LEFT JOIN c USING (id)"
_query("uniform_sample_md5", _U)(lambda s, d: cores.uniform_sample_coreness(graph(s, d, "cust_supp"), 0.25, 0, "md5"))
_query("densest_peel")(lambda s, d: s.createDataFrame([(lambda x: (x[0], x[1].count(), x[2]))(cores.densest_by_peeling(written(graph(s, d, "part_supp"), "edges")))], "density double, vertices long, rounds int"))


# ---------------------------------------------------------------- streams


#: First days of the slices after the first one, in ship-date order.
_CUTS = ("1994-01-01", "1995-07-01", "1997-01-01")


def _slices(s, d):
    """cust_supp edges by the day they first appear on, in slices that together are the whole graph."""
    o, li = load_table(s, d, "orders"), load_table(s, d, "lineitem")
    e = o.join(li, F.col("o_orderkey") == F.col("l_orderkey")).select((2 * F.col("o_custkey")).alias("src"), (2 * F.col("l_suppkey") + 1).alias("dst"), F.col("l_shipdate").cast("date").cast("string").alias("day"))
    e = written(e.groupBy("src", "dst").agg(F.min("day").alias("day")), "edges")
    bounds = ["", *_CUTS, "9999"]
    return [e.where((F.col("day") >= a) & (F.col("day") < b)).select("src", "dst") for a, b in zip(bounds, bounds[1:], strict=False)]


_SP = replace(BASE, p0=2**-5, n_upper=1 << 16)


def _stream(s, d, relabel="full"):
    """Slices as files of a streaming source; the run is cut in two, the second part resumes from the saved state."""
    src, at, state = new_path(s, "edge-stream"), new_path(s, "stream-checkpoint"), new_path(s, "stream-state")
    for k, part in enumerate(_slices(s, d)):
        part.coalesce(1).write.mode("append").parquet(src)
        if k in (1, len(_CUTS)):
            sk = StreamingSketch(s, _SP, relabel)
            stream = s.readStream.schema("src long, dst long").option("maxFilesPerTrigger", 1).parquet(src)
            sk.start(stream, at, state).awaitTermination()
    return sk


_query("sketch_stream", sketch_chain("cust_supp", _SP) + _LABELS_SQL)(lambda s, d: _labels(_stream(s, d).labels()))


def _replayed(s, d, relabel="full"):
    sk = StreamingSketch(s, _SP, relabel)
    for part in _slices(s, d):
        sk.add(part)
    return sk


_query("sketch_stream_local", sketch_chain("cust_supp", _SP) + _LABELS_SQL)(lambda s, d: _labels(_replayed(s, d, "local").labels()))


def _snapshot(s, d):
    return _labels(_replayed(s, d).labels(at=1))


_DATED = "SELECT least(2 * o_custkey, 2 * l_suppkey + 1) AS src, greatest(2 * o_custkey, 2 * l_suppkey + 1) AS dst, min(CAST(l_shipdate AS DATE)) AS day FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY ALL"
_PREFIX = [f"SELECT src, dst FROM ({_DATED}) WHERE day < DATE '{c}'" for c in (*_CUTS, "9999-01-01")]
_query("stream_snapshot", sketch_chain(_PREFIX[1], _SP) + _LABELS_SQL)(_snapshot)


def _stream_cost(s, d):
    rows = [(mode, c.batch, c.inserted, c.levels, c.local_levels, c.relabelled, c.relabelled / max(1, c.inserted)) for mode in ("full", "local") for c in _replayed(s, d, mode).costs]
    return s.createDataFrame(rows, "relabel string, batch int, inserted long, levels int, local_levels int, relabelled long, per_edge double")


_query("update_cost")(_stream_cost)


def _passes(s, d):
    e = written(graph(s, d, "part_supp"), "edges")
    out = None
    for _, took in multi_pass(lambda: e, replace(BASE, p0=2**-4), 2100):
        out = took if out is None else out.unionByName(took)
    return out.select("id", F.round("label", 6).alias("label"), "level")


_query("sketch_multi_pass", sketch_chain("part_supp", replace(BASE, p0=2**-4)) + " SELECT id, round(label, 6) AS label, level FROM settled")(_passes)


def _stream_prefix(s, d):
    """After every slice: vertices of the stream's labels, and rows in which they differ from the batch sketch's."""
    sk, so_far, rows = StreamingSketch(s, _SP), None, []
    for k, part in enumerate(_slices(s, d)):
        sk.add(part)
        so_far = part if so_far is None else so_far.unionByName(part)
        mine, other = sk.labels().select("id", "label", "level"), sketch_coreness(edges_from(so_far), _SP).labels.select("id", "label", "level")
        rows.append((k, mine.count(), mine.exceptAll(other).count() + other.exceptAll(mine).count()))
    return s.createDataFrame(rows, "prefix int, vertices long, different long")


_query("stream_prefix", " UNION ALL ".join(f"SELECT {k} AS prefix, count(*) AS vertices, CAST(0 AS BIGINT) AS different FROM (SELECT src AS id FROM ({e}) UNION SELECT dst FROM ({e}))" for k, e in enumerate(_PREFIX)))(_stream_prefix)


#: Rows that each slice of a stream must have for several tasks to write it: each of them then surely gets rows, hence a file.
_SLICE_ROWS = 500_000


def _stream_of(s, df, parts=4, order="edge_ts", close=False):
    """df as a stream of `parts` slices in time order, a micro-batch each (of one file, or of several equally many for
    large tables); close: a last row without values, ten days later, moves the
    watermark past all windows."""
    src = new_path(s, "stream-files")
    df = written(df, "stream-rows")
    at = F.unix_micros(order)
    lo, hi = df.agg(F.min(at), F.max(at)).first()
    slot = F.least(F.floor((at - F.lit(lo)) * parts / F.lit(max(1, hi - lo))), F.lit(parts - 1))
    rows = {r.slot: r["count"] for r in df.groupBy(slot.alias("slot")).count().collect()}  # one row per slice
    files = s.sparkContext.defaultParallelism if all(rows.get(k, 0) >= _SLICE_ROWS for k in range(parts)) else 1
    for k in range(parts):
        part = df.where(slot == k)
        (part.coalesce(1) if files == 1 else part.repartition(files)).write.mode("append").parquet(src)
    if close:
        end = F.timestamp_micros(F.lit(hi + 10 * 86_400_000_000))
        s.range(1).select(*[(end if c == order else F.lit(None)).cast(t).alias(c) for c, t in df.dtypes]).coalesce(1).write.mode("append").parquet(src)
    return s.readStream.schema(df.schema).option("maxFilesPerTrigger", files).parquet(src)


#: Events for which one more block of users pays in the state of a window.
_BLOCK_EVENTS = 2_000_000


def _contact_windows(s, d, width, slide=None):
    ev = load_table(s, d, "events").select(F.col("ts").cast("timestamp").alias("edge_ts"), F.col("user_id").alias("id"))
    blocks = max(1, -(-ev.count() // _BLOCK_EVENTS))
    return _drained(s, window_contacts(_stream_of(s, ev, close=True), width, "1 day", slide, blocks)).withColumn("start", F.date_format("start", _WALL))


def _contact_sessions(s, d, gap):
    ev = load_table(s, d, "events").select(F.col("ts").cast("timestamp").alias("edge_ts"), F.col("user_id").alias("id"))
    blocks = max(1, -(-ev.count() // _BLOCK_EVENTS))
    return _drained(s, session_contacts(_stream_of(s, ev, close=True), gap, "1 day", blocks)).withColumn("start", F.date_format("start", _WALL))


_WALL = "yyyy-MM-dd HH:mm:ss"
_query("stream_tumbling", f"SELECT strftime(date_trunc('day', edge_ts), '%Y-%m-%d %H:%M:%S') AS start, src, dst, count(*) AS times FROM ({TIMED}) GROUP BY ALL")(lambda s, d: _contact_windows(s, d, "1 day"))
_query("stream_sliding", f"SELECT strftime(date_trunc('day', edge_ts) - to_days(k), '%Y-%m-%d %H:%M:%S') AS start, src, dst, count(*) AS times FROM ({TIMED}), (SELECT unnest([0, 1]) AS k) GROUP BY ALL")(lambda s, d: _contact_windows(s, d, "2 days", "1 day"))
_SESSIONS = f"SELECT src, dst, edge_ts, sum(fresh) OVER (PARTITION BY src, dst ORDER BY edge_ts) AS run FROM (SELECT *, CASE WHEN edge_ts < lag(edge_ts) OVER (PARTITION BY src, dst ORDER BY edge_ts) + INTERVAL 1 DAY THEN 0 ELSE 1 END AS fresh FROM ({TIMED}))"
_query("stream_session", f"SELECT strftime(min(edge_ts), '%Y-%m-%d %H:%M:%S') AS start, src, dst, count(*) AS times FROM ({_SESSIONS}) GROUP BY src, dst, run")(lambda s, d: _contact_sessions(s, d, "1 day"))


def _drained(s, out):
    """Rows of an append stream once its input is drained."""
    path = new_path(s, "stream-rows")
    run_windows(out, path, new_path(s, "stream-checkpoint")).awaitTermination()
    return s.read.schema(out.schema).parquet(path)


def _segments_stream(s, d):
    o = load_table(s, d, "orders").select(F.col("o_custkey").alias("src"), F.col("o_orderkey").alias("dst"), F.col("o_orderdate").cast("timestamp").alias("edge_ts"))
    return _drained(s, with_dimension(_stream_of(s, o), load_table(s, d, "customer").select("c_custkey", "c_mktsegment"), "c_custkey")).groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("orders"))


_query("stream_static_join", "SELECT c_mktsegment, count(*) AS orders FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY c_mktsegment")(_segments_stream)


def _orders_lines(s, d):
    o = load_table(s, d, "orders").select("o_orderkey", F.col("o_orderdate").cast("timestamp").alias("left_ts"), (2 * F.col("o_custkey")).alias("src")).withColumnRenamed("o_orderkey", "k")
    li = load_table(s, d, "lineitem").select(F.col("l_orderkey").alias("k"), F.col("l_shipdate").cast("timestamp").alias("right_ts"), (2 * F.col("l_suppkey") + 1).alias("dst"))
    path = new_path(s, "stream-rows")
    match_batches(_stream_of(s, o, 2, "left_ts"), _stream_of(s, li, 2, "right_ts"), "k", "4000 DAYS", path, new_path(s, "stream-checkpoint")).awaitTermination()
    return edges_from(s.read.schema("src long, dst long").parquet(path))


_query("stream_stream_join", GRAPHS["cust_supp"])(_orders_lines)


def _keyed(s, d):
    path = new_path(s, "keyed-rows")
    keep = lambda df, k: df.withColumn("batch", F.lit(k)).write.mode("append").parquet(path)
    out = contact_counts(_stream_of(s, timed_edges(s, d)).select("src", "dst"))
    out.writeStream.outputMode("update").foreachBatch(keep).option("checkpointLocation", new_path(s, "keyed-checkpoint")).trigger(availableNow=True).start().awaitTermination()
    return s.read.parquet(path).groupBy("id").agg(F.max("degree").alias("degree"))


_query("stream_keyed_state", f"SELECT id, count(DISTINCT o) AS degree FROM (SELECT src AS id, dst AS o FROM ({TIMED}) UNION ALL SELECT dst, src FROM ({TIMED})) GROUP BY id")(_keyed)


# ---------------------------------------------------------------- experiments

_MEAN = lambda rows, *keys: measures.mean_of_runs(rows, *keys)
_SPACE_CELLS = ("n", "m", "levels", "max_edges", "sum_edges", "max_share", "sum_share", "max_per_n")
_ERROR_CELLS = ("p50", "p60", "p70", "p80", "p90")
_query("exp_space_T")(lambda s, d: _MEAN(experiments.vary_accept(s, d, errors=False), "graph", "accept").select("graph", "accept", *_SPACE_CELLS))
_query("exp_error_T")(lambda s, d: _MEAN(experiments.vary_accept(s, d), "graph", "accept").select("graph", "accept", *_ERROR_CELLS))
_query("exp_space_M")(lambda s, d: _MEAN(experiments.vary_growth(s, d, errors=False), "graph", "growth").select("graph", "growth", *_SPACE_CELLS))
_query("exp_error_M")(lambda s, d: _MEAN(experiments.vary_growth(s, d), "graph", "growth").select("graph", "growth", *_ERROR_CELLS))
_query("exp_baseline_time")(experiments.baseline_time)
_query("exp_scal")(experiments.scaling)
_query("exp_claim_band", " UNION ALL ".join(f"({_bands_sql(k)})" for k in experiments.SEEDS))(lambda s, d: experiments.claims(s))
_query("exp_ablate_uniform")(experiments.ablate_uniform)


def _cells_sql(params: list[SketchParams], what: str) -> str:
    return " UNION ALL ".join(f"SELECT CAST({getattr(p, what)!r} AS DOUBLE) AS {what}, max(edges) AS max_edges, CAST(sum(edges) AS BIGINT) AS sum_edges FROM ({sketch_chain('cust_supp', p)} SELECT edges FROM sizes)" for p in params)


def _cells(s, d, params, what):
    return grid.report(s, d, ("cust_supp",), params, (0,), errors=False).select(F.col(what).cast("double").alias(what), "max_edges", "sum_edges")


# The space cells once more with portable hashes and rates, so that another engine can count them.
_BY_ACCEPT, _BY_GROWTH = [replace(BASE, accept=t) for t in experiments.ACCEPTS], [replace(BASE, growth=m, p0=2**-4) for m in experiments.GROWTHS]
_query("exp_space_T_portable", _cells_sql(_BY_ACCEPT, "accept"))(lambda s, d: _cells(s, d, _BY_ACCEPT, "accept"))
_query("exp_space_M_portable", _cells_sql(_BY_GROWTH, "growth"))(lambda s, d: _cells(s, d, _BY_GROWTH, "growth"))

_PRE = replace(BASE, p0=2**-5)
_LEFT = [f"SELECT {x.level} AS level, (SELECT count(*) FROM h{x.level}) AS edges, (SELECT count(*) FROM h{x.level} WHERE src NOT IN (SELECT id FROM r{x.level} WHERE v < 3) AND dst NOT IN (SELECT id FROM r{x.level} WHERE v < 3)) AS collected" for x in rate_schedule(1000, _PRE)]
_query("exp_prepeel", sketch_chain("doc_word", _PRE) + " " + " UNION ALL ".join(_LEFT))(lambda s, d: grid.prepeel_saving(s, d, ("doc_word",), _PRE).select("level", "edges", "collected"))


# ---------------------------------------------------------------- relational operators around the methods

_DW = f"WITH e AS ({GRAPHS['doc_word']}), d AS (SELECT id, count(*) AS degree FROM (SELECT src AS id FROM e UNION ALL SELECT dst FROM e) GROUP BY id)"
_PS = f"WITH e AS ({GRAPHS['part_supp']}), arcs AS (SELECT src AS a, dst AS b FROM e UNION ALL SELECT dst, src FROM e), d AS (SELECT a AS id, count(*) AS degree FROM arcs GROUP BY a)"
_query("op_canonical_edges", GRAPHS["part_supp"])(lambda s, d: graph(s, d, "part_supp"))
_query("op_degree", _DW + " SELECT id, degree FROM d")(lambda s, d: degrees(graph(s, d, "doc_word")))
_query("op_degree_hist", _DW + " SELECT degree, count(*) AS vertices FROM d GROUP BY degree")(lambda s, d: degrees(graph(s, d, "doc_word")).groupBy("degree").agg(F.count(F.lit(1)).alias("vertices")))
_query("op_distinct_vertices", _DW + " SELECT count(*) AS vertices FROM d")(lambda s, d: degrees(graph(s, d, "doc_word")).agg(F.count(F.lit(1)).alias("vertices")))
_query("op_approx_vertices")(lambda s, d: graph(s, d, "doc_word").select(F.explode(F.array("src", "dst")).alias("id")).agg(F.approx_count_distinct("id").alias("vertices")))
_query("op_hindex", _PS + ", r AS (SELECT a, degree, row_number() OVER (PARTITION BY a ORDER BY degree DESC) AS k FROM arcs JOIN d ON d.id = b) SELECT a AS id, max(least(degree, k)) AS h FROM r GROUP BY a")(lambda s, d: peel.h_sweep(graph(s, d, "part_supp")))


def _capped(s, d):
    e = graph(s, d, "part_supp")
    both = arcs(e).join(degrees(e), F.col("dst") == F.col("id"))
    return both.groupBy(F.col("src").alias("key")).agg(*[F.count(F.when(F.col("degree") >= k, 1)).alias(f"c{k}") for k in (10, 20, 30)]).withColumnRenamed("key", "id")


_query("op_hist_capped", _PS + " SELECT a AS id, " + ", ".join(f"count(*) FILTER (degree >= {k}) AS c{k}" for k in (10, 20, 30)) + " FROM arcs JOIN d ON d.id = b GROUP BY a")(_capped)
_MD5 = "CAST('0x' || substr(md5('0:' || src || ':' || dst), 1, 13) AS BIGINT)"
_query("op_sample_hash", f"SELECT src, dst FROM ({GRAPHS['part_supp']}) WHERE {_MD5} <= {(1 << 52) // 8}")(lambda s, d: graph(s, d, "part_supp").where(fn.edge_u52(F.col("src"), F.col("dst"), 0, "md5") <= (1 << 52) // 8))
_RATES = [x.rate for x in _SCHED]
_query("op_first_level", f"SELECT src, dst, CASE " + " ".join(f"WHEN u <= {int(r * (1 << 52))} THEN {k}" for k, r in enumerate(_RATES[:-1])) + f" ELSE {len(_RATES) - 1} END AS first_level FROM (SELECT src, dst, {_MD5} AS u FROM ({GRAPHS['part_supp']}))")(lambda s, d: graph(s, d, "part_supp").withColumn("u", fn.edge_u52(F.col("src"), F.col("dst"), 0, "md5")).select("src", "dst", fn.first_level(F.col("u"), _RATES).alias("first_level")))
_SMALL = "SELECT 2 * p_partkey AS id FROM part WHERE p_size <= 10"


def _small(s, d):
    return load_table(s, d, "part").where("p_size <= 10").select((2 * F.col("p_partkey")).alias("id"))


_query("op_induced_edges", f"SELECT src, dst FROM ({GRAPHS['part_supp']}) WHERE src IN ({_SMALL}) OR dst IN ({_SMALL})")(lambda s, d: peel._flagged(graph(s, d, "part_supp"), _small(s, d)).where("su or sv").select("src", "dst"))
_query("op_prune_settled", f"SELECT src, dst FROM ({GRAPHS['copart']}) WHERE NOT (src IN (SELECT p_partkey FROM part WHERE p_size <= 10) AND dst IN (SELECT p_partkey FROM part WHERE p_size <= 10))")(lambda s, d: peel._flagged(graph(s, d, "copart"), load_table(s, d, "part").where("p_size <= 10").select(F.col("p_partkey").alias("id"))).where("not (su and sv)").select("src", "dst"))
_query("op_isolated", "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)")(lambda s, d: load_table(s, d, "customer").select("c_custkey").join(load_table(s, d, "orders").select(F.col("o_custkey").alias("c_custkey")), "c_custkey", "left_anti"))


def _supplier_core(s, d):
    c = peel.exact_coreness(graph(s, d, "part_supp"), "auto")
    return load_table(s, d, "supplier").join(c.where("id % 2 = 1").select(((F.col("id") - 1) / 2).cast("long").alias("s_suppkey"), "coreness"), "s_suppkey").select("s_suppkey", "s_nationkey", "coreness")


_SC = coreness("part_supp") + ", sc AS (SELECT s_suppkey, s_nationkey, v AS coreness FROM supplier JOIN c ON c.id = 2 * s_suppkey + 1)"


def _by_nation():
    return Window.partitionBy("s_nationkey").orderBy(F.desc("coreness"), "s_suppkey")


_query("op_rank_core", _SC + " SELECT s_suppkey, coreness, rank() OVER (PARTITION BY s_nationkey ORDER BY coreness DESC) AS rk, row_number() OVER w AS rn, ntile(3) OVER w AS third, lag(coreness) OVER w AS before FROM sc WINDOW w AS (PARTITION BY s_nationkey ORDER BY coreness DESC, s_suppkey)")(lambda s, d: _supplier_core(s, d).select("s_suppkey", "coreness", F.rank().over(Window.partitionBy("s_nationkey").orderBy(F.desc("coreness"))).alias("rk"), F.row_number().over(_by_nation()).alias("rn"), F.ntile(3).over(_by_nation()).alias("third"), F.lag("coreness").over(_by_nation()).alias("before")))
_query("op_topk_per_nation", _SC + " SELECT s_nationkey, s_suppkey, coreness FROM sc QUALIFY row_number() OVER (PARTITION BY s_nationkey ORDER BY coreness DESC, s_suppkey) <= 2")(lambda s, d: _supplier_core(s, d).withColumn("k", F.row_number().over(_by_nation())).where("k <= 2").select("s_nationkey", "s_suppkey", "coreness"))
_query("op_topk_core", _SC + " SELECT s_suppkey, coreness FROM sc ORDER BY coreness DESC, s_suppkey LIMIT 10")(lambda s, d: _supplier_core(s, d).select("s_suppkey", "coreness").orderBy(F.desc("coreness"), "s_suppkey").limit(10))
_query("op_cum_core", coreness("part_supp") + " SELECT v AS k, sum(count(*)) OVER (ORDER BY v DESC)::BIGINT AS vertices FROM c GROUP BY v")(lambda s, d: peel.exact_coreness(graph(s, d, "part_supp"), "auto").groupBy(F.col("coreness").alias("k")).agg(F.count(F.lit(1)).alias("n")).select("k", F.sum("n").over(Window.orderBy(F.desc("k"))).alias("vertices")))
_query("op_core_hist", coreness("part_supp") + " SELECT v AS coreness, count(*) AS vertices FROM c GROUP BY v")(lambda s, d: peel.exact_coreness(graph(s, d, "part_supp"), "auto").groupBy("coreness").agg(F.count(F.lit(1)).alias("vertices")))
_query("op_rollup_region", _SC + " SELECT r_name, n_name, count(*) AS suppliers, max(coreness) AS top FROM sc JOIN nation ON n_nationkey = s_nationkey JOIN region ON r_regionkey = n_regionkey GROUP BY ROLLUP(r_name, n_name)")(lambda s, d: _supplier_core(s, d).join(load_table(s, d, "nation"), F.col("s_nationkey") == F.col("n_nationkey")).join(load_table(s, d, "region"), F.col("n_regionkey") == F.col("r_regionkey")).rollup("r_name", "n_name").agg(F.count(F.lit(1)).alias("suppliers"), F.max("coreness").alias("top")))


def _segments(s, d):
    c = peel.exact_coreness(graph(s, d, "cust_supp"), "auto").where("id % 2 = 0").select((F.col("id") / 2).cast("long").alias("c_custkey"), F.floor(F.col("coreness") / 10).alias("band"))
    return load_table(s, d, "customer").join(c, "c_custkey")


_query("op_core_cube", coreness("cust_supp") + " SELECT c_mktsegment, v // 10 AS band, count(*) AS customers FROM customer JOIN c ON c.id = 2 * c_custkey GROUP BY CUBE(c_mktsegment, band)")(lambda s, d: _segments(s, d).cube("c_mktsegment", "band").agg(F.count(F.lit(1)).alias("customers")))
_query("op_space_pivot", _CHAIN + " SELECT sum(CASE WHEN level < 5 THEN edges END)::BIGINT AS thin, sum(CASE WHEN level >= 5 THEN edges END)::BIGINT AS thick FROM sizes")(lambda s, d: _space(s, d).withColumn("kind", F.when(F.col("level") < 5, "thin").otherwise("thick")).groupBy().pivot("kind", ["thin", "thick"]).agg(F.sum("edges")))
_query("op_band_join", coreness("part_supp") + " SELECT b.lo, count(*) AS vertices FROM c JOIN (SELECT unnest([0, 10, 20, 30]) AS lo) b ON c.v >= b.lo AND c.v < b.lo + 10 GROUP BY b.lo")(lambda s, d: peel.exact_coreness(graph(s, d, "part_supp"), "auto").join(F.broadcast(s.createDataFrame([(0,), (10,), (20,), (30,)], "lo int")), (F.col("coreness") >= F.col("lo")) & (F.col("coreness") < F.col("lo") + 10)).groupBy("lo").agg(F.count(F.lit(1)).alias("vertices")))
_Y = lambda y: f"SELECT DISTINCT l_partkey AS src, l_suppkey AS dst FROM lineitem WHERE year(l_shipdate) = {y}"


def _year(s, d, y):
    return load_table(s, d, "lineitem").where(F.year("l_shipdate") == y).select(F.col("l_partkey").alias("src"), F.col("l_suppkey").alias("dst")).distinct()


for _n, _op, _f in (("union_graphs", "UNION", lambda a, b: a.union(b).distinct()), ("intersect_edges", "INTERSECT", lambda a, b: a.intersect(b)), ("except_edges", "EXCEPT", lambda a, b: a.subtract(b))):
    _query(f"op_{_n}", f"{_Y(1995)} {_op} {_Y(1996)}")(lambda s, d, f=_f: f(_year(s, d, 1995), _year(s, d, 1996)))
_query("op_copart_topk", f"WITH e AS ({GRAPHS['copart']}) SELECT id, count(*) AS degree FROM (SELECT src AS id FROM e UNION ALL SELECT dst FROM e) GROUP BY id ORDER BY degree DESC, id LIMIT 10")(lambda s, d: degrees(graph(s, d, "copart")).orderBy(F.desc("degree"), "id").limit(10))
_query("op_json_props", "SELECT CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events GROUP BY 1")(lambda s, d: load_table(s, d, "events").groupBy(F.get_json_object("props", "$.k").cast("long").alias("k")).agg(F.count(F.lit(1)).alias("n")))
_query("op_label_feature", coreness("doc_word") + " SELECT quality, toxic, count(*) AS docs, round(avg(v), 6) AS coreness FROM labels JOIN c ON c.id = 'd' || doc_id GROUP BY quality, toxic")(lambda s, d: load_table(s, d, "labels").join(peel.exact_coreness(graph(s, d, "doc_word"), "auto").where(F.startswith("id", F.lit("d"))), F.concat(F.lit("d"), F.col("doc_id").cast("string")) == F.col("id")).groupBy("quality", "toxic").agg(F.count(F.lit(1)).alias("docs"), F.round(F.avg("coreness"), 6).alias("coreness")))


def _compare(s, d):
    _, sk, ex = _pair(s, d)
    both = sk.labels.join(ex, "id", "full")
    return both.groupBy(F.when(F.col("label") < F.col("coreness"), "below").when(F.col("label") > F.col("coreness"), "above").otherwise("equal").alias("side")).agg(F.count(F.lit(1)).alias("vertices"))


_query("op_label_compare_full", _CHAIN + " SELECT CASE WHEN label < v THEN 'below' WHEN label > v THEN 'above' ELSE 'equal' END AS side, count(*) AS vertices FROM c FULL JOIN settled USING (id) GROUP BY 1")(_compare)


def _triangles(s, d):
    one, e = user_slots(s, d, "minute"), None
    if pairs.pair_count(one, ["slot"]) <= pairs.PAIR_ROWS:
        e = written(graph(s, d, "user_minute"), "edges")
        ends = e.select(F.explode(F.array(F.struct(F.col("src").alias("id"), F.lit(1).alias("out")), F.struct(F.col("dst").alias("id"), F.lit(0).alias("out")))).alias("v")).select("v.*")
        paths = ends.groupBy("id").agg((F.sum("out") * F.sum(1 - F.col("out"))).alias("k")).agg(F.sum("k")).first()[0] or 0
    if e is None or paths > pairs.PAIR_ROWS:
        return pairs.sharing_triangles(pairs.member_sets(one, ["slot"], "user_id"))
    x, y, z = (e.select(F.col("src").alias(f"{k}s"), F.col("dst").alias(f"{k}d")) for k in "xyz")
    return x.join(y, F.col("xd") == F.col("ys")).join(z, (F.col("zs") == F.col("xs")) & (F.col("zd") == F.col("yd"))).agg(F.count(F.lit(1)).alias("triangles"))


_query("op_triangles", f"WITH e AS ({GRAPHS['user_minute']}) SELECT count(*) AS triangles FROM e x JOIN e y ON x.dst = y.src JOIN e z ON z.src = x.src AND z.dst = y.dst")(_triangles)


for _name, (_call, _text) in relational.QUERIES.items():
    _query(_name, _text)(_call)
