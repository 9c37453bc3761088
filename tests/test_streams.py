"""The stream's state: empty batches, restarts, local relabelling, snapshots, costs; windows and keyed state."""

from dataclasses import replace

import duckdb
import numpy as np
import pytest

from stratacore import registry, streaming
from stratacore.operators.sketch import sketch_coreness
from stratacore.params import SketchParams
from stratacore.sources import edges_from, path_graph, random_graph
from stratacore.streaming import StreamingSketch, multi_pass, session_edges

P = SketchParams(accept=3, p0=2**-3, cap="scaled", n_upper=1 << 10, hash="md5")


def rows(labels):
    return sorted(map(tuple, labels.select("id", "label", "level", "raw").collect()))


def batches(spark):
    whole = random_graph(spark, 120, 1500, 3)
    return [whole.where(f"pmod(xxhash64(src, dst), 4) = {k}") for k in range(4)]


@pytest.mark.parametrize("relabel", ["full", "local"])
def test_every_prefix_equals_the_batch_sketch(spark, relabel):
    sk, so_far = StreamingSketch(spark, P, relabel), None
    sk.add(batches(spark)[0].where("false"))
    assert sk.labels().count() == 0 and sk.space() == []
    for k, part in enumerate(batches(spark)):
        sk.add(part)
        so_far = part if so_far is None else so_far.unionByName(part)
        if k in (1, 3):
            assert rows(sk.labels()) == rows(sketch_coreness(edges_from(so_far), P).labels)
    assert rows(sk.labels(at=sk.last_batch)) == rows(sk.labels())
    assert [c.inserted for c in sk.costs][0] == 0 and all(c.relabelled >= 0 for c in sk.costs)
    with pytest.raises(KeyError):
        sk.labels(at=99)


def test_local_relabelling_of_one_level_equals_a_full_peel(spark):
    p = replace(P, p0=1.0)
    full, local = StreamingSketch(spark, p), StreamingSketch(spark, p, "local")
    base = random_graph(spark, 60, 400, 1)
    for part in (base.where("(src + dst) % 7 < 5"), base.where("(src + dst) % 7 = 5"), base.where("(src + dst) % 7 = 6"), path_graph(spark, 70)):
        full.add(part), local.add(part)
        assert rows(full.labels()) == rows(local.labels())
    assert sum(c.local_levels for c in local.costs) == 3
    assert sum(c.relabelled for c in local.costs) < sum(c.relabelled for c in full.costs)


def test_a_killed_stream_goes_on_from_its_state(spark, tmp_path):
    src, at, state = (f"{tmp_path}/{x}" for x in ("src", "checkpoint", "state"))
    parts = batches(spark)
    for k in (0, 1):
        parts[k].coalesce(1).write.mode("append").parquet(src)
    stream = lambda: spark.readStream.schema("src long, dst long").option("maxFilesPerTrigger", 1).parquet(src)
    StreamingSketch(spark, P).start(stream(), at, state).awaitTermination()
    for k in (2, 3):
        parts[k].coalesce(1).write.mode("append").parquet(src)
    second = StreamingSketch(spark, P)
    second.start(stream(), at, state).awaitTermination()
    assert second.last_batch == 3
    whole = rows(sketch_coreness(random_graph(spark, 120, 1500, 3), P).labels)
    assert rows(second.labels()) == whole == rows(StreamingSketch.load(spark, state, P).labels())
    assert StreamingSketch.load(spark, state, P, at=1).labels().count() < len(whole) + 1
    second.add(parts[0], batch_id=1)  # a replay
    assert rows(second.labels()) == whole


def test_an_empty_first_batch_is_saved(spark, tmp_path):
    sk = StreamingSketch(spark, P)
    sk.add(spark.createDataFrame([], "src long, dst long"), 0)
    sk.save(f"{tmp_path}/state")
    back = StreamingSketch.load(spark, f"{tmp_path}/state", P)
    assert back.last_batch == 0 and back.edges is None
    back.add(path_graph(spark, 5), 1)
    assert back.labels().count() == 5


@pytest.mark.parametrize("more", [{"side": "upper", "eps": 0.2}, {"peeler": "distributed"}, {"prepeel": 2}])
def test_passes_follow_their_parameters(spark, more):
    e = random_graph(spark, 80, 700, 2)
    p = replace(P, n_upper=None, **more)
    out = None
    for _, took in multi_pass(lambda: e, p, 80):
        out = took if out is None else out.unionByName(took)
    assert rows(out) == rows(sketch_coreness(e, p, 80).labels)


def test_sessions_of_a_pair(spark):
    df = spark.createDataFrame([(0, 1, 2), (50, 2, 1), (200, 1, 2), (10, 3, 4)], "t int, src long, dst long").selectExpr("timestamp_seconds(t) as edge_ts", "src", "dst")
    got = sorted((r.src, r.dst, r.times) for r in session_edges(df, "60 seconds").collect())
    assert got == [(1, 2, 1), (1, 2, 2), (3, 4, 1)]


def test_many_new_edges_are_peeled_by_arrays(spark, monkeypatch):
    """The same labels and the same vertices moved as by walks, without a walk."""
    base = random_graph(spark, 60, 400, 1)
    costs = []
    for few in (1000, 0):
        monkeypatch.setattr(streaming, "WALK_EDGES", few)
        local = StreamingSketch(spark, P, "local")
        for part in (base.where("(src + dst) % 7 < 5"), base.where("(src + dst) % 7 >= 5")):
            local.add(part)
        assert rows(local.labels()) == rows(sketch_coreness(base, P).labels)
        costs.append(local.costs)
    assert costs[0] == costs[1] and sum(c.local_levels for c in costs[0]) > 0
    seen = []
    real = streaming.locally_relabelled
    monkeypatch.setattr(streaming, "locally_relabelled", lambda h, new, raw: seen.append(new) or real(h, new, raw))
    local.add(path_graph(spark, 70))
    assert seen and all(x is None for x in seen)


@pytest.mark.parametrize("name", ["stream_tumbling", "stream_sliding", "stream_session"])
def test_windows_keep_events_and_not_pairs(spark, sf_dir, name, monkeypatch):
    """The same rows as SQL with several blocks and small steps; what streams is a table of events, a row each."""
    monkeypatch.setattr(registry, "_BLOCK_EVENTS", 300)
    monkeypatch.setattr(streaming, "CONTACT_PAIRS", 3)
    sent = []
    real = registry._stream_of
    monkeypatch.setattr(registry, "_stream_of", lambda s, df, *a, **k: sent.append(df.count()) or real(s, df, *a, **k))
    con = duckdb.connect()
    con.execute(f"create view events as select * from '{sf_dir}/events.parquet'")
    got = sorted(map(tuple, registry.queries()[name](spark, sf_dir).select("start", "src", "dst", "times").collect()))
    assert got == sorted(con.execute(registry.oracle_sql()[name]).fetchall()) and got
    assert sent == [con.execute("select count(*) from events").fetchone()[0]]


def test_contacts_count_the_rows_of_src(spark):
    at = np.array([0, 1, 2, 61, 62, 63]) * 1_000_000
    got = list(streaming._contacts(at, np.array([5, 5, 9, 5, 9, 9]), np.zeros(6, int), 0, 0))
    assert [x.tolist() for x in got[0]] == [[5], [9], [3]]


def _two_streams(spark, tmp_path, slices):
    """Streams (k, left_ts, src) and (k, right_ts, dst), a file for each slice of (left rows, right rows); times in seconds."""
    out = []
    for side, schema, cols in ((0, "k long, t long, src long", "k, timestamp_seconds(t) as left_ts, src"), (1, "k long, t long, dst long", "k, timestamp_seconds(t) as right_ts, dst")):
        path = f"{tmp_path}/side-{side}"
        for rows in slices:
            df = spark.createDataFrame(rows[side], schema).selectExpr(*cols.split(", "))
            df.coalesce(1).write.mode("append").parquet(path)
        out.append(spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(path))
    return out


def test_streams_are_joined_by_tables(spark, tmp_path):
    """Rows of one key at most a minute apart, across batches in both directions, repeated rows too; nulls match nothing."""
    first = ([(1, 0, 10), (1, 30, 11), (2, 0, 12), (None, 0, 13)], [(1, 60, 20), (1, 61, 21), (3, 5, 22), (None, 0, 23)])
    second = ([(3, 20, 14), (1, 90, 15)], [(2, 40, 24), (2, 40, 24), (1, 95, 25)])
    left, right = _two_streams(spark, tmp_path, (first, second))
    streaming.match_batches(left, right, "k", "60 SECONDS", f"{tmp_path}/out", f"{tmp_path}/checkpoint").awaitTermination()
    got = sorted((r.src, r.dst) for r in spark.read.parquet(f"{tmp_path}/out").collect())
    a, b = ([r for part in (first, second) for r in part[side]] for side in (0, 1))
    assert got == sorted((x[2], y[2]) for x in a for y in b if x[0] is not None and x[0] == y[0] and abs(x[1] - y[1]) <= 60)


def test_the_stream_join_has_no_state_store(spark, sf_dir, monkeypatch):
    """Its state are tables: no state folder under the checkpoint, which the row by row join filled."""
    import glob

    paths, real = [], registry.new_path
    monkeypatch.setattr(registry, "new_path", lambda s, label: paths.append(real(s, label)) or paths[-1])
    assert registry.queries()["stream_stream_join"](spark, sf_dir).count() > 0
    checkpoint = next(x for x in paths if "stream-checkpoint" in x).removeprefix("file:")
    assert glob.glob(f"{checkpoint}/commits/*") and not glob.glob(f"{checkpoint}/state/*")


def test_runs_of_contacts_end_at_a_pause(spark):
    """A run ends where the next row of src comes `gap` or more later; a row counts once for each dst of its minute."""
    at = np.array([0, 1, 2, 99, 100, 200, 201]) * 1_000_000
    got = list(streaming._contact_runs(at, np.array([5, 9, 9, 9, 5, 5, 9]), np.zeros(7, int), 0, 0, 100_000_000))
    assert [x.tolist() for x in got[0]] == [[0, 100_000_000, 200_000_000], [5, 5, 5], [9, 9, 9], [1, 1, 1]]
    got = list(streaming._contact_runs(at, np.array([5, 9, 9, 9, 5, 5, 9]), np.zeros(7, int), 0, 0, 101_000_000))
    assert [x.tolist() for x in got[0]] == [[0], [5], [9], [3]]
