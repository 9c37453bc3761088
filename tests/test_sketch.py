import math
from dataclasses import replace

import pytest

from stratacore.operators import peel
from stratacore.operators.sketch import sketch_coreness, with_isolated
from stratacore.params import Level, SketchParams, deflation, rate_schedule, without_idle
from stratacore.runtime import written
from stratacore.sources import degrees, graph, random_graph
from stratacore.streaming import StreamingSketch, multi_pass

P = SketchParams(accept=3, p0=2**-3, cap="scaled", peeler="local")


@pytest.fixture(scope="module")
def edges(spark, sf_dir):
    return written(graph(spark, sf_dir, "cust_supp"), "edges")


def rows(s):
    return {(r.id, r.label, r.level) for r in s.labels.collect()}


def test_every_form_gives_the_same_labels(edges):
    base = rows(sketch_coreness(edges, P))
    assert len(base) == 160 and len({r[2] for r in base}) > 1
    for change in ({"rounds": "fused"}, {"peeler": "distributed"}, {"prepeel": 3}):
        assert rows(sketch_coreness(edges.repartition(3), replace(P, **change))) == base, change


def test_rate_one_is_exact(edges):
    exact = {r.id: r.coreness for r in peel.exact_coreness(edges, "local").collect()}
    got = {r.id: r.label for r in sketch_coreness(edges, SketchParams(exact_last=True)).labels.collect()}
    assert got == exact
    lower = {r.id: r.label for r in sketch_coreness(edges, SketchParams(eps=0.25)).labels.collect()}
    assert lower == {k: 0.75 * v for k, v in exact.items()}


def test_space_and_isolated(spark, edges):
    s = sketch_coreness(edges, P)
    assert s.space_max() <= s.space_sum() == s.sample.count()
    assert s.space_max() <= 3 * 160
    more = with_isolated(s.labels, spark.createDataFrame([(10**9,)], "id long"))
    assert more.where("id = 1000000000").first().label == 0


def test_stream_equals_batch_on_prefixes_in_any_order(spark):
    e = written(random_graph(spark, 60, 700, 4), "edges")
    parts = [written(x, "part") for x in e.randomSplit([1.0, 1.0, 1.0], 7)]
    p = replace(P, n_upper=64, p0=2**-3)
    for order in ((0, 1, 2), (2, 0, 1)):
        sk, seen = StreamingSketch(spark, p), None
        for k, part in enumerate(order):
            sk.add(parts[part], k)
            sk.add(parts[part], k)  # a replay
            seen = parts[part] if seen is None else seen.unionByName(parts[part])
            assert {(r.id, r.label, r.level) for r in sk.labels().collect()} == rows(sketch_coreness(seen, p))


def test_stream_resumes(spark, tmp_path):
    e = random_graph(spark, 40, 300, 9)
    p = replace(P, n_upper=64)
    a, b = e.where("src % 2 = 0"), e.where("src % 2 = 1")
    sk = StreamingSketch(spark, p)
    sk.add(a, 0)
    sk.save(str(tmp_path))
    again = StreamingSketch.load(spark, str(tmp_path), p)
    again.add(a, 0)
    again.add(b, 1)
    assert {(r.id, r.label, r.level) for r in again.labels().collect()} == rows(sketch_coreness(e, p))


def test_multi_pass(edges):
    out = {(r.id, r.label, r.level) for _, took in multi_pass(lambda: edges, P, 160) for r in took.collect()}
    assert out == rows(sketch_coreness(edges, P))


@pytest.mark.parametrize("p", [SketchParams(hash="md5"), SketchParams(side="upper"), SketchParams(exact_last=True)])
def test_levels_that_can_settle_nothing_are_not_counted(spark, p):
    edges = written(random_graph(spark, 20_000, 50_000, 2), "edges")
    exact = {r.id: r.coreness for r in peel.exact_coreness(edges, "local").collect()}
    assert len(rate_schedule(len(exact), p)) > 1 and peel.coreness_bound(edges) >= max(exact.values())
    factor = deflation(Level(0, 1.0, 0.0, math.inf), p)
    got = {r.id: (r.level, r.raw, r.label) for r in sketch_coreness(edges, p).labels.collect()}
    assert got == {k: (0, v, factor * v) for k, v in exact.items()}


def test_a_level_that_can_settle_something_stays():
    levels = [Level(0, 0.25, 50.0, 100.0), Level(1, 0.5, 40.0, 80.0), Level(2, 1.0, 0.0, math.inf)]
    assert without_idle(levels, 40) == [Level(0, 0.5, 40.0, 80.0), Level(1, 1.0, 0.0, math.inf)]
    assert without_idle(levels, 39) == [Level(0, 1.0, 0.0, math.inf)] and without_idle(levels, 50) == levels


def test_a_cap_below_the_threshold_settles_the_same_vertices(edges):
    """The refinement clipped values below what they must reach, and settled nothing before the last level."""
    p = replace(P, cap=2)
    assert rows(sketch_coreness(edges, replace(p, peeler="distributed"))) == rows(sketch_coreness(edges, p))


def test_first_levels_in_one_task_change_nothing(spark):
    named = random_graph(spark, 60, 90, 2).selectExpr("concat('v', src) as src", "concat('v', dst) as dst")
    for edges, sizes in ((random_graph(spark, 300, 3000, 7), (10_000_000, 300)), (named, (10_000_000,))):
        p = SketchParams(accept=3, p0=2**-5, cap="scaled")
        n = degrees(edges).count()
        two = sketch_coreness(edges, replace(p, rounds="two"))
        for most in sizes:
            one = sketch_coreness(edges, replace(p, max_local_edges=most), n if most == 300 else None)
            assert one.space == two.space and one.rounds.levels == len(one.space), most
            assert sorted(map(tuple, one.labels.collect())) == sorted(map(tuple, two.labels.collect())), most
            assert sorted(map(tuple, one.sample.collect())) == sorted(map(tuple, two.sample.collect())), most
            assert most == 300 or one.rounds.jobs * 2 < two.rounds.jobs
