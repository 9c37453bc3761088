"""The experiment workloads: grids equal single sketches, claims that can fail, the reported trends."""

from dataclasses import replace

import pytest

from stratacore.functions import register
from stratacore.operators import cores, peel
from stratacore.operators.sketch import sketch_coreness
from stratacore.params import SketchParams
from stratacore.plans import experiments, grid, measures
from stratacore.runtime import Rounds
from stratacore.sources import clique_ladder, cycle_graph, degrees, graph, grid_graph, hub_groups, path_graph, random_graph


def test_a_grid_equals_single_sketches(spark, sf_dir):
    params = [replace(experiments.PRACTICAL, accept=t) for t in (2, 4)]
    got = grid.report(spark, sf_dir, ("part_supp",), params, (0, 1)).collect()
    assert len(got) == 4
    edges = graph(spark, sf_dir, "part_supp")
    exact = peel.exact_coreness(edges, "local")
    for r in got:
        s = sketch_coreness(edges, replace(experiments.PRACTICAL, accept=r.accept, seed=r.seed))
        assert (r.max_edges, r.sum_edges, r.levels) == (s.space_max(), s.space_sum(), len(s.space))
        e = measures.error_percentiles(s.labels, exact).first()
        assert [r[f"p{k}"] for k in grid.POINTS] == pytest.approx([e[f"p{k}"] for k in grid.POINTS], abs=1e-6)


def test_space_grows_and_error_falls_with_the_threshold(spark, sf_dir):
    rows = measures.mean_of_runs(experiments.vary_accept(spark, sf_dir, ("doc_word", "cust_supp"), (2, 5)), "graph", "accept").collect()
    by = {(r.graph, r.accept): r for r in rows}
    for g in ("doc_word", "cust_supp"):
        assert by[g, 5].max_edges > by[g, 2].max_edges and by[g, 5].sum_edges > by[g, 2].sum_edges
        assert by[g, 5].p90 <= by[g, 2].p90
    rows = measures.mean_of_runs(experiments.vary_growth(spark, sf_dir, ("doc_word",), (1.2, 2.0)), "graph", "growth").collect()
    small, large = sorted(rows, key=lambda r: r.growth)
    assert small.max_edges < large.max_edges and small.sum_edges > large.sum_edges


def test_claims_speak_of_several_levels_and_can_fail(spark):
    rows = experiments.claims(spark, seeds=(0,)).collect()
    assert len(rows) > 2 and sum(r.vertices for r in rows) == sum(range(2, experiments.LADDER + 1))
    exact = degrees(clique_ladder(spark, 12)).selectExpr("id", "degree as coreness")
    wrong = exact.selectExpr("id", "1.0 as label", "5 as level", "0.5 as rate")
    assert measures.band_check(wrong, exact, 77, 0.1).first().too_dense > 0
    edges = clique_ladder(spark, experiments.LADDER).selectExpr("'ladder' as graph", "src", "dst")
    few = grid.success(edges, experiments.SMALL, (0, 1)).collect()
    many = grid.success(edges, replace(experiments.SMALL, c_rate=96, c_accept=192, c_cap=384), (0, 1)).collect()
    assert not all(r.labels for r in few) and all(r.bands and r.sizes and r.labels for r in many)


def test_prepeel_sends_less(spark, sf_dir):
    rows = grid.prepeel_saving(spark, sf_dir, ("doc_word",), replace(experiments.PRACTICAL, p0=2**-4)).collect()
    assert all(r.collected <= r.edges for r in rows) and sum(r.collected for r in rows) < sum(r.edges for r in rows)


def test_scaling_has_a_slope(spark, sf_dir):
    rows = experiments.scaling(spark, sf_dir, ("cust_supp",), (0.25, 1.0)).collect()
    assert len(rows) == 2 and rows[0].m < rows[1].m and experiments.slope([(1, 1.0), (10, 2.0)]) == pytest.approx(0.30103, abs=1e-4)


def test_refinement_runs_until_nothing_changes(spark):
    r = Rounds()
    got = peel.exact_coreness(path_graph(spark, 40), "refine", r).collect()
    assert {x.coreness for x in got} == {1} and r.sweeps >= 19 and r.jobs > r.sweeps


@pytest.mark.parametrize("method", ["local", "waves"])
def test_orders_point_few_edges_at_a_vertex(spark, method):
    edges = random_graph(spark, 60, 300, 5)
    order = cores.peel_order(edges, method)
    exact = {r.id: r.coreness for r in peel.exact_coreness(edges, "local").collect()}
    into = {r["head"]: r["count"] for r in cores.orient_edges(edges, order).groupBy("head").count().collect()}
    assert {r.id: r.coreness for r in order.collect()} == exact and all(n <= exact[v] for v, n in into.items())


def test_fused_levels_are_fewer_jobs(spark):
    edges = random_graph(spark, 100, 800, 1)
    p = SketchParams(accept=3, p0=2**-4, cap="scaled", peeler="local")
    two, one = sketch_coreness(edges, replace(p, rounds="two")), sketch_coreness(edges, replace(p, rounds="fused"))
    assert sorted(two.labels.collect()) == sorted(one.labels.collect()) and two.space == one.space and one.rounds.jobs < two.rounds.jobs


def test_new_graphs_hubs_and_sql_names(spark):
    assert {r.coreness for e in (cycle_graph(spark, 7), grid_graph(spark, 3, 4)) for r in peel.exact_coreness(e, "local").collect()} == {2}
    assert grid_graph(spark, 3, 4).count() == 17
    df = spark.createDataFrame([(1, k) for k in range(5)] + [(2, 1)], "g int, m int")
    assert [tuple(r) for r in hub_groups(df, ["g"], "m", 3).collect()] == [(1, 5, 10)]
    register(spark)
    assert [r[0] for r in spark.sql("SELECT first_level(u, array(0.25D, 0.5D, 1D)) FROM VALUES (1L), (1125899906842625L), (4503599627370495L) t(u)").collect()] == [0, 1, 2]
    cycle_graph(spark, 4).createOrReplaceTempView("four")
    assert {r.coreness for r in spark.sql("SELECT * FROM peel_order(TABLE(SELECT CAST(src AS STRING) AS src, CAST(dst AS STRING) AS dst FROM four))").collect()} == {2}


def test_graphs_above_one_task_are_swept_by_the_cluster(spark, sf_dir, monkeypatch):
    params = [replace(experiments.PRACTICAL, accept=3, p0=2**-2)]
    columns = ("graph", "seed", "accept", "n", "m", "levels", "max_edges", "sum_edges", "p50")
    some = lambda e: sorted(tuple(r) for r in grid.report(spark, sf_dir, ("page_link", "part_supp"), params, (1,), e).select(*columns).collect())
    one_task = some(False)
    two = replace(params[0], p0=2**-1)
    saved = sorted(map(tuple, grid.prepeel_saving(spark, sf_dir, ("page_link",), two).collect()))
    size = {r[0]: r[4] for r in one_task}
    assert size["page_link"] < size["part_supp"]
    monkeypatch.setattr(grid, "SPACE_EDGES", size["page_link"])
    assert some(False) == one_task and all(r[-1] is None for r in one_task)
    monkeypatch.setattr(grid, "SPACE_EDGES", 1)
    assert sorted(map(tuple, grid.prepeel_saving(spark, sf_dir, ("page_link",), two).collect())) == saved


def test_an_ablation_takes_few_jobs_and_is_the_same_at_any_size(spark, sf_dir, monkeypatch):
    names, n_jobs = ("page_link", "copart"), lambda: spark.sparkContext._jsc.sc().dagScheduler().numTotalJobs()
    run = lambda: {tuple(r)[:2] + (r.band,): tuple(r)[2:] for r in experiments.ablate_uniform(spark, sf_dir, names).collect()}
    before = n_jobs()
    one_task = run()
    assert n_jobs() - before < 40 and len(one_task) == 12
    edges = graph(spark, sf_dir, "copart")
    exact = peel.exact_coreness(edges, "refine")
    s = sketch_coreness(edges, replace(experiments.PRACTICAL, rounds="two"))
    rate = min(1.0, s.space_max() / edges.count())
    for method, labels in (("adaptive", s.labels), ("uniform_largest", cores.uniform_sample_coreness(edges, rate))):
        e = measures.error_percentiles(labels, exact).first()
        assert one_task["copart", method, "5 and more"][2:] == pytest.approx(tuple(e), abs=2e-6)
    assert one_task["copart", "uniform_largest", "5 and more"][0] == rate
    monkeypatch.setattr(grid, "EXACT_EDGES", 1)
    large = run()
    for packed in (1, 0):
        monkeypatch.setattr(experiments, "PACKED_EDGES", packed * experiments.PACKED_EDGES)
        large = run() if not packed else large
        assert large.keys() == one_task.keys()
        for k, r in large.items():
            assert r[0] == one_task[k][0] and r[1:3] == one_task[k][1:3] and r[3:] == pytest.approx(one_task[k][3:], abs=2e-6), k
