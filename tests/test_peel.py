import random
from collections import defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from stratacore.operators import cores, peel
from stratacore.runtime import Rounds, written
from stratacore.sources import arcs, clique_ladder, degrees, dense_ids, edges_from, path_graph, random_graph, read_edge_text, star_graph


def slow_labels(edges, settled=()):
    """Brute force: remove a least-degree vertex outside `settled` until none is left."""
    nbr = defaultdict(set)
    for a, b in edges:
        nbr[a].add(b)
        nbr[b].add(a)
    left, label, level = set(nbr) - set(settled), {}, 0
    while left:
        v = min(left, key=lambda x: (len(nbr[x]), x))
        level = max(level, len(nbr[v]))
        label[v] = level
        left.discard(v)
        for u in nbr.pop(v):
            nbr[u].discard(v)
    return label


def frame(spark, pairs):
    return edges_from(spark.createDataFrame([(int(a), int(b)) for a, b in pairs], "src long, dst long"))


def random_pairs(seed, n=30, m=90):
    r = random.Random(seed)
    return {(min(a, b), max(a, b)) for a, b in ((r.randrange(n), r.randrange(n)) for _ in range(m)) if a != b}


def test_local_kernel_on_random_graphs():
    for seed in range(60):
        pairs = sorted(random_pairs(seed, m=20 + 3 * seed))
        r = random.Random(seed)
        ids = sorted({x for p in pairs for x in p})
        settled = set(r.sample(ids, r.randrange(len(ids) // 2))) if seed % 2 else set()
        number = {x: k for k, x in enumerate(ids)}
        a, b = (np.array([number[p[k]] for p in pairs]) for k in (0, 1))
        label, _ = peel.local_labels(a, b, len(ids), np.array([x in settled for x in ids]))
        assert {x: int(label[number[x]]) for x in ids if x not in settled} == slow_labels(pairs, settled)


def test_three_methods_agree(spark):
    pairs = random_pairs(5)
    e, want = frame(spark, pairs), slow_labels(pairs)
    for method in ("local", "refine", "waves", "auto"):
        assert {r.id: r.coreness for r in peel.exact_coreness(e, method).collect()} == want, method


def test_hand_graphs(spark):
    ladder = {r.id: r.coreness for r in peel.exact_coreness(clique_ladder(spark, 6), "local").collect()}
    assert all(v == k // 1000 - 1 for k, v in ladder.items())
    assert {r.coreness for r in peel.exact_coreness(path_graph(spark, 5), "local").collect()} == {1}
    star = peel.exclusive_labels(star_graph(spark, 4), spark.createDataFrame([(0,)], "id long"), method="local").collect()
    assert {(r.id, r.label) for r in star} == {(k, 1) for k in range(1, 5)}
    pair = frame(spark, [(5, 1), (5, 2), (5, 3)])
    pinned = spark.createDataFrame([(1,), (2,), (3,)], "id long")
    assert [(r.id, r.label) for r in peel.exclusive_labels(pair, pinned).collect()] == [(5, 3)]
    assert peel.exclusive_labels(pair, pinned.union(spark.createDataFrame([(5,)], "id long"))).count() == 0


def test_capped_and_edges_inside_settled(spark):
    pairs = random_pairs(8, m=140)
    settled = {0, 1, 2, 3}
    e, s = frame(spark, pairs), spark.createDataFrame([(x,) for x in settled], "id long")
    want = slow_labels(pairs, settled)
    got = {r.id: r.label for r in peel.exclusive_labels(e, s, cap=3).collect()}
    assert got == {k: min(v, 3) for k, v in want.items()}
    more = frame(spark, pairs | {(0, 1), (0, 2), (1, 3), (2, 3)})
    assert {r.id: r.label for r in peel.exclusive_labels(more, s, method="local").collect()} == want


def test_empty_and_dirty_edges(spark):
    none = spark.createDataFrame([], "src long, dst long")
    for method in ("local", "refine", "waves"):
        assert peel.exact_coreness(none, method).count() == 0
    dirty = spark.createDataFrame([(1, 2), (2, 1), (1, 1), (None, 2), (1, 2)], "src long, dst long")
    assert [(r.src, r.dst) for r in edges_from(dirty).collect()] == [(1, 2)]


def test_k_core_prepeel_and_order(spark):
    pairs = random_pairs(11, m=120)
    e, want = frame(spark, pairs), slow_labels(pairs)
    kept = {x for p in peel.k_core(e, 3).collect() for x in p}
    assert kept == {k for k, v in want.items() if v >= 3}
    rest, low = peel.prepeel_labels(e, 3)
    assert {r.id: r.label for r in low.collect()} == {k: v for k, v in want.items() if v < 3}
    assert {x for p in rest.collect() for x in p} == kept
    order = cores.peel_order(e)
    into = {r["head"]: r["count"] for r in cores.orient_edges(e, order).groupBy("head").count().collect()}
    assert all(k <= want[v] for v, k in into.items())


def test_approximate_core_needs_closing(spark):
    e = frame(spark, [(1, 2), (1, 3), (1, 4), (2, 3), (2, 4), (3, 4), (5, 6), (6, 7), (5, 7)])
    labels = spark.createDataFrame([(i, 3.0) for i in (1, 2, 3, 4, 5)] + [(6, 1.0), (7, 1.0)], "id long, label double")
    vertices, _ = cores.approx_k_core(e, labels, 3, 2 / 3)
    assert {r.id for r in vertices.collect()} == {1, 2, 3, 4}


def test_baselines(spark):
    pairs = random_pairs(3, n=40, m=300)
    e, want = frame(spark, pairs), slow_labels(pairs)
    waves = {r.id: r.estimate for r in cores.threshold_waves(e).collect()}
    assert waves == {k: next(4 * 2**i for i in range(9) if 4 * 2**i > v) for k, v in want.items()}
    exact = {r.id: r.raw for r in cores.uniform_sample_coreness(e, 1.0).collect()}
    assert exact == want
    density, found, _ = cores.densest_by_peeling(e)
    assert density >= len(pairs) / degrees(e).count() and found.count() > 0


def test_arcs_ids_and_text(spark, tmp_path):
    e = frame(spark, [(1, 2), (2, 3)])
    assert {tuple(r) for r in arcs(e).collect()} == {(1, 2), (2, 1), (2, 3), (3, 2)}
    ids = dense_ids(spark.createDataFrame([(x,) for x in "abcabd"], "key string")).collect()
    assert sorted(r.id for r in ids) == [0, 1, 2, 3] and {r.key for r in ids} == set("abcd")
    (tmp_path / "g.txt").write_text("# a comment\n1\t2\n2 1\n3 3\n2 4\n")
    assert {tuple(r) for r in read_edge_text(spark, str(tmp_path / "g.txt")).collect()} == {(1, 2), (2, 4)}


@pytest.mark.parametrize("values,h", [([], 0), ([5], 1), ([1, 1, 1], 1), ([3, 3, 3, 1], 3)])
def test_h_index(spark, values, h):
    from stratacore.functions import h_index, register

    df = spark.createDataFrame([(values,)], "v array<bigint>")
    assert df.select(h_index(F.col("v"))).first()[0] == h
    register(spark)
    assert df.selectExpr("h_index(v)").first()[0] == h


def test_exclusive_labels_beyond_one_task(spark, monkeypatch):
    pairs = random_pairs(8, m=120)
    pinned = spark.createDataFrame([(k,) for k in range(0, 30, 5)], "id long")
    want = slow_labels({p for p in pairs if p[0] % 5 or p[1] % 5}, range(0, 30, 5))
    for most in (10_000_000, 10):
        monkeypatch.setattr(peel, "LOCAL_EDGES", most)
        assert {r.id: r.label for r in peel.exclusive_labels(frame(spark, pairs), pinned, method="auto").collect()} == want


def test_numbered_vertices_peel_in_one_task(spark, monkeypatch):
    pairs = random_pairs(9, m=150)
    e = frame(spark, pairs).selectExpr("concat('v', src) as src", "concat('v', dst) as dst")
    monkeypatch.setattr(peel, "LOCAL_EDGES", 10)
    monkeypatch.setattr(peel, "exclusive_refined", None)
    assert {r.id: r.coreness for r in peel.exact_coreness(e, "auto").collect()} == {f"v{k}": v for k, v in slow_labels(pairs).items()}


@pytest.mark.parametrize("most", [2_000_000, 0])
def test_a_refinement_leaves_out_what_lies_below_its_floor(spark, monkeypatch, most):
    """Both layouts of the arcs, with settled vertices: from the floor on the labels of one task, below it no row."""
    monkeypatch.setattr(peel, "BROADCAST_ROWS", most)
    e = written(random_graph(spark, 40, 120, 3).withColumns({"su": F.col("src") % 10 == 0, "sv": F.col("dst") % 10 == 0}).where("not (su and sv)"), "flagged")
    whole = {r.id: r.raw for r in peel.exclusive_local(e).collect()}
    assert {r.id: r.raw for r in peel.exclusive_refined(e).collect()} == whole
    assert {r.id: r.raw for r in peel.exclusive_refined(e, 4, floor=4, size=10).collect()} == {k: 4 for k, v in whole.items() if v >= 4}
    assert 0 < sum(v >= 4 for v in whole.values()) < len(whole)


def test_a_sweep_is_one_write_whose_changes_are_counted_on_the_way(spark):
    """With few vertices a sweep moves no arcs and asks no second query: 23 jobs for 10 sweeps (before: 67)."""
    e, r = written(path_graph(spark, 20).withColumns({"su": F.lit(False), "sv": F.lit(False)}), "flagged"), Rounds()
    peel.exclusive_refined(e, rounds=r)
    assert peel.exclusive_refined(e, floor=3).count() == peel.exclusive_refined(e.limit(0)).count() == 0
    assert r.sweeps == 10 and r.jobs <= 3 * r.sweeps


def test_packed_lists_change_nothing(spark, monkeypatch):
    edges = random_graph(spark, 300, 3000, 7)
    want = sorted(map(tuple, peel.exact_coreness(edges, "waves").collect()))
    for name, value in (("LOCAL_EDGES", 10), ("NUMBERED_EDGES", 10), ("ROW_EDGES", 100), ("SPAN", 50)):
        monkeypatch.setattr(peel, name, value)
    r = Rounds()
    assert sorted(map(tuple, peel.exact_coreness(edges, "auto", r).collect())) == want and not r.sweeps
    ends = np.array([tuple(e) for e in edges.collect()])
    label, _ = peel.local_labels(ends[:, 0], ends[:, 1], 300, np.zeros(300, bool))
    assert [(v, c) for v, c in enumerate(label.tolist()) if c] == [(v, c) for v, c in want if c]
