"""Grids over graphs whose edges come in bands: the same rows as whole graphs in one task."""

from dataclasses import replace

import numpy as np
import pytest

from stratacore.operators.peel import local_labels
from stratacore.plans import banded, experiments, grid


def test_bands_give_the_rows_of_whole_graphs(spark, sf_dir, monkeypatch):
    params = [replace(experiments.PRACTICAL, accept=t, growth=g) for t, g in ((2, 2.0), (3, 1.2), (2.5, 1.4))]
    params.append(replace(params[0], cap=None, p0=2**-3))
    run = lambda errors: {(r.graph, r.seed, k): tuple(r)[2:-1] for k, r in enumerate(sorted(grid.report(spark, sf_dir, ("doc_word", "part_supp"), params, (0, 1), errors).collect()))}
    whole = run(True), run(False)
    assert len(whole[0]) == 16
    monkeypatch.setattr(experiments, "sweep", None)
    monkeypatch.setattr(grid, "BANDED_EDGES", 0)
    monkeypatch.setattr(grid, "per_run", None)
    monkeypatch.setattr(banded, "ROW_EDGES", 700)
    for size, errors in ((500, True), (10, True), (500, False)):
        monkeypatch.setattr(banded, "GROUP_EDGES", size)
        got = run(errors)
        assert got.keys() == whole[not errors].keys()
        for k, r in got.items():
            assert r[:11] == whole[not errors][k][:11] and (r[11:] == pytest.approx(whole[0][k][11:], abs=1e-12) if errors else r[11:] == (None,) * 5), k


def test_clipped_cores_beside_settled_vertices():
    rng = np.random.default_rng(4)
    for n, m in ((40, 200), (200, 900), (3000, 60)):
        ends = np.unique(np.sort(rng.integers(0, n, (m, 2)), 1), axis=0)
        a, b = ends[ends[:, 0] < ends[:, 1]].T.astype(np.int32)
        settled = rng.random(n) < 0.2
        keep = ~(settled[a] & settled[b])
        a, b = a[keep], b[keep]
        want = local_labels(a, b, n, settled)[0]
        for least, top in ((0, None), (3, None), (3, 5), (2, 2)):
            who, raw = banded.pinned_cores(a, b, settled, least, top)
            some = np.flatnonzero((want >= max(least, 1)) & ~settled)
            assert sorted(zip(who.tolist(), raw.tolist(), strict=True)) == [(v, min(want[v], top or n)) for v in some.tolist()]
