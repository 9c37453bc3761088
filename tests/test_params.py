import math

import pytest

from stratacore.params import Level, SketchParams, label_of, plan_space, rate_schedule, recommend_growth


def test_schedule_grows_and_ends_at_one():
    for growth in (1.2, 1.4, 2.0):
        rates = [x.rate for x in rate_schedule(10_000, SketchParams(accept=3, p0="scaled", cap="scaled", growth=growth))]
        assert rates == sorted(rates) and rates[-1] == 1 and rates[0] == pytest.approx(3 / 20_000)


def test_theory_constants_degenerate_on_small_graphs():
    assert [x.rate for x in rate_schedule(1000, SketchParams())] == [1.0]
    assert [x.rate for x in rate_schedule(1, SketchParams())] == [1.0]


def test_two_branches_are_one_clipped_formula():
    n, eps = 10**9, 0.9
    p = SketchParams(eps=eps, deflate=False)
    for lv in rate_schedule(n, p)[:-1]:
        band_top = 2 * n / 2 ** (lv.level - 1)
        assert label_of(10 * lv.cap, lv, p) == pytest.approx(band_top)
        assert label_of(lv.cap / 2, lv, p) == pytest.approx(lv.cap / 2 / lv.rate)
        assert lv.cap == pytest.approx(2 * lv.accept)
        assert lv.accept == pytest.approx(2 * n * rate_schedule(n, p)[0].rate)


def test_last_level_is_not_clipped_and_sides():
    last = Level(3, 1.0, 0.0, math.inf)
    assert label_of(100, last, SketchParams(eps=0.25)) == 75
    assert label_of(100, last, SketchParams(eps=0.25, exact_last=True)) == 100
    assert label_of(100, last, SketchParams(eps=0.25, side="upper")) == 150


def test_bad_parameters():
    for bad in ({"eps": 0}, {"eps": 1.0}, {"growth": 1.0}, {"sampler": "x"}):
        with pytest.raises(ValueError):
            SketchParams(**bad)
    with pytest.warns(UserWarning):
        SketchParams(eps=0.6)


def test_planning():
    assert plan_space(1000, SketchParams(accept=4))["rule_max"] == 4000
    assert recommend_growth("max", 1500, 1000, 3) < recommend_growth("max", 5000, 1000, 3)
    assert recommend_growth("sum", 1000, 1000, 3) > recommend_growth("sum", 30_000, 1000, 3)
