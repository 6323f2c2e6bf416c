import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from annspark.functions.metric import Metric
from annspark.functions.rules import ScaledBall, ScaledShiftedBall, ShiftedBall, UnitBall, alpha_bar
from annspark.functions.select import adaptive_select, alpha_steps, cap_nearest, fixed_select, scan_pairs, select_neighbors

RULES = [UnitBall(), ShiftedBall(0.1), ScaledBall(1.2), ScaledShiftedBall(1.2, 0.05), ScaledShiftedBall(0.9, 0.0)]
pos = st.floats(0, 100, allow_nan=False)


def candidates(seed, n=80, d=3):
    rng = np.random.default_rng(seed)
    x = rng.normal(size=(n, d))
    dist = np.sqrt((x * x).sum(1))
    order = np.argsort(dist)
    return dist[order], x[order]


def line(values, rule):
    x = np.array(values, float)[:, None]
    order = np.argsort(np.abs(x[:, 0]))
    return [values[order[i]] for i in select_neighbors(np.abs(x[order, 0]), x[order], rule).kept]


@settings(deadline=None)
@given(pos, pos, st.floats(0.5, 3), st.floats(0, 5))
def test_rule_identities(d_pu, d_uv, alpha, tau):
    r4 = ScaledShiftedBall(alpha, tau)
    assert bool(ScaledShiftedBall(alpha, 0).drops(d_pu, d_uv)) == bool(ScaledBall(alpha).drops(d_pu, d_uv))
    assert bool(ScaledShiftedBall(1, 0).drops(d_pu, d_uv)) == bool(UnitBall().drops(d_pu, d_uv))
    margin = abs(d_pu - (alpha * d_uv + (alpha + 1) * tau))
    if margin > 1e-6:
        assert bool(r4.drops(d_pu, d_uv)) == bool(d_uv < r4.radius(d_pu)) == bool(alpha_bar(d_pu, d_uv, tau) > alpha)


def test_threshold_form_without_distance():
    assert alpha_bar(1.0, 0.0, 0.0) == np.inf and alpha_bar(0.0, 0.0, 0.0) == -np.inf


def test_worked_lines():
    assert line([1, 2, 3, 10], UnitBall()) == [1]
    assert line([1, 2, 3, 10], ScaledShiftedBall(2, 1)) == [1, 2, 3, 10]
    assert line([1, 2, 3, 10], ScaledShiftedBall(2, 0)) == [1, 2, 10]
    assert not ScaledShiftedBall(2, 1).drops(2 * 3 + 3, 3)  # a tie is kept


def test_grid_keeps_the_axes():
    pts = np.array([(x, y) for x in (-1, 0, 1) for y in (-1, 0, 1) if (x, y) != (0, 0)], float)
    d = np.sqrt((pts**2).sum(1))
    order = np.lexsort((np.arange(8), d))
    kept = pts[order][select_neighbors(d[order], pts[order], UnitBall()).kept]
    assert sorted(map(tuple, kept)) == [(-1, 0), (0, -1), (0, 1), (1, 0)]


@pytest.mark.parametrize("rule", RULES)
@pytest.mark.parametrize("cap", [None, 1, 5])
def test_kernel_equals_the_double_loop(rule, cap):
    for seed in range(5):
        d, x = candidates(seed)
        assert select_neighbors(d, x, rule, cap).kept == scan_pairs(d, x, rule, cap)[0]
        assert select_neighbors(d, x, rule, 5).kept == cap_nearest(select_neighbors(d, x, rule).kept, 5)


def test_alpha_goes_by_whole_steps():
    steps = alpha_steps(0.9, 1.6, 0.05)
    assert len(steps) == 15 and steps[-1] == pytest.approx(1.6)


@pytest.mark.parametrize("m", [4, 5, 16, 64])
@pytest.mark.parametrize("tau", [0.0, 0.05])
def test_adaptive_is_the_first_alpha_that_fills(m, tau):
    for seed in range(6):
        d, x = candidates(seed)
        sets = [fixed_select(d, x, m, a, tau).kept for a in alpha_steps(0.9, 1.6, 0.05)]
        first = next((i for i, s in enumerate(sets) if 2 * len(s) >= m), 14)
        got, plain = adaptive_select(d, x, m, tau=tau), adaptive_select(d, x, m, tau=tau, reuse=False)
        assert got.kept == sets[first] == plain.kept and got.steps == first + 1 and got.pairs <= plain.pairs


def test_small_candidate_sets():
    empty = np.empty(0)
    assert adaptive_select(empty, np.empty((0, 2)), 8).kept == [] and adaptive_select(empty, np.empty((0, 2)), 8).steps == 15
    assert adaptive_select(np.array([1.0]), np.ones((1, 2)), 8).kept == [0]
    d, x = candidates(1, 3)
    assert adaptive_select(d, x, 8).alpha_used == pytest.approx(1.6)


def test_copies_give_no_nan():
    x = np.array([[0.0, 0], [0, 0], [1, 0], [0, 2]])
    d = np.sqrt((x * x).sum(1))
    assert adaptive_select(d, x, 4, tau=0.0).kept[0] == 0


@pytest.mark.parametrize("name", ["l2", "l1", "chord", "angular"])
def test_metrics_satisfy_the_triangle_inequality(name):
    m = Metric(name)
    x = m.prepare(np.random.default_rng(3).normal(size=(30, 4)))
    d = m.cross(x, x)
    assert (d[:, None, :] <= d[:, :, None] + d[None, :, :] + 1e-9).all() and np.allclose(d, d.T)
    ids, dist = m.nearest(x, x, np.arange(30), 4, skip=np.arange(30))
    for i in range(30):
        row = [(v, j) for j, v in enumerate(d[i]) if j != i]
        assert [j for _, j in sorted(row)[:4]] == ids[i].tolist() and np.allclose(dist[i], d[i][ids[i]])


def test_what_is_no_metric_is_refused():
    with pytest.raises(ValueError):
        Metric("cosine")


def test_ranking_distances_round_as_fused_sums():
    import math

    x = np.random.default_rng(4).normal(size=(2, 200, 128))
    want = []
    for a, b in zip(*x):
        s = 0.0
        for u, v in zip(a, b):
            s = math.fma(u - v, u - v, s)
        want.append(math.sqrt(s))
    assert Metric().ranking(*x).tolist() == want
    near, dist = Metric().nearest(x[0][:1], x[1], np.arange(200), 200)
    assert dist[0].tolist() == Metric().ranking(x[0][0], x[1][near[0]]).tolist()


def test_few_distance_calls_where_many_are_kept(monkeypatch):
    calls, rows = [0], Metric.rows

    def counted(self, a, b):
        calls[0] += 1
        return rows(self, a, b)

    rng = np.random.default_rng(9)
    for d, n in ((2, 60), (3, 150), (16, 200), (64, 600)):
        for scale in (1.0, 1e-4):
            # On a grid there are ties at the ball's edge.
            v = np.round(rng.normal(size=(n, d)) * 2) / 2 * scale + 1
            p = Metric()
            dist = p.rows(v, np.ones(d))
            order = np.lexsort((np.arange(n), dist))
            v, dist = v[order], dist[order]
            for rule in (UnitBall(), ShiftedBall(0.05 * scale), ScaledBall(1.2), ScaledShiftedBall(1.05, 0.001 * scale)):
                for cap in (None, 16, 50):
                    monkeypatch.setattr(Metric, "rows", counted)
                    calls[0] = 0
                    got = select_neighbors(dist, v, rule, cap)
                    monkeypatch.setattr(Metric, "rows", rows)
                    assert got.kept == scan_pairs(dist, v, rule, cap)[0]
                    asked = got.kept if cap is None or len(got.kept) < cap else got.kept[:-1]
                    assert got.pairs == sum(n - 1 - i for i in asked)
                    if d == 16 and len(asked) > 40:
                        assert calls[0] < len(asked) / 2


@pytest.mark.parametrize("tau", [0.0, 0.05])
def test_selections_of_many_points_equal_the_double_loop(tau):
    from annspark.functions.rules import ScaledBall, ScaledShiftedBall, ShiftedBall
    from annspark.functions.select import adaptive_many, select_many

    rng = np.random.default_rng(5)
    x = np.unique(np.round(rng.normal(size=(500, 3)) * 4) / 4, axis=0) + rng.choice([0.0, 1e6])
    ids, dist = [], []
    for p in range(0, len(x), 9):
        d = np.linalg.norm(x - x[p], axis=1)
        order = np.lexsort((np.arange(len(x)), d))
        order = order[order != p][: p % 140]
        ids.append(order)
        dist.append(d[order])
    for rule in (UnitBall(), ShiftedBall(tau), ScaledBall(1.2), ScaledShiftedBall(1.1, tau)):
        for cap in (None, 7):
            for i, d, got in zip(ids, dist, select_many(x, ids, dist, rule, cap)):
                assert got.kept == scan_pairs(d, x[i], rule, cap)[0]
    for reuse in (True, False):
        for i, d, got in zip(ids, dist, adaptive_many(x, ids, dist, 12, tau=tau, reuse=reuse)):
            assert got == adaptive_select(d, x[i], 12, tau=tau, reuse=reuse)
