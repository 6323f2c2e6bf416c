import numpy as np
import pytest

from annspark.functions import graphs as G
from annspark.functions.beam import beam_search, greedy_route, padded
from annspark.functions.metric import Metric
from annspark.functions.rules import ScaledShiftedBall, UnitBall


def points(n=150, d=3, seed=0):
    return np.random.default_rng(seed).normal(size=(n, d))


def reference(neighbors, x, q, entry, width):
    """Beam search as words describe it."""
    dist = lambda v: float(np.sqrt(((x[v] - q) ** 2).sum()))
    queue, explored, seen, hops = [(dist(entry), entry)], set(), {entry}, 0
    while any(v not in explored for _, v in queue):
        u = min((d, v) for d, v in queue if v not in explored)[1]
        explored.add(u)
        hops += 1
        for v in neighbors[u]:
            if v not in seen:
                seen.add(v)
                queue.append((dist(v), v))
        queue = sorted(queue)[:width]
    return [v for _, v in queue], len(seen), hops, seen


@pytest.mark.parametrize("width", [1, 4, 20, 150])
def test_beam_equals_the_reference(width):
    x = points()
    g = G.build("lcg_adaptive", x, G.Params(K=10, M=8, L=15, C=40, tau=0.01))
    q = points(12, 3, 9)
    got = beam_search(g.adjacency(), x, q, g.entry, width, pools=True)
    for i in range(len(q)):
        ids, ndc, hops, seen = reference(g.neighbors, x, q[i], g.entry, width)
        assert got.ids[i][got.ids[i] >= 0].tolist() == ids and got.ndc[i] == ndc and got.hops[i] == hops and set(got.pools[i][0].tolist()) == seen


def test_ties_go_to_smaller_places():
    x = np.array([[0.0], [1], [-1], [1], [2]])
    adjacency = padded([[4, 3, 2, 1], [0], [0], [0], [0]])
    assert beam_search(adjacency, x, np.zeros((1, 1)), 0, 3).ids.tolist() == [[0, 1, 2]]


@pytest.mark.parametrize("method", G.METHODS)
def test_every_builder_gives_a_sound_graph(method):
    x, p = points(120), G.Params(K=12, M=8, L=15, C=60, alpha=1.2, tau=0.01, hnsw_m=4, hnsw_ef=15, vamana_m=8, vamana_l=15)
    g = G.build(method, x, p)
    extra = {u for u, _ in g.repairs}
    full = method in ("mrng", "shifted_full", "scaled_full", "fcg")
    for v, (ns, ds) in enumerate(zip(g.neighbors, g.dists)):
        assert v not in ns and len(set(ns)) == len(ns) and all(0 <= u < len(x) for u in ns)
        assert full or len(ns) <= p.M + sum(u == v for u, _ in g.repairs) or v in extra
        assert np.allclose(ds, np.sqrt(((x[ns] - x[v]) ** 2).sum(1)) if ns else [])
    assert G.reached(g.neighbors, g.entry).mean() >= (1.0 if method.startswith("lcg") or full or method in ("nsg", "shifted_local") else 0.95)
    again = G.build(method, x, p)
    assert again.neighbors == g.neighbors and again.entry == g.entry
    found = G.search_layered(g, x, x[:20], len(x), 5)
    exact, _ = Metric().nearest(x[:20], x, np.arange(len(x)), 5)
    assert method.startswith(("hnsw", "vamana")) or (found.ids == exact).all()


def test_two_islands_are_joined():
    x = np.concatenate([points(40, 2, 1), points(40, 2, 2) + 1000])
    p = G.Params(K=5, M=6, L=10, C=20, include_knn=True)
    g = G.build("lcg_adaptive", x, p)
    assert g.repairs and G.reached(g.neighbors, g.entry).all()


def test_lazy_pruning_needs_fewer_selections():
    x, p = points(300, 4), G.Params(K=20, M=12, L=20, C=80)
    lazy, eager = G.build("lcg_adaptive", x, p), G.build("lcg_adaptive_eager", x, p)
    assert len(x) <= lazy.selections <= 2 * len(x) and lazy.selections <= eager.selections


def test_cutting_to_the_nearest_loses_the_way_and_adaptive_keeps_it():
    # A hub with a tight bunch on one side and a far region on the other.
    bunch = [(0.1, 0), (0.11, 0.01), (0.12, -0.01), (0.13, 0), (0.105, 0.02), (0.115, -0.02)]
    x = np.array([(0.0, 0), *bunch, (-5, 0), (-5.5, 0.5), (-6, 0)])
    d = np.sqrt((x[1:] ** 2).sum(1))
    order = np.argsort(d, kind="stable")
    cut = {1 + int(i) for i in order[:4]}
    kept = {1 + int(order[i]) for i in G.make_select("adaptive", G.Params(M=4), Metric())(d[order], x[1:][order]).kept}
    assert not cut & {7, 8, 9} and kept & {7, 8, 9}


def test_exact_when_queries_are_within_tau():
    x = np.unique(np.round(points(200, 2, 4), 3), axis=0)
    tau, alpha = 0.02, 1.2
    rows = G.full_graph(x, ScaledShiftedBall(alpha, tau))
    adjacency = padded([r[0] for r in rows])
    rng = np.random.default_rng(1)
    v = rng.normal(size=x.shape)
    q = x + tau * rng.uniform(0, 1, (len(x), 1)) * v / np.linalg.norm(v, axis=1, keepdims=True)
    got = greedy_route(adjacency, x, q, 0)
    near, dist = Metric().nearest(q, x, np.arange(len(x)), 1)
    assert np.allclose(got.dist[:, 0], dist[:, 0])
    d = Metric().cross(x, x)
    ratio = d.max() / d[d > 0].min()
    assert (got.hops <= np.log(4 * ratio) / np.log(alpha) + 2).all()
    unit = greedy_route(padded([r[0] for r in G.full_graph(x, UnitBall())]), x, q, 0)
    assert got.hops.mean() < unit.hops.mean() and np.mean([len(r[0]) for r in rows]) > np.mean([len(r[0]) for r in G.full_graph(x, UnitBall())])


def test_degree_grows_with_tau():
    x = points(120, 2)
    mean = [np.mean([len(r[0]) for r in G.full_graph(x, ScaledShiftedBall(1.2, t))]) for t in (0.0, 0.01, 0.1, 0.5)]
    assert mean == sorted(mean)


def test_recall_grows_with_width():
    x = points(400, 8)
    g = G.build("lcg_adaptive", x, G.Params(K=16, M=16, L=20, C=100))
    q = points(40, 8, 3)
    exact, _ = Metric().nearest(q, x, np.arange(len(x)), 10)
    recall = [np.mean([len(set(a) & set(b)) for a, b in zip(beam_search(g.adjacency(), x, q, g.entry, w, 10).ids, exact)]) for w in (10, 20, 80, 400)]
    assert recall == sorted(recall) and recall[-1] == 10


@pytest.mark.parametrize("n", [0, 1, 2, 5])
def test_tiny_sets(n):
    for method in G.METHODS:
        g = G.build(method, points(n), G.Params(K=4, M=4, L=4, C=8))
        assert len(g.neighbors) == n and all(len(r) < n for r in g.neighbors)


def test_descent_comes_near_the_exact_graph():
    x = points(1500, 8)
    (ids, dist), (exact, _) = G.descent_knn_graph(x, 20), G.exact_knn_graph(x, 20)
    assert np.mean([len(np.intersect1d(a, b)) / 20 for a, b in zip(ids, exact)]) >= 0.9
    assert np.allclose(dist, np.sqrt(((x[ids] - x[:, None]) ** 2).sum(2))) and (np.diff(dist, axis=1) >= 0).all() and (ids != np.arange(len(x))[:, None]).all()
    assert (G.descent_knn_graph(x[:3], 20)[0].shape, G.descent_knn_graph(x[:1], 5)[0].tolist()) == ((3, 2), [[-1]])


def test_large_shards_take_the_descent(monkeypatch):
    monkeypatch.setattr(G, "EXACT_POINTS", 100)
    x = points(300, 4)
    g = G.build("lcg_adaptive", x, G.Params(K=16, M=16, L=20, C=100))
    exact, _ = Metric().nearest(x[:40], x, np.arange(len(x)), 5)
    got = beam_search(g.adjacency(), x, x[:40], g.entry, 60, 5).ids
    assert np.mean(got == exact) > 0.95


def test_published_settings():
    assert {(p.K, p.M, p.L, p.C) for p in G.PRESETS.values()} == {(200, 50, 40, 500), (200, 70, 60, 500), (200, 100, 100, 500), (200, 80, 100, 500)}
    p = G.Params()
    assert (p.hnsw_m, p.hnsw_ef, p.vamana_m, p.vamana_l, p.vamana_alpha, p.alpha0, p.alpha_step, p.alpha_max) == (32, 500, 70, 75, 1.2, 0.9, 0.05, 1.6)


def eager(x, forward, m, select):
    """Reversed edges one at a time, as words describe it."""
    rows = [list(r) for r in forward]
    for v in range(len(x)):
        for u in forward[v]:
            if v in rows[u]:
                continue
            rows[u].append(v)
            if len(rows[u]) > m:
                ids = np.array(sorted(rows[u], key=lambda w: (float(np.sqrt(((x[w] - x[u]) ** 2).sum())), w)))
                d = np.sqrt(((x[ids] - x[u]) ** 2).sum(1))
                rows[u] = ids[select(d, x[ids]).kept].tolist()
    return rows


@pytest.mark.parametrize("method,policy", [("nsg", "unit"), ("shifted_local", "shifted"), ("lcg_adaptive_eager", "adaptive")])
def test_eager_insertion_by_brute_force(method, policy):
    from dataclasses import replace

    x, p = points(200, 4), G.Params(K=16, M=8, L=20, C=60, tau=0.02)
    forward = G.build(method, x, replace(p, backward="none")).neighbors
    want = eager(x, forward, p.M, G.make_select(policy, p, Metric()))
    got = G.build(method, x, p)
    fixed: dict = {}
    for u, v in got.repairs:
        fixed.setdefault(u, []).append(v)
    assert [[v for v in row if v not in fixed.get(u, [])] for u, row in enumerate(got.neighbors)] == want


@pytest.mark.parametrize("rule", [UnitBall(), ScaledShiftedBall(1.05, 0.001)])
@pytest.mark.parametrize("shape", ["spread", "copies", "lattice", "far"])
def test_full_rows_equal_the_filter_over_all_and_look_at_few(rule, shape):
    x = points(300, 6, 3)
    x = {"spread": x, "copies": x[np.arange(300) % 40], "lattice": np.round(x), "far": x * 1e-6 + 5}[shape]
    full = G.FullRows(x, rule)
    for cap in (None, 4):
        for p, (ids, dist) in enumerate(full.rows(np.arange(0, 300, 7), cap)):
            want, d = full._plain(7 * p, cap)
            assert ids.tolist() == want.tolist() and dist.tolist() == d.tolist()


def test_full_rows_measure_few_pairs(monkeypatch):
    x, looked = points(4000, 8, 3), []
    rows = Metric.rows
    monkeypatch.setattr(Metric, "rows", lambda self, a, b: looked.append(len(a)) or rows(self, a, b))
    [(ids, _)] = G.full_graph(x, ScaledShiftedBall(1.05, 0.001), Metric(), np.array([5]))
    assert len(ids) > 5 and sum(looked) < len(x)


def _cloud(n: int, dim: int, seed: int = 3) -> np.ndarray:
    """Points on a coarse grid, so that many distances are equal."""
    return np.unique(np.round(np.random.default_rng(seed).normal(size=(n, dim)) * 4) / 4, axis=0)


@pytest.mark.parametrize("dim, width", [(3, 20), (8, 400)])
def test_beam_by_products_equals_the_plain_one_and_measures_less(dim, width, monkeypatch):
    from annspark.functions import beam

    x = _cloud(900, dim)
    knn, _ = G.exact_knn_graph(x, 40)
    queries = x[::7] + 0.01
    measured = [0]
    rows = Metric.rows
    monkeypatch.setattr(Metric, "rows", lambda self, a, b: measured.__setitem__(0, measured[0] + len(a)) or rows(self, a, b))
    got = beam.beam_search(knn, x, queries, 0, width, 10, traces=True)
    quick, measured[0] = measured[0], 0
    nearest = beam.beam_search(knn, x, queries, 0, 20, 1, pools=True, most=30).pools
    monkeypatch.setattr(beam, "COARSE_POINTS", 0)
    measured[0] = 0
    plain = beam.beam_search(knn, x, queries, 0, width, 10, traces=True)
    assert width > 20 or 3 * quick < 2 * measured[0]
    for f in ("ids", "dist", "ndc", "hops", "edges"):
        assert np.array_equal(getattr(got, f), getattr(plain, f))
    assert got.traces == plain.traces
    for (ids, d), (all_ids, all_d) in zip(nearest, beam.beam_search(knn, x, queries, 0, 20, 1, pools=True).pools):
        best = np.lexsort((all_ids, all_d))[:30]
        own = np.lexsort((ids, d))[:30]
        assert np.array_equal(ids[own], all_ids[best]) and np.array_equal(d[own], all_d[best])


def test_methods_over_the_same_candidates_share_a_group():
    from dataclasses import replace

    from annspark.operators.build import _families

    p = G.Params()
    settings = {m: (m, p) for m in ("hnsw", "lcg_adaptive", "lcg_fixed", "nsg", "shifted_local", "vamana")}
    assert _families(settings, 8, 6) == [["lcg_adaptive", "lcg_fixed", "nsg", "shifted_local"], ["hnsw"], ["vamana"]]
    assert _families(settings, 1, 6) == [[m] for m in settings]
    assert len(_families({"a": ("nsg", p), "b": ("nsg", replace(p, K=9))}, 8, 6)) == 2


@pytest.mark.parametrize("policy", ["unit", "shifted", "fixed"])
def test_eager_edges_by_additions_equal_whole_selections(policy):
    x, p, calls = _cloud(400, 3), G.Params(K=30, M=6, C=40, tau=0.05), [0, 0]
    _, pools = G.prepare_local(x, p)

    def built(number: int, rule):
        select = G.make_select(policy, p, Metric())
        first = [select(d, x[ids]).kept for ids, d in pools]
        near, far = [ids[k].tolist() for (ids, _), k in zip(pools, first)], [d[k].tolist() for (_, d), k in zip(pools, first)]
        counted = lambda d, v: calls.__setitem__(number, calls[number] + 1) or select(d, v)
        return G.add_backward_eager(x, near, far, counted, p, rule), near, far

    assert built(0, G.make_rule(policy, p)) == built(1, None)
    assert 2 * calls[0] < calls[1]
