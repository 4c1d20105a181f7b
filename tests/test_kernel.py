"""The array kernel: identities, enumeration, invariants, rings, recall."""

import itertools
import tracemalloc

import numpy as np
import pytest

from vecgraph.operators import baselines as B
from vecgraph.operators.kernel import EMPTY, Graph, _ids, _keys, _push, build
from vecgraph.operators.projection import orthogonal, prepare, profile, references, target_table
from vecgraph.params import Params
from vecgraph.plans import experiments as X


def points(n=400, d=32, seed=1):
    return np.random.default_rng(seed).normal(size=(n, d)).astype(np.float32)


def exact(x, q, k):
    d = np.linalg.norm(q[:, None] - x[None], axis=2)
    return np.sort(d, axis=1)[:, :k]


def recall(found, truth):
    return (found.dist[:, : truth.shape[1]] <= truth[:, -1:] + 1e-4).mean()


def test_rotation_keeps_distances_and_references_are_unit():
    x = points(20, 30)
    p = Params(30, blocks=4)
    y = prepare(x, p)
    assert y.shape[1] == 32
    assert np.allclose(np.linalg.norm(x[0] - x[1]), np.linalg.norm(y[0] - y[1]), atol=1e-4)
    t = orthogonal(32, 3)
    assert np.allclose(t @ t.T, np.eye(32), atol=1e-5)
    refs = references(32, 4, 24, 3)
    assert np.allclose(np.linalg.norm(refs, axis=2), 0.5, atol=1e-5)  # 1 / sqrt(4)
    for b in range(4):  # closed under negation
        assert all(np.isclose(refs[b], -r, atol=1e-6).all(axis=1).any() for r in refs[b])


def test_block_choice_is_the_best_of_the_product_set():
    refs = references(6, 3, 4, 5)
    rng = np.random.default_rng(0)
    p, x = rng.normal(size=(10, 6)).astype(np.float32), rng.normal(size=(10, 6)).astype(np.float32)
    _, own, _, codes = profile(p, x, refs)
    for i in range(10):
        diff = x[i] - p[i]
        best = max(itertools.product(range(4), repeat=3), key=lambda c: np.concatenate([refs[b, j] for b, j in enumerate(c)]) @ diff)
        assert tuple(codes[i]) == best
        assert np.isclose(own[i], np.concatenate([refs[b, j] for b, j in enumerate(best)]) @ diff / np.linalg.norm(diff), atol=1e-5)


def test_cosine_law_identities():
    rng = np.random.default_rng(2)
    for _ in range(200):
        p, q, x = rng.normal(size=(3, 8))
        a, b, r = np.linalg.norm(x - p), np.linalg.norm(q - p), rng.uniform(0.5, 5)
        cos = (x - p) @ (q - p) / (a * b)
        tau, delta = (a * a + b * b - r * r) / (2 * a * b), a / (2 * b)
        assert (cos >= tau) == (np.linalg.norm(x - q) <= r)
        assert (cos > delta) == (np.linalg.norm(x - q) < b)
        assert np.isclose(delta - tau, (r * r - b * b) / (2 * a * b))


def test_projection_estimate_is_unbiased_and_better_with_more_blocks():
    x = points(3000, 64)
    p, q, n = x[:1000], x[1000:2000], x[2000:]
    errors = []
    for blocks in (2, 8, 16):
        refs = references(64, blocks, 32, 1)
        a, own, shift, codes = profile(p, n, refs)
        table = target_table(q, refs)
        dots = table[np.arange(1000)[:, None], np.arange(blocks), codes].sum(axis=1) - shift
        b = np.linalg.norm(q - p, axis=1)
        estimate = dots / b / own
        true = ((n - p) * (q - p)).sum(axis=1) / (a * b)
        assert abs((estimate - true).mean()) < 0.03
        errors.append(np.sqrt(((estimate - true) ** 2).mean()))
    assert errors[0] > errors[1] > errors[2]


def test_ring_overwrites_its_oldest():
    keys, used = np.full((2, 3), EMPTY), np.zeros(2, dtype=np.int64)
    _push(keys, used, np.array([0, 0, 0, 0, 1]), _keys(np.array([10, 11, 12, 13, 20]), np.arange(5.0)), True)
    assert _ids(keys)[:, 0].tolist() == [13, 20] and _ids(keys)[0].tolist() == [13, 11, 12] and (keys[1, 1:] == EMPTY).all() and used.tolist() == [4, 1]


@pytest.mark.parametrize("params", [Params(32), Params.throughput(32), Params.compact(32), B.hnsw_params(32), B.plugin_params(32), B.gate_only_params(32), B.no_gate_params(32)])
def test_invariants_and_recall(params):
    x = points()
    g = build(np.arange(400) * 3, x, params)
    r, target, _, _ = g.edges()
    assert g.size == 400 and (g.degree[:400] <= params.cap).all()
    assert (r != target).all() and ((0 <= target) & (target < 400)).all()
    assert len(set(zip(r.tolist(), target.tolist()))) == len(r)
    assert not g.pending
    f = g.search(x[:50], 10, 128)
    assert recall(f, exact(x, x[:50], 10)) >= 0.9
    assert (np.diff(f.dist, axis=1) >= 0).all()
    h = build(np.arange(400) * 3, x, params)
    assert (h.adj == g.adj).all()  # the same seed gives the same graph


def test_wide_search_without_gate_is_exact():
    x = points()
    g = build(np.arange(400), x, B.no_gate_params(32))
    f = g.search(x[:30] + 0.1, 10, 400)
    assert np.allclose(f.dist, exact(x, x[:30] + 0.1, 10), atol=1e-4)


def test_gate_saves_exact_distances_and_rings_save_more():
    x = points(1500, 64)
    q = points(40, 64, 9)
    cost = {}
    for name, p in {"none": B.no_gate_params(64), "gate": B.gate_only_params(64, blocks=16), "rings": Params(64, blocks=16, screen=False)}.items():
        cost[name] = build(np.arange(1500), x, p).search(q, 10, 64).counters["n_exact"].mean()
    assert cost["rings"] < cost["gate"] < 0.6 * cost["none"]


def test_working_set_as_large_as_the_search_is_the_queue():
    x = points()
    g = build(np.arange(400), x, Params(32, screen=False))
    a = g.search(x[:20], 5, 64, rings=True, work=64)
    b = g.search(x[:20], 5, 64, rings=False)
    assert (a.ids == b.ids).all() and (a.counters["n_exact"] == b.counters["n_exact"]).all()


def test_gate_passes_most_that_qualify():
    x = points(600, 64)
    g = build(np.arange(600), x, Params(64, blocks=16, refs_per_block=64))
    q = prepare(points(30, 64, 5), g.params, g.rotation)
    table = target_table(q, g.refs)
    hit = total = 0
    for i in range(30):
        for u in range(0, 600, 7):
            near = g.adj[u, : g.degree[u]]
            b = np.linalg.norm(q[i] - g.x[u])
            dots = table[i][np.arange(16), g.codes[u, : len(near)]].sum(axis=1) - g.shift[u, : len(near)]
            d = np.linalg.norm(g.x[near] - q[i], axis=1)
            r = np.median(d)
            a = g.length[u, : len(near)]
            ok = dots / b / g.own[u, : len(near)] >= (a * a + b * b - r * r) / (2 * a * b)
            hit += (ok & (d <= r)).sum()
            total += (d <= r).sum()
    assert hit / total >= 0.5


def test_copies_share_a_node_and_are_answers():
    x = np.vstack([points(50, 16), points(50, 16)])
    g = build(np.arange(100), x, Params(16))
    assert g.size == 50 and sum(len(v) for v in g.copies.values()) == 50
    g.insert(np.array([1000]), x[:1])
    assert g.size == 50 and 1000 in [c for v in g.copies.values() for c in v]


@pytest.mark.parametrize("dim", [16, 64, 96, 128])
def test_copies_turn_to_the_same_bits_at_any_place(dim):
    x = points(50, dim)
    p = Params(dim)
    y = prepare(np.vstack([x, x[:3], x]), p)
    assert (y[:50] == y[53:]).all() and (y[50:53] == y[:3]).all()
    assert np.allclose(y[:50], x.astype(np.float64) @ orthogonal(p.padded, p.seed), atol=1e-5)


def test_copies_join_nodes_that_no_edge_leads_to():
    x = points(80, 16)
    g = build(np.arange(80), x, Params(16))
    g.adj[:], g.degree[:] = -1, 0
    g.insert(np.arange(100, 180), x)
    assert g.size == 80 and sorted(c for v in g.copies.values() for c in v) == list(range(100, 180))


@pytest.mark.parametrize("n", [0, 1, 2, 3])
def test_tiny_graphs(n):
    g = build(np.arange(n), points(n, 8), Params(8, blocks=2))
    f = g.search(points(2, 8, 3), 5, 8)
    assert (f.ids >= 0).sum(axis=1).tolist() == [n, n]


def test_zero_vectors_under_cosine():
    x = np.vstack([np.zeros((1, 8)), points(20, 8)]).astype(np.float32)
    g = build(np.arange(21), x, Params(8, blocks=2, metric="cosine"))
    assert (g.search(x[:3], 5, 16).ids[:, 0] >= 0).all()


def test_incremental_build_keeps_recall():
    x = points(600, 32)
    g = build(np.arange(300), x[:300], Params(32))
    g.insert(np.arange(300, 600), x[300:])
    assert recall(g.search(x[:60], 10, 96), exact(x, x[:60], 10)) >= 0.9


def test_batches_against_single_insertions():
    x = points(300, 24)
    truth = exact(x, x[:60], 10)
    one = recall(build(np.arange(300), x, Params(24, max_batch=1)).search(x[:60], 10, 64), truth)
    many = recall(build(np.arange(300), x, Params(24, max_batch=128)).search(x[:60], 10, 64), truth)
    assert many >= one - 0.05


def test_screen_gives_edges_to_starved_nodes():
    rng = np.random.default_rng(4)
    hubs = rng.normal(size=(8, 48))
    x = (hubs[rng.integers(0, 8, 800)] + rng.normal(scale=0.6, size=(800, 48)) * rng.uniform(0.2, 1.5, (800, 1))).astype(np.float32)
    counts = {}
    for on in (False, True):
        g = build(np.arange(800), x, Params(48, screen=on))
        counts[on] = (np.bincount(g.edges()[1], minlength=800) <= 1).sum(), (g.edges()[3] == 2).sum()
    assert counts[True][1] > 0 == counts[False][1]
    assert counts[True][0] <= counts[False][0]


def test_incoming_rule_by_hand():
    # 0 at the origin with an out-neighbour 1 between it and 2: the edge 0 -> 2 has a witness; 0 -> 3 has none.
    g = Graph(Params(2, blocks=1, refs_per_block=4, m_links=4))
    g._room(4)
    g.size = 4
    g.x[:4, :2] = [[0, 0], [1, 0], [1.8, 0], [0, 2]]
    g._set_edges(np.array([0]), np.array([1]), 0)
    assert g.keeps_incoming(np.array([0, 0]), np.array([2, 3])).tolist() == [False, True]


@pytest.mark.parametrize("params", [Params(24), Params(24, gate=False), Params(24, threshold="queue", rings=False), B.hnsw_params(24), B.plugin_params(24), Params(24, metric="cosine")])
@pytest.mark.parametrize("work", [16, 300])
def test_a_search_as_wide_as_its_graph_finds_nodes_that_no_edge_leads_to(params, work):
    x = points(300, 24)
    g = build(np.arange(300), x, params.but(work=work))
    lost = np.isin(g.adj, np.arange(250, 300)) & (g.adj >= 0)
    for i in np.flatnonzero(lost.any(axis=1)):
        keep = g.adj[i][(g.adj[i] >= 0) & ~lost[i]]
        g.adj[i], g.degree[i] = -1, len(keep)
        g.adj[i, : len(keep)] = keep
    f = g.search(x[:40], 12, 300)
    y = g.x[:300]
    d = np.linalg.norm(prepare(x[:40], g.params)[:, None] - y[None], axis=2)
    assert (np.sort(f.ids, axis=1) == np.sort(np.argsort(d, axis=1)[:, :12], axis=1)).all()
    assert np.allclose(f.dist, np.sort(d, axis=1)[:, :12], atol=1e-5) and (f.counters["n_exact"] >= 300).all()


def test_a_beam_as_wide_as_its_quantised_graph_is_exact():
    x = points(300, 24)
    f = B.QuantisedGraph(np.arange(300), x, 24).search(x[:40], 12, 8 * 300)
    assert np.allclose(f.dist, exact(x, x[:40], 12), atol=1e-5)


def test_published_graphs_reach_recall():
    x = points()
    truth = exact(x, x[:40], 10)
    assert recall(B.build_vamana(np.arange(400), x, 32).search(x[:40], 10, 64), truth) >= 0.9
    assert recall(B.build_nsg(np.arange(400), x, 32).search(x[:40], 10, 96), truth) >= 0.9
    assert recall(B.QuantisedGraph(np.arange(400), x, 32).search(x[:40], 10, 128), truth) >= 0.7


def test_narrow_sums_overflow_at_high_dimensions():
    x = np.random.default_rng(0).normal(size=(200, 1536)).astype(np.float32)
    truth = exact(x, x[:20] + 0.3, 10)
    good = recall(B.QuantisedGraph(np.arange(200), x, 1536).search(x[:20] + 0.3, 10, 48), truth)
    bad = recall(B.QuantisedGraph(np.arange(200), x, 1536, accumulator="u16").search(x[:20] + 0.3, 10, 48), truth)
    assert bad < good


@pytest.mark.parametrize("kind", ["throughput", "hnsw", "plugin", "gate_only", "vamana", "qgraph"])
def test_searches_of_rising_width_go_on_and_find_the_same(kind):
    x, ids = points(900, 16, seed=3), np.arange(900)
    make = {"throughput": Params.throughput(16), "hnsw": B.hnsw_params(16), "plugin": B.plugin_params(16), "gate_only": B.gate_only_params(16)}
    g = build(ids, x, make[kind]) if kind in make else B.build_vamana(ids, x, 16) if kind == "vamana" else B.QuantisedGraph(ids, x, 16)
    q, settings = points(70, 16, seed=4), [(100, 100), (10, 8), (10, 64), (20, 64), (400, 400), (11, 24), (900, 900)]
    for (k, ef), (found, seconds) in zip(settings, g.search_each(q, settings)):
        alone = g.search(q, k, ef)
        assert (found.ids == alone.ids).all() and (found.dist == alone.dist).all() and seconds > 0
        assert all((found.counters[c] == alone.counters[c]).all() for c in alone.counters)


@pytest.mark.parametrize("kind", ["throughput", "hnsw", "qgraph"])
def test_wider_searches_take_no_step_twice(kind, monkeypatch):
    from vecgraph.operators import kernel
    from vecgraph.plans import experiments as X

    x, ids, steps = points(600, 16, seed=3), np.arange(600), []
    method = X.Method(kind, "qgraph" if kind == "qgraph" else "graph", B.hnsw_params(16) if kind == "hnsw" else Params.throughput(16))
    made = X.make(method, ids, x)
    seen = kernel.Stamps.seen
    monkeypatch.setattr(kernel.Stamps, "seen", lambda self, rows, nodes: steps.append(1) or seen(self, rows, nodes))
    list(X._searches(made, x[:5], [(200, 200)], True))
    widest = len(steps)
    list(X._searches(made, x[:5], [(k, k) for k in (64, 100, 150, 200)], True))
    assert len(steps) - widest <= 1.1 * widest


def test_distances_in_pieces_are_those_of_all_at_once(monkeypatch):
    """Fetched vectors stay within a core's cache, whatever a step asks for."""
    from vecgraph.operators import kernel

    x = points(300, 48)
    g = build(np.arange(300), x, Params(48))
    q, rng = g.x[:7] + np.float32(0.1), np.random.default_rng(2)
    node, row = rng.integers(0, 300, 1000), np.sort(rng.integers(0, 7, 1000))
    whole = g._distances(node, q, row)
    diff = g.x[node] - q[row]
    assert (whole == np.sqrt(np.einsum("nd,nd->n", diff, diff))).all()
    monkeypatch.setattr(kernel, "CACHED_BYTES", 4 * 48 * 16)
    assert (g._distances(node, q, row) == whole).all() and len(g._distances(node[:0], q, row[:0])) == 0
    again = build(np.arange(300), x, Params(48))
    assert (again.adj == g.adj).all() and again.exact == g.exact


def test_builds_work_on_vectors_in_pieces():
    """Beside the graph, linking and coding hold a few MB of fetched vectors or doubles, whatever the dimension; the results are those of whole arrays."""
    rng = np.random.default_rng(8)
    n, d = 800, 2048
    x = rng.normal(size=(n, d)).astype(np.float32)
    x[700:] = x[:100]
    own = n * d * 4
    for method, most in ((X.all_methods(d)[3], 40 * own), (X.all_methods(d)[5], 11 * own), (X.all_methods(d)[8], 25 * own)):
        tracemalloc.start()
        made = X.make(method, np.arange(n), x)
        peak = tracemalloc.get_traced_memory()[1]
        tracemalloc.stop()
        assert peak < most, (method.name, peak / own)
    assert made.graph.size == 700 and made.graph.copies[int(np.flatnonzero(made.graph.ids[:700] == 5)[0])] == [705]
    g = made.graph
    cand = np.array([[1, 2, -1], [3, -1, -1]])
    whole = np.where(cand >= 0, np.linalg.norm(g.x[np.maximum(cand, 0)] - g.x[[7, 8]][:, None, :], axis=2), np.inf)
    assert (g.gaps(cand, np.array([7, 8])) == whole).all()
