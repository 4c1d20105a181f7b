"""Published graph baselines on the same arrays as the gated graph.

HNSW and its plug-in routing test are settings of ``Params``; here are the graphs
that are built otherwise (Vamana, NSG), and the quantised graph whose beam is
ranked by estimates only.
"""

from __future__ import annotations

import time

import numpy as np

from ..params import Params
from .kernel import COUNTERS, EMPTY, EXPANDED, Found, Graph, Spill, _by_distance, _dist, _ids, _joined, _keys, _ranks, _scramble, build
from .projection import prepare


def hnsw_params(dim: int, **changes) -> Params:
    """Layered graph, one queue, every neighbour measured."""
    return Params(dim=dim, layers=True, gate=False, rings=False, screen=False, preset="hnsw").but(**changes)


def plugin_params(dim: int, **changes) -> Params:
    """A finished layered graph whose searches use the routing test with the queue's threshold."""
    return hnsw_params(dim).but(gate=True, gate_in_build=False, threshold="queue", preset="hnsw+test").but(**changes)


def gate_only_params(dim: int, **changes) -> Params:
    """The test in build and search, with the queue's threshold, no rings, no screen."""
    return Params(dim=dim, rings=False, screen=False, threshold="queue", preset="gate only").but(**changes)


def no_gate_params(dim: int, **changes) -> Params:
    """The flat graph without any test: the control."""
    return Params(dim=dim, gate=False, rings=False, screen=False, preset="no gate").but(**changes)


def _with_nodes(ids: np.ndarray, vectors: np.ndarray, params: Params) -> Graph:
    """A graph that holds the distinct vectors and no edges yet."""
    g = Graph(params)
    x = prepare(vectors, params, g.rotation)
    ids = np.asarray(ids, dtype=np.int64)
    _, first, inverse = np.unique(np.ascontiguousarray(x).view([("", x.dtype)] * x.shape[1]).ravel(), return_index=True, return_inverse=True)
    order = np.sort(first)
    place = np.full(len(ids), -1)
    place[order] = np.arange(len(order))
    g._room(len(order))
    g.size = len(order)
    g.x[: g.size], g.ids[: g.size] = x[order], ids[order]
    for i in np.flatnonzero(place < 0).tolist():
        g.copies.setdefault(int(place[first[inverse[i]]]), []).append(int(ids[i]))
    mean = g.x[: g.size].mean(axis=0) if g.size else 0
    g.entries = [int(((g.x[: g.size] - mean) ** 2).sum(axis=1).argmin())] if g.size else []
    g.entries_at = 1 << 60
    return g


def _relink(g: Graph, batch: np.ndarray, cand: np.ndarray, cap: int, alpha: float) -> None:
    """New out-edges of a batch of nodes from candidates, and their reverse edges."""
    cand = np.where(cand == batch[:, None], -1, cand)
    order = np.argsort(cand, axis=1, kind="stable")
    ranked = np.take_along_axis(cand, order, 1)
    ranked[:, 1:] = np.where(ranked[:, 1:] == ranked[:, :-1], -1, ranked[:, 1:])
    dist = g.gaps(ranked, batch)
    g.exact += int((ranked >= 0).sum())
    order = _by_distance(ranked, dist)
    ranked, dist = np.take_along_axis(ranked, order, 1), np.take_along_axis(dist, order, 1)
    kept = g.prune_out(g.x[batch], ranked, dist, cap, alpha)
    g.adj[batch], g.degree[batch] = -1, 0
    r, c = np.nonzero(kept)
    order = np.argsort(batch[r], kind="stable")
    source, target = batch[r][order], ranked[r, c][order]
    g._set_edges(source, target, 0)
    new = ~(g.adj[target] == source[:, None]).any(axis=1)
    g.add_incoming(target[new], source[new], 1)


def build_vamana(ids, vectors, dim: int, r: int = 32, l_build: int = 64, alpha: float = 1.2, metric: str = "l2", seed: int = 17) -> Graph:
    """Random regular graph, then two passes of search from the medoid, pruning and reverse edges."""
    params = Params(dim=dim, metric=metric, m_links=max(1, r // 2), gate=False, rings=False, screen=False, alpha=alpha, seed=seed, preset="vamana")
    g = _with_nodes(ids, vectors, params)
    n, rng = g.size, np.random.default_rng(seed)
    if n < 2:
        return g
    some = min(params.cap, n - 1)
    start = np.stack([rng.choice(n - 1, size=some, replace=False) for _ in range(n)])
    start += start >= np.arange(n)[:, None]
    g._set_edges(np.repeat(np.arange(n), some), start.ravel(), 0)
    order = np.argsort(_scramble(g.ids[:n], seed), kind="stable")
    for a in (1.0, alpha):
        for i in range(0, n, 256):
            batch = np.sort(order[i : i + 256])
            found = g.search_prepared(g.x[batch], l_build)
            g.exact += int(found.counters["n_exact"].sum())
            _relink(g, batch, np.hstack([found.ids, g.adj[batch]]), params.cap, a)
    return g


def exact_neighbours(x: np.ndarray, k: int) -> np.ndarray:
    """Places of the k nearest others of each vector."""
    out = np.empty((len(x), k), dtype=np.int64)
    sq = (x * x).sum(axis=1)
    for i in range(0, len(x), 512):
        d = sq[None, :] - 2 * x[i : i + 512] @ x.T
        d[np.arange(len(d)), np.arange(i, i + len(d))] = np.inf
        part = np.argpartition(d, k - 1, axis=1)[:, :k]
        out[i : i + 512] = np.take_along_axis(part, np.take_along_axis(d, part, 1).argsort(axis=1), 1)
    return out


def build_nsg(ids, vectors, dim: int, k: int = 24, r: int = 32, l_build: int = 64, metric: str = "l2", seed: int = 17) -> Graph:
    """Neighbour graph, pruned search paths from the medoid, and repair of what cannot be reached."""
    params = Params(dim=dim, metric=metric, m_links=max(1, r // 2), gate=False, rings=False, screen=False, seed=seed, preset="nsg")
    g = _with_nodes(ids, vectors, params)
    n = g.size
    if n < 2:
        return g
    k = min(k, n - 1, params.cap)
    near = exact_neighbours(g.x[:n], k)
    g.exact += n * (n - 1)
    g._set_edges(np.repeat(np.arange(n), k), near.ravel(), 0)
    paths = g.search_prepared(g.x[:n], l_build)
    g.exact += int(paths.counters["n_exact"].sum())
    cand = np.hstack([paths.ids, near])
    g.adj[:n], g.degree[:n] = -1, 0
    for i in range(0, n, 256):
        _relink(g, np.arange(i, min(i + 256, n)), cand[i : i + 256], params.cap, 1.0)
    while True:
        seen, front = np.zeros(n, dtype=bool), np.array(g.entries)
        seen[front] = True
        while len(front):
            front = np.unique(g.adj[front])
            front = front[(front >= 0)]
            front = front[~seen[front]]
            seen[front] = True
        lost = np.flatnonzero(~seen)
        if not len(lost):
            return g
        # The nearest reached node with room takes the edge; without room its farthest edge gives way.
        node = int(lost[0])
        reached = np.flatnonzero(seen)
        u = int(reached[((g.x[reached] - g.x[node]) ** 2).sum(axis=1).argmin()])
        if g.degree[u] == params.cap:
            roomy = reached[g.degree[reached] < params.cap]
            if len(roomy):
                u = int(roomy[((g.x[roomy] - g.x[node]) ** 2).sum(axis=1).argmin()])
            else:
                g.adj[u, params.cap - 1] = -1
                g.degree[u] -= 1
        g._set_edges(np.array([u]), np.array([node]), 1)


#: Bytes of neighbours' vectors that get their codes at once.
CODED_BYTES = 4 << 20


class QuantisedGraph:
    """A graph whose neighbours carry one-bit codes relative to the pivot; the beam is ranked by estimates.

    Estimates are compared with estimates; only expanded pivots are measured.
    ``accumulator="u16"`` adds 8-bit query levels in unsigned 16-bit integers,
    which overflow at high dimensions; ``"i32"`` does not.
    """

    def __init__(self, ids, vectors, dim: int, degree: int = 32, ef_build: int = 64, metric: str = "l2", accumulator: str = "i32"):
        degree = -(-degree // 32) * 32
        self.graph = build(ids, vectors, Params(dim=dim, metric=metric, m_links=degree // 2, ef_build=ef_build, gate=False, rings=False, screen=False, preset="quantised graph"))
        self.accumulator = accumulator
        g, n = self.graph, self.graph.size
        d = g.x.shape[1]
        self.bits = np.zeros((n, g.params.cap, -(-d // 8)), dtype=np.uint8)
        self.factor = np.ones((n, g.params.cap), dtype=np.float32)
        step = max(1, min(256, CODED_BYTES // (4 * g.params.cap * d)))
        for i in range(0, n, step):
            near = g.adj[i : min(i + step, n)]
            diff = g.x[np.maximum(near, 0)] - g.x[i : min(i + step, n), None, :]
            self.bits[i : i + len(near)] = np.packbits(diff > 0, axis=2)
            length = np.linalg.norm(diff, axis=2)
            self.factor[i : i + len(near)] = np.abs(diff).sum(axis=2) / (np.sqrt(d) * np.where(length > 0, length, 1))
        self.factor[self.factor == 0] = 1

    def bytes_by_part(self) -> dict[str, int]:
        sizes = self.graph.bytes_by_part()
        n, cap = self.graph.size, self.graph.params.cap
        return sizes | {"edges": n * cap * 4, "projection": n * cap * (self.bits.shape[2] + 8)}

    def search(self, vectors: np.ndarray, k: int, ef: int) -> Found:
        return self.search_each(vectors, [(k, ef)])[0][0]

    def search_each(self, vectors: np.ndarray, settings: list[tuple[int, int]]) -> list[tuple[Found, float]]:
        """What a search finds for each (k, ef), and its seconds; a wider beam goes on where the narrower one stops, as its first steps are the same."""
        g, began = self.graph, time.perf_counter()
        q = prepare(vectors, g.params, g.rotation)
        turning, out = time.perf_counter() - began, {}
        run = sorted((max(ef, k), k, i) for i, (k, ef) in enumerate(settings))
        for ef, k, i in run:
            if not len(q) or ef >= g.size:
                # A beam that holds every node expands and measures them all, whatever their estimates.
                began = time.perf_counter()
                out[i] = g.search_prepared(q, ef, k), turning + time.perf_counter() - began
        run = [r for r in run if r[2] not in out]
        parts = [self._search(q[j : j + 64], [(ef, k) for ef, k, _ in run]) for j in range(0, len(q), 64)] if run else []
        for at, (_, _, i) in enumerate(run):
            out[i] = _joined([part[at][0] for part in parts]), turning + sum(part[at][1] for part in parts)
        return [out[i] for i in range(len(settings))]

    def _search(self, q: np.ndarray, stops: list[tuple[int, int]]) -> list[tuple[Found, float]]:
        """(answers, seconds so far) at each of the rising (ef, k)."""
        began, stages, (ef, k) = time.perf_counter(), [], stops[0]
        g, m, n, d = self.graph, len(q), self.graph.size, q.shape[1]
        count = {c: np.zeros(m, dtype=np.int64) for c in COUNTERS}
        stamps = g.stamps
        stamps.begin(m, n)
        start = np.full(m, g.entries[0])
        work = np.full((m, ef), EMPTY)
        work[:, 0] = _keys(start, np.zeros(m))
        stamps.mark(np.arange(m), start)
        spill = Spill(m, stops[-1][0]) if len(stops) > 1 else None
        measured: list[tuple[np.ndarray, np.ndarray]] = []  # the rows and exact keys of expanded nodes
        active = np.arange(m)
        while True:
            closed = (work[active] & EXPANDED).astype(bool)
            best = closed.argmin(axis=1)
            go = ~closed[np.arange(len(active)), best]
            active, best = active[go], best[go]
            if not len(active):
                stages.append((Found(*self._measured(measured, m, k), {c: v.copy() for c, v in count.items()}), time.perf_counter() - began))
                if len(stages) == len(stops):
                    return stages
                if stops[len(stages)][0] > ef:
                    work = spill.widen(work, stops[len(stages)][0])
                ef, k = stops[len(stages)]
                active = np.arange(m)
                continue
            pivot = _ids(work[active, best])
            work[active, best] |= EXPANDED
            way = q[active] - g.x[pivot]
            b = np.linalg.norm(way, axis=1)
            measured.append((active, _keys(pivot, b)))
            count["n_exact"][active] += 1
            count["n_visited"][active] += 1
            near = g.adj[pivot]
            fresh = (near >= 0) & ~stamps.seen(active[:, None], np.maximum(near, 0))
            count["n_checked"][active] += fresh.sum(axis=1)
            # Inner products of sign codes with the quantised way: sums of levels where the bit is set.
            low, span = way.min(axis=1), np.maximum(np.ptp(way, axis=1), 1e-12)
            level = np.round((way - low[:, None]) / span[:, None] * 255).astype(np.int64)
            bit = np.unpackbits(self.bits[pivot], axis=2)[:, :, :d].astype(np.float32)
            on = np.einsum("acd,ad->ac", bit, level.astype(np.float32), optimize=True).astype(np.int64)
            if self.accumulator == "u16":
                on &= 0xFFFF
            ones = bit.sum(axis=2)
            half = (on * span[:, None] / 255 + ones * low[:, None]).astype(np.float64)
            inner = (2 * half - way.sum(axis=1)[:, None]) / np.sqrt(d)
            with np.errstate(divide="ignore", invalid="ignore"):
                cosine = np.where(b[:, None] > 0, inner / b[:, None] / self.factor[pivot], 0)
            a = g.length[pivot]
            guess = np.sqrt(np.maximum(a * a + (b * b)[:, None] - 2 * a * b[:, None] * np.clip(cosine, -1, 1), 0)).astype(np.float32)
            r, c = np.nonzero(fresh)
            stamps.mark(active[r], near[r, c])
            new = np.full(near.shape, EMPTY)
            new[r, c] = _keys(near[r, c], guess[r, c])
            both = np.sort(np.hstack([work[active], new]), axis=1)
            work[active] = both[:, :ef]
            if spill is not None:
                spill.push(active, both[:, ef:])

    @staticmethod
    def _measured(measured: list[tuple[np.ndarray, np.ndarray]], m: int, k: int) -> tuple[np.ndarray, np.ndarray]:
        """(places, distances) of the k nearest that each target has measured."""
        out = np.full((m, k), EMPTY)
        rows, keys = (np.concatenate([v[j] for v in measured]) for j in (0, 1))
        order = np.lexsort((keys, rows))
        rows, keys = rows[order], keys[order]
        place = _ranks(rows)
        out[rows[place < k], place[place < k]] = keys[place < k]
        return np.where(out == EMPTY, -1, _ids(out)), _dist(out)
