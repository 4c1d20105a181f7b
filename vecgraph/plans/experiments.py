"""Experiments: every method over one corpus, each (method, shard) by one task.

The corpus is written once as blobs, a file a shard; each method reads the files
in place, so vectors are not copied for methods and nothing is exchanged. ``run``
gives the answers of all methods at all widths with their counters; ``counted``
holds them in the tasks against the exact distances, and ``summary`` averages that.
Times and peaks of memory are taken inside the tasks, after a search that warms up;
counts are what comparisons rest on, as they do not depend on the machine.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, replace
from functools import reduce

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from ..operators import baselines as B
from ..operators import measures as M
from ..operators.exact import HELD_FLOATS, each_sent, kth_distances
from ..operators.index import SENT_FLOATS, kmeans, on_shards, raw_shards, raw_vectors, vectors_of, with_copies
from ..operators.kernel import Graph, build
from ..operators.quantised import Coder
from ..params import Params
from ..sources.session import materialise, ship

RUN = (
    "method string, k int, ef int, qid bigint, vec_id bigint, dist double, rank int, n_checked bigint, n_pass bigint, n_exact bigint, n_visited bigint, "
    "n_fp bigint, n_fp_reused bigint, n_rounds bigint, search_s double"
)
COUNTS = "method string, k int, ef int, qid bigint, good bigint, " + RUN[RUN.index("n_checked") :]
BUILT = "method string, shard int, n bigint, build_exact bigint, build_search bigint, build_s double, edges bigint, screen_edges bigint, vectors_b bigint, edges_b bigint, projection_b bigint, codes_b bigint, zero_in bigint, build_peak bigint, search_peak bigint"

#: Runs over different corpora that are under way at once.
AT_ONCE = 3
#: What a search costs in a shard.
COUNTED = ("n_checked", "n_pass", "n_exact", "n_visited", "n_fp", "n_fp_reused", "n_rounds", "search_s")


@dataclass(frozen=True)
class Method:
    """A method and its settings."""

    name: str
    kind: str  # graph, vamana, nsg, qgraph, pq, aniso, scalar, exact
    params: Params | None = None
    options: tuple[tuple[str, object], ...] = ()
    inserts: bool = True  # whether vectors can be added to what is built


def all_methods(dim: int, metric: str = "l2", **changes) -> list[Method]:
    """The two presets, the ablation arms, and the published methods."""
    common = {"metric": metric} | changes
    base = Params.throughput(dim, **common)
    return [
        Method("throughput", "graph", base),
        Method("compact", "graph", Params.compact(dim, **common)),
        Method("hnsw", "graph", B.hnsw_params(dim, m_links=32, ef_build=128, **common)),
        Method("vamana", "vamana", Params(dim=dim, **common)),
        Method("nsg", "nsg", Params(dim=dim, **common)),
        Method("ivfpq", "pq", Params(dim=dim, **common)),
        Method("aniso", "aniso", Params(dim=dim, **common)),
        Method("scalar", "scalar", Params(dim=dim, **common)),
        Method("qgraph", "qgraph", Params(dim=dim, **common), inserts=False),
        Method("hnsw_test", "graph", B.plugin_params(dim, m_links=32, ef_build=128, blocks=base.blocks, refs_per_block=64, **common), inserts=False),
    ]


def ablation_methods(dim: int, metric: str = "l2", **changes) -> list[Method]:
    """Gate only, with rings, with rings and screen, and the control without a gate."""
    full = Params.throughput(dim, metric=metric, **changes)
    return [
        Method("no_gate", "graph", full.but(gate=False, rings=False, screen=False)),
        Method("gate", "graph", full.but(rings=False, screen=False, threshold="queue")),
        Method("gate_rings", "graph", full.but(screen=False)),
        Method("gate_rings_screen", "graph", full),
    ]


class Cells:
    """A shard's quantised codes in memory."""

    #: Vectors that codebooks are trained on.
    TRAIN = 20_000
    #: Queries that are turned at once.
    TURNED = 256

    def __init__(self, kind: str, ids: np.ndarray, x: np.ndarray, params: Params, rerank: int = 4):
        if params.metric == "cosine":
            x = x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-12)
        self.ids, self.x, self.metric, self.rerank = ids, x, params.metric, rerank
        nlist = max(1, int(np.sqrt(len(x)) / 2))
        sample = self.x[np.random.default_rng(params.seed).choice(len(x), size=min(len(x), self.TRAIN), replace=False)]
        self.coder = Coder(kind, kmeans(sample, nlist, params.seed).astype(np.float64), parts=max(4, params.dim // 8)).fit(sample)
        self.cell, self.codes, self.norm, self.factor = self.coder.encode(self.x)
        self.members = [np.flatnonzero(self.cell == c) for c in range(len(self.coder.centroids))]

    def search(self, q: np.ndarray, k: int, ef: int):
        if self.metric == "cosine":
            q = q / np.maximum(np.linalg.norm(q, axis=1, keepdims=True), 1e-12)
        nprobe = int(np.clip(ef // 8, 1, len(self.members)))
        ids, dist = np.full((len(q), k), -1), np.full((len(q), k), np.inf)
        checked, exact = np.zeros(len(q), dtype=np.int64), np.zeros(len(q), dtype=np.int64)
        for begin in range(0, len(q), self.TURNED):
            some = q[begin : begin + self.TURNED].astype(np.float64)
            for i, (v, turned) in enumerate(zip(some, self.coder.turn(some)), begin):
                probes = ((self.coder.centroids - v) ** 2).sum(axis=1).argsort()[:nprobe]
                rows, parts = np.concatenate([self.members[c] for c in probes]), [(int(c), self.members[c]) for c in probes]
                est = np.concatenate([self.coder.estimate(v, c, self.codes[m], self.norm[m], self.factor[m], turned) for c, m in parts])
                best = rows[np.argsort(est, kind="stable")[: self.rerank * k]]
                d = np.sqrt(((self.x[best] - v) ** 2).sum(axis=1))
                order = np.lexsort((self.ids[best], d))[:k]
                ids[i, : len(order)], dist[i, : len(order)] = best[order], d[order]
                checked[i], exact[i] = len(rows), len(best)
        return ids, dist, checked, exact


def make(method: Method, ids: np.ndarray, x: np.ndarray):
    """The built structure of a method over vectors."""
    p, options = method.params, dict(method.options)
    if method.kind == "graph":
        return build(ids, x, p)
    if method.kind == "vamana":
        return B.build_vamana(ids, x, p.dim, metric=p.metric, seed=p.seed, **options)
    if method.kind == "nsg":
        return B.build_nsg(ids, x, p.dim, metric=p.metric, seed=p.seed, **options)
    if method.kind == "qgraph":
        return B.QuantisedGraph(ids, x, p.dim, metric=p.metric, **options)
    return Cells(method.kind, ids, x, p, **options)


def built_row(method: Method, made, seconds: float, n: int) -> dict:
    sizes = {"vectors": 0, "edges": 0, "projection": 0, "codes": 0}
    edges = screened = exact = searched = zero = 0
    if isinstance(made, Cells):
        width = made.codes.shape[1] * (made.coder.bits if method.kind == "scalar" else 4) // 8
        sizes |= {"vectors": made.x.shape[0] * made.x.shape[1] * 4, "codes": made.x.shape[0] * (width + 12)}
        exact = n * len(made.members)
    else:
        sizes |= made.bytes_by_part()
        g: Graph = getattr(made, "graph", made)
        exact, searched = g.exact + sum(u.exact for u in g.upper), g.exact_search
        _, target, _, origin = g.edges()
        edges, screened = len(target), int((origin == 2).sum())
        zero = int((np.bincount(target, minlength=g.size)[: g.size] == 0).sum())
    return {
        "n": n,
        "build_exact": exact,
        "build_search": searched,
        "build_s": seconds,
        "edges": edges,
        "screen_edges": screened,
        "vectors_b": sizes["vectors"],
        "edges_b": sizes["edges"],
        "projection_b": sizes["projection"],
        "codes_b": sizes["codes"],
        "zero_in": zero,
    }


def _searches(made, q: np.ndarray, settings: list[tuple[int, int]], exclude_self: bool) -> Iterator[tuple]:
    """(places, distances, counters, seconds a query) of each setting; searches of a graph go on where narrower ones stop."""
    if not isinstance(made, Cells):
        for out, seconds in made.search_each(q, [(k + exclude_self, ef) for k, ef in settings]):
            yield out.ids, out.dist, out.counters, seconds / max(1, len(q))
        return
    for k, ef in settings:
        began = time.perf_counter()
        found, dist, checked, exact = made.search(q, k + exclude_self, ef)
        yield found, dist, {"n_checked": checked, "n_exact": exact}, (time.perf_counter() - began) / max(1, len(q))


def _ranked(made, qid: np.ndarray, found: np.ndarray, dist: np.ndarray, k: int, exclude_self: bool):
    """(row, ids, dist, rank) of the k answers of each query, nearest first."""
    g = getattr(made, "graph", made)
    row, ids, dist = with_copies(found, dist, g.ids, getattr(g, "copies", {}), k + exclude_self)
    if exclude_self:
        other = ids != qid[row]
        row, ids, dist = row[other], ids[other], dist[other]
    order = np.lexsort((ids, dist, row))
    row, ids, dist = row[order], ids[order], dist[order]
    begins = np.flatnonzero(np.concatenate([[True], row[1:] != row[:-1]])) if len(row) else row
    rank = np.arange(len(row)) - np.repeat(begins, np.diff(np.append(begins, len(row)))) + 1
    return tuple(v[rank <= k] for v in (row, ids, dist, rank))


def _answers(method: Method, made, qid: np.ndarray, search: tuple, limits: np.ndarray | None, k: int, ef: int, exclude_self: bool) -> pd.DataFrame:
    """A row for each answer; with limits a row for each query that has answers, with how many of them lie within its limit."""
    found, dist, counters, seconds = search
    row, ids, dist, rank = _ranked(made, qid, found, dist, k, exclude_self)
    if limits is None:
        rows = pd.DataFrame({"qid": qid[row], "vec_id": ids, "dist": dist, "rank": rank})
    else:
        good = np.bincount(row[dist <= limits[row] + M.TIE], minlength=len(qid))
        row = np.unique(row)
        rows = pd.DataFrame({"qid": qid[row], "good": good[row]})
    for c in ("n_checked", "n_pass", "n_exact", "n_visited", "n_fp", "n_fp_reused", "n_rounds"):
        rows[c] = counters.get(c, np.zeros(len(qid), dtype=np.int64))[row]
    return rows.assign(search_s=seconds, method=method.name, k=k, ef=ef)


class Peak:
    """Bytes by which this process's memory rises at most, where the system tells."""

    def __enter__(self) -> Peak:
        self.bytes = None
        try:
            with open("/proc/self/clear_refs", "w") as f:
                f.write("5")  # the peak starts anew
            self.before = self._read("VmRSS")
        except OSError:
            self.before = None
        return self

    def __exit__(self, *_) -> None:
        if self.before is not None:
            self.bytes = max(0, self._read("VmHWM") - self.before)

    @staticmethod
    def _read(name: str) -> int:
        with open("/proc/self/status") as f:
            return next(int(line.split()[1]) * 1024 for line in f if line.startswith(name))


def run(corpus: DataFrame, queries: DataFrame, methods: list[Method], settings: list[tuple[int, int]], shards: int = 1, exclude_self: bool = False) -> tuple[DataFrame, DataFrame]:
    """(answers, builds) of all methods at all settings (k, ef); both tables are materialised.

    Every query is searched in every shard. Counters of a query and sizes and
    seconds of a build are sums over the shards.
    """
    answers, builds = _runs(corpus, queries, None, methods, settings, shards, exclude_self)
    over = Window.partitionBy("method", "k", "ef", "qid")
    totals = {c: F.sum(F.when(F.col("rank") == 1, F.col(c))).over(over) for c in COUNTED}  # one answer of each shard has rank 1
    answers = answers.withColumns(totals | {"rank": F.row_number().over(over.orderBy("dist", "vec_id"))}).where(F.col("rank") <= F.col("k"))
    return answers, builds


def counted(
    corpus: DataFrame, queries: DataFrame, limits: DataFrame, methods: list[Method], settings: list[tuple[int, int]], shards: int = 1, exclude_self: bool = False
) -> tuple[DataFrame, DataFrame]:
    """(counts, builds): as ``run``, but tasks hold the answers against ``limits(qid, k, limit)`` and emit a row for each setting and query.

    Answers within a query's limit are among its k nearest of all shards, so
    their number over the shards is what a merge of the answers would count.
    """
    of_query = limits.groupBy("qid").agg(F.map_from_entries(F.collect_list(F.struct("k", "limit"))).alias("limits"))
    return _runs(corpus, materialise(queries.join(of_query, "qid", "left"), "limited"), sorted({k for k, _ in settings}), methods, settings, shards, exclude_self)


def _runs(corpus: DataFrame, queries: DataFrame, ks: list[int] | None, methods: list[Method], settings: list[tuple[int, int]], shards: int, exclude_self: bool) -> tuple[DataFrame, DataFrame]:
    spark = corpus.sparkSession
    ship(spark)
    params = methods[0].params
    raw, _ = raw_shards(corpus, params, shards)
    shape = RUN if ks is None else COUNTS
    sent = _sent(queries, params.dim, ks)
    done = materialise(reduce(DataFrame.unionByName, [_run_method(raw, sent, ks, m, settings, exclude_self) for m in methods]), "experiment")
    for block in sent:
        block.destroy()
    built = [c.split()[0] for c in BUILT.split(", ")]
    one = done.where("n IS NOT NULL").select(*built).groupBy("method")
    builds = one.agg(*[(F.max if c.endswith("_peak") else F.sum)(c).alias(c) for c in built if c not in ("method", "shard")])
    return done.where("qid IS NOT NULL").select(*[c.split()[0] for c in shape.split(", ")]), builds


def _sent(queries: DataFrame, dim: int, ks: list[int] | None) -> list[Broadcast]:
    """(qid, vectors, limits by k) in blocks of a checked size, sent once for all methods; the driver holds one at a time."""
    reads = max(1, -(-queries.count() * (dim + len(ks or ())) // min(SENT_FLOATS, HELD_FLOATS)))
    out = []
    for i in range(reads):
        block = queries if reads == 1 else queries.where(F.pmod(F.xxhash64("qid"), F.lit(reads)) == i)
        rows = block.select("qid", "qvec", *[F.col("limits")[k].alias(f"limit_{k}") for k in ks or ()]).toArrow().sort_by("qid")
        if rows.num_rows:
            limits = {k: rows.column(f"limit_{k}").to_numpy() for k in ks or ()}  # NaN: no vector is near
            out.append(queries.sparkSession.sparkContext.broadcast((rows.column("qid").to_numpy(), vectors_of(rows.column("qvec").combine_chunks(), dim), limits)))
    return out


def builds(corpus: DataFrame, methods: list[Method], shards: int = 1) -> DataFrame:
    """The builds of ``run`` alone: nothing is searched."""
    none = corpus.sparkSession.createDataFrame([], "qid bigint, qvec array<float>")
    return _runs(materialise(corpus, "corpus"), none, None, methods, [], shards, False)[1]


def _run_method(raw: DataFrame, sent: list[Broadcast], ks: list[int] | None, method: Method, settings: list[tuple[int, int]], exclude_self: bool) -> DataFrame:
    """One method over all shards, each built once for all blocks of queries; a build has a row of its own."""
    dim = method.params.dim
    shape = RUN if ks is None else COUNTS
    both = shape + ", " + BUILT.removeprefix("method string, ")
    kinds = {"string": "object", "int": "Int32", "bigint": "Int64", "double": "float64"}

    def batch(rows: pd.DataFrame) -> pa.RecordBatch:
        columns = [c.split() for c in both.split(", ")]
        return pa.RecordBatch.from_pandas(rows.reindex(columns=[c for c, _ in columns]).astype({c: kinds[t] for c, t in columns}), preserve_index=False)

    def work(shard: int, parts: list[dict]):
        ids, x = raw_vectors(parts, dim)
        parts.clear()
        with Peak() as build_peak:
            began = time.perf_counter()
            made = make(method, ids, x)
            seconds = time.perf_counter() - began
        row = built_row(method, made, seconds, len(ids)) | {"method": method.name, "shard": shard, "build_peak": build_peak.bytes}
        del x
        peaks, warm = [], False
        for qid, q, limits in each_sent(sent):
            if not warm:
                warm = made.search(q[:8], 8, 16) is not None
            with Peak() as search_peak:
                searches = zip(settings, _searches(made, q, settings, exclude_self))
                found = [_answers(method, made, qid, search, limits.get(k), k, ef, exclude_self) for (k, ef), search in searches]
            peaks.append(search_peak.bytes)
            for rows in found:
                if len(rows):
                    yield batch(rows)
        row["search_peak"] = None if None in peaks else max(peaks, default=0)
        yield batch(pd.DataFrame([row]))

    return on_shards(raw, work, both)


def summary(counts: DataFrame, limits: DataFrame) -> DataFrame:
    """(method, k, ef, queries, recall, qps and mean counters) of each run; ``limits`` holds every k."""
    by = ["method", "k", "ef"]
    one = materialise(counts.groupBy(*by, "qid").agg(*[F.sum(c).alias(c) for c in ("good", *COUNTED)]), "counts")
    groups = one.select(*by).distinct().join(limits.select("k", "qid", "want"), "k").join(one.select(*by, "qid", "good"), [*by, "qid"], "left")
    recall = groups.groupBy(*by).agg(F.avg(F.least(F.coalesce("good", F.lit(0)), "want") / F.col("want")).alias("recall"))
    speed = one.groupBy(*by).agg((1 / F.avg("search_s")).alias("qps"))
    return recall.join(M.cost_report(one, by), by).join(speed, by).withColumn("queries", F.lit(limits.select("qid").distinct().count()))


def curve(
    spark: SparkSession, corpus: DataFrame, queries: DataFrame, methods: list[Method], k: int, efs: list, metric: str = "l2", shards: int = 1, exclude_self: bool = False, stored: bool = False
) -> tuple[DataFrame, DataFrame]:
    """(runs, builds): the throughput-recall runs of all methods over a corpus of more than k vectors; ``efs`` are widths, or pairs (k, width). ``stored``: both tables are files already."""
    if not stored:
        corpus, queries = materialise(corpus, "corpus"), materialise(queries, "queries")
    settings = [e if isinstance(e, tuple) else (k, e) for e in efs]
    most = max(k for k, _ in settings)
    if most + exclude_self > (n := corpus.count()):
        raise ValueError(f"{most} neighbours are asked for among {n} vectors")
    limits = kth_distances(corpus, queries, [k for k, _ in settings], metric, exclude_self)
    if metric == "cosine":  # the methods report Euclidean distances of unit vectors
        limits = limits.withColumn("limit", F.sqrt(2 * F.greatest("limit", F.lit(0.0))))
    limits = materialise(limits, "limits")
    counts, builds = counted(corpus, queries, limits, methods, settings, shards, exclude_self)
    return summary(counts, limits), builds


def together(spark: SparkSession, runs: list[Callable[[], object]]) -> list:
    """What independent runs give, in their order; cores that one run's last builds leave idle are taken by the next."""
    ship(spark)
    with ThreadPoolExecutor(AT_ONCE) as pool:
        return list(pool.map(lambda run: run(), runs))


def with_name(methods: list[Method], **changes) -> list[Method]:
    return [replace(m, params=m.params.but(**changes)) for m in methods]
