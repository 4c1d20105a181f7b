"""The sharded index: graphs as files of array blobs, built, searched and extended by Spark.

A corpus is cut into shards of bounded size in bytes; each shard is a graph of its
own that one task builds (``kernel``). A shard is a file: a few rows, each with
the arrays of a range of nodes, in one row group, so that one task reads it whole.
A search sends every query to the shards it probes: the queries go to the files
(in blocks of a checked size), no row of the index is exchanged, and files of
shards that nobody probes are not read. Answers are merged by (distance, id).

An insertion routes the new vectors and rewrites the shards they go to; the other
shards stay where they are. A version of the index is a manifest that names the
generation of every shard; generations are never changed, so readers of an older
version are not disturbed.

Shards: with more than one, vectors go to the nearest of the coarse centroids
(k-means on a bounded sample); a cell over the size limit is dealt into several
shards by a hash of the vector, so that copies meet.
"""

from __future__ import annotations

import json
import time
import zlib
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field, replace
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from ..params import Params
from ..sources.session import materialise, shared_folder, ship
from .kernel import COUNTERS, ORIGINS, Graph, build

#: Arrays of a range of nodes as bytes; what belongs to the whole graph stands in a shard's first part.
_ARRAYS = ("ids", "x", "degree", "adj", "length", "own", "shift", "codes", "origin", "entries", "copy_at", "copy_id", "pending")
PARTS = "part int, n int, " + ", ".join(f"{c} binary" for c in _ARRAYS) + ", layers array<struct<places:binary,degree:binary,adj:binary>>, shard int"
RAW = "part int, ids binary, x binary, shard int"
HIT = "qid bigint, vec_id bigint, dist double, " + ", ".join(f"{c} bigint" for c in COUNTERS) + ", search_s double"
NODE = (
    "shard int, place int, vec_id bigint, vector binary, adj array<int>, edge_len array<float>, cos_own array<float>, "
    "proj_src array<float>, codes binary, origin array<tinyint>, copies array<bigint>, entry boolean"
)
EDGE = "shard int, src bigint, dst bigint, edge_len float, cos_own float, proj_src float, origin string"
#: Vectors read for each coarse centroid, the fewest read in all, and the most centroids; beyond, cells are dealt by a hash.
SAMPLE_EACH, SAMPLE_LEAST, MOST_CELLS = 32, 20_000, 1024
#: Numbers of vectors (rows x dimension) that are sent to every task at once, and how often the index is read for queries before they are shuffled to it.
SENT_FLOATS, MOST_READS = 20_000_000, 8
#: Bytes of doubles that k-means works on at once.
MEANS_BYTES = 16 << 20
#: Bytes of vectors in one part of a shard.
PART_BYTES = 8 << 20
#: Generations after which the changed shards are written together.
MOST_GENERATIONS = 8
#: A shard's file is one row group, whatever its size.
_ONE_GROUP = {"parquet.block.size": str(1 << 30), "parquet.enable.dictionary": "false", "compression": "none"}
#: Vectors of texts are mostly zeros: raw shards, which every method reads, are a fraction of their size.
_RAW_GROUP = _ONE_GROUP | {"compression": "zstd"}


# --- graphs as blobs ------------------------------------------------------------------


def _schema(ddl: str) -> pa.Schema:
    kinds = {"int": pa.int32(), "bigint": pa.int64(), "binary": pa.binary(), "double": pa.float64(), "float": pa.float32(), "string": pa.string(), "boolean": pa.bool_()}
    kinds |= {"array<int>": pa.list_(pa.int32()), "array<float>": pa.list_(pa.float32()), "array<bigint>": pa.list_(pa.int64()), "array<tinyint>": pa.list_(pa.int8())}
    kinds["array<struct<places:binary,degree:binary,adj:binary>>"] = pa.list_(pa.struct([(c, pa.binary()) for c in ("places", "degree", "adj")]))
    cut = []
    for part in ddl.split(", "):
        name, kind = part.split(" ", 1)
        cut.append((name, kinds[kind]))
    return pa.schema(cut)


_PARTS, _RAW, _HIT, _NODE, _EDGE = map(_schema, (PARTS, RAW, HIT, NODE, EDGE))


def _ranges(n: int, width: int) -> list[tuple[int, int]]:
    step = max(1, PART_BYTES // max(1, width))
    return [(i, min(n, i + step)) for i in range(0, n, step)] or [(0, 0)]


def to_parts(graph: Graph, shard: int) -> Iterator[pa.RecordBatch]:
    """The rows of a shard's file, one batch each."""
    kind = np.float16 if graph.params.half else np.float32
    for part, (i, j) in enumerate(_ranges(graph.size, 4 * graph.x.shape[1])):
        edges = graph.adj[i:j] >= 0
        row: dict = {"shard": shard, "part": part, "n": j - i, "ids": graph.ids[i:j], "x": graph.x[i:j].astype(kind), "degree": graph.degree[i:j]}
        row |= {c: getattr(graph, c)[i:j][edges] for c in ("adj", "length", "own", "shift", "codes", "origin")}
        if part == 0:
            row["entries"] = np.array(graph.entries, dtype=np.int32)
            row["copy_at"] = np.repeat(np.array(list(graph.copies), dtype=np.int32), [len(v) for v in graph.copies.values()])
            row["copy_id"] = np.array([v for own in graph.copies.values() for v in own], dtype=np.int64)
            row["pending"] = np.concatenate([np.zeros((0, 3)), *[np.column_stack(p) for p in graph.pending]])
            row["layers"] = [
                {"places": l.places.astype(np.int32).tobytes(), "degree": l.degree[: l.size].tobytes(), "adj": l.adj[: l.size][l.adj[: l.size] >= 0].tobytes()} for l in graph.upper
            ]
        blob = {c: [v.tobytes() if isinstance(v, np.ndarray) else v] for c, v in row.items()}
        yield pa.RecordBatch.from_arrays([pa.array(blob.get(f.name, [None]), type=f.type) for f in _PARTS], schema=_PARTS)


def from_parts(parts: list[dict], params: Params) -> Graph:
    """The graph of a shard's rows."""
    parts = sorted(parts, key=lambda r: r["part"])
    graph, n = Graph(params), sum(r["n"] for r in parts)
    graph._room(n)
    graph.size = n
    if n == 0:
        return graph
    read = lambda c, kind: np.frombuffer(b"".join(r[c] for r in parts), dtype=kind)
    graph.ids[:n] = read("ids", np.int64)
    graph.x[:n] = read("x", np.float16 if params.half else np.float32).reshape(n, -1)
    degree = graph.degree[:n] = read("degree", np.int32)
    there = np.arange(params.cap) < degree[:, None]
    for c, kind in (("adj", np.int32), ("length", np.float32), ("own", np.float32), ("shift", np.float32), ("origin", np.uint8)):
        getattr(graph, c)[:n][there] = read(c, kind)
    graph.codes[:n][there] = read("codes", np.uint8).reshape(-1, params.blocks)
    first = parts[0]
    graph.entries, graph.entries_at = np.frombuffer(first["entries"], dtype=np.int32).tolist(), n
    for at, vec_id in zip(np.frombuffer(first["copy_at"], dtype=np.int32).tolist(), np.frombuffer(first["copy_id"], dtype=np.int64).tolist()):
        graph.copies.setdefault(at, []).append(vec_id)
    pending = np.frombuffer(first["pending"]).reshape(-1, 3)
    if len(pending):
        graph.pending = [(pending[:, 0].astype(np.int64), pending[:, 1].astype(np.int64), pending[:, 2])]
    flat = params.but(layers=False, gate=False, rings=False, screen=False, m_links=max(2, params.m_links // 2))
    for level in first["layers"] or ():
        places = np.frombuffer(level["places"], dtype=np.int32).astype(np.int64)
        layer = Graph(flat, places=places)
        layer._room(len(places))
        layer.size = len(places)
        layer.x[: layer.size], layer.ids[: layer.size] = graph.x[places], graph.ids[places]
        degree = layer.degree[: layer.size] = np.frombuffer(level["degree"], dtype=np.int32)
        layer.adj[: layer.size][np.arange(flat.cap) < degree[:, None]] = np.frombuffer(level["adj"], dtype=np.int32)
        layer._choose_entries()
        graph.upper.append(layer)
    return graph


def shards_of(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, list[dict]]]:
    """(shard, its rows) one after the other; the rows of a shard stand together in its file."""
    shard, rows = None, []
    for batch in batches:
        for row in batch.to_pylist():
            if rows and row["shard"] != shard:
                yield shard, rows
                rows = []
            shard = row["shard"]
            rows.append(row)
    batch = row = None  # noqa: F841  what a shard's work lets go of is not held here
    if rows:
        yield shard, rows


def on_shards(blobs: DataFrame, work: Callable[[int, list[dict]], Iterator[pa.RecordBatch]], ddl: str) -> DataFrame:
    """``work(shard, rows)`` on every shard, where its file is read: nothing is exchanged."""
    ship(blobs.sparkSession)

    def over(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for shard, rows in shards_of(batches):
            yield from work(shard, rows)

    return blobs.mapInArrow(over, ddl)


def vectors_of(column: pa.Array, dim: int) -> np.ndarray:
    """An Arrow list column as a matrix."""
    return np.asarray(column.flatten(), dtype=np.float32).reshape(len(column), dim)


# --- shards ---------------------------------------------------------------------------


def packed(corpus: DataFrame, dim: int, centroids: np.ndarray | None = None) -> DataFrame:
    """(vec_id, cell, deal, x): vectors as bytes, with the nearest centroid's place and a hash of the vector."""
    ship(corpus.sparkSession)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                x = vectors_of(b.column(1), dim) + np.float32(0)  # one zero
                cell = np.zeros(len(x), dtype=np.int32) if centroids is None else nearest_cells(x, centroids, 1)[:, 0].astype(np.int32)
                whole = pa.py_buffer(x)
                ends = pa.py_buffer(np.arange(len(x) + 1, dtype=np.int32) * (4 * dim))
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array(cell), pa.array(dealt(x)), pa.Array.from_buffers(pa.binary(), len(x), [None, ends, whole])], ["vec_id", "cell", "deal", "x"])

    return corpus.select("vec_id", "embedding").mapInArrow(work, "vec_id bigint, cell int, deal bigint, x binary")


def dealt(x: np.ndarray) -> np.ndarray:
    """A hash of each vector: copies go to one shard, where they share a node."""
    return np.array([zlib.crc32(row) for row in np.ascontiguousarray(x, dtype=np.float32) + np.float32(0)], dtype=np.int64)


def nearest_cells(x: np.ndarray, centroids: np.ndarray, k: int) -> np.ndarray:
    """Places of the k nearest centroids of each vector, nearest first."""
    out = np.empty((len(x), k), dtype=np.int64)
    norms = (centroids**2).sum(axis=1)
    for i in range(0, len(x), 256):
        d = norms - 2 * x[i : i + 256] @ centroids.T
        out[i : i + 256] = d.argmin(axis=1)[:, None] if k == 1 else d.argsort(axis=1, kind="stable")[:, :k]
    return out


def assign_shards(corpus: DataFrame, params: Params, shards: int = 1) -> tuple[DataFrame, np.ndarray]:
    """(vec_id, x, shard) of ``corpus(vec_id, embedding)``, and the centroid of each shard; ``shards`` asks for more than the size needs."""
    spark = corpus.sparkSession
    n = corpus.count()
    wanted = max(1, shards, -(-n // params.per_shard))
    cells = min(wanted, MOST_CELLS, max(1, n // 2))
    if cells == 1:
        limit = -(-n // wanted) if wanted > 1 else n
        centroids = np.zeros((1, params.dim), dtype=np.float32)
        placed = packed(corpus, params.dim)
        sizes = {0: n}
    else:
        limit = max(params.per_shard, 1) if shards == 1 else min(params.per_shard, -(-2 * n // wanted))
        sample = max(SAMPLE_LEAST, SAMPLE_EACH * cells)
        share = max(1, n // sample)
        centroids = _means(corpus.where(F.pmod(F.xxhash64(F.lit(params.seed), "vec_id"), F.lit(share)) == 0).select("vec_id", "embedding").limit(2 * sample), cells, params)
        placed = materialise(packed(corpus, params.dim, centroids), "cells")
        sizes = {r.cell: r["count"] for r in placed.groupBy("cell").count().collect()}  # one row a cell
    first, at, of = {}, 0, []
    for cell in sorted(sizes):
        parts = max(1, -(-sizes[cell] // max(1, limit)))
        first[cell] = (at, parts)
        of += [cell] * parts
        at += parts
    if at <= 1:
        return placed.select("vec_id", "x", F.lit(0).alias("shard")), centroids[of or [0]]
    table = spark.createDataFrame([(c, a, k) for c, (a, k) in first.items()], "cell int, base int, parts int")
    out = placed.join(F.broadcast(table), "cell")  # a row a cell
    return out.select("vec_id", "x", (F.col("base") + F.pmod("deal", F.col("parts"))).cast("int").alias("shard")), centroids[of]


def _means(sample: DataFrame, cells: int, params: Params) -> np.ndarray:
    """The centroids of a sample, by one task: the driver gets no vector of the sample."""
    ship(sample.sparkSession)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        x = np.concatenate([np.zeros((0, params.dim), dtype=np.float32), *[vectors_of(b.column(1), params.dim) for b in batches]])
        if len(x):
            if params.metric == "cosine":
                x /= np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-12)
            yield pa.RecordBatch.from_arrays([pa.array([kmeans(x, cells, params.seed).tobytes()])], ["x"])

    found = sample.coalesce(1).sortWithinPartitions("vec_id").mapInArrow(work, "x binary").first()
    return np.frombuffer(found.x if found else b"", dtype=np.float32).reshape(-1, params.dim)


def kmeans(x: np.ndarray, k: int, seed: int, rounds: int = 8) -> np.ndarray:
    """Lloyd's k-means on a sample in memory; an empty cell takes the worst served point."""
    rng = np.random.default_rng(seed)
    c = x[rng.choice(len(x), size=min(k, len(x)), replace=False)].astype(np.float64)
    own, least = np.empty(len(x), dtype=np.int64), np.empty(len(x))
    step = max(1024, MEANS_BYTES // (8 * max(1, x.shape[1], len(c))))
    for _ in range(rounds):
        for i in range(0, len(x), step):
            d = (c**2).sum(1) - 2 * x[i : i + step] @ c.T
            own[i : i + step], least[i : i + step] = d.argmin(axis=1), d.min(axis=1)
        for j in range(len(c)):
            mine = x[own == j]
            c[j] = mine.mean(axis=0) if len(mine) else x[least.argmax()]
    return c.astype(np.float32)


def raw_shards(corpus: DataFrame, params: Params, shards: int = 1) -> tuple[DataFrame, np.ndarray]:
    """The vectors of each shard as blobs in a file of its own (``RAW``), and the centroids."""
    spark = corpus.sparkSession
    placed, centroids = assign_shards(corpus, params, shards)

    step = max(1, PART_BYTES // (4 * params.dim))

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shard, part, held, n = None, 0, [], 0  # n rows of a part are held

        def out() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array([v], type=f.type) for v, f in zip((part, b"".join(i for i, _ in held), b"".join(x for _, x in held), shard), _RAW)], schema=_RAW)

        for b in batches:
            ids, of, at = b.column(0).to_numpy(), b.column(2).to_numpy(), 0
            while at < len(of):
                if of[at] != shard:
                    if held:
                        yield out()
                    shard, part, held, n = int(of[at]), 0, [], 0
                to = min(int(np.searchsorted(of, shard, side="right")), at + step - n)
                held.append((ids[at:to].tobytes(), b"".join(b.column(1).slice(at, to - at).to_pylist())))
                at, n = to, n + to - at
                if n == step:
                    yield out()
                    part, held, n = part + 1, [], 0
        if held:
            yield out()

    path = shared_folder(spark, "raw")
    # A shard's rows come in order to one task, which holds a part of them at a time.
    rows = placed.select("vec_id", "x", "shard").repartition("shard").sortWithinPartitions("shard", "vec_id")
    rows.mapInArrow(work, RAW).write.options(**_RAW_GROUP).partitionBy("shard").parquet(path)
    return spark.read.schema(RAW).parquet(path), centroids


def raw_vectors(rows: list[dict], dim: int) -> tuple[np.ndarray, np.ndarray]:
    """(ids, vectors) of a raw shard's rows."""
    rows = sorted(rows, key=lambda r: r["part"])
    return np.frombuffer(b"".join(r["ids"] for r in rows), dtype=np.int64), np.frombuffer(b"".join(r["x"] for r in rows), dtype=np.float32).reshape(-1, dim)


# --- the index ------------------------------------------------------------------------


@dataclass
class Index:
    """A built index: its parameters, the centroids of its shards, and the generations that hold them."""

    spark: SparkSession
    params: Params
    centroids: np.ndarray
    #: (folder, the shards it holds; None: all that no later generation holds)
    generations: list[tuple[str, list[int] | None]]
    path: str | None = None
    _cells: np.ndarray | None = field(default=None, repr=False)

    @property
    def shards(self) -> int:
        return len(self.centroids)

    @property
    def cells(self) -> np.ndarray:
        """The number of each shard's cell; shards that a hash deals share one."""
        if self._cells is None:
            self._cells = np.unique(self.centroids, axis=0, return_inverse=True)[1].ravel()
        return self._cells

    def blobs(self, shards: list[int] | None = None) -> DataFrame:
        """The rows (``PARTS``) of all shards, or of some: files of others are not read."""
        taken: set[int] = set()
        parts = []
        for folder, held in reversed(self.generations):
            rows = self.spark.read.schema(PARTS).parquet(folder)
            if held is None:
                mine = rows.where(~F.col("shard").isin(sorted(taken))) if taken else rows
                parts.append(mine if shards is None else mine.where(F.col("shard").isin(shards)))
            else:
                live = [s for s in held if s not in taken and (shards is None or s in set(shards))]
                taken.update(held)
                if live:
                    parts.append(rows.where(F.col("shard").isin(live)))
        out = parts[0]
        for p in parts[1:]:
            out = out.unionByName(p)
        return out

    # --- views ---------------------------------------------------------------------

    @property
    def rows(self) -> DataFrame:
        """A row for each node (``NODE``)."""
        params = self.params

        def work(shard: int, parts: list[dict]) -> Iterator[pa.RecordBatch]:
            g = from_parts(parts, params)
            n, entries = g.size, set(g.entries)
            each = lambda a: [a[i, : g.degree[i]] for i in range(n)]
            kind = np.float16 if params.half else np.float32
            columns = [
                np.full(n, shard), np.arange(n), g.ids[:n], [v.tobytes() for v in g.x[:n].astype(kind)], each(g.adj), each(g.length), each(g.own), each(g.shift),
                [c.tobytes() for c in each(g.codes)], [o.astype(np.int8) for o in each(g.origin)], [g.copies.get(i, []) for i in range(n)], [i in entries for i in range(n)],
            ]
            yield pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(columns, _NODE)], schema=_NODE)

        return on_shards(self.blobs(), work, NODE)

    def nodes(self) -> DataFrame:
        return self.rows.select("shard", "place", "vec_id", "vector", "entry")

    def edges(self) -> DataFrame:
        """(shard, src, dst, edge_len, cos_own, proj_src, origin) by vector id."""
        params = self.params

        def work(shard: int, parts: list[dict]) -> Iterator[pa.RecordBatch]:
            g = from_parts(parts, params)
            source, target, length, origin = g.edges()
            there = g.adj[: g.size] >= 0
            columns = [np.full(len(source), shard), g.ids[source], g.ids[target], length, g.own[: g.size][there], g.shift[: g.size][there], np.array(ORIGINS)[origin]]
            yield pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(columns, _EDGE)], schema=_EDGE)

        return on_shards(self.blobs(), work, EDGE)

    def copies(self) -> DataFrame:
        """(rep_id, vec_id): exact copies and the node that stands for them."""
        return self.rows.select(F.col("vec_id").alias("rep_id"), F.explode("copies").alias("vec_id"))

    def members(self) -> DataFrame:
        """(rep_id, vec_id): every vector and the node that stands for it, itself for a node; of the shards only names are read."""

        def work(shard: int, parts: list[dict]) -> Iterator[pa.RecordBatch]:
            parts = sorted(parts, key=lambda r: r["part"])
            ids = np.frombuffer(b"".join(r["ids"] for r in parts), dtype=np.int64)
            at, copy = np.frombuffer(parts[0]["copy_at"] or b"", dtype=np.int32), np.frombuffer(parts[0]["copy_id"] or b"", dtype=np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([ids, ids[at]])), pa.array(np.concatenate([ids, copy]))], ["rep_id", "vec_id"])

        return on_shards(self.blobs().select("shard", "part", "ids", "copy_at", "copy_id"), work, "rep_id bigint, vec_id bigint")

    def pending(self) -> DataFrame:
        """(shard, pivot, target, stat): screened edges that wait for their verification."""
        params = self.params

        def work(shard: int, parts: list[dict]) -> Iterator[pa.RecordBatch]:
            g = from_parts(parts, params)
            for pivot, node, stat in g.pending:
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(pivot), shard, dtype=np.int32)), pa.array(g.ids[pivot]), pa.array(g.ids[node]), pa.array(stat.astype(np.float64))], ["shard", "pivot", "target", "stat"])

        return on_shards(self.blobs(), work, "shard int, pivot bigint, target bigint, stat double")

    def size_report(self) -> DataFrame:
        """(part, bytes) of the index, from the lengths of its arrays."""
        total = lambda *cs: F.coalesce(sum((F.sum(F.coalesce(F.octet_length(c), F.lit(0))) for c in cs), F.lit(0)), F.lit(0)).cast("bigint")
        p = self.params
        tested = ("length", "own", "shift", "codes") if p.gate or p.screen else ()
        upper = F.aggregate(F.coalesce("layers", F.array()), F.lit(0), lambda s, l: s + (F.octet_length(l["degree"]) + F.octet_length(l["adj"]) + F.octet_length(l["places"])).cast("int"))
        one = self.blobs().agg(
            total("x").alias("vectors"),
            (total("adj", "degree") + F.coalesce(F.sum(upper), F.lit(0))).alias("edges"),
            (total(*tested) if tested else F.lit(0).cast("bigint")).alias("projection"),
            total("ids", "origin", "copy_at", "copy_id", "entries").alias("names"),
            total("pending").alias("pending"),
        )
        return one.unpivot([], ["vectors", "edges", "projection", "names", "pending"], "part", "bytes")

    def manifest(self) -> dict:
        return {"format_version": 2, "params": self.params.as_dict(), "shards": self.shards, "generations": self.generations, "centroids": self.centroids.tolist()}

    # --- searching -----------------------------------------------------------------

    def search(
        self, queries: DataFrame, k: int, ef: int, probes: int | None = None, timed: bool = False, within: float | None = None, with_copies: bool = True, **options
    ) -> DataFrame:
        """(qid, rank, vec_id, dist and the counters): the k nearest found for each ``queries(qid, qvec)``; ``timed`` adds the query's share of the tasks' seconds.

        ``within`` leaves answers farther away out before they are exchanged, and
        without ``with_copies`` a node answers for its copies (``members``).
        """
        params = self.params
        options = {"within": within, "own_copies": with_copies} | options
        reads = max(1, -(-queries.count() * params.dim // SENT_FLOATS))
        blocks = [queries] if reads == 1 else [queries.where(F.pmod(F.xxhash64("qid"), F.lit(reads)) == i) for i in range(reads)]
        if reads <= MOST_READS:
            return _ranked(reduce(DataFrame.unionByName, [self._search_in_place(b, k, ef, probes, options)[0] for b in blocks]), k, timed, within)
        if probes is not None and probes < self.shards:
            return _ranked(self._search_shuffled(queries, k, ef, probes, options), k, timed, within)
        # Every query meets every shard: a shuffle would write each as often as there are shards. Block after block is
        # sent, answered and forgotten.
        parts = []
        for block in blocks:
            found, sent = self._search_in_place(block, k, ef, probes, options)
            parts.append(materialise(_ranked(found, k, timed, within), "hits"))
            sent.destroy()
        return reduce(DataFrame.unionByName, parts)

    def _search_in_place(self, block: DataFrame, k: int, ef: int, probes: int | None, options: dict) -> tuple[DataFrame, Broadcast]:
        """A block of queries of checked size goes to the files of the shards that it probes; the answers, and what was sent."""
        params = self.params
        rows = block.select("qid", "qvec").toArrow()
        qid, q = rows.column("qid").to_numpy(), vectors_of(rows.column("qvec").combine_chunks(), params.dim)
        asked = self.probed(q, probes)
        wanted = {s: np.flatnonzero((asked == s).any(axis=1)) for s in np.unique(asked).tolist()} if probes and probes < self.shards else None
        sent = self.spark.sparkContext.broadcast((qid, q, wanted))

        def work(shard: int, parts: list[dict]) -> Iterator[pa.RecordBatch]:
            qid, q, wanted = sent.value
            mine = slice(None) if wanted is None else wanted[shard]
            yield answers(from_parts(parts, params), qid[mine], q[mine], k, ef, options)

        return on_shards(self.blobs(None if wanted is None else sorted(wanted)), work, HIT), sent

    def _search_shuffled(self, queries: DataFrame, k: int, ef: int, probes: int | None, options: dict) -> DataFrame:
        """Queries without a bound are shuffled to the shards, and the blobs with them."""
        params = self.params
        ship(self.spark)

        def work(key: tuple[pa.Scalar, ...], parts: pa.Table, asked: pa.Table) -> pa.Table:
            graph = from_parts(parts.to_pylist(), params)
            hits = [
                answers(graph, b.column("qid").to_numpy(), vectors_of(b.column("qvec"), params.dim), k, ef, options) for b in asked.to_batches(max_chunksize=4096) if b.num_rows
            ]
            return pa.Table.from_batches(hits, schema=_HIT)

        return self.blobs().groupBy("shard").cogroup(self.route(queries, probes).groupBy("shard")).applyInArrow(work, HIT)

    def probed(self, q: np.ndarray, probes: int | None) -> np.ndarray:
        """Places of the shards that each vector probes (all if not said)."""
        if probes is None or probes >= self.shards:
            return np.tile(np.arange(self.shards), (len(q), 1))
        return nearest_cells(self._unit(q), self.centroids, probes)

    def _unit(self, x: np.ndarray) -> np.ndarray:
        return x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-12) if self.params.metric == "cosine" else x

    def home(self, ids: np.ndarray, x: np.ndarray) -> np.ndarray:
        """The shard that each new vector goes to: of the nearest cell's shards, by a hash of the vector."""
        near = self.cells[nearest_cells(self._unit(x), self.centroids, 1)[:, 0]]
        members = [np.flatnonzero(self.cells == c) for c in range(int(self.cells.max()) + 1)]
        return np.array([members[c][h % len(members[c])] for c, h in zip(near.tolist(), dealt(x).tolist())], dtype=np.int64)

    def route(self, queries: DataFrame, probes: int | None = None) -> DataFrame:
        """(shard, qid, qvec): each query once for each shard it probes."""
        if probes is None or probes >= self.shards:
            return queries.select(F.explode(F.sequence(F.lit(0), F.lit(self.shards - 1))).alias("shard"), "qid", "qvec")
        ship(self.spark)
        me, dim = replace(self, spark=None), self.params.dim

        def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                if b.num_rows:
                    near = me.probed(vectors_of(b.column(1), dim), probes)
                    at = pa.array(np.repeat(np.arange(b.num_rows), probes))
                    yield pa.RecordBatch.from_arrays([pa.array(near.ravel().astype(np.int32)), b.column(0).take(at), b.column(1).take(at)], ["shard", "qid", "qvec"])

        return queries.select("qid", "qvec").mapInArrow(work, "shard int, qid bigint, qvec array<float>")

    # --- files ---------------------------------------------------------------------

    def write(self, rows: DataFrame) -> str:
        """A new generation: the rows of whole shards, a file each."""
        folder = shared_folder(self.spark, "generation")
        rows.write.options(**_ONE_GROUP).partitionBy("shard").parquet(folder)
        return folder

    def save(self, path: str | None = None) -> Index:
        """Write the manifest, which comes last, so that a reader never sees a part."""
        self.path = path or shared_folder(self.spark, "index")
        self.spark.createDataFrame([(json.dumps(self.manifest()),)], "manifest string").coalesce(1).write.text(f"{self.path}/manifest")
        return self

    @staticmethod
    def open(spark: SparkSession, path: str) -> Index:
        note = json.loads(spark.read.text(f"{path}/manifest").first()[0])
        if note["format_version"] != 2:
            raise ValueError(f"index format {note['format_version']} is not known")
        return Index(spark, Params(**note["params"]), np.array(note["centroids"], dtype=np.float32), [(f, s) for f, s in note["generations"]], path)

    def compacted(self) -> Index:
        """The same index with all changed shards in one generation; blobs are copied as they are."""
        changed = sorted({s for _, held in self.generations[1:] for s in held})
        if len(self.generations) < 3:
            return self
        # A shard's rows stand together in a partition and stay so: nothing is exchanged.
        folder = self.write(self.blobs(changed))
        return replace(self, generations=[self.generations[0], (folder, changed)], path=None)


def _ranked(found: DataFrame, k: int, timed: bool, within: float | None) -> DataFrame:
    """The k nearest of all shards' answers to each query, with the sums of their counters."""
    order = Window.partitionBy("qid").orderBy("dist", "vec_id")
    over = Window.partitionBy("qid")
    told = [*COUNTERS, *["search_s"] * timed]
    totals = [F.sum(c).over(over).alias(c) for c in told]  # each shard reports its counters on one row
    ranked = found.select("qid", "vec_id", "dist", *totals, F.row_number().over(order).alias("rank"))
    best = F.col("rank") <= k
    return ranked.where(best if within is None else best & (F.col("dist") <= within)).select("qid", "rank", "vec_id", "dist", *told)


def answers(graph: Graph, qid: np.ndarray, q: np.ndarray, k: int, ef: int, options: dict) -> pa.RecordBatch:
    """Answers of one shard; copies of a node are answers too, the k least ids of them."""
    if not len(qid) or graph.size == 0:
        return pa.RecordBatch.from_arrays([pa.array([], type=f.type) for f in _HIT], schema=_HIT)
    options = dict(options)
    within, own_copies = options.pop("within", None), options.pop("own_copies", True)
    began = time.perf_counter()
    found = graph.search(q, k, ef, **options)
    seconds = (time.perf_counter() - began) / len(qid)
    row, ids, dist = with_copies(found.ids, found.dist, graph.ids, graph.copies if own_copies else {}, k)
    first = np.zeros(len(row), dtype=bool)
    first[np.unique(row, return_index=True)[1]] = True
    if within is not None:
        near = first | (dist <= within)  # a query's first row has its counters
        row, ids, dist, first = row[near], ids[near], dist[near], first[near]
    counters = [np.where(first, found.counters[c][row], 0) for c in COUNTERS]
    return pa.RecordBatch.from_arrays([pa.array(v, type=f.type) for v, f in zip([qid[row], ids, dist, *counters, np.where(first, seconds, 0.0)], _HIT)], schema=_HIT)


def with_copies(found: np.ndarray, dist: np.ndarray, labels: np.ndarray, copies: dict[int, list[int]], k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, label, distance) of all found places and of the k least copies of each."""
    row, col = np.nonzero(found >= 0)
    at = found[row, col]
    ids, dist = labels[at], dist[row, col].astype(np.float64)
    if copies:
        more = [(i, c) for i, a in enumerate(at.tolist()) if a in copies for c in sorted(copies[a])[:k]]
        if more:
            source = np.array([i for i, _ in more])
            row, dist, ids = np.concatenate([row, row[source]]), np.concatenate([dist, dist[source]]), np.concatenate([ids, np.array([c for _, c in more])])
    return row, ids, dist


def build_index(corpus: DataFrame, params: Params, path: str | None = None, shards: int = 1) -> Index:
    """Build and save the index of ``corpus(vec_id, embedding)``; each shard by one task. ``shards`` asks for more shards than the size needs."""
    spark = corpus.sparkSession
    ship(spark)
    placed, centroids = assign_shards(corpus.select("vec_id", "embedding"), params, shards)

    def work(key: tuple[pa.Scalar, ...], rows: pa.Table) -> pa.Table:
        rows = rows.sort_by("vec_id")
        x = np.frombuffer(b"".join(rows.column("x").to_pylist()), dtype=np.float32).reshape(-1, params.dim)
        return pa.Table.from_batches(to_parts(build(rows.column("vec_id").to_numpy(), x, params), key[0].as_py()), schema=_PARTS)

    index = Index(spark, params, centroids, [])
    index.generations = [(index.write(placed.groupBy("shard").applyInArrow(work, PARTS)), None)]
    return index.save(path)


def insert_batch(index: Index, new: DataFrame, path: str | None = None, verify: bool = True, stats: list | None = None) -> Index:
    """A new version of the index with ``new(vec_id, embedding)``; only shards that get vectors are written again.

    A vector that its shard holds under the same id is left out, so a repeated
    batch changes nothing. Without ``verify`` screened edges wait in the shards.
    ``stats`` receives (shard, vectors, seconds, exact distances) of each insertion.
    """
    params, spark = index.params, index.spark
    ship(spark)
    fresh = new.select("vec_id", "embedding").dropDuplicates(["vec_id"])
    reads = -(-fresh.count() * params.dim // SENT_FLOATS)
    if reads == 0:
        return index
    for i in range(reads):
        part = fresh if reads == 1 else fresh.where(F.pmod(F.xxhash64("vec_id"), F.lit(reads)) == i)
        index = _insert_block(index, part, verify, stats)
    if len(index.generations) > MOST_GENERATIONS:
        index = index.compacted()
    return index.save(path)


def _insert_block(index: Index, part: DataFrame, verify: bool, stats: list | None) -> Index:
    """Vectors of a checked size go to the files of their shards."""
    params, spark = index.params, index.spark
    rows = part.toArrow().sort_by("vec_id")
    ids, x = rows.column("vec_id").to_numpy(), vectors_of(rows.column("embedding").combine_chunks(), params.dim)
    home = index.home(ids, x)
    touched = np.unique(home).tolist()
    sent = spark.sparkContext.broadcast((ids, x, home))
    spent = spark.sparkContext.accumulator([], _Notes()) if stats is not None else None

    def work(shard: int, parts: list[dict]) -> Iterator[pa.RecordBatch]:
        ids, x, home = sent.value
        graph = from_parts(parts, params)
        held = np.isin(ids, np.concatenate([graph.ids[: graph.size], *[np.array(v) for v in graph.copies.values()]]))
        mine = (home == shard) & ~held
        began, paid = time.perf_counter(), graph.exact
        graph.insert(ids[mine], x[mine], verify)
        if spent is not None:
            spent.add([(shard, int(mine.sum()), time.perf_counter() - began, graph.exact - paid)])
        yield from to_parts(graph, shard)

    folder = index.write(on_shards(index.blobs(touched), work, PARTS))
    if stats is not None:
        stats += spent.value
    return replace(index, generations=[*index.generations, (folder, touched)], path=None)


class _Notes:
    """Lists that tasks add to."""

    def zero(self, value: list) -> list:
        return []

    def addInPlace(self, a: list, b: list) -> list:  # noqa: N802  Spark's name
        return a + b
