"""Exact search: the ground truth, and joins by distance.

Two ways with one result. ``plan="sql"`` compares every pair in a nested-loop
join and keeps the k best with a ranking window, which Spark limits within each
partition before it shuffles. ``plan="blocks"`` multiplies blocks of vectors in
the workers and emits k rows for each query and batch. Either needs the
queries on every machine, so their size is checked; more queries are taken in
blocks of their own.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame, Window, functions as F

from ..functions import vectors as V
from ..sources.session import ship

#: Numbers of query vectors (queries x dimension) that every machine may hold at once.
BROADCAST_FLOATS = 20_000_000
#: Bytes of vectors that a task gathers before it compares them, and pairs compared at once.
GATHERED_BYTES, PAIRS = 64 << 20, 2_560_000
#: Bytes of vectors that are measured again at once.
MEASURED_BYTES = 1 << 20
#: Numbers of query vectors that the driver holds at once.
HELD_FLOATS = 4_000_000


def query_blocks(queries: DataFrame, dim: int, most: int | None = None) -> list[DataFrame]:
    """The queries in parts of a bounded size each."""
    parts = -(-queries.count() * dim // (most or BROADCAST_FLOATS)) or 1
    if parts == 1:
        return [queries]
    return [queries.where(F.pmod(F.xxhash64("qid"), F.lit(parts)) == k) for k in range(parts)]


def each_sent(blocks: list[Broadcast]) -> Iterator[tuple]:
    """The values of broadcast blocks one after the other, in a task: it holds one at a time."""
    for sent in blocks:
        yield sent.value
        if sent._path is not None:
            vars(sent).pop("_value", None)  # read again from its file when it is next asked for


def pairs(corpus: DataFrame, queries: DataFrame, dim: int) -> DataFrame:
    """Every vector with every query, which are broadcast in blocks of a checked size."""
    return reduce(DataFrame.unionByName, [corpus.crossJoin(F.broadcast(b)) for b in query_blocks(queries, dim)])


def top_k(pairs: DataFrame, k: int, key: str = "qid") -> DataFrame:
    """The k rows of least (dist, vec_id) of each query, with their rank."""
    order = Window.partitionBy(key).orderBy("dist", "vec_id")
    return pairs.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)


def exact_knn(corpus: DataFrame, queries: DataFrame, k: int, metric: str = "l2", plan: str = "auto", exclude_self: bool = False) -> DataFrame:
    """(qid, rank, vec_id, dist): the k nearest of each query; ``corpus(vec_id, embedding)``, ``queries(qid, qvec)``."""
    first = queries.select(F.size("qvec").alias("d")).first()
    if first is None:
        return corpus.sparkSession.createDataFrame([], "qid bigint, rank int, vec_id bigint, dist double")
    dim = max(1, first.d)
    if plan == "auto":
        plan = "blocks" if dim >= 256 or metric in ("l2", "cosine") and dim >= 64 and not exclude_self else "sql"
    parts = []
    for block in query_blocks(queries, dim):
        if plan == "sql":
            pairs = corpus.join(F.broadcast(block), F.col("vec_id") != F.col("qid") if exclude_self else None, "inner" if exclude_self else "cross")
            parts.append(pairs.select("qid", "vec_id", V.distance("embedding", "qvec", metric).alias("dist")))
        else:
            parts.append(_block_pairs(corpus, block, k, metric, exclude_self))
    return top_k(reduce(DataFrame.unionByName, parts), k).select("qid", "rank", "vec_id", "dist")


def _block_pairs(corpus: DataFrame, block: DataFrame, k: int, metric: str, exclude_self: bool) -> DataFrame:
    """The k best of each batch for each query, by block products and exact re-measurement."""
    if metric not in ("l2", "cosine", "dot"):
        raise ValueError("block products serve l2, cosine and dot")
    ship(corpus.sparkSession)
    rows = block.select("qid", "qvec").toArrow()  # a block of checked size
    qid = rows.column("qid").to_numpy().astype(np.int64)
    q = np.asarray(rows.column("qvec").combine_chunks().flatten(), dtype=np.float64).reshape(len(qid), -1)
    sent = corpus.sparkSession.sparkContext.broadcast((qid, q))

    def work(batches):
        qid, q = sent.value
        for batch in batches:
            if not batch.num_rows or not len(qid):
                continue
            ids = batch.column(0).to_numpy(zero_copy_only=False)
            x = np.asarray(batch.column(1).flatten(), dtype=np.float64).reshape(batch.num_rows, -1)
            yield from _best(ids, x, qid, q, k, metric, exclude_self)

    return corpus.select("vec_id", "embedding").mapInArrow(work, "qid bigint, vec_id bigint, dist double")


def kth_distances(corpus: DataFrame, queries: DataFrame, ks: list[int], metric: str = "l2", exclude_self: bool = False) -> DataFrame:
    """(qid, k, limit, want): the distance of each query's k-th nearest, and how many there are up to it.

    Tasks gather batches and emit one array of their least distances for each
    query, so that no row is made for a pair.
    """
    first = queries.select(F.size("qvec").alias("d")).first()
    if first is None:
        return corpus.sparkSession.createDataFrame([], "qid bigint, k int, limit double, want int")
    most = max(ks)
    least = _least(corpus, query_blocks(queries, max(1, first.d), HELD_FLOATS), most, metric, exclude_self).groupBy("qid").agg(F.slice(F.array_sort(F.flatten(F.collect_list("dists"))), 1, most).alias("dists"))
    each = least.select("qid", "dists", F.explode(F.array(*[F.lit(k) for k in sorted(set(ks))])).alias("k")).withColumn("want", F.least("k", F.size("dists")))
    return each.select("qid", "k", F.element_at("dists", F.col("want")).alias("limit"), "want")


def _sent(block: DataFrame) -> Broadcast:
    """A block of queries of checked size, as every machine gets it; the driver keeps none."""
    rows = block.select("qid", "qvec").toArrow()
    qid = rows.column("qid").to_numpy().astype(np.int64)
    q = np.asarray(rows.column("qvec").combine_chunks().flatten()).reshape(len(qid), -1)
    return block.sparkSession.sparkContext.broadcast((qid, q))


def _least(corpus: DataFrame, blocks: list[DataFrame], k: int, metric: str, exclude_self: bool) -> DataFrame:
    """(qid, dists): the k least distances among what a task has gathered; vectors are read once for all blocks."""
    ship(corpus.sparkSession)
    sent = [_sent(block) for block in blocks]

    def arrays(gathered):
        ids, x = np.concatenate([g[0] for g in gathered]), np.concatenate([g[1] for g in gathered], dtype=np.float64)
        gathered.clear()
        for qid, q in each_sent(sent):
            for found in _best(ids, x, qid, q.astype(np.float64), k, metric, exclude_self) if len(qid) else ():
                own = found.column(0).to_numpy()
                if len(own):
                    begins = np.flatnonzero(np.concatenate([[True], own[1:] != own[:-1]]))
                    ends = pa.array(np.append(begins, len(own)).astype(np.int32))
                    yield pa.RecordBatch.from_arrays([pa.array(own[begins]), pa.ListArray.from_arrays(ends, found.column(2))], ["qid", "dists"])

    def work(batches):
        gathered, size = [], 0
        for batch in batches:
            if not batch.num_rows:
                continue
            gathered.append((batch.column(0).to_numpy(zero_copy_only=False), np.asarray(batch.column(1).flatten()).reshape(batch.num_rows, -1)))
            size += 8 * gathered[-1][1].size
            if size >= GATHERED_BYTES:
                yield from arrays(gathered)
                size = 0
        if gathered:
            yield from arrays(gathered)

    return corpus.select("vec_id", "embedding").mapInArrow(work, "qid bigint, dists array<double>")


def _best(ids, x, qid, q, k, metric, exclude_self):
    take = min(k + 1, len(ids))
    step = max(1, min(256, PAIRS // len(ids)))
    size = np.einsum("nd,nd->n", x, x) if metric == "l2" else np.linalg.norm(x, axis=1) if metric == "cosine" else None
    few = max(1, MEASURED_BYTES // (8 * max(1, x.shape[1])))
    for i in range(0, len(q), step):
        part = q[i : i + step]
        inner = part @ x.T
        if metric == "l2":
            rough = (part**2).sum(1)[:, None] + size[None, :] - 2 * inner
        elif metric == "cosine":
            norms = np.linalg.norm(part, axis=1)[:, None] * size[None, :]
            rough = 1 - inner / np.where(norms > 0, norms, np.nan)
        else:
            rough = -inner
        if exclude_self:
            rough[qid[i : i + step, None] == ids[None, :]] = np.inf
        rough = np.where(np.isnan(rough), np.inf, rough)
        # The k-th value, and all rows within rounding of it: they are measured again, and the k least by (distance, id) stay.
        kth = np.partition(rough, take - 1, axis=1)[:, take - 1]
        r, c = np.nonzero(rough <= kth[:, None] + 1e-9 * (1 + np.abs(kth[:, None])))
        keep = np.isfinite(rough[r, c])
        r, c = r[keep], c[keep]
        if metric == "l2":
            dist = np.concatenate([np.zeros(0), *[np.sqrt(((part[r[j : j + few]] - x[c[j : j + few]]) ** 2).sum(axis=1)) for j in range(0, len(r), few)]])
        else:
            dist = rough[r, c]
        order = np.lexsort((ids[c], dist, r))
        r, c, dist = r[order], c[order], dist[order]
        if len(r):
            begins = np.flatnonzero(np.concatenate([[True], r[1:] != r[:-1]]))
            first = np.arange(len(r)) - np.repeat(begins, np.diff(np.append(begins, len(r)))) < k
            r, c, dist = r[first], c[first], dist[first]
        yield pa.RecordBatch.from_arrays([pa.array(qid[i + r]), pa.array(ids[c]), pa.array(dist)], ["qid", "vec_id", "dist"])


def range_search(corpus: DataFrame, queries: DataFrame, radius: float, metric: str = "l2") -> DataFrame:
    """(qid, vec_id, dist): all vectors within the radius."""
    dim = max(1, (queries.select(F.size("qvec")).first() or [1])[0])
    parts = [
        corpus.crossJoin(F.broadcast(b)).select("qid", "vec_id", V.distance("embedding", "qvec", metric).alias("dist")).where(F.col("dist") <= radius)
        for b in query_blocks(queries, dim)
    ]
    return reduce(DataFrame.unionByName, parts)


def knn_join(left: DataFrame, right: DataFrame, k: int, metric: str = "l2") -> DataFrame:
    """Every row of ``left(qid, qvec)`` with its k nearest rows of ``right(vec_id, embedding)``."""
    return exact_knn(right, left, k, metric)


def filtered_knn(corpus: DataFrame, queries: DataFrame, k: int, allowed: DataFrame, mode: str = "pre", overfetch: int = 4) -> DataFrame:
    """Search among ``allowed(vec_id)``: restrict before, or search for more and drop after (doubling until k are left or all seen)."""
    if mode == "pre":
        return exact_knn(corpus.join(allowed, "vec_id", "left_semi"), queries, k)
    n, wide = corpus.count(), k * overfetch
    while True:
        hits = exact_knn(corpus, queries, min(wide, n)).join(allowed, "vec_id", "left_semi").select("qid", "vec_id", "dist")
        out = top_k(hits, k).select("qid", "rank", "vec_id", "dist")
        if wide >= n or out.groupBy("qid").count().where(F.col("count") < k).isEmpty() and out.select("qid").distinct().count() == queries.count():
            return out
        wide *= 2
