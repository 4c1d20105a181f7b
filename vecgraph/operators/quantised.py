"""Quantisation baselines as tables: cells, codes, a scan of codes, exact reranking.

Codebooks are trained on a bounded sample; every row is encoded by one pass that
moves no vectors. A search reads only cells and codes, keeps the best ``rerank * k``
candidates of each query and partition, and fetches vectors for those alone.

Three codes: product codes of residuals with 16 centroids a part and 8-bit
lookup tables ("pq"); the same with a loss that weighs the error along the vector
("aniso"); and scalar codes of rotated unit residuals with an unbiased inner
product ("scalar").
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from ..functions import vectors as V
from ..sources.session import ship
from .exact import query_blocks, top_k
from .index import kmeans
from .projection import orthogonal

TRAIN_SAMPLE = 20_000
#: Vectors that are worked on in doubles at once.
ROWS = 2048


@dataclass
class Coder:
    """What encodes vectors and estimates distances."""

    kind: str
    centroids: np.ndarray
    parts: int = 8
    bits: int = 4
    eta: float = 4.0
    seed: int = 17
    books: np.ndarray | None = None
    rotation: np.ndarray | None = None
    turned_centroids: np.ndarray | None = None

    def fit(self, x: np.ndarray) -> Coder:
        if self.kind == "scalar":
            self.rotation = orthogonal(x.shape[1], self.seed)
            return self
        blocks = (x[i : i + ROWS].astype(np.float64) for i in range(0, max(1, len(x)), ROWS))
        told = [(self._residual(b)[0], np.linalg.norm(b, axis=1, keepdims=True)) for b in blocks]
        own, norm = (np.concatenate([t[j] for t in told]) for j in (0, 1))
        width, books = -(-x.shape[1] // self.parts), []
        for j in range(self.parts):
            # The columns of one book in doubles; the error along the vector itself is what inner products feel.
            some = slice(j * width, (j + 1) * width)
            piece = x[:, some].astype(np.float64)
            pad = ((0, 0), (0, width - piece.shape[1]))
            books.append(self._book(np.pad(piece - self.centroids[:, some][own], pad), np.pad(piece / np.maximum(norm, 1e-12), pad)))
        self.books = np.stack(books)
        return self

    def _residual(self, x):
        own = ((self.centroids**2).sum(1) - 2 * x @ self.centroids.T).argmin(axis=1)
        return own, x - self.centroids[own]

    def _cut(self, x):
        width = -(-x.shape[1] // self.parts)
        return np.pad(x, ((0, 0), (0, width * self.parts - x.shape[1]))).reshape(len(x), self.parts, width)

    def _weights(self, along):
        n = np.linalg.norm(along, axis=1, keepdims=True)
        return along / np.where(n > 0, n, 1)

    def _loss(self, piece, book, along):
        diff = piece[:, None, :] - book[None]
        loss = (diff**2).sum(axis=2)
        if self.kind == "aniso":
            loss += (self.eta - 1) * np.einsum("nkd,nd->nk", diff, self._weights(along)) ** 2
        return loss

    def _book(self, piece, along):
        book = kmeans(piece.astype(np.float32), 16, self.seed).astype(np.float64)
        if len(book) < 16:
            book = np.vstack([book, np.repeat(book[:1], 16 - len(book), axis=0)])
        if self.kind == "aniso":
            u = self._weights(along)
            for _ in range(4):
                own = self._loss(piece, book, along).argmin(axis=1)
                for k in range(16):
                    mine, w = piece[own == k], u[own == k]
                    if len(mine):
                        a = len(mine) * np.eye(piece.shape[1]) + (self.eta - 1) * w.T @ w
                        book[k] = np.linalg.solve(a, mine.sum(axis=0) + (self.eta - 1) * w.T @ (w * mine).sum(axis=1))
        return book

    def encode(self, x: np.ndarray):
        """(cell, codes uint8, norm, factor) of each vector."""
        parts = [self._encode(x[i : i + ROWS].astype(np.float64)) for i in range(0, max(1, len(x)), ROWS)]
        return tuple(np.concatenate([p[j] for p in parts]) for j in range(4))

    def _encode(self, x: np.ndarray):
        own, residual = self._residual(x)
        n = len(x)
        if self.kind != "scalar":
            pieces, along = self._cut(residual), self._cut(x)
            codes = np.stack([self._loss(pieces[:, j], self.books[j], along[:, j]).argmin(axis=1) for j in range(self.parts)], axis=1).astype(np.uint8)
            return own, codes, np.zeros(n, dtype=np.float32), np.ones(n, dtype=np.float32)
        norm = np.linalg.norm(residual, axis=1)
        unit = (residual / np.where(norm > 0, norm, 1)[:, None]) @ self.rotation
        top = 2**self.bits - 1
        best, codes, factor = np.full(n, -np.inf), np.zeros(unit.shape, dtype=np.uint8), np.ones(n)
        peak = np.maximum(np.abs(unit).max(axis=1), 1e-12)
        for shrink in (1.0, 0.85, 0.7, 0.55, 0.4):  # how much of the range the grid spans
            step = 2 * peak * shrink / (top + 1)
            level = np.clip(np.floor(unit / step[:, None]) + (top + 1) // 2, 0, top)
            grid = level - top / 2
            fit = (grid * unit).sum(axis=1) / np.linalg.norm(grid, axis=1)
            better = fit > best
            best[better], codes[better] = fit[better], level[better].astype(np.uint8)
            factor[better] = ((grid * unit).sum(axis=1))[better]
        return own, codes, norm.astype(np.float32), np.where(factor > 0, factor, 1).astype(np.float32)

    def turn(self, queries: np.ndarray) -> np.ndarray:
        """What ``estimate`` asks of each query beforehand: its turned vector, so that no query is turned again for each cell."""
        return queries @ self.rotation if self.kind == "scalar" else queries

    def estimate(self, query: np.ndarray, cell: int, codes: np.ndarray, norm: np.ndarray, factor: np.ndarray, turned: np.ndarray | None = None) -> np.ndarray:
        """Estimated squared distances of one query to coded rows of one cell; ``turned`` is the query's row of ``turn``."""
        residual = query - self.centroids[cell]
        if self.kind != "scalar":
            piece = self._cut(residual[None])[0]
            table = ((piece[:, None, :] - self.books) ** 2).sum(axis=2)
            # Lookup tables of 8 bits: a shared scale, rounded entries.
            low = table.min(axis=1, keepdims=True)
            unit = max((table - low).max(), 1e-12) / 255
            rounded = np.round((table - low) / unit)
            return rounded[np.arange(self.parts), codes].sum(axis=1) * unit + low.sum()
        if turned is None:
            turned = residual @ self.rotation
        else:
            if self.turned_centroids is None:
                self.turned_centroids = self.centroids @ self.rotation
            turned = turned - self.turned_centroids[cell]
        inner = (codes.astype(np.float32) @ turned - (2**self.bits - 1) / 2 * turned.sum()) / factor
        return norm**2 + (residual**2).sum() - 2 * norm * inner


@dataclass
class QuantisedIndex:
    codes: DataFrame  # vec_id, cell, code, norm, factor
    vectors: DataFrame  # vec_id, embedding
    coder: Coder

    def search(self, queries: DataFrame, k: int, nprobe: int, rerank: int = 8) -> DataFrame:
        """(qid, rank, vec_id, dist, n_checked, n_exact)."""
        dim = self.coder.centroids.shape[1]
        parts = [self._candidates(b, k * rerank, nprobe) for b in query_blocks(queries, dim)]
        near = top_k(reduce(DataFrame.unionByName, parts), k * rerank).drop("rank")
        full = near.join(queries, "qid").join(self.vectors, "vec_id").select("qid", "vec_id", "scanned", V.l2("embedding", "qvec").alias("dist"))
        each = full.withColumn("n_exact", F.count("*").over(_by_query())).withColumn("n_checked", F.max("scanned").over(_by_query()))
        return top_k(each, k).select("qid", "rank", "vec_id", "dist", "n_checked", "n_exact")

    def _candidates(self, block: DataFrame, most: int, nprobe: int) -> DataFrame:
        ship(self.codes.sparkSession)
        rows = block.select("qid", "qvec").collect()  # a block of checked size
        qid, q, coder = [r.qid for r in rows], np.array([r.qvec for r in rows], dtype=np.float64), self.coder
        probes = ((coder.centroids**2).sum(1) - 2 * q @ coder.centroids.T).argsort(axis=1)[:, :nprobe]
        turned = coder.turn(q)
        wanted: dict[int, list[int]] = {}
        for i, cells in enumerate(probes.tolist()):
            for c in cells:
                wanted.setdefault(c, []).append(i)

        def work(batches):
            for pdf in batches:
                found: dict[int, list[tuple[np.ndarray, np.ndarray]]] = {}
                for cell, part in pdf.groupby("cell"):
                    codes = np.frombuffer(b"".join(part["code"]), dtype=np.uint8).reshape(len(part), -1)
                    norm, factor, ids = part["norm"].to_numpy(), part["factor"].to_numpy(), part["vec_id"].to_numpy()
                    for i in wanted.get(int(cell), ()):
                        found.setdefault(i, []).append((ids, coder.estimate(q[i], int(cell), codes, norm, factor, turned[i])))
                out = []
                for i, parts in found.items():
                    ids, est = (np.concatenate([p[j] for p in parts]) for j in (0, 1))
                    best = np.argsort(est, kind="stable")[:most]
                    out.append(pd.DataFrame({"qid": qid[i], "vec_id": ids[best], "dist": est[best], "scanned": len(ids)}))
                if out:
                    yield pd.concat(out)

        # The filter on cells prunes rows before they reach Python.
        probed = sorted(wanted)
        found = self.codes.where(F.col("cell").isin(probed)).mapInPandas(work, "qid bigint, vec_id bigint, dist double, scanned bigint")
        return found.withColumn("scanned", F.max("scanned").over(_by_query()))


def _by_query():
    from pyspark.sql import Window

    return Window.partitionBy("qid")


def build_quantised(corpus: DataFrame, kind: str, nlist: int = 16, parts: int = 8, bits: int = 4, eta: float = 4.0, seed: int = 17) -> QuantisedIndex:
    """Train on a bounded sample and encode ``corpus(vec_id, embedding)``."""
    n = corpus.count()
    share = max(1, n // TRAIN_SAMPLE)
    rows = corpus.where(F.pmod(F.xxhash64(F.lit(seed), "vec_id"), F.lit(share)) == 0).select("vec_id", "embedding").limit(2 * TRAIN_SAMPLE).collect()
    x = np.array([r.embedding for r in sorted(rows, key=lambda r: r.vec_id)], dtype=np.float64)
    coder = Coder(kind, kmeans(x.astype(np.float32), min(nlist, len(x)), seed).astype(np.float64), parts, bits, eta, seed).fit(x)
    ship(corpus.sparkSession)

    def work(batches):
        for batch in batches:
            if batch.num_rows:
                v = np.asarray(batch.column(1).flatten(), dtype=np.float64).reshape(batch.num_rows, -1)
                cell, codes, norm, factor = coder.encode(v)
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0), pa.array(cell.astype(np.int32)), pa.array([c.tobytes() for c in codes]), pa.array(norm), pa.array(factor)], ["vec_id", "cell", "code", "norm", "factor"]
                )

    codes = corpus.select("vec_id", "embedding").mapInArrow(work, "vec_id bigint, cell int, code binary, norm float, factor float")
    return QuantisedIndex(codes, corpus.select("vec_id", "embedding"), coder)
