"""Reference directions, edge profiles and the angle estimate.

The space is turned by a fixed orthogonal transform and cut into blocks. Each
block has a set of unit directions, scaled by 1/sqrt(blocks); taking one of each
block gives a unit vector, and the set of all such choices is never formed: an
inner product is a sum over blocks, so every block picks its best direction
alone. The cosine between an edge and its own best reference, and the cosine
between that reference and the way to a target, have the cosine between edge
and way as their ratio, up to noise.
"""

from __future__ import annotations

from functools import lru_cache

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, functions as F

from ..params import Params


#: Vectors that are turned at once, and columns of the rotation.
ROTATED = 512


@lru_cache(maxsize=4)
def orthogonal(dim: int, seed: int) -> np.ndarray:
    """A random orthogonal matrix (QR of a Gaussian one, signs fixed); kept, so not to be written to."""
    q, r = np.linalg.qr(np.random.default_rng(seed).normal(size=(dim, dim)))
    out = (q * np.sign(np.diag(r))).astype(np.float32)
    out.flags.writeable = False
    return out


@lru_cache(maxsize=8)
def references(dim: int, blocks: int, per_block: int, seed: int) -> np.ndarray:
    """(blocks, per_block, dim/blocks): the axes and their opposites under as many rotations as are needed, scaled."""
    width = dim // blocks
    rng = np.random.default_rng([seed, blocks, per_block])
    out = np.empty((blocks, per_block, width), dtype=np.float32)
    for b in range(blocks):
        got: list[np.ndarray] = []
        while len(got) < per_block:
            q, r = np.linalg.qr(rng.normal(size=(width, width)))
            q = q * np.sign(np.diag(r))
            got += [x for row in q for x in (row, -row)]
        out[b] = np.array(got[:per_block])
    out /= np.sqrt(blocks)
    out.flags.writeable = False
    return out


def prepare(vectors: np.ndarray, params: Params, rotation: np.ndarray | None = None) -> np.ndarray:
    """Vectors normalised (cosine), padded and rotated."""
    x = np.asarray(vectors, dtype=np.float32).reshape(-1, params.dim)
    if params.metric == "cosine":
        norms = np.linalg.norm(x, axis=1, keepdims=True)
        x = x / np.where(norms > 0, norms, 1)
    if params.padded > params.dim:
        x = np.hstack([x, np.zeros((len(x), params.padded - params.dim), dtype=np.float32)])
    return turned(x, orthogonal(params.padded, params.seed) if rotation is None else rotation)


def turned(x: np.ndarray, rotation: np.ndarray) -> np.ndarray:
    """``x @ rotation``, a vector to the same bits whatever stands beside it, so that copies stay copies.

    A matrix product in floats adds up rows in an order that depends on their place.
    Here a row is brought to 24 bits below its largest entry and the rotation is the
    sum of two parts of 16 bits: products and sums are exact in doubles in any order.
    """
    out = np.empty(x.shape, dtype=np.float32)
    for j in range(0, x.shape[1], ROTATED):
        some = rotation[:, j : j + ROTATED].astype(np.float64)
        coarse = np.rint(some * 2.0**16) / 2.0**16
        fine = np.rint((some - coarse) * 2.0**32) / 2.0**32
        for i in range(0, len(x), ROTATED):
            part = x[i : i + ROTATED].astype(np.float64)
            scale = np.ldexp(1.0, 24 - np.frexp(np.abs(part).max(axis=1, keepdims=True))[1])
            part = np.rint(part * scale)
            out[i : i + ROTATED, j : j + ROTATED] = (part @ coarse + part @ fine) / scale
    out += np.float32(0)  # one zero, so that equal vectors have equal bits
    return out


def profile(source: np.ndarray, target: np.ndarray, refs: np.ndarray):
    """For edges source -> target: length, cosine with the own reference, <reference, source>, codes."""
    blocks, per_block, width = refs.shape
    n = len(source)
    codes = np.empty((n, blocks), dtype=np.uint8)
    best = np.zeros(n, dtype=np.float32)
    shift = np.zeros(n, dtype=np.float32)
    diff = target - source
    for b in range(blocks):
        part = slice(b * width, (b + 1) * width)
        values = diff[:, part] @ refs[b].T
        codes[:, b] = values.argmax(axis=1)
        best += values[np.arange(n), codes[:, b]]
        shift += np.einsum("nd,nd->n", refs[b][codes[:, b]], source[:, part])
    length = np.linalg.norm(diff, axis=1).astype(np.float32)
    return length, best / np.where(length > 0, length, 1), shift, codes


def target_table(targets: np.ndarray, refs: np.ndarray) -> np.ndarray:
    """(targets, blocks, per_block): inner products of the targets with all directions."""
    blocks, per_block, width = refs.shape
    return np.einsum("nbw,bmw->nbm", targets.reshape(len(targets), blocks, width), refs, optimize=True).astype(np.float32)


# --- the same as columns, with deterministic directions that SQL can form -------------


def walsh_sign(i: Column, j: Column) -> Column:
    """Entry (i, j) of a Walsh-Hadamard matrix."""
    return F.when(F.bit_count(i.bitwiseAND(j)) % 2 == 0, F.lit(1.0)).otherwise(F.lit(-1.0))


def walsh_references(spark: SparkSession, dim: int, blocks: int, per_block: int) -> DataFrame:
    """(block, ref, dir): rows of a Walsh-Hadamard matrix and their opposites, unit and scaled; needs dim/blocks a power of two."""
    width = dim // blocks
    if width & (width - 1) or per_block > 2 * width:
        raise ValueError("the block width must be a power of two and hold half of the directions")
    grid = spark.range(blocks * per_block).select((F.col("id") / per_block).cast("int").alias("block"), (F.col("id") % per_block).cast("int").alias("ref"))
    row, sign = (F.col("ref") / 2).cast("int"), F.when(F.col("ref") % 2 == 0, 1.0).otherwise(-1.0)
    scale = 1.0 / (width * blocks) ** 0.5
    direction = F.transform(F.sequence(F.lit(0), F.lit(width - 1)), lambda j: sign * walsh_sign(row, j) * scale)
    return grid.select("block", "ref", direction.alias("dir"))


def split_blocks(vector: Column, blocks: int, dim: int) -> Column:
    """The vector as an array of ``blocks`` equal slices."""
    width = dim // blocks
    return F.transform(F.sequence(F.lit(0), F.lit(blocks - 1)), lambda i: F.slice(vector, i * width + 1, width))


def _one_row(refs: DataFrame) -> DataFrame:
    """A table of directions as one row."""
    return refs.groupBy("block").agg(F.array_sort(F.collect_list(F.struct("ref", "dir"))).alias("own")).agg(F.array_sort(F.collect_list(F.struct("block", "own"))).alias("refs"))


def chosen_references(vectors: DataFrame, refs: DataFrame, dim: int, blocks: int) -> DataFrame:
    """(vec_id, block, ref): for each of ``vectors(vec_id, embedding)`` the direction of each block with the largest inner product; ties go to the lowest reference."""
    width = dim // blocks
    cut = lambda b: F.slice("embedding", b * width + 1, F.lit(width))
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda u, v: u.cast("double") * v), F.lit(0.0), lambda s, u: s + u)
    best = F.transform("refs", lambda b: F.struct(b["block"].alias("block"), (-F.array_max(F.transform(b["own"], lambda r: F.struct(F.round(dot(cut(b["block"]), r["dir"]), 9).alias("k"), (-r["ref"]).alias("r"))))["r"]).alias("ref")))
    return vectors.crossJoin(F.broadcast(_one_row(refs))).select("vec_id", F.inline(best))  # one row


def profile_triples(triples: DataFrame, refs: DataFrame, dim: int, blocks: int) -> DataFrame:
    """``triples(.., p, q, x)`` (pivot, target, neighbour vectors) without the vectors and with edge_len, way_len, cos_own, cos_target, cos_exact.

    ``refs`` is a table of a few hundred directions (blocks x per_block). They go
    into one broadcast row, and every triple picks its directions by itself:
    nothing is exploded or shuffled.
    """
    width = dim // blocks
    family = _one_row(refs)
    diff = lambda a, b: F.zip_with(F.col(a), F.col(b), lambda u, v: u.cast("double") - v.cast("double"))
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda u, v: u * v), F.lit(0.0), lambda s, u: s + u)
    kept = [c for c in triples.columns if c not in ("p", "q", "x")]
    base = triples.select(*kept, diff("x", "p").alias("edge"), diff("q", "p").alias("way")).crossJoin(F.broadcast(family))  # one row
    cut = lambda c, b: F.slice(F.col(c), b * width + 1, F.lit(width))
    # Of each block the direction with the largest product; ties go to the lowest reference.
    seen = lambda b, r: F.struct(F.round(dot(cut("edge", b), r["dir"]), 9).alias("k"), (-r["ref"]).alias("r"), dot(cut("edge", b), r["dir"]).alias("own"), dot(cut("way", b), r["dir"]).alias("seen"))
    best = F.transform("refs", lambda b: F.array_max(F.transform(b["own"], lambda r: seen(b["block"], r))))
    total = lambda c: F.aggregate("best", F.lit(0.0), lambda s, b: s + b[c])
    sized = base.select(
        *kept, best.alias("best"), F.sqrt(dot(F.col("edge"), F.col("edge"))).alias("edge_len"), F.sqrt(dot(F.col("way"), F.col("way"))).alias("way_len"), dot(F.col("edge"), F.col("way")).alias("inner")
    )
    return sized.select(
        *kept,
        "edge_len",
        "way_len",
        (total("own") / F.col("edge_len")).alias("cos_own"),
        (total("seen") / F.col("way_len")).alias("cos_target"),
        (F.col("inner") / (F.col("edge_len") * F.col("way_len"))).alias("cos_exact"),
    )
