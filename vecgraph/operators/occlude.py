"""Occlusion pruning and the edge screen as joins.

An edge pivot -> target is redundant if the pivot has an out-neighbour that is
not farther from the target than the pivot, and not farther from the pivot than
the target: that neighbour is a witness. "No witness" is a left anti join.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window, functions as F

from ..functions import vectors as V
from ..sources.session import ship


def knn_edges(hits: DataFrame) -> DataFrame:
    """(src, dst, edge_len) of a neighbour list (qid, vec_id, dist)."""
    return hits.select(F.col("qid").alias("src"), F.col("vec_id").alias("dst"), F.col("dist").alias("edge_len"))


def candidate_pairs(edges: DataFrame) -> DataFrame:
    """(pivot, target, dist): every out-neighbour u of v as a candidate in-neighbour, the reference reading."""
    return edges.select(F.col("dst").alias("pivot"), F.col("src").alias("target"), F.col("edge_len").alias("dist"))


def witnesses(pairs: DataFrame, edges: DataFrame, vectors: DataFrame, alpha: float = 1.0) -> DataFrame:
    """(pivot, target, witness): out-neighbours of the pivot that make the edge to the target redundant.

    The comparison rounds at the ninth decimal, so equal lengths count as equal.
    """
    near = pairs.join(edges.select(F.col("src").alias("pivot"), F.col("dst").alias("witness"), "edge_len"), "pivot").where(
        (F.col("witness") != F.col("target")) & (F.round(alpha * F.col("edge_len"), 9) <= F.round("dist", 9))
    )
    seen = near.join(vectors.select(F.col("vec_id").alias("witness"), F.col("embedding").alias("wv")), "witness").join(
        vectors.select(F.col("vec_id").alias("target"), F.col("embedding").alias("tv")), "target"
    )
    return seen.where(F.round(alpha * V.l2("wv", "tv"), 9) <= F.round("dist", 9)).select("pivot", "target", "witness")


def occlude_incoming(pairs: DataFrame, edges: DataFrame, vectors: DataFrame, alpha: float = 1.0) -> DataFrame:
    """The pairs without a witness."""
    return pairs.join(witnesses(pairs, edges, vectors, alpha), ["pivot", "target"], "left_anti")


def occlude_outgoing(cands: DataFrame, vectors: DataFrame, cap: int, alpha: float = 1.0) -> DataFrame:
    """(target, vec_id, dist): the greedy choice of each target among its candidates ``cands(target, vec_id, dist)``.

    A target's candidates are a search's harvest, bounded by its width, so each group fits a worker.
    """
    ship(cands.sparkSession)
    rows = cands.join(vectors.select("vec_id", "embedding"), "vec_id")

    def choose(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["dist", "vec_id"], ignore_index=True)
        x = np.array(pdf["embedding"].tolist(), dtype=np.float64)
        kept: list[int] = []
        for j in range(len(pdf)):
            if len(kept) == cap:
                break
            if not kept or (np.round(alpha * np.linalg.norm(x[kept] - x[j], axis=1), 9) > round(pdf["dist"][j], 9)).all():
                kept.append(j)
        return pdf.loc[kept, ["target", "vec_id", "dist"]]

    return rows.groupBy("target").applyInPandas(choose, "target bigint, vec_id bigint, dist double")


def collect_pending(survivors: DataFrame, cap: int) -> DataFrame:
    """At most ``cap`` pending edges of each target ``survivors(pivot, target, stat)``: the most negative first, then by id."""
    order = Window.partitionBy("target").orderBy("stat", "pivot")
    return survivors.withColumn("place", F.row_number().over(order)).where(F.col("place") <= cap).drop("place")


def verify_pending(pending: DataFrame, edges: DataFrame, vectors: DataFrame) -> DataFrame:
    """The pending edges that the exact rule keeps."""
    measured = (
        pending.join(vectors.select(F.col("vec_id").alias("pivot"), F.col("embedding").alias("pv")), "pivot")
        .join(vectors.select(F.col("vec_id").alias("target"), F.col("embedding").alias("tv")), "target")
        .select("pivot", "target", V.l2("pv", "tv").alias("dist"))
    )
    return occlude_incoming(measured, edges, vectors)
