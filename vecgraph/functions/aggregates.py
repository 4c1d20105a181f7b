"""Aggregates and table functions that Spark does not have, in Arrow batches."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, functions as F
from pyspark.sql.functions import arrow_udf, pandas_udf, udtf

from ..operators.index import Index, answers, from_parts
from ..sources.session import ship


def top_k_by(k: int):
    """An aggregate ``(distance, id) -> ids`` of the k least pairs, in order.

    A group must fit a task: trim large ones before (``exact.top_k`` does).
    """

    @pandas_udf("array<bigint>")
    def best(dist: pd.Series, ids: pd.Series) -> list:
        order = np.lexsort((ids.to_numpy(), dist.to_numpy()))[:k]
        return ids.to_numpy()[order].tolist()

    return best


@pandas_udf("array<double>")
def vec_avg(v: pd.Series) -> list:
    """The mean of the vectors of a group."""
    return np.stack(v.tolist()).astype(np.float64).mean(axis=0).tolist()


def vector_mean(rows: DataFrame, key: str, vector: str = "embedding") -> DataFrame:
    """(key, n, mean) by partial sums: each task sums its vectors for each key, so no group meets in one place as vectors."""
    ship(rows.sparkSession)

    def work(batches):
        sums: dict = {}
        for b in batches:
            if b.num_rows:
                x = np.asarray(b.column(1).flatten(), dtype=np.float64).reshape(b.num_rows, -1)
                keys = b.column(0).to_pylist()
                for key in set(keys):
                    mine = x[[k == key for k in keys]]
                    n, s = sums.get(key, (0, 0.0))
                    sums[key] = (n + len(mine), s + mine.sum(axis=0))
        for key, (n, s) in sums.items():
            yield pa.RecordBatch.from_arrays([pa.array([key] * len(s), type=kind), pa.array(range(len(s)), type=pa.int32()), pa.array(s), pa.array([n] * len(s), type=pa.int64())], ["key", "pos", "s", "n"])

    from pyspark.sql.pandas.types import to_arrow_type

    kind = to_arrow_type(rows.schema[key].dataType)
    parts = rows.select(key, vector).mapInArrow(work, f"key {rows.schema[key].dataType.simpleString()}, pos int, s double, n bigint")
    each = parts.groupBy("key", "pos").agg(F.sum("s").alias("s"), F.sum("n").alias("n"))
    return each.groupBy(F.col("key").alias(key)).agg(F.max("n").alias("n"), F.transform(F.array_sort(F.collect_list(F.struct("pos", (F.col("s") / F.col("n")).alias("v")))), lambda p: p["v"]).alias("mean"))


def arrow_norm(column: str) -> Column:
    """Lengths of vectors by an Arrow function."""

    @arrow_udf("double")
    def norm(v: pa.Array) -> pa.Array:
        x = np.asarray(v.flatten(), dtype=np.float64).reshape(len(v), -1)
        return pa.array(np.sqrt((x * x).sum(axis=1)))

    return norm(column)


def register_search(spark: SparkSession, index: Index, name: str = "ann_search") -> None:
    """``SELECT * FROM name(TABLE(SELECT * FROM name_shards) PARTITION BY (shard), array(..), k, ef)``: the hits of each shard.

    The view ``name_shards`` holds the index's blobs. A shard's hits are k rows;
    an outer ORDER BY dist, vec_id LIMIT k merges them.
    """
    ship(spark)
    index.blobs().createOrReplaceTempView(f"{name}_shards")
    params = index.params

    class Search:
        def __init__(self):
            self.parts, self.asked = [], None

        def eval(self, part, query: list, k: int, ef: int):
            self.parts.append(part.asDict(recursive=True))
            self.asked = (query, k, ef)

        def terminate(self):
            if self.parts:
                query, k, ef = self.asked
                hits = answers(from_parts(self.parts, params), np.zeros(1, dtype=np.int64), np.array([query], dtype=np.float32), k, ef, {})
                for row in hits.to_pylist():
                    yield row["vec_id"], row["dist"], row["n_exact"]

    spark.udtf.register(name, udtf(Search, returnType="vec_id bigint, dist double, n_exact bigint"))


def register_inspection(spark: SparkSession, index: Index, prefix: str = "index") -> list[str]:
    """Views of the index's parts: nodes, edges, copies, pending, sizes, manifest."""
    views = {"nodes": index.nodes(), "edges": index.edges(), "copies": index.copies(), "pending": index.pending(), "sizes": index.size_report()}
    views["manifest"] = spark.createDataFrame([(k, str(v)) for k, v in index.params.as_dict().items()], "name string, value string")
    for name, df in views.items():
        df.createOrReplaceTempView(f"{prefix}_{name}")
    return [f"{prefix}_{name}" for name in views]
