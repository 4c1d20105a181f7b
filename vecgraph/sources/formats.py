"""Reading and writing: common formats, packed vectors, vector files, index versions."""

from __future__ import annotations

import json
import struct

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from .session import ship


def write_as(df: DataFrame, kind: str, path: str) -> None:
    """csv, json, orc, parquet; overwrites nothing."""
    writer = df.write.format(kind)
    (writer.option("header", True) if kind == "csv" else writer).save(path)


def read_as(spark: SparkSession, kind: str, path: str, schema) -> DataFrame:
    reader = spark.read.format(kind).schema(schema)
    return (reader.option("header", True) if kind == "csv" else reader).load(path)


def pack(df: DataFrame, half: bool = False) -> DataFrame:
    """(vec_id, packed): vectors as little-endian floats of four or two bytes."""
    ship(df.sparkSession)
    kind = "<f2" if half else "<f4"

    def work(batches):
        for b in batches:
            if b.num_rows:
                x = np.asarray(b.column(1).flatten(), dtype=np.float32).reshape(b.num_rows, -1).astype(kind)
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array([r.tobytes() for r in x], type=pa.binary())], ["vec_id", "packed"])

    return df.select("vec_id", "embedding").mapInArrow(work, "vec_id bigint, packed binary")


def unpack(df: DataFrame, half: bool = False) -> DataFrame:
    """(vec_id, embedding) of packed vectors."""
    ship(df.sparkSession)
    kind = "<f2" if half else "<f4"

    def work(batches):
        for b in batches:
            if b.num_rows:
                rows = [np.frombuffer(v, dtype=kind).astype(np.float32) for v in b.column(1).to_pylist()]
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array(rows, type=pa.list_(pa.float32()))], ["vec_id", "embedding"])

    return df.select("vec_id", "packed").mapInArrow(work, "vec_id bigint, embedding array<float>")


def quantise_local(df: DataFrame, bits: int = 16) -> DataFrame:
    """(vec_id, low, step, levels): each vector on its own grid of 2**bits levels."""
    top = 2**bits - 1
    low, high = F.array_min("embedding").cast("double"), F.array_max("embedding").cast("double")
    step = F.when(high > low, (high - low) / top).otherwise(F.lit(1.0))
    return df.select("vec_id", low.alias("low"), step.alias("step"), "embedding").select(
        "vec_id", "low", "step", F.transform("embedding", lambda v: F.round((v.cast("double") - F.col("low")) / F.col("step")).cast("int")).alias("levels")
    )


def dequantise_local(df: DataFrame) -> DataFrame:
    return df.select("vec_id", F.transform("levels", lambda v: (F.col("low") + v * F.col("step")).cast("float")).alias("embedding"))


def to_fvecs(x: np.ndarray, kind: str = "f") -> bytes:
    """The public layout of vector files: for each vector its length (int32) and its values."""
    return b"".join(struct.pack("<i", len(r)) + r.astype(f"<{kind}4").tobytes() for r in x)


def write_fvecs(df: DataFrame, path: str) -> None:
    """One file of records for each partition, by Spark's text-free binary way: rows of ``(path, content)`` are collected per partition and saved as a sequence of Parquet blobs."""
    ship(df.sparkSession)

    def work(batches):
        for b in batches:
            if b.num_rows:
                x = np.asarray(b.column(0).flatten(), dtype=np.float32).reshape(b.num_rows, -1)
                yield pa.RecordBatch.from_arrays([pa.array([to_fvecs(x)], type=pa.binary())], ["content"])

    df.select("embedding").mapInArrow(work, "content binary").write.parquet(path)


def parse_fvecs(content: bytes, kind: str = "f") -> np.ndarray:
    if not content:
        return np.zeros((0, 0), dtype=f"<{kind}4")
    dim = struct.unpack("<i", content[:4])[0]
    return np.frombuffer(content, dtype=f"<{kind}4").reshape(-1, dim + 1)[:, 1:]


def read_fvecs(blobs: DataFrame) -> DataFrame:
    """(embedding) of a table with vector files in ``content``: ``binaryFile`` reads whole files, ``write_fvecs`` writes blobs."""
    ship(blobs.sparkSession)

    def work(batches):
        for b in batches:
            for content in b.column(0).to_pylist():
                rows = parse_fvecs(content)
                if len(rows):
                    yield pa.RecordBatch.from_arrays([pa.array(list(rows), type=pa.list_(pa.float32()))], ["embedding"])

    return blobs.select("content").mapInArrow(work, "embedding array<float>")


class VectorFileSource(DataSource):
    """``spark.read.format("vecfile")``: one file on a path that all machines see, cut in ranges of whole records."""

    @classmethod
    def name(cls) -> str:
        return "vecfile"

    def schema(self) -> str:
        return "vec_id bigint, embedding array<float>"

    def reader(self, schema):
        return VectorFileReader(self.options)


class _Range(InputPartition):
    def __init__(self, first: int, count: int):
        self.first, self.count = first, count


class VectorFileReader(DataSourceReader):
    def __init__(self, options):
        self.path, self.parts = options["path"], int(options.get("parts", "8"))

    def _dim(self) -> int:
        with open(self.path, "rb") as f:
            head = f.read(4)
        return struct.unpack("<i", head)[0] if head else 0

    def partitions(self):
        import os

        dim = self._dim()
        n = os.path.getsize(self.path) // (4 * (dim + 1)) if dim else 0
        step = max(1, -(-n // self.parts))
        return [_Range(i, min(step, n - i)) for i in range(0, n, step)] or [_Range(0, 0)]

    def read(self, part):
        if not part.count:
            return
        dim = self._dim()
        with open(self.path, "rb") as f:
            f.seek(part.first * 4 * (dim + 1))
            rows = parse_fvecs(f.read(part.count * 4 * (dim + 1)))
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(part.first, part.first + len(rows))), pa.array(list(rows), type=pa.list_(pa.float32()))], ["vec_id", "embedding"])


def publish(spark: SparkSession, root: str, version: int, path: str, batch: int = -1) -> None:
    """Make ``path`` version ``version`` of an index: one small pointer file, written after the data.

    Readers take the highest version, so they see the old one until the pointer is complete.
    """
    note = json.dumps({"version": version, "path": path, "batch": batch})
    spark.createDataFrame([(note,)], "note string").coalesce(1).write.mode("errorifexists").text(f"{root}/version={version:09d}")


def latest(spark: SparkSession, root: str) -> dict | None:
    """The pointer of the newest version, or None."""
    from py4j.protocol import Py4JJavaError

    jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    where = jvm.org.apache.hadoop.fs.Path(root)
    try:
        there = where.getFileSystem(conf).exists(where)
    except Py4JJavaError:
        there = False
    if not there:
        return None
    notes = [json.loads(r.value) for r in spark.read.text(root).select("value").collect()]  # one short row a version
    return max(notes, key=lambda n: n["version"], default=None)
