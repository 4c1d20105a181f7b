"""Small helpers shared by the corpus operators."""

from __future__ import annotations

import os
import tempfile
import zipfile
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, functions as F

_PACKAGE = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))


def ship(spark: SparkSession) -> None:
    """Make this package importable in the Python workers, once per application.

    Where the workers already see the source tree this only costs one small
    zip; on a cluster Spark's own file server delivers it.
    """
    context = spark.sparkContext
    if getattr(context, "_corpus_operators_shipped", False):
        return
    target = os.path.join(tempfile.mkdtemp(prefix="corpus_ops_"), "corpus_ops.zip")
    root = os.path.dirname(_PACKAGE)
    with zipfile.ZipFile(target, "w", zipfile.ZIP_DEFLATED) as z:
        for folder, _, names in os.walk(_PACKAGE):
            for name in sorted(names):
                if name.endswith(".py"):
                    path = os.path.join(folder, name)
                    z.write(path, os.path.relpath(path, root))
    context.addPyFile(target)
    context._corpus_operators_shipped = True


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def fold(column: str | Column, parts: int) -> Column:
    """crc32 of an id written as text, modulo ``parts``; a null id falls in fold 0."""
    c = F.col(column) if isinstance(column, str) else column
    return F.coalesce(F.crc32(c.cast("string").cast("binary")) % F.lit(parts), F.lit(0))


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share; without a setting a local one, which only a local master may use."""
    context = spark.sparkContext
    folder = spark.conf.get("spark.checkpoint.dir", None) or context.getConf().get("spark.checkpoint.dir")
    if not folder and (known := context._jsc.sc().getCheckpointDir()).isDefined():
        folder = known.get()
    if not folder:
        if not context.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all machines share")
        folder = tempfile.mkdtemp(prefix="corpus_checkpoints_")
    return folder.rstrip("/")


def checkpoint(df: DataFrame) -> DataFrame:
    """Reliable checkpoint in the shared folder."""
    context = df.sparkSession.sparkContext
    if context._jsc.sc().getCheckpointDir().isEmpty():
        context.setCheckpointDir(shared_folder(df.sparkSession))
    return df.checkpoint(eager=True)


def pieces(batch: pa.RecordBatch, rows: int, size: int) -> Iterator[pa.RecordBatch]:
    """The batch cut in pieces of at most ``rows`` rows and about ``size`` bytes (one row at least)."""
    step = max(1, min(rows, batch.num_rows * size // max(1, batch.nbytes)))
    for i in range(0, batch.num_rows, step):
        part = batch.slice(i, step)
        if part.num_rows > 1 and part.nbytes > 2 * size:  # long texts stand together here
            yield from pieces(part, max(1, step // 2), size)
        else:
            yield part


def map_texts(
    docs: DataFrame,
    columns: list[str],
    work: Callable[[pa.RecordBatch], pa.RecordBatch | None],
    schema: str,
    rows: int = 512,
    size: int = 4 << 20,
) -> DataFrame:
    """Apply ``work`` to the named columns in batches of at most ``rows`` rows and about ``size`` bytes."""
    ship(docs.sparkSession)

    def over(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in pieces(batch, rows, size):
                out = work(part)
                if out is not None and out.num_rows:
                    yield out

    return docs.select(*columns).mapInArrow(over, schema)


def clear_name(docs: DataFrame, name: str) -> str:
    """The name, or with more underscores, so that no column of ``docs`` has it (names differ by more than case)."""
    taken = {c.lower() for c in docs.columns}
    while name.lower() in taken:
        name += "_"
    return name


def sample_rows(docs: DataFrame, columns: list[str], cap: int, seed: int = 7) -> DataFrame:
    """At most ``2 * cap`` rows: those whose doc_id is among the ``cap`` ids with the least seeded hashes.

    Ids are chosen from the id column alone, so texts are read for the sample only.
    """
    ids = docs.select(F.col("doc_id").alias("__id")).where("__id is not null").orderBy(F.xxhash64(F.lit(seed), "__id"), "__id").limit(cap)
    return docs.select("doc_id", *columns).join(F.broadcast(ids.distinct()), F.col("doc_id") == F.col("__id"), "left_semi").limit(2 * cap)
