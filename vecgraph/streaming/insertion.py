"""Online insertion and search as a stream.

A micro-batch is a slot of the schedule: its inserts become a new index version,
then its searches run on the version they may see. The batch's number is kept in
the version's pointer, so a replayed batch changes nothing.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from ..operators.index import Index, insert_batch
from ..sources.formats import latest, publish
from ..sources.session import shared_folder

REQUEST = "req_id bigint, batch int, op string, vec_id bigint, vec array<float>, ts timestamp"


def mixed_requests(corpus: DataFrame, share: int = 4, batches: int = 4) -> tuple[DataFrame, DataFrame]:
    """(initial corpus, requests): one vector in ``share`` is inserted, as many are searched, in interleaved batches, inserts first.

    Vectors are dealt by the MD5 of their ids.
    """
    digest = F.conv(F.substring(F.md5(F.col("vec_id").cast("string").cast("binary")), 1, 7), 16, 10).cast("bigint")
    dealt = corpus.withColumn("h", digest).withColumn("deal", F.col("h") % share)
    pairs = [("insert", 0, 0), ("search", 1, 1)]
    parts = [
        dealt.where(F.col("deal") == deal).select(
            F.col("vec_id").alias("req_id"), (2 * (F.floor(F.col("h") / share) % batches) + side).cast("int").alias("batch"), F.lit(op).alias("op"), "vec_id", F.col("embedding").alias("vec")
        )
        for op, deal, side in pairs
    ]
    return dealt.where("deal != 0").drop("h", "deal"), parts[0].unionByName(parts[1])


def step(spark: SparkSession, root: str, requests: DataFrame, batch_id: int, k: int, ef: int, probes: int | None = None) -> DataFrame | None:
    """Apply one batch; the answers of its searches, or None without any."""
    note = latest(spark, root)
    index = Index.open(spark, note["path"])
    inserts = requests.where("op = 'insert'").select("vec_id", F.col("vec").alias("embedding"))
    if note["batch"] < batch_id and not inserts.isEmpty():
        index = insert_batch(index, inserts)
        publish(spark, root, note["version"] + 1, index.path, batch_id)
    searches = requests.where("op = 'search'").select(F.col("req_id").alias("qid"), F.col("vec").alias("qvec"))
    return None if searches.isEmpty() else index.search(searches, k, ef, probes)


def start(requests: DataFrame, root: str, out: str, checkpoint: str, k: int, ef: int, watermark: str | None = None):
    """A streaming query over ``requests``: inserts extend the index under ``root``, answers are appended to ``out``.

    With a watermark (on ``ts``), repeated requests inside it are dropped.
    """
    if watermark:
        requests = requests.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["req_id", "op"])

    def each(rows: DataFrame, batch_id: int) -> None:
        rows.persist()
        answers = step(rows.sparkSession, root, rows, batch_id, k, ef)
        if answers is not None:
            # one folder a batch: a replay overwrites its own
            answers.withColumn("batch_id", F.lit(batch_id)).write.mode("overwrite").parquet(f"{out}/batch={batch_id:06d}")
        rows.unpersist()

    return requests.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def new_root(spark: SparkSession, index: Index) -> str:
    """A place of versions that begins with an index."""
    root = shared_folder(spark, "versions")
    publish(spark, root, 0, index.path)
    return root
