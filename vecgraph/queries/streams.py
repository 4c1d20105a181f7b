"""Streams run over what the tables hold, to the end.

Each query starts a stream on a table, waits until all of it is processed, and
returns the sink. Where the batch answer is the same, its SQL is given.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from ..functions import vectors as V
from ..operators import exact as E
from ..operators.index import build_index
from ..params import Params
from ..sources import corpora as C
from ..sources.session import shared_folder
from ..sources.tables import load
from ..streaming import insertion as S
from ..streaming import windows as W
from .base import Book
from .methods import whole_shards
from .vectors import NATIVE_Q, knn_sql, l2

BOOK = Book()


def events_stream(spark, d, parts: int = 1) -> DataFrame:
    """The events table, dealt to files in order of time, as a stream with a time column."""
    folder = shared_folder(spark, "events")
    load(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp")).repartitionByRange(parts, "ts").sortWithinPartitions("ts").write.parquet(folder)
    return W.stream_table(spark, folder, spark.read.parquet(folder).schema, files=parts)


def finish(df: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream to its end into Parquet in the shared folder and read it."""
    spark = df.sparkSession
    out, log = shared_folder(spark, "stream_out"), shared_folder(spark, "stream_log")
    if mode == "append":
        query = df.writeStream.format("parquet").outputMode("append").option("path", out).option("checkpointLocation", log).trigger(availableNow=True).start()
        query.awaitTermination()
        return spark.read.schema(df.schema).parquet(out)

    def each(rows, batch_id):
        rows.write.mode("overwrite").parquet(f"{out}/batch={batch_id:06d}")

    df.writeStream.foreachBatch(each).outputMode(mode).option("checkpointLocation", log).trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(out)


@BOOK.add("t05_deduplicated", "SELECT DISTINCT event_id FROM events")
def t05(spark, d):
    """Events with a watermark, each id once, though the stream has all twice."""
    s = events_stream(spark, d).withWatermark("ts", "10 minutes")
    twice = s.withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2)))).drop("copy")
    return finish(twice.dropDuplicatesWithinWatermark(["event_id"]).select("event_id"))


@BOOK.add("t06_streamed_windows", "SELECT strftime(date_trunc('hour', ts), '%Y-%m-%d %H') AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def t06(spark, d):
    """Hourly rates of the stream, in complete mode."""
    w = F.window("ts", "1 hour")
    counts = events_stream(spark, d).groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.date_format("w.start", "yyyy-MM-dd HH").alias("start"), "event_type", "n")
    return finish(counts, "complete").drop("batch")


_MARK = "(SELECT max(ts) - INTERVAL 10 MINUTE AS mark FROM events)"


@BOOK.add(
    "t06_sliding_windows",
    f"""SELECT strftime(date_trunc('hour', ts) - INTERVAL 1 HOUR * back, '%Y-%m-%d %H') AS start, event_type, count(*) AS n FROM events, (SELECT unnest([0, 1]) AS back), {_MARK}
    WHERE date_trunc('hour', ts) - INTERVAL 1 HOUR * back + INTERVAL 2 HOUR <= mark GROUP BY 1, 2""",
)
def t06b(spark, d):
    """Two-hour windows that begin every hour, as they close behind the watermark."""
    out = finish(W.rates(events_stream(spark, d), "2 hours", "1 hour"))
    return out.select(F.date_format("start", "yyyy-MM-dd HH").alias("start"), "event_type", "n")


@BOOK.add(
    "t06_streamed_sessions",
    f"""WITH g AS (SELECT user_id, ts, event_id, CASE WHEN ts - lag(ts) OVER w < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
    s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS k FROM g),
    x AS (SELECT user_id, min(ts) AS start, max(ts) + INTERVAL 30 MINUTE AS fin, count(*) AS n FROM s GROUP BY user_id, k)
    SELECT user_id, strftime(start, '%Y-%m-%d %H:%M:%S') AS start, n FROM x, {_MARK} WHERE fin <= mark""",
)
def t06c(spark, d):
    """Sessions, as they close behind the watermark."""
    return finish(W.sessions(events_stream(spark, d))).select("user_id", F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n")


@BOOK.add("t07_late_events")
def t07(spark, d):
    """Files in reverse order of time: windows drop what is later than the watermark allows."""
    folder = shared_folder(spark, "late")
    rows = load(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    rows.repartitionByRange(4, F.desc("ts")).write.parquet(folder)
    return finish(W.rates(W.stream_table(spark, folder, spark.read.parquet(folder).schema)))


@BOOK.add("t09_interval_join", "SELECT b.event_id AS purchase, v.event_id AS view FROM events b JOIN events v ON v.user_id = b.user_id AND v.ts <= b.ts AND v.ts >= b.ts - INTERVAL 1 HOUR WHERE b.event_type = 'purchase' AND v.event_type = 'view'")
def t09(spark, d):
    """Purchases with the same user's views within the hour before, both sides as streams."""
    s = events_stream(spark, d)
    buy = s.where("event_type = 'purchase'").select(F.col("user_id").alias("s_id"), F.col("ts").alias("s_ts"), F.col("event_id").alias("purchase"))
    view = events_stream(spark, d).where("event_type = 'view'").select(F.col("user_id").alias("i_id"), F.col("ts").alias("i_ts"), F.col("event_id").alias("view"))
    return finish(W.interval_join(buy, view).select("purchase", "view"))


@BOOK.add("t01_stream_insertion", "SELECT count(*) AS nodes FROM embeddings")
def t01(spark, d):
    """Insertions and searches as a stream of two files a batch; the index ends with every vector."""
    emb = C.embeddings(spark, d)
    initial, requests = S.mixed_requests(emb, share=4, batches=2)
    folder, log, out = shared_folder(spark, "requests"), shared_folder(spark, "log"), shared_folder(spark, "answers")
    requests = requests.withColumn("ts", F.lit("2024-01-01 00:00:00").cast("timestamp") + F.make_interval(mins=F.col("batch")))
    requests.repartition(2, "batch").write.parquet(folder)
    root = S.new_root(spark, build_index(initial, Params(64)))
    stream = W.stream_table(spark, folder, spark.read.parquet(folder).schema)
    S.start(stream, root, out, log, k=5, ef=32, watermark="10 minutes").awaitTermination()
    from ..operators.index import Index
    from ..sources.formats import latest

    index = Index.open(spark, latest(spark, root)["path"])
    return index.rows.agg((F.count("*") + F.sum(F.size("copies"))).alias("nodes"))


@BOOK.add("t03_replayed_batch", "SELECT 1::BIGINT AS versions_after_replay, true AS same")
def t03(spark, d):
    """A batch that comes twice changes nothing."""
    from ..sources.formats import latest

    emb = C.embeddings(spark, d)
    initial, requests = S.mixed_requests(emb, share=4, batches=1)
    root = S.new_root(spark, build_index(initial, Params(64)))
    S.step(spark, root, requests, 0, 5, 32)
    first = latest(spark, root)
    S.step(spark, root, requests, 0, 5, 32)
    second = latest(spark, root)
    return spark.range(1).select(F.lit(second["version"]).cast("bigint").alias("versions_after_replay"), F.lit(first == second).alias("same"))


@BOOK.add("t09_search_insert_join", "SELECT s.vec_id AS search, i.vec_id AS hit FROM embeddings s JOIN embeddings i ON i.vec_id = s.vec_id - 1 WHERE s.vec_id % 2 = 1")
def t09b(spark, d):
    """Searches joined with the insertions that created their hits, at most an hour before: both sides are streams."""
    emb = C.embeddings(spark, d)
    folder = shared_folder(spark, "requests")
    ts = F.timestamp_seconds(1_700_000_000 + F.col("vec_id") * 60)
    # every odd vector is searched a minute after the even one before it is inserted, and finds it
    emb.select("vec_id", ts.alias("ts"), F.when(F.col("vec_id") % 2 == 0, "insert").otherwise("search").alias("op")).coalesce(1).write.parquet(folder)
    read = lambda: W.stream_table(spark, folder, spark.read.parquet(folder).schema)
    searches = read().where("op = 'search'").select(F.col("vec_id").alias("search"), (F.col("vec_id") - 1).alias("s_id"), F.col("ts").alias("s_ts"))
    inserts = read().where("op = 'insert'").select(F.col("vec_id").alias("i_id"), F.col("ts").alias("i_ts"))
    return finish(W.interval_join(searches, inserts).select("search", F.col("i_id").alias("hit")))


@BOOK.add("t04_stream_static_search", knn_sql("SELECT vec_id, embedding FROM embeddings", NATIVE_Q, 5).replace("round(dist, 6)", "round(dist, 5)"))
def t04(spark, d):
    """A stream of queries against one pinned version, as wide as its graph."""
    emb = C.embeddings(spark, d)
    n = emb.count()
    index = build_index(emb, Params(64, work=n), shards=whole_shards(n))
    folder = shared_folder(spark, "queries")
    C.native_queries(emb).repartition(2).write.parquet(folder)
    stream = W.stream_table(spark, folder, spark.read.parquet(folder).schema)
    out, log = shared_folder(spark, "answers"), shared_folder(spark, "log")

    def each(rows, batch_id):
        hits = index.search(rows, 10, n).select("qid", "vec_id").join(emb, "vec_id").join(rows, "qid")
        again = hits.select("qid", "vec_id", V.l2("embedding", "qvec").alias("dist"))  # in doubles, as floats may swap neighbours
        E.top_k(again, 5).write.mode("overwrite").parquet(f"{out}/batch={batch_id:06d}")

    stream.writeStream.foreachBatch(each).option("checkpointLocation", log).trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(out).select("qid", "rank", "vec_id", F.round("dist", 5).alias("dist"))


_HELD = """WITH r AS (SELECT vec_id, vec_id % 4 AS key, embedding, CASE WHEN vec_id % 60 = 59 THEN 'verify' WHEN vec_id % 5 = 3 THEN 'search' ELSE 'insert' END AS op FROM embeddings),
  s AS (SELECT q.vec_id AS req, q.embedding AS qvec, q.key, coalesce((SELECT max(v.vec_id) FROM r v WHERE v.op = 'verify' AND v.key = q.key AND v.vec_id < q.vec_id), -1) AS since FROM r q WHERE q.op = 'search')"""


@BOOK.add("t08_recent_vectors", _HELD + f" SELECT req, hit, round(dist, 5) AS dist FROM (SELECT req, i.vec_id AS hit, {l2('qvec', 'i.embedding')} AS dist, row_number() OVER (PARTITION BY req ORDER BY {l2('qvec', 'i.embedding')}, i.vec_id) AS place FROM s JOIN r i ON i.op = 'insert' AND i.key = s.key AND i.vec_id < req AND i.vec_id > since) WHERE place = 1")
def t08(spark, d):
    """Per key, vectors inserted since the last verification are scanned exactly by searches; a verification lets them go."""
    op = F.when(F.col("vec_id") % 60 == 59, "verify").when(F.col("vec_id") % 5 == 3, "search").otherwise("insert")
    rows = C.embeddings(spark, d).select((F.col("vec_id") % 4).alias("key"), F.col("vec_id").alias("seq"), op.alias("op"), "vec_id", "embedding")
    folder = shared_folder(spark, "requests")
    rows.repartitionByRange(2, "seq").sortWithinPartitions("seq").write.parquet(folder)
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    stream = W.stream_table(spark, folder, spark.read.parquet(folder).schema, files=2)
    return finish(W.recent(stream), "update").select("req", "hit", F.round("dist", 5).alias("dist"))
