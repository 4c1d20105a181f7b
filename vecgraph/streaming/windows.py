"""Windowed and stateful streams over request events."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from ..sources.session import ship


def stream_table(spark: SparkSession, folder: str, schema, files: int = 1) -> DataFrame:
    """A Parquet folder as a stream."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(folder)


def rates(events: DataFrame, size: str = "1 hour", slide: str | None = None, late: str = "10 minutes") -> DataFrame:
    """Requests and mean value of each tumbling (or sliding) window and kind; later events than the watermark are left out."""
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return events.withWatermark("ts", late).groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n"), F.avg("value").alias("mean")).select(F.col("w.start").alias("start"), "event_type", "n", "mean")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "10 minutes") -> DataFrame:
    """Sessions of each user."""
    s = F.session_window("ts", gap)
    return events.withWatermark("ts", late).groupBy(s.alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def interval_join(searches: DataFrame, inserts: DataFrame, within: str = "1 hour") -> DataFrame:
    """Searches with the insertions of the same vector at most ``within`` before them, both sides bounded by watermarks."""
    a = searches.withWatermark("s_ts", "10 minutes")
    b = inserts.withWatermark("i_ts", "10 minutes")
    return a.join(b, F.expr(f"s_id = i_id AND i_ts <= s_ts AND i_ts >= s_ts - INTERVAL {within}"))


def run_once(df: DataFrame, name: str, checkpoint: str, mode: str = "append") -> DataFrame:
    """Run a stream over what is there and give its result table (tests and small reports: the sink is in memory)."""
    query = df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    return df.sparkSession.table(name)


class RecentVectors(StatefulProcessor):
    """Per key, the vectors that no verification has seen yet: a search scans them exactly, ``verify`` lets them go, and so does the time to live, if there is one."""

    def __init__(self, ttl_ms: int | None = None):
        self.ttl_ms = ttl_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.held = handle.getListState("held", "vec_id long, embedding array<float>", ttlDurationMs=self.ttl_ms)

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timers) -> Iterator[pd.DataFrame]:
        held = [(int(r[0]), list(r[1])) for r in self.held.get()]
        out = []
        for r in pd.concat(list(rows)).sort_values("seq").itertuples(index=False):
            if r.op == "insert":
                held.append((int(r.vec_id), [float(v) for v in r.embedding]))
            elif r.op == "verify":
                held = []
            elif held:
                diff = np.array([v for _, v in held], dtype=np.float64) - np.asarray(r.embedding, dtype=np.float64)
                dist = np.sqrt((diff * diff).sum(axis=1))
                best = min(range(len(held)), key=lambda i: (dist[i], held[i][0]))
                out.append((int(r.vec_id), held[best][0], float(dist[best])))
        self.held.put(held) if held else self.held.clear()
        yield pd.DataFrame(out, columns=["req", "hit", "dist"]).astype({"req": "int64", "hit": "int64", "dist": "float64"})

    def close(self) -> None:
        pass


def recent(requests: DataFrame, ttl_ms: int | None = None) -> DataFrame:
    """(req, hit, dist): the nearest unverified vector of each search ``requests(key, seq, op, vec_id, embedding)``.

    A time to live needs processing time, which keeps a stream running: it is for streams without an end.
    """
    ship(requests.sparkSession)
    return requests.groupBy("key").transformWithStateInPandas(RecentVectors(ttl_ms), "req bigint, hit bigint, dist double", "Update", "ProcessingTime" if ttl_ms else "None")
