"""Event streams: windowed features with watermarks, dedupe, running verdicts, joins, and index upkeep.

Each function takes a streaming DataFrame and gives one; ``drain`` runs it over what there is now.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators.cluster import Layers, assign
from ..operators.index import choose_home
from ..session import fresh_path
from ..sources.tables import SCHEMAS

EVENTS = SCHEMAS["events"].replace("TIMESTAMP_NTZ", "TIMESTAMP")


def read_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a stream of its files (one file, or a folder of them)."""
    return spark.readStream.schema(EVENTS).option("recursiveFileLookup", "true").parquet(f"{sf_dir}/events.parque[t]")


def tumbling(events: DataFrame, every: str = "1 hour", late: str = "2 hours") -> DataFrame:
    """Events and mean value per window and type."""
    w = events.withWatermark("ts", late).groupBy(F.window("ts", every), "event_type").agg(F.count("*").alias("n"), F.avg("value").alias("mean"))
    return w.select(F.col("window.start").alias("start"), "event_type", "n", "mean")


def sliding(events: DataFrame, size: str = "2 hours", step: str = "1 hour", late: str = "2 hours") -> DataFrame:
    w = events.withWatermark("ts", late).groupBy(F.window("ts", size, step), "event_type").agg(F.count("*").alias("n"))
    return w.select(F.col("window.start").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: str = "6 hours", late: str = "12 hours") -> DataFrame:
    """Per user, spells of events with no longer pause than ``gap``."""
    w = events.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"))
    return w.select(F.col("session_window.start").alias("start"), F.col("session_window.end").alias("end"), "user_id", "n")


def deduped(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def twin_feed(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """Stream-stream interval join: two users with the same type of event within ``gap``."""
    a = events.select(F.col("event_id").alias("a_id"), F.col("ts").alias("a_ts"), F.col("user_id").alias("a_user"), "event_type").withWatermark("a_ts", late)
    b = events.select(F.col("event_id").alias("b_id"), F.col("ts").alias("b_ts"), F.col("user_id").alias("b_user"), F.col("event_type").alias("b_type")).withWatermark("b_ts", late)
    near = (F.col("event_type") == F.col("b_type")) & (F.col("b_ts") >= F.col("a_ts")) & (F.col("b_ts") <= F.col("a_ts") + F.expr(f"interval {gap}")) & (F.col("a_user") < F.col("b_user"))
    return a.join(b, near).select("a_id", "b_id", "event_type")


#: Events whose running counts are held at a time.
COUNTED_ROWS = 4096


def running_leader(kinds: list[str], base: np.ndarray, seen: np.ndarray) -> np.ndarray:
    """After each event the place of the kind seen most so far; ``kinds`` are sorted, so ties go to the first by name."""
    counts = base + np.cumsum(seen[:, None] == np.arange(len(kinds)), axis=0)
    return counts.argmax(1)


def verdict_changes(events: DataFrame, forget: str | None = None, late: str = "1 hour") -> DataFrame:
    """Per user a running verdict, the type seen most so far (ties: first by name): a row whenever it changes.

    Events without a type count for nothing. With ``forget`` (such as ``30 days``) the state of a user who
    sends nothing for so long after the last event is dropped, and the user starts anew; without it every user's counts are kept.
    """
    idle = int(pd.Timedelta(forget).total_seconds() * 1000) if forget else None
    typed = events.filter("event_type is not null").withColumn("ms", F.unix_millis(F.col("ts").cast("timestamp")))
    if idle:
        typed = typed.withWatermark("ts", late)

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        counts, verdict = (dict(zip(*state.get[:2], strict=True)), state.get[2]) if state.exists else ({}, None)
        f = pd.concat(frames).sort_values(["ts", "event_id"])
        kinds = sorted({*counts, *f["event_type"]})
        base = np.array([counts.get(k, 0) for k in kinds], np.int64)
        place = {k: i for i, k in enumerate(kinds)}
        seen, ts = f["event_type"].map(place).to_numpy(), f["ts"].to_numpy()
        for at in range(0, len(seen), COUNTED_ROWS):
            part = seen[at : at + COUNTED_ROWS]
            now = running_leader(kinds, base, part)
            base = base + np.bincount(part, minlength=len(kinds))
            before = np.concatenate(([place.get(verdict, -1)], now[:-1]))
            new = np.flatnonzero(now != before)
            yield pd.DataFrame({"user_id": key[0], "ts": ts[at + new], "before": [kinds[i] if i >= 0 else None for i in before[new]], "after": [kinds[i] for i in now[new]]})
            verdict = kinds[now[-1]]
        state.update((kinds, base.tolist(), verdict))
        if idle:
            state.setTimeoutTimestamp(max(int(f["ms"].max()) + idle, state.getCurrentWatermarkMs() + 1))

    timeout = GroupStateTimeout.EventTimeTimeout if idle else GroupStateTimeout.NoTimeout
    return typed.groupBy("user_id").applyInPandasWithState(
        step, "user_id long, ts timestamp, before string, after string", "kinds array<string>, counts array<long>, verdict string", "append", timeout
    )


def upkeep(arrivals: DataFrame, layers: Layers, path: str) -> DataFrame:
    """Assign arriving signatures (node_id, verdict, sig) to the fitted layers and append them to the index at ``path``.

    Centroids stay; ``drift`` says when a rebuild is due. Each micro-batch is one append, so a
    batch that is run again after a failure is found by its number.
    """

    def append(batch: DataFrame, number: int) -> None:
        choose_home(assign(batch, layers), layers).write.mode("overwrite").parquet(f"{path}/batch={number}")

    q = arrivals.writeStream.foreachBatch(append).option("checkpointLocation", fresh_path(arrivals.sparkSession, "upkeep")).trigger(availableNow=True).start()
    q.awaitTermination()
    return arrivals.sparkSession.read.parquet(path)


def drift(nodes: DataFrame, batches: DataFrame) -> DataFrame:
    """``base, arrived``: mean weight at home of the fitted nodes and of the arrivals."""
    home = lambda df: df.agg(F.avg(F.array_min("weights")).alias("w"))
    return home(nodes).withColumnRenamed("w", "base").crossJoin(home(batches).withColumnRenamed("w", "arrived"))


def drain(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run over all that the source holds and read the result: append to Parquet files, else the last complete table.

    Windows that the watermark has not closed are not appended; ``complete`` emits all of them.
    """
    spark = stream.sparkSession
    path = fresh_path(spark, "stream")
    if mode == "append":
        q = stream.writeStream.outputMode("append").format("parquet").option("path", path).option("checkpointLocation", f"{path}-state").trigger(availableNow=True).start()
    else:
        q = stream.writeStream.outputMode(mode).foreachBatch(lambda b, i: b.write.mode("overwrite").parquet(path)).option("checkpointLocation", f"{path}-state").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(path)
