"""Streams: session components on a time axis, windowed fields, and components of edges that keep arriving.

Components only merge as edges arrive, so late edges are safe; segmentations change with late values and are recomputed per
window.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fieldseg.operators.contraction import contract_components
from fieldseg.runtime import shared_dir

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def stream_path(folder: str, name: str) -> str:
    """A table as the path of a file stream; the pattern lets it be one file as well as a folder of files."""
    return f"{folder}/{name}.parque[t]"


def events_stream(spark: SparkSession, path: str, files_per_batch: int | None = None) -> DataFrame:
    reader = spark.readStream.schema(EVENTS).format("parquet")
    if files_per_batch:
        reader = reader.option("maxFilesPerTrigger", files_per_batch)
    return reader.load(path).withColumn("ts", F.col("ts").cast("timestamp"))


def sessions(events: DataFrame, gap: str, late: str | None = None) -> DataFrame:
    """(user_id, first_ts, events): components of the events of a user on the time axis, joined over gaps shorter than `gap`."""
    if late:
        events = events.withWatermark("ts", late)
    return events.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.min("ts").alias("first_ts"), F.count("*").alias("events")).select("user_id", "first_ts", "events")


def windowed_field(events: DataFrame, width: str = "1 day", slide: str | None = None, late: str | None = None) -> DataFrame:
    """(day, id, f): a field over users for each window of time."""
    if late:
        events = events.withWatermark("ts", late)
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    sums = events.groupBy(w.alias("w"), F.col("user_id").alias("id")).agg(F.sum(F.round(F.col("value") * 100).cast("long")).alias("f"))
    return sums.select(F.col("w.start").alias("day"), "id", "f")


def drain(stream: DataFrame, each: Callable[[DataFrame, int], None], mode: str = "append") -> None:
    """Run a stream over what is there and wait for its end; progress is kept in the shared folder."""
    at = f"{shared_dir(stream.sparkSession)}/stream-{uuid.uuid4().hex}"
    query = stream.writeStream.outputMode(mode).foreachBatch(each).option("checkpointLocation", at).trigger(availableNow=True).start()
    query.awaitTermination()


def drained(stream: DataFrame, mode: str = "complete") -> DataFrame:
    """The result table of a stream over what is there (each batch of `complete` replaces the last one's)."""
    spark, path, seen = stream.sparkSession, f"{shared_dir(stream.sparkSession)}/drained-{uuid.uuid4().hex}", []

    def write(batch: DataFrame, n: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/{n}")
        seen.append(n)

    drain(stream, write, mode)
    last = seen[-1:] if mode == "complete" else seen
    return spark.read.schema(stream.schema).parquet(*(f"{path}/{n}" for n in last)) if last else spark.createDataFrame([], stream.schema)


class IncrementalComponents:
    """Labels of the components of all edges so far, in the shared folder; each batch merges labels.

    A batch costs what its edges touch: its ends are renamed to labels, and those that differ are contracted.  The label table
    is written anew with a version number, so a batch that is run twice gives the same table.
    """

    def __init__(self, spark: SparkSession, winner: str = "max"):
        self.spark, self.winner, self.version = spark, winner, 0
        self.path = f"{shared_dir(spark)}/labels-{uuid.uuid4().hex}"

    def labels(self) -> DataFrame:
        if not self.version:
            return self.spark.createDataFrame([], "id long, label long")
        return self.spark.read.schema("id long, label long").parquet(f"{self.path}/{self.version}")

    def update(self, edges: DataFrame, batch: int | None = None) -> None:
        old = self.labels()
        e = edges.select("src", "dst").where("src is not null and dst is not null")
        named = lambda c: old.select(F.col("id").alias(f"_{c}"), F.col("label").alias(f"_l{c}"))
        roots = e.join(named("src"), F.col("src") == F.col("_src"), "left").join(named("dst"), F.col("dst") == F.col("_dst"), "left")
        roots = roots.select(F.coalesce("_lsrc", "src").alias("src"), F.coalesce("_ldst", "dst").alias("dst"))
        moved = contract_components(roots, winner=self.winner).select(F.col("id").alias("_id"), F.col("label").alias("_label"))
        ends = e.select(F.col("src").alias("id")).union(e.select(F.col("dst").alias("id"))).distinct()
        fresh = ends.join(old, "id", "left_anti").select("id", F.col("id").alias("label"))
        new = old.unionByName(fresh).join(moved, F.col("label") == F.col("_id"), "left").select("id", F.coalesce("_label", "label").alias("label"))
        new.write.mode("overwrite").parquet(f"{self.path}/{self.version + 1}")
        self.version += 1


def running_maxima(events: DataFrame, value: str = "value") -> DataFrame:
    """(user_id, ts, value): events larger than the one before and the one after them, sent when the next one has come.

    Each user's last two events are the state; events of a batch are taken in the order of time.
    """
    import pandas as pd

    def step(key, frames, state):
        rows = pd.concat(list(frames)).sort_values("ts")
        last = list(state.get) if state.exists else [None, None, None]
        out = []
        before, now, at = last
        for t, v in zip(rows["ts"], rows[value]):
            if now is not None and now > v and (before is None or now > before):
                out.append((key[0], pd.Timestamp(at), now))
            before, now, at = now, float(v), str(t)
        state.update((before, now, at))
        yield pd.DataFrame(out, columns=["user_id", "ts", "value"])

    return events.select("user_id", "ts", value).groupBy("user_id").applyInPandasWithState(step, "user_id long, ts timestamp, value double", "before double, now double, at string", "append", "NoTimeout")
