"""Graph questions over event streams: windows, late rows, duplicates, state, and joins with a stored oracle."""

from __future__ import annotations

import json

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.scratch import new_scratch_path

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """A folder of event files as a stream."""
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def run_to_table(stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Run all that is available to a Parquet sink (append) or a memory table, and return the result."""
    spark = stream.sparkSession
    place = new_scratch_path(spark, f"stream-{name}")
    if mode == "append":
        stream.writeStream.outputMode("append").format("parquet").option("path", f"{place}/out").option("checkpointLocation", f"{place}/state").trigger(availableNow=True).start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{place}/out")
    table = f"stream_{name}_{abs(hash(place)) % 10**9}"
    stream.writeStream.outputMode(mode).format("memory").queryName(table).option("checkpointLocation", f"{place}/state").trigger(availableNow=True).start().awaitTermination()
    return spark.table(table)


def run_to_batches(stream: DataFrame, name: str, place: str | None = None, mode: str = "update", change=None) -> tuple[DataFrame, list[dict], str]:
    """(every row with the number of its batch as ``batch``, the progress of each batch, the folder), through a foreachBatch sink.

    A batch that runs again after a failure overwrites its own folder, so that every row is there once.  Given the folder
    of an earlier run, the stream goes on where that one stopped.  ``change`` works on each batch before it is written."""
    spark = stream.sparkSession
    place = place or new_scratch_path(spark, f"stream-{name}")

    def keep(batch: DataFrame, number: int) -> None:
        rows = batch if change is None else change(batch)
        rows.withColumn("batch", F.lit(number).cast("long")).write.mode("overwrite").parquet(f"{place}/out/part={number}")

    query = stream.writeStream.outputMode(mode).foreachBatch(keep).option("checkpointLocation", f"{place}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    progress = [{"batch": p["batchId"], "rows": p["numInputRows"], "dropped": sum(o.get("numRowsDroppedByWatermark", 0) for o in p["stateOperators"])} for p in (json.loads(q.json) if hasattr(q, "json") else q for q in query.recentProgress)]
    return spark.read.option("recursiveFileLookup", "true").parquet(f"{place}/out"), progress, place


def latest(rows: DataFrame, keys: list[str]) -> DataFrame:
    """The last update of every key, from rows with their batch."""
    rest = [c for c in rows.columns if c not in (*keys, "batch")]
    return rows.groupBy(*keys).agg(F.max_by(F.struct(*rest), "batch").alias("last")).select(*keys, *[F.col(f"last.{c}").alias(c) for c in rest])


def window_edges(events: DataFrame, size: str = "1 day", delay: str = "40 days") -> DataFrame:
    """(key, a, b): one graph a window, its number as the key; users linked to what their events name, each edge once."""
    start = F.unix_micros(F.window("ts", size)["start"])
    edges = events.withWatermark("ts", delay).select("ts", F.floor(start / 86_400_000_000).cast("bigint").alias("key"), F.col("user_id").alias("a"), (F.get_json_object("props", "$.k").cast("bigint") + 1_000_000).alias("b"))
    return edges.dropDuplicatesWithinWatermark(["key", "a", "b"]).select("key", "a", "b")


def window_counts(events: DataFrame, size: str = "1 day", delay: str = "2 days") -> DataFrame:
    """(start, event_type, n) of tumbling windows; complete mode keeps every window."""
    w = F.window("ts", size)
    return events.withWatermark("ts", delay).groupBy(w.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: str = "12 hours", delay: str = "2 days") -> DataFrame:
    """(user_id, start, n): sessions of a user's events."""
    return events.withWatermark("ts", delay).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def distinct_edges(events: DataFrame, delay: str = "40 days") -> DataFrame:
    """(user_id, event_type): each pair once within the watermark."""
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["user_id", "event_type"]).select("user_id", "event_type")


def incremental_components(edges: DataFrame) -> DataFrame:
    """(key, vid, comp) label changes of insert-only edges (key, a, b): the state of a key is its union forest."""

    def step(key, frames, state):
        root: dict[int, int] = dict(zip(*state.get, strict=True)) if state.exists else {}
        before = dict(root)

        def find(x):
            while root.setdefault(x, x) != x:
                root[x] = root[root[x]]
                x = root[x]
            return x

        for f in frames:
            for a, b in zip(f["a"], f["b"], strict=True):
                p, q = sorted((find(int(a)), find(int(b))))
                root[q] = p
        now = {v: find(v) for v in list(root)}
        state.update((list(now), list(now.values())))
        moved = [v for v in now if before.get(v) != now[v]]
        yield pd.DataFrame({"key": [key[0]] * len(moved), "vid": moved, "comp": [now[v] for v in moved]})

    return edges.groupBy("key").applyInPandasWithState(step, "key long, vid long, comp long", "vids array<long>, roots array<long>", "append", "NoTimeout")


def with_oracle(pairs: DataFrame, component: DataFrame) -> DataFrame:
    """Stream of (qid, u, v) answered by a stored component table: a stream-static join."""
    x, y = component.select(F.col("vid").alias("u"), F.col("comp").alias("cu")), component.select(F.col("vid").alias("v"), F.col("comp").alias("cv"))
    return pairs.join(x, "u").join(y, "v").select("qid", (F.col("cu") == F.col("cv")).alias("connected"))


def click_to_purchase(events: DataFrame, within: str = "1 hour") -> DataFrame:
    """(click_id, purchase_id): stream-stream interval join on the user."""
    c = events.filter("event_type = 'click'").select(F.col("user_id").alias("cu"), F.col("event_id").alias("click_id"), F.col("ts").alias("t0")).withWatermark("t0", "1 day")
    p = events.filter("event_type = 'purchase'").select(F.col("user_id").alias("pu"), F.col("event_id").alias("purchase_id"), F.col("ts").alias("t1")).withWatermark("t1", "1 day")
    return c.join(p, F.expr(f"cu = pu and t1 >= t0 and t1 <= t0 + interval {within}")).select("click_id", "purchase_id")
