"""Event streams: windows, profiles, snapshots of graphs and stateful counts.

Parquet timestamps carry no zone, and watermarks need one: times are counted
from 1970 in universal time whatever the session's zone, and results give window
bounds as seconds.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sparsegrid.plans.lineage import ensure_checkpoint_dir


def instant(ts: str):
    return F.timestamp_micros(F.expr(f"timestampdiff(MICROSECOND, TIMESTAMP_NTZ '1970-01-01 00:00:00', {ts})"))


def stream_events(spark: SparkSession, path: str, files_per_trigger: int = 4) -> DataFrame:
    """The events table as a stream of files, with ``at``: the instant of each event."""
    schema = spark.read.parquet(path).schema
    # a stream names folders; a class of one letter makes a single file look like one
    head, _, name = path.rpartition("/")
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(f"{head}/[{name[0]}]{name[1:]}")
    return stream.withColumn("at", instant("ts"))


def run_to_table(df: DataFrame, mode: str = "complete") -> DataFrame:
    """Runs a streaming query over all files that are there and returns its result as a batch table.

    Each trigger's rows are written as Parquet under the shared checkpoint
    folder; in complete mode the last trigger's are the result.
    """
    spark = df.sparkSession
    base = f"{ensure_checkpoint_dir(spark)}/stream-{uuid.uuid4().hex}"

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{base}/out/batch={number if mode != 'complete' else 0}")

    query = df.writeStream.outputMode(mode).foreachBatch(write).option("checkpointLocation", f"{base}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema(df.schema).parquet(f"{base}/out/*")


def tumbling(events: DataFrame, width: str, slide: str | None = None, late: str = "40 days") -> DataFrame:
    """(start, event_type, n) for windows of ``width``, sliding by ``slide`` where given."""
    window = F.window("at", width, slide) if slide else F.window("at", width)
    return events.withWatermark("at", late).groupBy(window, "event_type").agg(F.count("*").alias("n")).select(F.unix_seconds("window.start").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: str, late: str = "40 days") -> DataFrame:
    """(user_id, start, n): a user's events without a pause of ``gap``."""
    return events.withWatermark("at", late).groupBy(F.session_window("at", gap), "user_id").agg(F.count("*").alias("n")).select("user_id", F.unix_seconds("session_window.start").alias("start"), "n")


def distinct_events(events: DataFrame, late: str = "40 days") -> DataFrame:
    """Events by id, each once within the watermark."""
    return events.withWatermark("at", late).dropDuplicatesWithinWatermark(["event_id"])


def profile(events: DataFrame) -> DataFrame:
    """(user_id, nz): rows per user so far, the streaming form of a row profile."""
    return events.groupBy("user_id").agg(F.count("*").alias("nz"))


def running_degrees(events: DataFrame) -> DataFrame:
    """(user_id, n, last): stateful counts per user by a keyed state function; a row for each user and trigger."""
    import pandas as pd

    def count(key, batches, state):
        n, last = state.get if state.exists else (0, -1)
        for pdf in batches:
            n, last = n + len(pdf), max(last, int(pdf["event_id"].max()))
        state.update((n, last))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "last": [last]})

    return events.select("user_id", "event_id").groupBy("user_id").applyInPandasWithState(count, "user_id bigint, n bigint, last bigint", "n bigint, last bigint", "update", "NoTimeout")


def snapshots(events: DataFrame, width_seconds: int, measure: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """``measure`` of the hand-offs inside every window, in batch form: (start, ...).

    ``measure`` gets distinct (start, src, dst) rows and must aggregate by
    ``start``.  A window's events may lie in many tasks.
    """
    from sparsegrid.sources.tables import neighbours

    base = events.withColumn("start", F.floor(F.unix_seconds("at") / width_seconds) * width_seconds)
    return measure(neighbours(base, ["at", "event_id"], "user_id", "start").where("src <> dst").distinct())


def triangles_by_window(edges: DataFrame) -> DataFrame:
    """(start, edges, triangles) of directed graphs (start, src, dst)."""
    one = edges.select("start", F.col("src").alias("v1"), F.col("dst").alias("v2"))
    two = edges.select("start", F.col("src").alias("v2"), F.col("dst").alias("v3"))
    back = edges.select("start", F.col("src").alias("v3"), F.col("dst").alias("v1"))
    found = one.join(two, ["start", "v2"]).where("v1 < v2 AND v1 < v3").join(back, ["start", "v3", "v1"], "left_semi")
    counts = found.groupBy("start").agg(F.count("*").alias("triangles"))
    return edges.groupBy("start").agg(F.count("*").alias("edges")).join(counts, "start", "left").select("start", "edges", F.coalesce("triangles", F.lit(0)).alias("triangles"))


def closed_windows(events: DataFrame, width_seconds: int, late_seconds: int, measure: Callable[[DataFrame], DataFrame]) -> tuple[DataFrame, int]:
    """A graph job for every window of a stream once it is closed: ``measure`` of its hand-offs, and how many events came too late.

    Each trigger's events are kept by window; a window is closed when the latest
    event is ``late_seconds`` past its end, and all are when the stream ends.
    Events of closed windows are counted and left out.  The kept events lie in
    the shared checkpoint folder; the driver holds one number for each window.
    """
    spark = events.sparkSession
    base = f"{ensure_checkpoint_dir(spark)}/windows-{uuid.uuid4().hex}"
    state = {"latest": None, "late": 0, "closed": set(), "jobs": 0}

    def close(upto: int | None) -> None:
        held = spark.read.parquet(f"{base}/events")
        starts = {r.start for r in held.select("start").distinct().collect()} - state["closed"]
        ready = sorted(s for s in starts if upto is None or s + width_seconds <= upto)
        if ready:
            snapshots(held.where(F.col("start").isin(ready)), width_seconds, measure).write.parquet(f"{base}/out/{state['jobs']}")
            state["closed"].update(ready)
            state["jobs"] += 1

    def take(batch: DataFrame, number: int) -> None:
        batch = batch.withColumn("start", F.floor(F.unix_seconds("at") / width_seconds) * width_seconds)
        late = F.col("start").isin(sorted(state["closed"])) if state["closed"] else F.lit(False)
        seen = batch.agg(F.max(F.unix_seconds("at")).alias("latest"), F.count(F.when(late, 1)).alias("late")).first()
        if seen.latest is None:
            return
        batch.where(~late).write.mode("overwrite").parquet(f"{base}/events/batch={number}")
        state["late"] += seen.late
        state["latest"] = max(seen.latest, state["latest"] or seen.latest)
        close(state["latest"] - late_seconds)

    query = events.writeStream.foreachBatch(take).option("checkpointLocation", f"{base}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    close(None)
    return spark.read.parquet(f"{base}/out/*"), state["late"]


def wedges_within(events: DataFrame, seconds: int, late: str = "2 hours") -> DataFrame:
    """Stream-stream join: pairs of a view and a later purchase of one user within ``seconds``."""
    a = events.where("event_type = 'view'").select(F.col("user_id").alias("u1"), F.col("at").alias("t1"), F.col("event_id").alias("e1")).withWatermark("t1", late)
    b = events.where("event_type = 'purchase'").select(F.col("user_id").alias("u2"), F.col("at").alias("t2"), F.col("event_id").alias("e2")).withWatermark("t2", late)
    return a.join(b, F.expr(f"u1 = u2 AND t2 > t1 AND t2 <= t1 + INTERVAL {seconds} SECONDS")).select("e1", "e2")


def with_customers(events: DataFrame, customers: DataFrame) -> DataFrame:
    """Stream-static join: events with the nation of the customer whose key is the user's id."""
    return events.join(customers.select(F.col("c_custkey").alias("user_id"), "c_nationkey"), "user_id").groupBy("c_nationkey").agg(F.count("*").alias("n"))
