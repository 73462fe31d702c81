"""Forests and edges on streams: incremental, per window, stateful sequences. ``events`` replays as a file stream."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from starforest.forest.loop import minimum_spanning_forest
from starforest.graph.builders import vertex
from starforest.graph.order import canonical_edges, rank_edges
from starforest.runtime import cut, cut_state, read_table, shared_dir


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``events`` as a stream; ``at`` is the event time as TIMESTAMP, which watermarks need."""
    batch = read_table(spark, sf_dir, "events")
    lines = spark.readStream.schema(batch.schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return lines.withColumn("at", F.col("ts").cast("timestamp"))


def replay(stream: DataFrame, *, mode: str = "append", each=None, folder: str | None = None) -> DataFrame:
    """Runs a stream over what is there now; its output (or what ``each(batch, id)`` does to it) is materialised.

    The stream's checkpoint lies in ``folder``; a later call with the same one goes on from there.
    """
    spark = stream.sparkSession
    folder = folder or f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    if each is None and mode == "append":
        w = stream.writeStream.format("parquet").option("path", f"{folder}/out").outputMode("append")
    else:
        def keep(batch: DataFrame, k: int) -> None:
            batch.write.mode("overwrite").parquet(f"{folder}/out")

        w = stream.writeStream.outputMode(mode).foreachBatch(each or keep)
    w.option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{folder}/out") if each is None else stream


class IncrementalForest:
    """Keeps the forest of all edges seen: each batch's forest is that of the old forest and the new edges.

    Nothing but the forest (fewer edges than vertices) is carried from batch to batch, as version ``v<batch>`` in
    ``folder``; no state is held in the driver. Batch ``n`` starts from the last whole version before ``n``, so a batch
    that is delivered again writes the same version, and a stream that is restarted with the same folder goes on.
    Versions before the one a batch starts from are deleted. Without a folder a new one is made in the shared folder:
    give one to any stream that may be restarted.
    """

    def __init__(self, spark: SparkSession, folder: str | None = None, **options) -> None:
        self.folder = folder or f"{shared_dir(spark)}/forest-{uuid.uuid4().hex}"
        self.options = options

    def versions(self, spark: SparkSession) -> list[int]:
        """Whole versions in order; one whose writing was interrupted does not count."""
        path = spark._jvm.org.apache.hadoop.fs.Path(self.folder)
        files = path.getFileSystem(spark._jsc.hadoopConfiguration())
        if not files.exists(path):
            return []
        found = [f.getPath() for f in files.listStatus(path) if f.getPath().getName()[1:].isdigit()]
        whole = [p for p in found if files.exists(spark._jvm.org.apache.hadoop.fs.Path(p, "_SUCCESS"))]
        return sorted(int(p.getName()[1:]) for p in whole)

    def current(self, spark: SparkSession, before: int | None = None) -> DataFrame:
        """The forest, or the one that the batches before ``before`` have left."""
        known = [v for v in self.versions(spark) if before is None or v < before]
        if not known:
            return spark.createDataFrame([], "lo long, hi long, w long")
        return spark.read.parquet(f"{self.folder}/v{known[-1]}")

    def add(self, edges: DataFrame, batch: int) -> None:
        spark = edges.sparkSession
        both = self.current(spark, batch).union(edges.select("lo", "hi", "w"))
        found = minimum_spanning_forest(rank_edges(canonical_edges(both, "lo", "hi", "w")), **self.options).forest
        found.select("lo", "hi", "w").write.mode("overwrite").parquet(f"{self.folder}/v{batch}")
        for old in [v for v in self.versions(spark) if v < batch][:-1]:
            path = spark._jvm.org.apache.hadoop.fs.Path(f"{self.folder}/v{old}")
            path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def stream_forest(edges: DataFrame, *, folder: str | None = None, **options) -> DataFrame:
    """Forest of an edge stream ``(lo, hi, w)``. With a ``folder`` a later call goes on where the last one ended or broke off."""
    spark = edges.sparkSession
    keeper = IncrementalForest(spark, folder and f"{folder}/forest", **options)
    replay(edges, each=keeper.add, folder=folder)
    return keeper.current(spark)


def merge_forests(forests: list[DataFrame], **options) -> DataFrame:
    """Forest of a union from the forests of its parts: window slices merge this way."""
    spark = forests[0].sparkSession
    every = forests[0].select("lo", "hi", "w")
    for f in forests[1:]:
        every = every.union(f.select("lo", "hi", "w"))
    return minimum_spanning_forest(rank_edges(canonical_edges(every, "lo", "hi", "w")), **options).forest.select("lo", "hi", "w")


def _tagged_forest(edges: DataFrame, tag: str, **options) -> DataFrame:
    """``(tag, lo, hi, w)``: the forests of all groups at once, as one forest of their disjoint union."""
    most = edges.agg(F.max(tag), F.max("hi")).first()
    if most[0] is None:
        return edges.select(tag, "lo", "hi", "w")
    span = most[0] + 1
    if (most[1] + 1) * span >= 1 << 62:
        raise ValueError("vertex ids times the number of groups exceed a LONG")
    own = edges.select((F.col("lo") * span + F.col(tag)).alias("lo"), (F.col("hi") * span + F.col(tag)).alias("hi"), "w")
    found = minimum_spanning_forest(rank_edges(canonical_edges(own, "lo", "hi", "w")), **options).forest
    return found.select((F.col("lo") % span).alias(tag), F.expr(f"lo div {span}").alias("lo"), F.expr(f"hi div {span}").alias("hi"), "w")


def sliding_forest(edges: DataFrame, length: int, **options) -> DataFrame:
    """``(win, lo, hi, w)`` of ``edges(slice, lo, hi, w)`` with slices from 0: window ``win`` holds its slice and the
    ``length - 1`` before. Each slice is thinned to its own forest first; only those rows are copied into windows.
    """
    thin = cut_state(_tagged_forest(edges, "slice", **options))
    copied = thin.withColumn("win", F.explode(F.sequence(F.col("slice"), F.col("slice") + (length - 1))))
    return _tagged_forest(copied.select("win", "lo", "hi", "w"), "win", **options)


def daily_distinct(events: DataFrame, *, late: str = "1 hour") -> DataFrame:
    """``(user_id, event_type, day)`` once each: repeats within the watermark are dropped by state."""
    keyed = events.withWatermark("at", late).withColumn("day", F.to_date("ts"))
    return keyed.dropDuplicates(["user_id", "event_type", "day"]).select("user_id", "event_type", "day")


def follow_ups(clicks: DataFrame, buys: DataFrame, *, within: str = "1 hour", late: str = "1 hour") -> DataFrame:
    """``(user_id, click, buy)``: purchases less than ``within`` after a click, stream against stream; state is bounded by the watermarks."""
    a = clicks.where("event_type = 'click'").withWatermark("at", late).select("user_id", F.col("event_id").alias("click"), F.col("at").alias("t0"))
    b = buys.where("event_type = 'purchase'").withWatermark("at", late).select(F.col("user_id").alias("u"), F.col("event_id").alias("buy"), F.col("at").alias("t1"))
    return a.join(b, F.expr(f"user_id = u and t1 >= t0 and t1 < t0 + interval {within}")).select("user_id", "click", "buy")


def user_type_edges(events: DataFrame) -> DataFrame:
    """Stateless edges of an event: its user and its type, weighing the value in cents."""
    kind = F.crc32(F.col("event_type").cast("binary"))
    return events.select(F.least(vertex("user_id", "user"), vertex(kind, "event")).alias("lo"), F.greatest(vertex("user_id", "user"), vertex(kind, "event")).alias("hi"), F.round(F.col("value") * 100).cast("long").alias("w"))


def windowed_activity(events: DataFrame, *, length: str = "1 day", late: str = "1 hour") -> DataFrame:
    """``(start, user_id, n)`` of closed windows; rows later than the watermark are dropped."""
    return events.withWatermark("at", late).groupBy(F.window("at", length).alias("win"), "user_id").agg(F.count("*").alias("n")).select(F.col("win.start").alias("start"), "user_id", "n")


def session_activity(events: DataFrame, *, gap: str = "2 hours") -> DataFrame:
    """``(start, user_id, n)`` of sessions that a pause of ``gap`` ends."""
    return events.withWatermark("at", "1 hour").groupBy(F.session_window("at", gap).alias("win"), "user_id").agg(F.count("*").alias("n")).select(F.col("win.start").alias("start"), "user_id", "n")


def sequence_stream(events: DataFrame) -> DataFrame:
    """``(a, b, w)``: each event of a user with the one before, across batches, by state per user."""

    def step(key: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        rows = pd.concat(list(batches)).sort_values(["us", "event_id"])
        ids, at = rows["event_id"].tolist(), rows["us"].tolist()
        if state.exists:
            last = state.get
            ids, at = [last[0], *ids], [last[1], *at]
        state.update((ids[-1], at[-1]))
        yield pd.DataFrame({"a": ids[:-1], "b": ids[1:], "w": [y - x for x, y in zip(at, at[1:], strict=False)]})

    timed = events.select("user_id", "event_id", F.unix_micros("at").alias("us"))
    return timed.groupBy("user_id").applyInPandasWithState(step, "a long, b long, w long", "last long, us long", "append", "NoTimeout")


def running_components(edges: DataFrame, vertices: int, **options) -> int:
    """Number of trees after a stream: vertices less accepted edges."""
    return vertices - stream_forest(edges, **options).count()


__all__ = ["IncrementalForest", "cut", "daily_distinct", "event_stream", "follow_ups", "merge_forests", "replay", "running_components", "sequence_stream", "session_activity", "sliding_forest", "stream_forest", "user_type_edges", "windowed_activity"]
