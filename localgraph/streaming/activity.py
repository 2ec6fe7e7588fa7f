"""Streams that keep graphs fresh: events replayed as a file stream, drained with availableNow."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..graph import Graph
from ..session import cut, drop, shared_dir
from ..sources.builders import pairs, vid


def source(spark: SparkSession, d: str) -> DataFrame:
    """events.parquet as a stream; ts as a timestamp."""
    schema = spark.read.parquet(f"{d}/events.parquet").schema
    s = spark.readStream.schema(schema).option("pathGlobFilter", "events*.parquet").parquet(d)
    return s.withColumn("ts", F.col("ts").cast("timestamp"))


def drain(stream: DataFrame, mode: str, keys: list[str] | None = None) -> DataFrame:
    """Run to the end of the input and return the result rows.

    Each micro-batch is written to the shared folder by foreachBatch; in update mode the last version of a key wins.
    """
    spark = stream.sparkSession
    base = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"

    def keep(batch: DataFrame, n: int) -> None:
        batch.withColumn("batch", F.lit(n)).write.mode("overwrite").parquet(f"{base}/out/part={n}")

    q = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{base}/state").trigger(availableNow=True).foreachBatch(keep).start()
    q.awaitTermination()
    out = spark.read.parquet(f"{base}/out").drop("part")
    if mode != "update":
        return out.drop("batch")
    rest = [c for c in out.columns if c not in keys]
    return out.groupBy(*keys).agg(F.max_by(F.struct(*rest), "batch").alias("r")).select(*keys, *[f"r.{c}" for c in rest if c != "batch"])


def windows(spark, d: str, length: str, slide: str | None = None) -> DataFrame:
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    agg = source(spark, d).withWatermark("ts", "1 hour").groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n"))
    return drain(agg.select(F.unix_seconds("w.start").alias("start"), "event_type", "n"), "complete")


def sessions(spark, d: str, gap: str) -> DataFrame:
    agg = source(spark, d).withWatermark("ts", "1 hour").groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))
    return drain(agg.select(F.unix_seconds("w.start").alias("start"), "user_id", "n"), "complete")


def distinct_arcs(spark, d: str) -> DataFrame:
    """User - hour arcs, duplicates dropped inside the watermark."""
    e = source(spark, d).withColumn("hour", F.floor(F.unix_seconds("ts") / 3600)).withWatermark("ts", "365 days")
    return drain(e.dropDuplicatesWithinWatermark(["user_id", "hour"]).select("user_id", "hour"), "append")


def running_degree(spark, d: str) -> DataFrame:
    return drain(source(spark, d).groupBy("user_id").agg(F.count("*").alias("deg")), "update", ["user_id"])


def static_drift(spark, d: str, tracked: DataFrame) -> DataFrame:
    """Events inside and outside a stored set of users, per type."""
    e = source(spark, d).join(tracked.select("user_id", F.lit(1).alias("inside")), "user_id", "left")
    agg = e.groupBy("event_type").agg(F.count("inside").alias("inside"), F.count(F.when(F.col("inside").isNull(), 1)).alias("outside"))
    return drain(agg, "complete")


def interval_join(spark, d: str, first: str, second: str, minutes: int) -> DataFrame:
    """Pairs of two event types of one user, the second at most `minutes` after the first."""
    one = source(spark, d).filter(F.col("event_type") == first).select(F.col("event_id").alias("a"), F.col("user_id").alias("u"), F.col("ts").alias("ta")).withWatermark("ta", "1 day")
    two = source(spark, d).filter(F.col("event_type") == second).select(F.col("event_id").alias("b"), "user_id", F.col("ts").alias("tb")).withWatermark("tb", "1 day")
    hit = one.join(two, F.expr(f"u = user_id and tb >= ta and tb <= ta + interval {minutes} minutes"))
    return drain(hit.select("a", "b"), "append")


def stateful_volume(spark, d: str) -> DataFrame:
    """Per user: events and distinct hours, kept by a custom state."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupStateTimeout

    def update(key, batches, state):
        n, hours = state.get if state.exists else (0, [])
        seen = set(hours)
        for b in batches:
            n += len(b)
            seen |= set(b["hour"])
        state.update((n, sorted(int(h) for h in seen)))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "hours": [len(seen)]})

    e = source(spark, d).select("user_id", F.floor(F.unix_seconds("ts") / 3600).alias("hour"))
    out = e.groupBy("user_id").applyInPandasWithState(update, "user_id long, n long, hours long", "n long, hours array<long>", "update", GroupStateTimeout.NoTimeout)
    return drain(out, "update", ["user_id"])


def arrivals(parts: list[DataFrame], plan: Callable[[DataFrame], DataFrame], sink: Callable[[DataFrame, int], None], mode: str, base: str) -> None:
    """Deliver the parts one after the other as files of one stream, draining it after each.

    Every part restarts the query from the checkpoint that the one before left, so state, watermark and batch numbers go on.
    """
    for part in parts:
        part.write.mode("append").parquet(f"{base}/in")
        stream = part.sparkSession.readStream.schema(part.schema).parquet(f"{base}/in")
        q = plan(stream).writeStream.outputMode(mode).option("checkpointLocation", f"{base}/state").trigger(availableNow=True).foreachBatch(sink).start()
        q.awaitTermination()


def late_rows(spark: SparkSession, d: str, last: str, length: str, delay: str) -> DataFrame:
    """Per window: rows counted by a stream in which one event type arrives after all others, and rows past its watermark.

    The stream's state holds open windows only. Rows behind the watermark are not lost: they are counted from the stored events.
    """
    e = spark.read.parquet(f"{d}/events.parquet").select("event_type", F.col("ts").cast("timestamp").alias("ts")).filter("ts is not null")
    after = F.coalesce(F.col("event_type") == last, F.lit(False))
    base = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    w = F.window("ts", length).alias("w")

    def plan(stream: DataFrame) -> DataFrame:
        agg = stream.withWatermark("ts", delay).groupBy(w).agg(F.count("*").alias("n"))
        return agg.select(F.unix_seconds("w.start").alias("start"), "n")

    def keep(batch: DataFrame, n: int) -> None:
        batch.withColumn("batch", F.lit(n)).write.mode("overwrite").parquet(f"{base}/out/part={n}")

    arrivals([e.filter(~after), e.filter(after)], plan, keep, "update", base)
    counted = spark.read.parquet(f"{base}/out").groupBy("start").agg(F.max_by("n", "batch").alias("n"))
    every = e.groupBy(w).agg(F.count("*").alias("total")).select(F.unix_seconds("w.start").alias("start"), "total")
    n = F.coalesce("n", F.lit(0))
    return every.join(counted, "start", "left").select("start", n.alias("n"), (F.col("total") - n).alias("late"))


class Buckets:
    """Arcs in buckets of their first vertex, grown by micro-batches; a batch rewrites only the buckets that it touches.

    Batch n writes the folders n/bucket=b; the live version of a bucket is the one of the greatest n. A repeated batch
    overwrites its own folders and reads only earlier ones, so it changes nothing. Versions that no repetition can need
    go when the next batch begins.
    """

    def __init__(self, spark: SparkSession, path: str, buckets: int = 16):
        self.spark, self.path, self.buckets = spark, path, buckets

    def _versions(self) -> dict[int, list[tuple[int, str]]]:
        """bucket -> its (batch, folder), oldest first; at most two of a bucket outlive a batch."""
        at = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{self.path}/*/bucket=*")
        self._fs = at.getFileSystem(self.spark._jsparkSession.sessionState().newHadoopConf())
        out: dict[int, list[tuple[int, str]]] = {}
        for status in self._fs.globStatus(at) or []:
            here = status.getPath()
            out.setdefault(int(here.getName().split("=")[1]), []).append((int(here.getParent().getName()), here.toString()))
        return {b: sorted(v) for b, v in out.items()}

    def _read(self, folders: list[str]) -> DataFrame:
        return self.spark.read.schema("src long, dst long").parquet(*folders) if folders else self.spark.createDataFrame([], "src long, dst long")

    def merge(self, arcs: DataFrame, n: int) -> None:
        """Add the arcs (src, dst) of batch n."""
        new = cut(arcs.select("src", "dst"), "upsert")
        bucket = F.pmod("src", F.lit(self.buckets)).cast("int")
        touched = {r.b for r in new.select(bucket.alias("b")).distinct().collect()}
        old = []
        for b, versions in self._versions().items():
            before = [v for v in versions if v[0] < n]
            for _, folder in before[:-1]:
                self._fs.delete(self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(folder), True)
            if b in touched and before:
                old.append(before[-1][1])
        both = self._read(old).union(new).distinct().withColumn("bucket", bucket)
        # ranges of all three columns spread the arcs of a hub over several files of its bucket
        rows = both.repartitionByRange("bucket", "src", "dst").sortWithinPartitions("bucket", "src", "dst")
        rows.write.mode("overwrite").partitionBy("bucket").parquet(f"{self.path}/{n}")
        drop(new)

    def graph(self) -> Graph:
        return Graph(self._read([v[-1][1] for v in self._versions().values()]))


def upserted(spark: SparkSession, d: str, split: str) -> Graph:
    """User - hour graph grown by a stream: events before the given time first, the others after them."""
    e = spark.read.parquet(f"{d}/events.parquet").select("user_id", F.col("ts").cast("timestamp").alias("ts"))
    base = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    table = Buckets(spark, f"{base}/arcs")
    early = F.coalesce(F.col("ts") < F.lit(split).cast("timestamp"), F.lit(False))

    def sink(batch: DataFrame, n: int) -> None:
        hour = F.floor(F.unix_micros("ts") / 3_600_000_000)
        table.merge(Graph.from_edges(pairs(batch, vid("user_id", "user"), vid(hour, "hour"))).arcs, n)

    arrivals([e.filter(early), e.filter(~early)], lambda stream: stream, sink, "append", base)
    return table.graph()


def against_batch(stream: DataFrame, batch: DataFrame) -> DataFrame:
    """Arcs of two graphs: how many each has and how many both have."""
    tag = stream.select("src", "dst", F.lit(1).alias("s"), F.lit(0).alias("b")).union(batch.select("src", "dst", F.lit(0), F.lit(1)))
    n = tag.groupBy("src", "dst").agg(F.sum("s").alias("s"), F.sum("b").alias("b"))
    return n.agg(F.sum("s").alias("arcs_stream"), F.sum("b").alias("arcs_batch"), F.count(F.when((F.col("s") == 1) & (F.col("b") == 1), 1)).alias("arcs_both"))
