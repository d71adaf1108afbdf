"""The graph of user co-presence kept fresh from the stream of events. Each query runs to the end of what is there (availableNow) and returns its table."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle
from pyspark.sql.types import IntegerType, StructField, StructType

from ..functions.packed import pack, unpack
from ..operators.prepare import normalise_edges
from ..sources.graphs import copresence_lists, copresence_packed, pair_counts, pair_lists
from ..sources.shared import shared_dir, written
from ..sources.tables import table


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """events as a stream; the file's schema is read first, without data."""
    schema = table(spark, sf_dir, "events").schema
    return spark.readStream.schema(schema).option("pathGlobFilter", "*.parquet").parquet(_folder(spark, sf_dir)).withColumn("ts", F.col("ts").cast("timestamp"))


def _folder(spark: SparkSession, sf_dir: str) -> str:
    """A folder that holds the events alone, as the file source asks for."""
    key = f"_seedcluster_events_{sf_dir}"
    found = getattr(spark, key, None)
    if not found:
        found = f"{shared_dir(spark)}/events-{uuid.uuid4().hex}"
        table(spark, sf_dir, "events").repartitionByRange(4, "ts").write.parquet(found)
        setattr(spark, key, found)
    return found


def drained(stream: DataFrame, mode: str = "append", keys: tuple[str, ...] = ()) -> DataFrame:
    """Runs a stream to its end into a Parquet table. Where the mode rewrites rows, each batch writes its own folder: the last one counts (complete), or the last row of each key (update)."""
    spark = stream.sparkSession
    at = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{at}/state").trigger(availableNow=True)
    if mode == "append":
        writer.format("parquet").option("path", f"{at}/out").start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{at}/out")
    writer.foreachBatch(lambda batch, i: batch.write.mode("overwrite").parquet(f"{at}/out/batch={i}")).start().awaitTermination()
    rows = spark.read.schema(StructType([*stream.schema.fields, StructField("batch", IntegerType())])).parquet(f"{at}/out")
    if mode == "complete":
        return rows.join(rows.agg(F.max("batch").alias("batch")), "batch").drop("batch")
    rest = [c for c in stream.columns if c not in keys]
    return rows.groupBy(*keys).agg(F.max_by(F.struct(*rest), "batch").alias("r")).select(*keys, "r.*")


def tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(start, event_type, n) of one-hour windows."""
    s = event_stream(spark, sf_dir).withWatermark("ts", "1 day").groupBy(F.window("ts", "1 hour"), "event_type").count()
    return drained(s, "complete").select(F.unix_seconds("window.start").alias("start"), "event_type", F.col("count").alias("n"))


def sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(start, n) of two-hour windows that begin each hour."""
    s = event_stream(spark, sf_dir).withWatermark("ts", "1 day").groupBy(F.window("ts", "2 hours", "1 hour")).count()
    return drained(s, "complete").select(F.unix_seconds("window.start").alias("start"), F.col("count").alias("n"))


def sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(user_id, start, n) of a user's events less than six hours apart."""
    s = event_stream(spark, sf_dir).withWatermark("ts", "1 day").groupBy(F.session_window("ts", "6 hours"), "user_id").count()
    return drained(s, "complete").select("user_id", F.unix_seconds("session_window.start").alias("start"), F.col("count").alias("n"))


def late_drop(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(start, n) of one-hour windows that the watermark, two hours behind, has closed.

    Every tenth event of the first half comes a whole stream late, in the last file: by then its window is closed, and the watermark drops it. The last event has a
    file of its own in between, since a batch judges lateness by the watermark that the batch before it began with.
    """
    folder = f"{shared_dir(spark)}/late-{uuid.uuid4().hex}"
    e = table(spark, sf_dir, "events")
    half = e.agg(F.min("ts").alias("a"), F.max("ts").alias("b")).select("b", (F.unix_seconds(F.col("a").cast("timestamp")) + F.unix_seconds(F.col("b").cast("timestamp"))).alias("s")).first()
    half, top = half["s"] // 2, half["b"]
    late = (F.col("event_id") % 10 == 0) & (F.unix_seconds(F.col("ts").cast("timestamp")) < half)
    e.where(~late & (F.col("ts") < F.lit(top))).coalesce(1).write.mode("append").parquet(folder)
    e.where(~late & (F.col("ts") == F.lit(top))).coalesce(1).write.mode("append").parquet(folder)
    e.where(late).coalesce(1).write.mode("append").parquet(folder)
    s = spark.readStream.schema(e.schema).option("maxFilesPerTrigger", 1).parquet(folder).withColumn("ts", F.col("ts").cast("timestamp"))
    s = s.withWatermark("ts", "2 hours").groupBy(F.window("ts", "1 hour")).count()
    return drained(s).select(F.unix_seconds("window.start").alias("start"), F.col("count").alias("n"))


def deduplicated(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(event_id, user_id): each event once, though the stream is read twice over."""
    a = event_stream(spark, sf_dir)
    s = a.unionByName(event_stream(spark, sf_dir)).withWatermark("ts", "30 days").dropDuplicatesWithinWatermark(["event_id"])
    return drained(s).select("event_id", "user_id")


def moment_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(event_type, b, users, times, ts) as a stream: the events of a type and of ten minutes in a row, with the begin of the ten minutes; times in microseconds."""
    key = f"_seedcluster_moments_{sf_dir}"
    found = getattr(spark, key, None)
    if not found:
        found = f"{shared_dir(spark)}/moments-{uuid.uuid4().hex}"
        ts = F.col("ts").cast("timestamp")
        e = table(spark, sf_dir, "events").select("event_type", F.floor(F.unix_seconds(ts) / 600).alias("b"), F.col("user_id").cast("bigint").alias("user"), F.unix_micros(ts).alias("at")).dropna()
        rows = e.groupBy("event_type", "b").agg(F.collect_list(F.struct("user", "at")).alias("e"))
        rows.select("event_type", "b", "e.user", "e.at").toDF("event_type", "b", "users", "times").repartitionByRange(4, "b").write.parquet(found)
        setattr(spark, key, found)
    schema = f"event_type {table(spark, sf_dir, 'events').schema['event_type'].dataType.simpleString()}, b long, users array<long>, times array<long>"
    return spark.readStream.schema(schema).parquet(found).withColumn("ts", F.timestamp_seconds(F.col("b") * 600))


def pair_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(u, vs, ns) as a stream: co-presence pairs by a join of two streams with an interval on time, by equality of type and of ten minutes' bucket; the earlier event is in its bucket and the next.

    The state holds a row for a type and bucket, and what meets are two lists of events, whose pairs come out as lists: u, the packed later users, how often each. A pair can come in several rows.
    """
    a = moment_stream(spark, sf_dir).select("event_type", F.col("users").alias("us"), F.col("times").alias("t0s"), F.col("ts").alias("t0"), F.explode(F.array("b", F.col("b") + 1)).alias("b")).withWatermark("t0", "60 days")
    b = moment_stream(spark, sf_dir).select("event_type", F.col("users").alias("vs"), F.col("times").alias("t1s"), F.col("ts").alias("t1"), "b").withWatermark("t1", "60 days")
    met = a.join(b, F.expr("t1 >= t0 AND t1 < t0 + INTERVAL 20 MINUTES") & (a["event_type"] == b["event_type"]) & (a["b"] == b["b"]))
    return met.select("us", "t0s", "vs", "t1s").mapInArrow(_pairs, "u long, vs binary, ns binary")


def _pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The lists of pairs of rows (us, t0s, vs, t1s), whose left events meet the right ones less than ten minutes later."""

    def events(batch: pa.RecordBatch, users: str, times: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        u, t = batch.column(users), batch.column(times)
        return np.repeat(np.arange(len(u)), np.diff(u.offsets.to_numpy())), u.flatten().to_numpy(), t.flatten().to_numpy()

    for batch in batches:
        yield from copresence_lists(events(batch, "us", "t0s"), events(batch, "vs", "t1s"), 600_000_000).to_batches(1000)


def copresence(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(u, v, n): co-presence pairs of the stream, counted in batch."""
    return pair_counts(drained(pair_stream(spark, sf_dir)))


def new_triangles(old: DataFrame, new: DataFrame) -> DataFrame:
    """(a, b, c) of triangles with at least one new edge: three new edges, two and an old one, or one and two old ones, each by its own joins from the new edges; old triangles are not listed.

    Triangles are placed by their edges: of the new ones, the least in order starts the joins, so that each comes once.
    """
    mark = lambda df, x, y, new_: df.select(F.col("src").alias(x), F.col("dst").alias(y), F.lit(new_).alias(f"n{x}{y}"))
    # Edges with an end at a new edge close every new triangle; others are not read.
    ends = new.select(F.explode(F.array("src", "dst")).alias("node")).distinct()
    near = old.join(ends.withColumnRenamed("node", "src"), "src", "left_semi").unionByName(old.join(ends.withColumnRenamed("node", "dst"), "dst", "left_semi")).distinct()
    every = lambda x, y: mark(new, x, y, True).unionByName(mark(near, x, y, False))
    first = mark(new, "a", "b", True).join(every("a", "c"), "a").where("b < c").join(every("b", "c"), ["b", "c"])
    second = mark(new, "a", "c", True).join(every("a", "b"), "a").where("b < c AND NOT nab").join(every("b", "c"), ["b", "c"])
    third = mark(new, "b", "c", True).join(every("a", "b"), "b").where("a < b AND NOT nab").join(every("a", "c").where("NOT nac"), ["a", "c"])
    return first.select("a", "b", "c").unionByName(second.select("a", "b", "c")).unionByName(third.select("a", "b", "c"))


def triangle_delta(spark: SparkSession, edges: DataFrame, batches: int = 3) -> DataFrame:
    """(batch, new): triangles that each batch of a stream of edges closes. foreachBatch joins the batch with the graph so far and then adds it to the graph."""
    at = f"{shared_dir(spark)}/delta-{uuid.uuid4().hex}"
    for i in range(batches):
        edges.where(F.pmod(F.col("src") + F.col("dst"), F.lit(batches)) == i).select("src", "dst").coalesce(1).write.mode("append").parquet(f"{at}/in")
    schema = "src bigint, dst bigint"

    def merge(batch: DataFrame, i: int) -> None:
        session = batch.sparkSession
        # Folders of batches before this one; a batch that runs again after a failure sees and writes the same.
        new = written(normalise_edges(batch), "new")
        old = session.read.schema(f"{schema}, batch int").option("basePath", f"{at}/graph").parquet(*[f"{at}/graph/batch={j}" for j in range(i)]).select("src", "dst") if i else session.createDataFrame([], schema)
        new = written(new.join(old, ["src", "dst"], "left_anti"), "new")
        new_triangles(old, new).agg(F.count(F.lit(1)).alias("new")).write.mode("overwrite").parquet(f"{at}/out/batch={i}")
        new.write.mode("overwrite").parquet(f"{at}/graph/batch={i}")

    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(f"{at}/in")
    stream.writeStream.foreachBatch(merge).option("checkpointLocation", f"{at}/state").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema("new bigint, batch int").parquet(f"{at}/out").select("batch", "new")


class Degrees(StatefulProcessor):
    """Keeps each user's distinct partners in a list state, packed, and gives out the user's degree when it grows. Partners come one a row (nbr) or as packed lists (vs)."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.partners = handle.getListState("partners", "vs binary")

    def handleInputRows(self, key, rows, timerValues) -> Iterator[pd.DataFrame]:
        # One call reads all partners of a user and one adds the new ones: a call for each costs a round trip to the JVM.
        old = np.concatenate([np.zeros(0, np.int64), *(unpack(r[0]) for r in self.partners.get())])
        come = [frame["nbr"].to_numpy() if "nbr" in frame else np.concatenate([unpack(v) for v in frame["vs"]]) for frame in rows]
        new = np.setdiff1d(np.concatenate([old[:0], *come]), old)
        if len(new):
            self.partners.appendList([(pack(new),)])
            yield pd.DataFrame({"user_id": [key[0]], "d": [len(old) + len(new)]})

    def close(self) -> None:
        pass


def user_degree(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(user_id, d): the number of users with whom a user was co-present, kept by a stateful processor over the stream of pairs, which come as packed lists, a user's of a slice of time in a row. State stores are RocksDB's while it runs, as list state asks for."""
    at = f"{shared_dir(spark)}/pairs-{uuid.uuid4().hex}"
    copresence_packed(table(spark, sf_dir, "events"), both=True).select(F.col("u").alias("user_id"), "vs").repartition(4).write.option("compression", "none").parquet(at)
    # A partition of the state starts a worker each batch, whatever it holds: there are as many as the lists ask for, and no more than are set.
    held = spark.read.parquet(at).agg(F.sum(F.octet_length("vs"))).first()[0] or 0
    fit = max(spark.sparkContext.defaultParallelism, held // 16_000_000)
    parts = "spark.sql.shuffle.partitions"
    conf = {"spark.sql.streaming.stateStore.providerClass": "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider", parts: str(min(fit, int(spark.conf.get(parts))))}
    before = {key: spark.conf.get(key, None) for key in conf}
    for key, value in conf.items():
        spark.conf.set(key, value)
    try:
        s = spark.readStream.schema("user_id long, vs binary").option("maxFilesPerTrigger", 2).parquet(at)
        s = s.groupBy("user_id").transformWithStateInPandas(Degrees(), "user_id long, d long", "Update", "none")
        return drained(s, "update", ("user_id",))
    finally:
        for key, value in before.items():
            spark.conf.unset(key) if value is None else spark.conf.set(key, value)


def incremental_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Co-presence edges merged batch by batch through foreachBatch into a table of pair counts, which are kept as lists."""
    at = f"{shared_dir(spark)}/pairs-{uuid.uuid4().hex}"

    def merge(batch: DataFrame, i: int) -> None:
        pair_lists(written(batch, "batch")).write.mode("overwrite").parquet(f"{at}/out/batch={i}")

    pair_stream(spark, sf_dir).writeStream.foreachBatch(merge).option("checkpointLocation", f"{at}/state").trigger(availableNow=True).start().awaitTermination()
    pairs = spark.read.schema("u long, vs binary, ns binary, batch int").parquet(f"{at}/out")
    return normalise_edges(pair_counts(pairs, 2), "u", "v")
