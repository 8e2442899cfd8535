"""Streams of call records: windowed edges and shares, sessions, deduplication, incremental hops, stateful callees."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from netprop import session
from netprop.operators import problems
from netprop.operators.graphs import Graph


def windowed_edges(stream: DataFrame, width: str = "1 day", late: str = "1 hour") -> DataFrame:
    """Edge weights per tumbling window, rows later than ``late`` dropped by the watermark."""
    return stream.withWatermark("ts", late).groupBy(F.window("ts", width), "src", "dst").agg(F.sum("dur").alias("w")).select("window", "src", "dst", "w")


def windowed_share(stream: DataFrame, tariff: str, width: str = "7 days", slide: str = "1 day", late: str = "1 hour") -> DataFrame:
    mine = F.sum(F.when(F.col("tariff") == tariff, F.col("dur")).otherwise(0))
    return stream.withWatermark("ts", late).groupBy(F.window("ts", width, slide), F.col("src").alias("id")).agg((mine / F.nullif(F.sum("dur"), F.lit(0))).alias("p"))


def sessions(stream: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "src").agg(F.count("*").alias("calls"), F.sum("dur").alias("dur"))


def labelled_calls(stream: DataFrame, labels: DataFrame) -> DataFrame:
    """Stream-static join: the caller's label on each call."""
    return stream.join(labels.withColumnRenamed("id", "src"), "src", "left")


def returned_calls(stream: DataFrame, other: DataFrame, within: str = "10 minutes", late: str = "1 hour") -> DataFrame:
    """Stream-stream join: calls that go back within an interval."""
    a = stream.withWatermark("ts", late).select(F.col("ts").alias("at"), F.col("src").alias("a"), F.col("dst").alias("b"))
    b = other.withWatermark("ts", late).select("ts", "src", "dst")
    return a.join(b, F.expr(f"a = dst AND b = src AND ts > at AND ts <= at + INTERVAL {within}"))


def drain(stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Run a stream over what there is into a table of the shared folder and return it."""
    spark = stream.sparkSession
    out = session.fresh_path(spark, name)
    if mode == "append":
        query = stream.writeStream.format("parquet").outputMode("append").option("checkpointLocation", out + "-at").trigger(availableNow=True).start(out)
    else:  # the last full result replaces what came before

        def put(batch, number):
            batch.write.mode("overwrite").parquet(out)

        query = stream.writeStream.outputMode(mode).option("checkpointLocation", out + "-at").trigger(availableNow=True).foreachBatch(put).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def upserted(stream: DataFrame, name: str, keys: list[str]) -> DataFrame:
    """Run a stream in update mode: each batch writes the rows it changed, and the last one of each key counts. State is bounded by the watermark."""
    spark = stream.sparkSession
    out = session.fresh_path(spark, name)

    def put(batch, number):
        batch.write.mode("overwrite").parquet(f"{out}/batch={number}")  # a batch that runs again writes the same place

    stream.writeStream.outputMode("update").option("checkpointLocation", out + "-at").trigger(availableNow=True).foreachBatch(put).start().awaitTermination()
    rows = spark.read.option("basePath", out).schema(stream.schema.add("batch", "integer")).parquet(f"{out}/batch=*")
    return rows.groupBy(*keys).agg(F.max_by(F.struct(*stream.columns), "batch").alias("_row")).select("_row.*")


def replayed(df: DataFrame, files: int = 4) -> DataFrame:
    """A frame as a stream: files of ascending time, written one after the other, read one a batch."""
    spark = df.sparkSession
    path = session.fresh_path(spark, "replay")
    dealt = session.stored(df.repartitionByRange(files, "ts").sortWithinPartitions("ts").withColumn("_file", F.spark_partition_id()), "replay-rows")
    for k in range(files):  # a file source takes files by the time they were written
        dealt.where(F.col("_file") == k).drop("_file").coalesce(1).sortWithinPartitions("ts").write.mode("append").parquet(path)
    return spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(path)


def _stamped(df: DataFrame) -> DataFrame:
    return df.withColumn("ts", F.col("ts").cast("timestamp"))


def closed(df: DataFrame) -> DataFrame:
    """``df`` and, one batch later, a row far ahead in time (null but for ``ts``), by which the watermark passes all others."""
    ahead = df.agg((F.max("ts") + F.expr("INTERVAL 1000 DAYS")).alias("ts")).where("ts is not null")
    return df.unionByName(ahead, allowMissingColumns=True)


def windowed_edges_of(spark: SparkSession, calls: DataFrame, width: str) -> DataFrame:
    """Edge weights per day of a replayed log, under a watermark."""
    edges = windowed_edges(replayed(_stamped(calls)), width)
    return upserted(edges.select("window.start", "src", "dst", "w"), "windows", ["start", "src", "dst"]).select(F.col("start").cast("date").alias("day"), "src", "dst", "w")


def windowed_share_of(spark: SparkSession, calls: DataFrame, tariff: str) -> DataFrame:
    shares = windowed_share(replayed(_stamped(calls)), tariff)
    return upserted(shares.select("window.start", "id", "p"), "shares", ["start", "id"])


def sessions_of(spark: SparkSession, calls: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """Sessions that the watermark has closed: all, after a row far ahead."""
    found = sessions(replayed(closed(_stamped(calls))), gap)
    return drain(found.select("session_window.start", "src", "calls", "dur"), "sessions").where("src is not null")


def labelled_calls_of(spark: SparkSession, calls: DataFrame, labels: DataFrame) -> DataFrame:
    return drain(labelled_calls(replayed(_stamped(calls)), labels), "labelled")


def returned_calls_of(spark: SparkSession, calls: DataFrame) -> DataFrame:
    rows = _stamped(calls)
    return drain(returned_calls(replayed(rows), replayed(rows), late="30 days"), "returned")


def late_split_of(spark: SparkSession, calls: DataFrame, late: str = "1 hour") -> DataFrame:
    """Counts of rows on time and late, by tariff. Each batch is split at the latest time of the batches before, less ``late``; late rows go to a side table."""
    out = session.fresh_path(spark, "split")
    seen: dict[int, object] = {}

    def step(batch, number):
        mark = seen.get(number - 1)
        on_time, behind = late_split(batch, mark) if mark is not None else (batch, batch.where("false"))
        both = on_time.withColumn("late", F.lit(False)).unionByName(behind.withColumn("late", F.lit(True)))
        both.write.mode("overwrite").parquet(f"{out}/batch={number}")
        newest = batch.agg((F.max("ts") - F.expr(f"INTERVAL {late}")).alias("m")).first()["m"]
        seen[number] = newest if mark is None or newest is None or newest > mark else mark

    stream = replayed_late(_stamped(calls))
    stream.writeStream.foreachBatch(step).option("checkpointLocation", out + "-at").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema.add("late", "boolean")).parquet(f"{out}/batch=*").groupBy("tariff", "late").agg(F.count("*").alias("n"))


#: Every so many hundredths of a second's worth of talk marks a call that is delayed.
LATE_EVERY = 97


def replayed_late(df: DataFrame) -> DataFrame:
    """Two batches: all calls but those whose ``dur`` is a multiple of LATE_EVERY, then those."""
    spark = df.sparkSession
    path = session.fresh_path(spark, "replay-late")
    behind = F.col("dur") % LATE_EVERY == 0
    for rows in (df.where(~behind), df.where(behind)):
        rows.coalesce(1).write.mode("append").parquet(path)
    return spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(path)


def deduplicated_counts(spark: SparkSession, events: DataFrame) -> DataFrame:
    """Every event sent twice counts once."""
    rows = _stamped(events.select("event_id", "ts", "event_type"))
    stream = replayed(rows.unionByName(rows)).withWatermark("ts", "30 days").dropDuplicatesWithinWatermark(["event_id"])
    return drain(stream, "once").groupBy("event_type").agg(F.count("*").alias("n"))


def incremental_hops(state: DataFrame, known: Graph, new_edges: DataFrame, options=None) -> DataFrame:
    """Hop counts after edges were added: these can only shorten paths, so the ends they improve are the frontier."""
    graph = Graph.of(known.edges.unionByName(new_edges.select("src", "dst", "w")), name=known.name)
    offers = new_edges.join(state.select(F.col("id").alias("src"), "hops"), "src").where("hops is not null").groupBy(F.col("dst").alias("id")).agg(F.min(F.col("hops") + 1).alias("offer"))
    now = graph.vertices.join(state, "id", "left").join(offers, "id", "left")
    better = F.col("offer").isNotNull() & (F.col("hops").isNull() | (F.col("offer") < F.col("hops")))
    start = now.select("id", F.when(better, F.col("offer")).otherwise(F.col("hops")).alias("hops"), better.alias("_active"))
    from netprop.operators.engines import Resident

    return Resident().run(graph, problems.hop_program(), start, None, "quiescent", options).state


def incremental_hops_of(spark: SparkSession, graph: Graph, source: int, batches: int) -> DataFrame:
    """Edges arriving as a stream of files; each batch of it brings hop counts up to date, from those of the batch before."""
    from netprop.operators.engines import EngineOptions

    path, out = session.fresh_path(spark, "arriving"), session.fresh_path(spark, "hops")
    edges = session.stored(graph.edges.select("src", "dst", "w").withColumn("_batch", F.pmod(F.xxhash64("src", "dst"), F.lit(batches))), "edges")
    for k in range(batches):
        edges.where(F.col("_batch") == k).drop("_batch").coalesce(1).write.mode("append").parquet(path)
    spark.createDataFrame([(source, 0)], "id long, hops int").write.parquet(f"{out}/state=-1")
    options = EngineOptions(partitions=8)

    def step(batch, number):
        batch.write.mode("overwrite").parquet(f"{out}/edges={number}")
        kinds = {"state": "id long, hops int", "edges": "src long, dst long, w double"}
        read = lambda what, n: spark.read.schema(kinds[what]).parquet(f"{out}/{what}={n}")
        known = Graph(spark.read.schema(kinds["edges"]).parquet(*[f"{out}/edges={n}" for n in range(number)]) if number else read("edges", 0).where("false"), name=graph.name)
        incremental_hops(read("state", number - 1), known, read("edges", number), options).write.mode("overwrite").parquet(f"{out}/state={number}")

    stream = spark.readStream.schema("src long, dst long, w double").option("maxFilesPerTrigger", 1).parquet(path)
    query = stream.writeStream.foreachBatch(step).option("checkpointLocation", out + "-at").trigger(availableNow=True).start()
    query.awaitTermination()
    last = query.lastProgress["batchId"]
    return spark.read.schema("id long, hops int").parquet(f"{out}/state={last}")


def last_callee_of(spark: SparkSession, calls: DataFrame) -> DataFrame:
    """Latest callee of each caller, kept as the maximum of (time, callee) by the stream's own state."""
    stream = replayed(_stamped(calls))
    latest = stream.groupBy("src").agg(F.max(F.struct("ts", "dst")).alias("x")).select("src", F.col("x.dst").alias("dst"))
    return drain(latest, "callee", "complete")


def late_split(batch: DataFrame, watermark) -> tuple[DataFrame, DataFrame]:
    """Rows of a batch on time, and late ones for a side table."""
    late = F.col("ts") < F.lit(watermark)
    return batch.where(~late), batch.where(late)


def windowed_influence(stream: DataFrame, labels: DataFrame, out: str, rounds: int = 3):
    """Influence over the calls of each batch, started from the labels given; one table per batch under ``out``."""

    def step(batch, number):
        edges = batch.groupBy("src", "dst").agg(F.sum("dur").cast("double").alias("w")).where("w > 0")
        if batch.take(1):
            problems.relational_influence(Graph(session.stored(edges, "window-edges")), labels, rounds).state.write.mode("overwrite").parquet(f"{out}/batch={number}")

    return stream.writeStream.foreachBatch(step).option("checkpointLocation", out + "-at").trigger(availableNow=True)


def windowed_influence_of(spark: SparkSession, calls: DataFrame, labels: DataFrame, rounds: int = 3) -> DataFrame:
    """``(batch, id, p)`` of the two batches of :func:`replayed_late`."""
    out = session.fresh_path(spark, "windowed")
    windowed_influence(replayed_late(_stamped(calls)), session.stored(labels, "labels"), out, rounds).start().awaitTermination()
    return spark.read.option("basePath", out).schema("id long, p double, batch int").parquet(f"{out}/batch=*").select("batch", "id", "p")
