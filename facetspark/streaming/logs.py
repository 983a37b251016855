"""A query log as a stream: counts that grow by increments, windows, sessions, duplicates."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from facetspark.sources.storage import scratch


def events_stream(spark: SparkSession, path: str, files_per_batch: int = 1) -> DataFrame:
    """Events with event time as timestamp (watermarks need it) and the query text."""
    schema = spark.read.parquet(path).schema
    # a pattern, as the file source takes folders and patterns but no single file
    pattern = path[:-1] + f"[{path[-1]}]"
    rows = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(pattern)
    k = F.get_json_object("props", "$.k")
    query = F.when(F.col("event_id") % 2 == 0, F.col("event_type")).otherwise(F.concat_ws(" k", "event_type", k))
    return rows.select("event_id", "user_id", F.col("ts").cast("timestamp").alias("ts"), query.alias("query"))


def run_increments(stream: DataFrame, delta, label: str) -> DataFrame:
    """Run to the end of the available input; each batch writes its own ``delta`` once.

    A batch that is tried again overwrites its own folder, so counts stay exact.
    """
    spark = stream.sparkSession
    out, state = scratch(spark, label), scratch(spark, f"{label}-state")

    def write(batch: DataFrame, number: int) -> None:
        delta(batch).write.mode("overwrite").parquet(f"{out}/batch={number}")

    query = stream.writeStream.foreachBatch(write).option("checkpointLocation", state).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.parquet(out).drop("batch")


def query_counts(spark: SparkSession, path: str) -> DataFrame:
    """``query, freq`` kept incrementally."""
    parts = run_increments(events_stream(spark, path), lambda b: b.groupBy("query").agg(F.count("*").alias("freq")), "counts")
    return parts.groupBy("query").agg(F.sum("freq").alias("freq"))


def daily_counts(spark: SparkSession, path: str) -> DataFrame:
    """``day, n``: tumbling windows of one day, late rows included since increments add up."""
    parts = run_increments(events_stream(spark, path), lambda b: b.groupBy(F.window("ts", "1 day").alias("w")).agg(F.count("*").alias("n")), "daily")
    return parts.groupBy(F.date_format("w.start", "yyyy-MM-dd").alias("day")).agg(F.sum("n").alias("n"))


def distinct_events(spark: SparkSession, path: str) -> DataFrame:
    """``query, n`` of a log that delivers every event twice, each counted once within the watermark."""
    twice = events_stream(spark, path)
    twice = twice.unionByName(events_stream(spark, path)).withWatermark("ts", "60 days").dropDuplicatesWithinWatermark(["event_id"])
    parts = run_increments(twice, lambda b: b.groupBy("query").agg(F.count("*").alias("n")), "distinct")
    return parts.groupBy("query").agg(F.sum("n").alias("n"))


def closed_sessions(spark: SparkSession, path: str, gap: str = "8 hours", late: str = "1 day") -> DataFrame:
    """``user_id, start, n`` of sessions that the watermark has closed; open ones are held back."""
    out, state = scratch(spark, "sessions"), scratch(spark, "sessions-state")
    windows = events_stream(spark, path).withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n"))
    query = windows.select("user_id", F.col("w.start").alias("start"), "n").writeStream.format("parquet").option("path", out).option("checkpointLocation", state).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.schema("user_id long, start timestamp, n long").parquet(out)


def _collected(stream: DataFrame, label: str) -> DataFrame:
    """The rows that an appending query has written by the end of the available input."""
    spark = stream.sparkSession
    out, state = scratch(spark, label), scratch(spark, f"{label}-state")
    stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", state).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def sliding_counts(spark: SparkSession, path: str) -> DataFrame:
    """``start, n``: windows of a day, one every six hours; increments add up, so late rows count."""
    parts = run_increments(events_stream(spark, path), lambda b: b.groupBy(F.window("ts", "1 day", "6 hours").alias("w")).agg(F.count("*").alias("n")), "sliding")
    return parts.groupBy(F.date_format("w.start", "yyyy-MM-dd HH").alias("start")).agg(F.sum("n").alias("n"))


def segment_counts(spark: SparkSession, path: str, customers: DataFrame) -> DataFrame:
    """``c_mktsegment, n``: the stream joined with a static table."""
    joined = events_stream(spark, path).join(customers.select("c_custkey", "c_mktsegment"), F.col("user_id") == F.col("c_custkey"))
    parts = run_increments(joined, lambda b: b.groupBy("c_mktsegment").agg(F.count("*").alias("n")), "segments")
    return parts.groupBy("c_mktsegment").agg(F.sum("n").alias("n"))


def followed_events(spark: SparkSession, path: str) -> DataFrame:
    """``a, b``: events with k under 50 and later ones of the user with k of 50 or more, within two hours.

    Two streams with watermarks: state older than the interval is dropped.
    """
    schema = spark.read.parquet(path).schema
    rows = spark.readStream.schema(schema).parquet(path[:-1] + f"[{path[-1]}]")
    rows = rows.select("event_id", "user_id", F.col("ts").cast("timestamp").alias("ts"), F.get_json_object("props", "$.k").cast("long").alias("k"))
    a = rows.where("k < 50").select(F.col("event_id").alias("a"), F.col("user_id").alias("ua"), F.col("ts").alias("ta")).withWatermark("ta", "1 day")
    b = rows.where("k >= 50").select(F.col("event_id").alias("b"), F.col("user_id").alias("ub"), F.col("ts").alias("tb")).withWatermark("tb", "1 day")
    within = (F.col("ua") == F.col("ub")) & (F.col("tb") > F.col("ta")) & (F.col("tb") <= F.col("ta") + F.expr("INTERVAL 2 HOURS"))
    return _collected(a.join(b, within).select("a", "b"), "followed")


def next_queries(spark: SparkSession, path: str) -> DataFrame:
    """``query, next, n``: a user's consecutive queries, with the last one kept as state between batches."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def pairs(key: tuple, frames, state: GroupState):
        last = state.get[0] if state.exists else None
        rows = pd.concat(list(frames)).sort_values(["ts", "event_id"])
        out = []
        for query in rows["query"]:
            if last is not None and last != query:
                out.append((last, query))
            last = query
        state.update((last,))
        yield pd.DataFrame(out, columns=["query", "next"])

    stream = events_stream(spark, path).groupBy("user_id")
    found = stream.applyInPandasWithState(pairs, "query string, next string", "last string", "append", GroupStateTimeout.NoTimeout)
    return _collected(found, "pairs").groupBy("query", "next").agg(F.count("*").alias("n"))


def late_rows(spark: SparkSession, path: str) -> DataFrame:
    """``counted, dropped``: rows that windows take in, and rows behind the watermark that they do not.

    The input is the events, then three of them again, a year and more older than the last, on three days:
    they come too late.
    """
    source = scratch(spark, "late")
    events = spark.read.parquet(path).select("event_id", F.col("ts").cast("timestamp").alias("ts"))
    events.repartition(1).write.parquet(f"{source}/part=1")
    last = events.agg(F.max("ts").alias("last"))
    older = events.orderBy("event_id").limit(3).crossJoin(last).select("event_id", F.expr("last - make_dt_interval(365 + cast(2 * event_id as int))").alias("ts"))
    stream = spark.readStream.schema("event_id long, ts timestamp, part int").option("maxFilesPerTrigger", 1).parquet(source)
    state = scratch(spark, "late-state")

    def run():
        counts = stream.withWatermark("ts", "1 day").groupBy(F.window("ts", "1 day").alias("w")).agg(F.count("*").alias("n"))
        query = counts.writeStream.foreachBatch(lambda batch, _: batch.write.format("noop").mode("overwrite").save()).outputMode("update").option("checkpointLocation", state).trigger(availableNow=True).start()
        query.awaitTermination()
        return sum(o["numRowsDroppedByWatermark"] for p in query.recentProgress for o in p["stateOperators"])

    run()
    older.repartition(1).write.parquet(f"{source}/part=2")
    dropped = run()
    return events.agg(F.count("*").alias("counted")).withColumn("dropped", F.lit(int(dropped)).cast("long"))
