"""Structured Streaming over event files: windowed moments of quantised values, sessions, deduplication.

``events.ts`` has no zone; watermarks need a timestamp with one, so it is cast first.
"""

from __future__ import annotations

import uuid

import numpy as np
import pandas as pd

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

EPS = 0.05  # an absolute bound: a stream has no range yet


def source(spark: SparkSession, folder: str, name: str = "events.parquet") -> DataFrame:
    """A stream of the files ``name`` in ``folder``."""
    schema = spark.read.parquet(f"{folder}/{name}").schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).option("pathGlobFilter", name).parquet(folder).withColumn("ts", F.col("ts").cast("timestamp"))


def quantised(events: DataFrame, eps: float = EPS) -> DataFrame:
    return events.withColumn("q", F.floor(F.col("value") / (2 * eps) + 0.5).cast("bigint"))


def moments(events: DataFrame, *keys) -> DataFrame:
    return events.groupBy(*keys).agg(F.count("*").alias("n"), F.sum("q").alias("s1"), F.sum(F.col("q") * F.col("q")).alias("s2"))


def tumbling(events: DataFrame) -> DataFrame:
    w = moments(quantised(events).withWatermark("ts", "1 hour"), F.window("ts", "1 day"))
    return w.select(F.date_format("window.start", "yyyy-MM-dd").alias("day"), "n", "s1", "s2")


def sliding(events: DataFrame) -> DataFrame:
    w = moments(quantised(events).withWatermark("ts", "1 hour"), F.window("ts", "6 hours", "1 hour"))
    return w.select(F.date_format("window.start", "yyyy-MM-dd HH:mm").alias("start"), "n", "s1", "s2")


def sessions(events: DataFrame) -> DataFrame:
    w = moments(quantised(events).withWatermark("ts", "1 hour"), "user_id", F.session_window("ts", "30 minutes"))
    return w.select("user_id", F.date_format("session_window.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n", "s1", "s2")


def once_each(events: DataFrame) -> DataFrame:
    return quantised(events).withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "q")


def weighted(events: DataFrame) -> DataFrame:
    """Each event with the weight of its type from a static table: a join of stream and table."""
    weights = events.sparkSession.createDataFrame([("click", 1), ("purchase", 5), ("error", 0)], "event_type string, weight int")
    return quantised(events).join(F.broadcast(weights), "event_type").select("event_id", (F.col("q") * F.col("weight")).alias("weighted"))


def chained(events: DataFrame) -> DataFrame:
    """(event_id, p): each event's integer less its predecessor's of the same type, which the state keeps between batches."""

    def run(key, batches, state):
        last = state.get[0] if state.exists else 0
        held = [b for b in batches]
        if not held:
            return
        rows = pd.concat(held).sort_values("event_id")
        q = rows["q"].to_numpy()
        state.update((int(q[-1]),))
        yield pd.DataFrame({"event_id": rows["event_id"].to_numpy(), "p": np.diff(q, prepend=last)})

    keyed = quantised(events).select("event_type", "event_id", "q").groupBy("event_type")
    return keyed.applyInPandasWithState(run, "event_id bigint, p bigint", "last bigint", "append", "NoTimeout")


def shared_folder(spark) -> str:
    """The session's checkpoint folder; a folder of this machine only where the session is on one machine."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not found and not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    return (found or "file:///tmp/checkpoints/fieldloom").rstrip("/")


def finished(stream: DataFrame, mode: str) -> DataFrame:
    """Run to the end of the input at hand and give what it put out: in complete mode the last batch, else all of them.

    Each batch goes to a folder of its number in the session's shared folder, so no row passes through the
    driver, and a replay overwrites itself.
    """
    spark = stream.sparkSession
    folder = f"{shared_folder(spark)}/stream_{uuid.uuid4().hex}"
    done: list[str] = []

    def write(batch: DataFrame, number: int) -> None:
        path = f"{folder}/out/{number}"
        batch.write.mode("overwrite").parquet(path)
        if path not in done:
            done.append(path)

    stream.writeStream.foreachBatch(write).outputMode(mode).option("checkpointLocation", f"{folder}/checkpoint").trigger(availableNow=True).start().awaitTermination()
    held = done[-1:] if mode == "complete" else done
    return spark.read.schema(stream.schema).parquet(*held) if held else spark.createDataFrame([], stream.schema)


def in_turns(spark: SparkSession, turns: list[DataFrame], make) -> DataFrame:
    """What a stream appends if its input arrives in turns: each is read to its end before the next one comes."""
    folder = f"{shared_folder(spark)}/turns_{uuid.uuid4().hex}"
    schema = turns[0].schema
    for rows in turns:
        rows.write.mode("append").parquet(f"{folder}/in")
        stream = make(spark.readStream.schema(schema).parquet(f"{folder}/in"))
        stream.writeStream.format("parquet").outputMode("append").option("path", f"{folder}/out").option("checkpointLocation", f"{folder}/checkpoint").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{folder}/out")


def late_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Days as they close, where the first day's rows come a second time at the very end: they change nothing."""
    events = spark.read.parquet(f"{sf_dir}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    first, last = events.agg(F.min("ts"), F.max("ts")).first()
    middle = F.lit(first) + (F.lit(last) - F.lit(first)) / 2
    turns = [events.where(F.col("ts") < middle), events.where(F.col("ts") >= middle), events.where(F.to_date("ts") == F.to_date(F.lit(first)))]
    return in_turns(spark, turns, tumbling)


def followed(events: DataFrame) -> DataFrame:
    """Pairs of a click and a purchase of the same user within six hours after it: an interval join of two streams."""
    side = lambda kind, name: events.where(F.col("event_type") == kind).select("user_id", F.col("event_id").alias(name), F.col("ts").alias(f"{name}_ts"))
    a, b = side("click", "click").withWatermark("click_ts", "1 hour"), side("purchase", "purchase").withWatermark("purchase_ts", "1 hour")
    near = F.col("purchase_ts").between(F.col("click_ts"), F.col("click_ts") + F.expr("INTERVAL 6 HOURS"))
    return a.join(b.withColumnRenamed("user_id", "buyer"), (F.col("user_id") == F.col("buyer")) & near).select("user_id", "click", "purchase")


def rate(spark: SparkSession, rows: int) -> DataFrame:
    """A stream of ``rows`` numbered rows a batch, as values to quantise."""
    ticks = spark.readStream.format("rate-micro-batch").option("rowsPerBatch", rows).option("numPartitions", 4).load()
    return ticks.select(F.col("value").alias("event_id"), (F.col("value") / 7).alias("value"))


def drained(stream: DataFrame, mode: str = "append"):
    """Run a stream to the end of its input without keeping anything: the cost of the work alone."""
    q = stream.writeStream.format("noop").outputMode(mode).option("checkpointLocation", f"{shared_folder(stream.sparkSession)}/drain_{uuid.uuid4().hex}").trigger(availableNow=True).start()
    q.awaitTermination()
    return q


def first_batch(spark: SparkSession, rows: int) -> DataFrame:
    """The integers of the rate source's first batch."""
    folder = f"{shared_folder(spark)}/rate_{uuid.uuid4().hex}"
    stream = quantised(rate(spark, rows)).select("event_id", "q")
    stream.writeStream.foreachBatch(lambda batch, n: batch.write.mode("overwrite").parquet(f"{folder}/out/batch={n}")).option("checkpointLocation", f"{folder}/checkpoint").trigger(once=True).start().awaitTermination()
    return spark.read.parquet(f"{folder}/out/batch=0")


RUN = 65_536  # consecutive ids that are numbered in one piece


def numbered(rows: DataFrame, key: str, order: str) -> DataFrame:
    """``rows`` with ``g``: their place from 0 within ``key`` by the integer column ``order``.

    Runs of ids are numbered apart, then moved by how many rows come before them: one count a run and key
    is all that meets in one task.
    """
    run = F.floor(F.col(order) / RUN).cast("bigint")
    r = rows.withColumn("run_", run)
    before = Window.partitionBy(key).orderBy("run_").rowsBetween(Window.unboundedPreceding, -1)
    base = r.groupBy(key, "run_").agg(F.count("*").alias("n_")).withColumn("base_", F.coalesce(F.sum("n_").over(before), F.lit(0))).drop("n_")
    own: Column = F.row_number().over(Window.partitionBy(key, "run_").orderBy(order)) - 1
    return r.withColumn("own_", own).join(base, [key, "run_"]).withColumn("g", (F.col("own_") + F.col("base_")).cast("bigint")).drop("run_", "own_", "base_")


def compress_batches(stream: DataFrame, path: str, checkpoint: str):
    """Each micro-batch becomes containers of its own, under its batch number: a replay overwrites itself."""
    from fieldloom.model import ErrorBound
    from fieldloom.operators.codecs import compress_points

    def write(batch: DataFrame, number: int) -> None:
        zero = F.lit(0).cast("bigint")
        points = numbered(batch, "event_type", "event_id").select(F.col("event_type").alias("field"), F.col("g").alias("i"), zero.alias("j"), zero.alias("k"), "value")
        compress_points(points, "mean1d", ErrorBound(EPS, relative=False), 1).write.mode("overwrite").parquet(f"{path}/batch={number}")

    return stream.writeStream.foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True)


Q = f"CAST(floor(value / (2 * CAST({EPS} AS DOUBLE)) + 0.5) AS BIGINT)"
SUMS = "count(*) AS n, CAST(sum(q) AS BIGINT) AS s1, CAST(sum(q * q) AS BIGINT) AS s2"


def _query(make, mode):
    return lambda s, d: finished(make(source(s, d)), mode)


QUERIES = {
    "stream_tumbling": _query(tumbling, "complete"),
    "stream_sliding": _query(sliding, "complete"),
    "stream_session": _query(sessions, "complete"),
    "stream_dedup": _query(once_each, "append"),
    "stream_static_join": _query(weighted, "append"),
    "stream_chain_encoder": _query(chained, "append"),
    "stream_late": late_rows,
    "stream_stream_join": _query(followed, "append"),
    "stream_rate": lambda s, d: first_batch(s, 10_000),
}
ORACLES = {
    "stream_tumbling": f"SELECT strftime(ts, '%Y-%m-%d') AS day, {SUMS} FROM (SELECT ts, {Q} AS q FROM events) GROUP BY 1",
    "stream_sliding": f"SELECT strftime(date_trunc('hour', ts) - to_hours(h), '%Y-%m-%d %H:%M') AS start, {SUMS} FROM (SELECT ts, {Q} AS q FROM events), range(0, 6) r(h) GROUP BY 1",
    "stream_session": f"WITH e AS (SELECT user_id, ts, {Q} AS q, CASE WHEN ts >= lag(ts) OVER w + INTERVAL 30 MINUTE OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)), s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM e) SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, {SUMS} FROM s GROUP BY user_id, s",
    "stream_dedup": f"SELECT event_id, {Q} AS q FROM events",
    "stream_static_join": f"SELECT event_id, {Q} * CASE event_type WHEN 'click' THEN 1 WHEN 'purchase' THEN 5 ELSE 0 END AS weighted FROM events WHERE event_type IN ('click', 'purchase', 'error')",
    "stream_chain_encoder": f"WITH e AS (SELECT event_type, event_id, {Q} AS q FROM events) SELECT event_id, q - lag(q, 1, 0) OVER (PARTITION BY event_type ORDER BY event_id) AS p FROM e",
    "stream_late": f"SELECT strftime(d, '%Y-%m-%d') AS day, {SUMS} FROM (SELECT date_trunc('day', ts) AS d, {Q} AS q FROM events) GROUP BY d HAVING d + INTERVAL 1 DAY <= (SELECT max(ts) FROM events) - INTERVAL 1 HOUR",
    "stream_stream_join": "SELECT a.user_id, a.event_id AS click, b.event_id AS purchase FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 6 HOUR WHERE a.event_type = 'click' AND b.event_type = 'purchase'",
    "stream_rate": f"SELECT event_id, {Q} AS q FROM (SELECT range AS event_id, range / CAST(7 AS DOUBLE) AS value FROM range(0, 10000))",
}
