"""Streaming forms: fold-in of rating events, windowed popularity, sessions, de-duplication, capped state and interval joins.

Event times in the given files are without a zone; they are cast to TIMESTAMP before any watermark (session time zone UTC).
"""

from __future__ import annotations

import tempfile
import time
import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events file as a stream: event_id, ts (timestamp), user_id, event_type, value, item_id."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    raw = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return prepared(raw)


def prepared(raw: DataFrame) -> DataFrame:
    return raw.withColumn("ts", F.col("ts").cast("timestamp")).withColumn("item_id", F.get_json_object("props", "$.k").cast("int"))


def run_to_table(stream: DataFrame, mode: str) -> DataFrame:
    """Runs a stream over all that is there and returns what its sink holds."""
    spark, name = stream.sparkSession, f"stream_{uuid.uuid4().hex}"
    query = stream.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", f"{shared_folder(spark)}/{name}").trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.table(name)


def shared_folder(spark: SparkSession) -> str:
    """The cluster's checkpoint folder; only a local session may go without one."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        folder = spark.conf.get("spark.checkpoint.dir", None)
        if folder is None and not sc.master.startswith("local"):
            raise ValueError("name a folder that all executors share in spark.checkpoint.dir")
        sc.setCheckpointDir(folder or tempfile.mkdtemp(prefix="proxrec-"))
    return sc.getCheckpointDir()


def popularity(events: DataFrame, size: str = "1 day", slide: str | None = None, late: str = "2 hours") -> DataFrame:
    """Events by item and window, tumbling or sliding."""
    window = F.window("ts", size, slide) if slide else F.window("ts", size)
    return events.withWatermark("ts", late).groupBy(window.alias("w"), "item_id").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "item_id", "n")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "2 hours") -> DataFrame:
    """Sessions of a user: stretches without a gap."""
    return events.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def deduplicated(events: DataFrame, late: str = "2 hours") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def factors(events: DataFrame, latent: DataFrame) -> DataFrame:
    """Each user's latent factor by component: a sum over events, so it is kept up additively. latent: item_id, v."""
    parts = events.join(F.broadcast(latent), "item_id").select("user_id", F.posexplode("v").alias("k", "p"))
    return parts.groupBy("user_id", "k").agg(F.sum("p").alias("p"))


def capped_deltas(events: DataFrame, cap: int = 5) -> DataFrame:
    """(user_id, item_id, delta): what each batch adds to the rating least(count, cap), from per-pair state.

    A capped count isn't additive, its changes are; their sum feeds the factors.
    """

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        seen = state.get[0] if state.exists else 0
        fresh = seen + sum(len(b) for b in batches)
        state.update((fresh,))
        delta = min(fresh, cap) - min(seen, cap)
        if delta:
            yield pd.DataFrame({"user_id": [key[0]], "item_id": [key[1]], "delta": [float(delta)]})

    return events.groupBy("user_id", "item_id").applyInPandasWithState(step, "user_id long, item_id int, delta double", "seen long", "append", GroupStateTimeout.NoTimeout)


def followed(events: DataFrame, first: str = "view", then: str = "purchase", within: str = "1 day", late: str = "2 hours") -> DataFrame:
    """Stream-stream interval join: an event of one type and a later one of another by the same user."""
    a = events.where(F.col("event_type") == first).select(F.col("event_id").alias("first_id"), "user_id", F.col("ts").alias("t0")).withWatermark("t0", late)
    b = events.where(F.col("event_type") == then).select(F.col("event_id").alias("then_id"), F.col("user_id").alias("u"), F.col("ts").alias("t1")).withWatermark("t1", late)
    return a.join(b, F.expr(f"user_id = u AND t1 >= t0 AND t1 <= t0 + INTERVAL {within}")).select("first_id", "then_id", "user_id")


def drift(now: DataFrame, model_items: DataFrame, limit: float = 0.2) -> DataFrame:
    """Relative change of item norms since the fit; retrain is true where the mean change exceeds the limit."""
    both = now.select("item_id", F.col("norm").alias("norm_now")).join(model_items.select("item_id", F.col("norm").alias("norm_then")), "item_id", "full")
    change = F.abs(F.coalesce("norm_now", F.lit(0.0)) - F.coalesce("norm_then", F.lit(0.0))) / F.greatest(F.coalesce("norm_now", F.lit(0.0)), F.coalesce("norm_then", F.lit(0.0)), F.lit(1e-12))
    return both.agg(F.avg(change).alias("change")).withColumn("retrain", F.col("change") > limit)


def stream_drift(events: DataFrame, model_items: DataFrame, limit: float = 0.2) -> DataFrame:
    """Drift of the ratings that a stream of events adds up to, against the model's items: capped ratings are kept per pair, their changes summed."""
    from proxrec.operators.ratings import item_stats

    deltas = run_to_table(capped_deltas(events), "append")
    return drift(item_stats(deltas.groupBy("user_id", "item_id").agg(F.sum("delta").alias("rating"))), model_items, limit)


def refreshed_lists(events: DataFrame, latent: DataFrame, n: int = 10) -> DataFrame:
    """Top-N lists kept up by a stream: each batch updates the factors of the users it names and rewrites their lists, and no others.

    Lists are versions of a table in the shared folder, one a batch, so a batch that is run again writes the same. latent: item_id, v.
    """
    spark, name = events.sparkSession, f"lists_{uuid.uuid4().hex}"
    folder = f"{shared_folder(spark)}/{name}"
    order = Window.partitionBy("user_id").orderBy(F.desc(F.round("score", 9)), "item_id")
    done: list[int] = []

    def write(batch: DataFrame, number: int) -> None:
        own = batch.groupBy("user_id").agg(F.array_sort(F.collect_list(F.struct("k", "p"))).alias("e")).select("user_id", F.col("e.p").alias("p"))
        dot = F.aggregate(F.zip_with("p", "v", lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
        lists = own.crossJoin(F.broadcast(latent)).select("user_id", "item_id", dot.alias("score")).withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= n)
        if done:
            lists = lists.unionByName(spark.read.parquet(f"{folder}/v{done[-1]}").join(own.select("user_id"), "user_id", "left_anti"))
        lists.write.mode("overwrite").parquet(f"{folder}/v{number}")
        if not done or done[-1] != number:
            done.append(number)

    # factors by user and component come in update mode: all components of a user change with any of their events
    query = factors(events, latent).writeStream.outputMode("update").foreachBatch(write).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.parquet(f"{folder}/v{done[-1]}")


def late_rows(events: DataFrame) -> DataFrame:
    """Hourly counts of the given events as they come late, with a watermark of two hours: every fourth event, then later ones of the last hour,
    then every fourth again, of which those in closed windows are dropped. Two rows a day later close all windows.

    Rows are judged by the watermark that the batch before last has set, hence the batch between.
    """
    spark = events.sparkSession
    folder = f"{shared_folder(spark)}/late_{uuid.uuid4().hex}"
    rows = events.select("event_id", "ts", F.lit(1).alias("item_id"))
    newest = rows.agg(F.max(F.when(F.col("event_id") % 4 == 0, F.col("ts"))).alias("t"), F.max("ts").alias("last"))
    dealt = rows.crossJoin(F.broadcast(newest))
    after = lambda by: newest.select(F.lit(-1).cast("long").alias("event_id"), F.expr(f"last + INTERVAL {by}").alias("ts"), F.lit(1).alias("item_id"))
    batches = (dealt.where("event_id % 4 = 0"), dealt.where("event_id % 4 = 1 AND ts > t - INTERVAL 1 HOUR"), dealt.where("event_id % 4 = 2"), after("24 HOUR"), after("1470 MINUTE"))
    for batch in batches:
        batch.select("event_id", "ts", "item_id").repartition(1).write.mode("append").parquet(folder)
        time.sleep(0.05)  # files, one a batch, are read in order of their times
    stream = spark.readStream.schema("event_id long, ts timestamp, item_id int").option("maxFilesPerTrigger", 1).parquet(folder)
    return run_to_table(popularity(stream, "1 hour"), "append").select("start", "n")
