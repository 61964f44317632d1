"""Streams: encoding of arriving texts and windows over events, each equal to its batch twin once all input is read."""

from __future__ import annotations

import atexit
import shutil
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from slotweave.operators.encode import encode
from slotweave.operators.exposure import exposures
from slotweave.operators.visibility import Tokenizer
from slotweave.sources.tables import delete, shared_folder


def table_stream(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    """The table as a stream, be it one file or a folder of files: a path with a pattern may name either, a plain one only a folder."""
    path = f"{sf_dir}/{table}.parquet"
    read = spark.readStream.schema(spark.read.parquet(path).schema).parquet(f"{path[:-1]}[t]")
    return read.withColumn("ts", F.col("ts").cast("timestamp")) if "ts" in read.columns else read


def rate_events(spark: SparkSession, per_second: int, types: int = 4) -> DataFrame:
    """Events without files, for load tests: event_id counts up, ts is the time of making, event_type goes round."""
    made = spark.readStream.format("rate").option("rowsPerSecond", per_second).load()
    return made.select(F.col("value").alias("event_id"), F.col("timestamp").alias("ts"), F.concat(F.lit("type"), F.col("value") % types).alias("event_type"))


def to_console(stream: DataFrame, mode: str = "append", rows: int = 20, every: str = "1 second") -> StreamingQuery:
    """Shows the first rows of each micro-batch; the caller stops it."""
    return stream.writeStream.outputMode(mode).format("console").option("numRows", rows).option("truncate", False).trigger(processingTime=every).start()


def run_to_end(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Reads all that is there, into a table in the shared folder, which goes when the process ends: no row passes through the driver."""
    spark = stream.sparkSession
    folder, own = shared_folder(spark)
    root, written = f"{folder}/stream-{uuid.uuid4().hex[:12]}", {}
    atexit.register(_gone, spark, root, own)

    def put(batch: DataFrame, number: int) -> None:
        path = f"{root}/rows/{number}"  # a repeated batch overwrites its own
        batch.write.mode("overwrite").parquet(path)
        written[number] = path

    writer = stream.writeStream.outputMode(mode).foreachBatch(put).option("checkpointLocation", f"{root}/checkpoint")
    writer.trigger(availableNow=True).start().awaitTermination()
    delete(spark, f"{root}/checkpoint")
    paths = [written[n] for n in sorted(written)]
    # a batch of the complete mode holds the whole result so far
    paths = paths[-1:] if mode == "complete" else paths
    return spark.read.schema(stream.schema).parquet(*paths) if paths else spark.createDataFrame([], stream.schema)


def _gone(spark: SparkSession, root: str, own: str | None) -> None:
    try:
        delete(spark, root)
    except Exception:  # the session may have ended; the folder is the cluster's to clean
        pass
    if own:
        shutil.rmtree(own, ignore_errors=True)


def encode_stream(docs: DataFrame, tok: Tokenizer) -> DataFrame:
    return encode(docs, tok).select("doc_id", F.size("ids").cast("long").alias("tokens"))


def tumbling(events: DataFrame, length: str = "1 hour", slide: str | None = None) -> DataFrame:
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    return events.withWatermark("ts", "2 hours").groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").cast("timestamp_ntz").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    return events.withWatermark("ts", "2 hours").groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select(F.col("w.start").cast("timestamp_ntz").alias("start"), "user_id", "n")


def deduplicated(events: DataFrame) -> DataFrame:
    return events.withWatermark("ts", "400 days").dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "event_type")


def with_customers(events: DataFrame, customers: DataFrame) -> DataFrame:
    return events.join(customers, events["user_id"] == customers["c_custkey"]).select("event_id", "c_mktsegment")


def stream_pairs(clicks: DataFrame, purchases: DataFrame, within: str = "1 hour") -> DataFrame:
    """Two streams: each purchase with the clicks of its user in the time before. Both sides forget what is past the watermark."""
    a = clicks.filter("event_type = 'click'").withWatermark("ts", "2 hours").select(F.col("event_id").alias("click_id"), F.col("user_id").alias("who"), F.col("ts").alias("clicked"))
    b = purchases.filter("event_type = 'purchase'").withWatermark("ts", "2 hours").select(F.col("event_id").alias("purchase_id"), "user_id", "ts")
    return a.join(b, F.expr(f"who = user_id AND ts > clicked AND ts <= clicked + INTERVAL {within}")).select("click_id", "purchase_id")


def running_exposure(docs: DataFrame, tok: Tokenizer, id_col: str = "doc_id") -> DataFrame:
    """How often each visible id has come so far: exposure is a sum, so the micro-batches' counts add up."""
    return encode(docs, tok, id_col=id_col).select(F.explode("ids").alias("id")).groupBy("id").agg(F.count("*").alias("n"))


def drift(running: DataFrame, tok: Tokenizer) -> DataFrame:
    """id, its share of the arriving text, and its share of the training text."""
    ids = tok.export_ids()
    at_training = exposures(tok.log)
    fans = tok.expansions()
    weight = dict.fromkeys((ids[t] for t in tok.visible), 0)
    for t, fan in enumerate(fans):
        for v in fan:
            weight[ids[v]] += at_training[t]
    known = running.sparkSession.createDataFrame(list(weight.items()), "id int, trained long")
    sums = running.agg(F.sum("n").alias("all"))
    return known.join(running, "id", "left").crossJoin(F.broadcast(sums)).select("id", (F.coalesce("n", F.lit(0)) / F.col("all")).alias("share"), (F.col("trained") / max(1, sum(weight.values()))).alias("trained_share"))


def encode_to_folder(docs: DataFrame, tok: Tokenizer, path: str, checkpoint: str) -> StreamingQuery:
    """Ids of arriving texts, a folder for each micro-batch, which a repeated batch overwrites: a restart gives the same files."""

    def put(batch: DataFrame, number: int) -> None:
        encode(batch, tok).write.mode("overwrite").parquet(f"{path}/batch={number}")

    return docs.writeStream.foreachBatch(put).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def dropped_as_late(query: StreamingQuery) -> int:
    """Rows that came after the watermark had passed them, over the progress that the query still holds."""
    return sum(int(op["numRowsDroppedByWatermark"]) for p in query.recentProgress for op in p["stateOperators"])
