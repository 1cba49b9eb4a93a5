"""Keeping graphs and statistics up to date from streams of fragments and events."""

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graftmill.operators.kg import build as K

FRAGMENT_SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
EVENT_SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def stream_fragments(spark: SparkSession, path: str, *, files_per_trigger: int = 10) -> DataFrame:
    return spark.readStream.schema(FRAGMENT_SCHEMA).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def stream_events(spark: SparkSession, path: str, *, delay: str = "10 minutes", files_per_trigger: int = 10) -> DataFrame:
    """Events with a watermark; the zone-less time is read as UTC, since a watermark needs an instant."""
    raw = spark.readStream.schema(EVENT_SCHEMA).option("maxFilesPerTrigger", files_per_trigger).parquet(path)
    return raw.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)


def stream_triples(fragments: DataFrame, known: DataFrame | None = None) -> DataFrame:
    """doc_id, h, r, t extracted from each fragment; known (static h, r, t) marks what the graph holds already."""
    out = K.extract_copular(fragments).unionByName(K.extract_connective(fragments))
    if known is None:
        return out
    k = known.select("h", "r", "t", F.lit(True).alias("known"))
    return out.join(k, ["h", "r", "t"], "left").withColumn("known", F.coalesce("known", F.lit(False)))


def upsert_kg(path: str):
    """A foreachBatch sink: each batch's supports go to a folder of its own number, so a repeated batch replaces itself."""

    def write(batch: DataFrame, batch_id: int) -> None:
        batch.groupBy("h", "r", "t").agg(F.count(F.lit(1)).alias("support")).write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    return write


def read_kg(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema("h string, r string, t string, support long, batch long").parquet(path).groupBy("h", "r", "t").agg(F.sum("support").alias("support"))


def windowed_counts(events: DataFrame, kind: str = "tumbling", *, size: str = "1 day", slide: str = "12 hours", gap: str = "30 minutes") -> DataFrame:
    """start, end, event_type, n, for tumbling, sliding or session windows (sessions are per user)."""
    if kind == "session":
        g = events.groupBy(F.session_window("ts", gap).alias("w"), "user_id")
        return g.agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "user_id", "n")
    w = F.window("ts", size) if kind == "tumbling" else F.window("ts", size, slide)
    return events.groupBy(w.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "event_type", "n")


def dedup_stream(events: DataFrame, keys: list[str]) -> DataFrame:
    return events.dropDuplicatesWithinWatermark(keys)


def error_cause_stream(events: DataFrame, *, within: str = "6 hours") -> DataFrame:
    """error_id, cause_id, cause_type: earlier events of the same user within the interval before an error (stream-stream join)."""
    err = events.filter("event_type = 'error'").select(F.col("event_id").alias("error_id"), F.col("ts").alias("error_ts"), F.col("user_id").alias("u"))
    own = events.filter("event_type <> 'error'").select(F.col("event_id").alias("cause_id"), F.col("event_type").alias("cause_type"), "ts", "user_id")
    return err.join(own, F.expr(f"u = user_id and ts < error_ts and ts >= error_ts - interval {within}")).select("error_id", "cause_id", "cause_type")


def late_rows(query) -> int:
    """Rows that the watermark has dropped so far."""
    return sum(int(op.get("numRowsDroppedByWatermark", 0)) for p in query.recentProgress for op in p["stateOperators"])


def run_available(df: DataFrame, sink, checkpoint: str, *, mode: str = "append"):
    """Run a stream over what is there now with a foreachBatch sink, and wait."""
    q = df.writeStream.foreachBatch(sink).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    return q
