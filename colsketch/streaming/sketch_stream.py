"""Sketches of streams: every fixed map is linear, so running sums per (user, bucket) equal the batch sketch at the end."""

from __future__ import annotations

import uuid
from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupStateTimeout
from pyspark.sql.types import IntegerType, StructType

from ..functions.hashing import bucket_of, sign_of
from ..operators.adaptive import MAX_BROADCAST, SketchModel
from ..session import shared_dir


def read_events(spark: SparkSession, path: str, schema, files: int | None = None) -> DataFrame:
    """Event files as they arrive, at most `files` at a time; ts becomes a timestamp in the session's (UTC) zone."""
    reader = spark.readStream.schema(schema)
    df = (reader.option("maxFilesPerTrigger", files) if files else reader).parquet(path)
    return df.withColumn("ts", F.col("ts").cast("timestamp"))


def generated_events(spark: SparkSession, rows: int, users: int = 100, features: int = 100) -> DataFrame:
    """A stream of made-up events, `rows` in each micro-batch, for load tests; the same at every run."""
    made = spark.readStream.format("rate-micro-batch").option("rowsPerBatch", rows).load()
    k = F.pmod(F.xxhash64("value"), F.lit(features))
    return made.select(F.col("value").alias("event_id"), F.pmod("value", F.lit(users)).alias("user_id"), F.col("timestamp").alias("ts"), F.to_json(F.struct(k.alias("k"))).alias("props"))


def increments(events: DataFrame, r: int, seed: int) -> DataFrame:
    """(user_id, ts, bucket, delta) from the feature props.k; stateless."""
    k = F.get_json_object("props", "$.k").cast("long")
    e = events.withColumn("feature_id", k).where("feature_id is not null and user_id is not null")
    return e.select("event_id", "user_id", "ts", bucket_of(F.col("feature_id"), r, seed).alias("bucket"), (F.lit(1) * sign_of(F.col("feature_id"), seed)).cast("long").alias("delta"))


def running_sketch(rows: DataFrame) -> DataFrame:
    return rows.groupBy("user_id", "bucket").agg(F.sum("delta").alias("value"))


def windowed_sketch(rows: DataFrame, size: str, slide: str | None = None, late: str = "2 hours") -> DataFrame:
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return rows.withWatermark("ts", late).groupBy(w.alias("w"), "bucket").agg(F.sum("delta").alias("value"))


def session_sketch(rows: DataFrame, gap: str, late: str = "2 hours") -> DataFrame:
    return rows.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.sum("delta").alias("value"))


def deduplicated(rows: DataFrame, late: str = "2 hours") -> DataFrame:
    return rows.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def drain(df: DataFrame, mode: str = "complete", checkpoint: str | None = None) -> DataFrame:
    """Runs a streaming frame over all that is there now and returns what it wrote to the shared folder.

    Each micro-batch replaces its own folder, so one that runs twice is written once. The result of mode complete is the
    last micro-batch, that of the other modes all of them.
    """
    spark, seen = df.sparkSession, []
    home = f"{shared_dir(spark)}/sink_{uuid.uuid4().hex}"

    def one(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{home}/rows/batch={number}")
        seen.append(number)

    q = df.writeStream.foreachBatch(one).outputMode(mode).option("checkpointLocation", checkpoint or f"{home}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    if not seen:
        return spark.createDataFrame([], df.schema)
    rows = spark.read.schema(StructType([*df.schema.fields]).add("batch", IntegerType())).parquet(f"{home}/rows")
    return (rows.where(F.col("batch") == seen[-1]) if mode == "complete" else rows).drop("batch")


def merged(*sketches: DataFrame) -> DataFrame:
    """The sketch of the union of what the sketches saw."""
    out = sketches[0]
    for s in sketches[1:]:
        out = out.unionByName(s)
    return out.groupBy("user_id", "bucket").agg(F.sum("value").alias("value"))


def learned_increments(rows: DataFrame, model: SketchModel, feature: str = "feature_id", max_broadcast: int = MAX_BROADCAST) -> DataFrame:
    """Arriving (user_id, ..., feature_id) rows sent through a learned map: a stream-static join without state.

    Maps of more than max_broadcast features, or of unknown size, are joined by a shuffle.
    """
    fmap = model.feature_map.select(F.col("feature_id").alias("known"), "bucket", "sign").join(F.broadcast(model.groups.select("bucket", "size")), "bucket")
    fmap = F.broadcast(fmap) if model.meta.get("d", max_broadcast + 1) <= max_broadcast else fmap
    return rows.join(fmap, F.col(feature) == F.col("known")).drop("known").withColumn("delta", F.col("sign") / F.col("size"))


def online_centres(rows: DataFrame, ttl_ms: int = 86_400_000, late: str = "2 hours") -> DataFrame:
    """(user_id, bucket, seen, centre): centres as running means of the values (user_id, bucket, ts, value) that arrive,
    each with the rate 1 / seen. State is a count and a mean for each cell; cells idle for ttl_ms of event time are
    forgotten. Null values are left out, and a cell without others has the centre 0."""

    def step(key, frames, state):
        if state.hasTimedOut:
            state.remove()
            return
        seen, centre = state.get if state.exists else (0, 0.0)
        last = state.getCurrentWatermarkMs()
        for frame in frames:
            values = frame["value"].dropna()
            seen += len(values)
            centre += (float(values.sum()) - len(values) * centre) / max(1, seen)
            last = max(last, int(frame["ms"].max()))
        state.update((seen, centre))
        state.setTimeoutTimestamp(last + ttl_ms)
        yield pd.DataFrame({"user_id": [key[0]], "bucket": [key[1]], "seen": [seen], "centre": [centre]})

    cells = rows.where("ts is not null").withWatermark("ts", late).select("user_id", "bucket", "ts", F.unix_millis("ts").alias("ms"), F.col("value").cast("double").alias("value"))
    return cells.groupBy("user_id", "bucket").applyInPandasWithState(step, "user_id long, bucket int, seen long, centre double", "seen long, centre double", "update", GroupStateTimeout.EventTimeTimeout)


def followed_by(left: DataFrame, right: DataFrame, within: str = "1 hour", late: str = "2 hours") -> DataFrame:
    """Pairs (user_id, first_id, then_id) of events of the two streams, the right one at most `within` later; rows (event_id, user_id, ts)."""
    a = left.select(F.col("event_id").alias("first_id"), "user_id", F.col("ts").alias("first_ts")).withWatermark("first_ts", late)
    b = right.select(F.col("event_id").alias("then_id"), F.col("user_id").alias("then_user"), F.col("ts").alias("then_ts")).withWatermark("then_ts", late)
    on = F.expr(f"user_id = then_user and then_ts >= first_ts and then_ts <= first_ts + interval {within}")
    return a.join(b, on).select("user_id", "first_id", "then_id")


def apply_models(rows: DataFrame, model_of: Callable[[int], SketchModel], path: str, checkpoint: str) -> None:
    """Each micro-batch through the model that is current when it starts; a batch that runs twice replaces its own folder,
    so every row is written once."""

    def one(batch: DataFrame, number: int) -> None:
        out = learned_increments(batch, model_of(number)).groupBy("user_id", "bucket").agg(F.sum("delta").alias("value"))
        out.write.mode("overwrite").parquet(f"{path}/batch={number}")

    rows.writeStream.foreachBatch(one).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
