"""Sets and index rows from streams."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from overlapix.functions import hashing as H
from overlapix.operators import bucketing, schemes, sets
from overlapix.sources.formats import scratch

EVENTS = "event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string"
LATE = "1 hour"


def cut_into_days(spark: SparkSession, events: DataFrame, path: str) -> None:
    """Daily files of a table, in the order of time: what a stream reads in a test."""
    events.withColumn("day", F.to_date("ts")).repartitionByRange("day").sortWithinPartitions("ts").drop("day").write.parquet(path)


def event_stream(spark: SparkSession, path: str, files: int = 4) -> DataFrame:
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files).parquet(path)


def drain(df: DataFrame, name: str) -> DataFrame:
    """Run a stream over what is there now; its result as a table."""
    spark = df.sparkSession
    out, marks = scratch(spark, f"{name}-out"), scratch(spark, f"{name}-marks")
    q = df.writeStream.format("parquet").option("path", out).option("checkpointLocation", marks).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(df.schema).parquet(out)


def drain_updates(df: DataFrame, name: str) -> DataFrame:
    """The same for a stream of updates.  A batch is written under its own number,
    so one that is run again replaces itself."""
    spark = df.sparkSession
    out, marks = scratch(spark, f"{name}-out"), scratch(spark, f"{name}-marks")

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/batch={number}")

    q = df.writeStream.foreachBatch(keep).outputMode("update").option("checkpointLocation", marks).trigger(availableNow=True).start()
    q.awaitTermination()
    schema = T.StructType([*df.schema.fields, T.StructField("batch", T.IntegerType())])
    return spark.read.schema(schema).option("basePath", out).parquet(out).drop("batch")


def deduplicated(events: DataFrame) -> DataFrame:
    """Events once each, however often they are sent within the watermark."""
    return events.withWatermark("ts", LATE).dropDuplicatesWithinWatermark(["event_id"])


def hourly_counts(events: DataFrame) -> DataFrame:
    """Tumbling counts by type; rows later than the watermark are left out."""
    return events.withWatermark("ts", LATE).groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(F.count("*").alias("n"), F.sum("value").alias("total")).select(F.col("w.start").alias("start"), "event_type", "n", "total")


def _grow(h: int, seed: int):
    def run(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        elems, sig = state.get if state.exists else ([], [])
        known, codes = set(elems), np.array(sig or [np.iinfo(np.int64).max] * h, np.int64)
        draws = H.draws(h, seed)
        for batch in batches:
            new = np.array(sorted(set(batch["e"].tolist()) - known), np.int64)
            if len(new):
                known |= set(new.tolist())
                codes = np.minimum(codes, [H.hash_values(new, d, "poly").min() for d in draws])
        state.update((sorted(known), codes.tolist()))
        yield pd.DataFrame({"id": [key[0]], "f": [len(known)], "sig": [codes.tolist()]})

    return run


def signature_stream(events: DataFrame, h: int, seed: int) -> DataFrame:
    """A user's hours as a set, with its raw signature, kept as state and sent on at
    each change.  Minima merge, so rows may come in any order and more than once."""
    rows = events.select(F.col("user_id").alias("id"), H.fp(F.date_format("ts", "yyyy-MM-dd HH")).alias("e"))
    return rows.groupBy("id").applyInPandasWithState(_grow(h, seed), "id bigint, f int, sig array<bigint>", "elems array<bigint>, sig array<bigint>", "update", GroupStateTimeout.NoTimeout)


def latest_signatures(updates: DataFrame) -> DataFrame:
    """Of each id the row with most elements: sets only grow."""
    return updates.groupBy("id").agg(F.max(F.struct("f", "sig")).alias("x")).select("id", "x.f", "x.sig", F.lit(None).cast("array<boolean>").alias("pad"))


def index_stream(spark: SparkSession, path: str, h: int, seed: int, k: int, l: int, m: int) -> DataFrame:  # noqa: E741
    """Index rows of the users' sets after the stream is read."""
    raw = latest_signatures(drain_updates(signature_stream(event_stream(spark, path), h, seed), "index"))
    return bucketing.index_rows(schemes.repad(raw, schemes.opm1(h, seed, m)), k, l)


def probe_stream(stream: DataFrame, index: DataFrame, h: int, seed: int, k: int, l: int, key: str = "doc_id") -> DataFrame:  # noqa: E741
    """Stream-static join: texts as they come against a stored index."""
    queries = sets.word_sets(stream, key, "text").where("f > 0")
    probes = bucketing.index_rows(schemes.minhash(h, seed).query_signatures(queries), k, l).select("j", "key", F.col("id").alias("q_id"))
    return probes.join(index.select("j", "key", F.col("id").alias("x_id")), ["j", "key"]).select("q_id", "x_id")


def paired(events: DataFrame) -> DataFrame:
    """Stream-stream join: each purchase with the same user's clicks of the hour before."""
    left = events.where("event_type = 'purchase'").select(F.col("event_id").alias("p_id"), F.col("user_id").alias("u"), F.col("ts").alias("p_ts")).withWatermark("p_ts", LATE)
    right = events.where("event_type = 'click'").select(F.col("event_id").alias("c_id"), F.col("user_id").alias("v"), F.col("ts").alias("c_ts")).withWatermark("c_ts", LATE)
    return left.join(right, F.expr("u = v and c_ts <= p_ts and c_ts >= p_ts - interval 1 hour")).select("p_id", "c_id")
