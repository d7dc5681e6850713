"""Streaming twins: at least T of several kinds per window or per user, near duplicates on arrival, an index that grows, joins and first events."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.index import CHUNK_BITS, Index, of_words, words_of_members
from ..session import shared_folder
from .arrivals import Arrivals

KINDS = ("view", "click", "purchase", "login", "search")


def folder(spark: SparkSession) -> str:
    """A new folder beneath the shared one."""
    return f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"


def any_t(events: DataFrame, kinds: list[str], t: int, window, watermark: str = "10 minutes") -> DataFrame:
    """Users with at least t of the kinds per window: the state is one bit mask for each user and window."""
    number = F.array_position(F.array(*map(F.lit, kinds)), F.col("event_type")).cast("int")
    bit = F.call_function("shiftleft", F.lit(1).cast("long"), number - 1)
    # watermarks need a time with a zone; windows go back to the given type
    kind = events.schema["ts"].dataType.simpleString()
    masks = events.where(number > 0).withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", watermark).groupBy(window.alias("win"), "user_id").agg(F.bit_or(bit).alias("mask"))
    return masks.select(F.col("win.start").cast(kind).alias("win_start"), F.col("win.end").cast(kind).alias("win_end"), "user_id", F.bit_count("mask").cast("long").alias("kinds")).where(F.col("kinds") >= t)


def windows(kind: str):
    if kind == "tumbling":
        return F.window("ts", "1 hour")
    if kind == "sliding":
        return F.window("ts", "1 hour", "30 minutes")
    return F.session_window("ts", "30 minutes")


def source(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """A file stream of a table that may be one file or a folder of them."""
    schema = spark.read.parquet(path).schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).option("recursiveFileLookup", "true").parquet(path)


def finished(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over what is there; its rows as a table, each batch once. In append mode a window's row comes when the watermark has closed it."""
    spark = stream.sparkSession
    out = folder(spark)

    def put(batch: DataFrame, number: int) -> None:
        # a batch that runs again after a failure overwrites its own folder: exactly once
        batch.write.mode("overwrite").parquet(f"{out}/data/batch={number}")

    query = stream.writeStream.outputMode(mode).foreachBatch(put).option("checkpointLocation", f"{out}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    spark.createDataFrame([], stream.schema).write.mode("append").parquet(f"{out}/data/batch=-1")
    return spark.read.schema(stream.schema).parquet(f"{out}/data/batch=*")


def near_duplicates(grams: DataFrame, t: int, q: int = 1) -> DataFrame:
    """From a stream of (doc_id, grams array): pairs (doc_id, earlier) that share at least t distinct runs of q grams, found when the later one arrives.

    Each batch is added to an index of runs and meets what arrived before and itself there, by ranges of runs. Less than t of a document's runs, the commonest,
    only confirm, so that a run of most documents doesn't pair them all.
    """
    spark = grams.sparkSession
    out = folder(spark)
    query = grams.writeStream.foreachBatch(Arrivals(spark, out, q, t).step).option("checkpointLocation", f"{out}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    spark.createDataFrame([], "doc_id long, earlier long, shared long").write.parquet(f"{out}/pairs/batch=-1")
    return spark.read.schema("doc_id long, earlier long, shared long").parquet(f"{out}/pairs/batch=*")


def index_append(members: DataFrame, rows: int, chunk_bits: int = CHUNK_BITS) -> Index:
    """An index of a stream of members (attr, value, rid). New rids mostly add chunks; the words of a chunk that several batches met are joined."""
    spark = members.sparkSession
    out = folder(spark)
    schema = "attr string, value string, chunk long, w int, b long"

    def step(batch: DataFrame, number: int) -> None:
        words_of_members(batch, chunk_bits).write.mode("overwrite").parquet(f"{out}/words/batch={number}")

    query = members.writeStream.foreachBatch(step).option("checkpointLocation", f"{out}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    spark.createDataFrame([], schema).write.parquet(f"{out}/words/batch=-1")
    every = spark.read.schema(schema).parquet(f"{out}/words/batch=*")
    return of_words(every.groupBy("attr", "value", "chunk", "w").agg(F.bit_or("b").alias("b")), rows, chunk_bits)


def first_of_each(events: DataFrame, *keys: str, watermark: str = "10 minutes") -> DataFrame:
    """One event for each value of keys; another comes only after the watermark has passed the first."""
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", watermark).dropDuplicatesWithinWatermark(list(keys))


def followed(first: DataFrame, second: DataFrame, key: str, within: str = "10 minutes", watermark: str = "10 minutes") -> DataFrame:
    """Pairs (first_id, second_id) of events of a key, the second at most that long after the first: both streams keep no more than that."""
    side = lambda df, x: df.select(F.col("event_id").alias(f"{x}_id"), F.col(key).alias(f"{x}_key"), F.col("ts").cast("timestamp").alias(f"{x}_ts")).withWatermark(f"{x}_ts", watermark)
    soon = F.expr(f"first_key = second_key AND second_ts >= first_ts AND second_ts <= first_ts + INTERVAL {within}")
    return side(first, "first").join(side(second, "second"), soon).select("first_id", "second_id")


def reached(events: DataFrame, kinds: list[str], t: int) -> DataFrame:
    """user_id of each user once, when t of the kinds are there: the state is a bit mask for each user."""
    number = {k: i for i, k in enumerate(kinds)}

    def step(key: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        mask = state.get[0] if state.exists else 0
        before = mask.bit_count()
        for batch in batches:
            for kind in batch["event_type"].unique():
                mask |= 1 << number[kind]
        state.update((mask,))
        if before < t <= mask.bit_count():
            yield pd.DataFrame({"user_id": [key[0]]})

    rows = events.where(F.col("event_type").isin(kinds)).select("user_id", "event_type")
    return rows.groupBy("user_id").applyInPandasWithState(step, "user_id long", "mask long", "append", "NoTimeout")
