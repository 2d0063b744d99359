"""Streaming forms: word counts, windows, de-duplication, normalization of text streams."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from lexnorm.functions import tokens
from lexnorm.operators import infer, rewrite
from lexnorm.sources.store import new_folder, table


def replay(spark: SparkSession, d: str, name: str, files: int = 3, order: str | None = None) -> DataFrame:
    """A given table as a stream of a few files, in order of a column."""
    path = new_folder(spark, f"stream-{name}")
    whole = table(spark, d, name)
    if order is None:
        whole.repartition(files).write.parquet(path)
    else:
        # One write a file, so that files are listed, and read, in order.
        place = F.unix_micros(F.col(order).cast("timestamp")) if dict(whole.dtypes)[order].startswith("timestamp") else F.col(order).cast("long")
        keyed = whole.withColumn("_place", place)
        cuts = keyed.approxQuantile("_place", [i / files for i in range(1, files)], 0.01)
        for lo, hi in zip([None, *cuts], [*cuts, None], strict=True):
            part = keyed.where(F.lit(True) if lo is None else F.col("_place") >= lo).where(F.lit(True) if hi is None else F.col("_place") < hi)
            part.drop("_place").coalesce(1).write.mode("append").parquet(path)
    stream = spark.readStream.schema(whole.schema).option("maxFilesPerTrigger", 1).parquet(path)
    # Watermarks need a timestamp with a zone; the tables' have none and count as the session's.
    zoneless = [c for c, k in stream.dtypes if k == "timestamp_ntz"]
    return stream.withColumns({c: F.col(c).cast("timestamp") for c in zoneless}) if zoneless else stream


def collected(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over all it has now; what it wrote, as a table.

    Append writes Parquet files; complete and update keep the last batch's or
    the latest rows by folder of the batch.
    """
    spark = stream.sparkSession
    out, state = new_folder(spark, "stream-out"), new_folder(spark, "stream-state")
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", state).trigger(availableNow=True)
    if mode == "append":
        query = writer.format("parquet").option("path", out).start()
    else:
        query = writer.foreachBatch(lambda rows, batch: rows.write.mode("overwrite").parquet(f"{out}/batch={batch}")).start()
    query.awaitTermination()
    if mode == "append":
        return spark.read.schema(stream.schema).parquet(out)
    rows = spark.read.parquet(out)
    if mode == "complete":
        last = rows.agg(F.max("batch")).first()[0]
        return rows.where(F.col("batch") == last).drop("batch")
    return rows


def word_counts(stream: DataFrame, text_col: str = "text") -> DataFrame:
    return stream.select(F.explode(tokens.words(F.col(text_col))).alias("word")).groupBy("word").agg(F.count("*").alias("freq"))


def tumbling(events: DataFrame, late: str = "2 hours", width: str = "1 hour", slide: str | None = None) -> DataFrame:
    window = F.window("ts", width, slide) if slide else F.window("ts", width)
    return events.withWatermark("ts", late).groupBy(window.alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def sessions(events: DataFrame, late: str = "2 hours", gap: str = "4 hours") -> DataFrame:
    return events.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def distinct_events(events: DataFrame, late: str = "2 hours") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def clicks_to_purchases(events: DataFrame, late: str = "2 hours") -> DataFrame:
    """Stream-stream join: purchases within an hour after a click of the same user."""
    kind = lambda k, p: events.where(F.col("event_type") == k).select(F.col("user_id").alias(f"{p}_user"), F.col("event_id").alias(f"{p}_id"), F.col("ts").alias(f"{p}_ts")).withWatermark(f"{p}_ts", late)
    c, p = kind("click", "click"), kind("purchase", "purchase")
    return c.join(p, F.expr("click_user = purchase_user AND purchase_ts >= click_ts AND purchase_ts <= click_ts + interval 1 hour")).select("click_id", "purchase_id")


def normalized(stream: DataFrame, mapping: DataFrame, id_cols: list[str], text_col: str = "text") -> DataFrame:
    """Texts of a stream rewritten with a static map: a narrow step, no state."""
    return rewrite.apply(stream, id_cols, text_col, mapping, "broadcast")


def attached_batches(stream: DataFrame, index, out: str, text_col: str = "text"):
    """Start a stream that attaches each batch's words and appends their map rows under ``out``."""

    def each(batch: DataFrame, number: int) -> None:
        infer.attach(tokens.vocabulary(batch, text_col), index).write.mode("overwrite").parquet(f"{out}/batch={number}")

    return stream.writeStream.foreachBatch(each).option("checkpointLocation", new_folder(stream.sparkSession, "stream-state")).trigger(availableNow=True).start()


def frequent_unseen(stream: DataFrame, k: int, text_col: str = "text") -> DataFrame:
    """Emit a word once, in the batch in which its count reaches ``k``: one counter a word."""

    def count(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        before = state.get[0] if state.exists else 0
        now = before + sum(int(b["n"].sum()) for b in batches)
        state.update((now,))
        if before < k <= now:
            yield pd.DataFrame({"word": [key[0]], "freq": [now]})

    words = stream.select(F.explode(tokens.words(F.col(text_col))).alias("word"), F.lit(1).alias("n"))
    return words.groupBy("word").applyInPandasWithState(count, "word string, freq long", "n long", "append", GroupStateTimeout.NoTimeout)


def stream_word_counts(spark: SparkSession, d: str) -> DataFrame:
    return collected(word_counts(replay(spark, d, "conversations")), "complete")


def stream_tumbling_counts(spark: SparkSession, d: str) -> DataFrame:
    return collected(tumbling(replay(spark, d, "events", order="ts")))


def stream_sessions(spark: SparkSession, d: str) -> DataFrame:
    return collected(sessions(replay(spark, d, "events", order="ts")))


def stream_distinct(spark: SparkSession, d: str) -> DataFrame:
    return collected(distinct_events(replay(spark, d, "events", order="ts"))).select("event_id", "user_id")


def stream_interval_join(spark: SparkSession, d: str) -> DataFrame:
    return collected(clicks_to_purchases(replay(spark, d, "events", order="ts")))


def stream_frequent_words(spark: SparkSession, d: str) -> DataFrame:
    return collected(frequent_unseen(replay(spark, d, "benchmark"), 5)).select("word")


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: f for f in (stream_word_counts, stream_tumbling_counts, stream_sessions, stream_distinct, stream_interval_join, stream_frequent_words)}
