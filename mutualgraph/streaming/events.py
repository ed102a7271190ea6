"""Events as a stream: windowed counts, late and repeated rows, follow links as they arise, counts kept up to date."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

SCHEMA = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def read(spark: SparkSession, folder: str, files_per_trigger: int = 1) -> DataFrame:
    """The events of Parquet files in a folder, as they come."""
    return prepared(spark.readStream.schema(SCHEMA.replace("ts timestamp", "ts timestamp_ntz")).option("maxFilesPerTrigger", files_per_trigger).parquet(folder))


def prepared(events: DataFrame) -> DataFrame:
    """With ts as a timestamp, k and the three attributes."""
    e = events.withColumn("ts", F.col("ts").cast("timestamp")).withColumn("k", F.get_json_object("props", "$.k").cast("int"))
    return e.withColumn("word", F.concat_ws(":", "event_type", F.floor(F.col("value") / 10).cast("string")))


def distinct_events(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Without repeats of an event_id within the watermark."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def tumbling(events: DataFrame, width: str = "1 hour", late: str = "1 hour") -> DataFrame:
    """start, word, cnt of each window; rows later than the watermark go."""
    return events.withWatermark("ts", late).groupBy(F.window("ts", width).alias("w"), "word").agg(F.count("*").alias("cnt")).select(F.col("w.start").alias("start"), "word", "cnt")


def sliding(events: DataFrame, width: str = "2 hours", step: str = "1 hour", late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.window("ts", width, step).alias("w"), "k").agg(F.count("*").alias("cnt")).select(F.col("w.start").alias("start"), "k", "cnt")


def sessions(events: DataFrame, gap: str = "6 hours", late: str = "1 hour") -> DataFrame:
    """start, user_id, cnt of each user's sessions."""
    return events.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("cnt")).select(F.col("w.start").alias("start"), "user_id", "cnt")


def follow_links(events: DataFrame, gap_seconds: int = 3600) -> DataFrame:
    """src, dst as they arise: a user follows the other user who was last at the same k within the gap. The state of a k is
    its last event; rows of a batch are taken in order of (ts, event_id), a batch's rows after the last one's."""

    def links(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        rows = pd.concat(list(batches)).sort_values(["ts", "event_id"])
        last = state.get if state.exists else None
        out = []
        for ts, user in zip(rows.ts.astype("int64") // 1000, rows.user_id, strict=True):
            if last is not None and last[0] != user and 0 <= ts - last[1] <= gap_seconds * 1_000_000:
                out.append((int(user), last[0]))
            last = (int(user), int(ts))
        state.update(last)
        yield pd.DataFrame(out, columns=["src", "dst"]).astype("int64")

    slim = events.select("k", "user_id", "event_id", F.col("ts").cast("timestamp_ntz").alias("ts"))
    return slim.groupBy("k").applyInPandasWithState(links, "src long, dst long", "last_user long, last_ts long", "append", GroupStateTimeout.NoTimeout)


def merge_counts(batch: DataFrame, _id: int, path: str) -> None:
    """For foreachBatch: adds a batch's user and word counts to a folder, one part for each batch id; a batch that is
    replayed replaces its part, so counts stay exact."""
    batch.groupBy("user_id", F.col("word").alias("attr")).agg(F.count("*").alias("cnt")).write.mode("overwrite").parquet(f"{path}/batch={_id}")


def merged_counts(spark: SparkSession, path: str) -> DataFrame:
    """user_id, attr, cnt over all parts."""
    return spark.read.parquet(path).groupBy("user_id", "attr").agg(F.sum("cnt").alias("cnt"))
