"""Unique users over event time: batch twins, streams, and releases that are answered once."""

from __future__ import annotations

import json
import math
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fuzzcount.functions.python_udfs import draw

EVENTS = "event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string"


def stream_of(spark: SparkSession, folder: str, pattern: str = "*.parquet") -> DataFrame:
    """Events as they arrive in a folder."""
    return spark.readStream.schema(EVENTS).option("pathGlobFilter", pattern).option("maxFilesPerTrigger", 1).parquet(folder)


def late_ok(events: DataFrame, delay: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", delay) if events.isStreaming else events


def tumbling(events: DataFrame, width: str = "1 day", delay: str = "1 hour") -> DataFrame:
    """(start, users): approximately distinct in a stream, exactly in a batch."""
    users = F.approx_count_distinct("user_id", 0.01) if events.isStreaming else F.count_distinct("user_id")
    return late_ok(events, delay).groupBy(F.window("ts", width)).agg(users.alias("users")).select(F.col("window.start").alias("start"), "users")


def sliding(events: DataFrame, width: str = "1 hour", slide: str = "15 minutes", delay: str = "1 hour") -> DataFrame:
    users = F.approx_count_distinct("user_id", 0.01) if events.isStreaming else F.count_distinct("user_id")
    return late_ok(events, delay).groupBy(F.window("ts", width, slide)).agg(users.alias("users")).select(F.col("window.start").alias("start"), "users")


def sessions(events: DataFrame, gap: str = "30 minutes", delay: str = "1 hour") -> DataFrame:
    """(user_id, start, stop, events)."""
    grouped = late_ok(events, delay).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("events"))
    return grouped.select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("stop"), "events")


def first_releases(events: DataFrame, horizon: str = "1 day") -> DataFrame:
    """The first event of each user, in a stream within the horizon: a person's filter is released once, not perturbed again."""
    if events.isStreaming:
        return events.withWatermark("ts", horizon).dropDuplicatesWithinWatermark(["user_id"])
    first = events.groupBy("user_id").agg(F.min(F.struct("ts", *(c for c in events.columns if c not in ("ts", "user_id")))).alias("e"))
    return first.select(*("user_id" if c == "user_id" else F.col(f"e.{c}").alias(c) for c in events.columns))


def followed_by(events: DataFrame, others: DataFrame, within: str = "1 hour", delay: str = "2 hours") -> DataFrame:
    """(user_id, first_id, then_id) of each event and each of the others by the same user up to so much later.

    An interval join of two streams, whose state is dropped behind both watermarks, or of two tables.
    """
    x, y = late_ok(events, delay).alias("x"), late_ok(others, delay).alias("y")
    later = (F.col("y.ts") > F.col("x.ts")) & (F.col("y.ts") <= F.col("x.ts") + F.expr(f"INTERVAL {within}"))
    return x.join(y, (F.col("x.user_id") == F.col("y.user_id")) & later).select("x.user_id", F.col("x.event_id").alias("first_id"), F.col("y.event_id").alias("then_id"))


def labelled(events: DataFrame, static: DataFrame) -> DataFrame:
    """Events beside what a table says of their users (user_id, ...): a stream may be joined with a table."""
    return events.join(static, "user_id", "left")


ANSWERS = "event_id bigint, user_id bigint, answer string, asked bigint"


def memoised_answers(events: DataFrame, epsilon: float = 1.0, key: str = "k") -> DataFrame:
    """Each event's type under randomised response, drawn once for each user and type and answered alike ever after.

    The state of a user holds the answers given and how often each was asked, a handful however many events come.
    """
    keep, kinds = math.exp(epsilon) / (math.exp(epsilon) + 1), ("click", "view")

    def answer(names: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        known = json.loads(state.get[0]) if state.exists else {}
        for batch in batches:
            out = []
            for row in batch.sort_values(["ts", "event_id"]).itertuples():
                seen = known.setdefault(row.event_type, [None, 0])
                if seen[0] is None:
                    told = draw(f"{key}|{names[0]}|{row.event_type}") < keep * 2**32
                    seen[0] = kinds[(row.event_type == "view") == told]
                seen[1] += 1
                out.append((row.event_id, names[0], seen[0], seen[1]))
            yield pd.DataFrame(out, columns=["event_id", "user_id", "answer", "asked"])
        state.update((json.dumps(known),))

    return events.groupBy("user_id").applyInPandasWithState(answer, ANSWERS, "known string", "append", "NoTimeout")


def run_to(df: DataFrame, folder: str, checkpoint: str, mode: str = "append"):
    """Run a stream over what is there, into Parquet."""
    return df.writeStream.format("parquet").option("path", folder).option("checkpointLocation", checkpoint).outputMode(mode).trigger(availableNow=True).start()
