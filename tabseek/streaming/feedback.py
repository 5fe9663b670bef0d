"""Windows, sessions and joins over the event stream (T3s-T9s).

Every function takes a batch or a streaming DataFrame of events; on a stream the
watermark bounds the state, on a batch it has no effect.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout


def stamped(events: DataFrame) -> DataFrame:
    """``events`` with a zoned timestamp, as event-time windows need."""
    return events.withColumn("ts", F.col("ts").cast("timestamp"))


def tumbling(events: DataFrame, length: str = "1 hour", delay: str = "10 minutes") -> DataFrame:
    return stamped(events).withWatermark("ts", delay).groupBy(F.window("ts", length).alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def sliding(events: DataFrame, length: str = "1 hour", slide: str = "30 minutes", delay: str = "10 minutes") -> DataFrame:
    return stamped(events).withWatermark("ts", delay).groupBy(F.window("ts", length, slide).alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: str = "30 minutes", delay: str = "10 minutes") -> DataFrame:
    """Sessions of each user: runs of events less than ``gap`` apart."""
    return stamped(events).withWatermark("ts", delay).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def once(events: DataFrame, delay: str = "10 minutes") -> DataFrame:
    """Each event_id once; on a stream, duplicates within the watermark."""
    if events.isStreaming:
        return stamped(events).withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])
    return events.dropDuplicates(["event_id"])


def click_grades(events: DataFrame) -> DataFrame:
    """Implicit grades of (user, item): purchase 2, click 1, else 0; the best counts."""
    grade = F.when(F.col("event_type") == "purchase", 2).when(F.col("event_type") == "click", 1).otherwise(0)
    return events.groupBy("user_id", F.get_json_object("props", "$.k").cast("long").alias("item")).agg(F.max(grade).alias("grade"))


def view_then_click(events: DataFrame, within: str = "10 minutes", delay: str = "10 minutes") -> DataFrame:
    """Pairs of a view and a click of the same user up to ``within`` later."""
    e = stamped(events)
    views = e.where("event_type = 'view'").select(F.col("event_id").alias("view_id"), "user_id", F.col("ts").alias("viewed")).withWatermark("viewed", delay)
    clicks = e.where("event_type = 'click'").select(F.col("event_id").alias("click_id"), F.col("user_id").alias("u"), F.col("ts").alias("clicked")).withWatermark("clicked", delay)
    near = (F.col("user_id") == F.col("u")) & (F.col("clicked") >= F.col("viewed")) & (F.col("clicked") <= F.col("viewed") + F.expr(f"INTERVAL {within}"))
    return views.join(clicks, near).select("view_id", "click_id", "user_id")


def daily_wins(events: DataFrame, delay: str = "1 hour") -> DataFrame:
    """Per day and item: views, and the clicks and purchases they won; on a stream the watermark closes a day."""
    item = F.get_json_object("props", "$.k").cast("long")
    won = F.count_if(F.col("event_type").isin("click", "purchase"))
    counted = stamped(events).withWatermark("ts", delay).groupBy(F.window("ts", "1 day").alias("w"), item.alias("item"))
    return counted.agg(F.count_if(F.col("event_type") == "view").alias("views"), won.alias("wins")).select(F.col("w.start").alias("start"), "item", "views", "wins")


def running_wins(events: DataFrame) -> DataFrame:
    """(item, wins) after each batch in which an item wins: clicks and purchases so far, in custom state.

    The state of an item is one number; events are cut to the winning ones before they are shuffled.
    """
    won = events.where(F.col("event_type").isin("click", "purchase")).select(F.get_json_object("props", "$.k").cast("long").alias("item"))

    def add(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        wins = (state.get[0] if state.exists else 0) + sum(len(f) for f in frames)
        state.update((wins,))
        yield pd.DataFrame({"item": [key[0]], "wins": [wins]})

    return won.groupBy("item").applyInPandasWithState(add, "item long, wins long", "wins long", "update", GroupStateTimeout.NoTimeout)
