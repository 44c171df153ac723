"""Streams with state of their own: the last events of each user, and pairs of events in an interval."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupStateTimeout

from .streams import drained, event_stream


def last_of_each(stream: DataFrame, k: int) -> DataFrame:
    """(user_id, n, last): a row whenever a user's state changes; the state is a count and k ids."""
    import pandas as pd

    def keep(key, frames, state):
        n, ids = state.get if state.exists else (0, [])
        ids = list(ids)
        for f in frames:
            got = f["event_id"].tolist()
            n += len(got)
            ids = sorted(ids + got)[-k:]
        state.update((n, ids))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "last": [",".join(map(str, ids))]})

    return stream.select("user_id", "event_id").groupBy("user_id").applyInPandasWithState(keep, "user_id long, n long, last string", "n long, ids array<long>", "update", GroupStateTimeout.NoTimeout)


def last_events(spark, sf_dir, k: int = 3) -> DataFrame:
    """The newest state of each user: of several updates the one with the highest count."""
    d = drained(last_of_each(event_stream(spark, sf_dir), k), "update")
    return d.groupBy("user_id").agg(F.max("n").alias("n"), F.max_by("last", "n").alias("last"))


def views_and_clicks(spark, sf_dir) -> DataFrame:
    """Clicks of a user within six hours after a view: two streams, each with a watermark."""
    side = lambda kind, a, t, u: event_stream(spark, sf_dir).where(F.col("event_type") == kind).withWatermark("ts", "1 day").select(F.col("event_id").alias(a), F.col("ts").alias(t), F.col("user_id").alias(u))
    on = F.expr("viewer = clicker AND clicked_at >= seen_at AND clicked_at <= seen_at + INTERVAL 6 HOURS")
    return drained(side("view", "viewed", "seen_at", "viewer").join(side("click", "clicked", "clicked_at", "clicker"), on).select("viewed", "clicked"))
