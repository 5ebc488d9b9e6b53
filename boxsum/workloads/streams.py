"""Streams: upkeep of anchors from micro-batches, windows, sessions, late data and stateful carries."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from boxsum.operators import query
from boxsum.operators.build import AnchorStore
from boxsum.sources.grids import G2, cents, dictionary, hours, table
from boxsum.sources.io import scratch
from boxsum.streaming.upkeep import closed, event_stream, gathered, repair_late, stream_cells, stream_store
from boxsum.workloads.cases import add, all_subsets, anchor_sql, box_sql, store_of


def from_stream(s, d) -> DataFrame:
    """A store that each micro-batch adds to."""
    return stream_store(stream_cells(event_stream(s, d)), G2.sized(s, d), all_subsets("ut")).table("ut")


# the stream's axis ends with the last event's hour, so anchors beyond it are not there yet
_SEEN = "(SELECT max(CAST(floor((epoch_us(ts) - epoch_us(TIMESTAMP '2024-01-01')) / 3600000000) AS INT)) + 1 FROM events)"
add("w21_stream_equals_batch", from_stream, f"SELECT * FROM ({anchor_sql(G2, 'ut')}) WHERE q_t * 24 <= {_SEEN}")


def stream_series(s, d) -> DataFrame:
    """A series of all users from the tables that a stream grew."""
    return query.area_series(stream_store(stream_cells(event_stream(s, d)), G2.sized(s, d), [("u",)]).read(), {"u": (3, 101)})


add("w21_stream_series", stream_series, box_sql(G2, {"u": (3, 101)}, "u"))


def sliced(s, d) -> DataFrame:
    """Hourly slices, each appended once, when the watermark has passed it."""
    rows = lambda events: events.select("ts", cents("value").alias("v"))
    slices = lambda events: rows(events).withWatermark("ts", "2 hours").groupBy(F.window("ts", "1 hour")).agg(F.sum("v").alias("s"), F.count("*").alias("n"))
    return closed(s, d, lambda events: slices(events).select(F.unix_micros("window.start").alias("start"), "s", "n"))


_HOUR = "CAST(floor(epoch_us(ts) / 3600000000) * 3600000000 AS BIGINT)"
add("s01_hour_slices", sliced, f"SELECT {_HOUR} AS start, CAST(sum(CAST(round(value * 100) AS BIGINT)) AS BIGINT) AS s, count(*) AS n FROM events GROUP BY 1")


def sliding(s, d) -> DataFrame:
    def windows(events: DataFrame) -> DataFrame:
        held = events.select("ts", cents("value").alias("v")).withWatermark("ts", "2 hours").groupBy(F.window("ts", "6 hours", "1 hour"))
        return held.agg(F.sum("v").alias("s"), F.count("*").alias("n")).select(F.unix_micros("window.start").alias("start"), "s", "n")

    return closed(s, d, windows)


add("s02_sliding", sliding, f"SELECT start, CAST(sum(v) AS BIGINT) AS s, count(*) AS n FROM (SELECT CAST({_HOUR} - k * 3600000000 AS BIGINT) AS start, CAST(round(value * 100) AS BIGINT) AS v FROM events, range(6) r(k)) GROUP BY start")


def sessions(s, d) -> DataFrame:
    def found(events: DataFrame) -> DataFrame:
        held = events.select("ts", "user_id").withWatermark("ts", "2 hours").groupBy(F.session_window("ts", "3 hours"), "user_id")
        return held.agg(F.count("*").alias("n")).select("user_id", F.unix_micros("session_window.start").alias("start"), "n")

    return closed(s, d, found)


add("s03_session", sessions, "WITH e AS (SELECT user_id, epoch_us(ts) AS t, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts) < 10800000000 THEN 0 ELSE 1 END AS new FROM events), k AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY t ROWS UNBOUNDED PRECEDING) AS k FROM e) SELECT user_id, CAST(min(t) AS BIGINT) AS start, count(*) AS n FROM k GROUP BY user_id, k")


def carry(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
    """A user's running total from batch to batch."""
    total, n = state.get if state.exists else (0, 0)
    for b in batches:
        total, n = total + int(b["v"].sum()), n + len(b)
    state.update((total, n))
    yield pd.DataFrame({"user_id": [key[0]], "s": [total], "n": [n]})


def carried(s, d) -> DataFrame:
    rows = event_stream(s, d).select("user_id", cents("value").alias("v"))
    out = rows.groupBy("user_id").applyInPandasWithState(carry, "user_id long, s long, n long", "s long, n long", "update", GroupStateTimeout.NoTimeout)
    return gathered(out, "update").groupBy("user_id").agg(F.max_by("s", "n").alias("s"), F.max("n").alias("n"))


add("s04_carry", carried, "SELECT user_id, CAST(sum(CAST(round(value * 100) AS BIGINT)) AS BIGINT) AS s, count(*) AS n FROM events GROUP BY user_id")


def late(s, d) -> DataFrame:
    """A fifth of the events come after the tables were built, and are added to every later anchor."""
    is_late = "event_id % 5 = 3"
    rows = lambda df: df.groupBy(F.col("user_id").cast("int").alias("u"), hours("ts").alias("t")).agg(F.sum(cents("value")).alias("sx"), F.count("*").alias("n"))
    events = table(s, d, "events")
    store = AnchorStore.build(rows(events.where(f"not ({is_late})")), G2.sized(s, d), [("u",), ("t",)])
    return repair_late(store, rows(events.where(is_late))).tables["t",]


add("s05_late_repair", late, anchor_sql(G2, "t"))


def against_watermark(s, d) -> DataFrame:
    """Events that come late: after the others every 11th of the last two hours, then every 7th of the first 20 days.

    The first are within the watermark and count, the second are behind it and are dropped (a batch filters by the
    watermark of the one before). (start, n) of the hourly slices, and how many rows were dropped under a start of -1.
    """
    events = table(s, d, "events")
    last = events.agg(F.max("ts")).first()[0]
    early = (F.col("event_id") % 7 == 3) & (F.col("ts") < F.lit("2024-01-21").cast("timestamp_ntz"))
    edge = (F.col("event_id") % 11 == 5) & (F.col("ts") >= F.lit(last) - F.expr("interval 2 hours")) & (F.col("ts") < F.lit(last))
    root = scratch(s, "late")
    for part in (~early & ~edge, edge, early):  # a file each, in this order
        events.where(F.coalesce(part, F.lit(False))).coalesce(1).write.mode("append").parquet(f"{root}/events.parquet")
    slices = closed(s, root, lambda e: e.select("ts").withWatermark("ts", "3 hours").groupBy(F.window("ts", "1 hour")).agg(F.count("*").alias("n")).select(F.unix_micros("window.start").alias("start"), "n"))
    slices = slices.where(F.col("start") < F.unix_micros(F.lit("2100-01-01").cast("timestamp")))
    dropped = slices.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("kept")).crossJoin(events.where("ts is not null").agg(F.count("*").alias("all")))  # a row each
    return slices.unionByName(dropped.select(F.lit(-1).cast("long").alias("start"), (F.col("all") - F.col("kept")).alias("n")))


_EARLY = "(event_id % 7 = 3 AND ts < TIMESTAMP '2024-01-21')"
add("s05_late_against_watermark", against_watermark, f"SELECT {_HOUR} AS start, count(*) AS n FROM events WHERE NOT {_EARLY} GROUP BY 1 UNION ALL SELECT -1 AS start, count(*) AS n FROM events WHERE {_EARLY}")


def with_dictionary(s, d) -> DataFrame:
    names = dictionary(table(s, d, "events"), "event_type", "e").withColumn("code", F.upper(F.substring("event_type", 1, 3)))
    rows = event_stream(s, d).join(F.broadcast(names), "event_type")  # a row a type of event, their number is checked
    return gathered(rows.groupBy("code").agg(F.count("*").alias("n")), "complete")


add("s06_stream_static", with_dictionary, "SELECT upper(substr(event_type, 1, 3)) AS code, count(*) AS n FROM events GROUP BY 1")


def deduplicated(s, d) -> DataFrame:
    rows = event_stream(s, d).select("event_id", "ts")
    twice = rows.union(rows).withWatermark("ts", "40 days").dropDuplicatesWithinWatermark(["event_id"])
    return gathered(twice.select("event_id"))


add("s07_dedup_within_watermark", deduplicated, "SELECT event_id FROM events")


def joined(s, d) -> DataFrame:
    """Events with others of the same user within the next ten minutes: two streams, both with watermarks."""
    a = event_stream(s, d).select(F.col("event_id").alias("a"), "user_id", F.col("ts").alias("ta")).withWatermark("ta", "1 hour")
    b = event_stream(s, d).select(F.col("event_id").alias("b"), F.col("user_id").alias("user_b"), F.col("ts").alias("tb")).withWatermark("tb", "1 hour")
    return gathered(a.join(b, F.expr("user_id = user_b and tb > ta and tb <= ta + interval 10 minutes")).select("a", "b"))


add("s08_stream_stream", joined, "SELECT x.event_id AS a, y.event_id AS b FROM events x JOIN events y ON x.user_id = y.user_id AND y.ts > x.ts AND y.ts <= x.ts + INTERVAL 10 MINUTE")


def store_from_batch(s, d) -> DataFrame:
    return store_of(s, d, G2, all_subsets("ut")).tables["u", "t"]


add("w21_batch", store_from_batch, anchor_sql(G2, "ut"))
