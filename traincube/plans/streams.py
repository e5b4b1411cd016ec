"""Queries over the events table as a stream of daily files."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from traincube.operators import trains
from traincube.plans.registry import query
from traincube.plans.workloads import TENTH, VEHICLE_LEVELS_SQL, vehicle_tree_report
from traincube.sources import grids
from traincube.sources.scratch import shared_folder
from traincube.streaming.segments import TrainStream, daily_files, events_stream, roster_counts, run_available, segment_stats, sessions


def _folder(spark) -> str:
    return f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"


def feed(spark, sf_dir: str, files_per_batch: int = 5, ends: int = 0) -> DataFrame:
    """The events table day by day, some days in each batch."""
    return events_stream(spark, daily_files(grids.read(spark, sf_dir, "events"), _folder(spark), ends), files_per_batch)


def _rounded(out: DataFrame) -> DataFrame:
    return out.select("seg", "n", F.round("vmin", 4).alias("vmin"), F.round("vmax", 4).alias("vmax"))


_SEG = "date_diff('microsecond', TIMESTAMP '2024-01-01', ts) // {}"
_AGG = "CAST(count(*) AS BIGINT) AS n, round(min(value), 4) AS vmin, round(max(value), 4) AS vmax"


@query("q_stream_segments", f"SELECT ({_SEG.format(28800000000)}) AS seg, {_AGG} FROM events GROUP BY ALL")
def stream_segments(spark, sf_dir):
    return _rounded(segment_stats(feed(spark, sf_dir), _folder(spark)))


@query("q_stream_sliding", f"SELECT ({_SEG.format(1800000000)}) - k AS seg, {_AGG} FROM events, (SELECT unnest(range(16)) AS k) GROUP BY ALL")
def stream_sliding(spark, sf_dir):
    """Windows of eight hours every half hour; seg numbers their first half hour."""
    return _rounded(segment_stats(feed(spark, sf_dir, 10), _folder(spark), slide=30))


@query("q_stream_sessions", """WITH e AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events),
s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM e)
SELECT user_id, epoch_us(min(ts)) AS start_us, CAST(count(*) AS BIGINT) AS n FROM s GROUP BY user_id, k""")
def stream_sessions(spark, sf_dir):
    """Sessions of each user, closed by a gap of six hours."""
    return sessions(feed(spark, sf_dir, 10, ends=11), _folder(spark)).where("user_id >= 0")


@query("q_stream_roster_join", f"WITH r AS (SELECT DISTINCT user_id FROM events WHERE ({_SEG.format(28800000000)}) = 0) SELECT ({_SEG.format(28800000000)}) AS seg, CAST(count(*) AS BIGINT) AS n, round(sum(value), 4) AS total FROM events JOIN r USING (user_id) GROUP BY ALL")
def stream_roster_join(spark, sf_dir):
    """Later events of the users that the first segment has."""
    first = grids.read(spark, sf_dir, "events").where(grids.step_of("ts", "2024-01-01 00:00:00", 480) == 0).select("user_id").distinct()
    out = roster_counts(feed(spark, sf_dir, 10), first, _folder(spark))
    return out.select("seg", "n", F.round("total", 4).alias("total"))


def train_stream(spark, sf_dir, files_per_batch: int = 10) -> TrainStream:
    """The vehicle set folded in from the stream; users and the box of positions are known beforehand."""
    shape, cells = grids.vehicle(spark, sf_dir)
    own = TrainStream(spark, shape, grids.level_box(cells), TENTH)
    micros = F.unix_micros("ts") - F.lit(1_704_067_200_000_000)

    def batch(df, number):
        k = F.get_json_object("props", "$.k").cast("double")
        step = F.floor(micros / 1_800_000_000).cast("long")
        part = df.select(step.alias("step"), F.col("user_id").alias("entity"), "value", k.alias("k")).where(F.col("step").between(0, shape.steps - 1))
        own.fold(part.groupBy("step", "entity").agg(F.sum("value").alias("c1"), F.sum("k").alias("c2"), F.count("*").cast("double").alias("c3")), number)

    run_available(feed(spark, sf_dir, files_per_batch), batch)
    own.finish()
    return own


@query("q_stream_trains", VEHICLE_LEVELS_SQL)
def stream_trains(spark, sf_dir):
    """Three batches of ten days; errors are the trains' own bounds, as orders are not kept in the stream."""
    return vehicle_tree_report(trains.numel(train_stream(spark, sf_dir).all()))
