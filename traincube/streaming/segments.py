"""Segments of a growing stream: statistics, and trains folded in as segments close.

Steps and entities are known beforehand. A segment closes when the stream has
passed its end by ``lateness`` steps, or when the stream is finished. What is kept
between batches are tables in one folder: cells by batch and segment, totals of every
entity where the open segments begin, and trains by level and batch. Closing reads the
cells of the segments that close and those totals, never what is closed already. A
batch that runs again overwrites its own files, and what is closed follows from the
tables, so a restart neither loses nor doubles anything. Rows for closed segments are
set apart.
"""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from traincube.functions.budget import Budget
from traincube.operators import compress, merge
from traincube.operators.trains import SCHEMA
from traincube.sources.grids import COMPONENTS, ParticleSet
from traincube.sources.scratch import shared_folder

_CELLS = "step long, entity long, c1 double, c2 double, c3 double"
_TOTALS = "entity long, c1 double, c2 double, c3 double"


_EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def as_utc(ts: str) -> Column:
    """A time without zone as an instant, read as UTC whatever the session's zone is."""
    return F.to_timestamp(F.concat(F.col(ts).cast("string"), F.lit("+00:00")))


def events_stream(spark: SparkSession, folder: str, files_per_batch: int = 1) -> DataFrame:
    """Files of events under a folder as a stream, oldest first, with a fixed schema."""
    raw = spark.readStream.schema(_EVENTS).option("recursiveFileLookup", True).option("pathGlobFilter", "*.parquet").option("maxFilesPerTrigger", files_per_batch).parquet(folder)
    return raw.withColumn("ts", as_utc("ts"))


def daily_files(events: DataFrame, folder: str, ends: int = 0) -> str:
    """Events as one file for each day, whose times follow the days, so that a stream reads them in turn.

    ends: so many files with one event of user -1 each, a year later, which let a stream's
    watermark pass all others.
    """
    spark = events.sparkSession
    day = F.to_date("ts").cast("string")
    events.withColumn("day", day).repartition("day").sortWithinPartitions("day").write.partitionBy("day").parquet(folder)
    last = events.agg(F.max("ts")).first()[0]
    for k in range(ends if last is not None else 0):
        end = spark.range(1).select(F.lit(-1).cast("long").alias("event_id"), (F.lit(last) + F.make_dt_interval(F.lit(365 + k))).cast("timestamp_ntz").alias("ts"), F.lit(-1).cast("long").alias("user_id"), F.lit(None).cast("string").alias("event_type"), F.lit(0.0).alias("value"), F.lit(None).cast("string").alias("props"))
        end.withColumn("day", day).repartition(1).write.mode("append").partitionBy("day").parquet(folder)
    at = spark._jvm.org.apache.hadoop.fs.Path(folder)
    fs, found = at.getFileSystem(spark._jsc.hadoopConfiguration()), []
    files = fs.listFiles(at, True)
    while files.hasNext():
        own = files.next().getPath()
        if own.getName().endswith(".parquet"):
            found.append((own.getParent().getName(), own.getName(), own))
    for k, (_, _, own) in enumerate(sorted(found, key=lambda x: x[:2])):
        fs.setTimes(own, 1_600_000_000_000 + 1000 * k, -1)
    return folder


def _exists(spark: SparkSession, path: str) -> bool:
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark._jsc.hadoopConfiguration()).exists(p)


def run_available(stream: DataFrame, batch, mode: str = "append", checkpoint: str | None = None) -> None:
    """Run all that is there through foreachBatch and stop."""
    checkpoint = checkpoint or f"{shared_folder(stream.sparkSession)}/stream-{uuid.uuid4().hex}"
    stream.writeStream.foreachBatch(batch).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()


_ORIGIN = 1_704_067_200_000_000


def _latest(updates: DataFrame, keys: list[str], folder: str) -> DataFrame:
    """Run a stream of updates; of each key the row of the last batch counts."""
    schema = updates.schema

    def write(df: DataFrame, batch: int):
        df.withColumn("batch", F.lit(batch).cast("long")).write.mode("overwrite").parquet(f"{folder}/stats/b={batch}")

    run_available(updates, write, "update")
    rows = updates.sparkSession.read.schema(", ".join(f"{f.name} {f.dataType.simpleString()}" for f in schema) + ", batch long").parquet(f"{folder}/stats")
    rest = [c for c in updates.columns if c not in keys]
    return rows.groupBy(*keys).agg(F.max_by(F.struct(*rest), "batch").alias("_s")).select(*keys, "_s.*")


def segment_stats(stream: DataFrame, folder: str, minutes: int = 480, slide: int | None = None) -> DataFrame:
    """seg, n, vmin and vmax of ``value`` in windows of some minutes, tumbling, or sliding by ``slide``; seg counts slides."""
    step = slide or minutes
    window = F.window("ts", f"{minutes} minutes", f"{step} minutes")
    windows = stream.withWatermark("ts", "1 hour").groupBy(window).agg(F.count("*").alias("n"), F.min("value").alias("vmin"), F.max("value").alias("vmax"))
    seg = F.floor((F.unix_micros("window.start") - F.lit(_ORIGIN)) / (step * 60_000_000)).cast("long")
    return _latest(windows.select(seg.alias("seg"), "n", "vmin", "vmax"), ["seg"], folder)


def sessions(stream: DataFrame, folder: str, hours: int = 6) -> DataFrame:
    """user_id, start_us and n of each session: events of a user with no gap of ``hours`` between them; appended when the watermark has passed them."""
    own = stream.withWatermark("ts", "1 hour").groupBy("user_id", F.session_window("ts", f"{hours} hours")).agg(F.count("*").alias("n"))
    own = own.select("user_id", F.unix_micros("session_window.start").alias("start_us"), "n")
    run_available(own, lambda df, batch: df.write.mode("overwrite").parquet(f"{folder}/sessions/b={batch}"))
    return stream.sparkSession.read.schema("user_id long, start_us long, n long").parquet(f"{folder}/sessions").select("user_id", "start_us", "n")


def roster_counts(stream: DataFrame, roster: DataFrame, folder: str, minutes: int = 480) -> DataFrame:
    """seg, n and total of ``value`` over the events whose user is in a static roster (user_id): a stream joined with a table."""
    met = stream.withWatermark("ts", "1 hour").join(roster, "user_id")
    windows = met.groupBy(F.window("ts", f"{minutes} minutes")).agg(F.count("*").alias("n"), F.sum("value").alias("total"))
    seg = F.floor((F.unix_micros("window.start") - F.lit(_ORIGIN)) / (minutes * 60_000_000)).cast("long")
    return _latest(windows.select(seg.alias("seg"), "n", "total"), ["seg"], folder)


class TrainStream:
    """Trains of a particle stream, kept up to date batch by batch."""

    def __init__(self, spark: SparkSession, shape: ParticleSet, box, budget: Budget, folder: str | None = None, lateness: int = 2):
        self.spark, self.shape, self.box, self.budget, self.lateness = spark, shape, box, budget, lateness
        self.folder = folder or f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"
        self.known: tuple[int, list[int]] | None = None  # after which batch, and what was closed then

    def cells(self, first: int, last: int) -> DataFrame:
        """Cells of the segments from first to before last; only their files are read."""
        path = f"{self.folder}/cells"
        if not _exists(self.spark, path):
            return self.spark.createDataFrame([], _CELLS)
        rows = self.spark.read.option("basePath", path).schema(_CELLS + ", b long, seg long").parquet(path).where(F.col("seg").between(first, last - 1))
        return rows.groupBy("step", "entity").agg(*(F.sum(c).alias(c) for c in COMPONENTS))

    def totals(self, upto: int, batch: int) -> DataFrame:
        """Totals of each entity before segment ``upto``, as an earlier batch left them."""
        path = f"{self.folder}/totals"
        if not upto or not _exists(self.spark, path):
            return self.spark.createDataFrame([], _TOTALS)
        rows = self.spark.read.option("basePath", path).schema(_TOTALS + ", b long, upto long").parquet(path)
        return rows.where((F.col("upto") == upto) & (F.col("b") != batch)).drop("b", "upto")

    def trains(self, level: int) -> DataFrame:
        path = f"{self.folder}/trains{level}"
        if not _exists(self.spark, path):
            return self.spark.createDataFrame([], SCHEMA)
        return self.spark.read.schema(SCHEMA).parquet(path)

    def _closed(self, level: int, batch: int) -> int:
        """Segments of a level that are there already, without those of this batch, which may run again."""
        path = f"{self.folder}/trains{level}"
        if not _exists(self.spark, path):
            return 0
        seen = self.spark.read.option("basePath", path).schema(SCHEMA + ", b long").parquet(path).where(F.col("b") != batch).agg(F.max("seg")).first()[0]
        return 0 if seen is None else seen + 1

    def _before(self, batch: int) -> list[int]:
        """Closed segments by level before this batch: from memory after an earlier one, from the tables after a restart or in a second run."""
        if self.known and self.known[0] < batch:
            return self.known[1]
        return [self._closed(level, batch) for level in range(len(self.shape.fanin) + 1)]

    def fold(self, cells: DataFrame, batch: int) -> None:
        """Take in a batch of cells (step, entity, c1, c2, c3) and close what can be closed."""
        span = self.shape.segment
        first_open = self._before(batch)[0] * span
        cells.where(F.col("step") < first_open).write.mode("overwrite").parquet(f"{self.folder}/late/b={batch}")
        own = cells.where(F.col("step") >= first_open).select("step", "entity", *COMPONENTS, F.floor(F.col("step") / span).cast("long").alias("seg"))
        own.repartition("seg").write.mode("overwrite").partitionBy("seg").parquet(f"{self.folder}/cells/b={batch}")
        last = self.spark.read.schema(_CELLS + ", seg long").parquet(f"{self.folder}/cells/b={batch}").agg(F.max("step")).first()[0]
        if last is not None:
            self._close(max(0, (int(last) + 1 - self.lateness) // span), batch)

    def finish(self) -> None:
        """Close all segments; the stream has ended."""
        self._close(self.shape.segments, 1 << 40)

    def _close(self, upto: int, batch: int) -> None:
        fanin, before = self.shape.fanin, self._before(batch)
        now, have = list(before), before[0]
        if upto > have:
            cells, base = self.cells(have, upto), self.totals(have, batch)
            own = cells.select(F.floor(F.col("step") / self.shape.segment).cast("long").alias("seg"), F.col("entity").cast("int").alias("entity"), *COMPONENTS)
            # The last totals of each entity, added in the order in which a batch job adds them.
            after = compress.running_sums(own, have, base).groupBy("entity").agg(F.max_by(F.struct(*COMPONENTS), "seg").alias("c")).select(F.col("entity").cast("long").alias("entity"), "c.*")
            after.write.mode("overwrite").parquet(f"{self.folder}/totals/b={batch}/upto={upto}")
            new = compress.segments(cells, self.shape, self.budget, share=1.0 / (1 + len(fanin)), box=self.box, only=(have, upto), base=base)
            new.write.mode("overwrite").parquet(f"{self.folder}/trains0/b={batch}")
            now[0] = upto
        for level, f in enumerate(fanin):
            ready = now[level] // f
            if ready > before[level + 1]:
                part = self.trains(level).where(F.col("seg").between(before[level + 1] * f, ready * f - 1))
                merge.merge_level(part, f, self.budget, 1.0 / (len(fanin) - level)).write.mode("overwrite").parquet(f"{self.folder}/trains{level + 1}/b={batch}")
                now[level + 1] = ready
        self.known = (batch, now)

    def all(self) -> DataFrame:
        out = self.trains(0)
        for level in range(1, len(self.shape.fanin) + 1):
            out = out.unionByName(self.trains(level))
        return out
