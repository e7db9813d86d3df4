"""Structured Streaming: updates in, latest states, hourly histograms, sessions, and a controller that routes to parts."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle, StreamingQuery
from pyspark.sql.types import DoubleType, IntegerType, LongType, StringType, StructField, StructType, TimestampNTZType, TimestampType

from kinetic.plans.params import OptimizerParams
from kinetic.sources.standins import COLUMNS, _steps, events_expressions

#: The events table as a stream reads it: fixed, never inferred.
EVENTS = StructType(
    [StructField("event_id", LongType()), StructField("ts", TimestampNTZType()), StructField("user_id", LongType()), StructField("event_type", StringType()), StructField("value", DoubleType()), StructField("props", StringType())]
)


def updates_source(spark: SparkSession, sf_dir: str, files_per_batch: int = 4, watermark: str = "10 minutes") -> DataFrame:
    """Status updates as a file stream, with event time in UTC, a watermark, and repeated event ids dropped."""
    raw = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_batch).option("recursiveFileLookup", "true").parquet(f"{sf_dir}/events*.parquet")
    rows = _steps(raw.withColumn("ts", F.col("ts").cast("timestamp")), events_expressions()).withColumn("oid", F.col("user_id"))
    return rows.select(*COLUMNS, "ts", "hr", "event_id").withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["event_id"])


def run_to_end(stream: DataFrame, path: str, mode: str = "append") -> DataFrame:
    """Everything that is there now, through the stream, into a Parquet sink with its own checkpoint; reread as a table."""
    query = stream.writeStream.format("parquet").outputMode(mode).option("checkpointLocation", f"{path}/checkpoint").option("path", f"{path}/out").trigger(availableNow=True).start()
    query.awaitTermination()
    return stream.sparkSession.read.schema(stream.schema).parquet(f"{path}/out")


def events_by_time(spark: SparkSession, sf_dir: str, folder: str, slices: int = 4) -> str:
    """The events as files in the order of time, one for each slice of the time that they span; returns a folder that updates_source reads."""
    events = spark.read.parquet(f"{sf_dir}/events.parquet")
    us = F.unix_micros(F.col("ts").cast("timestamp"))
    low, high = events.agg(F.min(us), F.max(us)).first()
    for i in range(slices if low is not None else 0):
        inside = F.least(F.lit(slices - 1), F.floor((us - low) * slices / (high - low + 1))) == i
        events.where(inside).coalesce(1).write.mode("append").parquet(f"{folder}/events.parquet")
    return folder


def _before(spark: SparkSession, path: str, epoch: int, schema: StructType) -> DataFrame:
    """What earlier epochs wrote; a retried epoch sees the same as its first try."""
    return spark.read.schema(StructType([*schema.fields, StructField("gen", LongType())])).option("basePath", path).option("ignoreMissingFiles", "true").parquet(path).where(F.col("gen") < epoch)


def _write(df: DataFrame, path: str, epoch: int, by: tuple[str, ...] = ()) -> None:
    """One folder for each epoch, written anew by a retry."""
    df.write.mode("overwrite").partitionBy(*by).parquet(f"{path}/gen={epoch}")


STATUS = StructType([StructField("oid", LongType()), *[StructField(c, DoubleType()) for c in COLUMNS[1:]], StructField("ts", TimestampType()), StructField("event_id", LongType()), StructField("part", IntegerType()), StructField("quadrant", IntegerType())])
PLANS = StructType([*[StructField(c, IntegerType()) for c in ("part", "lo_layer", "hi_layer")], StructField("lo", DoubleType()), StructField("hi", DoubleType()), StructField("quadrants", IntegerType()), StructField("cost", DoubleType()), StructField("since", TimestampType())])
MOVES = StructType([StructField("oid", LongType()), *[StructField(c, IntegerType()) for c in ("old_part", "new_part", "old_quadrant", "new_quadrant")], StructField("action", StringType())])


def newest(rows: DataFrame) -> DataFrame:
    """Newest row of each object over all generations: of the latest status, and of equal ones the latest generation."""
    rest = [c for c in rows.columns if c != "oid"]
    return rows.groupBy("oid").agg(F.max_by(F.struct(*rest), F.struct("ts", "event_id", "gen")).alias("_s")).select("oid", "_s.*")


def stream_controller(updates: DataFrame, plan: DataFrame, path: str, checkpoint: str, params: OptimizerParams | None = None, period: str = "1 hour") -> StreamingQuery:
    """Routes every batch of updates to parts, tells what moved, and with ``params`` plans anew when a period has begun.

    Below ``path`` each epoch has a folder of its own in objects (rows that
    changed), moves (insert, update, migrate, late; replan for objects that a
    new plan moves) and plans (where a new one was made). A retried epoch
    overwrites its folders, so that nothing counts twice. Plans are broadcast;
    they have as many rows as parts.
    """
    from kinetic.functions.motion import latest_status
    from kinetic.operators.update import STATE, apply_updates, migrate
    from kinetic.plans.optimise import optimise
    from kinetic.sources.shared import kept

    spark = updates.sparkSession
    rows = plan.select(*PLANS.fieldNames()[:-1]).collect()
    for name, fields in (("objects", STATUS), ("moves", MOVES), ("plans", PLANS)):
        spark.createDataFrame([], fields).withColumn("gen", F.lit(-1).cast("long")).write.mode("append").partitionBy("gen").parquet(f"{path}/{name}")

    def upsert(batch: DataFrame, epoch: int) -> None:
        own = batch.sparkSession
        new = kept(latest_status(batch.select("oid", *STATE)))
        state = kept(newest(_before(own, f"{path}/objects", epoch, STATUS)).select("oid", *STATE, "part", "quadrant"))
        plans = _before(own, f"{path}/plans", epoch, PLANS)
        last = plans.agg(F.max("gen")).first()[0]
        now = plans.where(F.col("gen") == last).drop("gen") if last is not None else own.createDataFrame([(*r, None) for r in rows], PLANS)
        now, moved = kept(now), None
        begun = new.agg(F.date_trunc(period.split()[1], F.max("ts")).alias("t")).first()["t"]
        since = now.agg(F.max("since").alias("t")).first()["t"]
        if params is not None and begun is not None and (since is None or begun > since):
            both = state.select("oid", *STATE).unionByName(new.select("oid", *STATE))
            found = optimise(latest_status(both), params).plan
            if not found.isEmpty():
                after_plan = kept(found.select(*PLANS.fieldNames()[:-1]).withColumn("since", F.lit(begun)))
                moved = migrate(state, now, after_plan).withColumn("action", F.lit("replan"))
                now = after_plan
                _write(now, f"{path}/plans", epoch)
        after, moves = apply_updates(state, new, now)
        touched = new.select("oid") if moved is None else new.select("oid").union(moved.select("oid")).distinct()
        _write(after.join(touched, "oid", "left_semi").select(*STATUS.fieldNames()), f"{path}/objects", epoch, ("part", "quadrant"))
        moves = moves.select(*MOVES.fieldNames())
        if moved is not None:
            moves = moves.unionByName(moved.join(new.select("oid"), "oid", "left_anti").select(*MOVES.fieldNames()))
        _write(moves, f"{path}/moves", epoch)

    return updates.writeStream.foreachBatch(upsert).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def controlled(spark: SparkSession, path: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(newest objects, moves, plans) that a controller has written so far."""
    read = [_before(spark, f"{path}/{n}", 2**62, schema) for n, schema in (("objects", STATUS), ("moves", MOVES), ("plans", PLANS))]
    return newest(read[0]), read[1], read[2]


def hourly_speeds(updates: DataFrame, width: float = 5.0) -> DataFrame:
    """hour, bin, n: speed histogram of each tumbling hour, which re-optimisation starts from."""
    return updates.groupBy(F.window("ts", "1 hour"), F.floor(F.col("speed") / width).cast("long").alias("bin")).agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").alias("hour"), "bin", "n")


def sliding_speeds(updates: DataFrame) -> DataFrame:
    """start, n, fastest: over one hour, every quarter."""
    return updates.groupBy(F.window("ts", "1 hour", "15 minutes")).agg(F.count(F.lit(1)).alias("n"), F.max("speed").alias("fastest")).select(F.col("window.start").alias("start"), "n", "fastest")


def trips(updates: DataFrame, idle: str = "6 hours") -> DataFrame:
    """oid, start, stop, n: sessions parted by idle gaps."""
    return updates.groupBy("oid", F.session_window("ts", idle).alias("w")).agg(F.count(F.lit(1)).alias("n")).select("oid", F.col("w.start").alias("start"), F.col("w.end").alias("stop"), "n")


LATEST = StructType([StructField("oid", LongType()), StructField("event_id", LongType()), StructField("us", LongType()), StructField("speed", DoubleType()), StructField("late", IntegerType())])


class LatestStatus(StatefulProcessor):
    """Keeps the newest status of each object; rows older than it come out marked as late and change nothing."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.newest = handle.getValueState("newest", StructType([StructField("us", LongType()), StructField("event_id", LongType())]))

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        known = tuple(self.newest.get()) if self.newest.exists() else (-(2**63), -(2**63))
        for pdf in rows:
            out = []
            for r in pdf.sort_values(["us", "event_id"]).itertuples():
                late = (r.us, r.event_id) < known
                if not late:
                    known = (int(r.us), int(r.event_id))
                out.append((key[0], r.event_id, r.us, r.speed, int(late)))
            yield pd.DataFrame(out, columns=[f.name for f in LATEST])
        self.newest.update(known)

    def close(self) -> None:
        pass


def stateful_latest(updates: DataFrame) -> DataFrame:
    """Every update with whether it came late, by a value state for each object (needs the RocksDB state store)."""
    rows = updates.select("oid", "event_id", F.unix_micros("ts").alias("us"), "speed")
    return rows.groupBy("oid").transformWithStateInPandas(LatestStatus(), LATEST, "Append", "None")
