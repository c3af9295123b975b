"""Streams of events: parity of degrees as they come, windows, late rows, joins."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from tourspark.session import read_table, stage_path

EVENT = "event_id long, ts timestamp, user_id long, event_type string, value double"
#: Longer than the span of the given events: nothing is late unless a query wants it so.
PATIENT = "90 days"


def rows_of(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events with a time that watermarks accept."""
    rows = read_table(spark, sf_dir, "events")
    return rows.select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type", "value")


def staged_copies(rows: list[DataFrame], gap: float = 0.0) -> str:
    """A folder that a stream reads in the order of the list, a file or more for each part."""
    spark = rows[0].sparkSession
    path = stage_path(spark, "stream")
    for i, part in enumerate(rows):
        if i and gap:
            time.sleep(gap)  # files are taken by time of change
        part.write.mode("append").parquet(path)
    return path


def stream_of(spark: SparkSession, path: str, delay: str = PATIENT, files: int | None = 1) -> DataFrame:
    """``files``: how many a batch takes; one here, so that small tables make several batches.
    None: all that are there."""
    source = spark.readStream.schema(EVENT)
    if files is not None:
        source = source.option("maxFilesPerTrigger", files)
    return source.parquet(path).withWatermark("ts", delay)


def stream_in_steps(rows: list[DataFrame], delay: str = PATIENT) -> tuple[DataFrame, Iterator[None]]:
    """A stream, and the steps by which it gets the parts of the list.

    A step writes the next part, in as many files as its tasks make; a run of the stream
    after each step takes them all as one batch, so batches don't depend on the table's size.
    """
    spark = rows[0].sparkSession
    path = stage_path(spark, "stream")
    rows[0].limit(0).write.parquet(path)  # a stream needs its folder

    def steps() -> Iterator[None]:
        for part in rows:
            part.write.mode("append").parquet(path)
            yield

    return stream_of(spark, path, delay, None), steps()


def halves(rows: DataFrame) -> list[DataFrame]:
    """Two batches over the same time, so that windows meet rows of both."""
    return [rows.where("event_id % 2 = 0"), rows.where("event_id % 2 = 1")]


def drain(stream: DataFrame, mode: str, keys: list[str] | None = None, steps: Iterable[None] = (None,)) -> DataFrame:
    """Run a stream over what is there, after each of the steps, and give its final rows.

    Every batch is written with its number, so a batch that is run again replaces itself.
    ``update``: the last row of each key counts; ``complete``: the last batch does.
    """
    spark = stream.sparkSession
    out, check = stage_path(spark, "stream-out"), stage_path(spark, "stream-check")
    schema = stream.schema

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/batch={number}")

    for _ in steps:
        run = stream.writeStream.outputMode(mode).option("checkpointLocation", check).trigger(availableNow=True).foreachBatch(keep).start()
        run.awaitTermination()
    found = spark.read.schema(schema.add("batch", "long")).option("basePath", out).parquet(f"{out}/batch=*")
    names = [f.name for f in schema.fields if f.name != "batch"]
    if mode == "append":
        return found.select(names)
    if mode == "complete":
        last = found.agg(F.max("batch").alias("last"))
        return found.join(F.broadcast(last), F.col("batch") == F.col("last")).select(names)
    return found.groupBy(*keys).agg(F.max_by(F.struct(*[n for n in names if n not in keys]), "batch").alias("s")).select(*keys, "s.*")


def micros(c) -> F.Column:
    return F.unix_micros(c)


def tumbling(stream: DataFrame, width: str = "1 hour") -> DataFrame:
    """start, event_type, n, users_odd: events in each window and whether they are odd."""
    made = stream.groupBy(F.window("ts", width).alias("w"), "event_type").agg(F.count("*").alias("n"))
    return made.select(micros("w.start").alias("start"), "event_type", "n", (F.col("n") % 2 == 1).alias("odd"))


def sliding(stream: DataFrame, width: str = "1 day", step: str = "6 hours") -> DataFrame:
    return stream.groupBy(F.window("ts", width, step).alias("w")).agg(F.count("*").alias("n")).select(micros("w.start").alias("start"), "n")


def sessions(stream: DataFrame, gap: str = "30 minutes") -> DataFrame:
    made = stream.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))
    return made.select("user_id", micros("w.start").alias("start"), "n")


def deduplicated(stream: DataFrame) -> DataFrame:
    return stream.dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id")


def follow_ups(left: DataFrame, right: DataFrame, within: str = "1 hour") -> DataFrame:
    """Pairs of events of one user, the right one up to ``within`` after the left."""
    a = left.select(F.col("event_id").alias("first"), F.col("user_id").alias("u1"), F.col("ts").alias("t1"))
    b = right.select(F.col("event_id").alias("second"), F.col("user_id").alias("u2"), F.col("ts").alias("t2"))
    return a.join(b, F.expr(f"u1 = u2 AND t2 > t1 AND t2 <= t1 + INTERVAL {within}")).select("first", "second")


def parity_of(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
    degree = state.get[0] if state.exists else 0
    degree += sum(len(b) for b in batches)
    state.update((degree,))
    yield pd.DataFrame({"v": [key[0]], "degree": [degree], "odd": [degree % 2 == 1]})


def parity(stream: DataFrame) -> DataFrame:
    """v, degree, odd of every user that a batch touches; the state is one number a user."""
    return stream.select(F.col("user_id").alias("v")).groupBy("v").applyInPandasWithState(parity_of, "v long, degree long, odd boolean", "degree long", "update", GroupStateTimeout.NoTimeout)


def with_parts(stream: DataFrame, vertices: DataFrame) -> DataFrame:
    """Events a part: the stream joined with the static table of parts."""
    return stream.join(vertices, stream["user_id"] == vertices["v"]).groupBy("part").agg(F.count("*").alias("n"))


DAY = 86_400


def circuits_of_days(stream: DataFrame, build: Callable[[DataFrame], DataFrame], delay: int = 0, steps: Iterable[None] = (None,)) -> tuple[DataFrame, DataFrame]:
    """What ``build`` gives of the rows of each day, once the day is closed; and the rows that
    came too late, by batch: (batch, late). The stream is run after each of the steps.

    A batch's rows are written and wait. A day is closed when a row ``delay`` seconds after
    its end has come; then it is built once, from all batches that brought rows of it, and
    rows that come later are counted as late and left out. The days still open at the end of
    the stream are built last. A batch that is run again finds the same rows before it and
    replaces what it has written. ``build`` gets the rows of all days closed by a batch, with
    their ``day``.
    """
    spark = stream.sparkSession
    out, check, rows, seen = (stage_path(spark, f"days-{x}") for x in ("out", "check", "rows", "marks"))
    schema = stream.schema.add("day", "long")

    def marks(before: int) -> int:
        """The last second that batches before that number have seen, less the delay."""
        found = spark.read.schema("batch long, top long, late long").parquet(f"{seen}/*").where(F.col("batch") < before) if before else None
        top = found.agg(F.max("top")).first()[0] if found is not None else None
        return (top if top is not None else -(1 << 40)) - delay

    def waiting(upto: int) -> DataFrame:
        return spark.read.schema(schema).option("basePath", rows).parquet(f"{rows}/batch=*").where(F.col("batch") <= upto)

    def closed(low: int, high: int) -> F.Column:
        """Days that end after ``low`` and not after ``high``."""
        end = (F.col("day") + 1) * DAY
        return (end > low) & (end <= high)

    def each(batch: DataFrame, number: int) -> None:
        before = marks(number)
        dated = batch.withColumn("day", F.floor(F.unix_seconds("ts") / DAY))
        (stage_rows := dated.where((F.col("day") + 1) * DAY > before)).write.mode("overwrite").parquet(f"{rows}/batch={number}")
        found = dated.agg(F.max(F.unix_seconds("ts")).alias("top"), F.count_if((F.col("day") + 1) * DAY <= before).alias("late"))
        found.select(F.lit(number).cast("long").alias("batch"), "top", "late").write.mode("overwrite").parquet(f"{seen}/batch-{number}")
        done = waiting(number).where(closed(before, marks(number + 1)))
        build(done.select(stage_rows.columns)).write.mode("overwrite").parquet(f"{out}/batch={number}")

    for _ in steps:
        run = stream.writeStream.option("checkpointLocation", check).trigger(availableNow=True).foreachBatch(each).start()
        run.awaitTermination()
    late = spark.read.schema("batch long, top long, late long").parquet(f"{seen}/*").select("batch", "late")
    last = late.agg(F.max("batch")).first()[0]
    rest = waiting(last).where((F.col("day") + 1) * DAY > marks(last + 1)).drop("batch")
    build(rest).write.mode("overwrite").parquet(f"{out}/batch={last + 1}")
    return spark.read.option("basePath", out).parquet(f"{out}/batch=*").drop("batch"), late
