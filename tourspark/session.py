"""Session helpers: tables, and the shared folder in which lineage is cut.

Nothing here changes a setting fixed at the start of a session; every method works with
the session that it is given.
"""

from __future__ import annotations

import tempfile
import uuid
import zipfile
from collections.abc import Callable, Iterator
from contextlib import contextmanager
from contextvars import ContextVar
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows up to which a table of parts, which a parameter bounds, is broadcast.
MOST_BROADCAST = 1_000_000


def local_session(cpus: str = "*", partitions: int = 8, memory: str = "8g") -> SparkSession:
    """A session on this machine, for tests and the bench only."""
    return (
        SparkSession.builder.master(f"local[{cpus}]")
        .appName("tourspark")
        .config("spark.driver.memory", memory)
        .config("spark.sql.shuffle.partitions", str(partitions))
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .getOrCreate()
    )


_SHIPPED: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Send this package to the executors, once for each application.

    Workers unpickle kernels by the names of their modules; they need not have the package
    installed, nor see the driver's folders.
    """
    context = spark.sparkContext
    if context.applicationId in _SHIPPED:
        return
    root = Path(__file__).resolve().parent
    archive = Path(tempfile.mkdtemp(prefix="tourspark-")) / "tourspark.zip"
    with zipfile.ZipFile(archive, "w", zipfile.ZIP_DEFLATED) as out:
        for p in sorted(root.rglob("*.py")):
            out.write(p, p.relative_to(root.parent).as_posix())
    context.addPyFile(str(archive))
    _SHIPPED.add(context.applicationId)


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share.

    Read from ``spark.checkpoint.dir``. Only a session on one machine (``local``) that names
    none gets a temporary folder; on a cluster a missing folder is an error.
    """
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    context = spark.sparkContext
    option = context._jsc.sc().getCheckpointDir()
    if option.isDefined():
        return option.get().rstrip("/")
    if not context.master.startswith("local[") and context.master != "local":
        raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
    context.setCheckpointDir(tempfile.mkdtemp(prefix="tourspark-"))
    return context._jsc.sc().getCheckpointDir().get().rstrip("/")


def stages_dir(spark: SparkSession) -> str:
    """Where this application keeps its tables in the shared folder."""
    return f"{shared_dir(spark)}/tourspark-{spark.sparkContext.applicationId}"


def stage_path(spark: SparkSession, label: str) -> str:
    ship(spark)
    return f"{stages_dir(spark)}{_SCRATCH.get()}/{label}-{uuid.uuid4().hex}"


#: Folder in that of the stages where tables go that are deleted together.
_SCRATCH: ContextVar[str] = ContextVar("scratch", default="")


@contextmanager
def scratch(spark: SparkSession) -> Iterator[None]:
    """Tables staged within are deleted at the end; what reads them must be done by then."""
    here = f"{_SCRATCH.get()}/scratch-{uuid.uuid4().hex}"
    outer = _SCRATCH.set(here)
    try:
        yield
    finally:
        _SCRATCH.reset(outer)
        drop_path(spark, stages_dir(spark) + here)


def stage_alone(spark: SparkSession, make: Callable[[], DataFrame], label: str) -> DataFrame:
    """The rows of ``make()``, staged; the tables that it has staged on the way, which nothing
    else may read, are deleted."""
    path = stage_path(spark, label)
    with scratch(spark):
        df = make()
        df.write.parquet(path)
        return _read_again(df, path)


def stage(df: DataFrame, label: str, partition_by: tuple[str, ...] = ()) -> DataFrame:
    """Write ``df`` to the shared folder and read it again.

    The table outlives any executor, cuts the lineage, and fixes the rows that a later
    numbering or join reads more than once.
    """
    spark, path = df.sparkSession, stage_path(df.sparkSession, label)
    df.write.partitionBy(*partition_by).parquet(path) if partition_by else df.write.parquet(path)
    return _read_again(df, path)


def _read_again(df: DataFrame, path: str) -> DataFrame:
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._staged_at = path
    return out


def drop(*tables: DataFrame) -> None:
    """Delete staged tables whose rows are no longer needed."""
    for table in tables:
        drop_path(table.sparkSession, table._staged_at)


def lookup(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    """A small table for joins: broadcast up to MOST_BROADCAST rows, joined as it is beyond."""
    made = spark.createDataFrame(rows, schema)
    return F.broadcast(made) if len(rows) <= MOST_BROADCAST else made


def drop_path(spark: SparkSession, path: str) -> None:
    """Delete a staged table whose rows are no longer needed."""
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


def clear_stages(spark: SparkSession) -> None:
    """Delete all tables that this application has staged. Results that read them, which are
    most DataFrames that the methods return, must have been written before."""
    drop_path(spark, stages_dir(spark))
