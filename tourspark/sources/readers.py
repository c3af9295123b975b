"""Edge lists in files and tables, in and out. Schemas are fixed, never inferred."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tourspark.session import stage_path

PAIR = "u long, v long"
KINDS = ("csv", "tsv", "json", "parquet", "adjacency")


def write_edges(edges: DataFrame, path: str, kind: str) -> None:
    """``adjacency``: a line a vertex, its id and its larger neighbours, with repeats."""
    pairs = edges.select("u", "v")
    writer = pairs.write.mode("overwrite")
    if kind in ("csv", "tsv"):
        writer.option("sep", "," if kind == "csv" else "\t").csv(path)
    elif kind == "json":
        writer.json(path)
    elif kind == "parquet":
        writer.parquet(path)
    elif kind == "adjacency":
        # long lists are cut to lines of a bounded length
        line = F.concat_ws(" ", F.col("u").cast("string"), F.transform(F.collect_list("v"), lambda x: x.cast("string")))
        salted = pairs.withColumn("salt", F.pmod(F.xxhash64("v"), F.lit(64)))
        salted.groupBy("u", "salt").agg(line.alias("value")).select("value").write.mode("overwrite").text(path)
    else:
        raise ValueError(f"unknown kind {kind}")


def read_edges(spark: SparkSession, path: str, kind: str, bad_rows: bool = False) -> DataFrame:
    """(u, v), and with ``bad_rows`` a column ``bad`` with each line that is no pair of ids.

    Without it such lines are left out of csv, tsv and json.
    """
    if kind == "parquet":
        return spark.read.schema(PAIR).parquet(path)
    if kind == "adjacency":
        rows = spark.read.text(path).select(F.split("value", r"\s+").alias("w")).where(F.size("w") > 1)
        return rows.select(F.col("w")[0].cast("long").alias("u"), F.explode(F.slice("w", 2, F.size("w"))).alias("v")).select("u", F.col("v").cast("long").alias("v"))
    if kind not in KINDS:
        raise ValueError(f"unknown kind {kind}")
    reader = spark.read.schema(f"{PAIR}, bad string").option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", "bad")
    rows = reader.json(path) if kind == "json" else reader.option("sep", "," if kind == "csv" else "\t").csv(path)
    return rows if bad_rows else rows.where("u IS NOT NULL AND v IS NOT NULL").select("u", "v")


def save_bucketed(edges: DataFrame, name: str, by: str, buckets: int) -> str:
    """A catalog table bucketed by a vertex column: later joins on it need no exchange.

    Its files go to a new folder among the shared ones, so a table of that name left in the
    warehouse by an earlier session is not in the way.
    """
    where = stage_path(edges.sparkSession, name)
    edges.write.mode("overwrite").bucketBy(buckets, by).sortBy(by).option("path", where).format("parquet").saveAsTable(name)
    return name


def write_circuit(circuit: DataFrame, path: str, kind: str = "parquet") -> None:
    """The circuit in order: files by ranges of component and position."""
    ordered = circuit.repartitionByRange("comp", "pos").sortWithinPartitions("comp", "pos")
    getattr(ordered.write.mode("overwrite"), kind)(path)
