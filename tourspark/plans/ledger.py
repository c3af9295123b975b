"""The ledger: fragment headers and bodies on disk, one folder a level."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from tourspark.plans.phase1 import OUT
from tourspark.session import drop_path, stage_path


@dataclass(frozen=True)
class Ledger:
    """Each level's write is a barrier: a level is there as a whole or not at all."""

    spark: SparkSession
    path: str

    @staticmethod
    def create(spark: SparkSession, path: str | None = None) -> Ledger:
        return Ledger(spark, path or stage_path(spark, "ledger"))

    def _at(self, level: int) -> str:
        return f"{self.path}/level={level}"

    def has(self, level: int) -> bool:
        jvm = self.spark.sparkContext._jvm
        where = jvm.org.apache.hadoop.fs.Path(f"{self._at(level)}/_SUCCESS")
        return where.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).exists(where)

    def levels(self, most: int = 64) -> list[int]:
        return [level for level in range(most) if self.has(level)]

    def write(self, level: int, rows: DataFrame) -> None:
        """The rows are dealt out first: a part's one task would sort and write all of its."""
        rows.repartition("fid", "seq").write.mode("overwrite").partitionBy("tag").parquet(self._at(level))

    def drop(self, level: int) -> None:
        drop_path(self.spark, self._at(level))

    def _read(self, level: int, tag: str) -> DataFrame:
        return self.spark.read.schema(OUT).parquet(self._at(level)).where(f"tag = '{tag}'")

    def frags(self, level: int) -> DataFrame:
        return self._read(level, "frag").selectExpr("fid", f"{level} AS level", "part", "ftype", "src", "dst", "n_edges", "rs", "rd")

    def items(self, level: int) -> DataFrame:
        return self._read(level, "item").selectExpr("fid", f"{level} AS level", "seq", "off", "item_kind", "item_id", "fwd", "a", "b", "len")

    def figures(self, level: int) -> DataFrame:
        """One row a part: its items, the seconds of each step, and its process's peak memory."""
        return self._read(level, "part").selectExpr(f"{level} AS level", "part", "len AS items", "receive", "build", "walk", "emit", "build + walk + emit AS seconds", "peak")

    def all_figures(self) -> DataFrame:
        return self._union(self.figures)

    def all_frags(self) -> DataFrame:
        return self._union(self.frags)

    def all_items(self) -> DataFrame:
        return self._union(self.items)

    def _union(self, read) -> DataFrame:
        out = None
        for level in self.levels():
            out = read(level) if out is None else out.unionByName(read(level))
        if out is None:
            raise ValueError("the ledger has no level")
        return out
