"""All registered queries of the library outside the llm subpackage."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from tourspark.operators import methods, relational, streams, workloads  # noqa: F401  register their queries
from tourspark.operators.registry import ORACLES, QUERIES
from tourspark.plans.circuit import circuit


def queries():
    return dict(QUERIES)


def oracle_sql():
    return dict(ORACLES)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return circuit(methods.held(spark, sf_dir, "event_trail"))
