"""All queries of the engine and the SQL they are checked against."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from .queries import completion, detection, graphs, mining, streams

_PARTS = [graphs, mining, detection, completion, streams]

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {k: v for p in _PARTS for k, v in p.QUERIES.items()}
ORACLES: dict[str, str] = {k: v for p in _PARTS for k, v in p.ORACLES.items()}


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mining.flagship(spark, sf_dir)
