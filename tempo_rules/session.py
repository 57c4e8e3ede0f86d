"""Settings to start a session with; queries also work with a session as given."""

from __future__ import annotations

from pyspark.sql import SparkSession

SETTINGS = {
    "spark.sql.session.timeZone": "UTC",
    "spark.sql.adaptive.enabled": "true",
    "spark.sql.adaptive.skewJoin.enabled": "true",
    "spark.sql.adaptive.coalescePartitions.enabled": "true",
    "spark.sql.adaptive.localShuffleReader.enabled": "true",
}


def builder(app: str = "tempo_rules") -> SparkSession.Builder:
    return SparkSession.builder.appName(app).config(map=SETTINGS)
