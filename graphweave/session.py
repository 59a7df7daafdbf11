"""Session settings that the engine's plans rely on."""

from __future__ import annotations

from pyspark.sql import SparkSession

#: Settings that may change in a running session. The first lets a join on (part, vid) use data dealt by part.
RUNTIME = {
    "spark.sql.requireAllClusterKeysForCoPartition": "false",
    "spark.sql.adaptive.enabled": "true",
    "spark.sql.adaptive.skewJoin.enabled": "true",
}


def prepare(spark: SparkSession) -> SparkSession:
    """Apply the runtime settings to a session as given."""
    for key, value in RUNTIME.items():
        spark.conf.set(key, value)
    return spark


def build(master: str = "local[*]", partitions: int = 8) -> SparkSession:
    builder = SparkSession.builder.master(master).config("spark.sql.shuffle.partitions", partitions)
    return prepare(builder.config("spark.sql.session.timeZone", "UTC").getOrCreate())
