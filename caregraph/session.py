"""Session defaults and the SQL surface."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession


def build(master: str = "local[*]", shuffle_partitions: int = 8, **more: str) -> SparkSession:
    """A session with the settings the engine assumes: UTC, adaptive plans."""
    b = SparkSession.builder.master(master).appName("caregraph")
    conf = {
        "spark.sql.session.timeZone": "UTC",
        "spark.sql.adaptive.enabled": "true",
        "spark.sql.adaptive.skewJoin.enabled": "true",
        "spark.sql.shuffle.partitions": str(shuffle_partitions),
        "spark.ui.enabled": "false",
    } | more
    for k, v in conf.items():
        b = b.config(k, v)
    return b.getOrCreate()


def register_views(views: dict[str, DataFrame], shared: bool = False) -> None:
    """Makes the graph's tables visible to SQL users under their names."""
    for name, df in views.items():
        if shared:
            df.createOrReplaceGlobalTempView(name)
        else:
            df.createOrReplaceTempView(name)
