"""Session for local runs and tests; on a cluster the session is given."""

from __future__ import annotations

from pyspark.sql import SparkSession


def build_session(app: str = "forkline", shuffle_partitions: int | None = None, local: str | None = None, shared: str | None = None) -> SparkSession:
    builder = SparkSession.builder.appName(app).config("spark.sql.session.timeZone", "UTC").config("spark.sql.adaptive.enabled", "true").config("spark.sql.ansi.enabled", "true")
    if local:
        builder = builder.master(f"local[{local}]").config("spark.ui.enabled", "false").config("spark.driver.memory", "8g").config("spark.ui.showConsoleProgress", "false")
    if shared:
        builder = builder.config("spark.checkpoint.dir", shared)
    if shuffle_partitions:
        builder = builder.config("spark.sql.shuffle.partitions", str(shuffle_partitions))
    return builder.getOrCreate()
