"""Connected components of links between ids, written to the shared folder after every round.

Each round takes for every id the smallest label among its neighbours and itself, then
follows labels of labels, so that long chains halve. Minima are combined before the shuffle,
hence a hub costs one row a task. Nothing but the number of changes reaches the driver.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from forkline.llm.common import drop, shared_folder, through_disk


def components(links: DataFrame) -> DataFrame:
    """``(id, component)`` for each id in ``links(a, b)``; ``component`` is the smallest id that it reaches.

    Null ends and links of an id to itself are left out; no links give no rows.
    """
    spark, folder = links.sparkSession, shared_folder(links.sparkSession, "labels")
    both = links.select("a", "b").union(links.select(F.col("b").alias("a"), F.col("a").alias("b"))).where("a <> b")
    edges = through_disk(both.distinct(), "links")

    def put(k: int, df: DataFrame) -> DataFrame:
        df.write.parquet(f"{folder}/{k}")
        return spark.read.schema(df.schema).parquet(f"{folder}/{k}")

    labels, k = put(0, edges.groupBy(F.col("a").alias("id")).agg(F.least("a", F.min("b")).alias("component"))), 0
    while True:
        heard = edges.join(labels, edges.b == labels.id).groupBy("a").agg(F.min("component").alias("heard"))
        lower = labels.join(heard, labels.id == heard.a).select("id", "component", F.least("component", "heard").alias("lower"))
        target = labels.select(F.col("id").alias("lower"), F.col("component").alias("beyond"))
        step = lower.join(target, "lower", "left").select("id", F.least("lower", F.coalesce("beyond", "lower")).alias("component"), (F.col("component") > F.least("lower", F.coalesce("beyond", "lower"))).alias("changed"))
        k += 1
        written = put(k, step)
        labels = written.select("id", "component")
        drop(spark, f"{folder}/{k - 1}")
        if not written.where("changed").limit(1).count():
            return labels
