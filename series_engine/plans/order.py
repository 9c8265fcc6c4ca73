"""Places of rows in a global order, without one task for all of them."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .storage import written


def positions(rows: DataFrame, order: list[str]) -> DataFrame:
    """``rows`` with ``pos``, their place in the order: numbers inside range partitions,
    after the counts of the partitions before (one row a partition on the driver)."""
    ranked = written(rows.repartitionByRange(*order).withColumn("part", F.spark_partition_id()), "ranked")
    inside = ranked.withColumn("i", F.row_number().over(Window.partitionBy("part").orderBy(*order)) - 1)
    counts = {r["part"]: r["count"] for r in ranked.groupBy("part").count().collect()}
    start, total = [], 0
    for k in sorted(counts):
        start.append((k, total))
        total += counts[k]
    offsets = rows.sparkSession.createDataFrame(start, "part int, first long")
    return inside.join(F.broadcast(offsets), "part").withColumn("pos", F.col("i") + F.col("first")).drop("part", "i", "first")
