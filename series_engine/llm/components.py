"""Connected components of a links table, wholly in DataFrames.

Alternates two star operations (each node is linked to the least node of its
neighbourhood: first by its larger neighbours, then by its smaller ones) until the
links no longer change, which takes a logarithmic number of rounds.  Every round is
written to the shared folder; nothing but a count and a checksum reaches the driver.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, materialize


def _star(links: DataFrame, large: bool) -> DataFrame:
    """links: (u, v) with u > v.  Returns links of the same form."""
    if large:
        around = links.union(links.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = around.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u"), F.least("u", "m").alias("m"))
        moved = around.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
    else:
        least = links.groupBy("u").agg(F.min("v").alias("m"))
        moved = links.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).union(least.select("u", F.col("m").alias("v")))
    return moved.where("u > v").distinct()


def components(links: DataFrame, left: str, right: str, max_rounds: int = 60) -> DataFrame:
    """(node, component) for every node that has a link; component is its least node.

    Nulls and loops in ``links`` are ignored; repeated links count once.  An empty table
    gives an empty table.
    """
    a, b = F.col(left).cast("long"), F.col(right).cast("long")
    now = materialize(links.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).where("u > v").distinct(), "links")
    mark = lambda d: d.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
    before = mark(now)
    for _ in range(max_rounds if before[0] else 0):
        last, now = now, materialize(_star(_star(now, True), False), "links")
        discard(last)
        after = mark(now)
        if after == before:
            break
        before = after
    else:
        if before[0]:
            raise RuntimeError(f"components: not settled after {max_rounds} rounds")
    return now.select(F.col("u").alias("node"), F.col("v").alias("component")).union(now.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())
