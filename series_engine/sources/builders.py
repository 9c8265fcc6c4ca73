"""Series assembled from tables.  All return (series_id, values array<double>) and, where
it is of use, what the series come from.

``series_id`` of built series is owner key * 1000003 + window number.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..plans import arrow

OWNER = 1000003
ALPHABET = "abcdefghijklmnopqrstuvwxyz"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def summed(steps: DataFrame, n: int, centre: bool = False) -> DataFrame:
    """(series_id, steps) -> (series_id, values): running sums, of steps less their mean if ``centre``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = arrow.matrix_of(b.column(1), n)
            yield pa.RecordBatch.from_arrays([b.column(0), arrow.lists_of(np.cumsum(x - x.mean(1, keepdims=True) if centre else x, axis=1))], names=["series_id", "values"])

    return steps.select("series_id", "steps").mapInArrow(run, "series_id long, values array<double>")


def assembled(rows: DataFrame, key: Column, pos: Column, value: Column, n: int) -> DataFrame:
    """Long form to (series_id, steps); series without all ``n`` points are left out."""
    grouped = rows.select(key.cast("long").alias("series_id"), F.struct(pos.cast("int").alias("p"), value.cast("double").alias("v")).alias("x"))
    lists = grouped.groupBy("series_id").agg(F.sort_array(F.collect_list("x")).alias("x")).where(F.size("x") == n)
    return lists.select("series_id", F.transform("x", lambda s: s["v"]).alias("steps"))


def vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Embeddings as they are."""
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("series_id"), F.transform("embedding", lambda v: v.cast("double")).alias("values"), "label")


#: Line items have no unique key; these columns together order them wholly.
LINE_ORDER = ("l_shipdate", "l_orderkey", "l_linenumber", "l_partkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax")


def walks(spark: SparkSession, sf_dir: str, n: int = 64) -> DataFrame:
    """Random walks: sums of quantities less 25.5 over blocks of a supplier's line items."""
    rows = table(spark, sf_dir, "lineitem").select("l_suppkey", *LINE_ORDER)
    rows = rows.withColumn("i", F.row_number().over(Window.partitionBy("l_suppkey").orderBy(*LINE_ORDER)) - 1)
    key = F.col("l_suppkey") * OWNER + F.floor(F.col("i") / n)
    return summed(assembled(rows, key, F.col("i") % n, F.col("l_quantity") - 25.5, n), n)


def _text_windows(docs: DataFrame, n: int, centre: bool, shift: float) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            keys, rows = [], []
            for key, text in zip(b.column(0).to_pylist(), b.column(1)):
                points = np.frombuffer((text.as_py() or "").encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.int64)
                k = len(points) // n
                if k and key is not None:
                    letters = points[: k * n].reshape(k, n) - 96
                    x = np.where((letters >= 1) & (letters <= 26), letters, 0).astype(np.float64)
                    rows.append(np.cumsum(x - (x.mean(1, keepdims=True) if centre else shift), axis=1))
                    keys.append(key * OWNER + np.arange(k))
                if sum(map(len, rows)) > 20_000:
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(keys)), arrow.lists_of(np.concatenate(rows))], names=["series_id", "values"])
                    keys, rows = [], []
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(keys)), arrow.lists_of(np.concatenate(rows))], names=["series_id", "values"])

    return docs.mapInArrow(run, "series_id long, values array<double>")


def letters(spark: SparkSession, sf_dir: str, n: int = 128) -> DataFrame:
    """Symbol sequences made numeric: sums of letter ranks less the window's mean, over windows of text."""
    return _text_windows(table(spark, sf_dir, "documents").select("doc_id", "text"), n, True, 0.0)


def ramps(spark: SparkSession, sf_dir: str, n: int = 256) -> DataFrame:
    """Letter ranks less 10, not centred: a collection with very uneven cells."""
    return _text_windows(table(spark, sf_dir, "documents").select("doc_id", "text"), n, False, 10.0)


def pulses(spark: SparkSession, sf_dir: str, n: int = 32, stride: int = 4) -> DataFrame:
    """Sliding windows of a user's recording.  Each event goes to the windows that hold it, so
    no user's whole recording meets in one row."""
    return pulses_of(table(spark, sf_dir, "events"), n, stride)


def pulses_of(events: DataFrame, n: int = 32, stride: int = 4) -> DataFrame:
    rows = events.select("user_id", "ts", "event_id", "value").withColumn("i", F.row_number().over(Window.partitionBy("user_id").orderBy("ts", "event_id")) - 1)
    first = F.greatest(F.lit(0), F.ceil((F.col("i") - (n - 1)) / stride)).cast("int")
    rows = rows.withColumn("window", F.explode(F.sequence(first, F.floor(F.col("i") / stride).cast("int"))))
    key = F.col("user_id") * OWNER + F.col("window")
    return summed(assembled(rows, key, F.col("i") - F.col("window") * stride, F.col("value"), n), n, centre=True)


def monthly(spark: SparkSession, sf_dir: str, n: int = 64) -> DataFrame:
    """Revenue by nation and month from 1995-01, months without orders as zero; with nation and region."""
    orders = table(spark, sf_dir, "orders").select("o_custkey", "o_orderdate", "o_totalprice")
    customers = table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey")
    nations = table(spark, sf_dir, "nation").join(F.broadcast(table(spark, sf_dir, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    month = (F.year("o_orderdate") - 1995) * 12 + F.month("o_orderdate") - 1
    spent = orders.join(customers, F.col("o_custkey") == F.col("c_custkey")).groupBy(F.col("c_nationkey").alias("nation"), month.alias("m")).agg(F.sum("o_totalprice").alias("v"))
    grid = nations.select(F.col("n_nationkey").alias("nation"), "n_name", "r_name").withColumn("m", F.explode(F.sequence(F.lit(0), F.lit(n - 1))))
    rows = grid.join(spent, ["nation", "m"], "left").na.fill(0.0, ["v"])
    series = assembled(rows, F.col("nation"), F.col("m"), F.col("v"), n).withColumnRenamed("steps", "values")
    return series.join(F.broadcast(nations.select(F.col("n_nationkey").cast("long").alias("series_id"), "n_name", "r_name")), "series_id")


def synthetic_walks(spark: SparkSession, n_series: int, n: int, seed: int = 1) -> DataFrame:
    """Random walks of standard normal steps, each from its own hashed seed: the same at any partitioning."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids = b.column(0).to_numpy()
            x = np.stack([np.cumsum(np.random.Generator(np.random.SFC64([seed, int(i)])).standard_normal(n)) for i in ids]) if len(ids) else np.zeros((0, n))
            yield pa.RecordBatch.from_arrays([b.column(0), arrow.lists_of(x)], names=["series_id", "values"])

    return spark.range(n_series).select(F.col("id").alias("series_id")).mapInArrow(run, "series_id long, values array<double>")


BUILDERS = {"vectors": vectors, "walks": walks, "letters": letters, "ramps": ramps, "pulses": pulses, "monthly": monthly}


def held_out(series: DataFrame, step: int = 25, rest: int = 7, limit: int | None = 200) -> tuple[DataFrame, DataFrame]:
    """(collection, queries): rows whose id leaves ``rest`` are queries, at most ``limit`` by least id."""
    is_query = F.pmod("series_id", F.lit(step)) == rest
    queries = series.where(is_query).select(F.col("series_id").alias("query_id"), "values")
    if limit is not None:
        queries = queries.orderBy("query_id").limit(limit)
    return series.where(~is_query), queries


def windows_of(series: DataFrame, length: int, stride: int) -> DataFrame:
    """Sub-windows of long series: (series_id, offset, values)."""
    at = F.sequence(F.lit(0), F.size("values") - length, F.lit(stride))
    rows = series.where(F.size("values") >= length).withColumn("offset", F.explode(at))
    return rows.select("series_id", "offset", F.slice("values", F.col("offset") + 1, length).alias("values"))
