"""Fixed-width files of little-endian 32-bit floats: one series after the other.

Reading goes through Spark's own binary reader, split by file; writing through partitions.
A Python data source (``spark.read.format("rawseries")``) offers the same to SQL users.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..plans import arrow


def read_raw(spark: SparkSession, path: str, n: int) -> DataFrame:
    """(file, record, values); trailing bytes that do not fill a record are left out."""
    files = spark.read.format("binaryFile").load(path).select("path", "content")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for path, content in zip(b.column(0).to_pylist(), b.column(1)):
                raw = content.as_buffer()
                k = raw.size // (4 * n)
                for at in range(0, k, 10_000):
                    x = np.frombuffer(raw, "<f4", min(10_000, k - at) * n, at * 4 * n).reshape(-1, n)
                    yield pa.RecordBatch.from_arrays([pa.array([path] * len(x)), pa.array(np.arange(at, at + len(x))), arrow.lists_of(x, pa.float32())], names=["file", "record", "values"])

    return files.mapInArrow(run, "file string, record long, values array<float>")


_RECORDS = "org.apache.hadoop.mapreduce.lib.input.FixedLengthInputFormat"


def read_records(spark: SparkSession, path: str, n: int) -> DataFrame:
    """(record, values) of one file of any size on any file system that Spark reads.

    The file is split at record bounds, so no task holds more than a split.  A file that ends
    inside a record fails; an empty one gives an empty table.  Records come as rows of an RDD,
    as no built-in source knows the format.
    """
    width = 4 * n
    raw = spark.sparkContext.newAPIHadoopFile(path, _RECORDS, "org.apache.hadoop.io.LongWritable", "org.apache.hadoop.io.BytesWritable", conf={"fixedlengthinputformat.record.length": str(width)})
    rows = spark.createDataFrame(raw.map(lambda r: (r[0] // width, bytes(r[1]))), "record long, content binary")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = np.frombuffer(b"".join(b.column(1).to_pylist()), "<f4").reshape(-1, n)
            yield pa.RecordBatch.from_arrays([b.column(0), arrow.lists_of(x, pa.float32())], names=["record", "values"])

    return rows.mapInArrow(run, "record long, values array<float>")


def write_raw(series: DataFrame, path: str, n: int) -> None:
    """Values of (series_id, values) by id into the one file ``path``; rows of another length fail.

    Partitions stream through the driver one after the other, as one file has one writer; it
    holds one partition at a time.
    """
    spark = series.sparkSession
    jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    target = jvm.org.apache.hadoop.fs.Path(path)
    out = target.getFileSystem(conf).create(target, False)
    try:
        for row in series.orderBy("series_id").select("series_id", "values").toLocalIterator(prefetchPartitions=True):
            if len(row["values"]) != n:
                raise ValueError(f"series {row['series_id']}: {len(row['values'])} values, not {n}")
            out.write(bytearray(np.asarray(row["values"], "<f4").tobytes()))
    finally:
        out.close()


class _Part(InputPartition):
    def __init__(self, path: str, first: int, count: int):
        self.path, self.first, self.count = path, first, count


class _Reader(DataSourceReader):
    def __init__(self, options):
        self.path, self.n, self.block = options["path"], int(options["length"]), int(options.get("block", 100_000))

    def partitions(self):
        import os

        total = os.path.getsize(self.path) // (4 * self.n)
        return [_Part(self.path, at, min(self.block, total - at)) for at in range(0, total, self.block)] or [_Part(self.path, 0, 0)]

    def read(self, part):
        x = np.fromfile(part.path, "<f4", part.count * self.n, offset=part.first * 4 * self.n).reshape(-1, self.n)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(part.first, part.first + len(x))), arrow.lists_of(x, pa.float32())], names=["series_id", "values"])


class RawSeriesSource(DataSource):
    """One file on a path that all executors open; splits of ``block`` records."""

    @classmethod
    def name(cls) -> str:
        return "rawseries"

    def schema(self) -> str:
        return "series_id long, values array<float>"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(RawSeriesSource)
