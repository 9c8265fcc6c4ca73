"""Helpers that the operators of this folder share."""

from __future__ import annotations

import uuid
import weakref

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.storage import own_shuffles_go, remove, shared_dir

#: White space of all operators: U+0020 and U+0009 to U+000D.
SPACE = r"[\x20\x09-\x0D]+"
#: ``bytes.split()`` and ``bytes.translate`` with these bytes follow the same rule.
SPACE_BYTES = b" \t\n\x0b\x0c\r"


def materialize(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` once into the shared folder and read it back.

    Cuts lineage and survives lost executors: the files are not kept on any executor.
    ``Dataset.checkpoint`` would compute a stage without a shuffle twice.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    with own_shuffles_go(spark):
        df.write.option("compression", "zstd").parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    _paths[id(out)] = (weakref.ref(out), path)
    return out


def own_name(taken, name: str) -> str:
    """``name``, or with underscores in front while a column of the user has it."""
    low = {c.lower() for c in taken}
    while name.lower() in low:
        name = "_" + name
    return name


_paths: dict = {}


def discard(df: DataFrame) -> None:
    """Removes the files of a materialised table that nothing will read again."""
    known = _paths.pop(id(df), None)
    if known is not None and known[0]() is df:
        remove(df.sparkSession, known[1])


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def text_of(docs: DataFrame, column: str = "text") -> Column:
    """The text column with null as empty."""
    return F.coalesce(docs[column].cast("string"), F.lit(""))


def unsigned_hex(value: Column) -> Column:
    """16 lowercase hex digits of a 64-bit integer."""
    return F.lower(F.lpad(F.hex(value), 16, "0"))
