"""SimHash near-duplicate groups by multi-index hashing.

A text is lower-cased (A-Z), cut into words and shingles; bit b of its fingerprint is 1
if more than half of the shingles' XXH64 values (repeats included) have it.  Fingerprints
at most two bits apart are linked, and groups are the connected components.

Fingerprints of all documents are first reduced to distinct ones, so copies cost nothing
more.  The 64 bits are two segments of 32.  Two fingerprints at distance two or less
agree in the upper segment up to one bit or in the lower one exactly; so each fingerprint
is stored in a table by both segments and probes the upper one with the 33 values of its
Hamming ball, the lower one with its own value.  Matches are verified by their complete
distance.

A table entry that holds more than ``BUCKET`` fingerprints would match all pairs of them.
Fingerprints that are in or probe such an entry are linked in another exact way: both
list all 65 values within one bit of themselves, and two are within two bits if and only
if they list a value in common.  Each is linked to the least of those who list a value,
which is linear in their number.

Edge cases: a text without words (null and empty ones) has fingerprint zero and is linked
like any other; rows with a null key get a group but never name it; repeated rows are
alike; an empty table gives an empty table.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from xxhash import xxh64_intdigest

from .common import materialize, own_name
from .components import components

BUCKET = 64
SEED = 42
_BIT_MASKS = [1 << b if b < 63 else -(1 << 63) for b in range(64)]
_PART = 1 << 16


def shingles(text: str | None, size: int) -> list[bytes]:
    """Space-joined shingles of the words, or the whole sequence if there are fewer words."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if len(words) <= size:
        return [b" ".join(words)] if words else []
    return [b" ".join(x) for x in zip(*(words[i:] for i in range(size)))]


def fingerprint(text: str | None, size: int = 3) -> int:
    """The 64 bits as a signed integer.  Memory beyond the text is bounded: bits are counted part by part."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return 0
    n = max(1, len(words) - size + 1)
    ones = np.zeros(64, np.int64)
    for at in range(0, n, _PART):
        part = words[at : at + _PART + size - 1]
        hashes = np.fromiter((xxh64_intdigest(b" ".join(x), SEED) for x in zip(*(part[i:] for i in range(size)))) if n > 1 or len(words) == size else [xxh64_intdigest(b" ".join(words), SEED)], np.uint64)
        ones += np.unpackbits(hashes.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(2 * ones > n, bitorder="little").view(np.int64)[0])


def fingerprints(docs: DataFrame, key: str = "doc_id", size: int = 3) -> DataFrame:
    """(key, fp) of every row."""
    return _fingerprints(docs, key, size).select("key", "fp")


def _text_hash(text: Column) -> Column:
    return F.xxhash64(F.length(text), text)


def _fingerprints(docs: DataFrame, key: str, size: int) -> DataFrame:
    """(key, text_hash, fp) of every row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fps = np.fromiter((fingerprint(t.as_py(), size) for t in batch.column(2)), np.int64, batch.num_rows)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(fps)], names=["key", "text_hash", "fp"])

    text = F.col("text").cast("string")
    return docs.select(F.col(f"`{key}`").cast("long").alias("key"), _text_hash(text).alias("text_hash"), text.alias("text")).mapInArrow(run, "key bigint, text_hash bigint, fp bigint")


def _bit_ball(value, bits: range):
    return F.array(value, *[value.bitwiseXOR(F.lit(_BIT_MASKS[b])) for b in bits])


def near_links(nodes: DataFrame, bucket: int = BUCKET) -> DataFrame:
    """nodes: distinct ``fp`` with a representative ``rep``.  Returns links (a, b) between
    representatives whose transitive closure is that of all pairs at distance 1 or 2."""
    low = F.col("fp").bitwiseAND(F.lit(0xFFFFFFFF))
    high = F.shiftrightunsigned("fp", 32)
    entry = lambda s, v: F.struct(F.lit(s).cast("byte").alias("seg"), v.alias("value"))
    stored = nodes.select("fp", "rep", F.explode(F.array(entry(0, high), entry(1, low))).alias("e")).select("fp", "rep", "e.*")
    asked = nodes.select("fp", "rep", F.explode(F.concat(F.transform(_bit_ball(high, range(32)), lambda v: entry(0, v)), F.array(entry(1, low)))).alias("e")).select(F.col("fp").alias("fp2"), F.col("rep").alias("rep2"), "e.*")
    crowded = materialize(stored.groupBy("seg", "value").count().where(F.col("count") > bucket).select("seg", "value"), "crowded")
    some = not crowded.isEmpty()
    if some:
        stored = stored.join(crowded, ["seg", "value"], "left_anti")
    near = (F.col("fp") < F.col("fp2")) & (F.bit_count(F.col("fp").bitwiseXOR(F.col("fp2"))) <= 2)
    # Spark's estimate leaves out that rows are multiplied; by it either side could go through the driver
    links = stored.join(asked.hint("merge"), ["seg", "value"]).where(near).select(F.col("rep").alias("a"), F.col("rep2").alias("b"))
    if some:
        among = asked.join(crowded, ["seg", "value"], "left_semi").select(F.col("fp2").alias("fp"), F.col("rep2").alias("rep")).distinct()
        around = materialize(among.select("rep", F.explode(_bit_ball(F.col("fp"), range(64))).alias("middle")), "middles")
        least = around.groupBy("middle").agg(F.min("rep").alias("a"), F.max("rep").alias("z")).where("a < z").select("middle", "a")
        links = links.union(around.join(least.hint("merge"), "middle").where("a <> rep").select("a", F.col("rep").alias("b")))
    return links


def near_duplicates(docs: DataFrame, key: str = "doc_id", size: int = 3, bucket: int = BUCKET) -> DataFrame:
    """key, fp, component (least key reachable) for every row."""
    rows = materialize(fingerprints(docs, key, size), "fingerprints")
    nodes = materialize(rows.where("key is not null").groupBy("fp").agg(F.min("key").alias("rep")), "nodes")
    groups = components(near_links(nodes, bucket), "a", "b")
    named = nodes.join(groups.withColumnRenamed("node", "rep"), "rep", "left").select("fp", F.coalesce("component", "rep").alias("component"))
    return rows.join(named, "fp", "left").select("key", "fp", "component")


def drop_near_duplicates(docs: DataFrame, key: str = "doc_id", size: int = 3) -> DataFrame:
    """One row of each group of linked fingerprints, with its columns as they were.

    The row whose key names the group (the least one) stays; in a group without any key one
    row stays.  Rows are told apart by key and text: what has the same key but another text
    is judged by its own group, a null key is no key, and repeated rows count once.
    """
    rows = materialize(_fingerprints(docs, key, size), "fingerprints")
    nodes = materialize(rows.groupBy("fp").agg(F.min("key").alias("low")).select("fp", "low", F.monotonically_increasing_id().alias("rep")), "nodes")
    groups = components(near_links(nodes, BUCKET), "a", "b")
    named = nodes.join(groups.withColumnRenamed("node", "rep"), "rep", "left").select("fp", "low", F.coalesce("component", "rep").alias("component"))
    # of each group the fingerprint with the least key, then the least fingerprint; of its rows the least text hash
    first = named.groupBy("component").agg(F.min(F.struct(F.col("low").isNull().alias("no"), "low", "fp")).alias("stay"))
    mine = rows.join(first.select("stay.low", "stay.fp"), "fp").where(F.col("key").eqNullSafe(F.col("low")))
    tag = lambda k, h: F.concat(F.coalesce(k.cast("string"), F.lit("null")), F.lit(":"), h.cast("string"))
    names = [own_name(docs.columns, c) for c in ("_tag", "_turn", "_row")]
    stay = materialize(mine.groupBy("fp").agg(F.first("key").alias("key"), F.min("text_hash").alias("h")).select(tag(F.col("key"), F.col("h")).alias(names[0])).distinct(), "stay")
    own = F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias(names[2])
    tagged = docs.select(own, tag(F.col(f"`{key}`").cast("long"), _text_hash(F.col("text").cast("string"))).alias(names[0]))
    turn = F.row_number().over(Window.partitionBy(names[0]).orderBy(names[0]))
    # sorted, not broadcast: the window needs the same shuffle
    kept = tagged.join(stay.hint("merge"), names[0], "left_semi").withColumn(names[1], turn).where(F.col(names[1]) == 1)
    return kept.select(*[F.col(names[2]).getField(c).alias(c) for c in docs.columns])
