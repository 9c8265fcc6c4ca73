"""Exact de-duplication by deterministic block naming.

A text without its white space is cut into blocks of a fixed number of bytes.  All
blocks of the corpus are sorted and equal blocks get the same integer name; then pairs
of adjacent names are sorted and named in the same way, level by level, until each
document is down to one name.  Two documents have the same (level, name) exactly when
their texts are equal, whatever any hash function does.

Blocks are dealt out by content.  Before that each task merges its equal blocks, batch
by batch, so a block that a third of all documents share arrives as one row a batch.

Edge cases: null counts as empty text, and all empty texts are equal; repeated rows and
rows with equal or null keys are documents of their own; an empty table gives an empty table.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import SPACE, SPACE_BYTES, materialize, own_name

BLOCK_BYTES = 4096
#: Names of a level are (bucket << 36) + rank in the bucket; ranks stay far below 2 ** 36.
BUCKETS = 1 << 16
_BLOCKS = pa.schema([("block", pa.binary()), ("seen", pa.list_(pa.struct([("row", pa.int64()), ("at", pa.int32()), ("blocks", pa.int32()), ("key", pa.int64()), ("chars", pa.int64()), ("sha", pa.string())])))])
_BLOCKS_SQL = "block binary, seen array<struct<row: bigint, at: int, blocks: int, key: bigint, chars: bigint, sha: string>>"


def _cutter(size: int):
    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        row = TaskContext.get().partitionId() << 36
        for batch in batches:
            seen: dict[bytes, list] = {}
            for key, text in zip(batch.column(0).to_pylist(), batch.column(1)):
                text = text.as_py() or ""
                squeezed = text.encode("utf-8", "surrogatepass").translate(None, SPACE_BYTES)
                sha, n = hashlib.sha256(squeezed).hexdigest(), max(1, -(-len(squeezed) // size))
                for i in range(n):
                    seen.setdefault(squeezed[i * size : (i + 1) * size], []).append((row, i, n, key, len(text), sha) if i == 0 else (row, i, n, None, None, None))
                row += 1
            fields = [f.name for f in _BLOCKS.field("seen").type.value_type]
            if seen:
                yield pa.RecordBatch.from_arrays([pa.array(seen.keys(), pa.binary()), pa.array([[dict(zip(fields, s)) for s in x] for x in seen.values()], _BLOCKS.field("seen").type)], schema=_BLOCKS)

    return cut


def _named(rows: DataFrame, *content: str) -> DataFrame:
    """Adds ``name``: the same integer for rows of the same content, by sorting each bucket."""
    rows = rows.withColumn("bucket", F.pmod(F.xxhash64(*content), F.lit(BUCKETS)))
    rank = F.dense_rank().over(Window.partitionBy("bucket").orderBy(*content))
    return rows.withColumn("name", F.shiftleft(F.col("bucket"), 36) + rank)


def block_identities(docs: DataFrame, key: str = "doc_id", block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """One row per document: row, key, chars (of the original text), sha, level, name.

    ``row`` numbers the rows of the scan and is stable when a task runs again.
    """
    blocks = docs.select(F.col(key).cast("long").alias("key"), F.col("text").cast("string").alias("text")).mapInArrow(_cutter(block_bytes), _BLOCKS_SQL)
    named = _named(blocks, "block").select("name", F.explode("seen").alias("s")).select("s.*", "name")
    now = materialize(named, "names")
    facts = now.where("at = 0").select("row", "key", "chars", "sha", "blocks", "name")
    done: list[DataFrame] = []
    now = now.where("blocks > 1").select("row", "at", "blocks", "name")
    most = now.agg(F.max("blocks")).first()[0] or 1
    level = 0
    while most > 1:
        level, most = level + 1, (most + 1) // 2
        pairs = now.groupBy("row", F.expr("at div 2").cast("int").alias("at"), F.expr("(blocks + 1) div 2").cast("int").alias("blocks")).agg(
            F.max(F.expr("if(at % 2 = 0, name, null)")).alias("a"), F.coalesce(F.max(F.expr("if(at % 2 = 1, name, null)")), F.lit(-1)).alias("b"))
        now = materialize(_named(pairs, "a", "b").select("row", "at", "blocks", "name"), "names")
        done.append(now.where("blocks = 1").select("row", F.lit(level).alias("level"), "name"))
        now = now.where("blocks > 1")
    single = facts.where("blocks = 1").select("row", "key", "chars", "sha", F.lit(0).alias("level"), "name")
    if not done:
        return single
    names = done[0]
    for d in done[1:]:
        names = names.union(d)
    return single.union(facts.where("blocks > 1").select("row", "key", "chars", "sha").join(names, "row").select("row", "key", "chars", "sha", "level", "name"))


def duplicate_groups(docs: DataFrame, key: str = "doc_id", block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """row, key, keep (key of the row that stays), group_size, kept, sha for every document.

    Of equal texts the one with the most code points stays, then the smallest key (null
    last), then the first row.
    """
    rows = materialize(block_identities(docs, key, block_bytes), "identities")
    best = F.min(F.struct((-F.col("chars")).alias("c"), F.col("key").isNull().alias("no"), F.col("key").alias("key"), F.col("row").alias("row")))
    groups = rows.groupBy("level", "name").agg(best.alias("best"), F.count(F.lit(1)).alias("group_size"))
    out = rows.join(groups, ["level", "name"])
    return out.select("row", "key", F.col("best.key").alias("keep"), "group_size", (F.col("row") == F.col("best.row")).alias("kept"), "sha")


def drop_duplicates(docs: DataFrame, key: str = "doc_id") -> DataFrame:
    """The rows of ``docs`` that stay, with their columns as they were.

    Texts are shuffled once, by (key, digest); of repeated rows with one key the longest
    original text stays.
    """
    tag = lambda k, sha: F.concat(F.coalesce(k.cast("string"), F.lit("null")), F.lit(":"), sha)
    name, chars, turn, row = (own_name(docs.columns, c) for c in ("_tag", "_chars", "_turn", "_row"))
    stay = duplicate_groups(docs, key).where("kept").select(tag(F.col("key"), F.col("sha")).alias(name)).distinct()
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    own = F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias(row)
    tagged = docs.select(own, tag(F.col(f"`{key}`").cast("long"), F.sha2(F.regexp_replace(text, SPACE, ""), 256)).alias(name), F.length(text).alias(chars))
    first = F.row_number().over(Window.partitionBy(name).orderBy(F.col(chars).desc()))
    out = tagged.join(stay, name, "left_semi").withColumn(turn, first).where(F.col(turn) == 1)
    return out.select(*[F.col(row).getField(c).alias(c) for c in docs.columns])
