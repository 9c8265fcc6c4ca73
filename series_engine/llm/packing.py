"""Mixture-controlled packing of token ids into sequences.

Documents are encoded once and dealt out by a hash of their key, so every partition holds
all sources.  In a partition each source has a queue, and windows of ``length`` tokens are
filled by deficit round-robin: before a window each source earns its target share of the
window's tokens; sources are served in the order of what they are owed, and what is still
owed or overdrawn is carried to the next window.  Deficits are carried over partitions
too: all partitions before one have given T tokens in all and T_s of source s, so its
deficits start at share_s * T - T_s, a prefix sum over the table of (partition, source)
totals.  Repeated rows are dealt by their turn among the equal rows of an Arrow batch too,
so a row that makes up a large part of the table is spread over all partitions.  A
partition learns the shares and deficits of the sources that it holds, from that
table, so their number has no limit and no list of them passes the driver.

A window is filled whatever the mixture: when a source's queue is empty the others give
more and stay overdrawn.  All windows but a partition's last are full, and the rest of a
partition is cut into sequences whose lengths are powers of two, so nothing is padded.

Queues hold at most ``lookahead`` tokens beyond the document in hand (a bound of memory);
when they are full the next window is filled with what is there, and what its sources are
owed is carried on.

Edge cases: a null or empty text is its end token alone; a null source counts as the empty
one; repeated rows are packed each (which of them goes where depends on the batches); rows with a null key are packed and keep a null key;
an empty table gives an empty table.
"""

from __future__ import annotations

import zlib
from collections import deque
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import materialize
from .tokens import default_file, encoder

LENGTH = 2048
END = 1
LOOKAHEAD = 1 << 20


def turns(values: np.ndarray) -> np.ndarray:
    """For each value how many equal ones stand before it."""
    order = np.argsort(values, kind="stable")
    fresh = np.flatnonzero(np.diff(values[order], prepend=values[order][:1] ^ 1)) if len(values) else order
    out = np.empty(len(values), np.int64)
    out[order] = np.arange(len(values)) - np.repeat(fresh, np.diff(fresh, append=len(values)))
    return out


def encoded(docs: DataFrame, buckets: int, key: str = "doc_id", source: str = "source", file: str | None = None) -> DataFrame:
    """(bucket, place, key, source, ids, tokens): ids as little-endian 16-bit numbers, 32-bit if any needs it."""
    file = file or default_file()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(file)
        for batch in batches:
            ids, sizes = [], []
            for text in batch.column(3):
                found = np.append(enc.ids(text.as_py() or ""), np.uint32(END))
                sizes.append(len(found))
                ids.append(found.astype("<u2" if len(enc.lengths) <= 65536 else "<u4").tobytes())
            turn = pa.array(turns(batch.column(0).to_numpy()))
            yield pa.RecordBatch.from_arrays([*batch.columns[:3], pa.array(ids, pa.binary()), pa.array(sizes, pa.int64()), turn], names=["place", "key", "source", "ids", "tokens", "turn"])

    place = F.xxhash64(F.col(key), F.col("text"))
    rows = docs.select(place.alias("place"), F.col(key).cast("long").alias("key"), F.coalesce(F.col(source).cast("string"), F.lit("")).alias("source"), F.col("text").cast("string").alias("text"))
    dealt = F.when(F.col("turn") == 0, F.xxhash64("place")).otherwise(F.xxhash64("place", "turn"))
    out = rows.mapInArrow(run, "place bigint, key bigint, source string, ids binary, tokens bigint, turn bigint")
    return out.withColumn("bucket", F.pmod(dealt, F.lit(buckets)).cast("int")).drop("turn")


class Packer:
    """Deficit round-robin over source queues of one partition.  starts: (source, share of a
    window, deficit) of every source that the partition holds."""

    def __init__(self, starts: list[tuple], length: int, first: int, lookahead: int = LOOKAHEAD):
        self.length, self.sequence, self.lookahead = length, first, lookahead
        self.of = {s: i for i, (s, _, _) in enumerate(starts)}
        self.shares = np.array([p for _, p, _ in starts], np.float64)
        self.owed = np.array([d for _, _, d in starts], np.float64)
        self.least = (length * self.shares).astype(np.int64)
        self.queues: list[deque] = [deque() for _ in starts]
        self.held = np.zeros(len(starts), np.int64)
        self.total = 0

    def push(self, source, key, ids: np.ndarray) -> None:
        i = self.of[source]
        self.queues[i].append([key, ids, 0])
        self.held[i] += len(ids)
        self.total += len(ids)

    def ready(self) -> bool:
        """Every source can give its part of a window, or the queues are full."""
        return self.total >= self.length and (self.total >= self.lookahead or bool((self.held >= self.least).all()))

    def _take(self, i: int, most: int) -> Iterator[tuple]:
        queue = self.queues[i]
        self.owed[i] -= most
        self.held[i] -= most
        self.total -= most
        while most:
            item = queue[0]
            n = min(len(item[1]) - item[2], most)
            yield item[0], item[2], n, item[1]
            most -= n
            item[2] += n
            if item[2] == len(item[1]):
                queue.popleft()

    def window(self, size: int) -> list[tuple]:
        """Fills one sequence with exactly ``size`` of the held tokens: (key, at, n, ids, sequence, offset)."""
        self.owed += self.shares * size
        room, pieces = size, []
        for spare in (False, True):  # first what is owed, then what others have left over
            give = self.held if spare else np.minimum(self.held, np.maximum(0, self.owed).astype(np.int64))
            able = np.flatnonzero(give > 0)
            for i in able[np.lexsort((able, -self.owed[able]))].tolist():
                if not room:
                    break
                for key, at, n, ids in self._take(i, min(room, int(give[i]))):
                    pieces.append((key, at, n, ids, self.sequence, size - room))
                    room -= n
        self.sequence += 1
        return pieces

    def rest(self) -> Iterator[list[tuple]]:
        """All that is held: full windows, then lengths that are powers of two."""
        while self.total:
            yield self.window(self.length if self.total >= self.length else 1 << (self.total.bit_length() - 1))


def starts_of(totals: DataFrame, shares: dict[str, float] | None) -> DataFrame:
    """(bucket, starts): source, share and deficit of the sources in each bucket.

    totals: (bucket, source, tokens).  Sources that ``shares`` doesn't name divide what it
    leaves by their tokens.
    """
    before = Window.orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)  # one row a bucket
    given = totals.groupBy("bucket").agg(F.sum("tokens").alias("given")).withColumn("ahead", F.coalesce(F.sum("given").over(before), F.lit(0)))
    overall = totals.groupBy("source").agg(F.sum("tokens").cast("double").alias("all"))
    if shares:
        named = F.try_element_at(F.create_map(*[F.lit(x) for s, p in shares.items() for x in (s, float(p))]), F.col("source"))
        overall = overall.withColumn("named", named)
    else:
        overall = overall.withColumn("named", F.lit(None).cast("double"))
    rest = overall.where("named is null").agg(F.sum("all")).first()[0] or 1.0
    share = F.coalesce("named", F.col("all") / F.lit(rest) * F.lit(max(0.0, 1.0 - sum((shares or {}).values()))))
    own = Window.partitionBy("source").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    debts = totals.join(given, "bucket").join(overall.select("source", share.alias("share")), "source")
    debts = debts.withColumn("deficit", F.col("share") * F.col("ahead") - F.coalesce(F.sum("tokens").over(own), F.lit(0)))
    return debts.groupBy("bucket").agg(F.sort_array(F.collect_list(F.struct("source", "share", "deficit"))).alias("starts"))


_PIECES = "key bigint, source string, start bigint, length bigint, ids_crc32 bigint, doc_tokens bigint, sequence_id bigint, offset bigint"


def packed(docs: DataFrame, key: str = "doc_id", source: str = "source", length: int = LENGTH, shares: dict[str, float] | None = None, file: str | None = None, buckets: int | None = None, with_ids: bool = False, lookahead: int = LOOKAHEAD) -> DataFrame:
    """One row per piece: key, source, start, length, ids_crc32, doc_tokens, sequence_id, offset (and ids).

    shares: target part of each source in a window; by default each source's part of all
    tokens, so that the mixture holds to the end.  buckets: partitions that pack by
    themselves; by default as many as a shuffle makes.  Sequence ids begin at
    bucket * 2 ** 40.  lookahead: most tokens that a partition's queues hold.
    """
    spark = docs.sparkSession
    buckets = buckets or int(spark.conf.get("spark.sql.shuffle.partitions"))
    wide = 4 if len(encoder(file or default_file()).lengths) > 65536 else 2
    rows = materialize(encoded(docs, buckets, key, source, file), "ids")
    totals = rows.groupBy("bucket", "source").agg(F.sum("tokens").alias("tokens"))
    start = starts_of(totals, shares)
    fields = [f.split()[0] for f in _PIECES.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        packer, now = None, None
        out: list[tuple] = []

        def flush():
            cols = list(zip(*out)) or [()] * (len(fields) + 1)
            kinds = [pa.int64(), pa.string(), *[pa.int64()] * 6, pa.binary()]
            n = len(fields) + with_ids
            batch = pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols[:n], kinds)], names=[*fields, "ids"][:n])
            out.clear()
            return batch

        def take(pieces):
            for (k, s), at, n, ids, sequence, offset in pieces:
                raw = ids[at : at + n].astype("<u4").tobytes()
                out.append((k, s, at, n, zlib.crc32(raw), len(ids), sequence, offset, raw if with_ids else None))

        for batch in batches:
            for bucket, k, s, ids, starts in zip(*(c.to_pylist() for c in batch.columns)):
                if bucket != now:
                    for pieces in packer.rest() if packer else ():
                        take(pieces)
                    now, packer = bucket, Packer([(x["source"], x["share"], x["deficit"]) for x in starts], length, bucket << 40, lookahead)
                if ids is None:  # the row that only brings shares and deficits
                    continue
                packer.push(s, (k, s), np.frombuffer(ids, f"<u{wide}"))
                while packer.ready():
                    take(packer.window(length))
                if len(out) >= 20_000:
                    yield flush()
        for pieces in packer.rest() if packer else ():
            take(pieces)
            if len(out) >= 20_000:
                yield flush()
        if out:
            yield flush()

    none = lambda kind: F.lit(None).cast(kind)
    heads = start.select("bucket", F.lit(0).alias("turn"), none("bigint").alias("place"), none("bigint").alias("key"), none("string").alias("source"), none("binary").alias("ids"), "starts")
    bodies = rows.select("bucket", F.lit(1).alias("turn"), "place", "key", "source", "ids", none("array<struct<source:string,share:double,deficit:double>>").alias("starts"))
    dealt = heads.union(bodies).repartition(buckets, "bucket").sortWithinPartitions("bucket", "turn", "place", "key")
    return dealt.select("bucket", "key", "source", "ids", "starts").mapInArrow(run, _PIECES + (", ids binary" if with_ids else ""))
