"""The index as users hold it: its tree, its data files by version, and what was deleted."""

from __future__ import annotations

import json
import pickle
import uuid
from dataclasses import replace

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .params import BuildParams
from .storage import fresh_path

DATA_SCHEMA = T.StructType([
    T.StructField("leaf_id", T.LongType()), T.StructField("series_id", T.LongType()), T.StructField("word", T.BinaryType()),
    T.StructField("values", T.ArrayType(T.DoubleType())), T.StructField("is_copy", T.BooleanType()),
])
#: Most nodes of a tree that the driver holds; past it, leaves must be made larger (th).
MAX_NODES = 5_000_000
#: Most intervals of leaf ids that a read's filter names; Parquet statistics serve all of them.
MAX_RANGES = 200


def intervals(ids, most: int = MAX_RANGES) -> tuple[list[tuple[int, int]], bool]:
    """Closed intervals that cover ``ids``, at most ``most`` of them (the widest gaps stay
    open), and whether they hold nothing else."""
    x = np.unique(np.asarray(list(ids), np.int64))
    if not len(x):
        return [], True
    gaps = np.flatnonzero(np.diff(x) > 1)
    exact = len(gaps) < most
    if not exact:
        width = np.diff(x)[gaps]
        gaps = np.sort(gaps[np.lexsort((gaps, -width))[: most - 1]])
    starts, stops = np.append(x[0], x[gaps + 1]), np.append(x[gaps], x[-1])
    return list(zip(starts.tolist(), stops.tolist())), exact


def within(column: Column, ranges: list[tuple[int, int]]) -> Column:
    """Whether the column lies in one of the intervals; a balanced tree of comparisons, which
    are pushed down to files whatever their number is."""
    if len(ranges) == 1:
        (a, b), = ranges
        return column == a if a == b else (column >= a) & (column <= b)
    half = len(ranges) // 2
    return within(column, ranges[:half]) | within(column, ranges[half:])


class SeriesIndex:
    """tree: WordTree or DynTree.  segments: [(path, born)] in the order in which they were
    written; rows of leaf ids that the tree no longer has are void.  tombstones: path of
    (series_id, until) or None: a deleted id hides its rows in segments born up to ``until``,
    so what is inserted again later is seen.  taken: by stream, intervals of the batch ids
    that were inserted.  uid: name of this line of changes; a copy has its own.
    """

    def __init__(self, spark: SparkSession, tree, params: BuildParams, n: int, segments: list, tombstones: str | None = None, version: int = 0, timings: dict | None = None, deleted: int = 0, inserted: int = 0, clock: int = 0, taken: dict | None = None, uid: str | None = None):
        if len(tree) > MAX_NODES:
            raise ValueError(f"{len(tree)} nodes; the driver holds at most {MAX_NODES}: raise th")
        self.spark, self.tree, self.params, self.n = spark, tree, params, n
        self.segments, self.tombstones, self.version = segments, tombstones, version
        self.timings, self.deleted, self.inserted = timings or {}, deleted, inserted
        self.clock, self.taken, self.uid = clock, taken or {}, uid or uuid.uuid4().hex
        self._shared = None

    # ---- data -------------------------------------------------------------------------

    def data(self, leaf_ids=None, columns: tuple[str, ...] = ("leaf_id", "series_id", "word", "values", "is_copy"), loose: bool = False) -> DataFrame:
        """Live rows, of all leaves or of the given ones.  Leaf ids become a filter of at most
        ``MAX_RANGES`` intervals; where those hold other leaves too, a join takes them out
        unless the caller does it itself (``loose``)."""
        t = self.tree
        ranges, exact = intervals(t.leaf_id if leaf_ids is None else leaf_ids)
        ranges = [(max(0, a), b) for a, b in ranges if b >= 0]
        out = None
        for path, born in self.segments if ranges else ():
            df = self.spark.read.schema(DATA_SCHEMA).parquet(path).where(within(F.col("leaf_id"), ranges))
            df = df.select(*dict.fromkeys(("leaf_id", "series_id", *columns)))
            if self.tombstones:
                gone = self.spark.read.schema("series_id long, until long").parquet(self.tombstones).where(F.col("until") >= born).select("series_id")
                df = df.join(gone, "series_id", "left_anti")
            out = df if out is None else out.unionByName(df)
        if out is None:
            out = self.spark.createDataFrame([], DATA_SCHEMA)
        elif not exact and not loose:
            wanted = {int(x) for x in (t.leaf_id if leaf_ids is None else leaf_ids) if x >= 0}
            out = out.join(self.spark.createDataFrame([(x,) for x in sorted(wanted)], "leaf_id long"), "leaf_id", "left_semi")
        return out.select(*columns)

    def tree_broadcast(self):
        if self._shared is None:
            self._shared = self.spark.sparkContext.broadcast(self.tree)
        return self._shared

    def touched(self) -> None:
        """After a change of the tree."""
        self._shared = None
        self.version += 1

    def commit(self, tree, path: str | None, replaces: bool = False) -> None:
        """Switches to ``tree`` and the rows written under ``path`` (in place of all before)."""
        self.clock += 1
        kept = [] if replaces else self.segments
        self.tree, self.segments = tree, kept + ([(path, self.clock)] if path else [])
        if replaces:
            self.tombstones = None
        self.touched()

    # ---- batches of streams -------------------------------------------------------------

    def was_taken(self, stream: str, batch_id: int) -> bool:
        return any(a <= batch_id <= b for a, b in self.taken.get(stream, ()))

    def take(self, stream: str, batch_id: int) -> None:
        merged: list[list[int]] = []
        for a, b in sorted([*self.taken.get(stream, ()), [batch_id, batch_id]]):
            if merged and a <= merged[-1][1] + 1:
                merged[-1][1] = max(b, merged[-1][1])
            else:
                merged.append([a, b])
        self.taken = {**self.taken, stream: merged}

    # ---- node table -------------------------------------------------------------------

    def nodes(self) -> DataFrame:
        t = self.tree
        schema = "node_id long, parent_id long, depth int, kind string, csl array<int>, pfx_bits array<int>, pfx_len array<int>, size long, n_copies long, routes map<int,long>, leaf_id long, members array<int>, oversize boolean"
        word = hasattr(t, "csl")
        rows = [
            (i, t.parent[i], t.depth[i], t.kind[i] if word else ("leaf" if t.is_leaf(i) else "internal"), list(t.csl[i]) if word else [], list(t.pfx_bits[i]) if word else [], list(t.pfx_len[i]) if word else [], int(t.size[i]), int(t.n_copies[i]) if word else 0,
             {int(s): int(c) for s, c in t.routes[i].items()} if word else dict(enumerate(map(int, t.kids[i]))), t.leaf_id[i] if t.is_leaf(i) else None, list(t.members[i]) if word else [], bool(t.oversize[i]))
            for i in range(len(t))
        ]
        return self.spark.createDataFrame(rows, schema)

    # ---- save and load ----------------------------------------------------------------

    def save(self, path: str) -> str:
        """Writes node table, data and one row of meta; a manifest of version ``v`` is written
        last.  It holds the batches that were taken, so a stream goes on after loading."""
        self.data().repartitionByRange("leaf_id", "series_id").sortWithinPartitions("leaf_id", "series_id").write.mode("overwrite").parquet(f"{path}/data-{self.version}")
        self.nodes().write.mode("overwrite").parquet(f"{path}/nodes-{self.version}")
        meta = {"params": self.params.asdict(), "n": self.n, "version": self.version, "taken": self.taken, "uid": self.uid, "inserted": self.inserted, "deleted": self.deleted}
        blob = bytearray(pickle.dumps(self.tree))
        self.spark.createDataFrame([(self.version, json.dumps(meta), blob)], "version long, meta string, tree binary").coalesce(1).write.mode("append").parquet(f"{path}/manifest")
        return path

    def copy(self) -> "SeriesIndex":
        """Another handle on the same files, which can change by itself."""
        return SeriesIndex(
            self.spark, pickle.loads(pickle.dumps(self.tree)), replace(self.params), self.n, list(self.segments), self.tombstones, self.version, dict(self.timings), self.deleted, self.inserted,
            self.clock, {s: [list(x) for x in v] for s, v in self.taken.items()})


def load_index(spark: SparkSession, path: str) -> SeriesIndex:
    """The latest version under ``path``."""
    row = spark.read.parquet(f"{path}/manifest").orderBy(F.desc("version")).first()
    meta = json.loads(row["meta"])
    return SeriesIndex(
        spark, pickle.loads(bytes(row["tree"])), BuildParams(**meta["params"]), meta["n"], [(f"{path}/data-{row['version']}", 0)], version=row["version"],
        deleted=meta.get("deleted", 0), inserted=meta.get("inserted", 0), taken=meta.get("taken"), uid=meta.get("uid"))


def new_segment(spark: SparkSession) -> str:
    return fresh_path(spark, "segment")
