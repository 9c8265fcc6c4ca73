"""Accuracy and cost measures over answers, trees and data."""

from __future__ import annotations

import pickle

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .functions.distances import upper_bounds_rows
from .plans import arrow
from .plans.index import SeriesIndex
from .plans.order import positions

TIE = 1e-9


def hits(answers: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """Answers up to rank k with ``hit``: a true neighbour, or as near as the k-th true one."""
    true = truth.where(F.col("rank") <= k)
    last = true.groupBy("query_id").agg(F.max("distance").alias("last"))
    members = true.select("query_id", "series_id", F.lit(1).alias("member"))
    rows = answers.where(F.col("rank") <= k).join(last, "query_id").join(members, ["query_id", "series_id"], "left")
    return rows.withColumn("hit", (F.col("member").isNotNull() | (F.col("distance") <= F.col("last") + TIE)).cast("int"))


def average_precision(answers: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """(query_id, ap): sum over hits of the precision at their ranks, over k.  Queries without answers have 0."""
    so_far = Window.partitionBy("query_id").orderBy("rank")
    rows = hits(answers, truth, k).withColumn("p", F.col("hit") * F.sum("hit").over(so_far) / F.col("rank"))
    sums = rows.groupBy("query_id").agg((F.sum("p") / k).alias("ap"))
    return truth.select("query_id").distinct().join(sums, "query_id", "left").na.fill(0.0, ["ap"])


def mean_average_precision(answers: DataFrame, truth: DataFrame, k: int) -> float:
    return float(average_precision(answers, truth, k).agg(F.avg("ap")).first()[0] or 0.0)


def recall_at_k(answers: DataFrame, truth: DataFrame, k: int) -> float:
    sums = hits(answers, truth, k).groupBy("query_id").agg((F.sum("hit") / k).alias("r"))
    all_queries = truth.select("query_id").distinct().join(sums, "query_id", "left").na.fill(0.0, ["r"])
    return float(all_queries.agg(F.avg("r")).first()[0] or 0.0)


def error_ratio(answers: DataFrame, truth: DataFrame, k: int) -> float:
    """Mean over ranks and queries of found over true distance; 0 over 0 is 1."""
    both = answers.where(F.col("rank") <= k).select("query_id", "rank", F.col("distance").alias("d")).join(truth.select("query_id", "rank", F.col("distance").alias("t")), ["query_id", "rank"])
    ratio = F.when(F.col("t") > TIE, F.col("d") / F.col("t")).when(F.col("d") <= TIE, 1.0)
    return float(both.select(F.avg(ratio)).first()[0] or 0.0)


def accuracies(answers: DataFrame, truth: DataFrame, ks) -> dict[int, tuple[float, float]]:
    """k -> (mean average precision, error ratio), for several k in one job."""
    at = F.explode(F.array(*[F.lit(int(k)) for k in ks]))
    spread = lambda df: df.withColumn("k", at).where(F.col("rank") <= F.col("k"))
    true = spread(truth)
    last = true.groupBy("query_id", "k").agg(F.max("distance").alias("last"))
    members = true.select("query_id", "k", "series_id", F.lit(1).alias("member"))
    place = true.select("query_id", "k", "rank", F.col("distance").alias("t"))
    rows = spread(answers).join(last, ["query_id", "k"]).join(members, ["query_id", "k", "series_id"], "left").join(place, ["query_id", "k", "rank"], "left")
    hit = (F.col("member").isNotNull() | (F.col("distance") <= F.col("last") + TIE)).cast("int")
    so_far = F.sum("hit").over(Window.partitionBy("query_id", "k").orderBy("rank"))
    ratio = F.when(F.col("t") > TIE, F.col("distance") / F.col("t")).when(F.col("distance") <= TIE, 1.0)
    rows = rows.withColumn("hit", hit).withColumn("p", F.col("hit") * so_far / F.col("rank") / F.col("k"))
    total = truth.agg(F.countDistinct("query_id").alias("q"))
    found = rows.groupBy("k").agg(F.sum("p").alias("p"), F.avg(ratio).alias("e")).crossJoin(F.broadcast(total)).collect()  # the total is one row
    sums = {r["k"]: (float(r["p"] / r["q"]), float(r["e"] or 0.0)) for r in found}
    return {k: sums.get(k, (0.0, 0.0)) for k in ks}


def improvement(value: float, other: float) -> float:
    """In percent over another method's value."""
    return 100.0 * (value - other) / other if other else float("nan")


def structure(ix: SeriesIndex) -> dict:
    """Leaves, nodes, height, fill factor, average path and fan-out, copies, and size in bytes."""
    t = ix.tree
    leaves = t.below(0) if len(t) else []
    inner, stack = [], [0] if len(t) else []
    while stack:
        n = stack.pop()
        if not t.is_leaf(n):
            inner.append(n)
            stack += t.children(n)
    total = t.size[0] if len(t) else 0
    copies = sum(t.n_copies[n] for n in leaves) if hasattr(t, "n_copies") else 0
    lam = [len(t.csl[n]) for n in inner] if hasattr(t, "csl") else [1] * len(inner)
    weights = np.array([t.size[n] for n in leaves], float)
    depth = np.array([t.depth[n] for n in leaves], float)
    return {
        "leaves": len(leaves), "nodes": len(leaves) + len(inner), "height": int(depth.max()) if len(depth) else 0, "fill": total / (len(leaves) * ix.params.th) if leaves else 0.0,
        "path": float((depth * weights).sum() / weights.sum()) if weights.sum() else 0.0, "fanout_bits": float(np.mean(lam)) if lam else 0.0, "copies_share": copies / total if total else 0.0,
        "degenerate": sum(len(t.children(n)) == 1 for n in inner), "oversize": sum(bool(t.oversize[n]) for n in leaves), "model_bytes": space_model(ix), "pickled_bytes": len(pickle.dumps(t)),
    }


def space_model(ix: SeriesIndex) -> int:
    """Bytes by formula: words of all series, and node and leaf entries."""
    t, p = ix.tree, ix.params
    if hasattr(t, "space"):
        return t.space()
    if not hasattr(t, "csl"):
        return sum(8 * (len(c) + 4 * (len(c) - 1)) for c in t.cuts)
    leaves = t.below(0)
    inner = [n for n in range(len(t)) if not t.is_leaf(n)]
    entry = p.w * p.bits / 8
    return int(np.ceil(p.w * p.bits * t.size[0] / 8) + sum(8 * 2 ** len(t.csl[n]) + entry + len(t.csl[n]) for n in inner) + entry * len(leaves))


def upper_bound_histogram(ix: SeriesIndex, width: float = 4.0) -> dict[int, int]:
    """Leaves by floor(upper bound / width)."""
    t = ix.tree
    nodes = t.below(0)
    bounds = upper_bounds_rows(np.array([t.pfx_bits[n] for n in nodes]), np.array([t.pfx_len[n] for n in nodes]), ix.n)
    values, counts = np.unique(np.floor(bounds / width).astype(int), return_counts=True)
    return dict(zip(values.tolist(), counts.tolist()))


def uneven_leaves(ix: SeriesIndex, apart: int = 4) -> float:
    """Share of leaves with a segment more than ``apart`` bits finer than another."""
    t = ix.tree
    nodes = t.below(0)
    return float(np.mean([max(t.pfx_len[n]) - min(t.pfx_len[n]) > apart for n in nodes])) if nodes else 0.0


def leaf_proximity(ix: SeriesIndex) -> float:
    """Mean squared distance of members to their leaf's centroid, by series.

    Batches give count, sum and sum of squares by leaf and position; what is shuffled is a
    row for each leaf of a batch, not for each value.
    """
    n = ix.n

    def sums(batches):
        for b in batches:
            leaf, x = b.column(0).to_numpy(), arrow.matrix_of(b.column(1), n)
            ids, at = np.unique(leaf, return_inverse=True)
            one, two = np.zeros((len(ids), n)), np.zeros((len(ids), n))
            np.add.at(one, at, x)
            np.add.at(two, at, x * x)
            yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(np.bincount(at, minlength=len(ids))), arrow.lists_of(one), arrow.lists_of(two)], names=["leaf_id", "n", "one", "two"])

    def joined(key, table):
        total = int(np.sum(table.column("n").to_numpy()))
        one, two = (arrow.matrix_of(table.column(c).combine_chunks(), n).sum(0) for c in ("one", "two"))
        spread = float(np.maximum(two / total - (one / total) ** 2, 0.0).sum())
        return pa.table({"n": pa.array([total]), "d": pa.array([spread])})

    rows = ix.data(None, ("leaf_id", "values")).mapInArrow(sums, "leaf_id long, n long, one array<double>, two array<double>")
    leaves = rows.groupBy("leaf_id").applyInArrow(joined, "n long, d double")
    return float(leaves.select(F.sum(F.col("d") * F.col("n")) / F.sum("n")).first()[0] or 0.0)


def written_bytes(ix: SeriesIndex) -> int:
    """Size of the index's data files, as the file system has it."""
    jvm, conf = ix.spark.sparkContext._jvm, ix.spark.sparkContext._jsc.hadoopConfiguration()
    paths = [jvm.org.apache.hadoop.fs.Path(p) for p, _ in ix.segments]
    return sum(p.getFileSystem(conf).getContentSummary(p).getLength() for p in paths)


def random_writes(ix: SeriesIndex, buffer: int) -> int:
    """Leaf flushes when series arrive in the order of their ids and ``buffer`` of them are held at a time."""
    rows = ix.data(None, ("leaf_id", "series_id", "is_copy")).where("not is_copy")
    numbered = positions(rows.select("leaf_id", "series_id"), ["series_id"])
    return numbered.select(F.floor(F.col("pos") / buffer).alias("b"), "leaf_id").distinct().count()


def pruned_shares(ix: SeriesIndex, leaves_read: int, series_read: int, queries: int) -> tuple[float, float]:
    """(share of leaves, share of series) that an average query did not read."""
    leaves = len(ix.tree.below(0))
    series = ix.tree.size[0]
    return 1 - leaves_read / (queries * leaves), 1 - series_read / (queries * series)


def linear_fit_r2(points: DataFrame, x: str, y: str) -> float:
    return float(points.select(F.regr_r2(F.col(y).cast("double"), F.col(x).cast("double"))).first()[0])


def root_cell_shares(cells: DataFrame, small: int = 100, top: float = 0.02) -> dict:
    """Of first-layer cells: share with under ``small`` series, and the part of all series in the ``top`` largest."""
    total = cells.agg(F.count(F.lit(1)).alias("c"), F.sum("n").alias("n")).first()
    first = max(1, int(np.ceil(total["c"] * top)))
    largest = cells.orderBy(F.desc("n")).limit(first).agg(F.sum("n")).first()[0]
    few = cells.where(F.col("n") < small).count()
    return {"cells": total["c"], "small_share": few / total["c"], "top_share": largest / total["n"]}


def operation_counts(w: int, low: int, high: int) -> dict[str, int]:
    """Plans and cell visits of a restricted plan search, in closed form."""
    from math import comb

    return {"plans": sum(comb(w, i) for i in range(low, high + 1)), "cells": comb(w, high) * 2**w + sum(comb(w, i) * 2 ** (i + 1) for i in range(low, high))}
