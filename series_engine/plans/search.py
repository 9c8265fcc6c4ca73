"""Search: the scan, one leaf, several leaves of a subtree, and exact search by pruning.

Queries are few and the tree is on the driver, so the leaves to read are chosen there by
their lower bounds, before the job that reads them is built: its file filter is a literal
of intervals of leaf ids.  The job reads each leaf once, computes distances batch by batch
and keeps k rows and one row of counts per query and batch; only those are shuffled.

Ties: equal bounds by leaf id, equal distances by series id.
"""

from __future__ import annotations

import time
import warnings
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.distances import BAND, SLACK, QuerySummary, mindist_cells_rows
from ..functions.summaries import cells_rows, edges, words_rows, znormalize_rows
from . import arrow
from .dynseg import DynTree
from .index import SeriesIndex
from .tree import WordTree

ANSWERS = "query_id long, rank int, series_id long, distance double"
#: Most queries answered together; larger sets are taken block by block.  Long series: ``LONG_QUERIES``,
#: where the values of more would be over ``QUERY_BYTES``.
MAX_QUERIES, LONG_QUERIES, QUERY_BYTES = 8_000, 2_000, 64 << 20


@dataclass
class Queries:
    ids: list[int]
    summaries: list[QuerySummary]
    words: np.ndarray


@dataclass
class SearchStats:
    """By query: leaves read, series read, series whose distance was computed.  seconds: wall
    clock; cpu_seconds: spent in tasks on bounds and distances of what was read, the rest being
    reading and scheduling."""

    leaves: dict[int, int] = field(default_factory=dict)
    series: dict[int, int] = field(default_factory=dict)
    computed: dict[int, int] = field(default_factory=dict)
    waves: int = 0
    seconds: float = 0.0
    cpu_seconds: float = 0.0


def prepare(queries: DataFrame, n: int, w: int, bits: int, normalize: bool = True, metric: str = "ed", band: float = BAND, strict: bool = False) -> Queries:
    """Queries on the driver.  Those without an id or values have no answers; those of another
    length than ``n`` have none either and are warned of (``strict``: raise)."""
    most = min(MAX_QUERIES, max(LONG_QUERIES, QUERY_BYTES // (8 * max(1, n))))
    rows = sorted(queries.select("query_id", "values").where("query_id is not null and values is not null").limit(most + 1).collect(), key=lambda r: r["query_id"])
    if len(rows) > most:
        raise ValueError(f"more than {most} queries: take them block by block (see in_blocks)")
    other = [r["query_id"] for r in rows if len(r["values"]) != n]
    if other and strict:
        raise ValueError(f"{len(other)} queries are not of length {n}, the first is {other[0]}")
    if other:
        warnings.warn(f"{len(other)} queries are not of length {n} and get no answers, the first is {other[0]}", stacklevel=2)
    rows = [r for r in rows if len(r["values"]) == n]
    x = np.array([r["values"] for r in rows], np.float64).reshape(-1, n)
    x = znormalize_rows(x) if normalize else x
    return Queries([r["query_id"] for r in rows], [QuerySummary(v, w, metric, band) for v in x], words_rows(x, w, bits))


def in_blocks(queries: DataFrame, answer, blocks: int) -> DataFrame:
    """Answers of ``answer(part)`` over hash parts of a large query set."""
    out = None
    for i in range(blocks):
        part = answer(queries.where(F.pmod(F.xxhash64("query_id"), F.lit(blocks)) == i))
        out = part if out is None else out.unionByName(part)
    return out


def _best(rows: dict[int, tuple[np.ndarray, np.ndarray]], k: int):
    for q, (d, i) in rows.items():
        order = np.lexsort((i, d))[:k]
        yield q, d[order], i[order]


def _batch(rows: list[tuple[int, np.ndarray, np.ndarray]]) -> pa.RecordBatch:
    q = np.concatenate([np.full(len(i), q, np.int64) for q, _, i in rows]) if rows else np.zeros(0, np.int64)
    d = np.concatenate([d for _, d, _ in rows]) if rows else np.zeros(0)
    i = np.concatenate([i for _, _, i in rows]) if rows else np.zeros(0, np.int64)
    return pa.RecordBatch.from_arrays([pa.array(q), pa.array(i.astype(np.int64)), pa.array(d)], names=["query_id", "series_id", "distance"])


def top_k(found: DataFrame, k: int, distinct: bool = False) -> DataFrame:
    """Ranked answers from (query_id, series_id, distance); repeats of a series count once."""
    if distinct:
        found = found.groupBy("query_id", "series_id").agg(F.min("distance").alias("distance"))
    order = Window.partitionBy("query_id").orderBy("distance", "series_id")
    return found.withColumn("rank", F.row_number().over(order).cast("int")).where(F.col("rank") <= k).select("query_id", "rank", "series_id", "distance")


def knn_scan(series: DataFrame, queries: DataFrame, k: int, metric: str = "ed", normalize: bool = True, band: float = BAND, exclude_self: bool = False) -> DataFrame:
    """Brute force: every series against every query; no index.  The ground truth."""
    from .build import checked

    good, _, n = checked(series)
    if n == 0:
        return series.sparkSession.createDataFrame([], ANSWERS)
    shared = series.sparkSession.sparkContext.broadcast(prepare(queries, n, 1, 1, normalize, metric, band))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        q = shared.value
        for b in batches:
            ids, x = b.column(0).to_numpy(zero_copy_only=False), arrow.matrix_of(b.column(1), n)
            x = znormalize_rows(x) if normalize else x
            found = {}
            for qid, s in zip(q.ids, q.summaries):
                d = s.distances(x)
                found[qid] = (np.where(ids == qid, np.inf, d), ids) if exclude_self else (d, ids)
            yield _batch([r for r in _best(found, k) if len(r[1])])

    def run_ed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """All queries at once: products of matrices say which pairs can be among a query's k best."""
        q = shared.value
        names = np.array(q.ids, np.int64)
        values = np.array([s.values for s in q.summaries]).reshape(-1, n)
        far, top = np.full(len(names), np.inf), (np.zeros(0, np.int64), np.zeros(0), np.zeros(0, np.int64))
        step, waiting, pairs = max(1, _STEP // max(1, len(names))), [], 0

        def merge() -> None:
            nonlocal far, top, pairs
            top = _nearest(*(np.concatenate(v) for v in zip(top, *waiting)), k, False)
            last = np.flatnonzero(np.diff(np.append(top[0], len(names))) != 0)
            far = np.full(len(names), np.inf)
            far[top[0][last]] = np.where(np.bincount(top[0], minlength=len(names))[top[0][last]] >= k, top[1][last], np.inf)
            waiting.clear()
            pairs = 0

        for b in batches if len(names) else ():
            all_ids, all_x = b.column(0).to_numpy(zero_copy_only=False), arrow.matrix_of(b.column(1), n)
            for at in range(0, len(all_x), step):
                ids, x = all_ids[at : at + step], all_x[at : at + step]
                x = znormalize_rows(x) if normalize else x
                own = ids[:, None] == names if exclude_self else None
                near = _close(x, values, far, 0 if np.isfinite(far).all() else k, own)
                i, j = np.nonzero(near & ~own if exclude_self else near)
                d = _pair_distances(x, values, i, j)
                ok = np.isfinite(d)
                waiting.append((j[ok], d[ok], ids[i[ok]]))
                pairs += int(ok.sum())
                if pairs > _STEP // 8 or not np.isfinite(far).all():
                    merge()
        if waiting:
            merge()
        yield pa.RecordBatch.from_arrays([pa.array(names[top[0]]), pa.array(top[2]), pa.array(top[1])], names=["query_id", "series_id", "distance"])

    found = good.mapInArrow(run_ed if metric == "ed" else run, "query_id long, series_id long, distance double")
    return top_k(found.where("distance < double('Infinity')"), k)


#: Most numbers of one step on many rows and queries at once.
_STEP = 1 << 21


def _nearest(at: np.ndarray, d: np.ndarray, ids: np.ndarray, k: int, distinct: bool = True) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of each query position the k least by (distance, id); ``distinct``: a series once."""
    if distinct and len(at):
        order = np.lexsort((d, ids, at))
        at, d, ids = at[order], d[order], ids[order]
        fresh = np.append(True, (np.diff(at) != 0) | (np.diff(ids) != 0))
        at, d, ids = at[fresh], d[fresh], ids[fresh]
    order = np.lexsort((ids, d, at))
    at, d, ids = at[order], d[order], ids[order]
    if len(at):
        first = np.flatnonzero(np.append(True, np.diff(at) != 0))
        few = np.arange(len(at)) - np.repeat(first, np.diff(np.append(first, len(at)))) < k
        at, d, ids = at[few], d[few], ids[few]
    return at, d, ids


def _close(x: np.ndarray, v: np.ndarray, far: np.ndarray, k: int = 0, but: np.ndarray | None = None) -> np.ndarray:
    """Rows x queries: False only where the distance is above ``far`` of the query, or above that of k other rows
    (which must be other series), or where ``but`` is True; from one product of matrices, so that pairs on the edge are True."""
    xx, vv = np.einsum("ij,ij->i", x, x), np.einsum("ij,ij->i", v, v)
    slack = 8 * (x.shape[1] + 8) * np.finfo(np.float64).eps * (np.max(xx, initial=0.0, where=np.isfinite(xx)) + vv)
    near = x @ (2 * v).T
    near -= xx[:, None]  # the squared distance is vv less this
    if but is not None:
        near[but] = -np.inf
    least = vv - np.broadcast_to((far + SLACK) ** 2, vv.shape)
    if 0 < k < len(x):
        kth = np.partition(near, len(x) - k, axis=0)[len(x) - k]
        least = np.maximum(least, np.where(np.isnan(near).any(0), -np.inf, kth))
    return near >= least - 2 * slack


def _pair_distances(x: np.ndarray, v: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Distances of rows i from queries j, summed as :func:`ed_rows` does."""
    out, step = np.zeros(len(i)), max(1, _STEP // x.shape[1])
    for a in range(0, len(i), step):
        for c in range(0, x.shape[1], 64):
            d = x[i[a : a + step], c : c + 64] - v[j[a : a + step], c : c + 64]
            out[a : a + step] += np.einsum("ij,ij->i", d, d)
    return np.sqrt(out)


def _read(ix: SeriesIndex, q: Queries, wanted: dict[int, list[int]], best: np.ndarray, k: int, word_filter: bool = True) -> tuple[list, dict[int, tuple[int, int, float]]]:
    """Reads leaves (leaf_id -> query positions; best: k-th distance so far, by position); k best rows per query, and
    (series read, computed, seconds of work) by query position.  One scan; rows of leaves that the file filter
    lets through beside the wanted ones are passed over.  A leaf meets all its queries at once."""
    if not wanted:
        return [], {}
    shared = ix.spark.sparkContext.broadcast((q, {leaf: np.array(at, np.int32) for leaf, at in wanted.items()}, best))
    p, n = ix.params, ix.n
    use_words = word_filter and not isinstance(ix.tree, DynTree)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        q, wanted, best = shared.value
        ends, count = edges(p.bits), len(q.ids)
        values, hi_q, lo_q = (np.stack([getattr(s, f) for s in q.summaries]) for f in ("values", "hi", "lo"))
        warped = q.summaries[0].metric != "ed"
        read, done, spent = np.zeros(count, np.int64), np.zeros(count, np.int64), np.zeros(count)
        top = np.zeros(0, np.int64), np.zeros(0), np.zeros(0, np.int64)
        for b in batches:
            began = time.process_time()
            leaf, ids = b.column(0).to_numpy(), b.column(1).to_numpy()
            x, words = arrow.matrix_of(b.column(3), n), arrow.words_from(b.column(2), p.w).astype(np.int64)
            order = np.argsort(leaf, kind="stable")
            names, first = np.unique(leaf[order], return_index=True)
            found, met = [top], np.zeros(count, bool)
            for one, rows in zip(names, np.split(order, first[1:])):
                asked = wanted.get(int(one))
                if asked is None:
                    continue
                met[asked] = True
                read[asked] += len(rows)
                mine, lo, hi = x[rows], ends[words[rows]], ends[words[rows] + 1]
                step = max(1, _STEP // (len(rows) * p.w))
                apart = len(rows) > 4 * k and len(np.unique(ids[rows])) == len(rows)
                for at in np.split(asked, range(step, len(asked), step)):
                    far, near = best[at], np.ones((len(rows), len(at)), bool)
                    if use_words and np.isfinite(far).any():
                        gap = np.maximum(np.maximum(lo[:, None] - hi_q[at], lo_q[at] - hi[:, None]), 0.0)
                        near = np.sqrt(n / p.w * (gap**2).sum(axis=2)) <= far + SLACK
                    done[at] += near.sum(0)
                    if warped:
                        for j in np.flatnonzero(near.any(0)):
                            i = np.flatnonzero(near[:, j])
                            d = q.summaries[at[j]].distances(mine[i], far[j])
                            found.append((np.full(len(i), at[j], np.int64), d, ids[rows[i]]))
                        continue
                    if near.any() and (np.isfinite(far).any() or apart):
                        near &= _close(mine, values[at], far, k if apart else 0, ~near if apart else None)
                    i, j = np.nonzero(near)
                    if len(i):
                        d = _pair_distances(mine, values, i, at[j])
                        ok = d <= far[j] + SLACK
                        found.append((at[j[ok]].astype(np.int64), d[ok], ids[rows[i[ok]]]))
            at, d, i = (np.concatenate(v) for v in zip(*found))
            ok = np.isfinite(d)
            top = _nearest(at[ok], d[ok], i[ok], k)
            spent[met] += (time.process_time() - began) / max(1, met.sum())
        seen = np.flatnonzero(read)
        pad = lambda m, kind: pa.nulls(m, kind)
        answers, counts = len(top[0]), len(seen)
        yield pa.RecordBatch.from_arrays([
            pa.array(np.concatenate((top[0], seen))), pa.concat_arrays([pa.array(top[2]), pad(counts, pa.int64())]), pa.concat_arrays([pa.array(top[1]), pad(counts, pa.float64())]),
            *(pa.concat_arrays([pad(answers, pa.from_numpy_dtype(v.dtype)), pa.array(v[seen])]) for v in (read, done, spent))], names=["query_id", "series_id", "distance", "read", "done", "spent"])

    data = ix.data(sorted(wanted), ("leaf_id", "series_id", "word", "values"), loose=True)
    found = data.mapInArrow(run, "query_id long, series_id long, distance double, read long, done long, spent double")
    # rows of counts have no series id: together they are one group of each query, and its first
    merged = found.groupBy("query_id", "series_id").agg(F.min("distance").alias("distance"), F.sum("read").alias("read"), F.sum("done").alias("done"), F.sum("spent").alias("spent"))
    order = Window.partitionBy("query_id").orderBy(F.col("series_id").isNotNull(), "distance", "series_id")
    rows = merged.withColumn("i", F.row_number().over(order)).where(F.col("i") <= k + 1).collect()
    return [(r["query_id"], r["distance"], r["series_id"]) for r in rows if r["series_id"] is not None], {r["query_id"]: (r["read"], r["done"], r["spent"]) for r in rows if r["series_id"] is None}


class _Best:
    """k best (distance, series_id) of each query, copies counted once."""

    def __init__(self, count: int, k: int):
        self.k, self.rows = k, [dict() for _ in range(count)]

    def take(self, found) -> None:
        for at, d, i in found:
            if i not in self.rows[at] or d < self.rows[at][i]:
                self.rows[at][i] = d
        for at, rows in enumerate(self.rows):
            if len(rows) > self.k:
                self.rows[at] = dict(sorted(rows.items(), key=lambda r: (r[1], r[0]))[: self.k])

    def bsf(self, at: int) -> float:
        return max(self.rows[at].values()) if len(self.rows[at]) >= self.k else np.inf


def _answers(spark: SparkSession, q: Queries, best: _Best) -> DataFrame:
    rows = [(q.ids[at], r, int(i), float(d)) for at, found in enumerate(best.rows) for r, (i, d) in enumerate(sorted(found.items(), key=lambda x: (x[1], x[0])), 1)]
    kinds = (pa.int64(), pa.int32(), pa.int64(), pa.float64())
    return spark.createDataFrame(pa.table([pa.array(c, t) for c, t in zip(zip(*rows) if rows else [()] * 4, kinds)], names=["query_id", "rank", "series_id", "distance"]))


def _prepared(ix: SeriesIndex, queries: DataFrame, metric: str, band: float) -> Queries:
    p = ix.params
    return prepare(queries, ix.n, p.w, p.bits, p.normalize, metric, band)


def _leaf_counts(tree) -> list[int]:
    """Number of leaves under each node."""
    out = [0] * len(tree)
    for node in tree.below(0) if len(tree) else ():
        while node >= 0:
            out[node] += 1
            node = tree.parent[node]
    return out


def _first_leaf(tree, node: int) -> int:
    while not tree.is_leaf(node):
        node = tree.children(node)[0]
    return node


def extended_leaves(tree, query: QuerySummary, word: np.ndarray, nbr: int, counts: list[int] | None = None, nodes: _Nodes | None = None) -> list[int]:
    """Leaf nodes that a search over ``nbr`` leaves reads, in reading order.

    Down from the root while a node has more than ``nbr`` leaves; where the way ends, that
    node and its siblings are taken by lower bound (the node itself first).  A subtree with
    more leaves than are still to be read gives its best ones by bound.  counts: of the
    leaves under each node, and nodes: shared by descents, where a caller asks for many queries.
    """
    counts = _leaf_counts(tree) if counts is None else counts
    if counts[0] <= nbr:
        return tree.below(0)
    path = tree.path(word, query.values)
    end = next((i for i, node in enumerate(path) if counts[node] <= nbr), len(path) - 1)
    node = path[end]
    if not tree.is_leaf(node) and counts[node] > nbr:  # the way ends in a cell without series
        family, own = tree.children(node), None
    else:
        family, own = (tree.children(path[end - 1]) if end else [node]), node
    family = [n for n in family if counts[n]]
    bounds = dict(zip(family, tree.bounds(query, family)))
    key = lambda n: (n != own, bounds[n], tree.leaf_id[_first_leaf(tree, n)])
    out: list[int] = []
    for member in sorted(family, key=key):
        room = nbr - len(out)
        if counts[member] <= room:
            out += tree.below(member)
        else:
            way = _Descent(tree, query, None, member, nodes)
            out += [way.next_node(np.inf) for _ in range(room)]
        if len(out) >= nbr:
            break
    return out


def search_extended(ix: SeriesIndex, queries: DataFrame, k: int, nbr: int, metric: str = "ed", band: float = BAND, stats: SearchStats | None = None) -> DataFrame:
    """k nearest among the series of ``nbr`` leaves around where each query belongs."""
    began, stats = time.time(), stats if stats is not None else SearchStats()
    q = _prepared(ix, queries, metric, band)
    wanted: dict[int, list[int]] = {}
    counts, nodes = _leaf_counts(ix.tree), _Nodes(ix.tree)
    for at, (s, w) in enumerate(zip(q.summaries, q.words)):
        leaves = extended_leaves(ix.tree, s, w, nbr, counts, nodes)
        stats.leaves[q.ids[at]] = len(leaves)
        for node in leaves:
            wanted.setdefault(ix.tree.leaf_id[node], []).append(at)
    best = _Best(len(q.ids), k)
    found, seen = _read(ix, q, wanted, np.full(len(q.ids), np.inf), k)
    best.take(found)
    for at, (read, done, spent) in seen.items():
        stats.series[q.ids[at]], stats.computed[q.ids[at]] = read, done
        stats.cpu_seconds += spent
    stats.waves, stats.seconds = 1, time.time() - began
    return _answers(ix.spark, q, best)


def search_leaf(ix: SeriesIndex, queries: DataFrame, k: int, metric: str = "ed", band: float = BAND, stats: SearchStats | None = None) -> DataFrame:
    """k nearest in the one leaf that each query belongs to."""
    return search_extended(ix, queries, k, 1, metric, band, stats)


def delta_radius(ix: SeriesIndex, q: Queries, delta: float, sample: int = 1_000) -> list[float]:
    """By query: the distance within which no series lies with probability ``delta``, from
    distances to a bounded sample of the collection (those with the least hashes)."""
    if delta >= 1:
        return [0.0] * len(q.ids)
    data = ix.data(None, ("series_id", "values", "is_copy")).where("not is_copy")
    total = max(1, data.count())
    part = min(1.0, 2.0 * sample / total)
    rows = data.where(F.pmod(F.xxhash64("series_id"), F.lit(1 << 20)) < int(part * (1 << 20)) + 1).orderBy(F.xxhash64("series_id"), "series_id").limit(sample).collect()
    x = np.array([r["values"] for r in rows]).reshape(-1, ix.n)
    share = 1 - delta ** (1 / total)
    out = []
    for s in q.summaries:
        d = np.sort(s.distances(x))
        at = int(np.floor(share * len(d)))
        out.append(float(d[at - 1]) if at >= 1 else 0.0)
    return out


#: Most bounds of all queries together that the driver computes; beyond it, each query's
#: leaves come from a descent of the tree that bounds what it reaches alone.
MAX_BOUNDS = 200_000_000
#: Leaves of a query that wait in order; more come by bounding all leaves again.
_WAITING = 1_000


class _Sorted:
    """A query's leaf ids by (bound, leaf id), its own leaf first; those that wait are kept."""

    def __init__(self, tree, query: QuerySummary, home: int | None, nodes: np.ndarray, leaf_ids: np.ndarray):
        self.tree, self.query, self.ids, self.home = tree, query, leaf_ids, home
        self.own = -1 if home is None else tree.leaf_id[home]
        self.bounds, self.order, self.at, self.more, self.last = np.zeros(0), leaf_ids[:0], 0, True, (-1.0, -1)

    def _fill(self, cut: float) -> None:
        """The next leaves below ``cut``; it only sinks, so others are not needed again."""
        b, (bound, leaf) = self.tree.bounds(self.query), self.last
        i = np.flatnonzero((b < cut) & ((b > bound) | (b == bound) & (self.ids > leaf)) & (self.ids != self.own))
        self.more = len(i) > _WAITING
        if self.more:
            i = i[b[i] <= np.partition(b[i], _WAITING - 1)[_WAITING - 1]]
        i = i[np.lexsort((self.ids[i], b[i]))]
        self.bounds, self.order, self.at = b[i], self.ids[i], 0
        if len(i):
            self.last = (b[i[-1]], self.ids[i[-1]])

    def next(self, cut: float) -> int | None:
        """The next leaf id whose bound is below ``cut``."""
        if self.home is not None:
            home, self.home = self.home, None
            if not np.isfinite(cut) or self.tree.bounds(self.query, [home])[0] < cut:
                return int(self.own)
        if self.at == len(self.order) and self.more:
            self._fill(cut)
        if self.at < len(self.order) and self.bounds[self.at] < cut:
            self.at += 1
            return int(self.order[self.at - 1])
        self.at, self.more = len(self.order), False
        return None


class _Nodes:
    """Children of the inner nodes that descents reach, as arrays that all queries of a search share."""

    def __init__(self, tree):
        self.tree, self.ids, self.kept = tree, np.array(tree.leaf_id, np.int64), {}

    def below(self, query: QuerySummary, node: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(children, their bounds, which are leaves)."""
        t = self.tree
        if node not in self.kept:
            kids = t.children(node)
            cells = [np.array([f[n] for n in kids], np.uint8).reshape(-1, t.w) for f in (t.pfx_bits, t.pfx_len)] if isinstance(t, WordTree) else None
            self.kept[node] = np.array(kids, np.int32), np.array([t.is_leaf(n) for n in kids], bool), cells
        kids, leaf, cells = self.kept[node]
        if cells is None:
            return kids, np.asarray(t.bounds(query, kids.tolist()), np.float64), leaf
        lo, hi = cells_rows(cells[0].astype(np.int64), cells[1])
        return kids, mindist_cells_rows(query.hi, query.lo, lo, hi, query.n), leaf


#: Leaves that a descent puts in order at a time, at first and at most; inner nodes that it opens at a time.
_READY, _OPENED = (16, 512), 16


class _Descent:
    """The same order from a frontier of nodes: what was not reached is never bounded, and what the cut rules out is
    not kept (it only sinks).  An inner node goes before leaves of its bound, so leaves of equal bounds come by their
    ids.  nodes: shared by the descents of a search; the frontier is two arrays each of inner nodes and of leaves."""

    def __init__(self, tree, query: QuerySummary, home: int | None, root: int = 0, nodes: _Nodes | None = None):
        self.tree, self.query, self.home, self.own = tree, query, home, home
        self.nodes, self.few = nodes or _Nodes(tree), _READY[0]
        some = int(len(tree) > 0 and root != home)
        start, none = (np.zeros(some), np.full(some, root, np.int32)), (np.zeros(0), np.zeros(0, np.int32))
        self.inner, self.leaves = (none, start) if some and tree.is_leaf(root) else (start, none)
        self.bounds, self.order, self.at = *none, 0

    def next(self, cut: float) -> int | None:
        node = self.next_node(cut)
        return None if node is None else int(self.tree.leaf_id[node])

    def next_node(self, cut: float) -> int | None:
        if self.home is not None:
            node, self.home = self.home, None
            if self.tree.bounds(self.query, [node])[0] < cut:
                return node
        if self.at == len(self.order):
            self._fill(cut)
        if self.at < len(self.order) and self.bounds[self.at] < cut:
            self.at += 1
            return int(self.order[self.at - 1])
        none = np.zeros(0), np.zeros(0, np.int32)
        self.inner = self.leaves = none
        self.bounds, self.order, self.at = *none, 0
        return None

    def _fill(self, cut: float) -> None:
        """The next leaves below ``cut`` in order: inner nodes are opened until none is as near as the last of them."""
        (ib, inner), (lb, leaves) = ((b[b < cut], n[b < cut]) for b, n in (self.inner, self.leaves))
        while len(inner):
            last = np.partition(lb, self.few - 1)[self.few - 1] if len(lb) >= self.few else np.inf
            at = np.flatnonzero(ib <= last)
            if not len(at):
                break
            if len(at) > _OPENED:
                at = at[np.argpartition(ib[at], _OPENED)[:_OPENED]]
            more_b, more_n, is_leaf = [], [], []
            for i in at:
                kids, b, leaf = self.nodes.below(self.query, int(inner[i]))
                b = np.maximum(b, ib[i])
                ok = (b < cut) & (kids != (-1 if self.own is None else self.own))
                more_b.append(b[ok])
                more_n.append(kids[ok])
                is_leaf.append(leaf[ok])
            b, n, leaf = (np.concatenate(v) for v in (more_b, more_n, is_leaf))
            ib, inner = np.append(np.delete(ib, at), b[~leaf]), np.append(np.delete(inner, at), n[~leaf])
            lb, leaves = np.append(lb, b[leaf]), np.append(leaves, n[leaf])
        first = np.flatnonzero(lb < ib.min()) if len(ib) else np.arange(len(lb))
        first = first[np.lexsort((self.nodes.ids[leaves[first]], lb[first]))][: self.few]
        self.bounds, self.order, self.at = lb[first], leaves[first], 0
        self.inner, self.leaves = (ib, inner), (np.delete(lb, first), np.delete(leaves, first))
        self.few = min(2 * self.few, _READY[1])


def _homes(tree, q: Queries) -> list[int]:
    """The leaf node of each query."""
    ends = tree.route(q.words) if isinstance(tree, WordTree) and len(q.ids) else [-1] * len(q.ids)
    counts, nodes = _leaf_counts(tree), _Nodes(tree)
    return [int(end) if end >= 0 and tree.is_leaf(end) and counts[end] else extended_leaves(tree, s, w, 1, counts, nodes)[0] for end, s, w in zip(ends, q.summaries, q.words)]


def _ways(tree, q: Queries) -> list:
    nodes, leaf_ids, *_ = tree.leaves()
    homes = _homes(tree, q) if len(nodes) else [None] * len(q.ids)
    if len(nodes) * len(q.ids) <= MAX_BOUNDS:
        return [_Sorted(tree, s, home, nodes, leaf_ids) for s, home in zip(q.summaries, homes)]
    shared = _Nodes(tree)
    return [_Descent(tree, s, home, nodes=shared) for s, home in zip(q.summaries, homes)]


#: From so many queries on, a wave reads nearly all files whatever its leaves are: waves grow by four.
MANY_QUERIES = 1_000


def search_progressive(ix: SeriesIndex, queries: DataFrame, k: int, metric: str = "ed", epsilon: float = 0.0, delta: float = 1.0, max_leaves: int | None = None, band: float = BAND, stats: SearchStats | None = None, first_wave: int | None = None) -> Iterator[DataFrame]:
    """Answers after each wave; the last one is final.

    A wave reads, for every query that is not done, the next leaves by lower bound whose
    bound can still beat its k-th best distance; waves double (many queries: grow by four).  A query is done when no
    such leaf is left, when its budget of leaves is used, or (delta < 1) when its k-th
    distance is within (1 + epsilon) times the radius that ``delta`` gives.
    """
    stats = stats if stats is not None else SearchStats()
    for q, best in _waves(ix, queries, k, metric, epsilon, delta, max_leaves, band, stats, first_wave):
        yield _answers(ix.spark, q, best)


def _waves(ix: SeriesIndex, queries: DataFrame, k: int, metric: str, epsilon: float, delta: float, max_leaves: int | None, band: float, stats: SearchStats, first_wave: int | None = None) -> Iterator[tuple[Queries, _Best]]:
    """(queries, best so far) after each wave of :func:`search_progressive`."""
    began = time.time()
    q = _prepared(ix, queries, metric, band)
    best, tree = _Best(len(q.ids), k), ix.tree
    ways = _ways(tree, q)
    for qid in q.ids:
        stats.leaves[qid] = stats.series[qid] = stats.computed[qid] = 0
    radius = delta_radius(ix, q, delta)
    done = [False] * len(q.ids)
    size = first_wave or 1
    while True:
        wanted: dict[int, list[int]] = {}
        far = np.array([best.bsf(at) for at in range(len(q.ids))], np.float64)
        for at, qid in enumerate(q.ids):
            if done[at]:
                continue
            bsf, taken = far[at], 0
            if delta < 1 and np.isfinite(bsf) and bsf <= (1 + epsilon) * radius[at] + SLACK:
                done[at] = True
                continue
            cut = bsf / (1 + epsilon) + SLACK
            while taken < size and (max_leaves is None or stats.leaves[qid] < max_leaves):
                leaf = ways[at].next(cut)
                if leaf is None:
                    break
                wanted.setdefault(leaf, []).append(at)
                stats.leaves[qid] += 1
                taken += 1
            done[at] = not taken
        if not wanted:
            break
        found, seen = _read(ix, q, wanted, far, k)
        best.take(found)
        for at, (read, made, spent) in seen.items():
            stats.series[q.ids[at]] += read
            stats.computed[q.ids[at]] += made
            stats.cpu_seconds += spent
        stats.waves += 1
        stats.seconds = time.time() - began
        size *= 4 if stats.waves == 1 or len(q.ids) >= MANY_QUERIES else 2
        yield q, best
    if stats.waves == 0:
        yield q, best


def _last(ix: SeriesIndex, *settings, stats: SearchStats | None) -> DataFrame:
    """The final answers alone: those before go to no table."""
    for q, best in _waves(ix, *settings, stats if stats is not None else SearchStats()):  # noqa: B007
        pass
    return _answers(ix.spark, q, best)


def search_exact(ix: SeriesIndex, queries: DataFrame, k: int, metric: str = "ed", epsilon: float = 0.0, delta: float = 1.0, band: float = BAND, stats: SearchStats | None = None) -> DataFrame:
    """Exact answers (epsilon 0, delta 1); else each distance is within (1 + epsilon) of the
    true one, with probability ``delta``."""
    return _last(ix, queries, k, metric, epsilon, delta, None, band, stats=stats)


def search_budget(ix: SeriesIndex, queries: DataFrame, k: int, max_leaves: int, metric: str = "ed", band: float = BAND, stats: SearchStats | None = None) -> DataFrame:
    """The best of at most ``max_leaves`` leaves in the order of their bounds (own leaf first)."""
    return _last(ix, queries, k, metric, 0.0, 1.0, max_leaves, band, stats=stats)


def search_radius(ix: SeriesIndex, queries: DataFrame, radius: float, metric: str = "ed", band: float = BAND) -> DataFrame:
    """(query_id, series_id, distance) of all series within ``radius``; results stay distributed."""
    q = _prepared(ix, queries, metric, band)
    wanted: dict[int, list[int]] = {}
    for at, way in enumerate(_ways(ix.tree, q)):
        while (leaf := way.next(radius + 2 * SLACK)) is not None:
            wanted.setdefault(leaf, []).append(at)
    shared, n = ix.spark.sparkContext.broadcast((q, wanted)), ix.n

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        q, wanted = shared.value
        for b in batches:
            leaf, ids, x = b.column(0).to_numpy(), b.column(1).to_numpy(), arrow.matrix_of(b.column(2), n)
            out = []
            for one in np.unique(leaf):
                rows = np.flatnonzero(leaf == one)
                for at in wanted.get(int(one), ()):
                    d = q.summaries[at].distances(x[rows], radius)
                    ok = d <= radius
                    out.append((q.ids[at], d[ok], ids[rows[ok]]))
            yield _batch(out)

    found = ix.data(sorted(wanted), ("leaf_id", "series_id", "values"), loose=True).mapInArrow(run, "query_id long, series_id long, distance double")
    return found.groupBy("query_id", "series_id").agg(F.min("distance").alias("distance"))
