"""Insertions, deletions, and re-organisation of subtrees.

Data files never change.  An insertion adds a segment; a re-organised subtree's rows are
written again under new leaf ids, and rows of leaf ids that the tree no longer has are void.
Deleted ids are a table that reads of older segments leave out.  Every change works on a
copy of the tree and is committed after its files are written, so a change that fails leaves
the handle as it was, and readers of the old version are not disturbed.
"""

from __future__ import annotations

import pickle
import threading
import time
import uuid
from collections.abc import Iterator
from dataclasses import replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.summaries import paa_rows, sax_rows
from . import arrow
from .build import _dyn_tree, _normal, border_copies, checked, grow_full, materialize, new_leaf, write_by_leaf
from .dynseg import DynTree
from .index import DATA_SCHEMA, SeriesIndex, new_segment
from .objective import fanout_range
from .pack import pack_leaves, pack_prefix
from .search import SearchStats, search_exact
from .sortedtree import SortedTree, sorted_tree
from .storage import written
from .tree import LEAF, PACK, WordTree


def _clone(tree):
    return pickle.loads(pickle.dumps(tree))


def _fresh_ids(tree: WordTree, nodes: list[int]) -> None:
    """New leaf ids after all that were ever used, so that old ids stay void."""
    tree.leaf_id += [-1] * (len(tree) - len(tree.leaf_id))
    for n in nodes:
        tree.last_leaf_id += 1
        tree.leaf_id[n] = tree.last_leaf_id
    tree._leaves = None


def _plain(p):
    """Rows read back are normalised already."""
    return replace(p, normalize=False)


def _add_up(tree, node: int, n: int) -> None:
    """``n`` more series at a node and at all above it."""
    while node >= 0:
        tree.size[node] += n
        node = tree.parent[node]


# ---- insertion --------------------------------------------------------------------------


def insert(ix: SeriesIndex, series: DataFrame, batch_id: int | None = None, stream: str = "") -> SeriesIndex:
    """Adds series; new cells get leaves, and with ``f`` > 0 the leaves on the other side of
    near borders get copies while they have room.  A batch id that was taken from the same
    stream before is not taken again."""
    if batch_id is not None and ix.was_taken(stream, batch_id):
        return ix
    good, _, _ = checked(series, ix.n)
    added = _insert_whole(ix, good, ix.params) if isinstance(ix.tree, (DynTree, SortedTree)) else _insert_words(ix, good, ix.params)
    ix.inserted += added
    if batch_id is not None:
        ix.take(stream, batch_id)
    return ix


def _insert_words(ix: SeriesIndex, good: DataFrame, p) -> int:
    """Series are normalised and routed once, into a staged table; returns their number."""
    t, n_points = _clone(ix.tree), ix.n
    shared = ix.spark.sparkContext.broadcast(ix.tree)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        old = shared.value
        for b in batches:
            x = _normal(b.column(1), n_points, p)
            w = sax_rows(paa_rows(x, p.w), p.bits)
            at, sid = old.route(w), np.full(len(w), -1, np.int64)
            for node in np.unique(at):
                if not old.is_leaf(int(node)):
                    sid[at == node] = old.sids(int(node), w[at == node])
            yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(sid), b.column(0), arrow.bytes_of(w), arrow.lists_of(x)], names=["node", "sid", "series_id", "word", "values"])

    staged = written(good.select("series_id", "values").mapInArrow(run, "node long, sid long, series_id long, word binary, values array<double>"), "insert")
    counts = sorted((r["node"], r["sid"], r["count"]) for r in staged.groupBy("node", "sid").count().collect())
    if not counts:
        return 0
    fresh: dict[tuple[int, int], int] = {}
    for node, sid, n in counts:
        if sid >= 0:
            fresh[node, sid] = new_leaf(t, node, sid, 0)
        _add_up(t, fresh.get((node, sid), node), n)
        t.oversize[node] = t.oversize[node] and all(k == p.bits for k in t.pfx_len[node])  # what comes may be unlike what is there
    _fresh_ids(t, list(fresh.values()))
    homes = ix.spark.sparkContext.broadcast((np.array(t.leaf_id, np.int64), {key: t.leaf_id[n] for key, n in fresh.items()}))

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, new = homes.value
        for b in batches:
            at, sid = b.column(0).to_numpy(), b.column(1).to_numpy()
            leaf = np.where(sid < 0, ids[at], -1)
            for i in np.flatnonzero(sid >= 0):
                leaf[i] = new[int(at[i]), int(sid[i])]
            yield pa.RecordBatch.from_arrays([pa.array(leaf), *b.columns[2:], pa.array(np.zeros(len(leaf), bool))], names=["leaf_id", "series_id", "word", "values", "is_copy"])

    rows = staged.mapInArrow(place, DATA_SCHEMA)
    if p.f > 0:
        copies = written(border_copies(staged.select("series_id", "word"), t, p, t.below(0)), "copies")
        _more_copies(t, copies)
        values = staged.select("series_id", "word", "values").dropDuplicates(["series_id"])
        rows = rows.unionByName(values.join(copies.select("series_id", "leaf_id"), "series_id").select("leaf_id", "series_id", "word", "values", F.lit(True).alias("is_copy")))
    path, total = new_segment(ix.spark), sum(n for *_, n in counts)
    write_by_leaf(rows, p, ix.n, total, path)
    ix.commit(t, path)
    return total


def _more_copies(tree: WordTree, copies: DataFrame) -> None:
    at = {leaf: n for n, leaf in enumerate(tree.leaf_id) if leaf >= 0 and tree.is_leaf(n)}
    for r in copies.groupBy("leaf_id").count().collect():
        tree.n_copies[at[r["leaf_id"]]] += r["count"]
    tree._leaves = None


def _insert_whole(ix: SeriesIndex, good: DataFrame, p) -> int:
    """Trees whose leaves take everything widen their summaries by what arrives."""
    path, tree = new_segment(ix.spark), _clone(ix.tree)
    materialize(good, tree, None, p, ix.n, path)
    rows = ix.spark.read.schema(DATA_SCHEMA).parquet(path)
    total = tree.add_words(rows, p.th) if isinstance(tree, SortedTree) else _widen(tree, rows, ix.n)
    if total:
        ix.commit(tree, path)
    return total


def _widen(tree: DynTree, rows: DataFrame, n_points: int) -> int:
    """Ranges of means and deviations, and sizes, from the leaves up to the root."""
    shared = rows.sparkSession.sparkContext.broadcast(tree)

    def run(batches):
        t = shared.value
        home = {leaf: n for n, leaf in enumerate(t.leaf_id) if leaf >= 0 and t.is_leaf(n)}
        for b in batches:
            x, leaf = arrow.matrix_of(b.column(1), n_points), b.column(0).to_numpy()
            out: list[tuple] = []
            for one in np.unique(leaf):
                node, mine = home[int(one)], x[leaf == one]
                while node >= 0:
                    for i, (lo, hi) in enumerate(zip(t.cuts[node][:-1], t.cuts[node][1:])):
                        m, d = mine[:, lo:hi].mean(1), mine[:, lo:hi].std(1)
                        out.append((node, i, len(mine), float(m.min()), float(m.max()), float(d.min()), float(d.max())))
                    node = t.parent[node]
            c = list(zip(*out)) or [()] * 7
            yield pa.RecordBatch.from_arrays([pa.array(v, pa.int64() if i < 3 else pa.float64()) for i, v in enumerate(c)], names=["node", "seg", "n", "m0", "m1", "d0", "d1"])

    wide = rows.select("leaf_id", "values").mapInArrow(run, "node long, seg long, n long, m0 double, m1 double, d0 double, d1 double")
    total = 0
    for r in wide.groupBy("node", "seg").agg(F.sum("n").alias("n"), F.min("m0").alias("m0"), F.max("m1").alias("m1"), F.min("d0").alias("d0"), F.max("d1").alias("d1")).collect():
        s = tree.synopsis[r["node"]][r["seg"]]
        tree.synopsis[r["node"]][r["seg"]] = (min(s[0], r["m0"]), max(s[1], r["m1"]), min(s[2], r["d0"]), max(s[3], r["d1"]))
        if r["seg"] == 0:
            tree.size[r["node"]] += r["n"]
            total += r["n"] if r["node"] == 0 else 0
    return total


# ---- deletion ---------------------------------------------------------------------------


def delete(ix: SeriesIndex, ids: DataFrame) -> SeriesIndex:
    """Marks series ids as deleted: reads leave out their rows of all segments so far.  What
    is inserted under the same ids later is seen.  Sizes follow."""
    gone = written(ids.select(F.col("series_id").cast("long")).where("series_id is not null").distinct(), "gone")
    hidden = ix.data(None, ("leaf_id", "series_id", "is_copy")).join(gone, "series_id", "left_semi")
    counts = hidden.groupBy("leaf_id").agg(F.count_if(~F.col("is_copy")).alias("n"), F.count_if("is_copy").alias("c")).collect()
    rows = gone.withColumn("until", F.lit(ix.clock).cast("long"))
    if ix.tombstones:
        before = ix.spark.read.schema("series_id long, until long").parquet(ix.tombstones)
        rows = rows.unionByName(before).groupBy("series_id").agg(F.max("until").alias("until"))
    path, tree = new_segment(ix.spark), _clone(ix.tree)
    rows.write.parquet(path)
    at = {leaf: n for n, leaf in enumerate(tree.leaf_id) if leaf >= 0}
    for r in counts:
        _add_up(tree, at[r["leaf_id"]], -r["n"])
        if r["c"]:
            tree.n_copies[at[r["leaf_id"]]] -= r["c"]
    tree._leaves = None
    ix.tree, ix.tombstones = tree, path
    ix.deleted += sum(r["n"] for r in counts)
    ix.touched()
    return ix


def _recount(ix: SeriesIndex, tree, rows: DataFrame) -> None:
    """Sizes of all nodes from rows of the data schema."""
    counts = {r["leaf_id"]: r for r in rows.groupBy("leaf_id").agg(F.count_if(~F.col("is_copy")).alias("n"), F.count_if("is_copy").alias("c")).collect()}
    for n in range(len(tree)):
        tree.size[n] = 0
    for n in tree.below(0):
        r = counts.get(tree.leaf_id[n])
        _add_up(tree, n, r["n"] if r else 0)
        if isinstance(tree, WordTree):
            tree.n_copies[n] = r["c"] if r else 0
    tree._leaves = None


def vacuum(ix: SeriesIndex) -> SeriesIndex:
    """Writes live rows alone into one segment, forgets deleted ids, frees leaves without any
    rows and takes them out of their parents' routes."""
    path, tree = new_segment(ix.spark), _clone(ix.tree)
    write_by_leaf(ix.data(), ix.params, ix.n, tree.size[0] if len(tree) else 0, path)
    _recount(ix, tree, ix.spark.read.schema(DATA_SCHEMA).parquet(path))
    if isinstance(tree, WordTree):
        for n in range(len(tree)):
            tree.routes[n] = {s: c for s, c in tree.routes[n].items() if not tree.is_leaf(c) or tree.size[c] + tree.n_copies[c] > 0}
        kept = set(tree.below(0))
        for n in range(len(tree)):
            if tree.is_leaf(n) and n not in kept:
                tree.leaf_id[n] = -1
    ix.commit(tree, path, replaces=True)
    return ix


# ---- re-organisation --------------------------------------------------------------------


def violations(ix: SeriesIndex) -> list[int]:
    """Topmost nodes whose fan-out no longer fits their size, and leaves over the capacity
    that could split; the root is exempt."""
    t, p, out, stack = ix.tree, ix.params, [], [0]
    if not isinstance(t, WordTree):
        return [n for n in range(len(t)) if t.is_leaf(n) and t.size[n] > p.th and not t.oversize[n]]
    while stack:
        node = stack.pop()
        for child in t.children(node):
            n = t.size[child] + t.n_copies[child]
            usable = sum(k < p.bits for k in t.pfx_len[child])
            if t.is_leaf(child):
                if n > p.th and usable and not t.oversize[child] and not 0 < p.levels <= t.depth[child]:
                    out.append(child)
            elif p.policy == "adaptive":
                low, high = fanout_range(max(n, 1), p.th, p.f_low, p.f_high, p.w)
                lam = len(t.csl[child])
                if low <= lam <= high:
                    stack.append(child)
                elif lam < low and n > p.th:
                    out.append(child)
                else:
                    stack.append(child)
            else:
                stack.append(child)
    return sorted(out)


def reorganize(ix: SeriesIndex) -> SeriesIndex:
    """Grows the violating subtrees again from their words: by rounds over the cluster while
    one is too large for a task, then one task each.  Packs that outgrew their capacity give
    their members back first (see :func:`extract`).  Copies of the new leaves are made anew."""
    if not isinstance(ix.tree, WordTree):
        return _rebuilt(ix)
    bad = violations(ix)
    if not bad:
        return ix
    t, p = _clone(ix.tree), ix.params
    retired, starts = [], []
    for node in bad:
        for leaf in t.below(node):
            retired.append(t.leaf_id[leaf])
            t.leaf_id[leaf] = -1
        if t.kind[node] == PACK and len(t.members[node]) > 1:
            starts += [new_leaf(t, t.parent[node], m, 0) for m in t.members[node]]
        else:
            t.routes[node], t.csl[node], t.kind[node] = {}, (), LEAF
            starts.append(node)
    natives = ix.data(retired).where("not is_copy")
    words = written(natives.select("series_id", "word"), "again")
    counts = _by_node(words, t)
    for n in starts:
        t.size[n], t.n_copies[n] = counts.get(n, 0), 0
        t.oversize[n] = t.size[n] > p.th
        if not t.size[n]:
            parent = t.parent[n]
            t.routes[parent] = {s: c for s, c in t.routes[parent].items() if c != n}
    full = [(n, f"again{n}") for n in starts if t.size[n] > p.th and any(k < p.bits for k in t.pfx_len[n])]
    grow_full(words, t, full, replace(p, f=0.0))
    fresh = [leaf for n in starts if t.size[n] for leaf in t.below(n)]
    for leaf in fresh:
        t.n_copies[leaf] = 0
    _fresh_ids(t, fresh)
    copies, carriers = None, None
    if p.f > 0:
        copies, carriers = _copies_again(ix, t, fresh, retired)
    path = new_segment(ix.spark)
    materialize(natives.select("series_id", "values"), t, copies, _plain(p), ix.n, path, carriers)
    _switch(ix, t, path)
    return ix


def _switch(ix: SeriesIndex, tree, path: str) -> None:
    """Commits rows that were live before: they count as born now, without a step of the
    clock, so ids that were deleted so far (none of them is here) stay deleted."""
    clock = ix.clock
    ix.commit(tree, path)
    ix.clock, ix.segments[-1] = clock, (path, clock)


def _by_node(words: DataFrame, tree: WordTree) -> dict[int, int]:
    shared, w = words.sparkSession.sparkContext.broadcast(tree), tree.w

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            node, n = np.unique(shared.value.route(arrow.words_from(b.column(0), w)), return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(node), pa.array(n)], names=["node", "n"])

    return {r["node"]: r["n"] for r in words.select("word").mapInArrow(run, "node long, n long").groupBy("node").agg(F.sum("n").alias("n")).collect()}


def _copies_again(ix: SeriesIndex, tree: WordTree, fresh: list[int], retired: list[int]) -> tuple[DataFrame, DataFrame]:
    """Copies that new leaves take of any series, beside those it keeps in other leaves, and the
    rows that hold their values."""
    rows = ix.data(None, ("leaf_id", "series_id", "word", "is_copy"))
    every = rows.where("not is_copy").select("series_id", "word")
    void = ix.spark.createDataFrame([(leaf,) for leaf in retired], "leaf_id long")
    held = rows.where("is_copy").join(void, "leaf_id", "left_anti").groupBy("series_id").agg(F.count(F.lit(1)).alias("had"))
    copies = written(border_copies(every, tree, ix.params, fresh, held), "copies")
    _more_copies(tree, copies)
    new = {tree.leaf_id[n] for n in fresh}
    homes = {r["home"] for r in copies.select("home").distinct().collect()}
    leaves = sorted((homes - new) | (set(retired) if homes & new else set()))
    return copies, ix.data(leaves or [-1]).where("not is_copy")


def _rebuilt(ix: SeriesIndex) -> SeriesIndex:
    """Trees of other kinds are grown again as a whole when a leaf is over capacity."""
    if not violations(ix):
        return ix
    live = ix.data()
    if isinstance(ix.tree, SortedTree):
        tree = sorted_tree(written(live.select("series_id", "word"), "again"), ix.params)
    else:
        tree = _dyn_tree(live.select("series_id", "values"), _plain(ix.params), ix.n)
    path = new_segment(ix.spark)
    materialize(live.select("series_id", "values"), tree, None, _plain(ix.params), ix.n, path)
    ix.commit(tree, path, replaces=True)
    return ix


class Reorganization:
    """A re-organisation beside the index, which goes on taking insertions and deletions.

    It works on a copy of the handle; :meth:`finish` waits for it, gives the copy what the
    index took meanwhile, and then switches the index to it.
    """

    def __init__(self, ix: SeriesIndex):
        self.ix, self.work, self.error = ix, ix.copy(), None
        self.known, self.tombstones = list(ix.segments), ix.tombstones
        self.thread = threading.Thread(target=self._run, daemon=True)
        self.thread.start()

    def _run(self) -> None:
        try:
            reorganize(self.work)
        except Exception as e:  # handed to the caller of finish()
            self.error = e

    def finish(self) -> SeriesIndex:
        self.thread.join()
        if self.error is not None:
            raise self.error
        ix, work = self.ix, self.work
        if ix.segments[: len(self.known)] != self.known:
            raise RuntimeError("the index was rewritten meanwhile: reorganize it again")
        p = _plain(ix.params)
        for path, born in ix.segments[len(self.known) :]:
            rows = ix.spark.read.schema(DATA_SCHEMA).parquet(path).where("not is_copy").select("series_id", "values")
            work.clock = born - 1
            _insert_words(work, rows, p) if isinstance(work.tree, WordTree) else _insert_whole(work, rows, p)
        work.tombstones, work.clock = ix.tombstones, ix.clock
        if ix.tombstones != self.tombstones:
            _recount(work, work.tree, work.data(None, ("leaf_id", "series_id", "is_copy")))
        ix.tree, ix.segments = work.tree, work.segments
        ix.touched()
        return ix


# ---- packs ------------------------------------------------------------------------------


def _member_sids(rows: DataFrame, tree: WordTree, node: int) -> DataFrame:
    """(sid, series_id, values): which cell of the node's split each row lies in."""
    shared, w = rows.sparkSession.sparkContext.broadcast((tree.csl[node], tree.pfx_bits[node], tree.pfx_len[node], tree.bits)), tree.w

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        csl, bits, lens, full = shared.value
        probe = WordTree(w, full)
        probe.add(-1, LEAF, bits, lens, 0)
        probe.csl[0] = csl
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array(probe.sids(0, arrow.words_from(b.column(0), w)))], names=["sid"])

    return rows.select("word").mapInArrow(run, "sid long")


def extract(ix: SeriesIndex, pack: int, sid: int) -> SeriesIndex:
    """Takes one member out of a pack into a leaf of its own."""
    t, p = _clone(ix.tree), ix.params
    parent, old = t.parent[pack], t.leaf_id[pack]
    members = [m for m in t.members[pack] if m != sid]
    if sid not in t.members[pack] or not members:
        return ix
    rows = ix.data([old]).where("not is_copy")
    count = _member_sids(rows, t, parent).where(F.col("sid") == sid).count()
    bits, lens = pack_prefix(t.pfx_bits[parent], t.pfx_len[parent], t.csl[parent], members)
    t.members[pack], t.pfx_bits[pack], t.pfx_len[pack] = tuple(members), tuple(bits), tuple(lens)
    t.size[pack] -= count
    t.n_copies[pack] = 0
    t.kind[pack] = PACK if len(members) > 1 else LEAF
    leaf = new_leaf(t, parent, sid, count)
    _fresh_ids(t, [pack, leaf])
    return _rewritten(ix, t, rows, [pack, leaf], [old])


def _rewritten(ix: SeriesIndex, tree: WordTree, rows: DataFrame, fresh: list[int], retired: list[int]) -> SeriesIndex:
    copies, carriers = _copies_again(ix, tree, fresh, retired) if ix.params.f > 0 else (None, None)
    path = new_segment(ix.spark)
    materialize(rows.select("series_id", "values"), tree, copies, _plain(ix.params), ix.n, path, carriers)
    _switch(ix, tree, path)
    return ix


def repack(ix: SeriesIndex, node: int) -> SeriesIndex:
    """Packs the small leaf children of a node anew, member by member."""
    t, p = _clone(ix.tree), ix.params
    small = [c for c in t.children(node) if t.is_leaf(c) and t.size[c] <= p.th]
    if len(small) < 2:
        return ix
    old = [t.leaf_id[c] for c in small]
    rows = ix.data(old).where("not is_copy")
    sizes = {r["sid"]: r["count"] for r in _member_sids(rows, t, node).groupBy("sid").count().collect()}
    for c in small:
        t.leaf_id[c] = -1
        for s in [s for s, x in t.routes[node].items() if x == c]:
            del t.routes[node][s]
    fresh = []
    for g in pack_leaves(sizes, len(t.csl[node]), p.th, p.rho, p.r, p.seed, f"repack{node}"):
        b, k = pack_prefix(t.pfx_bits[node], t.pfx_len[node], t.csl[node], g)
        child = t.add(node, PACK if len(g) > 1 else LEAF, b, k, sum(sizes[s] for s in g), g)
        fresh.append(child)
        for s in g:
            t.routes[node][s] = child
    _fresh_ids(t, fresh)
    return _rewritten(ix, t, rows, fresh, old)


def run_mixed(ix: SeriesIndex, batches: list[DataFrame], queries: DataFrame, k: int, metric: str = "ed", rebuild: bool = True, stream: str | None = None) -> list[dict]:
    """Batches of insertions with exact queries in between; one row of costs for each batch.
    Every call is a stream of its own unless ``stream`` names one."""
    out, stream = [], stream or f"mixed-{uuid.uuid4().hex}"
    for i, batch in enumerate(batches):
        began = time.time()
        insert(ix, batch, i, stream)
        if rebuild:
            reorganize(ix)
        wrote, stats = time.time() - began, SearchStats()
        search_exact(ix, queries, k, metric, stats=stats)
        out.append({"batch": i, "insert_s": wrote, "query_s": stats.seconds, "leaves_read": sum(stats.leaves.values()), "series": ix.tree.size[0] if len(ix.tree) else 0})
    return out
