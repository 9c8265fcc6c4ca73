"""Bulk build: words, root, subtrees, packs and numbers, then one shuffle of the series.

Splits are decided from words alone.  Nodes too large for one task are split by aggregates
over the cluster (counts of next bits, sums of midpoints), round by round; once every node
fits a task, one shuffle of the words brings each subtree's words together and grows it
whole.  Series are read a second time to be written by leaf; they are shuffled once.
"""

from __future__ import annotations

import pickle
import time
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.summaries import midpoints, paa_rows, sax_rows, znormalize_rows
from . import arrow
from .dynseg import DynTree, grow_dynseg
from .index import SeriesIndex, new_segment
from .objective import SearchCost
from .pack import pack_prefix
from .params import BuildParams
from .sortedtree import sorted_tree
from .storage import own_shuffles_go, scratch, scratched, written
from .tree import INTERNAL, LEAF, PACK, ROOT, WordTree, border_gaps, decide, groups_of, grow


#: Most bytes of raw values from which one task grows a tree of dynamic segmentations.
DYN_BYTES = 256 << 20


def checked(series: DataFrame, n: int | None = None) -> tuple[DataFrame, DataFrame, int]:
    """(good, rejected, n): rows of another length, with nulls or NaN, or without an id go to
    the side output.  n is the first row's length where it isn't given."""
    if n is None:
        first = series.where("series_id is not null and size(values) > 0").select(F.size("values")).first()
        n = first[0] if first else 0
    ok = F.col("series_id").isNotNull() & F.col("values").isNotNull() & (F.size("values") == n) & ~F.exists("values", lambda v: v.isNull() | F.isnan(v))
    good = F.coalesce(ok, F.lit(False))
    values = F.transform("values", lambda v: v.cast("double")).alias("values")
    return series.where(good).select("series_id", values), series.where(~good), n


def _normal(column: pa.Array, n: int, p: BuildParams) -> np.ndarray:
    x = arrow.matrix_of(column, n)
    return znormalize_rows(x) if p.normalize else x


def words_of(series: DataFrame, p: BuildParams, n: int) -> DataFrame:
    """(series_id, word, cell): the words table, and each word's root cell (its symbols' first bits)."""
    top = 1 << np.arange(p.w - 1, -1, -1, dtype=np.int64)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            words = sax_rows(paa_rows(_normal(b.column(1), n, p), p.w), p.bits)
            yield pa.RecordBatch.from_arrays([b.column(0), arrow.bytes_of(words), pa.array((words >> (p.bits - 1)).astype(np.int64) @ top)], names=["series_id", "word", "cell"])

    return series.select("series_id", "values").mapInArrow(run, "series_id long, word binary, cell long")


def _attach(tree: WordTree, node: int, counts: dict[int, int], p: BuildParams, label: str) -> list[tuple[int, str]]:
    """Children of a node whose plan is set, from their sizes: packs of the small ones, and
    the full ones, which are returned with their labels."""
    csl, bits, lens = tree.csl[node], tree.pfx_bits[node], tree.pfx_len[node]
    full = []
    for s in sorted(s for s in counts if counts[s] > p.th):
        b, k = pack_prefix(bits, lens, csl, [s])
        child = tree.add(node, INTERNAL, b, k, counts[s], (s,))
        tree.routes[node][s] = child
        full.append((child, f"{label}.{s}"))
    small = {s: n for s, n in counts.items() if n <= p.th}
    for g in groups_of(p, small, len(csl), label) if small else []:
        b, k = pack_prefix(bits, lens, csl, g)
        child = tree.add(node, PACK if len(g) > 1 else LEAF, b, k, sum(small[s] for s in g), g)
        for s in g:
            tree.routes[node][s] = child
    return full


def root_tree(words: DataFrame, p: BuildParams) -> tuple[WordTree, list[tuple[int, str]]]:
    """The root, split on all segments; at most 2 ** w counts reach the driver."""
    tree = WordTree(p.w, p.bits)
    cells = {r["cell"]: r["n"] for r in words.groupBy("cell").agg(F.count(F.lit(1)).alias("n")).collect()}
    tree.add(-1, ROOT, [0] * p.w, [0] * p.w, sum(cells.values()))
    tree.csl[0] = tuple(range(p.w)) if cells else ()
    return tree, _attach(tree, 0, cells, p, "") if cells else []


def split_round(words: DataFrame, tree: WordTree, big: list[tuple[int, str]], p: BuildParams) -> list[tuple[int, str]]:
    """Splits nodes too large for a task by aggregates over all their words; returns their full
    children.  A node's counts (at most 2 ** w) meet in one task, which decides; only its plan
    and the sizes of its children reach the driver."""
    shared = words.sparkSession.sparkContext.broadcast(tree)
    wanted = np.array([n for n, _ in big])
    cells = words.sparkSession.sparkContext.broadcast({n: (tree.pfx_bits[n], tree.pfx_len[n]) for n, _ in big})
    names = [f"{x}{i}" for x in "sq" for i in range(p.w)]

    def counted(rows: DataFrame) -> DataFrame:
        return rows.mapInArrow(run, schema).groupBy("node", "sid").agg(F.sum("n").alias("n"), *[F.sum(x).alias(x) for x in names])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t, mids = shared.value, midpoints(p.bits)
        for b in batches:
            words = arrow.words_from(b.column(0), p.w)
            at = t.route(words)
            rows = []
            for node in wanted[np.isin(wanted, at)]:
                mine = words[at == node]
                usable = [s for s in range(p.w) if t.pfx_len[node][s] < p.bits]
                m = mids[mine]
                rows.append((int(node), -1, len(mine), *m.sum(0), *(m * m).sum(0)))
                probe = WordTree(p.w, p.bits)
                probe.add(-1, INTERNAL, t.pfx_bits[node], t.pfx_len[node], 0)
                probe.csl[0] = tuple(usable)
                for sid, n in zip(*np.unique(probe.sids(0, mine), return_counts=True)):
                    rows.append((int(node), int(sid), int(n), *[0.0] * (2 * p.w)))
            cols = list(zip(*rows)) or [()] * (3 + 2 * p.w)
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64() if i < 3 else pa.float64()) for i, c in enumerate(cols)], names=["node", "sid", "n", *names])

    def routed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array(shared.value.route(arrow.words_from(b.column(1), p.w))), *b.columns], names=["node", "series_id", "word"])

    def choose(key, pdf):
        import pandas as pd

        bits, lens = cells.value[int(key[0])]
        usable = tuple(s for s in range(p.w) if lens[s] < p.bits)
        first = pdf[pdf["first"]] if p.when == "just_full" else pdf
        sums = first[first["sid"] == -1].iloc[0]
        mean = np.array([sums[f"s{s}"] / sums["n"] for s in usable])
        var = np.maximum(np.array([sums[f"q{s}"] / sums["n"] for s in usable]) - mean * mean, 0.0)

        def base(of):
            out, own = np.zeros(1 << len(usable), np.int64), of[of["sid"] >= 0]
            out[own["sid"].to_numpy()] = own["n"].to_numpy()
            return out

        plan = decide(int(sums["n"]), mean, var, lambda: base(first), bits, lens, usable, p)
        every = base(pdf[~pdf["first"]])
        lacking = tuple(i for i, s in enumerate(usable) if s not in plan)
        counts = every.reshape((2,) * len(usable)).sum(axis=lacking).reshape(-1)
        sids = np.flatnonzero(counts)
        return pd.DataFrame({"node": [int(key[0])], "plan": [list(plan)], "sids": [sids.tolist()], "sizes": [counts[sids].tolist()]})

    schema = "node long, sid long, n long, " + ", ".join(f"{x} double" for x in names)
    rows = counted(words.select("word")).withColumn("first", F.lit(False))
    if p.when == "just_full":  # decided from the first th + 1 series of a node, counted over all
        order = F.row_number().over(Window.partitionBy("node").orderBy("series_id"))
        early = words.select("series_id", "word").mapInArrow(routed, "node long, series_id long, word binary").where(F.col("node").isin(wanted.tolist())).withColumn("i", order).where(F.col("i") <= p.th + 1)
        rows = rows.unionByName(counted(early.select("word")).withColumn("first", F.lit(True)))
    chosen = {r["node"]: r for r in rows.groupBy("node").applyInPandas(choose, "node long, plan array<int>, sids array<long>, sizes array<long>").collect()}
    out = []
    for node, label in big:
        tree.csl[node] = tuple(chosen[node]["plan"])
        out += _attach(tree, node, dict(zip(chosen[node]["sids"], chosen[node]["sizes"])), p, label)
    return out


def _walk_copies(words: DataFrame, tree: WordTree, p: BuildParams, only: set[int] | None = None) -> DataFrame:
    """Rows for the nodes that the driver's tree ends in: every series once as itself, and
    copies across the borders of that tree's own splits, nearest and highest first.  Copies
    to other ends than ``only`` are counted and left out."""
    shared = words.sparkSession.sparkContext.broadcast(tree)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = shared.value
        for b in batches:
            ids, w = b.column(0).to_numpy(zero_copy_only=False), arrow.words_from(b.column(1), p.w)
            ends, used = t.route(w), np.zeros(len(w), np.int64)
            rows: list[tuple] = []
            level = [(0, np.arange(len(w)))]
            while level and p.f > 0:
                node, at = level.pop(0)
                if t.is_leaf(node):
                    continue
                sid, lam = t.sids(node, w[at]), len(t.csl[node])
                gaps = border_gaps(w[at], t.pfx_bits[node], t.pfx_len[node], t.csl[node], sid, p)
                for gap, i, j in sorted((gaps[i, j], i, j) for i, j in zip(*np.nonzero(np.isfinite(gaps)))):
                    to = t.routes[node].get(int(sid[i]) ^ (1 << (lam - 1 - j)))
                    if to is None or to == t.routes[node].get(int(sid[i])) or used[at[i]] >= p.max_copies:
                        continue
                    used[at[i]] += 1
                    end = to
                    while not t.is_leaf(end):  # a copy goes on by its nearest cells
                        nxt = t.routes[end].get(int(t.sids(end, w[at[i]][None])[0]))
                        if nxt is None:
                            break
                        end = nxt
                    if t.is_leaf(end) and (only is None or end in only):
                        rows.append((end, int(ids[at[i]]), w[at[i]].tobytes(), True, float(gap), t.depth[node]))
                for s in np.unique(sid):
                    if (child := t.routes[node].get(int(s))) is not None:
                        level.append((child, at[sid == s]))
            natives = pa.RecordBatch.from_arrays([pa.array(ends), b.column(0), b.column(1), pa.array(np.zeros(len(w), bool)), pa.array(np.zeros(len(w))), pa.array(used.astype(np.int32))], names=["start", "series_id", "word", "is_copy", "gap", "used"])
            yield natives
            if rows:
                c = list(zip(*rows))
                yield pa.RecordBatch.from_arrays([pa.array(c[0], pa.int64()), pa.array(c[1], pa.int64()), pa.array(c[2], pa.binary()), pa.array(c[3], pa.bool_()), pa.array(c[4], pa.float64()), pa.array(c[5], pa.int32())], names=["start", "series_id", "word", "is_copy", "gap", "used"])

    return words.select("series_id", "word").mapInArrow(run, "start long, series_id long, word binary, is_copy boolean, gap double, used int")


def local_subtrees(placed: DataFrame, tree: WordTree, full: list[tuple[int, str]], p: BuildParams) -> DataFrame:
    """One row with the pickled subtree for each full node, and one for each copy made inside it."""
    shared = placed.sparkSession.sparkContext.broadcast({n: (tree.pfx_bits[n], tree.pfx_len[n], label, tree.depth[n]) for n, label in full})

    def run(key, table):
        start = key[0].as_py()
        bits, lens, label, above = shared.value[start]
        ids, copy, used = (table.column(c).to_numpy() for c in ("series_id", "is_copy", "used"))
        order = np.lexsort((copy, ids))
        order = order[np.append(True, np.diff(ids[order]) != 0)]  # one row a series, itself before its copies
        words, ids, copy, used = arrow.words_from(table.column("word").combine_chunks(), p.w)[order], ids[order], copy[order].astype(bool), used[order]
        cost = SearchCost()
        sub, at_leaf, copies = grow(words, ~copy, np.where(copy, p.max_copies, used).astype(np.int64), bits, lens, p, label, cost, above)
        guests = [(int(ids[i]), int(at_leaf[i])) for i in np.flatnonzero(copy)] + [(int(ids[i]), leaf) for i, leaf in copies]
        sub.guests_in = {}
        for _, leaf in guests:
            sub.guests_in[leaf] = sub.guests_in.get(leaf, 0) + 1
        sub.cost = (cost.plans_scored, cost.cells_touched)
        out = [(start, pickle.dumps(sub), None, None)] + [(start, None, i, leaf) for i, leaf in guests]
        return pa.table([pa.array(c, k) for c, k in zip(zip(*out), (pa.int64(), pa.binary(), pa.int64(), pa.int64()))], names=["start", "tree", "series_id", "leaf"])

    wanted = F.broadcast(placed.sparkSession.createDataFrame([(n,) for n, _ in full], "start long"))
    return placed.join(wanted, "start", "left_semi").groupBy("start").applyInArrow(run, "start long, tree binary, series_id long, leaf long")


def grow_full(words: DataFrame, tree: WordTree, full: list[tuple[int, str]], p: BuildParams) -> tuple[dict[int, list[int]], DataFrame | None, DataFrame, dict]:
    """Grows the subtrees of full nodes into ``tree``: by rounds over the cluster while a node
    is too large for a task, then one task each.  words: those that lead to these nodes or to
    other ends of the tree.

    Returns (new numbers of each subtree's nodes, copies made inside them as (start,
    series_id, leaf), where series lie in the driver's tree, counters).
    """
    counters = {"rounds": 0, "plans_scored": 0, "cells_touched": 0}
    open_ = lambda n: not 0 < p.levels <= tree.depth[n]
    while big := [(n, label) for n, label in full if tree.size[n] > p.local_limit and open_(n) and any(k < p.bits for k in tree.pfx_len[n])]:
        full = [x for x in full if x not in big] + split_round(words, tree, big, p)
        counters["rounds"] += 1
    placed = _walk_copies(words, tree, p)
    if p.f > 0:
        placed = written(placed, "placed")
    numbers: dict[int, list[int]] = {}
    for n in (n for n, _ in full if not open_(n)):
        tree.kind[n], tree.oversize[n], numbers[n] = LEAF, True, [n]
    full = [x for x in full if open_(x[0])]
    if not full:
        return numbers, None, placed, counters
    grown = written(local_subtrees(placed, tree, full, p), "subtrees")
    # by one partition at a time: all pickled subtrees together are several times the tree
    for r in grown.where("tree is not null").select("start", "tree").toLocalIterator():
        sub = pickle.loads(bytes(r["tree"]))
        counters["plans_scored"] += sub.cost[0]
        counters["cells_touched"] += sub.cost[1]
        if len(sub) == 1:  # words of equal bits: an oversize leaf
            tree.kind[r["start"]], tree.oversize[r["start"]] = LEAF, sub.oversize[0]
            numbers[r["start"]] = [r["start"]]
        else:
            numbers[r["start"]] = tree.graft(r["start"], sub)
        for leaf, n in sub.guests_in.items():
            tree.n_copies[numbers[r["start"]][leaf]] = n
    return numbers, grown.where("series_id is not null").select("start", "series_id", "leaf"), placed, counters


def _nearest(copies: DataFrame, tree: WordTree, ends: list[int], p: BuildParams) -> DataFrame:
    """(series_id, leaf_id, home): copies (start, series_id, gap, home) that the leaf nodes
    ``ends`` have room for, nearest first."""
    room = copies.sparkSession.createDataFrame([(n, int(tree.leaf_id[n]), int(p.th - tree.size[n] - tree.n_copies[n])) for n in ends], "start long, leaf_id long, room long")
    order = F.row_number().over(Window.partitionBy("start").orderBy("gap", "series_id"))
    near = copies.dropDuplicates(["start", "series_id"]).join(room.where("room > 0"), "start").withColumn("i", order)
    return near.where(F.col("i") <= p.th).where("i <= room").select("series_id", "leaf_id", "home")


def border_copies(words: DataFrame, tree: WordTree, p: BuildParams, ends: list[int], held: DataFrame | None = None) -> DataFrame:
    """(series_id, leaf_id, home): copies that the leaf nodes ``ends`` take of the series in
    ``words`` across borders of any split of the tree; home: the series' own leaf id.  held:
    (series_id, had) of copies that series have in other leaves; those count too."""
    ids = np.array(tree.leaf_id, np.int64)
    placed = _walk_copies(words, tree, p, set(ends)).where("is_copy")
    shared = words.sparkSession.sparkContext.broadcast((tree, ids))

    def homes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t, ids = shared.value
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), b.column(2), pa.array(ids[t.route(arrow.words_from(b.column(3), p.w))])], names=["start", "series_id", "gap", "home"])

    near = placed.select("start", "series_id", "gap", "word").mapInArrow(homes, "start long, series_id long, gap double, home long")
    if held is not None:
        turn = F.row_number().over(Window.partitionBy("series_id").orderBy("gap", "start"))
        near = near.dropDuplicates(["start", "series_id"]).join(held, "series_id", "left").withColumn("turn", turn)
        near = near.where(F.col("turn") + F.coalesce("had", F.lit(0)) <= p.max_copies).drop("turn", "had")
    return _nearest(near, tree, ends, p)


def build_tree(words: DataFrame, p: BuildParams) -> tuple[WordTree, DataFrame | None, dict]:
    """(tree with numbered leaves, copies as (series_id, leaf_id) or None, counters)."""
    spark = words.sparkSession
    tree, full = root_tree(words, p)
    numbers, inside, placed, counters = grow_full(words, tree, full, p)
    tree.number_leaves()
    if p.f <= 0:
        return tree, None, counters
    flat = [(s, i, tree.leaf_id[n]) for s, ns in numbers.items() for i, n in enumerate(ns) if tree.is_leaf(n)]
    named = spark.createDataFrame(flat, "start long, leaf long, leaf_id long") if flat else None
    copies = _leaves_of_copies(inside, named) if named is not None else spark.createDataFrame([], "series_id long, leaf_id long")
    # leaves of the driver's tree take copies, nearest first, while they have room
    grafted = {n for ns in numbers.values() for n in ns}
    ends = [n for n in range(len(tree)) if tree.is_leaf(n) and tree.leaf_id[n] >= 0 and n not in grafted]
    if ends:
        direct = _nearest(placed.where("is_copy").withColumn("home", F.lit(-1).cast("long")), tree, ends, p)
        copies = copies.unionByName(direct.select("series_id", "leaf_id"))
    copies = written(copies.distinct(), "copies")
    count_copies(tree, copies)
    return tree, copies, counters


def _leaves_of_copies(inside: DataFrame, named: DataFrame) -> DataFrame:
    """(series_id, leaf_id) of copies made inside subtrees.  Both sides are sorted: copies are one
    part of the file of subtrees, whose size says little about them."""
    return inside.join(named.hint("merge"), ["start", "leaf"]).select("series_id", "leaf_id")


#: Copies that may be sent to every task; the compressed size of their file is far below that in memory.
SENT_COPIES = 100_000


def _copied(rows: DataFrame, copies: DataFrame, count: int) -> DataFrame:
    """The rows of ``count`` copies (series_id, leaf_id)."""
    copies = copies.select("series_id", "leaf_id")
    joined = rows.drop("leaf_id", "is_copy").join(copies.hint("merge") if count > SENT_COPIES else copies, "series_id")
    return joined.select("leaf_id", "series_id", "word", "values", F.lit(True).alias("is_copy"))


def count_copies(tree: WordTree, copies: DataFrame) -> None:
    """Numbers of copies of the leaves that ``copies`` (series_id, leaf_id) are all of."""
    at = {leaf: n for n, leaf in enumerate(tree.leaf_id) if leaf >= 0 and tree.is_leaf(n)}
    for r in copies.groupBy("leaf_id").count().collect():
        tree.n_copies[at[r["leaf_id"]]] = r["count"]
    tree._leaves = None


def write_by_leaf(rows: DataFrame, p: BuildParams, n: int, count: int, path: str) -> None:
    """Rows of the data schema, range-partitioned and sorted by leaf: one shuffle.  Files hold
    at most about ``pack_bytes``; a leaf of many copies is spread by series id."""
    files = -(-count * (8 * n + p.w + 17) // p.pack_bytes)
    more = files > int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    by = rows.repartitionByRange(files, "leaf_id", "series_id") if more else rows.repartitionByRange("leaf_id", "series_id")
    with own_shuffles_go(rows.sparkSession):
        by.sortWithinPartitions("leaf_id", "series_id").write.option("parquet.block.size", str(min(p.pack_bytes, 128 << 20))).parquet(path)


def materialize(series: DataFrame, tree, copies: DataFrame | None, p: BuildParams, n: int, path: str, carriers: DataFrame | None = None) -> None:
    """Series with word and leaf: one shuffle of the raw data.  copies: (series_id, leaf_id);
    their values are those of ``carriers`` (by default of ``series``)."""
    shared = series.sparkSession.sparkContext.broadcast(tree)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = shared.value
        ids = np.array(t.leaf_id, np.int64)
        for b in batches:
            x = _normal(b.column(1), n, p)
            words = sax_rows(paa_rows(x, p.w), p.bits)
            at = t.route_values(x) if isinstance(t, DynTree) else t.route(words)
            yield pa.RecordBatch.from_arrays([pa.array(ids[at]), b.column(0), arrow.bytes_of(words), arrow.lists_of(x), pa.array(np.zeros(len(x), bool))], names=["leaf_id", "series_id", "word", "values", "is_copy"])

    schema = "leaf_id long, series_id long, word binary, values array<double>, is_copy boolean"
    rows = series.select("series_id", "values").mapInArrow(run, schema)
    if copies is not None:
        of = rows if carriers is None else carriers.select("series_id", "values").mapInArrow(run, schema)
        rows = rows.unionByName(_copied(of, copies, sum(tree.n_copies)))
    write_by_leaf(rows, p, n, tree.size[0] if len(tree) else 0, path)


def _dyn_tree(series: DataFrame, p: BuildParams, n: int) -> DynTree:
    """One task grows it while the collection fits (``local_limit`` series and ``DYN_BYTES`` of
    values); larger collections are first cut at quantiles of their first segments' means."""
    total = series.count()
    parts = max(1, -(-total // max(1, min(p.local_limit, DYN_BYTES // (8 * n)))))
    first = F.aggregate(F.slice("values", 1, max(1, n // 4)), F.lit(0.0), lambda a, v: a + v) / max(1, n // 4)
    keyed = series.select("series_id", "values")
    if p.normalize:
        def normal(batches):
            for b in batches:
                yield pa.RecordBatch.from_arrays([b.column(0), arrow.lists_of(znormalize_rows(arrow.matrix_of(b.column(1), n)))], names=["series_id", "values"])

        keyed = keyed.mapInArrow(normal, "series_id long, values array<double>")
    keyed = keyed.withColumn("m", first)
    cuts = sorted(set(keyed.approxQuantile("m", [i / parts for i in range(1, parts)], 0.001))) if parts > 1 else []
    part = sum((F.when(F.col("m") > c, 1).otherwise(0) for c in cuts), F.lit(0))

    def run(key, pdf):
        import pandas as pd

        pdf = pdf.sort_values("series_id")
        tree, _ = grow_dynseg(np.stack(pdf["values"].to_numpy()), p)
        return pd.DataFrame({"part": [key[0]], "tree": [pickle.dumps(tree)]})

    rows = {r["part"]: pickle.loads(bytes(r["tree"])) for r in keyed.withColumn("part", part).groupBy("part").applyInPandas(run, "part int, tree binary").collect()}
    if not rows:
        tree = DynTree(n)
        return tree
    if len(rows) == 1:
        return next(iter(rows.values()))
    return _chained(rows, cuts, n)


def _chained(rows: dict[int, DynTree], cuts: list[float], n: int) -> DynTree:
    """Trees of the parts under a balanced tree of the cuts between them."""
    out = DynTree(n)
    width = max(1, n // 4)

    def place(parts: list[int], parent: int) -> int:
        if len(parts) == 1:
            sub = rows[parts[0]]
            base = len(out)
            for i in range(len(sub)):
                out.add(base + sub.parent[i] if i else parent, sub.cuts[i], sub.size[i], sub.synopsis[i])
                out.rule[-1], out.kids[-1], out.oversize[-1] = sub.rule[i], tuple(base + c for c in sub.kids[i]), sub.oversize[i]
            return base
        half = len(parts) // 2
        node = out.add(parent, (0, width, n), sum(rows[x].size[0] for x in parts), np.array([[-1e9, 1e9, 0.0, 1e9]] * 2))
        out.rule[node] = (0, width, 0, cuts[parts[half] - 1])
        out.kids[node] = (place(parts[:half], node), place(parts[half:], node))
        return node

    place(sorted(rows), -1)
    out.number_leaves()
    return out


def build_index(series: DataFrame, params: BuildParams = BuildParams(), path: str | None = None, data: bool = True) -> SeriesIndex:
    """The index over (series_id, values).  Bad rows are left out (see :func:`checked`).

    ``data`` False: the same tree over all series without their files, to be measured but not
    searched.  Tables that only the build reads go when it ends.
    """
    spark = series.sparkSession
    good, _, n = checked(series)
    if n == 0:
        raise ValueError("no series")
    clock, timings = time.time(), {}

    def lap(name):
        nonlocal clock
        timings[name], clock = time.time() - clock, time.time()

    path = path or scratched(new_segment(spark))
    counters: dict = {}
    with scratch(spark):
        if params.policy == "dynseg":
            tree, copies = _dyn_tree(good, params, n), None
            lap("tree")
        elif params.packing == "sorted":
            tree, copies = sorted_tree(written(words_of(good, params, n), "words"), params), None
            lap("tree")
        else:
            words = written(words_of(good, params, n), "words")
            lap("words")
            decided = words if params.sample >= 1 else words.where(F.pmod(F.xxhash64("series_id"), F.lit(1_000_000)) < int(params.sample * 1_000_000))
            p = params if params.sample >= 1 else BuildParams(**{**params.asdict(), "th": max(1, int(params.th * params.sample))})
            tree, copies, counters = build_tree(decided, p)
            if params.sample < 1:
                complete(tree, words, params)
            lap("tree")
        if data:
            materialize(good, tree, copies, params, n, path)
            lap("materialize")
    return SeriesIndex(spark, tree, params, n, [(path, 0)] if data else [], timings=timings | counters)


def complete(tree: WordTree, words: DataFrame, p: BuildParams) -> None:
    """Leaves for cells that words reach but the tree lacks, and sizes of all leaves from the words."""
    shared = words.sparkSession.sparkContext.broadcast(tree)

    def run(batches):
        t = shared.value
        for b in batches:
            w = arrow.words_from(b.column(0), p.w)
            at = t.route(w)
            sid = np.full(len(w), -1, np.int64)
            for node in np.unique(at):
                if not t.is_leaf(int(node)):
                    sid[at == node] = t.sids(int(node), w[at == node])
            yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(sid)], names=["node", "sid"])

    counts = words.select("word").mapInArrow(run, "node long, sid long").groupBy("node", "sid").count().collect()
    for n in range(len(tree)):
        if tree.is_leaf(n):
            tree.size[n] = 0
    for r in sorted(counts, key=lambda r: (r["node"], r["sid"])):
        if r["sid"] < 0:
            tree.size[r["node"]] = r["count"]
        else:
            new_leaf(tree, r["node"], r["sid"], r["count"])
    for n in range(len(tree) - 1, -1, -1):
        if not tree.is_leaf(n):
            tree.size[n] = sum(tree.size[x] for x in tree.below(n))
    tree.number_leaves()


def new_leaf(tree: WordTree, node: int, sid: int, size: int) -> int:
    b, k = pack_prefix(tree.pfx_bits[node], tree.pfx_len[node], tree.csl[node], [sid])
    child = tree.add(node, LEAF, b, k, size, (sid,))
    tree.routes[node][sid] = child
    if len(tree.leaf_id) < len(tree):
        tree.leaf_id += [-1] * (len(tree) - len(tree.leaf_id))
    return child
