"""The experiments: each returns a table of what was measured.

Stand-ins of the given tables and leaf capacities scaled to them take the place of the
published collections; what carries over is which method wins and how measures move with
each parameter, not seconds.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import replace

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import downstream, measures
from .plans import arrow, search, update
from .plans.build import build_index, words_of
from .plans.objective import SearchCost, base_distribution, choose_plan, fanout_range, marginalize, plan_score
from .plans.order import positions
from .plans.params import BuildParams
from .plans.storage import scratch, written
from .plans.tree import next_bits, segment_variance
from .sources import builders

WORKLOADS: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
#: Series for one leaf of each stand-in at scale 0.01; larger tables have larger leaves.
CAPACITY = {"vectors": 6, "walks": 40, "letters": 300, "pulses": 40, "ramps": 300, "monthly": 5}
POLICIES = ("adaptive", "fuzzy", "binary", "fullary", "dynseg")


def workload(f):
    WORKLOADS[f.__name__.replace("run_", "w_")] = f
    return f


def params_for(policy: str, th: int, w: int = 8, **more) -> BuildParams:
    """Settings of a policy: only the adaptive ones pack small leaves."""
    base = BuildParams(w=w, th=th, **more)
    if policy == "adaptive":
        return base
    if policy == "fuzzy":
        return replace(base, f=base.f or 0.1)
    return replace(base, policy=policy, packing="none")


FOUR = ("walks", "letters", "pulses", "vectors")
#: Queries of accuracy, exact, warped exact and update experiments; a table with fewer held-out rows has all of them.
QUERIES, EXACT_QUERIES, WARPED_QUERIES, UPDATE_QUERIES = 200, 40, 10, 100


def stand_in(spark: SparkSession, sf_dir: str, name: str, queries: int = QUERIES) -> tuple[DataFrame, DataFrame, int]:
    """(collection, queries, leaf capacity)."""
    # a table of one row group is built by one task; what is read again and again should not be read by one
    s = written(builders.BUILDERS[name](spark, sf_dir).select("series_id", "values"), name, 8 << 20)
    coll, q = builders.held_out(s, limit=queries)
    base = {"vectors": 480, "walks": 856, "letters": 17_594, "pulses": 1_338, "ramps": 8_543, "monthly": 24}[name]
    return coll, written(q, "queries"), max(CAPACITY[name] // 4, round(CAPACITY[name] * max(0.1, coll.count() / base) ** 0.5))


def _table(spark, rows: list[dict]) -> DataFrame:
    return spark.createDataFrame([tuple(r.values()) for r in rows], list(rows[0])) if rows else spark.createDataFrame([], "nothing string")


def _f(x: float) -> float:
    return float(round(x, 6))


@workload
def run_build(spark, sf_dir) -> DataFrame:
    """Build time of each policy and stand-in, leaf flushes and bytes written."""
    rows = []
    for name in FOUR:
        coll, _, th = stand_in(spark, sf_dir, name)
        for policy in POLICIES:
            began = time.time()
            ix = build_index(coll, params_for(policy, th))
            rows.append({"dataset": name, "policy": policy, "seconds": _f(time.time() - began), "flushes": measures.random_writes(ix, 200), "written_bytes": measures.written_bytes(ix)})
    return _table(spark, rows)


@workload
def run_structure(spark, sf_dir) -> DataFrame:
    """Leaves, nodes, height, fill factor, average path and bits of a split, and size; the last
    two policies have border copies too."""
    rows = []
    for name in FOUR:
        with scratch(spark):
            coll, _, th = stand_in(spark, sf_dir, name)
            found = [(p, f, measures.structure(build_index(coll, params_for(p, th, f=f), data=False))) for p, f in (*((p, 0.0) for p in POLICIES), ("binary", 0.1), ("fullary", 0.1))]
        for policy, f, s in found:
            rows.append({"dataset": name, "policy": policy, "f": f or 0.1 * (policy == "fuzzy"), "leaves": s["leaves"], "nodes": s["nodes"], "height": s["height"], "fill": _f(s["fill"]), "path": _f(s["path"]), "fanout_bits": _f(s["fanout_bits"]), "bytes": s["pickled_bytes"], "copies": _f(s["copies_share"])})
    return _table(spark, rows)


@workload
def run_scaling(spark, sf_dir) -> DataFrame:
    """Build time over numbers and lengths of synthetic walks, and how linear it is in their number."""
    rows = []
    for n_series, n in ((1_000, 64), (4_000, 64), (16_000, 64), (64_000, 64), (4_000, 128), (4_000, 256), (4_000, 512), (4_000, 1_024)):
        s = written(builders.synthetic_walks(spark, n_series, n), "synthetic")
        began = time.time()
        build_index(s, BuildParams(w=16, th=100))
        rows.append({"series": n_series, "length": n, "seconds": _f(time.time() - began)})
    out = _table(spark, rows)
    r2 = measures.linear_fit_r2(out.where("length = 64"), "series", "seconds")
    return out.withColumn("r2_by_series", F.lit(_f(r2)))


def _accuracy(spark, sf_dir, names, ks, leaves, metric="ed", policies=POLICIES, queries=QUERIES) -> DataFrame:
    """MAP and error ratio; gain: of MAP in percent over the binary policy."""
    rows = []
    for name in names:
        coll, q, th = stand_in(spark, sf_dir, name, queries)
        truth = written(search.knn_scan(coll, q, max(ks), metric), "truth")
        for policy in policies:
            ix = build_index(coll, params_for(policy, th))
            for nbr in leaves:
                found = measures.accuracies(search.search_extended(ix, q, max(ks), nbr, metric), truth, ks)
                rows += [{"dataset": name, "policy": policy, "k": k, "leaves": nbr, "map": _f(m), "error_ratio": _f(e)} for k, (m, e) in found.items()]
    base = {(r["dataset"], r["k"], r["leaves"]): r["map"] for r in rows if r["policy"] == "binary"}
    for r in rows:
        r["gain"] = _f(measures.improvement(r["map"], base[r["dataset"], r["k"], r["leaves"]])) if base.get((r["dataset"], r["k"], r["leaves"])) else None
    return _table(spark, rows)


@workload
def run_one_leaf(spark, sf_dir) -> DataFrame:
    """Accuracy of one leaf over k."""
    return _accuracy(spark, sf_dir, FOUR, (1, 5, 10, 20, 50), (1,))


@workload
def run_extended(spark, sf_dir) -> DataFrame:
    """Accuracy over 1 to 25 leaves, k = 1."""
    return _accuracy(spark, sf_dir, FOUR, (1,), (1, 2, 5, 10, 25))


@workload
def run_length_accuracy(spark, sf_dir) -> DataFrame:
    """Accuracy of 25 leaves over the length of series."""
    rows = []
    for n in (64, 128, 256):
        coll, q = builders.held_out(written(builders.synthetic_walks(spark, 2_000, n), "synthetic"), limit=QUERIES)
        truth = written(search.knn_scan(coll, q, 1), "truth")
        for policy in POLICIES:
            m, e = measures.accuracies(search.search_extended(build_index(coll, params_for(policy, 40, 16)), q, 1, 25), truth, (1,))[1]
            rows.append({"length": n, "policy": policy, "map": _f(m), "error_ratio": _f(e)})
    return _table(spark, rows)


@workload
def run_query_time(spark, sf_dir) -> DataFrame:
    """Seconds of searches over one and 25 leaves, k = 50."""
    rows = []
    for name in FOUR:
        coll, q, th = stand_in(spark, sf_dir, name)
        for policy in POLICIES:
            ix = build_index(coll, params_for(policy, th))
            for nbr in (1, 25):
                stats = search.SearchStats()
                search.search_extended(ix, q, 50, nbr, stats=stats).count()
                rows.append({"dataset": name, "policy": policy, "leaves": nbr, "seconds": _f(stats.seconds), "cpu_seconds": _f(stats.cpu_seconds), "series_read": sum(stats.series.values())})
    return _table(spark, rows)


@workload
def run_upper_bounds(spark, sf_dir) -> DataFrame:
    """Histogram of the leaves' upper bounds of the nearest distance."""
    rows = []
    for name in FOUR:
        with scratch(spark):
            coll, _, th = stand_in(spark, sf_dir, name)
            found = [(p, measures.upper_bound_histogram(build_index(coll, params_for(p, th), data=False), 2.0)) for p in ("adaptive", "binary")]
        for policy, h in found:
            rows += [{"dataset": name, "policy": policy, "bin": b, "leaves": n} for b, n in sorted(h.items())]
    return _table(spark, rows)


@workload
def run_tradeoff(spark, sf_dir) -> DataFrame:
    """Accuracy against the number of leaves read in bound order, to the exact answer."""
    rows = []
    for name in ("walks", "letters"):
        coll, q, th = stand_in(spark, sf_dir, name)
        truth = written(search.knn_scan(coll, q, 50), "truth")
        for policy in POLICIES:
            ix = build_index(coll, params_for(policy, th))
            for budget in (1, 16, 1_000_000):
                stats = search.SearchStats()
                found = measures.accuracies(search.search_budget(ix, q, 50, budget, stats=stats), truth, (1, 50))
                rows += [{"dataset": name, "policy": policy, "budget": budget, "k": k, "map": _f(m), "leaves_read": sum(stats.leaves.values()), "seconds": _f(stats.seconds)} for k, (m, _) in found.items()]
    return _table(spark, rows)


@workload
def run_dtw(spark, sf_dir) -> DataFrame:
    """Accuracy under warping with a band of a tenth."""
    return _accuracy(spark, sf_dir, ("pulses", "monthly", "walks"), (1, 10), (1, 5, 25), "dtw", POLICIES, WARPED_QUERIES)


@workload
def run_w(spark, sf_dir) -> DataFrame:
    """Effect of the number of segments."""
    coll, q = builders.held_out(written(builders.synthetic_walks(spark, 2_000, 240), "synthetic"), limit=QUERIES)
    truth = written(search.knn_scan(coll, q, 5), "truth")
    rows = []
    for w in (4, 8, 12, 16, 20):
        for policy in ("adaptive", "binary"):
            ix = build_index(coll, params_for(policy, 40, w))
            found = written(search.search_extended(ix, q, 5, 5), "found")
            rows.append({"w": w, "policy": policy, "map": _f(measures.mean_average_precision(found, truth, 5)), "fill": _f(measures.structure(ix)["fill"])})
    return _table(spark, rows)


@workload
def run_alpha(spark, sf_dir) -> DataFrame:
    """Effect of the weight of balance."""
    rows = []
    with scratch(spark):
        coll, q, th = stand_in(spark, sf_dir, "letters")
        truth = written(search.knn_scan(coll, q, 5), "truth")
        for alpha in (0.0, 0.1, 0.2, 0.3):
            with scratch(spark):
                ix = build_index(coll, params_for("adaptive", th, alpha=alpha))
                found = written(search.search_leaf(ix, q, 5), "found")
                rows.append({"alpha": alpha, "fill": _f(measures.structure(ix)["fill"]), "map": _f(measures.mean_average_precision(found, truth, 5))})
    return _table(spark, rows)


@workload
def run_f(spark, sf_dir) -> DataFrame:
    """Effect of the width of the border that is copied."""
    rows = []
    for name in ("letters", "pulses"):
        coll, q, th = stand_in(spark, sf_dir, name)
        truth = written(search.knn_scan(coll, q, 5), "truth")
        for f in (0.0, 0.05, 0.1, 0.2, 0.3):
            began = time.time()
            ix = build_index(coll, params_for("adaptive", th, f=f))
            seconds = time.time() - began
            found = written(search.search_leaf(ix, q, 5), "found")
            s = measures.structure(ix)
            rows.append({"dataset": name, "f": f, "leaves": s["leaves"], "copies": _f(s["copies_share"]), "seconds": _f(seconds), "map": _f(measures.mean_average_precision(found, truth, 5))})
    return _table(spark, rows)


@workload
def run_fuzzy_policies(spark, sf_dir) -> DataFrame:
    """One leaf, k = 5, without and with border copies under each policy that splits by words:
    accuracy, gain in percent by the copies, leaves."""
    rows = []
    for name in ("walks", "letters", "pulses"):
        coll, q, th = stand_in(spark, sf_dir, name)
        truth = written(search.knn_scan(coll, q, 5), "truth")
        for policy in ("adaptive", "binary", "fullary"):
            found = {}
            for f in (0.0, 0.1):
                ix = build_index(coll, params_for(policy, th, f=f))
                found[f] = measures.mean_average_precision(written(search.search_leaf(ix, q, 5), "found"), truth, 5), measures.structure(ix)["leaves"]
            (plain, leaves), (copied, more) = found[0.0], found[0.1]
            rows.append({"dataset": name, "policy": policy, "map": _f(plain), "map_copies": _f(copied), "gain": _f(measures.improvement(copied, plain)) if plain else None, "leaves": leaves, "leaves_copies": more})
    return _table(spark, rows)


@workload
def run_exact(spark, sf_dir) -> DataFrame:
    """Exact search, k = 50, both distances: seconds, seconds of work in tasks, leaves read, shares pruned."""
    rows = []
    for name in ("walks", "letters"):
        coll, q, th = stand_in(spark, sf_dir, name, EXACT_QUERIES)
        for policy in ("binary", "dynseg", "fullary", "adaptive"):
            ix = build_index(coll, params_for(policy, th))
            for metric, asked in (("ed", q), ("dtw", q.orderBy("query_id").limit(WARPED_QUERIES))):
                stats = search.SearchStats()
                search.search_exact(ix, asked, 50, metric, stats=stats)
                read, series, n = sum(stats.leaves.values()), sum(stats.series.values()), max(1, len(stats.leaves))
                by_leaf, by_series = measures.pruned_shares(ix, read, series, n)
                rows.append({"dataset": name, "policy": policy, "metric": metric, "seconds": _f(stats.seconds), "cpu_seconds": _f(stats.cpu_seconds), "leaves_read": read, "pruned_leaf_share": _f(by_leaf), "pruned_series_share": _f(by_series), "waves": stats.waves})
    return _table(spark, rows)


@workload
def run_updates(spark, sf_dir) -> DataFrame:
    """Batches of insertions with exact queries between them: walks by supplier, pulses by the
    time of their events.  Half or a quarter of the series is there at first, and two or three
    batches bring the others."""
    rows = []
    for name in ("walks", "pulses"):
        coll, q, th = stand_in(spark, sf_dir, name, UPDATE_QUERIES)
        place = positions(coll.select("series_id", F.pmod("series_id", F.lit(builders.OWNER)).alias("window") if name == "pulses" else F.floor(F.col("series_id") / builders.OWNER).alias("window")), ["window", "series_id"])
        total = coll.count()
        ordered = written(coll.join(place.select("series_id", "pos"), "series_id"), "ordered")
        for first, batches in ((0.5, 2),) if name == "walks" else ((0.25, 3),):
            at = [round(total * (first + (1 - first) * i / batches)) for i in range(batches + 1)]
            parts = [ordered.where((F.col("pos") >= a) & (F.col("pos") < b)).select("series_id", "values") for a, b in zip(at[:-1], at[1:])]
            for policy in ("adaptive", "binary", "dynseg"):
                ix = build_index(ordered.where(F.col("pos") < at[0]).select("series_id", "values"), params_for(policy, th))
                for r in update.run_mixed(ix, parts, q, 10):
                    rows.append({"dataset": name, "policy": policy, "first": first, "batches": batches, "batch": r["batch"], "insert_s": _f(r["insert_s"]), "query_s": _f(r["query_s"]), "leaves_read": r["leaves_read"], "series": r["series"]})
    return _table(spark, rows)


@workload
def run_root_cells(spark, sf_dir) -> DataFrame:
    """How unevenly the first layer is filled."""
    rows = []
    for name in ("walks", "letters", "ramps"):
        coll, _, _ = stand_in(spark, sf_dir, name)
        n = {"walks": 64, "letters": 128, "ramps": 256}[name]
        cells = written(words_of(coll, BuildParams(w=8), n), "words").groupBy("cell").agg(F.count(F.lit(1)).alias("n"))
        s = measures.root_cell_shares(written(cells, "cells"))
        rows.append({"dataset": name, "cells": s["cells"], "small_share": _f(s["small_share"]), "top_share": _f(s["top_share"])})
    return _table(spark, rows)


@workload
def run_plan_ablation(spark, sf_dir) -> DataFrame:
    """Restricted search of plans on all full root cells against trying all sizes of plans
    (exhaustive), summing each plan's cells from the counts (flat) and counting its series
    anew (rescan): plans, cells visited, seconds, score against the best of all.

    Variances and counts of next bits come from aggregates over all words of a cell.
    """
    coll, _, th = stand_in(spark, sf_dir, "walks")
    p = BuildParams(w=8, th=th)
    words = written(words_of(coll, p, 64), "words")

    def measured(key, table):
        cell, words = int(key[0].as_py()), arrow.words_from(table.column("word").combine_chunks(), p.w)
        if len(words) <= p.th:
            return pa.table({c: pa.array([], t) for c, t in kinds.items()})
        bits = [(cell >> (7 - s)) & 1 for s in range(8)]
        codes = next_bits(words, bits, [1] * 8, range(8), 8)
        var, base, out = segment_variance(words, range(8), 8), base_distribution(codes), []
        every = tuple(range(8))
        for how in ("restricted", "flat", "rescan", "exhaustive"):
            cost, began = SearchCost(), time.perf_counter()
            plan = choose_plan(var, base, every, len(words), th, p.alpha, p.f_low, p.f_high, how, cost=cost, codes=codes)
            spent = time.perf_counter() - began
            score = float(plan_score(var[list(plan)], marginalize(base, every, plan), th, p.alpha)[0])
            out.append((cell, how, "-".join(map(str, plan)), cost.plans_scored, cost.cells_touched, _f(spent), _f(score), str(fanout_range(len(words), th, p.f_low, p.f_high, 8))))
        return pa.table([pa.array(c, t) for c, t in zip(zip(*out), kinds.values())], names=list(kinds))

    kinds = {"cell": pa.int64(), "search": pa.string(), "plan": pa.string(), "plans_scored": pa.int64(), "cells_touched": pa.int64(), "seconds": pa.float64(), "score": pa.float64(), "range": pa.string()}
    rows = words.groupBy("cell").applyInArrow(measured, "cell long, search string, plan string, plans_scored long, cells_touched long, seconds double, score double, range string")
    return written(rows, "plans").withColumn("of_best", F.round(F.col("score") / F.max("score").over(Window.partitionBy("cell")), 6))


@workload
def run_uneven(spark, sf_dir) -> DataFrame:
    """Share of leaves whose segments differ by more than four bits."""
    rows = []
    for name in ("letters", "walks"):
        with scratch(spark):
            coll, _, th = stand_in(spark, sf_dir, name)
            for policy in ("binary", "adaptive", "fullary"):
                rows.append({"dataset": name, "policy": policy, "uneven": _f(measures.uneven_leaves(build_index(coll, params_for(policy, th), data=False)))})
    return _table(spark, rows)


@workload
def run_downstream(spark, sf_dir) -> DataFrame:
    """Classifier accuracy, outlier ROC-AUC and softmax mass with approximate neighbours."""
    coll, q, th = stand_in(spark, sf_dir, "vectors", 80)
    labels = builders.vectors(spark, sf_dir).select("series_id", "label")
    true = labels.withColumnRenamed("series_id", "query_id")
    ix = build_index(coll, params_for("adaptive", th))
    truth = written(search.knn_scan(coll, q, 10), "truth")
    positive = {r["query_id"] for r in downstream.knn_outliers(truth, 10).orderBy(F.desc("score")).limit(8).collect()}
    rows = []
    for nbr in (1, 5, 25, 1_000_000):
        found = written(search.search_extended(ix, q, 10, nbr), "found")
        right = downstream.knn_classify(found, labels).join(true, "query_id").select(F.avg((F.col("predicted") == F.col("label")).cast("int"))).first()[0]
        scored = downstream.knn_outliers(found, 10).withColumn("positive", F.col("query_id").isin(list(positive)))
        rows.append({"leaves": nbr, "recall": _f(measures.recall_at_k(found, truth, 10)), "classifier_accuracy": _f(right or 0.0), "outlier_auc": _f(downstream.roc_auc(scored, "score", "positive"))})
    return _table(spark, rows)


@workload
def run_packing(spark, sf_dir) -> DataFrame:
    """Packing by demotion, by size, by sorted words, and none: leaves, fill, one-leaf accuracy, leaves read by exact search."""
    coll, q, th = stand_in(spark, sf_dir, "walks")
    truth = written(search.knn_scan(coll, q, 5), "truth")
    rows = []
    for packing, rho in (("none", 0.5), ("size", 0.5), ("sorted", 0.5), ("demotion", 0.25), ("demotion", 0.5), ("demotion", 0.75)):
        ix = build_index(coll, params_for("adaptive", th, packing=packing, rho=rho))
        s, stats = measures.structure(ix), search.SearchStats()
        found = written(search.search_leaf(ix, q, 5), "found")
        search.search_exact(ix, q, 5, stats=stats)
        rows.append({"packing": packing, "rho": rho, "leaves": s["leaves"], "fill": _f(s["fill"]), "map": _f(measures.mean_average_precision(found, truth, 5)), "leaves_read": sum(stats.leaves.values())})
    return _table(spark, rows)
