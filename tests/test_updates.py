"""Updates that must not lose, repeat or hide series, and what searches read."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from series_engine import measures
from series_engine.functions import summaries as S
from series_engine.functions.distances import QuerySummary
from series_engine.plans import build, search, update
from series_engine.plans.build import build_index
from series_engine.plans.index import intervals, load_index
from series_engine.plans.params import BuildParams
from series_engine.plans.storage import fresh_path, written
from series_engine.sources import builders
from series_engine.streaming import streams

P = BuildParams(w=8, th=20)


@pytest.fixture(scope="module")
def walks(spark):
    s = written(builders.synthetic_walks(spark, 500, 32), "walks")
    coll, q = builders.held_out(s, limit=6)
    return coll, written(q, "queries")


def rows(df):
    return sorted((r["query_id"], r["rank"], round(r["distance"], 6)) for r in df.collect())


def natives(ix):
    return ix.data(None, ("series_id", "is_copy")).where("not is_copy").count()


def thirds(coll):
    part = F.pmod(F.xxhash64("series_id"), F.lit(3))
    return [coll.where(part == i) for i in range(3)]


def test_every_mixed_run_takes_its_batches(walks):
    coll, q = walks
    a, b, c = thirds(coll)
    ix = build_index(a, P)
    update.run_mixed(ix, [b], q, 3)
    out = update.run_mixed(ix, [c], q, 3)
    assert natives(ix) == coll.count() == ix.tree.size[0] == out[-1]["series"]
    assert rows(search.search_exact(ix, q, 5)) == rows(search.knn_scan(coll, q, 5))
    update.run_mixed(ix, [c], q, 3, stream="again")
    update.run_mixed(ix, [c], q, 3, stream="again")  # the same stream and batch: not taken twice
    assert natives(ix) == coll.count() + c.count()


def test_streams_go_on_and_batches_outlive_a_save(spark, walks, tmp_path):
    coll, q = walks
    a, b, c = thirds(coll)
    folder = fresh_path(spark, "arrivals")
    b.write.parquet(folder)
    ix = build_index(a, P)
    source = lambda: spark.readStream.schema("series_id long, values array<double>").parquet(folder)
    streams.stream_into(ix, source(), name="arrivals")
    assert natives(ix) == a.count() + b.count()
    again = load_index(spark, ix.save(str(tmp_path / "ix")))
    assert again.taken == ix.taken and again.uid == ix.uid and again.was_taken("arrivals", 0) and not again.was_taken("other", 0)
    c.write.mode("append").parquet(folder)
    streams.stream_into(again, source(), name="arrivals")
    assert natives(again) == coll.count()
    assert rows(search.search_exact(again, q, 5)) == rows(search.knn_scan(coll, q, 5))


def test_deleted_ids_can_come_again(walks):
    coll, q = walks
    ix = build_index(coll, P)
    some = coll.where("series_id % 7 = 0")
    update.delete(ix, some.select("series_id"))
    left = coll.count() - some.count()
    assert natives(ix) == left == ix.tree.size[0] == sum(ix.tree.size[n] for n in ix.tree.below(0))
    update.insert(ix, some)
    assert natives(ix) == coll.count() == ix.tree.size[0]
    truth = rows(search.knn_scan(coll, q, 5))
    assert rows(search.search_exact(ix, q, 5)) == truth
    update.vacuum(ix)
    assert natives(ix) == coll.count() and rows(search.search_exact(ix, q, 5)) == truth
    update.delete(ix, some.select("series_id"))
    update.reorganize(ix)
    assert natives(ix) == left


@pytest.mark.parametrize("settings", [{}, {"policy": "dynseg"}, {"packing": "sorted"}])
def test_a_failed_insertion_changes_nothing(walks, monkeypatch, settings):
    coll, q = walks
    a, b, _ = thirds(coll)
    ix = build_index(a, BuildParams(w=8, th=20, **settings))
    before = (rows(search.search_exact(ix, q, 5)), ix.tree.size[0], len(ix.tree), ix.version, ix.taken)

    def fails(*args, **more):
        raise OSError("no room")

    with monkeypatch.context() as m:
        m.setattr(update, "write_by_leaf", fails)
        m.setattr(update, "materialize", fails)
        with pytest.raises(OSError):
            update.insert(ix, b, 0)
    assert (rows(search.search_exact(ix, q, 5)), ix.tree.size[0], len(ix.tree), ix.version, ix.taken) == before
    update.insert(ix, b, 0)
    assert natives(ix) == a.count() + b.count()


def test_copies_follow_insertions_and_rebuilds(walks):
    coll, q = walks
    a, b, c = thirds(coll)
    ix = build_index(a, BuildParams(w=8, th=30, f=0.3))
    copies = lambda: ix.data(None, ("series_id", "leaf_id", "is_copy")).where("is_copy")
    first = copies().count()
    update.insert(ix, b)
    second = copies().count()
    assert second > first and copies().join(b, "series_id", "left_semi").count() == second - first
    update.insert(ix, c)
    update.reorganize(ix)
    per = ix.data(None, ("series_id", "leaf_id", "is_copy")).groupBy("series_id").agg(F.count(F.lit(1)).alias("n"), F.countDistinct("leaf_id").alias("l"), F.count_if("is_copy").alias("c"))
    assert copies().join(c, "series_id", "left_semi").count() > 0 and copies().count() > first
    assert per.where("n <> l or n - c <> 1").count() == 0 and per.count() == coll.count()
    assert copies().count() == sum(ix.tree.n_copies[n] for n in ix.tree.below(0))
    assert rows(search.search_exact(ix, q, 5)) == rows(search.knn_scan(coll, q, 5))


def test_rebuild_beside_changes(walks):
    coll, q = walks
    a, b, c = thirds(coll)
    ix = build_index(a, BuildParams(w=8, th=10))
    update.insert(ix, b)
    beside = update.Reorganization(ix)
    update.insert(ix, c)
    gone = coll.where("series_id % 11 = 0").select("series_id")
    update.delete(ix, gone)
    left = coll.join(gone, "series_id", "left_anti")
    truth = rows(search.knn_scan(left, q, 5))
    assert rows(search.search_exact(ix, q, 5)) == truth
    beside.finish()
    assert rows(search.search_exact(ix, q, 5)) == truth and natives(ix) == left.count() == ix.tree.size[0]
    update.insert(ix, coll.join(gone, "series_id", "left_semi"))
    assert rows(search.search_exact(ix, q, 5)) == rows(search.knn_scan(coll, q, 5))


def test_large_subtrees_are_rebuilt_in_rounds(walks):
    coll, q = walks
    a, b, c = thirds(coll)
    shape = []
    for limit in (5_000_000, 25):
        ix = build_index(a, BuildParams(w=4, th=20, local_limit=limit))
        update.insert(update.insert(ix, b), c)
        update.reorganize(ix)
        assert not [n for n in update.violations(ix) if ix.tree.is_leaf(n)]
        assert rows(search.search_exact(ix, q, 5)) == rows(search.knn_scan(coll, q, 5))
        shape.append(sorted((ix.tree.pfx_bits[n], ix.tree.pfx_len[n], ix.tree.size[n]) for n in ix.tree.below(0)))
    assert shape[0] == shape[1]


def test_just_full_decides_alike_in_rounds(walks):
    coll, _ = walks
    words = written(build.words_of(coll, P, 32), "words")
    shape = []
    for limit in (5_000_000, 25):
        t, _, _ = build.build_tree(words.repartition(5), BuildParams(w=8, th=20, when="just_full", local_limit=limit))
        shape.append(sorted((t.pfx_bits[n], t.pfx_len[n], t.size[n]) for n in t.below(0)))
    full, _, _ = build.build_tree(words, P)
    assert shape[0] == shape[1] != sorted((full.pfx_bits[n], full.pfx_len[n], full.size[n]) for n in full.below(0))


def test_sorted_packing(walks):
    coll, q = walks
    a, b, c = thirds(coll)
    ix = build_index(coll, BuildParams(w=8, th=20, packing="sorted"))
    s = measures.structure(ix)
    assert s["fill"] > 0.9 and s["leaves"] == -(-coll.count() // 20) and s["model_bytes"] > 0
    for metric in ("ed", "dtw"):
        assert rows(search.search_exact(ix, q, 5, metric)) == rows(search.knn_scan(coll, q, 5, metric))
    grown = build_index(a, BuildParams(w=8, th=20, packing="sorted"))
    update.insert(update.insert(grown, b), c)
    truth = rows(search.knn_scan(coll, q, 5))
    assert rows(search.search_exact(grown, q, 5)) == truth and update.violations(grown)
    update.reorganize(grown)
    assert rows(search.search_exact(grown, q, 5)) == truth and not update.violations(grown) and natives(grown) == coll.count()
    copies = coll.select(F.lit(1).cast("long").alias("x")).sparkSession.createDataFrame([(i, [1.0, 3.0, 2.0, 0.0]) for i in range(90)], "series_id long, values array<double>")
    one = build_index(copies, BuildParams(w=4, th=20, packing="sorted"))
    assert measures.structure(one)["leaves"] == 1 and measures.structure(one)["oversize"] == 1 and one.data().count() == 90


def test_files_follow_pack_bytes(walks):
    coll, _ = walks
    ix = build_index(coll, BuildParams(w=8, th=20, pack_bytes=4_000))
    files = ix.spark.read.parquet(ix.segments[0][0]).select(F.input_file_name().alias("f")).groupBy("f").count().collect()
    assert len(files) >= 20 and max(r["count"] for r in files) * (8 * 32 + 25) < 16_000


def test_settings_are_checked():
    for bad in ({"when": "later"}, {"search": "x"}, {"f_low": 4.0}, {"rho": 2.0}, {"f": 1.0}, {"sample": 0.0}, {"pack_bytes": 0}, {"packing": "sorted", "f": 0.1}, {"packing": "sorted", "policy": "binary"}):
        with pytest.raises(ValueError):
            BuildParams(**bad)


# ---- what a search reads ----


def test_intervals():
    assert intervals([]) == ([], True) and intervals([5, 3, 4, 9]) == ([(3, 5), (9, 9)], True)
    got, exact = intervals([1, 2, 10, 20, 21, 90], 2)
    assert got == [(1, 21), (90, 90)] and not exact


def test_a_search_scans_once(spark, walks, monkeypatch):
    coll, q = walks
    ix = build_index(coll, P)
    plans = []
    collect = type(coll).collect

    def seen(df):
        plans.append(df._jdf.queryExecution().executedPlan().toString())
        return collect(df)

    monkeypatch.setattr(type(coll), "collect", seen)
    stats = search.SearchStats()
    search.search_exact(ix, q, 5, stats=stats)
    reads = [p for p in plans if "MapInArrow" in p and "leaf_id" in p]
    assert len(reads) == stats.waves
    for p in reads:
        final = p[p.index("Initial Plan"):] if "Initial Plan" in p else p
        assert final.count("FileScan parquet") == 1 and final.count("MapInArrow") == 1
        assert "GreaterThanOrEqual(leaf_id" in p or "EqualTo(leaf_id" in p or "Or(" in p


def test_descent_gives_the_order_of_all_bounds(walks):
    coll, q = walks
    for settings in ({}, {"packing": "none", "policy": "binary"}, {"packing": "sorted"}):
        ix = build_index(coll, BuildParams(w=8, th=10, **settings))
        asked = search._prepared(ix, q, "ed", 0.1)
        t = ix.tree
        nodes, ids, *_ = t.leaves()
        for s, w in zip(asked.summaries, asked.words):
            home = search.extended_leaves(t, s, w, 1)[0]
            a, b = search._Sorted(t, s, home, nodes, ids), search._Descent(t, s, home)
            first = [list(iter(lambda way=way: way.next(np.inf), None)) for way in (a, b)]
            assert first[0] == first[1] and sorted(first[0]) == sorted(ids.tolist())
            half = float(np.median(t.bounds(s)))
            c, d = search._Sorted(t, s, home, nodes, ids), search._Descent(t, s, home)
            assert [x for x in iter(lambda: c.next(half), None)] == [x for x in iter(lambda: d.next(half), None)]


def test_exact_search_by_descent(walks, monkeypatch):
    coll, q = walks
    monkeypatch.setattr(search, "MAX_BOUNDS", 1)
    for policy in ("adaptive", "dynseg"):
        ix = build_index(coll, BuildParams(w=8, th=20, policy=policy))
        assert rows(search.search_exact(ix, q, 5)) == rows(search.knn_scan(coll, q, 5))


def test_queries_of_another_length_are_named(spark, walks):
    coll, _ = walks
    short = spark.createDataFrame([(1, [1.0, 2.0])], "query_id long, values array<double>")
    with pytest.warns(UserWarning, match="not of length 32"):
        search.prepare(short, 32, 8, 8)
    with pytest.raises(ValueError):
        search.prepare(short, 32, 8, 8, strict=True)


def test_a_rebuild_counts_copies_that_series_keep(walks):
    coll, _ = walks
    a, b, _ = thirds(coll)
    ix = update.insert(build_index(a, BuildParams(w=8, th=20, f=0.3, max_copies=1)), b)
    update.reorganize(update.insert(ix, thirds(coll)[2]))
    copies = ix.data(None, ("series_id", "is_copy")).where("is_copy").groupBy("series_id").count()
    assert copies.count() > 0 and copies.where("count > 1").count() == 0


def test_equal_words_are_not_split(spark):
    """Copies of one series beyond a leaf's capacity make one leaf, not a chain of splits; others that come later part it."""
    rng = np.random.default_rng(3)
    x = [[float(v) for v in np.cumsum(rng.standard_normal(32))] for _ in range(12)]
    coll = spark.createDataFrame([(100 * i + c, v) for i, v in enumerate(x) for c in range(30)], "series_id long, values array<double>")
    q = coll.where("series_id % 100 = 0").withColumnRenamed("series_id", "query_id")
    for policy in ("adaptive", "binary", "fullary"):
        ix = build_index(coll, BuildParams(w=8, th=10, policy=policy, packing="none"))
        inner = [n for n in range(len(ix.tree)) if not ix.tree.is_leaf(n)]
        assert len(inner) < 12 and all(ix.tree.oversize[n] for n in ix.tree.below(0))
        assert rows(search.search_exact(ix, q, 40)) == rows(search.knn_scan(coll, q, 40))
    noisy = [(5_000 + i, [a + float(e) for a, e in zip(x[0], rng.standard_normal(32))]) for i in range(30)]
    more = spark.createDataFrame(noisy, "series_id long, values array<double>")
    update.insert(ix, more)
    leaves = len(ix.tree.below(0))
    update.reorganize(ix)
    assert len(ix.tree.below(0)) > leaves
    assert rows(search.search_exact(ix, q, 40)) == rows(search.knn_scan(coll.unionByName(more), q, 40))


def test_reads_of_many_queries_give_what_a_plain_scan_gives(spark, walks, monkeypatch):
    """Leaves meet all their queries at once, and orders of leaves are kept in part."""
    coll, q = walks
    x = {r["series_id"]: np.array(r["values"]) for r in coll.collect()}
    ids = np.array(sorted(x))
    z = {i: (v - v.mean()) / v.std() for i, v in x.items()}
    monkeypatch.setattr(search, "_WAITING", 2)
    for k in (3, len(ids) + 5):
        expected = []
        for r in q.collect():
            v = np.array(r["values"])
            v = (v - v.mean()) / v.std()
            d = np.array([np.sqrt(((z[i] - v) ** 2).sum()) for i in ids])
            expected += [(r["query_id"], rank, int(ids[j]), round(float(d[j]), 6)) for rank, j in enumerate(np.lexsort((ids, d))[:k], 1)]
        short = lambda df: sorted((r["query_id"], r["rank"], r["series_id"], round(r["distance"], 6)) for r in df.collect())
        assert short(search.knn_scan(coll, q, k)) == sorted(expected)
        for policy in ("adaptive", "dynseg"):
            assert short(search.search_exact(build_index(coll, BuildParams(w=8, th=10, policy=policy)), q, k)) == sorted(expected)


def test_pairs_that_a_product_of_matrices_passes(monkeypatch):
    """What may be among the k nearest always passes, far from zero and for equal rows too; steps change no distance."""
    rng = np.random.default_rng(5)
    x, v = 1e6 + rng.standard_normal((40, 70)), 1e6 + rng.standard_normal((5, 70))
    x[7] = v[2]
    d = np.sqrt(((x[:, None] - v) ** 2).sum(2))
    assert search._close(x, v, np.full(5, np.inf), 3)[np.argsort(d, 0)[:3], np.arange(5)].all()
    assert search._close(x, v, d[9])[d <= d[9]].all() and search._close(x, v, np.zeros(5))[7, 2]
    i, j = np.nonzero(np.ones_like(d, bool))
    whole = search._pair_distances(x, v, i, j)
    monkeypatch.setattr(search, "_STEP", 700)
    assert (search._pair_distances(x, v, i, j) == whole).all() and np.allclose(whole, d.reshape(-1)) and whole[7 * 5 + 2] == 0
    at, far, ids = search._nearest(np.array([1, 0, 1, 1]), np.array([2.0, 1.0, 1.0, 3.0]), np.array([9, 4, 8, 8]), 2)
    assert at.tolist() == [0, 1, 1] and far.tolist() == [1.0, 1.0, 2.0] and ids.tolist() == [4, 8, 9]


def test_descent_keeps_what_the_cut_leaves(walks):
    """After the first leaves of many, a descent holds no node at or above the cut, and few Python objects."""
    coll, q = walks
    ix = build_index(coll, BuildParams(w=8, th=2, policy="fullary", packing="none"))
    asked, t = search._prepared(ix, q, "ed", 0.1), ix.tree
    shared = search._Nodes(t)
    for s, home in zip(asked.summaries, search._homes(t, asked)):
        cut = float(np.quantile(t.bounds(s), 0.2))
        way = search._Descent(t, s, home, nodes=shared)
        got = [x for x in iter(lambda way=way: way.next(cut), None)]
        nodes, ids, *_ = t.leaves()
        assert got == [x for x in iter(lambda b=search._Sorted(t, s, home, nodes, ids): b.next(cut), None)] and len(way.order) == 0
        way = search._Descent(t, s, home, nodes=shared)
        way.next(cut), way.next(cut)
        assert all((b < cut).all() for b in (way.inner[0], way.leaves[0], way.bounds))


def test_many_queries_take_larger_waves(walks, monkeypatch):
    coll, q = walks
    ix = build_index(coll, BuildParams(w=8, th=2, policy="fullary", packing="none"))
    few, many = search.SearchStats(), search.SearchStats()
    plain = rows(search.search_exact(ix, q, 5, stats=few))
    monkeypatch.setattr(search, "MANY_QUERIES", 1)
    assert rows(search.search_exact(ix, q, 5, stats=many)) == plain == rows(search.knn_scan(coll, q, 5)) and many.waves < few.waves


def test_bounds_of_many_segmentations_are_those_of_one():
    """All leaves at once, and few means of the query: not one for each leaf."""
    from series_engine.plans import dynseg

    rng = np.random.default_rng(5)
    x = S.znormalize_rows(np.cumsum(rng.standard_normal((400, 32)), 1))
    t, _ = dynseg.grow_dynseg(x[40:], BuildParams(w=8, th=5, policy="dynseg"))
    t.number_leaves()
    for metric in ("ed", "dtw"):
        for v in x[:10]:
            q = QuerySummary(v, 8, metric)
            one = [dynseg.mindist_eapca(q, t.cuts[n], t.synopsis[n]) for n in t.leaf_nodes()]
            ends = np.array([(a, b) for n in t.leaf_nodes() for a, b in zip(t.cuts[n][:-1], t.cuts[n][1:])])
            node = np.repeat(np.arange(len(one)), [len(t.cuts[n]) - 1 for n in t.leaf_nodes()])
            assert np.allclose(dynseg.bounds_eapca(q, node, ends, np.concatenate([t.synopsis[n] for n in t.leaf_nodes()])), one, rtol=1e-12, atol=1e-12)
            assert np.allclose(t.bounds(q), one, rtol=1e-12, atol=1e-12) and np.allclose(t.bounds(q, [0]), [dynseg.mindist_eapca(q, t.cuts[0], t.synopsis[0])])
