"""Worked examples, bounds and properties of the search methods."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from series_engine import measures
from series_engine.functions import distances as D
from series_engine.functions import summaries as S
from series_engine.plans import search, update
from series_engine.plans.build import build_index, build_tree, checked, words_of
from series_engine.plans.index import load_index
from series_engine.plans.objective import SearchCost, base_distribution, choose_plan, fanout_asked, fanout_range, marginalize, plan_score
from series_engine.plans.pack import demotion, pack_leaves, pack_prefix
from series_engine.plans.params import BuildParams
from series_engine.plans.storage import written
from series_engine.plans.tree import WordTree, border_gaps, grow, next_bits, segment_variance
from series_engine.sources import builders, rawfloat

P = BuildParams(w=8, th=20)


@pytest.fixture(scope="module")
def walks(spark):
    s = written(builders.synthetic_walks(spark, 600, 64), "walks")
    coll, q = builders.held_out(s, limit=8)
    return s, coll, q


def rows(df):
    return sorted((r["query_id"], r["rank"], round(r["distance"], 6)) for r in df.collect())


# ---- worked examples ----


def test_three_segments():
    assert S.sax_rows(np.array([[0.28, -0.31, -0.49]]), 3).tolist() == [[4, 3, 2]]


def test_coarser_breakpoints_are_among_finer_ones():
    assert set(S.breakpoints(3)) <= {round(b, 15) for b in S.breakpoints(6)} | set(S.breakpoints(6)) or np.allclose(S.breakpoints(3), S.breakpoints(6)[7::8])
    assert S.cell(0, 0, 8) == (-4.0, 4.0, 0.0)


def test_child_sizes_are_reused():
    assert marginalize(np.array([300, 60, 23, 25]), (0, 1), (0,)).tolist() == [360, 48]
    assert marginalize(np.array([300, 60, 23, 25]), (0, 1), (1,)).tolist() == [323, 85]


def test_demoted_bits():
    assert demotion([0b0010, 0b0100]) == 2 and demotion([0b0010, 0b0101]) == 3 and demotion([5]) == 0
    assert pack_prefix([0, 1], [1, 1], (0, 1), [0b01, 0b11]) == ([0, 3], [1, 2])


def test_promoted_bits_of_three_segments():
    t = WordTree(4, 3)
    t.add(-1, "internal", [0] * 4, [0] * 4, 1)
    t.csl[0] = (0, 2, 3)
    assert t.sids(0, np.array([[4, 0, 3, 7]], np.uint8)).tolist() == [0b101]


def test_coarse_leaf_has_an_upper_bound_of_64():
    assert D.upper_bounds_rows(np.zeros((1, 16), int), np.ones((1, 16), int), 256)[0] == pytest.approx(64)


def test_wide_and_balanced_wins():
    wide, narrow, even, uneven = [2.0, 2.0], [0.1, 0.1], [25, 25, 25, 25], [97, 1, 1, 1]
    score = lambda v, s: float(plan_score(np.array(v), np.array(s), 30, 0.2)[0])
    assert score(wide, even) > max(score(wide, uneven), score(narrow, even)) and score(narrow, uneven) < min(score(wide, uneven), score(narrow, even))


def test_fanout_range():
    assert fanout_range(100, 40, 0.5, 3.0, 8) == (1, 2) and fanout_range(10**6, 10**4, 0.5, 3.0, 16) == (6, 7) and fanout_range(10**6, 10, 0.5, 3.0, 4) == (4, 4)


def test_border_copies_depend_on_f():
    words = np.array([[127, 10], [128, 10], [200, 10]], np.uint8)
    sid = np.array([0, 1, 1])
    near = lambda f: np.isfinite(border_gaps(words, [0, 0], [0, 0], (0,), sid, BuildParams(w=2, f=f))[:, 0]).tolist()
    assert near(0.1) == [True, True, False] and near(1e-9) == [False] * 3


# ---- summaries and bounds ----


def test_expressions_equal_arrays(spark, walks):
    s, _, _ = walks
    z = s.select("series_id", S.znormalize(F.col("values")).alias("z"))
    m = z.select("series_id", "z", S.paa(F.col("z"), 8, 64).alias("m")).select("*", S.sax(F.col("m"), 8).alias("s"))
    got = m.orderBy("series_id").limit(50).collect()
    x = S.znormalize_rows(np.array([r["values"] for r in s.orderBy("series_id").limit(50).collect()]))
    assert np.allclose(x, [r["z"] for r in got]) and np.allclose(S.paa_rows(x, 8), [r["m"] for r in got])
    assert S.words_rows(x, 8, 8).tolist() == [r["s"] for r in got]


def test_flat_series_become_zeros(spark):
    assert not S.znormalize_rows(np.full((2, 8), 3.3)).any()
    df = spark.createDataFrame([([2.5] * 8,)], "v array<double>")
    assert df.select(S.znormalize(F.col("v")).alias("z")).first()["z"] == [0.0] * 8


def test_ragged_segments():
    x = np.arange(10.0)[None]
    assert S.paa_rows(x, 4)[0] == pytest.approx([(0 + 1 + 0.5 * 2) / 2.5, (0.5 * 2 + 3 + 4) / 2.5, (5 + 6 + 0.5 * 7) / 2.5, (0.5 * 7 + 8 + 9) / 2.5])
    with pytest.raises(ValueError):
        S.paa(F.lit(None), 4, 10)


def _dtw(a, b, r):
    n = len(a)
    d = np.full((n + 1, n + 1), np.inf)
    d[0, 0] = 0
    for i in range(n):
        for j in range(n):
            if abs(i - j) <= r:
                d[i + 1, j + 1] = (a[i] - b[j]) ** 2 + min(d[i, j], d[i, j + 1], d[i + 1, j])
    return np.sqrt(d[n, n])


def test_distances_and_bounds():
    rng = np.random.default_rng(0)
    x = S.znormalize_rows(np.cumsum(rng.standard_normal((40, 32)), 1))
    q = x[0]
    assert D.dtw_rows(x, q, 3) == pytest.approx([_dtw(q, y, 3) for y in x])
    assert D.dtw_rows(x, q, 0) == pytest.approx(D.ed_rows(x, q))
    abandoned = D.ed_rows(x, q, 4.0, 8)
    assert np.isinf(abandoned[D.ed_rows(x, q) > 4.1]).all()
    for metric in ("ed", "dtw"):
        s = D.QuerySummary(q, 8, metric)
        true = s.distances(x)
        assert (D.lb_envelope_rows(x, s.upper, s.lower) <= true + 1e-9).all()
        w = S.words_rows(x, 8, 8).astype(int)
        before = np.full(len(x), np.inf)
        for k in (8, 5, 2, 0):  # coarser prefixes have smaller bounds
            lo, hi = S.cells_rows(w >> (8 - k), np.full(w.shape, k))
            b = D.mindist_cells_rows(s.hi, s.lo, lo, hi, 32)
            assert (b <= true + 1e-9).all() and (b <= before + 1e-9).all()
            before = b


# ---- plan search ----


def test_restricted_search_against_all_plans():
    rng = np.random.default_rng(2)
    words = S.words_rows(S.znormalize_rows(np.cumsum(rng.standard_normal((500, 64)), 1)), 6, 8)
    every = tuple(range(6))
    var, base = segment_variance(words, every, 8), base_distribution(next_bits(words, [0] * 6, [0] * 6, every, 8))
    cost = {k: SearchCost() for k in ("restricted", "flat", "exhaustive")}
    plans = {k: choose_plan(var, base, every, 500, 30, 0.2, 0.5, 3.0, k, cost=c) for k, c in cost.items()}
    score = lambda p: float(plan_score(var[list(p)], marginalize(base, every, p), 30, 0.2)[0])
    assert plans["restricted"] == plans["flat"] and score(plans["restricted"]) <= score(plans["exhaustive"]) + 1e-12
    assert cost["restricted"].cells_touched < cost["flat"].cells_touched and cost["restricted"].plans_scored < cost["exhaustive"].plans_scored == 63


def test_packs_stay_within_limits():
    rng = np.random.default_rng(4)
    sizes = {int(s): int(n) for s, n in zip(rng.permutation(64)[:50], rng.integers(1, 30, 50))}
    packs = pack_leaves(sizes, 6, 40, 0.5, 1.0, 0, "x")
    assert sorted(s for p in packs for s in p) == sorted(sizes) and all(sum(sizes[s] for s in p) <= 40 and demotion(p) <= 3 for p in packs)
    assert packs == pack_leaves(dict(reversed(sizes.items())), 6, 40, 0.5, 1.0, 0, "x") and len(packs) < len(sizes)


def test_equal_series_make_one_oversize_leaf(spark):
    df = spark.createDataFrame([(i, [1.0, 2.0, 3.0, 0.0] * 4) for i in range(50)], "series_id long, values array<double>")
    for policy in ("adaptive", "binary", "fullary", "dynseg"):
        ix = build_index(df, BuildParams(w=4, th=10, policy=policy))
        s = measures.structure(ix)
        assert s["oversize"] == 1 and ix.data().count() == 50


# ---- index ----


@pytest.mark.parametrize("metric", ["ed", "dtw"])
@pytest.mark.parametrize("settings", [{}, {"f": 0.2}, {"policy": "binary", "packing": "none"}, {"policy": "binary_rr"}, {"policy": "fullary", "packing": "size"}, {"policy": "dynseg"}, {"packing": "none", "when": "just_full"}, {"sample": 0.3}])
def test_exact_search_equals_the_scan(spark, walks, settings, metric):
    _, coll, q = walks
    ix = build_index(coll, BuildParams(w=8, th=20, **settings))
    truth = search.knn_scan(coll, q, 7, metric)
    stats = search.SearchStats()
    assert rows(search.search_exact(ix, q, 7, metric, stats=stats)) == rows(truth)
    natives = ix.data().where("not is_copy")
    assert natives.count() == coll.count() == natives.select("series_id").distinct().count()
    if metric == "ed":
        assert rows(search.search_extended(ix, q, 7, 10**6)) == rows(truth)
        maps = [measures.mean_average_precision(search.search_extended(ix, q, 7, n), truth, 7) for n in (1, 10**6)]
        assert maps[0] <= maps[1] == pytest.approx(1.0)


def test_rounds_over_the_cluster_equal_the_local_build(spark, walks):
    _, coll, _ = walks
    words = written(words_of(coll, P, 64), "words")
    shape = lambda t: sorted((t.pfx_bits[n], t.pfx_len[n], t.size[n]) for n in t.below(0))
    for policy in ("adaptive", "binary", "fullary"):
        p = BuildParams(w=8, th=20, policy=policy)
        local, _, _ = build_tree(words, p)
        spread, _, c = build_tree(words.repartition(7), BuildParams(w=8, th=20, policy=policy, local_limit=21))
        assert shape(local) == shape(spread) and c["rounds"] >= 1


def test_copies_are_bounded_and_never_change_words(spark, walks):
    _, coll, _ = walks
    plain, fuzzy = build_index(coll, BuildParams(w=8, th=20, f=0.0)), build_index(coll, BuildParams(w=8, th=20, f=0.3))
    per = fuzzy.data().groupBy("series_id").agg(F.count_if("is_copy").alias("c"))
    assert 1 <= per.agg(F.max("c")).first()[0] <= 3 and plain.data().where("is_copy").count() == 0
    x, y = (i.data().where("not is_copy").select("series_id", "word") for i in (plain, fuzzy))
    assert x.exceptAll(y).count() == 0


def test_approximate_stops(spark, walks):
    _, coll, q = walks
    ix = build_index(coll, P)
    truth = {(a, b): d for a, b, d in rows(search.knn_scan(coll, q, 3))}
    for a, b, d in rows(search.search_exact(ix, q, 3, epsilon=0.5)):
        assert d <= 1.5 * truth[a, b] + 1e-5
    assert len(rows(search.search_exact(ix, q, 3, epsilon=0.5, delta=0.9))) == len(truth)
    stats = search.SearchStats()
    search.search_budget(ix, q, 3, 2, stats=stats)
    assert max(stats.leaves.values()) <= 2
    steps = list(search.search_progressive(ix, q, 3))
    assert rows(steps[-1]) == [(a, b, d) for (a, b), d in sorted(truth.items())]
    near = search.search_radius(ix, q, 5.0)
    scan = search.knn_scan(coll, q, 10**6).where("distance <= 5.0")
    assert sorted((r[0], r[1]) for r in near.select("query_id", "series_id").collect()) == sorted((r[0], r[1]) for r in scan.select("query_id", "series_id").collect())


def test_small_and_odd_inputs(spark):
    bad = [(1, [1.0, 2.0, 3.0, 4.0]), (2, [1.0, 2.0]), (3, None), (4, [1.0, float("nan"), 2.0, 3.0]), (5, [1.0, None, 2.0, 3.0]), (None, [1.0] * 4), (6, [4.0, 1.0, 0.0, 2.0])]
    df = spark.createDataFrame(bad, "series_id long, values array<double>")
    good, rejected, n = checked(df)
    assert n == 4 and good.count() == 2 and rejected.count() == 5
    q = spark.createDataFrame([(9, [1.0, 2.0, 3.0, 4.0]), (10, [0.0, 0.0])], "query_id long, values array<double>")
    for w in (1, 4):
        ix = build_index(df, BuildParams(w=w, th=10))
        found = search.search_exact(ix, q, 5).collect()
        assert [(r["query_id"], r["rank"], r["series_id"]) for r in found] == [(9, 1, 1), (9, 2, 6)] and found[0]["distance"] == 0
    with pytest.raises(ValueError):
        build_index(spark.createDataFrame([], "series_id long, values array<double>"), P)
    assert search.knn_scan(spark.createDataFrame([], "series_id long, values array<double>"), q, 3).count() == 0


def test_save_and_load(spark, walks, tmp_path):
    _, coll, q = walks
    ix = build_index(coll, P)
    again = load_index(spark, ix.save(str(tmp_path / "ix")))
    assert rows(search.search_exact(again, q, 4)) == rows(search.search_exact(ix, q, 4)) and again.nodes().count() == len(ix.tree)


# ---- updates ----


@pytest.mark.parametrize("policy", ["adaptive", "binary", "dynseg"])
def test_updates(spark, walks, policy):
    _, coll, q = walks
    first = coll.where("series_id % 2 = 0")
    ix = build_index(first, BuildParams(w=8, th=10, policy=policy))
    update.insert(ix, coll.where("series_id % 2 = 1"), 1)
    update.insert(ix, coll.where("series_id % 2 = 1"), 1)  # the same batch again
    assert ix.data().where("not is_copy").count() == coll.count()
    truth = rows(search.knn_scan(coll, q, 5))
    assert rows(search.search_exact(ix, q, 5)) == truth
    old = ix.copy()
    update.reorganize(ix)
    assert rows(search.search_exact(ix, q, 5)) == truth == rows(search.search_exact(old, q, 5))
    assert ix.data().where("not is_copy").count() == coll.count()
    gone = coll.where("series_id % 5 = 0").select("series_id")
    left = rows(search.knn_scan(coll.where("series_id % 5 <> 0"), q, 5))
    update.delete(ix, gone)
    assert rows(search.search_exact(ix, q, 5)) == left
    update.vacuum(ix)
    assert rows(search.search_exact(ix, q, 5)) == left and ix.tombstones is None


def test_packs_are_taken_apart_and_made_again(spark, walks):
    _, coll, q = walks
    ix = build_index(coll, BuildParams(w=8, th=60))
    truth = rows(search.search_exact(ix, q, 5))
    pack = max((n for n in ix.tree.below(0) if ix.tree.kind[n] == "pack"), key=lambda n: len(ix.tree.members[n]))
    update.extract(ix, pack, ix.tree.members[pack][0])
    assert rows(search.search_exact(ix, q, 5)) == truth
    update.repack(ix, ix.tree.parent[pack])
    assert rows(search.search_exact(ix, q, 5)) == truth and ix.data().where("not is_copy").count() == coll.count()


# ---- measures and sources ----


def test_measures(spark):
    truth = spark.createDataFrame([(1, i, i, float(i)) for i in (1, 2, 3)], search.ANSWERS)
    found = spark.createDataFrame([(1, 1, 1, 1.0), (1, 2, 9, 4.0), (1, 3, 3, 3.0)], search.ANSWERS)
    assert measures.mean_average_precision(found, truth, 3) == pytest.approx((1 + 2 / 3) / 3) and measures.recall_at_k(found, truth, 3) == pytest.approx(2 / 3)
    assert measures.error_ratio(found, truth, 3) == pytest.approx((1 + 2 + 1) / 3) and measures.improvement(3, 2) == 50


def test_raw_files(spark, tmp_path):
    x = np.arange(24, dtype="<f4").reshape(4, 6)
    (tmp_path / "a.bin").write_bytes(x.tobytes() + b"\0\0")
    got = rawfloat.read_raw(spark, str(tmp_path / "a.bin"), 6).orderBy("record").collect()
    assert [r["values"] for r in got] == x.tolist()
    rawfloat.register(spark)
    again = spark.read.format("rawseries").option("path", str(tmp_path / "a.bin")).option("length", "6").option("block", "3").load()
    assert [r["values"] for r in again.orderBy("series_id").collect()] == x.tolist()


def test_walks_do_not_depend_on_partitions(spark):
    a = builders.synthetic_walks(spark, 50, 16).orderBy("series_id").collect()
    assert a == builders.synthetic_walks(spark, 50, 16).repartition(3).orderBy("series_id").collect()
    sub = builders.windows_of(spark.createDataFrame([(1, [float(i) for i in range(10)])], "series_id long, values array<double>"), 4, 3)
    assert [(r["offset"], r["values"][0]) for r in sub.orderBy("offset").collect()] == [(0, 0.0), (3, 3.0), (6, 6.0)]


def test_growth_needs_no_order(spark):
    rng = np.random.default_rng(8)
    words = S.words_rows(S.znormalize_rows(np.cumsum(rng.standard_normal((300, 64)), 1)), 8, 8)
    p = BuildParams(w=8, th=20)
    a, _, _ = grow(words, np.ones(300, bool), np.zeros(300, int), [0] * 8, [0] * 8, p, "x")
    b, _, _ = grow(words[::-1], np.ones(300, bool), np.zeros(300, int), [0] * 8, [0] * 8, p, "x")
    assert sorted((a.pfx_bits[n], a.size[n]) for n in a.below(0)) == sorted((b.pfx_bits[n], b.size[n]) for n in b.below(0))


def test_levels_end_a_tree(spark):
    s = written(builders.synthetic_walks(spark, 600, 32), "walks")
    deep = build_index(s, BuildParams(w=8, th=5, packing="none")).tree
    ix = build_index(s, BuildParams(w=8, th=5, packing="none", levels=1, local_limit=10))
    t, at = ix.tree, build_index(s, BuildParams(w=8, th=5, packing="none", levels=2)).tree
    assert max(deep.depth) > 2 and max(t.depth) == 1 and max(at.depth) == 2
    assert {(t.pfx_bits[n], t.pfx_len[n], t.size[n]) for n in range(len(t))} == {(deep.pfx_bits[n], deep.pfx_len[n], deep.size[n]) for n in range(len(deep)) if deep.depth[n] <= 1}
    assert sum(t.size[n] for n in t.below(0)) == 600 and update.reorganize(ix).tree is t


def test_a_very_full_cell_asks_for_more_segments_than_there_are():
    assert fanout_asked(40_000, 40, 0.5, 3.0, 8) == (9, 9) and fanout_range(40_000, 40, 0.5, 3.0, 8) == (8, 8)
    for size in range(1, 30_721, 97):
        assert fanout_asked(size, 40, 0.5, 3.0, 8) == fanout_range(size, 40, 0.5, 3.0, 8)


def test_pairs_on_arrays_are_those_of_one_query_at_a_time():
    r = np.random.default_rng(5)
    x, z = S.znormalize_rows(r.standard_normal((70, 64)).cumsum(1)), S.znormalize_rows(r.standard_normal((9, 64)).cumsum(1))
    x[3] = z[2]
    words, q = S.words_rows(x, 8, 8), [D.QuerySummary(v, 8, "dtw") for v in z]
    u, l, hi, lo = (np.array([getattr(s, f) for s in q]) for f in ("upper", "lower", "hi", "lo"))
    ends = S.edges(8)
    assert np.allclose(D.ed_pairs(x, z).T, [D.ed_rows(x, v) for v in z]) and D.ed_pairs(x, z)[3, 2] == 0
    assert np.allclose(D.lb_envelope_pairs(x, u, l).T, [D.lb_envelope_rows(x, s.upper, s.lower) for s in q])
    assert np.allclose(D.mindist_word_pairs(words, 8, hi, lo, 64).T, [D.mindist_cells_rows(s.hi, s.lo, ends[words.astype(int)], ends[words.astype(int) + 1], 64) for s in q])
    m = S.paa_rows(x, 8)
    assert np.allclose(D.mindist_paa_pairs(m, m[:4], 64), np.sqrt(8 * ((m[:, None] - m[None, :4]) ** 2).sum(2)))
