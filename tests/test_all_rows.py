"""Searches and bounds of every row with an id divisible by 50 against all rows, by brute force."""

import numpy as np
import pytest

from series_engine import queries
from series_engine.functions import distances as D
from series_engine.functions import summaries as S
from series_engine.sources import builders


@pytest.fixture(scope="module")
def data(spark, sf_dir):
    def load(name):
        rows = builders.BUILDERS[name](spark, sf_dir).select("series_id", S.znormalize("values").alias("z")).collect()
        ids, z = np.array([r["series_id"] for r in rows]), np.array([r["z"] for r in rows])
        return ids, z, [i for i in ids.tolist() if i % 50 == 0]

    return {name: load(name) for name in ("walks", "vectors")}


@pytest.mark.parametrize("name, table, k", [("exact_ed_adaptive_all_rows", "walks", 10), ("exact_fuzzy_all_rows", "walks", 10), ("knn_scan_ed_all_rows", "vectors", 5)])
def test_answers(spark, sf_dir, data, monkeypatch, name, table, k):
    monkeypatch.setattr(queries, "_BLOCK", 2)
    ids, z, asked = data[table]
    got = {(r["query_id"], r["rank"]): r["distance"] for r in queries.QUERIES[name](spark, sf_dir).collect()}
    want = {(q, i + 1): d for q in asked for i, d in enumerate(np.sort(np.sqrt(((z - z[ids == q][0]) ** 2).sum(1)))[:k].tolist())}
    assert asked and got.keys() == want.keys() and all(abs(got[x] - want[x]) < 2e-5 for x in want)


@pytest.mark.parametrize("name", ["extended_1", "extended_5", "extended_25", "budget_search", "epsilon_search", "delta_epsilon_search"])
def test_every_query_is_answered(spark, sf_dir, data, name):
    rows = queries.QUERIES[name](spark, sf_dir).collect()
    assert {r["query_id"] for r in rows} == set(data["walks"][2])
    assert all(r["distance"] < 1e-5 for r in rows if r["rank"] == 1)  # a row is in its own leaf


def test_pairs_and_bounds(spark, sf_dir, data):
    ids, z, asked = data["walks"]
    got = {(r["query_id"], r["series_id"]): r["distance"] for r in queries.QUERIES["ed_pairs_all_rows"](spark, sf_dir).collect()}
    assert got.keys() == {(q, i) for q in asked for i in ids.tolist()}
    assert all(abs(got[q, i] - np.sqrt(((z[ids == i][0] - z[ids == q][0]) ** 2).sum())) < 2e-6 for q, i in got)
    rows = queries.QUERIES["bound_violations_all_rows"](spark, sf_dir).collect()
    assert {(r["query_id"], r["pairs"], r["above"]) for r in rows} == {(q, len(ids), 0) for q in asked}


def test_pairs_by_tiles():
    """More rows and queries than a tile, points that no step divides, equal and nearly equal rows, open cells."""
    rng = np.random.default_rng(3)
    q = S.znormalize_rows(np.cumsum(rng.standard_normal((D._TILE_QUERIES + 9, 61)), 1))
    x = np.concatenate((q[:3], q[3:6] + 1e-7, S.znormalize_rows(np.cumsum(rng.standard_normal((D._TILE_ROWS + 5, 61)), 1))))
    plain = np.array([D.ed_rows(x, v) for v in q]).T
    assert np.allclose(D.ed_products(x, q), plain, rtol=1e-9, atol=1e-12) and (D.ed_products(x, q)[range(3), range(3)] == 0).all()
    assert np.allclose(D.ed_pairs(x, q), plain, rtol=1e-12, atol=1e-12)
    u, l = S.envelope_rows(q, 6)  # noqa: E741
    assert np.allclose(D.lb_envelope_pairs(x, u, l).T, [D.lb_envelope_rows(x, a, b) for a, b in zip(u, l)])
    m, ends = rng.standard_normal((len(q), 7)), np.array([-np.inf, *S.breakpoints(3), np.inf])
    words = rng.integers(0, 8, (len(x), 7))
    for hi, lo in ((m, m), (m + 0.2, m - 0.1)):
        assert np.allclose(D.mindist_word_pairs(words, 3, hi, lo, 63).T, [D.mindist_cells_rows(a, b, ends[words], ends[words + 1], 63) for a, b in zip(hi, lo)])
