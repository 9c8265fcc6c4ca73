"""Distances and lower bounds, as column expressions and as array functions."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from .summaries import CAP, breakpoints, cells_rows, envelope_rows

#: A bound prunes only if it exceeds the best distance by more than this.
SLACK = 1e-7
#: Part of the length that a warping path may stray.
BAND = 0.1


def radius_of(n: int, band: float = BAND) -> int:
    return int(np.floor(band * n + 1e-9))


# ---- column expressions -------------------------------------------------------------


def _total(col: Column) -> Column:
    return F.aggregate(col, F.lit(0.0), lambda a, v: a + v)


def ed(a: Column, b: Column) -> Column:
    return F.sqrt(_total(F.zip_with(a, b, lambda x, y: (x.cast("double") - y.cast("double")) * (x.cast("double") - y.cast("double")))))


def _gap(v: Column, lo: Column, hi: Column) -> Column:
    return F.greatest(lo - v, v - hi, F.lit(0.0))


def lb_envelope(upper: Column, lower: Column, candidate: Column) -> Column:
    """Distance of a raw candidate from an envelope; at most its warped distance from the query."""
    both = F.zip_with(F.arrays_zip(lower.alias("l"), upper.alias("u")), candidate, lambda e, v: F.pow(_gap(v.cast("double"), e["l"].cast("double"), e["u"].cast("double")), 2.0))
    return F.sqrt(_total(both))


def _ends(bits: int) -> tuple[Column, Column]:
    cuts = breakpoints(bits)
    lows = F.array(*[F.lit(float(v)) for v in (float("-inf"), *cuts)])
    highs = F.array(*[F.lit(float(v)) for v in (*cuts, float("inf"))])
    return lows, highs


def mindist_word(q_paa: Column, word: Column, bits: int, n: int, w: int) -> Column:
    """Lower bound between a query's segment means and all series with the (full-length) word."""
    lows, highs = _ends(bits)
    return F.sqrt(F.lit(n / w) * _total(F.zip_with(q_paa, word, lambda v, s: F.pow(_gap(v, F.get(lows, s), F.get(highs, s)), 2.0))))


def mindist_paa(p: Column, q: Column, n: int, w: int) -> Column:
    return F.sqrt(F.lit(n / w) * _total(F.zip_with(p, q, lambda a, b: (a - b) * (a - b))))


def mindist_word_dtw(u_paa: Column, l_paa: Column, word: Column, bits: int, n: int, w: int) -> Column:
    """The same under warping: the cell against the band between the envelope's segment means."""
    lows, highs = _ends(bits)
    ends = F.transform(word, lambda s: F.struct(F.get(lows, s).alias("lo"), F.get(highs, s).alias("hi")))
    band = F.zip_with(u_paa, l_paa, lambda u, v: F.struct(u.alias("u"), v.alias("l")))
    return F.sqrt(F.lit(n / w) * _total(F.zip_with(band, ends, lambda b, e: F.pow(F.greatest(e["lo"] - b["u"], b["l"] - e["hi"], F.lit(0.0)), 2.0))))


def leaf_upper_bound(pfx_len: Column, pfx_bits: Column, n: int, w: int, bits: int, cap: float = CAP) -> Column:
    """No two series of the leaf have segment means farther apart than this (open cells closed at the cap)."""
    def width(b, k):
        out = F.lit(2 * cap)
        for length in range(1, bits + 1):
            e = (-cap, *breakpoints(length), cap)
            widths = F.array(*[F.lit(float(y - x)) for x, y in zip(e[:-1], e[1:])])
            out = F.when(k == length, F.get(widths, b)).otherwise(out)
        return out

    return F.sqrt(F.lit(n / w) * _total(F.zip_with(pfx_bits, pfx_len, lambda b, k: F.pow(width(b, k), 2.0))))


# ---- array functions ----------------------------------------------------------------


def ed_rows(x: np.ndarray, q: np.ndarray, bsf: float = np.inf, chunk: int = 64) -> np.ndarray:
    """Distances of all rows from ``q``; rows that pass ``bsf`` on the way are abandoned as infinite."""
    out = np.zeros(len(x))
    alive = np.arange(len(x))
    for at in range(0, x.shape[1], chunk):
        d = x[alive, at : at + chunk] - q[at : at + chunk]
        out[alive] += np.einsum("ij,ij->i", d, d)
        if np.isfinite(bsf):
            alive = alive[out[alive] <= (bsf + SLACK) ** 2]
            if not len(alive):
                break
    if np.isfinite(bsf):
        out[out > (bsf + SLACK) ** 2] = np.inf
    return np.sqrt(out)


def dtw_rows(x: np.ndarray, q: np.ndarray, radius: int) -> np.ndarray:
    """Warped distances of all rows from ``q`` at once: the band's cells in order, rows as the vector."""
    n, m = x.shape[1], len(x)
    before = np.full((m, n + 1), np.inf)
    before[:, 0] = 0.0
    for i in range(n):
        now = np.full((m, n + 1), np.inf)
        for j in range(max(0, i - radius), min(n, i + radius + 1)):
            best = np.minimum(np.minimum(before[:, j], before[:, j + 1]), now[:, j])
            now[:, j + 1] = (q[i] - x[:, j]) ** 2 + best
        before = now
    return np.sqrt(before[:, n])


def lb_envelope_rows(x: np.ndarray, upper: np.ndarray, lower: np.ndarray) -> np.ndarray:
    gap = np.maximum(np.maximum(lower - x, x - upper), 0.0)
    return np.sqrt(np.einsum("ij,ij->i", gap, gap))


def mindist_cells_rows(q_hi: np.ndarray, q_lo: np.ndarray, lo: np.ndarray, hi: np.ndarray, n: int) -> np.ndarray:
    """Bounds of one query (its means, or its envelope's means as q_hi and q_lo) from many cells."""
    gap = np.maximum(np.maximum(lo - q_hi, q_lo - hi), 0.0)
    return np.sqrt(n / lo.shape[1] * (gap**2).sum(axis=1))


def upper_bounds_rows(pfx_bits: np.ndarray, pfx_len: np.ndarray, n: int) -> np.ndarray:
    lo, hi = cells_rows(pfx_bits, pfx_len, CAP)
    return np.sqrt(n / lo.shape[1] * ((hi - lo) ** 2).sum(axis=1))


# Rows against many queries at once: by tiles of rows and queries that stay in a core's cache, a few points at a time.

_TILE_ROWS, _TILE_QUERIES, _POINTS = 32, 512, 8


def _by_point(x: np.ndarray) -> np.ndarray:
    return np.ascontiguousarray(x.T, np.float64)


def _sum_squares(gaps, n: int, m: int, k: int) -> np.ndarray:
    """Roots of the sums of squared gaps over ``n`` points, rows x queries; ``gaps(t, i, j, out)`` fills points x rows x queries."""
    out, room = np.zeros((m, k)), np.empty(_POINTS * _TILE_ROWS * _TILE_QUERIES)
    for a in range(0, m, _TILE_ROWS):
        for b in range(0, k, _TILE_QUERIES):
            i, j = slice(a, min(m, a + _TILE_ROWS)), slice(b, min(k, b + _TILE_QUERIES))
            for c in range(0, n, _POINTS):
                t = slice(c, min(n, c + _POINTS))
                shape = t.stop - c, i.stop - a, j.stop - b
                g = room[: shape[0] * shape[1] * shape[2]].reshape(shape)
                gaps(t, i, j, g)
                out[i, j] += np.einsum("trq,trq->rq", g, g)
    return np.sqrt(out, out=out)


def _outside(low, high, v, out) -> None:
    """How far values lie beside intervals, up to the sign (none inside)."""
    np.minimum(v, high, out=out)
    np.maximum(out, low, out=out)
    np.subtract(out, v, out=out)


def ed_pairs(x: np.ndarray, q: np.ndarray) -> np.ndarray:
    """Distances of all rows of ``x`` from all rows of ``q``."""
    xs, qs = _by_point(x)[:, :, None], _by_point(q)[:, None]
    return _sum_squares(lambda t, i, j, out: np.subtract(xs[t, i], qs[t, :, j], out=out), x.shape[1], len(x), len(q))


#: Pairs whose squared distance is below this part of their squared lengths lose digits in a product.
_NEAR = 1e-3


def ed_products(x: np.ndarray, q: np.ndarray) -> np.ndarray:
    """The same from one product of matrices; near pairs, which lose digits there, are summed point by point."""
    size = np.einsum("ij,ij->i", x, x)[:, None] + np.einsum("ij,ij->i", q, q)
    out = size - x @ (2 * q).T
    i, j = np.nonzero(~(out > _NEAR * size))
    for a in range(0, len(i), 1 << 14):
        d = x[i[a : a + (1 << 14)]] - q[j[a : a + (1 << 14)]]
        out[i[a : a + (1 << 14)], j[a : a + (1 << 14)]] = np.einsum("ij,ij->i", d, d)
    return np.sqrt(out, out=out)


def mindist_paa_pairs(p: np.ndarray, q: np.ndarray, n: int) -> np.ndarray:
    return np.sqrt(n / p.shape[1]) * ed_pairs(p, q)


def mindist_word_pairs(words: np.ndarray, bits: int, q_hi: np.ndarray, q_lo: np.ndarray, n: int) -> np.ndarray:
    """Bounds of all queries (their means, or their envelopes' means as q_hi and q_lo) from all words."""
    ends = np.array([-np.inf, *breakpoints(bits), np.inf])
    at = words.astype(np.int64)
    low, high = _by_point(ends[at])[:, :, None], _by_point(ends[at + 1])[:, :, None]
    above, below = _by_point(q_hi)[:, None], _by_point(q_lo)[:, None]

    def apart(t, i, j, out):
        np.maximum(low[t, i] - above[t, :, j], below[t, :, j] - high[t, i], out=out)
        np.maximum(out, 0.0, out=out)

    def beside(t, i, j, out):
        _outside(low[t, i], high[t, i], below[t, :, j], out)

    return np.sqrt(n / words.shape[1]) * _sum_squares(beside if q_hi is q_lo else apart, words.shape[1], len(words), len(q_hi))


def lb_envelope_pairs(x: np.ndarray, upper: np.ndarray, lower: np.ndarray) -> np.ndarray:
    xs, low, high = _by_point(x)[:, :, None], _by_point(lower)[:, None], _by_point(upper)[:, None]
    return _sum_squares(lambda t, i, j, out: _outside(low[t, :, j], high[t, :, j], xs[t, i], out), x.shape[1], len(x), len(upper))


class QuerySummary:
    """What pruning needs of one query: its values, and under warping its envelope."""

    def __init__(self, values: np.ndarray, w: int, metric: str = "ed", band: float = BAND):
        from .summaries import paa_rows

        self.values, self.metric, self.n = values, metric, len(values)
        self.radius = radius_of(self.n, band) if metric == "dtw" else 0
        self.upper, self.lower = (e[0] for e in envelope_rows(values[None], self.radius))
        self.hi, self.lo = paa_rows(self.upper[None], w)[0], paa_rows(self.lower[None], w)[0]

    def distances(self, x: np.ndarray, bsf: float = np.inf) -> np.ndarray:
        if self.metric == "ed":
            return ed_rows(x, self.values, bsf)
        out = np.full(len(x), np.inf)
        near = np.flatnonzero(lb_envelope_rows(x, self.upper, self.lower) <= bsf + SLACK)
        if len(near):
            out[near] = dtw_rows(x[near], self.values, self.radius)
        return out
