"""Summaries of series as column expressions, with array (numpy) twins for bulk work.

Symbols are cut at quantiles of the standard normal distribution.  Segment means are
rounded to nine places before they become symbols, in expressions, arrays and SQL alike,
so that exact zeros fall on one side.
"""

from __future__ import annotations

from functools import lru_cache
from statistics import NormalDist

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

#: Finite stand-in for the open ends of the outermost cells, where midpoints and widths are asked for.
CAP = 4.0
DIGITS = 9


@lru_cache(maxsize=16)
def breakpoints(bits: int) -> tuple[float, ...]:
    """The 2 ** bits - 1 inner quantiles; those of fewer bits are among those of more."""
    cells = 1 << bits
    return tuple(0.0 if 2 * i == cells else NormalDist().inv_cdf(i / cells) for i in range(1, cells))


def _literals(values) -> Column:
    return F.array(*[F.lit(float(v)) for v in values])


# ---- column expressions -------------------------------------------------------------


def let(value: Column, body) -> Column:
    """``body`` of a value that is computed once: a lambda would compute a column's
    expression again for every element that it is used on."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def _add(col: Column) -> Column:
    return F.aggregate(col, F.lit(0.0), lambda a, v: a + v)


def znormalize(col: Column) -> Column:
    """Mean 0 and population deviation 1; a series without deviation becomes all zeros."""
    def spread(x):
        return let(F.struct(x.alias("x"), (_add(x) / F.size(x)).alias("mean")), lambda s: let(
            F.struct(F.transform(s["x"], lambda v: v - s["mean"]).alias("d")), lambda t: let(
                F.struct(t["d"].alias("d"), (F.aggregate(t["d"], F.lit(0.0), lambda a, v: a + v * v) / F.size(t["d"])).alias("var")),
                lambda u: F.transform(u["d"], lambda v: F.when(u["var"] > 1e-18, v / F.sqrt(u["var"])).otherwise(0.0)))))

    return let(F.transform(col, lambda v: v.cast("double")), spread)


def paa(col: Column, w: int, n: int, allow_ragged: bool = False) -> Column:
    """Means of ``w`` segments of a series of length ``n``.

    Lengths that ``w`` does not divide are refused unless ``allow_ragged``: then each
    point counts for the segments it reaches into by its share.
    """
    if n % w and not allow_ragged:
        raise ValueError(f"{w} segments do not divide a length of {n}")
    if n % w == 0:
        m = n // w
        return let(col, lambda x: F.transform(F.sequence(F.lit(0), F.lit(w - 1)), lambda i: F.aggregate(F.slice(x, i * m + 1, m), F.lit(0.0), lambda a, v: a + v.cast("double")) / m))
    weights = _ragged_weights(w, n)
    return let(col, lambda x: F.array(*[_add(F.zip_with(x, _literals(row), lambda v, p: v.cast("double") * p)) for row in weights]))


def _ragged_weights(w: int, n: int) -> np.ndarray:
    m = n / w
    at = np.arange(n)
    return np.array([np.clip(np.minimum(at + 1, (i + 1) * m) - np.maximum(at, i * m), 0, 1) / m for i in range(w)])


def sax(paa_col: Column, bits: int) -> Column:
    """Symbols 0 .. 2 ** bits - 1: how many breakpoints are at or below the mean."""
    cuts = _literals(breakpoints(bits))
    return F.transform(paa_col, lambda v: F.size(F.filter(cuts, lambda b: b <= F.round(v, DIGITS))))


def prefix(word: Column, lengths, bits: int) -> Column:
    """The first ``lengths[i]`` bits of each symbol; zero bits match everything."""
    lens = F.array(*[F.lit(int(x)) for x in lengths])
    # shifts by a column: a product with a power of two, floored
    return F.zip_with(word, lens, lambda s, k: F.floor(s / F.pow(F.lit(2.0), F.lit(bits) - k)).cast("int"))


def promote(word: Column, lengths, csl, bits: int) -> Column:
    """The bits that the chosen segments gain next, concatenated (first segment highest)."""
    out = F.lit(0)
    for s in csl:
        bit = F.shiftright(F.get(word, F.lit(s)), bits - lengths[s] - 1).bitwiseAND(F.lit(1))
        out = out * 2 + bit
    return out


def interleave(word: Column, w: int, bits: int) -> Column:
    """Bits of all symbols, most significant first, segment by segment, as a string of 0 and 1."""
    parts = [F.shiftright(F.get(word, F.lit(s)), b).bitwiseAND(F.lit(1)).cast("string") for b in range(bits - 1, -1, -1) for s in range(w)]
    return F.concat(*parts)


def hex_word(word: Column) -> Column:
    return F.array_join(F.transform(word, lambda s: F.lpad(F.lower(F.hex(s.cast("long"))), 2, "0")), "")


def eapca(col: Column, cuts) -> Column:
    """(lo, hi, mean, population deviation) of the segments that begin at ``cuts`` (the last one is the length)."""
    def part(x, lo, hi):
        y = F.transform(F.slice(x, lo + 1, hi - lo), lambda v: v.cast("double"))
        sums = F.aggregate(y, F.struct(F.lit(0.0).alias("s"), F.lit(0.0).alias("q")), lambda a, v: F.struct((a["s"] + v).alias("s"), (a["q"] + v * v).alias("q")))
        return let(sums, lambda a: F.struct(F.lit(lo).alias("lo"), F.lit(hi).alias("hi"), (a["s"] / (hi - lo)).alias("mean"), F.sqrt(F.greatest(a["q"] / (hi - lo) - F.pow(a["s"] / (hi - lo), 2.0), F.lit(0.0))).alias("std")))

    return let(col, lambda x: F.array(*[part(x, a, b) for a, b in zip(cuts[:-1], cuts[1:])]))


def envelope(col: Column, radius: int) -> Column:
    """Struct of the running maximum and minimum over ``radius`` points to both sides."""
    def both(x):
        at = F.sequence(F.lit(1), F.size(x))
        part = lambda i: F.slice(x, F.greatest(i - radius, F.lit(1)), F.least(i + radius, F.size(x)) - F.greatest(i - radius, F.lit(1)) + 1)
        return F.struct(F.transform(at, lambda i: F.array_max(part(i))).alias("upper"), F.transform(at, lambda i: F.array_min(part(i))).alias("lower"))

    return let(col, both)


# ---- array twins --------------------------------------------------------------------


def znormalize_rows(x: np.ndarray) -> np.ndarray:
    x = np.asarray(x, np.float64)
    mean = x.mean(axis=1, keepdims=True)
    var = ((x - mean) ** 2).mean(axis=1, keepdims=True)
    return np.where(var > 1e-18, (x - mean) / np.sqrt(np.where(var > 1e-18, var, 1.0)), 0.0)


def paa_rows(x: np.ndarray, w: int) -> np.ndarray:
    n = x.shape[1]
    return x.reshape(len(x), w, n // w).mean(axis=2) if n % w == 0 else x @ _ragged_weights(w, n).T


def sax_rows(means: np.ndarray, bits: int) -> np.ndarray:
    return np.searchsorted(np.array(breakpoints(bits)), np.round(means, DIGITS), side="right").astype(np.uint8)


def words_rows(x: np.ndarray, w: int, bits: int) -> np.ndarray:
    return sax_rows(paa_rows(x, w), bits)


def envelope_rows(x: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    upper, lower, n = x.copy(), x.copy(), x.shape[1]
    for d in range(1, min(radius, n - 1) + 1):
        upper[:, :-d] = np.maximum(upper[:, :-d], x[:, d:])
        upper[:, d:] = np.maximum(upper[:, d:], x[:, :-d])
        lower[:, :-d] = np.minimum(lower[:, :-d], x[:, d:])
        lower[:, d:] = np.minimum(lower[:, d:], x[:, :-d])
    return upper, lower


@lru_cache(maxsize=64)
def edges(bits: int, cap: float | None = None) -> np.ndarray:
    """All cell ends of an alphabet, outermost ones infinite or at +-cap."""
    end = np.inf if cap is None else cap
    return np.concatenate(([-end], breakpoints(bits), [end])) if bits else np.array([-end, end])


def cell(symbol, length: int, bits: int, cap: float | None = CAP) -> tuple[float, float, float]:
    """(low end, high end, middle) of the values whose symbol begins with the ``length`` bits ``symbol``."""
    e = edges(length, cap)
    lo, hi = float(e[int(symbol)]), float(e[int(symbol) + 1])
    return lo, hi, (lo + hi) / 2


@lru_cache(maxsize=16)
def midpoints(bits: int) -> np.ndarray:
    """Middle of each full symbol's cell, outermost cells closed at +-CAP."""
    e = edges(bits, CAP)
    return (e[:-1] + e[1:]) / 2


def cells_rows(pfx_bits: np.ndarray, pfx_len: np.ndarray, cap: float | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Low and high ends for arrays of prefixes."""
    lo, hi = np.empty(pfx_bits.shape), np.empty(pfx_bits.shape)
    for k in np.unique(pfx_len):
        at = pfx_len == k
        e = edges(int(k), cap)
        lo[at], hi[at] = e[pfx_bits[at]], e[pfx_bits[at] + 1]
    return lo, hi
