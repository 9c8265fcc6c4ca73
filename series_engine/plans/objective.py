"""Which segments a node splits on: score of a plan, and the search for the best plan.

A plan is a set of segments.  Its score grows with the spread of the series along its
segments and with the evenness of the cells it makes; cells over the leaf capacity count
against it.  The search works on arrays with one axis of length two for each segment that
still has bits: the sizes that a plan's cells would have are sums over the axes that it
lacks, so each plan is derived from one that has one segment more, level by level.
"""

from __future__ import annotations

from dataclasses import dataclass
from itertools import combinations

import numpy as np


@dataclass
class SearchCost:
    plans_scored: int = 0
    cells_touched: int = 0


def plan_score(seg_var: np.ndarray, sizes: np.ndarray, th: int, alpha: float) -> np.ndarray:
    """Scores of plans given along the first axis: variances of their segments, sizes of all their cells."""
    seg_var, sizes = np.atleast_2d(seg_var), np.atleast_2d(sizes)
    spread = np.exp(np.sqrt(seg_var.mean(axis=1)))
    fill = sizes / th
    return spread + alpha * np.exp(-(1 + (sizes > th).mean(axis=1)) * fill.std(axis=1))


def fanout_asked(size: int, th: int, f_low: float, f_high: float, w: int) -> tuple[int, int]:
    """Least and most segments that leaves of the wanted fill ask for; the least may be more than the ``w`` there are."""
    low = max(1, int(np.ceil(np.log2(size / (f_high * th)) - 1e-12)))
    most = int(np.floor(np.log2(size / (f_low * th)) + 1e-12))
    return low, max(low, min(w, most))


def fanout_range(size: int, th: int, f_low: float, f_high: float, w: int) -> tuple[int, int]:
    """Least and most segments of a split of ``size`` series when ``w`` segments have bits left."""
    low, high = fanout_asked(size, th, f_low, f_high, w)
    return min(w, low), min(w, high)


def marginalize(sizes: np.ndarray, plan: tuple[int, ...], keep: tuple[int, ...]) -> np.ndarray:
    """Cell sizes of the sub-plan ``keep`` from those of ``plan`` (first segment is the highest bit)."""
    gone = tuple(i for i, s in enumerate(plan) if s not in keep)
    return sizes.reshape((2,) * len(plan)).sum(axis=gone).reshape(-1)


def base_distribution(bits_next: np.ndarray) -> np.ndarray:
    """Counts of all combinations of next bits; rows are series, columns usable segments."""
    k = bits_next.shape[1]
    sid = bits_next.astype(np.int64) @ (1 << np.arange(k - 1, -1, -1, dtype=np.int64))
    return np.bincount(sid, minlength=1 << k)


def choose_plan(seg_var: np.ndarray, base: np.ndarray, usable: tuple[int, ...], size: int, th: int, alpha: float, f_low: float, f_high: float, search: str = "restricted", skip_degenerate: bool = False, cost: SearchCost | None = None, byte_budget: int = 64 << 20, codes: np.ndarray | None = None) -> tuple[int, ...]:
    """The plan with the best score; larger plans win ties, then the lexicographically first.

    seg_var: variance of each usable segment; base: counts over all combinations of the
    usable segments' next bits.  "exhaustive" tries all sizes of plans; "flat" sums every
    plan's cells from the base again; "rescan" counts them over all series (``codes``: the
    next bits by series and segment), as a search without any counts to reuse must.
    """
    w, cost = len(usable), cost if cost is not None else SearchCost()
    low, high = (1, w) if search == "exhaustive" else fanout_range(size, th, f_low, f_high, w)
    cube = base.reshape((2,) * w)
    best: tuple | None = None
    above: dict[tuple[int, ...], np.ndarray] = {}
    for lam in range(high, low - 1, -1):
        plans = list(combinations(range(w), lam))
        room = max(1, byte_budget // (8 << lam))
        level: dict[tuple[int, ...], np.ndarray] = {}
        for at in range(0, len(plans), room):
            part = plans[at : at + room]
            cells = []
            for plan in part:
                lacking = [s for s in range(w) if s not in plan]
                parent = tuple(sorted((*plan, lacking[0]))) if lacking else None  # the one superset that each plan comes from
                if codes is not None and search == "rescan":
                    got = base_distribution(codes[:, list(plan)])
                    cost.cells_touched += len(codes)
                elif search not in ("flat", "rescan") and parent in above:
                    got = above[parent].sum(axis=parent.index(lacking[0]))
                    cost.cells_touched += 2 << lam
                else:
                    got = cube.sum(axis=tuple(lacking)) if lacking else cube
                    cost.cells_touched += 1 << w
                if len(plans) <= room:
                    level[plan] = got
                cells.append(got.reshape(-1))
            sizes = np.stack(cells)
            scores = plan_score(seg_var[np.array(part)], sizes, th, alpha)
            cost.plans_scored += len(part)
            if skip_degenerate:
                scores = np.where(sizes.max(axis=1) == size, -np.inf, scores)
            i = int(np.argmax(scores))  # the first of equals
            if best is None or scores[i] > best[0] + 1e-12:
                best = (float(scores[i]), part[i])
        above = level
    return tuple(usable[s] for s in best[1])
