"""Baseline tree over dynamic segmentations: nodes keep ranges of segment means and deviations.

A split either divides the members at the middle of one segment's range of means or
deviations, or first halves a segment and divides on one half.  The split with the largest
drop of the size-weighted total of length x (mean range ^ 2 + largest deviation ^ 2) is
taken.  Two children a split, no packing; raw values are needed to decide.
"""

from __future__ import annotations

import numpy as np

from .params import BuildParams


class _Sums:
    """Prefix sums of values and squares, for means and deviations of any segment."""

    def __init__(self, x: np.ndarray):
        zero = np.zeros((len(x), 1))
        self.one, self.two = np.concatenate((zero, np.cumsum(x, 1)), 1), np.concatenate((zero, np.cumsum(x * x, 1)), 1)

    def stats(self, lo: int, hi: int, rows=slice(None)) -> tuple[np.ndarray, np.ndarray]:
        m = (self.one[rows, hi] - self.one[rows, lo]) / (hi - lo)
        return m, np.sqrt(np.maximum((self.two[rows, hi] - self.two[rows, lo]) / (hi - lo) - m * m, 0.0))


class DynTree:
    """Nodes as parallel lists; node 0 is the root.  rule: (lo, hi, on deviation, threshold)."""

    def __init__(self, n: int):
        self.n = n
        self.parent, self.depth, self.cuts, self.rule, self.kids, self.size, self.synopsis, self.oversize = ([] for _ in range(8))
        self.leaf_id: list[int] = []

    def __len__(self) -> int:
        return len(self.parent)

    def add(self, parent: int, cuts: tuple[int, ...], size: int, synopsis: np.ndarray) -> int:
        for field, value in zip((self.parent, self.depth, self.cuts, self.rule, self.kids, self.size, self.synopsis, self.oversize), (parent, self.depth[parent] + 1 if parent >= 0 else 0, cuts, None, (), size, synopsis, False)):
            field.append(value)
        return len(self) - 1

    def is_leaf(self, node: int) -> bool:
        return not self.kids[node]

    def children(self, node: int) -> list[int]:
        return list(self.kids[node])

    def route_values(self, x: np.ndarray) -> np.ndarray:
        out, sums = np.zeros(len(x), np.int64), _Sums(np.asarray(x, np.float64))
        stack = [(0, np.arange(len(x)))]
        while stack:
            node, at = stack.pop()
            out[at] = node
            if self.is_leaf(node) or not len(at):
                continue
            lo, hi, dev, cut = self.rule[node]
            right = sums.stats(lo, hi, at)[1 if dev else 0] > cut
            stack += [(self.kids[node][0], at[~right]), (self.kids[node][1], at[right])]
        return out

    def number_leaves(self) -> None:
        self.leaf_id, stack, k = [-1] * len(self), [0] if len(self) else [], 0
        while stack:
            node = stack.pop()
            if self.is_leaf(node):
                self.leaf_id[node], k = k, k + 1
            else:
                stack += reversed(self.kids[node])
        self.last_leaf_id = k - 1

    def leaf_nodes(self) -> list[int]:
        return sorted((n for n in range(len(self)) if self.is_leaf(n)), key=lambda n: self.leaf_id[n])

    def leaves(self):
        nodes = np.array(self.leaf_nodes(), np.int64)
        return nodes, np.array([self.leaf_id[n] for n in nodes], np.int64), None, None, np.array([self.size[n] for n in nodes], np.int64)

    def bounds(self, query, of=None) -> np.ndarray:
        of = self.leaf_nodes() if of is None else of
        if len(of) < 2:
            return np.array([mindist_eapca(query, self.cuts[n], self.synopsis[n]) for n in of])
        ends = np.array([(lo, hi) for n in of for lo, hi in zip(self.cuts[n][:-1], self.cuts[n][1:])])
        return bounds_eapca(query, np.repeat(np.arange(len(of)), [len(self.cuts[n]) - 1 for n in of]), ends, np.concatenate([self.synopsis[n] for n in of]))

    below = None  # set after the class: shared with the word tree

    def path(self, summary_words, values: np.ndarray) -> list[int]:
        node, out = int(self.route_values(values[None])[0]), []
        while node >= 0:
            out.append(node)
            node = self.parent[node]
        return out[::-1]


def _below(self, node: int) -> list[int]:
    out, stack = [], [node]
    while stack:
        n = stack.pop()
        if self.is_leaf(n):
            out.append(n)
        else:
            stack += reversed(self.children(n))
    return out


DynTree.below = _below


def mindist_eapca(query, cuts, synopsis: np.ndarray) -> float:
    """Lower bound from ranges of means and deviations; synopsis rows: min, max mean, min, max deviation.

    Under warping (radius > 0) only means are used, of the query's envelope.
    """
    x = query.values
    total = 0.0
    for (lo, hi), (m0, m1, d0, d1) in zip(zip(cuts[:-1], cuts[1:]), synopsis):
        if query.radius:
            up, low = query.upper[lo:hi].mean(), query.lower[lo:hi].mean()
            total += (hi - lo) * max(m0 - up, low - m1, 0.0) ** 2
        else:
            m, d = x[lo:hi].mean(), x[lo:hi].std()
            total += (hi - lo) * (max(m0 - m, m - m1, 0.0) ** 2 + max(d0 - d, d - d1, 0.0) ** 2)
    return float(np.sqrt(total))


def bounds_eapca(query, node: np.ndarray, ends: np.ndarray, synopsis: np.ndarray) -> np.ndarray:
    """:func:`mindist_eapca` of nodes 0, 1, ... at once, from one row a segment: its node, its ends, its synopsis.
    The query's means and deviations are taken once for each pair of ends that occurs."""
    key, at = np.unique(ends[:, 0] * (query.n + 1) + ends[:, 1], return_inverse=True)
    pairs = [divmod(int(k), query.n + 1) for k in key]
    m0, m1, d0, d1 = synopsis.T
    if query.radius:
        up, low = (np.array([v[a:b].mean() for a, b in pairs])[at] for v in (query.upper, query.lower))
        gap = np.maximum(np.maximum(m0 - up, low - m1), 0.0) ** 2
    else:
        m, d = np.array([(query.values[a:b].mean(), query.values[a:b].std()) for a, b in pairs])[at].T
        gap = np.maximum(np.maximum(m0 - m, m - m1), 0.0) ** 2 + np.maximum(np.maximum(d0 - d, d - d1), 0.0) ** 2
    return np.sqrt(np.bincount(node, (ends[:, 1] - ends[:, 0]) * gap))


def _synopsis(sums: _Sums, rows: np.ndarray, cuts) -> np.ndarray:
    out = []
    for lo, hi in zip(cuts[:-1], cuts[1:]):
        m, d = sums.stats(lo, hi, rows)
        out.append((m.min(), m.max(), d.min(), d.max()) if len(m) else (0.0, 0.0, 0.0, 0.0))
    return np.array(out)


def _spread(m: np.ndarray, d: np.ndarray, length: int) -> float:
    return length * ((m.max() - m.min()) ** 2 + d.max() ** 2) if len(m) else 0.0


def grow_dynseg(x: np.ndarray, p: BuildParams, segments: int = 4) -> tuple[DynTree, np.ndarray]:
    """(tree, leaf node of each row) over raw (normalised) values."""
    n = x.shape[1]
    tree, sums, at_leaf = DynTree(n), _Sums(np.asarray(x, np.float64)), np.zeros(len(x), np.int64)
    cuts = tuple(sorted({round(i * n / segments) for i in range(segments + 1)}))
    tree.add(-1, cuts, len(x), _synopsis(sums, np.arange(len(x)), cuts))
    stack = [(0, np.arange(len(x)))]
    while stack:
        node, rows = stack.pop()
        if len(rows) <= p.th:
            at_leaf[rows] = node
            continue
        best = None
        cuts = tree.cuts[node]
        for lo, hi in zip(cuts[:-1], cuts[1:]):
            middle = (lo + hi) // 2
            m, d = sums.stats(lo, hi, rows)
            whole = _spread(m, d, hi - lo)
            options = [(lo, hi, cuts)]
            if hi - lo >= 2:
                finer = tuple(sorted({*cuts, middle}))
                options += [(lo, middle, finer), (middle, hi, finer)]
            for a, b, new_cuts in options:
                am, ad = (m, d) if (a, b) == (lo, hi) else sums.stats(a, b, rows)
                for dev, v in enumerate((am, ad)):
                    cut = (v.min() + v.max()) / 2
                    right = v > cut
                    if not right.any() or right.all():
                        continue
                    after = 0.0
                    for side in (right, ~right):
                        parts = [(lo, hi)] if new_cuts == cuts else [(lo, middle), (middle, hi)]
                        after += side.sum() * sum(_spread(*(s[side] for s in ((am, ad) if (q, t) == (a, b) else sums.stats(q, t, rows))), t - q) for q, t in parts)
                    gain = whole - after / len(rows)
                    if best is None or gain > best[0] + 1e-12:
                        best = (gain, (a, b, dev, float(cut)), new_cuts, right)
        if best is None:
            tree.oversize[node] = True
            at_leaf[rows] = node
            continue
        _, tree.rule[node], new_cuts, right = best
        kids = []
        for side in (rows[~right], rows[right]):
            kids.append(tree.add(node, new_cuts, len(side), _synopsis(sums, side, new_cuts)))
            stack.append((kids[-1], side))
        tree.kids[node] = tuple(kids)
    tree.number_leaves()
    return tree, at_leaf
