"""The node table of a word tree, and the growth of a subtree from words alone."""

from __future__ import annotations

import numpy as np

from ..functions.summaries import CAP, breakpoints, cells_rows, edges, midpoints
from .objective import SearchCost, base_distribution, choose_plan
from .pack import pack_by_size, pack_leaves, pack_prefix
from .params import BuildParams

ROOT, INTERNAL, LEAF, PACK = "root", "internal", "leaf", "pack"


class WordTree:
    """Nodes as parallel lists; number 0 is the root of the (sub)tree."""

    FIELDS = ("parent", "depth", "kind", "csl", "pfx_bits", "pfx_len", "size", "n_copies", "routes", "members", "oversize")

    def __init__(self, w: int, bits: int):
        self.w, self.bits = w, bits
        for f in self.FIELDS:
            setattr(self, f, [])
        self.leaf_id: list[int] = []
        self.last_leaf_id = -1  # ids are never used again
        self._leaves = None

    def __len__(self) -> int:
        return len(self.parent)

    def add(self, parent: int, kind: str, pfx_bits, pfx_len, size: int, members=(), n_copies: int = 0, oversize: bool = False) -> int:
        self.parent.append(parent)
        self.depth.append(self.depth[parent] + 1 if parent >= 0 else 0)
        self.kind.append(kind)
        self.csl.append(())
        self.pfx_bits.append(tuple(int(b) for b in pfx_bits))
        self.pfx_len.append(tuple(int(b) for b in pfx_len))
        self.size.append(int(size))
        self.n_copies.append(int(n_copies))
        self.routes.append({})
        self.members.append(tuple(int(m) for m in members))
        self.oversize.append(oversize)
        self._leaves = None
        return len(self.parent) - 1

    def is_leaf(self, node: int) -> bool:
        return not self.csl[node]

    def children(self, node: int) -> list[int]:
        """In the order of their least sid."""
        return list(dict.fromkeys(child for _, child in sorted(self.routes[node].items())))

    def sids(self, node: int, words: np.ndarray) -> np.ndarray:
        """Next bits of the words on the node's segments; words outside of its cells count as its nearest."""
        csl, lens = self.csl[node], self.pfx_len[node]
        lo = np.array([b << (self.bits - k) for b, k in zip(self.pfx_bits[node], lens)])[list(csl)]
        hi = lo + np.array([(1 << (self.bits - lens[s])) - 1 for s in csl])
        part = np.clip(words[:, list(csl)].astype(np.int64), lo, hi)
        shift = np.array([self.bits - lens[s] - 1 for s in csl])
        return ((part >> shift) & 1) @ (1 << np.arange(len(csl) - 1, -1, -1, dtype=np.int64))

    def route(self, words: np.ndarray) -> np.ndarray:
        """The last node on each word's way; not a leaf where a cell without series is met."""
        out = np.zeros(len(words), np.int64)
        stack = [(0, np.arange(len(words)))]
        while stack:
            node, at = stack.pop()
            out[at] = node
            if self.is_leaf(node) or not len(at):
                continue
            sid = self.sids(node, words[at])
            order = np.argsort(sid, kind="stable")
            values, first = np.unique(sid[order], return_index=True)
            for v, rows in zip(values, np.split(at[order], first[1:])):
                if (child := self.routes[node].get(int(v))) is not None:
                    stack.append((child, rows))
        return out

    def graft(self, at: int, other: "WordTree") -> list[int]:
        """Puts ``other`` in the place of the leaf ``at``; returns its nodes' new numbers."""
        base = len(self)
        number = [at] + [base + i for i in range(len(other) - 1)]
        depth = self.depth[at]
        for i in range(len(other)):
            if i:
                for f in self.FIELDS:
                    getattr(self, f).append(None)
            n = number[i]
            self.parent[n] = number[other.parent[i]] if i else self.parent[at]
            self.depth[n] = depth + other.depth[i]
            self.kind[n] = other.kind[i] if i else (INTERNAL if other.csl[0] else LEAF)
            for f in ("csl", "pfx_bits", "pfx_len", "size", "n_copies", "members", "oversize"):
                getattr(self, f)[n] = getattr(other, f)[i]
            if not i:
                self.members[n] = ()
            self.routes[n] = {s: number[c] for s, c in other.routes[i].items()}
        self._leaves = None
        return number

    def number_leaves(self) -> None:
        """Dense depth-first numbers for leaves: the leaves of a subtree are neighbours."""
        self.leaf_id = [-1] * len(self)
        stack, k = [0] if len(self) else [], 0
        while stack:
            node = stack.pop()
            if self.is_leaf(node):
                self.leaf_id[node] = k
                k += 1
            else:
                stack += reversed(self.children(node))
        self.last_leaf_id = k - 1
        self._leaves = None

    # ---- what searches ask for --------------------------------------------------------

    def leaves(self) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(node, leaf_id, low ends, high ends, size with copies) by leaf_id."""
        if self._leaves is None:
            nodes = np.array(sorted((n for n in range(len(self)) if self.is_leaf(n) and self.leaf_id[n] >= 0), key=lambda n: self.leaf_id[n]), np.int64)
            lo, hi = cells_rows(np.array([self.pfx_bits[n] for n in nodes]).reshape(-1, self.w), np.array([self.pfx_len[n] for n in nodes]).reshape(-1, self.w))
            self._leaves = (nodes, np.array([self.leaf_id[n] for n in nodes], np.int64), lo, hi, np.array([self.size[n] + self.n_copies[n] for n in nodes], np.int64))
        return self._leaves

    def bounds(self, query, of=None) -> np.ndarray:
        """Lower bounds of one query summary from all leaves, or from the nodes ``of``."""
        from ..functions.distances import mindist_cells_rows

        if of is None:
            _, _, lo, hi, _ = self.leaves()
        else:
            lo, hi = cells_rows(np.array([self.pfx_bits[n] for n in of]).reshape(-1, self.w), np.array([self.pfx_len[n] for n in of]).reshape(-1, self.w))
        return mindist_cells_rows(query.hi, query.lo, lo, hi, query.n)

    def below(self, node: int) -> list[int]:
        """Leaf nodes under a node, depth first."""
        out, stack = [], [node]
        while stack:
            n = stack.pop()
            if self.is_leaf(n):
                out.append(n)
            else:
                stack += reversed(self.children(n))
        return out

    def path(self, summary_words: np.ndarray, values: np.ndarray) -> list[int]:
        """Nodes from the root to where one word leads."""
        node, out = int(self.route(summary_words[None])[0]), []
        while node >= 0:
            out.append(node)
            node = self.parent[node]
        return out[::-1]


def segment_variance(words: np.ndarray, segments, bits: int) -> np.ndarray:
    """Population variance of the symbols' midpoints, by segment."""
    return midpoints(bits)[words[:, list(segments)]].var(axis=0)


def next_bits(words: np.ndarray, pfx_bits, pfx_len, segments, bits: int) -> np.ndarray:
    out = np.empty((len(words), len(segments)), np.int64)
    for j, s in enumerate(segments):
        lo = pfx_bits[s] << (bits - pfx_len[s])
        hi = lo + (1 << (bits - pfx_len[s])) - 1
        out[:, j] = (np.clip(words[:, s].astype(np.int64), lo, hi) >> (bits - pfx_len[s] - 1)) & 1
    return out


def split_point(pfx_bits, pfx_len, s: int) -> float:
    """The breakpoint that cuts the node's cell on segment ``s``."""
    return breakpoints(pfx_len[s] + 1)[2 * pfx_bits[s]]


def decide(size: int, mid_mean: np.ndarray, seg_var: np.ndarray, base_of, pfx_bits, pfx_len, usable: tuple[int, ...], p: BuildParams, cost: SearchCost | None = None, codes_of=None) -> tuple[int, ...]:
    """Segments to split on, from aggregates alone: means and variances of midpoints, and
    counts of next bits (``base_of()`` gives them when they are needed).  The "rescan" search
    counts the series of every plan anew where ``codes_of`` can give their next bits."""
    if p.policy == "fullary":
        return usable
    if p.policy == "binary":
        return (min(usable, key=lambda s: (abs(mid_mean[usable.index(s)] - split_point(pfx_bits, pfx_len, s)), s)),)
    if p.policy == "binary_rr":
        return (min(usable, key=lambda s: (pfx_len[s], s)),)
    return choose_plan(seg_var, base_of(), usable, size, p.th, p.alpha, p.f_low, p.f_high, p.search, p.skip_degenerate, cost, codes=codes_of() if p.search == "rescan" and codes_of else None)


def border_gaps(words: np.ndarray, pfx_bits, pfx_len, csl, sids: np.ndarray, p: BuildParams) -> np.ndarray:
    """Rows x chosen segments: distance from the split's breakpoint where a series is within
    ``f`` of the width of the cell on the other side, else infinite."""
    lam, out = len(csl), np.full((len(words), len(csl)), np.inf)
    for j, s in enumerate(csl):
        gap = np.abs(midpoints(p.bits)[words[:, s]] - split_point(pfx_bits, pfx_len, s))
        own = (sids >> (lam - 1 - j)) & 1
        e = edges(pfx_len[s] + 1, CAP)
        other = 2 * pfx_bits[s] + (1 - own)
        near = gap <= p.f * (e[other + 1] - e[other])
        out[near, j] = gap[near]
    return out


def groups_of(p: BuildParams, sizes: dict[int, int], lam: int, node: str) -> list[list[int]]:
    """Which small children share a leaf."""
    if p.packing == "none":
        return [[s] for s in sorted(sizes)]
    if p.packing == "size":
        return pack_by_size(sizes, p.th)
    return pack_leaves(sizes, lam, p.th, p.rho, p.r, p.seed, node)


def grow(words: np.ndarray, native: np.ndarray, used: np.ndarray, pfx_bits, pfx_len, p: BuildParams, name: str, cost: SearchCost | None = None, above: int = 0):
    """The subtree over ``words`` (rows in order of series id), ``above`` splits below the root.

    native: False for rows that are copies; used: copies that a series already has.
    Returns (tree, leaf node of each row, copies as (row, leaf node) pairs made here).
    """
    tree = WordTree(p.w, p.bits)
    tree.add(-1, INTERNAL, pfx_bits, pfx_len, int(native.sum()), n_copies=int((~native).sum()))
    at_leaf, made = np.zeros(len(words), np.int64), []
    used = used.copy()
    stack = [(0, np.arange(len(words)), np.zeros(0, np.int64), name)]
    while stack:
        node, rows, guests, label = stack.pop()
        everyone = np.concatenate((rows, guests))
        usable = tuple(s for s in range(p.w) if tree.pfx_len[node][s] < p.bits)
        alike = p.levels == 0 and len(everyone) > p.th and len(rows) > 0 and (words[rows] == words[rows[0]]).all()  # no split parts equal words
        if len(everyone) <= p.th or not usable or alike or 0 < p.levels <= above + tree.depth[node]:
            tree.kind[node] = LEAF
            tree.oversize[node] = len(everyone) > p.th
            at_leaf[rows] = node
            made += [(int(g), node) for g in guests]
            continue
        seen = np.sort(everyone)[: p.th + 1] if p.when == "just_full" else everyone
        mine = words[seen]
        bits, lens = tree.pfx_bits[node], tree.pfx_len[node]
        need_spread = p.policy not in ("fullary", "binary_rr")
        plan = decide(
            len(seen), midpoints(p.bits)[mine[:, list(usable)]].mean(axis=0) if need_spread else None, segment_variance(mine, usable, p.bits) if need_spread else None,
            lambda: base_distribution(next_bits(mine, bits, lens, usable, p.bits)), bits, lens, usable, p, cost, lambda: next_bits(mine, bits, lens, usable, p.bits))
        tree.csl[node], tree.kind[node] = plan, INTERNAL
        lam = len(plan)
        sid, guest_sid = tree.sids(node, words[rows]), tree.sids(node, words[guests])
        counts = dict(zip(*np.unique(np.concatenate((sid, guest_sid)), return_counts=True)))
        counts = {int(s): int(n) for s, n in counts.items()}
        full = [s for s in sorted(counts) if counts[s] > p.th]
        small = {s: n for s, n in counts.items() if n <= p.th}
        child_rows = {s: rows[sid == s] for s in counts}
        child_guests = {s: guests[guest_sid == s] for s in counts}
        packs = groups_of(p, small, lam, label) if small else []
        if p.f > 0:
            gaps = border_gaps(words[rows], bits, lens, plan, sid, p)
            own = native[rows] if len(rows) else np.zeros(0, bool)
            pair = [(gaps[i, j], int(rows[i]), int(sid[i]), int(sid[i]) ^ (1 << (lam - 1 - j))) for i, j in zip(*np.nonzero(np.isfinite(gaps))) if own[i]]
            room = {tuple(g): p.th - sum(counts[s] for s in g) for g in packs}
            pack_of = {s: tuple(g) for g in packs for s in g}
            extra: dict[int, list[int]] = {}
            for gap, row, home, to in sorted(pair):
                if to not in counts or used[row] >= p.max_copies:
                    continue
                if to in small:
                    if pack_of[to] == pack_of.get(home) or room[pack_of[to]] <= 0:
                        continue
                    room[pack_of[to]] -= 1
                used[row] += 1
                extra.setdefault(to, []).append(row)
            for s, more in extra.items():
                child_guests[s] = np.concatenate((child_guests[s], np.array(more, np.int64)))
        for s in full:
            b, k = pack_prefix(bits, lens, plan, [s])
            child = tree.add(node, INTERNAL, b, k, len(child_rows[s]), (s,), len(child_guests[s]))
            tree.routes[node][s] = child
            stack.append((child, child_rows[s], child_guests[s], f"{label}.{s}"))
        for g in packs:
            b, k = pack_prefix(bits, lens, plan, g)
            r, q = np.concatenate([child_rows[s] for s in g]), np.concatenate([child_guests[s] for s in g])
            child = tree.add(node, PACK if len(g) > 1 else LEAF, b, k, len(r), g, len(q))
            for s in g:
                tree.routes[node][s] = child
            at_leaf[r] = child
            made += [(int(x), child) for x in q]
    guests_by_row: dict[int, set[int]] = {}
    for row, leaf in made:
        guests_by_row.setdefault(row, set()).add(leaf)
    copies = [(row, leaf) for row, ls in sorted(guests_by_row.items()) for leaf in sorted(ls) if leaf != at_leaf[row]]
    return tree, at_leaf, copies
