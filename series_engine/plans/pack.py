"""Packs of small sibling leaves.

Siblings are named by the bits that their parent's split gave them.  A pack's word drops
every bit in which its members differ (the bit is demoted), so packs of alike siblings keep
tight words.
"""

from __future__ import annotations

import hashlib

import numpy as np


def demotion(sids) -> int:
    """Number of bits in which the members differ."""
    sids = list(sids)
    return int(np.bitwise_or.reduce(sids) ^ np.bitwise_and.reduce(sids)).bit_count()


def _rank(seed: int, node: str, sid: int) -> bytes:
    return hashlib.blake2b(f"{seed}/{node}/{sid}".encode(), digest_size=8).digest()


def pack_leaves(children: dict[int, int], lam: int, th: int, rho: float, r: float, seed: int, node: str) -> list[list[int]]:
    """Groups of child sids (sizes in ``children``); groups of one are leaves of their own.

    As many packs as the small children would fill are opened by seeds in hashed order, so
    the result depends neither on partitions nor on the order of rows.  Each further child,
    fullest first, joins the pack that it adds the fewest demoted bits to, if at most
    rho * lam bits are demoted then and the pack stays within th; else it opens a pack.
    """
    small = {s: n for s, n in children.items() if n <= r * th}
    out = [[s] for s in sorted(children) if s not in small]
    if not small:
        return out
    limit = rho * lam
    order = sorted(small, key=lambda s: _rank(seed, node, s))
    first = max(1, sum(small.values()) // th)
    packs = [[s, s, small[s], [s]] for s in order[:first]]  # or, and, size, members
    for s in sorted(order[first:], key=lambda s: (-small[s], s)):
        best = None
        for i, (ors, ands, size, _) in enumerate(packs):
            if size + small[s] <= th:
                bits = ((ors | s) ^ (ands & s)).bit_count()
                if bits <= limit:
                    added = bits - (ors ^ ands).bit_count()
                    if best is None or (added, i) < best:
                        best = (added, i)
        if best is None:
            packs.append([s, s, small[s], [s]])
        else:
            p = packs[best[1]]
            p[0], p[1], p[2] = p[0] | s, p[1] & s, p[2] + small[s]
            p[3].append(s)
    return out + [sorted(p[3]) for p in packs]


def pack_by_size(children: dict[int, int], th: int) -> list[list[int]]:
    """Neighbours in sid order share a pack while it has room."""
    out: list[list[int]] = []
    room = 0
    for s in sorted(children):
        if out and children[s] <= room:
            out[-1].append(s)
            room -= children[s]
        else:
            out.append([s])
            room = max(0, th - children[s])
    return out


def pack_prefix(parent_bits, parent_len, csl, sids) -> tuple[list[int], list[int]]:
    """(bits, lengths) of the word that covers the children ``sids`` of a split on ``csl``."""
    bits, lens, lam = list(parent_bits), list(parent_len), len(csl)
    differ = int(np.bitwise_or.reduce(list(sids)) ^ np.bitwise_and.reduce(list(sids)))
    for i, s in enumerate(csl):
        at = lam - 1 - i
        if not differ >> at & 1:
            bits[s], lens[s] = bits[s] * 2 + (sids[0] >> at & 1), lens[s] + 1
    return bits, lens
