"""Packing by sorted words: series in the order of their interleaved words, cut every ``th``.

A leaf is an interval of that order, not a cell, so it is full whatever the data, but its
words can lie far apart: bounds come from the box of the symbols that it holds.  Equal words
are never parted, so a leaf of copies may be oversize.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.distances import mindist_cells_rows
from ..functions.summaries import edges
from . import arrow
from .order import positions
from .params import BuildParams


def sort_keys(words: np.ndarray, bits: int) -> np.ndarray:
    """Interleaved bits of all symbols, most significant first, as fixed-width byte strings."""
    planes = np.concatenate([(words >> b) & 1 for b in range(bits - 1, -1, -1)], axis=1)
    packed = np.ascontiguousarray(np.packbits(planes, axis=1))
    return packed.view(f"S{packed.shape[1]}").ravel()


class SortedTree:
    """Node 0 is the root, the others are its leaves in order; lo, hi: least and greatest
    symbols by leaf and segment."""

    def __init__(self, w: int, bits: int, starts: np.ndarray):
        k = len(starts)
        self.w, self.bits, self.starts = w, bits, starts
        self.parent, self.depth = [-1] + [0] * k, [0] + [1] * k
        self.size, self.oversize = [0] * (k + 1), [False] * (k + 1)
        self.kids = [tuple(range(1, k + 1))] + [()] * k
        self.leaf_id, self.last_leaf_id = [-1] + list(range(k)), k - 1
        self.lo, self.hi = np.full((k, w), (1 << bits) - 1, np.int64), np.zeros((k, w), np.int64)

    def __len__(self) -> int:
        return len(self.parent)

    def is_leaf(self, node: int) -> bool:
        return node > 0

    def children(self, node: int) -> list[int]:
        return list(self.kids[node])

    def below(self, node: int) -> list[int]:
        return [node] if node else self.children(0)

    def route(self, words: np.ndarray) -> np.ndarray:
        return np.maximum(np.searchsorted(self.starts, sort_keys(words, self.bits), side="right"), 1).astype(np.int64)

    def path(self, word: np.ndarray, values: np.ndarray) -> list[int]:
        return [0, int(self.route(word[None])[0])]

    def leaves(self):
        nodes = np.arange(1, len(self), dtype=np.int64)
        return nodes, np.array(self.leaf_id[1:], np.int64), None, None, np.array(self.size[1:], np.int64)

    def bounds(self, query, of=None) -> np.ndarray:
        at = np.arange(len(self) - 1) if of is None else np.asarray(of, np.int64) - 1
        e = edges(self.bits)
        out = np.zeros(len(at))
        real = at >= 0
        out[real] = mindist_cells_rows(query.hi, query.lo, e[self.lo[at[real]]], e[self.hi[at[real]] + 1], query.n)
        return out

    def space(self) -> int:
        return len(self.starts) * (self.starts.dtype.itemsize + 2 * self.w)

    def add_words(self, words: DataFrame, th: int) -> int:
        """Counts words into leaves and widens their boxes; returns how many there were."""
        shared, w = words.sparkSession.sparkContext.broadcast(self), self.w
        names = [f"{x}{i}" for x in ("lo", "hi") for i in range(w)]

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                mine = arrow.words_from(b.column(0), w)
                at = shared.value.route(mine)
                rows = [(int(n), int((at == n).sum()), *mine[at == n].min(0).tolist(), *mine[at == n].max(0).tolist()) for n in np.unique(at)]
                cols = list(zip(*rows)) or [()] * (2 + 2 * w)
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in cols], names=["node", "n", *names])

        found = words.select("word").mapInArrow(run, ", ".join(f"{c} long" for c in ("node", "n", *names)))
        total = 0
        for r in found.groupBy("node").agg(F.sum("n").alias("n"), *[F.min(c).alias(c) if c[0] == "l" else F.max(c).alias(c) for c in names]).collect():
            i = r["node"] - 1
            self.lo[i] = np.minimum(self.lo[i], [r[f"lo{s}"] for s in range(w)])
            self.hi[i] = np.maximum(self.hi[i], [r[f"hi{s}"] for s in range(w)])
            self.size[r["node"]] += r["n"]
            total += r["n"]
            self.oversize[r["node"]] = self.size[r["node"]] > th and bool((self.lo[i] == self.hi[i]).all())
        self.size[0] += total
        return total


def sorted_tree(words: DataFrame, p: BuildParams) -> SortedTree:
    """words: (series_id, word).  Cuts are the keys at every ``th``-th place of the order."""

    def keyed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            keys = sort_keys(arrow.words_from(b.column(1), p.w), p.bits)
            raw = np.frombuffer(keys.tobytes(), np.uint8).reshape(len(keys), -1)
            yield pa.RecordBatch.from_arrays([b.column(0), arrow.bytes_of(raw)], names=["series_id", "k"])

    rows = words.select("series_id", "word").mapInArrow(keyed, "series_id long, k binary")
    cuts = positions(rows, ["k", "series_id"]).where(F.col("pos") % p.th == 0).select("k").distinct().collect()
    width = -(-p.w * p.bits // 8)
    tree = SortedTree(p.w, p.bits, np.array(sorted(bytes(r["k"]) for r in cuts), f"S{width}"))
    tree.add_words(words, p.th)
    return tree
