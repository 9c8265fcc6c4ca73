"""The engine's functions for SQL users.

``series_paa(values, w)``, ``series_word(values, w, bits)`` (hex), ``series_ed(a, b)``,
``series_dtw(a, b, radius)``, ``series_mindist(values, word, bits)``, the aggregate
``series_var(x)`` and the table functions ``series_windows(values, length, stride)``,
``series_cells(bits)`` and ``series_knn(TABLE(t) PARTITION BY (...), query, k)``.  The last one
gives the k nearest rows (series_id, values) of each partition; the k nearest of all are
among them, so a final ORDER BY ... LIMIT k over partitions by a hash has no large task.
"""

from __future__ import annotations

import heapq

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from .distances import dtw_rows, ed_rows, mindist_cells_rows
from .summaries import edges, paa_rows, sax_rows


def series_paa(values: pd.Series, w: pd.Series) -> pd.Series:
    return pd.Series([None if v is None else paa_rows(np.asarray(v, float)[None], int(k))[0] for v, k in zip(values, w)])


def series_word(values: pd.Series, w: pd.Series, bits: pd.Series) -> pd.Series:
    return pd.Series([None if v is None else sax_rows(paa_rows(np.asarray(v, float)[None], int(k)), int(b))[0].tobytes().hex() for v, k, b in zip(values, w, bits)], dtype=object)


def series_ed(a: pd.Series, b: pd.Series) -> pd.Series:
    return pd.Series([None if x is None or y is None else float(ed_rows(np.asarray(x, float)[None], np.asarray(y, float))[0]) for x, y in zip(a, b)], dtype=object).astype("Float64")


def series_dtw(a: pd.Series, b: pd.Series, radius: pd.Series) -> pd.Series:
    return pd.Series([None if x is None or y is None else float(dtw_rows(np.asarray(x, float)[None], np.asarray(y, float), int(r))[0]) for x, y, r in zip(a, b, radius)], dtype=object).astype("Float64")


def series_mindist(values: pd.Series, word: pd.Series, bits: pd.Series) -> pd.Series:
    def one(v, h, b):
        s, e = np.frombuffer(bytes.fromhex(h), np.uint8).astype(int), edges(int(b))
        q = paa_rows(np.asarray(v, float)[None], len(s))[0]
        return float(mindist_cells_rows(q, q, e[s][None], e[s + 1][None], len(v))[0])

    return pd.Series([None if v is None or h is None else one(v, h, b) for v, h, b in zip(values, word, bits)], dtype=object).astype("Float64")


def series_var(x: pd.Series) -> float:
    return float(x.var(ddof=0)) if len(x) else float("nan")


class Windows:
    def eval(self, values, length: int, stride: int):
        for at in range(0, len(values or []) - length + 1, stride):
            yield at, values[at : at + length]


class Cells:
    def eval(self, bits: int):
        e = edges(bits)
        for i in range(len(e) - 1):
            yield i, float(e[i]), float(e[i + 1])


class Nearest:
    """k nearest of a partition's rows by (distance, series_id); holds k rows.  Rows with a null
    or of another length than the query's are no neighbours."""

    def __init__(self):
        self.best: list[tuple[float, int]] = []

    def eval(self, row, query, k: int):
        values = row["values"]
        if row["series_id"] is None or values is None or query is None or len(values) != len(query) or None in values:
            return
        found = (-float(ed_rows(np.asarray(values, float)[None], np.asarray(query, float))[0]), -int(row["series_id"]))
        if len(self.best) < k:
            heapq.heappush(self.best, found)
        elif k > 0 and found > self.best[0]:
            heapq.heapreplace(self.best, found)

    def terminate(self):
        for d, i in sorted(self.best, reverse=True):
            yield -i, -d


#: Result types; the functions become UDFs only when they are registered, for a running session.
KINDS = {series_paa: "array<double>", series_word: "string", series_ed: "double", series_dtw: "double", series_mindist: "double", series_var: "double"}


def register(spark: SparkSession) -> None:
    for f, kind in KINDS.items():
        spark.udf.register(f.__name__, F.pandas_udf(f, kind))
    spark.udtf.register("series_windows", F.udtf(Windows, returnType="start int, part array<double>"))
    spark.udtf.register("series_knn", F.udtf(Nearest, returnType="series_id long, distance double"))
    spark.udtf.register("series_cells", F.udtf(Cells, returnType="cell int, lo double, hi double"))
