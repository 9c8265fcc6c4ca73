"""Token counts of fields or sections by offset-mapped attribution.

A document is encoded once, whole, so counts are those of the text as a model sees it.
Each token has a span of characters; spans are joined with the sections' intervals by
binary search in sorted bounds inside the document (no shuffle, and no pairs beyond real
overlaps).  A token that crosses a bound is allocated by a stated rule:

- ``start``: to the section with its first character;
- ``end``: to the section with its last character;
- ``split``: to every section it overlaps, by share of its bytes.

A token that begins or ends inside a character covers that character.  Sections are the
lines of a text (with their line feed) or, from a table, (key, section, start, stop) rows
in code points; where sections of a document overlap, one ends where the next one (by start,
then stop, then name) starts.  Tokens outside of all sections count as section -1.

Edge cases: a null or empty text has one section without tokens by lines; empty sections
have no tokens; sections beyond the text's end are cut; repeated documents are counted each
by itself; an empty table gives an empty table.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .tokens import default_file, encoder

RULES = ("start", "end", "split")


def line_bounds(text: str) -> tuple[np.ndarray, np.ndarray]:
    """Starts and stops, in bytes, of the lines with their line feeds; one empty line for an empty text."""
    raw = np.frombuffer(text.encode("utf-8", "surrogatepass"), np.uint8)
    ends = np.flatnonzero(raw == 10) + 1
    if not len(ends) or ends[-1] != len(raw):
        ends = np.append(ends, len(raw))
    return np.concatenate(([0], ends[:-1])), ends


def attribute(lengths: np.ndarray, starts: np.ndarray, stops: np.ndarray, lead: np.ndarray, rule: str) -> tuple[np.ndarray, np.ndarray, float]:
    """Tokens for each section, tokens of each that cross its bounds, tokens outside of all.

    lengths: bytes of each token; starts, stops: of the sections, ascending, in bytes;
    lead: for each byte, where its character starts, then the text's length.
    """
    k = len(starts)
    stop = np.cumsum(lengths)
    start = lead[stop - lengths] if len(stop) else stop
    size = int(lead[-1])
    # a token that ends inside a character reaches to that character's end
    bounds = np.unique(lead)
    stop = bounds[np.minimum(np.searchsorted(bounds, stop, side="left"), len(bounds) - 1)] if len(stop) else stop
    starts, stops = np.minimum(starts, size), np.minimum(stops, size)
    first = np.searchsorted(stops, start, side="right")  # first section that ends after the token's start
    last = np.searchsorted(starts, stop, side="left") - 1  # last section that starts before its end
    crossing = np.zeros(k, np.int64)
    tokens = np.zeros(k + 1)
    whole = (first == last) & (first < k)
    inside = whole & (starts[np.minimum(first, k - 1)] <= start) & (stop <= stops[np.minimum(first, k - 1)]) if k else whole
    np.add.at(tokens, first[inside], 1.0)
    for i in np.flatnonzero(~inside):
        a, b = int(start[i]), int(stop[i])
        touched = range(int(first[i]), min(int(last[i]), k - 1) + 1)
        for s in touched:
            crossing[s] += 1
        if rule == "split":
            left = 1.0
            for s in touched:
                share = (min(b, stops[s]) - max(a, starts[s])) / (b - a)
                tokens[s] += share
                left -= share
            tokens[k] += max(0.0, left)
        else:
            at = a if rule == "start" else b - 1
            own = [s for s in touched if starts[s] <= at < stops[s]]
            tokens[own[0] if own else k] += 1
    return tokens[:k], crossing, float(tokens[k])


def _leads(text: str) -> np.ndarray:
    raw = np.frombuffer(text.encode("utf-8", "surrogatepass"), np.uint8)
    at = np.where((raw & 0xC0) != 0x80, np.arange(len(raw)), 0)
    return np.append(np.maximum.accumulate(at) if len(at) else at, len(raw)).astype(np.int64)


def section_token_counts(docs: DataFrame, sections: DataFrame | None = None, key: str = "doc_id", text: str = "text", rule: str = "start", file: str | None = None) -> DataFrame:
    """(key, section, start, stop, tokens, crossing): start and stop in code points.

    With ``sections`` (key, section, start, stop) the texts are joined with their sorted
    intervals; without, sections are lines numbered from 0.
    """
    if rule not in RULES:
        raise ValueError(f"rule: one of {RULES}")
    file = file or default_file()
    given = sections is not None
    texts = docs.select(F.col(key).cast("long").alias("key"), F.col(text).cast("string").alias("text"))
    if given:
        listed = sections.groupBy(F.col(key).cast("long").alias("_key")).agg(F.sort_array(F.collect_list(F.struct("start", "stop", "section"))).alias("parts"))
        texts = texts.join(listed, F.col("key") == F.col("_key"), "left").select("key", "text", "parts")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(file)
        for batch in batches:
            out: list[list] = [[] for _ in range(6)]
            for i, (k, t) in enumerate(zip(batch.column(0).to_pylist(), batch.column(1))):
                t = t.as_py() or ""
                lead = _leads(t)
                first = lead[:-1] == np.arange(len(lead) - 1)  # bytes that begin a character
                of_byte = np.concatenate(([0], np.cumsum(first)))  # code points before each byte
                if given:
                    parts = batch.column(2)[i].as_py() or []
                    at = np.append(np.flatnonzero(first), len(lead) - 1)
                    starts, stops = (at[np.clip(np.array([p[n] for p in parts], np.int64), 0, len(at) - 1)] for n in ("start", "stop"))
                    stops = np.maximum(starts, np.minimum(stops, np.append(starts[1:], len(lead) - 1))) if len(starts) else stops
                    names = [p["section"] for p in parts]
                else:
                    starts, stops = line_bounds(t)
                    names = list(range(len(starts)))
                tokens, crossing, rest = attribute(enc.lengths[enc.ids(t)], starts, stops, lead, rule)
                rows = [names, of_byte[starts].tolist(), of_byte[stops].tolist(), tokens.tolist(), crossing.tolist()]
                if rest > 1e-9:
                    for r, x in zip(rows, (-1, None, None, rest, 0)):
                        r.append(x)
                out[0] += [k] * len(rows[0])
                for o, r in zip(out[1:], rows):
                    o += r
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.float64(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(o, t) for o, t in zip(out, kinds)], names=["key", "section", "start", "stop", "tokens", "crossing"])

    return texts.mapInArrow(run, "key bigint, section bigint, start bigint, stop bigint, tokens double, crossing bigint")
