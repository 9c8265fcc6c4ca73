"""Substring de-duplication on a de Bruijn graph of word k-mers.

The k-mers (``k`` consecutive words of one document) are the edges of the graph.  Each
document is cut into paths: maximal runs of edges with the same minimizer, the least hash
of ``M`` consecutive words inside the k-mer.  Equal edges have equal minimizers, so a join
by minimizer brings all occurrences of an edge together while only about one row for
every five words is shuffled, and only minimizers that several documents have go further.

What repeats is found first.  A path that occurs in several documents is a repeated piece as
a whole.  Paths that share a minimizer with a smaller document without being equal to one
(the ends of repeated passages, edited places) are opened into edges, and each edge that
occurs in several documents is a repeated piece.  A piece knows its source: document and
position of its first occurrence (least id, then least start).

Pieces are then compacted.  A piece's in- and out-degree are the numbers of different pieces
before and after it, over all its occurrences, where the end of a document or of what
repeats counts as one more.  Where a piece's only successor has it as its only predecessor
the path does not branch; joins of the degrees tell which pieces go on such a path.  Edges
are opened where documents part, i.e. at branches.  Paths and edges that follow each other
both in a document and in one source become one span with the coordinates of that source.

Spans are verified: the words at a span and at its source's coordinates are read from both
texts and compared by 128-bit digests.  Hashes only propose: a span whose words differ is
left in place.

Joins with texts never broadcast the other side: spans grow with the corpus, and their
compressed size in a file says little about their size in memory.

Words are named by 64-bit hashes, found for all words of a batch at once from prefix sums
over its bytes, and edges by two independent 64-bit sums over them.

Edge cases: null and empty texts have no words; texts under ``k`` words keep all of them;
a document never removes its own words, however often they repeat inside it; rows with a
null key have nothing removed and remove nothing; rows that repeat a key count as one
document for the question which is smaller, and a span is only removed from the row whose
words it has; an empty table gives an empty table.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from xxhash import xxh64_intdigest

from .common import discard, materialize, own_name

K = 13
M = 5
_CHUNK = 1 << 17
_MULT = (np.uint64(0x9E3779B97F4A7C15), np.uint64(0xD6E8FEB86659FD93))
_INV = tuple(np.uint64(pow(int(m), -1, 1 << 64)) for m in _MULT)


def words_of(text: str | None) -> list[bytes]:
    return (text or "").encode("utf-8", "surrogatepass").split()


def _mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


_BYTE = _mixed(np.arange(1, 257, dtype=np.uint64) * np.uint64(0x9FB21C651E98DF25))
_BYTE_MULT = np.uint64(0xD1342543DE82EF95)
_BYTE_INV = np.uint64(pow(int(_BYTE_MULT), -1, 1 << 64))
_PIECE = 1 << 18


def _blank(data: np.ndarray) -> np.ndarray:
    return (data == 32) | (data - np.uint8(9) < 5)


def _pieces(data: np.ndarray, bounds: np.ndarray) -> Iterator[tuple[int, int]]:
    """Ranges of at most ``_PIECE`` bytes that end where a text or a word does; a longer word is a range by itself."""
    lo = 0
    while lo < len(data):
        hi = min(lo + _PIECE, len(data))
        text = int(bounds[np.searchsorted(bounds, hi, "right") - 1])
        if hi < len(data) and text > lo:
            hi = text
        elif hi < len(data):
            blank = np.flatnonzero(_blank(data[lo:hi]))
            end = int(bounds[np.searchsorted(bounds, lo, "right")])
            if len(blank):
                hi = lo + int(blank[-1]) + 1
            while not len(blank) and hi < end:
                blank = np.flatnonzero(_blank(data[hi : min(hi + _PIECE, end)]))
                hi = hi + int(blank[0]) if len(blank) else min(hi + _PIECE, end)
        yield lo, hi
        lo = hi


def named_words(texts: pa.Array, bits: int = 64) -> tuple[np.ndarray, np.ndarray]:
    """(hash, number of its text) of all words of some texts, read from their bytes without an object for each word."""
    texts = pc.cast(pc.fill_null(texts, ""), pa.large_string())
    _, offsets, raw = texts.buffers()
    bounds = np.frombuffer(offsets, np.int64)[texts.offset : texts.offset + len(texts) + 1] if len(texts) else np.zeros(1, np.int64)
    data = np.frombuffer(raw, np.uint8)[bounds[0] : bounds[-1]] if raw is not None else np.zeros(0, np.uint8)
    bounds = bounds - bounds[0]
    names, of = [np.zeros(0, np.uint64)], [np.zeros(0, np.int64)]
    for lo, hi in _pieces(data, bounds):
        part = data[lo:hi]
        if hi - lo > _PIECE:
            name, starts = np.array([xxh64_intdigest(part)], np.uint64), np.zeros(1, np.int64)
        else:
            blank = _blank(part)
            word = ~blank
            first, last = word.copy(), word.copy()
            first[1:] &= blank[:-1]
            last[:-1] &= blank[1:]
            inner = bounds[np.searchsorted(bounds, lo, "right") : np.searchsorted(bounds, hi, "left")] - lo
            first[inner], last[inner - 1] = word[inner], word[inner - 1]
            starts, stops = np.flatnonzero(first), np.flatnonzero(last) + 1
            sums = np.zeros(len(part) + 1, np.uint64)
            np.cumsum(_BYTE.take(part) * _powers(_BYTE_MULT, len(part)), out=sums[1:])
            name = _mixed((sums[stops] - sums[starts]) * _powers(_BYTE_INV, len(part))[starts])
        names.append(name)
        of.append(np.searchsorted(bounds, lo + starts, "right") - 1)
    h = np.concatenate(names)
    return (h >> np.uint64(64 - bits) if bits < 64 else h), np.concatenate(of)


def _windows(h: np.ndarray, size: int, which: int) -> np.ndarray:
    """Hash of each run of ``size`` words, by its start."""
    out = h[: len(h) - size + 1].copy()
    for j in range(1, size):
        out = out * _MULT[which] + h[j : len(h) - size + 1 + j]
    return _mixed(out)


def paths(h: np.ndarray, doc: np.ndarray, k: int = K, m: int = M) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(minimizer, start, edges, content) of all paths of some documents, one after the other.

    h: word hashes; doc: number of each word's document.  start: first edge; edges: how
    many; content: hash of all words of the path.
    """
    n = len(h) - k + 1
    if n <= 0:
        return (np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.uint64))
    small = _windows(h, m, 0)
    least = small[:n].copy()
    for j in range(1, k - m + 1):
        np.minimum(least, small[j : n + j], out=least)
    inside = np.flatnonzero(doc[:n] == doc[k - 1 :])
    fresh = np.ones(len(inside), bool)
    fresh[1:] = (least[inside[1:]] != least[inside[:-1]]) | (inside[1:] != inside[:-1] + 1)
    first = np.flatnonzero(fresh)
    starts, edges = inside[first], np.diff(np.append(first, len(inside)))
    stops = starts + edges + k - 1
    mixed = []
    for mult, inv, seed in zip(_MULT, _INV, (np.uint64(1), np.uint64(0x2545F4914F6CDD1D))):
        sums = np.concatenate((np.zeros(1, np.uint64), np.cumsum(_mixed(h ^ seed) * _powers(mult, len(h)))))
        mixed.append(_mixed((sums[stops] - sums[starts]) * _powers(inv, len(h))[starts]))
    return least[starts], starts, edges, mixed[0] ^ (mixed[1] * np.uint64(3)) ^ edges.astype(np.uint64)


_POWERS: dict[int, np.ndarray] = {}


def _powers(base: np.uint64, n: int) -> np.ndarray:
    have = _POWERS.get(int(base))
    if have is None or len(have) < n:
        have = np.full(max(n, _CHUNK + K), base)
        have[0] = 1
        have = _POWERS[int(base)] = np.cumprod(have)
    return have[:n]


def _signed(x: np.ndarray) -> pa.Array:
    return pa.array(x.view(np.int64))


def _first_words(doc: np.ndarray, n: int) -> np.ndarray:
    """Number of words before each text, and of all words."""
    return np.concatenate((np.zeros(1, np.int64), np.cumsum(np.bincount(doc, minlength=n))))


def _cut(batches: Iterator[pa.RecordBatch], bits: int = 64) -> Iterator[pa.RecordBatch]:
    """(mini, key, start, edges, content) of all paths.

    Works on chunks of a batch's words: several short documents, or a part of a long one.
    A chunk ends inside a path at worst; its two parts are paths of their own, which
    together still hold each edge once.
    """
    for batch in batches:
        keys = batch.column(0).to_numpy(zero_copy_only=False).astype(np.int64)
        h, doc = named_words(batch.column(1), bits)
        begin = _first_words(doc, len(keys))
        for lo in range(0, len(h) - K + 1, _CHUNK):
            mini, starts, edges, content = paths(h[lo : lo + _CHUNK + K - 1], doc[lo : lo + _CHUNK + K - 1])
            of = doc[lo + starts]
            yield pa.RecordBatch.from_arrays([_signed(mini), pa.array(keys[of]), pa.array((lo + starts - begin[of]).astype(np.int32)), pa.array(edges.astype(np.int32)), _signed(content)], names=["mini", "key", "start", "edges", "content"])


def _open(batches: Iterator[pa.RecordBatch], bits: int = 64) -> Iterator[pa.RecordBatch]:
    """Texts with the paths to open -> one row for each of their edges: (e1, e2, key, start).

    Paths of a key's other rows may go beyond this row's text; what does is left out.
    """
    for batch in batches:
        keys = batch.column(0).to_numpy(zero_copy_only=False).astype(np.int64)
        h, doc = named_words(batch.column(1), bits)
        begin = _first_words(doc, len(keys))
        starts, edges = (batch.column(i).flatten().to_numpy(zero_copy_only=False).astype(np.int64) for i in (2, 3))
        of = np.repeat(np.arange(len(keys)), pc.list_value_length(batch.column(2)).to_numpy(zero_copy_only=False))
        start = np.repeat(starts - (np.cumsum(edges) - edges), edges) + np.arange(edges.sum())
        of = np.repeat(of, edges)
        there = start + K <= (begin[of + 1] - begin[of])
        of, start = of[there], start[there]
        at = begin[of] + start
        e1, e2 = (h[at] for _ in _MULT)
        for j in range(1, K):
            word = h[at + j]
            e1, e2 = e1 * _MULT[0] + word, e2 * _MULT[1] + word
        yield pa.RecordBatch.from_arrays([_signed(_mixed(e1)), _signed(_mixed(e2)), pa.array(keys[of]), pa.array(start.astype(np.int32))], names=["e1", "e2", "key", "start"])


def _texts(docs: DataFrame, key: str) -> DataFrame:
    text = F.col("text").cast("string")
    return docs.select(F.col(f"`{key}`").cast("long").alias("key"), F.xxhash64(text).alias("row"), text.alias("text"))


def repeated_pieces(docs: DataFrame, key: str = "doc_id", bits: int = 64) -> DataFrame:
    """(kind, piece, key, start, edges, source, source_start): all occurrences of pieces that
    start in several documents, those in their source too.  kind: 0 for whole paths, 1 for
    single edges.  bits: of a word's hash (fewer are for tests of collisions).
    """
    texts = _texts(docs, key).where("key is not null").select("key", "text")
    cut = texts.mapInArrow(lambda b: _cut(b, bits), "mini bigint, key bigint, start int, edges int, content bigint")
    several = cut.groupBy("mini").agg(F.min("key").alias("low"), F.max("key").alias("high")).where("low < high").select("mini", "low")
    shared = materialize(cut.join(several, "mini"), "paths")
    at = F.struct("key", "start")
    first = shared.groupBy("mini", "content").agg(F.min(at).alias("s"), F.max("key").alias("last")).where("s.key < last")
    judged = materialize(shared.join(first.select("mini", "content", F.col("s.key").alias("source"), F.col("s.start").alias("source_start")), ["mini", "content"], "left"), "judged")
    discard(shared)
    columns = ("key", "start", "edges", "source", "source_start")
    whole = judged.where("source is not null").select(F.lit(0).alias("kind"), F.xxhash64("mini", "content").alias("piece"), *columns)
    # open what may share single edges with a smaller document: its own paths, and those of
    # others that could hold them; a path equal to a smaller document's needs no opening
    doubtful = judged.where("low < key and not coalesce(source < key, false)").select("mini").distinct()
    holders = judged.where("not coalesce(source < key, false)").join(doubtful, "mini", "left_semi").select("key", "start", "edges")
    to_open = materialize(holders.groupBy("key").agg(F.collect_list(F.struct("start", "edges")).alias("p")), "open")
    asked = texts.join(to_open.hint("merge"), "key").select("key", "text", F.col("p.start").alias("starts"), F.col("p.edges").alias("edges"))
    edges = materialize(asked.mapInArrow(lambda b: _open(b, bits), "e1 bigint, e2 bigint, key bigint, start int"), "edges")
    discard(to_open)
    least = edges.groupBy("e1", "e2").agg(F.min(at).alias("s"), F.max("key").alias("last")).where("s.key < last").select("e1", "e2", F.col("s.key").alias("source"), F.col("s.start").alias("source_start"))
    single = edges.join(least, ["e1", "e2"]).select(F.lit(1).alias("kind"), F.xxhash64("e1", "e2").alias("piece"), "key", "start", F.lit(1).alias("edges"), "source", "source_start")
    return whole.union(single)


def nonbranching_paths(pieces: DataFrame) -> DataFrame:
    """(key, start, words, source, source_start): one row for each occurrence of a maximal
    nonbranching path of whole pieces, and for each single edge (edges are opened where
    documents part, so they lie at branches), but those in the source document."""
    whole = pieces.where("kind = 0")
    order = Window.partitionBy("key").orderBy("start", "piece")
    stop = F.col("start") + F.col("edges")
    linked = whole.withColumns({"a": F.lead("start").over(order), "b": F.lead("piece").over(order), "c": F.lag(stop).over(order), "d": F.lag("piece").over(order)})
    linked = materialize(linked.select("piece", "key", "start", "edges", "source", "source_start", F.when(F.col("a") == stop, F.col("b")).alias("next"), F.when(F.col("c") == F.col("start"), F.col("d")).alias("last")), "links")
    every = F.count(F.lit(1))
    only = lambda c: F.when((F.min(c) == F.max(c)) & (F.count(c) == every), F.min(c)).alias(c)
    degrees = materialize(linked.groupBy("piece").agg(only("next"), only("last")), "degrees")
    # the path goes on where the only piece before has this one as its only piece after
    ends = degrees.where("next is not null").select(F.col("piece").alias("last"), F.col("next").alias("piece"))
    goes_on = degrees.where("last is not null").select("piece", "last").join(ends, ["piece", "last"], "left_semi").select("piece", F.lit(0).alias("fresh"))
    mine = linked.where("source < key").join(goes_on, "piece", "left").withColumn("path", F.sum(F.coalesce("fresh", F.lit(1))).over(Window.partitionBy("key").orderBy("start", "piece")))
    paths = mine.groupBy("key", "path").agg(F.min(F.struct("start", "source", "source_start")).alias("h"), F.max(stop).alias("stop"))
    long = lambda n: (n + (K - 1)).cast("int").alias("words")
    compact = paths.select("key", F.col("h.start").alias("start"), long(F.col("stop") - F.col("h.start")), F.col("h.source").alias("source"), F.col("h.source_start").alias("source_start"))
    return compact.union(pieces.where("kind = 1 and source < key").select("key", "start", long(F.col("edges")), "source", "source_start"))


def merged_spans(paths: DataFrame) -> DataFrame:
    """Paths of a document that follow each other in one source too are one long span."""
    order = Window.partitionBy("key").orderBy("start", "words")
    shift, stop = F.col("source_start") - F.col("start"), F.col("start") + F.col("words")
    same = (F.lag("source").over(order) == F.col("source")) & (F.lag(shift).over(order) == shift) & (F.lag(stop).over(order) >= F.col("start"))
    grouped = paths.withColumn("fresh", F.when(same, 0).otherwise(1)).withColumn("span", F.sum("fresh").over(order)).groupBy("key", "span")
    out = grouped.agg(F.min(F.struct("start", "source", "source_start")).alias("h"), F.max(stop).alias("stop"))
    return out.select("key", F.col("h.start").alias("start"), (F.col("stop") - F.col("h.start")).cast("int").alias("words"), F.col("h.source").alias("source"), F.col("h.source_start").alias("source_start"))


_SPAN = "start int, words int, source bigint, source_start int"


def _read_spans(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(key, row, text, spans) -> (key, row, start, words, source, source_start, digest)."""
    names = ("key", "row", "start", "words", "source", "source_start", "digest")
    for batch in batches:
        out: list[list] = [[] for _ in names]
        for key, row, text, spans in zip(*(batch.column(i) for i in range(4))):
            words = words_of(text.as_py())
            for s in spans.as_py():
                if s["start"] + s["words"] <= len(words):
                    digest = hashlib.blake2b(b" ".join(words[s["start"] : s["start"] + s["words"]]), digest_size=16).digest()
                    for o, x in zip(out, (key.as_py(), row.as_py(), s["start"], s["words"], s["source"], s["source_start"], digest)):
                        o.append(x)
        kinds = (pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.int32(), pa.binary())
        yield pa.RecordBatch.from_arrays([pa.array(o, t) for o, t in zip(out, kinds)], names=list(names))


def verified_spans(docs: DataFrame, spans: DataFrame, key: str = "doc_id") -> DataFrame:
    """(key, row, start, words, source, source_start): ``spans`` whose words are those at their
    source's coordinates; row: hash of the text that has them."""
    spans = materialize(spans, "spans")
    none = lambda kind: F.lit(None).cast(kind)
    own = spans.select("key", F.struct("start", "words", "source", "source_start").alias("s"))
    # of copies only one asks for the source's words
    asked = spans.select("source", "source_start", "words").distinct().select(F.col("source").alias("key"), F.struct(F.col("source_start").alias("start"), "words", none("bigint").alias("source"), none("int").alias("source_start")).alias("s"))
    wanted = materialize(own.union(asked).groupBy("key").agg(F.collect_list("s").alias("spans")), "wanted")
    texts = _texts(docs, key).where("key is not null").join(wanted.hint("merge"), "key").select("key", "row", "text", "spans")
    read = materialize(texts.mapInArrow(_read_spans, f"key bigint, row bigint, {_SPAN}, digest binary"), "digests")
    for t in (spans, wanted):
        discard(t)
    there = read.where("source is null").select(F.col("key").alias("source"), F.col("start").alias("source_start"), "words", "digest")
    return read.where("source is not null").join(there, ["source", "source_start", "words", "digest"], "left_semi").select("key", "row", "start", "words", "source", "source_start")


def _spans(docs: DataFrame, key: str, bits: int) -> DataFrame:
    return verified_spans(docs, merged_spans(nonbranching_paths(repeated_pieces(docs, key, bits))), key)


def repeated_spans(docs: DataFrame, key: str = "doc_id", bits: int = 64) -> DataFrame:
    """(key, start, words, source, source_start): verified spans, in words.  Spans of
    different sources may overlap in up to K - 1 words."""
    return _spans(docs, key, bits).select("key", "start", "words", "source", "source_start").distinct()


def _kept(words: list[bytes], spans) -> list[bytes]:
    kept, at = [], 0
    for s in sorted(spans, key=lambda s: s["start"]):
        if s["start"] > at:
            kept += words[at : s["start"]]
        at = max(at, s["start"] + s["words"])
    return kept + words[at:]


def _removed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        out: list[list] = [[], [], [], []]
        for key, text, spans in zip(*(batch.column(i) for i in range(3))):
            words = words_of(text.as_py())
            kept = _kept(words, spans.as_py() or [])
            rest = b" ".join(kept)
            for part, x in zip(out, (key.as_py(), len(words), len(words) - len(kept), rest)):
                part.append(x)
        yield pa.RecordBatch.from_arrays([pa.array(out[0], pa.int64()), pa.array(out[1], pa.int64()), pa.array(out[2], pa.int64()), pa.array([hashlib.sha256(x).hexdigest() for x in out[3]])], names=["key", "n_words", "n_removed", "kept_sha256"])


def _by_row(docs: DataFrame, key: str, bits: int) -> DataFrame:
    return materialize(_spans(docs, key, bits).groupBy("key", "row").agg(F.collect_list(F.struct("start", "words")).alias("spans")), "spans")


def removal_digests(docs: DataFrame, key: str = "doc_id", bits: int = 64) -> DataFrame:
    """key, n_words, n_removed, kept_sha256 (of the kept words joined by one space) for every row."""
    spans = _by_row(docs, key, bits)
    return _texts(docs, key).join(spans.hint("merge"), ["key", "row"], "left").select("key", "text", "spans").mapInArrow(_removed, "key bigint, n_words bigint, n_removed bigint, kept_sha256 string")


def drop_repeats(docs: DataFrame, key: str = "doc_id", bits: int = 64) -> DataFrame:
    """``docs`` with repeated words removed from the text, kept words joined by one space;
    texts without any stay as they were."""
    spans = _by_row(docs, key, bits)
    row, mine, at, found = (own_name(docs.columns, c) for c in ("_row", "_key", "_hash", "_spans"))

    @F.pandas_udf("string")
    def cleaned(texts, spans):
        def one(text, found):
            if text is None or found is None or not len(found):
                return text
            return b" ".join(_kept(words_of(text), found)).decode("utf-8", "surrogatepass")

        import pandas as pd

        return pd.Series([one(t if isinstance(t, str) else None, s) for t, s in zip(texts, spans)], dtype=object)

    text = F.col("text").cast("string")
    tagged = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias(row), F.col(f"`{key}`").cast("long").alias(mine), F.xxhash64(text).alias(at))
    spans = spans.select(F.col("key").alias(mine), F.col("row").alias(at), F.col("spans").alias(found))
    out = tagged.join(spans.hint("merge"), [mine, at], "left")
    return out.select(*[(cleaned(F.col(row).getField(c), F.col(found)) if c == "text" else F.col(row).getField(c)).alias(c) for c in docs.columns])
