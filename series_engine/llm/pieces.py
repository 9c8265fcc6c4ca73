"""SentencePiece encoding by streaming Viterbi, and decoding.

The best segmentation is the one with the greatest sum of piece scores.  Text is read
character by character; only the last ``longest piece`` positions can begin a piece that
is still to come, so whenever the backpointer paths of all those positions meet in one
boundary, everything before it is decided: its ids are committed and dropped from the
window.  Characters that no piece covers are written as byte pieces.

Where the vocabulary shows that no piece crosses from a character into a space mark, all
paths meet before such a mark whatever follows, so units between them are encoded by
themselves and remembered in a table of bounded size.

The segmentation is that of a unigram model with the file's pieces and scores.  A file
whose own type is BPE would be merged pair by pair by its library; its ids can differ from
these, and decode to the same text.

Edge cases: null and empty texts have no ids; a text that the normaliser of the file
changes decodes to its normalised form; very long texts and words keep a bounded window
(but for text in which no boundary is ever decided); an empty table gives an empty table.
"""

from __future__ import annotations

import hashlib
import re
import zlib
from collections.abc import Iterator
from functools import lru_cache
from struct import pack

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

MARK = "▁"
#: Most units remembered by a process, and the most characters of one.
MEMO, MEMO_CHARS = 200_000, 64
_BEFORE_SPACES = re.compile(r"[^ ] ")
_UNITS = re.compile(f"{MARK}+[^{MARK}]*|[^{MARK}]+")


def default_file() -> str:
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


class Pieces:
    """Vocabulary of a model file: text of each id, scores of the pieces that text can be cut into."""

    def __init__(self, file: str):
        import sentencepiece

        self.lib = sentencepiece.SentencePieceProcessor(model_file=file)
        lib, n = self.lib, self.lib.get_piece_size()
        self.unknown = lib.unk_id()
        self.bytes = [lib.piece_to_id(f"<0x{b:02X}>") for b in range(256)]
        self.scores: dict[str, tuple[float, int]] = {}
        self.text: list[bytes] = []
        for i in range(n):
            piece = lib.id_to_piece(i)
            if lib.is_byte(i):
                self.text.append(bytes([int(piece[3:5], 16)]))
            elif lib.is_control(i):
                self.text.append(b"")
            else:
                self.text.append(piece.replace(MARK, " ").encode())
                if not lib.is_unknown(i) and not lib.is_unused(i):
                    self.scores[piece] = (lib.get_score(i), i)
        #: Scores and ids again, with what only begins a piece as an empty entry: a walk from a
        #: start ends at the first text that is not in here.
        self.walk: dict[str, tuple] = {p[:i]: () for p in self.scores for i in range(1, len(p))}
        self.walk.update(self.scores)
        self.longest = max(map(len, self.scores), default=1)
        self.penalty = min((s for s, _ in self.scores.values()), default=0.0) - 10.0
        self.cut_at_marks = all(MARK not in p[1:] or not p.strip(MARK) for p in self.scores)
        self.byte_fallback = all(lib.is_byte(i) for i in self.bytes)
        self.dummy = lib.normalize("a") == f"{MARK}a"
        #: Whether spaces come out as they are, so that a text can be normalised in parts.
        self.plain_spaces = lib.normalize(" a  b ").replace(MARK, " ").removeprefix(" " * self.dummy) == " a  b "

    def fallback(self, char: str) -> list[int]:
        return [self.bytes[b] for b in char.encode("utf-8", "surrogatepass")] if self.byte_fallback else [self.unknown]


class StreamingViterbi:
    """push() characters, finish() at the end; both return the ids that are decided by then."""

    def __init__(self, vocabulary: Pieces):
        self.v = vocabulary
        self.base, self.most = 0, 0  # start of the window; the largest window so far
        self.chars = ""
        self.best = [0.0]  # by position in the window
        self.back: list[tuple[int, int]] = [(0, -1)]  # (start of the last piece, its id or -1 for an uncovered character)

    def push(self, text: str) -> list[int]:
        out: list[int] = []
        step = max(32, 2 * self.v.longest)
        for at in range(0, len(text), step):
            self._extend(text[at : at + step])
            out += self._commit()
        return out

    def _extend(self, text: str) -> None:
        scores, longest, first = self.v.scores, self.v.longest, len(self.chars)
        self.chars += text
        chars, best, back = self.chars, self.best, self.back
        for end in range(first + 1, len(chars) + 1):
            top, via, piece = -float("inf"), end - 1, -1
            for start in range(max(0, end - longest), end):
                found = scores.get(chars[start:end])
                if found is not None and best[start] + found[0] > top:
                    top, via, piece = best[start] + found[0], start, found[1]
            if chars[end - 1] not in scores and best[end - 1] + self.v.penalty > top:
                top, via, piece = best[end - 1] + self.v.penalty, end - 1, -1
            best.append(top)
            back.append((via, piece))
        self.most = max(self.most, len(chars))

    def _ids(self, end: int) -> list[int]:
        parts = []
        while end > 0:
            start, piece = self.back[end]
            parts.append([piece] if piece >= 0 else self.v.fallback(self.chars[start:end]))
            end = start
        return [i for p in reversed(parts) for i in p]

    def _commit(self) -> list[int]:
        end = len(self.chars)
        alive = set(range(max(0, end - self.v.longest + 1), end + 1))
        while len(alive) > 1:  # the last position steps back until all have met
            last = max(alive)
            alive.remove(last)
            alive.add(self.back[last][0])
        met = alive.pop()
        if met <= 0:
            return []
        out = self._ids(met)
        self.base += met
        self.chars, zero = self.chars[met:], self.best[met]
        self.best = [b - zero for b in self.best[met:]]
        self.back = [(0, -1)] + [(a - met, p) for a, p in self.back[met + 1 :]]
        return out

    def finish(self) -> list[int]:
        out = self._ids(len(self.chars))
        self.__init__(self.v)
        return out


def short_cut(unit: str, v: Pieces) -> list[int]:
    """The same segmentation for a unit that lies in one window: nothing can be committed
    before its end.  Walks from each start over the texts that begin a piece."""
    n, walk, low = len(unit), v.walk, -float("inf")
    best, back = [0.0] + [low] * n, [(0, -1)] * (n + 1)
    for start in range(n):
        score = best[start]
        for end in range(start + 1, n + 1):
            found = walk.get(unit[start:end])
            if found is None:
                break
            if found and score + found[0] > best[end]:
                best[end], back[end] = score + found[0], (start, found[1])
        if best[start + 1] < score + v.penalty and unit[start] not in v.scores:
            best[start + 1], back[start + 1] = score + v.penalty, (start, -1)
    out: list[int] = []
    while n:
        start, piece = back[n]
        if piece >= 0:
            out.append(piece)
        else:
            out += reversed(v.fallback(unit[start:n]))
        n = start
    out.reverse()
    return out


class _Memo(dict):
    """Unit -> its ids as little-endian 32-bit bytes.  A full table becomes the old generation,
    from which units that are asked for again come back."""

    def __init__(self, vocabulary: Pieces):
        super().__init__()
        self.v, self.old = vocabulary, {}

    def __missing__(self, unit: str) -> bytes:
        found = self.old.get(unit)
        if found is None and len(unit) <= MEMO_CHARS:
            ids = short_cut(unit, self.v)
            found = pack(f"<{len(ids)}I", *ids)
        elif found is None:
            stream = StreamingViterbi(self.v)
            return np.array(stream.push(unit) + stream.finish(), "<u4").tobytes()
        if len(self) >= MEMO:
            self.old = dict(self)
            self.clear()
        self[unit] = found
        return found


@lru_cache(maxsize=4)
def vocabulary(file: str) -> tuple[Pieces, _Memo]:
    v = Pieces(file)
    return v, _Memo(v)


#: Characters that are normalised together, up to the next space; longer texts are cut there.
NORMAL = 1 << 16


def normal_parts(text: str, v: Pieces) -> Iterator[str]:
    """The normalised text, part by part: a part after the first begins with a space, at which
    normalisation never looks back, and loses the mark that the file puts before every text."""
    at = 0
    while at < len(text):
        stop = len(text)
        if stop - at > NORMAL and v.plain_spaces:  # before a run of spaces, as pieces hold several
            near = _BEFORE_SPACES.search(text, at + NORMAL)
            stop = near.start() + 1 if near else stop
        part = v.lib.normalize(text[at:stop])
        yield part[1:] if at and v.dummy else part
        at = stop


def encode(text: str | None, file: str) -> np.ndarray:
    """Ids of the normalised text."""
    v, memo = vocabulary(file)
    if not text:
        return np.zeros(0, "<u4")
    if v.cut_at_marks:  # a part begins with a mark, before which all paths meet
        return np.frombuffer(b"".join(ids for part in normal_parts(text, v) for ids in map(memo.__getitem__, _UNITS.findall(part))), "<u4")
    stream, out = StreamingViterbi(v), []
    for part in normal_parts(text, v):
        out += stream.push(part)
    return np.array(out + stream.finish(), "<u4")


def decode(ids, file: str) -> str:
    v, _ = vocabulary(file)
    raw = b"".join(map(v.text.__getitem__, ids.tolist() if isinstance(ids, np.ndarray) else ids))
    if v.dummy and raw[:1] == b" ":
        raw = raw[1:]
    return raw.decode("utf-8", "replace")


def with_ids(docs: DataFrame, key: str = "doc_id", text: str = "text", file: str | None = None) -> DataFrame:
    """(key, ids array<int>) for every row."""
    file = file or default_file()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([encode(t.as_py(), file).astype(np.int32) for t in batch.column(1)], pa.list_(pa.int32()))], names=["key", "ids"])

    return docs.select(F.col(key).cast("long").alias("key"), F.col(text).cast("string").alias("text")).mapInArrow(run, "key bigint, ids array<int>")


def with_text(encoded: DataFrame, file: str | None = None) -> DataFrame:
    """(key, text) from (key, ids)."""
    file = file or default_file()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([decode(i.as_py() or [], file) for i in batch.column(1)], pa.string())], names=["key", "text"])

    return encoded.select("key", "ids").mapInArrow(run, "key bigint, text string")


def piece_digests(docs: DataFrame, key: str = "doc_id", text: str = "text", file: str | None = None) -> DataFrame:
    """key, n_pieces, ids_crc32 (little-endian 32-bit ids), decoded_sha256, round_trip for every row."""
    file = file or default_file()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: list[list] = [[], [], [], []]
            for t in batch.column(1):
                t = t.as_py() or ""
                ids = encode(t, file)
                back = decode(ids, file)
                for o, x in zip(out, (len(ids), zlib.crc32(ids.tobytes()), hashlib.sha256(back.encode("utf-8", "surrogatepass")).hexdigest(), back == t)):
                    o.append(x)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out[0], pa.int64()), pa.array(out[1], pa.int64()), pa.array(out[2]), pa.array(out[3])], names=["key", "n_pieces", "ids_crc32", "decoded_sha256", "round_trip"])

    return docs.select(F.col(key).cast("long").alias("key"), F.col(text).cast("string").alias("text")).mapInArrow(run, "key bigint, n_pieces bigint, ids_crc32 bigint, decoded_sha256 string, round_trip boolean")
