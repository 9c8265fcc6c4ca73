"""Personal data by weak-supervision aggregation.

Base kinds (email, ip, card, phone) are found by fixed patterns and always stay.  Wide
patterns propose further spans, most of which are not personal data: values after a name,
known key prefixes and any long run of letters and digits (secrets), bank and identity
numbers and any long number (accounts), and all dates (births).  Labelers vote on each
proposed span or abstain: its form (regex), a gazetteer of cue words and of words that say
otherwise (in four languages) for what is close, cues in the wider context, its mix of
characters, and what is odd about it or its surroundings.  For each kind by itself,
expectation-maximisation over counts of vote patterns estimates how often proposals are
personal data and how often each labeler is right; the posteriors train the kind's logistic
span classifier on votes and features of the proposals, and spans that it accepts are added.

Texts are read once: their spans and proposals are written, never the texts themselves.
Vote patterns number at most 3 ** 5 a kind.

Edge cases: null counts as empty and has no spans; overlapping proposals keep the base span
or else the leftmost, longest one; repeated rows are alike; an empty table gives an empty table.
"""

from __future__ import annotations

import hashlib
import math
import re
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialize

KINDS = ("email", "ip", "card", "phone")
ADDED = ("account", "birth", "secret")
LABELERS = ("form", "cue", "context", "mix", "odd")
#: Features of a proposal after its bias and votes: length, digits, letters, whether a name stands before it.
OTHER_FEATURES = 4

_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
# A match cannot begin inside a run of digits whose beginning fails, so the look-behind
# only keeps long runs from being tried at every digit.
_IP = re.compile(r"(?<![0-9])([0-9]+)\.([0-9]+)\.([0-9]+)\.([0-9]+)")
_CARD = re.compile(r"[0-9](?:[ -]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
_DIGIT = re.compile(r"[0-9]")


def _emails(text: str) -> list[tuple[int, int]]:
    """One backward walk from each @ over the characters of a local part; linear in the text."""
    found, free, at = [], 0, text.find("@")
    while at >= 0:
        start = at
        while start > free and text[start - 1] in _LOCAL:
            start -= 1
        tail = _DOMAIN.match(text, at + 1) if start < at else None
        if tail:
            found.append((start, tail.end()))
        free = tail.end() if tail else at + 1
        at = text.find("@", free)
    return found


def _luhn(digits: str) -> bool:
    total = 0
    for i, d in enumerate(map(int, reversed(digits))):
        total += d if i % 2 == 0 else d * 2 - 9 * (d > 4)
    return total % 10 == 0


def base_spans(text: str | None) -> list[tuple[str, int, int]]:
    """(kind, start, end) by kind, then start; code points, end exclusive."""
    text = text or ""
    out = [("email", a, b) for a, b in _emails(text)] if "@" in text else []
    if _DIGIT.search(text):
        small = lambda p: len(p := p.lstrip("0")) <= 3 and int(p or 0) <= 255
        out += [("ip", m.start(), m.end()) for m in _IP.finditer(text) if all(map(small, m.groups()))] if "." in text else []
        for m in _CARD.finditer(text):
            if 16 <= m.end() - m.start() <= 37 and 16 <= len(d := re.sub("[ -]", "", m[0])) <= 19 and _luhn(d):
                out.append(("card", m.start(), m.end()))
        if "+" in text:
            out += [("phone", m.start(), m.end()) for m in _PHONE.finditer(text) if 8 <= sum(map(str.isdigit, m[0])) <= 15]
    return out


#: Words that name a kind of personal data, in English, German, French, Spanish.
_CUE = {
    "secret": (
        "password", "passwd", "pwd", "pass", "passphrase", "passcode", "pin", "token", "secret", "api_key", "apikey", "api", "access_key", "key", "private", "bearer", "credential", "credentials", "auth", "authorization",
        "oauth", "session", "cookie", "signature", "login", "passwort", "kennwort", "geheim", "schlüssel", "zugang", "motdepasse", "clé", "jeton", "secrète", "contraseña", "clave", "secreto", "ficha",
    ),
    "account": (
        "iban", "bic", "swift", "account", "acct", "acc", "routing", "konto", "kontonummer", "bankverbindung", "blz", "compte", "bancaire", "rib", "cuenta", "bancaria", "ssn", "social", "security", "passport", "reisepass",
        "passeport", "pasaporte", "ausweis", "steuernummer", "steuer", "tax", "taxpayer", "insurance", "policy", "versicherung", "licence", "license", "dni", "nif", "nie",
    ),
    "birth": (
        "born", "birth", "birthday", "birthdate", "dob", "geboren", "geburt", "geburtstag", "geburtsdatum", "geb", "né", "née", "naissance", "anniversaire", "nacido", "nacida", "nacimiento", "cumpleaños",
    ),
}
#: Words that say that a number, date or name is something else.
_OTHER = frozenset((
    "section", "chapter", "page", "figure", "table", "version", "release", "build", "part", "paragraph", "line", "lines", "id", "no", "number", "nr", "nummer", "ratio", "total", "sum", "amount", "price", "size", "length", "count",
    "isbn", "issn", "doi", "order", "invoice", "ticket", "meeting", "published", "updated", "posted", "created", "date", "due", "deadline", "conference", "edition", "volume", "title", "name", "author", "commit", "revision", "checksum", "digest", "hash", "sha", "md5", "http", "https", "url", "see",
    "kapitel", "seite", "abschnitt", "rechnung", "datum", "termin", "treffen", "chapitre", "facture", "réunion", "publié", "capítulo", "página", "factura", "reunión", "publicado", "fecha",
))
# Names and values have any length.  Possessive runs, and names that only begin where a run
# does, keep the search linear.
_SECRET = re.compile(r"(?i)(?<![a-z0-9_-])[0-9_-]*+([a-z][a-z0-9_-]{2,}+)\s{0,2}[:=]\s{0,2}[\"']?([^\s\"',;]{8,}+)|\b((?:sk|pk|ghp|xox[abp]|AKIA)[_-]?[A-Za-z0-9_-]{16,}(?<=[A-Za-z0-9_]))")
# Any long run could be a secret, any long number an account: most are not, and show the labelers so.
_RUN = re.compile(r"(?<![A-Za-z0-9_+/-])[A-Za-z0-9_+/-]{16,}(?<=[A-Za-z0-9_])")
_NUMBER = re.compile(r"(?<![0-9A-Za-z.+-])[0-9]{8,}+(?![0-9A-Za-z])")
_PARTS = re.compile(r"[^\W_]+")
_ACCOUNT = re.compile(r"\b([A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){3,7}(?: ?[A-Z0-9]{1,3})?|[0-9]{3}-[0-9]{2}-[0-9]{4})\b")
_BIRTH = re.compile(r"\b((?:19|20)[0-9]{2}[-/.](?:0?[1-9]|1[0-2])[-/.](?:0?[1-9]|[12][0-9]|3[01])|(?:0?[1-9]|[12][0-9]|3[01])[-/.](?:0?[1-9]|1[0-2])[-/.](?:19|20)[0-9]{2})\b")
_FORM = {"secret": re.compile(r"(?=.*[0-9])(?=.*[A-Za-z])[A-Za-z0-9+/_=.-]{8,}$"), "account": re.compile(r"[A-Z]{2}[0-9]{2}[A-Z0-9 ]{11,}$|[0-9]{3}-[0-9]{2}-[0-9]{4}$")}
_HEX = re.compile(r"(?:[0-9a-f]+|[0-9A-F]+)$")
_YEAR = re.compile(r"(?:19|20)[0-9]{2}")
_WORD = re.compile(r"[^\W\d_]+")


def _vote(yes: bool, no: bool) -> int:
    return 1 if yes else -1 if no else 0


def _raw(text: str) -> list[tuple[int, int, str, str]]:
    """(start, end, kind, name before it) of all that might be personal data."""
    out: list[tuple[int, int, str, str]] = []
    if "=" in text or ":" in text or "_" in text or "-" in text:
        for m in _SECRET.finditer(text):
            out.append((m.start(2), m.end(2), "secret", m[1]) if m[2] else (m.start(3), m.end(3), "secret", ""))
            if m[2]:  # the name is no candidate of its own
                out.append((m.start(1), m.end(1), "", ""))
    out += [(m.start(), m.end(), "secret", "") for m in _RUN.finditer(text)]
    if _DIGIT.search(text):
        out += [(m.start(), m.end(), "account", "") for m in _ACCOUNT.finditer(text)]
        out += [(m.start(), m.end(), "account", "") for m in _NUMBER.finditer(text)]
        out += [(m.start(), m.end(), "birth", "") for m in _BIRTH.finditer(text)]
    return out


_ORDER = {"": 0, "birth": 1, "account": 2, "secret": 3}


def _labels(kind: str, name: str, span: str, before: str, after: str) -> tuple[int, ...]:
    """Votes of the labelers in the order of ``LABELERS``."""
    near, later = _WORD.findall(before.lower()), _WORD.findall(after.lower())[:4]
    parts = _PARTS.findall(name.lower()) + ([name.lower()] if name else [])
    digits, letters = sum(map(str.isdigit, span)) / len(span), sum(map(str.isalpha, span)) / len(span)
    entropy = -sum(p * math.log2(p) for p in (span.count(c) / len(span) for c in set(span)))
    cues, close = _CUE[kind], parts or near[-3:]
    cue = any(w in cues for w in close)
    around = any(w in cues for w in near[-8:] + later + parts)
    if kind == "secret":
        return (
            _vote(bool(_FORM[kind].match(span)), not digits or not letters),
            _vote(cue, bool(name) or any(w in _OTHER for w in close)),
            _vote(around, not name and len(near) + len(later) > 2 or bool(name)),
            0 if _HEX.match(span) else _vote(digits >= 0.1 and letters > 0.05, digits < 0.05 or letters <= 0.05),  # hex may be a mere digest
            _vote(entropy >= 2.5 and digits > 0, entropy < 2.0 or not digits),
        )
    if kind == "account":
        return (
            _vote(bool(_FORM[kind].match(span)), len(span) > 34),
            _vote(cue, not near or any(w in _OTHER for w in close)),
            _vote(around, True),
            _vote(letters > 0, len(set(span)) < 3),
            _vote(bool(re.search(r"(?:[:=#]|\bis|\bist|\best|\bes|\bno\.?|\bnr\.?|\bnumber|\bnummer|\bnuméro|\bnúmero)\s*$", before)), before[-1:].isalpha() or bool(re.search(r"[^\W\d_]\s+$", before))),
        )
    year = int(_YEAR.search(span)[0])
    return (
        0,  # the pattern that proposes a date says nothing more
        _vote(cue, True),
        _vote(around, any(w in _OTHER for w in near[-8:] + later) or not cue),
        _vote(1920 <= year <= 2010, year > 2015),
        _vote(bool(re.search(r"[:=(*]\s*$", before)) and around, bool(re.search(r"(?:\b(?:until|till|by|since|from|bis|ab|seit|depuis|desde|hasta))\s+$", before.lower()))),
    )


def proposals(text: str | None, taken: list[tuple[str, int, int]]) -> list[tuple[str, int, int, tuple[int, ...], tuple[float, ...]]]:
    """(kind, start, end, votes, features) of spans that no base span overlaps."""
    text = text or ""
    out, base, end, at = [], sorted((a, b) for _, a, b in taken), 0, 0
    for a, b, kind, name in sorted(_raw(text), key=lambda r: (r[0], _ORDER[r[2]], -r[1])):
        while at < len(base) and base[at][1] <= a:
            at += 1
        if a < end or (at < len(base) and base[at][0] < b):
            continue
        if not kind:
            end = b
            continue
        end, span = b, text[a:b]
        short = span if len(span) <= 4096 else span[:4096]  # of its characters' mix, which a part shows
        votes = _labels(kind, name, short, text[max(0, a - 64) : a], text[b : b + 48])
        digits, letters = sum(map(str.isdigit, short)) / len(short), sum(map(str.isalpha, short)) / len(short)
        out.append((kind, a, b, votes, (1.0, *map(float, votes), min(len(span), 64) / 64, digits, letters, float(bool(name)))))
    return out


_SCHEMA = "key bigint, base array<struct<kind: string, start: int, stop: int>>, more array<struct<kind: string, start: int, stop: int, votes: string, features: array<double>>>"


def _scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    span = [("kind", pa.string()), ("start", pa.int32()), ("stop", pa.int32())]
    base_type = pa.list_(pa.struct(span))
    more_type = pa.list_(pa.struct([*span, ("votes", pa.string()), ("features", pa.list_(pa.float64()))]))
    for batch in batches:
        base, more = [], []
        for text in batch.column(1):
            found = base_spans(text := text.as_py())
            base.append([{"kind": k, "start": a, "stop": b} for k, a, b in found])
            more.append([{"kind": k, "start": a, "stop": b, "votes": ",".join(map(str, v)), "features": list(x)} for k, a, b, v, x in proposals(text, found)])
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(base, base_type), pa.array(more, more_type)], names=["key", "base", "more"])


@dataclass(frozen=True)
class PiiParams:
    """right, prior: what estimation starts from, of a labeler and of a kind's proposals; they
    count as ``smoothing`` further votes and ``anchor`` of those given.  ridge: pull of the
    classifier's weights to those of the votes alone.  threshold: least accepted probability.
    fit_rows: most distinct (kind, votes, rounded features) rows that the classifier is fitted on."""

    right: float = 0.8
    prior: float = 0.3
    smoothing: float = 4.0
    anchor: float = 0.2
    ridge: float = 4.0
    threshold: float = 0.5
    iterations: int = 50
    fit_rows: int = 5_000


class KindModel:
    """For one kind: how often proposals are personal data, how often each labeler is right
    when it votes, and the classifier that the posteriors train."""

    def __init__(self, patterns: list[tuple[tuple[int, ...], float]], rows: list[tuple[tuple[int, ...], list[float], float]], params: PiiParams = PiiParams()):
        p, k = params, len(LABELERS)
        self.prior, self.right = p.prior, [p.right] * k
        blend = lambda hits, n, start: (hits + (p.smoothing + p.anchor * n) * start) / (n + p.smoothing + p.anchor * n)
        for _ in range(p.iterations if patterns else 0):
            hits, given, yes, total = [0.0] * k, [0.0] * k, 0.0, 0.0
            for votes, n in patterns:
                q = self.posterior(votes)
                yes, total = yes + n * q, total + n
                for j, v in enumerate(votes):
                    if v:
                        hits[j] += n * (q if v > 0 else 1 - q)
                        given[j] += n
            # a labeler that is wrong more often than right says nothing
            self.prior, self.right = blend(yes, total, p.prior), [max(0.5, blend(h, g, p.right)) for h, g in zip(hits, given)]
        self.weights = self._train(rows, p)

    def posterior(self, votes: tuple[int, ...]) -> float:
        s = math.log(self.prior / (1 - self.prior)) + sum(v * math.log(r / (1 - r)) for v, r in zip(votes, self.right))
        return 1 / (1 + math.exp(-max(-60.0, min(60.0, s))))

    def _train(self, rows, p: PiiParams) -> list[float]:
        """Logistic regression on posteriors; the ridge pulls to the votes' own weights, so
        with few rows the classifier is the labelers' weighted vote."""
        import numpy as np

        start = np.zeros(1 + len(LABELERS) + OTHER_FEATURES)
        start[0] = math.log(self.prior / (1 - self.prior))
        start[1 : 1 + len(LABELERS)] = [math.log(r / (1 - r)) for r in self.right]
        w = start.copy()
        if rows:
            x, n = np.array([r[1] for r in rows]), np.array([r[2] for r in rows])
            y = np.array([self.posterior(r[0]) for r in rows])
            for _ in range(50):
                q = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
                h = (x * (n * np.maximum(q * (1 - q), 1e-6))[:, None]).T @ x + p.ridge * np.eye(len(w))
                step = np.linalg.solve(h, x.T @ (n * (y - q)) - p.ridge * (w - start))
                step *= min(1.0, 5.0 / max(1e-9, np.abs(step).max()))
                w = w + step
                if np.abs(step).max() < 1e-9:
                    break
        return [float(v) for v in w]


class SpanModel:
    """One :class:`KindModel` for each kind; a kind that nothing was proposed for keeps its start."""

    def __init__(self, patterns: dict[str, list], rows: dict[str, list], params: PiiParams = PiiParams()):
        self.threshold = params.threshold
        self.kinds = {kind: KindModel(patterns.get(kind, []), rows.get(kind, []), params) for kind in ADDED}

    def score(self, kind: str, features) -> float:
        s = sum(w * f for w, f in zip(self.kinds[kind].weights, features))
        return 1 / (1 + math.exp(-max(-60.0, min(60.0, s))))

    def accepts(self, kind: str, features) -> bool:
        return self.score(kind, features) >= self.threshold


def fit_spans(found: DataFrame, params: PiiParams = PiiParams()) -> SpanModel:
    """Patterns over all proposals; classifiers on the distinct rows with the least hashes, at most ``fit_rows``."""
    one = found.select(F.explode("more").alias("m")).select("m.kind", "m.votes", F.transform("m.features", lambda v: F.round(v, 2)).alias("features"))
    read = lambda v: tuple(map(int, v.split(",")))
    patterns: dict[str, list] = {}
    for r in sorted(one.groupBy("kind", "votes").count().collect(), key=lambda r: (r["kind"], r["votes"])):
        patterns.setdefault(r["kind"], []).append((read(r["votes"]), float(r["count"])))
    rows: dict[str, list] = {}
    for r in sorted(one.groupBy("kind", "votes", "features").count().orderBy(F.xxhash64("kind", "votes", "features"), "kind", "votes").limit(params.fit_rows).collect(), key=lambda r: (r["kind"], r["votes"], r["features"])):
        rows.setdefault(r["kind"], []).append((read(r["votes"]), list(r["features"]), float(r["count"])))
    return SpanModel(patterns, rows, params)


def joined(spans: list[tuple[str, int, int]]) -> str:
    order = {k: i for i, k in enumerate(KINDS + ADDED)}
    return ",".join(f"{k}:{a}:{b}" for k, a, b in sorted(spans, key=lambda s: (order[s[0]], s[1])))


def find_personal_data(docs: DataFrame, key: str = "doc_id", params: PiiParams = PiiParams()) -> DataFrame:
    """key, base and spans (arrays of kind, start, stop) for every row."""
    found = materialize(docs.select(F.col(f"`{key}`").cast("long").alias("key"), F.col("text").cast("string").alias("text")).mapInArrow(_scan, _SCHEMA), "spans")
    model = fit_spans(found, params)
    weights = F.create_map(*[x for kind in ADDED for x in (F.lit(kind), F.array(*map(F.lit, model.kinds[kind].weights)))])
    score = lambda m: F.aggregate(F.zip_with(m["features"], F.try_element_at(weights, m["kind"]), lambda a, b: a * b), F.lit(0.0), lambda a, v: a + v)
    more = F.filter("more", lambda m: 1 / (1 + F.exp(-score(m))) >= model.threshold)
    plain = lambda m: F.struct(m["kind"].alias("kind"), m["start"].alias("start"), m["stop"].alias("stop"))
    return found.select("key", "base", F.concat("base", F.transform(more, plain)).alias("spans"))


def span_string(spans):
    """``kind:start:end`` by kind as listed, then start."""
    names = F.array(*map(F.lit, KINDS + ADDED))
    keyed = F.sort_array(F.transform(spans, lambda s: F.struct(F.array_position(names, s["kind"]).alias("k"), s["start"].alias("a"), s["stop"].alias("b"), s["kind"].alias("n"))))
    return F.concat_ws(",", F.transform(keyed, lambda s: F.concat_ws(":", s["n"], s["a"], s["b"])))


def redact(docs: DataFrame, text: str = "text", params: PiiParams = PiiParams()) -> DataFrame:
    """``docs`` with every span of the text replaced by its kind in brackets, e.g. ``[email]``.

    Of spans that overlap, the leftmost (then longest) names the replacement of them all.
    Other columns stay as they were.  Two passes over the texts, no shuffle of them.
    """
    scanned = docs.select(F.lit(0).cast("long").alias("key"), F.col(text).cast("string").alias("text")).mapInArrow(_scan, _SCHEMA)
    model = fit_spans(materialize(scanned.where("size(more) > 0").select("more"), "proposals"), params)

    @F.pandas_udf("string")
    def cleaned(texts):
        return texts.map(lambda t: redacted(t, model) if isinstance(t, str) else None)

    return docs.withColumn(text, cleaned(F.col(text)))


def redacted(text: str, model: SpanModel) -> str:
    base = base_spans(text)
    spans = base + [(k, a, b) for k, a, b, _, x in proposals(text, base) if model.accepts(k, x)]
    out, at, end = [], 0, 0
    for kind, a, b in sorted(spans, key=lambda s: (s[1], -s[2], s[0])):
        if a >= end:
            out += [text[at:a], f"[{kind}]"]
        end = max(end, b)
        at = end
    return "".join(out) + text[at:]


def digest(base: list[tuple[str, int, int]]) -> str:
    return hashlib.sha256(joined(base).encode()).hexdigest()
