"""Quality rules by weak supervision.

Rules vote good (1), bad (-1) or abstain (0) on a document.  Votes are summarised as
counts of vote patterns (at most 3 ** number of rules rows, whatever the corpus) of the
documents that pass the base rules (the others are decided without votes), and
expectation-maximisation over the patterns estimates how often each rule gives each
vote in good and in bad documents.  The posterior probability of "good" replaces a
filter that asks for all rules to pass.

Every step over documents is a DataFrame expression; the driver only sees patterns.

Edge cases: a null or empty text has no words, fails the base rules and is not kept;
repeated rows are judged alike; an empty table gives an empty table (the estimation
then stays at its starting values); further columns pass through untouched.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import SPACE, materialize, text_of

WINDOW = 8
MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
RULES = ("symbols", "dup_lines", "repeats", "word_length", "upper_case", "shouting", "variety")
_P = "_quality_"


@dataclass(frozen=True)
class QualityParams:
    """min_words, max_repeat_percent: base rules.  threshold: least posterior that is kept.
    prior_good, blamed, caught: start values, which also anchor what is estimated: they count
    as ``smoothing`` further rows and as the share ``anchor`` of the votes that a rule gives in
    a class, ``anchor_prior`` of the documents."""

    min_words: int = 20
    max_repeat_percent: int = 30
    threshold: float = 0.5
    iterations: int = 60
    prior_good: float = 0.85
    smoothing: float = 2.0
    anchor: float = 0.2
    anchor_prior: float = 1.0
    blamed: float = 0.005
    caught: float = 0.2


def _covered(positions: Column) -> Column:
    """Words under windows that start at the given ascending positions."""
    start = F.struct(F.lit(0).cast("long").alias("n"), F.lit(0).cast("long").alias("end"))
    step = lambda a, p: F.struct((a["n"] + WINDOW - F.greatest(F.lit(0).cast("long"), a["end"] - p)).alias("n"), (p + WINDOW).alias("end"))
    return F.aggregate(positions, start, step, lambda a: a["n"])


def measure(docs: DataFrame, text: str = "text") -> DataFrame:
    """``docs`` with the measures and those that only the rules need (prefix ``_quality_``).

    Window repeats are found inside a row: hashes of all windows, and only where some
    hash comes twice (a linear check) a sort of (hash, position).  No row is exploded
    and nothing is shuffled.
    """
    t = text_of(docs, text)
    out = docs.withColumns({f"{_P}t": t})
    out = out.withColumns({f"{_P}w": F.filter(F.split(F.col(f"{_P}t"), SPACE), lambda w: w != ""), f"{_P}l": F.filter(F.split(F.col(f"{_P}t"), "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))})
    w, lines, t = F.col(f"{_P}w"), F.col(f"{_P}l"), F.col(f"{_P}t")
    hashes = F.when(F.size(w) >= WINDOW, F.transform(F.sequence(F.lit(1), F.size(w) - (WINDOW - 1)), lambda i: F.xxhash64(F.slice(w, i, WINDOW)))).otherwise(F.array().cast("array<bigint>"))
    kept = [c for c in out.columns if c not in (f"{_P}w", f"{_P}l", f"{_P}t")]
    out = out.select(
        *[F.col(f"`{c}`") for c in kept],
        F.size(w).cast("long").alias(f"{_P}n_words"),
        F.length(F.regexp_replace(t, SPACE, "")).cast("long").alias(f"{_P}word_chars"),
        F.length(F.regexp_replace(t, r"[^#*$%&|<>]+", "")).cast("long").alias(f"{_P}n_symbols"),
        (F.size(lines) - F.size(F.array_distinct(lines))).cast("long").alias(f"{_P}n_dup_lines"),
        F.size(lines).cast("long").alias(f"{_P}n_lines"),
        F.length(F.regexp_replace(t, r"[^A-ZÀ-ÖØ-Þ]+", "")).cast("long").alias(f"{_P}n_upper"),
        F.length(F.regexp_replace(t, r"[^!]+", "")).cast("long").alias(f"{_P}n_shout"),
        F.size(F.array_distinct(w)).cast("long").alias(f"{_P}n_distinct"),
        hashes.alias(f"{_P}h"),
    )
    h = F.col(f"{_P}h")
    pairs = F.when(F.size(h) > F.size(F.array_distinct(h)), F.sort_array(F.transform(h, lambda x, i: F.struct(x.alias("h"), i.cast("long").alias("p")))))
    out = out.withColumn(f"{_P}s", pairs).drop(f"{_P}h")
    s = F.col(f"{_P}s")
    same = lambda e, i: F.coalesce(e["h"] == F.get(s, i)["h"], F.lit(False))
    twice = F.transform(s, lambda e, i: F.when(same(e, i - 1) | same(e, i + 1), e["p"]))
    repeats = F.when(s.isNull(), F.lit(0).cast("long")).otherwise(_covered(F.sort_array(F.filter(twice, lambda p: p.isNotNull()))))
    # A generator of one row ends the projection: a filter on what stands above would
    # otherwise be pushed below it and take the array expressions along, once for each use.
    facts = [c for c in out.columns if c.startswith(_P) and c != f"{_P}s"]
    own = [F.col(f"`{c}`") for c in out.columns if not c.startswith(_P)]
    return out.select(*own, F.inline(F.array(F.struct(*facts, repeats.alias(f"{_P}n_repeat_words")))))


def _m(name: str) -> Column:
    return F.col(f"{_P}{name}")


def _vote(bad: Column, good: Column) -> Column:
    return F.when(bad, -1).when(good, 1).otherwise(0).cast("tinyint")


def votes() -> dict[str, Column]:
    """One vote column for each rule, over the columns of :func:`measure`."""
    n = F.greatest(_m("n_words"), F.lit(1))
    chars = F.greatest(_m("word_chars"), F.lit(1))
    return {
        "symbols": _vote(_m("n_symbols") > 0.25 * n, _m("n_symbols") <= 0.02 * n),
        "dup_lines": _vote(_m("n_dup_lines") > 0.4 * _m("n_lines"), (_m("n_dup_lines") == 0) & (_m("n_lines") >= 3)),
        "repeats": _vote(_m("n_repeat_words") > 0.25 * n, (_m("n_repeat_words") == 0) & (n >= 50)),
        "word_length": _vote((chars < 2.5 * n) | (chars > 12 * n), (chars >= 3.5 * n) & (chars <= 9 * n)),
        "upper_case": _vote(_m("n_upper") > 0.4 * chars, _m("n_upper") < 0.1 * chars),
        "shouting": _vote(_m("n_shout") > 0.3 * n, _m("n_shout") <= 0.02 * n),
        # distinct words grow as a power of the length, so the power is what is compared
        "variety": _vote((_m("n_distinct") < F.pow(n, F.lit(0.7))) & (n >= 20), (_m("n_distinct") > F.pow(n, F.lit(0.8))) & (n >= 20)),
    }


@dataclass(frozen=True)
class VoteModel:
    """prior: of good.  caught[rule]: share of bad votes among its votes on bad documents;
    blamed[rule]: the same on good ones.  An abstention says nothing."""

    prior: float
    caught: dict[str, float]
    blamed: dict[str, float]

    def accuracy(self, rule: str) -> float:
        """Share of right votes among the votes that the rule gives."""
        return self.prior * (1 - self.blamed[rule]) + (1 - self.prior) * self.caught[rule]

    def weight(self, rule: str, vote: int) -> float:
        """Log odds of good that a vote adds."""
        if vote == 0:
            return 0.0
        bad, good = self.caught[rule], self.blamed[rule]
        return math.log(good / bad) if vote < 0 else math.log((1 - good) / (1 - bad))

    def log_odds(self, columns: dict[str, Column]) -> Column:
        total = F.lit(math.log(self.prior / (1 - self.prior)))
        for rule, vote in columns.items():
            total = total + F.when(vote == 1, self.weight(rule, 1)).when(vote == -1, self.weight(rule, -1)).otherwise(0.0)
        return total


def fit(patterns: list[tuple[tuple[int, ...], float]], rules: tuple[str, ...] = RULES, params: QualityParams = QualityParams()) -> VoteModel:
    """Expectation-maximisation over (votes, count) rows.

    Classes keep their meaning by where the estimation starts and by anchors, not by bounds:
    what a rule shows in the corpus decides how much its bad vote says and whether good
    votes of others outweigh it.  A rule whose bad votes would speak for a document says nothing.
    """
    model = VoteModel(params.prior_good, dict.fromkeys(rules, params.caught), dict.fromkeys(rules, params.blamed))

    def rate(hits: float, n: float, start: float, anchor: float = params.anchor) -> float:
        weight = params.smoothing + anchor * n
        return (hits + weight * start) / (n + weight)

    for _ in range(params.iterations if patterns else 0):
        bad = {r: [0.0, 0.0] for r in rules}  # bad votes, votes
        good = {r: [0.0, 0.0] for r in rules}
        of_good = total = 0.0
        for pattern, count in patterns:
            odds = math.log(model.prior / (1 - model.prior)) + sum(model.weight(r, v) for r, v in zip(rules, pattern))
            p = 1 / (1 + math.exp(-max(-60.0, min(60.0, odds))))
            of_good, total = of_good + count * p, total + count
            for r, v in zip(rules, pattern):
                if v:
                    bad[r][0] += count * (1 - p) * (v < 0)
                    bad[r][1] += count * (1 - p)
                    good[r][0] += count * p * (v < 0)
                    good[r][1] += count * p
        caught = {r: rate(*bad[r], params.caught) for r in rules}
        blamed = {r: rate(*good[r], params.blamed) for r in rules}
        for r in rules:
            if caught[r] < blamed[r]:
                caught[r] = blamed[r] = rate(bad[r][0] + good[r][0], bad[r][1] + good[r][1], params.blamed)
        model = VoteModel(rate(of_good, total, params.prior_good, params.anchor_prior), caught, blamed)
    return model


def _failed(params: QualityParams) -> Column:
    return (_m("n_words") < params.min_words) | (_m("n_repeat_words") * 100 > _m("n_words") * params.max_repeat_percent)


def vote_patterns(measured: DataFrame, params: QualityParams = QualityParams()) -> list[tuple[tuple[int, ...], float]]:
    """Counts of vote patterns of all documents that votes decide, i.e. that pass the base
    rules; at most 3 ** len(RULES) = 2,187 rows reach the driver."""
    rows = measured.where(~_failed(params)).select(*[v.alias(r) for r, v in votes().items()]).groupBy(*RULES).count().collect()
    return sorted((tuple(int(r[x]) for x in RULES), float(r["count"])) for r in rows)


def judge(measured: DataFrame, model: VoteModel, params: QualityParams = QualityParams()) -> DataFrame:
    """Adds the measures under their own names, ``base_failed``, ``quality_score`` and ``kept``."""
    failed = _failed(params)
    quality = 1 / (1 + F.exp(-model.log_odds(votes())))
    out = measured.withColumns({f"{_P}failed": failed, f"{_P}good": quality})
    added = {m: _m(m) for m in MEASURES} | {"base_failed": _m("failed"), "quality_score": _m("good"), "kept": ~_m("failed") & (_m("good") >= params.threshold)}
    own = [c for c in out.columns if not c.startswith(_P) and c not in added]
    return out.select(*[F.col(f"`{c}`") for c in own], *[v.alias(k) for k, v in added.items()])


def quality_verdicts(docs: DataFrame, key: str = "doc_id", params: QualityParams = QualityParams()) -> DataFrame:
    """key, measures, base_failed, quality_score, kept for every row of ``docs``.

    Texts are read once; measures (some tens of bytes a row) are written to the shared
    folder, counted into vote patterns and judged from there.
    """
    measured = materialize(measure(docs.select(key, "text")).drop("text"), "quality")
    return judge(measured, fit(vote_patterns(measured, params), params=params), params)


def keep_good(docs: DataFrame, params: QualityParams = QualityParams()) -> DataFrame:
    """The rows of ``docs`` that are kept, with their columns as they were.

    Texts are read and measured once: rows go with their measures into a table of the shared
    folder, votes are counted over its measures alone, and what is kept is read from it.
    No text is shuffled.
    """
    columns = docs.columns
    tagged = docs.select(F.struct(*[F.col(f"`{c}`") for c in columns]).alias("row"), F.col("text"))
    measured = materialize(measure(tagged).drop("text"), "measured")
    model = fit(vote_patterns(measured, params), params=params)
    kept = judge(measured, model, params).where("kept")
    return kept.select(*[F.col("row").getField(c).alias(c) for c in columns])
