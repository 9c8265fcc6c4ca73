"""URL filter: host rules, and gradient-boosted trees on lexical features for the rest.

URLs that a rule decides are the labelled ones.  Trees are boosted on a bounded sample of
them (``GbtParams.sample``: the rows with the least hashes, so the sample does not depend
on partitions) and become one SQL expression, so that scoring is a plain projection.

Features: lengths, depth, digit ratio, entropy of the host's characters, number of
parameters, hyphens, and the share of blocked rows among labelled URLs with the same host
suffix and with the same first path part (smoothed; every value is counted, over all
labelled rows, in a table that is joined).

Trees never see a rate that the row's own label went into.  They are fitted on rates out of
fold (hosts are dealt to ``GbtParams.folds`` folds; a row's rates come from labelled rows of
hosts in other folds), and each row is fitted twice, the second time with both rates
withheld, i.e. at the mean that values without labelled rows have: so trees also learn what
lexical features alone say, which is what is left for hosts that no rule knows.

Edge cases: a null URL or one without ``://`` has empty host and path, no rule fits, and
the trees judge it on its (zero) features; repeated rows are judged alike; without labelled
rows every URL gets the default verdict; an empty table gives an empty table.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import materialize

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: (host and path as one string, verdict)
RULES = (("net/", "block"), ("example.net/en/", "allow"), ("example.com/de/", "block"), ("org/fr/", "allow"))
NUMERIC = ("url_chars", "host_chars", "path_chars", "depth", "labels", "digit_ratio", "entropy", "params", "hyphens")
FEATURES = (*NUMERIC, "suffix_rate", "part_rate")


@dataclass(frozen=True)
class GbtParams:
    """sample: most labelled rows that the trees are fitted on.  folds: of hosts, for rates."""

    sample: int = 20_000
    trees: int = 30
    depth: int = 3
    rate: float = 0.2
    bins: int = 32
    ridge: float = 1.0
    threshold: float = 0.5
    default: str = "allow"
    folds: int = 5


def host_of(url: Column) -> Column:
    rest = F.when(F.instr(url, "://") > 0, F.regexp_extract(url, r"(?s)^.*?://([^/?#]*)", 1))
    return F.coalesce(F.translate(rest, UPPER, LOWER), F.lit(""))


def path_of(url: Column) -> Column:
    return F.coalesce(F.when(F.instr(url, "://") > 0, F.regexp_extract(url, r"(?s)^.*?://[^/?#]*([^?#]*)", 1)), F.lit(""))


def rule_of(host: Column, path: Column, rules=RULES) -> Column:
    """The longest rule that fits, or null."""
    found = F.lit(None).cast("string")
    for rule, _ in sorted(rules, key=lambda r: (len(r[0]), r[0])):
        domain, slash, start = rule.partition("/")
        fits = ((host == domain) | host.endswith("." + domain)) & path.startswith(slash + start)
        found = F.when(fits, F.lit(rule)).otherwise(found)
    return found


def _entropy(text: Column) -> Column:
    """Bits a character.  Characters are sorted; runs are counted by their ends."""
    chars = F.filter(F.split(text, ""), lambda c: c != "")
    n = F.greatest(F.size(chars), F.lit(1)).cast("double")
    counts = F.transform(F.array_distinct(chars), lambda c: (F.length(text) - F.length(F.replace(text, c, F.lit("")))).cast("double") / n)
    return F.aggregate(counts, F.lit(0.0), lambda a, p: a - p * F.log2(p))


def with_features(pages: DataFrame, url: str = "url") -> DataFrame:
    """``pages`` with host, path, rule, the numeric features, suffix and part (prefix ``_url_``)."""
    u = F.coalesce(pages[url].cast("string"), F.lit(""))
    out = pages.withColumns({"_url_host": host_of(pages[url].cast("string")), "_url_path": path_of(pages[url].cast("string"))})
    host, path = F.col("_url_host"), F.col("_url_path")
    query = F.regexp_extract(u, r"(?s)\?([^#]*)", 1)
    count = lambda text, char: (F.length(text) - F.length(F.replace(text, F.lit(char), F.lit("")))).cast("double")
    digits = F.length(F.regexp_replace(u, r"[^0-9]+", ""))
    return out.withColumns({
        "_url_rule": rule_of(host, path),
        "_url_url_chars": F.length(u).cast("double"), "_url_host_chars": F.length(host).cast("double"), "_url_path_chars": F.length(path).cast("double"),
        "_url_depth": count(path, "/"), "_url_labels": count(host, "."), "_url_digit_ratio": digits / F.greatest(F.length(u), F.lit(1)),
        "_url_entropy": _entropy(host), "_url_params": F.when(query == "", 0.0).otherwise(count(query, "&") + 1), "_url_hyphens": count(host, "-"),
        "_url_suffix": F.substring_index(host, ".", -2), "_url_part": F.get(F.split(path, "/"), F.lit(1)),
    })


def _with_rates(seen: DataFrame, labelled: DataFrame) -> DataFrame:
    """``seen`` with suffix_rate and part_rate: the share of blocked rows among labelled rows
    of the same value, for every value; values without labelled rows get the mean of all."""
    mean = _mean_rate(labelled)
    for k in ("suffix", "part"):
        value = F.coalesce(F.col(f"_url_{k}"), F.lit(""))
        rates = labelled.groupBy(value.alias("_url_value")).agg(((F.sum("y") + 10 * mean) / (F.count(F.lit(1)) + 10)).alias(f"{k}_rate"))
        seen = seen.join(rates, value == F.col("_url_value"), "left").drop("_url_value").na.fill(mean, [f"{k}_rate"])
    return seen


def _mean_rate(labelled: DataFrame) -> float:
    n, y = labelled.agg(F.count(F.lit(1)), F.sum("y")).first()
    return ((y or 0) + 1) / (n + 2)


def with_held_out_rates(sample: DataFrame, labelled: DataFrame, mean: float, folds: int) -> DataFrame:
    """``sample`` with suffix_held and part_held: the rates without the labelled rows of any
    host in the row's own fold; the mean where none is left."""
    fold = F.pmod(F.xxhash64("_url_host"), F.lit(folds))
    for k in ("suffix", "part"):
        value = F.coalesce(F.col(f"_url_{k}"), F.lit(""))
        by = labelled.groupBy(value.alias("_url_value"), fold.alias("_url_fold")).agg(F.sum("y").alias("_url_y"), F.count(F.lit(1)).alias("_url_n"))
        every = by.groupBy("_url_value").agg(F.sum("_url_y").alias("_url_all_y"), F.sum("_url_n").alias("_url_all_n"))
        held = (F.col("_url_all_y") - F.col("_url_y") + 10 * mean) / (F.col("_url_all_n") - F.col("_url_n") + 10)
        rates = by.join(every, "_url_value").select("_url_value", "_url_fold", held.alias(f"{k}_held"))
        sample = sample.join(rates, (value == F.col("_url_value")) & (fold == F.col("_url_fold")), "left").drop("_url_value", "_url_fold").na.fill(mean, [f"{k}_held"])
    return sample


def _grow(rows, bins, grad, hess, members, depth, p: GbtParams):
    """A tree as nested (feature, bin, left, right) or a leaf value."""
    g, h = sum(grad[i] for i in members), sum(hess[i] for i in members)
    leaf = -p.rate * g / (h + p.ridge)
    if depth == p.depth or len(members) < 20:
        return leaf
    best = (1e-6, None, None)
    for f in range(len(FEATURES)):
        sums = {}
        for i in members:
            s = sums.setdefault(rows[i][f], [0.0, 0.0])
            s[0] += grad[i]
            s[1] += hess[i]
        gl = hl = 0.0
        for b in sorted(sums)[:-1]:
            gl, hl = gl + sums[b][0], hl + sums[b][1]
            gain = gl * gl / (hl + p.ridge) + (g - gl) ** 2 / (h - hl + p.ridge) - g * g / (h + p.ridge)
            if gain > best[0] and hl > 1e-3 and h - hl > 1e-3:
                best = (gain, f, b)
    if best[1] is None:
        return leaf
    _, f, b = best
    return (f, b, _grow(rows, bins, grad, hess, [i for i in members if rows[i][f] <= b], depth + 1, p), _grow(rows, bins, grad, hess, [i for i in members if rows[i][f] > b], depth + 1, p))


def boost(values: list[tuple[float, ...]], labels: list[int], params: GbtParams = GbtParams()) -> tuple[float, list, list[list[float]]]:
    """Logistic boosting over binned features.  Returns (start, trees, cut points by feature).

    A row is the features as scoring sees them.  It may go on with (suffix_held, part_held,
    mean): then it is fitted once with the held-out rates in place of its own and once with
    the mean, and its own rates only help to choose cut points.
    """
    cuts = []
    for f in range(len(FEATURES)):
        v = sorted({x[f] for x in values})
        step = max(1, len(v) // params.bins)
        cuts.append(v[step - 1 : -1 : step])
    rate = (sum(labels) + 1) / (len(labels) + 2)
    start = math.log(rate / (1 - rate))
    import bisect

    views = [(x[: len(FEATURES)], y) for x, y in zip(values, labels)]
    if values and len(values[0]) > len(FEATURES):
        views = [((*x[: len(NUMERIC)], *rates), y) for x, y in zip(values, labels) for rates in (x[-3:-1], (x[-1], x[-1]))]
        labels = [y for _, y in views]
    rows = [tuple(bisect.bisect_left(cuts[f], x[f]) for f in range(len(FEATURES))) for x, _ in views]
    # equal rows are one row with a weight: gradients depend on bins and labels alone
    merged: dict[tuple, list] = {}
    for r, y in zip(rows, labels):
        merged.setdefault(r, [0, 0])[y] += 1
    keys = sorted(merged)
    score, trees = [start] * len(keys), []
    for _ in range(params.trees if len(set(labels)) == 2 else 0):
        grad, hess = [], []
        for k, s in zip(keys, score):
            zeros, ones = merged[k]
            q = 1 / (1 + math.exp(-s))
            grad.append((zeros + ones) * q - ones)
            hess.append((zeros + ones) * q * (1 - q))
        tree = _grow(keys, cuts, grad, hess, list(range(len(keys))), 0, params)
        trees.append(tree)
        for i, k in enumerate(keys):
            score[i] += _walk(tree, k)
    return start, trees, cuts


def _walk(tree, row):
    while isinstance(tree, tuple):
        f, b, left, right = tree
        tree = left if row[f] <= b else right
    return tree


def tree_column(tree, cuts, features: dict[str, Column]) -> Column:
    if not isinstance(tree, tuple):
        return F.lit(float(tree))
    f, b, left, right = tree
    return F.when(features[FEATURES[f]] <= F.lit(float(cuts[f][b])), tree_column(left, cuts, features)).otherwise(tree_column(right, cuts, features))


def url_verdicts(pages: DataFrame, key: str = "page_id", url: str = "url", rules=RULES, params: GbtParams = GbtParams()) -> DataFrame:
    """key, host, path, rule, verdict, block_score for every row."""
    seen = materialize(with_features(pages.select(F.col(key).alias("key"), F.col(url).cast("string").alias("url"))), "urls")
    verdicts = F.create_map(*[F.lit(x) for r in rules for x in r])
    label = lambda rows: rows.where("_url_rule is not null").withColumn("y", (F.try_element_at(verdicts, F.col("_url_rule")) == "block").cast("int"))
    scored = materialize(_with_rates(seen, label(seen)), "rates")
    labelled = label(scored)
    named = {n: F.col(f"_url_{n}") if n in NUMERIC else F.col(n) for n in FEATURES}
    order = F.xxhash64("url", "key")
    # rows over a threshold of the hash never leave their task, so the driver gets little more than the sample
    share = min(1.0, 1.2 * params.sample / max(1, labelled.count()))
    near = labelled.withColumn("o", order).where(F.pmod("o", F.lit(1 << 20)) < F.lit(int(share * (1 << 20))))
    mean = _mean_rate(labelled)
    held = with_held_out_rates(near, labelled, mean, params.folds)
    rows = held.select(F.pmod("o", F.lit(1 << 20)).alias("p"), "o", "y", *[c.alias(n) for n, c in named.items()], "suffix_held", "part_held").orderBy("p", "o", *FEATURES, "y").limit(params.sample).collect()
    start, trees, cuts = boost([(*(float(r[n]) for n in FEATURES), r["suffix_held"], r["part_held"], mean) for r in rows], [r["y"] for r in rows], params)
    score = F.lit(start if rows else (-1.0 if params.default == "allow" else 1.0))
    for t in trees:
        score = score + tree_column(t, cuts, named)
    block = F.round(1 / (1 + F.exp(-score)), 9)
    rule = F.col("_url_rule")
    verdict = F.coalesce(F.try_element_at(verdicts, rule), F.when(F.col("block_score") >= params.threshold, "block").otherwise("allow"))
    return scored.withColumn("block_score", block).select("key", F.col("_url_host").alias("host"), F.col("_url_path").alias("path"), rule.alias("rule"), verdict.alias("verdict"), "block_score")
