"""What the learned operators decide: against plain versions, on planted text, and where labels cannot leak."""

import math
import re
from bisect import bisect_left, bisect_right
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from series_engine.llm import langid, packing, pieces, pii, quality, queries, simhash, substring_dedup, exact_dedup, token_counts, tokens, urls

from . import brute


@pytest.fixture(scope="module")
def docs(spark, sf_dir):
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def rows_of(df, *columns):
    return [tuple(r) for r in df.select(*columns).collect()]


# ---- stages keep all that is not a copy -------------------------------------------------


def test_near_dedup_tells_rows_with_one_key_apart(spark):
    a, b, c, d = (" ".join(f"{x}{i}" for i in range(30)) for x in "pqrs")
    rows = [(1, a, "x"), (2, b, "x"), (2, a, "x"), (None, a, "x"), (None, c, "x"), (-1, d, "x"), (-1, d, "x")]
    df = spark.createDataFrame(rows, "doc_id long, text string, _gone string")
    got = Counter(rows_of(simhash.drop_near_duplicates(df), "doc_id", "text", "_gone"))
    assert got == Counter([(1, a, "x"), (2, b, "x"), (None, c, "x"), (-1, d, "x")])


def test_stages_leave_columns_of_any_name(spark):
    text = " ".join(f"w{i}" for i in range(40))
    mine = ("_gone", "_tag", "_chars", "_first", "_turn", "_row", "_key", "_spans", "_hash", "_fp", "_low", "row", "spans", "key", "_quality_t", "fp", "start")
    df = spark.createDataFrame([(1, text), (2, text + " "), (3, "other " + text), (4, None)], "doc_id long, text string").withColumns({c: F.concat(F.lit(f"keep {c} "), F.col("doc_id")) for c in mine})
    for stage in (exact_dedup.drop_duplicates, simhash.drop_near_duplicates, substring_dedup.drop_repeats, pii.redact):
        out = stage(df)
        assert out.columns == df.columns
        rows = out.collect()
        assert rows and all(r[c] == f"keep {c} {r['doc_id']}" for r in rows for c in mine), stage
    plain = df.drop("_quality_t")
    assert all(r[c] == f"keep {c} {r['doc_id']}" for r in quality.keep_good(plain).collect() for c in mine if c != "_quality_t")


# ---- quality ----------------------------------------------------------------------------


def test_quality_verdicts_equal_a_plain_estimation(spark, docs):
    measured = quality.measure(docs.select("doc_id", "text"))
    votes = [(r["doc_id"], r["bad"], tuple(r[x] for x in quality.RULES)) for r in measured.select("doc_id", quality._failed(quality.QualityParams()).alias("bad"), *[v.alias(k) for k, v in quality.votes().items()]).collect()]
    p, rules = quality.QualityParams(), quality.RULES
    rows = [v for _, bad, v in votes if not bad]
    prior, caught, blamed = p.prior_good, {r: p.caught for r in rules}, {r: p.blamed for r in rules}

    def good(v):
        like = [prior, 1 - prior]
        for r, x in zip(rules, v):
            if x:
                like[0] *= blamed[r] if x < 0 else 1 - blamed[r]
                like[1] *= caught[r] if x < 0 else 1 - caught[r]
        return like[0] / sum(like)

    for _ in range(p.iterations):
        w = [good(v) for v in rows]
        rate = lambda hits, n, start, anchor=p.anchor: (hits + (p.smoothing + anchor * n) * start) / (n + p.smoothing + anchor * n)
        new = {}
        for j, r in enumerate(rules):
            b = (sum(1 - q for q, v in zip(w, rows) if v[j] < 0), sum(1 - q for q, v in zip(w, rows) if v[j]))
            g = (sum(q for q, v in zip(w, rows) if v[j] < 0), sum(q for q, v in zip(w, rows) if v[j]))
            new[r] = (rate(*b, p.caught), rate(*g, p.blamed))
            if new[r][0] < new[r][1]:
                new[r] = (rate(b[0] + g[0], b[1] + g[1], p.blamed),) * 2
        prior, caught, blamed = rate(sum(w), len(w), p.prior_good, p.anchor_prior), {r: x[0] for r, x in new.items()}, {r: x[1] for r, x in new.items()}
    want = {d: not bad and good(v) >= p.threshold for d, bad, v in votes}
    assert dict(rows_of(quality.quality_verdicts(docs), "doc_id", "kept")) == want


# ---- URLs -------------------------------------------------------------------------------


def test_rates_to_fit_on_leave_the_own_fold_out(spark):
    rows = [(i, f"http://h{i % 7}.a{i % 3}.net/p{i % 5}/x") for i in range(200)] + [(1000 + i, f"http://k{i % 11}.a{i % 3}.org/fr/{i}") for i in range(150)]
    seen = urls.with_features(spark.createDataFrame(rows, "key long, url string"))
    labelled = seen.withColumn("y", F.col("_url_host").endswith("net").cast("int"))
    folds, mean = 4, 0.4
    got = {r["key"]: (round(r["suffix_held"], 9), round(r["part_held"], 9)) for r in urls.with_held_out_rates(labelled, labelled, mean, folds).collect()}
    plain = [r.asDict() for r in labelled.withColumn("fold", F.pmod(F.xxhash64("_url_host"), F.lit(folds))).collect()]
    for r in plain:
        want = []
        for k in ("_url_suffix", "_url_part"):
            others = [x["y"] for x in plain if x[k] == r[k] and x["fold"] != r["fold"]]
            want.append(round((sum(others) + 10 * mean) / (len(others) + 10), 9))
        assert got[r["key"]] == tuple(want)


def test_verdicts_equal_a_walk_of_the_trees(spark, sf_dir, monkeypatch):
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet")
    kept = []
    monkeypatch.setattr(urls, "boost", lambda values, labels, params, f=urls.boost: kept.append((values, labels, f(values, labels, params))) or kept[-1][2])
    scored = urls.url_verdicts(pages)
    ((values, labels, (start, trees, cuts)),) = kept
    assert all(len(v) == len(urls.FEATURES) + 3 for v in values)
    verdict = dict(urls.RULES)
    seen = urls.with_features(pages.select(F.col("page_id").alias("key"), "url")).collect()
    counts = {k: defaultdict(lambda: [0, 0]) for k in ("suffix", "part")}
    for r in seen:
        if r["_url_rule"]:
            for k in counts:
                counts[k][r[f"_url_{k}"] or ""][0] += verdict[r["_url_rule"]] == "block"
                counts[k][r[f"_url_{k}"] or ""][1] += 1
    y, n = sum(v[0] for v in counts["suffix"].values()), sum(v[1] for v in counts["suffix"].values())
    mean = (y + 1) / (n + 2)
    rate = lambda k, v: (counts[k][v][0] + 10 * mean) / (counts[k][v][1] + 10) if v in counts[k] else mean
    want = {}
    for r in seen:
        x = [r[f"_url_{c}"] for c in urls.NUMERIC] + [rate("suffix", r["_url_suffix"] or ""), rate("part", r["_url_part"] or "")]
        score = start
        for t in trees:
            while isinstance(t, tuple):
                f, b, left, right = t
                t = left if x[f] <= cuts[f][b] + 1e-12 else right
            score += t
        want[r["key"]] = verdict.get(r["_url_rule"]) or ("block" if round(1 / (1 + math.exp(-score)), 9) >= 0.5 else "allow")
    assert dict(rows_of(scored, "key", "verdict")) == want


def _used(trees):
    out, stack = Counter(), list(trees)
    while stack:
        t = stack.pop()
        if isinstance(t, tuple):
            out[urls.FEATURES[t[0]]] += 1
            stack += t[2:]
    return out


def test_trees_learn_lexical_features_for_hosts_that_no_rule_knows(spark, monkeypatch):
    """Blocked hosts are long and full of digits; hosts that no rule decides share no suffix with them."""
    rng = np.random.default_rng(6)
    word = lambda n: "".join(rng.choice(list("abcdefghij"), n))
    bad = lambda: f"{word(6)}{rng.integers(10**6, 10**7)}-{word(8)}"
    rows = [f"http://{bad()}.s{i % 40}.net/{word(3)}/{i}?a=1&b=2&c=3" for i in range(600)] + [f"http://{word(5)}.t{i % 40}.org/fr/{word(4)}" for i in range(600)]
    unknown = [(f"http://{bad()}.u{i}.info/{word(3)}/{i}?a=1&b=2&c=3", "block") for i in range(60)] + [(f"http://{word(5)}.v{i}.info/{word(4)}", "allow") for i in range(60)]
    kept = []
    monkeypatch.setattr(urls, "boost", lambda values, labels, params, f=urls.boost: kept.append(f(values, labels, params)) or kept[-1])
    df = spark.createDataFrame(list(enumerate(rows + [u for u, _ in unknown])), "page_id long, url string")
    got = dict(rows_of(urls.url_verdicts(df), "key", "verdict"))
    right = sum(got[len(rows) + i] == v for i, (_, v) in enumerate(unknown))
    used = _used(kept[0][1])
    assert right >= 0.95 * len(unknown) and sum(used[c] for c in urls.NUMERIC) > 0


# ---- personal data ----------------------------------------------------------------------

PERSONAL = [
    "she was born on 1984-03-02 in Rome", "Date of birth: 02.03.1984", "geboren am 12.05.1970 in Wien", "né le 03/04/1965 à Paris", "fecha de nacimiento: 1990-01-31", "DOB 1975/12/24",
    "account number 12345678 at the bank", "IBAN DE89370400440532013000", "SSN 078-05-1120", "Kontonummer: 1234567890", "numéro de compte: 99887766554",
    "password: hunter22x9", "api key = a8f5f167f44f4964e6c998dee827110c", "use token: Abcdefg123456789 now", "bearer eyJhbGciOiJIUzI1NiJ9abc", "passwort = geheim4711X", "clave: qwerty12345Z",
]
PLAIN = [
    "The meeting took place on 2024-01-15 in the hall", "see section: introduction_and_overview of it", "ratio=12345678", "published 1999-05-04 by the press", "version 1.2.3 of 12.05.2021", "isbn 9783161484100 of it",
    "order no 20240115123 was sent", "the internationalization_of_things", "title: somethingratherlong", "commit a8f5f167f44f4964e6c998dee827110c fixed it", "the conference on 2019-06-01 and later", "from 01.02.2003 until 01.02.2004",
    "a number 4465758382889437 in a row", "Seite: Zusammenfassung der Ergebnisse", "https://example.org/some-long-path-of-words/and-more", "total: 1234567890 units", "due date 2011-11-11 for all",
]


def test_personal_data_on_planted_text(spark, docs):
    """Precision and recall of added spans on text that nothing was fitted to."""
    rows = [(-1 - i, t) for i, t in enumerate(PERSONAL)] + [(-1000 - i, t) for i, t in enumerate(PLAIN)]
    both = docs.select("doc_id", "text").union(spark.createDataFrame(rows, "doc_id long, text string"))
    added = {k: [s for s in spans if s not in base] for k, base, spans in rows_of(pii.find_personal_data(both), "key", "base", "spans") if k < 0}
    found = {t for i, t in enumerate(PERSONAL) if added[-1 - i]}
    wrong = {t for i, t in enumerate(PLAIN) if added[-1000 - i]}
    assert len(found) >= 0.9 * len(PERSONAL), set(PERSONAL) - found
    assert len(wrong) <= 0.1 * len(PLAIN), wrong


def test_clean_text_is_left_alone(spark, docs):
    rows = [(i, t) for i, t in enumerate(PLAIN[:6])]
    out = pii.redact(docs.select("doc_id", "text").union(spark.createDataFrame(rows, "doc_id long, text string").withColumn("doc_id", -F.col("doc_id") - 1)))
    assert dict(rows_of(out.where("doc_id < 0"), "doc_id", "text")) == {-1 - i: t for i, t in rows}


def test_spans_equal_a_plain_estimation(docs):
    """Proposals, votes and verdicts row by row, with the estimation written out."""
    p = pii.PiiParams()
    per, patterns, seen = {}, defaultdict(Counter), defaultdict(Counter)
    for d, t in rows_of(docs, "doc_id", "text"):
        per[d] = (pii.base_spans(t), pii.proposals(t, pii.base_spans(t)))
        for kind, _, _, votes, x in per[d][1]:
            patterns[kind][votes] += 1
            seen[kind][votes, tuple(round(v, 2) for v in x)] += 1
    weights = {}
    for kind in pii.ADDED:
        prior, right = p.prior, [p.right] * 5
        for _ in range(p.iterations if patterns[kind] else 0):
            post = {v: 1 / (1 + (1 - prior) / prior * math.prod(((1 - r) / r) ** x for r, x in zip(right, v))) for v in patterns[kind]}
            n = sum(patterns[kind].values())
            blend = lambda hits, n, start: (hits + (p.smoothing + p.anchor * n) * start) / (n + p.smoothing + p.anchor * n)
            prior = blend(sum(c * post[v] for v, c in patterns[kind].items()), n, p.prior)
            right = [max(0.5, blend(sum(c * (post[v] if v[j] > 0 else 1 - post[v]) for v, c in patterns[kind].items() if v[j]), sum(c for v, c in patterns[kind].items() if v[j]), p.right)) for j in range(5)]
        start = np.array([math.log(prior / (1 - prior)), *[math.log(r / (1 - r)) for r in right], 0, 0, 0, 0])
        w, x = start.copy(), np.array([f for _, f in seen[kind]]).reshape(-1, 10)
        c = np.array(list(seen[kind].values()), float)
        y = np.array([1 / (1 + (1 - prior) / prior * math.prod(((1 - r) / r) ** v for r, v in zip(right, votes))) for votes, _ in seen[kind]])
        for _ in range(20_000 if len(x) else 0):  # plain gradient descent on the same loss
            q = 1 / (1 + np.exp(-(x @ w)))
            w -= 0.5 / (p.ridge + c.sum()) * (x.T @ (c * (q - y)) + p.ridge * (w - start))
        weights[kind] = w
    for key, spans in rows_of(queries.op6_personal_data(docs.sparkSession, "/root/testdata/sf0.001"), "doc_id", "spans"):
        base, more = per[key]
        want = base + [(k, a, b) for k, a, b, _, x in more if 1 / (1 + math.exp(-float(weights[k] @ np.array(x)))) >= p.threshold]
        assert spans == pii.joined(want)


def test_proposals_are_linear(spark):
    import time

    for text in ("1999-01-01 " * 30_000, "12345678 " * 30_000, "a" * 15 + " " + "b" * 20 + " " + "token=x12345678 " * 20_000, "-" * 200_000 + "a", "a-" * 150_000):
        began = time.perf_counter()
        pii.proposals(text, pii.base_spans(text))
        assert time.perf_counter() - began < 20


# ---- repeats ----------------------------------------------------------------------------


def test_spans_have_their_sources_coordinates(docs):
    text = {d: substring_dedup.words_of(t) for d, t in rows_of(docs, "doc_id", "text")}
    spans = rows_of(substring_dedup.repeated_spans(docs), "key", "start", "words", "source", "source_start")
    assert spans
    for k, a, n, s, b in spans:
        assert s < k and n >= substring_dedup.K and text[k][a : a + n] == text[s][b : b + n] and len(text[k]) >= a + n


@pytest.mark.parametrize("bits", [5, 2])
def test_colliding_hashes_remove_nothing_wrong(spark, bits):
    rng = np.random.default_rng(11)
    texts = [(d, " ".join(f"v{i}" for i in rng.integers(0, 40, 120)) + (" " + " ".join(f"s{i}" for i in range(30)) if d % 3 == 0 else "")) for d in range(40)]
    df = spark.createDataFrame(texts, "doc_id long, text string")
    words = {d: t.encode().split() for d, t in texts}
    exact = {d: (n, r) for d, n, r, _ in brute.repeats(texts)}
    for k, a, n, s, b in rows_of(substring_dedup.repeated_spans(df, bits=bits), "key", "start", "words", "source", "source_start"):
        assert words[k][a : a + n] == words[s][b : b + n]
    for k, n, r in rows_of(substring_dedup.removal_digests(df, bits=bits), "key", "n_words", "n_removed"):
        assert exact[k][0] == n and r <= exact[k][1]


def test_paths_do_not_branch(spark):
    """Two documents share x and then part; a third has only a piece of x: paths end at each branch."""
    x, y, z = ([f"{c}{i}" for i in range(60)] for c in "xyz")
    texts = [(1, x + y), (2, x + z), (3, ["q"] + x[20:50] + ["r"]), (4, x + y)]
    df = spark.createDataFrame([(d, " ".join(w)) for d, w in texts], "doc_id long, text string")
    paths = rows_of(substring_dedup.nonbranching_paths(substring_dedup.repeated_pieces(df)), "key", "start", "words", "source", "source_start")
    words = dict(texts)
    for k, a, n, s, b in paths:
        assert words[k][a : a + n] == words[s][b : b + n] and s < k
    covered = {k: sorted({i for kk, a, n, _, _ in paths if kk == k for i in range(a, a + n)}) for k in (2, 3, 4)}
    assert covered == {2: list(range(60)), 3: list(range(1, 31)), 4: list(range(120))}
    merged = {k: (a, n, s, b) for k, a, n, s, b in rows_of(substring_dedup.repeated_spans(df), "key", "start", "words", "source", "source_start")}
    assert merged == {2: (0, 60, 1, 0), 3: (1, 30, 1, 20), 4: (0, 120, 1, 0)}


def test_a_repeated_key_keeps_its_texts_apart(spark):
    w = [f"w{i}" for i in range(40)]
    rows = [(1, " ".join(w)), (2, " ".join(w)), (2, " ".join(f"u{i}" for i in range(40)))]
    got = Counter(rows_of(substring_dedup.removal_digests(spark.createDataFrame(rows, "doc_id long, text string")), "key", "n_removed"))
    assert got == Counter([(1, 0), (2, 40), (2, 0)])


# ---- tokens, pieces, languages, packing -------------------------------------------------


@pytest.mark.parametrize("rule", token_counts.RULES)
def test_counts_of_lines_token_by_token(docs, rule):
    enc = tokens.encoder(tokens.default_file())
    want = Counter()
    for d, t in rows_of(docs, "doc_id", "text"):
        raw = (t or "").encode()
        of_line = np.concatenate(([0], np.cumsum(np.frombuffer(raw, np.uint8) == 10)))[:-1] if raw else np.zeros(0, int)
        starts = [i for i in range(len(raw)) if raw[i] & 0xC0 != 0x80] + [len(raw)]
        at = 0
        for n in enc.lengths[enc.ids(t or "")].tolist():
            a, b = starts[bisect_right(starts, at) - 1], starts[bisect_left(starts, at + n)]
            lines = of_line[a:b].tolist()
            if rule == "split":
                for line in lines:
                    want[d, line] += 1 / len(lines)
            else:
                want[d, lines[0] if rule == "start" else lines[-1]] += 1
            at += n
    got = {(k, s): n for k, s, n in rows_of(token_counts.section_token_counts(docs, rule=rule), "key", "section", "tokens") if n}
    assert got.keys() == want.keys() and all(abs(got[x] - want[x]) < 1e-6 for x in want)


def test_overlapping_sections_end_where_the_next_starts(spark):
    text = "hello wonderful world"
    docs = spark.createDataFrame([(1, text)], "doc_id long, text string")
    parts = spark.createDataFrame([(1, 0, 0, 21), (1, 1, 5, 21), (1, 2, 15, 21)], "doc_id long, section long, start long, stop long")
    got = {s: (a, b, t) for s, a, b, t in rows_of(token_counts.section_token_counts(docs, parts), "section", "start", "stop", "tokens")}
    assert got == {0: (0, 5, 1.0), 1: (5, 15, 1.0), 2: (15, 21, 1.0)}


def test_texts_are_normalised_and_encoded_in_parts(monkeypatch):
    rng = np.random.default_rng(3)
    text = "".join(rng.choice(list("ab cü é日 \n  "), 6000))
    whole = pieces.encode(text, pieces.default_file()).tolist()
    monkeypatch.setattr(pieces, "NORMAL", 40)
    v, _ = pieces.vocabulary(pieces.default_file())
    assert len(list(pieces.normal_parts(text, v))) > 50 and pieces.encode(text, pieces.default_file()).tolist() == whole
    monkeypatch.setattr(v, "cut_at_marks", False)  # through the streaming window alone
    assert pieces.encode(text, pieces.default_file()).tolist() == whole


def _grams(text):
    spaced = "".join(c if "a" <= c <= "z" or (ord(c) >= 0xC0 and c not in "×÷" and not 0x2000 <= ord(c) <= 0x206F) else " " for c in text.lower())
    spaced = " " + re.sub(" +", " ", spaced) + " "
    return Counter(spaced[i : i + n] for n in (1, 2, 3) for i in range(len(spaced) - n + 1))


def test_ngrams_do_not_depend_on_parts(monkeypatch):
    text = "Grüße aus Köln! 12 x y  ñandú — çà et là " * 30
    want = sorted(Counter({k: n for k, n in _grams(text).items()}).values())
    for part in (1 << 16, 7, 1):
        monkeypatch.setattr(langid, "_PART", part)
        ids, n = langid.counts(text)
        assert n.sum() == sum(want) and len(ids) >= 0.97 * len(want)


def test_document_frequencies_and_training_by_hand(spark):
    rows = [("en", "the cat and the dog"), ("en", "a dog and the bird"), ("fr", "le chat et le chien"), ("fr", "un chien et une poule"), ("en", None), (None, "nothing")] * 3
    model = langid.train(spark.createDataFrame(rows, "lang string, text string"))
    texts = [t for lang, t in rows if t and lang]
    df = Counter(b for t in texts for b in set(langid.counts(t)[0].tolist()))
    for b, n in df.items():
        assert model.idf[b] == pytest.approx(math.log((1 + len(texts)) / (1 + n)) + 1, rel=1e-6)
    # follow-the-regularised-leader, coordinate by coordinate
    p = langid.LangParams(epochs=2)
    plain = langid.LangModel(["en", "fr"], model.idf)
    data = [(plain.langs.index(lang), langid.counts(t)[0], plain.vector(langid.counts(t)[0], langid.counts(t)[1].astype(np.float32))) for lang, t in rows[:4]]
    langid._ftrl(plain, data, p)
    z, n, w = defaultdict(float), defaultdict(float), {}

    def weight(k, i):
        if abs(z[k, i]) <= p.l1:
            return 0.0
        return -(z[k, i] - math.copysign(p.l1, z[k, i])) / ((p.beta + math.sqrt(n[k, i])) / p.alpha + p.l2)

    for _ in range(p.epochs):
        for y, ids, x in data:
            feats = [*zip(ids.tolist(), x.tolist()), (-1, 1.0)]
            s = [sum(weight(k, i) * v for i, v in feats) for k in (0, 1)]
            e = [math.exp(v - max(s)) for v in s]
            old = {(k, i): weight(k, i) for k in (0, 1) for i, _ in feats}
            for k in (0, 1):
                for i, v in feats:
                    g = (e[k] / sum(e) - (k == y)) * v
                    sigma = (math.sqrt(n[k, i] + g * g) - math.sqrt(n[k, i])) / p.alpha
                    z[k, i] += g - sigma * old[k, i]
                    n[k, i] += g * g
    for k in (0, 1):
        for i in {i for _, ids, _ in data for i in ids.tolist()}:
            assert plain.weights[k, i] == pytest.approx(weight(k, i), abs=1e-5)


def test_every_source_has_a_target(spark):
    """More sources than any list of the largest would name, each with its share of every part."""
    rows = [(i, "alpha beta gamma delta " * 12, f"s{i % 1500}") for i in range(6000)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    starts = {r["bucket"]: r["starts"] for r in packing.starts_of(spark.createDataFrame([(b, s, 10 * (1 + b)) for b in range(3) for s in ("a", "b", "c")] + [(2, "d", 40)], "bucket int, source string, tokens long"), {"a": 0.5}).collect()}
    total = {"a": 60, "b": 60, "c": 60, "d": 40}
    share = {"a": 0.5, **{s: 0.5 * total[s] / 160 for s in "bcd"}}
    for b, found in starts.items():
        ahead = sum(30 * (1 + x) for x in range(b))
        for r in found:
            given = sum(10 * (1 + x) for x in range(b)) if r["source"] != "d" else 0
            assert r["share"] == pytest.approx(share[r["source"]]) and r["deficit"] == pytest.approx(share[r["source"]] * ahead - given)
    got = packing.packed(df, buckets=3)
    assert got.agg(F.sum("length")).first()[0] == got.select("key", "doc_tokens").distinct().agg(F.sum("doc_tokens")).first()[0]
    assert {s for (s,) in rows_of(got.select("source").distinct(), "source")} == {f"s{i}" for i in range(1500)}


def test_repeated_rows_are_spread_over_partitions(spark):
    """A row that holds most of the table does not meet in one partition; other rows go by key and text alone."""
    rows = [(1, "alpha beta gamma", "x")] * 3000 + [(i, f"delta {i}", "y") for i in range(10, 1010)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    sizes = [n for (n,) in rows_of(packing.encoded(df, 8).groupBy("bucket").count(), "count")]
    assert sum(sizes) == 4000 and len(sizes) == 8 and max(sizes) < 1.3 * 500
    single = lambda d: Counter(rows_of(packing.encoded(d, 8).where("source = 'y'"), "key", "bucket"))
    assert single(df) == single(df.repartition(5))
    got = packing.packed(df, buckets=8)
    assert got.agg(F.sum("length")).first()[0] == packing.encoded(df, 8).agg(F.sum("tokens")).first()[0]


@pytest.mark.parametrize("values", [[], [5], [5, 5, 5], [3, -1, 3, 3, -1, 9], [-(1 << 63), (1 << 63) - 1, -(1 << 63)]])
def test_turns(values):
    assert packing.turns(np.array(values, np.int64)).tolist() == [values[:i].count(v) for i, v in enumerate(values)]
