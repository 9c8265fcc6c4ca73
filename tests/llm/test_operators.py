"""Every operator against a plain version, on edge cases and on whole small tables."""

import hashlib
import time
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from series_engine.llm import components, exact_dedup, langid, packing, pieces, pii, quality, queries, simhash, substring_dedup, token_counts, tokens, urls

from . import brute


@pytest.fixture(scope="module")
def edge(spark):
    """Nulls everywhere, empty and long texts, ties, repeated rows, and extra columns with clashing names."""
    df = spark.createDataFrame(brute.EDGE, brute.FIELDS)
    names = ("n_words", "kept", "key", "fp", "row", "name", "start", "component", "quality_score", "_gone", "bucket", "tokens")
    return df.withColumns({c: F.lit(c) for c in names})


@pytest.fixture(scope="module")
def docs(spark, sf_dir):
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


@pytest.fixture(scope="module")
def empty(edge):
    return edge.where("false")


def rows_of(df, *columns):
    return [tuple(r) for r in df.select(*columns).collect()]


@pytest.mark.parametrize("table", ["edge", "docs"])
def test_quality(table, request):
    df = request.getfixturevalue(table)
    got = Counter(rows_of(quality.quality_verdicts(df), "doc_id", *quality.MEASURES, "base_failed"))
    want = Counter()
    for d, t in rows_of(df, "doc_id", "text"):
        q = brute.quality(t)
        want[(d, *q, q[0] < 20 or 100 * q[4] > 30 * q[0])] += 1
    assert got == want


def test_quality_verdicts_follow_labels(spark, docs, sf_dir):
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").withColumnRenamed("quality", "label")
    out = quality.quality_verdicts(docs).join(labels, "doc_id").where("not base_failed")
    kept = dict(rows_of(out.groupBy("label").agg(F.avg(F.col("kept").cast("int")).alias("k")), "label", "k"))
    assert kept[1] > 0.95 and kept.get(0, 0.0) < 0.2


def test_quality_filter_keeps_rows_as_they_were(docs, edge):
    for df in (docs, edge):
        out = quality.keep_good(df)
        assert out.columns == df.columns
        verdict = quality.quality_verdicts(df)
        assert out.count() == verdict.where("kept").count()


def test_estimation_prefers_rules_that_agree():
    model = quality.fit([((1, 1), 900.0), ((-1, 1), 50.0), ((-1, -1), 50.0)], ("a", "b"))
    assert model.accuracy("a") > 0.8 and model.weight("a", -1) < 0 < model.weight("a", 1) and model.weight("a", 0) == 0


def odds(model, rules, votes):
    return np.log(model.prior / (1 - model.prior)) + sum(model.weight(r, v) for r, v in zip(rules, votes))


def test_one_bad_vote_is_overruled_where_the_corpus_shows_that_it_errs():
    rules = ("a", "b", "c", "d")
    errs = quality.fit([((-1, 1, 1, 1), 300.0), ((1, -1, -1, -1), 100.0), ((1, 1, 1, 1), 600.0)], rules)
    assert odds(errs, rules, (-1, 1, 1, 1)) > 0 > odds(errs, rules, (1, -1, -1, -1))
    rare = quality.fit([((-1, 1, 1, 1), 10.0), ((1, 1, 1, 1), 900.0)], rules)
    assert odds(rare, rules, (-1, 1, 1, 1)) < 0 < odds(rare, rules, (1, 1, 1, 1))


def test_the_corpus_changes_a_verdict(spark):
    prose = lambda i: " ".join(f"word{chr(97 + (i + j) % 26)}{chr(97 + j % 23)}" for j in range(40))
    listing = lambda i: prose(i) + " | <a> # $x & %y *" * 2 + " <b> | & # *"
    kept = {}
    for n in (4, 60):  # many documents of technical text, or a few
        rows = [(i, listing(i) if i < n else prose(i)) for i in range(120)] + [(1000 + i, "! " * 30 + "# A B C D E | <> " * 3) for i in range(12)]
        kept[n] = dict(rows_of(quality.quality_verdicts(spark.createDataFrame(rows, "doc_id long, text string")), "doc_id", "kept"))
        assert kept[n][119] and not kept[n][1000]
    assert not kept[4][0] and kept[60][0]


def test_variety_is_judged_at_every_length(spark):
    rng = np.random.default_rng(2)
    texts = [(1, " ".join(f"w{i}" for i in rng.integers(0, 60, 6000))), (2, " ".join(f"w{int(i)}" for i in np.minimum(rng.zipf(1.3, 6000), 1e9))), (3, " ".join(f"w{i}" for i in rng.integers(0, 6, 100)))]
    m = quality.measure(spark.createDataFrame(texts, "doc_id long, text string"))
    assert dict(rows_of(m.select("doc_id", quality.votes()["variety"].alias("v")), "doc_id", "v")) == {1: -1, 2: 1, 3: -1}


@pytest.mark.parametrize("table", ["edge", "docs"])
def test_exact_dedup(table, request):
    df = request.getfixturevalue(table)
    got = Counter(rows_of(exact_dedup.duplicate_groups(df, block_bytes=16 if table == "edge" else 512), "key", "keep", "group_size", "sha"))
    assert got == Counter(brute.exact(rows_of(df, "doc_id", "text")))


def test_exact_dedup_keeps_one_of_each(edge, docs):
    for df in (edge, docs):
        out = exact_dedup.drop_duplicates(df)
        assert out.columns == df.columns
        assert Counter(brute.squeezed(t) for (t,) in rows_of(out, "text")) == Counter({brute.squeezed(t) for (t,) in rows_of(df, "text")})


@pytest.mark.parametrize("table", ["edge", "docs"])
@pytest.mark.parametrize("bucket", [64, 1])
def test_simhash(table, bucket, request):
    df = request.getfixturevalue(table)
    keyed = rows_of(df, "doc_id", "text")
    fps = defaultdict(list)
    for d, t in keyed:
        fps[brute.fingerprint(t)].append(d)
    reps = {f: min((d for d in ds if d is not None), default=None) for f, ds in fps.items()}
    known = {r: f for f, r in reps.items() if r is not None}
    group = brute.closure(known, lambda a, b: bin(known[a] ^ known[b]).count("1") <= 2)
    want = Counter((d, brute.fingerprint(t), group.get(reps[brute.fingerprint(t)])) for d, t in keyed)
    got = Counter((k, f % (1 << 64), c) for k, f, c in rows_of(simhash.near_duplicates(df, bucket=bucket), "key", "fp", "component"))
    assert got == want


def test_simhash_crowded_entries(spark):
    """Many fingerprints that share a half: both ways to link them agree with all pairs."""
    rng = np.random.default_rng(3)
    values = sorted({int(x) for x in (rng.integers(0, 1 << 9, 150).astype(np.int64) | (7 << 40))} | {int(x) << 33 for x in rng.integers(0, 1 << 8, 60)})
    nodes = spark.createDataFrame([(v, i) for i, v in enumerate(values)], "fp long, rep long")
    want = brute.closure(range(len(values)), lambda a, b: bin(values[a] ^ values[b]).count("1") <= 2)
    for bucket in (4, 64, 10_000):
        got = dict(rows_of(components.components(simhash.near_links(nodes, bucket), "a", "b"), "node", "component"))
        assert {i: got.get(i, i) for i in range(len(values))} == want


@pytest.mark.parametrize("bucket", [1, 64])
def test_simhash_sends_no_multiplied_rows_through_the_driver(spark, bucket):
    fps = spark.range(200).select(F.xxhash64("id").bitwiseAND(F.lit(0xFFFF)).alias("fp"), F.col("id").alias("rep")).dropDuplicates(["fp"])
    nodes = simhash.materialize(fps, "nodes")
    plan = simhash.near_links(nodes, bucket)._jdf.queryExecution().executedPlan().toString()
    multiplied = [line for line in plan.splitlines() if "Join" in line and "Inner" in line]
    assert multiplied and all("SortMergeJoin" in line for line in multiplied)


def test_components_on_a_long_path(spark):
    links = spark.range(200).select(F.col("id").alias("a"), (F.col("id") + 1).alias("b"))
    assert {c for _, c in rows_of(components.components(links, "a", "b"), "node", "component")} == {0}


def test_near_dedup_keeps_one_of_each_group(docs, edge):
    for df in (docs, edge):
        keyed = df.where("doc_id is not null").dropDuplicates(["doc_id"])
        out = simhash.drop_near_duplicates(keyed)
        assert out.columns == df.columns
        assert {d for (d,) in rows_of(out, "doc_id")} == {c for (c,) in rows_of(simhash.near_duplicates(keyed), "component")}


def test_near_dedup_counts_repeated_rows_once(spark):
    rows = [(1, "one text of five words"), (1, "one text of five words"), (2, "another text of some words"), (None, "a third text without key"), (None, "a third text without key")]
    out = simhash.drop_near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"))
    assert Counter(rows_of(out, "doc_id", "text")) == Counter(set(rows))


def test_url_rules_and_parts(spark):
    cases = {
        "http://A.B.Example.NET/en/x?q=1#z": ("a.b.example.net", "/en/x", "example.net/en/", "allow"), "https://example.net": ("example.net", "", None, None), "ftp://xexample.com/de/": ("xexample.com", "/de/", None, None),
        "http://example.com/de/": ("example.com", "/de/", "example.com/de/", "block"), "http://x.org/fr/a://b": ("x.org", "/fr/a://b", "org/fr/", "allow"), "nothing": ("", "", None, None), None: ("", "", None, None), "http://n.net?x": ("n.net", "", None, None),
        "http://n.net/\n?x": ("n.net", "/\n", "net/", "block"), "://": ("", "", None, None),
    }
    df = spark.createDataFrame([(i, u) for i, u in enumerate(cases)], "page_id long, url string")
    got = {k: (h, p, r, v) for k, h, p, r, v in rows_of(urls.url_verdicts(df), "key", "host", "path", "rule", "verdict")}
    for i, (h, p, r, v) in enumerate(cases.values()):
        assert got[i][:3] == (h, p, r) and got[i][3] == (v or got[i][3]) and got[i][3] in ("allow", "block")


def test_url_trees_learn_and_the_column_equals_the_walk(spark):
    rng = np.random.default_rng(1)
    values = [tuple(map(float, rng.integers(0, 9, len(urls.FEATURES)))) for _ in range(400)]
    labels = [int(v[2] > 4 and v[5] < 6) for v in values]
    start, trees, cuts = urls.boost(values, labels)
    df = spark.createDataFrame([(*v, y) for v, y in zip(values, labels)], [*urls.FEATURES, "y"])
    score = F.lit(start)
    for t in trees:
        score = score + urls.tree_column(t, cuts, {n: F.col(n) for n in urls.FEATURES})
    assert df.select(((score > 0).cast("int") == F.col("y")).cast("int").alias("r")).agg(F.avg("r")).first()[0] > 0.97


def test_url_rates_are_counted_for_every_value(spark, monkeypatch):
    """More host suffixes and path parts than any list of the most frequent ones would hold."""
    blocked = [f"http://n{i}.net/p{i}/x" for i in range(1500) for _ in range(1 + (i < 1100))]
    allowed = [f"http://w.o{i}.org/fr/x" for i in range(1500) for _ in range(1 + (i < 1100))]
    rows = [(i, u) for i, u in enumerate(blocked + allowed + ["http://o1400.org/p1400/", "http://new.example/other", None])]
    seen = []
    monkeypatch.setattr(urls, "boost", lambda values, labels, params, f=urls.boost: seen.extend(values) or f(values, labels, params))
    out = urls.url_verdicts(spark.createDataFrame(rows, "page_id long, url string"))
    assert out.count() == len(rows)
    mean = (len(blocked) + 1) / (len(blocked + allowed) + 2)
    rate = lambda n, y: round((y + 10 * mean) / (n + 10), 9)
    suffix, part = urls.FEATURES.index("suffix_rate"), urls.FEATURES.index("part_rate")
    want = Counter({(rate(1, 1), rate(1, 1)): 400, (rate(2, 2), rate(2, 2)): 2200, (rate(1, 0), rate(len(allowed), 0)): 400, (rate(2, 0), rate(len(allowed), 0)): 2200})
    assert Counter((round(v[suffix], 9), round(v[part], 9)) for v in seen) == want


@pytest.mark.parametrize("table", ["edge", "docs"])
def test_personal_data(table, request):
    df = request.getfixturevalue(table)
    for _, text in rows_of(df, "doc_id", "text"):
        assert pii.base_spans(text) == brute.personal(text)
    out = rows_of(pii.find_personal_data(df), "key", "base", "spans")
    assert Counter((k, tuple(map(tuple, b))) for k, b, _ in out) == Counter((d, tuple(brute.personal(t))) for d, t in rows_of(df, "doc_id", "text"))
    assert all(set(map(tuple, b)) <= set(map(tuple, s)) for _, b, s in out)


def test_personal_data_finds_secrets_and_leaves_prose(spark, docs):
    out = pii.find_personal_data(docs).join(docs, docs.doc_id == F.col("key")).where("size(spans) > size(base)")
    for text, spans in rows_of(out, "text", "spans"):
        for s in spans:
            if s["kind"] == "secret":
                assert any(w in text[max(0, s["start"] - 20) : s["start"]] for w in ("password", "token", "key", "secret"))
    secret = docs.where("text rlike 'password=[0-9a-f]{18}'")
    clean = pii.redact(docs)
    assert clean.columns == docs.columns and clean.count() == docs.count()
    if secret.count() >= 3:
        assert clean.where("text rlike 'password=[0-9a-f]{18}'").count() == 0
    assert clean.where(r"text rlike '[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+([.][A-Za-z0-9-]+)+'").count() == 0


def test_secrets_of_any_length(spark, docs):
    rng = np.random.default_rng(4)
    secret = lambda n: "".join(rng.choice(list("ABCDEFGHabcdefghijkmnpq0123456789_"), n - 1)) + "x"
    rows = []
    for n in (150, 500, 5000):
        s = secret(n)
        for text in (f"use token: {s} now", f"PRODUCTION_SECRET_ACCESS_KEY={s}", f"--password='{s}'", f"take sk-{s}, then", f"AKIA{s}- end"):
            (kind, a, b, _, _), *more = pii.proposals(text, [])
            assert kind == "secret" and text[a:b].endswith(s) and len(text[a:b]) - n <= 4 and not more, text
            rows.append((-len(rows) - 1, text, s))
    assert pii.proposals("PRODUCTION_SECRET_ACCESS_KEY=a1b2c3d4e5f6", [])[0][3][1] == 1
    planted = spark.createDataFrame(rows, "doc_id long, text string, secret string")
    both = docs.select("doc_id", "text").union(planted.select("doc_id", "text"))
    clean = dict(rows_of(pii.redact(both).where("doc_id < 0"), "doc_id", "text"))
    assert len(clean) == len(rows) and not any(s[-50:] in clean[d] for d, _, s in rows)


def test_secret_pattern_is_linear_on_long_runs():
    for text in ("a-" * 200_000, "sk-" * 100_000 + "-" * 100_000, "-" * 200_000, "a=" * 200_000, "abc:short " * 20_000, "9" * 200_000 + "_a:"):
        start = time.perf_counter()
        assert len([1 for _ in pii._SECRET.finditer(text)]) <= 1
        assert time.perf_counter() - start < 5


def test_base_patterns_on_long_runs():
    assert pii.base_spans("9" * 200_000) == [] and pii.base_spans("a" * 200_000 + "@") == [] and pii.base_spans("1." * 100_000) != []


def test_ids_equal_the_tokenizers_library(docs, edge):
    fast, slow = tokens.encoder(tokens.default_file()), tokens.Encoder(tokens.default_file(), fast=False)
    for (t,) in [*rows_of(docs, "text"), *rows_of(edge, "text")]:
        assert fast.ids(t or "").tolist() == slow.ids(t or "").tolist()
    assert (fast.lengths[:1000] == slow.lengths[:1000]).all()


@pytest.mark.parametrize("rule", token_counts.RULES)
def test_token_counts(rule, docs, edge):
    enc = tokens.encoder(tokens.default_file())
    for df in (docs, edge):
        total, lines = Counter(), Counter()
        for d, t in rows_of(df, "doc_id", "text"):
            total[d] += len(enc.ids(t or ""))
            lines[d] += len((t or "").split("\n")) - ((t or "").endswith("\n"))
        got, sections = Counter(), Counter()
        for k, s, n in rows_of(token_counts.section_token_counts(df, rule=rule), "key", "section", "tokens"):
            got[k] += n
            sections[k] += s >= 0
        assert sections == Counter({k: v for k, v in lines.items()}) or all(sections[k] == max(v, 1) for k, v in lines.items() if k != 16)
        assert all(abs(got[k] - total[k]) < 1e-6 for k in total)


def test_boundary_crossing_tokens(spark):
    enc = tokens.encoder(tokens.default_file())
    text = "hello wonderful world"
    docs = spark.createDataFrame([(1, text)], "doc_id long, text string")
    ids = enc.ids(text)
    assert len(ids) == 3  # "hello", " wonderful", " world"
    parts = spark.createDataFrame([(1, 0, 0, 8), (1, 1, 8, 15), (1, 2, 18, 99)], "doc_id long, section long, start long, stop long")
    want = {"start": {0: 2.0, 1: 0.0, 2: 0.0, -1: 1.0}, "end": {0: 1.0, 1: 1.0, 2: 1.0}, "split": {0: 1.3, 1: 0.7, 2: 0.5, -1: 0.5}}
    for rule, sums in want.items():
        got = {s: round(t, 6) for s, t in rows_of(token_counts.section_token_counts(docs, parts, rule=rule), "section", "tokens")}
        assert got == sums, rule


def unigram_library():
    import sentencepiece
    from sentencepiece import sentencepiece_model_pb2 as model

    proto = model.ModelProto()
    proto.ParseFromString(open(pieces.default_file(), "rb").read())
    proto.trainer_spec.model_type = 1
    return sentencepiece.SentencePieceProcessor(model_proto=proto.SerializeToString())


def test_pieces_equal_the_whole_lattice(docs, edge):
    v, _ = pieces.vocabulary(pieces.default_file())

    def lattice(text):
        best, back = [0.0] + [-1e300] * len(text), [None] * (len(text) + 1)
        for start in range(len(text)):
            for end in range(start + 1, min(len(text), start + v.longest) + 1):
                found = v.scores.get(text[start:end])
                if found and best[start] + found[0] > best[end]:
                    best[end], back[end] = best[start] + found[0], (start, [found[1]])
            if text[start] not in v.scores and best[start] + v.penalty > best[start + 1]:
                best[start + 1], back[start + 1] = best[start] + v.penalty, (start, v.fallback(text[start]))
        out, end = [], len(text)
        while end:
            end, ids = back[end]
            out.append(ids)
        return [i for ids in reversed(out) for i in ids]

    texts = [t for (t,) in rows_of(docs.limit(40), "text")] + [t[:3000] for (t,) in rows_of(edge, "text") if t] + ["   spaces   inside ", "x" * 500, "日本" * 200, "ab\u00a0cd"]
    for t in texts:
        normal = v.lib.normalize(t)
        stream = pieces.StreamingViterbi(v)
        streamed = [i for at in range(0, len(normal), 7) for i in stream.push(normal[at : at + 7])]
        most = stream.most
        streamed += stream.finish()
        assert streamed == pieces.encode(t, pieces.default_file()).tolist()
        assert [v.scores and i for i in streamed] == streamed and most <= 400
        if len(t) < 1500:
            score = lambda ids: sum(v.lib.get_score(i) if not v.lib.is_byte(i) else 0 for i in ids)
            assert score(streamed) == score(lattice(normal))
        assert pieces.decode(streamed, pieces.default_file()) == t.replace("\x00", "\x00")


def test_pieces_equal_the_library_as_a_unigram_model(docs):
    lib = unigram_library()
    words = sorted({w for (t,) in rows_of(docs.limit(30), "text") for w in t.split()})[:2000]
    for w in words:
        assert pieces.encode(w, pieces.default_file()).tolist() == lib.encode(w), w
        v, _ = pieces.vocabulary(pieces.default_file())
        stream = pieces.StreamingViterbi(v)
        assert pieces.short_cut(w, v) == stream.push(w) + stream.finish()


def test_piece_tables_round_trip(docs, edge):
    for df in (docs, edge):
        back = pieces.with_text(pieces.with_ids(df))
        assert Counter(rows_of(back, "key", "text")) == Counter((d, t or "") for d, t in rows_of(df, "doc_id", "text"))


def test_language_id_on_held_out_documents(spark):
    out = queries.op8_language_id(spark, "/root/testdata/sf0.01")
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    both = out.join(docs, "doc_id").where("held_out and lang is not null")
    assert out.count() == docs.count() and both.count() > 100
    assert all(h == (zlib.crc32(str(d).encode()) % 4 == 2) for d, h in rows_of(out, "doc_id", "held_out"))
    assert both.where("lang = lang_pred").count() / both.count() > 0.97
    gap = both.select(F.avg("score") - F.avg((F.col("lang") == F.col("lang_pred")).cast("int"))).first()[0]
    assert abs(gap) < 0.05


def test_language_id_edge_cases(edge, empty):
    model = langid.train(edge)
    got = rows_of(langid.predict(edge, model), "doc_id", "lang_pred", "score")
    assert len(got) == len(brute.EDGE) and all(0 <= s <= 1 for *_, s in got)
    assert {d for d, lang, _ in got if lang == "und"} >= {1, 2, 3, 19}
    assert np.count_nonzero(model.weights) < model.weights.size / 2
    nothing = langid.train(empty)
    assert {lang for _, lang, _ in rows_of(langid.predict(edge, nothing), "doc_id", "lang_pred", "score")} == {"und"}


@pytest.mark.parametrize("table", ["edge", "docs"])
def test_substring_dedup(table, request):
    df = request.getfixturevalue(table)
    got = Counter(rows_of(substring_dedup.removal_digests(df), "key", "n_words", "n_removed", "kept_sha256"))
    assert got == Counter(brute.repeats(rows_of(df, "doc_id", "text")))


def test_substring_dedup_of_spliced_texts(spark):
    """Passages that begin and end anywhere, nested, overlapping and repeated inside a document."""
    rng = np.random.default_rng(5)
    pool = [f"v{i}" for i in rng.integers(0, 60, 4000)]
    texts = []
    for d in range(120):
        parts = []
        for _ in range(rng.integers(1, 5)):
            a = rng.integers(0, 3900)
            parts += pool[a : a + rng.integers(3, 60)] + [f"own{d}_{len(parts)}"] * int(rng.integers(0, 4))
        texts.append((d, " ".join(parts)))
    texts += [(200, "same " * 100), (201, "same " * 60), (202, "other " * 40 + "same " * 30)]
    df = spark.createDataFrame(texts, "doc_id long, text string").repartition(5)
    got = Counter(rows_of(substring_dedup.removal_digests(df), "key", "n_words", "n_removed", "kept_sha256"))
    assert got == Counter(brute.repeats(texts))
    spans = rows_of(substring_dedup.repeated_spans(df), "key", "words", "source")
    assert spans and all(s < k and w >= substring_dedup.K for k, w, s in spans)
    text = {d: t for d, t in rows_of(substring_dedup.drop_repeats(df), "doc_id", "text")}
    assert all(hashlib.sha256(text[d].encode()).hexdigest() == sha or n == 0 for d, _, n, sha in brute.repeats(texts))


def test_substring_dedup_cuts_long_documents(spark, monkeypatch):
    texts = [(1, brute.LONG), (2, brute.LONG[500:]), (3, "z " * 40 + brute.LONG[9000:20000])]
    want = [r for r in brute.repeats(texts)]
    monkeypatch.setattr(substring_dedup, "_CHUNK", 1000)
    found = []
    import pyarrow as pa

    for batch in substring_dedup._cut(iter([pa.RecordBatch.from_arrays([pa.array([d for d, _ in texts]), pa.array([t for _, t in texts])], names=["key", "text"])])):
        found += batch.to_pylist()
    assert sum(f["edges"] for f in found) == sum(max(0, w - 12) for _, w, _, _ in want)


@pytest.mark.parametrize("piece", [1, 5, 1 << 18])
def test_substring_dedup_names_words(monkeypatch, piece):
    """Equal words and only they have one name, wherever texts and pieces of bytes end."""
    import pyarrow as pa

    monkeypatch.setattr(substring_dedup, "_PIECE", piece)
    texts = [None, "", "a b", "b", "\tab  a\n", "é a\x1cb longer words", " ", "longer", "words", "\x0b\x0c\r"]
    h, of = substring_dedup.named_words(pa.array(texts).slice(1))
    words = [(i, w) for i, t in enumerate(texts[1:]) for w in substring_dedup.words_of(t)]
    assert of.tolist() == [i for i, _ in words]
    pairs = set(zip((w for _, w in words), h.tolist()))
    assert len(pairs) == len({w for w, _ in pairs}) == len({x for _, x in pairs})


def test_substring_dedup_of_a_key_with_two_texts(spark):
    """Paths to open of one row lie beyond the end of the other row of its key."""
    words = [f"w{i}" for i in range(200)]
    rows = [(1, " ".join(words)), (2, " ".join(["x", *words[20:150], "y", *words[60:180]])), (2, " ".join(words[:14])), (3, " ".join(words[10:26]))]
    got = sorted(rows_of(substring_dedup.removal_digests(spark.createDataFrame(rows, "doc_id long, text string")), "key", "n_words", "n_removed"))
    want = sorted(r[:3] for r in brute.repeats(rows))
    assert [g[:2] for g in got] == [w[:2] for w in want] and all(g[2] <= w[2] for g, w in zip(got, want)) and got[-1] == want[-1]


@pytest.mark.parametrize("table", ["edge", "docs"])
@pytest.mark.parametrize("buckets", [1, 5])
def test_packing(table, buckets, request):
    df = request.getfixturevalue(table)
    enc = tokens.encoder(tokens.default_file())
    out = packing.packed(df, buckets=buckets, with_ids=True)
    got = [r.asDict() for r in out.collect()]
    want = Counter((d, tuple(enc.ids(t or "").tolist() + [1])) for d, t in rows_of(df, "doc_id", "text"))
    sequences = defaultdict(list)
    for r in got:
        assert zlib.crc32(r["ids"]) == r["ids_crc32"] and len(r["ids"]) == 4 * r["length"] and r["length"] > 0
        sequences[r["sequence_id"]].append(r)
    for rows in sequences.values():
        rows.sort(key=lambda r: r["offset"])
        assert [r["offset"] for r in rows] == np.cumsum([0] + [r["length"] for r in rows[:-1]]).tolist()
        size = sum(r["length"] for r in rows)
        assert size <= 2048 and size & (size - 1) == 0
    by_doc = defaultdict(list)
    for r in got:
        by_doc[r["key"], r["doc_tokens"]].append(r)
    found = Counter()
    for (k, n), rows in by_doc.items():
        copies = defaultdict(list)  # repeated rows: several pieces with one start
        for r in sorted(rows, key=lambda r: (r["start"], r["sequence_id"], r["offset"])):
            copies[r["start"]].append(r)
        if all(len(x) == 1 for x in copies.values()):
            ids = np.frombuffer(b"".join(copies[s][0]["ids"] for s in sorted(copies)), "<u4")
            assert len(ids) == n
            found[k, tuple(ids.tolist())] += 1
        else:
            assert sum(r["length"] for r in rows) % n == 0
            found.update({x: c for x, c in want.items() if x[0] == k and len(x[1]) == n})
    assert found == want


def test_packing_holds_the_mixture(spark):
    rows = [(i, " ".join(["alpha beta gamma"] * (20 if s == "x" else 60)), s) for s, n in (("x", 600), ("y", 200), ("z", 100)) for i in range(n)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    got = packing.packed(df, buckets=2).groupBy("sequence_id").pivot("source", ["x", "y", "z"]).sum("length").na.fill(0).collect()
    total = Counter()
    for r in got:
        total.update({s: r[s] for s in "xyz"})
    share = {s: n / sum(total.values()) for s, n in total.items()}
    full = [r for r in got if r["x"] + r["y"] + r["z"] == 2048]
    near = [r for r in full if all(abs(r[s] / 2048 - share[s]) < 0.1 for s in "xyz")]
    assert len(near) > 0.8 * len(full)


def test_empty_tables(spark, empty):
    pages = spark.createDataFrame([], "page_id long, url string")
    for df in (
        quality.quality_verdicts(empty), quality.keep_good(empty), exact_dedup.duplicate_groups(empty), exact_dedup.drop_duplicates(empty), simhash.near_duplicates(empty), simhash.drop_near_duplicates(empty), urls.url_verdicts(pages),
        pii.find_personal_data(empty), pii.redact(empty), substring_dedup.removal_digests(empty), substring_dedup.drop_repeats(empty), packing.packed(empty), token_counts.section_token_counts(empty), pieces.piece_digests(empty), langid.predict(empty, langid.train(empty)),
    ):
        assert df.count() == 0


def test_pipeline_stages(spark, sf_dir):
    import corpus_pipeline as cp

    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    columns, now = docs.columns, docs
    for name, stage in cp.STAGES[:-1]:
        before = rows_of(now, "doc_id", "text")
        now = spark.createDataFrame(stage(spark, now, sf_dir).collect(), docs.schema)
        assert now.columns == columns
        after = dict(rows_of(now, "doc_id", "text"))
        if name == "exact_dedup":
            assert set(after) == {k for d, k, *_ in brute.exact(before)}
        if name == "near_dedup":
            fp = {d: brute.fingerprint(t) for d, t in before}
            assert set(after) == set(brute.closure(fp, lambda a, b: bin(fp[a] ^ fp[b]).count("1") <= 2).values())
        if name == "personal_data":
            assert set(after) == {d for d, _ in before} and not any(brute.personal(t) for t in after.values())
    out = cp.STAGES[-1][1](spark, now, sf_dir)
    assert {d for (d,) in rows_of(out, "doc_id")} == set(after)
    assert Counter(rows_of(cp.run(spark, sf_dir), "doc_id", "start", "ids_crc32")) == Counter(rows_of(out, "doc_id", "start", "ids_crc32"))
