"""The operators against plain versions, on the given tables and on rows with nulls, repeats and long texts."""

import gzip
import hashlib
import random
import time
import zlib
from collections import Counter

import duckdb
import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from varlink.llm import byte_cnn, decontamination, line_dedup, mixing, quality, queries, secret_scan, simhash, tokens, url_filter, warc
from varlink.llm.common import load
from varlink.llm.reference_sql import SQL

from . import brute
from .conftest import messy_rows

TEXTS = [r[1] for r in messy_rows()]
BENCH = [(1, _B := "beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi"), (2, "no such words anywhere at all in here my dear friend indeed"), (3, "ONE two"), (None, "alpha"), (4, None), (5, "--"), (3, "hunter2hunter2")]


def rows(df):
    return sorted((tuple(r) for r in df.collect()), key=repr)


@pytest.mark.parametrize("name", sorted(SQL))
def test_sql(spark, sf_dir, name):
    con = duckdb.connect()
    for t in ("documents", "pages", "benchmark", "labels"):
        con.execute(f"create view {t} as select * from '{sf_dir}/{t}.parquet'")
    got = queries.queries()[name](spark, sf_dir)
    want = con.execute(f"select {', '.join(got.columns)} from ({SQL[name]})").fetchall()
    assert rows(got) == sorted(want, key=repr)


# ------------------------------------------------------------------ 1: quality rules


def test_quality_counts():
    for t in TEXTS:
        assert quality.measure_text(t)[:5] == brute.base_counts(t)


@settings(max_examples=200, deadline=None)
@given(st.text(alphabet="ab \n\t#é\u00a0\x1c", max_size=60))
def test_quality_counts_any(t):
    assert quality.measure_text(t)[:5] == brute.base_counts(t)


def test_quality_messy(messy, clashing, nothing):
    judged, counts, failed, kept = quality.judge(clashing)
    got = {r["doc_id"]: r for r in judged.collect()}
    assert len(judged.collect()) == len(TEXTS) and got[1][failed] and not got[1][kept] and got[4][counts[0]] > 50
    assert judged.columns[: len(clashing.columns)] == clashing.columns
    assert quality.quality_filter(clashing).columns == clashing.columns
    assert quality.quality_filter(nothing).count() == 0


def test_sketches_merge(messy):
    measured = quality.measure(messy, list(quality.COUNTS)).withColumns({"l": F.coalesce("lang", F.lit("")), "s": F.coalesce("source", F.lit(""))})
    values = quality.measures({c: F.col(c) for c in quality.COUNTS})
    group = [F.col("l"), F.col("s")]
    whole = quality.sketch(measured, group, values)
    parts = [quality.sketch(measured.filter(F.expr(f"coalesce(doc_id, 0) % 2 = {i}")), group, values) for i in (0, 1)]
    assert rows(whole) == rows(quality.merge_sketches(*parts))


def test_sketch_accuracy(spark):
    rng = np.random.default_rng(1)
    x = rng.lognormal(0, 1, 2000)
    df = spark.createDataFrame([("a", "b", float(v)) for v in x], "lang string, source string, v double")
    s = quality.sketch(df, [F.col("lang"), F.col("source")], {"v": F.col("v")})
    q = quality.quartiles(s).filter("level = 0").first()
    for got, p in ((q["q1"], 25), (q["q3"], 75)):
        assert abs(got / np.percentile(x, p) - 1) < 2 * quality.RULES.accuracy


def prose(rng, n, size=80, mean=5):
    return [" ".join("x" * max(1, k) for k in rng.poisson(mean, size)) for _ in range(n)]


def fences_by_source(spark, texts):
    rows_ = [(i, t, "en", s) for i, (s, t) in enumerate((s, t) for s, ts in texts.items() for t in ts)]
    docs = spark.createDataFrame(rows_, "doc_id long, text string, lang string, source string")
    measured = quality.measure(docs, list(quality.COUNTS)).filter("n_words > 0")
    s = quality.sketch(measured, [F.col("lang"), F.col("source")], quality.measures({c: F.col(c) for c in quality.COUNTS}))
    return {(r["source"], r["measure"]): r for r in quality.fence_rows(s).collect()}, docs


def test_fences_follow_their_source(spark):
    """A source whose documents use longer words gets its fences there, and no other source's fences move much."""
    rng = np.random.default_rng(3)
    texts = {"a": prose(rng, 300), "b": prose(rng, 300)}
    before, _ = fences_by_source(spark, texts)
    after, _ = fences_by_source(spark, texts | {"b": prose(rng, 300, mean=9)})
    moved = lambda source, side: after[source, "word_length"][side] - before[source, "word_length"][side]
    for side in ("low", "high"):
        assert moved("b", side) > 2 and abs(moved("a", side)) < moved("b", side) / 2
    assert before["a", "word_length"]["own"] > 0.8
    few, _ = fences_by_source(spark, texts | {"c": prose(rng, 5)})
    assert few["c", "word_length"]["own"] < 0.1 and abs(few["c", "word_length"]["high"] - before["a", "word_length"]["high"]) < 0.3


def test_fences_reject_each_kind(spark):
    rng = np.random.default_rng(4)
    words = lambda: [f"w{k}" for k in rng.integers(0, 10**9, 120)]
    good = [" ".join(words()) for _ in range(400)]
    bad = {
        "word_length": " ".join("x" * 20 + w for w in words()),
        "symbol_rate": " ".join(w + "|" for w in words()),
        "dup_line_share": "\n".join(f"{a}" for a in words() for _ in range(2)),
        "repeat_share": " ".join((x := words())[:40] + x[:40] + x[40:]),
    }
    docs = spark.createDataFrame([(i, t, "en", "s") for i, t in enumerate([*good, *bad.values()])], "doc_id long, text string, lang string, source string")
    judged, _, failed, kept = quality.judge(docs, quality.QualityRules(max_repeat_percent=90), keep=["doc_id"], report=True)
    got = {r["doc_id"]: r for r in judged.collect()}
    assert sum(not got[i][kept] for i in range(400)) == 0
    for i, name in enumerate(bad):
        assert name in got[400 + i][f"{kept}_by"] and not got[400 + i][failed], name


def test_sketch_sets_most_fences(spark, sf_dir):
    """In most groups of the given table the group's own sketch weighs more than what it is shrunk to."""
    docs = load(spark, sf_dir.rsplit("/", 1)[0] + "/sf0.1", "documents")
    measured = quality.measure(docs, list(quality.COUNTS), keep=["lang", "source"])
    count = {c: F.col(c) for c in quality.COUNTS}
    s = quality.sketch(measured.filter(~quality.base_failed(count)), quality.group_columns(), quality.measures(count))
    own = [r["own"] for r in quality.fence_rows(s).collect()]
    assert sum(w > 0.5 for w in own) > 0.5 * len(own)
    said = {r["rule"]: r["n"] for r in quality.rejections(docs).groupBy("rule").agg(F.sum("documents").alias("n")).collect()}
    assert said["base"] > 0 and said["word_length"] > 0 and said["symbol_rate"] > 0


# ------------------------------------------------------------------ 2: token counts


@pytest.fixture(scope="module")
def counter():
    return tokens.TokenCounter(queries.tokenizer_path(), 400, 40)


PIECES = st.lists(st.sampled_from(["the", "don't", "İstanbul", "e\u0301", " ", "\n", "\u00a0", "\u2003", "12345", "<|endoftext|>", "日本語", "x" * 90, "--", "\x1c", "ß", "'ll", "\t\r\n"]), max_size=60)


@settings(max_examples=150, deadline=None)
@given(PIECES, st.sampled_from(["", " "]))
def test_tokens_like_library(pieces, glue):
    c = tokens.TokenCounter(queries.tokenizer_path(), 90, 12)
    t = glue.join(pieces)
    assert c.count(t) == len(c.encode(t).ids)


def test_long_tokens(counter):
    random.seed(3)
    t = "".join(random.choice(["word ", "x" * 700, "a1-b2 ", "\n\n", "été ", "<|startoftext|>"]) for _ in range(800))
    whole = counter.encode(t)
    ids = [i for part, _ in counter.spliced(t) for i in part]
    places = [o for _, part in counter.spliced(t) for o in part]
    assert ids == whole.ids and places == list(whole.offsets) and counter.widened > 0


def test_tokens_messy(clashing, nothing):
    c = tokens.TokenCounter(queries.tokenizer_path())
    got = tokens.token_counts(clashing, queries.tokenizer_path())
    want = sorted(((r[0], len((r[1] or "").encode()), len(c.encode(r[1] or "").ids)) for r in messy_rows()), key=repr)
    assert rows(got.select("doc_id", "n_bytes", "n_tokens")) == want
    assert tokens.token_counts(nothing, queries.tokenizer_path()).count() == 0


def test_clashing_names(spark):
    """The caller's columns keep their names and values; results step aside."""
    own = spark.createDataFrame([("a token=abcdefgh1", 1, "mine", 2.0, 3)], "text string, N_TOKENS int, spans string, score double, n_bytes int")
    made = tokens.token_counts(own, queries.tokenizer_path())
    assert made.columns == [*own.columns, "n_bytes_", "n_tokens_", "over_limit"] and made.first()["n_bytes"] == 3
    made = secret_scan.scan_secrets(own)
    assert made.columns == [*own.columns, "n_assign", "n_access", "n_hex", "base_sha256", "spans_"] and made.first()["spans"] == "mine"
    made = byte_cnn.score_quality(own, byte_cnn.train([], np.array([])))
    assert made.columns == [*own.columns, "score_", "predicted"] and made.first()["score"] == 2.0


def test_long_tokens_without_blanks(counter):
    """Texts without white space are spliced at punctuation and digits, in time that grows with their length."""
    rng = random.Random(2)
    letters = [chr(rng.randrange(0x4E00, 0x9FA0)) for _ in range(500)] + list("aß\u0130é")
    for sign in ("，。！", "1", ".|'", "\u0301,"):
        text = "".join(rng.choice(sign) if rng.random() < 0.05 else rng.choice(letters) for _ in range(6000))
        text = text[:3000] + "<|endoftext|>" + text[3000:]
        assert counter.count_long(text) == len(counter.encode(text).ids)
        for p in counter.stable_points(text, 0, len(text))[::40]:
            assert len(counter.encode(text[:p]).ids) + len(counter.encode(text[p:]).ids) == len(counter.encode(text).ids)
    bare = "".join(rng.choice(letters) for _ in range(5000))
    assert counter.count_long(bare) == len(counter.encode(bare).ids)
    big = tokens.TokenCounter(queries.tokenizer_path())
    seconds, encoded = [], []
    plain = big.encode
    for n in (200_000, 800_000):
        text = "".join(rng.choice("，。") if rng.random() < 0.05 else rng.choice(letters) for _ in range(n))
        spent = []
        big.encode = lambda t, spent=spent: spent.append(len(t)) or plain(t)
        began = time.process_time()
        big.count(text)
        seconds.append(time.process_time() - began)
        encoded.append(sum(spent) / n)
        assert max(spent) < 2 * big.chunk
    assert max(encoded) < 1.2 and seconds[1] < 8 * seconds[0]


# ------------------------------------------------------------------ 3: secrets


@settings(max_examples=300, deadline=None)
@given(st.lists(st.sampled_from(["password", "PassWD", "token", "ToKeN", "api_key", "APIKEY", "secret", "AKIA", "=", ":", " ", "'", "abcdefgh", "0123456789abcdef", "A" * 12, "é", "\u017f", "K", "\n"]), max_size=25))
def test_secrets_like_patterns(pieces):
    t = "".join(pieces)
    assert [s for s in secret_scan.find_secrets(t) if s[0] in secret_scan.BASE_KINDS] == brute.base_secrets(t)


def test_checksums():
    body = "aQ" * 15
    good = "ghp_" + body + secret_scan.base62_crc(body.encode()).decode()
    assert secret_scan.find_secrets(f"é {good} x") == [("forge", 2, 42)]
    assert secret_scan.find_secrets("ghp_" + "Q" * 36) == []
    assert secret_scan.mask_secrets(f"see {good}.") == "see [forge]."
    assert secret_scan.mask_secrets(None) is None


def test_secrets_messy(clashing, nothing):
    got = {(r["doc_id"], r["text"]): r for r in secret_scan.scan_secrets(clashing).collect()}
    for d, t, *_ in messy_rows():
        want = brute.base_secrets(t)
        r = got[d, t]
        assert (r["n_assign"], r["n_access"], r["n_hex"]) == tuple(sum(k == x for k, *_ in want) for x in secret_scan.BASE_KINDS)
        assert r["base_sha256"] == hashlib.sha256(secret_scan.digest(want).encode()).hexdigest()
    assert secret_scan.scan_secrets(nothing).count() == 0


# ------------------------------------------------------------------ 4: urls


def test_url_rules(spark):
    urls = [None, "", "nowhere", "http://A.Example.COM/en/71?x", "http://example.com/en/1", "https://x.net/de/1", "https://example.net/de/81#a", "ftp://b.org/es/", "http://notexample.com/en/7", "http://c.org", "http://[::1]:80/x", "a://b://c/d"]
    pages = spark.createDataFrame([(i, u) for i, u in enumerate(urls)], "page_id long, url string").withColumns({"host": F.lit(1), "verdict": F.lit(2)})
    judged, (host, path, rule, verdict) = url_filter.judge_urls(pages)
    got = {r["page_id"]: (r[host], r[path], r[rule], r[verdict]) for r in judged.collect()}
    assert got[0][:3] == ("", "", None) and got[2][:3] == ("", "", None)
    assert got[3] == ("a.example.com", "/en/71", "example.com/en/7", "allow")
    assert got[4][2:] == ("com/en/", "block") and got[5][2:] == ("net/de/", "allow") and got[6][2:] == ("example.net/de/8", "block")
    assert got[7][2:] == ("org/es/", "block") and got[8][2:] == ("com/en/", "block") and got[9][:2] == ("c.org", "") and got[11][:2] == ("b:", "//c/d")
    assert url_filter.judge_urls(pages.limit(0))[0].count() == 0


def test_reputation_shrinks(spark):
    rng = random.Random(2)
    outcomes = [(f"http://bad{i}.spam.example/", True) for i in range(40) for _ in range(5)] + [(f"http://h{i}.good.example/", rng.random() < 0.05) for i in range(40) for _ in range(5)]
    out = spark.createDataFrame(outcomes, "url string, bad boolean")
    pages = spark.createDataFrame([(1, "http://new.spam.example/"), (2, "http://new.good.example/"), (3, "http://other/")], "page_id long, url string")
    judged, names = url_filter.judge_urls(pages, out, rules=())
    assert {r["page_id"]: r[names[3]] for r in judged.collect()} == {1: "block", 2: "allow", 3: "allow"}
    assert {r["page_id"]: r[names[3]] for r in url_filter.judge_urls(pages, out.limit(0), rules=())[0].collect()} == {1: "allow", 2: "allow", 3: "allow"}


def test_reputation_finds_planted_hosts(spark):
    """Of hosts below one domain, those that show bad documents are blocked, and the rules say nothing of it."""
    rng = random.Random(6)
    bad_hosts, rows_ = {"h3", "h7"}, []
    labels = [(i, i % 2 == 0) for i in range(4000)]
    for h in range(20):
        for _ in range(60):
            bad = rng.random() < (0.8 if f"h{h}" in bad_hosts else 0.1)
            rows_.append((len(rows_), f"http://h{h}.example.net/fr/{2 * rng.randrange(2000) + (not bad)}?x"))
    rows_ += [(len(rows_) + i, f"http://h1.example.net/de/{2 * i}") for i in range(300)]  # allowed by a rule, so no outcomes
    pages = spark.createDataFrame(rows_, "page_id long, url string")
    judged, names = url_filter.judge_urls(pages, labels=spark.createDataFrame(labels, "key long, bad boolean"))
    blocked = {r[names[0]].split(".")[0] for r in judged.collect() if r[names[3]] == "block" and "/fr/" in r["url"]}
    assert blocked == bad_hosts


def test_hosts(spark):
    hosts = {"a.b.co.uk": ("b.co.uk", "co.uk"), "u@x.y.com:80": ("y.com", "com"), "10.0.0.1:8080": ("10.0.0.1", "#address"), "[::1]:80": ("[::1]", "#address"), "w.org..": ("w.org", "org"), "one": ("one", "one"), "": ("", "")}
    bare = url_filter.bare_host(F.col("h"))
    got = {r["h"]: (r["d"], r["s"]) for r in spark.createDataFrame([(h,) for h in hosts], "h string").select("h", url_filter.domain_of(bare).alias("d"), url_filter.suffix_of(bare).alias("s")).collect()}
    assert got == hosts


# ------------------------------------------------------------------ 5: classifier


def test_classifier_held_out(spark):
    got = queries.op5_quality_classifier(spark, "/root/testdata/sf0.01").join(load(spark, "/root/testdata/sf0.01", "labels"), "doc_id").toPandas()
    own = got[got.held_out]
    assert all((zlib.crc32(str(i).encode()) % 5 == 0) == h for i, h in zip(got.doc_id, got.held_out, strict=True))
    a, b = own[own.quality == 1].score.to_numpy(), own[own.quality == 0].score.to_numpy()
    assert ((a[:, None] > b) + 0.5 * (a[:, None] == b)).mean() > 0.93
    assert (own[own.quality == 1].predicted == 1).mean() > 0.95


def test_classifier_whole_text():
    c = byte_cnn.CnnConfig(epochs=3)
    clean, junk = [b"some plain words here " * 4] * 30, [b"some $$$ words %%% here " * 4] * 30
    model = byte_cnn.train(clean + junk, np.array([1.0] * 30 + [0.0] * 30), byte_cnn.CnnConfig(epochs=12))
    long = "some plain words here " * 3000
    assert model.score(long) > 0.5 > model.score(long + "$$$ words %%% here ")
    raw = bytes(random.Random(1).randrange(256) for _ in range(20_000))
    small = byte_cnn.ByteCnn(model.tables, model.bias, model.out, model.out_bias, byte_cnn.CnnConfig(chunk=100))
    assert np.allclose(small.pooled(raw), model.pooled(raw), atol=1e-6)
    assert 0 <= model.score(None) == model.score("") <= 1 and 0 <= model.score("a") <= 1
    assert byte_cnn.train([], np.array([]), c).score("x") == 0.5
    assert byte_cnn.train([b"x"], np.array([1.0]), c).score("x") == byte_cnn.train([b"x"], np.array([1.0]), c).score("")


def test_classifier_forward_brute(spark):
    """Scores of the given documents against windows taken one at a time."""
    rng = np.random.default_rng(5)
    c = byte_cnn.CnnConfig(widths=(2, 4), filters=3, chunk=64)
    model = byte_cnn.ByteCnn([rng.normal(size=(w, 256, 3)).astype(np.float32) for w in c.widths], [rng.normal(size=3).astype(np.float32) for _ in c.widths], rng.normal(size=6), 0.2, c)
    docs = load(spark, "/root/testdata/sf0.001", "documents").filter("length(text) < 1500")
    assert docs.count() > 50
    for r in byte_cnn.score_quality(docs, model, keep=["text"]).collect():
        raw = r["text"].encode()
        raw = raw.ljust(4, b" ") if raw else raw
        feats = []
        for w, table, bias in zip(c.widths, model.tables, model.bias, strict=True):
            for f in range(3):
                best = max((sum(float(table[i, raw[at + i], f]) for i in range(w)) for at in range(len(raw) - w + 1)), default=None)
                feats.append(0.0 if best is None else np.tanh(max(0.0, best + float(bias[f]))))
        assert abs(r["score"] - 1 / (1 + np.exp(-(np.dot(feats, model.out) + 0.2)))) < 1e-5


def test_classifier_learns_from_the_end():
    """Marks that come only after the first 5,000 bytes are learned, and found there."""
    plain = "some plain words of a long text here " * 200
    rows_ = [(plain + f"tail {i} ") for i in range(40)] + [(plain + f"@@~~ {i} @@~~") for i in range(40)]
    model = byte_cnn.train([t.encode() for t in rows_], np.array([1.0] * 40 + [0.0] * 40), byte_cnn.CnnConfig(epochs=15))
    assert model.score(plain + "tail 99 ") > 0.5 > model.score(plain + "@@~~ 99 @@~~")


def test_classifier_sample(spark):
    """One row an id, the same on every run, whole texts, at most ``sample_rows``."""
    docs = spark.createDataFrame([(i % 50, f"text {i} " + "x" * 9000) for i in range(400)], "doc_id long, text string").repartition(7)
    labels = spark.createDataFrame([(i, i % 2) for i in range(50)], "doc_id long, quality int")
    taken = lambda d: sorted((r["doc_id"], bytes(r["raw"])) for r in byte_cnn.training_sample(d, labels, byte_cnn.CnnConfig(sample_rows=20)).collect())
    one = taken(docs)
    assert one == taken(docs.repartition(3)) and len(one) == len({d for d, _ in one}) == 20 and all(len(t) > 9000 for _, t in one)


def test_classifier_messy(spark, clashing, nothing):
    labels = spark.createDataFrame([(4, 1), (7, 1), (7, 0), (11, 0), (None, 1), (12, None)], "doc_id long, quality int")
    model = byte_cnn.fit(clashing, labels, byte_cnn.CnnConfig(epochs=1))
    assert byte_cnn.score_quality(clashing, model).count() == len(TEXTS)
    assert byte_cnn.score_quality(nothing, byte_cnn.fit(nothing, labels)).count() == 0


# ------------------------------------------------------------------ 6: mixing


def fill(budget, caps, weights):
    """Water filling by bisection."""
    low, high = 0.0, 1e12
    for _ in range(200):
        mid = (low + high) / 2
        low, high = (mid, high) if sum(min(c, mid * w) for c, w in zip(caps, weights, strict=True)) < budget else (low, mid)
    return [min(c, low * w) for c, w in zip(caps, weights, strict=True)]


def test_budgets(spark):
    rng = random.Random(5)
    leaves = [(f"d{d}", f"l{x}", f"s{s}", rng.choice([0, 10, 500, 20_000])) for d in range(3) for x in range(3) for s in range(3)]
    t = mixing.MixTargets(weights={"d0": 3.0, "d1/l1": 0.0, "d2/l0/s1": 5.0}, budget=60_000, max_epochs=2)
    got = {tuple(r)[:3]: r["budget"] for r in mixing.allot(spark.createDataFrame(leaves, "domain string, lang string, source string, tokens long"), t).collect()}
    w = lambda *p: t.weights.get("/".join(p), 1.0)
    cap = {x[:3]: 2.0 * x[3] for x in leaves}
    langs = {k: sum(c for x, c in cap.items() if x[:2] == k and w(*x) > 0) for k in {x[:2] for x in cap}}
    doms = {k: sum(c for x, c in langs.items() if x[0] == k and w(*x) > 0) for k in {x[0] for x in cap}}
    names = sorted(doms)
    for d, bd in zip(names, fill(min(60_000, sum(doms.values())), [doms[n] for n in names], [w(n) for n in names]), strict=True):
        ls = sorted(k for k in langs if k[0] == d)
        for k, bl in zip(ls, fill(bd, [langs[n] if w(*n) > 0 else 0 for n in ls], [w(*n) for n in ls]), strict=True):
            ss = sorted(x for x in cap if x[:2] == k)
            for x, b in zip(ss, fill(bl, [cap[n] for n in ss], [w(*n) for n in ss]), strict=True):
                assert abs(got[x] - b) <= 1.01, (x, got[x], b)


@pytest.mark.parametrize("bucket_rows", [3, 1000])
def test_prefix(spark, sf_dir, bucket_rows):
    t = mixing.MixTargets(bucket_rows=bucket_rows, budget_share=0.6, max_epochs=3)
    docs = load(spark, sf_dir, "documents")
    mixed, (domain, n, copies) = mixing.mix(docs, t)
    got = {r["doc_id"]: r[copies] for r in mixed.collect()}
    with_tokens = docs.select("doc_id", mixing.default_domain(t).alias("domain"), "lang", "source", "text", mixing.count_tokens(F.col("text")).alias("n")).collect()
    leaves = Counter()
    for r in with_tokens:
        leaves[r["domain"], r["lang"], r["source"]] += r["n"]
    budgets = {tuple(r)[:3]: r for r in mixing.allot(spark.createDataFrame([(*k, v) for k, v in leaves.items()], "domain string, lang string, source string, tokens long"), t).collect()}
    for leaf, b in budgets.items():
        own = [r for r in with_tokens if (r["domain"], r["lang"], r["source"]) == leaf]
        key = lambda r: int(hashlib.md5(f"{t.seed}|{b['epochs']}|{r['doc_id']}|{hashlib.md5(r['text'].encode()).hexdigest()}".encode()).hexdigest()[:15], 16)  # noqa: E731, B023
        through = 0
        for r in sorted(own, key=key):
            through += r["n"]
            assert got.get(r["doc_id"], 0) == b["epochs"] + (through <= b["rest"])
    assert sum(r[n] * r[copies] for r in mixed.collect()) <= 0.6 * sum(leaves.values()) + 1


def test_mix_messy(clashing, nothing):
    mixed, names = mixing.mix(clashing)
    assert mixed.columns[: len(clashing.columns)] == clashing.columns and 0 < mixed.count() <= len(TEXTS)
    assert all(r[names[1]] > 0 for r in mixed.collect())
    assert mixing.mix(nothing)[0].count() == 0


# ------------------------------------------------------------------ 7: near copies


def test_simhash_given(spark, sf_dir):
    docs = load(spark, sf_dir, "documents").select("doc_id", "text").collect()
    got = {r["doc_id"]: (r["fingerprint"], r["component_id"]) for r in queries.op7_simhash(spark, sf_dir).collect()}
    prints = [brute.simhash(r["text"]) for r in docs]
    comps = brute.components([r["doc_id"] for r in docs], prints)
    assert got == {r["doc_id"]: (f"{p:016x}", c) for r, p, c in zip(docs, prints, comps, strict=True)}


@pytest.mark.parametrize("limit", [1, 4, 1000])
def test_links_any_bucket(spark, limit):
    rng = random.Random(limit)
    prints = {rng.getrandbits(64) for _ in range(40)}
    for base in list(prints)[:6]:
        for _ in range(30):
            x = base
            for _ in range(rng.randrange(4)):
                x ^= 1 << rng.randrange(64)
            prints.add(x)
    signed = [(p - (1 << 64) if p >> 63 else p,) for p in prints]
    df = spark.createDataFrame(signed, "fp long")
    roots = {r["node"]: r["root"] for r in simhash.components(simhash.find_links(df, limit)).collect()}
    want = brute.components([s for s, in signed], [s & (2**64 - 1) for s, in signed])
    assert [roots.get(s, s) for s, in signed] == want


def test_copies_messy(clashing, nothing):
    grouped, fp, comp = simhash.group_near_copies(clashing)
    docs = messy_rows()
    prints = [brute.simhash(r[1]) for r in docs]
    want = sorted(((r[0], c) for r, c in zip(docs, brute.components([r[0] for r in docs], prints), strict=True)), key=repr)
    assert rows(grouped.select("doc_id", comp)) == want
    kept = simhash.drop_near_copies(clashing)
    assert kept.columns == clashing.columns
    assert sorted((r["doc_id"] for r in kept.collect() if r["doc_id"] is not None)) == sorted({c for _, c in want if c is not None})
    assert simhash.drop_near_copies(nothing).count() == 0


# ------------------------------------------------------------------ 8: archives


def test_archives(spark, tmp_path):
    big = "x<é>" * 40_000
    pages = [(1, "http://a/", big), (2, "http://b/ ü", big), (3, None, None), (4, "http://c/", ""), (5, "u", "small"), (6, "u", "small"), (2, "http://again/", big), (None, "http://n/", big), (7, "v", "\r\n\r\nWARC/1.1\r\n" * 200)]
    df = spark.createDataFrame(pages, "page_id long, url string, html string").withColumn("record_type", F.lit(1)).repartition(3)
    planned = warc.plan_records(df)
    manifest = warc.write_archives(planned, f"file://{tmp_path}/w", chunk_bytes=1000)
    chunks = warc.read_archives(spark, manifest, f"file://{tmp_path}/w", chunk_bytes=997).collect()
    want = sorted(((p[0], *x) for p, x in zip(pages, brute.archive(pages), strict=True)), key=repr)
    ends = [r for r in chunks if r["last"]]
    assert sorted(((r["page_id"], r["stated_bytes"], r["stated_digest"], r["record_type"], r["refers_to"]) for r in ends), key=repr) == want
    own = sorted((r for r in chunks if r["page_id"] == 7), key=lambda r: r["chunk_no"])
    assert b"".join(r["data"] for r in own).decode() == pages[-1][2] and len(own) > 1 and all(len(r["data"]) <= 997 for r in own)
    assert rows(warc.round_trip(df)) == want
    assert warc.round_trip(df.limit(0)).count() == 0


def test_archives_by_other_reader(spark, tmp_path):
    """The files are gzip members of one record each, as the library's gzip reader and the length headers see them."""
    big = "ü|" * 3000
    pages = [(1, "http://a/", big), (2, "http://b/", big), (2, "http://c/", "other"), (3, None, None), (None, "n", "x" * 10)]
    df = spark.createDataFrame(pages, "page_id long, url string, html string").repartition(2)
    manifest = warc.write_archives(warc.plan_records(df), f"file://{tmp_path}/o", chunk_bytes=512).collect()
    found, members = {}, 0
    for row in manifest:
        raw = open(row["path"], "rb").read()
        while raw:
            z = zlib.decompressobj(31)
            record, raw, members = z.decompress(raw), z.unused_data, members + 1
            head, _, block = record.partition(b"\r\n\r\n")
            fields = dict(x.split(": ", 1) for x in head.decode().split("\r\n")[1:])
            assert block[int(fields["Content-Length"]) :] == b"\r\n\r\n" and gzip.decompress(gzip.compress(block)) == block
            payload = block[: int(fields["Content-Length"])].partition(b"\r\n\r\n")[2]
            found[fields["WARC-Record-ID"]] = (fields, payload)
    assert members == len(found) == len(pages) == sum(r["records"] for r in manifest)
    for fields, payload in found.values():
        whole = found[fields["WARC-Refers-To"]][1] if fields["WARC-Type"] == "revisit" else payload
        assert "sha1:" + hashlib.sha1(whole).hexdigest() == fields["WARC-Payload-Digest"] and len(whole) == int(fields["X-Payload-Length"])


def test_chunks_out_of_order(spark, tmp_path):
    planned = warc.plan_records(spark.createDataFrame([(1, "u", "abc" * 100)], "page_id long, url string, html string"))
    table = warc.chunk_table(planned, 64)
    assert table.count() > 10 and table.filter("last").first()["digest_so_far"] == hashlib.sha1(b"abc" * 100).hexdigest()
    with pytest.raises(Exception, match="not in order"):
        warc.write_chunks(table.filter("chunk_no <> 3").coalesce(1), f"file://{tmp_path}/x")


def test_archive_spoilt(tmp_path):
    head = warc.record_head("response", 1, "u", hashlib.sha1(b"abcdefgh").hexdigest(), 8, None)
    with open(tmp_path / "x", "wb") as out:
        warc.write_records(out, [(head, [b"ab"])])
    with open(tmp_path / "x", "rb") as source, pytest.raises(ValueError):
        list(warc.read_records(source))


# ------------------------------------------------------------------ 9: decontamination


def test_leaks_messy(spark, clashing, nothing):
    bench = spark.createDataFrame(BENCH, "item_id long, text string")
    judged, (words, hit, n_items, ids) = decontamination.judge_contamination(clashing, bench)
    want = sorted(((r[0], *x) for r, x in zip(messy_rows(), brute.leaks([r[:2] for r in messy_rows()], BENCH), strict=True)), key=repr)
    assert sorted(((r["doc_id"], r[words], r[hit], r[ids]) for r in judged.collect()), key=repr) == want
    assert judged.columns[: len(clashing.columns)] == clashing.columns
    kept = decontamination.decontaminate(clashing, bench)
    assert kept.columns == clashing.columns and kept.count() == sum(x[2] == 0 for x in want)
    assert decontamination.judge_contamination(nothing, bench)[0].count() == 0
    assert decontamination.decontaminate(clashing, bench.limit(0)).count() == len(TEXTS)


def test_leaks_random(spark):
    rng = random.Random(4)
    word = lambda: rng.choice("aa bb cc dd ee".split())
    docs = [(i, " ".join(word() for _ in range(rng.randrange(60)))) for i in range(60)]
    items = [(i, " ".join(word() for _ in range(rng.choice([1, 2, 3, 5, 10, 12])))) for i in range(12)]
    items += [(90 + i, " ".join(docs[i][1].split()[:14])) for i in range(6)]
    judged, (words, hit, _, ids) = decontamination.judge_contamination(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string"), size=4)
    assert sorted((r["doc_id"], r[words], r[hit], r[ids]) for r in judged.collect()) == [(d[0], *x) for d, x in zip(docs, brute.leaks(docs, items, 4), strict=True)]


def test_proximity(spark):
    docs = spark.createDataFrame([(1, "a x x b x a"), (2, "b a"), (3, "a x x x x x b")], "doc_id long, text string")
    forms = spark.createDataFrame([("a", "a"), ("b", "b")], "raw string, term string")
    pairs = spark.createDataFrame([(0, "a", "b")], "pair int, term_a string, term_b string")
    got = decontamination.proximity_matches(decontamination.build_postings(docs, forms), pairs, 3)
    assert rows(got.select("doc_id", "left", "right")) == [(1, 0, 3), (1, 5, 3), (2, 1, 0)]


def test_near_passage(spark):
    """A benchmark passage with every eighth word changed or an extra one has no exact window, and is near all the same."""
    rng = random.Random(9)
    words = lambda n: [f"w{rng.randrange(4000)}" for _ in range(n)]
    item = words(60)
    changed = [w if i % 8 else "other" for i, w in enumerate(item)]
    longer = [x for i, w in enumerate(item) for x in ([w, "extra"] if i % 8 == 4 else [w])]
    texts = [words(80) + changed + words(50), words(20) + longer, item[::-1] + words(9), words(10) + item] + [words(100) for _ in range(300)]
    docs = spark.createDataFrame([(i, " ".join(t)) for i, t in enumerate(texts)], "doc_id long, text string")
    bench = spark.createDataFrame([(1, " ".join(item)), (2, " ".join(words(30)))], "item_id long, text string")
    judged, (_, hit, n_items, _) = decontamination.judge_contamination(docs, bench, near="near")
    got = [(r[n_items], r["near"]) for r in judged.orderBy("doc_id").collect()]
    assert got[:4] == [(0, 1), (0, 1), (0, 0), (1, 1)] and set(got[4:]) == {(0, 0)}


# ------------------------------------------------------------------ 10: lines


def test_lines_messy(clashing, nothing):
    marked, n, dropped, kept = line_dedup.mark_lines(clashing)
    want = sorted(((r[0], *x) for r, x in zip(messy_rows(), brute.line_dedup([r[:2] for r in messy_rows()]), strict=True)), key=repr)
    assert sorted(((r["doc_id"], r[n], r[dropped], r[kept]) for r in marked.collect()), key=repr) == want
    out = line_dedup.drop_repeated_lines(clashing)
    assert out.columns == clashing.columns and out.count() == len(TEXTS)
    assert {r["doc_id"]: r["text"] for r in out.collect()}[1] is None
    assert line_dedup.drop_repeated_lines(nothing).count() == 0


# ------------------------------------------------------------------ pipeline


def test_pipeline(spark, sf_dir):
    """Every stage against its plain version, on what the stage before it kept."""
    import corpus_pipeline

    docs = load(spark, sf_dir, "documents")
    columns = docs.columns
    for name, stage in corpus_pipeline.STAGES:
        before = {r["doc_id"]: r for r in docs.collect()}
        made = stage(spark, docs, sf_dir)
        after = spark.createDataFrame(made.collect(), made.schema)
        got = {r["doc_id"]: r for r in after.collect()}
        order = sorted(before)
        pairs = [(i, before[i]["text"]) for i in order]
        if name == "quality_rules":
            failed = {i for i, t in pairs if (c := brute.base_counts(t))[0] < 50 or 100 * c[4] > 50 * c[0]}
            assert not failed & set(got) and len(got) > 0.9 * (len(before) - len(failed)) * 0.85
        elif name == "line_dedup":
            assert [got[i]["text"] for i in order] == [x[2] for x in brute.line_dedup(pairs)]
        elif name == "near_dedup":
            assert set(got) == set(brute.components(order, [brute.simhash(t) for _, t in pairs]))
        elif name == "decontamination":
            items = [tuple(r) for r in load(spark, sf_dir, "benchmark").select("item_id", "text").collect()]
            assert set(got) == {i for (i, _), x in zip(pairs, brute.leaks(pairs, items), strict=True) if not x[1]}
        else:
            assert set(got) <= set(before) and all(got[i]["copies"] > 0 for i in got)
        assert after.columns[: len(columns)] == columns
        docs = after
    assert rows(corpus_pipeline.run(spark, sf_dir).select("doc_id", "copies")) == rows(docs.select("doc_id", "copies"))
