"""Corpus operators against brute force, on small fixtures with nulls, ties, repeats, clashing columns and long texts."""

import hashlib
import html
import random
import re
import zlib

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from patternspark.llm import exact_dedup, html_text, langid, licenses, media, packing, pieces, resampling, simhash, url_filter
from patternspark.llm.graph import components

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, id string, fp string, h int"


def table(spark, texts, ids=None):
    ids = ids or range(len(texts))
    return spark.createDataFrame([(i, t, "en", "s", 0, "x", "y", 1) for i, t in zip(ids, texts)], SCHEMA)


def random_words(r, n):
    return " ".join("".join(r.choice("abcdefgh") for _ in range(r.randint(2, 8))) for _ in range(n))


# exact dedup


@pytest.mark.parametrize("keep", ["smallest", "largest"])
@pytest.mark.parametrize("hot_rows", [None, 3])
def test_exact_groups(spark, keep, hot_rows):
    texts = ["A b", "a B", None, "", "x", "É", "é", "a b", "a b"] + ["hot Copy"] * 40 + ["z" * 200_000, "Z" * 200_000]
    got = {r.id: r for r in exact_dedup.content_groups(table(spark, texts), keep=keep, hot_rows=hot_rows, partitions=5).collect()}
    norm = {i: "".join(c.lower() if "A" <= c <= "Z" else c for c in t or "") for i, t in enumerate(texts)}
    for i, t in norm.items():
        same = [j for j, u in norm.items() if u == t]
        best = (max if keep == "largest" else min)(same)
        assert (got[i].keep_id, got[i].group_size, got[i].kept, got[i].sha) == (best, len(same), i == best, hashlib.sha256(t.encode()).hexdigest())


def test_exact_edges(spark):
    assert exact_dedup.content_groups(table(spark, [])).count() == 0
    repeated = table(spark, ["a", "a", "b"], [1, 1, None])
    rows = exact_dedup.exact_dedup(repeated)
    assert rows.columns == repeated.columns and rows.count() == 2


def test_exact_is_native(spark):
    plan = exact_dedup.content_groups(table(spark, ["a"]))._jdf.queryExecution().toString()
    assert not re.search("Python|Pandas|Arrow", plan)


# URL filter


def test_urls(spark):
    rules = url_filter.UrlRules((("com/", "allow"), ("example.com/en/", "block"), ("www.example.com/en/", "allow"), ("net/es/", "block")))
    urls = ["http://a.EXAMPLE.com/en/1?x", "https://www.example.com/en/", "http://example.com/fr", "http://b.net/es/x#y", "http://b.net/en", "nonsense", None, "http://com", "http://xcom/", "http://spam.org/a", "http://www.spam.org", "http://notspam.org"]
    df = spark.createDataFrame([(i, u, "clash") for i, u in enumerate(urls)], "page_id long, url string, host string")
    got = [(r.host, r.path, r.rule, r.verdict) for r in url_filter.filter_urls(df, rules, ["spam.org"]).orderBy("id").collect()]
    assert got[0] == ("a.example.com", "/en/1", "example.com/en/", "block")
    assert got[1] == ("www.example.com", "/en/", "www.example.com/en/", "allow")
    assert got[2][2:] == ("com/", "allow") and got[3][2:] == ("net/es/", "block") and got[4][2:] == (None, "allow")
    assert got[5] == got[6] == ("", "", None, "allow")
    assert got[7][1:] == ("", None, "allow") and got[8][2] is None
    assert [x[3] for x in got[9:]] == ["block", "block", "allow"]
    assert url_filter.filter_urls(df.limit(0), rules).count() == 0


def test_hosts_named(spark):
    urls = ["http://A.Spam-farm.org/x", "https://spam.org", "http://a.spam-farm.org?y", "http://notspam.org/", "http://x.org/spam", None, "spam", "http://my.spammer.org"]
    df = spark.createDataFrame([(i, u, "clash") for i, u in enumerate(urls)], "page_id long, url string, host string")
    assert url_filter.hosts_named(df, ["spam", "ads"]) == ["a.spam-farm.org", "spam.org"]
    assert url_filter.hosts_named(df.limit(0), ["spam"]) == []
    from pyspark.sql import functions as F

    odd = ["HTTP://Ab.C/d/e?f#g", "a://b", "a://b#c/d", "://", "x://y://z", "a://é.Ñ/ß", "no", "", "a://b\n/c"]
    host, path = url_filter.url_parts(F.col("u"))
    got = spark.createDataFrame([(u,) for u in odd], "u string").select("u", host.alias("h"), path.alias("p")).collect()
    assert all((r.h, r.p) == url_filter.split_url(r.u) for r in got)


def test_digest_collisions_are_settled_by_the_strings():
    same = lambda b: 7
    a = url_filter.DigestArray.build([("one", 0), ("two", 1)], same)
    mapped = url_filter.map_bytes(a.pack())
    hits = mapped.find(np.array([7, 7, 7], dtype="<u8"), [b"two", b"one", b"three"])
    assert [bytes(mapped.blob[mapped.offsets[k]:mapped.offsets[k + 1]]).decode() if k >= 0 else None for k in hits] == ["two", "one", None]


def test_url_join_agrees(spark):
    urls = ["http://a.b.org/x/y/z", "http://b.org/x/q", "http://c.org", None]
    df = spark.createDataFrame(list(enumerate(urls)), "page_id long, url string")
    entries = spark.createDataFrame([("b.org/x/",), ("a.b.org/x/y/",), ("org",)], "entry string")
    got = {r.id: r.entry for r in url_filter.judge_urls_by_join(df, entries).collect()}
    assert got == {0: "a.b.org/x/y/", 1: "b.org/x/", 2: "org", 3: None}


# quality


def test_token_hashes_match_a_plain_reading():
    text = "Ab, c!! déf  ab\tAb"
    raw = np.frombuffer(text.encode(), dtype=np.uint8)
    starts, h = resampling.token_hashes(raw)
    found = re.findall(rb"[0-9A-Za-z\x80-\xff]+|[^\s0-9A-Za-z\x80-\xff]+", text.encode())
    assert len(starts) == len(found)
    by = {}
    for t, x in zip(found, h.tolist()):
        assert by.setdefault(t, x) == x
    assert len(set(by.values())) == len(by)
    who, what = resampling.features(["a a a", "zz zz", "", None])
    assert (np.bincount(who, minlength=4) == [5, 3, 0, 0]).all()
    pair = what[who == 1][2]
    assert pair in what[who == 0]  # repetitions share a bucket


def test_features_do_not_depend_on_chunks(monkeypatch):
    r = random.Random(1)
    texts = [random_words(r, 30) for _ in range(20)]
    whole = [np.sort(resampling.features([t])[1]) for t in texts]
    who, what = resampling.features(texts)
    assert all((np.sort(what[who == i]) == w).all() for i, w in enumerate(whole))


def test_resampling_keeps_good_documents(spark):
    r = random.Random(2)
    good = [random_words(r, 40) for _ in range(60)]
    bad = ["### $$$ " * 20 for _ in range(10)] + ["spam " * 30 for _ in range(10)]
    docs = table(spark, good + bad + [None, ""])
    labels = spark.createDataFrame([(i, int(i < 60)) for i in range(0, 80, 2)] + [(None, 1), (3, None), (0, 0)], "doc_id long, quality int")
    model = resampling.fit(docs, labels)
    assert model.share == 0.75 + (0.75 * 0.25 / 40) ** 0.5
    got = {x.doc_id: x for x in resampling.resample(docs, model, k=62, keep=["doc_id"]).collect()}
    assert all(got[i].selected for i in range(60)) and not any(got[i].selected for i in range(60, 80))
    assert got[80].log_weight == got[81].log_weight == 0
    assert sum(x.selected for x in resampling.resample(docs, model).collect()) == -(-82 * model.share // 1)
    assert len([x for x in resampling.resample(docs, model, k=7).collect() if x.selected]) == 7
    assert resampling.resample(docs.limit(0), model).count() == 0
    empty = resampling.fit(docs.limit(0), labels)
    assert empty.share == 1 and not empty.ratio.any()
    clash = docs.withColumn("c0", F.lit("x")).withColumn("score", F.lit("s")).withColumn("log_weight", F.lit("w")).withColumn("a.b", F.lit(1))
    one = resampling.resample(clash, model, k=1)
    assert set(one.columns) == {*clash.columns, "sample_key", "selected"} and {x.score for x in one.collect()} == {"s"}


def test_resampling_draws_by_gumbel_top_k(spark):
    """The draw, key by key: weights as a plain reading gives them, standard Gumbel noise, the k largest; by chance, not by weight alone."""
    r = random.Random(12)
    texts = [" ".join(r.choice(("aa", "bb", "cc")) for _ in range(r.randint(1, 4))) for _ in range(1500)]
    docs = table(spark, texts)
    model = resampling.fit(docs, spark.createDataFrame([(i, int("aa" in t)) for i, t in enumerate(texts)], "doc_id long, quality int"))
    got = resampling.resample(docs, model, k=500).toPandas().sort_values("doc_id", ignore_index=True)
    tokens = {t: int(resampling.features([t])[1][0]) for t in ("aa", "bb", "cc")}

    def grams(t):
        ws = t.split()
        return [tokens[w] for w in ws] + [int(resampling.features([f"{a} {b}"])[1][2]) for a, b in zip(ws, ws[1:])]

    raw, target = np.full(resampling.BUCKETS, resampling.SMOOTH), np.full(resampling.BUCKETS, resampling.SMOOTH)
    for i, t in enumerate(texts):
        for g in grams(t):
            raw[g] += 1
            target[g] += "aa" in t
    ratio = np.log(target / target.sum()) - np.log(raw / raw.sum())
    assert np.allclose(got["log_weight"], [ratio[grams(t)].sum() for t in texts], atol=1e-5)
    noise = np.sort((got["sample_key"] - got["log_weight"]).to_numpy())
    uniform = np.exp(-np.exp(-noise))
    assert np.abs(uniform - (np.arange(1500) + 0.5) / 1500).max() < 0.05  # Kolmogorov-Smirnov
    by_key = set(got.nlargest(500, "sample_key")["doc_id"])
    assert set(got.loc[got["selected"], "doc_id"]) == by_key
    assert len(by_key & set(got.nlargest(500, "log_weight")["doc_id"])) < 480  # the noise takes part


def test_kth_largest(spark):
    r = random.Random(3)
    vals = [round(r.gauss(0, 1), 3) for _ in range(3000)] + [5.0] * 50
    df = spark.createDataFrame([(v,) for v in vals], "x double")
    for k in (1, 50, 51, 700, len(vals), len(vals) + 5):
        assert resampling.kth_largest(df, "x", k) == sorted(vals, reverse=True)[min(k, len(vals)) - 1]
    assert resampling.kth_largest(df, "x", 0) is None


# language


def test_forward_sums_all_segmentations():
    vocab = ["▁", "a", "b", "ab", "▁a", "bb", "abb"]
    table_ = np.array([[0.2, 0.1], [0.1, 0.3], [0.1, 0.1], [0.2, 0.2], [0.1, 0.1], [0.2, 0.1], [0.1, 0.1], [1e-7, 1e-7]])
    m = langid.Model(langid.Vocabulary(vocab), ["x", "y"], table_)

    def total(s, k):
        if not s:
            return 1.0
        return sum((table_[vocab.index(s[:n]), k] if s[:n] in vocab else 1e-7 if n == 1 else 0) * total(s[n:], k) for n in range(1, len(s) + 1))

    from functools import cache

    total = cache(total)
    words = ["abb", "bbab", "aca", "abb" * 5, "ab" * 8 + "c", "abbab" * 20, "a" * 2000]
    got = m.log_words(words)
    for w, row in zip(words[:6], got):
        assert np.allclose(row, [np.log(total("▁" + w, k)) for k in (0, 1)])
    assert np.isfinite(got).all()
    for w in ("abb", "abbab" * 20, "ab" * 500):  # every character of a word counts once, however long the word is
        e = m.expected([w], np.array([1.0]), 0)
        assert np.isclose(sum(len(p) * c for p, c in zip(vocab, e)), 1 + len(w))


def test_language(spark):
    import public_tokenizers as known
    from pyspark.sql import functions as F

    r = random.Random(4)
    make = {"en": "the and ing tion er of to".split(), "de": "der die ung sch ein und zu".split()}
    rows = [(i, " ".join("".join(r.choice(make[l]) for _ in range(2)) for _ in range(20)), l) for i in range(120) for l in [("en", "de")[i % 2]]]
    rows += [(900, None, "en"), (901, "", "de"), (902, "123 !!", "en"), (903, rows[0][1], None)]
    docs = spark.createDataFrame([(*x, "clash") for x in rows], "doc_id long, text string, lang string, score string")
    model = langid.fit(docs, langid.public_pieces(known.path("piece_bpe_32k.model")), train=F.col("doc_id") % 4 != 0)
    got = {x.doc_id: x for x in langid.predict(docs, model, keep=["doc_id"]).collect()}
    assert all(got[i].lang_pred == l for i, _, l in rows[:120])
    assert all(got[i].lang_pred == "und" and got[i].score == 0 for i in (900, 901, 902))
    assert got[903].lang_pred == got[0].lang_pred and all(0 <= x.score <= 1 for x in got.values())
    nothing = langid.fit(docs.where("lang is null"), ["a"])
    assert {x.lang_pred for x in langid.predict(docs, nothing, keep=["doc_id"]).collect()} == {"und"}


# near duplicates


def brute_fp(text, size):
    ws = re.findall(r"[^\x20\x09-\x0D]+", "".join(c.lower() if "A" <= c <= "Z" else c for c in text or ""))
    if not ws:
        return 0
    sh = [" ".join(ws[i:i + size]) for i in range(max(1, len(ws) - size + 1))]
    hs = [xxhash.xxh64_intdigest(s.encode(), 42) for s in sh]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs))


def brute_components(ids, fps, distance):
    up = {i: i for i in ids}

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    for a in range(len(ids)):
        for b in range(a):
            if (fps[a] ^ fps[b]).bit_count() <= distance:
                x, y = find(ids[a]), find(ids[b])
                up[max(x, y)] = min(x, y)
    return {i: find(i) for i in ids}


@pytest.mark.parametrize("most", [2048, 2])
def test_simhash_groups(spark, most):
    r = random.Random(5)
    texts = [None, "", "A", "one Two\x1cthree", "É é   x"]
    for _ in range(12):
        ws = random_words(r, 120).split()
        texts.append(" ".join(ws))
        for _ in range(r.randint(0, 4)):
            if r.random() < 0.7:
                ws[r.randrange(len(ws))] = "new"
            texts.append(" ".join(ws))
    ids = list(range(100, 100 + len(texts)))
    got = {x.id: x for x in simhash.near_groups(table(spark, texts, ids), most=most).collect()}
    fps = [brute_fp(t, 4) for t in texts]
    assert [got[i].fp % 2**64 for i in ids] == fps
    want = brute_components(ids, fps, 4)
    assert {i: got[i].component_id for i in ids} == want
    assert len(set(want.values())) < len(ids)


@pytest.mark.parametrize("most", [10_000, 4])
def test_links_connect_just_those_within_distance(spark, most):
    r = random.Random(6)
    fps = {r.getrandbits(64) for _ in range(40)}
    for f in list(fps)[:10]:  # balls and chains
        for _ in range(8):
            for b in r.sample(range(64), r.randint(1, 4)):
                f ^= 1 << b
            fps.add(f)
    fps = sorted(fps)
    signed = [f - 2**64 if f >= 2**63 else f for f in fps]
    df = spark.createDataFrame([(f,) for f in signed], "fp long")
    links = [(x.a % 2**64, x.b % 2**64) for x in simhash.fingerprint_links(df, most=most).collect()]
    assert all((a ^ b).bit_count() <= 8 for a, b in links)
    lab = {x.node % 2**64: x.label % 2**64 for x in components(simhash.fingerprint_links(df, most=most)).collect()}
    want = brute_components(list(range(len(fps))), fps, 4)
    same = lambda a, b: lab.get(a, a) == lab.get(b, b)
    assert all(same(fps[a], fps[b]) == (want[a] == want[b]) for a in range(len(fps)) for b in range(a))


@pytest.mark.parametrize("most", [10_000, 2])
def test_links_of_an_odd_distance_in_crowded_keys(spark, most):
    r = random.Random(16)
    fps = {r.getrandbits(64) for _ in range(3)}
    for f in list(fps):
        for k in (2, 3, 3, 4):
            fps.add(f ^ sum(1 << b for b in r.sample(range(64), k)))
    fps = sorted(fps)
    df = spark.createDataFrame([(f - 2**64 if f >= 2**63 else f,) for f in fps], "fp long")
    links = simhash.fingerprint_links(df, distance=3, most=most)
    assert all(((x.a ^ x.b) % 2**64).bit_count() <= 3 for x in links.collect())
    lab = {x.node % 2**64: x.label for x in components(links).collect()}
    want = brute_components(list(range(len(fps))), fps, 3)
    same = lambda a, b: lab.get(a, a) == lab.get(b, b)
    assert all(same(fps[a], fps[b]) == (want[a] == want[b]) for a in range(len(fps)) for b in range(a))


def test_components_of_chains_and_stars(spark):
    edges = [(i, i + 1) for i in range(0, 50)] + [(100, i) for i in range(101, 130)] + [(7, 7), (0, 1)]
    got = {x.node: x.label for x in components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {i: 0 for i in range(51)} | {i: 100 for i in range(100, 130)}
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_near_copies(spark):
    r = random.Random(7)
    base = [random_words(r, 150).split() for _ in range(20)]
    texts = [" ".join(x) for x in base] + [" ".join([*x[:70], "changed", *x[71:]]) for x in base[:10]] + [None, "", "   "]
    got = simhash.drop_near_copies(table(spark, texts))
    assert got.columns == SCHEMA.replace(" long", "").replace(" string", "").replace(" int", "").split(", ")
    assert sorted(x.doc_id for x in got.collect()) == [*range(20), 30]
    assert simhash.drop_near_copies(table(spark, [])).count() == 0


def near_pairs(texts, similarity=0.8):
    sets = [simhash.shingle_set(t, 5) for t in texts]
    return [(a, b) for b in range(len(texts)) for a in range(b) if simhash.jaccard(sets[a], sets[b]) >= similarity]


def least_linked(pairs):
    up = {}
    for a, b in pairs:
        up.setdefault(a, a), up.setdefault(b, b)
    for _ in up:
        for a, b in pairs:
            up[a] = up[b] = min(up[a], up[b])
    return up


@pytest.mark.parametrize("most", [2048, 2])
def test_near_copies_beside_others_of_the_same_words(spark, most):
    r = random.Random(17)
    texts = []
    for _ in range(12):  # lesser ids have all words of the last two, or a half of their passages
        x = random_words(r, 120).split()
        texts += [" ".join(z) for z in (sorted(x), x[:62], x[58:], x, [*x[:119], "end"])]
    got = {x.id: x.component_id for x in simhash.near_copies(table(spark, texts), most=most).collect()}
    assert got == least_linked(near_pairs(texts)) and got


def test_parities_bound_the_difference():
    r = random.Random(21)
    for n in (1, 3, 60, 64, 65, 500, 3000):
        a = np.unique(np.array([r.getrandbits(63) for _ in range(n)], dtype="<i8"))
        others = []
        for share in (0.0, 0.5, 0.9, 1.0):
            b = np.array([x for x in a.tolist() if r.random() < share] + [r.getrandbits(63) for _ in range(r.randint(0, n // 2))], dtype="<i8")
            others.append(np.unique(b))
        apart = simhash.bits_apart(simhash.parity(a), [simhash.parity(b) for b in others])
        for b, d in zip(others, apart.tolist()):
            assert d <= len(np.setxor1d(a, b))
        assert simhash.bits_apart(simhash.parity(a), [simhash.parity(a)])[0] == 0
    long = [np.unique(np.array([r.getrandbits(63) for _ in range(4000)], dtype="<i8")) for _ in range(2)]
    n = np.array([len(x) for x in long])
    assert not len(simhash.possible(n, [simhash.parity(x) for x in long], 0, np.array([1]), 0.8))  # long strangers are told apart


def test_near_copies_by_brute_force(spark):
    r = random.Random(18)
    texts = []
    for n in (3, 5, 8, 14, 25, 40, 80, 160, 320):
        for _ in range(6):
            x = random_words(r, n).split()
            texts.append(" ".join(x))
            for share in (0.01, 0.02, 0.03, 0.05):
                texts.append(" ".join("".join(r.choices("abcdefghij", k=9)) if r.random() < share else w for w in x))
    r.shuffle(texts)
    pairs = near_pairs(texts)
    got = {x.id: x.component_id for x in simhash.near_copies(table(spark, texts)).collect()}
    assert got == least_linked(pairs) and len(pairs) > 50


@pytest.mark.parametrize("most", [2048, 2])
def test_near_copies_by_fingerprints_first(spark, monkeypatch, most):
    """Pairs of near fingerprints are verified first and by themselves, whether or not they are similar; others follow."""
    r = random.Random(19)
    texts = ["", None, "a b", "b a"]
    for _ in range(8):
        x = random_words(r, 400).split()
        texts += [" ".join(x), " ".join(x).upper(), " ".join([*x[:399], "end"]), " ".join([*x[:200], "in", "the", "middle", *x[203:]]), " ".join(x[:340])]
    fps = [simhash.fingerprint(t, 5) for t in texts]
    near = [(a, b) for b in range(len(texts)) for a in range(b) if (fps[a] ^ fps[b]).bit_count() <= 4]
    asked, verified = [], simhash.verified
    monkeypatch.setattr(simhash, "verified", lambda docs, pairs, **kw: asked.append([tuple(x) for x in pairs.collect()]) or verified(docs, pairs, **kw))
    got = {x.id: x.component_id for x in simhash.near_copies(table(spark, texts), most=most).collect()}
    pairs = near_pairs(texts)
    assert got == least_linked(pairs)
    assert set(asked[0]) <= set(near) and least_linked(asked[0]) == least_linked(near)
    assert set(pairs) - set(near) and not {x for turn in asked[1:] for x in turn} & set(asked[0])


# pieces


@pytest.fixture(scope="module")
def segmenter():
    import public_tokenizers as known

    return pieces.Segmenter(pieces.load(known.path("piece_bpe_32k.model")))


def test_n_best_is_exact():
    m = pieces.PieceModel(["▁", "a", "b", "ab", "▁a", "ba", "aba"], np.arange(10, 17), np.log(np.array([0.1, 0.2, 0.1, 0.2, 0.15, 0.2, 0.05])), list(range(1000, 1256)))
    s = pieces.Segmenter(m)

    def every(x):
        if not x:
            return [(0.0, [])]
        out = []
        for n in range(1, len(x) + 1):
            if x[:n] in m.pieces:
                k = m.pieces.index(x[:n])
                out += [(m.scores[k] + t, [10 + k, *ids]) for t, ids in every(x[n:])]
            elif n == 1:
                raw = x[0].encode()
                out += [(len(raw) * m.byte_score + t, [1000 + b for b in raw] + ids) for t, ids in every(x[1:])]
        return out

    for text in ("aba", "ab ba aba", "a\nbé ab", "", "  a"):
        want = sorted((t for t, _ in every(pieces.escape(text))), reverse=True)[:5]
        got = s.encode(text, 5)
        assert np.allclose([t for t, _ in got], want), text
        assert len({tuple(i) for _, i in got}) == len(got)
        assert all(s.decode(i) == text for _, i in got)
        assert np.isclose(s.encode(text)[0][0], want[0])


def test_pieces_round_trip(spark, segmenter):
    import public_tokenizers as known

    for text in ("Hello  world\nnext\tline", "naïve Ünïcode 日本 🙂", "", " ", "\n\n", "x" * 3000):
        assert all(segmenter.decode(ids) == text for _, ids in segmenter.encode(text, 3))
    docs = table(spark, ["some text here", None, "a▁b", "some text here"])
    got = {r.id: r for r in pieces.segment_documents(docs, known.path("piece_bpe_32k.model")).collect()}
    assert got[0].round_trip and got[1].round_trip and not got[2].round_trip
    assert got[0].others == got[3].others and got[0].nbest_scores == sorted(got[0].nbest_scores, reverse=True)
    assert got[0].n_pieces == len(got[0].ids) and got[0].ids_crc32 == zlib.crc32(np.array(got[0].ids, dtype="<u4").tobytes())
    assert got[0].decoded == "some text here" and got[1].decoded == "" and got[2].decoded == "a b"
    nbest = [got[0].ids, *[got[0].ids[:x.start] + x.ids + got[0].ids[x.stop:] for x in got[0].others]]
    assert [i for _, i in segmenter.encode("some text here", 4)] == nbest
    assert all(segmenter.decode(ids) == "some text here" for ids in nbest) and len({tuple(x) for x in nbest}) == 4
    assert pieces.segment_documents(docs.limit(0), known.path("piece_bpe_32k.model")).count() == 0


def test_n_best_of_whole_documents(spark, sf, segmenter):
    """Scores of the n best of given texts against a plain n-best dynamic program over the whole text, without segments."""
    import heapq

    import public_tokenizers as known

    m = segmenter.model
    score = dict(zip(m.pieces, m.scores.tolist()))
    docs = spark.read.parquet(f"{sf}/documents.parquet").where("length(text) < 3000").limit(12)
    texts = {r.doc_id: r.text for r in docs.select("doc_id", "text").collect()}
    for r in pieces.segment_documents(docs, known.path("piece_bpe_32k.model"), n=4).collect():
        text = pieces.escape(texts[r.id])
        best = [[0.0]] + [[] for _ in text]
        for j in range(1, len(text) + 1):
            cands = []
            for i in range(max(0, j - m.vocabulary.longest), j):
                s = score.get(text[i:j])
                if s is None and i == j - 1:
                    s = len(text[i].encode()) * m.byte_score
                if s is not None:
                    cands += [x + s for x in best[i]]
            best[j] = heapq.nlargest(4, cands)
        assert np.allclose(r.nbest_scores, best[-1], atol=1e-3)
        assert r.decoded == texts[r.id]
        of = dict(zip(m.ids.tolist(), m.scores.tolist())) | {i: m.byte_score for i in m.bytes_at}
        for s, ids in zip(r.nbest_scores, [r.ids, *[r.ids[:x.start] + x.ids + r.ids[x.stop:] for x in r.others]]):
            assert segmenter.decode(ids) == texts[r.id] and np.isclose(s, sum(of[i] for i in ids), atol=1e-3)


# media


@pytest.mark.parametrize("size", [0, 1, 63, 64, 65, 64 * 37, 100_000])
def test_payload_round_trip(size):
    r = random.Random(size)
    raw = bytes(r.choice([0, 255, 0xD8, r.randrange(256)]) for _ in range(size))
    p = media.pad(raw)
    assert len(p) % 64 == 0 and len(p) >= 64 and p.startswith(raw)
    jpeg = media.encode_payload(p)
    assert jpeg[:2] == b"\xff\xd8" and jpeg[-2:] == b"\xff\xd9"
    pics, coefs, levels = media.decode([jpeg, media.encode_payload(media.pad(b"other")), jpeg])
    assert media.payload_of(pics[0], coefs[0]) == p == media.payload_of(pics[2], coefs[2])
    assert levels[0].shape == (pics[0].height // 8, pics[0].width // 8)


def general_jpeg(dcs, rows, cols, comps, interval, ac):
    """A baseline JPEG with several components (sampling 2x2, 1x1, 1x1), standard-like codes and optional restarts."""
    dc_counts, dc_symbols = bytes([0, 1, 5, 1, 1, 1, 1, 1, 1] + [0] * 7), bytes(range(12))
    ac_symbols = bytes([0x01, 0x00, 0x11, 0xF0, 0x02])
    ac_counts = bytes([0, 2, 2, 1] + [0] * 12)

    def codes(counts, symbols):
        out, code, k = {}, 0, 0
        for length in range(1, 17):
            for _ in range(counts[length - 1]):
                out[symbols[k]] = format(code, f"0{length}b")
                code, k = code + 1, k + 1
            code <<= 1
        return out

    dcc, acc = codes(dc_counts, dc_symbols), codes(ac_counts, ac_symbols)
    amp = lambda v, s: "" if not s else format(v if v > 0 else v + (1 << s) - 1, f"0{s}b")
    out, bits_, pred, n = b"", "", [0] * len(comps), 0

    def flush():
        nonlocal out, bits_
        bits_ += "1" * (-len(bits_) % 8)
        raw = int(bits_, 2).to_bytes(len(bits_) // 8, "big") if bits_ else b""
        out += raw.replace(b"\xff", b"\xff\x00")
        bits_ = ""

    for mcu in range(rows * cols):
        if interval and n == interval:
            flush()
            out += bytes([0xFF, 0xD0 + (mcu // interval - 1) % 8])
            pred, n = [0] * len(comps), 0
        for ci, (h, v) in enumerate(comps):
            for _ in range(h * v):
                val = next(dcs)
                d = val - pred[ci]
                pred[ci] = val
                s = abs(d).bit_length()
                bits_ += dcc[s] + amp(d, s) + (acc[0x11] + "1" + acc[0xF0] + acc[0x01] + "0" if ac else "") + acc[0x00]
        n += 1
    flush()
    seg = media._segment
    hm, vm = max(h for h, _ in comps), max(v for _, v in comps)
    sof = media.struct.pack(">BHHB", 8, rows * 8 * vm - 3, cols * 8 * hm - 5, len(comps)) + b"".join(bytes([i + 1, h << 4 | v, 0]) for i, (h, v) in enumerate(comps))
    head = b"\xff\xd8" + seg(0xDB, b"\x00" + b"\x08" * 64) + seg(0xC0, sof) + seg(0xC4, b"\x00" + dc_counts + dc_symbols) + seg(0xC4, b"\x10" + ac_counts + ac_symbols)
    head += seg(0xDD, media.struct.pack(">H", interval)) if interval else b""
    return head + seg(0xDA, bytes([len(comps)]) + b"".join(bytes([i + 1, 0]) for i in range(len(comps))) + b"\x00\x3f\x00") + out + b"\xff\xd9"


@pytest.mark.parametrize("comps", [[(1, 1)], [(2, 2), (1, 1), (1, 1)], [(2, 1), (1, 1), (1, 1)]])
@pytest.mark.parametrize("interval", [0, 2])
@pytest.mark.parametrize("ac", [False, True])
def test_general_baseline_images(comps, interval, ac):
    r = random.Random(8)
    rows, cols = 3, 4
    vals = [r.randint(-120, 120) for _ in range(rows * cols * sum(h * v for h, v in comps))]
    jpeg = general_jpeg(iter(vals), rows, cols, comps, interval, ac)
    pics, coefs, levels = media.decode([jpeg, jpeg])
    per = sum(h * v for h, v in comps)
    h, v = comps[0]
    want = np.zeros((rows * v, cols * h), dtype=int)
    for m in range(rows * cols):
        for k in range(h * v):
            want[m // cols * v + k // h, m % cols * h + k % h] = np.clip(vals[m * per + k] + 128, 0, 255)
    assert (levels[0] == want[:levels[0].shape[0], :levels[0].shape[1]]).all() and (levels[1] == levels[0]).all()
    if ac:
        assert coefs[0][1][0][2] == 1 and coefs[0][1][0][19] == -1


def test_broken_images_are_refused():
    good = media.encode_payload(media.pad(b"x" * 500))
    for bad in (b"", b"abc", good[:40], good[:-30], good.replace(b"\xff\xc0", b"\xff\xc2", 1)):
        with pytest.raises(ValueError):
            media.decode([bad])


def test_media_columns(spark):
    texts = ["abc", None, "", "abc", "Ü" * 1000, "q" * 300_000]
    got = {r.id: r for r in media.media_columns(table(spark, texts)).collect()}
    for i, t in enumerate(texts):
        p = media.pad((t or "").encode())
        r = got[i]
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len((t or "").encode()), len(p), hashlib.sha256(p).hexdigest(), zlib.crc32(p[-64:]))
    assert got[0].media_sha256 == got[3].media_sha256 and got[1].feature == got[2].feature
    assert media.media_columns(table(spark, [])).count() == 0


# packing


@pytest.mark.parametrize("rule", ["norm", "dot"])
def test_best_fit_respects_every_capacity(rule):
    r = random.Random(9)
    cap = packing.Capacity(100, 4, 5000, rule, (1.0, 0.1, 0.1))
    lengths = np.array(sorted((r.randint(1, 70) for _ in range(500)), reverse=True))
    seq, off = packing.best_fit(lengths, cap)
    for s in set(seq.tolist()):
        own = lengths[seq == s]
        assert own.sum() <= 100 and len(own) <= 4 and (own**2).sum() <= 5000
        o = np.sort(off[seq == s])
        assert o[0] == 0 and (np.diff(o) == own[np.argsort(off[seq == s])][:-1]).all()
    with pytest.raises(ValueError):
        packing.best_fit(np.array([80]), packing.Capacity(100, 4, 100))


@pytest.mark.parametrize("rule", ["norm", "dot"])
def test_best_fit_looks_at_every_dimension(rule):
    """As a plain reading of the rule chooses; with the weights of two dimensions off, the choice is another one."""
    r = random.Random(19)
    lengths = np.array(sorted((r.randint(1, 1023) for _ in range(1500)), reverse=True))
    cap = packing.Capacity(1024, 6, 1024**2, rule)
    seq, off = packing.best_fit(lengths, cap)
    full, free = np.array([1024, 6, 1024**2], dtype=float), []
    for i, size in enumerate(lengths.tolist()):
        need = np.array([size, 1, size * size], dtype=float)
        fits = [k for k, f in enumerate(free) if (f >= need).all()]
        value = {k: (np.array(cap.weights) * need / full**2 * free[k]).sum() if rule == "dot" else -(np.array(cap.weights) * ((free[k] - need) / full) ** 2).sum() for k in fits}
        own = int(seq[i])
        if fits:
            assert value[own] >= max(value.values()) - 1e-12
        else:
            assert own == len(free)
            free.append(full.copy())
        free[own] -= need
    assert max(np.bincount(seq)) == 6 or rule == "norm"
    assert (off != packing.best_fit(lengths, packing.Capacity(1024, 6, 1024**2, rule, (1.0, 0.0, 0.0)))[1]).mean() > 0.02
    few = np.full(100, 3)
    assert packing.best_fit(few, cap)[0].max() + 1 == 17  # six documents at most


def test_packing_is_tight(spark):
    import public_tokenizers as known
    from tokenizers import Tokenizer

    r = random.Random(10)
    texts = [random_words(r, r.randint(0, 900)) for _ in range(60)] + [None, "", "<|endoftext|> x", "日本語 　 text", "a b", "x"]
    docs = table(spark, texts)
    got = packing.pack(packing.token_pieces(docs, known.path("byte_bpe_50k.json"), ranks_path=known.path("byte_bpe_50k.tiktoken"), pattern=known.PATTERN), bucket=40).collect()
    tok = Tokenizer.from_file(known.path("byte_bpe_50k.json"))
    for i, t in enumerate(texts):
        ids = np.array([*tok.encode(t or "", add_special_tokens=False).ids, 2], dtype="<u4")
        own = sorted((x for x in got if x.id == i), key=lambda x: x.piece)
        assert [x.start for x in own] == [0, *np.cumsum([x.length for x in own])[:-1]] and sum(x.length for x in own) == len(ids)
        assert all(x.length == 1024 for x in own[1:]) and (len(ids) > 1024) == (len(own) > 1)
        assert all(zlib.crc32(ids[x.start:x.start + x.length].tobytes()) == x.ids_crc32 for x in own)
    by = {}
    for x in got:
        by.setdefault(x.sequence_id, []).append(x)
    for own in by.values():
        own.sort(key=lambda x: x.offset)
        assert [x.offset for x in own] == [0, *np.cumsum([x.length for x in own])[:-1]] and sum(x.length for x in own) <= 1024
    assert len(by) <= sum(x.length for x in got) / 1024 + 4
    assert packing.pack(packing.token_pieces(table(spark, []), known.path("byte_bpe_50k.json"))).count() == 0


# licences


def test_licenses(spark):
    files = [
        (1, "a/LICENSE", "Released under the MIT License."), (2, "a/b/x.py", "code\nmore"), (3, "a/b/c/COPYING.txt", "intro\nLicensed under the Apache License, Version 2.0.\n"),
        (4, "a/b/c/d/y", None), (5, "z.txt", ""), (6, "a/own", "licensed under cc by-nc 4.0"), (7, None, "Released under the MIT License."), (8, "ab/q", "x" * 100_000), (2, "a/b/x.py", "code\nmore"),
    ]
    df = spark.createDataFrame([(*f, "clash") for f in files], "id long, path string, text string, license string")
    got = sorted((r.id, r.license, r.effective, r.from_dir) for r in licenses.scan(df).collect())
    none = lambda *x: tuple("-" if v is None else v for v in x)
    assert [none(*x) for x in got] == [
        (1, "MIT", "MIT", "-"), (2, "-", "MIT", "a"), (2, "-", "MIT", "a"), (3, "Apache-2.0", "Apache-2.0", "-"), (4, "-", "Apache-2.0", "a/b/c"),
        (5, "-", "-", "-"), (6, "CC-BY-NC-4.0", "CC-BY-NC-4.0", "-"), (7, "MIT", "MIT", "-"), (8, "-", "-", "-"),
    ]
    assert licenses.scan(df.limit(0)).count() == 0
    assert not re.search("Python|Pandas|Arrow", licenses.own_licenses(df)._jdf.queryExecution().toString())


def plain_passages(text):
    lines = [x for x in text.split("\n") if x.strip()]
    head = 0
    while head < len(lines) and re.match(r"\s*(#|//|/?\*|--|;|%|<!--)", lines[head]):
        head += 1
    out = [text, " ".join(lines[:head]), *re.split(r"\n[ \t#*/;-]*\n", text), *lines, *[" ".join(lines[i:i + k]) for k in (2, 3) for i in range(len(lines))], *re.split(r"(?<=[.!?;:]) ", re.sub(r"\s+", " ", text))]
    return [x for x in out if re.search(r"\b(" + "|".join(licenses.KEYWORDS) + ")", x)]


def test_license_cosines_match_a_plain_reading(spark):
    import math
    from collections import Counter

    r = random.Random(11)
    words = re.findall(r"[a-z0-9]+", " ".join(t for _, t in licenses.TEMPLATES[:11]).lower()) + ["foo", "bar"]
    lines = [" ".join(r.choice(words) for _ in range(r.randint(3, 9))) for _ in range(150)] + [t for _, t in licenses.TEMPLATES]
    lines += ["\n".join(r.sample(lines[:150], 5)) for _ in range(20)] + [f"# {t}\n#\n# code {lines[0]}" for _, t in licenses.TEMPLATES]
    idf, rare, vectors = licenses.weights()

    def best(text):
        out = (0, "")
        for line in plain_passages(text.lower()):
            v = {t: n * idf.get(t, rare) for t, n in Counter(re.findall(r"[a-z0-9]+", line)).items()}
            norm = math.sqrt(sum(x * x for x in v.values()))
            out = min(out, *((-round(sum(x * w.get(t, 0) for t, x in v.items()) / norm / n, 6), name) for name, w, n in vectors))
        return out

    got = {x.id: x for x in licenses.own_licenses(spark.createDataFrame(list(enumerate(lines)), "id long, text string")).collect()}
    for i, line in enumerate(lines):
        c, name = best(line)
        assert (got[i].license, got[i].cosine) == ((name, pytest.approx(-c, abs=2e-6)) if -c >= licenses.THRESHOLD else (None, None)), line
    for i, (name, text) in enumerate(licenses.TEMPLATES):
        assert got[150 + i].license == name and got[150 + i].whole and plain_passages(text.lower())
        assert got[150 + len(licenses.TEMPLATES) + 20 + i].license is not None


def test_license_texts_and_headers(spark):
    """A licence file with a name and year, headers in comments, texts far from any licence that use its words."""
    texts = dict(licenses.TEMPLATES[11:])
    mit = licenses.TEMPLATES[12][1].replace("Copyright (c)", "Copyright (c) 2021 Ann Other\n\n").replace("The above", "\n\nThe above").replace("THE SOFTWARE IS", "\n\nTHE SOFTWARE IS")
    bsd = dict(licenses.TEMPLATES[13:15])
    gpl = licenses.TEMPLATES[20][1]
    header = "\n".join(f" * {x}" for x in re.findall(r".{1,70}(?:\s|$)", gpl))  # with an empty line inside
    rows = [
        ("p/LICENSE", mit), ("p/src/deep/er/main.c", "int main() {}"), ("q/any-name", bsd["BSD-3-Clause"]), ("q/b2", "x = 1"), ("r/mod.c", f"/*\n * Tool, (C) 2001 Some One\n *\n{header}\n */\n\n" + "int f();\n" * 400),
        ("r/other.c", "int g();"), ("s/LICENSE", "Terms to follow. Ask for permission, all copies need a license and rights."), ("s/x", "y"), ("t/COPYING", bsd["BSD-2-Clause"]), ("t/u", None), ("v/u", texts["Unlicense"]),
    ]
    df = spark.createDataFrame([(i, p, t) for i, (p, t) in enumerate(rows)], "id long, path string, text string")
    got = {r.path: (r.license, r.effective, r.from_dir, r.licence_file) for r in licenses.scan(df).collect()}
    assert got["p/LICENSE"] == ("MIT", "MIT", None, True) and got["p/src/deep/er/main.c"] == (None, "MIT", "p", False)
    assert got["q/any-name"] == ("BSD-3-Clause", "BSD-3-Clause", None, True) and got["q/b2"] == (None, "BSD-3-Clause", "q", False)
    assert got["r/mod.c"][0] == "GPL-2.0" and not got["r/mod.c"][3] and got["r/other.c"] == (None, None, None, False)
    assert got["s/LICENSE"][0] is None and got["s/x"][1] is None
    assert got["t/COPYING"][0] == "BSD-2-Clause" and got["t/u"][1] == "BSD-2-Clause" and got["v/u"][0] == "Unlicense"


@pytest.mark.parametrize("most", [200_000, 0])
def test_licenses_of_a_hot_directory(spark, monkeypatch, most):
    monkeypatch.setattr(licenses, "BROADCAST_DIRS", most)
    files = spark.range(3000).select("id", F.concat(F.lit("hot/a/"), "id").alias("path"), F.when(F.col("id") == 7, "MIT").alias("license"))
    dirs = spark.createDataFrame([("hot", "ISC"), ("", "ARR"), ("cold", "MIT")], "dir string, dir_license string")
    got = licenses.inherit(files, dirs)
    assert got.count() == 3000 and {(r.effective, r.from_dir) for r in got.where("id <> 7").collect()} == {("ISC", "hot")}
    assert got.where("id = 7").first().effective == "MIT"


# HTML


def test_license_in_longer_lines_and_wrapped(spark):
    texts = ["Copyright 2020 Jane. Released under the MIT License.", "Some Project\nReleased under\nthe MIT License\nsee the docs", "a\n b This work is licensed under the GNU General\nPublic License, version 3. More words follow here, as ever", "Released under no terms."]
    df = spark.createDataFrame(list(enumerate(texts)), "id long, text string")
    got = {r.id: r.license for r in licenses.own_licenses(df).collect()}
    assert got == {0: "MIT", 1: "MIT", 2: "GPL-3.0", 3: None}


def test_html_article():
    page = """<!DOCTYPE html><html><head><title>T</title><style>p{}</style><script>var t="</p>";</script></head><body class="page with-sidebar">
    <header><a href=/>Home</a></header><nav><ul><li><a href="/a">Menu</a></ul></nav><!-- no <p>x</p> -->
    <div class="cookie-notice">We use cookies, honest.</div><div class="ad">Buy now.</div>
    <article><header><h1>Head &amp; line</h1></header><p><b>Bo</b>ld&nbsp;text<br>next
    line.<p>Second, para. <a href="x">link</a></p><ul><li>one<li>two</ul><form><input><label>mail</label></form><aside>Aside text, long.</aside></article>
    <section id="comments"><h2>Comments</h2><p>A reader says, well, things. Many, many things.</p></section><div id="sidebar"><p>Side.</p></div><footer>&copy; foot</footer></body></html>"""
    assert html_text.main_text(page) == "Head & line Bold text next line. Second, para. link one two"


def test_html_without_article_element():
    para = "".join(f"<p>Sentence number {i}, with words, and more words. It goes on, and on.</p>" for i in range(6))
    page = f"<html><body><div class=menu><a>x</a></div><div id=content><h1>Title</h1>{para}</div><div><a>a</a> <a>b</a></div><div class='footer'>f</div></body></html>"
    want = "Title " + " ".join(f"Sentence number {i}, with words, and more words. It goes on, and on." for i in range(6))
    assert html_text.main_text(page) == want
    assert html_text.main_text("<html><body><h1>Hi</h1><p>Only one, short.</p></body>") == "Hi Only one, short."


def test_html_nested_sections_are_whole():
    long_ = "A long paragraph, with marks, and words. " * 20
    text = long_.strip()
    assert html_text.main_text(f"<article><h1>Title</h1><div><p>{long_}</p><p>{long_}</p></div></article>") == f"Title {text} {text}"
    assert html_text.main_text(f"<body><main><section><p>{long_ * 19}</p></section><section><p>{long_}</p></section></main></body>") == " ".join([text] * 20)
    rows = "".join(f"<tr><td>{long_}</td></tr>" for _ in range(3))
    assert html_text.main_text(f"<body><div class=menu>m</div><div id=content><p>Intro.</p><table>{rows}</table></div></body>") == f"Intro. {text} {text} {text}"
    assert html_text.main_text(f"<body><h1>Title</h1><div><p>{long_}</p><p>{long_}</p></div></body>") == f"Title {text} {text}"
    assert html_text.main_text(f"<body><div><div><p>{long_ * 10}</p></div><div><p>{long_}</p></div></div></body>") == " ".join([text] * 11)


def test_html_edges(spark):
    pages = [None, "", "plain text", "<p>a<p>b", "<div><nav>x</nav></div>", "<p>&#233;&lt;b&gt;&unknown;</p>", "<article>" + "<p>word, word.</p>" * 20_000 + "</article>", "<<>><p"]
    df = spark.createDataFrame([(i, "u", p, "clash") for i, p in enumerate(pages)], "page_id long, url string, html string, text string")
    got = {r.id: r for r in html_text.extract(df).collect()}
    assert [got[i].text for i in range(6)] == ["", "", "plain text", "a b", "", html.unescape("é<b>&unknown;")]
    assert got[6].n_chars == len("word, word. ") * 20_000 - 1
    assert html_text.extract(df.limit(0)).count() == 0


def test_html_layout_classes():
    page = """<body><div class="layout has-sidebar"><div id="main-nav"><a>m</a></div><div class="article-header"><h1>Own, title</h1></div><article class="post"><p>First, text.</p>
    <div class="post-comments"><p>Reader, says.</p></div><div class="share-buttons">Share</div><p>Last, text.</p></article><div class="sidebar-right"><p>Side, bar.</p></div></div></body>"""
    assert html_text.main_text(page) == "First, text. Last, text."
    assert html_text.main_text('<body class="x"><div class="widget-area"><article><p>Inside, still.</p></article></div></body>') == "Inside, still."
    long_ = "".join(f"<p>Paragraph {i}, long enough, with words.</p>" for i in range(5))
    assert html_text.main_text(f'<body><div class="content-with-sidebar"><div class="post-header"><h1>Head</h1></div>{long_}</div><div class="sidebar">no, no</div></body>').startswith("Head Paragraph 0")


def plain_article(page):
    inner = re.search(r"<article>(.*)</article>", page, re.S)[1]
    plain = re.sub(r"</?[a-z0-9]+[^>]*>", lambda m: "" if m[0] in ("<b>", "</b>") else " ", inner)
    return " ".join(html.unescape(plain).split())


@pytest.mark.parametrize("shape", ["article", "div", "table"])
@pytest.mark.parametrize("names", [True, False])
def test_html_by_ratios(spark, sf, shape, names):
    """The given pages, also with other elements for article, and with the list of class names off: path ratios alone
    find the text then. With flat or random scores they do not, so the scores decide."""
    pages = [r.html for r in spark.read.parquet(f"{sf}/pages.parquet").collect()]
    change = {"article": lambda p: p, "div": lambda p: p.replace("<article>", "<div>").replace("</article>", "</div>"), "table": lambda p: p.replace("<article>", "<table><tr><td>").replace("</article>", "</td></tr></table>")}[shape]

    def right(**kw):
        return np.mean([html_text.main_text(change(p), names=names, **kw) == plain_article(p) for p in pages])

    assert right() >= (1.0 if names else 0.88)  # without names, an article shorter than its one advert cannot be told from it
    assert right(scores=lambda found, names=True: np.ones(len(found))) < 0.1
    r = np.random.default_rng(1)
    assert right(scores=lambda found, names=True: r.random(len(found))) < (0.8 if shape == "article" else 0.5)


def test_html_ratios_beside_long_boilerplate():
    para = "".join(f"<p>Sentence number {i}, with words, and more words. It goes on, and on, for some time.</p>" for i in range(8))
    links = "".join(f"<div><span>teaser {i}</span></div>" for i in range(30))
    page = f"<body><div>{links}</div><div><h2>Own title</h2>{para}</div><div><ul>{'<li>tag</li>' * 20}</ul></div></body>"
    assert html_text.main_text(page) == "Own title " + " ".join(f"Sentence number {i}, with words, and more words. It goes on, and on, for some time." for i in range(8))
    page = f"<body><main><h1>Head</h1><article>{para}<div class='share'>Share, this.</div></article><p>More: a, b.</p></main></body>"
    assert html_text.main_text(page).startswith("Head Sentence number 0") and "Share" not in html_text.main_text(page)
