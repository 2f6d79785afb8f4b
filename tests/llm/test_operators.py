"""Each operator against brute force, and on nulls, empty and long texts, ties, repeated rows, empty tables and foreign columns."""

import gzip
import hashlib
import itertools
import math
import re
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from catalogflow.llm import ctw, hilbert, hosts, imatch, language, mixing, neardup, packing, queries, text as tx, topk, warc
from catalogflow.session import fresh_path, table

DOCS = "doc_id bigint, text string, lang string, source string, n_chars bigint, digest string, h bigint"


def odd(spark, more=()):
    """Documents with every odd case; two columns have names that the operators use inside."""
    long = " ".join(f"word{i % 977} the and of" for i in range(30_000))
    rows = [
        (1, "the cat and the dog is in the house of that man", "en", "a", 46, "x", 1), (2, None, "en", "a", None, "x", 1), (3, "", None, None, 0, None, None),
        (None, "der hund und die katze ist in dem haus von dem mann", "de", "b", 50, "x", 1), (4, long, "en", "b", len(long), "x", 1), (5, "!!! ??? ...", "de", "a", 11, "x", 1),
        (1, "the cat and the dog is in the house of that man", "en", "a", 46, "x", 1), (6, "der die das und nicht mit von zu den sich", "de", "a", 40, "x", 2), (7, "café — naïve \U0001f600", "fr", "b", 13, "x", 1),
    ]
    return spark.createDataFrame([*rows, *more], DOCS)


def empty(spark):
    return spark.createDataFrame([], DOCS)


def rows(df):
    return [r.asDict() for r in df.collect()]


# words and shingles


def test_words_follow_documents_and_unicode():
    doc, code, start, end, low = tx.words(pa.array(["Éa b", None, "", "éa—B. b"]))
    words = [bytes(low[s:e]).decode() for s, e in zip(start, end)]
    assert words == ["éa", "b", "éa", "b", "b"] and list(doc) == [0, 0, 3, 3, 3]
    assert code[0] == code[2] and code[1] == code[3] == code[4] != code[0]


def test_shingles_match_sets():
    texts = ["a b c d", "b c d e", "a b", "a b", ""]
    doc, code, *_ = tx.words(pa.array(texts))
    d, s = tx.shingles(doc, code, len(texts), 3)
    got = [set(s[d == i]) for i in range(5)]
    assert len(got[0]) == 2 and len(got[0] & got[1]) == 1 and got[2] == got[3] and len(got[2]) == 1 and not got[4]


# 1


def test_warc_round_trip(spark):
    pages = spark.createDataFrame([(i, f"http://h{i % 7}.example.com/p/{i}", "<p>" + "é" * i + "</p>", "x") for i in range(400)] + [(None, None, None, "x"), (5, "http://h5.example.com/p/5", "<p>ééééé</p>", "x"), (6, "bad url\r\n", "", "x")], "page_id bigint, url string, html string, key string")
    first, again = fresh_path(spark, "w"), fresh_path(spark, "w")
    index = warc.write_warc(pages, first, shard_bytes=20_000, file_bytes=3_000).toPandas()
    warc.write_warc(pages.repartition(7), again, shard_bytes=20_000, file_bytes=3_000)
    back = warc.read_warc(spark, first).toPandas()
    assert len(index) == 403 and index["shard"].nunique() > 3 and back["digest_ok"].all()
    data = back[back["kind"] == "response"]
    j = index.merge(data, on=["file", "offset", "length"])
    assert len(j) == 403 and set(zip(j["uri"], j["payload"])) == {("urn:no-url" if r["url"] is None else r["url"].replace("\r\n", "%0D%0A"), (r["html"] or "").encode()) for r in rows(pages)}
    two = warc.read_warc(spark, again).toPandas()
    key = ["file", "offset", "length", "uri", "payload"]
    assert sorted(map(tuple, back[key].astype(str).values)) == sorted(map(tuple, two[key].astype(str).values))
    for _, g in data.sort_values(["file", "offset"]).groupby(data["file"].str[:11]):
        hosts_ = [re.sub(r"^https?://([^/]+).*", r"\1", u) for u in g["uri"]]
        assert hosts_ == sorted(hosts_, key=lambda h: ",".join(h.split(".")[::-1])) or any("url" in h for h in hosts_)
    per = index.groupby("file")["length"].sum()
    assert (per < 3_000 + index["length"].max()).all()


def test_warc_ranges_are_what_the_running_total_says(spark):
    """Equal bytes per range, computed anew; very long pages, ties and repeated rows; columns named like the operator's own."""
    rng = np.random.default_rng(6)
    sizes = np.minimum(rng.pareto(1.5, 3000) * 300, 8_000).astype(int).tolist()
    data = [(i, f"http://h{i % 50}.example.com/{i * 7919 % 3001}", "x" * n, "k", 1) for i, n in enumerate(sizes)] + [(5, "http://h5.example.com/1", "y" * 100, "k", 1)] * 3
    pages = spark.createDataFrame(data, "page_id bigint, url string, html string, key string, size int")
    index = warc.write_warc(pages, fresh_path(spark, "w"), shard_bytes=100_000, file_bytes=20_000).toPandas()
    per = index.groupby("shard")["raw_bytes"].sum()
    assert len(per) > 5 and per.max() <= 1.3 * per.mean() and index["raw_bytes"].sum() == sum(len(r[2]) for r in data)
    # brute force: keys in order, ranges of equal bytes, a key never divided
    keyed = sorted((warc_key(u, i), len(h), i) for i, u, h, _, _ in data)
    total = sum(n for _, n, _ in keyed)
    shards, before, edge = -(-total // 100_000), 0, {}
    for k, n, _ in keyed:
        edge.setdefault(before * shards // total, k)
        before += n
    cuts = sorted({k for s, k in edge.items() if s})
    want = Counter((sum(k >= c for c in cuts), i) for k, _, i in keyed)
    assert Counter(zip(index["shard"], index["page_id"])) == want
    long = spark.createDataFrame([(1, "http://a.example.com/", "é" * 3_000_000)], "page_id bigint, url string, html string")
    path = fresh_path(spark, "w")
    warc.write_warc(long, path, shard_bytes=1_000_000, file_bytes=1_000)
    back = [r for r in rows(warc.read_warc(spark, path)) if r["kind"] == "response"]
    assert len(back) == 1 and back[0]["digest_ok"] and bytes(back[0]["payload"]).decode() == "é" * 3_000_000


def warc_key(url, page_id):
    host, path = re.match("http://([^/]+)(.*)", url).groups()
    return ",".join(host.split(".")[::-1]) + ")" + path + " " + str(page_id).rjust(20, "0")


def test_warc_commit_is_repeatable_and_empty_is_fine(spark):
    from pyarrow import fs

    path = fresh_path(spark, "w")
    assert warc.write_warc(spark.createDataFrame([], "page_id bigint, url string, html string"), path).count() == 0
    system, root = fs.FileSystem.from_uri(path)
    assert {f.base_name for f in system.get_file_info(fs.FileSelector(root))} >= {"_SUCCESS", "_manifest"}
    assert "warc.gz" not in str(system.get_file_info(fs.FileSelector(root)))
    assert gzip.decompress(warc.member("response", "u", "t", b"x", None, "d")).endswith(b"\r\n\r\nx\r\n\r\n")


# 2


def brute_ctw(texts, depth):
    """Node by node, with dictionaries."""
    count = defaultdict(lambda: [0, 0])
    seen = []
    for t in texts:
        data = bytes(depth) + t.encode()
        for i in range(depth, len(data)):
            for k in range(8):
                prefix, bit = (1 << k) | (data[i] >> (8 - k)), (data[i] >> (7 - k)) & 1
                for d in range(depth + 1):
                    count[(data[i - d : i], prefix)][bit] += 1
    kt = lambda a, b: math.lgamma(a + 0.5) + math.lgamma(b + 0.5) - math.lgamma(a + b + 1) - math.log(math.pi)
    weighted, stay = {}, {}
    for key in sorted(count, key=lambda k: -len(k[0])):
        own = kt(*count[key])
        if len(key[0]) == depth:
            weighted[key], stay[key] = own, 1.0
        else:
            below = sum(weighted[k] for k in weighted if len(k[0]) == len(key[0]) + 1 and k[0][1:] == key[0] and k[1] == key[1])
            weighted[key] = np.logaddexp(own, below) - math.log(2)
            stay[key] = math.exp(own - math.log(2) - weighted[key])
    out = []
    for t in texts:
        data, bits = bytes(depth) + t.encode(), 0.0
        for i in range(depth, len(data)):
            for k in range(8):
                prefix, bit = (1 << k) | (data[i] >> (8 - k)), (data[i] >> (7 - k)) & 1
                q = None
                for d in range(depth, -1, -1):
                    key = (data[i - d : i], prefix)
                    p = (count[key][bit] + 0.5) / (sum(count[key]) + 1)
                    q = p if q is None else stay[key] * p + (1 - stay[key]) * q
                bits -= math.log2(q)
        out.append(bits)
    return out


def test_ctw_equals_brute_force(spark):
    texts = ["abracadabra", "abrakadabra é", "zzzzzz", "ab"]
    df = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id bigint, text string")
    for depth in (2, 3, 1):
        got = {r["doc_id"]: r for r in rows(ctw.code_lengths(df, depth=depth, chunk_chars=12, group_grams=5))}
        for i, want in enumerate(brute_ctw(texts, depth)):
            assert got[i]["bits"] == pytest.approx(want, rel=1e-4) and got[i]["n_bytes"] == len(texts[i].encode())


def test_ctw_odd_cases(spark):
    got = rows(ctw.code_lengths(odd(spark)))
    assert len(got) == 9
    assert {r["bits"] for r in got if r["doc_id"] in (2, 3)} == {None}
    assert len({r["bits"] for r in got if r["doc_id"] == 1}) == 1
    assert ctw.code_lengths(empty(spark)).count() == 0
    x = np.array([0.5, 1.5, 7.0, 1e6])
    assert np.allclose(ctw.log_gamma(x), [math.lgamma(v) for v in x], atol=1e-9)


# 3


def test_imatch_equals_brute_force(spark):
    df = odd(spark, [(10, "the cat and a zebra", "en", "a", 9, "x", 1), (11, "zebra the cat and a", "en", "a", 9, "x", 1)])
    docs = rows(df)
    terms = [{t for t in re.split("[^a-z0-9ß-öø-ÿà]+", (d["text"] or "").lower()) if t} for d in docs]
    n = Counter(t for s in terms for t in s)
    low, high = 0.1, 0.5
    lex = {t for t, c in n.items() if math.ceil(len(docs) * low) <= c <= math.floor(len(docs) * high) and c >= 2}
    got = sorted(rows(imatch.fingerprints(df, low, high, 2)), key=str)
    want = []
    for d, s in zip(docs, terms):
        use = sorted(s & lex)
        h = lambda ts: hashlib.md5(" ".join(ts).encode()).hexdigest() if ts else None
        sub = [[t for t in use if hashlib.md5(f"{k}:{t}".encode()).hexdigest()[0] < "a"] for k in range(2)]
        want.append({"doc_id": d["doc_id"], "n_terms": len(use), "full_hash": h(use), "hash_0": h(sub[0]), "hash_1": h(sub[1])})
    assert got == sorted(want, key=str)
    by = {r["doc_id"]: r["full_hash"] for r in got}
    assert by[10] == by[11] is not None and by[2] is None
    assert imatch.fingerprints(empty(spark)).count() == 0


# 4


def test_language_held_out_accuracy(spark):
    docs = table(spark, "/root/testdata/sf0.01", "documents")
    model = language.fit(docs.where("doc_id % 2 = 0"))
    got = language.identify(docs.where("doc_id % 2 = 1"), model, keep=["doc_id", "lang"]).toPandas()
    known = got[~got["li_rejected"]]
    assert (known["li_pred"] == known["lang"]).mean() > 0.97 and len(known) > 0.98 * len(got)


def test_language_mixture_and_brute_force(spark):
    docs = table(spark, "/root/testdata/sf0.01", "documents")
    model = language.fit(docs)
    longest = {r["lang"]: r["text"] for r in rows(docs.where("n_chars between 2000 and 4000").groupBy("lang").agg(F.min("text").alias("text")))}
    mixed = pa.array([longest["en"][:1500] + " " + longest["es"][:1500], longest["de"], None, "", "12345 %%% ..."])
    got = language.infer(mixed, *model)
    assert set(got["li_langs"][0].split(",")) == {"en", "es"} and 0.3 < got["li_share"][0] < 0.7 and got["li_langs"][1] == "de"
    assert got["li_pred"][2] is None and got["li_rejected"][2] and got["li_rejected"][3]
    # brute force: every subset of languages, fitted word by word
    names, table_ = model
    code, at, doc = language.trigrams(mixed.slice(0, 1), table_.shape[1])
    words = np.split(code, at[1:])
    like = np.array([[np.exp(table_[i][w].sum() - max(*(table_[j][w].sum() for j in range(len(names))), -np.log(table_.shape[1]) * len(w))) for i in range(len(names))] + [np.exp(-np.log(table_.shape[1]) * len(w) - max(*(table_[j][w].sum() for j in range(len(names))), -np.log(table_.shape[1]) * len(w)))] for w in words])
    best = None
    for k in range(1, len(names) + 1):
        for s in itertools.combinations(range(len(names)), k):
            use = like[:, [*s, len(names)]]
            p = np.full(k + 1, 1 / (k + 1))
            for _ in range(60):
                z = use * p
                p = (z / (z.sum(axis=1, keepdims=True) + 1e-300)).mean(axis=0)
            v = np.log(use @ p + 1e-300).sum() - k * np.log1p(len(words))
            best = max(best or (v, s), (v, s))
    assert {names[i] for i in best[1]} == set(got["li_langs"][0].split(","))


def test_language_of_a_document_is_the_same_alone_and_in_a_batch(spark):
    docs = table(spark, "/root/testdata/sf0.01", "documents").select("doc_id", "text", "lang")
    model = language.fit(docs)
    texts = docs.orderBy("doc_id").toArrow().column("text").combine_chunks()
    whole = language.infer(texts, *model)
    for i in range(0, len(texts), 3):
        alone = language.infer(texts.slice(i, 1), *model)
        assert all(alone[c][0] == whole[c][i] for c in whole), i
    # no fitted set is better than the bound says, and the bound is no looser than a longer search needs
    rng = np.random.default_rng(0)
    like = rng.random((4, 300))
    size = np.array([100, 5, 195])
    first = np.array([0, 100, 105])
    _, found, lack = language.mixture(like, first, size, np.ones((4, 3)), 1e-3)
    _, best, rest = language.mixture(like, first, size, np.ones((4, 3)), 1e-9)
    assert (best >= found - 1e-9).all() and (best <= found + lack + 1e-9).all() and (rest < 1e-3).all()


def test_language_odd_cases(spark):
    df = odd(spark)
    model = language.fit(df)
    got = rows(language.identify(df, model))
    assert len(got) == 9 and sum(r["li_rejected"] for r in got) >= 3
    kept = language.identify(df, model, keep=df.columns, accepted_only=True)
    assert kept.columns == df.columns and {r["doc_id"] for r in rows(kept)} >= {1, 4, None}
    none = language.fit(empty(spark))
    assert none[0] == [] and all(r["li_rejected"] for r in rows(language.identify(df, none)))
    assert language.identify(empty(spark), model).count() == 0


# 5


def brute_mix(docs, weights, default, percents):
    h = lambda d: int(hashlib.md5(("null" if d is None else str(d)).encode()).hexdigest()[:15], 16)
    by = defaultdict(list)
    for d in docs:
        by[d["source"] or ""].append((h(d["doc_id"]), len((d["text"] or "").split()), d["doc_id"]))
    have = {s: sum(n for _, n, _ in v) for s, v in by.items()}
    w = {s: weights.get(s, default) for s in by}
    unit = min((have[s] * 1_000_000 // w[s] for s in by if w[s] > 0 and have[s] > 0), default=0)
    out = Counter()
    for s, v in by.items():
        for x, n, d in v:
            upto = sum(m for y, m, _ in v if y <= x)
            ok = [i for i, p in enumerate(percents, 1) if upto <= unit * w[s] * p // 100_000_000]
            if ok:
                out[(d, s, n, ok[0])] += 1
    return out


@pytest.mark.parametrize("weights", [{}, {"a": 3}, {"b": 0}])
def test_mixing_equals_brute_force(spark, weights):
    more = [(100 + i, "w " * (i % 13), "en", "abc"[i % 3], 1, "x", 1) for i in range(300)] + [(100, "w w w", "en", "a", 1, "x", 1)]
    df = odd(spark, more)
    got = Counter((r["doc_id"], r["source"], r["tokens"], r["level"]) for r in rows(mixing.mix_levels(df, weights, 1, [20, 60, 100])))
    assert got == brute_mix(rows(df), weights, 1, [20, 60, 100])
    kept = mixing.mix_documents(df, weights)
    assert kept.columns == df.columns and kept.count() == sum(got.values())
    assert mixing.mix_levels(empty(spark)).count() == 0 and mixing.mix_documents(empty(spark)).count() == 0


def test_mixing_without_a_source_of_weight_and_tokens(spark):
    """Weight 0 for the only source that has tokens: nothing with tokens is taken; columns may have any names."""
    data = [(i, "a", "w w w", 1, 2) for i in range(20)] + [(50, "b", None, 1, 2), (51, None, "", 1, 2)]
    df = spark.createDataFrame(data, "doc_id bigint, source string, text string, mix_cut int, threshold int")
    got = rows(mixing.mix_levels(df, {"a": 0}, 1, [50, 100]))
    assert Counter((r["doc_id"], r["source"], r["tokens"], r["level"]) for r in got) == brute_mix(rows(df), {"a": 0}, 1, [50, 100])
    kept = mixing.mix_documents(df, {"a": 0})
    assert kept.columns == df.columns and {r["doc_id"] for r in rows(kept)} == {50, 51}


# 6


def test_hosts_shrink_and_filter(spark):
    urls = [f"http://bad.site{i % 2}.example.com/x/{i}" for i in range(40)] + [f"https://User@Good.Host.co.uk:80/{i}" for i in range(40)] + [None, "", "no url", "http://lone.org"]
    pages = spark.createDataFrame([(i, u, "x") for i, u in enumerate(urls)], "page_id bigint, url string, mean string")
    labels = spark.createDataFrame([(i, 1 if i < 40 else 0) for i in range(70)] + [(None, 1), (3, None)], "page_id bigint, bad int")
    got = {r["page_id"]: r for r in rows(hosts.filter_urls(pages, labels, ("co.uk", "example.com")))}
    assert len(got) == len(urls) and not got[0]["kept"] and got[41]["kept"] and got[0]["domain"] == "site0.example.com" and got[41]["domain"] == "host.co.uk" and got[41]["host"] == "good.host.co.uk"
    assert got[80]["kept"] and got[80]["mean"] is None and got[83]["mean"] is not None and got[83]["n"] == 0
    assert got[0]["n"] == 20 and 0 < got[41]["mean"] < 0.1 < 0.9 < got[0]["mean"] < 1
    nothing = hosts.filter_urls(pages, labels.where("false"))
    assert nothing.where("not kept").count() == 0 and hosts.filter_urls(pages.where("false"), labels).count() == 0


def test_hosts_count_repeated_rows_once_each(spark):
    """A row that stands r times counts r times, not r x r; long URLs, nulls and columns with the operator's own names do no harm."""
    page = "page_id bigint, url string, n string, host string, key_ string"
    one = (1, "http://h.example.org/1", "x", "y", "z")
    long = (2, "http://" + "a" * 50_000 + ".example.org/" + "b" * 200_000, "x", "y", "z")
    pages = spark.createDataFrame([one] * 4 + [long, (None, None, None, None, None)], page)
    got = rows(hosts.filter_urls(pages, spark.createDataFrame([(1, 1)], "page_id bigint, bad int")))
    assert [r["n"] for r in got if r["page_id"] == 1] == [4] * 4 and len(got) == 6
    assert [(len(r["host"]), r["n"]) for r in got if r["page_id"] == 2] == [(50_012, 0)]
    twice = rows(hosts.filter_urls(pages, spark.createDataFrame([(1, 1), (1, 0)], "page_id bigint, bad int")))
    assert [r["n"] for r in twice if r["page_id"] == 1] == [8] * 4


# 7


def test_a_tiny_source_does_not_set_the_budgets(spark):
    data = [(i, "hot", "w " * 50) for i in range(1800)] + [(9000 + i, "warm", "w " * 50) for i in range(200)] + [(9900, None, "w"), (9901, "void", None)]
    df = spark.createDataFrame(data, "doc_id bigint, source string, text string")
    kept = Counter(r["source"] for r in rows(mixing.mix_documents(df, temperature=0.9)))
    have = {"hot": 90_000, "warm": 10_000, None: 1, "void": 0}
    target = sum(have.values()) * 90_000**0.9 / sum(max(1, h**0.9) for h in have.values() if h)
    assert kept["warm"] == 200 and kept[None] == kept["void"] == 1
    assert target - 100 < kept["hot"] * 50 <= target + 1 < 90_000
    levels = Counter((r["source"], r["level"]) for r in rows(mixing.mix_levels(df, percents=[50, 100], temperature=0.9)))
    assert 98 <= levels["warm", 1] <= 100 and levels["warm", 1] + levels["warm", 2] == 200


def sets(text, k=3):
    w = re.findall(r"[^\W_]+", text.lower())
    return Counter(tuple(w[i : i + k]) for i in range(len(w) - k + 1)) if len(w) >= k else Counter([tuple(w)] if w else [])


def brute_jp(a, b):
    return sum(1 / sum(max(a[e] / a[d], b[e] / b[d]) for e in a | b) for d in a & b)


def test_probability_jaccard_and_estimate():
    rng = np.random.default_rng(1)
    texts = [" ".join(rng.choice([f"w{i}" for i in range(30)], 60)) for _ in range(4)]
    texts[1] = texts[0][: len(texts[0]) // 2] + texts[1][len(texts[1]) // 2 :]
    d, item, w = neardup.weighted(pa.array(texts), 1)
    who = neardup.signatures(d, item, w, 4, 4096)
    for i, j in itertools.combinations(range(4), 2):
        want = brute_jp(sets(texts[i], 1), sets(texts[j], 1))
        assert neardup.probability_jaccard(item[d == i], w[d == i], item[d == j], w[d == j]) == pytest.approx(want, abs=1e-9)
        assert (who[i] == who[j]).mean() == pytest.approx(want, abs=0.04)


def test_registers_that_differ_are_counted_from_four_bits_each(spark):
    rng = np.random.default_rng(4)
    who = rng.integers(0, 1 << 60, (40, 72), dtype=np.uint64)
    for i in range(1, 40):
        who[i, : 2 * i - 6 if i > 3 else 0] = who[0, : 2 * i - 6 if i > 3 else 0]
    t = pa.table({"i": list(range(40)), "sig": neardup.packed(who)})
    df = spark.createDataFrame(t)
    got = {r["i"]: r["d"] for r in rows(df.join(df.where("i = 0").select(F.col("sig").alias("other")), how="cross").select("i", neardup.differing("sig", "other", 5).alias("d")))}
    nib = tx.mix(who + np.uint64(0x2545F4914F6CDD1D)) >> np.uint64(60)
    assert got == {i: int((nib[i] != nib[0]).sum()) for i in range(40)}
    assert neardup.most_differing(72, 0.5) == 50


def test_signature_is_independent_of_batch():
    texts = ["a b c d e f g", "x y", "a b c d e f q r s"]
    whole = neardup.signatures(*neardup.weighted(pa.array(texts), 3), 3, 72)
    for i, t in enumerate(texts):
        assert (neardup.signatures(*neardup.weighted(pa.array([t]), 3), 1, 72)[0] == whole[i]).all()


def test_near_duplicates_against_brute_force(spark):
    docs = table(spark, "/root/testdata/sf0.001", "documents")
    data = {r["doc_id"]: r["text"] for r in rows(docs)}
    s = {i: sets(t) for i, t in data.items()}
    pairs = [(a, b) for a, b in itertools.combinations(sorted(s), 2) if s[a] and s[b] and s[a].keys() & s[b].keys() and brute_jp(s[a], s[b]) >= 0.5]
    group = {r["doc_id"]: r["group_id"] for r in rows(neardup.near_duplicate_groups(docs))}
    assert len(group) == len(data) and len(pairs) > 5
    assert sum(group[a] == group[b] for a, b in pairs) >= 0.9 * len(pairs)
    root = {i: i for i in data}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in pairs:
        root[max(find(a), find(b))] = min(find(a), find(b))
    for i, g in group.items():  # nothing is joined that brute force keeps apart
        assert find(i) == find(g)


def test_near_duplicates_through_a_member_that_passed(spark):
    """1 and 2 pass, 1 and 3 don't, 2 and 3 do, all in one bucket and no other; then families whose original has the largest id."""
    def edited(words, share, tag):
        return " ".join(f"{tag}{i}" if i % share == hash_of(tag) % share else w for i, w in enumerate(words))

    hash_of = lambda t: int(hashlib.md5(t.encode()).hexdigest()[:8], 16)
    hub = [f"w{i}" for i in range(400)]
    texts = {1: edited(hub, 11, "ax"), 2: " ".join(hub), 3: edited(hub, 11, "bx")}
    s = {i: sets(t) for i, t in texts.items()}
    assert brute_jp(s[1], s[2]) >= 0.5 and brute_jp(s[2], s[3]) >= 0.5 and brute_jp(s[1], s[3]) < 0.5
    docs = spark.createDataFrame([(i, t) for i, t in texts.items()], "doc_id bigint, text string")
    light = spark.createDataFrame([(i, [7]) for i in texts], "doc_id bigint, bands array<bigint>")
    assert {(r["a"], r["b"]) for r in rows(neardup.near_pairs(light, docs, 3, 0.5, 0))} == {(1, 2), (2, 3)}
    data = []
    for f in range(30):
        words = [f"f{f}w{i}" for i in range(400)]
        data += [(f * 10 + c, edited(words, 11, f"f{f}c{c}x")) for c in range(6)] + [(f * 10 + 9, " ".join(words))]
    group = {r["doc_id"]: r["group_id"] for r in rows(neardup.near_duplicate_groups(spark.createDataFrame(data, "doc_id bigint, text string")))}
    assert all(g // 10 == i // 10 for i, g in group.items()) and sum(g == group[i // 10 * 10 + 9] for i, g in group.items()) >= 0.97 * len(group)


def test_near_duplicates_odd_cases(spark):
    base = " ".join(f"tok{i}" for i in range(200))
    other = base.replace("tok7 ", "new7 ")
    passage = " ".join(f"share{i}" for i in range(60))
    clean = [(200 + i, passage + " " + " ".join(f"u{i}x{j}" for j in range(300)), "en", "a", 1, "x", 1) for i in range(30)]
    more = [(20, base, "en", "a", 1, "x", 1), (21, other, "en", "a", 1, "x", 1), (22, base, "en", "a", 1, "x", 1), (23, "", "en", "a", 0, "x", 1), *clean]
    df = odd(spark, more)
    got = rows(neardup.near_duplicate_groups(df))
    by = {r["doc_id"]: r for r in got}
    assert by[20]["group_id"] == by[21]["group_id"] == by[22]["group_id"] == 20 and by[20]["copies"] == 2 and by[20]["kept"] and not by[21]["kept"]
    assert by[23]["group_id"] == by[3]["group_id"] == 3 and by[2]["group_id"] == 2
    assert all(by[200 + i]["kept"] for i in range(30)) and by[None]["kept"] and by[None]["group_id"] is None
    kept = rows(neardup.drop_near_duplicates(df))
    ids = Counter(r["doc_id"] for r in kept)
    assert ids[1] == 1 and ids[20] == 1 and 21 not in ids and 22 not in ids and ids[None] == 1 and set(kept[0]) == set(df.columns)
    assert neardup.near_duplicate_groups(empty(spark)).count() == 0 and neardup.drop_near_duplicates(empty(spark)).count() == 0
    shuffled = neardup.near_duplicate_groups(df, small=0)  # the join without broadcast
    assert sorted(map(str, rows(shuffled))) == sorted(map(str, got))


def test_near_duplicates_of_an_id_with_two_texts(spark):
    """Digest, bands, verified text and kept row of an id come from one row."""
    a, b = " ".join(f"left{i}" for i in range(120)), " ".join(f"right{i}" for i in range(120))
    for first, second in ((a, b), (b, a)):
        low, high = sorted((first, second), key=lambda t: hashlib.md5(t.encode()).hexdigest())
        data = [(1, first, 0), (1, second, 0), (1, None, 0), (2, low.replace("7 ", "7x ", 1), 0), (3, high.replace("7 ", "7x ", 1), 0)]
        df = spark.createDataFrame(data, "doc_id bigint, text string, nd_rank int")
        got = {r["doc_id"]: r["group_id"] for r in rows(neardup.near_duplicate_groups(df))}
        assert got == {1: 1, 2: 1, 3: 3}
        kept = rows(neardup.drop_near_duplicates(df))
        assert sorted((r["doc_id"], r["text"]) for r in kept) == [(1, low), (3, data[-1][1])] and set(kept[0]) == set(df.columns)


# 8


def test_top_k_equals_brute_force(spark):
    rng = np.random.default_rng(3)
    x = rng.normal(size=(300, 8))
    x[50:60], x[7] = x[5], 0
    df = spark.createDataFrame([(i, v.tolist(), "x") for i, v in enumerate(x)] + [(None, [1.0] * 8, "x"), (900, None, "x"), (901, [1.0], "x"), (902, [float("nan")] * 8, "x"), (3, x[3].tolist(), "x")], "vec_id bigint, embedding array<double>, rank string")
    got = defaultdict(list)
    for r in rows(topk.top_k(df, k=5, block_rows=64, group=16).orderBy("vec_id", "rank")):
        got[r["vec_id"]].append(r["neighbour_id"])
    s = np.round(x @ x.T, 9)
    for i in range(300):
        assert got[i] == sorted((j for j in range(300) if j != i), key=lambda j: (-s[i, j], j))[:5], i
    assert set(got) == set(range(300))
    few = rows(topk.top_k(df.where("vec_id < 3"), k=5))
    assert Counter(r["vec_id"] for r in few) == {0: 2, 1: 2, 2: 2} and topk.top_k(df.where("false")).count() == 0


def test_top_k_of_some_queries_among_all_rows(spark):
    """The rows asked for get what they get when all ask; the query asks for ids divisible by 50."""
    rng = np.random.default_rng(11)
    x = rng.integers(-3, 4, size=(400, 6)).astype(float)  # many ties
    ids = [i - 200 for i in range(400)]
    data = [(i, v.tolist()) for i, v in zip(ids, x)] + [(None, [1.0] * 6), (1000, None), (1050, [1.0]), (-50, x[150].tolist())]
    df = spark.createDataFrame(data, "vec_id bigint, embedding array<double>")
    got = defaultdict(list)
    some = topk.top_k(df, k=5, block_rows=64, group=4, asked=F.col("vec_id") % 50 == 0, ask_rows=3)
    for r in rows(some.orderBy("vec_id", "rank")):
        got[r["vec_id"]].append((r["rank"], r["neighbour_id"], r["score"]))
    s = x @ x.T
    assert set(got) == {i for i in ids if i % 50 == 0} and len(got) == 8
    for i in got:
        best = sorted((j for j in ids if j != i), key=lambda j: (-s[i + 200, j + 200], j))[:5]
        assert got[i] == [(n, j, s[i + 200, j + 200]) for n, j in enumerate(best, 1)], i
    every = {tuple(r) for r in topk.top_k(df, k=5, block_rows=64).where("vec_id % 50 = 0").collect()}
    assert every == {(i, *r) for i, found in got.items() for r in found}
    assert topk.top_k(df, asked=F.lit(False)).count() == 0 and topk.top_k(df, asked=F.lit(None).cast("boolean")).count() == 0
    assert topk.top_k(df.where("false"), asked=F.col("vec_id") % 50 == 0).count() == 0


def test_top_k_query_asks_for_every_fiftieth_id(spark, sf):
    got = rows(queries.op8_exact_top_k(spark, sf))
    assert Counter(r["vec_id"] for r in got) == {i: 10 for i in range(0, 500, 50)} and any(r["neighbour_id"] % 50 for r in got)


def test_top_k_of_huge_numbers_and_columns_of_any_name(spark):
    """Finite vectors are never dropped; scores that overflow rank as infinities."""
    data = [(1, [1e31, 0.0]), (2, [2.0, 0.0]), (3, [0.0, 1.0]), (4, [1e300, 1e300]), (5, [1e300, -1e300]), (6, [float("inf"), 0.0])]
    df = spark.createDataFrame([(i, v, 0, 0.0, 0) for i, v in data], "vec_id bigint, embedding array<double>, lead int, value double, score int")
    got = defaultdict(list)
    for r in rows(topk.top_k(df, k=4, block_rows=2).orderBy("vec_id", "rank")):
        got[r["vec_id"]].append((r["neighbour_id"], r["score"]))
    assert set(got) == {1, 2, 3, 4, 5} and all(len(v) == 4 for v in got.values())
    assert got[2][0] == (4, 2e300) and got[2][1] == (5, 2e300) and got[2][2] == (1, 2e31) and got[4][0] == (1, float("inf")) and {j for j, _ in got[4]} == {1, 2, 3, 5}


def test_top_k_skips_blocks_that_cannot_matter(spark):
    """Rows in well separated directions: the bound of a block keeps it shut."""
    opened = []
    rng = np.random.default_rng(8)
    x = np.vstack([np.eye(8)[i] * 10 + rng.random((50, 8)) for i in range(8)])
    low, high = (np.array([f(x[i * 50 : i * 50 + 50], axis=0) for i in range(8)]) for f in (np.min, np.max))
    bound = topk.box_bounds(x, low, high)
    assert (bound + 1e-6 >= np.stack([(x @ x[i * 50 : i * 50 + 50].T).max(axis=1) for i in range(8)], axis=1)).all()
    for i in range(8):
        kth = np.sort(x[i * 50 : i * 50 + 50] @ x[i * 50 : i * 50 + 50].T, axis=1)[:, -6]
        opened.append((bound[i * 50 : i * 50 + 50] >= kth[:, None]).any(axis=0).sum())
    assert opened == [1] * 8


def test_threshold_stops_early():
    rng = np.random.default_rng(5)
    x = rng.normal(size=(4000, 4)) * 0.01
    x[17] = [1, 1, 1, 1]
    x[18] = [0.9, 1, 1, 1]
    top, who, scored = topk.Lists(np.arange(4000), x).search(np.array([-1]), np.ones((1, 4)), 2)
    assert list(who[0]) == [17, 18] and scored < 1000


# 9


def test_packing_properties(spark):
    more = [(100 + i, "w " * n, "en", "a", n, "x", 1) for i, n in enumerate(np.random.default_rng(2).integers(0, 150, 400).tolist())]
    df = odd(spark, more)
    got = packing.pack(df, window=64, open_windows=4, tokens_per_partition=5000).toPandas()
    size = Counter()
    for r in rows(df):
        size[r["doc_id"]] += len((r["text"] or "").split())
    placed = got[got["window_id"].notna()]
    assert {k: v for k, v in size.items() if v} == {(None if k != k else k): v for k, v in placed.groupby("doc_id", dropna=False)["tokens"].sum().items()}
    for _, w in placed.groupby("window_id"):
        w = w.sort_values("start")
        end = 0
        for s, n in zip(w["start"], w["tokens"]):
            assert s == end
            end = s + n
        assert end == w["used"].iloc[0] <= 64
    assert (got["window_id"].isna() == (got["tokens"] == 0)).all() and got["window_id"].isna().sum() == sum(1 for r in rows(df) if not (r["text"] or "").split())
    fill = placed["tokens"].sum() / (64 * placed["window_id"].nunique())
    assert fill > 0.9 and packing.pack(empty(spark)).count() == 0
    again = packing.pack(df.repartition(9), window=64, open_windows=4, tokens_per_partition=5000).toPandas()
    assert sorted(map(str, again.values.tolist())) == sorted(map(str, got.values.tolist()))


def test_best_fit_against_brute_force():
    sizes = list(np.random.default_rng(4).integers(1, 64, 500))
    got = packing.pack_partition(None, sizes, 64, 5)
    live, used, nxt, want = [], {}, 0, []
    for n in sizes:
        fit = sorted((w for w in live if 64 - used[w] >= n), key=lambda w: (64 - used[w], w))
        if fit:
            w = fit[0]
        else:
            if len(live) == 5:
                live.remove(min(live, key=lambda w: (64 - used[w], w)))
            w, nxt = nxt, nxt + 1
            live.append(w)
            used[w] = 0
        want.append((w, used[w]))
        used[w] += n
        if used[w] == 64:
            live.remove(w)
    assert list(zip(got["w"], got["start"])) == want


# 10


def test_hilbert_is_a_continuous_walk(spark):
    for n, bits in ((2, 4), (3, 3)):
        cells = spark.createDataFrame([tuple(p) for p in itertools.product(range(1 << bits), repeat=n)], ", ".join(f"c{i} int" for i in range(n)))
        got = rows(cells.withColumn("h", hilbert.hilbert_index([F.col(f"c{i}") for i in range(n)], bits)))
        got.sort(key=lambda r: r["h"])
        assert [r["h"] for r in got] == list(range(1 << (bits * n)))
        for a, b in zip(got, got[1:]):
            assert sum(abs(a[f"c{i}"] - b[f"c{i}"]) for i in range(n)) == 1


def test_hilbert_shards_and_pruning(spark):
    more = [(100 + i, "t", ["en", "de"][i % 2], f"s{i % 9}", (i * 37) % 5000, "x", 1) for i in range(600)]
    df = odd(spark, more)
    got = hilbert.assign(df, target=20_000).toPandas()
    assert len(got) == df.count() and got["doc_id"].isna().sum() == 1
    sizes = got.groupby("shard")["n_chars"].sum()
    assert len(sizes) > 20 and sizes.drop(sizes.idxmax()).max() < 60_000
    order = got.groupby("shard")["cell"].agg(["min", "max"]).sort_index()
    assert (order["min"].values[1:] >= order["max"].values[:-1]).all()
    path = fresh_path(spark, "hilbert")
    cell, shard = hilbert.write(df, path, target=20_000)
    back = spark.read.parquet(path)
    stats = hilbert.extents(back, shard).toPandas()
    assert stats["rows"].sum() == df.count()
    one = stats[(stats["min_source"] <= "s3") & (stats["max_source"] >= "s3") & (stats["min_lang"] <= "en") & (stats["max_lang"] >= "en")]
    assert len(one) < 0.6 * len(stats)
    # a shard is one file, in order of the curve
    files = back.select("*", F.input_file_name().alias("f")).toPandas()
    assert files.groupby(shard)["f"].nunique().max() == 1 and files.groupby("f")[shard].nunique().max() == 1
    assert all(g[cell].is_monotonic_increasing for _, g in files.groupby("f"))
    assert hilbert.assign(empty(spark)).count() == 0
    assert hilbert.shards(empty(spark), fresh_path(spark, "hilbert")).count() == 0


def test_hilbert_carries_columns_of_any_name(spark):
    """Nulls, long texts, repeated rows, negative sizes, and columns named like the operator's own, which come back as they were."""
    names = ["hb_0", "hb_1", "hb_hash", "HB_SIZE", "hilbert_cell", "hilbert_shard", "v", "one", "before", "shard"]
    data = [(1, "x" * 300_000, "en", "a", 300_000), (2, None, None, None, None), (None, "", "de", "b", -5), (1, "x" * 300_000, "en", "a", 300_000), (3, "t", "de", "a", 2_000)]
    df = spark.createDataFrame([r + tuple(range(7, 17)) for r in data], "doc_id bigint, text string, lang string, source string, n_chars bigint, " + ", ".join(f"{n} bigint" for n in names))
    path = fresh_path(spark, "hilbert")
    cell, shard = hilbert.write(df, path, target=100_000)
    assert (cell, shard) == ("hilbert_cell_", "hilbert_shard_")
    back = rows(spark.read.parquet(path).select(*df.columns))
    assert sorted(map(str, back)) == sorted(map(str, rows(df)))
    got = rows(hilbert.shards(df, fresh_path(spark, "hilbert"), target=100_000))
    assert len(got) == 5 and len({r["shard"] for r in got if r["doc_id"] == 1}) == 1 and not next(r["skipped"] for r in got if r["doc_id"] == 3)
