"""Operators of the llm subpackage against brute force, and on awkward inputs."""

import random
from collections import Counter
from itertools import combinations

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from caregraph.llm import audio, chat_format, common, decontaminate, language_id, line_dedup, mixing, quality, simhash, substring_dedup, url_filter

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def docs(spark, *texts, schema=DOCS):
    return spark.createDataFrame([(k, t, "en", f"s{k % 2}", len(t or "")) for k, t in enumerate(texts)], schema)


@pytest.fixture(scope="module")
def words():
    return _words(5)


def _words(seed):
    r = random.Random(seed)
    return lambda n: " ".join("".join(r.choice("abcdefgh") for _ in range(r.randint(3, 7))) for _ in range(n))


@pytest.fixture(scope="module")
def table(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet").cache()


# components


def test_components(spark):
    r = random.Random(1)
    e = [(r.randint(0, 300), r.randint(0, 300)) for _ in range(180)] + [(k, k + 1) for k in range(400, 460)]
    up = {}

    def find(x):
        while up.setdefault(x, x) != x:
            x = up[x]
        return x

    for a, b in e:
        x, y = find(a), find(b)
        up[max(x, y)] = min(x, y)
    want = {n: find(n) for a, b in e if a != b for n in (a, b)}
    got = {x["node"]: x["root"] for x in common.components(spark.createDataFrame(e, "a long, b long")).collect()}
    assert got == want
    assert common.components(spark.createDataFrame([], "a long, b long")).count() == 0


# 1 SimHash


def test_position_groups_cover():
    for shared in (4, 5, 6):
        g = simhash.position_groups(8, shared)
        assert all(any(set(t) <= set(c) for t in g) for c in combinations(range(8), shared))
    assert len(simhash.position_groups(8, 4)) == 20


def test_simhash_against_bruteforce(spark, table):
    rows = table.select("doc_id", "text").collect()
    fp = {r["doc_id"]: simhash.fingerprint(r["text"], 4) & (2**64 - 1) for r in rows}
    ids = sorted(fp)
    bits = np.array([fp[i] for i in ids], np.uint64)
    root = {i: i for i in ids}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for k, i in enumerate(ids):
        for j in np.nonzero(np.bitwise_count(bits ^ bits[k]) <= 4)[0]:
            x, y = find(i), find(ids[j])
            root[max(x, y)] = min(x, y)
    got = {r["doc_id"]: (r["fp"] & (2**64 - 1), r["component_id"]) for r in simhash.near_components(table).collect()}
    assert got == {i: (fp[i], find(i)) for i in ids}


def test_simhash_awkward(spark, words):
    t = words(80)
    d = docs(spark, t, t, None, "", "two words", t.upper()).unionByName(spark.createDataFrame([(None, t, None, None, None), (3, "", "x", "y", 0)], DOCS)).withColumn("component_id", F.lit("clash"))
    got = Counter((r["doc_id"], r["component_id"]) for r in simhash.near_components(d).collect())
    assert got == Counter({(0, 0): 1, (1, 0): 1, (5, 0): 1, (None, 0): 1, (2, 2): 1, (3, 2): 2, (4, 4): 1})
    assert simhash.near_components(d.limit(0)).count() == 0


def test_near_stage_keeps_one_of_a_group(spark, sf, words):
    base = words(200)
    edited = base.split()
    edited[20], edited[120] = "zzz", "qqq"
    other = words(200)
    d = docs(spark, base, " ".join(edited), other, base)
    assert sorted(r["doc_id"] for r in simhash.stage(spark, d, sf).collect()) == [0, 2]
    assert simhash.stage(spark, d, sf).columns == d.columns


# 2 mixing


def test_mixing_weights_and_budget(spark):
    rows = [(k, "w " * 10, "en", "big" if k % 10 else "small", 20) for k in range(2000)]
    d = spark.createDataFrame(rows, DOCS)
    m = mixing.mix(d, entropy=0.9, block_tokens=500).groupBy("source").agg(F.sum("__cg_n").alias("n"), F.countDistinct("doc_id").alias("ids"), F.max("epoch").alias("e")).collect()
    n = {r["source"]: r["n"] for r in m}
    p = np.array([n["big"], n["small"]]) / sum(n.values())
    assert -(p * np.log(p)).sum() / np.log(2) == pytest.approx(0.9, abs=0.01)
    assert 20000 - 20 <= sum(n.values()) <= 20000
    e = {r["source"]: r["e"] for r in m}
    assert e["small"] >= 2 and e["big"] == 0
    limited = mixing.mix(d, entropy=1.0, repeats=2.0, block_tokens=500).where("source = 'small'").groupBy("doc_id").count().agg(F.max("count").alias("m")).first()["m"]
    assert limited <= 2


def test_mixing_awkward(spark):
    d = docs(spark, "a b c", None, "", "a b c").withColumn("source", F.when(F.col("doc_id") == 1, None).otherwise(F.col("source"))).withColumn("epoch", F.lit("clash"))
    got = mixing.mix(d)
    assert {r["doc_id"] for r in got.collect()} >= {0, 3} and dict(got.dtypes)["epoch"] == "bigint"
    assert mixing.mix(d.limit(0)).count() == 0


# 3 quality


def test_quality_held_out(spark):
    sf = "/root/testdata/sf0.01"
    q = quality.query(spark, sf).join(spark.read.parquet(f"{sf}/labels.parquet"), "doc_id").where("held_out")
    assert q.where("predicted = quality").count() / q.count() > 0.95


def test_rules_column_equals_numpy(spark, table):
    named = quality.statistics(F.col("text"))
    x = np.array([tuple(r) for r in table.select(*(c.cast("double").alias(k) for k, c in named.items())).collect()])
    y = (x[:, 1] > np.median(x[:, 1])).astype(float)
    m = quality.fit(x, y, list(named))
    z = m.bias + sum(w * r.on(list(named), x) for r, w in zip(m.rules, m.weights, strict=True))
    got = np.array([r["score"] for r in quality.score(table, m).select("score").collect()])
    assert np.allclose(np.sort(got), np.sort(1 / (1 + np.exp(-z)))) and len(m.rules) > 0


def test_quality_awkward(spark):
    m = quality.fit(np.empty((0, 2)), np.empty(0), ["a", "b"])
    d = docs(spark, None, "", "x" * 100_000).withColumn("score", F.lit("clash"))
    got = quality.score(d, m).collect()
    assert [r["score"] for r in got] == [0.5] * 3 and quality.score(d.limit(0), m).count() == 0
    assert quality.train(spark.createDataFrame([("a", 1), ("b", None)], "text string, quality int")).rules == ()


# 4 substring dedup


def test_passages(spark, words):
    p = words(70).split()
    q = list(p)
    q[20], q[60] = "zz", "yy"
    q.insert(45, "xx")
    d = docs(spark, words(30) + " " + " ".join(p) + " " + words(20), words(100), words(10) + " " + " ".join(p), words(5) + "\n" + " ".join(q), None, "", words(40) + " " + " ".join(p[:40]))
    got = {r["doc_id"]: r for r in substring_dedup.find_passages(d.withColumn("seeds", F.lit(1))).collect()}
    assert set(got) == {2, 3} and got[2]["of_doc"] == 0 and (got[2]["first_word"], got[2]["end_word"], got[2]["of_first"]) == (10, 80, 30)
    left = {r["doc_id"]: r["text"] for r in substring_dedup.remove(d, substring_dedup.find_passages(d)).collect()}
    assert len(left[2].split()) == 10 and left[1] == d.where("doc_id = 1").first()["text"] and left[4] is None
    assert substring_dedup.find_passages(d.limit(0)).count() == 0


def test_chain_is_best():
    r = random.Random(2)
    for _ in range(30):
        m = sorted({(r.randint(0, 30), r.randint(0, 30)) for _ in range(9)})
        best = max(len(c) - substring_dedup.GAP_COST * (c[-1][0] - c[0][0] + c[-1][1] - c[0][1]) for n in range(1, 10) for c in combinations(m, n) if all(a[0] < b[0] and a[1] < b[1] for a, b in zip(c, c[1:], strict=False)))
        got = max(len(c) - substring_dedup.GAP_COST * (c[-1][0] - c[0][0] + c[-1][1] - c[0][1]) for c in substring_dedup.chain(m))
        assert got == pytest.approx(best)


# 5 audio


def test_tables():
    mu, al = audio.TABLES[audio.MULAW], audio.TABLES[audio.ALAW]
    assert (mu[0], mu[127], mu[128], mu[255]) == (-32124, 0, 32124, 0) and (al[0xD5], al[0x55], al[0xAA], al[0x2A]) == (8, -8, 32256, -32256)


def test_adpcm_and_resampling():
    t = np.arange(8000) / 8000
    x = (8000 * np.sin(2 * np.pi * 440 * t)).astype(np.int16)
    media = audio.wave(audio.IMA_ADPCM, 8000, 4, audio.adpcm_encode(x), 256, b"\xf9\x01", len(x))
    y, rate = audio.decode(media)
    assert rate == 8000 and len(y) == len(x) and np.sqrt(np.mean((x.astype(float) - y) ** 2)) < 200
    z, rate = audio.decode(audio.to_pcm(media, 16000))
    assert rate == 16000 and len(z) == 16000 and np.array_equal(z[::2], y)
    assert audio.to_pcm(None) is None and audio.decode(audio.to_pcm(audio.wave(audio.MULAW, 8000, 8, b"")))[0].size == 0


def test_audio_payload(spark):
    import hashlib
    import zlib

    d = docs(spark, "né", None, "x" * 64, "y" * 200_000)
    got = {r["doc_id"]: r for r in audio.describe(audio.encode_texts(d).withColumn("n_bytes", F.octet_length(F.coalesce("text", F.lit(""))).cast("long"))).collect()}
    for r in d.collect():
        raw = (r["text"] or "").encode()
        pay = raw.ljust(max(64, -(-len(raw) // 64) * 64), b"\0")
        x = got[r["doc_id"]]
        assert (x["n_bytes"], x["payload_bytes"], x["payload_sha256"], x["tail_crc32"]) == (len(raw), len(pay), hashlib.sha256(pay).hexdigest(), zlib.crc32(pay[-64:]))


# 6 language


def test_language_held_out(spark):
    sf = "/root/testdata/sf0.01"
    got = language_id.query(spark, sf).join(spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "lang"), "doc_id").where("held_out")
    assert got.where("lang = lang_pred").count() / got.count() > 0.95


def test_language_awkward(spark):
    d = docs(spark, None, "", "123 !!", "the and of").withColumn("score", F.lit("clash"))
    got = [(r["lang_pred"], r["score"], r["accepted"]) for r in language_id.predict(d, {"en": b"the and of with", "de": b"der die das und"}).orderBy("doc_id").collect()]
    assert got[:3] == [("und", 0.0, False)] * 3 and got[3][0] == "en"
    assert language_id.learn(d.limit(0)) == {} and language_id.predict(d, {}).where("lang_pred <> 'und'").count() == 0


def test_big_languages_leave_rare_ones_their_sample(spark, words, monkeypatch):
    monkeypatch.setattr(language_id, "BUCKETS", 8)
    rare = [words(4) for _ in range(5)]
    rows = [(words(4), lang) for lang in ("aa", "bb") for _ in range(600)] + [(t, "zz") for t in rare]
    got = language_id.learn(spark.createDataFrame(rows, "text string, lang string"), 5)
    assert set(got["zz"].decode().split("\n")) == set(rare)
    assert all(len(got[k].decode().split("\n")) == 5 for k in ("aa", "bb"))


def test_samples_are_not_prefixes(spark, words):
    texts = ["x" * 2000 + " " + words(900) for _ in range(20)]
    got = language_id.learn(spark.createDataFrame([(t, "aa") for t in texts], "text string, lang string"))["aa"].decode()
    assert any(set(part) - {"x"} for part in got.split("\n"))


# 7 decontamination


def test_alignment_against_bruteforce():
    r = random.Random(4)
    for _ in range(200):
        p, q = ([r.choice("abcd") for _ in range(r.randint(1, 12))] for _ in range(2))
        h = [[0] * (len(p) + 1) for _ in range(len(q) + 1)]
        for i in range(1, len(q) + 1):
            for j in range(1, len(p) + 1):
                h[i][j] = max(0, h[i - 1][j - 1] + (2 if p[j - 1] == q[i - 1] else -1), h[i - 1][j] - 1, h[i][j - 1] - 1)
        assert decontaminate.align(p, q)[0] == max(map(max, h))


def test_leaks(spark, words, monkeypatch):
    item, other = words(30), words(25)
    edited = item.split()
    edited[7], edited[19] = "zz", "yy"
    d = docs(spark, words(50) + " " + item + " " + words(9), words(60) + "\n" + " ".join(edited).upper() + ".", words(90), None, "", " ".join(item.split()[:9]))
    items = spark.createDataFrame([(1, item), (2, other), (3, None), (None, item), (4, "")], "item_id long, text string")
    want = {(0, 1), (1, 1)}
    assert {(r["doc_id"], r["item_id"]) for r in decontaminate.find_leaks(d, items).collect()} == want
    monkeypatch.setattr(decontaminate, "BLOCK_WORDS", 40)  # one item a block
    assert {(r["doc_id"], r["item_id"]) for r in decontaminate.find_leaks(d, items).collect()} == want
    assert decontaminate.find_leaks(d, items.limit(0)).count() == 0 and decontaminate.find_leaks(d.limit(0), items).count() == 0


def test_leaks_on_the_table(spark, sf, table):
    got = {(r["doc_id"], r["item_id"]) for r in decontaminate.query(spark, sf).collect()}
    items = spark.read.parquet(f"{sf}/benchmark.parquet")
    exact = {(r["doc_id"], r["item_id"]) for r in table.join(items.withColumnRenamed("text", "item"), F.contains("text", "item")).collect()}
    assert exact <= got and exact


def test_leaks_that_are_frequent_or_heavily_edited(spark, words):
    r = random.Random(8)
    item = words(15).split()
    assert len(set(item)) == 15
    texts = []
    for k in range(70):  # no run of four words stays, but the score is over the limit
        w = list(item)
        for j in (3, 7, 11):
            w[j] = f"x{k}y{j}"
        w.insert(14, f"z{k}")
        texts.append(" ".join([words(20), *w, words(20)]))
    for k in range(60):  # 60 copies of two different seeds of four words
        w = list(item)
        for j in (0, 5, 10, 11, 12)[: 4 + k % 2]:
            w[j] = f"u{k}v{j}"
        texts.append(" ".join([words(30), *w, words(3)]))
    for _ in range(60):
        texts.append(" ".join(x for w in item for x in ([w] if r.random() < 0.6 else [w, "q"] if r.random() < 0.5 else ["p"])))
    texts.append(" q ".join(item))
    want = {k for k, t in enumerate(texts) if decontaminate.align(t.split(), item)[0] >= 15}
    got = {x["doc_id"]: x for x in decontaminate.find_leaks(docs(spark, *texts), spark.createDataFrame([(1, " ".join(item))], "item_id long, text string")).collect()}
    assert set(got) == want and len(want) > 150
    assert all(got[k]["score"] == decontaminate.align(texts[k].split(), item)[0] / 30 for k in want)


# 8 lines


def distance(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        new = [i]
        for j, y in enumerate(b, 1):
            new.append(min(row[j] + 1, new[-1] + 1, row[j - 1] + (x != y)))
        row = new
    return row[-1]


def test_edit_kernels():
    r = random.Random(3)
    for _ in range(3000):
        a = "".join(r.choice("abc") for _ in range(r.randint(3, 14)))
        b = list(a)
        for _ in range(r.randint(0, 4)):
            k = r.randrange(len(b)) if b else 0
            b[k : k + r.randint(0, 1)] = r.choice(["", "a", "b"])
        b = "".join(b)
        near = distance(a, b) <= 2
        assert line_dedup.within(a, b) == near
        if near and len(b) >= 3:
            s, t = sorted((a, b), key=len)
            own = {(len(s), k, s[x : x + z]) for k, (x, z) in enumerate(line_dedup.segments(len(s)))}
            assert own & {(m, k, t[x : x + z]) for m, k, x, z in line_dedup.probes(len(t))}
            assert ((line_dedup._sign(a) ^ line_dedup._sign(b)) & line_dedup.PARITY).bit_count() <= 4


def test_edit_join_against_bruteforce(spark, words):
    base = [words(8) for _ in range(40)]
    lines = list(dict.fromkeys(base + [x[:9] + "q" + x[9:] for x in base[:20]] + [x[1:-1] for x in base[5:15]]))
    df = spark.createDataFrame([(x,) for x in lines + lines[:10]], "line string").withColumn("key", common.text_key(F.col("line")))
    name = {tuple(r["key"]): r["line"] for r in df.collect()}
    got = {tuple(sorted((name[tuple(r["a"])], name[tuple(r["b"])]))) for r in line_dedup.edit_links(df).collect()}
    assert got == {tuple(sorted(p)) for p in combinations(lines, 2) if distance(*p) <= 2}


def test_edit_join_of_very_long_lines(spark):
    r = random.Random(6)
    texts = []
    for k in range(8):  # which line of a pair has the greater hash is chance
        a = "".join(r.choice("abcdefgh ") for _ in range(40_000))
        texts += [a, a[:17_000] + "x" * (1 + k % 2) + a[17_000:]]
    lines = spark.createDataFrame(list(enumerate(texts)), "key long, line string")
    got = {tuple(sorted((x["a"], x["b"]))) for x in line_dedup.edit_links(lines).collect()}
    assert got == {(2 * k, 2 * k + 1) for k in range(8)}


def test_line_dedup(spark, words):
    a, b, c = words(9), words(9), words(9)
    d = docs(spark, f"{a}\n{b}", f"{c}\n\n {a.upper()} \n{b[:-1]}", None, "", f"{a}\n{a}").unionByName(spark.createDataFrame([(None, a, None, None, 5), (1, f"{c}\n\n {a.upper()} \n{b[:-1]}", "x", "y", 1)], DOCS)).withColumn("links", F.lit("clash"))
    got = sorted(((r["doc_id"] if r["doc_id"] is not None else -1, r["text"], r["n_chars"]) for r in line_dedup.dedup(d).collect()), key=str)
    left = f"{c}\n"
    assert got == sorted([(0, f"{a}\n{b}", len(a) + len(b) + 1), (1, left, len(left)), (1, left, len(left)), (2, None, None), (3, "", 0), (4, "", 0), (-1, "", 0)], key=str)
    assert line_dedup.dedup(d).columns == d.columns and line_dedup.dedup(d.limit(0)).count() == 0


# 9 URLs


def test_rules_and_hosts(spark):
    urls = ["http://www.Example.com/en/7x", "https://a.com/en/1?x=/en/7", "http://net/de/3", "http://m.example.net/de/8", "http://x.org/es/", "notaurl", None, "", "http://badexample.com/en/7", "ftp://h.net#/de/"]
    got = {r["page_id"]: r for r in url_filter.filter_urls(spark.createDataFrame(list(enumerate(urls)), "page_id long, url string").withColumn("host", F.lit(1))).collect()}
    assert [got[k]["rule"] for k in range(10)] == ["example.com/en/7", "com/en/", "net/de/", "example.net/de/8", "org/es/", None, None, None, "com/en/", None]
    assert [got[k]["verdict"] for k in (0, 1, 2, 3, 4, 8)] == ["allow", "block", "allow", "block", "block", "block"]
    assert (got[0]["host"], got[0]["path"], got[5]["host"], got[9]["path"]) == ("www.example.com", "/en/7x", "", "")
    assert url_filter.filter_urls(spark.createDataFrame([], "page_id long, url string")).count() == 0


def test_url_model_against_bruteforce(spark):
    good, bad = ["http://good.a/x1", "http://good.a/y2", "http://göod.a/"], ["http://spam.b/zz"]
    lab = spark.createDataFrame([(u, 1, True) for u in good] + [(u, 2, False) for u in bad], "url string, n long, good boolean").withColumn("line", url_filter.marked(F.col("url"))).drop("url")
    k = url_filter.ORDER
    other = url_filter.MARK * k + "http://new.a/x2?Ω" + url_filter.MARK
    lines = [(r["line"], r["n"], r["good"]) for r in lab.collect()]
    need = {x[at : at + k + 1] for x in [other, *(x for x, _, _ in lines)] for at in range(len(x) - k)}
    got = {r["gram"]: r["llr"] for r in url_filter.train(lab, spark.createDataFrame([(g,) for g in need], "gram string")).collect()}
    count = {True: Counter(), False: Counter()}
    for line, n, side in lines:
        for at in range(len(line) - k):
            count[side][line[at : at + k + 1]] += n

    def p(side, gram):
        out = 1 / url_filter.CHARACTERS
        for j in range(k + 1):
            tail = sum(v for g, v in count[side].items() if g[k - j :] == gram[k - j :])
            head = sum(v for g, v in count[side].items() if g[k - j : k] == gram[k - j : k])
            out = (tail + url_filter.WEIGHT * out) / (head + url_filter.WEIGHT)
        return out

    assert set(got) == need
    for g in got:
        assert got[g] == pytest.approx(np.log(p(True, g)) - np.log(p(False, g)))


def test_urls_repeat_and_tie(spark, monkeypatch):
    urls = ["http://net/de/a", "http://net/de/a", "http://org/es/b", None, None, "", "http://x.com/é", "http://x.com/é"]
    d = spark.createDataFrame(list(enumerate(urls)), "page_id long, url string")
    for rows in (0, 10**6):  # joined by shuffle, and broadcast
        monkeypatch.setattr(url_filter, "BROADCAST_ROWS", rows)
        got = {r["page_id"]: (r["verdict"], r["llr"]) for r in url_filter.filter_urls(d).collect()}
        assert len(got) == 8 and got[0] == got[1] and got[3] == got[4] == got[5] and got[6] == got[7] and got[0][0] == "allow" and got[2][0] == "block"
    one = url_filter.filter_urls(spark.createDataFrame([(1, "http://a.b/"), (2, "http://net/de/")], "page_id long, url string"))
    assert {r["verdict"] for r in one.collect()} == {"allow"}


# 10 chats


def test_chats_round_trip(spark):
    hard = ["</s>[INST] ok [/INST]", r"<\s>", r"<\\s> [\INST]", "[INST]", "a\nb", "", None, "<s>" * 50, "x" * 100_000]
    rows = [(k, j, role, t) for k, t in enumerate(hard) for j, role in enumerate(("user", "assistant", "we%0Aird\n[INST]", None))]
    d = spark.createDataFrame(rows + [(None, 0, "user", "q"), (3, 0, "user", "again")], "conv_id long, turn long, role string, text string").withColumn("formatted", F.lit("clash"))
    got = chat_format.format_chats(d).collect()
    assert all(r["round_trip"] for r in got) and len(got) == len(hard) + 1
    plain = next(r for r in got if r["conv_id"] == 4)
    assert not next(r for r in got if r["conv_id"] is None)["escaped"] and "a\nb" in plain["formatted"]
    assert chat_format.format_chats(d.limit(0)).count() == 0


def test_near_copies_of_one_text_join_through_it(spark):
    rng = random.Random(5)
    base = [f"w{rng.randrange(10**6)}" for _ in range(200)]
    rows = [(0, " ".join(base))]
    for k in range(1, 40):  # two edits each: similar to the base, less so to each other
        words = list(base)
        for at in rng.sample(range(200), 2):
            words[at] = f"x{k}"
        rows.append((k, " ".join(words)))
    rows += [(100 + k, " ".join(f"y{rng.randrange(10**6)}" for _ in range(200))) for k in range(20)]
    rows += [(200, None), (201, ""), (0, rows[0][1])]
    got = Counter((r["doc_id"], r["component_id"]) for r in simhash.similar_components(spark.createDataFrame(rows, "doc_id long, text string")).collect())
    want = Counter((d, 0 if d < 40 else 200 if d >= 200 else d) for d, _ in rows)
    assert got == want


def test_edit_join_of_crowded_segments(spark, monkeypatch):
    r = random.Random(9)
    head = "the same half of forty characters is in "

    def edited(x):
        x = list(x)
        for _ in range(r.randint(1, 3)):
            k = r.randrange(len(x))
            x[k : k + r.randint(0, 1)] = r.choice(["", "a", "b"])
        return "".join(x)

    lines = [head + "".join(r.choice("0123456789abcdef") for _ in range(40)) for _ in range(300)]
    lines = list(dict.fromkeys(lines + [edited(x) for x in lines[:100]]))
    df = spark.createDataFrame([(x, x) for x in lines], "key string, line string")
    want = {tuple(sorted(p)) for p in combinations(lines, 2) if abs(len(p[0]) - len(p[1])) < 3 and distance(*p) <= 2}
    for pairs, rows in ((50_000, 200_000), (20, 10), (0, 3)):
        monkeypatch.setattr(line_dedup, "PAIRS", pairs)
        monkeypatch.setattr(line_dedup, "ROWS", rows)
        assert {tuple(sorted((x["a"], x["b"]))) for x in line_dedup.edit_links(df).collect()} == want


def test_links_of_large_classes_make_no_rows_for_pairs(spark, monkeypatch):
    r = random.Random(13)
    base = "".join(r.choice("abcdefgh ") for _ in range(60))
    lines = {base}
    while len(lines) < 300:  # all within two edits
        k = r.randrange(60)
        lines.add(base[:k] + r.choice("uvwxyz") + base[k + 1 :])
    other = "ab" * 30
    loose = {other}
    while len(loose) < 90:  # some within two edits, of several lengths, with segments that fit at several places
        x = list(r.choice(sorted(loose)))
        k = r.randrange(len(x))
        x[k : k + r.randint(0, 1)] = r.choice(["", "a", "b", "c"])
        loose.add("".join(x))
    lines = sorted(lines | loose)
    near = [p for p in combinations(lines, 2) if abs(len(p[0]) - len(p[1])) < 3 and line_dedup.within(*p)]
    links = Counter(x for p in near for x in p)
    assert len(near) > 300 * 299 // 2
    written = []
    saved = line_dedup.saved
    monkeypatch.setattr(line_dedup, "saved", lambda df: (written.append(out := saved(df)), out)[1])
    df = spark.createDataFrame([(x, x) for x in lines], "key string, line string")
    for small in (256, 2):
        monkeypatch.setattr(line_dedup, "SMALL", small)
        assert {x["key"]: x["links"] for x in line_dedup.edit_classes(df).collect()} == links
    assert {tuple(sorted((x["a"], x["b"]))) for x in line_dedup.edit_links(df).collect()} == set(near)
    assert max(x.count() for x in written) < 30 * len(lines) < len(near)


# recall against all pairs


def test_passages_against_all_pairs(spark, words):
    """Planted passages, edited to several identities, and passages whose parts stand in other documents too."""
    r = random.Random(12)

    def edited(p, share):
        q = list(p)
        for k in r.sample(range(len(p)), int(len(p) * (1 - share))):
            q[k] = words(1)
        return q

    texts, want = [], {}
    for share, size, least in ((1.0, 51, 1.0), (0.95, 60, 1.0), (0.9, 60, 0.95), (0.85, 60, 0.9), (0.82, 100, 0.95)):
        for _ in range(30):
            p = words(size).split()
            texts.append(words(40) + " " + " ".join(p) + " " + words(30))
            texts.append(words(20) + "\n" + " ".join(edited(p, share)) + " " + words(30))
            want.setdefault((share, size, least), []).append((len(texts) - 1, len(texts) - 2))
    x, y = words(30), words(30)
    at = len(texts)
    texts += [f"{x} {words(40)}", f"{words(30)} {y}", f"{words(20)} {x} {y} {words(5)}", f"{x} {words(50)}", f"{y} {words(60)}", f"{words(7)} {x} {y} {words(9)}"]
    texts += [words(30) + " buy now click here" * 100, words(12) + " buy now click here" * 100]
    clean = len(texts)
    texts += [words(200) for _ in range(20)]
    got = substring_dedup.find_passages(docs(spark, *texts)).collect()
    pairs = {(g["doc_id"], g["of_doc"]) for g in got}
    for (_, _, least), planted in want.items():
        assert sum(p in pairs for p in planted) >= least * len(planted)
    assert (at + 5, at + 2) in pairs and (at + 7, at + 6) in pairs
    assert all(g["doc_id"] < clean for g in got)


def test_exact_passages_of_the_table(spark, table):
    """Every run of 51 words that an earlier document has is covered, by brute force over all runs."""
    rows = sorted((r["doc_id"], substring_dedup.words_of(r["text"])) for r in table.select("doc_id", "text").collect())
    covered = {}
    for g in substring_dedup.find_passages(table).collect():
        covered.setdefault(g["doc_id"], set()).update(range(g["first_word"], g["end_word"]))
    seen, missed, n = set(), 0, 0
    for doc_id, w in rows:
        own = [tuple(w[k : k + 51]) for k in range(len(w) - 50)]
        for k, run in enumerate(own):
            if run in seen:
                n += 1
                missed += not set(range(k, k + 51)) <= covered.get(doc_id, set())
        seen.update(own)
    assert n > 100 and missed <= 0.02 * n


def test_passages_of_crowded_batches(spark, words, monkeypatch):
    p = words(60)
    texts = [words(10 + k % 7) + " " + p + " " + words(5) for k in range(90)]
    d = docs(spark, *texts).coalesce(1)
    for hot, held in ((16, 10**6), (3, 10**6), (10**6, 20)):
        monkeypatch.setattr(substring_dedup, "HOT", hot)
        monkeypatch.setattr(substring_dedup, "HELD", held)
        got = substring_dedup.find_passages(d).collect()
        assert {g["doc_id"] for g in got} == set(range(1, 90)) and all(g["of_doc"] < g["doc_id"] for g in got)
        assert all(g["end_word"] - g["first_word"] >= 60 for g in got)


def test_passage_whose_seeds_stand_before_and_after_its_source(spark):
    """every seed of the passage has its first and its last earlier document elsewhere, in parts that are too short."""
    words = _words(21)
    p = words(60).split()
    parts = [" ".join(p[:45]), " ".join(p[15:])]
    texts = [f"{words(20)} {parts[0]} {words(20)}", f"{words(20)} {parts[1]} {words(20)}", f"{words(9)} {' '.join(p)} {words(9)}"]
    texts += [f"{words(20)} {parts[0]} {words(20)}", f"{words(20)} {parts[1]} {words(20)}", f"{words(30)} {' '.join(p)} {words(3)}"]
    got = substring_dedup.find_passages(docs(spark, *texts)).collect()
    assert [(g["doc_id"], g["first_word"], g["end_word"], g["of_doc"], g["of_first"], g["class_id"]) for g in got] == [(5, 30, 90, 2, 9, 2)]


def test_covered_words_meet_all_earlier_documents(spark):
    """a passage of one class covers the seeds, and a partner in the middle has more words, too few for seeds of their own; copies are no pairs."""
    words = _words(41)
    p, rest = words(60), words(9)
    texts = [f"{words(20)} {p} {words(20)}", f"{words(25)} {p} {words(20)}", f"{words(15)} {p} {rest} {words(20)}", f"{words(31)} {p} {words(20)}"]
    texts += [f"{words(12)} {p} {rest} {words(9)}", f"{words(28)} {p} {words(20)}"]
    texts += [texts[2], texts[4], texts[4], words(49), words(50)]
    texts += texts[-2:]
    got = substring_dedup.find_passages(docs(spark, *texts)).collect()
    assert max(g["end_word"] for g in got if g["doc_id"] == 4) == 81 and (4, 2) in {(g["doc_id"], g["of_doc"]) for g in got}
    assert [(g["of_doc"], g["first_word"], g["end_word"], g["identity"], g["class_id"]) for k in (6, 7, 8, 12) for g in got if g["doc_id"] == k] == [(2, 0, 104, 1.0, 0), (4, 0, 90, 1.0, 0), (4, 0, 90, 1.0, 0), (10, 0, 50, 1.0, 10)]
    assert {g["doc_id"] for g in got} == {1, 2, 3, 4, 5, 6, 7, 8, 12} and {g["class_id"] for g in got} == {0, 10} and all(g["seeds"] > 1 for g in got)


def test_all_earlier_documents_are_met():
    """20 documents have one seed: each is joined with all before it."""
    n = 20
    got = substring_dedup.matched_all(np.full(n, 8), np.arange(n), np.full(n, 3), np.zeros(n, int))
    assert len(got) == n * (n - 1) // 2 and (got["of_doc"] < got["doc_id"]).all()


def test_passages_behind_a_common_line(spark, monkeypatch):
    """Documents that share a line, which is no passage, and some of them what stands around it; batches replace its seeds or not."""
    words = _words(22)
    line, common, r = words(14), words(70), random.Random(5)
    texts = [f"{words(40)} {line} {words(40)}" for _ in range(60)]
    texts += [f"{words(30 + k)} {common} {words(9)}" for k in range(30)]
    want = {k: 60 for k in range(61, 90)}
    for _ in range(8):
        p = f"{words(20)} {line} {words(30)}".split()
        q = [words(1) if k not in range(20, 34) and r.random() < 0.1 else w for k, w in enumerate(p)]
        want[len(texts) + 1] = len(texts)
        texts += [f"{words(20)} {' '.join(p)} {words(20)}", f"{words(33)} {' '.join(q)} {words(20)}"]
    texts += [f"{words(40)} {line} {words(40)}" for _ in range(60)]
    for crowd, hot, held in ((10, 3, 10**6), (10**6, 10**6, 20)):
        for k, v in (("CROWD", crowd), ("HOT", hot), ("HELD", held)):
            monkeypatch.setattr(substring_dedup, k, v)
        got = {g["doc_id"]: g["class_id"] for g in substring_dedup.find_passages(docs(spark, *texts).coalesce(2)).collect()}
        assert got == want


def test_rows_alike_against_all_pairs(monkeypatch):
    monkeypatch.setattr(substring_dedup, "CROWD", 5)
    monkeypatch.setattr(substring_dedup, "BLOCK", 7)
    r = np.random.default_rng(3)
    around = r.integers(1, 60, (60, 96)).astype(np.uint16)
    around[:, 40:54], around[40:, 54:80] = 7, 8
    for k in range(0, 40, 2):
        at = r.integers(0, 50)
        keep = np.arange(at, at + 50)[r.random(50) < 0.85]
        around[k + 1, keep] = around[k, keep]
    around[5, 90:], around[6, :5] = 0, 0
    got = {frozenset(p[:2]) for both in substring_dedup.alike(around, lambda a, b: a != b) for p in both.tolist()}
    least = {frozenset((a, b)) for a in range(60) for b in range(a) if max(np.convolve((around[a] == around[b]) & (around[a] != 0), np.ones(50, int), "valid")) >= 40}
    assert len(least) > 100 and least <= got


def test_pairs_of_a_crowd_leave_in_parts(monkeypatch):
    """a seed's matches were made as one table; in small parts they are the same."""
    r = np.random.default_rng(4)
    around = r.integers(1, 60000, (150, 96)).astype(np.uint16)
    around[:, 30:66], around[::3, 66:80] = r.integers(1, 60000, 36), 7
    of = pd.DataFrame({"seed": 8, "doc_id": r.integers(0, 110, 150), "pos": range(150), "run": 0, "kin": r.integers(0, 20, 150), "covered": r.random(150) < 0.5, "words": [w.tobytes() for w in around]})
    whole = pd.concat(substring_dedup.crowd_met(of)).sort_values(["pos", "at"], ignore_index=True)
    monkeypatch.setattr(substring_dedup, "CELLS", 2000)
    monkeypatch.setattr(substring_dedup, "OUT", 300)
    parts = list(substring_dedup.crowd_met(of))
    assert len(parts) > 15 and max(map(len, parts)) <= 300 and len(whole) > 4000
    assert pd.concat(parts).sort_values(["pos", "at"], ignore_index=True).equals(whole)


def test_repeated_words_are_one_occurrence():
    """Ties made a seed of nearly every word of a repeated one: rows, matches and memory grew with them."""
    w = _words(31)
    texts = [f"{w(40)} {'the ' * 2000} {w(40)}", f"{w(40)} {'to be ' * 1000} {w(40)}"]
    got = substring_dedup.seeds(texts)
    assert len(got[0]) < 150
    # Each of their places is in an occurrence or run of it.
    for k, text in enumerate(texts):
        runs = [(p, r) for t, s, p, r in zip(*got, strict=True) if t == k and not s & 1 and r]
        assert len(text.split()) == 2080 and runs and min(p for p, _ in runs) <= 41 and max(p + r for p, r in runs) >= 2030


def test_passages_of_repeated_words(spark):
    """Runs of other lengths, several in a text, meet where they begin and where they end."""
    w = _words(32)
    texts = [f"{w(30)} {'by ' * 8}{'on ' * 50}", f"{w(20)} {'on ' * 9}{w(7)} {'on ' * 23}{w(90)} {'as ' * 8}{'on ' * 58}{w(6)}", f"{w(4)} {'up ' * 60}{w(40)}", f"{w(3)} {'up ' * 300}{w(4)}"]
    got = {}
    for g in substring_dedup.find_passages(docs(spark, *texts)).collect():
        got.setdefault((g["doc_id"], g["of_doc"]), []).append((g["first_word"], g["end_word"]))
    assert set(got) == {(1, 0), (3, 2)}
    assert {(157, 207), (165, 215)} & set(got[1, 0]) and {(3, 63), (243, 303)} <= set(got[3, 2])


def test_windows_of_a_large_batch_are_made_in_parts(monkeypatch):
    w, held, hashed = _words(33), [], substring_dedup._hashed
    texts = [w(50 + 13 * k) for k in range(30)] + [None, ""]
    at = [np.array([0, 7, 49], np.int32)] * 30 + [np.empty(0, np.int32)] * 2
    batch = pd.DataFrame({"doc_id": range(32), "kin": range(32), "text": texts, "seed": [a.astype(np.int64) for a in at], "pos": at, "run": [a * 0 for a in at], "covered": [a > 7 for a in at]})
    whole = pd.concat(substring_dedup.windows(batch), ignore_index=True)
    monkeypatch.setattr(substring_dedup, "CHARS", 5000)
    monkeypatch.setattr(substring_dedup, "_hashed", lambda x: held.append(sum(map(len, x))) or hashed(x))
    assert pd.concat(substring_dedup.windows(batch), ignore_index=True).equals(whole) and len(whole) == 90
    assert len(held) > 5 and max(held) < 5000 + max(len(t or "") for t in texts)
    mid = np.frombuffer(whole["words"][4], np.uint16)
    assert len(mid) == 2 * substring_dedup.ROOM + substring_dedup.SEED and (mid[:39] == 0).all() and (mid[39:] != 0).sum() == 57


def test_removal_counts_words_as_the_search_does(spark):
    d = docs(spark, "a b c d  e\n", None, "")
    spans = spark.createDataFrame([(0, 1, 3), (2, 0, 1)], "doc_id long, first_word int, end_word int")
    assert {r["doc_id"]: r["text"] for r in substring_dedup.remove(d, spans).collect()} == {0: "a d  e\n", 1: None, 2: ""}


def test_near_recall_at_the_limit(spark):
    """Pairs at a similarity of 0.8 to 0.85 are linked, pairs below aren't."""
    r = random.Random(3)
    new = lambda n: [f"w{r.randrange(10**6)}" for _ in range(n)]
    texts, pairs = [], {}
    for size in (60, 200, 600):
        for _ in range(60):
            p = new(size)
            for _ in range(200):
                q = list(p)
                for k in r.sample(range(size), r.randint(1, max(1, size // 40))):
                    q[k] = new(1)[0]
                q += new(r.randint(0, size // 8))
                same = simhash.jaccard(" ".join(p), " ".join(q), 5)
                if 0.74 <= same < 0.85:
                    break
            texts += [" ".join(p), " ".join(q)]
            pairs[len(texts) - 2] = same
    got = {x["doc_id"]: x["component_id"] for x in simhash.similar_components(docs(spark, *texts)).collect()}
    near = [k for k, s in pairs.items() if s >= 0.8]
    assert len(near) > 60 and sum(got[k + 1] == k for k in near) >= 0.95 * len(near)
    assert all(got[k + 1] == k + 1 for k, s in pairs.items() if s < 0.8)


def test_near_stage_judges_texts_not_ids(spark, sf):
    t, u = "a b c d e f g h", "other words that are quite unlike them all"
    x = spark.createDataFrame([(1, t, "x"), (2, t, "y"), (2, u, "z"), (None, t, "n"), (3, None, "q"), (4, "", "q"), (4, "", "r")], "doc_id long, text string, __cg_x string")
    got = {tuple(r) for r in simhash.stage(spark, x, sf).collect()}
    assert got == {(1, t, "x"), (2, u, "z"), (3, None, "q"), (None, t, "n")}
    assert simhash.stage(spark, x.limit(0), sf).count() == 0


def test_crowded_index_keys(spark, monkeypatch, table):
    want = {(r["doc_id"], r["component_id"]) for r in simhash.near_components(table).collect()}
    assert all(any(set(t) <= set(c) for t in simhash.position_groups(8, 4, 4)) for c in combinations(range(8), 4))
    monkeypatch.setattr(simhash, "CROWD", 4)
    monkeypatch.setattr(simhash, "MANY", 10)
    assert {(r["doc_id"], r["component_id"]) for r in simhash.near_components(table).collect()} == want


# 2, 5, 6 against brute force


def test_mixing_against_a_replay(spark, monkeypatch):
    """Blocks and documents taken one after the other in the order of their keys, as long as they fit."""
    r = random.Random(21)
    rows = [(k, "w " * r.randint(0, 40), "en", r.choice("aaaaaaab") + r.choice(["", "", "x"]), 0) for k in range(1500)] + [(k, "v " * 5, "en", "a", 0) for k in range(20)] + [(None, "w w w", "en", None, 0)]
    d = spark.createDataFrame(rows, DOCS)
    for slices in (1024, 2):
        monkeypatch.setattr(mixing, "SLICES", slices)
        keyed = d.select(mixing.source_key().alias("s"), F.col("doc_id").alias("d"), mixing.tokens().alias("n"))
        plan = mixing.plan(keyed, 0.9, 3.0, None, 300)
        own = {p["s"]: p for p in plan.collect()}
        total = sum(len(x[1].split()) for x in rows)
        size = Counter()
        for x in rows:
            size[x[3] or ""] += len(x[1].split())
        # weights: shares to one exponent
        a = [np.log(own[s]["weight"] / own["a"]["weight"]) / np.log(size[s] / size["a"]) for s in size if s != "a" and size[s]]
        assert np.allclose(a, a[0]) and sum(p["weight"] for p in own.values()) == pytest.approx(1)
        full = keyed.join(plan.select("s", "epochs", "blocks"), "s").select("s", "d", "n", mixing.doc_order(mixing.SEED), mixing.block_order(mixing.SEED)).collect()
        want = Counter()
        for s, p in own.items():
            budget = p["weight"] * total
            epochs = int(budget / size[s] + 1e-9)
            rest = max(0.0, budget - epochs * size[s])
            mine = [x for x in full if x["s"] == s]
            for x in mine:
                want[s, x["d"]] += epochs
            fits, used = True, 0
            for key in sorted({x["block_key"] for x in mine}):
                block = [x for x in mine if x["block_key"] == key]
                if used + sum(x["n"] for x in block) <= rest:
                    used += sum(x["n"] for x in block)
                    want.update((s, x["d"]) for x in block)
                    continue
                for dk in sorted({x["doc_key"] for x in block}):
                    docs_ = [x for x in block if x["doc_key"] == dk]
                    if used + sum(x["n"] for x in docs_) > rest:
                        break
                    used += sum(x["n"] for x in docs_)
                    want.update((s, x["d"]) for x in docs_)
                break
        got = Counter((x["source"] or "", x["doc_id"]) for x in mixing.mix(d, entropy=0.9, repeats=3.0, block_tokens=300).collect())
        assert got == +want


def test_clips_that_cannot_be_read(spark):
    ok = audio.wave(audio.PCM, 8000, 16, np.arange(8, dtype="<i2").tobytes(), 2)
    stereo = bytearray(audio.wave(audio.PCM, 16000, 16, np.array([2, 4, 6, 8], "<i2").tobytes(), 4))
    stereo[22] = 2
    eight = audio.wave(audio.PCM, 16000, 8, bytes([0, 128, 255]))
    clips = [ok, None, b"", b"RIFF", ok[:30], audio.wave(99, 8000, 8, b"ab"), bytes(stereo), eight, ok[:-3], audio.wave(audio.IMA_ADPCM, 8000, 4, b"", 0)]
    d = spark.createDataFrame(list(enumerate(clips)), "k int, media binary").withColumn("pcm_status", F.lit("clash"))
    got = {x["k"]: x for x in audio.store_pcm(d).collect()}
    assert [k for k in got if got[k]["pcm"] is not None] == [0, 6, 7, 8] and got[1]["pcm_status"] == "null" and got[0]["pcm_status"] == "ok"
    assert all(got[k]["pcm_status"] not in ("ok", "null") for k in (2, 3, 4, 5, 9))
    assert audio.decode(bytes(got[6]["pcm"]))[0].tolist() == [3, 7] and audio.decode(bytes(got[7]["pcm"]))[0].tolist() == [-32768, 0, 32512]
    assert audio.store_pcm(d.limit(0)).count() == 0


def test_features_of_clips_coded_together():
    r = np.random.default_rng(1)
    clips = [audio.TABLES[audio.MULAW][r.integers(0, 256, n)] for n in (64, 2048, 505, 128)]
    one = [audio.decode(audio.wave(audio.IMA_ADPCM, 8000, 4, audio.adpcm_encode(x), 256, b"\xf9\x01", len(x)))[0] for x in clips]
    assert audio.adpcm_features(clips) == [audio.feature(x) for x in one] and audio.adpcm_features([]) == []


def test_languages_against_plain_compression(spark, table):
    import zstandard

    dicts = language_id.learn(table.select("text", "lang"), 50)
    assert all(len(v) <= language_id.DICT_BYTES for v in dicts.values()) and len(dicts) > 1
    for r in language_id.predict(table, dicts).collect():
        t = r["text"]
        if t is None or not any(c.isalpha() for c in t):
            assert r["lang_pred"] == "und"
            continue
        size = {}
        for name, raw in dicts.items():
            d = zstandard.ZstdCompressionDict(raw, dict_type=zstandard.DICT_TYPE_RAWCONTENT)
            size[name] = len(zstandard.ZstdCompressor(level=3, dict_data=d, write_content_size=False).compress(language_id.folded(t).encode()))
        assert size[r["lang_pred"]] == min(size.values())


def test_dictionaries_hold_a_share_of_every_text():
    texts = [b"a" * 10, b"b" * 1000, b"c" * 400]
    assert language_id.shared_out(texts, 2000) == texts
    assert [len(t) for t in language_id.shared_out(texts, 610)] == [10, 300, 300]
