"""The training-data operators against brute force, on small fixtures and on whole small tables."""

import hashlib
import random
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from anchorscope.llm import ann, decontam, mixing, sharding, simhash, suffixdedup, text, tokencount, toxicity, urlfilter, warc
from anchorscope.llm.components import components
from anchorscope.llm.spark import cut

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
SPACE = re.compile("[^\x20\x09-\x0d]+")


def docs_of(spark, texts, sources=None, ids=None):
    ids = list(range(len(texts))) if ids is None else ids
    rows = [(i, t, "en", (sources or ["a", "b", None])[k % len(sources or "abc")], len(t or "")) for k, (i, t) in enumerate(zip(ids, texts, strict=True))]
    return spark.createDataFrame(rows, SCHEMA)


ODD = [None, "", " \t\n", "word", "Ünïcödé wörds hére", "x" * 5000, "a b c " * 900, "same text here for all", "same text here for all", "same text here for all", "\u00a0 \u3000 x"]


@pytest.fixture(scope="module")
def whole(spark, data):
    return spark.read.parquet(f"{data}/documents.parquet")  # never cached: other tests of the session read the same files


# ------------------------------------------------------------------ kernels


def test_word_bounds_and_hashes():
    rows = ["ab cd", "", "e", "fg", " h  i "]
    raw = [r.encode() for r in rows]
    data = np.frombuffer(b"".join(raw), np.uint8)
    offsets = np.cumsum([0, *map(len, raw)])
    starts, ends, bounds = text.word_bounds(data, offsets, text.NOT_SPACE)
    got = [data[s:e].tobytes().decode() for s, e in zip(starts, ends, strict=True)]
    assert got == ["ab", "cd", "e", "fg", "h", "i"] and bounds.tolist() == [0, 2, 2, 3, 4, 6]
    h = text.PrefixHash(np.frombuffer(b"xyzxyz", np.uint8)).of(np.array([0, 3, 1]), np.array([3, 6, 3]))
    assert h[0] == h[1] != h[2]


# ------------------------------------------------------------------ 1


def brute_nearest(rows, k, every):
    usable = [(i, np.array(v, float)) for i, v in rows if i is not None and v is not None and None not in v and np.isfinite(v).all() and np.any(v)]
    out = {}
    for i, q in usable:
        if i % every == 0:
            out[i] = sorted(((-float(x @ q), j) for j, x in usable if j != i))[:k]
    return out


@pytest.mark.parametrize("sf", ["sf0.01", "sf0.1"])
def test_nearest_vectors_recall(spark, sf):
    rows = spark.read.parquet(f"/root/testdata/{sf}/embeddings.parquet")
    want = brute_nearest([(r["vec_id"], r["embedding"]) for r in rows.collect()], 20, 20)
    got = {}
    for r in ann.report(rows).collect():
        got.setdefault(r["query_id"], []).append((r["rank"], r["vec_id"], r["score"]))
    assert set(got) == set(want)
    assert all(len(found) == min(20, len(want[q])) for q, found in got.items())
    hit = sum(len({v for _, v, _ in got[q]} & {j for _, j in want[q]}) for q in want)
    assert hit / sum(map(len, want.values())) > 0.92
    for q, found in got.items():
        assert [r for r, _, _ in sorted(found)] == list(range(1, len(found) + 1)) and q not in [v for _, v, _ in found]
        scores = [s for _, _, s in sorted(found)]
        assert scores == sorted(scores, reverse=True)


def test_nearest_vectors_odd_rows(spark):
    nan = float("nan")
    rows = [(0, [1.0, 0.0]), (1, [1.0, 0.0]), (2, [0.0, 2.0]), (3, None), (4, [nan, 1.0]), (5, [0.0, 0.0]), (6, [None, 1.0]), (None, [1.0, 1.0]), (8, [1.0, 0.0]), (20, [1.0, 0.0]), (20, [1.0, 0.0])]
    table = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = sorted((r["query_id"], r["rank"], r["vec_id"], r["score"]) for r in ann.search(table, table.filter("vec_id % 20 = 0"), 3).collect())
    assert got == [(0, 1, 1, 1.0), (0, 2, 8, 1.0), (0, 3, 20, 1.0), (20, 1, 0, 1.0), (20, 2, 1, 1.0), (20, 3, 8, 1.0)]
    assert ann.report(table.limit(0)).count() == 0


# ------------------------------------------------------------------ 2


def test_url_parts_and_rules(spark):
    urls = [(0, None), (1, "no scheme"), (2, "HTTP://WWW.Example.ORG/es/x?q"), (3, "http://example.org/en/12"), (4, "http://a.com#x"), (5, "http://x.com/fr/1?a#b"), (6, "http://notexample.org/es/1"), (7, "x://y://z/de/"), (8, "http://org/")]
    rows = {r["page_id"]: r for r in urlfilter.report(spark.createDataFrame(urls, "page_id long, url string")).collect()}
    parts = {i: (r["host"], r["path"], r["rule"]) for i, r in rows.items()}
    assert parts == {0: ("", "", None), 1: ("", "", None), 2: ("www.example.org", "/es/x", "example.org/es/"), 3: ("example.org", "/en/12", "example.org/en/1"), 4: ("a.com", "", None), 5: ("x.com", "/fr/1", "com/fr/"), 6: ("notexample.org", "/es/1", "org/"), 7: ("y:", "//z/de/", None), 8: ("org", "/", "org/")}
    assert rows[2]["verdict"] == "block" and rows[5]["verdict"] == "allow" and {r["verdict"] for r in rows.values()} <= {"allow", "block"}
    assert urlfilter.report(spark.createDataFrame([], "page_id long, url string")).count() == 0


def test_url_model_learns(spark, data):
    """Trained on half of the urls that rules decide, the model finds the rules' verdict on the other half."""
    pages = urlfilter.split_url(spark.read.parquet("/root/testdata/sf0.1/pages.parquet").select("url")).select("host", "path").distinct()
    labelled = urlfilter.labelled_urls(pages)
    half = cut(labelled.withColumn("k", urlfilter.F.pmod(urlfilter.F.xxhash64("host", "path"), urlfilter.F.lit(2))))
    model = urlfilter.train(half.filter("k = 0"))
    score = urlfilter._logit(urlfilter.features(urlfilter.F.col("host"), urlfilter.F.col("path")), urlfilter._weights(model[1]), model[0])
    right = half.filter("k = 1").select((score > 0).cast("int").alias("p"), "y").collect()
    assert sum(r["p"] == r["y"] for r in right) / len(right) > 0.88


def test_url_model_equals_numpy(spark, data):
    """The descent once more, on the same buckets, with NumPy."""
    pages = spark.read.parquet(f"{data}/pages.parquet")
    urls = urlfilter.split_url(pages)
    rows = urlfilter.labelled_urls(urls).select(urlfilter.features(F.col("host"), F.col("path")).alias("g"), "y").collect()
    x, y = np.zeros((len(rows), urlfilter.BUCKETS)), np.array([r["y"] for r in rows], float)
    for i, r in enumerate(rows):
        x[i, r["g"]] = 1 / np.sqrt(len(r["g"]))
    weight = np.where(y == 1, len(y) / 2 / y.sum(), len(y) / 2 / (1 - y).sum())
    w, m, b, bm = np.zeros(urlfilter.BUCKETS), np.zeros(urlfilter.BUCKETS), 0.0, 0.0
    for _ in range(urlfilter.STEPS):
        d = (1 / (1 + np.exp(-(x @ w + b))) - y) * weight / len(y)
        bm = 0.9 * bm - urlfilter.RATE * d.sum()
        b += bm
        m = 0.9 * m - urlfilter.RATE * (16 * (x.T @ d) + urlfilter.SHRINK * w)
        w = w + m
    for r in urlfilter.judge(urls.select("url", urlfilter.features(F.col("host"), F.col("path")).alias("g"))).collect():
        score = 1 / (1 + np.exp(-(w[r["g"]].sum() / np.sqrt(len(r["g"])) + b)))
        assert r["score"] == pytest.approx(score, abs=1e-6)
        assert r["rule"] is not None or r["verdict"] == ("block" if r["score"] >= 0.5 else "allow")


# ------------------------------------------------------------------ 3


@pytest.fixture(scope="module")
def tokenizer():
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def test_token_counts(spark, whole, tokenizer):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(tokenizer)
    texts = [*ODD, "a<|endoftext|>b" * 3]
    for table in (whole, docs_of(spark, texts)):
        rows = {r["doc_id"]: r for r in tokencount.report(table, tokenizer).collect()}
        for r in table.collect():
            s = r["text"] or ""
            got = rows[r["doc_id"]]
            assert (got["n_bytes"], got["n_tokens"]) == (len(s.encode()), len(t.encode(s, add_special_tokens=False)))


def test_resynchronised_counts_equal_whole(tokenizer, whole):
    _, exact = tokencount.load(tokenizer)
    draw = random.Random(5)
    texts = [r["text"] for r in whole.collect() if len(r["text"]) > 400][:25]
    texts += ["ab" * 2000, " " * 900 + "x" + " " * 900, "a" * 3000, "<|endoftext|>" * 200, "é日本 \n\n " * 300, "it's we'll " * 300, "12345" * 400 + "\n" * 500]
    texts += ["".join(draw.choice(["foo", " ", "  ", "\n", "'s", "9", "é", "<|endoftext|>", "...", "word"]) for _ in range(900)) for _ in range(20)]
    for s in texts:
        want = len(exact.encode(s, add_special_tokens=False))
        for chunk, overlap in ((200, 40), (333, 64), (1000, 33)):
            assert tokencount.count_long(s, exact, chunk, overlap) == want, (s[:60], chunk)


def test_an_endless_word_is_encoded_a_few_times_at_most(tokenizer):
    _, exact = tokencount.load(tokenizer)

    class Counting:
        done = 0

        def encode(self, text, **options):
            Counting.done += len(text)
            return exact.encode(text, **options)

    draw = random.Random(8)
    for n in (20_000, 80_000):
        Counting.done = 0
        s = "so " + "".join(draw.choice("abcdefghij") for _ in range(n)) + " it ends " * 50
        assert tokencount.count_long(s, Counting(), 1000, 64) == len(exact.encode(s, add_special_tokens=False))
        assert Counting.done < 14 * len(s)


# ------------------------------------------------------------------ 4


def brute_difference(rows):
    """A function from a list of words to the difference of their log-likelihoods, from plain dictionaries."""
    pairs, words, contexts = ([{}, {}] for _ in range(3))
    for s, toxic in rows:
        w = decontam.normalised_words(s)
        for v, x in set(zip([None, *w], w)):
            for table, key in ((pairs, (v, x)), (words, x), (contexts, v)):
                table[toxic][key] = table[toxic].get(key, 0) + 1

    def matched(tables, d):
        total = [sum(t.values()) for t in tables]
        share = sum(min(n, d) for n in tables[1].values()) / total[1]
        ordinary = toxicity.matching_discount([(n, 1) for n in tables[0].values()], total[0], share)
        assert sum(min(n, ordinary) for n in tables[0].values()) / total[0] == pytest.approx(share, abs=1e-6)
        return [ordinary, d], total

    d1, total = matched(words, toxicity.DISCOUNT[1])
    d2 = [toxicity.DISCOUNT[0] * total[0] / total[1], toxicity.DISCOUNT[0]]
    every = {*words[0], *words[1]}
    own = lambda t, key, d: toxicity.KEEP * max(t.get(key, 0) - d, 0)
    common = {w: min(words[c].get(w, 0) / total[c] for c in (0, 1)) for w in every}
    shared = {w: (1 - toxicity.FLOOR) * common[w] / sum(common.values()) + toxicity.FLOOR / len(every) for w in every}
    uni = [{w: own(words[c], w, d1[c]) / total[c] + (1 - sum(own(words[c], x, d1[c]) for x in every) / total[c]) * shared[w] for w in every} for c in (0, 1)]
    assert all(sum(p.values()) == pytest.approx(1, abs=1e-6) for p in uni)
    pair_keys = {*pairs[0], *pairs[1]}

    def given(c, v, w):
        n = contexts[c].get(v, 0)
        both = lambda x: min(pairs[k].get((v, x), 0) / contexts[k][v] if v in contexts[k] else 0 for k in (0, 1))
        all_both = sum(both(x) for y, x in pair_keys if y == v)
        lower = toxicity.LOWER_ORDER if all_both else 1
        free = 1 - (sum(own(pairs[c], (y, x), d2[c]) for y, x in pair_keys if y == v) / n if n else 0)
        return (own(pairs[c], (v, w), d2[c]) / n if n else 0) + free * ((1 - lower) * (both(w) / all_both if all_both else 0) + lower * uni[c][w])

    for c in (0, 1):
        for v in contexts[c]:
            assert sum(given(c, v, w) for w in every) == pytest.approx(1, abs=1e-6)
    # a word never met has the same probability in both classes: only its context tells
    free = lambda c, v: given(c, v, w0) / uni[c][w0] if (w0 := next((w for w in every if (v, w) not in pair_keys), None)) else 1.0
    return lambda ws: sum(np.log((given(1, v, w) if w in every else free(1, v)) / (given(0, v, w) if w in every else free(0, v))) for v, w in zip([None, *ws], ws))


def test_toxicity_score_equals_brute_force(spark, monkeypatch):
    monkeypatch.setattr(toxicity, "DISCOUNT", (2.0, 3.0))
    monkeypatch.setattr(toxicity, "LEAST", 1e-12)
    rows = [("You idiot abab idiot", 1), ("the cat", 1)] * 4 + [("the abab cat", 0), ("a cat ab", 0)] * 9 + [("idiot cat \u00e9", 1)] * 2 + [("the cat", 0)] * 5
    model = toxicity.Model(toxicity.fit(spark.createDataFrame(rows, "text string, toxic int")), 1.0, 0.0)
    brute = brute_difference(rows)
    texts = ["You idiot", "the cat", "THE abab cat ab", "a", "", None, "cat idiot idiot", "never met the cat", "a cat ab never", "x" * 1_000_000 + " idiot"]
    got = model.score(spark.createDataFrame([(i, t, 0.5) for i, t in enumerate(texts)], "__n long, text string, score double")).collect()
    for r in got:
        w = decontam.normalised_words(r["text"])
        assert r["score"] == pytest.approx(1 / (1 + np.exp(-brute(w) / len(w))) if w else 0.5, abs=1e-6), r["text"]
    assert len(got) == len(texts) and list(got[0].asDict()) == ["__n", "text", "score", "predicted"]


def test_both_levels_equal_brute_force(spark, monkeypatch):
    rows = [("You idiot abab idiot", 1), ("the cat", 1)] * 4 + [("the abab cat", 0), ("a cat ab", 0)] * 9 + [("idiot cat \u00e9", 1), ("once met", 1)] + [("the cat", 0)] * 5
    levels = (toxicity.WHOLE, ((3.0, 3.0), 0.01))
    table = toxicity.fit(spark.createDataFrame(rows, "text string, toxic int"), levels)
    texts = ["You idiot", "the cat", "once met", "THE abab cat ab", "cat idiot idiot", "never met the cat"]
    for j, (discount, keep) in enumerate(levels):
        monkeypatch.setattr(toxicity, "DISCOUNT", discount)
        monkeypatch.setattr(toxicity, "KEEP", keep)
        brute = brute_difference(rows)
        model = toxicity.Model(table.selectExpr("key", f"v{j} value"), 1.0, 0.0)
        for r in model.differences(spark.createDataFrame([(t,) for t in texts], "text string"), "text").collect():
            w = decontam.normalised_words(r["text"])
            assert r["__x"] == pytest.approx(brute(w) / len(w), abs=1e-6), r["text"]
    pairs = {p for s, _ in rows for w in [decontam.normalised_words(s)] for p in zip([None, *w], w)}
    seen = {p for s, y in rows if y for w in [decontam.normalised_words(s)] for p in zip([None, *w], w)}
    assert seen < pairs and table.filter("not of_word and v0 != 0").count() >= len(seen)  # each pair of one toxic document tells


def test_toxicity_tells_by_pairs_of_a_few_documents(spark):
    draw, words = random.Random(4), [f"w{i}" for i in range(30)]
    rows = []
    for i in range(240):
        phrase = "fox red" if i % 7 == 0 else "red fox"
        rows.append((i, " ".join([draw.choice(words), draw.choice(words), phrase, draw.choice(words)])))
    labels = spark.createDataFrame([(i, 1, int(i % 7 == 0)) for i, _ in rows], "doc_id long, quality int, toxic int")
    scores = toxicity.report(spark.createDataFrame(rows, "doc_id long, text string"), labels).filter("held_out").collect()
    bad, good = ([r["score"] for r in scores if (r["doc_id"] % 7 == 0) == toxic] for toxic in (True, False))
    assert len(bad) > 3 and min(bad) > max(good)


def test_toxicity_finds_held_out(spark):
    documents, labels = (spark.read.parquet(f"/root/testdata/sf0.1/{t}.parquet") for t in ("documents", "labels"))
    rows = toxicity.report(documents, labels)
    marked = rows.join(labels.filter("toxic is not null"), "doc_id").filter("held_out").select("score", "predicted", "toxic").collect()
    bad = [r for r in marked if r["toxic"] == 1]
    good = [r for r in marked if r["toxic"] == 0]
    print("recall", sum(r["predicted"] for r in bad) / len(bad), "false alarms", sum(r["predicted"] for r in good) / len(good))
    assert sum(r["predicted"] for r in bad) / len(bad) > 0.75 and sum(r["predicted"] for r in good) / len(good) < 0.01
    assert all(0 <= r["score"] <= 1 for r in marked) and rows.count() == documents.count()


def test_toxicity_odd_rows(spark):
    docs = docs_of(spark, ODD, ids=[None, *range(len(ODD) - 1)])
    for labels in ([], [(1, 1, 1)], [(i, 1, i % 2) for i in range(9)] + [(3, None, None), (None, 1, 1)]):
        rows = toxicity.report(docs, spark.createDataFrame(labels, "doc_id long, quality int, toxic int")).collect()
        assert len(rows) == len(ODD) and all(0 <= r["score"] <= 1 and r["held_out"] is not None for r in rows)
    assert toxicity.report(docs.limit(0), spark.createDataFrame([(1, 1, 1), (2, 1, 0)], "doc_id long, quality int, toxic int")).count() == 0
    left = toxicity.remove_toxic(docs, spark.createDataFrame([], "doc_id long, quality int, toxic int"))
    assert left.columns == docs.columns and left.count() == len(ODD)


def test_model_in_slices_scores_alike(spark, monkeypatch):
    data = "/root/testdata/sf0.01"
    whole = spark.read.parquet(f"{data}/documents.parquet")
    model = toxicity.train(whole, spark.read.parquet(f"{data}/labels.parquet"))
    monkeypatch.setattr(toxicity, "SLICE_WORDS", model.table.count() // 2)
    sliced = toxicity.Model(model.table, model.slope, model.bias)
    assert model.parts == 1 and sliced.parts in (2, 3)
    one, several = ({r["doc_id"]: r["score"] for r in m.score(whole).collect()} for m in (model, sliced))
    assert one.keys() == several.keys() and max(abs(one[k] - several[k]) for k in one) < 1e-4


# ------------------------------------------------------------------ 5


def brute_fingerprint(s):
    import xxhash

    words = SPACE.findall("".join(c.lower() if "A" <= c <= "Z" else c for c in s or ""))
    shingles = [" ".join(words[i : i + 3]) for i in range(len(words) - 2)] if len(words) >= 3 else [" ".join(words)] if words else []
    votes = [0] * 64
    for x in shingles:
        h = xxhash.xxh64_intdigest(x.encode(), 42)
        votes = [v + (h >> b & 1) for b, v in enumerate(votes)]
    return sum(1 << b for b, v in enumerate(votes) if 2 * v > len(shingles))


def brute_groups(prints):
    """Least index that links of 3 bits or fewer lead to."""
    n, root = len(prints), list(range(len(prints)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(n):
        for j in range(i):
            if (prints[i] ^ prints[j]).bit_count() <= 3:
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    return [find(i) for i in range(n)]


def test_simhash(spark, whole):
    for table in (whole, docs_of(spark, ODD)):
        rows = sorted(table.collect(), key=lambda r: r["doc_id"])
        prints = [brute_fingerprint(r["text"]) for r in rows]
        want = [(r["doc_id"], f"{p:016x}", rows[g]["doc_id"]) for r, p, g in zip(rows, prints, brute_groups(prints), strict=True)]
        assert sorted(map(tuple, simhash.report(table).collect())) == want
        kept = simhash.keep_one(table)
        assert sorted(r["doc_id"] for r in kept.collect()) == sorted({g for _, _, g in want}) and kept.columns == table.columns
    assert simhash.report(docs_of(spark, [])).count() == 0 and simhash.keep_one(docs_of(spark, [])).count() == 0
    odd = docs_of(spark, ["a b c d", "a b c d", "a b c d", "q"], ids=[None, None, 7, 7])
    assert sorted((r["doc_id"], r["text"]) for r in simhash.keep_one(odd).collect()) == [(7, "a b c d"), (7, "q")]


@pytest.mark.parametrize("block", [20_000, 8])
def test_links_connect_all_pairs(spark, block):
    draw = random.Random(3)
    prints = []
    for _ in range(12):
        base = draw.getrandbits(64)
        for _ in range(12):
            x = base
            for b in draw.sample(range(64), draw.choice([0, 1, 2, 3, 4])):
                x ^= 1 << b
            prints.append(x)
    prints = sorted(set(prints))
    signed = [x - (1 << 64) if x >> 63 else x for x in prints]
    got = {r["node"]: r["component"] for r in components(simhash.links(spark.createDataFrame([(x,) for x in signed], "fp long"), block=block)).collect()}
    groups = {}
    for i, g in enumerate(brute_groups(prints)):
        groups.setdefault(g, []).append(signed[i])
    for members in groups.values():
        assert len({got.get(m, m) for m in members}) == 1
    assert len({got.get(m, m) for m in signed}) == len(groups)


# ------------------------------------------------------------------ 6


def test_sharding(spark, whole):
    for table, n in ((whole, 40), (docs_of(spark, ODD * 5), 7), (docs_of(spark, ODD[:3]), 40)):
        rows = sharding.report(table, n).collect()
        texts = {}
        for r in table.collect():
            texts.setdefault(r["doc_id"], []).append(r)
        assert len(rows) == table.count()
        by = {}
        for r in rows:
            by.setdefault(r["shard"], []).append(r["slot"])
            raw = (texts[r["doc_id"]][0]["text"] or "").encode()
            assert (r["size"], r["text_crc32"], r["law"], r["grown_shard"]) == (len(raw) + 16, zlib.crc32(raw), "rows", None)
        assert all(sorted(s) == list(range(len(s))) for s in by.values()) and set(by) <= set(range(n))
        sizes = [len(by.get(i, [])) for i in range(n)]
        assert max(sizes) - min(sizes) <= 1
    assert sharding.report(docs_of(spark, []), 40).count() == 0
    # every shard holds the mixture
    sharded = sharding.shard(docs_of(spark, ["t"] * 400, ["a", "a", "a", "b"]), 10).groupBy("shard", "source").count().collect()
    assert all(abs(r["count"] - (30 if r["source"] == "a" else 10)) <= 2 for r in sharded)


# ------------------------------------------------------------------ 7


def brute_removed(rows, match):
    seen, out = {}, {}
    ordered = sorted(rows, key=lambda r: (r[0] is None, r[0]))
    for i, s in ordered:
        raw = (s or "").encode()
        gone = np.zeros(len(raw), bool)
        for a in range(len(raw) - match + 1):
            key = raw[a : a + match]
            if key in seen:
                gone[a : a + match] = True
            else:
                seen[key] = (i, a)
        kept = bytes(b for b, g in zip(raw, gone, strict=True) if not g)
        runs = int(np.sum(gone & ~np.r_[False, gone[:-1]])) if len(gone) else 0
        out[i] = (len(raw), int(gone.sum()), runs, hashlib.sha256(kept).hexdigest())
    return out


def test_suffix_array():
    draw = random.Random(1)
    for n in [1, 2, 3, 4, 5, 7, 8, 50, 51, 52, 300]:
        for k in (1, 2, 5):
            s = np.array([draw.randint(1, k) for _ in range(n)])
            assert suffixdedup.suffix_array(s).tolist() == sorted(range(n), key=lambda i, s=s: s[i:].tolist())


def test_suffix_array_to_a_depth():
    draw = random.Random(4)
    for _ in range(60):
        words = ["".join(draw.choice("ab") for _ in range(draw.choice([5, 9, 40]))) for _ in range(4)]
        s = np.array([ord(c) for c in "".join(draw.choice(words) for _ in range(draw.randint(2, 120)))])
        order = suffixdedup.suffix_array(s, 20)
        heads = [s[i : i + 20].tolist() for i in order]
        assert sorted(order.tolist()) == list(range(len(s))) and heads == sorted(heads)


def test_repeats_removed(spark, whole):
    got = {r["doc_id"]: tuple(r)[1:] for r in suffixdedup.report(whole).collect()}
    assert got == brute_removed([(r["doc_id"], r["text"]) for r in whole.collect()], suffixdedup.MATCH)


@pytest.mark.parametrize(("crowd", "hot"), [(4000, 64), (2, 64), (4000, 1), (4000, 0)])
def test_repeats_removed_odd(spark, crowd, hot):
    draw = random.Random(2)
    line = "".join(draw.choice("abcdefgh ") for _ in range(140))
    texts = [*ODD, line, line + "x" * 50, "q" + line[:120], line * 3, *[f"{draw.random()} {line} {draw.random()}" * 2 for _ in range(12)], line[5:105], "é" * 70, "zé" + "é" * 60]
    rows = list(enumerate(texts))
    done = suffixdedup.remove_repeats(docs_of(spark, texts), crowd=crowd, hot=hot).collect()
    want = brute_removed(rows, suffixdedup.MATCH)
    for r in done:
        n, removed, runs, sha = want[r["doc_id"]]
        assert (n - len(r["__kept"]), len(r["__spans"]) // 2, hashlib.sha256(r["__kept"]).hexdigest()) == (removed, runs, sha), r["doc_id"]
    assert suffixdedup.report(docs_of(spark, [])).count() == 0
    assert suffixdedup.report(docs_of(spark, [line, line], ids=[None, 3])).orderBy("n_removed").collect()[1]["doc_id"] is None


# ------------------------------------------------------------------ 8


def brute_targets(sizes, weights=(5, 2, 1), share=1.5, cap=2.0):
    names = sorted(sizes, key=lambda s: (s is None, (s or "").encode()))
    weight = {s: weights[i % 3] for i, s in enumerate(names)}
    target, open_, left = {}, set(names), share * sum(sizes.values())
    while open_:
        total = sum(weight[s] for s in open_)
        over = [s for s in open_ if left * weight[s] / total > cap * sizes[s]]
        if not over:
            target |= {s: left * weight[s] / total for s in open_}
            break
        for s in over:
            target[s] = cap * sizes[s]
            open_.remove(s)
        left = share * sum(sizes.values()) - sum(target.values())
    return target


def test_mixing(spark, whole):
    for table in (whole, docs_of(spark, ODD * 20)):
        sizes = {}
        for r in table.collect():
            sizes[r["source"]] = sizes.get(r["source"], 0) + len(SPACE.findall(r["text"] or ""))
        want = brute_targets(sizes)
        source = {}
        for r in table.collect():
            source.setdefault(r["doc_id"], []).append(r["source"])
        rows = mixing.report(table).collect()
        assert len(rows) == table.count() and sorted(map(tuple, rows)) == sorted(map(tuple, mixing.report(table.repartition(7)).collect()))
        assert [r for r in rows if not 0 <= r["taken"] <= 2 * r["size"]] == []
        for s, target in want.items():
            mine = [r for r in rows if abs(r["target"] - target) < 1e-6 and r["source_size"] == sizes[s]]
            assert mine
        total = sum(r["taken"] for r in rows)
        assert abs(total - 1.5 * sum(sizes.values())) / max(1, sum(sizes.values())) < 0.2
    assert mixing.report(docs_of(spark, [])).count() == 0
    mixed = mixing.repeat_rows(whole)
    assert mixed.groupBy("doc_id").count().join(mixing.report(whole).filter("size > 0").selectExpr("doc_id", "taken / size as n"), "doc_id", "full").filter("coalesce(count, 0) <> coalesce(n, 0)").count() == 0
    assert mixed.columns == whole.columns and mixed.count() > 0


def test_mixing_includes_by_the_odds(spark):
    """Over many sources of the same sizes (draws differ by id) a document is included about as often as its odds ask."""
    sizes, sources = [*range(1, 61), 2000], 300
    rows = spark.createDataFrame([(s * 100 + i, f"s{s:04d}", n) for s in range(sources) for i, n in enumerate(sizes)], "doc_id long, source string, size long")
    for inclusion, odds in ((None, lambda n: n), (F.lit(1.0), lambda n: 1), (F.col("size") % 4, lambda n: n % 4 if n < 2000 else 0)):
        out = mixing.mix(rows, doc_id="doc_id", source="source", size="size", inclusion=inclusion, weights=(1,), share=0.7, cap=2)
        got = {r["size"]: r["n"] / sources for r in out.groupBy("size").agg(F.sum("_copies").alias("n")).collect()}
        low, high = 0.0, 100.0
        for _ in range(60):  # c of p = min(1, c * odds) by bisection
            c = (low + high) / 2
            low, high = (c, high) if sum(min(1, c * odds(n)) * n for n in sizes) < 0.7 * sum(sizes) else (low, c)
        want = {n: min(1, c * odds(n)) for n in sizes}
        if inclusion is None:
            assert want[2000] == 1 and all(got[n] == pytest.approx(want[n], abs=0.12) for n in sizes)
        assert all(got[n] == 0 for n in sizes if want[n] == 0)
        assert all(got[n] == 1 for n in sizes if want[n] > 1 - 1e-9)


# ------------------------------------------------------------------ 9


def test_warc_round_trip(spark, data, tmp_path):
    pages = spark.read.parquet(f"{data}/pages.parquet")
    odd = [(None, None, None), (1, "http://x/ü\r\n", ""), (2, "http://y", "é" * 60), (3, "http://z", "é" * 60), (3, "http://z", "é" * 60), (None, "u", "é" * 60), (9, "a", "short"), (10, "b", "short"), (11, "c", "\x1f\x8b\x08" * 50)]
    for k, table in enumerate((pages, spark.createDataFrame(odd, "page_id long, url string, html string"))):
        rows = table.collect()
        least = {}
        for r in rows:
            p = (r["html"] or "").encode()
            if r["page_id"] is not None:
                least[p] = min(least.get(p, r["page_id"]), r["page_id"])
        want = []
        for r in rows:
            p = (r["html"] or "").encode()
            first = least.get(p)
            again = len(p) >= 100 and first is not None and (r["page_id"] is None or first < r["page_id"])
            want.append((r["page_id"], len(p), hashlib.sha256(p).hexdigest(), "revisit" if again else "response", first if again else None))
        key = lambda t: tuple(str(x) for x in t)
        folder = f"file://{tmp_path}/w{k}"
        assert sorted(map(tuple, warc.report(table, folder).collect()), key=key) == sorted(want, key=key)
        for size in (97, 1000, 1 << 30):  # ranges of any size read every record once
            got = sorted((r["file"], r["offset"]) for r in warc.read_archives(spark, folder, size).select("file", "offset").collect()) if k or size > 97 else None
            assert got is None or len(got) == len(set(got)) == len(rows)
    assert warc.report(pages.limit(0), f"file://{tmp_path}/none").count() == 0


def test_warc_keeps_pages_with_long_urls(spark, tmp_path):
    url = "http://x/" + "".join(random.Random(4).choices("abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789", k=3_000_000))
    pages = spark.createDataFrame([(1, url, "long"), (2, "http://y", "short")], "page_id long, url string, html string")
    assert {r["page_id"]: r["payload_bytes"] for r in warc.report(pages, f"file://{tmp_path}/long").collect()} == {1: 4, 2: 5}


# ------------------------------------------------------------------ 10


def brute_hits(docs, items):
    words = decontam.normalised_words
    wanted = {}
    for i, s in items:
        w = words(s)
        n = min(10, len(w))
        for a in range(len(w) - n + 1 if n else 0):
            wanted.setdefault(tuple(w[a : a + n]), set()).add(str(i))
    out = {}
    for i, s in docs:
        w, hit, names = words(s), set(), set()
        for key, ids in wanted.items():
            for a in range(len(w) - len(key) + 1):
                if tuple(w[a : a + len(key)]) == key:
                    hit |= set(range(a, a + len(key)))
                    names |= ids
        out[i] = (len(w), len(hit), len(names), hashlib.sha256(",".join(sorted(names)).encode()).hexdigest(), bool(hit))
    return out


@pytest.mark.parametrize("slices", [200_000, 3])
def test_decontamination(spark, monkeypatch, slices):
    monkeypatch.setattr(decontam, "SLICE_WINDOWS", slices)
    ten = "one two three four five six seven eight nine ten"
    items = [(1, ten + " eleven"), (2, "Rare-WORD"), (3, None), (4, "..."), (12, ten), (5, "Ünï çödé")]
    texts = [None, "", ten.upper(), f"x {ten}! eleven {ten}", "one two three", "a rare word", "rare, wordy", f"{ten[:-1]}", "rare", "word", "ünï çödé", "Ünï çödé x", "rare word rare word"]
    bench = spark.createDataFrame(items, "item_id long, text string")
    table = docs_of(spark, texts)
    assert {r["doc_id"]: tuple(r)[1:] for r in decontam.report(table, bench).collect()} == brute_hits(list(enumerate(texts)), items)
    clean = decontam.remove_documents(table, bench)
    assert clean.columns == table.columns and sorted(r["doc_id"] for r in clean.collect()) == [i for i, v in brute_hits(list(enumerate(texts)), items).items() if not v[-1]]
    trimmed = {r["doc_id"]: r["text"] for r in decontam.remove_spans(table, bench).collect()}
    assert trimmed[3] == "x ! eleven " or "one" not in trimmed[3]
    assert trimmed[5] == "a " and trimmed[4] == "one two three"
    assert decontam.report(table, bench.limit(0)).filter("contaminated").count() == 0


def test_decontamination_of_table(spark, whole, data):
    bench = spark.read.parquet(f"{data}/benchmark.parquet")
    got = {r["doc_id"]: tuple(r)[1:] for r in decontam.report(whole, bench).collect()}
    rows = [(r["doc_id"], r["text"]) for r in whole.collect()]
    assert got == brute_hits(rows, [tuple(r) for r in bench.collect()])


# ------------------------------------------------------------------ all

NAMES = ["doc", "th", "__words", "__spans", "__items", "__kept", "score", "predicted", "host", "path", "rule", "c0", "c1", "shard", "slot", "bucket", "kind", "blob", "_words", "_key", "_u", "fp", "component", "name"]


def clashing(spark):
    """A null id, null, empty and very long texts, ties and repeated rows, beside columns named like inner ones."""
    line = "a line of more than one hundred bytes that comes again and again, one two three four five six seven eight nine ten"
    texts = [None, "", "w " * 300_000 + line, line, line, line + " x", "x" * 400_000, "you are here"]
    ids = [1, None, 3, 4, 4, 5, 6, None]
    rows = [(i, t, "en", None if k % 3 else "s", 1, *[k] * len(NAMES)) for k, (i, t) in enumerate(zip(ids, texts, strict=True))]
    return spark.createDataFrame(rows, SCHEMA + "".join(f", `{n}` long" for n in NAMES))


@pytest.mark.parametrize("empty", [False, True])
def test_inner_names_nulls_and_long_texts(spark, empty, tokenizer):
    docs = clashing(spark)
    docs = docs.limit(0) if empty else docs
    n = docs.count()
    labels = spark.createDataFrame([(1, 1, 1), (4, 1, 0), (6, 1, 1), (5, 1, 0)], "doc_id long, quality int, toxic int")
    items = spark.createDataFrame([(7, "one two three four five six seven eight nine ten"), (7, "you are here"), (None, "one two three four five six seven eight nine ten"), (8, None)], "item_id long, text string")
    done = suffixdedup.remove_repeats(docs)
    assert done.columns[: len(docs.columns)] == docs.columns and done.count() == n and suffixdedup.report(docs).count() == n
    hits = decontam.find_hits(docs, items)
    assert set(hits.columns) == set(docs.columns) and hits.count() == n
    left = decontam.remove_documents(docs, items)
    assert left.columns == docs.columns and left.count() == (0 if empty else 3) and decontam.remove_spans(docs, items).count() == n
    if not empty:
        found = [tuple(r) for r in decontam.report(docs, items).select("doc_id", "n_items").collect()]
        assert sorted(found, key=str) == sorted([(1, 0), (None, 0), (3, 2), (4, 2), (4, 2), (5, 2), (6, 0), (None, 1)], key=str)
    assert toxicity.remove_toxic(docs, labels).columns == docs.columns
    scored = toxicity.train(docs, labels).score(docs)
    assert scored.count() == n and scored.columns[-2:] == ["score", "predicted"]
    assert simhash.keep_one(docs).columns == docs.columns and simhash.report(docs).count() == n
    sharded = sharding.shard(docs, 3)
    assert sharded.count() == n and sharding.report(docs, 3).count() == n
    mixed = mixing.repeat_rows(docs)
    assert mixed.columns == docs.columns and mixing.report(docs).count() == n and mixed.count() >= (0 if empty else 1)
    counted = tokencount.count_tokens(docs, tokenizer)
    assert counted.count() == n and counted.columns[:-1] == docs.columns
    judged = urlfilter.judge(docs.withColumn("url", F.col("text")).withColumn("verdict", F.lit(1)))
    assert judged.count() == n and judged.columns.count("host") == judged.columns.count("verdict") == 1


def test_archives_of_hot_payloads(spark, monkeypatch, tmp_path):
    monkeypatch.setattr(warc, "HOT", 3)
    pages = spark.createDataFrame([(i, f"http://h/{i}", "p" * 200 if i % 2 else "q" * 150 if i % 4 else None, i) for i in range(40)], "page_id long, url string, html string, payload long")
    rows = {r["page_id"]: r for r in warc.report(pages, f"file://{tmp_path}/hot").collect()}
    assert len(rows) == 40 and all(rows[i]["refers_to"] == (None if i == 1 else 1) and rows[i]["payload_bytes"] == 200 for i in range(1, 40, 2))
    assert all(rows[i]["refers_to"] == (None if i == 2 else 2) and rows[i]["payload_bytes"] == 150 for i in range(2, 40, 4))
    assert {rows[i]["payload_bytes"] for i in range(0, 40, 4)} == {0} and rows[0]["record_type"] == "response"
