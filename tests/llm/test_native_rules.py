"""Decontamination, quality rules and URL filters against brute force."""

import hashlib
import random
import re
from collections import Counter

from tauprobe.llm import decontaminate, quality_rules, queries, url_filters

SF = "/root/testdata/sf0.001"


def low(text):
    return "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "")


def bench_words(text):
    return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", low(text))


def brute_contamination(docs, items, width=13):
    windows = {}
    for item, text in items:
        w = bench_words(text)
        n = min(width, len(w))
        for i in range(len(w) - n + 1 if n else 0):
            windows.setdefault(tuple(w[i : i + n]), set()).add(item)
    out = []
    for doc, text in docs:
        w, hit, found = bench_words(text), set(), set()
        for n in {len(k) for k in windows}:
            for i in range(len(w) - n + 1):
                if k := windows.get(tuple(w[i : i + n])):
                    hit |= set(range(i, i + n))
                    found |= k
        names = ",".join(sorted(str(i) for i in found if i is not None))
        listed = sum(i is not None for i in found)
        out.append((doc, len(w), len(hit), listed, hashlib.sha256(names.encode()).hexdigest(), bool(hit) and 20 * len(hit) >= len(w)))
    return sorted(out, key=str)


def test_contamination_query_equals_brute_force(spark):
    docs = [tuple(r) for r in spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text").collect()]
    items = [tuple(r) for r in spark.read.parquet(f"{SF}/benchmark.parquet").select("item_id", "text").collect()]
    got = sorted((tuple(r)[:6] for r in queries.op1_decontaminate(spark, SF).collect()), key=str)
    want = brute_contamination(docs, items)
    assert got == want and sum(r[5] for r in want) > 0


def test_contamination_odd_rows(spark):
    rng = random.Random(2)
    word = lambda: rng.choice(["a", "b", "É", "é", "K", "x1"])
    items = [(i, " ".join(word() for _ in range(rng.choice([2, 5, 13, 14, 20])))) for i in range(12)] + [(7, "a b"), (None, "é a"), (20, ""), (21, None), (22, "\u212a A")]
    docs = [(i, rng.choice(["-", " ", "\n"]).join(word() for _ in range(rng.choice([0, 1, 5, 60])))) for i in range(30)] + [(3, items[2][1]), (3, items[2][1]), (None, None), (40, "q a b " * 30_000)]
    df = spark.createDataFrame([(*d, "x", 1) for d in docs], "doc_id bigint, text string, term string, pos int")
    bench = spark.createDataFrame(items, "item_id bigint, text string")
    got = sorted((tuple(r) for r in decontaminate.contamination(df, bench, 13).collect()), key=str)
    assert got == brute_contamination(docs, items)
    assert decontaminate.contamination(df.limit(0), bench).count() == 0
    assert decontaminate.contamination(df, bench.limit(0)).where("n_hit > 0 or contaminated").count() == 0


def brute_near(docs, asked, span):
    """(id, item, first) by trying every stretch of words around every place of the rarest term."""
    texts = [(d, bench_words(t)) for d, t in docs]
    total = Counter(w for _, ws in texts for w in ws)
    out = []
    for item, text in asked:
        want = Counter(bench_words(text))
        if not want or item is None or sum(want.values()) > span or not all(total[w] for w in want):
            continue
        rarest = min(want, key=lambda w: (total[w], w.encode()))
        for d, ws in texts:
            for p, w in enumerate(ws):
                if w == rarest and any(not want - Counter(ws[s : s + span]) for s in range(max(0, p - span + 1), p + 1)):
                    out.append((d, item, p))
    return sorted(out, key=str)


def test_near(spark):
    rng = random.Random(12)
    docs = [(1, "a x x b x c"), (2, "a " + "x " * 30 + "b c"), (3, "c b a"), (3, "b a c a"), (None, "c a b"), (5, None), (6, ""), (7, "a b " * 20_000 + "c"), (8, "b x x a x x b")]
    docs += [(20 + i, " ".join(rng.choice("abcxyz") for _ in range(rng.randint(0, 40)))) for i in range(30)]
    asked = [(9, "a b c"), (10, "a a b"), (11, "b b a"), (12, ""), (13, None), (None, "a b"), (14, "q a"), (15, "a " * 9), (16, "c"), (9, "x y")]
    df = spark.createDataFrame([(*d, "x", 1) for d in docs], "doc_id bigint, text string, term string, pos int")
    index = decontaminate.build_index(df)
    items = spark.createDataFrame(asked, "item_id bigint, text string")
    for span in (3, 4, 6):
        got = sorted((tuple(r) for r in decontaminate.near(index, items, span).collect()), key=str)
        assert got == brute_near(docs, asked, span) and got
    assert decontaminate.near(index, items.limit(0)).count() == 0
    assert decontaminate.near(decontaminate.build_index(df.limit(0)), items).count() == 0


def brute_features(text):
    words = re.findall(r"[^\x20\x09-\x0D]+", text or "")
    lines = [x for x in (text or "").split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    grams = Counter(tuple(words[i : i + 3]) for i in range(len(words) - 2))
    hit = {k for i in range(len(words) - 2) if grams[tuple(words[i : i + 3])] > 1 for k in range(i, i + 3)}
    return len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", text or "")), len(lines) - len(set(lines)), len(hit)


def test_quality_features(spark):
    docs = [tuple(r) for r in spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text").collect()]
    got = {r.doc_id: r for r in queries.op7_quality_rules(spark, SF).collect()}
    for d, text in docs:
        r, f = got[d], brute_features(text)
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == f
        assert r.base_failed == (f[0] < 50 or 100 * f[4] > 50 * f[0]) and not (r.base_failed and r.kept)


def test_quality_odd_rows(spark):
    odd = [None, "", " \n\t", "a", "a b", "a b c", "a b c a b c", "x x x x x x", "\x0b\x0ca\x1cb\u00a0é #|\n\nq\nq\n q", "w v u " * 40_000, "\ud7ff\U0001f600 " * 9]
    df = spark.createDataFrame([(i, t, None, 1, "k") for i, t in enumerate(odd)] + [(3, "a", "en", 1, "k"), (None, "a", "en", 1, "k")], "doc_id bigint, text string, lang string, words int, keys string")
    got = [(r.id, (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words)) for r in quality_rules.features(df).collect()]
    assert sorted(got, key=str) == sorted([(i, brute_features(t)) for i, t in enumerate(odd)] + [(3, brute_features("a")), (None, brute_features("a"))], key=str)
    nothing = spark.createDataFrame([], "doc_id bigint, quality int")
    assert {r.kept for r in quality_rules.judge(df, nothing).where("n_words >= 50").collect()} == {False}  # that one repeats itself
    assert quality_rules.judge(df.limit(0), nothing).count() == 0


COUNTED = "id bigint, stratum string, n_words bigint, word_chars bigint, n_symbols bigint, n_lines bigint, n_dup_lines bigint, n_repeat_words bigint"


def drawn(seed, n):
    """Feature rows and labels: two large strata, and a small one whose good rows look like the others' bad ones."""
    rng = random.Random(seed)
    rows, labels = [], []
    for i in range(n):
        bad, stratum = rng.random() < 0.1, "xx" if i % 150 == 0 else "en" if i % 3 else "fr"
        rows.append((i, stratum, 100, 500, rng.randint(5, 60) if bad or stratum == "xx" else rng.randint(0, 10), 10, 0, 0))
        labels.append((i, 1 - int(bad)))
    return rows, labels


def test_cutoffs_keep_their_promise(spark):
    """On the rows they are learnt from and on fresh ones, in every stratum; a stratum too small for the bound has no cutoff."""
    rows, labels = drawn(4, 9000)
    counted = spark.createDataFrame(rows, COUNTED)
    known = spark.createDataFrame([*labels, (0, None), (None, 1)], "doc_id bigint, quality int")
    cuts = quality_rules.cutoffs(counted, known, quality_rules.Risk(alpha=0.05)).collect()
    assert {(r.stratum, r.rule) for r in cuts} == {("en", "symbols"), ("fr", "symbols")}
    for seed in (4, 5, 6):
        rows, labels = drawn(seed, 9000)
        kept = {r.id: r.kept for r in quality_rules.verdicts(spark.createDataFrame(rows, COUNTED), spark.createDataFrame(cuts)).collect()}
        for stratum in ("en", "fr", "xx"):
            good = [r[0] for r, (_, q) in zip(rows, labels) if q and r[1] == stratum]
            assert sum(not kept[i] for i in good) <= 0.05 * len(good)
        bad = [i for i, q in labels if not q]
        assert sum(not kept[i] for i in bad) > 0.6 * len(bad)


def test_exact_binomial_bound(spark):
    from math import comb

    for n, alpha, level in ((0, 0.1, 0.05), (10, 0.01, 0.05), (400, 0.02, 0.01), (1000, 0.05, 0.001)):
        cdf, best = 0.0, -1
        for k in range(n + 1):
            cdf += comb(n, k) * alpha**k * (1 - alpha) ** (n - k)
            if cdf > level:
                break
            best = k
        from pyspark.sql import functions as F

        row = spark.range(1).select(quality_rules.allowed(F.lit(n).cast("bigint"), alpha, F.lit(level)).alias("k")).first()
        assert row.k == best


def test_url_odd_rows(spark):
    urls = [None, "", "no host", "http://A.Example.COM/en/7x?u=1", "http://example.com", "http://example.com?x://y/en/", "ftp://net/de/#q", "http://bnet/de/", "x://y.example.net/de/8/1", "http://é.org/es/" + "a/" * 30_000, "http://com/EN/"]
    df = spark.createDataFrame([(i, u, "h") for i, u in enumerate(urls)] + [(3, urls[3], "h"), (None, "http://org/es/", "h")], "page_id bigint, url string, host string")
    labels = spark.createDataFrame([(0, None, None), (3, 1, 1), (3, 0, 0), (None, 1, 1)], "doc_id bigint, quality int, toxic int")
    got = [(r.id, r.host, r.path[:8], r.rule, r.verdict) for r in url_filters.judge(df, labels, queries.URL_RULES).collect()]
    assert len(got) == len(urls) + 2
    by = dict((g[0], g[1:]) for g in got)
    assert by[0] == by[1] == by[2] == ("", "", None, "allow")
    assert by[3] == ("a.example.com", "/en/7x", "example.com/en/7", "allow")
    assert by[4] == ("example.com", "", None, "allow") and by[5] == ("example.com", "", None, "allow")
    assert by[6] == ("net", "/de/", "net/de/", "allow") and by[7] == ("bnet", "/de/", None, "allow")
    assert by[8] == ("y.example.net", "/de/8/1", "example.net/de/8", "block")
    assert by[9][2:] == ("org/es/", "block") and by[10][2:] == (None, "allow") and by[None][3] == "block"
    assert url_filters.judge(df.limit(0), labels, queries.URL_RULES).count() == 0


def test_urls_are_mined(spark):
    rng = random.Random(6)
    rows, labels = [], []
    for i in range(600):
        spam = i % 4 == 0
        rows.append((i, f"http://{'pills' if spam else 'site'}{rng.randint(1, 2)}.shop.com/{'buy' if spam else rng.choice(['buy', 'read'])}/{i}"))
        if i % 2 == 0:
            labels.append((i, int(not spam), 0))
    df, known = spark.createDataFrame(rows, "page_id bigint, url string"), spark.createDataFrame(labels, "doc_id bigint, quality int, toxic int")
    got = {r.id: r.verdict for r in url_filters.judge(df, known, []).collect()}
    assert all((got[i] == "block") == (i % 4 == 0) for i in got) and len(got) == 600


def brute_blocked(rows, labels, mining):
    """URLs' token sets that hold a qualifying combination of frequent tokens, by going through all of them."""
    from itertools import combinations

    known = [(tokens, labels[i]) for i, tokens in rows if i in labels]
    total, bad_total = len(known), sum(b for _, b in known)
    least = max(-(-mining.support * total // 1), mining.rows)
    frequent = {t for t, n in Counter(t for tokens, b in known if b for t in tokens).items() if n >= least}
    n, n_bad = Counter(), Counter()
    for tokens, b in known:
        own = sorted(frequent & set(tokens))
        for k in range(1, len(own) + 1):
            for c in combinations(own, k):
                n[c] += 1
                n_bad[c] += b
    rules = [set(c) for c in n if n_bad[c] >= least and n_bad[c] >= mining.confidence * n[c] and n_bad[c] * total >= mining.lift * n[c] * bad_total]
    return {i for i, tokens in rows if any(r <= set(tokens) for r in rules)}


def test_mined_rules_equal_all_combinations(spark):
    rng = random.Random(8)
    pages, labels = [], {}
    for i in range(900):
        tokens = [f"p:{c}" for c in "abcdefgh" if rng.random() < 0.45]
        if "p:a" in tokens and rng.random() < 0.9:
            tokens.append("p:twin")
        bad = {"p:a", "p:b"} <= set(tokens) and rng.random() < 0.95 or {"p:c", "p:d", "p:e"} <= set(tokens) and rng.random() < 0.85 or rng.random() < 0.05
        pages.append((i, "http://h/" + "/".join(t[2:] for t in tokens)))
        if i % 3:
            labels[i] = bad
    rows = [(i, ["h:h", *("p:" + x for x in u.split("/")[3:] if x)]) for i, u in pages]
    df = spark.createDataFrame(pages, "page_id bigint, url string")
    known = spark.createDataFrame([(i, int(not b), 0) for i, b in labels.items()], "doc_id bigint, quality int, toxic int")
    for mining in (url_filters.Mining(), url_filters.Mining(rows=30, confidence=0.7, lift=1.2)):
        got = {r.id for r in url_filters.judge(df, known, [], mining).where("verdict = 'block'").collect()}
        assert got == brute_blocked(rows, labels, mining) and 0 < len(got) < 900


def judged_and_brute(spark, pages, labels, mining):
    """Blocked ids of pages (id, segments), mined and by going through all combinations."""
    rows = [(i, ["h:h", *("p:" + x for x in segments)]) for i, segments in pages]
    df = spark.createDataFrame([(i, "http://h/" + "/".join(segments)) for i, segments in pages], "page_id bigint, url string")
    known = spark.createDataFrame([(i, int(not b), 0) for i, b in labels.items()], "doc_id bigint, quality int, toxic int")
    return {r.id for r in url_filters.judge(df, known, [], mining).where("verdict = 'block'").collect()}, brute_blocked(rows, labels, mining)


def test_rules_beyond_the_width_are_mined(spark):
    """Pages of more classes than FP-growth is given: rules that lie behind the most often blocked ones block wide and narrow pages."""
    rng = random.Random(21)
    pages, labels = [], {}
    for i in range(400):
        labels[i] = rng.random() < 0.25
        pages.append((i, [f"d{k}" for k in range(14) if rng.random() < (0.75 if labels[i] else 0.3)] + [x for x in "xyz" if rng.random() < 0.6]))
    got, want = judged_and_brute(spark, pages, labels, url_filters.Mining())
    assert got == want and 0 < len(got) < 400
    pages, labels = [], {}
    for i in range(300):
        bad = rng.random() < 0.3
        segments = [f"d{k}" for k in range(3) if rng.random() < (0.8 if bad else 0.5)] + [x for x in "xyz" if rng.random() < 0.5]
        labels[i] = bad or set("xyz") <= set(segments)
        pages.append((i, segments))
    pages += [(900, list("xyz")), (901, list("xy"))]
    got, want = judged_and_brute(spark, pages, labels, url_filters.Mining(width=2))
    assert got == want and 900 in got and 901 not in got


def test_rules_within_a_rule_do_not_hide_it(spark):
    """A combination with confidence but too little lift does not take the place of a larger one that has both."""
    kinds = [("abc", 30, 30), ("ab", 30, 21), ("ac", 35, 10), ("bc", 35, 10), ("a", 35, 10), ("b", 35, 9)]
    rows = [(segments, k < n_bad) for segments, n, n_bad in kinds for k in range(n)]
    got, want = judged_and_brute(spark, [(i, list(s)) for i, (s, _) in enumerate(rows)], {i: b for i, (_, b) in enumerate(rows)}, url_filters.Mining())
    assert got == want == set(range(30))


def test_long_urls_do_not_explode(spark):
    """Pages that share forty segments, and pages that each lack a few of forty, labelled bad and good."""
    rng = random.Random(9)
    shared = "/".join(f"s{k}" for k in range(40))
    pages = [(i, f"http://one.com/{shared}", i % 10 != 9) for i in range(80)]
    pages += [(100 + i, "http://two.com/" + "/".join(f"t{k}" for k in range(40) if rng.random() < 0.9), i % 3 != 2) for i in range(300)]
    pages += [(1000 + i, f"http://three.com/{i}", False) for i in range(600)]
    df = spark.createDataFrame([p[:2] for p in pages] + [(5000, "http://x.org/s7")], "page_id bigint, url string")
    known = spark.createDataFrame([(i, int(not b), 0) for i, _, b in pages], "doc_id bigint, quality int, toxic int")
    mined = url_filters.mine(df, known)
    assert mined.count() < 200
    got = {r.id for r in url_filters.judge(df, known, []).where("verdict = 'block'").collect()}
    assert got >= {*range(80), 5000} and not any(i >= 1000 for i in got - {5000})


def test_many_rules_are_joined(spark):
    rng = random.Random(3)
    urls = [None, "http://a.b.example.com/x/1", "http://example.com", "x"] + [f"http://{rng.choice(['', 'a.', 'b.a.'])}h{rng.randint(0, 9)}.com/{rng.choice('xyz')}/{rng.randint(0, 9)}" for _ in range(200)]
    rules = [("com/x", "block"), ("example.com/x/", "allow"), ("b.example.com/x/1", "block")] + [(f"h{k}.com/{c}/{d}", rng.choice(["block", "allow"])) for k in range(10) for c in "xy" for d in range(3)]
    df = spark.createDataFrame([(i, u) for i, u in enumerate(urls)], "id bigint, url string")
    from pyspark.sql import functions as F

    df = df.select("id", url_filters.host_of(F.col("url")).alias("host"), url_filters.path_of(F.col("url")).alias("path"))
    one, many = (sorted(map(tuple, url_filters.apply_rules(df, rules, most).collect())) for most in (500, 2))
    assert one == many and any(r[3] for r in one)


def test_small_counts_bytes(spark):
    from tauprobe.llm import arrow_kernels

    rows = spark.range(30).selectExpr("id", "repeat('x', 3000000) as t")
    hinted = lambda df: "ResolvedHint" in df._jdf.queryExecution().analyzed().toString()
    assert not hinted(arrow_kernels.small(rows)) and hinted(arrow_kernels.small(rows.select("id")))
