"""Language identification by held-out accuracy; SimHash classes against brute force."""

import itertools
import random
import re

import numpy as np
import pytest
import xxhash

from tauprobe.llm import language, queries, simhash
from tauprobe.operators.components import components, label_propagation

SF = "/root/testdata/sf0.001"


def test_language_held_out_accuracy(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").toPandas().set_index("doc_id")
    got = queries.op3_language(spark, "/root/testdata/sf0.01").toPandas().set_index("doc_id")
    assert len(got) == len(docs)
    out = got[got.held_out]
    assert (out.lang_pred == docs.loc[out.index].lang).mean() > 0.98
    assert got.score.between(0, 1).all()


def test_language_odd_rows(spark):
    odd = [None, "", "12 %% 3", "the and of", "der die und", "x" * 3_000_000, "é"]
    rows = [(i, t, "zz", 1.0) for i, t in enumerate(odd)] + [(3, "the and of", None, 1.0), (None, "the", "q", 1.0)]
    df = spark.createDataFrame(rows, "doc_id bigint, text string, lang_pred string, score double")
    model = language.learn(["the and of that"] * 9 + ["der die und das"] * 9, ["en"] * 9 + ["de"] * 9)
    got = [(r.id, r.lang_pred) for r in language.predict(df, model).collect()]
    assert len(got) == len(rows) and {g for g in got if g[0] in (0, 1, 2)} == {(0, "und"), (1, "und"), (2, "und")}
    assert got.count((3, "en")) == 2 and (4, "de") in got
    assert language.predict(df.limit(0), model).count() == 0
    nothing = language.train(spark.createDataFrame([], "doc_id bigint, text string, lang string"))
    assert {r.lang_pred for r in language.predict(df, nothing).collect()} == {"und"}
    one = language.learn(["the"], ["en"])
    assert one.predict(["the"])[0][0] == "en"


def plain_grams(text, buckets):
    """Counts of hashed byte grams, one at a time."""
    code = lambda c: 2 if c in b" \t\n\r\x0b\x0c" else 3 if 48 <= c < 58 else c - 93 if 97 <= c < 123 else c - 98 if c >= 128 else 1
    b, out, low = [code(c) for c in b"  " + text.lower().encode() + b"  "], [0] * buckets, (1 << 32) - 1
    for i in range(len(b) - 2):
        pair = b[i] * 61 + b[i + 1]
        out[(pair * 2654435761 & low) >> 7 & buckets - 1] += 1
        out[((pair * 257 + b[i + 2]) * 2246822519 & low) >> 9 & buckets - 1] += 1
    return out


def test_language_equals_plain_version():
    """Grams, bit classifiers' margins, loss-weighted decoding and the ambiguity flag, by loops."""
    texts = ["the and of that with", "der die und das mit", "le la et les avec", "the \u00fcber 12 of"]
    langs = ["en", "de", "fr"]
    settings = language.Settings(buckets=256, steps=30)
    model = language.learn(texts[:3] * 6, langs * 6, settings)
    for t in [*texts, "der the le", "\u00e9"]:
        grams = plain_grams(t, 256)
        assert grams == language.gram_counts([t], 256)[0].tolist()
        x = [g**0.5 for g in grams]
        size = sum(v * v for v in x) ** 0.5
        margin = [sum(v / size * w for v, w in zip(x, model.weights[:, j])) + model.bias[j] for j in range(model.codes.shape[1])]
        loss = [sum(np.exp(-m * c) * w for m, c, w in zip(margin, code, model.bit_weights)) for code in model.codes]
        share = [1 / v**2 / sum(1 / u**2 for u in loss) for v in loss]
        best = max(range(3), key=lambda k: share[k])
        name, score, unsure = model.predict([t])[0]
        assert name == model.names[best] and score == pytest.approx(share[best], abs=1e-4) and unsure == (share[best] < settings.sure)
    assert model.predict(["the and of that with"])[0][::2] == ("en", False)
    same = language.learn(["aa bb"] * 60 + ["cc"] * 20, ["x", "y", "z"] * 20 + ["w"] * 20, settings)
    assert same.predict(["aa bb"])[0][2] and not same.predict(["cc"])[0][2]  # three languages that cannot be told apart


def test_language_learns_from_whole_texts_and_bounded_labels(spark):
    rows = [(i, "0 " * 600_000 + ("the and of that " if i % 2 else "der die und das ") * 200, "en" if i % 2 else "de") for i in range(6)]
    rows += [(100 + i, f"junk{i}", f"dirt{i}") for i in range(50)] + [(7, "the and of", "en")] * 400
    df = spark.createDataFrame(rows, "doc_id bigint, text string, lang string")
    model = language.train(df, settings=language.Settings(languages=2, steps=40))
    assert model.names == ("de", "en")
    assert [m[0] for m in model.predict(["der die und das", "the and of that"])] == ["de", "en"]


def test_codewords_differ():
    for n in (2, 4, 7, 8, 20):
        m = language.code_matrix(n, 12, 1)
        gaps = [(m[i] != m[j]).sum() for i, j in itertools.combinations(range(n), 2)]
        assert min(gaps) >= (1 << (n - 2) if n <= 7 else 4)


def test_long_texts_count_whole():
    text = "abc dé " * 1000
    assert np.allclose(language.gram_counts([text], 4096, block=1 << 20), language.gram_counts([text], 4096, block=101))


def brute_fingerprint(text):
    words = [w.encode() for w in re.findall(r"[^\x20\x09-\x0D]+", "".join(c.lower() if "A" <= c <= "Z" else c for c in text or ""))]
    shingles = [b" ".join(words[i : i + 4]) for i in range(max(1, len(words) - 3))] if words else []
    hashes = [xxhash.xxh64_intdigest(s, 42) for s in shingles]
    return sum(1 << i for i in range(64) if 2 * sum(h >> i & 1 for h in hashes) > len(hashes)) if hashes else 0


def brute_classes(fps):
    label = {f: f for f in fps}

    def root(x):
        while label[x] != x:
            x = label[x]
        return x

    for a, b in itertools.combinations(sorted(fps), 2):
        if (a ^ b).bit_count() <= 4:
            ra, rb = root(a), root(b)
            label[max(ra, rb)] = min(ra, rb)
    return {f: root(f) for f in fps}


def test_simhash_query_equals_brute_force(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").toPandas()
    fps = {d: brute_fingerprint(t) for d, t in zip(docs.doc_id, docs.text, strict=True)}
    roots = brute_classes(set(fps.values()))
    least = {}
    for d, f in fps.items():
        least[roots[f]] = min(d, least.get(roots[f], d))
    got = {r.doc_id: (r.fingerprint, r.component_id) for r in queries.op4_simhash(spark, SF).collect()}
    assert got == {d: (f"{f:016x}", least[roots[f]]) for d, f in fps.items()}


def near_cloud(n, seed):
    rng = random.Random(seed)
    centre, out = rng.getrandbits(64), set()
    while len(out) < n:
        x = centre
        for i in rng.sample(range(64), rng.randint(0, 5)):
            x ^= 1 << i
        out.add(x)
    return out | {rng.getrandbits(64) for _ in range(n)}


@pytest.mark.parametrize("limit", [4096, 5])
def test_links_reach_all_pairs(spark, limit):
    fps = near_cloud(120, limit)
    signed = {f - (1 << 64) if f >> 63 else f: f for f in fps}
    df = spark.createDataFrame([(s,) for s in signed], "fp bigint")
    edges = simhash.links(df, bucket_limit=limit)
    pairs = [(signed[r.id_a], signed[r.id_b]) for r in edges.collect()]
    assert all((a ^ b).bit_count() <= 4 for a, b in pairs)
    got = {}
    for r in components(edges).collect():
        got.setdefault(r.component, set()).add(signed[r.node])
    want = {}
    for f, r in brute_classes(fps).items():
        want.setdefault(r, set()).add(f)
    assert sorted(map(sorted, got.values())) == sorted(sorted(v) for v in want.values() if len(v) > 1)


def test_every_pair_within_the_radius_collides():
    rng = random.Random(5)
    for radius in (1, 2, 4):
        ms = simhash.masks(radius)
        for _ in range(2000):
            flip = sum(1 << i for i in rng.sample(range(64), radius))
            assert any(flip & m & (1 << 64) - 1 == 0 for m in ms)


def test_components_agree(spark):
    rng = random.Random(3)
    edges = spark.createDataFrame([(rng.randrange(300), rng.randrange(300)) for _ in range(220)] + [(i, i + 1) for i in range(400, 460)] + [(7, 7)], "id_a bigint, id_b bigint")
    star = {r.node: r.component for r in components(edges).collect()}
    flood = {r.node: r.component for r in label_propagation(edges.where("id_a <> id_b")).collect()}
    assert star == flood
    assert components(edges.limit(0)).count() == 0


def test_simhash_odd_rows(spark):
    rows = [(5, None, 1), (3, "", 1), (9, " \t", 1), (2, "A b", 1), (1, "a B", 1), (1, "a B", 1), (None, "q r s t u v", 1), (8, "w x y z " * 50_000, 1)]
    df = spark.createDataFrame(rows, "doc_id bigint, text string, fp int")
    got = sorted(((r.id, r.component) for r in simhash.classes(df).collect()), key=str)
    assert got == sorted([(5, 3), (3, 3), (9, 3), (2, 1), (1, 1), (1, 1), (None, None), (8, 8)], key=str)
    assert sorted(str(r.doc_id) for r in simhash.keep_one(df).collect()) == ["1", "3", "8", "None"]
    assert simhash.classes(df.limit(0)).count() == 0
