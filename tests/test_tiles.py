"""Pairs within tiles: exact, and without a shuffle or a table of all links."""

import os

import numpy as np
import pytest

import __spark_entry__ as entry
from tauprobe.operators import components, edges, tiles
from tauprobe.session import shared_dir
from tauprobe.sources import workloads as wl


def written(spark):
    top = shared_dir(spark).removeprefix("file://")
    return sum(os.path.getsize(f"{d}/{f}") for d, _, files in os.walk(top) for f in files)


def same_set(pairs):
    up = {}
    top = lambda x: x if up.setdefault(x, x) == x else top(up[x])
    for a, b in pairs:
        a, b = sorted((top(a), top(b)))
        up[b] = a
    return {x: top(x) for x in up}


def made(spark, n, seed):
    """Rows of vectors in loose clumps, of words that depend on the clump, in two languages or none."""
    rng = np.random.default_rng(seed)
    near = rng.integers(-6, 7, (12, 8))
    clump = rng.integers(0, 12, n)
    mat = near[clump] + rng.integers(-2, 3, (n, 8))
    mat[~mat.any(1)] = 1
    rows = []
    for i, (c, v) in enumerate(zip(clump.tolist(), mat.tolist(), strict=True)):
        words = {int(w) << 32 | c for w in rng.integers(0, 8, rng.integers(0, 9))}
        rows.append((i * 3, [float(x) for x in v], ["x", "y"][i % 7 == 0], sorted(words)))
    return rows, spark.createDataFrame(rows, "id bigint, vec array<double>, lang string, words array<bigint>").repartition(3)


@pytest.mark.parametrize("opened", [True, False])
def test_pairs_of_tiles_equal_brute_force(spark, monkeypatch, opened):
    monkeypatch.setattr(tiles, "ROWS", 48)
    monkeypatch.setattr(tiles, "STEP", 16)
    monkeypatch.setattr(tiles, "SIDE", 4)
    if not opened:
        monkeypatch.setattr(tiles, "_readable", lambda path: False)
    rows, frame = made(spark, 400, 5)
    mat = np.array([r[1] for r in rows])
    sims = np.round(mat @ mat.T / np.sqrt(np.multiply.outer((mat * mat).sum(1), (mat * mat).sum(1))), 12)
    tau = float(np.sort(sims[np.triu_indices(400, 1)])[-300])  # a similarity that occurs: it counts as within
    links = [(i, j) for i, j in zip(*np.nonzero(sims >= tau)) if i < j]
    assert len(links) >= 300
    stored = tiles.write(frame)
    found = components.components(tiles.forest(stored, tau)).collect()
    assert {r.node: r.component for r in found} == same_set([(rows[i][0], rows[j][0]) for i, j in links])
    want = {}
    for i, j in links:
        a, b = set(rows[i][3]), set(rows[j][3])
        if rows[i][2] == rows[j][2] and a | b and len(a & b) / len(a | b) >= 0.5:
            want[rows[i][0], rows[j][0]] = (round(float(sims[i, j]), 9), round(len(a & b) / len(a | b), 9))
    got = tiles.agreeing(stored, tau).collect()
    assert want and len(got) == len(want)
    assert {(r.id_a, r.id_b): (round(r.sim, 9), round(r.jaccard, 9)) for r in got} == want


def test_no_rows_and_words_whose_bits_collide(spark):
    none = tiles.write(spark.createDataFrame([], "id bigint, vec array<double>"))
    assert tiles.forest(none, 0.5).count() == 0
    near, far = [1, 2, 3, 4], [1 + tiles.BITS, 2 + tiles.BITS, 3 + tiles.BITS, 4]
    rows = [(1, [1.0, 0.0], "x", near), (2, [1.0, 0.0], "x", far), (3, [1.0, 0.0], "x", near[:2]), (4, [1.0, 0.0], "x", [])]
    got = tiles.agreeing(tiles.write(spark.createDataFrame(rows, "id bigint, vec array<double>, lang string, words array<bigint>")), 0.9).collect()
    assert [(r.id_a, r.id_b, r.jaccard) for r in got] == [(1, 3, 0.5)]


def clump(spark, path, n=1500):
    """n texts that are all within the threshold of each other, but share one word of six."""
    rows = [(i, " ".join(["same"] * 60 + [f"w{i}x{j}" for j in range(5)]), "xx", "s", 300) for i in range(n)]
    spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint").coalesce(2).write.parquet(f"{path}/documents.parquet")
    spark.createDataFrame([(0, 1, 0)], "doc_id bigint, quality int, toxic int").write.parquet(f"{path}/labels.parquet")
    return str(path)


def test_components_write_no_table_of_all_links(spark, tmp_path):
    sf = clump(spark, tmp_path / "t")
    before = written(spark)
    rows = entry.queries()["components_docs_u"](spark, sf).collect()
    assert sorted(r.node for r in rows) == list(range(1500)) and {r.component for r in rows} == {0}
    assert written(spark) - before < 3_000_000  # a million links took more


def test_group_labels_write_no_table_of_all_links(spark, tmp_path):
    sf = clump(spark, tmp_path / "t")
    before = written(spark)
    rows = entry.queries()["group_labels_docs_u"](spark, sf).collect()
    assert len(rows) == 1500 and {r.group_size for r in rows} == {1500} and [r.id for r in rows if r.keep] == [0]
    assert written(spark) - before < 3_000_000


def test_content_filter_writes_only_links_that_agree(spark, tmp_path):
    sf = clump(spark, tmp_path / "t")
    before = written(spark)
    assert entry.queries()["content_filter_docs_u"](spark, sf).count() == 0
    assert written(spark) - before < 1_500_000  # a million links took more


def test_agreeing_equals_the_filter_of_all_links(spark):
    sf = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    links, _ = edges.pair_join(wl.index_of(spark, sf, "docs_u")[0], 0.85, True)
    want = {(r.id_a, r.id_b, round(r.jaccard, 6)) for r in edges.content_filter(links, docs).collect()}
    got = {tuple(r) for r in entry.queries()["content_filter_docs_u"](spark, sf).collect()}
    reps = {r.representative for r in edges.representatives(docs, ["text", "lang"]).collect()}
    assert want and got == {w for w in want if w[0] in reps and w[1] in reps}

