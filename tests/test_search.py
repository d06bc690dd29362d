"""The stopping rule, the executors, the index and the measures: fixtures worked by hand, properties, and exact baselines."""

import math

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from tauprobe.functions import vectors
from tauprobe.operators import approximate, calibrate, edges, ivf, metrics, rule, schedule, search
from tauprobe.params import SearchParams
from tauprobe.session import scratch
from tauprobe.sources import workloads as wl

SF1, SF2 = "/root/testdata/sf0.001", "/root/testdata/sf0.01"


def bits(text):
    return [c == "1" for c in text]


@pytest.mark.parametrize(
    ("hits", "window", "stop", "waves"),
    [
        ("0000000000", 3, 3, [[1, 2, 3]]),
        ("0010000000", 3, 6, [[1, 2, 3], [4, 5, 6]]),
        ("0001000000", 3, 3, [[1, 2, 3]]),
        ("1001001000", 3, 10, [[1, 2, 3], [4], [5, 6, 7], [8, 9, 10]]),
        ("1100000000", 3, 5, [[1, 2, 3], [4, 5]]),
        ("0100100000", 12, 10, [list(range(1, 11))]),
        ("1101111111", 1, 3, [[1], [2], [3]]),
        ("1111111111", 3, 10, [[1, 2, 3], [4, 5, 6], [7, 8, 9], [10]]),
    ],
)
def test_rule_fixtures(hits, window, stop, waves):
    assert rule.simulate(bits(hits), window) == stop
    assert rule.lookahead_waves(bits(hits), window) == waves


@settings(max_examples=300, deadline=None)
@given(st.lists(st.booleans(), min_size=1, max_size=25), st.integers(1, 12), st.integers(1, 30), st.integers(1, 4))
def test_lookahead_visits_what_the_rule_visits(hits, window, nprobe, few):
    stop = rule.simulate(hits, window, nprobe)
    for ranks in (None, few, 1):
        sent = [r for w in rule.lookahead_waves(hits, window, nprobe, ranks) for r in w]
        assert sent == list(range(1, stop + 1))
    assert rule.simulate(hits, window + 1, nprobe) >= stop >= min(window, nprobe, len(hits))
    assert len(rule.lookahead_waves(hits, window, nprobe)) <= min(nprobe, len(hits)) - min(window, nprobe, len(hits)) + 1


@settings(max_examples=60, deadline=None)
@given(st.integers(0, 10**6), st.integers(1, 5), st.integers(1, 3), st.integers(1, 5))
def test_scheduler_does_the_same_searches(seed, window, workers, cap):
    rng = np.random.default_rng(seed)
    probes = [schedule.Probe(i, tuple(rng.permutation(9).tolist()), tuple((rng.random(9) < 0.3).tolist())) for i in range(12)]
    want = sorted((p.query, r) for p in probes for r in range(1, rule.simulate(p.hits, window) + 1))
    for mode in ("basic", "lookahead"):
        for order in ("fifo", "random", "largest"):
            t = schedule.run(probes, window, mode, order, workers, cap)
            assert sorted(x for _, b in t.dispatches for x in b) == want and max(len(b) for _, b in t.dispatches) <= cap


def test_columns_agree_with_the_rule(spark):
    rng = np.random.default_rng(1)
    rows = [(q, 0, r + 1, r, int(rng.random() < 0.25)) for q in range(200) for r in range(15)]
    ranks = spark.createDataFrame(rows, "query_id bigint, shard_id int, rank int, pid int, n_hits bigint")
    local = ranks.where("n_hits > 0").select("query_id", "shard_id", "rank", F.lit(1).cast("bigint").alias("vec_id"), F.lit(1.0).alias("sim"))
    own = {q: [n > 0 for qq, _, _, _, n in rows if qq == q] for q in range(200)}
    for r in search.stops(ranks, local, [1, 3, 8, 40]).collect():
        assert r.stop == rule.simulate(own[r.query_id], r.w)
    seen = {(r.query_id, r.rank): r.visited for r in rule.trace(ranks, 3).collect()}
    assert all(v == (r <= rule.simulate(own[q], 3)) for (q, r), v in seen.items())


def held_out(spark, sf, name):
    """An index without the queries, around every twenty-fifth row, and the queries."""
    base, held = wl.held_out(wl.vectors_of(spark, sf, name))
    return ivf.build(base, ivf.seed_centroids(base, 25)), base, held


def test_golden_numbers(spark):
    for sf, queries, visits, hits in ((SF1, 50, 353, 88), (SF2, 50, 381, 117)):
        index, _, held = held_out(spark, sf, "emb")
        p = SearchParams(tau=0.30, window=4, nprobe=10_000)
        r, w = search.lookahead(index, held, p), search.waves(index, held, p)
        for x in (r, w):
            assert (held.count(), x.visits.agg(F.sum("visits")).first()[0], x.local.count()) == (queries, visits, hits)
        assert r.waves[0][1] == visits and max(n for n, _, _ in w.waves) <= index.lists - 4 + 1
    got = wl.vectors_of(spark, SF2, "docs_u").select("id", F.posexplode("vec").alias("b", "v")).agg(F.sum("v"), F.sum(F.col("v") * F.col("v")), F.sum((F.col("b") + 1) * F.col("v") * (F.col("id") + 1))).first()
    assert tuple(got) == (-5033, 6549447, -17342257)


def test_executors_agree(spark):
    index, base, held = held_out(spark, SF1, "docs_u")
    p = SearchParams(tau=0.6, window=2, nprobe=10_000)
    rows = lambda e: sorted(map(tuple, e.collect()))
    ahead = search.lookahead(index, held, p)
    others = [search.basic(index, held, p), search.waves(index, held, p), search.waves(index, held, p.with_(ranks_per_wave=2, microbatch=3)), search.speculative(index, held, p), search.serial(index, held, p), search.serial(ivf.saved_copy(index), held, p)]
    others += [search.walk(index, held, p.with_(microbatch=3), ahead=a, call=c, order=o) for a, c, o in ((True, 7, "fifo"), (False, 7, "largest"), (True, None, "random"))]
    for other in others:
        assert rows(other.edges) == rows(ahead.edges) and rows(other.visits) == rows(ahead.visits)
    every = search.fixed(index, held, p)
    assert rows(search.lookahead(index, held, p.with_(window=10_000)).edges) == rows(every.edges)
    joined = search.fixed_by_joins(index, held, p)
    assert rows(every.edges) == rows(search.exact(base, held, p.tau, p.k)) == rows(joined.edges) and rows(every.visits) == rows(joined.visits)
    empty = search.lookahead(index, held.limit(0), p)
    assert empty.edges.count() == 0 and empty.waves == [(1, 0, 0)]


def test_best_first_equals_a_stable_sort():
    rng = np.random.default_rng(5)
    sims = np.round(rng.integers(-30, 30, (50, 40)) / 30, ivf.DECIMALS)
    want = np.argsort(-sims, axis=1, kind="stable")
    for most in (1, 7, 39, 40, 90):
        assert (ivf.best_first(sims, most) == want[:, :most]).all()


def test_batching_serves_more_queries_a_dispatch(spark):
    """Serial, basic, lookahead: the same searches in ever fewer dispatches."""
    index, _ = wl.index_of(spark, SF2, "docs_u")
    every = wl.vectors_of(spark, SF2, "docs_u").coalesce(1)
    p = wl.WORKLOADS["docs_u"].params
    one, basic, ahead = search.serial(index, every, p), search.basic(index, every, p), search.lookahead(index, every, p)
    assert one.waves[0][1] == basic.waves[0][1] == ahead.waves[0][1]
    assert one.waves[0][2] == one.waves[0][1] > basic.waves[0][2] > ahead.waves[0][2]


def test_attribute_filter_comes_before_the_rule(spark):
    every = wl.vectors_of(spark, SF1, "docs_u").withColumn("odd", F.col("id") % 2)
    index = ivf.build(every, ivf.seed_centroids(every, 25), attribute="odd")
    p = SearchParams(tau=0.6, window=99, drop_self=True)
    got = sorted((r.query_id, r.vec_id) for r in search.walk(index, every, p, attribute="odd").edges.collect())
    want = [search.exact(every.where(f"odd = {k}"), every.where(f"odd = {k}"), 0.6, 10, drop_self=True) for k in (0, 1)]
    assert got == sorted((r.query_id, r.vec_id) for w in want for r in w.collect()) and got


def test_brute_force_over_a_grid_of_tiles(spark, monkeypatch):
    every, held = wl.split(wl.vectors_of(spark, SF2, "docs_u"))
    rows = lambda e: sorted(map(tuple, e.collect()))
    want = rows(search.exact(every, held, 0.5, 10, drop_self=True))
    monkeypatch.setattr(search, "SENT_BYTES", 0)
    monkeypatch.setattr(search, "QUERY_TILE", 3)
    got = search.exact(every, held, 0.5, 10, drop_self=True)
    assert rows(got) == want
    vecs = {r.id: np.array(r.vec) for r in every.collect()}
    unit = {i: v / np.linalg.norm(v) for i, v in vecs.items()}
    for q in [r.id for r in held.collect()][:5]:
        near = sorted(((round(float(unit[q] @ unit[i]), 9), -i) for i in unit if i != q), reverse=True)
        assert [x[1] for x in want if x[0] == q] == [-i for s, i in near if s >= 0.5][:10] or {x[1] for x in want if x[0] == q} <= {-i for s, i in near if s >= near[10][0] - 1e-9}


def test_serial_in_shards_and_self_search(spark):
    rows = lambda e: sorted(map(tuple, e.collect()))
    index, held = wl.shard_index_of(spark, SF1, "docs_u")
    p = wl.WORKLOADS["docs_u"].params.with_(window=2)
    one, many = search.serial(index, held, p), search.lookahead(index, held, p)
    assert rows(one.edges) == rows(many.edges) == rows(search.waves(index, held, p).edges) and rows(one.visits) == rows(many.visits)
    assert rows(search.lookahead(ivf.saved_copy(index), held, p).edges) == rows(many.edges)
    assert one.waves[0][1] == one.visits.agg(F.sum("visits")).first()[0]
    own, every = wl.index_of(spark, SF1, "docs_u")[0], wl.vectors_of(spark, SF1, "docs_u")
    assert rows(search.serial(own, every, p).edges) == rows(search.lookahead(own, every, p).edges)
    assert search.serial(index, held.limit(0), p).edges.count() == 0


def test_a_list_of_any_size_is_split(spark):
    """A third of the rows at one centroid: blocks stay within their size, whatever task they come from."""
    rows = [(i, [1.0, 0.001 * (i % 7)] if i % 3 else [0.0, 1.0 + i]) for i in range(900)]
    every = spark.createDataFrame(rows, "id bigint, vec array<double>").repartition(5)
    index = ivf.build(every, ivf.seed_centroids(every, 100), block_rows=64)
    assert index.blocks.agg(F.max("n")).first()[0] <= 64 and index.blocks.agg(F.sum("n")).first()[0] == 900
    assert index.blocks.select("shard_id", "pid", "block_no").distinct().count() == index.blocks.count()
    again = ivf.repack(index.blocks, 200)
    assert again.agg(F.sum("n")).first()[0] == 900 and again.count() < index.blocks.count()


def test_calls_of_the_scheduler_add_up(spark):
    rng = np.random.default_rng(3)
    hits = {q: (rng.random(9) < 0.3).tolist() for q in range(60)}
    table = spark.createDataFrame([(q, 0, r + 1, (q * 7 + r) % 9, int(h)) for q, own in hits.items() for r, h in enumerate(own)], "query_id bigint, shard_id int, rank int, pid int, n_hits bigint")
    want = sum(rule.simulate(own, 2) for own in hits.values())
    whole = schedule.compare_calls(table, 2).collect()
    parts = schedule.compare_calls(table, 2, call_queries=20).collect()
    assert len(whole) == len(parts) == 6 and {r["items"] for r in whole + parts} == {want}
    assert sorted(tuple(r) for r in whole) == sorted(schedule.compare(schedule.as_queries(table.orderBy("query_id", "rank").collect()), 2))


def test_edges_of_the_threshold(spark):
    index, base, held = held_out(spark, SF1, "emb")
    p = SearchParams(tau=0.85, window=8, nprobe=10_000)
    r = search.lookahead(index, held, p)
    assert r.edges.count() == 0 and {x.visits for x in r.visits.collect()} == {min(8, index.lists)}
    assert metrics.pooled_recall(r.edges, search.exact(base, held, 0.85, 10)) is None
    loose = search.lookahead(index, held, p.with_(tau=-1.0, window=1))
    assert {x.visits for x in loose.visits.collect()} == {index.lists}
    over = search.lookahead(index, held.limit(0), p)
    assert over.edges.count() == 0 and over.visits.count() == 0
    for bad in ({"window": 0}, {"k": 0}, {"nprobe": 0}, {"tau": math.nan}, {"microbatch": 0}, {"ranks_per_wave": 0}):
        with pytest.raises(ValueError):
            p.with_(**bad)


def test_loss_falls_and_work_rises_with_the_window(spark):
    from tauprobe.plans import vector_queries as vq

    for name in ("emb", "docs_u"):
        rows = sorted(vq.QUERIES[f"w_sweep_{name}"](spark, SF2).collect(), key=lambda r: r.w)
        assert [r.visits for r in rows] == sorted(r.visits for r in rows)
        assert [r.loss_pp for r in rows] == sorted((r.loss_pp for r in rows), reverse=True)
    share = {r.within: r.share for r in vq.QUERIES["front_load_docs_u"](spark, SF2).collect()}
    assert share[8] >= 0.99
    profile = vq.QUERIES["wave_profile_docs_u"](spark, SF2).collect()
    mean = lambda m: sum(r.items for r in profile if r.mode == m) / sum(r.groups for r in profile if r.mode == m)
    assert mean("lookahead") > 1.3 * mean("basic")
    lookahead_visits = [r.visits for r in sorted(vq.QUERIES["tau_sweep_docs_u"](spark, SF2).collect(), key=lambda r: r.tau)]
    assert lookahead_visits == sorted(lookahead_visits, reverse=True)
    assert len({r.visits for r in vq.QUERIES["k_sweep_docs_u"](spark, SF2).collect()}) == 1


def test_quarantine_and_vectors(spark):
    nan = float("nan")
    rows = [(1, [1.0, 0.0]), (2, [0.0, 0.0]), (3, None), (4, [1.0]), (5, [nan, 1.0]), (6, [None, 1.0]), (7, [3.0, 4.0])]
    good, bad = vectors.quarantine(spark.createDataFrame(rows, "id bigint, vec array<double>"), dim=2)
    assert {r.id for r in good.collect()} == {1, 7} and bad.count() == 5
    got = good.where("id = 7").select(vectors.normalize(F.col("vec")).alias("u"), vectors.cosine(F.col("vec"), F.array(F.lit(1.0), F.lit(0.0))).alias("c")).first()
    assert got.u == [0.6, 0.8] and got.c == pytest.approx(0.6)


def test_store_blocks_and_dimension(spark):
    base, held = wl.held_out(wl.vectors_of(spark, SF1, "docs_u"))
    index = ivf.build(base, ivf.seed_centroids(base, 25), block_rows=3)
    assert index.blocks.agg(F.max("n")).first()[0] <= 3
    path = scratch(spark, "t")
    ivf.save(index, path)
    again = ivf.load(spark, path, dim=64)
    p = SearchParams(tau=0.7, window=3, nprobe=99)
    rows = lambda i: sorted(map(tuple, search.lookahead(i, held, p).edges.collect()))
    assert rows(again) == rows(index) == rows(held_out(spark, SF1, "docs_u")[0])
    with pytest.raises(ValueError):
        ivf.load(spark, path, dim=32)
    assert ivf.suggest_nlist(9_900_000) == 2417
    assert [ivf.seed_every(n) for n in (1000, 10_000, 100_000_000)] == [25, 25, 2500]


def test_graph_and_cells(spark):
    base, _ = wl.split(wl.vectors_of(spark, SF2, "emb"))
    index, _ = wl.index_of(spark, SF2, "emb")
    c = index.centroids
    exact = {r.id: r.pid for r in index.postings().collect()}
    pick = lambda choose: {r.id: r.pid for r in ivf.assign(base, c, choose).collect()}
    assert pick(approximate.graph_chooser(c, links=16, beam=len(c.unit))) == exact
    assert pick(approximate.cell_chooser(c, probes=99)) == exact
    wrong = lambda got: sum(got[i] != exact[i] for i in exact) / len(exact)
    assert 0 < wrong(pick(approximate.graph_chooser(c, links=4, beam=1))) < 0.8


def test_codes(spark):
    rng = np.random.default_rng(2)
    unit = rng.normal(size=(200, 64))
    unit /= np.linalg.norm(unit, axis=1)[:, None]
    centre, q = unit[:50].mean(0), unit[150:]
    centre /= np.linalg.norm(centre)
    errors = []
    for b in (1, 2, 4, 7):
        coder = approximate.Coder(b, approximate.rotation(64, 3))
        codes, length, fit = coder.encode(unit[:100], centre)
        assert (approximate.unpack_bits(approximate.pack_bits(codes, b), b, 100, 64) == codes).all()
        est = coder.estimate(q @ coder.turn.T, q @ centre, codes, length, fit)
        errors.append(np.abs(est - q @ unit[:100].T).mean())
        assert abs((est - q @ unit[:100].T).mean()) < 0.01
    assert errors[0] > 1.5 * errors[1] > 3 * errors[2] > 6 * errors[3]


def test_pair_join_finds_all_and_prunes(spark):
    every = wl.vectors_of(spark, SF1, "docs_u")
    index = ivf.build(every, ivf.seed_centroids(every, 10), block_rows=4)
    want = {(r.query_id, r.vec_id) for r in search.exact(every, every, 0.97, drop_self=True).collect() if r.query_id < r.vec_id}
    for prune in (False, True):
        pairs, cost = edges.pair_join(index, 0.97, prune)
        got = [(r.id_a, r.id_b) for r in pairs.collect()]
        assert len(got) == len(set(got)) and set(got) == want
        assert cost.first().pairs_scored <= 200 * 199 / 2


def test_measures():
    assert metrics.matched_cost([(0.5, 10.0), (0.9, 30.0)], 0.7) == pytest.approx(20)
    assert metrics.matched_cost([(0.5, 10.0)], 0.7) is None and metrics.matched_cost([], None) is None
    assert metrics.break_even([(0.4, 1.2), (0.3, 1.1), (0.2, 0.9)]) == 0.3
    assert metrics.added_loss(0.9, 0.8, 1.0, 0.95) == pytest.approx(5)
    assert metrics.raw_gb(9_900_000, 768) == pytest.approx(30.4, abs=0.02)
    assert metrics.loss_pp(None, 1.0) is None


def test_gini_and_mismatch(spark):
    sizes = spark.createDataFrame([(0, 0, 0), (0, 1, 5), (0, 2, 5), (0, 3, 10)], "shard_id int, pid int, n bigint")
    s = metrics.partition_stats(sizes).first()
    assert (s.lists, s.empty, s.max_over_mean) == (4, 1, 2.0) and s.gini == pytest.approx(0.375)


def test_calibration(spark):
    index, held = wl.index_of(spark, SF2, "emb")
    p = wl.WORKLOADS["emb"].params
    c = calibrate.choose_window(index, held, p, 0.5)
    assert [x[1] for x in c.curve] == sorted((x[1] for x in c.curve), reverse=True) and c.loss_pp <= 0.5
    none = calibrate.choose_window(index, held, p.with_(tau=0.9), 0.5)
    assert none.window == calibrate.DEFAULT_WINDOW and none.loss_pp is None


def test_workload_shapes(spark):
    base, held = wl.split(wl.vectors_of(spark, SF2, "conv"))
    assert search.exact(base, held, 0.97).count() >= 0 and base.count() > held.count() > 0
    moved = wl.vectors_of(spark, SF2, "emb_plant").where("id >= 1000000")
    assert moved.count() == 50


def test_plans(spark):
    index, held = wl.index_of(spark, SF1, "docs_u")
    ranks = ivf.rank_table(ivf.probe_lists(held, index, 5))
    plan = lambda df: df._sc._jvm.PythonSQLUtils.explainString(df._jdf.queryExecution(), "simple")
    text = plan(search.merge_top(search.search(ranks, held, index, SearchParams(tau=0.5, nprobe=5)), 10))
    assert "CartesianProduct" not in text and "NestedLoop" not in text and "WindowGroupLimit" in text
    from tauprobe.plans.operator_queries import QUERIES

    scan = QUERIES["op_scan_pushdown_docs"](spark, SF1)
    text = scan._sc._jvm.PythonSQLUtils.explainString(scan._jdf.queryExecution(), "formatted")  # the simple form cuts long lists off
    pushed = next(line for line in text.splitlines() if line.startswith("PushedFilters"))
    assert "In(lang, [de,fr])" in pushed and "GreaterThanOrEqual(n_chars,500)" in pushed and "text" not in text


def test_arrivals_come_again_without_harm(spark):
    from tauprobe.streaming.arrivals import Arrivals

    every = wl.vectors_of(spark, SF1, "docs_u").select("id", "vec")
    sink = Arrivals(ivf.seed_centroids(every, 25), SearchParams(tau=0.8, window=3, nprobe=99), scratch(spark, "a"))
    first, second = every.where("id < 100"), every.where("id >= 100")
    sink(first, 0)
    sink(second, 1)
    once = sorted(map(tuple, sink.edges(spark).collect()))
    sink(second, 1)
    assert sorted(map(tuple, sink.edges(spark).collect())) == once
    assert all(e[1] < 100 for e in once)


def test_arrivals_are_packed_anew(spark):
    """Many batches with packing between them find what one index of all earlier rows finds."""
    from tauprobe.streaming.arrivals import Arrivals

    every = wl.vectors_of(spark, SF1, "docs_u").select("id", "vec")
    p, centroids = SearchParams(tau=0.8, window=99, nprobe=99), ivf.seed_centroids(every, 25)
    sink = Arrivals(centroids, p, scratch(spark, "a"), compact=2)
    for b in range(5):
        sink(every.where(f"id % 5 = {b}"), b)
    got = sorted((r.query_id, r.vec_id) for r in sink.edges(spark).where("batch = 4").collect())
    want = search.exact(every.where("id % 5 < 4"), every.where("id % 5 = 4"), 0.8, 10)
    assert got == sorted((r.query_id, r.vec_id) for r in want.collect()) and len(sink._folders(5)) == 2


def test_planner_and_experiments(spark):
    from tauprobe.plans import experiments, planner, vector_queries

    p = SearchParams(tau=0.8, window=8, nprobe=90)
    assert planner.choose(p, 100, 8).mode == "fixed" and planner.choose(p, 100_000, 2400).mode == "lookahead" and planner.choose(p, 100, 40, readable=False).mode == "waves"
    big = planner.choose(p, 3 * 10**9, 4000, shards=2000, vectors=3 * 10**10)
    assert big.needs_shards and big.tasks > 10**7 and big.chunks_of_largest_group > 1
    index, held = wl.index_of(spark, SF1, "docs_u")
    for window, mode in ((8, "fixed"), (2, "lookahead")):
        got, plan = planner.run(index, held, p.with_(window=window, drop_self=True))
        assert plan.mode == mode and sorted(map(tuple, got.edges.collect())) == sorted(map(tuple, search.waves(index, held, p.with_(window=window, drop_self=True)).edges.collect()))
    assert all(q in vector_queries.QUERIES for qs in experiments.EXPERIMENTS.values() for q in qs)


def test_a_changed_table_is_read_anew(spark):
    from tauprobe.session import release

    folder = scratch(spark, "tables")
    emb = spark.read.parquet(f"{SF1}/embeddings.parquet")
    emb.write.parquet(f"{folder}/embeddings.parquet")
    assert wl.vectors_of(spark, folder, "emb").count() == emb.count()
    emb.where("vec_id < 100").write.mode("overwrite").parquet(f"{folder}/embeddings.parquet")
    assert wl.vectors_of(spark, folder, "emb").count() == emb.where("vec_id < 100").count()
    release(spark, folder)
    with pytest.raises(Exception, match="PATH_NOT_FOUND|does not exist"):
        spark.read.parquet(f"{folder}/embeddings.parquet")


def test_many_centroids_make_shards(spark, monkeypatch):
    """Beyond the bound an index has shards, and finds the same when every list is visited."""
    monkeypatch.setattr(ivf, "MOST_CENTROIDS", 5)
    monkeypatch.setattr(wl, "_KEPT", type(wl._KEPT)())
    index, held = wl.index_of(spark, SF1, "docs_u")
    assert isinstance(index.centroids, ivf.StoredCentroids) and len(index.shards) > 1
    p = wl.WORKLOADS["docs_u"].params.with_(window=99)
    every = wl.vectors_of(spark, SF1, "docs_u")
    rows = lambda e: sorted(map(tuple, e.collect()))
    assert rows(search.lookahead(index, held, p).edges) == rows(search.exact(every, held, p.tau, p.k, drop_self=True))
    with pytest.raises(ValueError):
        ivf.seed_centroids(every, 25)
