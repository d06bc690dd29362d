"""Registered queries of the search methods, baselines, measures and experiments, with their DuckDB SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tauprobe.functions import vectors
from tauprobe.operators import approximate, edges, ivf, metrics, rule, schedule, search, tiles
from tauprobe.operators import calibrate as cal
from tauprobe.plans import planner
from tauprobe.plans import vector_sql as q
from tauprobe.session import materialize, table
from tauprobe.sources import workloads as wl

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return keep


def emb(tau=0.30, p=90, **kw):
    return q.probed("embeddings", tau, p, **kw)


def docs(tau=0.85, p=90, **kw):
    return q.probed("documents", tau, p, **kw)


KIND = {"emb": emb, "docs_u": docs, "docs_b": lambda tau=0.85, p=90, **kw: docs(tau, p, pairs=True, **kw), "pages": lambda tau=0.90, p=90, **kw: q.probed("pages", tau, p, seed_every=10, **kw)}
#: The windows of the registered searches.
WINDOW = {n: w.window for n, w in wl.WORKLOADS.items()}


def rounded(e: DataFrame) -> DataFrame:
    return e.select("query_id", "vec_id", F.round("sim", 6).alias("sim"), F.col("pos").cast("bigint").alias("pos"))


def full(spark, sf, name, rounds=0, **changes):
    """(index, queries, params, ranks, local) of a full pass, kept for the session: what sweeps are replayed from."""
    index, held = wl.index_of(spark, sf, name, rounds)
    params = wl.WORKLOADS[name].params.with_(**changes)
    ranks, local = wl._once(spark, ("full", sf, name, rounds, params), lambda: search.full_probe(index, held, params))
    return index, held, params, ranks, local


def truth(spark, sf, name, k=10, tau=None):
    every, held = wl.split(wl.vectors_of(spark, sf, name))
    tau = wl.WORKLOADS[name].tau if tau is None else tau
    return wl._once(spark, ("truth", sf, name, k, tau), lambda: materialize(search.exact(every, held, tau, k, drop_self=True), "truth"))


# ---- vectors

for _n, _src, _pairs in (("vec_hash_docs_u", "documents", False), ("vec_hash_docs_b", "documents", True)):

    @query(_n, f"WITH {q.vectors(_src, _pairs)} SELECT id AS doc_id, CAST(b AS INTEGER) AS bucket, CAST(c AS BIGINT) AS weight FROM cells")
    def _(spark, sf, name=_n[4:].replace("hash_", "")):
        v = wl.vectors_of(spark, sf, name)
        return v.select(F.col("id").alias("doc_id"), F.posexplode("vec").alias("bucket", "x")).where("x <> 0").select("doc_id", "bucket", F.col("x").cast("bigint").alias("weight"))


@query("vec_norm_emb", f"WITH {q.vectors('embeddings')} SELECT id AS vec_id, round(sqrt(n2), 6) AS norm, 1.0 AS unit_norm FROM v")
def _(spark, sf):
    v = wl.vectors_of(spark, sf, "emb")
    return v.select(F.col("id").alias("vec_id"), F.round(F.sqrt("norm2"), 6).alias("norm"), F.round(F.sqrt(vectors.norm2(vectors.normalize(F.col("vec")))), 6).alias("unit_norm"))


@query("vec_cosine_pairs_emb", f"WITH {q.vectors('embeddings')} SELECT a.id AS id_a, b.id AS id_b, round({q.sim('a', 'b')}, 6) AS sim FROM v a JOIN v b ON a.id < b.id WHERE {q.sim('a', 'b')} >= 0.4")
def _(spark, sf):
    index, _ = wl.index_of(spark, sf, "emb")
    pairs, _ = edges.pair_join(index, 0.40, prune=False)
    return pairs.select("id_a", "id_b", F.round("sim", 6).alias("sim"))


for _n in ("emb", "docs_u"):

    @query(f"exact_topk_{_n}", f"WITH {KIND[_n]()}, {q.truth()} {q.EDGES.format('SELECT * FROM truth')}")
    def _(spark, sf, name=_n):
        return rounded(truth(spark, sf, name, 10, -2.0))

    @query(f"ivf_assign_{_n}", f"WITH {KIND[_n]()} SELECT id AS vec_id, CAST(pid AS INTEGER) AS pid FROM assigned")
    def _(spark, sf, name=_n):
        index, _ = wl.index_of(spark, sf, name)
        return index.postings().select(F.col("id").alias("vec_id"), "pid")


@query("exact_range_docs_b", f"WITH {KIND['docs_b']()} SELECT query_id, vec_id, round(sim, 6) AS sim FROM scored WHERE sim >= 0.85")
def _(spark, sf):
    every, held = wl.split(wl.vectors_of(spark, sf, "docs_b"))
    return search.exact(every, held, 0.85, drop_self=True).select("query_id", "vec_id", F.round("sim", 6).alias("sim"))


# ---- index variants

@query("ivf_lloyd1_emb", f"WITH {emb(rounds=1)} SELECT CAST(pid AS INTEGER) AS pid, count(*) AS size FROM assigned GROUP BY pid")
def _(spark, sf):
    return wl.index_of(spark, sf, "emb", 1)[0].postings().groupBy("pid").agg(F.count(F.lit(1)).alias("size"))


@query("ivf_kmeans_ml_emb")
def _(spark, sf):
    base, _ = wl.split(wl.vectors_of(spark, sf, "emb"))
    return ivf.assign(base, ivf.train_ml(base, 16)).groupBy("pid").agg(F.count(F.lit(1)).alias("size"))


_CELLS = f"""cn_ AS (SELECT count(*) AS n, greatest(1, CAST(round_even(sqrt(count(*)), 0) AS BIGINT)) AS k FROM c),
heads AS (SELECT i AS cell, c.vec, c.n2 FROM cn_, LATERAL (SELECT unnest(range(0, k)) AS i) JOIN c ON c.pid = i * n // k),
of AS (SELECT c.pid, heads.cell FROM c, heads QUALIFY row_number() OVER (PARTITION BY c.pid ORDER BY round({q.sim('c', 'heads')}, 9) DESC, heads.cell) = 1),
go AS (SELECT base.id, heads.cell FROM base, heads QUALIFY row_number() OVER (PARTITION BY base.id ORDER BY round({q.sim('base', 'heads')}, 9) DESC, heads.cell) <= 1),
routed AS (SELECT base.id, c.pid FROM base JOIN go ON go.id = base.id JOIN of ON of.cell = go.cell JOIN c ON c.pid = of.pid QUALIFY row_number() OVER (PARTITION BY base.id ORDER BY round({q.sim('base', 'c')}, 9) DESC, c.pid) = 1)"""


@query("ivf_assign_cells_emb", f"WITH {emb()}, {_CELLS} SELECT r.id AS vec_id, CAST(r.pid AS INTEGER) AS pid, r.pid = a.pid AS is_nearest FROM routed r JOIN assigned a USING (id)")
def _(spark, sf):
    return _variant(spark, sf, approximate.cell_chooser)


@query("ivf_assign_graph_emb")
def _(spark, sf):
    return _variant(spark, sf, lambda c: approximate.graph_chooser(c, beam=4))


def _variant(spark, sf, chooser):
    base, _ = wl.split(wl.vectors_of(spark, sf, "emb"))
    index, _ = wl.index_of(spark, sf, "emb")
    stored = ivf.assign(base, index.centroids, chooser(index.centroids)).select(F.col("id").alias("vec_id"), "pid")
    nearest = index.postings().select(F.col("id").alias("vec_id"), F.col("pid").alias("nearest"))
    return stored.join(nearest, "vec_id").select("vec_id", "pid", (F.col("pid") == F.col("nearest")).alias("is_nearest"))


@query("ivf_store_roundtrip_emb", f"WITH {emb()} SELECT CAST(pid AS INTEGER) AS pid, count(*) AS before, count(*) AS after FROM assigned GROUP BY pid")
def _(spark, sf):
    index, _ = wl.index_of(spark, sf, "emb")
    again = ivf.saved_copy(index)
    count = lambda i, name: i.blocks.groupBy("pid").agg(F.sum("n").alias(name))
    return count(index, "before").join(count(again, "after"), "pid")


@query("ivf_codes_error_emb")
def _(spark, sf):
    index, held = wl.index_of(spark, sf, "emb")
    parts = [approximate.code_error(index, held, bits) for bits in (1, 2, 4, 7)]
    return parts[0].union(parts[1]).union(parts[2]).union(parts[3])


@query("ivf_codes_search_docs_u")
def _(spark, sf):
    index, held = wl.index_of(spark, sf, "docs_u")
    r = search.lookahead(approximate.coded(index), held, wl.WORKLOADS["docs_u"].params, approximate.code_scorer(index))
    return r.edges.select("query_id", "vec_id", "pos")


@query("ivf_codes_rerank_docs_u")
def _(spark, sf):
    index, held = wl.index_of(spark, sf, "docs_u")
    base, _ = wl.split(wl.vectors_of(spark, sf, "docs_u"))
    r = search.lookahead(approximate.coded(index), held, wl.WORKLOADS["docs_u"].params, approximate.code_scorer(index))
    return rounded(approximate.rerank(r.edges, base, held, 0.85, 10))


@query("probe_order_emb", f"WITH {emb(p=None)} SELECT query_id, CAST(rank AS INTEGER) AS rank, CAST(pid AS INTEGER) AS pid FROM probe")
def _(spark, sf):
    index, held = wl.index_of(spark, sf, "emb")
    return ivf.rank_table(ivf.probe_lists(held, index, index.lists)).select("query_id", "rank", "pid")


# ---- executors

for _n in ("emb", "docs_u", "docs_b"):

    @query(f"fixed_topk_{_n}", f"WITH {KIND[_n]()} {q.EDGES.format(q.top('met', 10))}")
    def _(spark, sf, name=_n):
        index, held = wl.index_of(spark, sf, name)
        return rounded(search.fixed(index, held, wl.WORKLOADS[name].params).edges)


@query("fixed_small_probe_docs_u", f"WITH {docs(p=4)} {q.EDGES.format(q.top('met', 10))}")
def _(spark, sf):
    index, held = wl.index_of(spark, sf, "docs_u")
    return rounded(search.fixed(index, held, wl.WORKLOADS["docs_u"].params.with_(nprobe=4)).edges)


_KEPT = "kept AS (SELECT m.* FROM met m JOIN stop s ON s.query_id = m.query_id AND m.rank <= s.stop)"


def adaptive_sql(chain: str, window: int) -> str:
    return f"WITH {chain}, {q.stops(f'[{window}]')}, {_KEPT} {q.EDGES.format(q.top('kept', 10))}"


for _n in ("emb", "docs_u", "docs_b", "pages"):

    @query(f"lookahead_edges_{_n}", adaptive_sql(KIND[_n](), WINDOW[_n]))
    def _(spark, sf, name=_n):
        index, held = wl.index_of(spark, sf, name)
        return rounded(search.lookahead(index, held, wl.WORKLOADS[name].params).edges)


for _n in ("emb", "docs_u"):

    @query(f"basic_edges_{_n}", adaptive_sql(KIND[_n](), WINDOW[_n]))
    def _(spark, sf, name=_n):
        index, held = wl.index_of(spark, sf, name)
        return rounded(search.basic(index, held, wl.WORKLOADS[name].params).edges)


@query("serial_edges_docs_u", adaptive_sql(docs(), WINDOW["docs_u"]))
def _(spark, sf):
    index, held = wl.index_of(spark, sf, "docs_u")
    return rounded(search.serial(index, held, wl.WORKLOADS["docs_u"].params).edges)


@query("planned_edges_pages", adaptive_sql(KIND["pages"](), WINDOW["pages"]))
def _(spark, sf):
    index, held = wl.index_of(spark, sf, "pages")
    return rounded(planner.run(index, held, wl.WORKLOADS["pages"].params)[0].edges)


@query("sql_views_docs_u", f"WITH {docs()}, {q.stops('[8]')}, {_KEPT}, found AS ({q.top('kept', 10)}) SELECT s.query_id, CAST(stop AS BIGINT) AS visits, count(f.vec_id) AS neighbours, round(max(sim), 6) AS best FROM stop s LEFT JOIN found f USING (query_id) GROUP BY s.query_id, stop")
def _(spark, sf):
    """A result's views in SQL."""
    index, held = wl.index_of(spark, sf, "docs_u")
    search.publish(search.lookahead(index, held, wl.WORKLOADS["docs_u"].params))
    return spark.sql("select v.query_id, v.visits, count(e.vec_id) as neighbours, round(max(e.sim), 6) as best from tau_visits v left join tau_edges e on e.query_id = v.query_id group by v.query_id, v.visits")


for _n in ("emb", "docs_u"):

    @query(f"waves_edges_{_n}", adaptive_sql(KIND[_n](), 4))
    def _(spark, sf, name=_n):
        index, held = wl.index_of(spark, sf, name)
        return rounded(search.waves(index, held, wl.WORKLOADS[name].params.with_(window=4)).edges)


@query("tail_dispatch_trim_emb", adaptive_sql(emb(), 4))
def _(spark, sf):
    index, held = wl.index_of(spark, sf, "emb")
    return rounded(search.speculative(index, held, wl.WORKLOADS["emb"].params.with_(window=4), trim=True).edges)


@query("tail_dispatch_keep_emb", f"WITH {emb()} {q.EDGES.format(q.top('met', 10))}")
def _(spark, sf):
    index, held = wl.index_of(spark, sf, "emb")
    return rounded(search.speculative(index, held, wl.WORKLOADS["emb"].params, trim=False).edges)


@query("lookahead_stop_lines_docs_u", f"WITH {docs()}, {q.stops('[8]')} SELECT query_id, CAST(stop AS BIGINT) AS visits FROM stop")
def _(spark, sf):
    index, held = wl.index_of(spark, sf, "docs_u")
    return search.lookahead(index, held, wl.WORKLOADS["docs_u"].params).visits.select("query_id", "visits")


@query("rule_trace_emb", f"WITH {emb()}, {q.stops('[4]')} SELECT z.query_id, CAST(z.rank AS INTEGER) AS rank, z.n_hits > 0 AS hit, CAST(z.stale AS INTEGER) AS stale, z.rank <= s.stop AS visited FROM quiet z JOIN stop s USING (query_id)")
def _(spark, sf):
    _, _, _, ranks, local = full(spark, sf, "emb")
    return rule.trace(search.outcomes(ranks, local), 4).select("query_id", "rank", "hit", F.col("stale").cast("int").alias("stale"), "visited")


@query("mode_difference_docs_u", "SELECT CAST(0 AS BIGINT) AS only_basic, CAST(0 AS BIGINT) AS only_lookahead")
def _(spark, sf):
    index, held = wl.index_of(spark, sf, "docs_u")
    p = wl.WORKLOADS["docs_u"].params
    a, b = search.basic(index, held, p), search.lookahead(index, held, p)
    return spark.createDataFrame([(a.edges.exceptAll(b.edges).count(), b.edges.exceptAll(a.edges).count())], "only_basic bigint, only_lookahead bigint")


def _wave_sql(calls: str, step: str) -> str:
    """CTEs: the waves of calls, from each query's hit ranks; step is the last rank sent."""
    return f"""hits AS (SELECT query_id, max(rank) AS p, list(rank ORDER BY rank) FILTER (n_hits > 0) AS h FROM outcome GROUP BY query_id),
part AS ({calls}),
run AS (SELECT call, query_id, 1 AS wave, CAST(1 AS BIGINT) AS a, least(8, p) AS line, p, coalesce(h, []) AS h FROM hits JOIN part USING (query_id)
  UNION ALL SELECT call, query_id, wave + 1, {step} + 1, greatest(line, least(coalesce(list_max(list_filter(h, lambda r: r >= a AND r <= {step})) + 8, 0), p)), p, h FROM run WHERE a <= line),
sent AS (SELECT r.call, r.wave, o.query_id, o.pid FROM (SELECT *, {step} AS z FROM run WHERE a <= line) r JOIN outcome o ON o.query_id = r.query_id AND o.rank BETWEEN r.a AND r.z)"""


_ONE = "SELECT query_id, 0 AS call FROM (SELECT DISTINCT query_id FROM outcome)"


def _profile(mode: str, step: str) -> str:
    return f"(WITH RECURSIVE {docs()}, {_wave_sql(_ONE, step)} SELECT '{mode}' AS mode, wave, count(*) AS items, count(DISTINCT pid) AS groups, round(count(*) / count(DISTINCT pid), 4) AS occupancy FROM sent GROUP BY wave)"


@query("wave_profile_docs_u", f"SELECT * FROM {_profile('basic', 'a')} UNION ALL SELECT * FROM {_profile('lookahead', 'line')}")
def _(spark, sf):
    index, held = wl.index_of(spark, sf, "docs_u")
    p = wl.WORKLOADS["docs_u"].params
    rows = [(m, w, i, g, round(i / g, 4)) for m, each in (("basic", 1), ("lookahead", None)) for w, i, g in search.waves(index, held, p.with_(ranks_per_wave=each)).waves]
    return spark.createDataFrame(rows, "mode string, wave int, items bigint, groups bigint, occupancy double")


_CALLS = [1, 10, 100, 1_000_000]


@query("call_size_docs_u", f"WITH {docs()}, {q.stops('[8]')}, {_KEPT}, found AS ({q.top('kept', 10)}), m AS (SELECT unnest(['basic', 'lookahead']) AS mode), z AS (SELECT CAST(unnest({_CALLS}) AS BIGINT) AS call_size) SELECT mode, call_size, (SELECT CAST(sum(stop) AS BIGINT) FROM stop) AS visits, (SELECT count(*) FROM found) AS edges FROM m, z")
def _(spark, sf):
    """Calls of one query up to all of a task: the same searches and results."""
    index, held = wl.index_of(spark, sf, "docs_u")
    rows = []
    for mode, ahead in (("basic", False), ("lookahead", True)):
        for n in _CALLS:
            r = search.walk(index, held, wl.WORKLOADS["docs_u"].params, ahead, call=n)
            rows.append((mode, n, r.waves[0][1], r.edges.count()))
    return spark.createDataFrame(rows, "mode string, call_size bigint, visits bigint, edges bigint")


@query("ablation_docs_u")
def _(spark, sf):
    """Fixed, serial, basic and lookahead: searches, dispatches, queries a dispatch, and partitions read."""
    index, held = wl.index_of(spark, sf, "docs_u")
    p, rows = wl.WORKLOADS["docs_u"].params, []
    for mode, run in (("fixed", search.fixed), ("serial", search.serial), ("basic", search.basic), ("lookahead", search.lookahead)):
        r = run(index, held, p)
        (_, items, groups), *_ = r.waves
        rows.append((mode, items, groups, round(items / max(1, groups), 4), r.loads))
    return spark.createDataFrame(rows, "mode string, visits bigint, dispatches bigint, occupancy double, loads bigint")


@query("microbatch_split_docs_u", f"WITH {docs(p=4)} SELECT CAST(0 AS INTEGER) AS shard_id, CAST(pid AS INTEGER) AS pid, count(*) AS items, true AS dealt FROM probe GROUP BY pid")
def _(spark, sf):
    """Items of the executor's microbatches with a cap of eight: nothing is lost, and chunk numbers keep to the group's size."""
    index, held = wl.index_of(spark, sf, "docs_u")
    frontier = ivf.rank_table(ivf.probe_lists(held, index, 4))
    parts = search.microbatches(frontier, held, 8).select("shard_id", "pid", "chunk", F.size("items").alias("n"))
    return parts.groupBy("shard_id", "pid").agg(F.sum("n").alias("items"), (F.max("chunk") < F.ceil(F.sum("n") / 8)).alias("dealt"))


@query("queue_policy_trace_docs_u")
def _(spark, sf):
    _, _, _, ranks, local = full(spark, sf, "docs_u")
    return schedule.compare_calls(search.outcomes(ranks, local), window=8)


# ---- sweeps and measures

_WINDOWS = [1, 2, 4, 8, 12, 16]


def _sweep_sql(chain: str, tau: float, windows: list[int]) -> str:
    return f"""WITH {chain}, {q.truth(10, tau)}, {q.stops(str(windows))},
kept AS (SELECT s.w, m.* FROM met m JOIN stop s ON s.query_id = m.query_id AND m.rank <= s.stop), found AS ({q.top('kept', 10, extra='w, ')}),
hit AS (SELECT w, count(*) AS found FROM found JOIN truth USING (query_id, vec_id) GROUP BY w), n AS (SELECT count(*) AS n FROM truth),
full_ AS (SELECT count(*) AS f FROM ({q.top('met', 10)}) JOIN truth USING (query_id, vec_id))
SELECT s.w, CAST(s.visits AS BIGINT) AS visits, coalesce(found, 0) AS found, round(coalesce(found, 0) / nullif(n, 0), 6) AS recall, round(100.0 * (f - coalesce(found, 0)) / nullif(n, 0), 4) AS loss_pp
FROM (SELECT w, sum(stop) AS visits FROM stop GROUP BY w) s LEFT JOIN hit USING (w), n, full_"""


def sweep(spark, ranks, local, gt, windows, k=10):
    """Rows (w, visits, found, recall, loss_pp) replayed from one full pass."""
    found, ended = search.replay(ranks, local, windows, k)
    n = gt.count()
    f = search.merge_top(local, k).join(gt.select("query_id", "vec_id"), ["query_id", "vec_id"]).count()
    hit = found.join(gt.select("query_id", "vec_id"), ["query_id", "vec_id"]).groupBy("w").agg(F.count(F.lit(1)).alias("found"))
    got = ended.groupBy("w").agg(F.sum("stop").alias("visits")).join(hit, "w", "left").withColumn("found", F.coalesce("found", F.lit(0)))
    share = lambda x: F.lit(None).cast("double") if not n else x / n
    return got.select("w", "visits", "found", F.round(share(F.col("found")), 6).alias("recall"), F.round(share(100.0 * (f - F.col("found"))), 4).alias("loss_pp"))


@query("w_sweep_trained_docs_u", _sweep_sql(docs(rounds=1), 0.85, _WINDOWS))
def _(spark, sf):
    _, _, _, ranks, local = full(spark, sf, "docs_u", 1)
    return sweep(spark, ranks, local, truth(spark, sf, "docs_u"), _WINDOWS)


@query("w_sweep_codes_docs_u")
def _(spark, sf):
    """The sweep on trained lists with 7-bit codes as the scorer; the loss is against fixed probing of the same codes."""
    index, held = wl.index_of(spark, sf, "docs_u", 3)
    ranks, local = search.full_probe(approximate.coded(index), held, wl.WORKLOADS["docs_u"].params, approximate.code_scorer(index))
    return sweep(spark, ranks, local, truth(spark, sf, "docs_u"), _WINDOWS)


for _n, _tau in (("emb", 0.30), ("docs_u", 0.85), ("docs_b", 0.85)):

    @query(f"w_sweep_{_n}", _sweep_sql(KIND[_n](), _tau, _WINDOWS))
    def _(spark, sf, name=_n):
        _, _, _, ranks, local = full(spark, sf, name)
        return sweep(spark, ranks, local, truth(spark, sf, name), _WINDOWS)


_TAUS = {"emb": [0.20, 0.30, 0.40, 0.85], "docs_u": [0.10, 0.50, 0.70, 0.85, 0.95]}


def _tau_sql(kind: str) -> str:
    parts = []
    for t in _TAUS[kind]:
        parts.append(f"SELECT * FROM (WITH {KIND[kind](t)}, {q.truth(10, t)}, {q.stops('[8]')}, {_KEPT}, found AS ({q.top('kept', 10)}) SELECT CAST({t} AS DOUBLE) AS tau, (SELECT CAST(sum(stop) AS BIGINT) FROM stop) AS visits, count(t.vec_id) AS truth, round(count(f.vec_id) / nullif(count(t.vec_id), 0), 6) AS recall FROM truth t LEFT JOIN found f USING (query_id, vec_id))")
    return " UNION ALL ".join(parts)


for _n in ("emb", "docs_u"):

    @query(f"tau_sweep_{_n}", _tau_sql(_n))
    def _(spark, sf, name=_n):
        """One full pass at the lowest threshold holds the passes of all higher ones: a partition's best k are its best k at any threshold."""
        taus = _TAUS[name]
        _, _, _, ranks, local = full(spark, sf, name, tau=min(taus))
        gt = truth(spark, sf, name, 10, -2.0)
        out = None
        for t in taus:
            own = local.where(F.col("sim") >= t)
            found, ended = search.replay(ranks, own, [8], 10)
            want = gt.where(F.col("sim") >= t)
            n = want.count()
            hit = found.join(want.select("query_id", "vec_id"), ["query_id", "vec_id"]).count()
            row = ended.agg(F.lit(t).alias("tau"), F.sum("stop").alias("visits"), F.lit(n).cast("bigint").alias("truth"), F.round(F.lit(hit / n if n else None).cast("double"), 6).alias("recall"))
            out = row if out is None else out.union(row)
        return out


_KS = [5, 10, 20, 50]


@query(
    "k_sweep_docs_u",
    " UNION ALL ".join(
        f"SELECT * FROM (WITH {docs()}, {q.truth(k, 0.85)}, {q.stops('[8]')}, {_KEPT}, found AS ({q.top('kept', k)}) SELECT CAST({k} AS BIGINT) AS k, (SELECT CAST(sum(stop) AS BIGINT) FROM stop) AS visits, count(t.vec_id) AS truth, round(count(f.vec_id) / nullif(count(t.vec_id), 0), 6) AS recall FROM truth t LEFT JOIN found f USING (query_id, vec_id))"
        for k in _KS
    ),
)
def _(spark, sf):
    _, _, _, ranks, local = full(spark, sf, "docs_u", k=50)
    rows = []
    for k in _KS:
        found, ended = search.replay(ranks, local, [8], k)
        gt = truth(spark, sf, "docs_u", 50).where(F.col("pos") <= k)
        n = gt.count()
        rows.append((k, ended.agg(F.sum("stop")).first()[0], n, round(found.join(gt.select("query_id", "vec_id"), ["query_id", "vec_id"]).count() / n, 6) if n else None))
    return spark.createDataFrame(rows, "k bigint, visits bigint, truth bigint, recall double")


_PROBES = [1, 4, 8, 16, 24]


@query(
    "probe_sweep_docs_u",
    " UNION ALL ".join(
        f"SELECT * FROM (WITH {docs(p=p)}, {q.truth(10, 0.85)}, {q.stops('[8]')}, {_KEPT}, found AS ({q.top('kept', 10)}), whole AS ({q.top('met', 10)}) SELECT CAST({p} AS BIGINT) AS p, round(count(w.vec_id) / nullif(count(t.vec_id), 0), 6) AS fixed_recall, round(count(f.vec_id) / nullif(count(t.vec_id), 0), 6) AS adaptive_recall, (SELECT CAST(sum(stop) AS BIGINT) FROM stop) AS visits FROM truth t LEFT JOIN found f USING (query_id, vec_id) LEFT JOIN whole w USING (query_id, vec_id))"
        for p in _PROBES
    ),
)
def _(spark, sf):
    return spark.createDataFrame([(p, f, a, v) for p, f, a, v, _ in _probe_points(spark, sf, _PROBES)], "p bigint, fixed_recall double, adaptive_recall double, visits bigint")


def _probe_points(spark, sf, probes, window=8):
    """(p, fixed recall, adaptive recall, adaptive visits, fixed visits) from one full pass."""
    _, _, _, ranks, local = full(spark, sf, "docs_u")
    gt = truth(spark, sf, "docs_u")
    n = gt.count()
    share = lambda e: round(e.join(gt.select("query_id", "vec_id"), ["query_id", "vec_id"]).count() / n, 6) if n else None
    for p in probes:
        few, own = ranks.where(F.col("rank") <= p), local.where(F.col("rank") <= p)
        found, ended = search.replay(few, own, [window], 10)
        yield p, share(search.merge_top(own, 10)), share(found), ended.agg(F.sum("stop")).first()[0], few.count()


_POINTS = [1, 2, 3, 4, 6, 8, 12, 16, 24]
_MATCHED = f"""WITH sweep AS ({_sweep_sql(docs(), 0.85, _WINDOWS)}),
pts AS ({" UNION ALL ".join(f"SELECT * FROM (WITH {docs(p=p)}, {q.truth(10, 0.85)}, whole AS ({q.top('met', 10)}) SELECT round(count(w.vec_id) / nullif(count(t.vec_id), 0), 6) AS r, (SELECT CAST(count(*) AS DOUBLE) FROM probe) AS c FROM truth t LEFT JOIN whole w USING (query_id, vec_id))" for p in _POINTS)}),
seq AS (SELECT r AS r0, c AS c0, lead(r) OVER o AS r1, lead(c) OVER o AS c1, row_number() OVER o AS i FROM pts WHERE r IS NOT NULL WINDOW o AS (ORDER BY r, c))
SELECT CAST(w AS INTEGER) AS w, recall, CAST(visits AS DOUBLE) AS adaptive_cost, (SELECT CASE WHEN r1 - r0 <= 1e-9 * greatest(r0, r1) THEN c0 ELSE c0 + (c1 - c0) * (recall - r0) / (r1 - r0) END FROM seq WHERE r0 <= recall AND recall <= r1 ORDER BY i LIMIT 1) AS matched_fixed_cost FROM sweep"""


@query("matched_cost_docs_u", _MATCHED)
def _(spark, sf):
    points = list(_probe_points(spark, sf, _POINTS))
    frontier = [(f, float(v)) for _, f, _, _, v in points]
    _, _, _, ranks, local = full(spark, sf, "docs_u")
    rows = [(r.w, r.recall, float(r.visits), metrics.matched_cost(frontier, r.recall)) for r in sweep(spark, ranks, local, truth(spark, sf, "docs_u"), _WINDOWS).collect()]
    return spark.createDataFrame(rows, "w int, recall double, adaptive_cost double, matched_fixed_cost double")


_TARGETS = [0.1, 0.5, 1.0]
#: The sample, and the smallest window of the grid whose loss on it keeps to the target.
_CALIBRATED = f"""WITH {docs()}, size_ AS (SELECT count(*) AS n, greatest(50, least(1000, count(*) // 100)) AS k FROM qs),
picked AS (SELECT id FROM qs, size_ WHERE ('0x' || substr(md5(CAST(id AS VARCHAR)), 1, 8))::BIGINT * greatest(n, 1) < k * 4294967296),
most AS (SELECT max(rank) AS m FROM probe WHERE query_id IN (FROM picked)),
grid0 AS (SELECT DISTINCT least(w, m) AS w FROM (SELECT unnest({list(cal.GRID)}) AS w), most UNION SELECT m FROM most),
quiet AS MATERIALIZED (SELECT query_id, rank, rank - coalesce(max(CASE WHEN n_hits > 0 THEN rank END) OVER (PARTITION BY query_id ORDER BY rank), 0) AS stale FROM outcome WHERE query_id IN (FROM picked)),
stop AS MATERIALIZED (SELECT query_id, w, coalesce(min(rank) FILTER (stale >= w), max(rank)) AS stop FROM quiet, grid0 GROUP BY ALL),
kept AS (SELECT s.w, m.* FROM met m JOIN stop s ON s.query_id = m.query_id AND m.rank <= s.stop), found AS ({q.top('kept', 10, extra='w, ')}),
whole AS (SELECT query_id, vec_id FROM ({q.top('met', 10)}) WHERE query_id IN (FROM picked)),
curve AS (SELECT g.w, round(100 * (1 - count(f.w) / (SELECT count(*) FROM whole)), 6) AS loss FROM grid0 g LEFT JOIN (found f JOIN whole USING (query_id, vec_id)) f ON f.w = g.w GROUP BY g.w)
SELECT t.target AS target_pp, CAST(coalesce((SELECT min(w) FROM curve WHERE loss <= t.target), 8) AS INTEGER) AS chosen_w, (SELECT loss FROM curve WHERE loss <= t.target ORDER BY w LIMIT 1) AS sample_loss_pp, (SELECT count(*) FROM picked) AS sampled FROM (SELECT CAST(unnest({_TARGETS}) AS DOUBLE) AS target) t"""


@query("calibrate_w_docs_u", _CALIBRATED)
def _(spark, sf):
    index, held = wl.index_of(spark, sf, "docs_u")
    rows = []
    for target in _TARGETS:
        c = cal.choose_window(index, held, wl.WORKLOADS["docs_u"].params, target)
        rows.append((target, c.window, c.loss_pp, c.sampled))
    return spark.createDataFrame(rows, "target_pp double, chosen_w int, sample_loss_pp double, sampled bigint")


_RULES = [("consecutive", 4.0), ("cumulative", 8.0), ("rate", 0.75)]


def _rule_sql() -> str:
    stop = {
        "consecutive": "stale >= 4",
        "cumulative": "empties >= 8",
        "rate": "rank >= 8 AND empties >= 0.75 * rank",
    }
    marks = "marks AS (SELECT o.query_id, o.rank, z.stale, sum(CASE WHEN o.n_hits = 0 THEN 1 ELSE 0 END) OVER (PARTITION BY o.query_id ORDER BY o.rank) AS empties FROM outcome o JOIN quiet z USING (query_id, rank))"
    return " UNION ALL ".join(
        f"SELECT * FROM (WITH {docs()}, {q.truth(10, 0.85)}, {q.stops('[4]')}, {marks}, ended AS (SELECT query_id, coalesce(min(rank) FILTER ({stop[r]}), max(rank)) AS stop FROM marks GROUP BY query_id), kept AS (SELECT m.* FROM met m JOIN ended s ON s.query_id = m.query_id AND m.rank <= s.stop), found AS ({q.top('kept', 10)}) SELECT '{r}' AS rule, (SELECT CAST(sum(stop) AS BIGINT) FROM ended) AS visits, round(count(f.vec_id) / nullif(count(t.vec_id), 0), 6) AS recall FROM truth t LEFT JOIN found f USING (query_id, vec_id))"
        for r, _ in _RULES
    )


@query("other_stop_rules_docs_u", _rule_sql())
def _(spark, sf):
    _, _, _, ranks, local = full(spark, sf, "docs_u")
    gt, rows = truth(spark, sf, "docs_u"), []
    for kind, limit in _RULES:
        ended = search.stops(ranks, local, [int(limit)]).drop("w") if kind == "consecutive" else rule.other_rule(search.outcomes(ranks, local), kind, limit)
        kept = local.join(ended, ["query_id", "shard_id"]).where("rank <= stop")
        r = metrics.pooled_recall(search.merge_top(kept, 10), gt)
        rows.append((kind, ended.agg(F.sum("stop")).first()[0], None if r is None else round(r, 6)))
    return spark.createDataFrame(rows, "rule string, visits bigint, recall double")


# ---- characteristics

for _n, _tau in (("emb", 0.30), ("docs_u", 0.85)):

    @query(f"density_{_n}", f"WITH {KIND[_n]()}, near AS (SELECT qs.id, least(count(s.vec_id), 50) AS n FROM qs LEFT JOIN scored s ON s.query_id = qs.id AND s.sim >= {_tau} GROUP BY qs.id) SELECT n AS neighbours, count(*) AS queries, round(count(*) / (SELECT count(*) FROM qs), 6) AS share FROM near GROUP BY n")
    def _(spark, sf, name=_n):
        _, held = wl.split(wl.vectors_of(spark, sf, name))
        return metrics.density(truth(spark, sf, name, 50), held)

    @query(f"partition_stats_{_n}", f"WITH {KIND[_n]()}, s AS (SELECT c.pid, count(a.id) AS n FROM c LEFT JOIN assigned a USING (pid) GROUP BY c.pid), i AS (SELECT n, row_number() OVER (ORDER BY n, pid) AS i FROM s) SELECT count(*) AS lists, round(stddev_pop(n) / avg(n), 6) AS cv, round(2 * sum(i * n) / (count(*) * sum(n)) - (count(*) + 1) / count(*), 6) AS gini, round(max(n) / avg(n), 6) AS max_over_mean, count(*) FILTER (n = 0) AS empty FROM i")
    def _(spark, sf, name=_n):
        return metrics.partition_stats(wl.index_of(spark, sf, name)[0].sizes())


_PLACE = "place AS (SELECT t.query_id, t.vec_id, p.rank FROM truth t JOIN assigned a ON a.id = t.vec_id JOIN probe p ON p.query_id = t.query_id AND p.pid = a.pid)"


@query("last_rank_docs_u", f"WITH {docs()}, {q.truth(10, 0.85)}, {_PLACE}, last_ AS (SELECT query_id, max(rank) AS r FROM place GROUP BY query_id) SELECT count(*) AS queries, quantile_cont(r, 0.5) AS p50, quantile_cont(r, 0.9) AS p90 FROM last_")
def _(spark, sf):
    index, _, _, ranks, _ = full(spark, sf, "docs_u")
    return metrics.last_rank(metrics.located(truth(spark, sf, "docs_u"), index, ranks))


@query("front_load_docs_u", f"WITH {docs()}, {q.truth(10, 0.85)}, {_PLACE}, g AS (SELECT unnest([1, 2, 4, 8, 16, 32]) AS within) SELECT CAST(within AS BIGINT) AS within, round(count(*) FILTER (rank <= within) / nullif(count(*), 0), 6) AS share FROM place, g GROUP BY within")
def _(spark, sf):
    index, _, _, ranks, _ = full(spark, sf, "docs_u")
    return metrics.front_load(metrics.located(truth(spark, sf, "docs_u"), index, ranks))


@query("prune_by_group_docs_u", f"WITH {docs()}, {q.truth(10, 0.85)}, {q.stops('[8]')}, n AS (SELECT s.query_id, stop, count(t.vec_id) AS n FROM stop s LEFT JOIN truth t USING (query_id) GROUP BY ALL) SELECT {metrics.GROUPS} AS neighbours, count(*) AS queries, round(100 * (1 - sum(stop) / (count(*) * max(p))), 4) AS pruned_pct FROM n, lists GROUP BY 1")
def _(spark, sf):
    index, held = wl.index_of(spark, sf, "docs_u")
    r = search.lookahead(index, held, wl.WORKLOADS["docs_u"].params)
    return metrics.prune_by_group(r.visits, truth(spark, sf, "docs_u"), min(index.lists, wl.WORKLOADS["docs_u"].params.nprobe))


@query("metadata_items_docs_u", f"WITH {docs()}, {q.stops('[8]')}, x AS (SELECT (SELECT count(*) FROM probe) AS f, (SELECT CAST(sum(stop) AS BIGINT) FROM stop) AS v, (SELECT count(*) FROM qs) AS n) SELECT unnest(['fixed', 'basic', 'basic_at_once', 'lookahead']) AS mode, unnest([f, v, n, v]) AS items FROM x")
def _(spark, sf):
    index, held, params, ranks, _ = full(spark, sf, "docs_u")
    r = search.lookahead(index, held, params)
    items = metrics.scheduled_items(ranks.count(), r.visits.agg(F.sum("visits")).first()[0], held.count())
    return spark.createDataFrame(list(items.items()), "mode string, items bigint")


def _shape_sql(name: str) -> str:
    w = wl.WORKLOADS[name]
    chain = q.probed(w.source, w.tau, 90, w.pairs, seed_every=w.seed_every, plant=name == "emb_plant")
    return f"""SELECT * FROM (WITH {chain}, {q.truth(10, w.tau)}, {_PLACE}, last_ AS (SELECT query_id, max(rank) AS r FROM place GROUP BY query_id), n_ AS (SELECT count(*) AS n FROM qs), per AS (SELECT query_id, count(*) AS k FROM truth GROUP BY query_id)
SELECT '{name}' AS workload, CAST({w.tau} AS DOUBLE) AS tau, (SELECT n FROM n_) AS queries, (SELECT round(100.0 * (1 - count(*) / greatest((SELECT n FROM n_), 1)), 2) FROM per) AS none_pct, (SELECT round(100.0 * count(*) FILTER (k >= 10) / greatest((SELECT n FROM n_), 1), 2) FROM per) AS ten_pct,
(SELECT quantile_cont(r, 0.5) FROM last_) AS p50, (SELECT quantile_cont(r, 0.9) FROM last_) AS p90, (SELECT round(count(*) FILTER (rank <= 8) / nullif(count(*), 0), 6) FROM place) AS first8)"""


@query("workload_shapes", " UNION ALL ".join(_shape_sql(n) for n in wl.WORKLOADS))
def _(spark, sf):
    """For each workload: queries, shares without and with ten or more neighbours, where the last one lies, and what the first eight ranks hold."""
    rows = []
    for name, w in wl.WORKLOADS.items():
        index, held, _, ranks, _ = full(spark, sf, name)
        n = held.count()
        gt = truth(spark, sf, name, 10)
        per = gt.groupBy("query_id").agg(F.count(F.lit(1)).alias("n")).agg(F.count(F.lit(1)), F.coalesce(F.sum((F.col("n") >= 10).cast("int")), F.lit(0))).first()
        place = metrics.located(gt, index, ranks)
        last = metrics.last_rank(place).first()
        eight = {r.within: r.share for r in metrics.front_load(place, (8,)).collect()}
        rows.append((name, w.tau, n, round(100 * (1 - per[0] / max(n, 1)), 2), round(100 * per[1] / max(n, 1), 2), last.p50, last.p90, eight.get(8)))
    return spark.createDataFrame(rows, "workload string, tau double, queries bigint, none_pct double, ten_pct double, p50 double, p90 double, first8 double")


@query("assign_effect_docs_u")
def _(spark, sf):
    """Exact, cell-routed and graph-assisted assignment over the same trained centroids: mismatch, and loss that early stopping adds."""
    index, held, params, _, _ = full(spark, sf, "docs_u", 3)
    base, _ = wl.split(wl.vectors_of(spark, sf, "docs_u"))
    gt, rows, exact = truth(spark, sf, "docs_u"), [], {}
    for name, choose in (("exact", None), ("cells", approximate.cell_chooser(index.centroids)), ("graph", approximate.graph_chooser(index.centroids))):
        own = index if choose is None else ivf.build(base, index.centroids, choose)
        wrong = metrics.mismatch(own.postings(), index.postings()).first().pct
        ranks, local = search.full_probe(own, held, params)
        fixed = metrics.pooled_recall(search.merge_top(local, 10), gt)
        for r in sweep(spark, ranks, local, gt, [2, 4, 8, 12, 16]).collect():
            exact.setdefault(r.w, (fixed, r.recall))
            added = None if fixed is None or r.recall is None else round(metrics.added_loss(fixed, r.recall, *exact[r.w]), 4)
            rows.append((name, r.w, wrong, r.visits, r.recall, added))
    return spark.createDataFrame(rows, "assignment string, w int, mismatch_pct double, visits bigint, recall double, added_loss_pp double")


_ROUTED = f"""WITH {docs()}, {_CELLS}, {q.truth(10, 0.85)}, grid AS (SELECT unnest([2, 4, 8, 12, 16]) AS w),
met_c AS MATERIALIZED (SELECT s.query_id, s.vec_id, s.sim, p.rank FROM scored s JOIN routed a ON a.id = s.vec_id JOIN probe p ON p.query_id = s.query_id AND p.pid = a.pid WHERE s.sim >= 0.85),
outcome_c AS MATERIALIZED (SELECT p.query_id, p.rank, count(m.vec_id) AS n_hits FROM probe p LEFT JOIN met_c m ON m.query_id = p.query_id AND m.rank = p.rank GROUP BY ALL),
quiet_c AS MATERIALIZED (SELECT query_id, rank, rank - coalesce(max(CASE WHEN n_hits > 0 THEN rank END) OVER (PARTITION BY query_id ORDER BY rank), 0) AS stale FROM outcome_c),
stop_c AS MATERIALIZED (SELECT query_id, w, coalesce(min(rank) FILTER (stale >= w), max(rank)) AS stop FROM quiet_c, grid GROUP BY ALL),
kept AS (SELECT s.w, m.* FROM met_c m JOIN stop_c s ON s.query_id = m.query_id AND m.rank <= s.stop), found AS ({q.top('kept', 10, extra='w, ')}),
hit AS (SELECT w, count(*) AS n FROM found JOIN truth USING (query_id, vec_id) GROUP BY w)
SELECT s.w, (SELECT round(100.0 * count(*) FILTER (r.pid <> a.pid) / count(*), 4) FROM routed r JOIN assigned a USING (id)) AS mismatch_pct, CAST(sum(stop) AS BIGINT) AS visits, round(coalesce(any_value(hit.n), 0) / nullif((SELECT count(*) FROM truth), 0), 6) AS recall FROM stop_c s LEFT JOIN hit USING (w) GROUP BY s.w"""


@query("assign_cells_effect_docs_u", _ROUTED)
def _(spark, sf):
    """Cell-routed assignment: mismatch, and what each window visits and finds."""
    index, held, params, _, _ = full(spark, sf, "docs_u")
    every, _ = wl.split(wl.vectors_of(spark, sf, "docs_u"))
    own = ivf.build(every, index.centroids, approximate.cell_chooser(index.centroids))
    ranks, local = search.full_probe(own, held, params)
    wrong = metrics.mismatch(own.postings(), index.postings()).first().pct
    return sweep(spark, ranks, local, truth(spark, sf, "docs_u"), [2, 4, 8, 12, 16]).select("w", F.lit(wrong).alias("mismatch_pct"), "visits", "recall")


# ---- shards

def _shard_sql(source: str, tau: float, window: int) -> str:
    return f"""{q.index(source)},
first4 AS MATERIALIZED (SELECT pid, vec, n2 FROM c ORDER BY pid LIMIT 4),
near4 AS MATERIALIZED (SELECT base.id, f.pid FROM base, first4 f QUALIFY row_number() OVER (PARTITION BY base.id ORDER BY round({q.sim('base', 'f')}, 9) DESC, f.pid) = 1),
{q.moved('near4', 'first4')},
go AS MATERIALIZED (SELECT base.id, m.pid AS shard_id FROM base, moved m QUALIFY row_number() OVER (PARTITION BY base.id ORDER BY round({q.sim('base', 'm')}, 9) DESC, m.pid) = 1),
fine AS MATERIALIZED (SELECT go.shard_id, row_number() OVER (PARTITION BY go.shard_id ORDER BY base.id) - 1 AS pid, base.vec, base.n2 FROM base JOIN go USING (id) WHERE base.id % (SELECT greatest(25, CAST(round_even(sqrt(count(*)) / 4, 0) AS BIGINT)) FROM v) = 0),
kept_ AS MATERIALIZED (SELECT base.id, go.shard_id, f.pid FROM base JOIN go USING (id) JOIN fine f ON f.shard_id = go.shard_id QUALIFY row_number() OVER (PARTITION BY base.id ORDER BY round({q.sim('base', 'f')}, 9) DESC, f.pid) = 1),
probe AS MATERIALIZED (SELECT * FROM (SELECT qs.id AS query_id, f.shard_id, f.pid, row_number() OVER (PARTITION BY qs.id, f.shard_id ORDER BY round({q.sim('qs', 'f')}, 9) DESC, f.pid) AS rank FROM qs, fine f) WHERE rank <= 90),
scored AS MATERIALIZED (SELECT qs.id AS query_id, base.id AS vec_id, round({q.sim('qs', 'base')}, 12) AS sim FROM qs, base WHERE qs.id <> base.id),
met AS MATERIALIZED (SELECT s.query_id, p.shard_id, s.vec_id, s.sim, p.rank FROM scored s JOIN kept_ a ON a.id = s.vec_id JOIN probe p ON p.query_id = s.query_id AND p.shard_id = a.shard_id AND p.pid = a.pid WHERE s.sim >= {tau}),
outcome AS MATERIALIZED (SELECT p.query_id, p.shard_id, p.rank, count(m.vec_id) AS n_hits FROM probe p LEFT JOIN met m USING (query_id, shard_id, rank) GROUP BY ALL),
quiet AS MATERIALIZED (SELECT query_id, shard_id, rank, rank - coalesce(max(CASE WHEN n_hits > 0 THEN rank END) OVER (PARTITION BY query_id, shard_id ORDER BY rank), 0) AS stale FROM outcome),
stop AS MATERIALIZED (SELECT query_id, shard_id, coalesce(min(rank) FILTER (stale >= {window}), max(rank)) AS stop FROM quiet GROUP BY ALL),
kept AS (SELECT m.* FROM met m JOIN stop s USING (query_id, shard_id) WHERE m.rank <= s.stop)"""


@query("shard_topk_emb", f"WITH {_shard_sql('embeddings', 0.3, 4)} {q.EDGES.format(q.top('kept', 10))}")
def _(spark, sf):
    index, held = wl.shard_index_of(spark, sf, "emb")
    return rounded(search.lookahead(index, held, wl.WORKLOADS["emb"].params.with_(window=4)).edges)


_SHARD_WINDOWS = [2, 4, 8, 12]

for _n, _src, _tau in (("docs_u", "documents", 0.85), ("emb", "embeddings", 0.30)):

    @query(
        f"shard_w_sweep_{_n}",
        " UNION ALL ".join(f"SELECT * FROM (WITH {_shard_sql(_src, _tau, w)}, {q.truth(10, _tau)}, found AS ({q.top('kept', 10)}) SELECT {w} AS w, (SELECT CAST(sum(stop) AS BIGINT) FROM stop) AS visits, round(count(f.vec_id) / nullif(count(t.vec_id), 0), 6) AS recall FROM truth t LEFT JOIN found f USING (query_id, vec_id))" for w in _SHARD_WINDOWS),
    )
    def _(spark, sf, name=_n):
        index, held = wl.shard_index_of(spark, sf, name)
        ranks, local = search.full_probe(index, held, wl.WORKLOADS[name].params)
        return sweep(spark, ranks, local, truth(spark, sf, name), _SHARD_WINDOWS).select("w", "visits", "recall")


# ---- groups

@query("self_search_docs_u", adaptive_sql(docs(everything=True), 8))
def _(spark, sf):
    index, _ = wl.index_of(spark, sf, "docs_u")
    return rounded(edges.self_search(index, wl.vectors_of(spark, sf, "docs_u"), wl.WORKLOADS["docs_u"].params).edges)


_PAIRS = f"WITH {q.vectors('documents')}, pairs AS (SELECT a.id AS id_a, b.id AS id_b, round({q.sim('a', 'b')}, 12) AS sim FROM v a JOIN v b ON a.id < b.id WHERE round({q.sim('a', 'b')}, 12) >= 0.85)"

for _n, _prune in (("pair_join_docs_u", False), ("pair_join_pruned_docs_u", True)):

    @query(_n, f"{_PAIRS} SELECT id_a, id_b, round(sim, 6) AS sim FROM pairs")
    def _(spark, sf, prune=_prune):
        return edges.pair_join(wl.index_of(spark, sf, "docs_u")[0], 0.85, prune)[0].select("id_a", "id_b", F.round("sim", 6).alias("sim"))


_ANGLE = "acos(greatest(-1.0, least(1.0, {})))"
_COST = f"""WITH {docs(everything=True)}, rad AS (SELECT c.pid, any_value(c.vec) AS vec, any_value(c.n2) AS n2, max({_ANGLE.format(q.sim('base', 'c'))}) AS r, count(*) AS n FROM assigned a JOIN base USING (id) JOIN c USING (pid) GROUP BY c.pid),
met_ AS (SELECT CASE WHEN x.pid = y.pid THEN x.n * (x.n - 1) // 2 ELSE x.n * y.n END AS n, x.pid = y.pid OR {_ANGLE.format(q.sim('x', 'y'))} - x.r - y.r <= acos(0.85) + 1e-9 AS near FROM rad x JOIN rad y ON x.pid <= y.pid)
SELECT 'all' AS method, CAST(sum(n) AS BIGINT) AS pairs_scored FROM met_ UNION ALL SELECT 'pruned', CAST(coalesce(sum(n) FILTER (near), 0) AS BIGINT) FROM met_"""


@query("pair_join_cost_docs_u", _COST)
def _(spark, sf):
    index, _ = wl.index_of(spark, sf, "docs_u")
    parts = [edges.pair_join(index, 0.85, p)[1].select(F.lit(m).alias("method"), "pairs_scored") for m, p in (("all", False), ("pruned", True))]
    return parts[0].union(parts[1])


def _self_edges(spark, sf, k=10):
    """(edges, components) of self-search: what the method finds with k neighbours a vector."""
    def make():
        index, _ = wl.index_of(spark, sf, "docs_u")
        r = edges.self_search(index, wl.vectors_of(spark, sf, "docs_u"), wl.WORKLOADS["docs_u"].params.with_(k=k))
        e = materialize(edges.canonical(r.edges), "canonical")
        return e, edges.components_of(e)

    return wl._once(spark, ("self-edges", sf, "docs_u", k), make)


def _members(spark, sf):
    """Membership of equal texts of a language, over the documents that have a vector: equal texts all have one, or none has."""
    def make():
        vectored = wl.vectors_of(spark, sf, "docs_u").select("id")
        return materialize(edges.representatives(table(spark, sf, "documents"), ["text", "lang"]).join(vectored, "id", "left_semi"), "members")

    return wl._once(spark, ("members", sf, "docs_u"), make)


def _representatives(spark, sf):
    """The vectors of the texts that stand for their copies."""
    reps = _members(spark, sf).where("id = representative").select("id")
    return wl.vectors_of(spark, sf, "docs_u").join(reps, "id", "left_semi").select("id", "vec")


def _connected(spark, sf):
    """(components of all links between different texts within the threshold, exactly; membership of equal ones)."""
    def make():
        stars = tiles.forest(tiles.write(_representatives(spark, sf)), wl.WORKLOADS["docs_u"].tau)
        return edges.components_of(materialize(stars, "stars"))

    return wl._once(spark, ("connected", sf, "docs_u"), make), _members(spark, sf)


def _agreed(spark, sf):
    """Links between representatives that the texts bear out; copies are in the membership."""
    def make():
        words = edges.word_sets(table(spark, sf, "documents").where("lang is not null"))
        worded = _representatives(spark, sf).join(words, "id")
        return materialize(tiles.agreeing(tiles.write(worded), wl.WORKLOADS["docs_u"].tau), "agreed")

    return wl._once(spark, ("agreed", sf, "docs_u"), make)


_CANON = f"WITH RECURSIVE {q.vectors('documents')}, member AS MATERIALIZED (SELECT doc_id AS id, min(doc_id) OVER (PARTITION BY text, lang) AS rep FROM documents WHERE doc_id IN (SELECT id FROM v)), w AS MATERIALIZED (SELECT * FROM v WHERE id IN (SELECT rep FROM member)), canon AS MATERIALIZED (SELECT a.id AS id_a, b.id AS id_b, round({q.sim('a', 'b')}, 12) AS sim FROM w a JOIN w b ON a.id < b.id WHERE round({q.sim('a', 'b')}, 12) >= 0.85)"
_WALK = "both_ AS (SELECT id_a AS u, id_b AS w FROM canon UNION SELECT id_b, id_a FROM canon), walk AS (SELECT DISTINCT u AS node, u AS seen FROM both_ UNION SELECT walk.node, both_.w FROM walk JOIN both_ ON both_.u = walk.seen), comp0 AS MATERIALIZED (SELECT node, min(seen) AS component FROM walk GROUP BY node)"
_COMP = f", {_WALK}, comp1 AS (SELECT m.id AS node, coalesce(component, rep) AS component FROM member m LEFT JOIN comp0 ON node = rep), comp AS MATERIALIZED (SELECT * FROM comp1 QUALIFY count(*) OVER (PARTITION BY component) > 1)"


@query("components_docs_u", f"{_CANON}{_COMP} SELECT node, component FROM comp")
def _(spark, sf):
    return edges.spread(*_connected(spark, sf))


_LABELLED = ", mark AS (SELECT doc_id, max(quality) AS quality FROM labels GROUP BY doc_id), every AS (SELECT d.doc_id AS id, coalesce(component, d.doc_id) AS component, n_chars, quality, lang, source FROM documents d LEFT JOIN comp ON node = d.doc_id LEFT JOIN mark USING (doc_id)), labelled AS (SELECT id, component, count(*) OVER (PARTITION BY component) AS group_size, row_number() OVER (PARTITION BY component ORDER BY coalesce(quality, -1) DESC, n_chars DESC, id) = 1 AS keep, lang, source FROM every)"


@query("group_labels_docs_u", f"{_CANON}{_COMP}{_LABELLED} SELECT id, component, group_size, keep FROM labelled")
def _(spark, sf):
    return edges.label_groups(edges.spread(*_connected(spark, sf)), table(spark, sf, "documents"), table(spark, sf, "labels"))


_JACCARD = ", wd AS MATERIALIZED (SELECT DISTINCT doc_id AS id, w FROM (SELECT doc_id, unnest(list_filter(regexp_split_to_array(coalesce(text, ''), '[ \\t\\r\\n]+'), lambda w: w <> '')) AS w FROM documents)), size_ AS (SELECT id, count(*) AS n FROM wd GROUP BY id), shared AS (SELECT id_a, id_b, count(*) AS n FROM canon JOIN wd a ON a.id = id_a JOIN wd b ON b.id = id_b AND b.w = a.w GROUP BY id_a, id_b), overlap AS (SELECT id_a, id_b, s.n / (x.n + y.n - s.n) AS j FROM shared s JOIN size_ x ON x.id = id_a JOIN size_ y ON y.id = id_b JOIN documents d ON d.doc_id = id_a JOIN documents e ON e.doc_id = id_b WHERE d.lang = e.lang)"


@query("content_filter_docs_u", f"{_CANON}{_JACCARD} SELECT id_a, id_b, round(j, 6) AS jaccard FROM overlap WHERE j >= 0.5")
def _(spark, sf):
    return _agreed(spark, sf).select("id_a", "id_b", F.round("jaccard", 6).alias("jaccard"))


def _coverage_sql(k: int) -> str:
    chain = f"{docs(everything=True)}, {q.stops('[8]')}, {_KEPT}, found AS ({q.top('kept', k)}), canon AS MATERIALIZED (SELECT least(query_id, vec_id) AS id_a, greatest(query_id, vec_id) AS id_b FROM found GROUP BY ALL), {_WALK}"
    return f"SELECT * FROM (WITH RECURSIVE {chain}, pairs AS (SELECT query_id AS id_a, vec_id AS id_b FROM scored WHERE query_id < vec_id AND sim >= 0.85) SELECT {k} AS k, count(*) AS pairs, round(100.0 * count(c.id_a) / nullif(count(*), 0), 4) AS direct_pct, round(100.0 * count(*) FILTER (x.component = y.component) / nullif(count(*), 0), 4) AS grouped_pct FROM pairs p LEFT JOIN canon c USING (id_a, id_b) LEFT JOIN comp0 x ON x.node = p.id_a LEFT JOIN comp0 y ON y.node = p.id_b)"


_COVER = (10, 20, 40)


@query("coverage_docs_u", " UNION ALL ".join(_coverage_sql(k) for k in _COVER))
def _(spark, sf):
    """How many of all true pairs self-search joins by an edge, or puts in one group."""
    pairs = wl._once(spark, ("pairs", sf, "docs_u"), lambda: materialize(edges.pair_join(wl.index_of(spark, sf, "docs_u")[0], 0.85, True)[0], "pairs"))
    out = None
    for k in _COVER:
        e, comp = _self_edges(spark, sf, k)
        row = metrics.pair_coverage(pairs, e, comp).select(F.lit(k).alias("k"), "pairs", "direct_pct", "grouped_pct")
        out = row if out is None else out.union(row)
    return out


@query("exact_hash_docs", "SELECT md5(text) AS hash, count(*) AS copies, min(doc_id) AS first_id FROM documents GROUP BY md5(text) HAVING count(*) > 1")
def _(spark, sf):
    return edges.exact_hash(table(spark, sf, "documents"))


_E2E = _CANON + _JACCARD + ", canon2 AS MATERIALIZED (SELECT id_a, id_b FROM overlap WHERE j >= 0.5)" + _COMP.replace("FROM canon", "FROM canon2") + _LABELLED


@query("end_to_end_docs", f"{_E2E} SELECT lang, source, count(*) FILTER (keep) AS kept, count(*) FILTER (NOT keep) AS dropped FROM labelled GROUP BY lang, source")
def _(spark, sf):
    d = table(spark, sf, "documents")
    marked = edges.label_groups(edges.spread(edges.components_of(_agreed(spark, sf)), _members(spark, sf)), d, table(spark, sf, "labels"))
    side = d.select(F.col("doc_id").alias("id"), "lang", "source")
    return marked.join(side, "id").groupBy("lang", "source").agg(F.sum(F.col("keep").cast("bigint")).alias("kept"), F.sum((~F.col("keep")).cast("bigint")).alias("dropped"))


_SAME = "(SELECT a.lang = b.lang FROM documents a, documents b WHERE a.doc_id = s.query_id AND b.doc_id = s.vec_id)"


@query("filtered_search_docs_lang", adaptive_sql(docs(same=_SAME), 8))
def _(spark, sf):
    """Neighbours in the query's language only: the filter comes before the local results and the rule."""
    lang = table(spark, sf, "documents").select(F.col("doc_id").alias("id"), F.xxhash64("lang").alias("lang_key")).where("lang_key is not null")
    every = wl.vectors_of(spark, sf, "docs_u").join(lang, "id")
    _, held = wl.split(every)
    index = ivf.build(every, wl.index_of(spark, sf, "docs_u")[0].centroids, attribute="lang_key")
    return rounded(search.walk(index, held, wl.WORKLOADS["docs_u"].params, attribute="lang_key").edges)


@query("stream_arrivals_docs")
def _(spark, sf):
    from tauprobe.streaming import arrivals

    return arrivals.replay(spark, wl.vectors_of(spark, sf, "docs_u"), wl.WORKLOADS["docs_u"].params, wl.SEED_EVERY, batches=10)


@query("vec_part_features", "WITH f AS (SELECT p_partkey AS id, [CAST(p_size AS DOUBLE) / 50, CAST(p_retailprice AS DOUBLE) / 2000, (p_partkey % 7 + 1) / 7.0] AS vec FROM part), v AS (SELECT id, vec, list_dot_product(vec, vec) AS n2 FROM f), s AS (SELECT a.id AS query_id, b.id AS vec_id, round(list_dot_product(a.vec, b.vec) / sqrt(a.n2 * b.n2), 12) AS sim FROM v a JOIN v b ON a.id % 50 = 0 AND b.id <> a.id) SELECT query_id, vec_id, round(sim, 6) AS sim, pos FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY sim DESC, vec_id) AS pos FROM s) WHERE pos <= 3")
def _(spark, sf):
    f = table(spark, sf, "part").select(F.col("p_partkey").cast("bigint").alias("id"), F.array(F.col("p_size").cast("double") / 50, F.col("p_retailprice").cast("double") / 2000, (F.col("p_partkey") % 7 + 1) / 7.0).alias("vec"))
    return rounded(search.exact(f, f.where("id % 50 = 0"), -2.0, 3, drop_self=True))

