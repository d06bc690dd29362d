"""Search of an inverted-file index: fixed probing, continuous batching with the stopping rule, waves, and replay.

Two executors share one kernel. In `walk`, tasks hold queries and read partitions: queries that look into the same
partitions first are dealt to the same task by range, so a task meets few partitions often. A task keeps a queue of groups,
one for each partition with ready items; it takes a group, reads the partition's blocks from the index's files (or from what
it read last), scores group and block in one matrix product, and at once makes the ranks ready that the answers commit. With
lookahead all committed ranks are ready, in basic mode one rank a query. The whole search is one pass over the queries.
The index is read where it lies; nothing of it is shuffled.

In `search`, query and partition pairs are grouped by partition into microbatches and joined with the partition's blocks.
That is how full passes for sweeps run, where all pairs are known beforehand, and `waves`, the rule in rounds of such joins: a wave
sends every rank that is committed and not yet sent, and the answers move the queries' stop lines (by maximum, so the order
within a wave does not matter). Waves need no files that Arrow can open, but a job for each wave.
"""

from __future__ import annotations

import random
from collections.abc import Callable, Iterator
from dataclasses import dataclass
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from tauprobe.operators import ivf, rule
from tauprobe.params import SearchParams
from tauprobe.session import materialize

LOCAL = "query_id bigint, shard_id int, rank int, vec_id bigint, sim double"
#: What a task of `walk` gives: hits (kind 0), where each query ended (1), and counts of each call (2).
WALKED = LOCAL + ", kind tinyint"
TILE = 1024
#: Similarities are rounded so far, so that the shape of a product does not change what compares as equal.
DECIMALS = 12


def score_exact(queries: np.ndarray, norms: np.ndarray, block: dict) -> np.ndarray:
    """Cosines of query rows and block rows. Products of whole numbers are exact in double precision."""
    if "wide" not in block:
        block["wide"] = np.frombuffer(block["mat"], "<f4").reshape(block["n"], -1).astype(np.float64)
    sims = queries @ block["wide"].T
    scale = np.multiply.outer(norms, block["norms"])
    np.sqrt(scale, out=scale)
    sims /= scale
    return np.round(sims, DECIMALS, out=sims)


def local_top(sims: np.ndarray, ids: np.ndarray, tau: float, k: int, own: np.ndarray | None) -> tuple[np.ndarray, np.ndarray]:
    """(row, column) of at most k hits a row, best first, ties to the smaller id."""
    hit = sims >= tau
    if own is not None:
        hit &= own[:, None] != ids[None, :]
    rows, columns = np.nonzero(hit)
    order = np.lexsort((ids[columns], -sims[rows, columns], rows))
    rows, columns = rows[order], columns[order]
    first = np.searchsorted(rows, rows)
    keep = np.arange(len(rows)) - first < k
    return rows[keep], columns[keep]


def microbatches(frontier: DataFrame, queries: DataFrame, cap: int, largest: int | None = None) -> DataFrame:
    """Rows (shard_id, pid, chunk, items): the queries that search a partition together, at most about cap of them.

    A group that is larger is dealt into chunks by a hash, so no row and no task has more than its share. largest is the
    size of the largest group, where it is known: up to cap there is nothing to deal.
    """
    vectors = queries.select(F.col("id").alias("query_id"), "vec")
    if largest is not None and largest <= cap:
        return frontier.join(vectors, "query_id").groupBy("shard_id", "pid").agg(F.lit(0).alias("chunk"), F.collect_list(F.struct("query_id", "rank", "vec")).alias("items"))
    sizes = frontier.groupBy("shard_id", "pid").agg(F.ceil(F.count(F.lit(1)) / cap).cast("int").alias("chunks")).where("chunks > 1")
    dealt = frontier.join(sizes, ["shard_id", "pid"], "left").withColumn("chunk", F.when(F.col("chunks") > 1, F.pmod(F.xxhash64("query_id"), F.col("chunks"))).otherwise(0).cast("int"))
    return dealt.join(vectors, "query_id").groupBy("shard_id", "pid", "chunk").agg(F.collect_list(F.struct("query_id", "rank", "vec")).alias("items"))


def search(frontier: DataFrame, queries: DataFrame, index: ivf.Index, params: SearchParams, scorer=score_exact, largest: int | None = None) -> DataFrame:
    """Local results of a frontier (query_id, shard_id, rank, pid): rows (query_id, shard_id, rank, vec_id, sim).

    Microbatches meet blocks one by one, by (shard, partition, block), so a large partition is as many keys as it has blocks.
    """
    places = index.blocks.select("shard_id", "pid", "block_no")
    batches_ = microbatches(frontier, queries, params.microbatch, largest).join(places, ["shard_id", "pid"])
    pairs = batches_.join(index.blocks, ["shard_id", "pid", "block_no"])
    columns = ["shard_id", "items", *[c for c in index.blocks.columns if c not in ("shard_id", "block_no")]]
    tau, k, drop_self = params.tau, params.k, params.drop_self

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(whole.num_rows):
                one = whole.slice(at, 1)
                items = one.column(1).flatten()
                qid = items.field(0).to_numpy()
                ranks = items.field(1).to_numpy()
                vecs = items.field(2).flatten().to_numpy(zero_copy_only=False).reshape(len(qid), -1)
                block = ivf.as_block(one)
                shard = one.column(0)[0].as_py()
                for lo in range(0, len(qid), TILE):
                    q = vecs[lo : lo + TILE]
                    sims = scorer(q, (q * q).sum(1), block)
                    rows, cols = local_top(sims, block["ids"], tau, k, qid[lo : lo + TILE] if drop_self else None)
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(qid[lo + rows]), pa.array(np.full(len(rows), shard, np.int32)), pa.array(ranks[lo + rows]), pa.array(block["ids"][cols]), pa.array(sims[rows, cols])],
                        ["query_id", "shard_id", "rank", "vec_id", "sim"],
                    )

    return pairs.select(*columns).mapInArrow(kernel, LOCAL)


def merge_top(local: DataFrame, k: int) -> DataFrame:
    """Edges (query_id, vec_id, sim, pos): each query's k best of all its local results, over all shards."""
    order = W.partitionBy("query_id").orderBy(F.desc("sim"), F.asc("vec_id"))
    return local.select("query_id", "vec_id", "sim", F.row_number().over(order).alias("pos")).where(F.col("pos") <= k)


@dataclass
class Result:
    edges: DataFrame
    #: (query_id, shard_id, visits)
    visits: DataFrame
    local: DataFrame
    #: Counts the work when it is asked for: the waves, and the partitions read.
    count: Callable[[], tuple[list[tuple[int, int, int]], int | None]] = lambda: ([], None)

    @cached_property
    def _counted(self) -> tuple[list[tuple[int, int, int]], int | None]:
        return self.count()

    @property
    def waves(self) -> list[tuple[int, int, int]]:
        """(wave, items, groups) of each wave; a walk is one."""
        return self._counted[0]

    @property
    def loads(self) -> int | None:
        """Partitions read."""
        return self._counted[1]


# ---- queues in tasks


class Queue:
    """The queries of one call: groups of ready items by partition, stop lines, and what is ready next."""

    def __init__(self, probes: list[np.ndarray], shards: np.ndarray, window: int, ahead: bool, order: str = "fifo", seed: int = 1):
        self.window, self.ahead, self.order = window, ahead, order
        self.most = np.array([len(p) for p in probes], np.int64)
        self.flat = np.concatenate(probes) if probes else np.zeros(0, np.int64)
        self.first = np.cumsum(self.most) - self.most
        self.shards = shards.astype(np.int64)
        self.line = np.minimum(window, self.most)
        self.sent = np.zeros(len(probes), np.int64)
        self.groups: dict[int, list[tuple[np.ndarray, np.ndarray]]] = {}  # in the order of their first item
        self.rng = random.Random(seed)
        self.admit(np.arange(len(probes)))

    def admit(self, who: np.ndarray) -> None:
        """Makes the committed ranks of these queries ready: all, or the next of each."""
        upto = self.line[who] if self.ahead else np.minimum(self.line[who], self.sent[who] + 1)
        n = upto - self.sent[who]
        items = np.repeat(who, n)
        if not len(items):
            return
        rank = self.sent[items] + 1 + np.arange(len(items)) - np.repeat(np.cumsum(n) - n, n)
        self.sent[who] = upto
        keys = self.shards[items] << 32 | self.flat[self.first[items] + rank - 1]
        by = np.argsort(keys, kind="stable")
        keys, items, rank = keys[by], items[by], rank[by]
        cuts = [0, *(np.flatnonzero(keys[1:] != keys[:-1]) + 1).tolist(), len(keys)]
        for a, b in zip(cuts, cuts[1:]):
            self.groups.setdefault(int(keys[a]), []).append((items[a:b], rank[a:b]))

    def take(self, cap: int) -> tuple[int, int, np.ndarray, np.ndarray]:
        """(shard, partition, queries, ranks) of the next microbatch; what is beyond the cap waits."""
        if self.order == "fifo":
            key = next(iter(self.groups))
        elif self.order == "random":
            key = self.rng.choice(list(self.groups))
        else:
            key = max(self.groups, key=lambda g: (sum(len(w) for w, _ in self.groups[g]), -g))
        parts = self.groups.pop(key)
        who, rank = (np.concatenate([p[i] for p in parts]) if len(parts) > 1 else parts[0][i] for i in (0, 1))
        if len(who) > cap:
            self.groups[key] = [(who[cap:], rank[cap:])]
        return key >> 32, key & 0xFFFFFFFF, who[:cap], rank[:cap]

    def answer(self, who: np.ndarray, rank: np.ndarray, hit: np.ndarray) -> None:
        """Moves stop lines by the ranks that had a hit, and admits what that commits."""
        moved = np.minimum(rank[hit] + self.window, self.most[who[hit]])
        np.maximum.at(self.line, who[hit], moved)
        self.admit(np.unique(who[hit]) if self.ahead else who)


def walk(index: ivf.Index, queries: DataFrame, params: SearchParams, ahead: bool = True, call: int | None = None, order: str = "fifo", scorer=score_exact, attribute: str | None = None) -> Result:
    """The stopping rule by continuous batching in tasks; `call` queries of a task are worked off at a time (default: the cap).

    `attribute` names an integer column of queries; the index's blocks have `attrs` then, and vectors with another value
    than the query's are no candidates: the filter comes before the rule.
    """
    files = tuple(sorted(index.blocks.inputFiles()))
    tau, k, window, cap, drop_self = params.tau, params.k, params.window, params.microbatch, params.drop_self
    call = call or cap

    def batch(rows: dict[str, np.ndarray | list], n: int, kind: int) -> pa.RecordBatch:
        types = [pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.float64()]
        return pa.RecordBatch.from_arrays([*(pa.array(rows[c], t) for c, t in zip(("query_id", "shard_id", "rank", "vec_id", "sim"), types)), pa.array(np.full(n, kind, np.int8))], ["query_id", "shard_id", "rank", "vec_id", "sim", "kind"])

    def one_call(store: ivf.BlockStore, part: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        qid, shards = part.column(0).to_numpy(), part.column(1).to_numpy()
        vecs = ivf._matrix(part.column(3))
        norms = (vecs * vecs).sum(1)
        wanted = part.column(4).to_numpy() if attribute else None
        lists = part.column(2)
        bounds, flat = lists.offsets.to_numpy(), lists.values.to_numpy().astype(np.int64)
        queue = Queue([flat[a:b] for a, b in zip(bounds, bounds[1:])], shards, window, ahead, order)
        held, n_held, dispatches, before = [], 0, 0, store.loads
        while queue.groups:
            shard, pid, who, rank = queue.take(cap)
            dispatches += 1
            hit = np.zeros(len(who), bool)
            for block in store.blocks(shard, pid):
                for lo in range(0, len(who), TILE):
                    some = who[lo : lo + TILE]
                    sims = scorer(vecs[some], norms[some], block)
                    if attribute:
                        sims[wanted[some][:, None] != block["attrs"][None, :]] = -9.0
                    rows, cols = local_top(sims, block["ids"], tau, k, qid[some] if drop_self else None)
                    if len(rows):
                        hit[lo + rows] = True
                        held.append((some[rows], rank[lo + rows], block["ids"][cols], sims[rows, cols]))
                        n_held += len(rows)
            queue.answer(who, rank, hit)
            if n_held > 1 << 16 or (n_held and not queue.groups):
                at, ranks, ids, sims = (np.concatenate([h[i] for h in held]) for i in range(4))
                yield batch({"query_id": qid[at], "shard_id": shards[at], "rank": ranks.astype(np.int32), "vec_id": ids, "sim": sims}, len(at), 0)
                held, n_held = [], 0
        none = [None] * len(qid)
        yield batch({"query_id": qid, "shard_id": shards, "rank": queue.line.astype(np.int32), "vec_id": none, "sim": none}, len(qid), 1)
        yield batch({"query_id": [int(queue.line.sum())], "shard_id": [0], "rank": [dispatches], "vec_id": [store.loads - before], "sim": [None]}, 1, 2)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, waiting, n = None, [], 0
        for b in batches:
            store = store or ivf.open_blocks(files)
            waiting.append(b)
            n += b.num_rows
            if n >= call:
                together = pa.Table.from_batches(waiting).combine_chunks().to_batches()[0]
                whole = n - n % call
                for lo in range(0, whole, call):
                    yield from one_call(store, _compact(together.slice(lo, call)))
                waiting, n = [together.slice(whole)], n - whole
        if n:
            together = pa.Table.from_batches(waiting).combine_chunks().to_batches()[0]
            yield from one_call(store, _compact(together))

    extra = [attribute] if attribute else []
    ranked = ivf.probe_lists(queries, index, params.nprobe, extra, with_vectors=True)
    first, rows = F.col("probes")[0], queries.count() * len(index.shards)
    tasks = task_count(rows, cap, queries.sparkSession.sparkContext.defaultParallelism)
    if rows <= 4 * cap:  # few enough for any deal; queries of one first partition go to four tasks at most
        near = ranked.repartition(tasks, "shard_id", first, F.pmod(F.xxhash64("query_id"), F.lit(4)))
    else:  # ranges are cut by a sample, for which the probes are written first
        near = materialize(ranked, "probes").repartitionByRange(tasks, "shard_id", first, "query_id")
    near = near.sortWithinPartitions("shard_id", first, "query_id")
    found = materialize(near.select("query_id", "shard_id", "probes", "vec", *extra).mapInArrow(kernel, WALKED), "walked")
    local = found.where("kind = 0").drop("kind")
    visits = found.where("kind = 1").select("query_id", "shard_id", F.col("rank").cast("bigint").alias("visits"))

    def count() -> tuple[list[tuple[int, int, int]], int]:
        items, dispatches, loads = found.where("kind = 2").agg(*[F.coalesce(F.sum(c), F.lit(0)) for c in ("query_id", "rank", "vec_id")]).first()
        return [(1, items, dispatches)], loads

    return Result(merge_top(local, k), visits, local, count)


def task_count(rows: int, cap: int, cores: int) -> int:
    """Tasks of a walk: as many as cores, twice as many where each has hundreds of queries, more where a task had many calls."""
    return max(1, cores if rows < 256 * cores else 2 * cores, -(-rows // (4 * cap)))


def _compact(part: pa.RecordBatch) -> pa.RecordBatch:
    """A slice as a batch of its own, so that its list columns begin at zero."""
    return pa.RecordBatch.from_arrays([pa.concat_arrays([c]) if c.offset == 0 else c.take(pa.array(np.arange(len(c)))) for c in part.columns], part.schema.names)


def publish(result: Result, prefix: str = "tau") -> None:
    """Makes a result's edges and visits known to SQL, as views <prefix>_edges and <prefix>_visits."""
    result.edges.createOrReplaceTempView(f"{prefix}_edges")
    result.visits.createOrReplaceTempView(f"{prefix}_visits")


def lookahead(index: ivf.Index, queries: DataFrame, params: SearchParams, scorer=score_exact) -> Result:
    return walk(index, queries, params, True, scorer=scorer) if ivf.readable(index) else waves(index, queries, params.with_(ranks_per_wave=None), scorer)


def basic(index: ivf.Index, queries: DataFrame, params: SearchParams, scorer=score_exact) -> Result:
    return walk(index, queries, params, False, scorer=scorer) if ivf.readable(index) else waves(index, queries, params.with_(ranks_per_wave=1), scorer)


def serial(index: ivf.Index, queries: DataFrame, params: SearchParams, scorer=score_exact) -> Result:
    """One query at a time, one partition after the other: the rule without any batching, which batching is compared with."""
    return walk(index, queries, params, False, call=1, scorer=scorer)


# ---- jobs over known pairs


def full_probe(index: ivf.Index, queries: DataFrame, params: SearchParams, scorer=score_exact) -> tuple[DataFrame, DataFrame]:
    """(ranked probes, local results of all of them)."""
    ranks = materialize(ivf.rank_table(ivf.probe_lists(queries, index, params.nprobe)), "probes")
    return ranks, materialize(search(ranks, queries, index, params, scorer), "local")


def fixed(index: ivf.Index, queries: DataFrame, params: SearchParams, scorer=score_exact) -> Result:
    """All nprobe partitions of every query; tau filters inside the partitions.

    This is the baseline of the stopping rule, so it runs by the same queues, which are its faster way too: a window of
    nprobe commits every rank at once.
    """
    if ivf.readable(index):
        return walk(index, queries, params.with_(window=params.nprobe), scorer=scorer)
    return fixed_by_joins(index, queries, params, scorer)


def fixed_by_joins(index: ivf.Index, queries: DataFrame, params: SearchParams, scorer=score_exact) -> Result:
    """The same as joins of microbatches and blocks."""
    ranks, local = full_probe(index, queries, params, scorer)
    visits = ranks.groupBy("query_id", "shard_id").agg(F.count(F.lit(1)).alias("visits"))

    def count() -> tuple[list[tuple[int, int, int]], int]:
        n = ranks.groupBy("shard_id", "pid").agg(F.count(F.lit(1)).alias("n")).agg(F.sum("n"), F.sum(F.ceil(F.col("n") / params.microbatch))).first()
        return [(1, n[0] or 0, n[1] or 0)], n[1] or 0

    return Result(merge_top(local, params.k), visits, local, count)


def waves(index: ivf.Index, queries: DataFrame, params: SearchParams, scorer=score_exact) -> Result:
    """The stopping rule in waves. Each wave's answers and state are on shared storage before the next begins."""
    p = F.size("probes")
    state = ivf.probe_lists(queries, index, params.nprobe).withColumn("cursor", F.lit(1)).withColumn("line", F.least(F.lit(params.window), p))
    state = materialize(state, "state")
    found, log, wave = [], [], 0
    while True:
        last = F.col("line") if params.ranks_per_wave is None else F.least("line", F.col("cursor") + params.ranks_per_wave - 1)
        active = state.where("cursor <= line").select("query_id", "shard_id", "probes", "cursor", last.alias("last"))
        sent = active.select("query_id", "shard_id", "probes", F.explode(F.sequence("cursor", "last")).alias("rank"))
        frontier = sent.select("query_id", "shard_id", "rank", F.element_at("probes", F.col("rank")).alias("pid"))  # follows from the stored state
        sizes = frontier.groupBy("shard_id", "pid").agg(F.count(F.lit(1)).alias("n"))
        items, groups, largest = sizes.agg(F.coalesce(F.sum("n"), F.lit(0)), F.coalesce(F.sum(F.ceil(F.col("n") / params.microbatch)), F.lit(0)), F.max("n")).first()
        if not items:
            break
        wave += 1
        log.append((wave, int(items), int(groups)))
        local = materialize(search(frontier, queries, index, params, scorer, largest), "local")
        found.append(local)
        hits = local.groupBy("query_id", "shard_id").agg(F.max("rank").alias("top"))
        moved = state.join(hits, ["query_id", "shard_id"], "left")
        moved = moved.select("query_id", "shard_id", "probes", F.when(F.col("cursor") <= F.col("line"), last + 1).otherwise(F.col("cursor")).alias("cursor"), F.greatest("line", F.least(F.coalesce(F.col("top") + params.window, F.lit(0)), p)).alias("line"))
        state = materialize(moved, "state")
    every = found[0] if found else queries.sparkSession.createDataFrame([], LOCAL)
    for more in found[1:]:
        every = every.union(more)
    return Result(merge_top(every, params.k), state.select("query_id", "shard_id", F.col("line").cast("bigint").alias("visits")), every, lambda: (log, sum(g for *_, g in log)))


def stops(ranks: DataFrame, local: DataFrame, windows: list[int]) -> DataFrame:
    """Rows (query_id, shard_id, w, stop): the rule's closed form for many windows from one full pass."""
    hits = local.groupBy("query_id", "shard_id").agg(F.sort_array(F.collect_set("rank")).alias("hits"))
    every = ranks.groupBy("query_id", "shard_id").agg(F.max("rank").alias("p"))
    grid = every.join(hits, ["query_id", "shard_id"], "left").select("query_id", "shard_id", "p", F.coalesce("hits", F.array().cast("array<int>")).alias("hits"), F.explode(F.lit(windows)).alias("w"))
    return grid.select("query_id", "shard_id", "w", rule.stop_line(F.col("hits"), F.col("w"), F.col("p")).alias("stop"))


def speculative(index: ivf.Index, queries: DataFrame, params: SearchParams, trim: bool = True) -> Result:
    """All ranks are sent, and the rule is applied afterwards: cut beyond the stop, or kept to see what changes."""
    ranks, local = full_probe(index, queries, params)
    ended = stops(ranks, local, [params.window]).drop("w")
    kept = local.join(ended, ["query_id", "shard_id"]).where("rank <= stop").drop("stop") if trim else local
    return Result(merge_top(kept, params.k), ended.select("query_id", "shard_id", F.col("stop").cast("bigint").alias("visits")), kept)


def replay(ranks: DataFrame, local: DataFrame, windows: list[int], k: int) -> tuple[DataFrame, DataFrame]:
    """(edges with w, stops with w) for each window, from one full pass."""
    ended = materialize(stops(ranks, local, windows), "stops")
    kept = local.join(ended, ["query_id", "shard_id"]).where("rank <= stop")
    order = W.partitionBy("w", "query_id").orderBy(F.desc("sim"), F.asc("vec_id"))
    return kept.select("w", "query_id", "vec_id", "sim", F.row_number().over(order).alias("pos")).where(F.col("pos") <= k), ended


def outcomes(ranks: DataFrame, local: DataFrame) -> DataFrame:
    """Rows (query_id, shard_id, rank, pid, n_hits) of all ranks."""
    hits = local.groupBy("query_id", "shard_id", "rank").agg(F.count(F.lit(1)).alias("n_hits"))
    return ranks.join(hits, ["query_id", "shard_id", "rank"], "left").select("query_id", "shard_id", "rank", "pid", F.coalesce("n_hits", F.lit(0)).alias("n_hits"))


# ---- brute force

#: Query vectors of a tile, base vectors of a tile, and bytes of query tiles that are sent to every task.
QUERY_TILE, BASE_TILE, SENT_BYTES = 1024, 2048, 64 << 20


def tiles(rows: DataFrame, size: int, prefix: str) -> DataFrame:
    """Rows (<prefix>ids, <prefix>mat): at most size vectors of (id, vec) each, as one matrix in double precision."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in ivf._tiles(batches, size):
            if b.num_rows:
                yield pa.RecordBatch.from_arrays([pa.array([b.column(0).to_numpy()], pa.list_(pa.int64())), pa.array([ivf._matrix(b.column(1)).tobytes()], pa.binary())], [f"{prefix}ids", f"{prefix}mat"])

    return rows.select("id", "vec").mapInArrow(kernel, f"{prefix}ids array<bigint>, {prefix}mat binary")


def exact(base: DataFrame, queries: DataFrame, tau: float = -2.0, k: int | None = None, drop_self: bool = False) -> DataFrame:
    """Brute force, without index or pruning: edges (query_id, vec_id, sim, pos) of the stated queries against all base rows.

    Queries and base rows meet as tiles. Where all query tiles are small enough to send, the base is not moved. Else tiles
    of the base are dealt over a grid of cells, to each of which the query tiles go once. Each pair of tiles leaves k
    candidates a query.
    """
    most = k or (1 << 31) - 1
    own = materialize(tiles(queries, QUERY_TILE, "q_"), "query-tiles")
    size, dim = own.agg(F.coalesce(F.sum(F.length("q_mat")), F.lit(0)), F.max(F.length("q_mat") / F.size("q_ids"))).first()
    cells = 1 if size <= SENT_BYTES else 4 * queries.sparkSession.sparkContext.defaultParallelism
    every = tiles(base, BASE_TILE, "").withColumn("cell", F.pmod(F.xxhash64(F.col("ids")[0]), F.lit(cells)))
    dealt = own.withColumn("cell", F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(cells - 1).cast("bigint"))))
    pairs = every.join(F.broadcast(dealt) if cells == 1 else dealt, "cell").select("q_ids", "q_mat", "ids", "mat")

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(whole.num_rows):
                qid, ids = (whole.column(c).slice(at, 1).flatten().to_numpy() for c in (0, 2))
                q, mat = (np.frombuffer(whole.column(c)[at].as_buffer(), np.float64).reshape(n, -1) for c, n in ((1, len(qid)), (3, len(ids))))
                norms = (mat * mat).sum(1)
                sims = np.round((q @ mat.T) / np.sqrt((q * q).sum(1)[:, None] * norms[None, :]), DECIMALS)
                rows, cols = local_top(sims, ids, tau, most, qid if drop_self else None)
                yield pa.RecordBatch.from_arrays([pa.array(qid[rows]), pa.array(np.zeros(len(rows), np.int32)), pa.array(np.zeros(len(rows), np.int32)), pa.array(ids[cols]), pa.array(sims[rows, cols])], ["query_id", "shard_id", "rank", "vec_id", "sim"])

    return merge_top(pairs.mapInArrow(kernel, LOCAL), most)
