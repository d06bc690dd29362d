"""Simulation of an asynchronous executor: a queue of partition groups, workers, microbatches and a partition cache.

It replays hit bits, so every policy must do the same searches; what differs is how full microbatches are, how often a
partition is loaded, how long the queue gets and when the last search ends.
"""

from __future__ import annotations

import heapq
import random
from collections import OrderedDict
from collections.abc import Iterable
from dataclasses import dataclass, field

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Probe:
    query: int
    pids: tuple[int, ...]
    hits: tuple[bool, ...]


@dataclass
class Trace:
    dispatches: list[tuple[int, tuple[tuple[int, int], ...]]] = field(default_factory=list)  # (pid, items)
    loads: int = 0
    peak_queue: int = 0
    makespan: float = 0.0

    @property
    def items(self) -> int:
        return sum(len(b) for _, b in self.dispatches)

    @property
    def occupancy(self) -> float:
        return self.items / len(self.dispatches) if self.dispatches else 0.0


def as_queries(outcomes: Iterable) -> list[Probe]:
    """Rows (query_id, shard_id, rank, pid, n_hits), ordered by query and rank, as probes."""
    held: dict[tuple[int, int], list] = {}
    for r in outcomes:
        held.setdefault((r.query_id, r.shard_id), []).append(r)
    return [Probe(k[0], tuple(r.pid for r in rows), tuple(r.n_hits > 0 for r in rows)) for k, rows in held.items()]


def run(probes: list[Probe], window: int, mode: str = "lookahead", order: str = "fifo", workers: int = 4, cap: int = 16384, cache: int = 8, seed: int = 1, cost: tuple[float, float, float] = (1.0, 0.02, 4.0)) -> Trace:
    """Events until no item is ready or under way. cost: of a dispatch, of an item, of loading a partition."""
    rng, trace = random.Random(seed), Trace()
    groups: OrderedDict[int, list[tuple[int, int]]] = OrderedDict()  # in the order of their first item
    kept: OrderedDict[int, None] = OrderedDict()
    line = [min(window, len(p.pids)) for p in probes]
    cursor = [1] * len(probes)

    def admit(i: int) -> None:
        last = line[i] if mode == "lookahead" else min(line[i], cursor[i])
        for rank in range(cursor[i], last + 1):
            groups.setdefault(probes[i].pids[rank - 1], []).append((i, rank))
        cursor[i] = max(cursor[i], last + 1)

    for i in range(len(probes)):
        admit(i)
    now, busy, n = 0.0, [], 0
    while groups or busy:
        while groups and len(busy) < workers:
            trace.peak_queue = max(trace.peak_queue, sum(map(len, groups.values())))
            pid = {"fifo": lambda: next(iter(groups)), "random": lambda: rng.choice(list(groups)), "largest": lambda: max(groups, key=lambda p: (len(groups[p]), -p))}[order]()
            items = groups.pop(pid)
            batch, rest = items[:cap], items[cap:]
            if rest:
                groups[pid] = rest
            loaded = pid in kept
            kept.pop(pid, None)
            kept[pid] = None
            if len(kept) > cache:
                kept.popitem(last=False)
            trace.loads += not loaded
            trace.dispatches.append((pid, tuple((probes[i].query, r) for i, r in batch)))
            n += 1
            heapq.heappush(busy, (now + cost[0] + cost[1] * len(batch) + (0 if loaded else cost[2]), n, batch))
        now, _, batch = heapq.heappop(busy)
        for i, rank in batch:
            if probes[i].hits[rank - 1]:
                line[i] = max(line[i], min(rank + window, len(probes[i].pids)))
            admit(i)
    trace.makespan = now
    return trace


def compare(probes: list[Probe], window: int, **more) -> list[tuple]:
    """Rows (policy, mode, dispatches, items, occupancy, loads, peak_queue, makespan) for every order and mode."""
    rows = []
    for mode in ("basic", "lookahead"):
        for order in ("fifo", "random", "largest"):
            t = run(probes, window, mode, order, **more)
            rows.append((order, mode, len(t.dispatches), t.items, round(t.occupancy, 4), t.loads, t.peak_queue, round(t.makespan, 4)))
    return rows


def compare_calls(outcomes: DataFrame, window: int, call_queries: int = 10_000) -> DataFrame:
    """The comparison for query sets of any size: queries come in calls of about call_queries, each simulated in a task of its own.

    Dispatches, items, loads and time add up over the calls; the queue's peak is that of the worst call.
    """
    calls = -(-outcomes.agg(F.count_distinct("query_id")).first()[0] // call_queries)
    dealt = outcomes.withColumn("call", F.pmod(F.xxhash64("query_id"), F.lit(max(1, calls))))

    def one(rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values(["query_id", "shard_id", "rank"])
        return pd.DataFrame(compare(as_queries(rows.itertuples(index=False)), window), columns=["policy", "mode", "dispatches", "items", "occupancy", "loads", "peak_queue", "makespan"])

    each = dealt.groupBy("call").applyInPandas(one, "policy string, mode string, dispatches bigint, items bigint, occupancy double, loads bigint, peak_queue bigint, makespan double")
    total = each.groupBy("policy", "mode").agg(*[F.sum(c).alias(c) for c in ("dispatches", "items", "loads")], F.max("peak_queue").alias("peak_queue"), F.round(F.sum("makespan"), 4).alias("makespan"))
    return total.select("policy", "mode", "dispatches", "items", F.round(F.col("items") / F.col("dispatches"), 4).alias("occupancy"), "loads", "peak_queue", "makespan")
