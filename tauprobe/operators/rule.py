"""The stopping rule: a query stops after `window` visited partitions in a row without a hit. In plain Python and as columns."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W


def simulate(hits: Sequence[bool], window: int, nprobe: int | None = None) -> int:
    """Partitions visited when ranks are searched one after another."""
    p = len(hits) if nprobe is None else min(nprobe, len(hits))
    quiet = 0
    for rank in range(1, p + 1):
        quiet = 0 if hits[rank - 1] else quiet + 1
        if quiet == window:
            return rank
    return p


def lookahead_waves(hits: Sequence[bool], window: int, nprobe: int | None = None, ranks_per_wave: int | None = None) -> list[list[int]]:
    """The ranks of each wave when all committed ranks are sent at once (or so many of them at most)."""
    p = len(hits) if nprobe is None else min(nprobe, len(hits))
    line, cursor, waves = min(window, p), 1, []
    while cursor <= line:
        last = line if ranks_per_wave is None else min(line, cursor + ranks_per_wave - 1)
        sent = list(range(cursor, last + 1))
        waves.append(sent)
        cursor = last + 1
        line = max([line, *(min(r + window, p) for r in sent if hits[r - 1])])
    return waves


def stop_line(hit_ranks: Column, window: Column, nprobe: Column) -> Column:
    """Where a query stops, from the sorted array of ranks that would hit if all were searched."""
    reach = lambda line, r: F.when(r <= line, F.greatest(line, F.least(r + window, nprobe))).otherwise(line)
    return F.aggregate(hit_ranks, F.least(window, nprobe), reach)


def trace(outcomes: DataFrame, window: int) -> DataFrame:
    """Rows (query_id, shard_id, rank, hit, stale, visited) from the outcomes of all ranks; stale counts ranks since the last hit."""
    order = W.partitionBy("query_id", "shard_id").orderBy("rank")
    marked = outcomes.withColumn("hit", F.col("n_hits") > 0)
    marked = marked.withColumn("stale", F.col("rank") - F.coalesce(F.max(F.when(F.col("hit"), F.col("rank"))).over(order), F.lit(0)))
    ended = F.coalesce(F.max((F.col("stale") >= window).cast("int")).over(order.rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    return marked.select("query_id", "shard_id", "rank", "hit", "stale", (ended == 0).alias("visited"))


def other_rule(outcomes: DataFrame, kind: str, limit: float) -> DataFrame:
    """Rows (query_id, shard_id, stop) under other stop signals: empties in all (`cumulative`), or their share after eight ranks (`rate`)."""
    order = W.partitionBy("query_id", "shard_id").orderBy("rank")
    empty = F.sum((F.col("n_hits") == 0).cast("int")).over(order)
    last = F.max("rank").over(W.partitionBy("query_id", "shard_id"))
    if kind == "cumulative":
        stops = empty >= int(limit)
    elif kind == "rate":
        stops = (F.col("rank") >= 8) & (empty >= limit * F.col("rank"))
    else:
        raise ValueError(kind)
    marked = outcomes.select("query_id", "shard_id", F.when(stops, F.col("rank")).alias("at"), last.alias("last"))
    return marked.groupBy("query_id", "shard_id").agg(F.coalesce(F.min("at"), F.max("last")).alias("stop"))
