"""How a search is to be run, decided from its size; the decision is a plain value that can be printed, and `run` follows it."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame

from tauprobe.operators import ivf, search
from tauprobe.params import SearchParams


@dataclass(frozen=True)
class Plan:
    mode: str  # "fixed", "lookahead", "waves"
    tasks: int
    needs_shards: bool
    chunks_of_largest_group: int
    reason: str


def choose(params: SearchParams, queries: int, lists: int, shards: int = 1, vectors: int | None = None, cores: int = 8, readable: bool = True) -> Plan:
    """fixed: the rule could not stop before the last list; lookahead: queues in tasks; waves: joins, where tasks cannot read the index."""
    probes = min(params.nprobe, lists)
    mode = "fixed" if params.window >= probes else "lookahead" if readable else "waves"
    whole, first = queries * shards * probes, queries * shards * min(params.window, probes)
    wanted = ivf.suggest_nlist(vectors) if vectors else lists
    tasks = search.task_count(queries * shards, params.microbatch, cores)
    reason = f"{first} searches at least and {whole} at most, by {queries * shards} queries and shards in {tasks} tasks"
    return Plan(mode, tasks, wanted > ivf.MOST_CENTROIDS, max(1, -(-queries // params.microbatch)), reason)


def run(index: ivf.Index, queries: DataFrame, params: SearchParams) -> tuple[search.Result, Plan]:
    """The search by the plan that fits its size."""
    cores = queries.sparkSession.sparkContext.defaultParallelism
    plan = choose(params, queries.count(), index.lists, len(index.shards), cores=cores, readable=ivf.readable(index))
    return {"fixed": search.fixed, "lookahead": search.lookahead, "waves": search.waves}[plan.mode](index, queries, params), plan
