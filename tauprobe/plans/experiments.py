"""The experiments, by name: which registered queries each one is, and a runner that prints their tables.

    python -m tauprobe.plans.experiments /root/testdata/sf0.01 window_sweep calibration
"""

from __future__ import annotations

import sys

from pyspark.sql import DataFrame, SparkSession

EXPERIMENTS: dict[str, tuple[str, ...]] = {
    "density_and_locality": ("workload_shapes", "density_emb", "density_docs_u", "last_rank_docs_u", "front_load_docs_u"),
    "partition_sizes": ("partition_stats_emb", "partition_stats_docs_u"),
    "window_sweep": ("w_sweep_emb", "w_sweep_docs_u", "w_sweep_docs_b", "w_sweep_trained_docs_u", "w_sweep_codes_docs_u"),
    "sharded_window_sweep": ("shard_topk_emb", "shard_w_sweep_docs_u", "shard_w_sweep_emb"),
    "same_budget": ("probe_sweep_docs_u",),
    "recall_matched": ("matched_cost_docs_u",),
    "ablation": ("wave_profile_docs_u", "serial_edges_docs_u", "ablation_docs_u", "queue_policy_trace_docs_u"),
    "pruning_by_neighbours": ("prune_by_group_docs_u",),
    "call_size": ("call_size_docs_u",),
    "threshold_sweep": ("tau_sweep_emb", "tau_sweep_docs_u"),
    "k_sweep": ("k_sweep_docs_u",),
    "approximate_assignment": ("assign_effect_docs_u", "ivf_assign_graph_emb", "ivf_assign_cells_emb"),
    "two_dedup_paths": ("coverage_docs_u", "pair_join_cost_docs_u"),
    "equivalence": ("mode_difference_docs_u",),
    "calibration": ("calibrate_w_docs_u",),
    "queue_order": ("queue_policy_trace_docs_u",),
    "metadata": ("metadata_items_docs_u",),
    "daily_arrivals": ("stream_arrivals_docs",),
    "end_to_end": ("end_to_end_docs",),
}


def run(spark: SparkSession, sf_dir: str, name: str) -> dict[str, DataFrame]:
    """The tables of an experiment."""
    from tauprobe.plans import vector_queries

    return {q: vector_queries.QUERIES[q](spark, sf_dir) for q in EXPERIMENTS[name]}


def main(args: list[str]) -> None:
    from tauprobe.session import build_session

    spark = build_session("experiments")
    spark.sparkContext.setLogLevel("ERROR")
    for name in args[1:] or EXPERIMENTS:
        for q, table in run(spark, args[0], name).items():
            print(f"{name}: {q}")
            table.show(60, truncate=False)


if __name__ == "__main__":
    main(sys.argv[1:])
