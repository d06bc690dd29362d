"""Measures of accuracy and cost, and characteristics of workloads and indexes, as aggregations."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from tauprobe.operators import ivf


def ratio(a: Column, b: Column) -> Column:
    """a / b, null where b is 0."""
    return F.when(b != 0, a / b)


def recall(edges: DataFrame, truth: DataFrame, by: list[str] | None = None) -> DataFrame:
    """Rows (by..., found, truth, recall): pooled share of the true pairs that were found; null without any true pair."""
    by = by or []
    total = truth.count()
    hit = edges.join(truth.select("query_id", "vec_id"), ["query_id", "vec_id"])
    return hit.groupBy(*by).agg(F.count(F.lit(1)).alias("found")).select(*by, "found", F.lit(total).cast("bigint").alias("truth"), ratio(F.col("found"), F.lit(total)).alias("recall"))


def pooled_recall(edges: DataFrame, truth: DataFrame) -> float | None:
    """One number."""
    total = truth.count()
    return edges.join(truth, ["query_id", "vec_id"], "left_semi").count() / total if total else None


def loss_pp(full: float | None, part: float | None) -> float | None:
    return None if full is None or part is None else 100 * (full - part)


def added_loss(own_fixed: float, own_adaptive: float, exact_fixed: float, exact_adaptive: float) -> float:
    """How much more an index loses to early stopping than the exactly assigned one; each against its own fixed probing."""
    return loss_pp(own_fixed, own_adaptive) - loss_pp(exact_fixed, exact_adaptive)


def visits_summary(visits: DataFrame, probes_each: int) -> DataFrame:
    """One row: total and mean visits, and the share of queries times probes that was saved."""
    return visits.agg(F.sum("visits").alias("visits"), F.avg("visits").alias("mean_visits"), (100 * (1 - F.sum("visits") / (F.count(F.lit(1)) * probes_each))).alias("saved_pct"))


GROUPS = "case when n = 0 then '0' when n = 1 then '1' when n <= 3 then '2-3' when n <= 6 then '4-6' when n <= 9 then '7-9' else '10' end"


def prune_by_group(visits: DataFrame, truth: DataFrame, probes_each: int) -> DataFrame:
    """Rows (neighbours, queries, pruned_pct) for six groups of queries by their number of true neighbours."""
    counts = truth.groupBy("query_id").agg(F.count(F.lit(1)).alias("n"))
    each = visits.groupBy("query_id").agg(F.sum("visits").alias("visits")).join(counts, "query_id", "left").withColumn("n", F.coalesce("n", F.lit(0)))
    return each.groupBy(F.expr(GROUPS).alias("neighbours")).agg(F.count(F.lit(1)).alias("queries"), F.round(100 * (1 - F.sum("visits") / (F.count(F.lit(1)) * probes_each)), 4).alias("pruned_pct"))


def scheduled_items(probes: int, visits: int, queries: int) -> dict[str, int]:
    """Items that are made ready in all, and the most at a time: fixed lists all up front, basic one for each query."""
    return {"fixed": probes, "basic": visits, "basic_at_once": queries, "lookahead": visits}


def density(exact50: DataFrame, queries: DataFrame, cap: int = 50) -> DataFrame:
    """Rows (neighbours, queries, share): histogram of qualifying neighbours, the last bin open."""
    n = queries.select(F.col("id").alias("query_id")).join(exact50.groupBy("query_id").agg(F.count(F.lit(1)).alias("n")), "query_id", "left")
    n = n.select(F.least(F.coalesce("n", F.lit(0)), F.lit(cap)).cast("bigint").alias("neighbours"))
    return n.groupBy("neighbours").agg(F.count(F.lit(1)).alias("queries")).withColumn("share", F.round(F.col("queries") / queries.count(), 6))


def located(truth: DataFrame, index: ivf.Index, ranks: DataFrame) -> DataFrame:
    """True pairs with the rank of the partition that holds them."""
    held = truth.join(index.postings().withColumnRenamed("id", "vec_id"), "vec_id")
    return held.join(ranks, ["query_id", "shard_id", "pid"]).select("query_id", "vec_id", "rank")


def last_rank(place: DataFrame) -> DataFrame:
    """One row (p50, p90): rank of the last partition with a true neighbour, over queries that have one."""
    last = place.groupBy("query_id").agg(F.max("rank").alias("last"))
    return last.agg(F.count(F.lit(1)).alias("queries"), F.percentile("last", 0.5).alias("p50"), F.percentile("last", 0.9).alias("p90"))


def front_load(place: DataFrame, ranks: tuple[int, ...] = (1, 2, 4, 8, 16, 32)) -> DataFrame:
    """Rows (within, share): pooled share of the true neighbours in the first partitions."""
    sums = [F.sum((F.col("rank") <= r).cast("int")).alias(f"r{r}") for r in ranks]
    one = place.agg(F.count(F.lit(1)).alias("n"), *sums)
    each = F.array(*[F.struct(F.lit(r).cast("bigint").alias("within"), F.round(ratio(F.col(f"r{r}"), F.col("n")), 6).alias("share")) for r in ranks])
    return one.select(F.explode(each).alias("e")).select("e.within", "e.share")


def partition_stats(sizes: DataFrame) -> DataFrame:
    """One row (lists, cv, gini, max_over_mean, empty) of partition sizes."""
    ranked = sizes.select("n", F.row_number().over(W.orderBy("n", "shard_id", "pid")).alias("i"))  # a row for each list
    lists, total = F.count(F.lit(1)), F.sum("n")
    gini = 2 * F.sum(F.col("i") * F.col("n")) / (lists * total) - (lists + 1) / lists
    return ranked.agg(
        lists.alias("lists"), F.round(F.stddev_pop("n") / F.avg("n"), 6).alias("cv"), F.round(gini, 6).alias("gini"), F.round(F.max("n") / F.avg("n"), 6).alias("max_over_mean"), F.sum((F.col("n") == 0).cast("bigint")).alias("empty")
    )


def mismatch(stored: DataFrame, nearest: DataFrame) -> DataFrame:
    """One row (vectors, mismatched, pct): vectors kept elsewhere than at their nearest centroid."""
    both = stored.select("id", F.col("pid").alias("stored")).join(nearest.select("id", F.col("pid").alias("nearest")), "id")
    wrong = F.sum((F.col("stored") != F.col("nearest")).cast("bigint"))
    return both.agg(F.count(F.lit(1)).alias("vectors"), wrong.alias("mismatched"), F.round(100 * wrong / F.count(F.lit(1)), 4).alias("pct"))


def pair_coverage(pairs: DataFrame, edges: DataFrame, components: DataFrame) -> DataFrame:
    """One row (pairs, direct_pct, grouped_pct) over true pairs (id_a, id_b): joined by an edge, or in one component."""
    a = components.select(F.col("node").alias("id_a"), F.col("component").alias("ca"))
    b = components.select(F.col("node").alias("id_b"), F.col("component").alias("cb"))
    seen = pairs.join(edges.select("id_a", "id_b", F.lit(1).alias("e")), ["id_a", "id_b"], "left").join(a, "id_a", "left").join(b, "id_b", "left")
    n_, direct, grouped = F.count(F.lit(1)), F.sum(F.col("e").isNotNull().cast("int")), F.sum(F.coalesce(F.col("ca") == F.col("cb"), F.lit(False)).cast("int"))
    return seen.agg(n_.alias("pairs"), F.round(ratio(100 * direct, n_), 4).alias("direct_pct"), F.round(ratio(100 * grouped, n_), 4).alias("grouped_pct"))


def matched_cost(frontier: list[tuple[float, float]], recall_at: float | None) -> float | None:
    """Cost of fixed probing at this recall, interpolated between measured (recall, cost) points; None outside them."""
    if recall_at is None:
        return None
    points = sorted((r, c) for r, c in frontier if r is not None)
    for (r0, c0), (r1, c1) in zip(points, points[1:]):
        if r0 <= recall_at <= r1:
            return c0 if math.isclose(r0, r1) else c0 + (c1 - c0) * (recall_at - r0) / (r1 - r0)
    return points[0][1] if points and math.isclose(points[0][0], recall_at) else None


def break_even(rows: list[tuple[float, float]]) -> float | None:
    """The first threshold of (tau, speedup) rows with speedup above 1."""
    return min((t for t, s in rows if s > 1), default=None)


def raw_gb(n: int, dim: int) -> float:
    """Decimal gigabytes of n single-precision vectors."""
    return n * dim * 4 / 1e9
