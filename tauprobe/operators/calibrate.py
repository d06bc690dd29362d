"""Choice of the window from a sample of the query batch, under a target for the loss against fixed probing."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tauprobe.operators import ivf, search
from tauprobe.params import SearchParams

GRID = (1, 2, 3, 4, 6, 8, 12, 16, 24, 32, 48, 64, 90)
DEFAULT_WINDOW = 8


@dataclass(frozen=True)
class Choice:
    window: int
    loss_pp: float | None
    sampled: int
    #: (window, loss in percentage points, visits)
    curve: tuple[tuple[int, float, int], ...]


def sample(queries: DataFrame, size: int) -> DataFrame:
    """About `size` queries, by a hash of their ids that any engine has, so that the same batch gives the same sample."""
    n = queries.count()
    h = F.conv(F.substring(F.md5(F.col("id").cast("string")), 1, 8), 16, 10).cast("bigint")
    return queries.where(h * max(n, 1) < F.lit(size).cast("bigint") * (1 << 32))


def choose_window(index: ivf.Index, queries: DataFrame, params: SearchParams, target_pp: float, size: int | None = None, grid: tuple[int, ...] = GRID) -> Choice:
    """The smallest window of the grid whose result on the sample misses at most target_pp of what fixed probing finds there.

    Without any qualifying neighbour in the sample there is nothing to measure, and the default window is returned.
    """
    size = size or max(50, min(1000, queries.count() // 100))
    picked = sample(queries, size)
    ranks, local = search.full_probe(index, picked, params)
    whole = search.merge_top(local, params.k)
    n = whole.count()
    most = ranks.agg(F.max("rank")).first()[0] or 1
    windows = sorted({min(w, most) for w in (*grid, most)})
    found, ended = search.replay(ranks, local, windows, params.k)
    hit = {r.w: r["count"] for r in found.join(whole.select("query_id", "vec_id"), ["query_id", "vec_id"]).groupBy("w").count().collect()}
    cost = {r.w: r.v for r in ended.groupBy("w").agg(F.sum("stop").alias("v")).collect()}
    sampled = ranks.select("query_id").distinct().count()
    if not n:
        return Choice(DEFAULT_WINDOW, None, sampled, ())
    curve = tuple((w, round(100 * (1 - hit.get(w, 0) / n), 6), cost.get(w, 0)) for w in windows)
    window, loss, _ = next((c for c in curve if c[1] <= target_pp), curve[-1])
    return Choice(window, loss, sampled, curve)
