"""Connected components of an undirected graph, by alternating stars.

Each round links every node's larger neighbours to the smallest node around it, then every node and its smaller neighbours
to the smallest of those. Rounds go on until the edges no longer change; then every edge points at the smallest node of
its component. A round is a handful of aggregations and equi-joins; its edges are written to the shared folder, so a lost
executor costs one round at most. A hub costs no task its whole neighbourhood: minima combine before the shuffle, and the
minima of the largest hubs go to all tasks instead of the hubs' edges to one.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tauprobe.session import materialize


#: Keys with the most rows whose values are sent to every task.
HOT = 10_000


def join_hot(rows: DataFrame, values: DataFrame, key: str) -> DataFrame:
    """rows joined with values, which has each key once and its number n of rows.

    The most frequent keys, HOT at most, go to all tasks; any other key has one in HOT of all rows at most, so no task gets
    many rows of one key. Both frames are read twice, so they should lie on storage.
    """
    hot = F.broadcast(values.where("n > 1").orderBy(F.desc("n"), key).limit(HOT))
    rest = rows.join(hot.select(key), key, "left_anti").hint("merge").join(values, key)
    return rows.join(hot, key).unionByName(rest)


def _around(edges: DataFrame) -> DataFrame:
    """The rows (u, v) with the least v of each u."""
    least = edges.groupBy("u").agg(F.min("v").alias("m"))
    return edges.hint("merge").join(least, "u")


def _large_star(edges: DataFrame) -> DataFrame:
    both = edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = materialize(both.groupBy("u").agg(F.min("v").alias("m"), F.count(F.lit(1)).alias("n")), "least")
    near = join_hot(both, least, "u").where("v > u")
    return near.select(F.col("v").alias("u"), F.least("m", "u").alias("v")).distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    """Edges have u > v here."""
    near = _around(edges)
    pairs = F.array(F.struct(F.col("u").alias("u"), F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v")))
    return near.select(F.explode(pairs).alias("p")).select("p.u", "p.v").where("u <> v").distinct()


def _digest(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())


def components(edges: DataFrame, a: str = "id_a", b: str = "id_b", max_rounds: int = 60) -> DataFrame:
    """Rows (node, component) for every node of an edge; the component is its smallest node. Nodes without edges are not listed."""
    now = edges.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).where("u <> v").distinct()
    now = materialize(now, "edges")
    before = _digest(now)
    for _ in range(max_rounds):
        if not before[0]:
            break
        now = materialize(_small_star(_large_star(now)), "edges")
        after = _digest(now)
        if after == before:
            break
        before = after
    else:
        raise RuntimeError("components did not settle")
    stars = now.select(F.col("u").alias("node"), F.col("v").alias("component"))
    return stars.union(now.select("v", "v").distinct())


def label_propagation(edges: DataFrame, a: str = "id_a", b: str = "id_b", max_rounds: int = 200) -> DataFrame:
    """The same result by passing smallest labels along edges, one step a round: the plain way, for small graphs and tests."""
    both = edges.select(F.col(a).alias("u"), F.col(b).alias("v")).union(edges.select(b, a)).distinct()
    both = materialize(both, "edges")
    labels = both.select(F.col("u").alias("node"), F.col("u").alias("component")).distinct()
    for _ in range(max_rounds):
        heard = both.join(labels, both.v == labels.node).groupBy("u").agg(F.min("component").alias("heard"))
        new = labels.join(heard, labels.node == heard.u).select("node", F.least("component", "heard").alias("component"), (F.col("heard") < F.col("component")).alias("moved"))
        new = materialize(new, "labels")
        moved = new.where("moved").limit(1).count()
        labels = new.drop("moved")
        if not moved:
            return labels
    raise RuntimeError("labels did not settle")
