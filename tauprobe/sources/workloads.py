"""The vector workloads: each gives vectors, queries, a threshold and an index, made once per session and kept on shared storage.

Queries are the rows whose id is a multiple of fifty, and they are searched for among all rows; a row does not find itself.
An index holds every row. Its lists lie around seeds (or centroids trained from them); their number follows from the rows.
"""

from __future__ import annotations

from collections import OrderedDict
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tauprobe.functions import vectors
from tauprobe.operators import ivf
from tauprobe.params import SearchParams
from tauprobe.session import materialize, signature, table

#: Rows whose id is a multiple of this are the queries.
QUERY_EVERY = 50
#: Rows whose id is a multiple of this are the seed centroids; of larger tables, fewer are.
SEED_EVERY = 25


@dataclass(frozen=True)
class Workload:
    name: str
    source: str
    tau: float
    window: int = 8
    pairs: bool = False
    seed_every: int = SEED_EVERY

    @property
    def params(self) -> SearchParams:
        return SearchParams(tau=self.tau, window=self.window, drop_self=True)


WORKLOADS = {
    w.name: w
    for w in (
        Workload("emb", "embeddings", 0.30, window=16),  # noise without locality: a shorter window finds less than nine tenths
        Workload("docs_u", "documents", 0.85),
        Workload("docs_u_loose", "documents", 0.80),
        Workload("docs_mid", "documents", 0.90),
        Workload("docs_b", "documents", 0.85, pairs=True),
        Workload("docs_sparse", "documents", 0.95, pairs=True),
        Workload("pages", "pages", 0.90, seed_every=10),
        Workload("conv", "conversations", 0.85, pairs=True),
        Workload("emb_plant", "embeddings", 0.90),
    )
}

_KEPT: OrderedDict[tuple, object] = OrderedDict()


def _once(spark: SparkSession, key: tuple, make):
    """What make returns, made once for a session and a state of the source table; the results used last are kept."""
    name, sf_dir, workload, *rest = key
    source = signature(spark, f"{sf_dir}/{WORKLOADS[workload].source}.parquet")
    key = (spark.sparkContext.applicationId, name, sf_dir, workload, *rest, source)
    if key not in _KEPT:
        _KEPT[key] = make()
        while len(_KEPT) > 100:
            _KEPT.popitem(last=False)
    _KEPT.move_to_end(key)
    return _KEPT[key]


def raw_vectors(spark: SparkSession, sf_dir: str, w: Workload) -> DataFrame:
    """Rows (id, vec, norm2) of the workload's table."""
    if w.source == "embeddings":
        rows = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.transform("embedding", lambda x: x.cast("double")).alias("vec"))
        if w.name == "emb_plant":  # every tenth vector again, moved a little by an amount that its id sets
            moved = F.transform("vec", lambda x, i: F.when(i == F.pmod("id", F.lit(64)), x + 0.05 * (1 + F.pmod("id", F.lit(3)))).otherwise(x))
            rows = rows.union(rows.where("id % 10 = 0").select((F.col("id") + 1_000_000).alias("id"), moved.alias("vec")))
        good, _ = vectors.quarantine(rows)
        return good.withColumn("norm2", vectors.norm2(F.col("vec")))
    if w.source == "documents":
        texts = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), "text")
    elif w.source == "pages":
        texts = table(spark, sf_dir, "pages").select(F.col("page_id").alias("id"), F.regexp_replace("html", "<[^>]*>", " ").alias("text"))
    else:
        texts = table(spark, sf_dir, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("id"), "text")
    return vectors.hashed_cells(texts, "text", w.pairs)


def _like(name: str) -> str:
    """The first workload with the same vectors."""
    w = WORKLOADS[name]
    return name if name == "emb_plant" else next(n for n, o in WORKLOADS.items() if (o.source, o.pairs) == (w.source, w.pairs))


def vectors_of(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """All usable vectors of a workload, kept."""
    name = _like(name)
    return _once(spark, ("vectors", sf_dir, name), lambda: materialize(raw_vectors(spark, sf_dir, WORKLOADS[name]), "vectors"))


def split(every: DataFrame) -> tuple[DataFrame, DataFrame]:
    """All rows, and the queries."""
    return every, every.where(F.pmod("id", F.lit(QUERY_EVERY)) == 0)


def held_out(every: DataFrame, rest: int = 3) -> tuple[DataFrame, DataFrame]:
    """A tenth of the rows as queries that the index does not hold, and the others: for experiments apart from the registered queries."""
    held = F.pmod("id", F.lit(10)) == rest
    return every.where(~held), every.where(held)


def seeds_of(spark: SparkSession, sf_dir: str, name: str) -> int:
    """Every how many-th row is a seed."""
    name = _like(name)
    return _once(spark, ("seeds", sf_dir, name), lambda: ivf.seed_every(vectors_of(spark, sf_dir, name).count(), WORKLOADS[name].seed_every))


def index_of(spark: SparkSession, sf_dir: str, name: str, rounds: int = 0) -> tuple[ivf.Index, DataFrame]:
    """The index over all rows, with lists around seeds, or around centroids trained in so many rounds from them; and the queries.

    Where the lists are too many for every task to hold their centroids, they lie in shards.
    """
    name = _like(name)
    every, queries = split(vectors_of(spark, sf_dir, name))

    def make() -> ivf.Index:
        lists = every.count() // seeds_of(spark, sf_dir, name)
        if lists > ivf.MOST_CENTROIDS:
            return shard_index_of(spark, sf_dir, name, -(-2 * lists // ivf.MOST_CENTROIDS))[0]
        start = ivf.seed_centroids(every, seeds_of(spark, sf_dir, name))
        return ivf.build(every, ivf.lloyd(every, start, rounds) if rounds else start)

    return _once(spark, ("index", sf_dir, name, rounds), make), queries


def shard_index_of(spark: SparkSession, sf_dir: str, name: str, shards: int = 4) -> tuple[ivf.Index, DataFrame]:
    """Coarse shards, trained in one round from the first seeds, each with lists of its own; and the queries."""
    name = _like(name)
    every, queries = split(vectors_of(spark, sf_dir, name))

    def make() -> ivf.Index:
        spacing = seeds_of(spark, sf_dir, name)
        seeds = every.where(F.pmod("id", F.lit(spacing)) == 0).orderBy("id").limit(shards)
        return ivf.build_shards(every, ivf.lloyd(every, ivf.seed_centroids(seeds, 1), 1), spacing)

    return _once(spark, ("shards", sf_dir, name, shards), make), queries
