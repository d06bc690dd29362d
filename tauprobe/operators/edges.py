"""From search results to duplicate groups, and the exact pair joins that search is compared with."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from tauprobe.operators import ivf, search
from tauprobe.operators.components import join_hot
from tauprobe.params import SearchParams
from tauprobe.session import materialize


def canonical(edges: DataFrame) -> DataFrame:
    """Undirected edges (id_a, id_b, sim), each once, the smaller id first."""
    both = edges.select(F.least("query_id", "vec_id").alias("id_a"), F.greatest("query_id", "vec_id").alias("id_b"), "sim").where("id_a <> id_b")
    return both.groupBy("id_a", "id_b").agg(F.max("sim").alias("sim"))


def word_sets(docs: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """Rows (id, lang, words): the different words of each text, by 64 bits of hash."""
    words = F.array_distinct(F.transform(F.filter(F.split(F.coalesce("text", F.lit("")), "[ \t\r\n]+"), lambda w: w != ""), lambda w: F.xxhash64(w)))
    return docs.select(F.col(id_col).alias("id"), "lang", words.alias("words"))


def content_filter(edges: DataFrame, docs: DataFrame, least_jaccard: float = 0.5, id_col: str = "doc_id") -> DataFrame:
    """Edges whose documents agree: the same language, and word sets that overlap enough. Adds the overlap.

    Words are compared by 64 bits of hash. Language and set sizes, a few bytes a document, rule most edges out before the
    sets themselves are met: sets whose sizes differ too much cannot overlap enough.
    """
    side = materialize(word_sets(docs, id_col).withColumn("n", F.size("words")), "word-sets")
    few = lambda x: side.select(F.col("id").alias(f"id_{x}"), F.col("lang").alias(f"l{x}"), F.col("n").alias(f"n{x}"))
    sets = lambda x: side.select(F.col("id").alias(f"id_{x}"), F.col("words").alias(f"w{x}"))
    likely = edges.join(few("a"), "id_a").join(few("b"), "id_b").where("la = lb").where(F.least("na", "nb") >= least_jaccard * F.greatest("na", "nb"))
    met = likely.join(sets("a"), "id_a").join(sets("b"), "id_b")
    shared = F.size(F.array_intersect("wa", "wb"))
    overlap = shared / F.greatest(F.col("na") + F.col("nb") - shared, F.lit(1))
    return met.select("id_a", "id_b", "sim", overlap.alias("jaccard")).where(F.col("jaccard") >= least_jaccard)


def label_groups(components: DataFrame, docs: DataFrame, labels: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """Rows (id, component, group_size, keep): the best document of each group stays, by quality, length, then smallest id."""
    marks = labels.groupBy(F.col(id_col).alias("id")).agg(F.max("quality").alias("quality"))
    every = docs.select(F.col(id_col).alias("id"), "n_chars").join(components.withColumnRenamed("node", "id"), "id", "left").join(marks, "id", "left")
    every = every.withColumn("component", F.coalesce("component", "id"))
    # a group of any size is one aggregate row: its size, and the place of its best document
    place = F.struct((-F.coalesce("quality", F.lit(-1))).alias("q"), F.coalesce(-F.col("n_chars"), F.lit(1)).alias("c"), F.col("id").alias("i"))
    every = materialize(every, "grouped")
    groups = materialize(every.groupBy("component").agg(F.count(F.lit(1)).alias("n"), F.min(place)["i"].alias("best")), "groups")
    return join_hot(every, groups, "component").select("id", "component", F.col("n").alias("group_size"), (F.col("id") == F.col("best")).alias("keep"))


def exact_hash(docs: DataFrame, text: str = "text", id_col: str = "doc_id") -> DataFrame:
    """Rows (hash, copies, first_id) of texts that occur more than once."""
    return docs.groupBy(F.md5(text).alias("hash")).agg(F.count(F.lit(1)).alias("copies"), F.min(id_col).alias("first_id")).where("copies > 1")


def self_search(index: ivf.Index, every: DataFrame, params: SearchParams) -> search.Result:
    """Every vector searches the base it is in; it does not count as its own neighbour, nor as a hit."""
    return search.lookahead(index, every, params.with_(drop_self=True))


def representatives(rows: DataFrame, by: list[str], id_col: str = "doc_id") -> DataFrame:
    """Rows (id, representative): rows that agree in the columns `by` are stood for by their smallest id.

    What is searched or joined afterwards are representatives, so copies cost one row each. Columns are compared by 128 bits
    of hash; a group of any size is one aggregate row.
    """
    keyed = rows.select(F.col(id_col).alias("id"), F.xxhash64(*by).alias("a"), F.xxhash64(F.lit(1), *by).alias("b"))
    first = keyed.groupBy("a", "b").agg(F.min("id").alias("representative"))
    return keyed.join(first, ["a", "b"]).select("id", "representative")


def spread(components: DataFrame, members: DataFrame) -> DataFrame:
    """Components of representatives as rows (node, component) of all members of a group of two or more rows."""
    of = members.join(components.withColumnRenamed("node", "representative"), "representative", "left")
    of = materialize(of.select(F.col("id").alias("node"), F.coalesce("component", "representative").alias("component")), "membership")
    sizes = materialize(of.groupBy("component").agg(F.count(F.lit(1)).alias("n")), "group-sizes")
    return join_hot(of, sizes, "component").where("n > 1").select("node", "component")


def _block_radii(index: ivf.Index) -> DataFrame:
    """Rows (shard_id, pid, radius): the largest angle of each partition's vectors to its centroid."""
    c = index.blocks.sparkSession.sparkContext.broadcast(index.centroids)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(b.num_rows):
                block = ivf.as_block(b.slice(i, 1))
                vecs = np.frombuffer(block["mat"], "<f4").reshape(block["n"], -1).astype(np.float64) / np.sqrt(block["norms"])[:, None]
                angle = np.arccos(np.clip(vecs @ c.value.vector(block["shard_id"], block["pid"]), -1, 1)).max()
                yield pa.RecordBatch.from_arrays([pa.array([block["shard_id"]], pa.int32()), pa.array([block["pid"]], pa.int32()), pa.array([float(angle)])], ["shard_id", "pid", "radius"])

    return index.blocks.mapInArrow(kernel, "shard_id int, pid int, radius double").groupBy("shard_id", "pid").agg(F.max("radius").alias("radius"))


#: Partitions of a tile, when all pairs of them are gone through.
PID_TILE = 2048


def block_pairs(index: ivf.Index, tau: float | None = None) -> DataFrame:
    """Rows (shard_id, pid, shard_b, pid_b) of partitions whose vectors may be within tau; all pairs without tau.

    By the triangle inequality of angles, partitions are too far apart if the angle of their centroids, less both radii, is
    more than the threshold's angle. Partitions come in tiles of centroids and radii; each pair of tiles is judged in a task.
    """
    spark = index.blocks.sparkSession
    radii = _block_radii(index)
    centres = index.centroids.table(spark).join(radii, ["shard_id", "pid"])
    numbered = centres.repartitionByRange(max(1, index.lists * len(index.shards) // PID_TILE), "shard_id", "pid")
    bound = None if tau is None else float(np.arccos(min(1.0, tau)) + 1e-9)

    def tile(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in ivf._tiles(batches, PID_TILE):
            if b.num_rows:
                mat = ivf._matrix(b.column(2))
                yield pa.RecordBatch.from_arrays([pa.array([b.column(c).to_numpy()], pa.list_(t)) for c, t in ((0, pa.int32()), (1, pa.int32()), (3, pa.float64()))] + [pa.array([mat.tobytes()], pa.binary())], ["shards", "pids", "radii", "mat"])

    tiles = materialize(numbered.select("shard_id", "pid", "vec", "radius").mapInArrow(tile, "shards array<int>, pids array<int>, radii array<double>, mat binary").withColumn("m", F.monotonically_increasing_id()), "centroid-tiles")
    tiles = tiles.withColumn("t", F.row_number().over(W.orderBy("m"))).drop("m")  # a row for each two thousand partitions
    last = tiles.count()
    grid = tiles.select("t", F.explode(F.sequence("t", F.lit(last))).alias("u"))
    other = tiles.select(*[F.col(c).alias(f"{c}_b") for c in ("shards", "pids", "radii", "mat")], F.col("t").alias("u"))

    def judged(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for i in range(whole.num_rows):
                row = ivf.as_block(whole.slice(i, 1))
                a, b = (np.frombuffer(row[m]).reshape(len(row[p]), -1) for m, p in (("mat", "pids"), ("mat_b", "pids_b")))
                near = np.ones((len(a), len(b)), bool) if bound is None else np.arccos(np.clip(a @ b.T, -1, 1)) - row["radii"][:, None] - row["radii_b"][None, :] <= bound
                if row["t"] == row["u"]:
                    near = np.triu(near) | np.eye(len(a), dtype=bool)
                x, y = np.nonzero(near)
                yield pa.RecordBatch.from_arrays([pa.array(v.astype(np.int32)) for v in (row["shards"][x], row["pids"][x], row["shards_b"][y], row["pids_b"][y])], ["shard_id", "pid", "shard_b", "pid_b"])

    return grid.join(tiles, "t").join(other, "u").mapInArrow(judged, "shard_id int, pid int, shard_b int, pid_b int")


def pair_join(index: ivf.Index, tau: float, prune: bool) -> tuple[DataFrame, DataFrame]:
    """(all pairs (id_a, id_b, sim) within tau, exactly; one row with the pairs scored). A task joins two blocks at a time."""
    pairs = block_pairs(index, tau if prune else None)
    a = index.blocks.select("shard_id", "pid", F.col("block_no").alias("no_a"), F.col("n").alias("n_a"), F.col("ids").alias("ids_a"), F.col("norms").alias("norms_a"), F.col("mat").alias("mat_a"))
    b = index.blocks.select(F.col("shard_id").alias("shard_b"), F.col("pid").alias("pid_b"), F.col("block_no").alias("no_b"), "n", "ids", "norms", "mat")
    met = pairs.join(a, ["shard_id", "pid"]).join(b, ["shard_b", "pid_b"])
    same = (F.col("shard_id") == F.col("shard_b")) & (F.col("pid") == F.col("pid_b"))
    met = met.where(~same | (F.col("no_b") >= F.col("no_a"))).select((same & (F.col("no_a") == F.col("no_b"))).alias("same"), "n_a", "ids_a", "norms_a", "mat_a", "n", "ids", "norms", "mat")
    cost = met.agg(F.sum(F.when(F.col("same"), F.col("n") * (F.col("n") - 1) / 2).otherwise(F.col("n_a").cast("bigint") * F.col("n"))).cast("bigint").alias("pairs_scored"))

    def found(held: list[tuple[np.ndarray, ...]]) -> pa.RecordBatch:
        x, y, sims = (np.concatenate([h[c] for h in held]) for c in range(3))
        return pa.RecordBatch.from_arrays([pa.array(np.minimum(x, y)), pa.array(np.maximum(x, y)), pa.array(sims)], ["id_a", "id_b", "sim"])

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            flat = {c: (whole.column(c).offsets.to_numpy(), whole.column(c).values.to_numpy()) for c in ("ids_a", "norms_a", "ids", "norms")}
            twin, n_a, n = (whole.column(c).to_numpy(zero_copy_only=False) for c in ("same", "n_a", "n"))
            mats = whole.column("mat_a"), whole.column("mat")
            held, n_held = [], 0
            for i in range(whole.num_rows):
                ids_a, norms_a, ids, norms = (values[bounds[i] : bounds[i + 1]] for bounds, values in flat.values())
                left, right = (np.frombuffer(m[i].as_buffer(), "<f4").reshape(k[i], -1).astype(np.float64) for m, k in zip(mats, (n_a, n), strict=True))
                for lo in range(0, len(left), search.TILE):
                    sims = np.round((left[lo : lo + search.TILE] @ right.T) / np.sqrt(norms_a[lo : lo + search.TILE, None] * norms[None, :]), search.DECIMALS)
                    hit = sims >= tau
                    if twin[i]:
                        hit &= ids_a[lo : lo + search.TILE, None] < ids[None, :]
                    r, c = np.nonzero(hit)
                    if len(r):
                        held.append((ids_a[lo + r], ids[c], sims[r, c]))
                        n_held += len(r)
                if n_held > 1 << 16:
                    yield found(held)
                    held, n_held = [], 0
            if held:
                yield found(held)

    return met.mapInArrow(kernel, "id_a bigint, id_b bigint, sim double"), cost


def components_of(edges: DataFrame) -> DataFrame:
    from tauprobe.operators.components import components

    return materialize(components(edges), "components")
