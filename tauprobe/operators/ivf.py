"""Inverted-file indexes as tables: training, assignment, storage, and the order in which queries visit partitions.

An index is two tables on shared storage: centroids (shard, pid) and blocks, a row for at most `BLOCK_ROWS` vectors of a
partition, packed as one matrix. Each block is a row group of its own, so that a task can read single partitions. Assignment
is one blocked matrix product per Arrow batch against the centroids. The centroids of an index without shards are sent to
every task; their number is checked. Beyond `MOST_CENTROIDS` an index has shards: the centroids are a table by shard, rows
and queries are dealt by shard, and a task reads the centroids of the shards it meets, one at a time.
"""

from __future__ import annotations

import json
from collections import OrderedDict
from collections.abc import Iterator
from dataclasses import dataclass
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from tauprobe.session import materialize, scratch

BLOCK_ROWS = 4096
#: Centroids sent to every task at most, in number and in bytes.
MOST_CENTROIDS, CENTROID_BYTES = 100_000, 512 << 20
#: Centroid similarities are compared as numbers of so many decimals, ties go to the smaller number.
DECIMALS = 9

BLOCKS = "shard_id int, pid int, block_no bigint, n int, ids array<bigint>, norms array<double>, mat binary"
#: A row group for each block, plain: vectors hardly compress, and a block is then read three times as fast.
LAYOUT = {"parquet.block.row.count.limit": "1", "compression": "none"}


@dataclass(frozen=True)
class Centroids:
    """Centroids in memory: (shard, pid) and a unit matrix."""

    shard: np.ndarray
    pid: np.ndarray
    unit: np.ndarray

    def of_shard(self, s: int) -> Centroids:
        own = self.shard == s
        return Centroids(self.shard[own], self.pid[own], self.unit[own])

    @property
    def counts(self) -> dict[int, int]:
        return dict(zip(*(x.tolist() for x in np.unique(self.shard, return_counts=True)), strict=True))

    @cached_property
    def _places(self) -> dict[tuple[int, int], int]:
        return {k: i for i, k in enumerate(zip(self.shard.tolist(), self.pid.tolist(), strict=True))}

    def vector(self, s: int, p: int) -> np.ndarray:
        return self.unit[self._places[s, p]]

    def table(self, spark: SparkSession) -> DataFrame:
        rows = [(int(s), int(p), u.tolist()) for s, p, u in zip(self.shard, self.pid, self.unit, strict=True)]
        return spark.createDataFrame(rows, "shard_id int, pid int, vec array<double>")


@dataclass(frozen=True)
class StoredCentroids:
    """Centroids of an index with shards: a table in a folder, a shard's rows read where they are needed."""

    folder: str
    counts: dict[int, int]

    def of_shard(self, s: int) -> Centroids:
        key = self.folder, s
        if key not in _SHARDS:
            import pyarrow.dataset as ds

            system, path = _arrow(self.folder)
            rows = ds.dataset(f"{path}/shard_id={s}", filesystem=system, format="parquet").to_table(columns=["pid", "vec"]).sort_by("pid").combine_chunks()
            mat = _matrix(rows["vec"].chunk(0))
            if len(_SHARDS) >= 2:
                _SHARDS.popitem(last=False)
            _SHARDS[key] = Centroids(np.full(len(mat), s, np.int64), rows["pid"].to_numpy().astype(np.int64), mat / np.sqrt((mat * mat).sum(1, keepdims=True)))
        return _SHARDS[key]

    def vector(self, s: int, p: int) -> np.ndarray:
        return self.of_shard(s).vector(s, p)

    def table(self, spark: SparkSession) -> DataFrame:
        return spark.read.schema("shard_id int, pid int, vec array<double>").parquet(self.folder)


#: The shards' centroids that this process read last.
_SHARDS: OrderedDict[tuple[str, int], Centroids] = OrderedDict()


def _arrow(path: str):
    from pyarrow.fs import FileSystem

    return FileSystem.from_uri(path if "://" in path else "file://" + path.removeprefix("file:"))


@dataclass(frozen=True)
class Index:
    blocks: DataFrame
    centroids: Centroids | StoredCentroids
    dim: int
    metric: str = "cosine"

    @property
    def shards(self) -> list[int]:
        return sorted(self.centroids.counts)

    @property
    def lists(self) -> int:
        """Partitions of the largest shard."""
        return max(self.centroids.counts.values(), default=0)

    def sizes(self) -> DataFrame:
        """Rows (shard_id, pid, n) of all partitions, empty ones too."""
        every = self.centroids.table(self.blocks.sparkSession).select("shard_id", "pid")
        held = self.blocks.groupBy("shard_id", "pid").agg(F.sum("n").alias("n"))
        return every.join(held, ["shard_id", "pid"], "left").select("shard_id", "pid", F.coalesce("n", F.lit(0)).cast("bigint").alias("n"))

    def postings(self) -> DataFrame:
        """Rows (id, shard_id, pid)."""
        return self.blocks.select(F.explode("ids").alias("id"), "shard_id", "pid")


def suggest_nlist(n: int, target: int = 4096) -> int:
    """Partitions for n vectors, so that each has about the target size."""
    return max(1, round(n / target))


def seed_every(n: int, least: int = 25) -> int:
    """Which rows are seeds: every so many-th, so that there are n / least lists up to ten thousand rows, and four roots of n beyond."""
    return max(least, round(n**0.5 / 4))


def collect_centroids(rows: DataFrame) -> Centroids:
    """Rows (shard_id, pid, vec) into the driver; their number and size are checked first."""
    n, dim = rows.agg(F.count(F.lit(1)), F.coalesce(F.max(F.size("vec")), F.lit(0))).first()
    if n > MOST_CENTROIDS or n * dim * 8 > CENTROID_BYTES:
        raise ValueError("too many centroids to send to every task: use shards")
    got = rows.orderBy("shard_id", "pid").collect()
    mat = np.array([r.vec for r in got], np.float64).reshape(len(got), -1)
    return Centroids(np.array([r.shard_id for r in got], np.int64), np.array([r.pid for r in got], np.int64), mat / np.sqrt((mat * mat).sum(1, keepdims=True)) if len(got) else mat)


def seed_centroids(base: DataFrame, every: int) -> Centroids:
    """Base rows whose id is a multiple of `every`, numbered by id."""
    got = collect_centroids(base.where(F.pmod("id", F.lit(every)) == 0).select(F.lit(0).alias("shard_id"), F.col("id").alias("pid"), "vec"))
    return Centroids(got.shard, np.arange(len(got.pid)), got.unit)


def rank(vecs: np.ndarray, centroids: Centroids) -> np.ndarray:
    """Similarities of vectors to centroids, rounded so that equal ones compare equal whatever the order of summation."""
    unit = vecs / np.sqrt((vecs * vecs).sum(1, keepdims=True))
    return np.round(unit @ centroids.unit.T, DECIMALS)


def _matrix(column: pa.Array) -> np.ndarray:
    """A list column as a matrix."""
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    return flat.reshape(len(column), -1) if len(column) else flat.reshape(0, 0)


def as_block(row: pa.RecordBatch) -> dict:
    """One row as a block: lists as arrays, the rest as plain values."""
    return {name: c.flatten().to_numpy(zero_copy_only=False) if pa.types.is_list(c.type) else c[0].as_py() for name, c in zip(row.schema.names, row.columns, strict=True) if name != "items"}


def _tiles(batches: Iterator[pa.RecordBatch], rows: int = 1024) -> Iterator[pa.RecordBatch]:
    for b in batches:
        for lo in range(0, b.num_rows, rows):
            yield b.slice(lo, rows)


def assign(base: DataFrame, centroids: Centroids, choose=None, attribute: str | None = None) -> DataFrame:
    """Rows (id, shard_id, pid, vec[, attr]): each vector at its nearest centroid, ties to the smaller pid; a map over the base.

    choose(unit vectors) may give other places in the list of centroids: the approximate variants.
    """
    more = [F.col(attribute).cast("bigint").alias("attr")] if attribute else []
    sent = base.sparkSession.sparkContext.broadcast(centroids)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = sent.value
        for b in _tiles(batches):
            vecs = _matrix(b.column(1))
            place = np.zeros(0, np.int64) if not len(vecs) else rank(vecs, c).argmax(1) if choose is None else choose(vecs / np.sqrt((vecs * vecs).sum(1, keepdims=True)))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(c.shard[place].astype(np.int32)), pa.array(c.pid[place].astype(np.int32)), *b.columns[1:]], ["id", "shard_id", "pid", "vec", "attr"][: 2 + b.num_columns])

    return base.select("id", "vec", *more).mapInArrow(kernel, "id bigint, shard_id int, pid int, vec array<double>" + ", attr bigint" * len(more))


def pack(assigned: DataFrame, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """Blocks of assigned vectors: each partition's rows come together once, in order of id, and stay together in blocks.

    Rows are dealt by partition in balanced parts: adaptive execution splits a partition that is much larger than others.
    A column attr, if there is one, goes along as attrs.
    """
    more = ["attr"] if "attr" in assigned.columns else []
    ordered = assigned.select("id", "shard_id", "pid", "vec", *more).hint("rebalance", F.col("shard_id"), F.col("pid")).sortWithinPartitions("shard_id", "pid", "id")

    def made(parts: list[pa.RecordBatch], number: int) -> pa.RecordBatch:
        rows = pa.Table.from_batches(parts).combine_chunks()
        mat = _matrix(rows["vec"].chunk(0))
        columns = [pa.array([rows["shard_id"][0].as_py()], pa.int32()), pa.array([rows["pid"][0].as_py()], pa.int32()), pa.array([number], pa.int64()), pa.array([len(mat)], pa.int32()), pa.array([rows["id"].to_numpy()], pa.list_(pa.int64()))]
        columns += [pa.array([(mat * mat).sum(1)], pa.list_(pa.float64())), pa.array([mat.astype("<f4").tobytes()], pa.binary())]
        columns += [pa.array([rows["attr"].to_numpy()], pa.list_(pa.int64()))] if more else []
        return pa.RecordBatch.from_arrays(columns, ["shard_id", "pid", "block_no", "n", "ids", "norms", "mat", *["attrs"] * len(more)])

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        number = TaskContext.get().partitionId() << 32  # a partition may lie in several tasks, and block numbers stay apart
        key, held, n = None, [], 0
        for b in batches:
            if not b.num_rows:
                continue
            keys = b.column(1).to_numpy().astype(np.int64) << 32 | b.column(2).to_numpy()
            cuts = [0, *(np.flatnonzero(keys[1:] != keys[:-1]) + 1).tolist(), len(keys)]
            for lo, hi in zip(cuts, cuts[1:]):
                while lo < hi:
                    if n and (keys[lo] != key or n == block_rows):
                        yield made(held, number)
                        number, held, n = number + 1, [], 0
                    key, few = keys[lo], min(hi - lo, block_rows - n)
                    held.append(b.slice(lo, few))
                    lo, n = lo + few, n + few
        if n:
            yield made(held, number)

    return ordered.mapInArrow(kernel, BLOCKS + ", attrs array<bigint>" * len(more))


def repack(blocks: DataFrame, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """Blocks of the same vectors, as full as can be: for an index that grew by small batches."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(b.num_rows):
                row = as_block(b.slice(i, 1))
                mat = np.frombuffer(row["mat"], "<f4").reshape(row["n"], -1).astype(np.float64)
                vecs = pa.ListArray.from_arrays(pa.array(np.arange(len(mat) + 1, dtype=np.int32) * mat.shape[1]), pa.array(mat.ravel()))
                yield pa.RecordBatch.from_arrays([pa.array(row["ids"]), *(pa.array(np.full(len(mat), row[c], np.int32)) for c in ("shard_id", "pid")), vecs], ["id", "shard_id", "pid", "vec"])

    return pack(blocks.mapInArrow(kernel, "id bigint, shard_id int, pid int, vec array<double>"), block_rows)


def build(base: DataFrame, centroids: Centroids, choose=None, block_rows: int = BLOCK_ROWS, attribute: str | None = None) -> Index:
    """Assigns and packs the base; the blocks are written to shared storage. `attribute` names an integer column to keep beside the ids."""
    assigned = assign(base, centroids, choose, attribute)
    blocks = materialize(pack(assigned, block_rows), "blocks", **LAYOUT)
    return Index(blocks, centroids, centroids.unit.shape[1] if len(centroids.unit) else 0)


def build_shards(base: DataFrame, coarse: Centroids, every: int, block_rows: int = BLOCK_ROWS) -> Index:
    """An index with a shard for each coarse centroid, and in each shard its own lists around the seeds that fall into it.

    The shards' centroids are a table; vectors are dealt by shard, in balanced parts, and meet the centroids of their shard.
    """
    spark = base.sparkSession
    placed = materialize(assign(base, coarse).select("id", F.col("pid").alias("shard_id"), "vec"), "shards")
    folder = scratch(spark, "centroids")
    number = F.row_number().over(W.partitionBy("shard_id").orderBy("id")) - 1
    seeds = placed.where(F.pmod("id", F.lit(every)) == 0).select("shard_id", number.cast("int").alias("pid"), "vec")
    seeds.write.partitionBy("shard_id").parquet(folder)
    counts = {r.shard_id: r["count"] for r in spark.read.parquet(folder).groupBy("shard_id").count().collect()}  # a row for each shard
    if max(counts.values(), default=0) > MOST_CENTROIDS:
        raise ValueError("too many lists in a shard: use more shards")
    stored = StoredCentroids(folder, counts)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b, s in _by_shard(batches, 1):
            near = rank(_matrix(b.column(2)), stored.of_shard(s))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(near.argmax(1).astype(np.int32)), b.column(2)], ["id", "shard_id", "pid", "vec"])

    dealt = placed.hint("rebalance", F.col("shard_id")).sortWithinPartitions("shard_id")
    assigned = dealt.mapInArrow(kernel, "id bigint, shard_id int, pid int, vec array<double>")
    return Index(materialize(pack(assigned, block_rows), "blocks", **LAYOUT), stored, coarse.unit.shape[1])


def _by_shard(batches: Iterator[pa.RecordBatch], column: int, rows: int = 1024) -> Iterator[tuple[pa.RecordBatch, int]]:
    """Tiles of one shard each, of rows sorted by shard."""
    for b in batches:
        shards = b.column(column).to_numpy()
        cuts = [0, *(np.flatnonzero(shards[1:] != shards[:-1]) + 1).tolist(), len(shards)]
        for lo, hi in zip(cuts, cuts[1:]):
            for at in range(lo, hi, rows):
                yield b.slice(at, min(rows, hi - at)), int(shards[lo])


def lloyd(base: DataFrame, start: Centroids, rounds: int) -> Centroids:
    """Spherical k-means: partial sums per task, added up by centroid in one shuffle; the driver gets a row for each centroid."""
    now = start
    for _ in range(rounds):
        sent = base.sparkSession.sparkContext.broadcast(now)

        def kernel(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
            c = sent.value
            sums, counts = np.zeros_like(c.unit), np.zeros(len(c.unit), np.int64)
            for b in _tiles(batches):
                vecs = _matrix(b.column(0))
                if len(vecs):
                    at = rank(vecs, c).argmax(1)
                    np.add.at(sums, at, vecs / np.sqrt((vecs * vecs).sum(1, keepdims=True)))
                    counts += np.bincount(at, minlength=len(counts))
            own = np.flatnonzero(counts)
            yield pa.RecordBatch.from_arrays([pa.array(own), pa.array([sums[i].tobytes() for i in own], pa.binary())], ["place", "total"])

        def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            total: dict[int, np.ndarray] = {}
            for b in batches:
                for place, part in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                    total[place] = total.get(place, 0.0) + np.frombuffer(part)
            yield pa.RecordBatch.from_arrays([pa.array(list(total), pa.int64()), pa.array([x.tobytes() for x in total.values()], pa.binary())], ["place", "total"])

        kind = "place bigint, total binary"
        unit = now.unit.copy()
        for r in base.select("vec").mapInArrow(kernel, kind).repartition("place").mapInArrow(add, kind).collect():  # as many as centroids, which are bounded
            total = np.frombuffer(r.total)
            if (size := np.sqrt((total * total).sum())) > 0:
                unit[r.place] = total / size
        now = Centroids(now.shard, now.pid, unit)
    return now


def train_ml(base: DataFrame, nlist: int, seed: int = 7) -> Centroids:
    """Centroids by Spark ML's k-means with cosine distance."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    model = KMeans(k=nlist, seed=seed, distanceMeasure="cosine", featuresCol="f", maxIter=5).fit(base.select(array_to_vector("vec").alias("f")))
    mat = np.array(model.clusterCenters())
    return Centroids(np.zeros(len(mat), np.int64), np.arange(len(mat)), mat / np.sqrt((mat * mat).sum(1, keepdims=True)))


#: Queries up to this number are dealt evenly over the cores before they meet the centroids.
FEW_QUERIES = 1 << 16


def best_first(sims: np.ndarray, most: int) -> np.ndarray:
    """Places of each row's `most` largest rounded similarities, largest first, ties to the smaller place."""
    n = sims.shape[1]
    keys = -np.rint(sims * 10**DECIMALS).astype(np.int64) * n + np.arange(n)  # all different, in the order wanted
    if most < n:
        keys = np.partition(keys, most - 1, axis=1)[:, :most]
    keys.sort(axis=1)
    return keys % n


def probe_lists(queries: DataFrame, index: Index, nprobe: int, extra: list[str] = (), with_vectors: bool = False) -> DataFrame:
    """Rows (query_id, shard_id, probes[, vec, extra]): the pids of each shard in the order of their centroids' similarity, best first."""
    centroids = index.centroids
    rows = queries.select(F.col("id").alias("query_id"), "vec", *extra)
    stored = isinstance(centroids, StoredCentroids)
    if stored:  # a task meets few shards, and reads their centroids
        rows = rows.select("*", F.explode(F.lit(index.shards)).alias("shard_id"))
        rows = rows.repartitionByRange("shard_id", "query_id").sortWithinPartitions("shard_id", "query_id")
        sent = None
    else:
        sent = queries.sparkSession.sparkContext.broadcast(centroids)
        if rows.count() <= FEW_QUERIES:  # a small table is often one file, which one task would read
            rows = rows.repartition(queries.sparkSession.sparkContext.defaultParallelism, "query_id")

    def near(b: pa.RecordBatch, own: Centroids, shard: int) -> pa.RecordBatch:
        order = best_first(rank(_matrix(b.column(1)), own), nprobe)
        lists = pa.ListArray.from_arrays(pa.array(np.arange(len(order) + 1, dtype=np.int32) * order.shape[1]), pa.array(own.pid[order].astype(np.int32).ravel()))
        columns = [b.column(0), pa.array(np.full(b.num_rows, shard, np.int32)), lists]
        return pa.RecordBatch.from_arrays([*columns, *(b.columns[1 : 2 + len(extra)] if with_vectors else [])], ["query_id", "shard_id", "probes", "vec", *extra][: 3 + (1 + len(extra)) * with_vectors])

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if stored:
            for b, s in _by_shard(batches, 2 + len(extra), 256):
                yield near(b, centroids.of_shard(s), s)
            return
        each = {s: sent.value.of_shard(s) for s in sent.value.counts}
        for b in _tiles(batches, 256):
            for s, own in each.items() if b.num_rows else ():
                yield near(b, own, s)

    kind = "query_id bigint, shard_id int, probes array<int>"
    if with_vectors:
        kind += ", vec array<double>" + "".join(f", {c} bigint" for c in extra)
    return rows.mapInArrow(kernel, kind)


def save(index: Index, path: str, label: str = "index") -> None:
    """Blocks clustered by (shard, pid), centroids, and a manifest."""
    spark = index.blocks.sparkSession
    ordered = index.blocks.repartitionByRange("shard_id", "pid", "block_no").sortWithinPartitions("shard_id", "pid", "block_no")
    ordered.write.options(**LAYOUT).partitionBy("shard_id").parquet(f"{path}/blocks")
    index.centroids.table(spark).write.partitionBy("shard_id").parquet(f"{path}/centroids")
    manifest = json.dumps({"dim": index.dim, "metric": index.metric, "counts": index.centroids.counts, "stored": isinstance(index.centroids, StoredCentroids), "label": label})
    spark.createDataFrame([(manifest,)], "value string").coalesce(1).write.text(f"{path}/manifest")


def load(spark: SparkSession, path: str, dim: int | None = None) -> Index:
    """A saved index; its dimension is checked where one is expected."""
    manifest = json.loads(spark.read.text(f"{path}/manifest").first()[0])
    if dim is not None and dim != manifest["dim"]:
        raise ValueError(f"the index has dimension {manifest['dim']}, not {dim}")
    blocks = spark.read.schema(BLOCKS).parquet(f"{path}/blocks")
    stored = StoredCentroids(f"{path}/centroids", {int(s): n for s, n in manifest["counts"].items()})
    return Index(blocks, stored if manifest["stored"] else collect_centroids(stored.table(spark)), manifest["dim"], manifest["metric"])


def saved_copy(index: Index) -> Index:
    """The index written and loaded again."""
    path = scratch(index.blocks.sparkSession, "index")
    save(index, path)
    return load(index.blocks.sparkSession, path)


def readable(index: Index) -> bool:
    """Whether tasks can open the index's files through Arrow."""
    files = index.blocks.inputFiles()
    try:
        return not files or _arrow(files[0])[0] is not None
    except (OSError, ValueError, NotImplementedError):
        return False


class BlockStore:
    """Reads single partitions of an index's files, and keeps what it read last."""

    def __init__(self, files: tuple[str, ...], most_bytes: int = 256 << 20):
        import re

        import pyarrow.parquet as pq

        self.most, self.held, self.loads = most_bytes, 0, 0
        self.kept: OrderedDict[tuple[int, int], tuple[list[dict], int]] = OrderedDict()
        self.files, self.where = [], {}
        for f in files:
            system, path = _arrow(f)
            file = pq.ParquetFile(path, filesystem=system)
            self.files.append(file)
            folder = re.search(r"/shard_id=(\d+)/", path)
            for g in range(file.metadata.num_row_groups):
                self._note(len(self.files) - 1, g, int(folder[1]) if folder else None)

    def _note(self, f: int, g: int, shard: int | None) -> None:
        """Where the partitions of a row group are: one that holds a single block is known by its statistics."""
        file = self.files[f]
        group = file.metadata.row_group(g)
        columns = ["shard_id", "pid"][shard is not None :]  # the first ones of the file
        if group.num_rows == 1:
            places = [[group.column(i).statistics.min for i in range(len(columns))]]
        else:
            places = zip(*(c.to_pylist() for c in file.read_row_group(g, columns=columns).columns), strict=True)
        for row, place in enumerate(places):
            self.where.setdefault((shard, *place) if shard is not None else tuple(place), []).append((f, g, row))

    def blocks(self, shard: int, pid: int) -> list[dict]:
        key = shard, pid
        if key in self.kept:
            self.kept.move_to_end(key)
            return self.kept[key][0]
        self.loads += 1
        found = []
        for f, g, row in self.where.get(key, ()):
            found.append(as_block(self.files[f].read_row_group(g).slice(row, 1).combine_chunks().to_batches()[0]))
        size = sum(3 * len(b["mat"]) if "mat" in b else 9 * len(b["code"]) for b in found)  # with its double form
        self.kept[key] = found, size
        self.held += size
        while self.held > self.most and len(self.kept) > 1:
            self.held -= self.kept.popitem(last=False)[1][1]
        return found


_STORES: OrderedDict[tuple[str, ...], BlockStore] = OrderedDict()


def open_blocks(files: tuple[str, ...]) -> BlockStore:
    """The store of an index's files, kept by the process for its next tasks."""
    if files not in _STORES:
        if len(_STORES) >= 2:
            _STORES.popitem(last=False)
        _STORES[files] = BlockStore(files)
    return _STORES[files]


def rank_table(probes: DataFrame) -> DataFrame:
    """Rows (query_id, shard_id, rank, pid), rank from 1."""
    return probes.select("query_id", "shard_id", F.posexplode("probes").alias("at", "pid")).select("query_id", "shard_id", (F.col("at") + 1).alias("rank"), "pid")
