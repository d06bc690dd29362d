"""Exact joins of all pairs of vectors that shuffle no vectors: vectors lie in tiles on shared storage, and tasks read them there.

A tile is a row of a table, and a row group of its files. The triangle of tile pairs is cut into squares, a task each, so a
task meets few tiles often. Products are taken in single precision, and what lies within their error bound of the threshold
is decided again in double precision, so the result is exact. Two ways to use the pairs keep the output small where pairs
are many: `forest` gives each task's connected sets as stars, which have the same components as all links, and `agreeing`
gives only links that the words bear out too, judged where the links are found. Files that Arrow cannot open are joined.
"""

from __future__ import annotations

from collections import OrderedDict
from collections.abc import Callable, Iterator
from dataclasses import dataclass
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tauprobe.operators import ivf
from tauprobe.operators.search import DECIMALS
from tauprobe.session import materialize

#: Vectors and words of a tile at most (one row may have more words), tiles of a square's side, and rows of a product.
ROWS, WORDS, SIDE, STEP = 4096, 1 << 21, 32, 256
#: Bytes of tiles that a task keeps.
KEPT = 256 << 20
#: Bits of the map that a text's words are hashed to, a multiple of 64.
BITS = 1 << 12

STARS, AGREED = "id_a bigint, id_b bigint", "id_a bigint, id_b bigint, sim double, jaccard double"


def write(rows: DataFrame) -> DataFrame:
    """The tiles of rows (id, vec[, lang, words]) on shared storage. The words of a row are different hashes; tiles hold them sorted."""
    worded = "words" in rows.columns
    kind = "n int, ids binary, norms binary, mat binary" + ", langs array<string>, sizes binary, words binary" * worded

    def made(parts: list[pa.RecordBatch]) -> pa.RecordBatch:
        t = pa.Table.from_batches(parts).combine_chunks()
        mat = ivf._matrix(t["vec"].chunk(0))
        columns = [pa.array([len(mat)], pa.int32()), *(pa.array([x.tobytes()], pa.binary()) for x in (t["id"].to_numpy(), (mat * mat).sum(1), mat.astype("<f4")))]
        if worded:
            words = t["words"].chunk(0)
            columns += [pa.array([t["lang"].to_pylist()], pa.list_(pa.string())), *(pa.array([x.tobytes()], pa.binary()) for x in (np.diff(words.offsets.to_numpy()), words.flatten().to_numpy()))]
        return pa.RecordBatch.from_arrays(columns, ["n", "ids", "norms", "mat", "langs", "sizes", "words"][: len(columns)])

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n, words = [], 0, 0
        for b in batches:
            for part in ivf._tiles([b], STEP):
                more = len(part.column(3).flatten()) if worded else 0
                if n and (n + part.num_rows > ROWS or words + more > WORDS):
                    yield made(held)
                    held, n, words = [], 0, 0
                held, n, words = [*held, part], n + part.num_rows, words + more
        if n:
            yield made(held)

    columns = ["id", "vec", *(["lang", F.sort_array("words").alias("words")] if worded else [])]
    return materialize(rows.select(*columns).mapInArrow(kernel, kind), "tiles", **ivf.LAYOUT)


#: Numbers of the languages that this process has met.
_CODES: dict[str, int] = {}


@dataclass
class Tile:
    ids: np.ndarray
    norms: np.ndarray
    mat: np.ndarray
    langs: list[str] | None = None
    sizes: np.ndarray | None = None
    words: np.ndarray | None = None

    @classmethod
    def of(cls, row: dict) -> Tile:
        tile = cls(np.frombuffer(row["ids"], np.int64), np.frombuffer(row["norms"]), np.frombuffer(row["mat"], "<f4").reshape(row["n"], -1))
        if row.get("words") is not None:
            tile.langs, tile.sizes, tile.words = row["langs"], np.frombuffer(row["sizes"], np.int32).astype(np.int64), np.frombuffer(row["words"], np.int64)
        return tile

    @cached_property
    def unit(self) -> np.ndarray:
        return (self.mat / np.sqrt(self.norms)[:, None]).astype(np.float32)

    @cached_property
    def starts(self) -> np.ndarray:
        return np.cumsum(self.sizes) - self.sizes

    @cached_property
    def codes(self) -> np.ndarray:
        return np.array([_CODES.setdefault(lang, len(_CODES)) for lang in self.langs])

    @cached_property
    def maps(self) -> tuple[np.ndarray, np.ndarray]:
        """Each row's words as bits, and how many words more than bits it has."""
        bits = np.zeros((len(self.ids), BITS), bool)
        bits[np.repeat(np.arange(len(self.ids)), self.sizes), self.words % BITS] = True
        return np.packbits(bits, axis=1).view(np.uint64), self.sizes - bits.sum(1)

    @property
    def bytes(self) -> int:
        return 2 * self.mat.nbytes + (0 if self.words is None else self.words.nbytes + len(self.ids) * BITS // 8)


def hits(a: Tile, b: Tile, tau: float, same: bool) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(places in a, places in b) of all pairs within tau, each once; same: a and b are one tile."""
    error = (a.unit.shape[1] + 8) * 2.0**-23  # of a product of unit vectors in single precision
    for lo in range(0, len(a.ids), STEP):
        first = lo if same else 0
        sims = a.unit[lo : lo + STEP] @ b.unit[first:].T
        found = np.flatnonzero(sims >= np.float32(tau - 2 * error))
        if not len(found):
            continue
        x, y = np.divmod(found, sims.shape[1])
        sure = sims.ravel()[found] >= tau + 2 * error
        x, y = x + lo, y + first
        if same:
            x, y, sure = (v[x < y] for v in (x, y, sure))
        open_ = np.flatnonzero(~sure)
        sure[open_] = exact(a, b, x[open_], y[open_]) >= tau
        yield x[sure], y[sure]


def exact(a: Tile, b: Tile, x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Similarities of pairs in double precision, rounded like any other."""
    out = np.empty(len(x))
    for lo in range(0, len(x), 1 << 14):
        i, j = x[lo : lo + (1 << 14)], y[lo : lo + (1 << 14)]
        out[lo : lo + len(i)] = np.einsum("ij,ij->i", a.mat[i].astype(np.float64), b.mat[j].astype(np.float64)) / np.sqrt(a.norms[i] * b.norms[j])
    return np.round(out, DECIMALS)


class Sets:
    """Disjoint sets of the places of several tiles, joined many pairs at a time."""

    def __init__(self, n: int):
        self.up = np.arange(n)

    def top(self, x: np.ndarray) -> np.ndarray:
        x = self.up[x]
        while ((y := self.up[x]) != x).any():
            x = y
        return x

    def join(self, x: np.ndarray, y: np.ndarray) -> None:
        while True:
            x, y = self.top(x), self.top(y)
            apart = x != y
            if not apart.any():
                return
            x, y = x[apart], y[apart]
            self.up[np.maximum(x, y)] = np.minimum(x, y)  # of several pairs with one upper end, one is done; the others come again

    def flatten(self) -> None:
        self.up = self.top(self.up)


def _span(starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """The places starts[0], starts[0] + 1, ... of all stretches, one after the other."""
    ends = np.cumsum(sizes)
    return np.arange(ends[-1] if len(ends) else 0) + np.repeat(starts - ends + sizes, sizes)


def overlaps(a: Tile, b: Tile, x: np.ndarray, y: np.ndarray, least: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(x, y, Jaccard overlap) of the pairs, sorted by x, whose word sets overlap by `least` at least and are of one language.

    Most pairs are ruled out by maps of bits: two texts share no more words than their maps share bits, and the words that one
    of the maps has no bits for. The words of the others are compared.
    """
    less, more = np.minimum(a.sizes[x], b.sizes[y]), np.maximum(a.sizes[x], b.sizes[y])
    fit = (a.codes[x] == b.codes[y]) & (less >= least * more) & (less > 0)
    x, y = x[fit], y[fit]
    (maps_a, spare_a), (maps_b, spare_b) = a.maps, b.maps
    likely = np.zeros(len(x), bool)
    for lo in range(0, len(x), 512):
        i, j = x[lo : lo + 512], y[lo : lo + 512]
        most = np.bitwise_count(maps_a[i] & maps_b[j]).sum(1, dtype=np.int64) + np.minimum(spare_a[i], spare_b[j])
        most = np.minimum(most, np.minimum(a.sizes[i], b.sizes[j]))
        likely[lo : lo + 512] = most >= least * (a.sizes[i] + b.sizes[j] - most)
    x, y = x[likely], y[likely]
    share = np.zeros(len(x))
    cuts = np.flatnonzero(np.diff(x, prepend=-1, append=-1)) if len(x) else []
    for first, end in zip(cuts, cuts[1:]):
        i = x[first]
        own = a.words[a.starts[i] : a.starts[i] + a.sizes[i]]
        for lo in range(first, end, 512):
            j = y[lo : min(end, lo + 512)]
            n = b.sizes[j]
            theirs = b.words[_span(b.starts[j], n)]
            met = own[np.minimum(np.searchsorted(own, theirs), len(own) - 1)] == theirs
            shared = np.add.reduceat(met, np.cumsum(n) - n, dtype=np.int64)
            share[lo : lo + len(j)] = shared / (n + len(own) - shared)
    enough = share >= least
    return x[enough], y[enough], share[enough]


#: Gets the places of a square's pairs of tiles and a way to get a tile by its place; gives what is found.
Judge = Callable[[list[tuple[int, int]], Callable[[int], Tile]], Iterator[pa.RecordBatch]]


def _over(tiles: DataFrame, judge: Judge, kind: str) -> DataFrame:
    """What judge finds in all pairs of tiles."""
    spark = tiles.sparkSession
    at = [tuple(r) for r in tiles.select("_metadata.file_path", "_metadata.row_index").collect()]  # a row for each few thousand vectors
    at.sort()
    if not at:
        return spark.createDataFrame([], kind)
    if not _readable(at[0][0]):
        return _joined(tiles, judge, kind)
    cores = spark.sparkContext.defaultParallelism
    sides = max(min(len(at), round((8 * cores) ** 0.5)), -(-len(at) // SIDE))
    cuts = [len(at) * i // sides for i in range(sides + 1)]
    squares = [(cuts[p], cuts[p + 1], cuts[q], cuts[q + 1]) for p in range(sides) for q in range(p, sides)]
    sent = spark.sparkContext.broadcast((at, squares))

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        where, squares = sent.value
        kept: OrderedDict[int, Tile] = OrderedDict()

        def tile(i: int) -> Tile:
            if i not in kept:
                kept[i] = _read(*where[i])
                while len(kept) > 2 and sum(t.bytes for t in kept.values()) > KEPT:
                    kept.popitem(last=False)
            kept.move_to_end(i)
            return kept[i]

        for b in batches:
            for s in b.column(0).to_pylist():
                a, z, c, e = squares[s]
                pairs = [(i, j) for i in range(a, z) for j in (range(c, e) if i % 2 else range(e - 1, c - 1, -1)) if i <= j]
                yield from judge(pairs, tile)

    return spark.range(0, len(squares), 1, len(squares)).mapInArrow(kernel, kind)


def _readable(path: str) -> bool:
    try:
        return ivf._arrow(path)[0] is not None
    except (OSError, ValueError, NotImplementedError):
        return False


def _read(path: str, row: int) -> Tile:
    import pyarrow.parquet as pq

    system, place = ivf._arrow(path)
    with pq.ParquetFile(place, filesystem=system) as file:
        return Tile.of(file.read_row_group(row).to_pylist()[0])


def _joined(tiles: DataFrame, judge: Judge, kind: str) -> DataFrame:
    """The same over tiles that Spark brings together."""
    place = F.struct("_metadata.file_path", "_metadata.row_index")
    side = lambda x: tiles.select(place.alias(f"at_{x}"), F.struct(*tiles.columns).alias(f"tile_{x}"))
    met = side("a").join(side("b"), F.col("at_a") <= F.col("at_b")).select((F.col("at_a") == F.col("at_b")).alias("same"), "tile_a", "tile_b")

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(b.num_rows):
                row = b.slice(i, 1).to_pylist()[0]
                both = [Tile.of(row["tile_a"]), Tile.of(row["tile_b"])]
                yield from judge([(0, 0 if row["same"] else 1)], both.__getitem__)

    return met.mapInArrow(kernel, kind)


def forest(tiles: DataFrame, tau: float) -> DataFrame:
    """Rows (id_a, id_b) with the same components as all pairs within tau: the stars of what each task has connected."""

    def judge(pairs: list[tuple[int, int]], tile: Callable[[int], Tile]) -> Iterator[pa.RecordBatch]:
        begins, ids, n = {}, [], 0
        for i in dict.fromkeys(x for p in pairs for x in p):
            begins[i] = n
            ids.append(tile(i).ids)
            n += len(ids[-1])
        sets, ids = Sets(n), np.concatenate(ids)
        for i, j in pairs:
            for x, y in hits(tile(i), tile(j), tau, i == j):
                sets.join(x + begins[i], y + begins[j])
            sets.flatten()
        rays = np.flatnonzero(sets.up != np.arange(n))
        for lo in range(0, len(rays), 1 << 16):
            some = rays[lo : lo + (1 << 16)]
            yield pa.RecordBatch.from_arrays([pa.array(ids[some]), pa.array(ids[sets.up[some]])], ["id_a", "id_b"])

    return _over(tiles, judge, STARS)


def agreeing(tiles: DataFrame, tau: float, least_jaccard: float = 0.5) -> DataFrame:
    """Rows (id_a, id_b, sim, jaccard): all pairs within tau of one language whose word sets overlap enough, the smaller id first."""

    def judge(pairs: list[tuple[int, int]], tile: Callable[[int], Tile]) -> Iterator[pa.RecordBatch]:
        for i, j in pairs:
            a, b = tile(i), tile(j)
            for x, y in hits(a, b, tau, i == j):
                x, y, share = overlaps(a, b, x, y, least_jaccard)
                if len(x):
                    p, q = a.ids[x], b.ids[y]
                    yield pa.RecordBatch.from_arrays([pa.array(v) for v in (np.minimum(p, q), np.maximum(p, q), exact(a, b, x, y), share)], ["id_a", "id_b", "sim", "jaccard"])

    return _over(tiles, judge, AGREED)
