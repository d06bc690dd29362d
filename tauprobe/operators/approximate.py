"""Approximate parts: graph-assisted and cell-routed assignment, and compressed codes with their search."""

from __future__ import annotations

import heapq
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tauprobe.operators import ivf, search
from tauprobe.session import materialize


class CentroidGraph:
    """A hierarchical small-world graph over unit centroids: greedy descent from the top level, then a beam at the bottom."""

    def __init__(self, unit: np.ndarray, links: int = 8, build_beam: int = 32, seed: int = 1):
        rng = np.random.default_rng(seed)
        self.unit, self.links = unit, links
        levels = np.minimum((-np.log(np.maximum(rng.random(len(unit)), 1e-12)) / np.log(max(links, 2))).astype(int), 8)
        self.near: list[dict[int, list[int]]] = [{} for _ in range(int(levels.max(initial=0)) + 1)]
        self.entry, self.top = -1, -1
        for i in range(len(unit)):
            self._insert(i, int(levels[i]), build_beam)

    def _beam(self, q: np.ndarray, entries: list[int], level: int, beam: int) -> list[tuple[float, int]]:
        """(similarity, node), best first."""
        seen = set(entries)
        best = [(float(self.unit[e] @ q), e) for e in entries]
        heapq.heapify(best)
        ahead = [(-s, e) for s, e in best]
        heapq.heapify(ahead)
        while ahead:
            s, at = heapq.heappop(ahead)
            if len(best) >= beam and -s < best[0][0]:
                break
            new = [n for n in self.near[level].get(at, ()) if n not in seen]
            seen.update(new)
            for n, sim in zip(new, self.unit[new] @ q if new else (), strict=True):
                if len(best) < beam or sim > best[0][0]:
                    heapq.heappush(best, (float(sim), n))
                    heapq.heappush(ahead, (-float(sim), n))
                    if len(best) > beam:
                        heapq.heappop(best)
        return sorted(best, reverse=True)

    def _insert(self, i: int, level: int, beam: int) -> None:
        q, at = self.unit[i], [self.entry]
        if self.entry >= 0:
            for lv in range(self.top, level, -1):
                at = [self._beam(q, at, lv, 1)[0][1]]
            for lv in range(min(level, self.top), -1, -1):
                found = self._beam(q, at, lv, beam)
                at = [n for _, n in found]
                self.near[lv][i] = at[: self.links]
                for n in at[: self.links]:
                    own = self.near[lv].setdefault(n, [])
                    own.append(i)
                    if len(own) > 2 * self.links:
                        own.sort(key=lambda x, n=n: -float(self.unit[x] @ self.unit[n]))
                        del own[2 * self.links :]
        for lv in range(level + 1):
            self.near[lv].setdefault(i, [])
        if level > self.top:
            self.entry, self.top = i, level

    def frozen(self) -> list[np.ndarray]:
        """Links of each level as a matrix, a row for each node, filled up with -1."""
        out = []
        for links in self.near:
            table = np.full((len(self.unit), max(map(len, links.values()), default=0) or 1), -1, np.int64)
            for i, near in links.items():
                table[i, : len(near)] = near
            out.append(table)
        return out

    def nearest(self, unit: np.ndarray, beam: int, tables: list[np.ndarray]) -> np.ndarray:
        """The best node that each row's walk finds: greedy steps down the levels, then a beam; all rows take a step at a time."""
        rows = np.arange(len(unit))
        at = np.full(len(unit), self.entry)
        best = (self.unit[at] * unit).sum(1)
        for table in tables[self.top : 0 : -1]:
            moving = rows
            while len(moving):
                near = table[at[moving]]
                sims = np.where(near >= 0, np.einsum("ijk,ik->ij", self.unit[near], unit[moving]), -9.0)
                pick = sims.argmax(1)
                top = sims[np.arange(len(moving)), pick]
                better = top > best[moving]
                moving, near, pick, top = moving[better], near[better], pick[better], top[better]
                at[moving], best[moving] = near[np.arange(len(moving)), pick], top
        nodes = np.full((len(unit), beam), -1)
        sims = np.full((len(unit), beam), -9.0)
        done = np.ones((len(unit), beam), bool)
        nodes[:, 0], sims[:, 0], done[:, 0] = at, best, False
        seen = np.zeros((len(unit), len(self.unit)), bool)
        seen[rows, at] = True
        active = rows
        while len(active := active[~done[active].all(1)]):
            step = np.where(done[active], -99.0, sims[active]).argmax(1)
            done[active, step] = True
            near = tables[0][nodes[active, step]]
            new = (near >= 0) & ~seen[active[:, None], near]
            seen[active[:, None], np.where(near >= 0, near, nodes[active, step][:, None])] = True
            found = np.where(new, np.einsum("ijk,ik->ij", self.unit[near], unit[active]), -9.0)
            every_n, every_s = np.hstack([nodes[active], near]), np.hstack([sims[active], found])
            every_d = np.hstack([done[active], found < -5])
            keep = np.argsort(-every_s, axis=1, kind="stable")[:, :beam]
            nodes[active], sims[active], done[active] = (np.take_along_axis(x, keep, 1) for x in (every_n, every_s, every_d))
        top = np.round(sims, ivf.DECIMALS)
        return np.where((top == top[:, :1]) & (nodes >= 0), nodes, len(self.unit)).min(1)


def graph_chooser(centroids: ivf.Centroids, links: int = 8, beam: int = 4, seed: int = 1):
    """For ivf.assign: the graph's answer instead of the nearest centroid; a beam of all centroids is nearly exact."""
    graph = CentroidGraph(centroids.unit, links, max(32, 2 * links), seed)
    tables = graph.frozen()

    def choose(unit: np.ndarray) -> np.ndarray:
        return graph.nearest(unit, beam, tables)

    return choose


def cell_chooser(centroids: ivf.Centroids, probes: int = 1):
    """Centroids in cells around every so many-th of them; a vector looks into the centroids of its nearest cells only."""
    n = len(centroids.unit)
    cells = max(1, int(round(n**0.5)))
    heads = centroids.unit[np.arange(cells) * n // cells]
    of = np.round(centroids.unit @ heads.T, ivf.DECIMALS).argmax(1)

    def choose(unit: np.ndarray) -> np.ndarray:
        near = ivf.best_first(np.round(unit @ heads.T, ivf.DECIMALS), probes)
        scores = np.round(unit @ centroids.unit.T, ivf.DECIMALS)
        scores[~(of[None, :, None] == near[:, None, :]).any(2)] = -np.inf
        return scores.argmax(1)

    return choose


def rotation(dim: int, seed: int) -> np.ndarray:
    q, r = np.linalg.qr(np.random.default_rng(seed).normal(size=(dim, dim)))
    return q * np.sign(np.diag(r))


@dataclass(frozen=True)
class Coder:
    """Codes of `bits` bits a dimension for what is left of a unit vector after its centroid, turned by a random rotation."""

    bits: int
    turn: np.ndarray

    def encode(self, unit: np.ndarray, centroid: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(grid points, residual length, alignment of grid point and direction)."""
        left = unit - centroid
        length = np.sqrt((left * left).sum(1))
        y = (left / np.maximum(length, 1e-30)[:, None]) @ self.turn.T
        half = 1 << (self.bits - 1)
        best, at = np.full(len(y), -2.0), np.zeros_like(y)
        biggest = np.maximum(np.abs(y).max(1, keepdims=True), 1e-30)
        for stretch in np.linspace(0.6, 1.3, 15) if self.bits > 1 else (1.0,):
            g = np.clip(np.floor(y / biggest * half * stretch), -half, half - 1) + 0.5
            fit = (g * y).sum(1) / np.sqrt((g * g).sum(1))
            better = fit > best
            best, at[better] = np.where(better, fit, best), g[better]
        return (at - 0.5).astype(np.int8), length, best

    def estimate(self, turned: np.ndarray, to_centroid: np.ndarray, codes: np.ndarray, length: np.ndarray, fit: np.ndarray) -> np.ndarray:
        """Estimated cosines of rotated unit queries and coded vectors."""
        g = codes.astype(np.float64) + 0.5
        return to_centroid[:, None] + (turned @ g.T) * (length / (np.sqrt((g * g).sum(1)) * np.where(length > 0, fit, 1.0)))[None, :]


def pack_bits(codes: np.ndarray, bits: int) -> bytes:
    """Codes as a stream of `bits` bits each."""
    shifted = (codes.astype(np.int16) + (1 << (bits - 1))).astype(np.uint8)
    return np.packbits(np.unpackbits(shifted[..., None], axis=-1)[..., 8 - bits :].ravel()).tobytes()


def unpack_bits(data: bytes, bits: int, n: int, dim: int) -> np.ndarray:
    raw = np.unpackbits(np.frombuffer(data, np.uint8))[: n * dim * bits].reshape(n, dim, bits)
    value = (raw.astype(np.int16) << np.arange(bits - 1, -1, -1)).sum(-1)
    return (value - (1 << (bits - 1))).astype(np.int8)


def coded(index: ivf.Index, bits: int = 7, seed: int = 5) -> ivf.Index:
    """The index with codes beside its ids: blocks have code, length, fit and no matrix."""
    sent = index.blocks.sparkSession.sparkContext.broadcast((Coder(bits, rotation(index.dim, seed)), index.centroids))

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder, c = sent.value
        for b in batches:
            for i in range(b.num_rows):
                row = ivf.as_block(b.slice(i, 1))
                unit = np.frombuffer(row["mat"], "<f4").reshape(row["n"], -1).astype(np.float64) / np.sqrt(row["norms"])[:, None]
                codes, length, fit = coder.encode(unit, c.vector(row["shard_id"], row["pid"]))
                yield pa.RecordBatch.from_pylist(
                    [{k: row[k] for k in ("shard_id", "pid", "block_no", "n", "ids")} | {"code": pack_bits(codes, coder.bits), "length": length.tolist(), "fit": fit.tolist(), "list_id": row["pid"], "list_shard": row["shard_id"]}],
                    pa.schema([("shard_id", pa.int32()), ("pid", pa.int32()), ("block_no", pa.int64()), ("n", pa.int32()), ("ids", pa.list_(pa.int64())), ("code", pa.binary()), ("length", pa.list_(pa.float64())), ("fit", pa.list_(pa.float64())), ("list_id", pa.int32()), ("list_shard", pa.int32())]),
                )

    kind = "shard_id int, pid int, block_no bigint, n int, ids array<bigint>, code binary, length array<double>, fit array<double>, list_id int, list_shard int"
    return ivf.Index(materialize(index.blocks.mapInArrow(kernel, kind), "codes", **ivf.LAYOUT), index.centroids, index.dim)


def code_scorer(index: ivf.Index, bits: int = 7, seed: int = 5):
    """For search: estimated instead of exact similarities."""
    coder, c = Coder(bits, rotation(index.dim, seed)), index.centroids

    def scorer(queries: np.ndarray, norms: np.ndarray, block: dict) -> np.ndarray:
        unit = queries / np.sqrt(norms)[:, None]
        if "grid" not in block:
            block["grid"] = unpack_bits(block["code"], coder.bits, block["n"], unit.shape[1])
        own = c.vector(block["list_shard"], block["list_id"])
        return np.round(coder.estimate(unit @ coder.turn.T, unit @ own, block["grid"], block["length"], block["fit"]), search.DECIMALS)

    return scorer


def code_error(index: ivf.Index, queries: DataFrame, bits: int, most: int = 256) -> DataFrame:
    """One row (bits, pairs, mean_abs_err, mean_err) of estimated less exact cosines, of at most `most` queries (by a hash) with all vectors.

    Errors are added up where the blocks lie; no pair leaves its task.
    """
    few = queries.orderBy(F.xxhash64("id"), "id").limit(most).select("vec").collect()
    q = np.array([r.vec for r in few], np.float64).reshape(len(few), -1)
    sent = index.blocks.sparkSession.sparkContext.broadcast((q / np.sqrt((q * q).sum(1, keepdims=True)) if len(q) else q, Coder(bits, rotation(index.dim, 5)), index.centroids))

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        q, coder, c = sent.value
        for b in batches:
            for i in range(b.num_rows if len(q) else 0):
                block = ivf.as_block(b.slice(i, 1))
                unit = np.frombuffer(block["mat"], "<f4").reshape(block["n"], -1).astype(np.float64) / np.sqrt(block["norms"])[:, None]
                own = c.vector(block["shard_id"], block["pid"])
                wrong = coder.estimate(q @ coder.turn.T, q @ own, *coder.encode(unit, own)) - q @ unit.T
                yield pa.RecordBatch.from_arrays([pa.array([wrong.size]), pa.array([float(np.abs(wrong).sum())]), pa.array([float(wrong.sum())])], ["n", "a", "e"])

    sums = index.blocks.mapInArrow(kernel, "n bigint, a double, e double").agg(*[F.sum(c).alias(c) for c in "nae"])
    return sums.select(F.lit(bits).alias("bits"), F.col("n").alias("pairs"), F.round(F.col("a") / F.col("n"), 6).alias("mean_abs_err"), F.round(F.col("e") / F.col("n"), 6).alias("mean_err"))


def rerank(edges: DataFrame, base: DataFrame, queries: DataFrame, tau: float, k: int) -> DataFrame:
    """Edges with exact similarities instead of estimates; those below tau go."""
    from tauprobe.functions import vectors

    met = edges.join(base.select(F.col("id").alias("vec_id"), F.col("vec").alias("bv")), "vec_id").join(queries.select(F.col("id").alias("query_id"), F.col("vec").alias("qv")), "query_id")
    scored = met.select("query_id", "vec_id", F.round(vectors.cosine(F.col("qv"), F.col("bv")), search.DECIMALS).alias("sim")).where(F.col("sim") >= tau)
    return search.merge_top(scored, k)
