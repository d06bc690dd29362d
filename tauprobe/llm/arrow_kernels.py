"""Shared parts of the Arrow-batched operators: chained batch functions, text segments, ASCII lower case."""

from __future__ import annotations

import re
from collections.abc import Callable, Iterable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

#: Places at which a text may be cut without changing the words or pre-tokens on either side: no run of white space,
#: Unicode's included, lies on both sides.
_CUT = re.compile(r"(?<=\S)(?=[ \t\n\r])")

#: Rows and bytes of the slices that are worked off together; keeps Python memory flat whatever Spark's own batch size is.
SLICE_ROWS, SLICE_BYTES = 128, 1 << 19


def segments(text: str, size: int = 1 << 20) -> Iterator[str]:
    """Consecutive pieces of about `size` characters, each but the first beginning at the first character of a run of white space."""
    at = 0
    while len(text) - at > size and (m := _CUT.search(text, at + size)):
        yield text[at : m.start()]
        at = m.start()
    yield text[at:] if at else text


def run(df: DataFrame, steps: Iterable[Callable[[pa.RecordBatch], pa.RecordBatch]], schema: StructType | str) -> DataFrame:
    """Applies batch functions one after another in a single Python pass over the frame."""
    steps = list(steps)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            rows = max(1, min(SLICE_ROWS, SLICE_BYTES * whole.num_rows // max(whole.nbytes, 1)))
            for at in range(0, whole.num_rows, rows):
                batch = whole.slice(at, rows)
                for step in steps:
                    batch = step(batch)
                yield batch
        give_back()

    return df.mapInArrow(kernel, schema)


@lru_cache(1)
def _trim():
    import ctypes

    try:
        return ctypes.CDLL(None).malloc_trim
    except (AttributeError, OSError):  # another C library
        return lambda _: 0


def give_back() -> None:
    """Returns memory that is free in this process to the system: a worker lives on while the JVM needs the memory."""
    pa.default_memory_pool().release_unused()
    _trim()(0)


class Memory:
    """What has been worked out for words, in two generations: words in use stay, the size is bounded.

    `learn` takes a list of new words and returns their values. After `fill`, `now` has every word asked for.
    """

    def __init__(self, learn: Callable[[list], Iterable], size: int = 1 << 18):
        self.learn, self.size = learn, size
        self.now: dict = {}
        self.past: dict = {}

    def fill(self, words: Iterable) -> dict:
        wanted = set(words)
        new = wanted.difference(self.now)
        if len(self.now) + len(new) > self.size:
            self.past, self.now = self.now, {}
            new = wanted
        past = self.past
        fresh = []
        for word in new:
            if (value := past.get(word)) is None:
                fresh.append(word)
            else:
                self.now[word] = value
        if fresh:
            self.now.update(zip(fresh, self.learn(fresh), strict=True))
        return self.now


#: Rows and bytes (of text) up to which the small side of a join is broadcast.
SMALL, SMALL_BYTES = 500_000, 48 << 20


def small(df: DataFrame) -> DataFrame:
    """df, marked for broadcast if its rows and their bytes were counted to be few; a join with it is shuffled otherwise."""
    if df.limit(SMALL + 1).count() > SMALL:
        return df
    width = F.length(F.to_json(F.struct(*df.columns)))
    return F.broadcast(df) if (df.agg(F.sum(width)).first()[0] or 0) <= SMALL_BYTES else df


def crc_rest(id_col: str, modulus: int) -> Column:
    """crc32 of the id, written as text, by the modulus; null for a null id."""
    return F.crc32(F.col(id_col).cast("string").cast("binary")) % modulus


def labelled_sample(df: DataFrame, group: str, per_group: int, groups: int, total: int) -> DataFrame | None:
    """A bounded sample of rows (id, text, group): at most about per_group rows of each of the `groups` most frequent groups, and total of all.

    Rows are picked by a hash of id and text that lies below a bar set by the group's count; equal rows come once. None
    without rows.
    """
    counts = df.groupBy(group).count().orderBy(F.desc("count"), group).limit(groups).collect()
    if not counts:
        return None
    whole, per_group = 1 << 30, min(per_group, total // len(counts))
    bars = F.create_map(*[F.lit(v) for r in counts for v in (r[group], min(whole, whole * per_group // r["count"]))])
    marked = df.withColumn("h", F.xxhash64("id", "text"))
    return marked.where(F.pmod("h", F.lit(whole)) < F.try_element_at(bars, F.col(group))).dropDuplicates(["id", "h"])


def pack_sparse(places: np.ndarray, numbers: np.ndarray) -> bytes:
    """Unsigned 32-bit places, then as many single-precision numbers."""
    return places.astype("<u4").tobytes() + numbers.astype("<f4").tobytes()


def unpack_sparse(data: bytes) -> tuple[np.ndarray, np.ndarray]:
    half = len(data) // 2
    return np.frombuffer(data[:half], "<u4").astype(np.int64), np.frombuffer(data[half:], "<f4")
