"""Vector expressions, JVM-side: dot products, norms, cosines; and signed word hashing over Arrow batches."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

DIM = 64


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def norm2(a: Column) -> Column:
    return F.aggregate(a, F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double"))


def cosine(a: Column, b: Column) -> Column:
    return dot(a, b) / F.sqrt(norm2(a) * norm2(b))


def normalize(a: Column) -> Column:
    return F.transform(a, lambda x: x.cast("double") / F.sqrt(norm2(a)))


def usable(vec: Column, dim: int) -> Column:
    """Whether a vector can be indexed: the right dimension, no null or NaN inside, and not all zero."""
    clean = ~F.exists(vec, lambda x: x.isNull() | F.isnan(x.cast("double")))
    return vec.isNotNull() & (F.size(vec) == dim) & clean & (norm2(vec) > 0)


def quarantine(df: DataFrame, vec: str = "vec", dim: int = DIM) -> tuple[DataFrame, DataFrame]:
    """Rows with usable vectors, and the rest."""
    good = F.coalesce(usable(F.col(vec), dim), F.lit(False))
    return df.where(good), df.where(~good)


#: Words whose hash a task keeps at most.
KNOWN = 1 << 18


def words_of(text: str, pairs: bool = False) -> list[str]:
    """Words between blanks, or neighbouring pairs of them; a text of one word keeps it."""
    words = [w for w in text.replace("\t", " ").replace("\r", " ").replace("\n", " ").split(" ") if w]
    return [f"{a} {b}" for a, b in zip(words, words[1:])] if pairs and len(words) > 1 else words


def hashed_cells(df: DataFrame, text: str, pairs: bool = False, dim: int = DIM) -> DataFrame:
    """Rows (id, vec, norm2): signed counts of hashed tokens; a text whose cells are all zero gives no row.

    Cells are whole numbers, so products are exact in any order. A text is counted in its row: nothing is shuffled, and a
    task hashes a word once while it remembers it.
    """

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known: dict[str, int] = {}

        def place(word: str) -> int:
            h = int(hashlib.md5(word.encode()).hexdigest()[:8], 16)
            return h % dim + dim * (h // dim % 2)

        for whole in batches:
            for lo in range(0, whole.num_rows, 256):
                b = whole.slice(lo, 256)
                cells = np.zeros((b.num_rows, dim))
                for row, value in zip(cells, b.column(1).to_pylist(), strict=True):
                    words = words_of(value or "", pairs)
                    if len(known) > KNOWN:
                        known.clear()
                    for w in set(words).difference(known):
                        known[w] = place(w)
                    if words:
                        both = np.bincount(np.fromiter(map(known.__getitem__, words), np.int64, len(words)), minlength=2 * dim)
                        row += both[dim:] - both[:dim]
                used = np.flatnonzero(cells.any(1))
                some = cells[used]
                vecs = pa.ListArray.from_arrays(pa.array(np.arange(len(used) + 1, dtype=np.int32) * dim), pa.array(some.ravel()))
                yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(used)), vecs, pa.array((some * some).sum(1))], ["id", "vec", "norm2"])

    return df.select(F.col("id").cast("bigint").alias("id"), F.col(text).alias("text")).mapInArrow(kernel, "id bigint, vec array<double>, norm2 double")
