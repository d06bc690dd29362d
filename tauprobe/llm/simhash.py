"""SimHash near-duplicates with covering locality-sensitive hashing.

`fingerprints` gives each text 64 bits: the majority, bit by bit, of the XXH64 values of its word shingles. `links` finds
fingerprints at most `radius` bits apart with structured masks: bit i stands for a non-zero vector over radius + 1 binary
digits, and the mask of each non-zero vector v keeps the bits whose vector has an odd product with v. At most `radius`
differing bits give as many equations in radius + 1 unknowns, so some mask leaves all of them out: every pair within the
radius falls into one bucket in at least one table, and none is missed. `classes` joins linked texts into classes.

Equal fingerprints are joined before any table is built, so copies cost one row. A bucket of two is checked in SQL. A
larger one, up to `bucket_limit` fingerprints, gives the edges of a spanning forest of its links. Beyond that the
fingerprints take another exact way that is linear in their number: two of them are within an even radius if and only if
they share a point at half the radius, so all that share a point are linked to the smallest of them.

Defined results: a text that is null or has no word has fingerprint zero and is linked like any other; fewer words than a
shingle has make one shingle; very long texts count whole, block by block; repeated rows and ids each give a row; a class
is named by its smallest non-null id, or null; an empty table gives an empty table; only the named columns are read.
"""

from __future__ import annotations

import itertools

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tauprobe.llm.arrow_kernels import run, small
from tauprobe.operators.components import components, join_hot
from tauprobe.session import materialize

BITS = 64
_BLOCK = 1 << 15


def fingerprint(text: str | None, words_each: int = 4, seed: int = 42) -> int:
    """Unsigned 64-bit fingerprint of a text."""
    import xxhash

    words = (text or "").encode().lower().split()  # ASCII letters and ASCII white space only, as bytes
    if not words:
        return 0
    joined = b" ".join(words)
    ends = np.cumsum([len(w) + 1 for w in words]) - 1
    starts = np.concatenate(([0], ends[:-1] + 1))
    ends = ends[min(words_each, len(words)) - 1 :].tolist()
    starts = starts[: len(ends)].tolist()
    digest = xxhash.xxh64_digest
    ones = np.zeros(BITS, np.int64)
    for lo in range(0, len(ends), _BLOCK):
        packed = b"".join([digest(joined[a:b], seed) for a, b in zip(starts[lo : lo + _BLOCK], ends[lo : lo + _BLOCK], strict=True)])
        bits = np.unpackbits(np.frombuffer(packed, np.uint8)).reshape(-1, BITS)
        ones += bits.sum(0, dtype=np.uint32)
    return int.from_bytes(np.packbits(2 * ones > len(ends)).tobytes(), "big")


def fingerprints(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", words_each: int = 4, seed: int = 42) -> DataFrame:
    """Rows (id, fp): the fingerprint as a signed 64-bit number."""
    picked = df.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))

    def step(batch: pa.RecordBatch) -> pa.RecordBatch:
        found = np.array([fingerprint(t, words_each, seed) for t in batch.column(1).to_pylist()], np.uint64)
        return pa.RecordBatch.from_arrays([batch.column(0), pa.array(found.view(np.int64))], ["id", "fp"])

    return run(picked, [step], f"id {picked.schema['id'].dataType.simpleString()}, fp bigint")


def masks(radius: int, bits: int = BITS) -> list[int]:
    """Covering masks as signed 64-bit numbers, one for each table."""
    vectors = [1 + i % ((1 << (radius + 1)) - 1) for i in range(bits)]
    out = []
    for v in range(1, 1 << (radius + 1)):
        kept = sum(1 << i for i, m in enumerate(vectors) if (m & v).bit_count() & 1)
        out.append(kept - (1 << 64) if kept >> 63 else kept)
    return out


def forest(members: np.ndarray, radius: int) -> list[tuple[int, int]]:
    """Edges of a spanning forest of the links between these distinct fingerprints."""
    left = members.view(np.uint64)
    edges = []
    while len(left):
        queue, left = [left[0]], left[1:]
        while queue and len(left):
            at = queue.pop()
            near = np.bitwise_count(left ^ at) <= radius
            edges += [(at, x) for x in left[near]]
            queue += list(left[near])
            left = left[~near]
    return [(int(a.view(np.int64)), int(b.view(np.int64))) for a, b in edges]


def half_radius_edges(fps: DataFrame, radius: int) -> DataFrame:
    """Edges that join all fingerprints of column fp within an even radius, over the points at half the radius."""
    flips = [0]
    for n in range(1, radius // 2 + 1):
        flips += [sum(1 << i for i in places) for places in itertools.combinations(range(BITS), n)]
    flips = [f - (1 << 64) if f >> 63 else f for f in flips]
    points = fps.select("fp", F.explode(F.lit(flips).cast("array<bigint>")).alias("flip")).select("fp", F.col("fp").bitwiseXOR(F.col("flip")).alias("z"))
    least = points.groupBy("z").agg(F.min("fp").alias("id_b"))
    return points.join(least, "z").where("fp <> id_b").select(F.col("fp").alias("id_a"), "id_b").distinct()


def links(fps: DataFrame, radius: int = 4, bucket_limit: int = 4096) -> DataFrame:
    """Edges (id_a, id_b) between distinct fingerprints (column fp) whose closure is that of all pairs within the radius."""
    tables = F.array(*[F.struct(F.lit(t).alias("t"), F.col("fp").bitwiseAND(F.lit(m)).alias("key")) for t, m in enumerate(masks(radius))])
    keyed = fps.select("fp", F.explode(tables).alias("k")).select("fp", "k.t", "k.key")
    buckets = keyed.groupBy("t", "key").agg(F.count(F.lit(1)).alias("n"), F.min("fp").alias("lo"), F.max("fp").alias("hi")).where("n > 1")
    buckets = materialize(buckets, "buckets")
    pairs = buckets.where("n = 2").where(F.bit_count(F.col("lo").bitwiseXOR(F.col("hi"))) <= radius).select(F.col("lo").alias("id_a"), F.col("hi").alias("id_b"))
    most = buckets.agg(F.max("n")).first()[0] or 0
    if most <= 2:
        return pairs.distinct()
    members = keyed.join(buckets.where("n > 2").select("t", "key", "n"), ["t", "key"])
    whole = members.where(F.col("n") <= bucket_limit).groupBy("t", "key").agg(F.collect_list("fp").alias("fps"))

    def step(batch: pa.RecordBatch) -> pa.RecordBatch:
        edges = [e for fps in batch.column(0) for e in forest(fps.values.to_numpy().copy(), radius)]
        a, b = zip(*edges, strict=True) if edges else ((), ())
        return pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], ["id_a", "id_b"])

    found = pairs.union(run(whole.select("fps"), [step], "id_a bigint, id_b bigint"))
    if most > bucket_limit:
        if radius % 2:
            raise ValueError("buckets beyond the limit need an even radius")
        found = found.union(half_radius_edges(members.where(F.col("n") > bucket_limit).select("fp").distinct(), radius))
    return found.select(F.least("id_a", "id_b").alias("id_a"), F.greatest("id_a", "id_b").alias("id_b")).distinct()


def classes(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", words_each: int = 4, radius: int = 4, bucket_limit: int = 4096) -> DataFrame:
    """Rows (id, fp, component): one for each row of df; component is the smallest id that links reach."""
    marked = materialize(fingerprints(df, id_col, text_col, words_each), "fingerprints")
    firsts = materialize(marked.groupBy("fp").agg(F.min("id").alias("first"), F.count(F.lit(1)).alias("n")), "distinct-fingerprints")
    joined = components(links(firsts.select("fp"), radius, bucket_limit))
    named = joined.join(firsts, joined.node == firsts.fp).select("fp", "component", "first")
    named = materialize(named, "named-fingerprints")
    least = materialize(named.groupBy("component").agg(F.min("first").alias("least"), F.count(F.lit(1)).alias("n")), "components")
    reached = join_hot(named, least, "component").select("fp", "least")
    of = materialize(firsts.join(reached, "fp", "left").select("fp", "n", F.coalesce("least", "first").alias("component")), "fingerprint-classes")
    return join_hot(marked, of, "fp").select("id", "fp", "component")


def keep_one(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of df that stay when one row of each class does: one with the smallest id. Rows count, whatever ids they share."""
    key = F.struct(F.col(id_col).isNull().alias("none"), F.col(id_col).alias("id"), F.monotonically_increasing_id().alias("row"))
    keyed = materialize(df.withColumn("_keep_one_key", key), "keyed")  # written once, so a row's key is the same in every retry
    gone = classes(keyed, "_keep_one_key", text_col).where("id.row <> component.row").select(F.col("id.row").alias("_gone_row"))
    return keyed.join(small(materialize(gone, "gone")), F.col("_keep_one_key.row") == F.col("_gone_row"), "left_anti").drop("_keep_one_key")
