"""Functions that SQL users can call: cosine as SQL, norms as an Arrow-batched UDF, a mean as an aggregate, and two table functions."""

from __future__ import annotations

import hashlib
import re

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import DoubleType, StructType


@pandas_udf(DoubleType())
def norm(vecs: pd.Series) -> pd.Series:
    return vecs.map(lambda v: float((v.astype("f8") ** 2).sum() ** 0.5))


@pandas_udf(DoubleType())
def mean_first(vecs: pd.Series) -> float:
    return float(vecs.map(lambda v: float(v[0])).mean())


@pandas_udf(DoubleType())
def rows_of(vecs: pd.Series) -> float:
    return float(len(vecs))


@udtf(returnType=StructType().add("rank", "integer").add("stale", "integer").add("visited", "boolean"))
class ProbeTrace:
    """The stopping rule over a string of hit bits."""

    def eval(self, hits: str, window: int):
        stale, ended = 0, False
        for rank, bit in enumerate(hits, 1):
            stale = 0 if bit == "1" else stale + 1
            yield rank, stale, not ended
            ended = ended or stale >= window


@udtf(returnType=StructType().add("token", "string").add("bucket", "integer").add("sign", "integer"))
class HashedTokens:
    def eval(self, text: str):
        for token in re.split("[ \t\r\n]+", text or ""):
            if token:
                h = int(hashlib.md5(token.encode()).hexdigest()[:8], 16)
                yield token, h % 64, 1 if h // 64 % 2 else -1


def register(spark: SparkSession) -> None:
    """Makes tau_cosine, tau_norm, tau_probe_trace and tau_hashed_tokens known to the session."""
    dot = "aggregate(zip_with({0}, {1}, (x, y) -> cast(x as double) * cast(y as double)), 0D, (s, x) -> s + x)"
    spark.sql(f"create or replace temporary function tau_cosine(a array<float>, b array<float>) returns double return {dot.format('a', 'b')} / sqrt({dot.format('a', 'a')} * {dot.format('b', 'b')})")
    spark.udf.register("tau_norm", norm)
    spark.udtf.register("tau_probe_trace", ProbeTrace)
    spark.udtf.register("tau_hashed_tokens", HashedTokens)
