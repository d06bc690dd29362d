"""Arriving batches: each searches the index as it is, gives its edges, and is then appended with the same centroids."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tauprobe.operators import ivf, search
from tauprobe.params import SearchParams
from tauprobe.session import scratch

#: After so many batches their blocks are packed anew into one folder, so that the number of folders read stays bounded.
COMPACT = 8


class Arrivals:
    """A foreachBatch sink. A batch's output lies under its number, and a batch that comes again overwrites its own."""

    def __init__(self, centroids: ivf.Centroids, params: SearchParams, path: str, compact: int = COMPACT):
        self.centroids, self.params, self.path, self.compact = centroids, params, path, compact

    def _folders(self, before: int) -> list[str]:
        """What holds the blocks of all batches before this one: the last packed folder, and the batches since."""
        packed = before - before % self.compact
        return [f"{self.path}/packed/{packed}"] * (packed > 0) + [f"{self.path}/blocks/{b}" for b in range(packed, before)]

    def _blocks(self, spark: SparkSession, folders: list[str]) -> DataFrame:
        return spark.read.schema(ivf.BLOCKS).parquet(*folders) if folders else spark.createDataFrame([], ivf.BLOCKS)

    def __call__(self, batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        if number and number % self.compact == 0:
            last = f"{self.path}/packed/{number - self.compact}"
            folders = [last] * (number > self.compact) + [f"{self.path}/blocks/{b}" for b in range(number - self.compact, number)]
            ivf.repack(self._blocks(spark, folders)).write.options(**ivf.LAYOUT).mode("overwrite").parquet(f"{self.path}/packed/{number}")
        index = ivf.Index(self._blocks(spark, self._folders(number)), self.centroids, self.centroids.unit.shape[1])
        rows = batch.select("id", "vec")
        search.lookahead(index, rows, self.params).edges.write.mode("overwrite").parquet(f"{self.path}/edges/batch={number}")
        ivf.pack(ivf.assign(rows, self.centroids)).write.options(**ivf.LAYOUT).mode("overwrite").parquet(f"{self.path}/blocks/{number}")

    def edges(self, spark: SparkSession) -> DataFrame:
        return spark.read.parquet(f"{self.path}/edges")


def replay(spark: SparkSession, every: DataFrame, params: SearchParams, seed_every: int, batches: int) -> DataFrame:
    """Rows (batch, queries_with_edges, edges): the table in slices of ids, as files that arrive day by day.

    Each day the files are written and the stream is started again from its progress; what is new is one batch. The
    centroids are seeds of the first slice, since later ones are not there yet.
    """
    source, out = scratch(spark, "arriving"), scratch(spark, "arrived")
    last = every.agg(F.max("id")).first()[0] or 0
    slices = every.withColumn("slice", F.least(F.floor(F.col("id") * batches / (last + 1)), F.lit(batches - 1)).cast("int"))
    sink = Arrivals(ivf.seed_centroids(slices.where("slice = 0"), seed_every), params, out)
    for s in range(batches):
        slices.where(F.col("slice") == s).drop("slice").write.mode("append").parquet(source)
        stream = spark.readStream.schema(every.schema).parquet(source)
        stream.writeStream.foreachBatch(sink).option("checkpointLocation", f"{out}/progress").trigger(availableNow=True).start().awaitTermination()
    found = sink.edges(spark)
    return found.groupBy("batch").agg(F.count_distinct("query_id").alias("queries_with_edges"), F.count(F.lit(1)).alias("edges"))
