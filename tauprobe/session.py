"""Session helpers: table access and the shared scratch folder."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def build_session(app: str = "tauprobe", master: str = "local[*]", shuffle_partitions: int = 8) -> SparkSession:
    """A session with the settings the engine is tuned for; used by tests, bench and examples only."""
    return (
        SparkSession.builder.master(master)
        .appName(app)
        .config("spark.sql.shuffle.partitions", str(shuffle_partitions))
        .config("spark.sql.adaptive.enabled", "true")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.driver.memory", "6g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .getOrCreate()
    )


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One given table, as a Parquet scan (columns and filters prune into it)."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that the driver and all executors share.

    It is the one named in spark.checkpoint.dir. Only where that is unset on one machine, as in tests, a temporary folder is
    chosen and set as the checkpoint folder; a cluster without the setting is an error.
    """
    sc = spark.sparkContext
    path = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if path:
        if not sc.getCheckpointDir():
            sc.setCheckpointDir(path)
        return path.rstrip("/")
    if not sc.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    path = "file://" + tempfile.mkdtemp(prefix="tauprobe-")
    sc.setCheckpointDir(path)
    return path


_ROOTS: set[str] = set()


def scratch(spark: SparkSession, label: str) -> str:
    """A new path under the shared folder. All of an application's paths go when it ends, or by `release`."""
    sc = spark.sparkContext
    root = f"{shared_dir(spark)}/tauprobe/{sc.applicationId}"
    if root not in _ROOTS:
        _ROOTS.add(root)
        fs, path = _filesystem(spark, root)
        fs.mkdirs(path)
        fs.deleteOnExit(path)
    return f"{root}/{label}-{uuid.uuid4().hex}"


def _filesystem(spark: SparkSession, path: str):
    sc = spark.sparkContext
    place = sc._jvm.org.apache.hadoop.fs.Path(path)
    return place.getFileSystem(sc._jsc.hadoopConfiguration()), place


def release(spark: SparkSession, path: str | None = None) -> None:
    """Deletes a scratch path, or all of this application's: for sessions that live on after their results were used."""
    for p in [path] if path else list(_ROOTS):
        fs, place = _filesystem(spark, p)
        fs.delete(place, True)


def signature(spark: SparkSession, path: str) -> tuple:
    """Total length and time of change of a stored table: another one means that the table was changed."""
    fs, place = _filesystem(spark, path)
    return fs.getContentSummary(place).getLength(), fs.getFileStatus(place).getModificationTime()


def materialize(df: DataFrame, label: str, **options: str) -> DataFrame:
    """Writes a frame to the shared folder and reads it back: cuts lineage, survives lost executors."""
    spark = df.sparkSession
    path = scratch(spark, label)
    df.write.options(**options).parquet(path)
    return spark.read.schema(df.schema).parquet(path)
