"""Session and shared storage."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_FALLBACK: list[str] = []
_OWN: set[str] = set()


def local_session(cores: int | str = "*", **conf: str) -> SparkSession:
    """A session for tests and benches; on a cluster the given session is used as it is."""
    builder = SparkSession.builder.master(f"local[{cores}]").config("spark.sql.shuffle.partitions", "8").config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC")
    for k, v in conf.items():
        builder = builder.config(k, v)
    return builder.getOrCreate()


def shared_dir(spark: SparkSession) -> str:
    """A fresh folder name in the shared folder of ``spark.checkpoint.dir``, deleted when the application ends.

    Without that setting a temporary folder serves a local master; on a cluster, whose executors could not
    see it, an error is raised.
    """
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local") or spark.sparkContext.master.startswith("local-cluster"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        if not _FALLBACK:
            _FALLBACK.append("file://" + tempfile.mkdtemp(prefix="divknn-"))
        base = _FALLBACK[0]
    own = f"{base.rstrip('/')}/divknn-{spark.sparkContext.applicationId}"
    if own not in _OWN:
        jvm = spark.sparkContext._jvm
        path = jvm.org.apache.hadoop.fs.Path(own)
        files = path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
        files.mkdirs(path)
        files.deleteOnExit(path)
        _OWN.add(own)
    return f"{own}/{uuid.uuid4().hex}"


def saved(df: DataFrame, path: str | None = None, **options: str) -> DataFrame:
    """Write and read back: cuts lineage in a way that survives lost executors."""
    path = path or shared_dir(df.sparkSession)
    df.write.options(**options).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def saved_vectors(df: DataFrame, path: str | None = None) -> DataFrame:
    """Coordinates seldom repeat: a dictionary of them is built in vain, and costs more than the codec."""
    return saved(df, path, **{"parquet.enable.dictionary": "false", "compression": "zstd"})


def delete(spark: SparkSession, path: str) -> None:
    """Remove a folder that is not read any more."""
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
