"""Where operators keep intermediate tables and raw files, and how they read their inputs."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession, name: str) -> str:
    """A fresh folder, as a URI, in the checkpoint folder that the whole cluster shares.

    ``spark.checkpoint.dir`` is read from the session; only where neither it nor a checkpoint
    folder is set (tests) is a local one made.
    """
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        root = "file://" + tempfile.mkdtemp(prefix="shared-")
        spark.sparkContext.setCheckpointDir(root)
    if "://" not in root and not root.startswith("file:"):
        root = "file://" + root
    return f"{root.rstrip('/')}/{name}-{uuid.uuid4().hex[:12]}"


#: Bytes of one Arrow batch; the rows of one very long text may exceed it.
BATCH_BYTES = 16 << 20


def small_batches(spark: SparkSession) -> None:
    """Smaller Arrow batches than usual: texts are long, and workers hold several arrays a batch."""
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(BATCH_BYTES))


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Write to the shared folder and read back: the lineage is cut and survives lost executors."""
    spark = df.sparkSession
    small_batches(spark)
    path = shared_dir(spark, name)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def open_fs(uri: str):
    """(file system, path) for a shared-folder URI, usable in executors for raw binary files."""
    from pyarrow import fs

    if uri.startswith("file:"):
        return fs.LocalFileSystem(), "/" + uri[5:].lstrip("/")
    return fs.FileSystem.from_uri(uri)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    small_batches(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
