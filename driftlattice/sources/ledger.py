"""Written tables: the append-only ledger of counts and lattices, and cut lineage."""

from __future__ import annotations

import atexit
import gc
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """The folder all executors share: spark.checkpoint.dir, or a folder of our own where that is unset and Spark itself runs on one machine.

    On a cluster without that setting this raises: any folder that we could make up is local to a machine.
    """
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if named:
        return named.rstrip("/")
    if spark.sparkContext.master.startswith("local"):
        folder = tempfile.mkdtemp(prefix="driftlattice-")
        atexit.register(shutil.rmtree, folder, True)
        spark.sparkContext.setCheckpointDir(f"file://{folder}")
        return f"file://{folder}"
    raise ValueError("set spark.checkpoint.dir to a folder that all executors share")


def written(df: DataFrame, partition: str | None = None) -> DataFrame:
    """`df` as a Parquet table in the shared folder: cuts the lineage and survives lost executors."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/table-{uuid.uuid4().hex}"
    writer = df.write
    (writer.partitionBy(partition) if partition else writer).parquet(path)
    gc.collect()
    spark.sparkContext._jvm.System.gc()  # lets Spark's cleaner drop the shuffle files of what is now written
    out = spark.read.schema(df.schema).parquet(path)
    out.ledger_path = path
    return out


def dropped(table: DataFrame) -> None:
    """Deletes a written table that nothing will read again, and the shuffle files of finished queries."""
    spark, jvm = table.sparkSession, table.sparkSession.sparkContext._jvm
    path = jvm.org.apache.hadoop.fs.Path(table.ledger_path)
    path.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()).delete(path, True)
    gc.collect()
    jvm.System.gc()


def write_batch(df: DataFrame, path: str) -> None:
    """Append or replace whole batches of a ledger (idempotent: only the batches in `df` are overwritten)."""
    df.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("batch_id").parquet(path)


_KEPT: dict[tuple, object] = {}


def folder_state(spark: SparkSession, folder: str) -> int:
    """A digest of the names, sizes and times of what lies in a folder and one level below."""
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(folder)
    fs = path.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf())
    found = []
    for one in fs.listStatus(path):
        inner = fs.listStatus(one.getPath()) if one.isDirectory() else [one]
        found += [(x.getPath().toString(), x.getLen(), x.getModificationTime()) for x in inner]
    return hash(tuple(sorted(found)))


def kept(spark: SparkSession, sf_dir: str, name: str, build):
    """What build() returns, made once per Spark application and state of the input folder."""
    key = (spark.sparkContext.applicationId, sf_dir, folder_state(spark, sf_dir), name)
    if key not in _KEPT:
        _KEPT[key] = build()
    return _KEPT[key]


def once(spark: SparkSession, sf_dir: str, name: str, build) -> DataFrame:
    """A ledger table, computed once and then read from Parquet."""
    return kept(spark, sf_dir, name, lambda: written(build()))
