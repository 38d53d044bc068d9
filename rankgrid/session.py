"""What the library needs of a running session: shared storage, code on the workers, tables."""

from __future__ import annotations

import os
import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

#: Used only where the session names no shared folder and everything runs on one machine.
LOCAL_CHECKPOINTS = "file:///tmp/checkpoints/rankgrid"
_ROOT = Path(__file__).resolve().parent.parent
_shipped: set[str] = set()


def _is_local(spark: SparkSession) -> bool:
    return spark.sparkContext.master == "local" or spark.sparkContext.master.startswith("local[")


def shared_dir(spark: SparkSession) -> str:
    """The folder in spark.checkpoint.dir; a local one is set only where that is unset and the master is local."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if found:
        return found.rstrip("/")
    if not _is_local(spark):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    return LOCAL_CHECKPOINTS


#: Shuffle files go at the end of the query that wrote them, not when the driver's JVM comes to collect garbage.
_SHUFFLES_GO = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def written(df: DataFrame, name: str, partition_by: tuple[str, ...] = (), shuffles_go: bool = False, group_bytes: int = 0) -> DataFrame:
    """df as a Parquet table in the shared folder, read again: a cut of the lineage that outlives lost executors.

    shuffles_go: the shuffle files of the write are deleted when it is done; not for a df of which a part is cached.
    group_bytes: size of a row group, of which a task that reads holds up to 4096 rows at once.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    writer = df.write.mode("errorifexists")
    if partition_by:
        writer = writer.partitionBy(*partition_by)
    if group_bytes:
        writer = writer.option("parquet.block.size", group_bytes)
    before = spark.conf.get(_SHUFFLES_GO, None)
    if shuffles_go:
        spark.conf.set(_SHUFFLES_GO, "true")
    try:
        writer.parquet(path)
    finally:
        if shuffles_go:
            spark.conf.unset(_SHUFFLES_GO) if before is None else spark.conf.set(_SHUFFLES_GO, before)
    return spark.read.schema(df.schema).parquet(path)


def forget(table: DataFrame) -> None:
    """Deletes the folder of a table that written made, once nothing reads it any more."""
    spark = table.sparkSession
    files = table.inputFiles()
    if not files:
        return
    folder = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(files[0]).getParent()
    system = folder.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    if folder.getParent() != system.makeQualified(spark.sparkContext._jvm.org.apache.hadoop.fs.Path(shared_dir(spark))):
        raise ValueError(f"not a table of the shared folder: {folder}")
    system.delete(folder, True)


def ship(spark: SparkSession) -> None:
    """Make this package importable in Python workers, wherever the driver found it."""
    app = spark.sparkContext.applicationId
    if app in _shipped:
        return
    _shipped.add(app)
    on_path = str(_ROOT) in os.environ.get("PYTHONPATH", "").split(os.pathsep)
    # the driver's working folder says nothing about workers on other machines
    if on_path or (_is_local(spark) and os.getcwd() == str(_ROOT)):
        return
    target = Path(tempfile.mkdtemp()) / "rankgrid_src.zip"
    with zipfile.ZipFile(target, "w") as out:
        for p in sorted((_ROOT / "rankgrid").rglob("*.py")):
            out.write(p, p.relative_to(_ROOT))
    spark.sparkContext.addPyFile(str(target))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
