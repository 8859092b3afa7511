"""Session helpers: reliable checkpoints, sizes and partition counts read from the session as given."""

from __future__ import annotations

import atexit
import re
import shutil
import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession


_shipped: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Send the package to the executors' Python, once a session, where it isn't on their path already."""
    sc = spark.sparkContext
    if sc.applicationId in _shipped:
        return
    package = Path(__file__).resolve().parent
    # the driver serves this file to the executors as long as the session lives
    folder = tempfile.mkdtemp(prefix="fieldseg-code-")
    atexit.register(shutil.rmtree, folder, ignore_errors=True)
    archive = f"{folder}/{package.name}-{uuid.uuid4().hex[:8]}.zip"
    with zipfile.ZipFile(archive, "w", zipfile.ZIP_DEFLATED) as z:
        for f in sorted(package.rglob("*.py")):
            z.write(f, f.relative_to(package.parent))
    sc.addPyFile(archive)
    _shipped.add(sc.applicationId)


def shared_dir(spark: SparkSession) -> str:
    """The shared checkpoint folder.  Where the session names none, a local session gets a private one; on a cluster that is an error."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        named = spark.conf.get("spark.checkpoint.dir", None)
        if named is None and not re.fullmatch(r"local(\[.*\])?", sc.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="fieldseg-"))
    return sc.getCheckpointDir()


def cut(df: DataFrame, eager: bool = True) -> DataFrame:
    """Cut lineage with a reliable checkpoint, so a lost executor costs a re-read and not a replay."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager)


def fresh(df: DataFrame) -> DataFrame:
    """`cut`, for loops: the plan is left with a schema alone.

    A checkpoint keeps the constraints that the optimizer found, which grow from round to round of a loop.
    """
    done = cut(df)
    jvm = df.sparkSession._jsparkSession
    return DataFrame(jvm.createDataFrame(done._jdf.javaRDD(), done._jdf.schema()), df.sparkSession)


def shuffle_width(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


class Scratch:
    """A table written to the shared folder as parquet, compact and splittable, until `drop` removes it."""

    def __init__(self, df: DataFrame, name: str = "scratch", partition_by: str | None = None):
        self.spark = df.sparkSession
        self.path = f"{shared_dir(self.spark)}/{name}-{uuid.uuid4().hex}"
        out = df.write.option("compression", "zstd")
        (out.partitionBy(partition_by) if partition_by else out).parquet(self.path)
        self.table = self.spark.read.schema(df.schema).parquet(self.path)

    def drop(self) -> None:
        sc = self.spark.sparkContext
        at = sc._jvm.org.apache.hadoop.fs.Path(self.path)
        at.getFileSystem(sc._jsc.hadoopConfiguration()).delete(at, True)
