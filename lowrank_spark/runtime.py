"""Session-level plumbing: shared scratch storage, shipping of the package, size-checked broadcasts."""

from __future__ import annotations

import os
import tempfile
import uuid
import zipfile

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows and bytes up to which a measured side may be broadcast.
BROADCAST_ROWS = 2_000_000
BROADCAST_BYTES = 64 << 20


def ship_package(spark: SparkSession) -> None:
    """Make this package importable in Python workers, on a cluster as in local mode.

    The zip goes through the driver's file server, once per application.
    """
    sc = spark.sparkContext
    if getattr(sc, "_lowrank_shipped", False):
        return
    root = os.path.dirname(os.path.abspath(__file__))
    path = os.path.join(tempfile.mkdtemp(prefix="lowrank_pkg_"), "lowrank_spark_pkg.zip")
    with zipfile.ZipFile(path, "w", zipfile.ZIP_DEFLATED) as z:
        for folder, _, names in os.walk(root):
            for n in sorted(names):
                if n.endswith(".py"):
                    full = os.path.join(folder, n)
                    z.write(full, os.path.join("lowrank_spark", os.path.relpath(full, root)))
    sc.addPyFile(path)
    sc._lowrank_shipped = True


def shared_dir(spark: SparkSession) -> str:
    """The cluster's shared checkpoint folder; a folder of our own only where none is set and all runs in one process."""
    sc = spark.sparkContext
    named = spark.conf.get("spark.checkpoint.dir", None) or sc.getConf().get("spark.checkpoint.dir") or getattr(sc, "_lowrank_shared", None)
    if not named and not (sc.master or "").startswith("local["):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if not named:
        named = "file://" + tempfile.mkdtemp(prefix="lowrank_shared_")
        sc._lowrank_shared = named
    if sc.getCheckpointDir() is None:
        sc.setCheckpointDir(named)
    return named.rstrip("/")


def drop_path(spark: SparkSession, path: str) -> None:
    """Delete a scratch folder through Hadoop's file system (any store Spark can write)."""
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


class Scratch:
    """Tables written to the shared folder to cut lineage; a lost executor loses none of them."""

    def __init__(self, spark: SparkSession, name: str):
        self.spark = spark
        self.base = f"{shared_dir(spark)}/lowrank-{name}-{uuid.uuid4().hex}"
        self.n = 0
        spark.sparkContext.__dict__.setdefault("_lowrank_scratch", set()).add(self.base)

    def keep(self, df: DataFrame, by: list[str] | None = None) -> DataFrame:
        """Write df (in a folder for each value of `by`, few of them), return it as a scan of the written files."""
        self.n += 1
        path = f"{self.base}/t{self.n}"
        schema = df.schema
        (df.write.partitionBy(*by) if by else df.write).parquet(path)
        out = self.spark.read.schema(schema).parquet(path)
        out._scratch_path = path
        return out

    def drop(self, df: DataFrame) -> None:
        path = getattr(df, "_scratch_path", None)
        if path:
            drop_path(self.spark, path)


def clear_scratch(spark: SparkSession) -> int:
    """Deletes every scratch table of this session; results that are still to be read must have been written before."""
    bases = spark.sparkContext.__dict__.pop("_lowrank_scratch", set())
    for b in bases:
        drop_path(spark, b)
    return len(bases)


def maybe_broadcast(df: DataFrame, rows: int, row_bytes: int) -> DataFrame:
    """Hint a broadcast only if the measured size is below the bound; else leave the join to Catalyst."""
    if rows <= BROADCAST_ROWS and rows * row_bytes <= BROADCAST_BYTES:
        return F.broadcast(df)
    return df
