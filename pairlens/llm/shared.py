"""Tables, shared scratch tables and shipping of the package to executors."""

from __future__ import annotations

import os
import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

ROOT = Path(__file__).resolve().parents[2]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder named in spark.checkpoint.dir; where it is unset (tests), one of our own."""
    sc = spark.sparkContext
    held = sc._jsc.sc().getCheckpointDir()
    if held.isDefined():
        return held.get()
    named = spark.conf.get("spark.checkpoint.dir", None) or sc.getConf().get("spark.checkpoint.dir")
    if not named and not sc.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
    sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="pairlens-"))
    return sc._jsc.sc().getCheckpointDir().get()


class Scratch:
    """Tables written to the shared folder: they cut lineage and outlive lost executors."""

    def __init__(self, spark: SparkSession, name: str):
        self.spark = spark
        self.base = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex[:12]}"

    def path(self, tag: str) -> str:
        return f"{self.base}/{tag}"

    def keep(self, df: DataFrame, tag: str) -> DataFrame:
        # shuffle files of a table that is written can go at once (a setting of the running session)
        self.spark.conf.set("spark.sql.classic.shuffleDependency.fileCleanup.enabled", "true")
        df.write.mode("overwrite").parquet(self.path(tag))
        return self.spark.read.schema(df.schema).parquet(self.path(tag))

    def drop(self, tag: str) -> None:
        path = self.spark._jvm.org.apache.hadoop.fs.Path(self.path(tag))
        path.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(path, True)


#: Rows and bytes of the batches that Python workers get: long texts must not add up in a worker's memory.
BATCH_ROWS, BATCH_BYTES = 2_000, 8 << 20


def ship(spark: SparkSession) -> None:
    """Gives executors this package, unless their PYTHONPATH has it already, and keeps Arrow batches small (running settings)."""
    sc = spark.sparkContext
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", BATCH_ROWS)
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", BATCH_BYTES)
    if str(ROOT) in os.environ.get("PYTHONPATH", "").split(":") or getattr(sc, "_pairlens_shipped", False):
        return
    out = Path(tempfile.mkdtemp(prefix="pairlens-zip-")) / "pairlens.zip"
    with zipfile.ZipFile(out, "w") as z:
        for f in sorted((ROOT / "pairlens").rglob("*.py")):
            z.write(f, f.relative_to(ROOT))
    sc.addPyFile(str(out))
    sc._pairlens_shipped = True
