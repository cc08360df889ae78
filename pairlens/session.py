"""Session helpers: shared checkpoint folder, lineage cuts."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame, SparkSession


def checkpointed(df: DataFrame) -> DataFrame:
    """df written to the folder in spark.checkpoint.dir (one of our own only where it is unset, as in tests)."""
    spark: SparkSession = df.sparkSession
    sc = spark.sparkContext
    if not sc._jsc.sc().getCheckpointDir().isDefined():
        named = spark.conf.get("spark.checkpoint.dir", None) or sc.getConf().get("spark.checkpoint.dir")
        if not named and not sc.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="pairlens-"))
    return df.checkpoint()


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def ship(spark: SparkSession) -> None:
    """Gives executors this package, unless their PYTHONPATH has it already."""
    import os
    import zipfile
    from pathlib import Path

    root, sc = Path(__file__).resolve().parents[1], spark.sparkContext
    if str(root) in os.environ.get("PYTHONPATH", "").split(":") or getattr(sc, "_pairlens_shipped", False):
        return
    out = Path(tempfile.mkdtemp(prefix="pairlens-zip-")) / "pairlens.zip"
    with zipfile.ZipFile(out, "w") as z:
        for f in sorted((root / "pairlens").rglob("*.py")):
            z.write(f, f.relative_to(root))
    sc.addPyFile(str(out))
    sc._pairlens_shipped = True
