"""What operators need of a session: worker paths, the shared scratch folder, sensible numbers of partitions."""

from __future__ import annotations

import atexit
import os
import shutil
import tempfile
import uuid
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

_OWN: list[str] = []


def local_session(cores: str = "8", **conf: str) -> SparkSession:
    """A session for tests and benches."""
    b = SparkSession.builder.master(f"local[{cores}]").appName("gramdist")
    base = {"spark.sql.shuffle.partitions": cores, "spark.ui.enabled": "false", "spark.sql.session.timeZone": "UTC", "spark.driver.memory": "8g", "spark.ui.showConsoleProgress": "false"}
    spark = b.config(map=base | conf).getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def workers(spark: SparkSession) -> None:
    """Python workers import this package from where the driver did."""
    root = str(Path(__file__).resolve().parents[1])
    env = spark.sparkContext.environment
    if root not in env.get("PYTHONPATH", "").split(os.pathsep):
        env["PYTHONPATH"] = os.pathsep.join(x for x in (root, env.get("PYTHONPATH", "")) if x)


def scratch(spark: SparkSession) -> str:
    """A new path in the folder that spark.checkpoint.dir names. Where that is unset, a temporary folder of this machine
    serves a local session; on a cluster, whose machines don't share it, that is an error."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = tempfile.mkdtemp(prefix="gramdist-")
        spark.sparkContext.setCheckpointDir(base)
        _OWN.append(base)
    path = f"{base.rstrip('/')}/gd-{uuid.uuid4().hex}"
    if path.startswith(("/", "file:")):
        _OWN.append(path.removeprefix("file://"))
    return path


def own(path: str) -> None:
    """Has a temporary folder of this machine deleted at the end."""
    _OWN.append(path)


@atexit.register
def _clean() -> None:
    for p in _OWN:
        shutil.rmtree(p, ignore_errors=True)


def kept(df: DataFrame) -> DataFrame:
    """Write a table to the shared folder and read it: cuts the lineage and survives lost executors."""
    path = scratch(df.sparkSession)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def parts(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))
