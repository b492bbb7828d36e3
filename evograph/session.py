"""Sessions, and getting this package to the Python workers."""

from __future__ import annotations

import os
import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

ROOT = Path(__file__).resolve().parent.parent
_SHIPPED: set[str] = set()
_OWN: dict[str, str] = {}


def local_session(name: str = "evograph", cpus: str = "8") -> SparkSession:
    """A session for tests and benches on one machine."""
    return (
        SparkSession.builder.master(f"local[{cpus}]")
        .appName(name)
        .config("spark.sql.shuffle.partitions", "8")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.sql.adaptive.enabled", "true")
        .config("spark.ui.enabled", "false")
        .config("spark.driver.memory", "6g")
        .getOrCreate()
    )


def work_dir(spark: SparkSession) -> str:
    """A folder that the driver and all executors share: the cluster's, or one of our own where none is named."""
    named = spark.sparkContext.getConf().get("spark.checkpoint.dir") or _OWN.get("dir")
    if not named:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        named = _OWN["dir"] = tempfile.mkdtemp(prefix="evograph-work-")
    return named.rstrip("/")


def ensure_checkpoints(spark: SparkSession) -> None:
    """Reliable checkpoints in the shared folder, unless the session has set theirs."""
    if not spark.sparkContext._jsc.sc().getCheckpointDir().isDefined():
        spark.sparkContext.setCheckpointDir(work_dir(spark))


def ship(spark: SparkSession) -> None:
    """Let workers import this package; needed where their path does not have it already."""
    paths = os.environ.get("PYTHONPATH", "").split(os.pathsep)
    if str(ROOT) in paths or spark.sparkContext.applicationId in _SHIPPED:
        return
    _SHIPPED.add(spark.sparkContext.applicationId)
    target = Path(tempfile.mkdtemp(prefix="evograph-")) / "evograph_package.zip"
    with zipfile.ZipFile(target, "w") as z:
        for f in sorted((ROOT / "evograph").rglob("*.py")):
            z.write(f, f.relative_to(ROOT))
    spark.sparkContext.addPyFile(str(target))
