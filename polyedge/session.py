"""Runtime settings that the plans of this engine rely on; none is fixed at start."""

from __future__ import annotations

import ctypes
import os
import tempfile
import zipfile
from functools import cache
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

RUNTIME = {
    "spark.sql.adaptive.enabled": "true",
    # joins on (tick, edge) reuse a partitioning by tick
    "spark.sql.requireAllClusterKeysForCoPartition": "false",
    "spark.sql.session.timeZone": "UTC",
}
_shipped: set[str] = set()


def configure(spark: SparkSession) -> SparkSession:
    for k, v in RUNTIME.items():
        if spark.conf.get(k, None) != v:
            spark.conf.set(k, v)
    return spark


def ship(spark: SparkSession) -> None:
    """Make this package importable in the Python workers, once per application."""
    app = spark.sparkContext.applicationId
    if app in _shipped:
        return
    root = Path(__file__).resolve().parent
    target = os.path.join(tempfile.mkdtemp(), f"{root.name}_engine.zip")
    with zipfile.ZipFile(target, "w", zipfile.ZIP_DEFLATED) as z:
        for p in sorted(root.rglob("*.py")):
            z.write(p, p.relative_to(root.parent))
    spark.sparkContext.addPyFile(target)
    _shipped.add(app)


@cache
def keep_freed(most: int = 32 << 20) -> None:
    """Have this worker use freed arrays again: a training step makes and frees hundreds of a size that the
    C library otherwise gives back to the machine, and takes anew page by page."""
    try:
        c = ctypes.CDLL(None)
        c.mallopt(-3, most)  # M_MMAP_THRESHOLD
        c.mallopt(-1, 2 * most)  # M_TRIM_THRESHOLD
    except (AttributeError, OSError):  # another C library
        pass


def checkpoint_dir(spark: SparkSession) -> str:
    """The shared folder the cluster names; one of our own only where none is set and all run on one machine."""
    sc = spark.sparkContext
    held = sc._jsc.sc().getCheckpointDir()
    where = spark.conf.get("spark.checkpoint.dir", None) or (held.get() if held.isDefined() else None)
    if where is None:
        if not sc.master.startswith("local["):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        where = tempfile.mkdtemp(prefix="shared")
    if not held.isDefined():
        sc.setCheckpointDir(where)
    return where


def materialise(df: DataFrame) -> DataFrame:
    """Compute once into the shared folder and cut the lineage."""
    checkpoint_dir(df.sparkSession)
    return df.checkpoint(eager=True)
