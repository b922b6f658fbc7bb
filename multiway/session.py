"""Session presets, and shipping of this package to executors that don't have it."""

from __future__ import annotations

import tempfile
import zipfile
from collections.abc import Iterator
from contextlib import contextmanager
from pathlib import Path

from pyspark.sql import SparkSession

#: Settings that hold at run time; nothing here is fixed at start.
PRESETS = {"spark.sql.adaptive.enabled": "true", "spark.sql.adaptive.skewJoin.enabled": "true", "spark.sql.session.timeZone": "UTC"}


def local_session(cores: int = 8, partitions: int = 8, memory: str = "8g") -> SparkSession:
    """A session for tests and the bench."""
    builder = SparkSession.builder.master(f"local[{cores}]").appName("multiway")
    fixed = {"spark.sql.shuffle.partitions": str(partitions), "spark.driver.memory": memory, "spark.ui.enabled": "false", "spark.ui.showConsoleProgress": "false"}
    session = builder.config(map=fixed | PRESETS).getOrCreate()
    session.sparkContext.setLogLevel("ERROR")
    return session


@contextmanager
def setting(spark: SparkSession, key: str, value: str) -> Iterator[None]:
    """A setting for some actions, and then what it was."""
    before = spark.conf.get(key) if key in spark.conf.getAll else None
    spark.conf.set(key, value)
    try:
        yield
    finally:
        spark.conf.unset(key) if before is None else spark.conf.set(key, before)


def ship(spark: SparkSession) -> SparkSession:
    """Send this package to the executors, once for each application; kernels are then importable anywhere."""
    sc = spark.sparkContext
    if any(name.endswith("multiway_package.zip") for name in sc.listFiles):
        return spark
    root = Path(__file__).resolve().parent
    path = Path(tempfile.mkdtemp(prefix="multiway-")) / "multiway_package.zip"
    with zipfile.ZipFile(path, "w") as z:
        for p in sorted(root.rglob("*.py")):
            z.write(p, f"{root.name}/{p.relative_to(root)}")
    sc.addPyFile(str(path))
    return spark
