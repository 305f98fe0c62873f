"""Getting the package to the executors' Python."""

from __future__ import annotations

import os
import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

ROOT = Path(__file__).resolve().parent
_SHIPPED: set[str] = set()


def ship_package(spark: SparkSession) -> None:
    """Send this package with the application, once, unless workers find it by PYTHONPATH or in their working folder."""
    home = str(ROOT.parent)
    known = [os.path.realpath(p) for p in os.environ.get("PYTHONPATH", "").split(os.pathsep) if p]
    app = spark.sparkContext.applicationId
    if app in _SHIPPED or home in known or (os.path.realpath(os.getcwd()) == home and spark.sparkContext.master.startswith("local[")):
        return
    target = Path(tempfile.mkdtemp(prefix="raydescent-package-")) / "raydescent.zip"
    with zipfile.ZipFile(target, "w") as z:
        for f in ROOT.rglob("*.py"):
            z.write(f, f.relative_to(ROOT.parent))
    spark.sparkContext.addPyFile(str(target))
    _SHIPPED.add(app)


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir. Only where it is unset and all run on one machine
    (tests) a local one is made; on a cluster that is an error, as executors would not see each other's tables."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        root = spark.sparkContext.getCheckpointDir()
    if not root and spark.sparkContext.master != "local" and not spark.sparkContext.master.startswith("local["):
        raise RuntimeError("spark.checkpoint.dir must name a folder that the driver and all executors share")
    if not root:
        root = "file://" + tempfile.mkdtemp(prefix="raydescent-")
        spark.sparkContext.setCheckpointDir(root)
    return root.rstrip("/")
