"""Session helpers: shipping this package to executors, and a session for local runs."""

from __future__ import annotations

import os
import shutil
import tempfile

from pyspark.sql import SparkSession

_SHIPPED: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Hands the package to Python workers that may not have it on their path, once for each application."""
    sc = spark.sparkContext
    if sc.applicationId in _SHIPPED:
        return
    here = os.path.dirname(os.path.abspath(__file__))
    with tempfile.TemporaryDirectory() as folder:
        root = os.path.join(folder, "src")
        shutil.copytree(here, os.path.join(root, os.path.basename(here)), ignore=shutil.ignore_patterns("__pycache__"))
        sc.addPyFile(shutil.make_archive(os.path.join(tempfile.mkdtemp(prefix="fieldlift-"), "fieldlift_package"), "zip", root))
    _SHIPPED.add(sc.applicationId)


def ensure_checkpoint_dir(spark: SparkSession) -> str:
    """The folder for lineage cuts: the one the session names in spark.checkpoint.dir. Where none is named, a temporary folder
    of this machine if it is the only one (local master), else a folder of the shared warehouse."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        named = spark.conf.get("spark.checkpoint.dir", None)
        alone = sc.master == "local" or sc.master.startswith("local[")
        sc.setCheckpointDir(named or (tempfile.mkdtemp(prefix="fieldlift-checkpoint-") if alone else spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/checkpoints"))
    return sc.getCheckpointDir()


def local_session(cores: str = "*", partitions: int = 8) -> SparkSession:
    """A session for tests and benches."""
    conf = {"spark.sql.shuffle.partitions": partitions, "spark.ui.enabled": "false", "spark.ui.showConsoleProgress": "false", "spark.sql.session.timeZone": "UTC", "spark.driver.memory": "8g", "spark.sql.adaptive.enabled": "true"}
    return SparkSession.builder.master(f"local[{cores}]").config(map=conf).getOrCreate()
