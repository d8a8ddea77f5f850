"""Session helpers: a local session for tests, and shipping this package to workers that cannot import it."""

from __future__ import annotations

import os
import sys
import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

ROOT = Path(__file__).resolve().parent.parent


def local_session(cores: int = 8, shuffle_partitions: int = 8) -> SparkSession:
    conf = {"spark.sql.shuffle.partitions": shuffle_partitions, "spark.sql.session.timeZone": "UTC", "spark.ui.enabled": "false", "spark.driver.memory": "6g", "spark.ui.showConsoleProgress": "false"}
    spark = SparkSession.builder.master(f"local[{cores}]").config(map=conf).getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def ship_code(spark: SparkSession) -> None:
    """Make the package importable by Python workers. Where they inherit it (PYTHONPATH or the working directory) there
    is nothing to do; else the package goes to all executors as a zip file, once a session."""
    paths = [Path(p or ".").resolve() for p in os.environ.get("PYTHONPATH", "").split(os.pathsep)]
    if ROOT in paths or Path.cwd().resolve() == ROOT or getattr(spark.sparkContext, "_waysite_shipped", False):
        return
    packed = Path(tempfile.mkdtemp(prefix="waysite-code-")) / "waysite_code.zip"
    with zipfile.ZipFile(packed, "w") as z:
        for p in sorted((ROOT / "waysite").rglob("*.py")):
            z.write(p, p.relative_to(ROOT))
    before = list(sys.path)
    spark.sparkContext.addPyFile(str(packed))
    sys.path[:] = before
    spark.sparkContext._waysite_shipped = True
