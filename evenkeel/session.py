"""Sessions: a builder for scripts and tests, and shipping of this package to workers."""

from __future__ import annotations

import importlib.util
import os
import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

_shipped: set[str] = set()


def build(cores: int | str = "*", shuffle_partitions: int = 8, **more: str) -> SparkSession:
    """A local session with the settings that results rely on (UTC, AQE, Arrow)."""
    conf = {
        "spark.sql.shuffle.partitions": str(shuffle_partitions),
        "spark.sql.adaptive.enabled": "true",
        "spark.sql.session.timeZone": "UTC",
        "spark.sql.execution.arrow.pyspark.enabled": "true",
        "spark.ui.enabled": "false",
        "spark.ui.showConsoleProgress": "false",
        "spark.driver.memory": "8g",
    } | more
    builder = SparkSession.builder.master(f"local[{cores}]").appName("evenkeel")
    return builder.config(map=conf).getOrCreate()


def ship(spark: SparkSession) -> SparkSession:
    """Make this package importable in the Python workers of a running session.

    A zip of the package goes out with ``addPyFile`` once for each application.  It is
    written to ``spark.checkpoint.dir`` where the session has one.
    """
    context = spark.sparkContext
    if context.applicationId in _shipped:
        return spark
    package = Path(importlib.util.find_spec("evenkeel").origin).parent
    shared = (context.getConf().get("spark.checkpoint.dir") or "").removeprefix("file://")
    if shared.startswith("/"):
        folder = os.path.join(shared, f"evenkeel-code-{uuid.uuid4().hex}")
        os.makedirs(folder)
    else:  # none is set, or it is not a file system that the driver sees
        folder = tempfile.mkdtemp(prefix="evenkeel-code-")
    path = os.path.join(folder, "evenkeel_code.zip")
    with zipfile.ZipFile(path, "w") as z:
        for p in sorted(package.rglob("*.py")):
            z.write(p, str(p.relative_to(package.parent)))
    context.addPyFile(path)
    _shipped.add(context.applicationId)
    return spark
