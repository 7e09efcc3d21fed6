"""What every entry point does to a session it is given: nothing but tell workers where this package is."""

from __future__ import annotations

import os
import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

_SHIPPED: set[str] = set()


def find_package(spark: SparkSession) -> SparkSession:
    """Let Python workers import this package when the driver found it by ``sys.path`` alone.

    Workers on this machine get its folder; those of a cluster get it as an
    archive, once an application.
    """
    root = Path(__file__).resolve().parent
    home, sc = str(root.parent), spark.sparkContext
    if not sc.master.startswith("local") and sc.applicationId not in _SHIPPED:
        archive = Path(tempfile.mkdtemp()) / f"{root.name}.zip"
        with zipfile.ZipFile(archive, "w") as z:
            for p in sorted(root.rglob("*.py")):
                z.write(p, p.relative_to(root.parent))
        sc.addPyFile(str(archive))
        _SHIPPED.add(sc.applicationId)
    env = sc.environment
    have = env.get("PYTHONPATH", "")
    if home not in have.split(os.pathsep):
        env["PYTHONPATH"] = os.pathsep.join(x for x in (home, have) if x)
    return spark
