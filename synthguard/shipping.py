"""Brings this package to the executors of a session that was started elsewhere."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

_sent: set[str] = set()
#: Rows that go to a Python worker at a time: whole texts may be long, and the session's default of 10,000 rows of them is a lot of memory.
ROWS_AT_A_TIME = "2000"


def ship(spark: SparkSession) -> SparkSession:
    """Adds the package's sources to the session once, so that Python workers can import it wherever they run."""
    if spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch") == "10000":
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", ROWS_AT_A_TIME)
    app = spark.sparkContext.applicationId
    if app not in _sent:
        here = Path(__file__).resolve().parent
        target = Path(tempfile.mkdtemp(prefix="synthguard-src-")) / "synthguard_src.zip"
        atexit.register(shutil.rmtree, target.parent, True)
        with zipfile.ZipFile(target, "w", zipfile.ZIP_DEFLATED) as z:
            for p in sorted(here.rglob("*.py")):
                z.write(p, p.relative_to(here.parent))
        spark.sparkContext.addPyFile(str(target))
        _sent.add(app)
    return spark
