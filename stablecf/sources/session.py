"""What a session needs before Python workers can run this package's code."""

from __future__ import annotations

import os
import tempfile
import threading
import zipfile

from pyspark.sql import SparkSession

_shipped: dict[str, bool] = {}
_shipping = threading.Lock()


def ship(spark: SparkSession) -> None:
    """Sends this package to the executors' Python, once per application, also when several threads ask for it at once."""
    with _shipping:
        _ship(spark)


def _ship(spark: SparkSession) -> None:
    app = spark.sparkContext.applicationId
    if app in _shipped:
        return
    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    out = os.path.join(tempfile.mkdtemp(prefix="stablecf-code-"), "stablecf_code.zip")
    with zipfile.ZipFile(out, "w") as z:
        for d, _, names in os.walk(root):
            for n in names:
                if n.endswith((".py", ".txt")):
                    full = os.path.join(d, n)
                    z.write(full, os.path.join("stablecf", os.path.relpath(full, root)))
    spark.sparkContext.addPyFile(out)
    _shipped[app] = True


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share; a temporary one only where none is named and all run on one machine."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named
    found = spark.sparkContext._jsc.sc().getCheckpointDir()
    if found.isDefined():
        return found.get()
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    return tempfile.mkdtemp(prefix="stablecf-shared-")
