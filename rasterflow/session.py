"""Sessions: a builder for local use, and sending this package to the workers of a session given to us."""

from __future__ import annotations

import os
import re
import tempfile
import uuid
import zipfile

from pyspark.sql import SparkSession

#: Settings of our own sessions.  A session that is given is used as it is.
SETTINGS = {
    "spark.sql.adaptive.enabled": "true",
    "spark.sql.adaptive.skewJoin.enabled": "true",
    "spark.sql.session.timeZone": "UTC",
    "spark.sql.execution.arrow.pyspark.enabled": "true",
    "spark.ui.enabled": "false",
    "spark.ui.showConsoleProgress": "false",
}


def local_session(cpus: int | str = "*", shuffle_partitions: int = 8, memory: str = "8g", **settings: str) -> SparkSession:
    builder = SparkSession.builder.master(f"local[{cpus}]").appName("rasterflow").config("spark.driver.memory", memory)
    builder = builder.config(map=SETTINGS | {"spark.sql.shuffle.partitions": str(shuffle_partitions)} | settings)
    spark = builder.getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    return ship(spark)


def ship(spark: SparkSession) -> SparkSession:
    """Add this package, as a zip, to what the session's Python workers import (once for each context)."""
    context = spark.sparkContext
    if ship.__dict__.get("done") == context.applicationId:
        return spark
    here = os.path.dirname(os.path.abspath(__file__))
    path = os.path.join(tempfile.mkdtemp(prefix="rasterflow-"), "rasterflow_package.zip")
    with zipfile.ZipFile(path, "w") as z:
        for folder, _, names in os.walk(here):
            for n in names:
                if n.endswith(".py"):
                    full = os.path.join(folder, n)
                    z.write(full, os.path.join("rasterflow", os.path.relpath(full, here)))
    context.addPyFile(path)
    ship.done = context.applicationId
    return spark


def shared_folder(spark: SparkSession, kind: str) -> str:
    """A new path that driver and executors share, in the session's spark.checkpoint.dir.

    Where that is unset, a local session gets a folder of its own; any other is refused.
    """
    base = spark.conf.get("spark.checkpoint.dir", None) or getattr(shared_folder, "own", None)
    if not base:
        if not re.fullmatch(r"local(\[[^\]]*\])?", spark.sparkContext.master):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        base = shared_folder.own = tempfile.mkdtemp(prefix="rasterflow-shared-")
    return f"{base.rstrip('/')}/{kind}-{uuid.uuid4().hex}"
