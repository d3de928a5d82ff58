"""Session helpers: settings that may change at run time, and a scratch folder that executors share."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import SparkSession

#: Settings for series work, all changeable in a running session: keys are evenly spread by construction, so joins on
#: part of them need no new shuffle.
RUNTIME = {"spark.sql.session.timeZone": "UTC", "spark.sql.adaptive.enabled": "true", "spark.sql.requireAllClusterKeysForCoPartition": "false"}


def tune(spark: SparkSession) -> SparkSession:
    for k, v in RUNTIME.items():
        spark.conf.set(k, v)
    return spark


def scratch(spark: SparkSession, label: str) -> str:
    """A new folder below spark.checkpoint.dir, which all executors share; on one machine a temporary one."""
    top = spark.conf.get("spark.checkpoint.dir", None)
    if not top:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        top = tempfile.mkdtemp(prefix="calseries-")
    return f"{top.rstrip('/')}/{label}-{uuid.uuid4().hex}"
