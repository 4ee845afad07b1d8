"""Places in the folder that the driver and all executors share."""

from __future__ import annotations

import atexit
import os
import shutil
import tempfile
import uuid

from pyspark.sql import SparkSession

_base: dict[str, str] = {}


def scratch(spark: SparkSession) -> str:
    """A fresh URI prefix below ``spark.checkpoint.dir``. Where that is unset, a local session gets a temporary folder that
    goes when it ends, and a cluster the warehouse."""
    app = spark.sparkContext.applicationId
    if app not in _base:
        base = spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
        if base is None:
            if spark.sparkContext.master.startswith("local[") or spark.sparkContext.master == "local":
                path = tempfile.mkdtemp(prefix="standq-scratch-")
                atexit.register(shutil.rmtree, path, ignore_errors=True)
                base = "file://" + path
            else:
                base = spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_standq_scratch"
            spark.sparkContext.setCheckpointDir(base)
        _base[app] = base if "://" in base or base.startswith("file:") else "file://" + os.path.abspath(base)
    return f"{_base[app].rstrip('/')}/standq-{uuid.uuid4().hex}"
