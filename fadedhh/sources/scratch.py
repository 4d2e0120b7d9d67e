"""A place for intermediate files that every executor sees."""

from __future__ import annotations

import re
import tempfile
import uuid

from pyspark.sql import SparkSession


def shared_root(spark: SparkSession) -> str:
    """The folder that the driver and all executors share: the session's checkpoint folder. Only a session whose tasks run
    in the driver's own process may do without one; it gets a temporary folder."""
    root = spark.conf.get("spark.checkpoint.dir", None) or getattr(spark, "_own_scratch", None)
    if not root:
        if not re.match(r"local($|\[)", spark.sparkContext.master):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        root = spark._own_scratch = tempfile.mkdtemp(prefix="scratch-")
    return root.rstrip("/")


def scratch_path(spark: SparkSession, name: str) -> str:
    """A fresh path under the shared folder."""
    return f"{shared_root(spark)}/{name}-{uuid.uuid4().hex}"
