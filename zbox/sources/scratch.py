"""Places for tables that a query writes and reads again."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import SparkSession

_own: list[str] = []


def scratch(spark: SparkSession, name: str) -> str:
    """A new path below the folder that all executors share (spark.checkpoint.dir); where the session
    names none, below a temporary one."""
    shared = spark.conf.get("spark.checkpoint.dir", None)
    if not shared:
        if not _own:
            _own.append(tempfile.mkdtemp(prefix="zbox-"))
            atexit.register(shutil.rmtree, _own[0], ignore_errors=True)
        shared = f"file://{_own[0]}"
    return f"{shared.rstrip('/')}/zbox-{name}-{uuid.uuid4().hex[:12]}"
