"""Folders that driver and executors share, and what is built once and read again from there."""

from __future__ import annotations

import hashlib
import tempfile
from collections.abc import Callable

from pyspark.sql import SparkSession

_own: dict[str, str] = {}
_built: dict[tuple[str, str, str], str] = {}


def shared_folder(spark: SparkSession) -> str:
    """``spark.checkpoint.dir``; where it is unset, a temporary folder on one machine, and an error on a cluster."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
    app = spark.sparkContext.applicationId
    if app not in _own:
        _own[app] = "file://" + tempfile.mkdtemp(prefix="vecpath-shared-")
    return _own[app]


def stored(spark: SparkSession, name: str, source: str, build: Callable[[str], None]) -> str:
    """Path of what ``build(path)`` writes, built once for each application, name and source folder."""
    key = (spark.sparkContext.applicationId, name, source)
    if key not in _built:
        mark = hashlib.sha256(source.encode()).hexdigest()[:12]
        path = f"{shared_folder(spark)}/vecpath-stored/{key[0]}/{name}-{mark}"
        build(path)
        _built[key] = path
    return _built[key]
