"""Shared scratch tables and small memory of built indexes."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

_MEMO: dict[tuple, object] = {}


def scratch(spark: SparkSession, name: str) -> str:
    """A new folder under spark.checkpoint.dir; only a session on one machine (tests) may have none, and gets a temporary one."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        base = tempfile.mkdtemp(prefix="evigraph-")
        spark.sparkContext.setCheckpointDir(base)
    return f"{base.rstrip('/')}/{name}-{uuid.uuid4().hex}"


def written(df: DataFrame, name: str = "step", **options) -> DataFrame:
    """Cut lineage by a table in the shared folder."""
    path = scratch(df.sparkSession, name)
    df.write.options(**options).parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._scratch = path
    return out


def forget(*tables: DataFrame) -> None:
    """Delete written tables that nothing will read again."""
    for df in tables:
        context = df.sparkSession.sparkContext
        path = context._jvm.org.apache.hadoop.fs.Path(df._scratch)
        path.getFileSystem(context._jsc.hadoopConfiguration()).delete(path, True)


@contextmanager
def clean_shuffles(spark: SparkSession, **more: str):
    """Shuffle files go as soon as a table is written, not when the driver happens to collect its garbage. ``more``: other settings to hold meanwhile."""
    held = {"spark.sql.classic.shuffleDependency.fileCleanup.enabled": "true", **more}
    before = {k: spark.conf.get(k, None) for k in held}
    for k, v in held.items():
        spark.conf.set(k, v)
    try:
        yield
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def once(spark: SparkSession, key: tuple, build: Callable[[], object]) -> object:
    """A built index is kept by application and key, as several queries share it."""
    full = (spark.sparkContext.applicationId, *key)
    if full not in _MEMO:
        _MEMO[full] = build()
    return _MEMO[full]


def known(spark: SparkSession, key: tuple) -> bool:
    """Whether ``once`` has it already."""
    return (spark.sparkContext.applicationId, *key) in _MEMO


def token(thing) -> str:
    """A name of an object that no other ever has, for keys of ``once``."""
    return thing.__dict__.setdefault("_token", uuid.uuid4().hex)
