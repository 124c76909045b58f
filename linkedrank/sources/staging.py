"""Intermediate tables in the folder that driver and executors share.

A staged table cuts lineage like a reliable checkpoint, but is columnar and
compressed, and later scans prune its columns. Executors can be lost at any
time without losing it. ``staging`` deletes what was staged inside it.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

_open: list[list[str]] = []


def shared_folder(spark: SparkSession) -> str:
    """The session's ``spark.checkpoint.dir``; where unset, a folder under the warehouse."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        folder = spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_staged"
    return folder.rstrip("/")


def staged(df: DataFrame, tag: str = "table") -> DataFrame:
    """Write ``df`` once to the shared folder and return a scan of what was written."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/{tag}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    if _open:
        _open[-1].append(path)
    return reread(spark, path, df.schema)


def reread(spark: SparkSession, path: str, schema) -> DataFrame:
    """A scan of a staged table; ``staged_path`` of the result names it."""
    out = spark.read.schema(schema).parquet(path)
    out.staged_path = path
    return out


def drop_staged(spark: SparkSession, paths: list[str]) -> None:
    """Delete staged tables, by whatever file system holds them."""
    jvm = spark._jvm
    for p in paths:
        at = jvm.org.apache.hadoop.fs.Path(p)
        at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


@contextmanager
def staging(spark: SparkSession, keep: list[DataFrame] | None = None):
    """Tables staged inside are deleted at the end, except those put in ``keep``, which the block may fill."""
    kept: list[DataFrame] = keep if keep is not None else []
    _open.append([])
    try:
        yield kept
    finally:
        paths = _open.pop()
        stay = {getattr(d, "staged_path", None) for d in kept}
        drop_staged(spark, [p for p in paths if p not in stay])
        if _open:
            _open[-1].extend(p for p in paths if p in stay)


def together(jobs: list[Callable]) -> list:
    """Results of independent jobs, started side by side so that small ones share the cluster."""
    if len(jobs) < 2:
        return [j() for j in jobs]
    with ThreadPoolExecutor(min(8, len(jobs))) as pool:
        return list(pool.map(lambda j: j(), jobs))
