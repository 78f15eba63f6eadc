"""Things every plan needs from the running session: shipped code, a shared folder, written tables.

Nothing here changes a setting that is fixed at start; the session is used as given.
"""

from __future__ import annotations

import atexit
import io
import os
import shutil
import tempfile
import uuid
import zipfile
from collections.abc import Callable
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

_shipped: set[str] = set()
_own_dirs: dict[str, str] = {}
_written: dict[str, set[str]] = {}
_once: dict[tuple, DataFrame] = {}


def ship(spark: SparkSession) -> None:
    """Send this package to the Python workers once for each application, whatever their import path is."""
    sc = spark.sparkContext
    if sc.applicationId in _shipped:
        return
    root = Path(__file__).resolve().parent
    out = io.BytesIO()
    with zipfile.ZipFile(out, "w") as z:
        for p in sorted(root.rglob("*.py")):
            z.write(p, f"{root.name}/{p.relative_to(root)}")
    at = Path(tempfile.mkdtemp(prefix="divmerge-code-")) / "divmerge_code.zip"
    at.write_bytes(out.getvalue())
    sc.addPyFile(str(at))  # the driver serves the file; executors fetch it
    _shipped.add(sc.applicationId)


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``; where that is unset, the warehouse, or one of our own if all tasks run in this process."""
    sc = spark.sparkContext
    given = spark.conf.get("spark.checkpoint.dir", None) or sc.getConf().get("spark.checkpoint.dir")
    if given:
        return given.rstrip("/")
    if not sc.master.startswith("local"):
        return spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_scratch"
    if sc.applicationId not in _own_dirs:
        _own_dirs[sc.applicationId] = tempfile.mkdtemp(prefix="divmerge-shared-")
    return "file://" + os.path.abspath(_own_dirs[sc.applicationId])


@atexit.register
def _remove_own_dirs() -> None:
    for path in _own_dirs.values():
        shutil.rmtree(path, ignore_errors=True)


def scratch(spark: SparkSession, name: str) -> str:
    path = f"{shared_dir(spark)}/divmerge/{name}-{uuid.uuid4().hex}"
    _written.setdefault(spark.sparkContext.applicationId, set()).add(path)
    return path


def _files(spark: SparkSession, path: str):
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark._jsc.hadoopConfiguration()), p


def _delete(spark: SparkSession, path: str) -> None:
    fs, p = _files(spark, path)
    fs.delete(p, True)
    _written.get(spark.sparkContext.applicationId, set()).discard(path)


def materialize(df: DataFrame, name: str = "t", compression: str = "snappy") -> DataFrame:
    """Write ``df`` to the shared folder and read it back: cuts the lineage and outlives any executor."""
    spark = df.sparkSession
    path = scratch(spark, name)
    df.write.option("compression", compression).parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._written_at = path  # type: ignore[attr-defined]
    return out


def discard(df: DataFrame) -> None:
    """Delete a table made by :func:`materialize` that no later plan reads."""
    path = getattr(df, "_written_at", None)
    if path:
        _delete(df.sparkSession, path)


def cleanup(spark: SparkSession) -> None:
    """Delete every table that this application has written and that :func:`once` does not keep; call it when the results have been read."""
    kept = {getattr(df, "_written_at", None) for df in _once.values()}
    for path in _written.get(spark.sparkContext.applicationId, set()) - kept:
        _delete(spark, path)


def once(spark: SparkSession, source: str, name: str, make: Callable[[], DataFrame]) -> DataFrame:
    """A written table derived from the file or folder ``source``, made once in an application for each state of the source."""
    fs, p = _files(spark, source)
    state = tuple(sorted((f.getPath().toString(), f.getLen(), f.getModificationTime()) for f in fs.listStatus(p)))
    key = (spark.sparkContext.applicationId, name, source, state)
    if key in _once:
        at, path = _files(spark, _once[key]._written_at)  # type: ignore[attr-defined]
        if at.exists(path):
            return spark.read.schema(_once[key].schema).parquet(_once[key]._written_at)  # type: ignore[attr-defined]
    written = _written.setdefault(spark.sparkContext.applicationId, set())
    before = set(written)
    _once[key] = materialize(make(), name)
    for path in written - before - {getattr(df, "_written_at", None) for df in _once.values()}:  # what only ``make`` reads
        _delete(spark, path)
    return _once[key]


def cores(spark: SparkSession) -> int:
    """In how many parts work is dealt at least: the session's shuffle partitions or the cluster's cores."""
    return max(int(spark.conf.get("spark.sql.shuffle.partitions")), spark.sparkContext.defaultParallelism)


def spread(df: DataFrame) -> DataFrame:
    """Deal the rows out where a scan has fewer partitions than the cluster has cores (small tables in one file); else as it is."""
    sc = df.sparkSession.sparkContext
    return df.repartition(sc.defaultParallelism) if df.rdd.getNumPartitions() < sc.defaultParallelism else df


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
