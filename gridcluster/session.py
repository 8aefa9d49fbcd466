"""Session helpers: shipping this package to executors, shared scratch tables."""

from __future__ import annotations

import atexit
import contextlib
import gc
import io
import tempfile
import uuid
import zipfile
from collections.abc import Iterator
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

_SHIPPED: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Makes this package importable in the executors' Python workers, once per application."""
    sc = spark.sparkContext
    if sc.applicationId in _SHIPPED:
        return
    root = Path(__file__).resolve().parent
    buf = io.BytesIO()
    with zipfile.ZipFile(buf, "w", zipfile.ZIP_DEFLATED) as z:
        for p in sorted(root.rglob("*.py")):
            z.write(p, f"{root.name}/{p.relative_to(root)}")
    path = Path(tempfile.mkdtemp()) / f"{root.name}_{uuid.uuid4().hex[:8]}.zip"
    path.write_bytes(buf.getvalue())
    sc.addPyFile(str(path))
    _SHIPPED.add(sc.applicationId)


def shared_dir(spark: SparkSession) -> str:
    """The folder that the driver and all executors share: the cluster's spark.checkpoint.dir.

    Where none is named, a folder of this machine will do for a local master, as in tests; elsewhere each
    executor would write to its own disk, so that is refused.
    """
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named and not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    return (named or "file:///tmp/checkpoints").rstrip("/")


def checkpoint(spark: SparkSession, df: DataFrame) -> DataFrame:
    """Cuts the lineage through a written table in the shared folder."""
    return materialise(spark, df, "step")


def materialise(spark: SparkSession, df: DataFrame, name: str) -> DataFrame:
    """Writes df to the shared folder and reads it back: recomputation after a lost executor starts there.

    The table lies there until `forget`, or until the driver's process ends.
    """
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    atexit.register(discard, spark, path)
    out = spark.read.schema(df.schema).parquet(path)
    _WRITTEN[id(out)] = (out, path)
    return out


#: Written tables by the identity of the data frame that reads them.
_WRITTEN: dict[int, tuple[DataFrame, str]] = {}


def forget(spark: SparkSession, *tables: DataFrame) -> None:
    """Deletes written tables that nothing reads any more: the earlier rounds of an iteration."""
    for t in tables:
        known = _WRITTEN.pop(id(t), None)
        if known:
            discard(spark, known[1])


@contextlib.contextmanager
def passing(spark: SparkSession) -> Iterator[None]:
    """For one of many runs whose results are with the driver: tables written inside are deleted at its end, and what its
    exchanges left on the executors' disks."""
    before = set(_WRITTEN)
    try:
        yield
    finally:
        forget(spark, *(t for key, (t, _) in list(_WRITTEN.items()) if key not in before))
        gc.collect()
        spark.sparkContext._jvm.System.gc()  # exchanges are deleted when the JVM finds that nothing refers to them


def discard(spark: SparkSession, path: str) -> None:
    """Deletes a table or folder of the shared folder."""
    try:
        jvm = spark.sparkContext._jvm
        where = jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
    except Exception:  # noqa: BLE001 - the session may have ended, the folder may be gone
        pass
