"""Small session helpers shared by the operators: tables, and steps kept in the shared checkpoint folder."""

from __future__ import annotations

import atexit
import gc
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

_folders: dict[str, str] = {}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """A folder of this application's own in the one that the cluster names in ``spark.checkpoint.dir``.

    Where that is unset the context's checkpoint folder is taken; with a local master a temporary one will do, on a
    cluster it would lie on one machine's disk, so that raises.  The folder is deleted when the driver ends.
    """
    sc = spark.sparkContext
    if sc.applicationId not in _folders:
        known = sc._jsc.sc().getCheckpointDir()
        base = sc.getConf().get("spark.checkpoint.dir") or (known.get() if known.isDefined() else None)
        if base is None:
            if not sc.master.startswith("local") or sc.master.startswith("local-cluster"):
                raise ValueError("spark.checkpoint.dir names no folder that all executors share")
            base = tempfile.mkdtemp(prefix="ckpt-")
        _folders[sc.applicationId] = folder = f"{base.rstrip('/')}/steps-{uuid.uuid4().hex}"
        atexit.register(lambda: sc._jsc and _delete(sc, folder))
    return _folders[sc.applicationId]


def _delete(sc, path: str) -> None:
    where = sc._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(sc._jsc.hadoopConfiguration()).delete(where, True)


def saved(df: DataFrame) -> DataFrame:
    """``df`` written once as a compressed table in the shared folder and read back, so its lineage ends there.

    Any executor can read it after others were lost; shuffle files of steps before it are released.
    """
    path = f"{shared_folder(df.sparkSession)}/{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    release(df.sparkSession)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._step = path
    for made in _watched:
        made.append(out)
    return out


def discard(*steps: DataFrame) -> None:
    """Deletes saved tables that nothing will read any more."""
    for step in steps:
        _delete(step.sparkSession.sparkContext, step._step)


_watched: list[list[DataFrame]] = []


@contextmanager
def steps_made() -> Iterator[list[DataFrame]]:
    """Collects the tables that are saved within."""
    made: list[DataFrame] = []
    _watched.append(made)
    try:
        yield made
    finally:
        _watched.remove(made)


def release(spark: SparkSession) -> None:
    """Lets Spark clean the shuffle files of finished steps now, not when the driver's heap next fills up."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()
