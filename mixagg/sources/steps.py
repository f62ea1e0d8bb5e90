"""Steps that several others read, written once to the folder that all executors share."""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import DataFrame

_folders: dict[str, str] = {}


def kept(df: DataFrame) -> DataFrame:
    """``df`` written as a table below ``spark.checkpoint.dir`` and read back; deleted when the driver ends.

    Where that is unset the context's checkpoint folder is taken, with a local master a temporary one; else this raises.
    """
    sc = df.sparkSession.sparkContext
    if sc.applicationId not in _folders:
        known = sc._jsc.sc().getCheckpointDir()
        base = sc.getConf().get("spark.checkpoint.dir") or (known.get() if known.isDefined() else None)
        if base is None:
            if not sc.master.startswith("local") or sc.master.startswith("local-cluster"):
                raise ValueError("spark.checkpoint.dir names no folder that all executors share")
            base = tempfile.mkdtemp(prefix="ckpt-")
        _folders[sc.applicationId] = folder = f"{base.rstrip('/')}/factors-{uuid.uuid4().hex}"
        where = sc._jvm.org.apache.hadoop.fs.Path(folder)
        atexit.register(lambda: sc._jsc and where.getFileSystem(sc._jsc.hadoopConfiguration()).delete(where, True))
    path = f"{_folders[sc.applicationId]}/{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
