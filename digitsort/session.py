"""Session helpers: shipping this package to executors and shared scratch tables.

Nothing here changes a setting of the session.  Scratch tables live under the
folder that ``spark.checkpoint.dir`` names; where that is unset, under the warehouse
folder, which a cluster shares, or for a local master under ``/tmp/checkpoints``.
"""

from __future__ import annotations

import atexit
import os
import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

_PACKAGE = Path(__file__).resolve().parent
_shipped: dict[str, str] = {}
_scratch: dict[str, str] = {}


def ship_package(spark: SparkSession) -> None:
    """Make this package importable in Python workers, once per application."""
    app = spark.sparkContext.applicationId
    if app in _shipped:
        return
    target = os.path.join(tempfile.mkdtemp(prefix="digitsort-"), f"{_PACKAGE.name}.zip")
    with zipfile.ZipFile(target, "w", zipfile.ZIP_DEFLATED) as z:
        for p in sorted(x for x in _PACKAGE.rglob("*") if x.suffix in (".py", ".json")):
            z.write(p, p.relative_to(_PACKAGE.parent))
    spark.sparkContext.addPyFile(target)
    _shipped[app] = target


def scratch_dir(spark: SparkSession) -> str:
    """A folder of this application that driver and executors share."""
    app = spark.sparkContext.applicationId
    if app not in _scratch:
        local = spark.sparkContext.master.split("[")[0] == "local"
        root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir() or (f"/tmp/checkpoints/{app}" if local else spark.conf.get("spark.sql.warehouse.dir"))
        _scratch[app] = f"{root.rstrip('/')}/digitsort-{uuid.uuid4().hex[:12]}"
        atexit.register(_remove, spark, _scratch[app])
    return _scratch[app]


def _remove(spark: SparkSession, path: str) -> None:
    try:
        jvm = spark.sparkContext._jvm
        target = jvm.org.apache.hadoop.fs.Path(path)
        target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)
    except Exception:  # noqa: BLE001  the session has ended already
        pass


def written(df: DataFrame, name: str, compression: str = "zstd") -> DataFrame:
    """Write ``df`` to a fresh shared Parquet table and return a scan of it.

    This cuts lineage: a lost executor re-reads files instead of recomputing,
    and later joins see plain scans, so that AQE can split skewed partitions.
    """
    spark = df.sparkSession
    path = f"{scratch_dir(spark)}/{name}-{uuid.uuid4().hex[:8]}"
    df.write.option("compression", compression).parquet(path)
    scan = spark.read.schema(df.schema).parquet(path)
    scan._scratch = path
    return scan


def release(*tables: DataFrame) -> None:
    """Delete scratch tables that nothing unfinished reads any more; other frames are left alone."""
    for df in tables:
        if path := df.__dict__.pop("_scratch", None):
            _remove(df.sparkSession, path)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
