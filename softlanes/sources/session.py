"""What every session needs before Python functions run on executors, and where tables are kept."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

_SHIPPED: set[str] = set()


def ship_package(spark: SparkSession) -> None:
    """Let executors import this package wherever the driver found it; once for each application."""
    context = spark.sparkContext
    if context.applicationId in _SHIPPED:
        return
    home = Path(__file__).resolve().parent.parent
    archive = Path(tempfile.mkdtemp(prefix="lanes-package-")) / f"{home.name}-{uuid.uuid4().hex[:8]}.zip"
    with zipfile.ZipFile(archive, "w") as z:
        for source in sorted(home.rglob("*.py")):
            z.write(source, source.relative_to(home.parent))
    context.addPyFile(str(archive))
    _SHIPPED.add(context.applicationId)


def shared_folder(spark: SparkSession) -> str:
    """Folder that all executors see: ``spark.checkpoint.dir`` of the session.

    Only on one machine (``local[...]``) is a temporary folder set where the session has none; on a cluster it would be
    a folder that the other machines do not see, so there it is an error.
    """
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        master = spark.sparkContext.master
        if master != "local" and not master.startswith("local["):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        folder = tempfile.mkdtemp(prefix="lanes-checkpoint-")
        atexit.register(shutil.rmtree, folder, ignore_errors=True)
        spark.conf.set("spark.checkpoint.dir", folder)
    return folder.rstrip("/")


#: What was written and not deleted yet, by application: folder, and the table's name if it is one.
_WRITTEN: dict[str, dict[str, str | None]] = {}


def _noted(df: DataFrame, path: str, table: str | None = None) -> DataFrame:
    _WRITTEN.setdefault(df.sparkSession.sparkContext.applicationId, {})[path] = table
    df._lanes_path = path
    return df


def _delete(spark: SparkSession, path: str) -> None:
    table = _WRITTEN.get(spark.sparkContext.applicationId, {}).pop(path, None)
    if table:
        spark.sql(f"DROP TABLE IF EXISTS {table}")
    place = spark._jvm.org.apache.hadoop.fs.Path(path)
    place.getFileSystem(spark._jsc.hadoopConfiguration()).delete(place, True)


def release(*frames: DataFrame | None) -> None:
    """Delete what ``materialise`` or ``bucketed`` wrote for these frames; nothing may read them any more."""
    for df in frames:
        if df is not None and getattr(df, "_lanes_path", None):
            _delete(df.sparkSession, df._lanes_path)


def forget(spark: SparkSession) -> None:
    """Delete all intermediate folders and tables of this application. Results that were not written yet need them."""
    for path in list(_WRITTEN.get(spark.sparkContext.applicationId, {})):
        _delete(spark, path)


def materialise(df: DataFrame, label: str) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: cuts lineage, survives lost executors."""
    spark = df.sparkSession
    ship_package(spark)
    path = f"{shared_folder(spark)}/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return _noted(spark.read.schema(df.schema).parquet(path), path)


def bucketed(df: DataFrame, key: str, parts: int, label: str, placed: bool = False) -> DataFrame:
    """``df`` as a table of ``parts`` buckets by ``key``, sorted within them, kept in the shared folder.

    Joins and aggregations on ``key`` read it where it lies: unlike a checkpoint, a bucketed table tells the
    planner how it is partitioned. ``placed``: its rows are partitioned by ``key`` already.
    """
    spark = df.sparkSession
    name = f"lanes_{label}_{uuid.uuid4().hex}"
    path = f"{shared_folder(spark)}/{name}"
    rows = df if placed else df.repartition(parts, key)
    rows.write.bucketBy(parts, key).sortBy(key).option("path", path).saveAsTable(name)
    return _noted(spark.table(name), path, name)
