"""Shared-folder tables: the only way this library cuts lineage or hands files between tasks.

Every table is written below ``spark.checkpoint.dir``, which all executors and the driver
share. Where the setting is absent a plain ``local[n]`` session falls back to a folder of
this machine; on any other master the warehouse folder is used, which is shared as well.
"""

from __future__ import annotations

import atexit
import contextlib
import io
import tempfile
import uuid
import zipfile
from collections.abc import Iterator
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

_ROOTS: set[str] = set()
#: Spark deletes the shuffle files of a query's own plan when the query ends, not when the driver next collects garbage
_FREE = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def shared_root(spark: SparkSession) -> str:
    """Folder that driver and executors share."""
    sc = spark.sparkContext
    root = sc.getConf().get("spark.checkpoint.dir") or sc.getCheckpointDir()
    if root:
        return root.rstrip("/")
    if sc.master.startswith("local[") or sc.master == "local":
        return f"file://{tempfile.gettempdir()}/binflow-shared"
    return spark.conf.get("spark.sql.warehouse.dir").rstrip("/")


def new_folder(spark: SparkSession, name: str) -> str:
    """A path below the shared folder that no other run uses; it is not created. The application's folder is removed when the driver ends."""
    sc = spark.sparkContext
    root = f"{shared_root(spark)}/binflow/{sc.applicationId}"
    if root not in _ROOTS:
        _ROOTS.add(root)
        atexit.register(_sweep, sc._jvm, sc._jsc.hadoopConfiguration(), root)
    return f"{root}/{uuid.uuid4().hex}/{name}"


def _sweep(jvm, conf, root: str) -> None:
    with contextlib.suppress(Exception):  # the JVM may be gone before this process ends
        p = jvm.org.apache.hadoop.fs.Path(root)
        p.getFileSystem(conf).delete(p, True)


def materialise(df: DataFrame, name: str, free: bool = False) -> DataFrame:
    """Write ``df`` as a Parquet table in the shared folder and read it back.

    The result has no lineage beyond the files, so a lost executor costs one file split.
    With ``free`` the shuffle files of the plan behind ``df`` are deleted as soon as it is written.
    """
    spark = df.sparkSession
    path = new_folder(spark, name)
    with _freed(spark) if free else contextlib.nullcontext():
        df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._binflow_path = path
    return out


@contextlib.contextmanager
def _freed(spark: SparkSession) -> Iterator[None]:
    """Queries that begin inside leave no shuffle files; the session's setting is put back."""
    before = spark.conf.get(_FREE, None)
    spark.conf.set(_FREE, "true")
    try:
        yield
    finally:
        if before is None:
            spark.conf.unset(_FREE)
        else:
            spark.conf.set(_FREE, before)


def forget(df: DataFrame | None) -> None:
    """Delete the files behind a materialised table that nothing reads any more."""
    path = getattr(df, "_binflow_path", None)
    if path:
        remove(df.sparkSession, path)


def cut(df: DataFrame) -> DataFrame:
    """Compute ``df`` once into a reliable checkpoint in the shared folder; the result keeps its partitioning.

    The partitioning is kept if the plan is made without adaptive execution.
    """
    sc = df.sparkSession.sparkContext
    if not sc.getCheckpointDir():
        sc.setCheckpointDir(f"{shared_root(df.sparkSession)}/binflow/checkpoints")
    out = df.checkpoint()
    out._binflow_path = out._jdf.queryExecution().analyzed().rdd().getCheckpointFile().get()
    return out


def drop_cut(df: DataFrame | None) -> None:
    """Delete the files of a checkpoint that nothing reads any more."""
    forget(df)


def shuffle_bytes(spark: SparkSession) -> int:
    """Bytes that this application's stages have written for shuffles so far."""
    jsc, jvm = spark.sparkContext._jsc.sc(), spark.sparkContext._jvm
    jsc.listenerBus().waitUntilEmpty(10_000)
    none = jvm.java.util.ArrayList()
    quantiles = spark.sparkContext._gateway.new_array(jvm.double, 0)
    stages = jsc.statusStore().stageList(none, False, False, quantiles, none)
    return sum(stages.apply(i).shuffleWriteBytes() for i in range(stages.size()))


def hadoop_path(spark: SparkSession, path: str):
    """(FileSystem, Path) of the JVM for ``path``."""
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), p


def remove(spark: SparkSession, path: str) -> None:
    fs, p = hadoop_path(spark, path)
    fs.delete(p, True)


def ship_package(spark: SparkSession) -> None:
    """Give the executors' Python this package, once per application, from the shared folder."""
    sc = spark.sparkContext
    if getattr(sc, "_binflow_shipped", False):
        return
    here = Path(__file__).resolve().parent
    packed = io.BytesIO()
    with zipfile.ZipFile(packed, "w") as z:
        for p in sorted(here.rglob("*.py")):
            z.write(p, p.relative_to(here.parent).as_posix())
    target = new_folder(spark, f"binflow_package_{uuid.uuid4().hex}.zip")
    fs, path = hadoop_path(spark, target)
    stream = fs.create(path, False)
    stream.write(bytearray(packed.getvalue()))
    stream.close()
    sc.addPyFile(target)
    sc._binflow_shipped = True


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given Parquet tables."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
