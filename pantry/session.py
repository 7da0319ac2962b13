"""Session helpers: shared scratch folder, tables that cut lineage, parquet access."""

from __future__ import annotations

import gc
import pathlib
import tempfile
import time
import uuid
import zipfile

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """Folder that driver and executors share.

    The cluster names it in ``spark.checkpoint.dir``. Only where that is unset and all executors are
    threads of this machine (tests) a temporary folder is made, once a session.
    """
    path = spark.conf.get("spark.checkpoint.dir", None)
    if not path:
        if not spark.sparkContext.master.startswith("local["):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        path = getattr(spark, "_pantry_scratch", None)
        if path is None:
            path = "file://" + tempfile.mkdtemp(prefix="pantry-")
            spark._pantry_scratch = path
    return path.rstrip("/")


def materialize(df: DataFrame, label: str) -> DataFrame:
    """Write ``df`` as Parquet to the shared folder and read it back: cuts lineage, survives executors.

    The files go when the driver's JVM ends.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/pantry-{label}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    files, target = _files(spark, path)
    files.deleteOnExit(target)
    out = spark.read.schema(df.schema).parquet(path)
    out._pantry_path = path
    return out


def _files(spark: SparkSession, path: str):
    """The file system of a path, and the path for it."""
    target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), target


def discard(*tables: DataFrame) -> None:
    """Delete the files of materialised tables that nothing reads any more."""
    for t in tables:
        files, target = _files(t.sparkSession, t._pantry_path)
        files.delete(target, True)


def kept(spark: SparkSession, name: str, make) -> DataFrame:
    """The table ``make()`` gives, written the first time in a session and read from then on, while its files are there."""
    tables = spark.__dict__.setdefault("_pantry_kept", {})
    if name in tables:
        files, target = _files(spark, tables[name]._pantry_path)
        if files.exists(target):
            return tables[name]
    tables[name] = materialize(make(), "kept")
    return tables[name]


def release(spark: SparkSession) -> None:
    """Let Spark drop the shuffle files of plans that nothing refers to any more.

    Its cleaner acts on what a collection of the driver's garbage has found unreferenced, in its own
    thread; a second collection gets what the first one made unreachable. With threads for executors
    (tests) there is nothing to save.
    """
    if spark.sparkContext.master.startswith("local["):
        return
    for _ in range(2):
        gc.collect()
        spark.sparkContext._jvm.System.gc()
        time.sleep(0.7)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ship(spark: SparkSession) -> None:
    """Make the package importable in the executors' Python, once a context."""
    sc = spark.sparkContext
    if getattr(sc, "_pantry_shipped", False):
        return
    home = pathlib.Path(__file__).parent
    target = pathlib.Path(tempfile.mkdtemp(prefix="pantry-")) / "pantry.zip"
    with zipfile.ZipFile(target, "w") as out:
        for p in sorted(home.rglob("*.py")):
            out.write(p, p.relative_to(home.parent))
    sc.addPyFile(str(target))
    sc._pantry_shipped = True
