"""Readers, and tables written to the folder that driver and executors share."""

from __future__ import annotations

import atexit
import contextlib
import os
import re
import shutil
import tempfile
import uuid
import zipfile
from pathlib import Path

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

_written: dict[str, object] = {}
_shipped: set[str] = set()
_roots: dict[str, str] = {}

#: Rows that go to a Python worker at a time. Rows of this package are whole texts, and a batch is held several times
#: over by JVM and worker; the default of ten thousand is meant for narrow rows. A batch ends at so many bytes, too.
BATCH_ROWS, BATCH_BYTES = 1000, 2 << 20
_BOUNDS = {"spark.sql.execution.arrow.maxRecordsPerBatch": BATCH_ROWS, "spark.sql.execution.arrow.maxBytesPerBatch": BATCH_BYTES}


def ship(spark: SparkSession) -> None:
    """Send this package to the Python workers, once for each application, unless their path has it anyway."""
    root = Path(__file__).resolve().parent.parent
    app = spark.sparkContext.applicationId
    if app in _shipped or str(root) in os.environ.get("PYTHONPATH", "").split(os.pathsep):
        return
    _shipped.add(app)
    folder = os.path.realpath(tempfile.mkdtemp(prefix="wordlid-code-"))
    with zipfile.ZipFile(f"{folder}/wordlid_code.zip", "w") as z:
        for f in sorted(root.joinpath("wordlid").rglob("*.py")):
            z.write(f, f.relative_to(root))
    spark.sparkContext.addPyFile(f"{folder}/wordlid_code.zip")


def bound_batches(spark: SparkSession) -> None:
    """Bound the batches of whole texts that Python workers get. A plan reads these settings when it runs, which is after an
    operator has returned, so they are the session's; what the user has set stays."""
    ship(spark)
    for name, most in _BOUNDS.items():
        if spark.conf.get(name, str(most)) == str(most):  # unset, or that anyway
            spark.conf.set(name, str(most))


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One input table; the path is only ever opened by Spark's own reader."""
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def file_state(spark: SparkSession, folder: str) -> tuple:
    """Names, sizes and times of what is in a folder of tables, by the file system that Spark uses."""
    path = spark._jvm.org.apache.hadoop.fs.Path(folder)
    found = path.getFileSystem(spark._jsc.hadoopConfiguration()).listStatus(path)
    return tuple(sorted((f.getPath().getName(), f.getLen(), f.getModificationTime()) for f in found))


def shared_root(spark: SparkSession) -> str:
    """The folder of spark.checkpoint.dir; where it is unset in one process (tests, a laptop), a temporary one."""
    context = spark.sparkContext
    root = spark.conf.get("spark.checkpoint.dir", None) or context.getCheckpointDir() or _roots.get(context.applicationId)
    if root:
        return root
    if not context.master.startswith("local") or context.master.startswith("local-cluster"):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if not _roots:
        atexit.register(lambda: [shutil.rmtree(r, ignore_errors=True) for r in _roots.values()])
    root = _roots[context.applicationId] = tempfile.mkdtemp(prefix="wordlid-")
    context.setCheckpointDir(root)
    return root


def cut_lineage(df: DataFrame, name: str = "t") -> DataFrame:
    """Write df as Parquet to the shared folder and read it back.

    Later stages then start from the files, so a lost executor costs one re-read and
    nothing upstream runs twice. The files go by discard(), or when the driver ends.
    """
    spark = df.sparkSession
    ship(spark)
    path = temporary(spark, name)
    df.write.parquet(path)
    back = spark.read.schema(df.schema).parquet(path)
    back._wordlid_path = path
    return back


def temporary(spark: SparkSession, name: str) -> str:
    """A path in the shared folder whose files go when the driver ends. Signs that readers take for a pattern are not in it."""
    path = f"{shared_root(spark)}/tables/{re.sub(r'[^A-Za-z0-9_.-]+', '_', name)}-{uuid.uuid4().hex}"
    if not _written:
        atexit.register(_clean)
    _written[path] = spark
    return path


def save_artifact(df: DataFrame, path: str, kind: str, version: int = 1) -> None:
    """Vectors, merges, tagged words or other tables to share: Parquet with what it is and the version of its columns in every row group."""
    df.selectExpr("*", f"'{kind}' AS artifact_kind", f"{int(version)} AS artifact_version").write.parquet(path)


def load_artifact(spark: SparkSession, path: str, kind: str, version: int = 1) -> DataFrame:
    """What save_artifact wrote; another kind or version is an error."""
    df = spark.read.parquet(path)
    found = df.select("artifact_kind", "artifact_version").distinct().limit(2).collect()
    if any((r[0], r[1]) != (kind, version) for r in found):
        raise ValueError(f"{path} has {[tuple(r) for r in found]}, not {(kind, version)}")
    return df.drop("artifact_kind", "artifact_version")


def discard(*tables: DataFrame | None) -> None:
    """Delete the files of tables from cut_lineage that nothing reads any more."""
    for t in tables:
        path = getattr(t, "_wordlid_path", None)
        if path in _written:
            _delete(_written.pop(path), path)


def _delete(spark, path: str) -> None:
    with contextlib.suppress(Exception):  # the session may be gone
        target = spark._jvm.org.apache.hadoop.fs.Path(path)
        target.getFileSystem(spark._jsc.hadoopConfiguration()).delete(target, True)


def _clean() -> None:
    for path, spark in _written.items():
        _delete(spark, path)


def small_table(spark: SparkSession, **columns: pa.Array) -> DataFrame:
    """A table of a few rows that goes to the JVM as Arrow; a list of rows would start Python workers on the executors."""
    return spark.createDataFrame(pa.table(columns))
