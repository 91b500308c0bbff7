"""Where intermediate tables and files live, and how the package reaches the executors.

Everything that cuts lineage goes to the folder named by ``spark.checkpoint.dir``: the one
place that driver and executors share. Only where that setting is absent (tests, notebooks)
a temporary folder of this machine is used.
"""

from __future__ import annotations

import ctypes
import os
import tempfile
import uuid
import zipfile

from pyspark.sql import DataFrame, SparkSession

_shipped: set[str] = set()
_fallback: dict[str, str] = {}


def table(sf_dir: str, name: str, spark: SparkSession) -> DataFrame:
    """A given table, read through Spark alone (the path may be in any store)."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ship(spark: SparkSession) -> None:
    """Send this package to the executors once for each application."""
    app = spark.sparkContext.applicationId
    if app in _shipped:
        return
    root = os.path.dirname(os.path.abspath(__file__))
    path = os.path.join(tempfile.mkdtemp(prefix="patchspace-"), "patchspace_pkg.zip")
    with zipfile.ZipFile(path, "w", zipfile.ZIP_DEFLATED) as z:
        for folder, _, names in os.walk(root):
            for n in names:
                if n.endswith(".py"):
                    full = os.path.join(folder, n)
                    z.write(full, os.path.join("patchspace", os.path.relpath(full, root)))
    spark.sparkContext.addPyFile(path)
    _shipped.add(app)


def shared_root(spark: SparkSession) -> str:
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        app = spark.sparkContext.applicationId
        root = _fallback.setdefault(app, "file://" + tempfile.mkdtemp(prefix="patchspace-shared-"))
    if "://" not in root and not root.startswith("file:"):
        root = "file://" + root if root.startswith("/") else root
    return root.rstrip("/")


def new_path(spark: SparkSession, what: str) -> str:
    """A fresh folder name below the shared root; an application's folders lie together."""
    return f"{shared_root(spark)}/patchspace/{spark.sparkContext.applicationId}/{what}-{uuid.uuid4().hex[:12]}"


def staged(df: DataFrame, what: str, partition_by: list[str] | None = None) -> DataFrame:
    """Write ``df`` once to the shared folder and read it back: lineage ends there."""
    return staged_at(df, what, partition_by)[0]


def staged_at(df: DataFrame, what: str, partition_by: list[str] | None = None) -> tuple[DataFrame, str]:
    spark = df.sparkSession
    path = new_path(spark, what)
    writer = df.write.option("compression", "zstd")
    if partition_by:
        writer = writer.partitionBy(*partition_by)
    schema = df.schema
    writer.parquet(path)
    return spark.read.schema(schema).parquet(path), path


def drop_path(spark: SparkSession, path: str) -> None:
    """Delete a staged folder that no plan reads any more."""
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


def trim() -> None:
    """Give freed memory of a worker back to the system; arrays here come in few, large sizes."""
    import pyarrow as pa

    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):
        pass  # another C library: nothing to give back by hand


def open_fs(uri: str):
    """(file system, path) of a URI, for code on executors that writes real files."""
    from pyarrow import fs

    if uri.startswith("file:"):
        return fs.LocalFileSystem(), "/" + uri[5:].lstrip("/")
    return fs.FileSystem.from_uri(uri)
