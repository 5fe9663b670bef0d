"""Input tables and shared scratch storage.

Everything that one task writes and another reads goes below the folder named
by ``spark.checkpoint.dir``, which all executors of a cluster share. Only a
local session without that setting (tests, a single machine) gets a temporary
folder; on a cluster its lack is an error. ``discard`` deletes what is read no more.
"""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_own_dir: list[str] = []


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The shared folder as a URI or path, without a trailing slash."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        if not _own_dir:
            _own_dir.append(tempfile.mkdtemp(prefix="tabseek-"))
        base = _own_dir[0]
    return base.rstrip("/")


def scratch_path(spark: SparkSession, label: str) -> str:
    return f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"


def materialise(df: DataFrame, label: str) -> DataFrame:
    """Cut the lineage: write ``df`` as Parquet into the shared folder and reread it.

    The files outlive the executors that wrote them, so a lost executor costs
    no recomputation of what stands before this point.
    """
    spark = df.sparkSession
    path = scratch_path(spark, label)
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._scratch = path
    return out


def discard(*frames: DataFrame) -> None:
    """Delete what ``materialise`` wrote for frames that nothing reads any more."""
    for df in frames:
        spark = df.sparkSession
        at = spark._jvm.org.apache.hadoop.fs.Path(df._scratch)
        at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


def free_prefix(columns: list[str]) -> str:
    """A prefix of which no name in ``columns`` is, for columns that an operator adds for itself."""
    prefix = "_own_"
    while any(c.lower().startswith(prefix) for c in columns):
        prefix = "_" + prefix
    return prefix


def executor_fs(uri: str):
    """(filesystem, path) of pyarrow for a shared folder; local, HDFS and object stores."""
    from pyarrow import fs

    if "://" not in uri and not uri.startswith("file:"):
        return fs.LocalFileSystem(), uri
    if uri.startswith("file:"):
        return fs.LocalFileSystem(), "/" + uri[len("file:"):].lstrip("/")
    return fs.FileSystem.from_uri(uri)


def write_atomically(uri: str, chunks) -> int:
    """Write byte chunks under a temporary name, then rename; returns the size.

    Attempts of one task write the same rows, if not in the same order, each
    under a temporary name of its own, so whichever ends last leaves a whole file.
    """
    fs, path = executor_fs(uri)
    fs.create_dir(path.rpartition("/")[0], recursive=True)
    part = f"{path}.{uuid.uuid4().hex}.tmp"
    size = 0
    with fs.open_output_stream(part, compression=None) as out:
        for chunk in chunks:
            out.write(chunk)
            size += len(chunk)
    fs.move(part, path)
    return size
