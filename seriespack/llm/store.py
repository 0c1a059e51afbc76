"""Places that the driver and all executors share, and atomic files in them.

Everything lives below ``spark.checkpoint.dir``; only where that is unset and Spark runs in one process (tests,
a notebook) does a temporary folder stand in; a cluster without it is refused.  Tables are cut by ``written``: one run of the plan, Parquet in the shared
folder, lineage gone.  Files appear under their final name by a rename, so a task that runs twice, or
dies half-way, never leaves a torn file.
"""

from __future__ import annotations

import sys
import tempfile
import types
import uuid

from pyspark.sql import DataFrame, SparkSession

_made: list[str] = []
_own: list[str] = []


def shared_root(spark: SparkSession) -> str:
    """The shared folder's URI."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        if not _own:
            _own.append("file://" + tempfile.mkdtemp(prefix="seriespack-"))
        root = _own[0]
    return root if "://" in root or root.startswith("file:") else f"file://{root}"


def new_path(spark: SparkSession, name: str) -> str:
    """A fresh path in the shared folder."""
    path = f"{shared_root(spark).rstrip('/')}/seriespack/{name}-{uuid.uuid4().hex}"
    _made.append(path)
    return path


def written(df: DataFrame, name: str, compression: str | None = None) -> DataFrame:
    """``df`` as a table in the shared folder; the result reads that table."""
    path = new_path(df.sparkSession, name)
    df.write.parquet(path, compression=compression)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def forget(spark: SparkSession) -> None:
    """Deletes what this session wrote to the shared folder."""
    jvm, conf = spark._jvm, spark._jsc.hadoopConfiguration()
    while _made:
        path = jvm.org.apache.hadoop.fs.Path(_made.pop())
        path.getFileSystem(conf).delete(path, True)


def worker_cache() -> dict:
    """A dictionary that lives as long as the Python process, whichever task asks."""
    return sys.modules.setdefault("_seriespack_worker", types.ModuleType("_seriespack_worker")).__dict__


def opened(uri: str):
    """File system and path of a URI."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri)


class AtomicFile:
    """A binary file that shows up at ``uri`` only when it is complete."""

    def __init__(self, uri: str):
        self.fs, self.path = opened(uri)
        self.fs.create_dir(self.path.rpartition("/")[0], recursive=True)
        self.temporary = f"{self.path}.{uuid.uuid4().hex}.part"
        self.stream = self.fs.open_output_stream(self.temporary, compression=None)

    def __enter__(self):
        return self.stream

    def __exit__(self, kind, value, trace):
        self.stream.close()
        if kind is None:
            self.fs.move(self.temporary, self.path)
        else:
            self.fs.delete_file(self.temporary)
        return False
