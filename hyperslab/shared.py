"""The folder that driver and executors share, and tables written into it."""

from __future__ import annotations

import atexit
import contextlib
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_written: list[str] = []
_own: list[str] = []


def shared_folder(spark: SparkSession) -> str:
    """``spark.checkpoint.dir``. Only a local session without that setting, as in tests, gets a temporary folder."""
    conf = spark.sparkContext.getConf()
    folder = conf.get("spark.checkpoint.dir", None)
    if folder:
        return folder.rstrip("/")
    if not conf.get("spark.master", "").startswith("local") or conf.get("spark.master", "").startswith("local-cluster"):
        raise ValueError("a cluster session needs spark.checkpoint.dir, a folder all its machines share")
    if not _own:
        _own.append(tempfile.mkdtemp(prefix="hyperslab-"))
    return _own[0]


def new_folder(spark: SparkSession, name: str) -> str:
    """A path not used yet in the shared folder; `sweep` removes what lies there."""
    path = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
    _written.append(path)
    return path


def written(df: DataFrame, name: str, *, compression: str = "zstd") -> DataFrame:
    """The rows of df from a Parquet table in the shared folder: cuts the lineage and survives lost executors."""
    path = new_folder(df.sparkSession, name)
    df.write.option("compression", compression).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def sweep() -> None:
    """Remove what `new_folder` named so far. Call it when no DataFrame that reads it is needed any more."""
    from pyarrow import fs

    while _written:
        uri = _written.pop()
        where, path = fs.FileSystem.from_uri(uri) if "://" in uri or uri.startswith(("/", "file:")) else (fs.LocalFileSystem(), uri)
        with contextlib.suppress(OSError):
            where.delete_dir(path)


atexit.register(sweep)
