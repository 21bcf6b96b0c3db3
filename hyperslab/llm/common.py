"""What the operators of this subpackage share: the shared folder, written tables, files from tasks."""

from __future__ import annotations

import atexit
import contextlib
import tempfile
import uuid
from collections.abc import Iterator

import pyarrow as pa
from pyarrow import fs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_written: list[str] = []


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``.

    Only a session without that setting, as in tests on one machine, gets a temporary folder.
    """
    conf = spark.sparkContext.getConf()
    folder = conf.get("spark.checkpoint.dir", None)
    if folder:
        return folder.rstrip("/")
    if not getattr(shared_folder, "own", None):
        if not conf.get("spark.master", "").startswith("local"):
            raise ValueError("a cluster session needs spark.checkpoint.dir, a folder all its machines share")
        shared_folder.own = tempfile.mkdtemp(prefix="hyperslab-")
    return shared_folder.own


def new_folder(spark: SparkSession, name: str) -> str:
    """A path not used yet in the shared folder; `sweep` removes what lies there."""
    path = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
    _written.append(path)
    return path


def written(df: DataFrame, name: str) -> DataFrame:
    """The rows of df from a Parquet table in the shared folder: cuts the lineage and survives lost executors."""
    spark = df.sparkSession
    path = new_folder(spark, name)
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


#: Rows of a few short columns that may go to every task, about 50 MB.
BROADCAST_ROWS = 1_000_000


def looked_up(rows: DataFrame, small: DataFrame, on: str, how: str = "inner") -> DataFrame:
    """rows joined with small, a written table that is unique by on. While it is known by count to fit, it goes to the
    rows, so no key gathers them; beyond, both are shuffled and Spark's adaptive skew join splits hot keys."""
    return rows.join(F.broadcast(small) if small.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS else small, on, how)


def made_since(n: int = 0) -> list[str]:
    """The folders that `new_folder` named after the first n, which are no longer its own to remove."""
    own = _written[n:]
    del _written[n:]
    return own


def made() -> int:
    """How many folders `new_folder` has named that are still its own to remove."""
    return len(_written)


def remove(folders: list[str]) -> None:
    """Remove tables and files; what is gone already is passed over."""
    while folders:
        where, path = open_store(folders.pop())
        with contextlib.suppress(OSError):
            where.delete_dir(path)


def sweep() -> None:
    """Remove the tables and files made so far. Call it when no DataFrame that reads them is needed any more."""
    remove(made_since())


atexit.register(sweep)


def open_store(uri: str) -> tuple[fs.FileSystem, str]:
    return fs.FileSystem.from_uri(uri) if "://" in uri or uri.startswith(("/", "file:")) else (fs.LocalFileSystem(), uri)


@contextlib.contextmanager
def whole_file(uri: str) -> Iterator[pa.NativeFile]:
    """Writes a file under a name of its own and then moves it to uri, so a task that is run again replaces it whole."""
    where, path = open_store(uri)
    where.create_dir(path.rpartition("/")[0], recursive=True)
    draft = f"{path}.{uuid.uuid4().hex}.draft"
    with where.open_output_stream(draft, compression=None) as out:
        yield out
    where.move(draft, path)


def parts(batch: pa.RecordBatch, column: str, most_bytes: int = 8 << 20, most_rows: int = 1 << 30) -> Iterator[pa.RecordBatch]:
    """Slices of batch whose texts in column take about most_bytes at most, or one row."""
    import numpy as np
    import pyarrow.compute as pc

    sizes = np.cumsum(pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False).astype(np.int64) + 16)
    at = 0
    while at < batch.num_rows:
        base = sizes[at - 1] if at else 0
        end = max(at + 1, min(int(np.searchsorted(sizes, base + most_bytes, side="right")), at + most_rows))
        yield batch.slice(at, end - at) if end - at == batch.num_rows else batch.take(pa.array(np.arange(at, end)))  # string kernels misread slices
        at = end
