"""Shared-folder tables, byte helpers and file access used by the corpus operators."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
LOWER = UPPER.lower()


def shared_root(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or one of our own in local mode only."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not root:
        if not spark.sparkContext.master.startswith(("local[", "local")) or spark.sparkContext.master.startswith("local-cluster"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        root = "file://" + tempfile.mkdtemp(prefix="schemaloom-")
        atexit.register(shutil.rmtree, root.removeprefix("file://"), True)
        spark.sparkContext.setCheckpointDir(root)
    return root.rstrip("/")


#: Folders that this process has made; results that are read late still need theirs.
_ROOTS: list[Scratch] = []


def sweep() -> None:
    """Deletes every operator's folder of this process. For when all results have been read or written elsewhere."""
    while _ROOTS:
        _ROOTS.pop().drop("")


class Scratch:
    """Tables and files of one query in a shared folder of its own. Written tables cut lineage: a lost executor costs
    the tasks that read from it, not the stages before."""

    def __init__(self, spark: SparkSession, name: str):
        self.spark, self.root = spark, f"{shared_root(spark)}/{name}-{uuid.uuid4().hex}"
        _ROOTS.append(self)

    def path(self, name: str) -> str:
        return f"{self.root}/{name}"

    def table(self, name: str, df: DataFrame) -> DataFrame:
        df.write.mode("overwrite").parquet(self.path(name))
        return self.spark.read.schema(df.schema).parquet(self.path(name))

    def inner(self, name: str) -> Scratch:
        """A folder in this one, which is deleted under its name."""
        found = object.__new__(Scratch)
        found.spark, found.root = self.spark, self.path(name)
        return found

    def drop(self, *names: str) -> None:
        """Deletes tables that no later plan reads."""
        jvm = self.spark.sparkContext._jvm
        for name in names:
            at = jvm.org.apache.hadoop.fs.Path(self.path(name).rstrip("/"))
            at.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


def filesystem(uri: str):
    """(pyarrow file system, path in it) of a URI, on whichever machine this runs."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri)


def write_whole(fs, path: str, chunks) -> None:
    """Writes a file under a name of this attempt, then moves it into place, so that a retried or speculative task
    leaves one whole file."""
    part = f"{path}.{uuid.uuid4().hex}.part"
    fs.create_dir(path.rpartition("/")[0], recursive=True)
    with fs.open_output_stream(part, compression=None) as out:
        for chunk in chunks:
            out.write(chunk)
    fs.move(part, path)


def ascii_lower(text: Column) -> Column:
    """A-Z to a-z; other letters stay."""
    return F.translate(text, UPPER, LOWER)


def byte_texts(column: pa.Array | pa.ChunkedArray) -> list[bytes]:
    """A string column's values as UTF-8 bytes; null is empty."""
    if pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type):
        return [x or b"" for x in column.cast(pa.large_binary()).to_pylist()]
    return [x or b"" for x in column.cast(pa.binary()).to_pylist()]


def slices(batches: Iterator[pa.RecordBatch], column: str, most_bytes: int) -> Iterator[pa.RecordBatch]:
    """Cuts batches so that a slice's texts hold about most_bytes; a longer text is a slice of its own."""
    import numpy as np
    import pyarrow.compute as pc

    for batch in batches:
        if not batch.num_rows:
            continue
        sizes = np.asarray(pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False), dtype=np.int64)
        cut = np.flatnonzero(np.diff(np.cumsum(sizes) // most_bytes)) + 1
        for a, b in zip([0, *cut], [*cut, batch.num_rows], strict=True):
            yield batch.slice(a, b - a)


def unused(name: str, *tables: DataFrame) -> str:
    """The name, or one like it that no column of the tables has, whatever the case of its letters."""
    taken = {c.lower() for t in tables for c in t.columns}
    while name.lower() in taken:
        name += "_"
    return name


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")
