"""What the operators share: the folder all machines see, files in it, and small column helpers."""

from __future__ import annotations

import gc
import os
import tempfile
import uuid
from urllib.parse import urlparse

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """The folder in spark.checkpoint.dir, or the one that the program has set; only in one local process, one of our own."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not spark.sparkContext.getCheckpointDir():
        if not spark.sparkContext.master.startswith("local") or spark.sparkContext.master.startswith("local-cluster"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all machines share")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="pqspark-"))
    return spark.sparkContext.getCheckpointDir().rstrip("/")


def fresh_path(spark: SparkSession, name: str) -> str:
    """A path in the shared folder that nothing has used yet."""
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def stored(df: DataFrame, name: str, path: str | None = None) -> DataFrame:
    """df written to the shared folder (under a fresh path unless one is given) and read back: lineage ends here, and lost executors cost no rerun."""
    path = path or fresh_path(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def remove(spark: SparkSession, path: str) -> None:
    """Delete what was stored under a path that no later read needs."""
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


def release_shuffles(spark: SparkSession) -> None:
    """Delete the shuffle files of what nothing refers to any more; they would lie there until the driver's garbage happens to be collected."""
    gc.collect()
    spark._jvm.System.gc()


def often(df: DataFrame, key: str, most: int) -> DataFrame | None:
    """(key, often) of keys that come more than most times, stored; None where there are none, as mostly.  At most rows / most keys."""
    found = stored(df.groupBy(key).agg(F.count("*").alias("n")).filter(F.col("n") > most).select(key, F.lit(True).alias("often")), "often")
    return None if found.isEmpty() else found


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def small(df: DataFrame, rows: int) -> bool:
    """Whether df (a stored table) has at most that many rows; the check behind every broadcast here."""
    return df.limit(rows + 1).count() <= rows


#: Rows of a table that may be broadcast, at most; a row here is a few numbers.
BROADCAST_ROWS = 1_000_000


def matched(texts: DataFrame, ids: DataFrame, on: str, how: str = "inner") -> DataFrame:
    """texts joined with a stored table of few columns, which is broadcast while it is small, so that texts need no shuffle."""
    return texts.join(F.broadcast(ids) if small(ids, BROADCAST_ROWS) else ids, on, how)


def lean_batches(spark: SparkSession, rows: int = 1000) -> None:
    """Whole texts cross to Python in batches of fewer rows than Spark's default, so that long ones fit in memory."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(key)) <= rows:
        spark.conf.set(key, str(rows))


def text_or_empty(name: str = "text"):
    return F.coalesce(F.col(name), F.lit(""))


def release_memory() -> None:
    """Give freed memory back to the system; a worker that waits for its next task would keep it."""
    import ctypes

    gc.collect()
    try:
        import pyarrow

        pyarrow.default_memory_pool().release_unused()
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):
        pass  # another C library: nothing to trim


class Files:
    """Files under a URI, from any machine: local and mounted paths by the OS, other stores by pyarrow's connectors."""

    def __init__(self, uri: str):
        self.uri = uri.rstrip("/")
        parsed = urlparse(self.uri)
        if parsed.scheme in ("", "file"):
            self.fs, self.root = None, parsed.path or self.uri
        else:
            from pyarrow import fs

            self.fs, self.root = fs.FileSystem.from_uri(self.uri)

    def write(self, name: str, chunks) -> int:
        """Write under a name of its own and rename at the end, so that no reader sees a part of it."""
        path, size = f"{self.root}/{name}", 0
        trial = f"{path}.{uuid.uuid4().hex}.part"
        if self.fs is None:
            os.makedirs(self.root, exist_ok=True)
            out = open(trial, "wb")  # noqa: SIM115
        else:
            self.fs.create_dir(self.root, recursive=True)
            out = self.fs.open_output_stream(trial)
        with out:
            for chunk in chunks:
                out.write(chunk)
                size += len(chunk)
        os.replace(trial, path) if self.fs is None else self.fs.move(trial, path)
        return size

    def open(self, name: str):
        """A seekable binary reader."""
        path = f"{self.root}/{name}"
        return open(path, "rb") if self.fs is None else self.fs.open_input_file(path)  # noqa: SIM115

    def size(self, name: str) -> int:
        path = f"{self.root}/{name}"
        return os.path.getsize(path) if self.fs is None else self.fs.get_file_info(path).size
