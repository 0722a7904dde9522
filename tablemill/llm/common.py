"""What the operators share: the folder all executors see, and Arrow helpers."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """The cluster's shared folder (``spark.checkpoint.dir``).

    Only a session in local mode without that setting gets a folder of its own;
    a cluster without one is refused, as its executors would not see each other's files.
    """
    at = spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if at:
        return at.rstrip("/")
    set_by_hand = spark.sparkContext._jsc.sc().getCheckpointDir()
    if set_by_hand.isEmpty():
        if not spark.sparkContext.master.startswith("local") or spark.sparkContext.master.startswith("local-cluster"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="tablemill-"))
        set_by_hand = spark.sparkContext._jsc.sc().getCheckpointDir()
    return set_by_hand.get()


def work_path(spark: SparkSession, name: str) -> str:
    return f"{shared_folder(spark)}/tablemill/{name}-{uuid.uuid4().hex}"


def stored(df: DataFrame, name: str, codec: str = "zstd") -> DataFrame:
    """Cut the lineage: write to the shared folder, read back.

    Lost executors then cost the tasks that ran on them, never the work before.
    """
    spark = df.sparkSession
    path = work_path(spark, name)
    df.write.option("compression", codec).parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.stored_at = path
    return out


def forget(df: DataFrame) -> None:
    """Delete the files of a ``stored`` table that nothing reads any more."""
    if path := getattr(df, "stored_at", None):
        drop_path(df.sparkSession, path)


def drop_path(spark: SparkSession, path: str) -> None:
    hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    hadoop.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(hadoop, True)


def put_text(spark: SparkSession, path: str, text: str) -> None:
    """Write a small file whole or not at all: under another name first, then renamed."""
    hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs.Path
    at, part = hadoop(path), hadoop(f"{path}.{uuid.uuid4().hex}.part")
    files = at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    out = files.create(part, True)
    out.write(bytearray(text.encode()))
    out.close()
    if not files.rename(part, at):
        files.delete(part, False)
        raise FileExistsError(path)


def texts_in(spark: SparkSession, folder: str) -> dict[str, str]:
    """Name and content of the small finished files of a folder; none if it does not exist."""
    hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(folder)
    files = hadoop.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    if not files.exists(hadoop):
        return {}
    out = {}
    for one in files.listStatus(hadoop):
        name = one.getPath().getName()
        if not name.endswith(".part"):
            stream = files.open(one.getPath())
            out[name] = bytes(stream.readAllBytes()).decode()
            stream.close()
    return out


def free_name(df: DataFrame, base: str) -> str:
    """A column name that ``df`` does not use in any case."""
    taken = {c.lower() for c in df.columns}
    while base in taken:
        base += "_"
    return base


def raw(column: pa.Array) -> pa.Array:
    """A text column as its UTF-8 bytes, without decoding."""
    return column.cast(pa.binary()) if not pa.types.is_binary(column.type) else column


def whole(column: pa.Array) -> list[bytes]:
    """Texts as bytes; null counts as empty."""
    return [x or b"" for x in raw(column).to_pylist()]


def sums(values: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Sums of consecutive groups of the given sizes; empty groups give 0. Works on rows of matrices."""
    ends = np.cumsum(sizes)
    total = np.concatenate([np.zeros((1, *values.shape[1:]), values.dtype), np.cumsum(values, axis=0, dtype=values.dtype)])
    return total[ends] - total[ends - sizes]


def lean(run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], keep: str = ""):
    """A batch function that gives its memory back when its task ends.

    Python workers outlive their tasks; without this each keeps the most that any
    operator before it took. What other operators remember in the worker is dropped
    too: only keys of the worker's cache that begin with ``keep`` stay.
    """

    def wrapped(batches):
        import sys

        cache = getattr(sys.modules.get("tablemill_worker_cache"), "__dict__", {})
        for key in [k for k in cache if not k.startswith("__") and not (keep and k.startswith(keep))]:
            del cache[key]
        # Freed batches of the plain allocator can be trimmed, those of a pooling one cannot.
        pa.set_memory_pool(pa.system_memory_pool())
        try:
            yield from run(batches)
        finally:
            trim()

    return wrapped


def trim() -> None:
    import ctypes
    import gc

    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


def columns(schema: str) -> pa.Schema:
    """Arrow schema of the few simple types the operators return."""
    kinds = {"long": pa.int64(), "int": pa.int32(), "string": pa.string(), "binary": pa.binary(), "double": pa.float64(), "boolean": pa.bool_(), "array<long>": pa.list_(pa.int64()), "array<int>": pa.list_(pa.int32())}
    return pa.schema([(n, kinds[k]) for n, k in (x.strip().split(" ", 1) for x in schema.split(", "))])
