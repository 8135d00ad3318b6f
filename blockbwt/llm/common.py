"""What the operators share: scratch tables, table reading, blobs."""

from __future__ import annotations

import contextlib
import re
import tempfile
import uuid

import numpy as np
import zstandard
from pyspark.sql import DataFrame, SparkSession

#: A word of the contracts: a run of anything but ASCII white space.
WORD = r"[^\x20\x09-\x0D]+"

_own: dict[str, str] = {}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that the cluster shares; one of our own only where the session names none and is one process, which shares its disk with itself."""
    named = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not re.fullmatch(r"local(\[[^\]]*\])?", spark.sparkContext.master):
        raise ValueError("a cluster has to name its shared folder in spark.checkpoint.dir")
    app = spark.sparkContext.applicationId
    if app not in _own:
        _own[app] = tempfile.mkdtemp(prefix="blockbwt-")
    return _own[app]


def scratch_path(spark: SparkSession, tag: str) -> str:
    """A fresh path in the shared folder, removed when the driver ends."""
    path = f"{shared_dir(spark)}/blockbwt-{tag}-{uuid.uuid4().hex}"
    jvm_path = spark._jvm.org.apache.hadoop.fs.Path(path)
    jvm_path.getFileSystem(spark._jsc.hadoopConfiguration()).deleteOnExit(jvm_path)
    return path


def remove(spark: SparkSession, path: str) -> None:
    jvm_path = spark._jvm.org.apache.hadoop.fs.Path(path)
    jvm_path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(jvm_path, True)


def write(df: DataFrame, tag: str) -> str:
    """Writes df to a fresh path; what its shuffles left on the executors' disks goes when the write is over."""
    path = scratch_path(df.sparkSession, tag)
    with setting(df.sparkSession, "spark.sql.classic.shuffleDependency.fileCleanup.enabled", "true"):
        df.write.option("compression", "zstd").parquet(path)
    return path


@contextlib.contextmanager
def setting(spark: SparkSession, key: str, value: str):
    """A session setting for a while; the session has its own again afterwards."""
    was = spark.conf.get(key, None)
    spark.conf.set(key, value)
    try:
        yield
    finally:
        spark.conf.unset(key) if was is None else spark.conf.set(key, was)


def materialise(df: DataFrame, tag: str) -> DataFrame:
    """Cuts the lineage at a written table that outlives any executor."""
    return df.sparkSession.read.schema(df.schema).parquet(write(df, tag))


def shuffle_parts(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def slices(batch, column: int, most: int = 1 << 20):
    """Runs of a batch's rows whose strings in `column` have about `most` bytes: few rows at a time become Python objects."""
    import pyarrow.compute as pc

    ends = np.cumsum(pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False), dtype=np.int64) + np.arange(batch.num_rows) * 64
    a = 0
    while a < batch.num_rows:
        before = ends[a - 1] if a else 0
        b = max(a + 1, int(np.searchsorted(ends, before + most)))
        yield batch.slice(a, b - a)
        a = b


def small_batches(spark: SparkSession, most_bytes: int = 8 << 20) -> None:
    """Arrow batches of 8 MB at most: whole texts pass by in them, and both sides hold several at once."""
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(most_bytes))


def trimmed(run):
    """An Arrow function that gives its memory back to the system when a task ends: workers wait for later stages with what they hold."""

    def wrapped(batches):
        try:
            yield from run(batches)
        finally:
            release()

    return wrapped


def release() -> None:
    import ctypes
    import gc

    import pyarrow as pa

    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


def pack(data: bytes | np.ndarray) -> bytes:
    """A zstd frame. Of an array, the planes of its bytes, lowest first, compress best one by one."""
    if isinstance(data, np.ndarray):
        data = np.ascontiguousarray(data).view(np.uint8).reshape(-1, data.itemsize).T.tobytes()
    return zstandard.ZstdCompressor(level=4, write_content_size=True).compress(data)


def unpack(data: bytes) -> bytes:
    return zstandard.ZstdDecompressor().decompress(data)


def unpack_array(data: bytes, dtype) -> np.ndarray:
    dtype = np.dtype(dtype)
    raw = np.frombuffer(unpack(data), np.uint8)
    return np.ascontiguousarray(raw.reshape(dtype.itemsize, -1).T).reshape(-1).view(dtype)


def pack_words(words: list[bytes]) -> bytes:
    """Byte strings of any content: their lengths, then the strings."""
    lens = np.fromiter(map(len, words), np.uint32, len(words))
    return pack(len(words).to_bytes(8, "little") + lens.tobytes() + b"".join(words))


def unpack_words(data: bytes) -> list[bytes]:
    raw = unpack(data)
    n = int.from_bytes(raw[:8], "little")
    ends = (np.frombuffer(raw, np.uint32, n, 8).astype(np.int64).cumsum() + 8 + 4 * n).tolist()
    return [raw[a:b] for a, b in zip([8 + 4 * n, *ends], ends)]
