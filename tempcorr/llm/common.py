"""What the text operators share: the shared folder, written tables, word hashes, arrow helpers."""

from __future__ import annotations

import ctypes
import os
import tempfile
import uuid
from functools import cache, wraps

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Word separators of the contracts: space and the ASCII controls 9 to 13, which are what bytes.split() cuts at.
WORD = r"[^\x20\x09-\x0D]+"


#: Bytes of rows that are sent to a Python worker at once; a longer row goes alone.
BATCH_BYTES = 4 << 20


def shared_folder(spark: SparkSession) -> str:
    """The folder that the driver and all executors see. Only a local session that names none (tests) gets a temporary one."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        kept = spark.sparkContext._jsc.sc().getCheckpointDir()
        if kept.isDefined():
            return kept.get()
        master = spark.sparkContext.master
        if not master.startswith("local") or master.startswith("local-cluster"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        found = tempfile.mkdtemp(prefix="tempcorr-")
        spark.sparkContext.setCheckpointDir(found)
    return found


def bounded(spark: SparkSession) -> None:
    """Bounds the bytes of a batch that goes to Python, a setting that any session may change; never raises it."""
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    now = spark.conf.get(key, None)
    if now is None or not now.isdigit() or not 0 < int(now) <= BATCH_BYTES:
        spark.conf.set(key, str(BATCH_BYTES))


def written(df: DataFrame, name: str) -> DataFrame:
    """df as a Parquet table in the shared folder, read again: cuts the lineage, survives lost executors."""
    spark = df.sparkSession
    bounded(spark)
    path = f"{shared_folder(spark).rstrip('/')}/tempcorr-{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.tempcorr_path = path
    return out


def dropped(*tables: DataFrame | None) -> None:
    """Deletes written tables that nothing reads any more."""
    for t in tables:
        path = getattr(t, "tempcorr_path", None)
        if path:
            spark = t.sparkSession
            at = spark._jvm.org.apache.hadoop.fs.Path(path)
            at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


def _trim() -> None:
    """Gives free memory back, so that an idle worker holds none of a task's."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except AttributeError:  # another C library
        pass


#: Names under which numpy's linear algebra library sets the number of its threads.
SET_THREADS = ("scipy_openblas_set_num_threads64_", "scipy_openblas_set_num_threads", "openblas_set_num_threads64_", "openblas_set_num_threads")


@cache
def one_thread() -> None:
    """A task has one core: threads of numpy's linear algebra would only wait for each other, at twice the CPU time."""
    folder = os.path.join(os.path.dirname(os.path.dirname(np.__file__)), "numpy.libs")
    for name in os.listdir(folder) if os.path.isdir(folder) else []:
        if "openblas" in name:
            library = ctypes.CDLL(os.path.join(folder, name))
            for symbol in SET_THREADS:
                if hasattr(library, symbol):
                    getattr(library, symbol)(1)
                    break


def lean(f):
    """A function over batches that uses one thread and leaves no free memory behind in its worker."""

    @wraps(f)
    def run(batches):
        one_thread()
        try:
            yield from f(batches)
        finally:
            _trim()

    return run


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions", "200"))


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def keyed(docs: DataFrame, *more: str) -> DataFrame:
    """Only the columns that an operator reads; clashing names among the others don't matter then."""
    bounded(docs.sparkSession)
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), *more)


class WordHashes(dict):
    """Word to 64-bit hash, remembered; bounded, since a full memory is emptied."""

    LIMIT = 400_000

    def __missing__(self, word: bytes) -> int:
        if len(self) >= self.LIMIT:
            self.clear()
        h = self[word] = xxhash.xxh3_64_intdigest(word)
        return h

    def of(self, words: list[bytes]) -> np.ndarray:
        return np.fromiter(map(self.__getitem__, words), np.uint64, len(words))


def mix(x: np.ndarray) -> np.ndarray:
    """A finaliser for 64-bit hashes, so that sums of products are spread over all bits."""
    x = (x ^ (x >> np.uint64(33))) * np.uint64(0xFF51AFD7ED558CCD)
    x = (x ^ (x >> np.uint64(33))) * np.uint64(0xC4CEB9FE1A85EC53)
    return x ^ (x >> np.uint64(33))


def powers(base: int, n: int) -> np.ndarray:
    out = np.full(n, base, np.uint64)
    out[:1] = 1
    return np.multiply.accumulate(out)


def ascii_lower(c: Column) -> Column:
    return F.translate(c, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def packed(text: bytes) -> bytes:
    import zstandard

    return zstandard.ZstdCompressor(level=1).compress(text)


def unpacked(text: bytes) -> bytes:
    import zstandard

    return zstandard.ZstdDecompressor().decompress(text)


def text_bytes(column: pa.Array) -> list[bytes | None]:
    """The UTF-8 bytes of a string column, without decoding them."""
    kind = pa.large_binary() if pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type) else pa.binary()
    return column.cast(kind).to_pylist()
