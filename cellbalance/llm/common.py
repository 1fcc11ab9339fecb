"""Shared helpers of the training-data operators: tables, the shared work folder, text chunks."""

from __future__ import annotations

import ctypes
import gc
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

LOWER = bytes.maketrans(bytes(range(65, 91)), bytes(range(97, 123)))
#: A-Z to a-z, every other ASCII byte that is no digit or letter to a space; bytes from 0x80 stay.
ALNUM = bytes(
    b + 32 if 65 <= b <= 90 else b if b >= 128 or 48 <= b <= 57 or 97 <= b <= 122 else 32
    for b in range(256)
)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def fold(modulus: int, of: str = "doc_id") -> Column:
    """crc32 of the id as text, modulo: folds of the learning operators."""
    return F.crc32(F.col(of).cast("string").cast("binary")) % modulus


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share; a local one only where none is set and Spark is local."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        found = "file://" + tempfile.mkdtemp(prefix="cellbalance-")
        spark.sparkContext.setCheckpointDir(found)
    return found


class Work:
    """Tables written to the shared folder: they cut lineage and survive lost executors."""

    def __init__(self, spark: SparkSession):
        self.spark, self.root = spark, f"{shared_dir(spark)}/work-{uuid.uuid4().hex}"

    def table(self, df: DataFrame, name: str, codec: str = "zstd") -> DataFrame:
        path = f"{self.root}/{name}-{uuid.uuid4().hex[:6]}"
        df.write.option("compression", codec).parquet(path)
        return self.spark.read.schema(df.schema).parquet(path)

    def drop(self, df: DataFrame) -> None:
        """Delete a written table that no later step reads."""
        jvm, sc = self.spark._jvm, self.spark.sparkContext
        for f in df.inputFiles()[:1]:
            path = jvm.org.apache.hadoop.fs.Path(f).getParent()
            path.getFileSystem(sc._jsc.hadoopConfiguration()).delete(path, True)

    def release(self) -> None:
        """Let the driver's cleaner delete shuffle files of finished steps."""
        gc.collect()
        self.spark._jvm.System.gc()


def runs(column: pa.Array, most: int = 4 << 20) -> Iterator[tuple[int, int, list[bytes | None]]]:
    """(start, end, texts) of runs of about `most` bytes of a text column; a longer text is a run by
    itself. Only one run at a time stands in Python's memory."""
    sizes = pc.fill_null(pc.binary_length(column), 0).to_numpy(zero_copy_only=False)
    start, size = 0, 0
    for i, n in enumerate([*sizes.tolist(), None]):
        if i > start and (n is None or size + n > most):
            yield start, i, column.slice(start, i - start).cast(pa.large_binary()).to_pylist()
            start, size = i, 0
        size += n or 0


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit words (published finaliser constants)."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


#: What a worker process remembers between tasks, by operator.
MEMORIES: dict[str, dict] = {}


def make_room(operator: str = "") -> None:
    """Forget what other operators left in this worker, and hand freed memory back."""
    for name, held in MEMORIES.items():
        if name != operator:
            held.clear()
    gc.collect()
    pa.default_memory_pool().release_unused()
    if hasattr(libc := ctypes.CDLL(None), "malloc_trim"):
        libc.malloc_trim(0)


class Interned(dict):
    """Remembers a value per word, at most `most` at a time."""

    def __init__(self, make, most: int = 200_000):
        super().__init__()
        self.make, self.most = make, most

    def __missing__(self, word):
        if len(self) >= self.most:
            self.clear()
        value = self[word] = self.make(word)
        return value


def keep_rows(docs: DataFrame, text_col: str, judge, most: int = 4 << 20) -> DataFrame:
    """The rows whose texts `judge` (list of bytes or None, to booleans) accepts, all columns as they
    are. It sees whole texts, some at a time; no row moves between tasks."""
    at = docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        make_room()
        for batch in batches:
            for a, b, texts in runs(batch.column(at), most):
                yield batch.slice(a, b - a).filter(pa.array(list(judge(texts)), pa.bool_()))

    return docs.mapInArrow(run, docs.schema)
