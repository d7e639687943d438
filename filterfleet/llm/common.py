"""Shared helpers of the training-data operators: tables, shared folder, Arrow batches, hashing."""

from __future__ import annotations

import uuid

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession

#: Bytes that the word rule treats as separators: blank, tab, line feed, vertical tab, form feed, carriage return.
#: `bytes.split()` without an argument splits on exactly these.
SPACE_CLASS = r"[\x20\x09-\x0D]"
WORD_CLASS = r"[^\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or one of our own where it is unset and all runs
    in one process (tests). On a cluster an unset folder is an error, as tables in a machine's own folder go with it."""
    place = spark.conf.get("spark.checkpoint.dir", None)
    if not place:
        current = spark.sparkContext._jsc.sc().getCheckpointDir()
        if current.isDefined():
            return current.get()
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir has to name a folder that the driver and all executors share")
        import tempfile

        place = tempfile.mkdtemp(prefix="filterfleet-")
        spark.sparkContext.setCheckpointDir(place)
    return place


#: Settings while a table is written: the shuffles behind it serve nothing once it is there, so their files go then;
#: and rows are wide (whole texts and sets), so fewer of them travel to Python at a time.
_WRITING = {"spark.sql.classic.shuffleDependency.fileCleanup.enabled": "true", "spark.sql.execution.arrow.maxRecordsPerBatch": "2000"}


def materialize(df: DataFrame, what: str) -> DataFrame:
    """Cuts lineage: writes df as Parquet in the shared folder and reads it back with the same schema."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{what}-{uuid.uuid4().hex}"
    before = {k: spark.conf.get(k, None) for k in _WRITING}
    for k, v in _WRITING.items():
        if before[k] is not None:
            spark.conf.set(k, v)
    try:
        df.write.parquet(path)
    finally:
        for k, v in before.items():
            if v is not None:
                spark.conf.set(k, v)
    return spark.read.schema(df.schema).parquet(path)


def reduce_tasks(spark: SparkSession) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))


def slices(batch: pa.RecordBatch, column: str, most_bytes: int = 1 << 20):
    """Cuts a batch into runs of rows whose `column` holds about `most_bytes`; a longer single row is a run of its own."""
    lengths = pc.binary_length(batch.column(column)).fill_null(0).to_numpy(zero_copy_only=False)
    start, held = 0, 0
    for i, n in enumerate(lengths):
        if i > start and held + n > most_bytes:
            yield batch.slice(start, i - start)
            start, held = i, 0
        held += int(n)
    if start < batch.num_rows:
        yield batch.slice(start)


def released(run):
    """A map over Arrow batches that gives freed memory back at the end of its partition, as workers are used again."""

    def inner(batches):
        import ctypes

        try:
            yield from run(batches)
        finally:
            pa.default_memory_pool().release_unused()
            trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
            if trim:
                trim(0)

    return inner


def mix64(x: np.ndarray) -> np.ndarray:
    """Finalizer that spreads every input bit over 64 bits (uint64 in, uint64 out)."""
    x = x.copy()
    x ^= x >> np.uint64(33)
    x *= np.uint64(0xFF51AFD7ED558CCD)
    x ^= x >> np.uint64(33)
    x *= np.uint64(0xC4CEB9FE1A85EC53)
    x ^= x >> np.uint64(33)
    return x


class WordHashes(dict):
    """word bytes -> 64-bit hash; forgets everything when it holds too many words."""

    def __init__(self, most: int = 100_000):
        super().__init__()
        self.most = most

    def __missing__(self, word: bytes) -> int:
        import xxhash

        if len(self) >= self.most:
            self.clear()
        self[word] = value = xxhash.xxh3_64_intdigest(word)
        return value

    def array(self, words: list[bytes]) -> np.ndarray:
        return np.fromiter(map(self.__getitem__, words), np.uint64, len(words))


def rolling(values: np.ndarray, width: int, seed: int = 1) -> np.ndarray:
    """64-bit hash of every run of `width` values (uint64); empty if there are fewer."""
    n = len(values) - width + 1
    if n <= 0:
        return np.empty(0, np.uint64)
    factors = mix64(np.arange(seed * 1000 + 1, seed * 1000 + 1 + width, dtype=np.uint64)) | np.uint64(1)
    out = np.zeros(n, np.uint64)
    for k in range(width):
        out += values[k : k + n] * factors[k]
    return mix64(out)


def id_buckets(docs: DataFrame, buckets: int, column: str = "doc_id"):
    """An expression that deals rows to 0 ... buckets-1 in ascending order of `column`, about evenly by rows; nulls go to 0.

    The bounds are approximate quantiles: at most buckets-1 numbers come to the driver.
    """
    from pyspark.sql import functions as F

    if buckets < 2:
        return F.lit(0)
    shares = [k / buckets for k in range(1, buckets)]
    bounds = docs.agg(F.percentile_approx(F.col(column).cast("bigint"), shares, 20 * buckets).alias("b")).first()["b"]
    bounds = sorted(set(bounds or []))
    if not bounds:
        return F.lit(0)
    array = f"array({', '.join(f'{b}L' for b in bounds)})"
    steps = ", ".join(str(1 << k) for k in range(len(bounds).bit_length() - 1, -1, -1))
    # Binary search: how many bounds lie at or below the value.
    return F.expr(f"coalesce(aggregate(array({steps}), 0, (at, step) -> if(at + step <= {len(bounds)} and element_at({array}, at + step) <= {column}, at + step, at)), 0)")
