"""Shared pieces of the corpus operators: stored tables, byte slicing, word hashes, merged sketches."""

from __future__ import annotations

import gc
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bytes of text that one vectorised step handles; bounds the memory of NumPy temporaries.
STEP_BYTES = 2_000_000

#: ASCII white space of the contracts: space and 0x09-0x0D.
SPACES = bytes([32, 9, 10, 11, 12, 13])


def shared_dir(spark: SparkSession) -> str:
    """Folder that driver and executors share, as the session names it; one of our own only where unset."""
    base = spark.conf.get("spark.checkpoint.dir", "")
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        base = f"file://{tempfile.gettempdir()}/geohist-shared"  # one machine: tests
    return f"{base}/geohist-{uuid.uuid4().hex}"


def stored(df: DataFrame, spark: SparkSession) -> DataFrame:
    """Write df as Parquet to the shared folder and read it back: cuts lineage, survives lost executors."""
    path = shared_dir(spark)
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


class Scratch:
    """Tables between the steps of one operator, in the shared folder; `drop` deletes them when its result no longer reads them."""

    def __init__(self, spark: SparkSession):
        self.spark, self.path, self.count = spark, shared_dir(spark), 0

    def keep(self, df: DataFrame) -> DataFrame:
        self.count += 1
        path = f"{self.path}/{self.count}"
        df.write.option("compression", "zstd").parquet(path)
        return self.spark.read.schema(df.schema).parquet(path)

    def drop(self) -> None:
        path = self.spark._jvm.org.apache.hadoop.fs.Path(self.path)
        path.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(path, True)
        release_shuffles(self.spark)


def release_shuffles(spark: SparkSession) -> None:
    """Let Spark delete the shuffle files of plans that are no longer used: it does so when the driver collects garbage, by default each half hour."""
    gc.collect()
    spark._jvm.System.gc()


def row_id() -> Column:
    """Identity of a row of an unshuffled scan; equal in each reading of the same plan."""
    return F.monotonically_increasing_id()


def free_name(df: DataFrame, name: str) -> str:
    """The name, with underscores added until no column of df has it (names differ by more than case)."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


def as_strings(col: pa.Array) -> pa.Array:
    """Null texts count as empty."""
    col = col.cast(pa.large_string()) if col.type != pa.large_string() else col
    return col.fill_null("") if col.null_count else col


def byte_view(arr: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The UTF-8 bytes of a large_string array and the n+1 offsets into them, from 0."""
    off = np.frombuffer(arr.buffers()[1], dtype=np.int64)[arr.offset : arr.offset + len(arr) + 1]
    data = arr.buffers()[2]
    raw = np.frombuffer(data, dtype=np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[off[0] : off[-1]], off - off[0]


def steps(arr: pa.Array, limit: int = STEP_BYTES) -> Iterator[tuple[int, int]]:
    """Ranges of rows whose texts hold about `limit` bytes; a longer text makes a range of its own."""
    _, off = byte_view(arr)
    lo, n = 0, len(arr)
    while lo < n:
        hi = max(lo + 1, int(np.searchsorted(off, off[lo] + limit, side="right")) - 1)
        yield lo, min(hi, n)
        lo = hi


_MULT = np.uint64(0x9E3779B97F4A7C15)
_IS_SPACE = np.zeros(256, bool)
_IS_SPACE[list(SPACES)] = True
_UPPER = np.zeros(256, np.uint8)
_UPPER[65:91] = 32
#: Bytes of a word that fit the vectorised hash; longer words are hashed one by one.
SHORT = 16
_TAIL = np.array([(1 << 8 * i) - 1 for i in range(9)], dtype=np.uint64)


def mix(h: np.ndarray, salt: int = 0) -> np.ndarray:
    """A 64-bit finaliser: every input bit moves every output bit."""
    with np.errstate(over="ignore"):
        h = h + np.uint64(salt * 2 + 1) * _MULT
        h = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        h = (h ^ (h >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        return h ^ (h >> np.uint64(31))


def word_spans(raw: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Words (runs of bytes that are not ASCII white space) of several texts laid end to end: first byte of each, the byte after it, n+1 offsets of each text's words."""
    n = len(raw)
    if n == 0:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(len(off), np.int64)
    space = _IS_SPACE[raw]
    inner = off[1:-1]
    inner = inner[(inner > 0) & (inner < n)]
    begins = ~space
    begins[1:] &= space[:-1]
    begins[inner] = ~space[inner]
    start = np.flatnonzero(begins)
    ends = ~space
    ends[:-1] &= space[1:]
    ends[inner - 1] = ~space[inner - 1]
    return start, np.flatnonzero(ends) + 1, np.searchsorted(start, off)


def word_hashes(raw: np.ndarray, off: np.ndarray, lower: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Words of several texts laid end to end: two 64-bit hashes of each, first byte, the byte after it, n+1 offsets of each text's words.

    Both hashes together are 128 bits. A word of at most 16 bytes is a 128-bit number that three rounds of a keyed
    permutation carry into them, so two such words of one length never share both; longer ones take xxh3's 128 bits.
    """
    start, stop, word = word_spans(raw, off)
    if not len(start):
        return np.zeros(0, np.uint64), np.zeros(0, np.uint64), start, stop, word
    padded = np.zeros(len(raw) + SHORT, np.uint8)
    padded[: len(raw)] = raw
    if lower:
        padded[: len(raw)] += _UPPER[raw]
    eight = np.ndarray((len(raw) + 8,), "<u8", padded, strides=(1,))  # eight bytes from any place on
    size = stop - start
    low = eight[start] & _TAIL[np.minimum(size, 8)]
    high = eight[start + 8 * (size > 8)] & _TAIL[np.clip(size - 8, 0, 8)]
    key = mix(size.astype(np.uint64), 61)
    low = low ^ mix(high ^ key, 62)
    high = high ^ mix(low, 63)
    low = low ^ mix(high, 64)
    long = np.flatnonzero(size > SHORT)
    if len(long):
        data = padded.data
        digests = b"".join([xxhash.xxh3_128_digest(data[a:z]) for a, z in zip(start[long].tolist(), stop[long].tolist())])
        low[long], high[long] = np.frombuffer(digests, ">u8").reshape(-1, 2).T
    return low, high, start, stop, word


def run_hashes(h: np.ndarray, k: int, salt: int) -> np.ndarray:
    """Hash of every run of k consecutive entries of h (runs across texts included: the caller masks them)."""
    m = len(h) - k + 1
    if m <= 0:
        return np.zeros(0, np.uint64)
    base = np.uint64((0xC2B2AE3D27D4EB4F + 2 * salt * 0x165667B19E3779F9) % 2**64 | 1)
    with np.errstate(over="ignore"):
        out = np.zeros(m, np.uint64)
        for j in range(k):
            out = out * base + h[j : j + m]
    return mix(out, salt)


def sliced(cells: np.ndarray, slices: int) -> list[tuple[int, bytes]]:
    """A sketch as rows (slice number, bytes) so that sketches of many tasks merge slice by slice."""
    return [(i, x.tobytes()) for i, x in enumerate(np.split(cells, slices))]


def merged_slices(df: DataFrame, dtype: str, how: str) -> DataFrame:
    """Merge rows (slice int, cells binary) of all tasks into one row for each slice, streaming.

    how: 'sum' (saturating at the type's limit) or 'or'. A task holds its own slices only, of fixed size.
    """

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, np.ndarray] = {}
        top = np.iinfo(dtype).max
        for b in batches:
            for i, cells in zip(b.column(0).to_pylist(), b.column(1)):
                x = np.frombuffer(cells.as_buffer(), dtype=dtype)
                if i not in held:
                    held[i] = x.copy()
                elif how == "or":
                    held[i] |= x
                else:
                    held[i] = np.where(held[i] > top - x, top, held[i] + x).astype(dtype)
        for i, x in held.items():
            yield pa.RecordBatch.from_arrays([pa.array([i], pa.int32()), pa.array([x.tobytes()], pa.binary())], ["slice", "cells"])

    return df.select("slice", "cells").repartition("slice").mapInArrow(merge, "slice int, cells binary")


#: Bytes of a sketch that the driver takes in one job; a larger one comes partition by partition, a job for each.
AT_ONCE = 1 << 24


def gathered_sketch(df: DataFrame, dtype: str, slices: int, cells: int) -> np.ndarray:
    """A merged sketch on the driver; its size is fixed by parameters and checked."""
    per = cells // slices
    out = np.zeros(cells, dtype)
    for r in df.collect() if out.nbytes <= AT_ONCE else df.toLocalIterator():
        x = np.frombuffer(bytes(r["cells"]), dtype)
        if len(x) != per:
            raise ValueError("slice of unexpected size")
        out[r["slice"] * per : (r["slice"] + 1) * per] = x
    return out
