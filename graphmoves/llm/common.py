"""Shared pieces of the corpus operators: table access, snapshots, zero-copy text views, rolling hashes."""

from __future__ import annotations

import tempfile
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Ids from here on stand for rows without one; they sort behind all others.
NO_ID = 2**62


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables, read by Spark only, so any store Spark knows will do."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: the session's checkpoint folder.

    Only a session on one machine (tests) that names none gets a temporary one; a cluster has to name it.
    """
    jsc = spark.sparkContext._jsc.sc()
    if jsc.getCheckpointDir().isEmpty():
        named = spark.conf.get("spark.checkpoint.dir", None)
        if named is None and not jsc.isLocal():
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        spark.sparkContext.setCheckpointDir(named or tempfile.mkdtemp(prefix="graphmoves-"))
    return jsc.getCheckpointDir().get()


def snapshot(df: DataFrame, compression: str = "zstd") -> DataFrame:
    """Cut lineage by a Parquet table in the shared folder; it outlives lost executors."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/t{uuid.uuid4().hex}"
    df.write.option("compression", compression).parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._snapshot_path = path
    return out


def small_batches(spark: SparkSession, rows: int = 1000, size: str = "4m") -> None:
    """Arrow batches between the JVM and Python of at most so many rows and about so many bytes, whatever texts are like.

    Both are run-time settings of the session; a smaller number of rows that it has set stays.
    """
    now = int(spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch", "0"))
    if not 0 < now <= rows:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", rows)
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", size)


def drop_snapshot(df: DataFrame) -> None:
    """Delete the files of a snapshot that no later plan reads."""
    spark = df.sparkSession
    path = spark._jvm.org.apache.hadoop.fs.Path(df._snapshot_path)
    path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def doc_key(doc_id: str = "doc_id", text: str = "text") -> list[Column]:
    """Columns d, tk: they tell documents apart even where ids are null or repeated.

    Rows that agree in both are repeats of one row and get equal results.
    """
    none = F.lit(NO_ID) + F.xxhash64(F.col(text), F.lit(1)).bitwiseAND(F.lit(NO_ID - 1))
    return [F.coalesce(F.col(doc_id).cast("long"), none).alias("d"), F.xxhash64(text).alias("tk")]


def real_id(d: str = "d") -> Column:
    return F.when(F.col(d) < NO_ID, F.col(d))


def packed(docs: DataFrame) -> DataFrame:
    """All columns of a row in one struct `doc`, beside which an operator's own names can't clash."""
    return docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("doc"))


def unpacked(df: DataFrame, columns: list[str]) -> DataFrame:
    return df.select(*[F.col("doc").getField(c).alias(c) for c in columns])


def utf8(arr: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and offsets (n + 1) of an Arrow string or binary array, without a copy; null counts as empty."""
    if isinstance(arr, pa.ChunkedArray):
        arr = arr.combine_chunks()
    if arr.null_count:
        arr = arr.fill_null(b"" if pa.types.is_binary(arr.type) or pa.types.is_large_binary(arr.type) else "")
    wide = pa.types.is_large_string(arr.type) or pa.types.is_large_binary(arr.type)
    _, offsets, data = arr.buffers()
    if offsets is None or len(arr) == 0:
        return np.empty(0, np.uint8), np.zeros(len(arr) + 1, np.int64)
    off = np.frombuffer(offsets, np.int64 if wide else np.int32)[arr.offset : arr.offset + len(arr) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None else np.empty(0, np.uint8)
    return raw[off[0] : off[-1]], off - off[0]


def blocks(offsets: np.ndarray, limit: int = 1 << 18):
    """Ranges of rows whose bytes stay near `limit` (some tens of bytes of arrays go with each byte); a longer row stands alone."""
    lo, n = 0, len(offsets) - 1
    while lo < n:
        hi = max(lo + 1, int(np.searchsorted(offsets, offsets[lo] + limit, side="right")) - 1)
        yield lo, hi
        lo = hi


def mix64(x: np.ndarray) -> np.ndarray:
    """Finaliser that spreads every bit of a 64-bit value (the public splitmix64 constants)."""
    with np.errstate(over="ignore"):
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class Rolling:
    """Polynomial hashes mod 2**64 of any byte range, from prefix sums over a random byte table."""

    BASE = 0x9E3779B97F4A7C15 | 1

    def __init__(self, fold_case: bool = False, seed: int = 20):
        self.table = np.random.default_rng(seed).integers(0, 2**63, 256, dtype=np.int64).astype(np.uint64) * np.uint64(2) + np.uint64(1)
        if fold_case:
            self.table[65:91] = self.table[97:123]
        self.up = self.down = np.ones(1, np.uint64)

    def _powers(self, n: int) -> None:
        if len(self.up) < n:
            def powers(b):
                steps = np.full(n, b & (2**64 - 1), np.uint64)
                steps[0] = 1
                return np.multiply.accumulate(steps)

            self.up, self.down = powers(self.BASE), powers(pow(self.BASE, -1, 2**64))

    def prefix(self, data: np.ndarray) -> np.ndarray:
        self._powers(len(data) + 1)
        out = np.zeros(len(data) + 1, np.uint64)
        np.cumsum(self.table[data] * self.up[: len(data)], out=out[1:])
        return out

    def ranges(self, prefix: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        return (prefix[end] - prefix[start]) * self.down[start]

    def grams(self, prefix: np.ndarray, k: int) -> np.ndarray:
        """Hash of the k bytes from each position on."""
        n = len(prefix) - k
        return (prefix[k:] - prefix[:n]) * self.down[:n] if n > 0 else np.empty(0, np.uint64)


SPACES = np.zeros(256, bool)
SPACES[[32, *range(9, 14)]] = True


def words_of(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start and end of each run of non-space bytes, cut at document bounds; and the word number at which each document begins."""
    solid = ~SPACES[data]
    first = solid.copy()
    first[1:] &= ~solid[:-1]
    last = solid.copy()
    last[:-1] &= ~solid[1:]
    cuts = offsets[1:-1]
    cuts = cuts[(cuts > 0) & (cuts < len(data))]
    first[cuts] = solid[cuts]
    last[cuts - 1] = solid[cuts - 1]
    start = np.flatnonzero(first)
    end = np.flatnonzero(last) + 1
    return start, end, np.searchsorted(start, offsets)
