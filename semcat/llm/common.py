"""Shared plumbing of the training-data operators: scratch tables, Arrow text buffers, hashing."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from semcat.functions.shipping import ship

_LOCAL: dict[str, str] = {}


def _folder(spark: SparkSession) -> str:
    base = spark.conf.get("spark.checkpoint.dir", None)
    app = spark.sparkContext.applicationId
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = _LOCAL.setdefault(app, tempfile.mkdtemp(prefix="semcat-"))
    return f"{base.rstrip('/')}/semcat-{app}"


def scratch(spark: SparkSession, name: str) -> str:
    """A fresh path in the application's part of the shared checkpoint folder; where none is set, a temporary folder, but only
    with a local master (tests). ``clear`` removes them all."""
    return f"{_folder(spark)}/{name}-{uuid.uuid4().hex}"


def _remove(spark: SparkSession, path: str) -> None:
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()).delete(at, True)


def clear(spark: SparkSession) -> None:
    """Remove all intermediate tables of this application; call it when the results have been written."""
    _remove(spark, _folder(spark))


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Cut the lineage: write ``df`` as Parquet into the shared folder and read it back."""
    spark = df.sparkSession
    path = scratch(spark, name)
    df.write.option("compression", "zstd").parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.scratch_path = path
    return out


def discard(*tables: DataFrame) -> None:
    """Remove intermediate tables that no result reads any more."""
    for t in tables:
        _remove(t.sparkSession, t.scratch_path)


def map_batches(df: DataFrame, fn: Callable[[pa.RecordBatch], pa.RecordBatch | None], schema: StructType | str) -> DataFrame:
    """``mapInArrow`` with a function of one batch."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                out = fn(b)
                if out is not None and out.num_rows:
                    yield out

    return map_stream(df, run, schema)


def map_stream(df: DataFrame, run: Callable, schema: StructType | str) -> DataFrame:
    """``mapInArrow`` with a function of all batches of a task; workers get this package first."""
    ship(df.sparkSession)
    return df.mapInArrow(run, schema)


def utf8(col: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(bytes, offsets, is_null) of a string or binary column; offsets start at 0; a null has no bytes."""
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks()
    if not pa.types.is_large_binary(col.type):
        col = col.cast(pa.binary()).cast(pa.large_binary()) if pa.types.is_string(col.type) else col.cast(pa.large_binary())
    n = len(col)
    nulls = np.asarray(col.is_null())
    buffers = col.buffers()
    offsets = np.frombuffer(buffers[1], np.int64, n + 1, col.offset * 8)
    data = np.frombuffer(buffers[2], np.uint8) if buffers[2] is not None else np.zeros(0, np.uint8)
    if nulls.any() and (np.diff(offsets)[nulls] > 0).any():
        return utf8(col.fill_null(b""))[:2] + (nulls,)
    return data[offsets[0] : offsets[-1]], offsets - offsets[0], nulls


def blocks(offsets: np.ndarray, most: int = 1 << 19) -> Iterator[tuple[int, int]]:
    """Runs of documents of about ``most`` bytes, so that temporary arrays stay small; a longer document is its own run."""
    i, n = 0, len(offsets) - 1
    while i < n:
        j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + most, "right")) - 1)
        yield i, min(j, n)
        i = min(j, n)


def mix(h: np.ndarray) -> np.ndarray:
    """A finaliser that spreads all bits of unsigned 64-bit integers (public splitmix64 constants)."""
    h = h ^ (h >> np.uint64(30))
    h = h * np.uint64(0xBF58476D1CE4E5B9)
    h = h ^ (h >> np.uint64(27))
    h = h * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


_BYTE = mix(np.arange(1, 257, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))
_BASE, _POWERS = 0x5851F42D4C957F2D, [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the odd base and of its inverse modulo 2**64, grown on demand."""
    if len(_POWERS[0]) < n:
        size = 1 << (n - 1).bit_length()
        for i, base in enumerate((_BASE, pow(_BASE, -1, 1 << 64))):
            p = np.full(size, base, np.uint64)
            p[0] = 1
            _POWERS[i] = np.cumprod(p, dtype=np.uint64)
    return _POWERS[0], _POWERS[1]


def span_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """64-bit hashes of the byte spans [start, end) of ``data``: prefix sums of a polynomial hash, then mixed."""
    if not len(starts):
        return np.zeros(0, np.uint64)
    p, inv = _powers(len(data) + 1)
    acc = np.zeros(len(data) + 1, np.uint64)
    np.cumsum(_BYTE[data] * p[: len(data)], out=acc[1:])
    h = (acc[ends] - acc[starts]) * inv[starts]
    return mix(h + (ends - starts).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))


#: Byte tables: A-Z to a-z; and the white space that separates words (space, and 09 to 0D).
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
SPACE = np.zeros(256, bool)
SPACE[[32, *range(9, 14)]] = True


def word_spans(data: np.ndarray, offsets: np.ndarray, cls: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(start, end, document index) of the words of a block. ``cls`` maps bytes to classes; class 0 separates,
    and a change of class starts a new token; by default words are runs of bytes that are not white space."""
    c = cls[data] if cls is not None else (~SPACE[data]).astype(np.uint8)
    n = len(c)
    if not n:
        e = np.zeros(0, np.int64)
        return e, e, e
    edge = np.zeros(n + 1, bool)
    edge[offsets[(offsets >= 0) & (offsets <= n)]] = True
    change = np.empty(n + 1, bool)
    change[0] = change[n] = True
    np.not_equal(c[1:], c[:-1], out=change[1:n])
    change |= edge
    at = np.flatnonzero(change)
    starts, ends = at[:-1], at[1:]
    live = c[starts] > 0
    starts, ends = starts[live], ends[live]
    return starts, ends, np.searchsorted(offsets, starts, "right") - 1


def fold(column: str, modulus: int):
    """The documented fold of a row: crc32 of the identifier as text, modulo ``modulus`` (null ids: fold of the empty text)."""
    return F.crc32(F.coalesce(F.col(column).cast("string"), F.lit("")).cast("binary")) % modulus


#: Bits of the fixed-size membership filter: 512 KiB, whatever the input.
FILTER_BITS = 1 << 22


def membership_filter(keys: DataFrame, column: str, hashed: bool = False) -> np.ndarray:
    """A bitmap of FILTER_BITS bits with the hashes of a long column (or the column itself, if it is a hash already). Its size does not depend on the data: with very
    many keys it fills up and lets everything pass, which costs time but never changes a result."""
    h = F.pmod(F.col(column) if hashed else F.xxhash64(F.col(column)), F.lit(FILTER_BITS))
    rows = keys.select(h.alias("h")).groupBy(F.floor(F.col("h") / 32768).cast("int").alias("part")).agg(F.bitmap_construct_agg(F.col("h") % 32768).alias("bits")).collect()
    out = np.zeros(FILTER_BITS, bool)
    for r in rows:
        bits = np.unpackbits(np.frombuffer(r["bits"], np.uint8), bitorder="little")
        out[r["part"] * 32768 : (r["part"] + 1) * 32768] = bits[:32768]
    return np.packbits(out, bitorder="little")


def may_contain(column: str):
    """The position of a key in a membership filter, as a Spark column."""
    return F.pmod(F.xxhash64(F.col(column)), F.lit(FILTER_BITS))


def passes(bits: np.ndarray, at: np.ndarray) -> np.ndarray:
    return (bits[at >> 3] >> (at & 7).astype(np.uint8)) & 1 == 1
