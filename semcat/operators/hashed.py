"""Distinct values as pairs of 64-bit hashes, sorted and cut into buckets in Arrow batches, so that a shuffle moves packed hashes
and not rows. Two different values agree in both hashes with a chance of 2**-128. Values of 64 bits go as they are, with their counts."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from semcat.functions.shipping import ship

#: Seed of the second hash; rows that a task sorts at a time; least buckets, and bytes of the input's files for each further one.
SECOND, ROWS, BUCKETS, BYTES = 0x5BD1E995, 1 << 19, 32, 1 << 23
PACKED = "at int, bucket int, n long, n_nonnull long, d binary"
_ARROW = pa.schema([("at", pa.int32()), ("bucket", pa.int32()), ("n", pa.int64()), ("n_nonnull", pa.int64()), ("d", pa.binary())])


def bits_for(frames: Iterable[DataFrame]) -> int:
    """Bits that name a bucket: more of them for larger input, as one task holds a bucket. Input whose size Spark does not know counts as
    BUCKETS * BYTES."""
    size = 0
    for df in frames:
        leaves = df._jdf.queryExecution().optimizedPlan().collectLeaves()
        known = [int(str(leaves.apply(i).stats().sizeInBytes())) for i in range(leaves.size())]
        size += sum(x if x < 1 << 60 else BUCKETS * BYTES for x in known)
    return min(24, max(BUCKETS, size // BYTES).bit_length())


def distinct(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The distinct pairs, in order."""
    if len(a) > 1:  # runs of one value, as in sorted tables
        new = np.concatenate([[True], (a[1:] != a[:-1]) | (b[1:] != b[:-1])])
        a, b = a[new], b[new]
    order = np.argsort(a)
    a, b = a[order], b[order]
    same = a[1:] == a[:-1]
    if same.any() and (same & (b[1:] != b[:-1])).any():  # a hash of two values, or one whose equals lie apart
        order = np.lexsort((b, a))
        a, b = a[order], b[order]
        same = a[1:] == a[:-1]
    keep = np.concatenate([[True], ~(same & (b[1:] == b[:-1]))]) if len(a) else np.zeros(0, bool)
    return a[keep], b[keep]


def pack(df: DataFrame, sets: dict[int, list[str]], bits: int, text: bool = False) -> DataFrame:
    """(at, bucket, n, n_nonnull, d): the distinct values of each column set by buckets of their first hash, for each batch of rows with
    the rows counted; a value with a null column is left out. ``text`` hashes the columns' text, else their typed values."""
    ship(df.sparkSession)
    cells = []
    for cols in sets.values():
        whole, values = F.lit(True), [F.col(c).cast("string") if text else F.col(c) for c in cols]
        for c in cols:
            whole = whole & F.col(c).isNotNull()
        cells += [F.when(whole, F.xxhash64(*values)), F.when(whole, F.xxhash64(F.lit(SECOND), *values))]
    places = list(sets)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def packed(held: list[pa.RecordBatch]) -> pa.RecordBatch:
            table, out = pa.Table.from_batches(held), []
            for i, at in enumerate(places):
                a, b = (table.column(2 * i + k).drop_null().to_numpy().view(np.uint64) for k in (0, 1))
                n_nonnull = len(a)
                a, b = distinct(a, b)
                bucket = (a >> np.uint64(64 - bits)).astype(np.int64)
                ends = np.concatenate([[0], np.flatnonzero(np.diff(bucket)) + 1, [len(a)]]) if len(a) else [0, 0]
                for k, (x, y) in enumerate(zip(ends[:-1], ends[1:], strict=True)):
                    counts = (table.num_rows, n_nonnull) if k == 0 else (0, 0)
                    out.append((at, int(bucket[x]) if y else 0, *counts, a[x:y].tobytes() + b[x:y].tobytes()))
            return pa.RecordBatch.from_arrays([pa.array(list(x), f.type) for x, f in zip(zip(*out, strict=True), _ARROW, strict=True)], schema=_ARROW)

        held, rows = [], 0
        for batch in batches:
            held.append(batch)
            rows += batch.num_rows
            if rows >= ROWS:
                yield packed(held)
                held, rows = [], 0
        if rows:
            yield packed(held)

    return df.select(*[c.alias(f"h{i}") for i, c in enumerate(cells)]).mapInArrow(run, PACKED)


def unpack(parts: pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """The distinct pairs of packed parts of one bucket."""
    found = [np.frombuffer(x.as_buffer(), np.uint64) for x in parts if len(x.as_buffer())]
    if not found:
        return np.zeros(0, np.uint64), np.zeros(0, np.uint64)
    return distinct(np.concatenate([x[: len(x) // 2] for x in found]), np.concatenate([x[len(x) // 2 :] for x in found]))


#: Counted values: packed by bucket, and what the merge of a bucket gives; values that a task holds of a column before it sends them.
COUNTED, HELD = "at int, bucket int, n long, d binary", 1 << 18
_COUNTED = pa.schema([("at", pa.int32()), ("bucket", pa.int32()), ("n", pa.int64()), ("d", pa.binary())])
#: An odd factor and its inverse: 64-bit integers are spread over all buckets and brought back without loss.
_ODD = 0x9E3779B97F4A7C15
_BACK = pow(_ODD, -1, 1 << 64)


def spread(v: np.ndarray, factor: int = _ODD) -> np.ndarray:
    """Another 64-bit integer for each; with ``_BACK`` the one it came from."""
    v = v.view(np.uint64) * np.uint64(factor)
    return (v ^ (v >> np.uint64(32))) * np.uint64(factor)


def add_up(v: np.ndarray, n: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """The distinct values in order and the sums of their counts, which are 1 where none are given."""
    if n is None:
        v = np.sort(v)
    else:
        order = np.argsort(v)
        v, n = v[order], n[order]
    first = np.flatnonzero(np.concatenate([[True], v[1:] != v[:-1]])) if len(v) else np.zeros(0, np.int64)
    sums = np.diff(np.append(first, len(v))) if n is None else np.add.reduceat(n, first) if len(v) else n
    return v[first], sums.astype(np.int64)


def pack_counts(df: DataFrame, places: list[int], bits: int) -> DataFrame:
    """(at, bucket, n, d): the distinct values of each column, which are longs or doubles, with their counts, spread and packed by bucket;
    bucket -1 counts nulls. A task adds up what it has seen of a column of few values and sends it at its end."""
    ship(df.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def packed(at: int, v: np.ndarray, n: np.ndarray) -> Iterator[tuple[int, int, int, bytes]]:
            bucket = (v >> np.uint64(64 - bits)).astype(np.int64)
            ends = np.concatenate([[0], np.flatnonzero(np.diff(bucket)) + 1, [len(v)]])
            for x, y in zip(ends[:-1], ends[1:], strict=True):
                yield at, int(bucket[x]), 0, v[x:y].tobytes() + n[x:y].tobytes()

        def rows(out: list) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(list(x), f.type) for x, f in zip(zip(*out, strict=True), _COUNTED, strict=True)], schema=_COUNTED)

        few, nulls = {}, dict.fromkeys(places, 0)

        def add(held: list[pa.RecordBatch]) -> list:
            table, out = pa.Table.from_batches(held), []
            for i, at in enumerate(places):
                column = table.column(i)
                nulls[at] += column.null_count
                v = column.drop_null().to_numpy()
                if v.dtype == np.float64:
                    v = np.where(np.isnan(v), np.nan, v)  # one NaN
                if not len(v):
                    continue
                v, n = add_up(spread(v))
                if at in few and len(v) <= HELD:
                    v, n = add_up(*(np.concatenate(x) for x in zip(few.pop(at), (v, n), strict=True)))
                if len(v) <= HELD:
                    few[at] = v, n
                else:
                    out += packed(at, v, n)
            return out

        held, size = [], 0
        for batch in batches:
            held.append(batch)
            size += batch.num_rows
            if size >= ROWS:
                if out := add(held):
                    yield rows(out)
                held, size = [], 0
        out = add(held) if size else []
        out += [r for at, (v, n) in few.items() for r in packed(at, v, n)] + [(at, -1, n, b"") for at, n in nulls.items() if n]
        if out:
            yield rows(out)

    return df.mapInArrow(run, COUNTED)


def merge_counts(packed: DataFrame, real: list[int]) -> DataFrame:
    """(at, n, v, x): the distinct values of packed counts, nulls included; v holds longs, and x the doubles of the columns in ``real``."""
    schema = pa.schema([("at", pa.int32()), ("n", pa.int64()), ("v", pa.int64()), ("x", pa.float64())])

    def merge(part: pa.Table) -> pa.Table:
        at = part.column("at")[0].as_py()
        v = x = None
        if part.column("bucket")[0].as_py() < 0:
            n = np.array([pc.sum(part.column("n")).as_py()])
        else:
            found = [np.frombuffer(d.as_buffer(), np.uint64) for d in part.column("d")]
            v, n = add_up(np.concatenate([d[: len(d) // 2] for d in found]), np.concatenate([d[len(d) // 2 :] for d in found]).view(np.int64))
            v = spread(v, _BACK)
            v, x = (None, v.view(np.float64)) if at in real else (v.view(np.int64), None)
        columns = [pa.nulls(len(n), f.type) if y is None else pa.array(y, f.type) for y, f in zip((np.full(len(n), at, np.int32), n, v, x), schema, strict=True)]
        return pa.Table.from_arrays(columns, schema=schema)

    return packed.groupBy("at", "bucket").applyInArrow(merge, "at int, n long, v long, x double")
