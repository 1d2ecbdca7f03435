"""Exact top-k inner products with vector-approximation files.

The vectors are quantised once into a compact table, the approximation file: one byte a component on the grid of its block of
vectors. Only that table is scanned for all queries; its cells bound every score from above and below, in blocks of rows
against blocks of queries. A row is a candidate while its upper bound reaches the k-th greatest lower bound of the query.
Exact vectors are then read for candidates alone, in the order of their upper bounds: the first few of each query, and after
that those whose upper bound still reaches the k-th exact score, so the result is certain.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import map_stream, materialise

#: Rows in a block of the approximation file, and queries in a block of queries.
ROWS, QUERIES = 4096, 512
#: Blocks of queries in one task of the query table; more queries give more tasks, never larger ones.
DEALT = 64
#: The greatest magnitude of an integer component; larger ones are taken as this.
MOST = 1 << 60


def integer_vectors(batch: pa.RecordBatch, scale: int) -> list[tuple[np.ndarray, np.ndarray]]:
    """(ids, integer matrix) by length of vector, of the rows (id, vector) of a batch that take part."""
    ids, lists = batch.column(0).to_numpy(), batch.column(1)
    start, size = lists.offsets.to_numpy()[:-1], np.diff(lists.offsets.to_numpy())
    values = lists.values
    flat = values.cast(pa.float64()).fill_null(float("nan")).to_numpy()
    out = []
    for n in np.unique(size):
        at = np.flatnonzero((size == n) & ~np.asarray(lists.is_null()))
        x = flat[start[at][:, None] + np.arange(n)] if n else np.zeros((len(at), 0))
        live = np.isfinite(x).all(1)
        v = np.clip(np.floor(x[live] * scale), -float(MOST), float(MOST)).astype(np.int64)
        out.append((ids[at[live]].astype(np.int64), v))
    return out


def _rows(vectors: DataFrame, id_col: str, vector_col: str) -> DataFrame:
    return vectors.where(F.col(id_col).isNotNull() & F.col(vector_col).isNotNull()).select(F.col(id_col).cast("long").alias("id"), F.col(vector_col).alias("x"))


def approximation_file(vectors: DataFrame, scale: int = 256, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """(n, ids, low, width, cells): a row for up to ROWS vectors of n components; cells hold a byte a component, and component j
    of a cell c lies within low[j] + c * width[j] and the next cell. Written once as Parquet in the shared folder."""

    def cut(batches):
        for b in batches:
            rows = []
            for ids, v in integer_vectors(b, scale):
                for s in range(0, len(ids), ROWS):
                    part = v[s : s + ROWS]
                    low, high = part.min(0), part.max(0)
                    width = (high - low) // 256 + 1
                    cells = ((part - low) // width).astype(np.uint8)
                    rows.append((part.shape[1], ids[s : s + ROWS].tobytes(), low.tobytes(), width.tobytes(), cells.tobytes()))
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int32()), *[pa.array([r[k] for r in rows], pa.binary()) for k in range(1, 5)]], ["n", "ids", "low", "width", "cells"])

    return materialise(map_stream(_rows(vectors, id_col, vector_col), cut, "n int, ids binary, low binary, width binary, cells binary"), "cells")


def bounds(low: np.ndarray, width: np.ndarray, cells: np.ndarray, q: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(upper, lower) bounds of the scores of all rows of a block with all queries. The product is taken in single precision;
    what rounding can change is added to both bounds, so they stay valid."""
    lowf, qf = low.astype(np.float64), q.astype(np.float64)
    scaled = (qf * width).T
    s = (cells.astype(np.float32) @ scaled.astype(np.float32)).astype(np.float64) + lowf @ qf.T
    span = width.astype(np.float64) - 1
    n = len(low) + 4
    slack = n * 2.0**-22 * 255 * np.abs(scaled).sum(0) + n * 2.0**-50 * (np.abs(lowf) + span) @ np.abs(qf).T + 1e-6
    return s + (np.maximum(qf, 0) @ span + slack), s + (np.minimum(qf, 0) @ span - slack)


def _candidates(file: DataFrame, blocks: DataFrame, k: int) -> DataFrame:
    """(query, qv, id, upper, lower) of rows that may be among a query's k best by what one task has seen. Blocks of rows meet
    blocks of queries; the planner broadcasts the queries where they are small, else it pairs partitions."""

    def scan(batches):
        best: dict[bytes, np.ndarray] = {}  # of each query block of this task: the k greatest lower bounds so far
        for b in batches:
            for r in b.to_pylist():
                if r["n"] != r["qn"]:
                    continue
                ids, n = np.frombuffer(r["ids"], np.int64), r["n"]
                qid, qv = np.frombuffer(r["qids"], np.int64), np.frombuffer(r["qvs"], np.int64)
                cells, q = np.frombuffer(r["cells"], np.uint8).reshape(len(ids), n), np.frombuffer(r["q"], np.int64).reshape(len(qid), n)
                upper, lower = bounds(np.frombuffer(r["low"], np.int64), np.frombuffer(r["width"], np.int64), cells, q)
                own = ids[:, None] == qid[None, :]
                if own.any():
                    upper[own] = lower[own] = -np.inf
                key = r["qids"] + r["qvs"]
                have = best.get(key, np.full((k, len(qid)), -np.inf))
                top = np.concatenate([have, np.partition(lower, max(len(ids) - k, 0), axis=0)[-k:]])
                best[key] = top = np.partition(top, len(top) - k, axis=0)[-k:]
                row, col = np.nonzero((upper >= top.min(0)) & (upper > -np.inf))
                if len(row):
                    yield pa.RecordBatch.from_arrays([pa.array(qid[col]), pa.array(qv[col]), pa.array(ids[row]), pa.array(upper[row, col]), pa.array(lower[row, col])], ["query", "qv", "id", "upper", "lower"])

    return materialise(map_stream(file.crossJoin(blocks), scan, "query long, qv long, id long, upper double, lower double"), "bounds")


def _query_table(vectors: DataFrame, every: int, scale: int, id_col: str, vector_col: str) -> tuple[DataFrame, DataFrame]:
    """(queries, blocks): the different query vectors (query, qv, q), and the same in blocks of at most QUERIES."""

    def whole(batches):
        for b in batches:
            for ids, v in integer_vectors(b, scale):
                if len(ids):
                    yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(list(v), pa.list_(pa.int64()))], ["query", "q"])

    def block(batches):
        for b in batches:
            by: dict[int, list] = {}
            for i, h, v in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True):
                by.setdefault(len(v), []).append((i, h, v))
            rows = [(n, rows[s : s + QUERIES]) for n, rows in by.items() for s in range(0, len(rows), QUERIES)]
            parts = [[np.array([r[c] for r in part], np.int64).tobytes() for _, part in rows] for c in range(3)]
            yield pa.RecordBatch.from_arrays([pa.array([n for n, _ in rows], pa.int32()), *[pa.array(p, pa.binary()) for p in parts]], ["qn", "qids", "qvs", "q"])

    mine = _rows(vectors, id_col, vector_col).where(F.col("id") % every == 0)
    queries = map_stream(mine, whole, "query long, q array<long>").distinct().select("query", F.xxhash64("q").alias("qv"), "q")
    queries = materialise(queries, "queries")
    dealt = queries.coalesce(-(-queries.count() // (QUERIES * DEALT)) or 1)
    return queries, materialise(map_stream(dealt, block, "qn int, qids binary, qvs binary, q binary"), "blocks")


def _exact(found: DataFrame, rows: DataFrame, queries: DataFrame, scale: int) -> DataFrame:
    """(query, qv, vec_id, score): the candidates (query, qv, id) with the inner products of their exact vectors."""

    def product(batches):
        for b in batches:
            if not b.num_rows:
                continue
            q = b.column("q")
            at = np.arange(b.num_rows, dtype=np.int64)
            for pos, v in integer_vectors(pa.RecordBatch.from_arrays([pa.array(at), b.column("x")], ["at", "x"]), scale):
                n = v.shape[1]
                mine = pa.compute.equal(pa.compute.list_value_length(q.take(pa.array(pos))), n).to_numpy(zero_copy_only=False)
                pos, v = pos[mine], v[mine]
                w = q.take(pa.array(pos)).flatten().to_numpy().reshape(len(pos), n)
                if n and len(pos) and float(np.abs(v).max()) * float(np.abs(w).max()) * n >= 2.0**62:
                    s = np.array([min(max(sum(int(a) * int(c) for a, c in zip(x, y, strict=True)), -(1 << 63)), (1 << 63) - 1) for x, y in zip(v, w, strict=True)], np.int64)
                else:
                    s = np.einsum("ij,ij->i", v, w) if n else np.zeros(len(pos), np.int64)
                if len(pos):
                    yield pa.RecordBatch.from_arrays([b.column(c).take(pa.array(pos)) for c in ("query", "qv", "id")] + [pa.array(s)], ["query", "qv", "vec_id", "score"])

    joined = found.select("query", "qv", "id").join(rows, "id").join(queries, ["query", "qv"]).select("query", "qv", "id", "x", "q")
    return map_stream(joined, product, "query long, qv long, vec_id long, score long")


def top_k(vectors: DataFrame, k: int = 5, every: int = 50, scale: int = 256, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """(query_id, rank, vec_id, score): for each row whose id is divisible by ``every``, its k best other rows.

    Components are floor(scale * x), at most 2**60 in magnitude; a score beyond the range of a long is the nearest long.
    Vectors that are null or hold a null or non-finite component take no part. Rows that share the query's id are its own and
    take no part; repeated candidate rows count once for each row, repeated query rows once for each different vector. Vectors
    of another length than the query's are compared with none. With fewer than k candidates all are returned; an empty input
    gives no rows; other columns are ignored.
    """
    rows = _rows(vectors, id_col, vector_col)
    queries, blocks = _query_table(vectors, every, scale, id_col, vector_col)
    near = _candidates(approximation_file(vectors, scale, id_col, vector_col), blocks, k)
    greatest = Window.partitionBy("query", "qv").orderBy(F.desc("lower"))
    kth = near.select("query", "qv", "lower", F.row_number().over(greatest).alias("nth")).where(F.col("nth") == k).select("query", "qv", F.col("lower").alias("least"))
    open_ = near.join(kth, ["query", "qv"], "left").where(F.col("least").isNull() | (F.col("upper") >= F.col("least")))
    open_ = open_.groupBy("query", "qv", "id").agg(F.max("upper").alias("upper"))
    order = Window.partitionBy("query", "qv").orderBy(F.desc("upper"), "id")
    open_ = materialise(open_.withColumn("nth", F.row_number().over(order)), "open")
    scores = _exact(open_.where(F.col("nth") <= 2 * k), rows, queries, scale)
    best = Window.partitionBy("query", "qv").orderBy(F.desc("score"), "vec_id")
    if not open_.where(F.col("nth") > 2 * k).isEmpty():
        scores = materialise(scores, "scores")
        sure = scores.withColumn("nth", F.row_number().over(best)).where(F.col("nth") == k).select("query", "qv", F.col("score").alias("least"))
        rest = open_.where(F.col("nth") > 2 * k).join(sure, ["query", "qv"], "left").where(F.col("least").isNull() | (F.col("upper") >= F.col("least")))
        scores = scores.unionByName(_exact(rest, rows, queries, scale))
    ranked = scores.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k)
    return ranked.select(F.col("query").alias("query_id"), F.col("rank").cast("int").alias("rank"), "vec_id", "score")
