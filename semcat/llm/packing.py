"""Packing of token pieces into sequences as a cutting-stock problem.

Documents are cut into full sequences and one remainder. The remainders' histogram (by length class) is the demand of a
cutting-stock problem: a linear program over patterns, whose columns are priced by a knapsack dynamic program. The rounded
patterns are laid out as intervals of ranks, and each remainder finds its sequence by its rank within its class.
"""

from __future__ import annotations

import json
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .bpe import byte_alphabet
from .common import map_batches, materialise

#: Ranks within a length class are counted in this many hash buckets first, so no task ranks a whole class.
BUCKETS = 1024


#: Fixed value: the pre-tokenizer pattern of byte-level vocabularies.
PATTERN = r"'(?:[sdmt]|ll|ve|re)| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
_ENCODERS: dict[str, object] = {}


def encoder(path: str):
    """An encoder with the ids of the tokenizers file at ``path`` (byte-level BPE whose ids are its merge ranks). The ranks
    are read from that file and handed to the tiktoken library, which encodes whole texts about four times as fast; special
    tokens that stand in a text get their own ids, as the tokenizers library gives them."""
    if path not in _ENCODERS:
        import tiktoken

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        if spec["model"]["type"] != "BPE" or spec["pre_tokenizer"]["type"] != "ByteLevel" or spec["pre_tokenizer"]["add_prefix_space"] or spec["normalizer"]:
            raise ValueError("not a byte-level BPE without normalizer")
        byte = {c: i for i, c in enumerate(byte_alphabet())}
        special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        ranks = {bytes(byte[c] for c in t): i for t, i in spec["model"]["vocab"].items() if t not in special}
        _ENCODERS[path] = tiktoken.Encoding("ranks", pat_str=PATTERN, mergeable_ranks=ranks, special_tokens=special)
    return _ENCODERS[path]


def token_pieces(documents: DataFrame, tokenizer: str, capacity: int, end_id: int, id_col: str, text_col: str) -> DataFrame:
    """(doc_id, start, length, ids_crc32, doc_tokens): each document's ids and the end id, cut at every ``capacity`` ids."""

    def cut(b: pa.RecordBatch) -> pa.RecordBatch:
        rows = [[] for _ in range(5)]
        enc, step = encoder(tokenizer), 4 * capacity
        end = np.array([end_id], "<u4").tobytes()
        for i, t in zip(b.column(0).to_pylist(), b.column(1), strict=True):
            e = enc.encode_to_numpy(t.as_py() or "", allowed_special="all").astype("<u4").tobytes() + end
            for at in range(0, len(e), step):
                part = e[at : at + step]
                for c, v in zip(rows, (i, at // 4, len(part) // 4, zlib.crc32(part), len(e) // 4), strict=True):
                    c.append(v)
        return pa.RecordBatch.from_arrays([pa.array(r, pa.int64()) for r in rows], ["doc_id", "start", "length", "ids_crc32", "doc_tokens"])

    source = documents.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"))
    return map_batches(source, cut, "doc_id long, start long, length long, ids_crc32 long, doc_tokens long")


def cutting_stock(demand: np.ndarray, units: int, most_columns: int = 2000, patience: int = 150) -> list[tuple[np.ndarray, int]]:
    """Patterns (pieces of each class, times used) that cover ``demand[c]`` pieces of class c + 1 units in bins of ``units``.

    Column generation: the basis starts with patterns of one class; duals of the restricted program price a new pattern by an
    unbounded knapsack over the capacity; the simplex step exchanges it for a basic one until none improves (or the number
    of bins has not improved for ``patience`` exchanges, as happens in degenerate programs). The solution is rounded down,
    and what is left is filled first fit by decreasing length; every piece is placed in any case."""
    classes = np.flatnonzero(demand > 0)
    if not len(classes):
        return []
    size, need = classes + 1, demand[classes].astype(float)
    m = len(size)
    basis = np.diag((units // size).astype(float))
    inverse, best, stalled = np.diag(1 / np.diag(basis)), np.inf, 0
    for _ in range(most_columns):
        dual = inverse.sum(0)
        value, choice = np.zeros(units + 1), np.full(units + 1, -1)
        for c in range(1, units + 1):
            fits = size <= c
            if fits.any():
                v = np.where(fits, value[np.maximum(c - size, 0)] + dual, -1)
                k = int(v.argmax())
                value[c], choice[c] = (v[k], k) if v[k] > value[c - 1] + 1e-12 else (value[c - 1], -1)
        if value[units] <= 1 + 1e-7:
            break
        column, c = np.zeros(m), units
        while c > 0:
            if choice[c] < 0:
                c -= 1
            else:
                column[choice[c]] += 1
                c -= size[choice[c]]
        move, x = (inverse * column).sum(1), (inverse * need).sum(1)  # no LAPACK: small, and exactness comes from the rounding
        ratio = np.where(move > 1e-9, np.maximum(x, 0) / np.where(move > 1e-9, move, 1), np.inf)
        row = int(ratio.argmin())
        basis[:, row] = column
        inverse[row] /= move[row]
        move[row] = 0
        inverse -= np.outer(move, inverse[row])
        stalled = 0 if x.sum() < best - 1e-6 else stalled + 1
        best = min(best, x.sum())
        if stalled > patience:
            break
    x = (inverse * need).sum(1)
    out, left = [], demand[classes].astype(np.int64).copy()
    for k in range(m):
        pattern = np.round(basis[:, k]).astype(np.int64)
        times = int(max(0, np.floor(x[k] + 1e-9)))
        used = pattern > 0
        times = min(times, int((left[used] // pattern[used]).min())) if used.any() else 0
        if times > 0:
            left -= times * pattern
            out.append((pattern, times))
    while left.sum() > 0:
        pattern, room = np.zeros(m, np.int64), units
        for k in range(m - 1, -1, -1):
            take = min(int(left[k]), room // size[k])
            pattern[k] += take
            room -= take * size[k]
        used = pattern > 0
        times = int((left[used] // pattern[used]).min())
        left -= times * pattern
        out.append((pattern, times))
    full = []
    for pattern, times in out:
        wide = np.zeros(len(demand), np.int64)
        wide[classes] = pattern
        full.append((wide, times))
    return full


def pack(documents: DataFrame, tokenizer: str, capacity: int = 2048, grain: int = 16, end_id: int = 1, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset) for each piece.

    Full pieces are sequences of their own; remainders are packed by the cutting-stock plan over capacity / grain length
    classes (lengths rounded up to ``grain``, so a sequence never overflows). The plan sees only the histogram.
    Defined cases: a null or empty text is one piece with the end id; a null id stays null; repeated rows are packed each
    for themselves; other columns are ignored; an empty input gives no rows.
    """
    spark = documents.sparkSession
    pieces = materialise(token_pieces(documents, tokenizer, capacity, end_id, id_col, text_col), "pieces")
    units = capacity // grain
    cls = F.ceil(F.col("length") / grain).cast("int")
    keyed = pieces.withColumns({"class": cls, "bucket": F.pmod(F.xxhash64("doc_id", "start", "ids_crc32", "length"), F.lit(BUCKETS)).cast("int")})
    counts = keyed.groupBy("class", "bucket").agg(F.count("*").alias("n"))
    before = counts.withColumn("base", F.sum("n").over(Window.partitionBy("class").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)))
    before = materialise(before.select("class", "bucket", "n", F.coalesce("base", F.lit(0)).alias("base")), "ranks")
    demand = np.zeros(units, np.int64)
    for r in before.groupBy("class").agg(F.sum("n").alias("n")).collect():
        demand[r["class"] - 1] = r["n"]
    whole = int(demand[units - 1])
    demand[units - 1] = 0
    rows, sequence = [(units, 0, max(whole, 1), 1, 0, 0)], whole
    done = np.zeros(units, np.int64)
    for pattern, times in cutting_stock(demand, units):
        slot = 0
        for c in np.flatnonzero(pattern)[::-1]:
            a = int(pattern[c])
            rows.append((int(c) + 1, int(done[c]), int(done[c]) + a * times, a, sequence, slot))
            done[c] += a * times
            slot += a
        sequence += times
    plan = spark.createDataFrame(rows, "class int, lo long, hi long, each long, first long, slot long")
    local = F.row_number().over(Window.partitionBy("class", "bucket").orderBy("doc_id", "start", "ids_crc32", "length")) - 1
    ranked = keyed.withColumn("local", local).join(before.select("class", "bucket", "base"), ["class", "bucket"]).withColumn("rank", F.col("local") + F.col("base"))
    # the plan has at most a few times (capacity / grain) ** 2 rows, whatever the input
    placed = ranked.join(F.broadcast(plan.withColumnRenamed("class", "kind")), (F.col("class") == F.col("kind")) & (F.col("rank") >= F.col("lo")) & (F.col("rank") < F.col("hi")))
    nth = F.col("rank") - F.col("lo")
    placed = placed.withColumns({"sequence_id": F.col("first") + F.floor(nth / F.col("each")).cast("long"), "place": F.col("slot") + nth % F.col("each")})
    along = Window.partitionBy("sequence_id").orderBy("place").rowsBetween(Window.unboundedPreceding, -1)
    return placed.select("doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", F.coalesce(F.sum("length").over(along), F.lit(0)).cast("long").alias("offset"))
