"""Column domains and the overlap of all column pairs in one shuffle of distinct values."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from semcat.operators import hashed
from semcat.operators.evidence import ColumnEvidence
from semcat.operators.profile import union_all
from semcat.sources.bundle import SourceBundle

INTEGER = ("tinyint", "smallint", "int", "bigint")


def integer_columns(bundle: SourceBundle) -> list[tuple[str, str]]:
    return [(t, f.name) for t, df in bundle.tables.items() for f in df.schema.fields if f.dataType.simpleString() in INTEGER]


def joinable(evidence: dict[tuple[str, str], ColumnEvidence]) -> list[tuple[str, str]]:
    """Columns that can refer to something: whole numbers and short texts, whatever their declared type. Fractions, times and
    prose cannot equal a key of these families, so they are left out without losing a pair."""
    return [k for k, e in evidence.items() if e.family in ("integer", "text")]


def build(bundle: SourceBundle, columns: list[tuple[str, str]]) -> DataFrame:
    """(col, value): the distinct non-null values of each column as canonical text; whole numbers lose a leading plus or
    zeros only when stored as numbers, so the text 007 stays apart from 7. Equal values of a partition are combined before the
    one shuffle."""
    by: dict[str, list[str]] = {}
    for t, c in columns:
        by.setdefault(t, []).append(c)
    parts = []
    for t, cols in by.items():
        cells = F.explode(F.array(*[F.struct(F.lit(f"{t}.{c}").alias("col"), F.col(c).cast("string").alias("value")) for c in cols]))
        parts.append(bundle[t].select(cells.alias("r")).select("r.*").where("value is not null"))
    return union_all(parts).distinct()


def pair_overlap(domain: DataFrame, targets: list[str]) -> DataFrame:
    """(source, target, n_common, n_source): every pair of a column with a key of another table that share a value. Each value
    meets its columns once; it has at most as many rows as there are columns, so no value is a hot group."""
    by_value = domain.groupBy("value").agg(F.collect_set("col").alias("cols"))
    keys = F.filter("cols", lambda c: c.isin(targets))
    sides = by_value.select(F.explode("cols").alias("source"), keys.alias("keys"))
    # a null target stands for the value itself, so that sizes come from the same pass
    pairs = sides.select("source", F.explode(F.array_append("keys", F.lit(None).cast("string"))).alias("target"))
    counted = pairs.groupBy("source", "target").agg(F.count("*").alias("n"))
    sizes = counted.where("target is null").select("source", F.col("n").alias("n_source"))
    other = F.split("source", r"\.")[0] != F.split("target", r"\.")[0]
    return counted.where(other).withColumnRenamed("n", "n_common").join(sizes, "source").select("source", "target", "n_common", "n_source")


#: Columns that one mask of a value's columns holds.
MASK = 63


def overlap_by_masks(bundle: SourceBundle, columns: list[tuple[str, str]], targets: list[str]) -> DataFrame:
    """The rows of ``pair_overlap`` from one shuffle: a value goes through it as two hashes of its text, packed by column and bucket after
    the copies of a batch are combined; a bucket then counts its values by masks of the columns that hold them, and pairs are
    made of the few masks."""
    names, words = [f"{t}.{c}" for t, c in columns], range((len(columns) + MASK - 1) // MASK)
    by: dict[str, dict[int, list[str]]] = {}
    for i, (t, c) in enumerate(columns):
        by.setdefault(t, {})[i] = [c]
    frames = {t: bundle[t].select(*[c for (c,) in at.values()]) for t, at in by.items()}
    bits = hashed.bits_for(frames.values())
    schema = ", ".join([*[f"m{w} long" for w in words], "k long"])

    def count(part: pa.Table) -> pa.Table:
        sides = [(i, *hashed.unpack(part.filter(pc.equal(part.column("at"), i)).column("d"))) for i in pc.unique(part.column("at")).to_pylist()]
        a, b = (np.concatenate([x[k] for x in sides]) for k in (1, 2))
        column = np.concatenate([np.full(len(x), i) for i, x, _ in sides])
        if not len(a):
            return pa.table({**{f"m{w}": pa.array([], pa.int64()) for w in words}, "k": pa.array([], pa.int64())})
        order = np.lexsort((b, a))
        a, b, column = a[order], b[order], column[order]
        first = np.concatenate([[0], np.flatnonzero((a[1:] != a[:-1]) | (b[1:] != b[:-1])) + 1])
        bit = np.int64(1) << (column % MASK).astype(np.int64)
        masks = np.stack([np.bitwise_or.reduceat(np.where(column // MASK == w, bit, 0), first) for w in words])
        found, k = np.unique(masks, axis=1, return_counts=True)
        return pa.table({**{f"m{w}": pa.array(found[w], pa.int64()) for w in words}, "k": pa.array(k, pa.int64())})

    packed = union_all([hashed.pack(frames[t], at, bits, text=True) for t, at in by.items()])
    masks = packed.groupBy("bucket").applyInArrow(count, schema).groupBy(*[f"m{w}" for w in words]).agg(F.sum("k").alias("k"))
    counted = count_pairs(masks, [list(enumerate(names))], targets)
    sizes = counted.where("target is null").select("source", F.col("n").alias("n_source"))
    other = F.split("source", r"\.")[0] != F.split("target", r"\.")[0]
    return counted.where(other).withColumnRenamed("n", "n_common").join(F.broadcast(sizes), "source").select("source", "target", "n_common", "n_source")  # a row a column


def count_pairs(masks: DataFrame, groups: list[list[tuple[int, str]]], targets: list[str]) -> DataFrame:
    """(source, target, n) from counted masks (m0, m1, ..., k), within each group of columns (place in the mask, name): values of a column
    that a key has too, and all its values where the target is null."""
    bit = lambda i: F.col(f"m{i // MASK}").bitwiseAND(F.lit(1 << i % MASK).cast("long")) != 0
    held = [F.filter(F.array(*[F.when(bit(i), F.lit(n)) for i, n in names]), lambda c: c.isNotNull()) for names in groups if names]
    sides = masks.select(F.explode(F.array(*held)).alias("cols"), "k").select(F.explode("cols").alias("source"), F.filter("cols", lambda c: c.isin(targets)).alias("keys"), "k")
    pairs = sides.select("source", F.explode(F.array_append("keys", F.lit(None).cast("string"))).alias("target"), "k")
    return pairs.groupBy("source", "target").agg(F.sum("k").alias("n"))


def pair_overlap_naive(domain: DataFrame, pairs: list[tuple[str, str]]) -> DataFrame:
    """One semi join for each pair: the plain baseline."""
    out = []
    for s, t in pairs:
        a, b = domain.where(F.col("col") == s).select("value"), domain.where(F.col("col") == t).select("value")
        out.append(a.join(b, "value", "left_semi").agg(F.count("*").alias("n_common")).select(F.lit(s).alias("source"), F.lit(t).alias("target"), "n_common"))
    return union_all(out).where("n_common > 0")


def sampled_overlap(domain: DataFrame, targets: list[str], share: int = 50) -> DataFrame:
    """Overlap seen through a sample of about 1 in ``share`` values on each side, drawn apart: may confirm, never rule out."""
    seen = domain.where(F.pmod(F.xxhash64("value", "col"), F.lit(share)) == 0)
    return pair_overlap(seen, targets)
