"""Symbolic profile: one scan of a table gives the evidence of all its columns."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from semcat.sources.bundle import SourceBundle, text_of

#: Named patterns of text values.
PATTERNS = {
    "n_int": r"^[+-]?[0-9]+$",
    "n_dec": r"^[+-]?[0-9]+\.[0-9]+$",
    "n_date": r"^[0-9]{4}-[0-9]{2}-[0-9]{2}$",
    "n_datetime": r"^[0-9]{4}-[0-9]{2}-[0-9]{2}[ T][0-9]{2}:[0-9]{2}(:[0-9]{2}(\.[0-9]+)?)?$",
    "n_leading_zero": r"^0[0-9]+$",
    "n_url": r"^https?://",
    "n_email": r"^[^@ ]+@[^@ ]+\.[a-z]+$",
    "n_phone": r"^\+?[0-9]{1,3}[-. ][0-9]{2,4}[-. ][0-9]{3,4}([-. ][0-9]{2,4})?$",
    "n_json": r"^[{\[].*[}\]]$",
    "n_bool": r"^(?i:true|false|yes|no|t|f|y|n)$",
}


def union_all(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)


def inventory(bundle: SourceBundle) -> list[tuple[str, str, str]]:
    """(table, column, type); metadata only."""
    return [(t, f.name, f.dataType.simpleString()) for t, df in bundle.tables.items() for f in df.schema.fields]


def melt(df: DataFrame, table: str, columns: list[str] | None = None) -> DataFrame:
    """(table_name, column_name, value as text), one row a cell."""
    cells = [F.struct(F.lit(c).alias("column_name"), text_of(df, c).alias("value")) for c in columns or df.columns]
    return df.select(F.lit(table).alias("table_name"), F.explode(F.array(*cells)).alias("cell")).select("table_name", "cell.*")


def melted(bundle: SourceBundle) -> DataFrame:
    return union_all([melt(df, t) for t, df in bundle.tables.items()])


def row_counts(bundle: SourceBundle) -> DataFrame:
    return union_all([df.agg(F.count("*").alias("n_rows")).select(F.lit(t).alias("table_name"), "n_rows") for t, df in bundle.tables.items()])


def column_stats(bundle: SourceBundle) -> DataFrame:
    """(table_name, column_name, n_rows, n_null, n_distinct), exact but for a chance of 2**-128 for each pair of values: values go
    through the one shuffle as two 64-bit hashes, so a long text costs as much as a number, and equal ones are combined before."""
    parts, names = [], []
    for t, df in bundle.tables.items():
        cells = []
        for c in df.columns:
            v = text_of(df, c) if df.schema[c].dataType.typeName() == "map" else F.col(c)
            cells.append(F.struct(F.lit(len(names)).alias("at"), F.when(v.isNotNull(), F.xxhash64(v)).alias("a"), F.xxhash64(F.lit(7), v).alias("b")))
            names.append((t, c))
        parts.append(df.select(F.explode(F.array(*cells)).alias("r")).select("r.*"))
    by_value = union_all(parts).groupBy("at", "a", "b").agg(F.count("*").alias("n"))
    out = by_value.groupBy("at").agg(F.sum("n").alias("n_rows"), F.sum(F.when(F.col("a").isNull(), F.col("n")).otherwise(0)).alias("n_null"), F.count("a").alias("n_distinct"))
    name = F.element_at(F.array(*[F.struct(F.lit(t).alias("table_name"), F.lit(c).alias("column_name")) for t, c in names]), F.col("at") + 1)
    return out.select(name.alias("r"), "n_rows", "n_null", "n_distinct").select("r.*", "n_rows", "n_null", "n_distinct")


def wide(bundle: SourceBundle, measures: dict[str, callable]) -> DataFrame:
    """Any per-column aggregates of a table in one scan without a shuffle of cells: measures map a name to f(df, column)."""
    out = []
    for t, df in bundle.tables.items():
        one = df.agg(*[f(df, c).alias(f"{c}|{m}") for c in df.columns for m, f in measures.items()])
        rows = [F.struct(F.lit(c).alias("column_name"), *[F.col(f"`{c}|{m}`").alias(m) for m in measures]) for c in df.columns]
        out.append(one.select(F.lit(t).alias("table_name"), F.explode(F.array(*rows)).alias("r")).select("table_name", "r.*"))
    return union_all(out)


def null_rates(bundle: SourceBundle) -> DataFrame:
    return wide(bundle, {"null_rate": lambda df, c: F.round(F.avg(F.col(c).isNull().cast("double")), 6)})


def ranges(bundle: SourceBundle) -> DataFrame:
    return wide(bundle, {"min_text": lambda df, c: F.min(text_of(df, c)), "max_text": lambda df, c: F.max(text_of(df, c))})


def lengths(bundle: SourceBundle) -> DataFrame:
    n = lambda df, c: F.length(text_of(df, c))
    return wide(bundle, {"min_len": lambda df, c: F.min(n(df, c)).cast("long"), "max_len": lambda df, c: F.max(n(df, c)).cast("long"), "avg_len": lambda df, c: F.round(F.avg(n(df, c)), 6)})


def pattern_stats(bundle: SourceBundle, names: list[str] | None = None) -> DataFrame:
    """How many values of each column match each pattern; one scan a table."""

    def count(p: str):
        return lambda df, c: F.count_if(text_of(df, c).rlike(PATTERNS[p]))

    return wide(bundle, {p: count(p) for p in names or PATTERNS})


def sketched_cardinality(df: DataFrame, columns: list[str], rsd: float = 0.02) -> DataFrame:
    """Approximate distinct counts, for screening only."""
    one = df.agg(*[F.approx_count_distinct(c, rsd).alias(c) for c in columns])
    return one.select(F.explode(F.array(*[F.struct(F.lit(c).alias("column_name"), F.col(c).alias("approx_distinct")) for c in columns])).alias("r")).select("r.*")


def bitmap_cardinality(df: DataFrame, columns: list[str]) -> DataFrame:
    """Exact distinct counts of whole-number columns by bitmaps of 32768 values; the shuffle carries bitmaps, not values."""
    cells = F.explode(F.array(*[F.struct(F.lit(c).alias("column_name"), F.col(c).cast("long").alias("v")) for c in columns]))
    rows = df.select(cells.alias("r")).select("r.*").where("v is not null")
    per = rows.groupBy("column_name", F.expr("bitmap_bucket_number(v)").alias("bucket")).agg(F.expr("bitmap_count(bitmap_construct_agg(bitmap_bit_position(v)))").alias("n"))
    return per.groupBy("column_name").agg(F.sum("n").alias("n_distinct"))


def samples(bundle: SourceBundle, k: int = 8, by_hash: bool = True) -> DataFrame:
    """k distinct values of each column as one text: those of the smallest hash (spread over the domain) or the smallest."""
    order: list[Column] = [F.xxhash64("value"), F.col("value")] if by_hash else [F.col("value")]
    distinct = melted(bundle).where("value is not null").distinct()
    # a rank limit within a window is pushed below the exchange, so a task sends k values a column, not its domain
    ranked = distinct.withColumn("k", F.row_number().over(Window.partitionBy("table_name", "column_name").orderBy(*order))).where(F.col("k") <= k)
    return ranked.groupBy("table_name", "column_name").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("k", "value"))), lambda x: x["value"]), "|").alias("samples"))


def fingerprint(bundle: SourceBundle) -> DataFrame:
    """(table_name, fingerprint): order-free checksum of all rows, to pin a snapshot."""
    return union_all([df.agg(F.bit_xor(F.xxhash64(*[text_of(df, c) for c in df.columns])).alias("fingerprint")).select(F.lit(t).alias("table_name"), "fingerprint") for t, df in bundle.tables.items()])


def freeze(bundle: SourceBundle, path: str) -> None:
    """Save the profile as the ground-truth artifact of evaluation and audit."""
    column_stats(bundle).join(pattern_stats(bundle), ["table_name", "column_name"]).join(samples(bundle), ["table_name", "column_name"], "left").write.mode("overwrite").parquet(path)
