"""Tables of a scope as DataFrames, their twins, derived views and declared metadata."""

from __future__ import annotations

import json
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = ["region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations"]
STAR = TABLES[:7]
#: Scopes of the experiment workloads.
SCOPES = {
    "W1": ["part", "supplier", "orders", "lineitem"],
    "W2": ["region", "nation", "customer", "orders", "lineitem"],
    "W3": TABLES,
    "W4": ["events"],
    "W6": ["documents", "labels", "pages", "conversations"],
    "W7": ["lineitem"],
}
CURVE = [STAR[:2], STAR[:3], STAR[:4], STAR[:5], STAR[:6], STAR, TABLES]
#: Declared metadata of the intact arm: identifiers, and foreign keys (table, column, referenced table, referenced column).
PRIMARY = {"region": ["r_regionkey"], "nation": ["n_nationkey"], "customer": ["c_custkey"], "supplier": ["s_suppkey"], "part": ["p_partkey"], "orders": ["o_orderkey"], "events": ["event_id"], "documents": ["doc_id"], "embeddings": ["vec_id"], "pages": ["page_id"], "benchmark": ["item_id"], "labels": ["doc_id"], "conversations": ["conv_id", "turn"]}
FOREIGN = [
    ("nation", "n_regionkey", "region", "r_regionkey"),
    ("customer", "c_nationkey", "nation", "n_nationkey"),
    ("supplier", "s_nationkey", "nation", "n_nationkey"),
    ("orders", "o_custkey", "customer", "c_custkey"),
    ("lineitem", "l_orderkey", "orders", "o_orderkey"),
    ("lineitem", "l_partkey", "part", "p_partkey"),
    ("lineitem", "l_suppkey", "supplier", "s_suppkey"),
    ("labels", "doc_id", "documents", "doc_id"),
]
#: Key spaces of the disjoint twin: column to prefix.
PREFIX = {"r_regionkey": "R", "n_regionkey": "R", "n_nationkey": "N", "c_nationkey": "N", "s_nationkey": "N", "c_custkey": "C", "o_custkey": "C", "s_suppkey": "S", "l_suppkey": "S", "p_partkey": "P", "l_partkey": "P", "o_orderkey": "O", "l_orderkey": "O", "event_id": "E", "user_id": "U", "doc_id": "D", "vec_id": "V", "page_id": "G", "item_id": "I", "conv_id": "K"}


@dataclass
class SourceBundle:
    """Named tables with whatever metadata is declared."""

    tables: dict[str, DataFrame]
    primary: dict[str, list[str]] = field(default_factory=dict)
    foreign: list[tuple[str, str, str, str]] = field(default_factory=list)

    def __getitem__(self, name: str) -> DataFrame:
        return self.tables[name]

    def scope(self, names: list[str]) -> SourceBundle:
        keep = [n for n in names if n in self.tables]
        return SourceBundle({n: self.tables[n] for n in keep}, {k: v for k, v in self.primary.items() if k in keep}, [f for f in self.foreign if f[0] in keep and f[2] in keep])


def from_parquet(spark: SparkSession, path: str, names: list[str] | None = None, declared: bool = False) -> SourceBundle:
    """Parquet tables; with ``declared`` the keys of the intact arm come along."""
    b = SourceBundle({n: spark.read.parquet(f"{path}/{n}.parquet") for n in names or TABLES})
    return SourceBundle(b.tables, PRIMARY, FOREIGN).scope(list(b.tables)) if declared else b


def with_manifest(bundle: SourceBundle, path: str) -> SourceBundle:
    """The bundle with the keys that a JSON manifest declares: primary (table to columns) and foreign (rows of table, column, table,
    column). What names no table of the bundle is left out."""
    text = "\n".join(r["value"] for r in next(iter(bundle.tables.values())).sparkSession.read.text(path, wholetext=True).collect())
    m = json.loads(text)
    return SourceBundle(bundle.tables, m.get("primary", {}), [tuple(f) for f in m.get("foreign", [])]).scope(list(bundle.tables))


def from_files(spark: SparkSession, path: str, names: list[str], kind: str = "csv") -> SourceBundle:
    """Flat files without keys or dependable types: every column of a CSV is text."""
    if kind == "excel":
        raise NotImplementedError("spreadsheets need an optional reader that is not installed; export them as CSV")
    read = {"csv": lambda p: spark.read.option("header", True).option("multiLine", True).option("escape", '"').csv(p), "json": spark.read.json, "orc": spark.read.orc, "text": spark.read.text, "parquet": spark.read.parquet}[kind]
    return SourceBundle({n: read(f"{path}/{n}") for n in names})


def from_jdbc(spark: SparkSession, url: str, names: list[str], **options: str) -> SourceBundle:
    """Tables of a database server, read lazily; partitioned reads by the usual options."""
    return SourceBundle({n: spark.read.format("jdbc").options(url=url, dbtable=n, **options).load() for n in names})


def text_of(df: DataFrame, column: str):
    kind = df.schema[column].dataType.typeName()
    return F.to_json(column) if kind in ("array", "struct", "map") else F.col(column).cast("string")


def stripped(bundle: SourceBundle) -> SourceBundle:
    """All columns as text, nothing declared."""
    return SourceBundle({n: df.select(*[text_of(df, c).alias(c) for c in df.columns]) for n, df in bundle.tables.items()})


def disjoint(bundle: SourceBundle) -> SourceBundle:
    """Stripped, with each key space under a prefix of its own, in keys and in the columns that refer to them."""
    text = stripped(bundle)
    return SourceBundle({n: df.select(*[(F.concat(F.lit(PREFIX[c]), F.col(c)) if c in PREFIX else F.col(c)).alias(c) for c in df.columns]) for n, df in text.tables.items()})


#: Bytes of a table's files for each further partition of its permuted rows.
DEALT = 1 << 24


def permuted(bundle: SourceBundle, seed: int) -> SourceBundle:
    """The same rows with tables, columns and partitions in another order. A row's partition is drawn by its place in the table's files,
    whose order does not change, so nothing is sorted; larger tables get more partitions."""
    key = lambda s: hash_text(f"{seed}:{s}")

    def dealt(df: DataFrame) -> DataFrame:
        size = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
        parts = 3 + seed % 5 + (size // DEALT if size < 1 << 60 else 0)
        return df.select(*sorted(df.columns, key=key)).repartition(parts, F.xxhash64(F.lit(seed), F.monotonically_increasing_id()))

    return SourceBundle({n: dealt(bundle[n]) for n in sorted(bundle.tables, key=key)}, bundle.primary, bundle.foreign)


def hash_text(s: str) -> int:
    import hashlib

    return int.from_bytes(hashlib.blake2b(s.encode(), digest_size=8).digest(), "big")


def nation_month_sales(bundle: SourceBundle) -> DataFrame:
    o, c = bundle["orders"], bundle["customer"]
    joined = o.join(c, o.o_custkey == c.c_custkey)
    return joined.groupBy(F.col("c_nationkey").alias("n_nationkey"), F.trunc("o_orderdate", "month").alias("month")).agg(F.avg("o_totalprice").alias("avg_price"), F.count("*").alias("n_orders"))


def trade_lane(bundle: SourceBundle) -> DataFrame:
    b = bundle
    j = b["lineitem"].join(b["orders"], F.col("l_orderkey") == F.col("o_orderkey")).join(b["customer"], F.col("o_custkey") == F.col("c_custkey")).join(b["supplier"], F.col("l_suppkey") == F.col("s_suppkey"))
    g = j.groupBy(F.col("c_nationkey").alias("buyer_nationkey"), F.col("s_nationkey").alias("seller_nationkey")).agg(F.count("*").alias("n_lines"), F.sum(F.col("l_extendedprice").cast("decimal(18,2)")).cast("double").alias("revenue"))
    return g.select((F.col("buyer_nationkey") * 100 + F.col("seller_nationkey")).cast("long").alias("lane_id"), "*")


def status_lookup(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([("F", "finished"), ("O", "open"), ("P", "partial")], "code string, meaning string")


def save(bundle: SourceBundle, path: str, kind: str = "parquet") -> None:
    """Write every table below ``path``; CSV gets a header."""
    for n, df in bundle.tables.items():
        w = df.write.mode("overwrite")
        (w.option("header", True).option("escape", '"').csv if kind == "csv" else getattr(w, kind))(f"{path}/{n}")
