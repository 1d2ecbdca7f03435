"""Storage type and analytic role of each column, decided from evidence; the two never depend on each other's declaration."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from semcat.operators import profile
from semcat.plans.lexicon import FLAG_WORDS, TIME_WORDS, id_like, measure_like, words
from semcat.sources.bundle import SourceBundle

#: What a role permits.
LICENCES = {"Numeric": "avg|max|min|sum", "Categorical": "count|filter|group", "Datetime": "filter|series|trunc", "Opaque": ""}
ISA = {"bigint": "integer", "int": "integer", "double": "float", "float": "float", "string": "string", "boolean": "boolean", "date": "date", "timestamp": "datetime", "timestamp_ntz": "datetime"}


def role(column: str, kind: str) -> str:
    """Role by name and declared storage alone, before any value is seen: digits alone never make a measure; identifiers and
    codes are categories. ``evidence`` decides by the values as well."""
    w = words(column)
    if kind.startswith("array"):
        return "Opaque"
    if kind.startswith(("timestamp", "date")) or w[-1] in TIME_WORDS and kind == "string":
        return "Datetime"
    if id_like(column) or w[-1] in FLAG_WORDS:
        return "Categorical"
    return "Numeric" if kind in ("int", "bigint", "double", "float") and (measure_like(column) or kind in ("double", "float")) else "Categorical"


def roles_of(bundle: SourceBundle) -> dict[str, dict[str, str]]:
    out: dict[str, dict[str, str]] = {}
    for t, c, kind in profile.inventory(bundle):
        out.setdefault(t, {})[c] = role(c, kind)
    return out


def symbolic_role(kind: str) -> str:
    """The arm without semantics: every number is a measure."""
    return "Numeric" if kind in ("int", "bigint", "double", "float") else "Datetime" if kind.startswith(("timestamp", "date")) else "Categorical"


def storage_from_text(bundle: SourceBundle) -> DataFrame:
    """(table_name, column_name, isa) of text columns from all their values: integer, float, date, datetime or string.
    A leading zero keeps the text."""
    m = {
        "n": lambda df, c: F.count(c),
        "n_int": lambda df, c: F.count_if(F.col(c).rlike(profile.PATTERNS["n_int"])),
        "n_num": lambda df, c: F.count_if(F.col(c).rlike(r"^[+-]?[0-9]+(\.[0-9]+)?([eE][+-]?[0-9]+)?$")),
        "n_zero": lambda df, c: F.count_if(F.col(c).rlike(profile.PATTERNS["n_leading_zero"])),
        "n_date": lambda df, c: F.count_if(F.col(c).rlike(r"^[0-9]{4}-[0-9]{2}-[0-9]{2}( 00:00:00)?$")),
        "n_time": lambda df, c: F.count_if(F.col(c).rlike(profile.PATTERNS["n_datetime"])),
    }
    e = profile.wide(bundle, m)
    some = F.col("n") > 0
    isa = F.when(some & (F.col("n_zero") > 0), "string").when(some & (F.col("n_int") == F.col("n")), "integer").when(some & (F.col("n_num") == F.col("n")), "float").when(some & (F.col("n_date") == F.col("n")), "date").when(some & (F.col("n_time") + F.col("n_date") >= F.col("n")) & (F.col("n_time") > 0), "datetime").otherwise("string")
    return e.select("table_name", "column_name", isa.alias("isa"))


def refine(df: DataFrame, column: str, proposed: str) -> DataFrame:
    """(column_name, role_before, role_after): Numeric over values that are no numbers, or Datetime over values that are no
    times, becomes Categorical."""
    text = F.col(column).cast("string")
    number, time = text.try_cast("double").isNotNull(), F.coalesce(text.try_cast("timestamp_ntz"), F.try_to_timestamp(text, F.lit("yyyyMMdd")).cast("timestamp_ntz")).isNotNull()
    ok = number if proposed == "Numeric" else time
    share = df.agg((F.count_if(F.col(column).isNotNull() & ~ok) == 0).alias("ok"))
    return share.select(F.lit(column).alias("column_name"), F.lit(proposed).alias("role_before"), F.when(F.col("ok"), proposed).otherwise("Categorical").alias("role_after"))


def granularity(bundle: SourceBundle, columns: list[tuple[str, str]]) -> DataFrame:
    """(column_name, granularity): datetime if any value has a clock part, else date."""
    out = [bundle[t].agg((F.count_if(F.date_trunc("day", c) != F.col(c)) > 0).alias("clock")).select(F.lit(f"{t}.{c}").alias("column_name"), F.when(F.col("clock"), "datetime").otherwise("date").alias("granularity")) for t, c in columns]
    return profile.union_all(out)


def boolean_flags(bundle: SourceBundle, columns: list[tuple[str, str]]) -> DataFrame:
    """(column_name, is_boolean): two values, all of them words of truth, or 0 and 1 under a name that speaks for neither
    identifier nor measure."""
    out = []
    for t, c in columns:
        v = F.lower(F.col(c).cast("string"))
        digits = [] if id_like(c) or measure_like(c) else ["0", "1"]
        word = v.isin("true", "false", "yes", "no", "t", "f", "y", "n", *digits)
        out.append(bundle[t].agg(((F.count_distinct(v) <= 2) & (F.count_if(v.isNotNull() & ~word) == 0)).alias("is_boolean")).select(F.lit(f"{t}.{c}").alias("column_name"), "is_boolean"))
    return profile.union_all(out)


def declared_violations(df: DataFrame, declared: dict[str, str]) -> DataFrame:
    """(column_name, n_violations): non-null values that do not obey the declared type."""
    one = df.agg(*[F.count_if(F.col(c).isNotNull() & F.col(c).cast("string").try_cast(k).isNull()).alias(c) for c, k in declared.items()])
    return one.unpivot([], one.columns, "column_name", "n_violations")
