"""Licensed questions over a catalog: roles decide what may be done with an attribute, paths decide how it is reached."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from semcat.operators.typing_rules import LICENCES
from semcat.plans.graph import JoinGraph, direction


class NotLicensed(ValueError):
    """The role of an attribute does not permit the operation."""


@dataclass(frozen=True)
class Question:
    """Aggregate ``measure`` of ``entity``, grouped by attributes of it or of tables on m:1 paths. where: Spark conditions on
    such attributes; agg: count, sum, avg, min, max or count_distinct."""

    entity: str
    agg: str = "count"
    measure: str | None = None
    by: tuple[str, ...] = ()
    where: tuple[str, ...] = ()
    limit: int | None = None
    needs: tuple[str, ...] = field(default=())


def plan(q: Question, tables: dict[str, DataFrame], roles: dict[str, str], joins: JoinGraph, value: str = "value") -> DataFrame:
    """The question as a DataFrame: only the m:1 joins it needs are made, so no row is multiplied."""
    if q.measure and q.agg not in LICENCES[roles[q.measure]].split("|") + ["count_distinct"]:
        raise NotLicensed(f"{q.agg} of {q.measure} ({roles[q.measure]})")
    for c in q.by:
        if "group" not in LICENCES[roles[c]] and "series" not in LICENCES[roles[c]]:
            raise NotLicensed(f"group by {c} ({roles[c]})")
    df, have = tables[q.entity], set(tables[q.entity].columns)
    wanted = [c for c in (*q.by, *q.needs, *((q.measure,) if q.measure else ())) if c not in have]
    for path in joins.paths(q.entity):
        if not wanted:
            break
        if direction(path) == "many_to_one" and any(c in tables[path[-1].far].columns for c in wanted):
            for s in path:
                if not set(tables[s.far].columns) <= have:
                    a, b, c, d = s.join
                    df = df.join(tables[s.far], F.col(b) == F.col(d), "left")
                    have |= set(tables[s.far].columns)
            wanted = [c for c in wanted if c not in have]
    if wanted:
        raise NotLicensed(f"{wanted[0]} is not reachable without multiplying rows")
    for w in q.where:
        df = df.where(w)
    m = {"count": lambda: F.count("*"), "sum": lambda: F.sum(F.col(q.measure).cast("decimal(18,2)")).cast("double"), "avg": lambda: F.round(F.avg(F.col(q.measure).cast("decimal(18,2)")).cast("double"), 6), "min": lambda: F.min(q.measure), "max": lambda: F.max(q.measure), "count_distinct": lambda: F.count_distinct(q.measure)}[q.agg]()
    out = df.groupBy(*q.by).agg(m.alias(value))
    return out.orderBy(F.desc(value), *q.by).limit(q.limit) if q.limit else out


def enumerate_questions(columns: dict[str, list[str]], roles: dict[str, str]) -> list[tuple[str, str]]:
    """(entity, question) for every one-measure question that the roles permit within an entity."""
    out = []
    for t, cols in columns.items():
        for c in cols:
            out += [(t, f"{op}({c})") for op in LICENCES[roles[c]].split("|") if op in ("avg", "max", "min", "sum", "group", "series")]
    return out


def register(tables: dict[str, DataFrame], joins: JoinGraph, max_hops: int = 2) -> list[str]:
    """One temporary view an entity with the attributes of its m:1 paths; names of the views."""
    out = []
    for t, df in tables.items():
        have = set(df.columns)
        for p in joins.paths(t, max_hops):
            if direction(p) == "many_to_one" and not have & set(tables[p[-1].far].columns) and all(set(tables[s.far].columns) <= have or s is p[-1] for s in p):
                a, b, c, d = p[-1].join
                df = df.join(tables[p[-1].far], F.col(b) == F.col(d), "left")
                have |= set(tables[p[-1].far].columns)
        df.createOrReplaceTempView(f"{t}_entity")
        out.append(f"{t}_entity")
    return out
