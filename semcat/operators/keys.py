"""Identifier verification and search: refuted cheaply, proved exactly on all rows."""

from __future__ import annotations

import math
from dataclasses import dataclass, field
from functools import reduce
from itertools import combinations

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from semcat.operators import hashed
from semcat.operators.profile import union_all
from semcat.plans.lexicon import id_like, own_key
from semcat.sources.bundle import SourceBundle


def verify_tables(jobs: list[tuple[str, DataFrame, list[list[str]]]]) -> DataFrame:
    """(table, cols, n, n_nonnull, n_distinct, is_unique) for candidate column sets of several tables in one scan of each and one shuffle.
    A key goes through the shuffle as two 64-bit hashes of its typed columns, whatever its width; copies are combined before. Two
    different keys agree in both with a chance of 2**-128, so a table of 10**13 rows counts one too few with a chance of 10**-13."""
    jobs = [j for j in jobs if j[2]]
    names = [(t, "|".join(c)) for t, _, cols in jobs for c in cols]
    bits, packed, at = hashed.bits_for(df for _, df, _ in jobs), [], 0
    for _, df, cols in jobs:
        packed.append(hashed.pack(df, dict(enumerate(cols, at)), bits))
        at += len(cols)

    def count(part: pa.Table) -> pa.Table:
        seen = {x: pc.sum(part.column(x)).as_py() for x in ("n", "n_nonnull")}
        return pa.table({"at": part.column("at")[:1], **{x: pa.array([v], pa.int64()) for x, v in seen.items()}, "n_distinct": pa.array([len(hashed.unpack(part.column("d"))[0])], pa.int64())})

    per = union_all(packed).groupBy("at", "bucket").applyInArrow(count, "at int, n long, n_nonnull long, n_distinct long")
    out = per.groupBy("at").agg(F.sum("n").alias("n"), F.sum("n_nonnull").alias("n_nonnull"), F.sum("n_distinct").alias("n_distinct"))
    name = lambda k: F.element_at(F.array(*[F.lit(x[k]) for x in names]), F.col("at") + 1)
    return out.select(name(0).alias("table"), name(1).alias("cols"), "n", "n_nonnull", "n_distinct").withColumn("is_unique", (F.col("n") == F.col("n_nonnull")) & (F.col("n") == F.col("n_distinct")) & (F.col("n") > 0))


def verify_many(df: DataFrame, candidates: list[list[str]]) -> DataFrame:
    """(cols, n, n_nonnull, n_distinct, is_unique): the same for one table."""
    if not candidates:
        return df.sparkSession.createDataFrame([], "cols string, n long, n_nonnull long, n_distinct long, is_unique boolean")
    return verify_tables([("", df, candidates)]).drop("table")


def verify_one_by_one(df: DataFrame, candidates: list[list[str]]) -> list[tuple[str, bool]]:
    """The same by one job for each candidate: the plain baseline of ``verify_many``."""
    return [("|".join(c), df.count() == df.dropna(subset=c).select(*c).distinct().count()) for c in candidates]


def prescreen(df: DataFrame, columns: list[str], slack: float = 0.8) -> list[str]:
    """Columns that a sketch cannot refute as keys: an estimate far below the row count refutes, nothing else does."""
    r = df.agg(F.count("*").alias("__n"), *[F.approx_count_distinct(c, 0.02).alias(c) for c in columns]).first()
    return [c for c in columns if r[c] >= slack * r["__n"]]


def order_candidates(columns: list[str], roles: dict[str, str], table: str = "", foreign: tuple[str, ...] = ()) -> list[str]:
    """Id-like names first, and of these the table's own and no foreign key; then the rest in table order; numeric measures
    never."""
    live = [(i, c) for i, c in enumerate(columns) if roles.get(c) not in ("Numeric", "Datetime", "Opaque")]
    return [c for i, c in sorted(live, key=lambda x: (not id_like(x[1], table), x[1] in foreign, bool(table) and not own_key(x[1], table), x[0]))]


@dataclass(frozen=True)
class KeySearch:
    """What a table's search may use: roles by column, id-like columns and declared foreign keys, dates, and ordinals (whole numbers that
    count within something); rows and sketched distinct counts, to leave out composites that cannot reach the row count."""

    roles: dict[str, str]
    foreign: tuple[str, ...] = ()
    dates: tuple[str, ...] = ()
    ordinals: tuple[str, ...] = ()
    rows: int = 0
    distinct: dict[str, int] = field(default_factory=dict)


@dataclass
class Facts:
    """What is proved of column sets of a snapshot, for several readings of it. It holds for columns whose values all readings tell
    apart alike; of sets with another column only copies are kept that the values as they are show, as equal values are equal
    texts."""

    alike: set[tuple[str, str]] = field(default_factory=set)
    unique: dict[tuple[str, ...], bool] = field(default_factory=dict)
    as_is: bool = False

    def get(self, table: str, cols: list[str]) -> bool | None:
        return self.unique.get((table, *cols))

    def put(self, table: str, cols: list[str], unique: bool) -> None:
        if self.as_is and not unique or all((table, c) in self.alike for c in cols):
            self.unique[(table, *cols)] = unique


def search_all(tables: dict[str, DataFrame], plans: dict[str, KeySearch], refuted: set[tuple[str, str]], budget: int = 12, max_width: int = 4, facts: Facts | None = None) -> dict[str, tuple[list[str], str]]:
    """(columns, status) of each table: the first verified single column in order, else the smallest verified composite of foreign
    keys and dates, else of these and ordinals, else the best candidate flagged ``fallback``. The budget counts candidates, so
    runs are repeatable; candidates beyond it that were never tried make the status ``fallback, budget spent``. The single
    columns of all tables are proved in one job; ``refuted`` are (table, column) that evidence has ruled out already; ``facts`` are
    not proved again, and grow by what is proved."""
    facts = facts or Facts()
    every = {t: order_candidates(tables[t].columns, p.roles, t, p.foreign) for t, p in plans.items()}
    live = {t: [[c] for c in cols[:budget] if (t, c) not in refuted] for t, cols in every.items()}
    found = {(t, c) for t, cols in live.items() for (c,) in cols if facts.get(t, [c])}
    jobs = [(t, tables[t], todo) for t, cols in live.items() if (todo := [c for c in cols if facts.get(t, c) is None])]
    found |= {(r["table"], r["cols"]) for r in verify_tables(jobs).where("is_unique").collect()} if jobs else set()
    out = {}
    for t, p in plans.items():
        singles = every[t][:budget]
        good = [c for c in singles if (t, c) in found]
        pools = [list(p.foreign)] + ([[*p.foreign, *p.ordinals]] if p.ordinals else [])
        if good:
            out[t] = ([good[0]], "verified")
            continue
        spent = len(every[t]) > budget
        for pool in pools:
            cols, cut = first_composite(tables[t], pool, p, max_width, facts, t)
            spent |= cut
            if cols:
                out[t] = (cols, "verified")
                break
        else:
            out[t] = (singles[:1] or tables[t].columns[:1], "fallback, budget spent" if spent else "fallback")
    return out


#: Composites that one job proves, and that one search tries at most; a search that ends at this limit says so in its status.
BATCH, COMPOSITES = 32, 256


#: Rows that one share of a table should hold, and the most shares, when copies are looked for in one share before all rows are.
SHARE_ROWS, SHARES = 100_000, 64


def refuted_by_share(df: DataFrame, candidates: list[list[str]], p: KeySearch) -> set[str]:
    """Candidates of which one share of the rows shows a copy. The share is drawn by the hash of a candidate's most varied column, so
    equal keys fall into it together and a copy in it is one among all rows. It refutes and never confirms."""
    shares = min(SHARES, p.rows // SHARE_ROWS)
    if shares < 2 or not candidates:
        return set()
    lead = [max(c, key=lambda x: p.distinct.get(x, 0)) for c in candidates]
    drawn = {c: F.pmod(F.xxhash64(F.col(c)), F.lit(shares)) == 0 for c in dict.fromkeys(lead)}
    cells = []
    for i, (cols, first) in enumerate(zip(candidates, lead, strict=True)):
        live = reduce(lambda x, y: x & y, [F.col(c).isNotNull() for c in cols], drawn[first])
        cells.append(F.when(live, F.struct(F.lit(i).alias("at"), F.xxhash64(*cols).alias("a"), F.xxhash64(F.lit(hashed.SECOND), *cols).alias("b"))))
    rows = df.where(reduce(lambda x, y: x | y, drawn.values())).select(F.explode(F.array(*cells)).alias("r")).where("r is not null").select("r.*")
    copies = rows.groupBy("at", "a", "b").agg(F.count("*").alias("m")).where("m > 1").select("at").distinct()
    return {"|".join(candidates[r["at"]]) for r in copies.collect()}


def first_composite(df: DataFrame, pool: list[str], p: KeySearch, max_width: int = 4, facts: Facts | None = None, table: str = "") -> tuple[list[str] | None, bool]:
    """(the first of the smallest verified composites or None, whether candidates were left untried). Narrow ones come first, in
    jobs of BATCH candidates; those whose distinct counts multiply to clearly less than the rows cannot be keys. Of a large table
    one share of the rows refutes most, and only what it leaves is proved on all rows."""
    left, facts = COMPOSITES, facts or Facts()
    for width in range(2, max_width + 1):
        enough = [c for c in composite_candidates(pool, list(p.dates), width) if not p.distinct or 1.5 * math.prod(max(1, p.distinct.get(x, p.rows)) for x in c) >= p.rows]
        todo, left = enough[:left], left - len(enough)
        for i in range(0, len(todo), BATCH):
            batch = todo[i : i + BATCH]
            gone = refuted_by_share(df, [c for c in batch if facts.get(table, c) is None], p)
            for c in batch:
                if "|".join(c) in gone:
                    facts.put(table, c, False)
            rest, most = [c for c in batch if "|".join(c) not in gone and facts.get(table, c) is not False], 1 if p.rows >= 2 * SHARE_ROWS else BATCH
            while rest:  # few are left of a large table, and mostly the first is a key
                part, rest, most = rest[:most], rest[most:], 2 * most
                open_ = [c for c in part if facts.get(table, c) is None]
                good = {r["cols"] for r in verify_many(df, open_).where("is_unique").collect()} if open_ else set()
                for c in open_:
                    facts.put(table, c, "|".join(c) in good)
                for c in part:
                    if "|".join(c) in good or facts.get(table, c):
                        return c, False
        if left <= 0:
            return None, left < 0 or width < max_width
    return None, False


def search(df: DataFrame, table: str, roles: dict[str, str], foreign: tuple[str, ...] = (), dates: tuple[str, ...] = (), ordinals: tuple[str, ...] = (), budget: int = 12, max_width: int = 4) -> tuple[list[str], str]:
    """The search for one table, with a sketch to refute candidates first."""
    tried = order_candidates(df.columns, roles, table, foreign)[:budget]
    pool = list(dict.fromkeys([*tried, *foreign, *dates, *ordinals]))
    r = df.agg(F.count("*").alias("__n"), *[F.approx_count_distinct(c).alias(c) for c in pool]).first()
    gone = {(table, c) for c in tried if r[c] < 0.75 * r["__n"]}
    return search_all({table: df}, {table: KeySearch(roles, foreign, dates, ordinals, r["__n"], {c: r[c] for c in pool})}, gone, budget, max_width)[table]


def composite_candidates(foreign: list[str], dates: list[str], width: int) -> list[list[str]]:
    """Dimension keys first, then with a date; in a fixed order."""
    pool = foreign + dates
    return sorted((list(c) for c in combinations(pool, width)), key=lambda c: (sum(x in dates for x in c), [pool.index(x) for x in c]))


def minimal_composites(df: DataFrame, foreign: list[str], dates: list[str], max_width: int = 4) -> list[list[str]]:
    """All minimal verified composites, narrow ones first: jobs of BATCH candidates for each width; supersets of accepted keys are
    not tried."""
    accepted: list[list[str]] = []
    for width in range(2, max_width + 1):
        todo = [c for c in composite_candidates(foreign, dates, width) if not any(set(a) <= set(c) for a in accepted)]
        for i in range(0, len(todo), BATCH):
            good = {r["cols"] for r in verify_many(df, todo[i : i + BATCH]).where("is_unique").collect()}
            accepted += [c for c in todo[i : i + BATCH] if "|".join(c) in good]
    return accepted


def duplicate_groups(df: DataFrame, cols: list[str]) -> DataFrame:
    return df.groupBy(*cols).agg(F.count("*").alias("n")).where("n > 1")


def is_weak(status: str) -> bool:
    """Whether an identifier was only assumed."""
    return status.startswith("fallback")


def choose_all(bundle: SourceBundle, roles: dict[str, dict[str, str]], ordinals: dict[str, tuple[str, ...]], found: dict, facts: Facts | None = None) -> dict[str, tuple[list[str], str]]:
    """Identifier of each table: a declared one is taken (and proved again by the claims), else searched. ``found`` is the evidence by
    (table, column)."""
    plans = {}
    for t, df in bundle.tables.items():
        if t not in bundle.primary:
            declared = [f[1] for f in bundle.foreign if f[0] == t]
            pool = tuple(c for c in df.columns if (c in declared or id_like(c, t)) and roles[t].get(c) != "Opaque")
            plans[t] = KeySearch(roles[t], pool, tuple(c for c in df.columns if roles[t].get(c) == "Datetime"), ordinals.get(t, ()), max((found[t, c].n_rows for c in df.columns), default=0), {c: found[t, c].about_distinct for c in df.columns})
    ids = search_all(bundle.tables, plans, {k for k, e in found.items() if e.no_key}, facts=facts)
    return {t: (bundle.primary[t], "declared") if t in bundle.primary else ids[t] for t in bundle.tables}
