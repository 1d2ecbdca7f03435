"""The comparison arms, each examined once for a session: what the builder finds in the intact tables and in their twins."""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import SparkSession

from semcat.operators.together import Reading
from semcat.plans.builder import State, examine, examine_together
from semcat.sources.bundle import FOREIGN, PREFIX, PRIMARY, TABLES, SourceBundle, disjoint, from_parquet, nation_month_sales, permuted, stripped, trade_lane

_STATES: dict[tuple[str, str, str], State] = {}
_TWINS: dict[tuple[str, str, str], SourceBundle] = {}


def twin(spark: SparkSession, sf: str, arm: str, typed: SourceBundle | None = None) -> SourceBundle:
    """meta: typed tables with declared keys; typed: without them; stripped: all text; disjoint: all text with a key space for each
    entity; run1 to run3: the disjoint twin with tables, columns and partitions in another order; views: derived tables.
    ``typed`` are the folder's tables, where they have been opened."""
    b = typed or from_parquet(spark, sf)
    if arm == "meta":
        return SourceBundle(b.tables, PRIMARY, FOREIGN).scope(list(b.tables))
    if arm == "views":
        return stripped(SourceBundle({"nation": b["nation"], "nation_month_sales": nation_month_sales(b), "trade_lane": trade_lane(b)}))
    if arm.startswith("run"):
        return disjoint(permuted(b, int(arm[3:])))  # rows are dealt out before they become text, which is wider
    return {"typed": lambda x: x, "stripped": stripped, "disjoint": disjoint}[arm](b)


def fresh(spark: SparkSession, sf: str, arm: str, tables: list[str]) -> State:
    """A scope of an arm, examined anew and without the tables outside it, whatever the session has kept."""
    return examine(twin(spark, sf, arm).scope(tables))


def state(spark: SparkSession, sf: str, arm: str, tables: list[str] | None = None) -> State:
    """What ``examine`` finds in an arm, cut to a scope. A folder is taken for a pinned snapshot: its evidence, which is a few rows
    a column, is kept for the session, and every scope and policy is decided on it without another scan. A column that another arm
    of the folder reads in the same way is not examined again."""
    key = (spark.sparkContext.applicationId, sf, arm)
    if arm.startswith("run"):
        apart(spark, sf, [arm])
    if key not in _STATES:
        known = [(_TWINS[k], s.evidence) for k, s in _STATES.items() if k[:2] == key[:2] and k in _TWINS]
        _TWINS[key] = twin(spark, sf, arm)
        _STATES[key] = examine(_TWINS[key], known=known)
    return _STATES[key].restrict(tables or (TABLES if arm != "views" else list(_STATES[key].tables)))


def _run(typed: SourceBundle, arm: str) -> State:
    """A permuted run, examined on its own rows, which are dealt out before they become text, and by nothing that another run has found."""
    dealt = permuted(typed, int(arm[3:]))
    return examine_together(dealt, [Reading(disjoint(dealt), True, PREFIX)])[0]


def apart(spark: SparkSession, sf: str, names: list[str]) -> None:
    """Examine those of some permuted runs that the session has not examined yet, each on its own, side by side: while the jobs of one
    wait for the driver or end in few tasks, the others have the cores."""
    key = lambda arm: (spark.sparkContext.applicationId, sf, arm)
    todo = [a for a in names if key(a) not in _STATES]
    if todo:
        typed = from_parquet(spark, sf)
        with ThreadPoolExecutor(len(todo)) as pool:
            _STATES.update(zip(map(key, todo), pool.map(lambda a: _run(typed, a), todo), strict=True))


def together(spark: SparkSession, sf: str, names: list[str]) -> None:
    """Examine those of some arms (meta, typed, stripped, disjoint) that the session has not examined yet in one go."""
    key = lambda arm: (spark.sparkContext.applicationId, sf, arm)
    todo = [a for a in names if key(a) not in _STATES]
    if len(todo) < 2:
        return
    typed = from_parquet(spark, sf)
    _TWINS.update({key(a): twin(spark, sf, a, typed) for a in todo})
    readings = [Reading(_TWINS[key(a)], a in ("stripped", "disjoint"), PREFIX if a == "disjoint" else {}) for a in todo]
    _STATES.update(zip(map(key, todo), examine_together(typed, readings), strict=True))
