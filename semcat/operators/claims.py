"""Self-generated claims of a catalog, run against the data in few scans, and the measures that judge catalogs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from semcat.operators import keys
from semcat.operators.profile import union_all
from semcat.plans.graph import JoinGraph, Step
from semcat.plans.model import Catalog, placeholders
from semcat.sources.bundle import SourceBundle


def generate(c: Catalog) -> list[tuple[str, str, str]]:
    """(class, entity, target): identifiers, attributes, aggregables and references; the suite grows with the catalog."""
    out = []
    for e in c.entities:
        out.append(("identifier", e.name, "|".join(e.id_columns)))
        out += [("attribute", e.name, a.name) for a in e.attributes]
        out += [("aggregable", e.name, f"{g.name}@{'/'.join(g.path)}") for g in e.aggregables]
        out.append(("reference", e.name, e.reference))
    return out


def run_identifiers(bundle: SourceBundle, ids: dict[str, list[str]]) -> DataFrame:
    """(entity, n, n_distinct, passed): over all rows, one job for all tables."""
    return keys.verify_tables([(t, bundle[t], [k]) for t, k in ids.items()]).select(F.col("table").alias("entity"), "n", "n_distinct", F.col("is_unique").alias("passed"))


def run_attributes(bundle: SourceBundle, attributes: list[tuple[str, str, str]]) -> list[tuple[str, str, bool]]:
    """(entity, attribute, passed): the declared table and column resolve; no data is read for that."""
    return [(t, a, t in bundle.tables and c in bundle[t].columns) for t, a, c in attributes]


def run_retrieval(bundle: SourceBundle, attributes: list[tuple[str, str, str]]) -> DataFrame:
    """(entity, attribute, n_values, passed) of attributes (entity, name, column): the declared table and column resolve, and the column
    is read over all rows; one scan a table. A column without values still resolves."""
    out, by = [], {}
    schema = "entity string, attribute string, n_values long, passed boolean"
    for t, a, ok in run_attributes(bundle, attributes):
        by.setdefault(t, {})[a] = ok
    cols = {(t, a): c for t, a, c in attributes}
    for t, resolved in by.items():
        good = [a for a, ok in resolved.items() if ok]
        if good:
            one = bundle[t].agg(*[F.count(F.col(f"`{cols[t, a]}`")).alias(f"n{i}") for i, a in enumerate(good)])
            cells = [F.struct(F.lit(a).alias("attribute"), F.col(f"n{i}").alias("n_values"), F.col(f"n{i}").isNotNull().alias("passed")) for i, a in enumerate(good)]
            out.append(one.select(F.lit(t).alias("entity"), F.explode(F.array(*cells)).alias("r")).select("entity", "r.*"))
    lost = [(t, a, 0, False) for t, resolved in by.items() for a, ok in resolved.items() if not ok]
    spark = next(iter(bundle.tables.values())).sparkSession
    return union_all(out + ([spark.createDataFrame(lost, schema)] if lost or not out else []))


def run_values(bundle: SourceBundle, attributes: list[tuple[str, str, str, str]]) -> DataFrame:
    """(entity, attribute, n_values, passed) of attributes (entity, name, column, storage): the column is retrieved, holds a value, and
    every value obeys the claimed storage; one scan a table."""
    kinds = {"integer": "bigint", "float": "double", "date": "date", "datetime": "timestamp_ntz", "boolean": None, "string": None, "array": None}
    by: dict[str, list[tuple[str, str, str]]] = {}
    for t, a, c, isa in attributes:
        by.setdefault(t, []).append((a, c, isa))
    out = []
    for t, cols in by.items():
        aggs = []
        for i, (_, c, isa) in enumerate(cols):
            bad = F.count_if(F.col(c).isNotNull() & F.col(c).cast("string").try_cast(kinds[isa]).isNull()) if kinds[isa] else F.lit(0)
            aggs += [F.count(c).alias(f"n{i}"), bad.cast("long").alias(f"b{i}")]
        one = bundle[t].agg(*aggs)
        rows = [F.struct(F.lit(a).alias("attribute"), F.col(f"n{i}").alias("n_values"), ((F.col(f"n{i}") > 0) & (F.col(f"b{i}") == 0)).alias("passed")) for i, (a, _, _) in enumerate(cols)]
        out.append(one.select(F.lit(t).alias("entity"), F.explode(F.array(*rows)).alias("r")).select("entity", "r.*"))
    return union_all(out)


def run_paths(bundle: SourceBundle, paths: list[tuple[str, tuple[Step, ...]]]) -> DataFrame:
    """(entity, path, rows_base, rows_joined, max_fanout, passed): a path of m:1 steps must not multiply rows; any path must
    yield rows. Nothing is joined out: from the far end, each step sums for each key how many rows the rest of the path gives
    one row, so a step shuffles keys and never their products; paths that end alike share those sums."""
    done: dict[tuple[Step, ...], DataFrame] = {}

    def sums(path: tuple[Step, ...]) -> DataFrame:
        """(k, n, hit): rows that one row with the near key k finds along the path, and those that reach its end."""
        if path not in done:
            s = path[0]
            a, b, c, d = s.join
            far = b if s.reverse else d
            rest = path[1:]
            if not rest:
                rows = bundle[s.far].select(F.col(far).alias("k"), F.lit(1).alias("n"), F.lit(1).alias("hit"))
            else:
                nxt = rest[0]
                near = nxt.join[3] if nxt.reverse else nxt.join[1]
                cols = [F.col(far).alias("k"), F.col(near).alias("j")]
                rows = bundle[s.far].select(*cols).join(sums(rest).withColumnRenamed("k", "j"), "j", "left")
                rows = rows.select("k", F.coalesce("n", F.lit(1)).alias("n"), F.coalesce("hit", F.lit(0)).alias("hit"))
            done[path] = rows.where("k is not null").groupBy("k").agg(F.sum("n").alias("n"), F.sum("hit").alias("hit"))
        return done[path]

    out = []
    for entity, path in paths:
        s = path[0]
        near = s.join[3] if s.reverse else s.join[1]
        per = bundle[entity].select(F.col(near).alias("k")).join(sums(path), "k", "left").select(F.coalesce("n", F.lit(1)).alias("n"), F.coalesce("hit", F.lit(0)).alias("hit"))
        one = per.agg(F.count("*").alias("rows_base"), F.sum("n").alias("rows_joined"), F.max("n").alias("max_fanout"), F.sum("hit").alias("hits"))
        flat = all(not s.reverse for s in path)
        passed = (F.col("hits") > 0) & (F.col("max_fanout") == 1 if flat else F.lit(True))
        out.append(one.select(F.lit(entity).alias("entity"), F.lit("/".join(s.text() for s in path)).alias("path"), "rows_base", "rows_joined", "max_fanout", passed.alias("passed")))
    return union_all(out)


def render(df: DataFrame, template: str, key: list[str]) -> DataFrame:
    """The key columns and ``label``: placeholders filled in; a null part falls back on the identifier."""
    import re

    parts = [F.col(p[1:-1]).cast("string") if p.startswith("{") else F.lit(p) for p in re.findall(r"\{[^{}]+\}|[^{}]+", template)]
    return df.select(*key, F.coalesce(F.concat(*parts), F.concat_ws("-", *[F.col(k).cast("string") for k in key])).alias("label"))


def run_references(bundle: SourceBundle, entities: dict[str, tuple[str, list[str]]]) -> DataFrame:
    """(entity, n_null_labels, passed)."""
    out = []
    for t, (template, key) in entities.items():
        known = set(placeholders(template)) <= set(bundle[t].columns)
        one = render(bundle[t], template, key).agg(F.count_if(F.col("label").isNull()).alias("n_null_labels"))
        out.append(one.select(F.lit(t).alias("entity"), "n_null_labels", ((F.col("n_null_labels") == 0) & F.lit(known)).alias("passed")))
    return union_all(out)


def lookup_instances(bundle: SourceBundle, ids: dict[str, list[str]], every: int = 10) -> DataFrame:
    """(entity, n_sampled, n_found): instances picked by the crc of their id are found again by it."""
    out = []
    for t, k in ids.items():
        pick = bundle[t].where(F.crc32(F.col(k[0]).cast("string").cast("binary")) % every == 0).select(*k).distinct()
        found = pick.join(bundle[t], k, "left_semi")
        out.append(pick.agg(F.count("*").alias("n_sampled")).crossJoin(found.agg(F.count("*").alias("n_found"))).select(F.lit(t).alias("entity"), "n_sampled", "n_found"))  # one row each
    return union_all(out)


def coverage(ref: DataFrame, got: DataFrame, on: list[str], by: list[str]) -> DataFrame:
    """(by..., n_hit, n_ref): reference items with a counterpart of the same provenance."""
    hit = got.select(*on).distinct().withColumn("hit", F.lit(1))
    return ref.join(hit, on, "left").groupBy(*by).agg(F.sum(F.coalesce("hit", F.lit(0))).alias("n_hit"), F.count("*").alias("n_ref"))


def agreement(ref: DataFrame, got: DataFrame, on: list[str], value: str, by: list[str]) -> DataFrame:
    """(by..., n_same, n_matched, pct) over matched items."""
    j = ref.join(got.select(*on, F.col(value).alias("__g")), on)
    g = j.groupBy(*by).agg(F.count_if(F.col(value) == F.col("__g")).alias("n_same"), F.count("*").alias("n_matched"))
    return g.withColumn("pct", F.round(100 * F.col("n_same") / F.col("n_matched"), 6))


#: What a role lets a reader derive from an attribute, beside its value.
DERIVED = {"Datetime": {"year", "month", "span"}, "Categorical": {"part"}, "Opaque": {"part"}}


def match(c: Catalog, cls: str, want: dict) -> tuple[str, str]:
    """(literal, adjudicated) verdict on an expectation against a built catalog. Literal: the table is placed, the column is an
    attribute, the join is an edge. Adjudicated: also what the attribute's role licenses, and columns that chains of joins
    equate. What names no column or table at all cannot be satisfied by any catalog."""
    if None in want.values():
        return "unsatisfiable", "unsatisfiable"
    say = lambda literal, adjudicated: tuple("satisfied" if x else "missed" for x in (literal, adjudicated))
    if cls == "entity":
        hit = want["table"] in {e.table for e in c.entities} | set(c.lookups) | set(c.links)
        return say(hit, hit)
    if cls == "feature":
        roles = [a.roles for e in c.entities for a in e.attributes if (e.table, a.src_cols[0]) == (want["table"], want["column"])]
        derive = want.get("derive")
        return say(bool(roles) and not derive, bool(roles) and (not derive or any(derive in DERIVED.get(r, ()) for r in roles[0])))
    g = JoinGraph([(j["from_table"], j["from_col"], j["to_table"], j["to_col"]) for j in c.joins])
    pair = (want["from"], want["to"])
    edges = {(f"{a}.{b}", f"{x}.{y}") for a, b, x, y in g.joins}
    return say(pair in edges, pair in edges or tuple(sorted(pair)) in g.equivalence())


def recall(items: DataFrame) -> DataFrame:
    """Per annotator and class; unsatisfiable items are reported apart, not counted against."""
    g = items.groupBy("annotator", "cls").agg(F.count_if(F.col("verdict") == "satisfied").alias("satisfied"), F.count_if(F.col("verdict") != "unsatisfiable").alias("satisfiable"), F.count_if(F.col("verdict") == "unsatisfiable").alias("unsatisfiable"))
    return g.withColumn("recall", F.round(F.col("satisfied") / F.nullif("satisfiable", F.lit(0)), 6))


def jaccard(runs: DataFrame) -> DataFrame:
    """(run_a, run_b, jaccard) of the item sets of runs (run, item)."""
    a, b = runs.select(F.col("run").alias("run_a"), "item"), runs.select(F.col("run").alias("run_b"), "item")
    size = runs.groupBy("run").agg(F.count("*").alias("n"))
    common = a.join(b, "item").where("run_a < run_b").groupBy("run_a", "run_b").agg(F.count("*").alias("both"))
    out = common.join(size.toDF("run_a", "na"), "run_a").join(size.toDF("run_b", "nb"), "run_b")
    return out.select("run_a", "run_b", F.round(F.col("both") / (F.col("na") + F.col("nb") - F.col("both")), 6).alias("jaccard"))


def audit(c: Catalog, bundle: SourceBundle, unique: dict[str, bool]) -> list[tuple[str, str, str]]:
    """(code, severity, target) of the defects a catalog shows against the frozen facts: columns, and which ids are unique."""
    out, names = [], {(t, col) for t in bundle.tables for col in bundle[t].columns}
    placed = {e.table for e in c.entities} | set(c.links) | set(c.lookups) | {i["table"] for i in c.ignored}
    joins = {f"{j['from_table']}.{j['from_col']}->{j['to_table']}.{j['to_col']}" for j in c.joins}
    for j in c.joins:
        if (j["from_table"], j["from_col"]) not in names or (j["to_table"], j["to_col"]) not in names:
            out.append(("D1", "critical", f"{j['from_table']}.{j['from_col']}"))
    out += [("D2", "critical", t) for t in bundle.tables if t not in placed]
    for e in c.entities:
        if not e.name or not e.table:
            out.append(("D0", "critical", e.table or "?"))
        if e.id_status == "fallback" or not unique.get(e.table, True):
            out.append(("D3", "critical", e.table))
        have = [a.src_cols[0] for a in e.attributes]
        for a in e.attributes:
            if "Metric" in a.roles and (a.isa not in ("integer", "float") or a.src_cols[0] in e.id_columns):
                out.append(("D4", "major", f"{e.table}.{a.name}"))
        out += [("D5", "major", f"{e.table}.{col}") for t, col in sorted(names) if t == e.table and col not in have]
        out += [("D6", "major", f"{e.table}.{p}") for p in placeholders(e.reference) if p not in bundle[e.table].columns]
        for g in e.aggregables:
            steps = [s if "->" in s else "->".join(reversed(s.split("<-"))) for s in g.path]
            if any(s not in joins for s in steps) or g.src_table == e.table:
                out.append(("D7", "major", f"{e.table}.{g.name}"))
            if (g.direction == "many_to_one") == any("<-" in s for s in g.path):
                out.append(("D9", "minor", f"{e.table}.{g.name}"))
        out += [("D8", "minor", f"{e.table}.{col}") for col in sorted({x for x in have if have.count(x) > 1})]
    return out
