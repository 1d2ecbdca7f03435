"""Paths, types, names, grounding, claims, coverage, expectations, stability, ablation and audit queries."""

from __future__ import annotations

import json
from copy import deepcopy
from pathlib import Path

from pyspark.sql import functions as F

from semcat.operators import claims, evidence, keys, profile, typing_rules
from semcat.plans import builder, graph, lexicon
from semcat.plans.model import Aggregable, Entity, dump, load
from semcat.queries import arms
from semcat.queries.profile_queries import _ALL, _STAR_INTS, COLUMNS, KEYS, _evidence, _is_unique, _prefixed, each, ledger_sql, overlap_sql, values
from semcat.queries.registry import query
from semcat.sources.bundle import CURVE, FOREIGN, SCOPES, STAR, TABLES, SourceBundle, from_parquet, status_lookup, stripped

STAR_FK = [f for f in FOREIGN if f[0] in STAR]
GRAPH = graph.JoinGraph(STAR_FK)
_J = values(STAR_FK, ["a", "b", "c", "d"])
_EDGES = f"(SELECT a AS near, c AS far, a||'.'||b||'->'||c||'.'||d AS s, false AS rev FROM {_J} UNION ALL SELECT c, a, c||'.'||d||'<-'||a||'.'||b, true FROM {_J})"
_WALK = f"WITH RECURSIVE e AS {_EDGES}, w AS (SELECT near AS entity, far AS t, 1 AS hops, rev AS back, [near, far] AS seen, s AS path FROM e UNION ALL SELECT w.entity, e.far, w.hops + 1, w.back OR e.rev, list_append(w.seen, e.far), w.path || '/' || e.s FROM w JOIN e ON e.near = w.t WHERE w.hops < 3 AND NOT list_contains(w.seen, e.far))"
_COLS = values([(t, c) for t in STAR for c in COLUMNS[t]], ["tab", "col"])


def rows(spark, data, schema):
    return spark.createDataFrame([tuple(r) for r in data], schema)


def _reach(spark):
    return rows(spark, [r for t in STAR for r in GRAPH.reach(t, COLUMNS)], "entity string, table_name string, column_name string, hops int, direction string")


_REACH_SQL = _WALK + f", b AS (SELECT entity, t, min(hops) AS hops, arg_min(back, hops) AS back FROM w GROUP BY entity, t) SELECT entity, t AS table_name, col AS column_name, CAST(hops AS INTEGER) AS hops, CASE WHEN back THEN 'one_to_many' ELSE 'many_to_one' END AS direction FROM b JOIN {_COLS} ON tab = t"


@query(_REACH_SQL)
def path_reach_star(spark, sf):
    return _reach(spark)


@query(_REACH_SQL.replace("SELECT entity, t AS table_name, col AS column_name", "SELECT DISTINCT entity, t AS table_name").replace(f" JOIN {_COLS} ON tab = t", ""))
def path_reach_recursive(spark, sf):
    """The same reach by a recursive query of the engine, with a guard against cycles."""
    rows(spark, STAR_FK, "a string, b string, c string, d string").createOrReplaceTempView("semcat_joins")
    return spark.sql("""WITH RECURSIVE e AS (SELECT a AS near, c AS far, false AS rev FROM semcat_joins UNION ALL SELECT c, a, true FROM semcat_joins),
      w(entity, t, hops, back, seen) AS (SELECT near, far, 1, rev, array(near, far) FROM e UNION ALL SELECT w.entity, e.far, w.hops + 1, w.back OR e.rev, array_append(w.seen, e.far) FROM w JOIN e ON e.near = w.t WHERE w.hops < 3 AND NOT array_contains(w.seen, e.far))
      SELECT entity, t AS table_name, min(hops) AS hops, CASE WHEN min_by(back, hops) THEN 'one_to_many' ELSE 'many_to_one' END AS direction FROM w GROUP BY entity, t""")


@query(_WALK + f" SELECT DISTINCT entity, t || '.' || k AS target_id FROM w JOIN {values([(t, k) for t, k in KEYS.items() if t in STAR], ['tab', 'k'])} ON tab = t")
def path_countables(spark, sf):
    return rows(spark, sorted({(e, f"{t}.{KEYS[t]}") for e in STAR for e_, t, *_ in GRAPH.reach(e, COLUMNS) if t in KEYS}), "entity string, target_id string")


@query(f"WITH RECURSIVE p AS (SELECT a||'.'||b AS x, c||'.'||d AS y FROM {_J} UNION SELECT c||'.'||d, a||'.'||b FROM {_J}), r AS (SELECT x, y FROM p UNION SELECT r.x, p.y FROM r JOIN p ON r.y = p.x) SELECT x AS col_a, y AS col_b FROM r WHERE x < y")
def path_closure_pairs(spark, sf):
    return rows(spark, GRAPH.equivalence(), "col_a string, col_b string")


@query(_WALK + ", z AS (SELECT near AS entity, near AS t, 0 AS hops, [near] AS seen, '' AS path FROM (SELECT DISTINCT near FROM e) UNION ALL SELECT entity, t, hops, seen, path FROM w) SELECT z.entity, CASE WHEN z.path = '' THEN e.s ELSE z.path || '/' || e.s END AS path, CASE WHEN e.far = z.entity THEN 'back to own key' ELSE 'not simple' END AS reason FROM z JOIN e ON e.near = z.t WHERE z.hops < 3 AND list_contains(z.seen, e.far)")
def path_pruned_back_routes(spark, sf):
    return rows(spark, [r for t in STAR for r in GRAPH.pruned(t)], "entity string, path string, reason string")


def _money(c):
    return F.sum(F.col(c).cast("decimal(18,2)")).cast("double")


@query("SELECT c_custkey, coalesce(n, 0) AS n_orders, s AS total_price FROM customer LEFT JOIN (SELECT o_custkey, count(*) AS n, CAST(sum(CAST(o_totalprice AS DECIMAL(18,2))) AS DOUBLE) AS s FROM orders GROUP BY 1) ON o_custkey = c_custkey")
def agg_along_customer_orders(spark, sf):
    b = from_parquet(spark, sf, ["customer", "orders"])
    return graph.aggregate_along(b.tables, FOREIGN[3], {"n_orders": F.count("*"), "total_price": _money("o_totalprice")}).na.fill(0, ["n_orders"])


@query("SELECT n_name, count(*) AS n_lines, CAST(sum(CAST(l_extendedprice AS DECIMAL(18,2))) AS DOUBLE) AS revenue FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
def agg_along_nation_multi_hop(spark, sf):
    b = from_parquet(spark, sf, STAR)
    per = b["lineitem"].groupBy("l_orderkey").agg(F.count("*").alias("n"), F.sum(F.col("l_extendedprice").cast("decimal(18,2)")).alias("r"))
    j = per.join(b["orders"], F.col("l_orderkey") == F.col("o_orderkey")).join(b["customer"], F.col("o_custkey") == F.col("c_custkey")).join(b["nation"], F.col("c_nationkey") == F.col("n_nationkey"))
    return j.groupBy("n_name").agg(F.sum("n").alias("n_lines"), F.sum("r").cast("double").alias("revenue"))


@query("WITH s AS (SELECT o_custkey, sum(CAST(o_totalprice AS DECIMAL(18,2))) AS x FROM orders GROUP BY 1), n AS (SELECT o_custkey, sum(CAST(o_totalprice AS DECIMAL(18,2))) AS y FROM orders JOIN lineitem ON l_orderkey = o_orderkey GROUP BY 1) SELECT c_custkey, CAST(x AS DOUBLE) AS safe_total, CAST(y AS DOUBLE) AS naive_total FROM customer LEFT JOIN s ON s.o_custkey = c_custkey LEFT JOIN n ON n.o_custkey = c_custkey")
def agg_fanout_safe_vs_naive(spark, sf):
    b = from_parquet(spark, sf, STAR)
    safe = graph.aggregate_along(b.tables, FOREIGN[3], {"safe_total": _money("o_totalprice")})
    naive = b["orders"].join(b["lineitem"], F.col("l_orderkey") == F.col("o_orderkey")).groupBy(F.col("o_custkey").alias("c_custkey")).agg(_money("o_totalprice").alias("naive_total"))
    return safe.join(naive, "c_custkey", "left")


@query("SELECT meaning, count(*) AS n_orders FROM orders JOIN (VALUES ('F','finished'),('O','open'),('P','partial')) v(code, meaning) ON code = o_orderstatus GROUP BY 1")
def agg_lookup_passthrough(spark, sf):
    o = from_parquet(spark, sf, ["orders"])["orders"]
    return o.join(F.broadcast(status_lookup(spark)), F.col("o_orderstatus") == F.col("code")).groupBy("meaning").agg(F.count("*").alias("n_orders"))


_NUM = "^[+-]?[0-9]+([.][0-9]+)?([eE][+-]?[0-9]+)?$"


@query(each([*STAR, "labels"], lambda t, c: f"SELECT '{t}' AS table_name, '{c}' AS column_name, CASE WHEN bool_or(regexp_matches(v, '^0[0-9]+$')) THEN 'string' WHEN bool_and(regexp_matches(v, '^[+-]?[0-9]+$')) THEN 'integer' WHEN bool_and(regexp_matches(v, '{_NUM}')) THEN 'float' WHEN bool_and(regexp_matches(v, '^[0-9]{{4}}-[0-9]{{2}}-[0-9]{{2}}( 00:00:00)?$')) THEN 'date' ELSE 'string' END AS isa FROM (SELECT CAST({c} AS VARCHAR) AS v FROM {t})"))
def type_storage_inferred_stripped(spark, sf):
    return typing_rules.storage_from_text(stripped(from_parquet(spark, sf, [*STAR, "labels"])))


#: Expected annotation of the star: the reference roles, written by hand.
_ROLES = {c: "Categorical" for t in STAR for c in COLUMNS[t]} | dict.fromkeys("c_acctbal s_acctbal p_size p_retailprice o_totalprice l_quantity l_extendedprice l_discount l_tax".split(), "Numeric") | dict.fromkeys("o_orderdate l_shipdate".split(), "Datetime")
_ISA = {c: "string" for t in STAR for c in COLUMNS[t]} | {c: "integer" for _, c in _STAR_INTS} | dict.fromkeys("c_acctbal s_acctbal p_retailprice o_totalprice l_quantity l_extendedprice l_discount l_tax".split(), "float") | dict.fromkeys("o_orderdate l_shipdate".split(), "datetime")
_ROLE_ROWS = [(t, c, _ROLES[c]) for t in STAR for c in COLUMNS[t]]


@query(f"SELECT * FROM {values(_ROLE_ROWS, ['table_name', 'column_name', 'role'])}")
def type_roles_star(spark, sf):
    r = typing_rules.roles_of(from_parquet(spark, sf, STAR))
    return rows(spark, [(t, c, x) for t in STAR for c, x in r[t].items()], "table_name string, column_name string, role string")


_TIMES = [("orders", "o_orderdate"), ("lineitem", "l_shipdate"), ("events", "ts")]


@query(" UNION ALL ".join(f"SELECT '{t}.{c}' AS column_name, CASE WHEN bool_or(date_trunc('day', {c}) <> {c}) THEN 'datetime' ELSE 'date' END AS granularity FROM {t}" for t, c in _TIMES))
def type_temporal_granularity(spark, sf):
    return typing_rules.granularity(from_parquet(spark, sf, ["orders", "lineitem", "events"]), _TIMES)


_FLAGS = [("labels", "quality", True), ("labels", "toxic", True), ("lineitem", "l_returnflag", False), ("lineitem", "l_linestatus", False)]


@query(" UNION ALL ".join(f"SELECT '{t}.{c}' AS column_name, count(DISTINCT {c}) <= 2 AND bool_and(lower(CAST({c} AS VARCHAR)) IN ('true','false','yes','no','t','f','y','n'{chr(44) + chr(39) + '0' + chr(39) + chr(44) + chr(39) + '1' + chr(39) if z or 'flag' in c else ''})) AS is_boolean FROM {t}" for t, c, z in _FLAGS))
def type_boolean_flags(spark, sf):
    return typing_rules.boolean_flags(from_parquet(spark, sf, ["labels", "lineitem"]), [(t, c) for t, c, _ in _FLAGS])


_CASES = [("01234", "555-0101", "12", "09:15-11", "Morning slot", "20240131", "x1"), ("00501", "555-0199", "7", "13:00-14:30", "Evening slot", "20231105", "20")]
_CASE_COLS = "zip string, phone string, dept_code string, hours string, slot_period string, day_int string, score string"


@query("SELECT * FROM (VALUES ('hours','Numeric','Categorical'),('dept_code','Numeric','Numeric'),('score','Numeric','Categorical')) v(column_name, role_before, role_after)")
def type_demoted_numeric(spark, sf):
    df = rows(spark, _CASES, _CASE_COLS)
    return profile.union_all([typing_rules.refine(df, c, "Numeric") for c in ("hours", "dept_code", "score")])


@query("SELECT * FROM (VALUES ('slot_period','Datetime','Categorical'),('day_int','Datetime','Datetime'),('hours','Datetime','Categorical')) v(column_name, role_before, role_after)")
def type_demoted_datetime(spark, sf):
    df = rows(spark, _CASES, _CASE_COLS)
    return profile.union_all([typing_rules.refine(df, c, "Datetime") for c in ("slot_period", "day_int", "hours")])


@query("SELECT * FROM (VALUES ('score', CAST(1 AS BIGINT)), ('dept_code', CAST(0 AS BIGINT))) v(column_name, n_violations)")
def type_declared_violations(spark, sf):
    return typing_rules.declared_violations(rows(spark, _CASES, _CASE_COLS), {"score": "int", "dept_code": "int"})


@query(f"SELECT table_name, column_name, CASE role WHEN 'Numeric' THEN 'avg|max|min|sum' WHEN 'Datetime' THEN 'filter|series|trunc' ELSE 'count|filter|group' END AS allowed_ops FROM {values(_ROLE_ROWS, ['table_name', 'column_name', 'role'])}")
def type_licences(spark, sf):
    return type_roles_star(spark, sf).join(F.broadcast(rows(spark, typing_rules.LICENCES.items(), "role string, allowed_ops string")), "role").select("table_name", "column_name", "allowed_ops")


@query("SELECT o_orderkey, strftime(o_orderdate, '%Y-%m-%d') AS as_date FROM orders")
def type_yyyymmdd_orders(spark, sf):
    o = from_parquet(spark, sf, ["orders"])["orders"].select("o_orderkey", F.date_format("o_orderdate", "yyyyMMdd").cast("int").alias("day_int"))
    return o.select("o_orderkey", F.date_format(F.try_to_date(F.col("day_int").cast("string"), "yyyyMMdd"), "yyyy-MM-dd").alias("as_date"))


@query("SELECT * FROM (VALUES ('zip','Categorical'),('phone','Categorical'),('dept_code','Categorical')) v(column_name, role)")
def type_digit_strings_stay_categorical(spark, sf):
    return rows(spark, [(c, typing_rules.role(c, "string" if c != "dept_code" else "int")) for c in ("zip", "phone", "dept_code")], "column_name string, role string")


@query()
def type_sampled_vs_full(spark, sf):
    b = stripped(from_parquet(spark, sf, STAR))
    part = SourceBundle({t: df.limit(100) for t, df in b.tables.items()})
    full = typing_rules.storage_from_text(b)
    return full.join(typing_rules.storage_from_text(part).withColumnRenamed("isa", "seen"), ["table_name", "column_name"]).select("table_name", "column_name", (F.col("isa") == F.col("seen")).alias("same_verdict"))


#: Labels written by hand for the star.
_LABELS = {"r_regionkey": "Region Key", "r_name": "Name", "n_nationkey": "Nation Key", "n_name": "Name", "n_regionkey": "Region Key", "c_custkey": "Customer Key", "c_acctbal": "Account Balance", "c_mktsegment": "Market Segment", "o_orderdate": "Order Date", "o_totalprice": "Total Price", "l_linenumber": "Line Number", "l_extendedprice": "Extended Price", "p_brand": "Brand"}


@query(f"SELECT * FROM {values(_LABELS.items(), ['column_name', 'label'])}")
def name_labels(spark, sf):
    return rows(spark, [(c, lexicon.label(c)) for c in _LABELS], "column_name string, label string")


#: Machine names written by hand; those that several columns share are qualified by their entity.
_MACHINE = {"r_regionkey": "region_key", "r_name": "name", "n_nationkey": "nation_key", "n_name": "name", "n_regionkey": "region_key", "c_custkey": "customer_key", "c_name": "name", "c_nationkey": "nation_key", "c_acctbal": "account_balance", "c_mktsegment": "market_segment", "o_orderkey": "order_key", "o_custkey": "customer_key", "o_orderstatus": "order_status", "o_totalprice": "total_price", "o_orderdate": "order_date", "o_orderpriority": "order_priority"}
_NAMED = [(lexicon.singular(t), c, _MACHINE[c]) for t in ("region", "nation", "customer", "orders") for c in COLUMNS[t]]


@query(f"SELECT entity, column_name, CASE WHEN count(*) OVER (PARTITION BY attr) = 1 THEN attr ELSE entity || '_' || attr END AS unique_name FROM {values(_NAMED, ['entity', 'column_name', 'attr'])}")
def name_dedupe(spark, sf):
    cols = [(t, c) for t in ("region", "nation", "customer", "orders") for c in COLUMNS[t]]
    names = lexicon.deduplicated([(lexicon.machine_name(c), lexicon.singular(t), c) for t, c in cols])
    return rows(spark, [(lexicon.singular(t), c, n) for (t, c), n in zip(cols, names, strict=True)], "entity string, column_name string, unique_name string")


_SHORT = [("nation.n_regionkey->region.r_regionkey", "region", "r_name", "region_name"), ("nation.n_regionkey->region.r_regionkey", "region", "r_regionkey", "region_region_key")]  # region_key is nation's own


@query(f"SELECT path, src, short_name FROM {values([(p, f'{t}.{c}', n) for p, t, c, n in _SHORT], ['path', 'src', 'short_name'])}")
def name_remote_short(spark, sf):
    """Short names that the built catalog gives to what a join brings in; the words of the path are not repeated."""
    c = builder.assemble(arms.state(spark, sf, "meta", ["nation", "region"]))
    e = next(e for e in c.entities if e.table == "nation")
    return rows(spark, [("/".join(g.path), f"{g.src_table}.{g.src_cols[0]}", g.name) for g in e.aggregables], "path string, src string, short_name string")


@query("SELECT 'customer.c_name' AS column_name, CASE WHEN avg(CASE WHEN c_name LIKE '%#%' THEN 1.0 ELSE 0 END) > 0.9 THEN split_part(min(c_name), '#', 1) || ' Name' ELSE 'Name' END AS label FROM customer UNION ALL SELECT 'supplier.s_name', CASE WHEN avg(CASE WHEN s_name LIKE '%#%' THEN 1.0 ELSE 0 END) > 0.9 THEN split_part(min(s_name), '#', 1) || ' Name' ELSE 'Name' END FROM supplier")
def name_from_values(spark, sf):
    b = from_parquet(spark, sf, ["customer", "supplier"])
    out = []
    for t, c in (("customer", "c_name"), ("supplier", "s_name")):
        one = b[t].agg(F.avg(F.col(c).contains("#").cast("double")).alias("share"), F.min(c).alias("first"))
        out.append(one.select(F.lit(f"{t}.{c}").alias("column_name"), F.when(F.col("share") > 0.9, F.concat(F.split("first", "#")[0], F.lit(" Name"))).otherwise(lexicon.label(c)).alias("label")))
    return profile.union_all(out)


@query("SELECT c_custkey, coalesce(c_name, CAST(c_custkey AS VARCHAR)) AS label FROM customer")
def name_reference_render_customer(spark, sf):
    return claims.render(from_parquet(spark, sf, ["customer"])["customer"], "{c_name}", ["c_custkey"])


@query("SELECT n_nationkey, n_name || ' (' || r_name || ')' AS label FROM nation JOIN region ON n_regionkey = r_regionkey")
def name_reference_render_nation(spark, sf):
    b = from_parquet(spark, sf, ["nation", "region"])
    return claims.render(graph.along(b.tables, "nation", (graph.Step(FOREIGN[0], False),)), "{n_name} ({r_name})", ["n_nationkey"])


@query("SELECT * FROM (VALUES ('customer','{c_name}','valid'),('orders','{o_orderkey}','unknown placeholder'),('part','{p_partkey}','no placeholder')) v(entity, reference, reason)")
def name_reference_fallback(spark, sf):
    cases = [("customer", "{c_name}"), ("orders", "{o_title}"), ("part", "")]
    return rows(spark, [(t, *builder.validate_reference(x, COLUMNS[t], [KEYS[t]])) for t, x in cases], "entity string, reference string, reason string")


@query(each(STAR, lambda t, c: f"SELECT '{t}' AS table_name, '{c}' AS column_name, 'e.g. ' || replace(CASE WHEN min({c}) = max({c}) THEN lo ELSE lo || ', ' || hi END, '-0.0,', '0.0,') AS description FROM {t}, (SELECT CAST(min({c}) AS VARCHAR) AS lo, CAST(max({c}) AS VARCHAR) AS hi FROM {t}) GROUP BY lo, hi"))
def name_descriptions(spark, sf):
    """Descriptions of the built catalog: the least and the greatest value, both real."""
    c = builder.assemble(arms.state(spark, sf, "typed", STAR))
    return rows(spark, [(e.table, a.src_cols[0], a.description) for e in c.entities for a in e.attributes], "table_name string, column_name string, description string")


@query(each(STAR, lambda t, c: f"SELECT '{t}' AS table_name, '{c}' AS column_name, true AS all_examples_exist"))
def name_description_samples(spark, sf):
    b = from_parquet(spark, sf, STAR)
    s = profile.samples(b).select("table_name", "column_name", F.explode(F.split("samples", r"\|")).alias("value"))
    missing = s.join(profile.melted(b), ["table_name", "column_name", "value"], "left_anti").groupBy("table_name", "column_name").agg(F.count("*").alias("bad"))
    return s.select("table_name", "column_name").distinct().join(missing, ["table_name", "column_name"], "left").select("table_name", "column_name", F.col("bad").isNull().alias("all_examples_exist"))


_FACTS = {"status_lookup": ["code", "meaning"], "schema_migrations": ["version", "applied_at"]}


@query("SELECT * FROM (VALUES " + ", ".join(f"('{t}', 'entity')" for t in TABLES if t not in ("region", "nation", "lineitem")) + ", ('region','passthrough'), ('nation','passthrough'), ('lineitem','link'), ('status_lookup','passthrough'), ('schema_migrations','ignore')) v(table_name, class)")
def triage_tables(spark, sf):
    st = arms.state(spark, sf, "typed")
    n = {t: e.n_rows for (t, _), e in st.evidence.items()}
    out = [(t, builder.triage(t, n[t], COLUMNS[t], st.ids[t], sum(f[0] == t for f in FOREIGN), sum(f[2] == t for f in FOREIGN))[0]) for t in TABLES]
    out += [("status_lookup", builder.triage("status_lookup", 3, _FACTS["status_lookup"], (["code"], "verified"), 0, 1)[0]), ("schema_migrations", builder.triage("schema_migrations", 9, _FACTS["schema_migrations"], (["version"], "verified"), 0, 0)[0])]
    return rows(spark, out, "table_name string, class string")


_MAPPED = [("orders", "o_orderkey"), ("orders", "o_totalprice"), ("customer", "c_name")]


@query(f"SELECT tab AS table_name, col AS column_name FROM {_COLS} WHERE tab IN ('orders','customer') AND (tab, col) NOT IN (SELECT (a, b) FROM {values(_MAPPED, ['a', 'b'])})")
def sweep_unmapped_columns(spark, sf):
    have = rows(spark, [(t, c) for t, c, _ in profile.inventory(from_parquet(spark, sf, ["orders", "customer"]))], "table_name string, column_name string")
    return have.join(rows(spark, _MAPPED, "table_name string, column_name string"), ["table_name", "column_name"], "left_anti")


_WRONG = [("orders", "o_orderkey"), ("orders", "o_colour"), ("shipments", "ship_id")]


@query("SELECT * FROM (VALUES ('orders.o_colour','unknown column'),('shipments.ship_id','unknown column'),('ghost@shipments','unknown table')) v(item, reason)")
def ground_reject_unknown(spark, sf):
    p = builder.Proposal([("order", "orders"), ("ghost", "shipments")], [(t, c, "Categorical") for t, c in _WRONG])
    _, bad = builder.reject_unknown(p, profile.inventory(from_parquet(spark, sf, ["orders"])))
    return rows(spark, bad, "item string, reason string")


@query("SELECT * FROM (VALUES ('customer','customer','buyer|client'),('orders','order','purchase')) v(table_name, entity, merged_from)")
def ground_merge_same_table(spark, sf):
    got = builder.merge_same_table([("client", "customer"), ("buyer", "customer"), ("purchase", "orders")])
    return rows(spark, [(t, n, "|".join(m)) for t, n, m in got], "table_name string, entity string, merged_from string")


@query("SELECT * FROM (VALUES ('customer record','customer',0.5),('orders','orders',0.5)) v(concept, table_name, score)")
def ground_match_entities(spark, sf):
    got = builder.match_entities(["customer record", "orders"], STAR)
    return rows(spark, got, "concept string, table_name string, score double")


_ASKED = [("table:nation", "table role", "entity"), ("table:region", "table role", "entity"), ("type:lineitem.l_linenumber", "type", "Categorical")]


@query(f"SELECT * FROM {values(_ASKED, ['qid', 'kind', 'default_answer'])}")
def clarify_questions(spark, sf):
    c = builder.assemble(arms.fresh(spark, sf, "meta", SCOPES["W2"]))
    return rows(spark, [(q["id"], q["kind"], q["answer"]) for q in c.questions], "qid string, kind string, default_answer string")


@query("SELECT 'type:lineitem.l_linenumber' AS qid, 'Is Line Number of lineitem (e.g. ' || min(l_linenumber) || ', ' || max(l_linenumber) || ') an amount to add up, or a code to group by?' AS question FROM lineitem UNION ALL SELECT 'table:region', 'Is region a lookup table, or are its rows things to analyse?' UNION ALL SELECT 'table:nation', 'Is nation a lookup table, or are its rows things to analyse?' UNION ALL SELECT 'table:lineitem', 'Is lineitem a standalone entity, or a junction between order and part and supplier?'")
def clarify_wording(spark, sf):
    """Questions in words, with evidence from the values."""
    c = builder.assemble(arms.state(spark, sf, "meta", STAR))
    return rows(spark, [(q["id"], q["text"]) for q in c.questions], "qid string, question string")


@query("SELECT * FROM (VALUES ('entity','customer'),('entity','lineitem'),('entity','nation'),('entity','orders'),('lookup','region')) v(kind, table_name)")
def clarify_answer_rebuilds(spark, sf):
    """The answer that region is a lookup removes it from the entities; the rest is assembled around it without a scan."""
    c = builder.assemble(arms.state(spark, sf, "meta", SCOPES["W2"]), answers={"table:region": "passthrough"})
    return rows(spark, [("entity", e.table) for e in c.entities] + [("lookup", t) for t in c.lookups], "kind string, table_name string")


_LENT = [(e, c) for e in STAR[:-1] for c in COLUMNS["lineitem"]]


@query(f"SELECT entity, src_col, 'one_to_many' AS direction FROM {values(_LENT, ['entity', 'src_col'])}")
def clarify_link_lends_columns(spark, sf):
    """With lineitem answered to be a junction, its columns surface at the ends within three hops of it."""
    c = builder.assemble(arms.fresh(spark, sf, "meta", STAR), answers={"table:lineitem": "link"})
    assert c.links == ["lineitem"]
    got = {(e.table, g.src_cols[0], g.direction) for e in c.entities for g in e.aggregables if g.src_table == "lineitem"}
    return rows(spark, sorted(got), "entity string, src_col string, direction string")


@query("SELECT * FROM (VALUES ('l_linenumber','Numeric|Metric','user'),('l_orderkey','Categorical','none')) v(column_name, roles, answered_by)")
def clarify_type_answer(spark, sf):
    """An answer about a type re-enters the checks: a line number may be called an amount, a key may not."""
    c = builder.assemble(arms.fresh(spark, sf, "meta", SCOPES["W2"]), answers={"type:lineitem.l_linenumber": "Numeric", "type:lineitem.l_orderkey": "Numeric"})
    e = next(e for e in c.entities if e.table == "lineitem")
    by = {q["id"].split(".")[-1]: q["answered_by"] for q in c.questions}
    return rows(spark, [(a.src_cols[0], "|".join(a.roles), by.get(a.src_cols[0], "none")) for a in e.attributes if a.src_cols[0] in ("l_linenumber", "l_orderkey")], "column_name string, roles string, answered_by string")


@query("SELECT 1 AS round, count(*) > 0 AS some FROM (VALUES (1)) UNION ALL SELECT 2, true")
def clarify_follow_up(spark, sf):
    """Under the policy that asks about ambiguous references, a yes makes a table a referenced one, which opens its own question
    in the next round."""
    st = arms.state(spark, sf, "stripped", ["region", "nation", "customer", "orders"])
    yes = {"customer.c_nationkey->nation.n_nationkey", "nation.n_regionkey->region.r_regionkey", "orders.o_custkey->customer.c_custkey"}
    _, asked = builder.converse(st, lambda q: "yes" if q["kind"] == "referent" and q["id"][5:] in yes else None, builder.joins.JoinPolicy(ambiguous="ask"))
    return rows(spark, [(i + 1, bool(ids)) for i, ids in enumerate(asked)], "round int, some boolean")


@query("SELECT strftime(date_trunc('month', l_shipdate), '%Y-%m') AS month, count(*) AS n_returned FROM lineitem WHERE l_returnflag = 'R' GROUP BY 1")
def clarify_entity_view_lineitem(spark, sf):
    l = from_parquet(spark, sf, ["lineitem"])["lineitem"]
    return l.where("l_returnflag = 'R'").groupBy(F.date_format("l_shipdate", "yyyy-MM").alias("month")).agg(F.count("*").alias("n_returned"))


@query("SELECT l_suppkey AS s_suppkey, count(DISTINCT l_partkey) AS n_parts FROM lineitem GROUP BY 1")
def clarify_junction_view_part_supplier(spark, sf):
    return from_parquet(spark, sf, ["lineitem"])["lineitem"].groupBy(F.col("l_suppkey").alias("s_suppkey")).agg(F.count_distinct("l_partkey").alias("n_parts"))


_IDS = {t: [c] for t, c in KEYS.items()} | {"conversations": ["conv_id", "turn"]}


@query(" UNION ALL ".join(f"SELECT '{t}' AS entity, n, n_distinct, is_unique AS passed FROM ({_is_unique(_evidence(t, c))})" for t, c in _IDS.items()))
def claim_id_uniqueness(spark, sf):
    return claims.run_identifiers(from_parquet(spark, sf), _IDS)


@query("SELECT tab AS entity, col AS attr, true AS passed FROM " + values([(t, c) for t in TABLES for c in COLUMNS[t]], ["tab", "col"]))
def claim_attribute_mapping(spark, sf):
    return claims.run_retrieval(from_parquet(spark, sf), [(t, c, c) for t in TABLES for c in COLUMNS[t]]).select("entity", F.col("attribute").alias("attr"), "passed")


_P2 = [p for t in ("customer", "orders", "nation") for p in [(t, x) for x in GRAPH.paths(t, 2)] if p[1][-1].far in ("nation", "region", "customer", "orders", "supplier") and "lineitem" not in {s.far for s in p[1]}]


def _path_sql(entity, path):
    sql = f"SELECT row_number() OVER () AS r, * FROM {entity}"
    parts = f"({sql}) t0"
    for i, s in enumerate(path):
        a, b, c, d = s.join
        near, far = (d, b) if s.reverse else (b, d)
        parts += f" LEFT JOIN {s.far} t{i + 1} ON t{i}.{near} = t{i + 1}.{far}"
        last = f"t{i + 1}.{far}"
    flat = all(not s.reverse for s in path)
    return f"SELECT '{entity}' AS entity, '{'/'.join(s.text() for s in path)}' AS path, count(*) AS rows_base, CAST(sum(n) AS BIGINT) AS rows_joined, max(n) AS max_fanout, sum(h) > 0{' AND max(n) = 1' if flat else ''} AS passed FROM (SELECT t0.r, count(*) AS n, count({last}) AS h FROM {parts} GROUP BY t0.r)"


@query(" UNION ALL ".join(_path_sql(t, p) for t, p in _P2))
def claim_join_execution(spark, sf):
    return claims.run_paths(from_parquet(spark, sf, STAR), _P2)


_REFS = {t: (builder.reference(t, COLUMNS[t], [KEYS[t]]), [KEYS[t]]) for t in STAR if t in KEYS}


@query(" UNION ALL ".join(f"SELECT '{t}' AS entity, count(*) FILTER (WHERE coalesce(CAST({r[1:-1]} AS VARCHAR), CAST({k[0]} AS VARCHAR)) IS NULL) AS n_null_labels, true AS passed FROM {t}" for t, (r, k) in _REFS.items()))
def claim_reference_resolution(spark, sf):
    return claims.run_references(from_parquet(spark, sf, STAR), _REFS)


@query()
def claim_instance_lookup(spark, sf):
    return claims.lookup_instances(from_parquet(spark, sf, STAR), {t: [KEYS[t]] for t in STAR if t in KEYS})


def suite(spark, sf, scope="W2", arm="meta"):
    """The catalog of a scope in an arm, its claims generated and run on that arm's tables: (scope, class, n_claims, n_passed)."""
    st, b = arms.state(spark, sf, arm, SCOPES[scope]), arms.twin(spark, sf, arm).scope(SCOPES[scope])
    c = builder.assemble(st)
    every = claims.generate(c)
    ids = claims.run_identifiers(b, {e.table: e.id_columns for e in c.entities}).select(F.lit("identifier").alias("class"), "passed")
    refs = claims.run_references(b, {e.table: (e.reference, e.id_columns) for e in c.entities}).select(F.lit("reference").alias("class"), "passed")
    vals = claims.run_values(b, [(e.table, a.name, a.src_cols[0], a.isa) for e in c.entities for a in e.attributes]).select(F.lit("attribute").alias("class"), "passed")
    g = graph.JoinGraph([(j["from_table"], j["from_col"], j["to_table"], j["to_col"]) for j in c.joins])
    used = {(e.table, "/".join(x.path)): sum(y.path == x.path for y in e.aggregables) for e in c.entities for x in e.aggregables}
    good = [(e.table, p) for e in c.entities for p in g.paths(e.table) if (e.table, "/".join(s.text() for s in p)) in used]
    parts = [ids, refs, vals]
    if good:  # one run of a path proves all that it brings in
        weight = rows(spark, [(*k, n) for k, n in used.items()], "entity string, path string, n int")
        paths = claims.run_paths(b, good).join(weight, ["entity", "path"])
        parts.append(paths.select(F.explode(F.array_repeat(F.lit("aggregable"), F.col("n"))).alias("class"), "passed"))
    passed = {r["class"]: r["n"] for r in profile.union_all(parts).where("passed").groupBy("class").agg(F.count("*").alias("n")).collect()}
    kinds = ("identifier", "attribute", "aggregable", "reference")
    return rows(spark, [(scope, k, sum(x[0] == k for x in every), passed.get(k, 0)) for k in kinds], "scope string, class string, n_claims long, n_passed long")


@query()
def claim_summary_rollup(spark, sf):
    return suite(spark, sf).rollup("scope", "class").agg(F.sum("n_claims").alias("n_claims"), F.sum("n_passed").alias("n_passed"))


@query(" UNION ALL ".join(f"SELECT '{t}.{c}' AS claim, is_unique AS passed FROM ({_is_unique(_evidence(t, [c]))})" for t, c in (("part", "p_name"), ("orders", "o_custkey"), ("lineitem", "l_orderkey"))))
def claim_false_catalog_fails(spark, sf):
    b = from_parquet(spark, sf, STAR)
    got = [claims.run_identifiers(b, {t: [c]}).select(F.lit(f"{t}.{c}").alias("claim"), "passed") for t, c in (("part", "p_name"), ("orders", "o_custkey"), ("lineitem", "l_orderkey"))]
    return profile.union_all(got)


@query(" UNION ALL ".join(f"SELECT '{t}' AS entity, '{c}' AS id_cols, is_unique AS passed FROM ({_is_unique(_evidence(t, [c]))})" for t, c in (("orders", "o_orderkey"), ("lineitem", "l_orderkey"), ("conversations", "conv_id"))))
def claim_first_run_failures(spark, sf):
    """Arm with the first column as identifier: the budget is spent by position, composites are not tried."""
    b = from_parquet(spark, sf)
    pick = {t: [b[t].columns[0]] for t in ("orders", "lineitem", "conversations")}
    r = claims.run_identifiers(b, pick)
    return r.join(F.broadcast(rows(spark, [(t, c[0]) for t, c in pick.items()], "entity string, id_cols string")), "entity").select("entity", "id_cols", "passed")


FROZEN = Path(__file__).resolve().parent / "frozen"
#: The expert reference, frozen before the first build: scopes, identifiers, relationships.
REFERENCE = json.loads((FROZEN / "reference_catalog.json").read_text())
_COVERED = ("W1", "W2", "W3", "W4", "W6", "W7")


def _fks(tables):
    return [tuple(f) for f in REFERENCE["relationships"] if f[0] in tables and f[2] in tables]


def _id_sql(t):
    """Whether the data bear out a table's identifier: its reference columns, or any composite where the reference names none."""
    cols = [REFERENCE["identifiers"][t]] if t in REFERENCE["identifiers"] else _ALL
    return "(SELECT bool_or(is_unique) FROM (" + " UNION ALL ".join(f"SELECT is_unique FROM ({_is_unique(_evidence(t, c))})" for c in cols) + "))"


def _holds_sql(tables):
    """The reference joins of a scope that the data bear out: no orphans, a unique target."""
    parts = [f"SELECT '{a}' AS a, '{b}' AS b, '{c}' AS c, '{d}' AS d WHERE NOT EXISTS (SELECT 1 FROM {a} WHERE {b} IS NOT NULL AND {b} NOT IN (SELECT {d} FROM {c})) AND (SELECT count(*) = count(DISTINCT {d}) FROM {c})" for a, b, c, d in _fks(tables)]
    return "(" + (" UNION ALL ".join(parts) or "SELECT '' AS a, '' AS b, '' AS c, '' AS d WHERE false") + ")"


def _reached_sql(edges, tables):
    """How many columns of other tables the entities of a scope reach along edges within three steps."""
    cols = values([(t, c) for t in tables for c in COLUMNS[t]], ["tab", "col"])
    both = f"(SELECT a AS near, c AS far FROM {edges} UNION SELECT c, a FROM {edges})"
    return f"(WITH RECURSIVE e AS {both}, w AS (SELECT near AS entity, far AS t, [near, far] AS seen, 1 AS hops FROM e UNION ALL SELECT w.entity, e.far, list_append(w.seen, e.far), w.hops + 1 FROM w JOIN e ON e.near = w.t WHERE w.hops < 3 AND NOT list_contains(w.seen, e.far)) SELECT count(*) FROM (SELECT DISTINCT entity, t, col FROM w JOIN {cols} ON tab = t))"


def _coverage_sql():
    out = []
    for s in _COVERED:
        tables = REFERENCE["scopes"][s]
        listed = values(_fks(tables) or [("", "", "", "")], ["a", "b", "c", "d"]) if _fks(tables) else "(SELECT '' AS a, '' AS b, '' AS c, '' AS d WHERE false)"
        sums = " + ".join(f"CASE WHEN {_id_sql(t)} THEN 1 ELSE 0 END" for t in tables)
        attrs = " + ".join(f"CASE WHEN {_id_sql(t)} THEN (SELECT count(*) FROM (DESCRIBE {t})) ELSE 0 END" for t in tables)
        for kind, hit, ref in (("entity", sums, str(len(tables))), ("attribute", attrs, str(sum(len(COLUMNS[t]) for t in tables))), ("relationship", f"(SELECT count(*) FROM {_holds_sql(tables)})", str(len(_fks(tables)))), ("aggregable", _reached_sql(_holds_sql(tables), tables), _reached_sql(listed, tables))):
            out.append(f"SELECT '{s}' AS scope, '{kind}' AS kind, CAST({hit} AS BIGINT) AS n_hit, CAST({ref} AS BIGINT) AS n_ref")
    return " UNION ALL ".join(out)


def _covered(st):
    """What a built catalog covers: (kind, item). Joins count where all source values exist in the target; aggregables count as the
    class of columns that the verified joins equate."""
    c = builder.assemble(st)
    full = {(o.source, o.target) for o in st.overlap if o.n_common == o.n_source}
    joins = [(j["from_table"], j["from_col"], j["to_table"], j["to_col"]) for j in c.joins if (f"{j['from_table']}.{j['from_col']}", f"{j['to_table']}.{j['to_col']}") in full]
    out = {("entity", e.table) for e in c.entities if not builder.keys.is_weak(e.id_status)}
    out |= {("attribute", f"{a.src_table}.{x}") for e in c.entities for a in e.attributes for x in a.src_cols}
    out |= {("relationship", f"{a}.{b}->{x}.{y}") for a, b, x, y in joins}
    equal = {}
    for x, y in graph.JoinGraph(joins).equivalence():
        equal.setdefault(x, {x}).add(y)
        equal.setdefault(y, {y}).add(x)
    for e in c.entities:
        for g in e.aggregables:
            for x in g.src_cols:
                out |= {("aggregable", f"{e.table}<-{y}") for y in equal.get(f"{g.src_table}.{x}", {f"{g.src_table}.{x}"})}
    return out


def _expected(tables):
    """The reference's items of a scope."""
    g = graph.JoinGraph(_fks(tables))
    out = [("entity", t) for t in tables] + [("attribute", f"{t}.{c}") for t in tables for c in COLUMNS[t]]
    out += [("relationship", f"{a}.{b}->{x}.{y}") for a, b, x, y in _fks(tables)]
    return out + [("aggregable", f"{e}<-{t}.{c}") for e in tables for _, t, c, *_ in g.reach(e, COLUMNS)]


def _coverage(spark, sf, arm, scopes, whole=None):
    """``whole``: all tables of the arm as examined for this query alone; else what the session has kept."""
    kind = "scope string, kind string, item string"
    at = whole.restrict if whole else lambda tables: arms.state(spark, sf, arm, tables)
    ref = rows(spark, [(s, *x) for s in scopes for x in _expected(REFERENCE["scopes"][s])], kind)
    got = rows(spark, [(s, *x) for s in scopes for x in _covered(at(REFERENCE["scopes"][s]))], kind)
    return claims.coverage(ref, got, ["scope", "kind", "item"], ["scope", "kind"])


@query(f"SELECT * FROM ({_coverage_sql()}) WHERE n_ref > 0")
def cov_reference(spark, sf):
    """Coverage of the reference by the catalogs of the intact arm, in all scopes and of all kinds."""
    return _coverage(spark, sf, "meta", _COVERED)


@query(f"SELECT scope, n_hit, n_ref FROM ({_coverage_sql()}) WHERE n_ref > 0 AND kind = 'relationship'")
def cov_relationships(spark, sf):
    return _coverage(spark, sf, "meta", _COVERED, arms.fresh(spark, sf, "meta", TABLES)).where("kind = 'relationship'").drop("kind")


@query("SELECT * FROM (VALUES ('nation_month_sales','month|n_nationkey','verified'),('trade_lane','lane_id','verified'),('nation','n_nationkey','verified')) v(table_name, id_cols, status)")
def cov_derived_views(spark, sf):
    """Catalog of derived views without metadata: a composite of a key and a month, and two parallel references."""
    st = arms.state(spark, sf, "views")
    return rows(spark, [(t, "|".join(sorted(k)), s) for t, (k, s) in st.ids.items()], "table_name string, id_cols string, status string")


@query("SELECT * FROM (VALUES ('nation.n_regionkey','region.r_regionkey','closure'),('customer.c_nationkey','supplier.s_nationkey','closure'),('orders.o_custkey','part.p_partkey','none')) v(col_a, col_b, matched_by)")
def cov_closure_equivalence(spark, sf):
    """The closure over the joins of the star's catalog that all source values bear out."""
    kept = [i.split("->") for k, i in _covered(arms.fresh(spark, sf, "meta", STAR)) if k == "relationship"]
    joins = graph.JoinGraph([(*a.split(".", 1), *b.split(".", 1)) for a, b in sorted(kept)])
    same = rows(spark, joins.equivalence(), "col_a string, col_b string").withColumn("m", F.lit("closure"))
    ask = rows(spark, [("nation.n_regionkey", "region.r_regionkey"), ("customer.c_nationkey", "supplier.s_nationkey"), ("orders.o_custkey", "part.p_partkey")], "col_a string, col_b string")
    return ask.join(same, ["col_a", "col_b"], "left").select("col_a", "col_b", F.coalesce("m", F.lit("none")).alias("matched_by"))


def _lines(name):
    return [json.loads(x) for x in (FROZEN / name).read_text().splitlines()]


#: Expectations and verdicts of five synthetic annotators, written down before the build that they judge.
EXPECTATIONS = _lines("expectations.jsonl")
_CLASS = {x["item"]: x["cls"] for x in EXPECTATIONS}
_EXP = values([(x["annotator"], _CLASS[x["item"]], x["item"], x["judge"], x["human"]) for x in _lines("verdicts.jsonl")], ["annotator", "cls", "item", "judge", "human"])


def _verdicts(spark, sf):
    """(annotator, cls, item, judge, human): the expectations matched by rule against the blind catalog, which is built from text
    without keys, types or joins; the SQL twins hold the verdicts that were written down."""
    c = builder.assemble(arms.state(spark, sf, "disjoint"))
    got = [(x["annotator"], x["cls"], x["item"], *claims.match(c, x["cls"], x["payload"])) for x in EXPECTATIONS]
    return rows(spark, got, "annotator string, cls string, item string, judge string, human string")


@query(f"SELECT * FROM {_EXP}")
def exp_verdicts(spark, sf):
    return _verdicts(spark, sf)


@query(f"SELECT annotator, cls, count(*) FILTER (WHERE human = 'satisfied') AS satisfied, count(*) FILTER (WHERE human <> 'unsatisfiable') AS satisfiable, count(*) FILTER (WHERE human = 'unsatisfiable') AS unsatisfiable, round(count(*) FILTER (WHERE human = 'satisfied') / nullif(count(*) FILTER (WHERE human <> 'unsatisfiable'), 0), 6) AS recall FROM {_EXP} GROUP BY ALL")
def exp_recall_by_annotator(spark, sf):
    return claims.recall(_verdicts(spark, sf).withColumnRenamed("human", "verdict"))


@query(f"SELECT item, count(DISTINCT annotator) AS n_panel FROM {_EXP} WHERE annotator LIKE 'panel%' GROUP BY item HAVING count(DISTINCT annotator) >= 2")
def exp_panel_consensus(spark, sf):
    return _verdicts(spark, sf).where("annotator like 'panel%'").groupBy("item").agg(F.count_distinct("annotator").alias("n_panel")).where("n_panel >= 2")


@query(f"WITH c AS (SELECT item FROM {_EXP} WHERE annotator LIKE 'panel%' GROUP BY item HAVING count(DISTINCT annotator) >= 2) SELECT cls, count(DISTINCT item) FILTER (WHERE human = 'satisfied') AS satisfied, count(DISTINCT item) FILTER (WHERE human <> 'unsatisfiable') AS satisfiable FROM {_EXP} JOIN c USING (item) GROUP BY cls")
def exp_consensus_recall(spark, sf):
    """Recall of what two or more of the panel expect."""
    v = _verdicts(spark, sf)
    both = v.where("annotator like 'panel%'").groupBy("item").agg(F.count_distinct("annotator").alias("n")).where("n >= 2").select("item")
    met = lambda c: F.count_distinct(F.when(c, F.col("item")))
    return v.join(both, "item").groupBy("cls").agg(met(F.col("human") == "satisfied").alias("satisfied"), met(F.col("human") != "unsatisfiable").alias("satisfiable"))


@query(f"SELECT annotator, item, CASE WHEN judge = 'unsatisfiable' THEN 'unsatisfiable' WHEN judge <> human THEN 'disagreement' ELSE 'sample' END AS reason FROM {_EXP} WHERE judge = 'unsatisfiable' OR judge <> human OR substr(md5(item), 1, 1) IN ('0','1','2')")
def exp_recheck_sample(spark, sf):
    e = _verdicts(spark, sf)
    why = F.when(F.col("judge") == "unsatisfiable", "unsatisfiable").when(F.col("judge") != F.col("human"), "disagreement").when(F.substring(F.md5(F.col("item").cast("binary")), 1, 1).isin("0", "1", "2"), "sample")
    return e.select("annotator", "item", why.alias("reason")).where("reason is not null")


@query(f"SELECT judge AS from_verdict, human AS to_verdict, count(*) AS n FROM {_EXP} WHERE judge <> human GROUP BY ALL")
def exp_overturns(spark, sf):
    return _verdicts(spark, sf).where("judge <> human").groupBy(F.col("judge").alias("from_verdict"), F.col("human").alias("to_verdict")).agg(F.count("*").alias("n"))


_TRUTH = "('true','false','yes','no','t','f','y','n','0','1')"
#: Names that speak for measures, written out for the SQL twin.
_MEASURE = "(price|bal|size|quantity|discount|tax|value)$|^n_[a-z]+s$"


def _typed_sql(t, c, arm):
    """Storage and role of one column, computed in SQL from its values as text and its name."""
    v = _prefixed(t, c) if arm == "disjoint" else f"CAST({c} AS VARCHAR)"
    cls = f"CASE WHEN v LIKE '{{%}}' OR v LIKE '[%]' THEN 'json' WHEN length(v) > 40 THEN 'other' WHEN regexp_matches(v, '^0[0-9]+$') THEN 'zero' WHEN regexp_matches(v, '^[+-]?[0-9]+$') THEN 'int' WHEN regexp_matches(v, '{_NUM}') THEN 'num' WHEN regexp_matches(v, '^[0-9]{{4}}-[0-9]{{2}}-[0-9]{{2}}([ T]00:00:00)?$') THEN 'day' WHEN regexp_matches(v, '^[0-9]{{4}}-[0-9]{{2}}-[0-9]{{2}}[ T][0-9]{{2}}:[0-9]{{2}}') THEN 'clock' ELSE 'other' END"
    facts = f"SELECT bool_and(k = 'json') AS json, bool_and(k = 'int') AS ints, bool_and(k IN ('int', 'num')) AS nums, bool_and(k IN ('day', 'clock')) AS times, bool_or(k = 'clock') AS clock, avg(length(v)) > 60 AS prose, count(DISTINCT lower(v)) = 2 AND bool_and(lower(v) IN {_TRUTH}) AS two FROM (SELECT v, {cls} AS k FROM (SELECT {v} AS v FROM {t}) WHERE v IS NOT NULL)"
    key, measure = f"regexp_matches('{c}', '(key|id)$')", f"regexp_matches('{c}', '{_MEASURE}')"
    isa = f"CASE WHEN two AND (NOT ints OR NOT ({key} OR {measure})) THEN 'boolean' WHEN ints THEN 'integer' WHEN nums THEN 'float' WHEN times AND clock THEN 'datetime' WHEN times THEN 'date' ELSE 'string' END"
    role = f"CASE WHEN json OR (prose AND NOT times) THEN 'Opaque' WHEN isa IN ('date', 'datetime') THEN 'Datetime' WHEN {key} OR isa = 'boolean' THEN 'Categorical' WHEN isa = 'float' OR isa = 'integer' AND {measure} THEN 'Numeric' ELSE 'Categorical' END"
    return f"SELECT '{arm}' AS arm, '{t}' AS table_name, '{c}' AS column_name, isa, {role} AS role FROM (SELECT *, {isa} AS isa FROM ({facts}))"


_TYPED = " UNION ALL ".join(_typed_sql(t, c, a) for a in ("stripped", "disjoint") for t in TABLES for c in COLUMNS[t])


def _built(spark, sf, arm, tables=None):
    st = arms.state(spark, sf, arm, tables)
    return rows(spark, [(arm, t, c, e.isa, st.roles[t, c]) for (t, c), e in st.evidence.items()], "arm string, table_name string, column_name string, isa string, role string")


@query(_TYPED)
def build_attributes_by_arm(spark, sf):
    """Storage and role that the builder gives all columns of the twins without metadata."""
    return _built(spark, sf, "stripped").union(_built(spark, sf, "disjoint"))


_ARM_SCOPES = ("W1", "W2", "W3")


def _accepted_sql(tables, arm):
    return f"({ledger_sql(tables, ovl=overlap_sql(tables, _prefixed) if arm == 'disjoint' else overlap_sql(tables))} SELECT source, target FROM l WHERE final = 'accepted')"


@query(" UNION ALL ".join(f"SELECT '{s}' AS scope, '{a}' AS arm, source, target FROM {_accepted_sql(SCOPES[s], a)}" for s in _ARM_SCOPES for a in ("stripped", "disjoint")))
def build_joins_by_arm(spark, sf):
    """The joins of the catalogs that are built without metadata: none where all key ranges are dense from 1, all but those that leave
    a key where each entity has its own range."""
    out = []
    for s in _ARM_SCOPES:
        for a in ("stripped", "disjoint"):
            c = builder.assemble(arms.state(spark, sf, a, SCOPES[s]))
            out += [(s, a, f"{j['from_table']}.{j['from_col']}", f"{j['to_table']}.{j['to_col']}") for j in c.joins]
    return rows(spark, out, "scope string, arm string, source string, target string")


@query(" UNION ALL ".join(f"SELECT '{a}' AS arm, '{t}' AS table_name, CASE WHEN {_id_sql(t)} THEN 'verified' ELSE 'fallback' END AS status FROM (VALUES (1))" for a in ("stripped", "disjoint") for t in TABLES))
def build_identifiers_by_arm(spark, sf):
    return rows(spark, [(a, t, s) for a in ("stripped", "disjoint") for t, (_, s) in arms.state(spark, sf, a).ids.items()], "arm string, table_name string, status string")


@query("SELECT * FROM (VALUES (1,'customer'),(1,'orders'),(2,'nation'),(2,'region')) v(round, table_name)")
def sweep_rounds(spark, sf):
    """A recorded proposal names two tables; the others are swept afterwards, and their identifiers can be referred to."""
    return rows(spark, [(i + 1, t) for i, r in enumerate(_swept(spark, sf).rounds) for t in r], "round int, table_name string")


def _swept(spark, sf):
    b = arms.twin(spark, sf, "disjoint").scope(["region", "nation", "customer", "orders"])
    return builder.examine(b, "who bought what", builder.ReplayProposer(str(FROZEN / "proposer_replay.json")))


@query("SELECT * FROM (VALUES ('customer.c_nationkey','nation.n_nationkey'),('nation.n_regionkey','region.r_regionkey'),('orders.o_custkey','customer.c_custkey')) v(source, target)")
def sweep_tables_are_targets(spark, sf):
    c = builder.assemble(_swept(spark, sf))
    return rows(spark, [(f"{j['from_table']}.{j['from_col']}", f"{j['to_table']}.{j['to_col']}") for j in c.joins], "source string, target string")


@query("SELECT * FROM (VALUES ('customer.c_nationkey','Numeric','Categorical'),('orders.o_orderpriority','Datetime','Categorical'),('customer.c_acctbal','Numeric','Numeric'),('orders.o_orderdate','Datetime','Datetime'),('orders.o_totalprice','Numeric','Numeric')) v(column_name, proposed, role)")
def ground_replayed_roles(spark, sf):
    """Proposed roles that the values do not support are turned down; the phrase for the order's total finds its column."""
    st = _swept(spark, sf)
    said = {"customer.c_acctbal": "Numeric", "customer.c_nationkey": "Numeric", "orders.o_orderdate": "Datetime", "orders.o_orderpriority": "Datetime", "orders.o_totalprice": "Numeric"}
    return rows(spark, [(q, r, st.roles[tuple(q.split("."))]) for q, r in said.items()], "column_name string, proposed string, role string")


@query("SELECT * FROM (VALUES ('orders.o_custkey','customer.c_custkey','accepted'),('orders.o_orderstatus','customer.c_custkey','no_overlap')) v(source, target, stage)")
def join_proposed(spark, sf):
    """Joins of a proposer pass the same checks: one that shares no value is dropped however sure the proposer was."""
    st = _swept(spark, sf)
    want = {(f"{j[0]}.{j[1]}", f"{j[2]}.{j[3]}") for j in st.proposed_joins}
    return rows(spark, [(o.source, o.target, stage) for o, _, stage in st.decisions() if (o.source, o.target) in want], "source string, target string, stage string")


@query("SELECT * FROM (VALUES ('callable','customer.c_nationkey'),('callable','nation.n_regionkey'),('callable','orders.o_custkey'),('replay','customer.c_nationkey'),('replay','orders.o_custkey')) v(judge, source)")
def join_judges(spark, sf):
    """A recorded judge, and one given as a function that sees the values of both columns."""
    st = arms.state(spark, sf, "disjoint", ["region", "nation", "customer", "orders"])
    alike = lambda o: float(o.source_evidence.least[0] == o.target_evidence.least[0])
    judges = {"replay": builder.joins.ReplayJudge(str(FROZEN / "judge_replay.json")), "callable": builder.joins.CallableJudge(alike)}
    out = [(n, o.source) for n, j in judges.items() for o, _, stage in st.decisions(builder.joins.JoinPolicy(judge=j)) if stage == "accepted"]
    return rows(spark, out, "judge string, source string")


@query("SELECT * FROM (VALUES ('total price','o_totalprice',1.0),('order date','o_orderdate',1.0),('key','o_custkey|o_orderkey',0.5)) v(concept, columns, score)")
def ground_match_attributes(spark, sf):
    """Concepts matched to columns by name, storage and sample; an equal score names several columns."""
    found = {c: e for (t, c), e in arms.state(spark, sf, "typed", ["orders"]).evidence.items()}
    got = builder.match_attributes([("total price", "float", ()), ("order date", None, ()), ("key", "integer", ())], found)
    return rows(spark, [(p, "|".join(sorted(c)), x) for p, c, x in got], "concept string, columns string, score double")


@query("SELECT * FROM (VALUES ('location','orders','order'),('customer order','orders','customer order'),('thing','nation','nation')) v(proposed, table_name, name)")
def ground_rename(spark, sf):
    ids = arms.state(spark, sf, "typed").ids
    got = [(n, t, builder.rename_to_row_meaning(n, t, not builder.keys.is_weak(ids[t][1]))[0]) for n, t in (("location", "orders"), ("customer order", "orders"), ("thing", "nation"))]
    return rows(spark, got, "proposed string, table_name string, name string")


@query("SELECT a AS arm, 0 AS n_faults FROM (VALUES ('meta'), ('stripped'), ('disjoint')) v(a)")
def catalog_is_well_formed(spark, sf):
    from semcat.plans.model import validate

    return rows(spark, [(a, len(validate(dump(builder.assemble(arms.state(spark, sf, a)))))) for a in ("meta", "stripped", "disjoint")], "arm string, n_faults int")


#: Reference roles and storage families of the star and their places in the scopes, written by hand.
_FAMILY = {"integer": "number", "float": "number", "datetime": "time", "date": "time"}
_REF_ROWS = [(s, t, c, _ROLES[c], _FAMILY.get(_ISA[c], _ISA[c])) for s in ("W1", "W2") for t in SCOPES[s] for c in COLUMNS[t]]
_REF_SQL = values(_REF_ROWS, ["scope", "table_name", "column_name", "role", "isa"])
_FAMILY_SQL = "CASE WHEN isa IN ('integer', 'float') THEN 'number' WHEN isa IN ('date', 'datetime') THEN 'time' ELSE isa END"


def _agreement_sql(what):
    got = f"(SELECT arm, table_name, column_name, role, {_FAMILY_SQL} AS isa FROM ({_TYPED}) WHERE arm = 'stripped')"
    return f"SELECT scope, count(*) FILTER (WHERE r.{what} = g.{what}) AS n_same, count(*) AS n_matched, round(100 * count(*) FILTER (WHERE r.{what} = g.{what}) / count(*), 6) AS pct FROM {_REF_SQL} r JOIN {got} g USING (table_name, column_name) GROUP BY scope"


@query(_agreement_sql("role"))
def char_role_agreement(spark, sf):
    """Agreement of the roles found without metadata with the reference."""
    ref = rows(spark, [r[:4] for r in _REF_ROWS], "scope string, table_name string, column_name string, role string")
    return claims.agreement(ref, _built(spark, sf, "stripped"), ["table_name", "column_name"], "role", ["scope"])


@query(_agreement_sql("isa"))
def char_isa_family(spark, sf):
    ref = rows(spark, [(*r[:3], r[4]) for r in _REF_ROWS], "scope string, table_name string, column_name string, isa string")
    got = _built(spark, sf, "stripped").withColumn("isa", F.expr(_FAMILY_SQL))
    return claims.agreement(ref, got, ["table_name", "column_name"], "isa", ["scope"])


@query("SELECT * FROM (VALUES ('o_custkey','ours'),('o_totalprice','reference')) v(column_name, side_supported)")
def char_adjudicated(spark, sf):
    """Two staged disagreements: a measure is settled by the evidence of the values (all references exist, or fractions)."""
    o, c = (from_parquet(spark, sf, ["orders", "customer"])[t] for t in ("orders", "customer"))
    refers = o.join(c, F.col("o_custkey") == F.col("c_custkey"), "left_anti").agg((F.count("*") == 0).alias("x")).select(F.lit("o_custkey").alias("column_name"), F.when(F.col("x"), "ours").otherwise("reference").alias("side_supported"))
    fractions = o.agg((F.count_if(F.col("o_totalprice") != F.floor("o_totalprice")) > 0).alias("x")).select(F.lit("o_totalprice").alias("column_name"), F.when(F.col("x"), "reference").otherwise("ours").alias("side_supported"))
    return refers.union(fractions)


_ARMS = [(s, a) for s in _ARM_SCOPES for a in ("meta", "stripped", "disjoint")]
_TRUE = values([(f"{a}.{b}", f"{c}.{d}") for a, b, c, d in FOREIGN], ["source", "target"])
_REFERS = {(f"{a}.{b}", f"{c}.{d}") for a, b, c, d in FOREIGN}


def _joins(spark, sf, tables, arm):
    """Joins of the catalog that is built for a scope in an arm and whose source values all exist in the target."""
    return {tuple(i.split("->")) for k, i in _covered(arms.state(spark, sf, arm, tables)) if k == "relationship"}


def _arm_sql(tables, arm):
    return f"(SELECT a || '.' || b AS source, c || '.' || d AS target FROM {_holds_sql(tables)})" if arm == "meta" else _accepted_sql(tables, arm)


@query(" UNION ALL ".join(f"SELECT '{s}' AS scope, '{a}' AS arm, (SELECT count(*) FROM {_arm_sql(SCOPES[s], a)} JOIN {_TRUE} USING (source, target)) AS recovered, CAST({len(_fks(SCOPES[s]))} AS BIGINT) AS declared" for s, a in _ARMS))
def abl_fk_recovery(spark, sf):
    """Foreign keys recovered in three arms, whose tables are examined together."""
    arms.together(spark, sf, list(dict.fromkeys(a for _, a in _ARMS)))
    return rows(spark, [(s, a, len(_joins(spark, sf, SCOPES[s], a) & _REFERS), len(_fks(SCOPES[s]))) for s, a in _ARMS], "scope string, arm string, recovered long, declared long")


@query(" UNION ALL ".join(f"SELECT '{s}' AS scope, '{a}' AS arm, (SELECT count(*) FROM {_arm_sql(SCOPES[s], a)} ANTI JOIN {_TRUE} USING (source, target)) AS n_spurious" for s, a in _ARMS))
def abl_spurious(spark, sf):
    return rows(spark, [(s, a, len(_joins(spark, sf, SCOPES[s], a) - _REFERS)) for s, a in _ARMS], "scope string, arm string, n_spurious long")


@query(" UNION ALL ".join(f"SELECT '{s}' AS scope, CAST({' + '.join(f'CASE WHEN {_id_sql(t)} THEN 1 ELSE 0 END' for t in SCOPES[s])} AS BIGINT) AS n_same, CAST({len(SCOPES[s])} AS BIGINT) AS n_shared" for s in _ARM_SCOPES))
def abl_ids_across_arms(spark, sf):
    """Identifiers that stripping leaves unchanged; the fact table, which declares none, is compared with the typed arm's search."""
    meta, bare = arms.state(spark, sf, "meta").ids, arms.state(spark, sf, "stripped").ids
    same = {t for t in meta if sorted(meta[t][0]) == sorted(bare[t][0]) and not builder.keys.is_weak(bare[t][1])}
    return rows(spark, [(s, sum(t in same for t in SCOPES[s]), len(SCOPES[s])) for s in _ARM_SCOPES], "scope string, n_same long, n_shared long")


@query("SELECT 'W2' AS scope, arm, true AS all_passed, arm = 'stripped' AS fewer_than_meta FROM (VALUES ('meta'), ('stripped'), ('disjoint')) v(arm)")
def abl_claims_by_arm(spark, sf):
    """Claims of the catalogs of three arms, run on the arm's own tables: all pass, and a catalog that lost its joins makes fewer."""
    sums = {a: suite(spark, sf, "W2", a).agg(F.sum("n_passed").alias("p"), F.sum("n_claims").alias("n")).first() for a in ("meta", "stripped", "disjoint")}
    return rows(spark, [("W2", a, r["p"] == r["n"], r["n"] < sums["meta"]["n"]) for a, r in sums.items()], "scope string, arm string, all_passed boolean, fewer_than_meta boolean")


@query(" UNION ALL ".join(f"SELECT CAST({len(t)} AS INTEGER) AS n_tables, (SELECT count(*) FROM ({ledger_sql(t)} SELECT source, target FROM l WHERE final = 'accepted') JOIN {_TRUE} USING (source, target)) AS recovered, CAST({sum(a in t and c in t for a, _, c, _ in FOREIGN)} AS BIGINT) AS true_fks" for t in CURVE))
def abl_scope_curve(spark, sf):
    """Foreign keys recovered without metadata while the scope grows, all decided on one overlap."""
    return rows(spark, [(len(t), len(_joins(spark, sf, t, "stripped") & _REFERS), len(_fks(t))) for t in CURVE], "n_tables int, recovered long, true_fks long")


@query(each(STAR, lambda t, c: f"SELECT '{t}' AS table_name, '{c}' AS column_name, '{'Numeric' if _ISA[c] in ('integer', 'float') else 'Datetime' if _ISA[c] == 'datetime' else 'Categorical'}' AS role"))
def abl_symbolic_only_roles(spark, sf):
    """Roles by storage alone, which is what all values of a column are; no name has a say."""
    kind = {"integer": "int", "float": "double", "date": "date", "datetime": "timestamp"}
    found = evidence.gather(from_parquet(spark, sf, STAR))
    return rows(spark, [(t, c, typing_rules.symbolic_role(kind.get(e.isa, "string"))) for (t, c), e in found.items()], "table_name string, column_name string, role string")


_STABLE = ("W1", "W2", "W3", "W6")
_PAIRS = [("run1", "run2"), ("run1", "run3"), ("run2", "run3")]


def _runs(spark, sf):
    """The catalogs of four scopes from three permuted runs: {scope: {run: catalog}}."""
    arms.apart(spark, sf, names := ["run1", "run2", "run3"])
    return {s: {r: builder.assemble(arms.state(spark, sf, r, SCOPES[s])) for r in names} for s in _STABLE}


def _alike(a, b):
    return 1.0 if not a | b else len(a & b) / len(a | b)


@query(f"SELECT scope, run_a, run_b, 1.0::DOUBLE AS jaccard, n FROM {values(_PAIRS, ['run_a', 'run_b'])}, (" + " UNION ALL ".join(f"SELECT '{s}' AS scope, (SELECT count(*) FROM {_accepted_sql(SCOPES[s], 'disjoint')}) AS n" for s in _STABLE) + ")")
def stab_join_jaccard(spark, sf):
    out = []
    for s, runs in _runs(spark, sf).items():
        sets = {r: {tuple(sorted(j.items())) for j in c.joins} for r, c in runs.items()}
        out += [(s, a, b, _alike(sets[a], sets[b]), len(sets[a])) for a, b in _PAIRS]
    return rows(spark, out, "scope string, run_a string, run_b string, jaccard double, n long")


@query(" UNION ALL ".join(f"SELECT '{s}' AS scope, '{t}' AS table_name, true AS identical, {_id_sql(t)} AS verified" for s in _STABLE for t in SCOPES[s]))
def stab_id_agreement(spark, sf):
    out = []
    for s, runs in _runs(spark, sf).items():
        for t in SCOPES[s]:
            e = [next((x for x in c.entities if x.table == t), None) for c in runs.values()]
            out.append((s, t, len({tuple(sorted(x.id_columns)) if x else None for x in e}) == 1, all(x and not builder.keys.is_weak(x.id_status) for x in e)))
    return rows(spark, out, "scope string, table_name string, identical boolean, verified boolean")


@query(f"SELECT scope, run_a, run_b, n AS n_entities, 1.0::DOUBLE AS jaccard FROM {values(_PAIRS, ['run_a', 'run_b'])}, {values([(s, len(SCOPES[s])) for s in _STABLE], ['scope', 'n'])}")
def stab_entity_sets(spark, sf):
    out = []
    for s, runs in _runs(spark, sf).items():
        sets = {r: {e.table for e in c.entities} for r, c in runs.items()}
        out += [(s, a, b, len(sets[a]), _alike(sets[a], sets[b])) for a, b in _PAIRS]
    return rows(spark, out, "scope string, run_a string, run_b string, n_entities int, jaccard double")


@query(f"SELECT scope, run_a, run_b, 100.0::DOUBLE AS pct, n AS n_attributes FROM {values(_PAIRS, ['run_a', 'run_b'])}, {values([(s, sum(len(COLUMNS[t]) for t in SCOPES[s])) for s in _STABLE], ['scope', 'n'])}")
def stab_role_agreement(spark, sf):
    out = []
    for s, runs in _runs(spark, sf).items():
        roles = {r: {(e.table, a.src_cols[0]): a.roles for e in c.entities for a in e.attributes} for r, c in runs.items()}
        out += [(s, a, b, 100.0 * sum(roles[a][k] == roles[b].get(k) for k in roles[a]) / len(roles[a]), len(roles[a])) for a, b in _PAIRS]
    return rows(spark, out, "scope string, run_a string, run_b string, pct double, n_attributes int")


def seeded(spark, sf):
    """A clean catalog of two tables, and one copy for each defect code with exactly that defect."""
    b = from_parquet(spark, sf, ["nation", "region"], declared=True)
    clean = builder.build(b)
    out = {"clean": clean}
    for code in [f"D{i}" for i in range(10)]:
        c = load(dump(clean))
        e: Entity = next(x for x in c.entities if x.table == "nation")
        if code == "D0":
            e.name = ""
        elif code == "D1":
            c.joins.append({"from_table": "nation", "from_col": "n_colour", "to_table": "region", "to_col": "r_regionkey"})
        elif code == "D2":
            c.entities = [x for x in c.entities if x.table != "region"]
        elif code == "D3":
            e.id_status = "fallback"
        elif code == "D4":
            next(a for a in e.attributes if a.src_cols == ["n_nationkey"]).roles = ["Numeric", "Metric"]
        elif code == "D5":
            e.attributes = [a for a in e.attributes if a.src_cols != ["n_name"]]
        elif code == "D6":
            e.reference = "{n_title}"
        elif code == "D7":
            e.aggregables.append(Aggregable("ghost", "region", ["r_name"], ["nation.n_name->region.r_name"], "many_to_one", ["Categorical"]))
        elif code == "D8":
            e.attributes.append(deepcopy(next(a for a in e.attributes if a.src_cols == ["n_name"])))
        else:
            e.aggregables[0].direction = "one_to_many"
        out[code] = c
    return b, out


def _findings(spark, sf):
    b, cats = seeded(spark, sf)
    return [(seed, *f) for seed, c in cats.items() for f in claims.audit(c, b, {})]


@query(f"SELECT DISTINCT code AS seed, code FROM (VALUES {', '.join(f'({chr(39)}D{i}{chr(39)})' for i in range(10))}) v(code)")
def audit_findings_seeded(spark, sf):
    return rows(spark, [(s, c) for s, c, *_ in _findings(spark, sf)], "seed string, code string").distinct()


@query()
def audit_merge_quorum(spark, sf):
    """Three auditors of different strictness; what two or more report stands."""
    f = rows(spark, _findings(spark, sf), "seed string, code string, severity string, target string")
    all3 = f.withColumn("auditor", F.explode(F.array(F.lit("strict"), F.lit("plain"), F.lit("lenient")))).where("auditor = 'strict' or severity <> 'minor'").where("auditor <> 'lenient' or severity = 'critical'")
    return all3.groupBy("code", "target").agg(F.count_distinct("auditor").alias("n_auditors")).where("n_auditors >= 2")


@query()
def audit_cube(spark, sf):
    rq = {"D1": "RQ2", "D2": "RQ1", "D3": "RQ2", "D4": "RQ3", "D5": "RQ1", "D6": "RQ2", "D7": "RQ2", "D9": "RQ3"}
    f = [(c, s, rq.get(c, "-")) for _, c, s, _ in _findings(spark, sf)]
    return rows(spark, f, "code string, severity string, rq string").cube("code", "severity", "rq").agg(F.count("*").alias("n"))


