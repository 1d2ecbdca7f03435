"""Profile, identifier and overlap queries."""

from __future__ import annotations

from pyspark.sql import functions as F

from semcat.operators import domains, evidence, joins, keys, profile
from semcat.plans import builder
from semcat.queries import arms
from semcat.queries.registry import query
from semcat.sources.bundle import FOREIGN, STAR, TABLES, SourceBundle, from_parquet, nation_month_sales, stripped, trade_lane

COLUMNS = {
    "region": "r_regionkey r_name",
    "nation": "n_nationkey n_name n_regionkey",
    "customer": "c_custkey c_name c_nationkey c_acctbal c_mktsegment",
    "supplier": "s_suppkey s_name s_nationkey s_acctbal",
    "part": "p_partkey p_name p_brand p_type p_size p_retailprice",
    "orders": "o_orderkey o_custkey o_orderstatus o_totalprice o_orderdate o_orderpriority",
    "lineitem": "l_orderkey l_partkey l_suppkey l_linenumber l_quantity l_extendedprice l_discount l_tax l_returnflag l_linestatus l_shipdate",
    "events": "event_id ts user_id event_type value props",
    "documents": "doc_id text lang source n_chars",
    "embeddings": "vec_id embedding label",
    "pages": "page_id url html",
    "benchmark": "item_id text",
    "labels": "doc_id quality toxic",
    "conversations": "conv_id turn role text",
}
COLUMNS = {t: c.split() for t, c in COLUMNS.items()}
INTS = [(t, c) for t in TABLES for c in COLUMNS[t] if c in "r_regionkey n_nationkey n_regionkey c_custkey c_nationkey s_suppkey s_nationkey p_partkey p_size o_orderkey o_custkey l_orderkey l_partkey l_suppkey l_linenumber event_id user_id doc_id n_chars vec_id label page_id item_id quality toxic conv_id turn".split()]
KEYS = {"region": "r_regionkey", "nation": "n_nationkey", "customer": "c_custkey", "supplier": "s_suppkey", "part": "p_partkey", "orders": "o_orderkey", "events": "event_id", "documents": "doc_id", "embeddings": "vec_id", "pages": "page_id", "benchmark": "item_id", "labels": "doc_id"}
#: COLUMNS, INTS, KEYS and the measures below are the annotation of the SQL twins; the Spark side finds its own.
_KEY_IDS = [f"{t}.{c}" for t, c in KEYS.items()]
_MEASURES = ["part.p_size", "documents.n_chars"]


def each(tables, make, columns=COLUMNS, sep=" UNION ALL "):
    return sep.join(make(t, c) for t in tables for c in columns[t])


@query(" UNION ALL ".join(f"SELECT '{t}' AS table_name, count(*) AS n_rows FROM {t}" for t in TABLES))
def prof_row_counts(spark, sf):
    return profile.row_counts(from_parquet(spark, sf))


@query(each([*STAR, "events"], lambda t, c: f"SELECT '{t}' AS table_name, '{c}' AS column_name, count(*) AS n_rows, count(*) - count({c}) AS n_null, count(DISTINCT {c}) AS n_distinct FROM {t}"))
def prof_column_stats(spark, sf):
    return profile.column_stats(from_parquet(spark, sf, [*STAR, "events"]))


_HOLED = "(SELECT * REPLACE (CASE WHEN o_orderkey % 7 = 0 THEN NULL ELSE o_orderpriority END AS o_orderpriority) FROM orders)"


def holed(orders):
    """Orders with a null priority in every seventh key: the tables have no nulls of their own."""
    return orders.withColumn("o_orderpriority", F.when(F.col("o_orderkey") % 7 != 0, F.col("o_orderpriority")))


@query(each(TABLES, lambda t, c: f"SELECT '{t}' AS table_name, '{c}' AS column_name, round(avg(CASE WHEN {c} IS NULL THEN 1.0 ELSE 0.0 END), 6) AS null_rate FROM {_HOLED if t == 'orders' else t}"))
def prof_null_rates(spark, sf):
    b = from_parquet(spark, sf)
    b.tables["orders"] = holed(b["orders"])
    return profile.null_rates(b)


@query(each(["lineitem"], lambda t, c: f"SELECT '{c}' AS column_name, count(DISTINCT {c}) AS n_distinct FROM {t}"))
def prof_exact_cardinality(spark, sf):
    return profile.column_stats(from_parquet(spark, sf, ["lineitem"])).select("column_name", "n_distinct")


_LKEYS = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber"]


@query(" UNION ALL ".join(f"SELECT '{c}' AS column_name, count(DISTINCT {c}) AS n_distinct FROM lineitem" for c in _LKEYS))
def prof_bitmap_cardinality(spark, sf):
    return profile.bitmap_cardinality(from_parquet(spark, sf, ["lineitem"])["lineitem"], _LKEYS)


_TEXTUAL = {t: [c for c in COLUMNS[t] if c not in "c_acctbal s_acctbal p_retailprice o_totalprice o_orderdate l_quantity l_extendedprice l_discount l_tax l_shipdate".split()] for t in STAR}


@query(each(STAR, lambda t, c: f"SELECT '{t}' AS table_name, '{c}' AS column_name, min(CAST({c} AS VARCHAR)) AS min_text, max(CAST({c} AS VARCHAR)) AS max_text FROM {t}", _TEXTUAL))
def prof_value_ranges(spark, sf):
    b = from_parquet(spark, sf, STAR)
    return profile.ranges(SourceBundle({t: b[t].select(*_TEXTUAL[t]) for t in STAR}))


_PAT = {"n_int": "^[+-]?[0-9]+$", "n_leading_zero": "^0[0-9]+$", "n_url": "^https?://"}


@query(each([*STAR, "pages"], lambda t, c: f"SELECT '{t}' AS table_name, '{c}' AS column_name, " + ", ".join(f"count(*) FILTER (WHERE regexp_matches(CAST({c} AS VARCHAR), '{p}')) AS {k}" for k, p in _PAT.items()) + f" FROM {t}", _TEXTUAL | {"pages": COLUMNS["pages"]}))
def prof_pattern_counts(spark, sf):
    cols = _TEXTUAL | {"pages": COLUMNS["pages"]}
    b = stripped(from_parquet(spark, sf, [*STAR, "pages"]))
    return profile.pattern_stats(SourceBundle({t: b[t].select(*cols[t]) for t in b.tables}), list(_PAT))


@query(each(STAR, lambda t, c: f"SELECT '{t}' AS table_name, '{c}' AS column_name, (SELECT string_agg(v, '|' ORDER BY v) FROM (SELECT DISTINCT CAST({c} AS VARCHAR) AS v FROM {t} ORDER BY v LIMIT 8)) AS samples", _TEXTUAL))
def prof_samples_first_k(spark, sf):
    b = from_parquet(spark, sf, STAR)
    return profile.samples(SourceBundle({t: b[t].select(*_TEXTUAL[t]) for t in STAR}), 8, by_hash=False)


@query()
def prof_samples_hash_k(spark, sf):
    return profile.samples(from_parquet(spark, sf, STAR))


_LONG = ["documents", "pages", "conversations"]


@query(each(_LONG, lambda t, c: f"SELECT '{t}' AS table_name, '{c}' AS column_name, min(length(CAST({c} AS VARCHAR))) AS min_len, max(length(CAST({c} AS VARCHAR))) AS max_len, round(avg(length(CAST({c} AS VARCHAR))), 6) AS avg_len FROM {t}"))
def prof_string_lengths(spark, sf):
    return profile.lengths(from_parquet(spark, sf, _LONG))


@query()
def prof_sketch_error(spark, sf):
    b = from_parquet(spark, sf, ["lineitem"])
    exact = profile.column_stats(b).select("column_name", "n_distinct")
    return profile.sketched_cardinality(b["lineitem"], _LKEYS).join(exact, "column_name").select("column_name", (F.abs(F.col("approx_distinct") - F.col("n_distinct")) <= 0.1 * F.col("n_distinct")).alias("within_bound"))


@query()
def prof_fingerprint(spark, sf):
    return profile.fingerprint(from_parquet(spark, sf))


def _evidence(table, cols, source=None):
    key = cols[0] if len(cols) == 1 else "(" + ", ".join(cols) + ")"
    whole = " AND ".join(f"{c} IS NOT NULL" for c in cols)
    return f"SELECT count(*) AS n, count(*) FILTER (WHERE {whole}) AS n_nonnull, count(DISTINCT {key}) FILTER (WHERE {whole}) AS n_distinct FROM {source or table}"


def _is_unique(sql):
    return f"SELECT *, (n = n_nonnull AND n = n_distinct AND n > 0) AS is_unique FROM ({sql})"


@query(each(STAR, lambda t, c: f"SELECT '{t}' AS table_name, '{c}' AS column_name, * FROM ({_is_unique(_evidence(t, [c]))})"))
def key_single_column_evidence(spark, sf):
    b = from_parquet(spark, sf, STAR)
    out = [keys.verify_many(b[t], [[c] for c in b[t].columns]).select(F.lit(t).alias("table_name"), F.col("cols").alias("column_name"), "n", "n_nonnull", "n_distinct", "is_unique") for t in STAR]
    return profile.union_all(out)


_POOL = [["l_orderkey", "l_linenumber"], ["l_orderkey", "l_partkey"], ["l_orderkey", "l_suppkey"], ["l_partkey", "l_suppkey"], ["l_orderkey", "l_shipdate"], ["l_orderkey", "l_partkey", "l_suppkey"], ["l_orderkey", "l_partkey", "l_shipdate"], ["l_orderkey", "l_suppkey", "l_shipdate"], ["l_orderkey", "l_partkey", "l_suppkey", "l_shipdate"]]


@query(" UNION ALL ".join(f"SELECT '{'|'.join(c)}' AS cols, n_distinct, is_unique FROM ({_is_unique(_evidence('lineitem', c))})" for c in _POOL))
def key_lineitem_composites(spark, sf):
    return keys.verify_many(from_parquet(spark, sf, ["lineitem"])["lineitem"], _POOL).select("cols", "n_distinct", "is_unique")


_DIMS, _DATES = ["l_orderkey", "l_partkey", "l_suppkey"], ["l_shipdate"]
_ALL = [c for w in (2, 3, 4) for c in keys.composite_candidates(_DIMS, _DATES, w)]
_UNIQUE = " UNION ALL ".join(f"SELECT '{'|'.join(c)}' AS cols, {len(c)} AS w, is_unique FROM ({_is_unique(_evidence('lineitem', c))})" for c in _ALL)


@query(f"WITH u AS ({_UNIQUE}) SELECT cols FROM u WHERE is_unique AND NOT EXISTS (SELECT 1 FROM u s WHERE s.is_unique AND s.w < u.w AND list_has_all(string_split(u.cols, '|'), string_split(s.cols, '|')))")
def key_minimal_composites(spark, sf):
    found = keys.minimal_composites(from_parquet(spark, sf, ["lineitem"])["lineitem"], _DIMS, _DATES)
    return spark.createDataFrame([("|".join(c),) for c in found], "cols string")


@query(_is_unique(_evidence("conversations", ["conv_id", "turn"])))
def key_conversation_turns(spark, sf):
    return keys.verify_many(from_parquet(spark, sf, ["conversations"])["conversations"], [["conv_id", "turn"]]).drop("cols")


@query("SELECT l_orderkey, l_linenumber, count(*) AS n FROM lineitem GROUP BY ALL HAVING count(*) > 1")
def key_duplicate_groups_lineitem(spark, sf):
    return keys.duplicate_groups(from_parquet(spark, sf, ["lineitem"])["lineitem"], ["l_orderkey", "l_linenumber"])


@query(" UNION ALL ".join(f"SELECT '{c}' AS column_name, n, n_distinct, is_unique FROM ({_is_unique(_evidence('part', [c]))})" for c in ("p_name", "p_partkey")))
def key_name_trap_part(spark, sf):
    return keys.verify_many(from_parquet(spark, sf, ["part"])["part"], [["p_name"], ["p_partkey"]]).select(F.col("cols").alias("column_name"), "n", "n_distinct", "is_unique")


_NMS = "(SELECT c_nationkey AS n_nationkey, date_trunc('month', o_orderdate) AS month FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY ALL)"


@query(_is_unique(_evidence("", ["n_nationkey", "month"], _NMS)))
def key_nation_month_composite(spark, sf):
    return keys.verify_many(nation_month_sales(from_parquet(spark, sf, ["orders", "customer"])), [["n_nationkey", "month"]]).drop("cols")


@query(f"SELECT n, n_nonnull, (n = n_nonnull) AS ok FROM ({_evidence('', ['o_orderpriority'], _HOLED)})")
def key_null_refutes(spark, sf):
    return keys.verify_many(holed(from_parquet(spark, sf, ["orders"])["orders"]), [["o_orderpriority"]]).select("n", "n_nonnull", (F.col("n") == F.col("n_nonnull")).alias("ok"))


_MEASURED = {"c_acctbal": "customer", "s_acctbal": "supplier", "p_retailprice": "part", "o_totalprice": "orders", "l_extendedprice": "lineitem"}


@query(" UNION ALL ".join(f"SELECT '{t}' AS table_name, '{c}' AS column_name, is_unique, false AS eligible FROM ({_is_unique(_evidence(t, [c]))})" for c, t in _MEASURED.items()))
def key_unique_measures_excluded(spark, sf):
    b = from_parquet(spark, sf, list(_MEASURED.values()))
    roles = evidence.roles(evidence.gather(b))
    out = []
    for c, t in _MEASURED.items():
        ok = c in keys.order_candidates(b[t].columns, roles[t], t)
        out.append(keys.verify_many(b[t], [[c]]).select(F.lit(t).alias("table_name"), F.lit(c).alias("column_name"), "is_unique", F.lit(ok).alias("eligible")))
    return profile.union_all(out)


_CHOSEN = " UNION ALL ".join([f"SELECT '{t}' AS table_name, '{c}' AS id_cols, CASE WHEN is_unique THEN 'verified' ELSE 'fallback' END AS status FROM ({_is_unique(_evidence(t, [c]))})" for t, c in KEYS.items()])


@query(f"{_CHOSEN} UNION ALL SELECT 'conversations', 'conv_id|turn', CASE WHEN is_unique THEN 'verified' ELSE 'fallback' END FROM ({_is_unique(_evidence('conversations', ['conv_id', 'turn']))}) UNION ALL (WITH u AS ({_UNIQUE}), r AS (SELECT *, row_number() OVER () AS o FROM u) SELECT 'lineitem', cols, 'verified' FROM r WHERE is_unique ORDER BY w, o LIMIT 1)")
def key_chosen_per_table(spark, sf):
    got = arms.state(spark, sf, "stripped").ids
    return spark.createDataFrame([(t, "|".join(c), s) for t, (c, s) in sorted(got.items())], "table_name string, id_cols string, status string")


def overlap_sql(tables=TABLES, text=lambda t, c: f"CAST({c} AS VARCHAR)"):
    """Independent SQL of all overlaps: one semi join a pair."""
    srcs = [(t, c) for t, c in INTS if t in tables]
    pairs = [(t, c, k) for t, c in srcs for k in KEYS if k != t and k in tables]
    is_key = {k: f"(SELECT count(*) > 0 AND count(*) = count(DISTINCT {KEYS[k]}) FROM {k})" for k in KEYS}
    return " UNION ALL ".join(f"SELECT '{t}.{c}' AS source, '{k}.{KEYS[k]}' AS target, (SELECT count(*) FROM (SELECT DISTINCT {text(t, c)} AS v FROM {t} WHERE {c} IS NOT NULL) WHERE v IN (SELECT {text(k, KEYS[k])} FROM {k})) AS n_common, (SELECT count(DISTINCT {c}) FROM {t}) AS n_source WHERE {is_key[k]}" for t, c, k in pairs)


_OVL = f"SELECT * FROM ({overlap_sql()}) WHERE n_common > 0"


@query(f"SELECT source, target, n_common, round(n_common / n_source, 6) AS containment FROM ({_OVL})")
def ovl_all_pairs(spark, sf):
    b = from_parquet(spark, sf)
    st = arms.state(spark, sf, "typed")
    return joins.overlaps(b, st.keys, domains.joinable(st.evidence)).select("source", "target", "n_common", F.round(F.col("n_common") / F.col("n_source"), 6).alias("containment"))


def _found(spark, sf, tables=TABLES, arm="stripped"):
    """The overlaps that the builder found in an arm: (source, target, n_common, n_source)."""
    st = arms.state(spark, sf, arm, tables)
    return spark.createDataFrame([(o.source, o.target, o.n_common, o.n_source) for o in st.overlap], "source string, target string, n_common long, n_source long")


@query(f"SELECT source, target, n_common FROM ({overlap_sql(STAR)}) WHERE n_common > 0")
def ovl_naive_pairs(spark, sf):
    b = from_parquet(spark, sf, STAR)
    pairs = [(f"{t}.{c}", f"{k}.{KEYS[k]}") for t, c in INTS for k in KEYS if t in STAR and k in STAR and k != t]
    return domains.pair_overlap_naive(domains.build(b, [x for x in INTS if x[0] in STAR]), pairs)


_NAMES = [("region", "r_name"), ("nation", "n_name"), ("customer", "c_name"), ("supplier", "s_name"), ("part", "p_name")]


@query(" UNION ALL ".join(f"SELECT '{t}.{c}' AS source, '{k}.{d}' AS target WHERE NOT EXISTS (SELECT 1 FROM {t} WHERE {c} IN (SELECT {d} FROM {k}))" for t, c in _NAMES for k, d in _NAMES if k != t))
def ovl_zero_pairs(spark, sf):
    b = from_parquet(spark, sf, STAR)
    ids = [f"{t}.{c}" for t, c in _NAMES]
    hit = domains.pair_overlap(domains.build(b, _NAMES), ids).select("source", "target")
    every = spark.createDataFrame([(s, t) for s in ids for t in ids if s != t], "source string, target string")
    return every.join(hit, ["source", "target"], "left_anti")


@query(f"SELECT source, count(DISTINCT target) AS n_targets FROM ({_OVL}) GROUP BY source")
def ovl_target_counts(spark, sf):
    return joins.target_counts(_found(spark, sf))


@query(f"SELECT source, count(DISTINCT target) AS n_targets_full FROM ({_OVL}) WHERE n_common = n_source GROUP BY source")
def ovl_contained_counts(spark, sf):
    return joins.target_counts(_found(spark, sf), 1.0).withColumnRenamed("n_targets", "n_targets_full")


@query(" UNION ALL ".join(f"SELECT 'integer' AS family, '{t}.{c}' AS column_name, count(DISTINCT {c}) AS n_values FROM {t}" for t, c in INTS))
def ovl_domain_sizes(spark, sf):
    d = domains.build(from_parquet(spark, sf), INTS)
    return d.groupBy(F.col("col").alias("column_name")).agg(F.count("*").alias("n_values")).select(F.lit("integer").alias("family"), "column_name", "n_values")


_STAR_INTS = [(t, c) for t, c in INTS if t in STAR]


@query("WITH r AS (" + " UNION ALL ".join(f"SELECT '{t}.{c}' AS col, '{t}' AS t, min({c}) AS lo, max({c}) AS hi FROM {t}" for t, c in _STAR_INTS) + ") SELECT a.col AS source, b.col AS target FROM r a JOIN r b ON a.t <> b.t AND (a.hi < b.lo OR b.hi < a.lo)")
def ovl_range_disjoint_pairs(spark, sf):
    b = from_parquet(spark, sf, STAR)
    r = profile.union_all([b[t].agg(F.min(c).cast("long").alias("lo"), F.max(c).cast("long").alias("hi")).select(F.lit(f"{t}.{c}").alias("col"), F.lit(t).alias("t"), "lo", "hi") for t, c in _STAR_INTS])
    x, y = r.alias("x"), r.alias("y")  # one row a column
    return x.join(y, (F.col("x.t") != F.col("y.t")) & ((F.col("x.hi") < F.col("y.lo")) | (F.col("y.hi") < F.col("x.lo")))).select(F.col("x.col").alias("source"), F.col("y.col").alias("target"))


def values(rows, names):
    lit = lambda v: "NULL" if v is None else ("true" if v is True else "false" if v is False else f"'{v}'" if isinstance(v, str) else str(v))
    return f"(SELECT * FROM (VALUES {', '.join('(' + ', '.join(map(lit, r)) + ')' for r in rows)}) AS v({', '.join(names)}))"


#: The judge's score by names, in SQL: the same stem before key or id is 1, anything else 0.
_STEM = "regexp_extract(split_part({}, '.', 2), '^(?:[a-z]_)?(.*?)_?(?:key|id)$', 1)"
_SCORE = f"CASE WHEN {_STEM.format('source')} <> '' AND {_STEM.format('source')} = {_STEM.format('target')} THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END"


def ledger_sql(tables=TABLES, exempt=False, ovl=None):
    measures = ", ".join(f"'{m}'" for m in _MEASURES)
    ids = ", ".join(f"'{k}'" for k in _KEY_IDS)
    named = "(score >= 0.9 AND n_common = n_source)" if exempt else "false"
    return f"""WITH o AS (SELECT *, {_SCORE} AS score FROM ({ovl or overlap_sql(tables)}) WHERE n_common > 0), c AS (SELECT source, count(DISTINCT target) AS n_targets FROM o GROUP BY source),
 s AS (SELECT o.*, CASE WHEN source IN ({ids}) THEN 'source_is_key' WHEN source IN ({measures}) THEN 'measure' WHEN n_targets >= 3 AND NOT {named} THEN 'ambiguous' WHEN score < 0.7 THEN 'judge' ELSE 'accepted' END AS stage FROM o JOIN c USING (source)),
 l AS (SELECT *, CASE WHEN stage = 'accepted' AND row_number() OVER (PARTITION BY source, stage ORDER BY score DESC, n_common DESC, target) > 1 THEN 'second_referent' ELSE stage END AS final FROM s)"""


def _ledger(spark, sf, tables=TABLES, policy=joins.JoinPolicy(), arm="stripped"):
    st = arms.state(spark, sf, arm, tables)
    return joins.as_table(spark, joins.decide(st.overlap, st.keys, st.measures, policy))


@query(ledger_sql() + " SELECT source, target, final AS stage FROM l")
def join_ledger_all(spark, sf):
    return _ledger(spark, sf).select("source", "target", "stage")


@query(ledger_sql(STAR) + " SELECT source, target, final AS stage FROM l")
def join_ledger_star(spark, sf):
    return _ledger(spark, sf, STAR).select("source", "target", "stage")


@query(f"SELECT source, bool_or(source IN ({', '.join(repr(k) for k in _KEY_IDS)})) AS dropped FROM ({_OVL}) GROUP BY source")
def join_guard_source_key(spark, sf):
    return _ledger(spark, sf).groupBy("source").agg(F.bool_or(F.col("stage") == "source_is_key").alias("dropped"))


@query(ledger_sql(STAR) + " SELECT source, bool_or(final = 'measure') AS dropped FROM l GROUP BY source")
def join_guard_measures(spark, sf):
    return _ledger(spark, sf, STAR).groupBy("source").agg(F.bool_or(F.col("stage") == "measure").alias("dropped"))


@query(ledger_sql(STAR, True) + " SELECT source, target AS kept_target, CAST(1 AS INTEGER) AS rank FROM l WHERE final = 'accepted'")
def join_guard_single_referent(spark, sf):
    return _ledger(spark, sf, STAR, joins.JoinPolicy(ambiguous="exempt_named")).where("stage = 'accepted'").select("source", F.col("target").alias("kept_target"), F.lit(1).alias("rank"))


_SCOPES = {"W1": ["part", "supplier", "orders", "lineitem"], "W2": ["region", "nation", "customer", "orders", "lineitem"], "W6": ["documents", "labels", "pages", "conversations"], "all": TABLES}


@query(" UNION ALL ".join(f"SELECT '{s}' AS scope, source, count(DISTINCT target) AS n_targets, count(DISTINCT target) >= 3 AS dropped FROM ({overlap_sql(t)}) WHERE n_common > 0 GROUP BY source" for s, t in _SCOPES.items()))
def join_guard_ambiguous(spark, sf):
    out = []
    for s, tables in _SCOPES.items():
        out.append(joins.target_counts(_found(spark, sf, tables)).select(F.lit(s).alias("scope"), "source", "n_targets", (F.col("n_targets") >= 3).alias("dropped")))
    return profile.union_all(out)


def _named(tables):
    pairs = values([(f"{t}.{c}", f"{k}.{KEYS[k]}") for t in tables for c in COLUMNS[t] for k in KEYS if k in tables and k != t], ["source", "target"])
    return f"(SELECT source, target, {_SCORE} AS score FROM {pairs})"


@query(f"SELECT source, target, score FROM {_named(TABLES)} WHERE score >= 0.7")
def join_candidates_by_name(spark, sf):
    st = arms.state(spark, sf, "stripped")
    return spark.createDataFrame(joins.by_name(list(st.evidence), st.keys), "source string, target string, score double")


@query(f"SELECT source, target, string_agg(origin, '|' ORDER BY origin) AS origins FROM (SELECT source, target, 'values' AS origin FROM ({overlap_sql(STAR)}) WHERE n_common > 0 UNION ALL SELECT source, target, 'name' FROM {_named(STAR)} WHERE score >= 0.7) GROUP BY ALL")
def join_candidates_union(spark, sf):
    st = arms.state(spark, sf, "stripped", STAR)
    by_name = [(s, t, "name") for s, t, _ in joins.by_name(list(st.evidence), st.keys)]
    both = spark.createDataFrame(by_name + [(o.source, o.target, "values") for o in st.overlap], "source string, target string, origin string")
    return both.groupBy("source", "target").agg(F.array_join(F.array_sort(F.collect_set("origin")), "|").alias("origins"))


def _mult(rows):
    return " UNION ALL ".join(f"SELECT '{a}.{b}->{c}.{d}' AS join_id, (SELECT max(n) FROM (SELECT count(*) AS n FROM {a} GROUP BY {b})) AS max_per_key, CASE WHEN (SELECT max(n) FROM (SELECT count(*) AS n FROM {c} GROUP BY {d})) > 1 THEN 'm:m' WHEN (SELECT max(n) FROM (SELECT count(*) AS n FROM {a} GROUP BY {b})) > 1 THEN 'm:1' ELSE '1:1' END AS kind" for a, b, c, d in rows)


@query(_mult(FOREIGN))
def join_multiplicity(spark, sf):
    return joins.multiplicity(from_parquet(spark, sf), FOREIGN)


@query(f"SELECT split_part(join_id, '->', 1) AS from_col, split_part(join_id, '->', 2) AS to_col, kind AS multiplicity FROM ({_mult(FOREIGN)})")
def join_final_meta(spark, sf):
    m = joins.multiplicity(from_parquet(spark, sf, declared=True), FOREIGN)
    return m.select(F.split("join_id", "->")[0].alias("from_col"), F.split("join_id", "->")[1].alias("to_col"), F.col("kind").alias("multiplicity"))


@query(ledger_sql() + " SELECT source AS from_col, target AS to_col FROM l WHERE final = 'accepted'")
def join_final_stripped(spark, sf):
    return _ledger(spark, sf).where("stage = 'accepted'").select(F.col("source").alias("from_col"), F.col("target").alias("to_col"))


@query(ledger_sql(exempt=True) + " SELECT source AS from_col, target AS to_col FROM l WHERE final = 'accepted'")
def join_final_exempt_named(spark, sf):
    return _ledger(spark, sf, policy=joins.JoinPolicy(ambiguous="exempt_named")).where("stage = 'accepted'").select(F.col("source").alias("from_col"), F.col("target").alias("to_col"))


def _prefixed(t, c):
    from semcat.sources.bundle import PREFIX

    return f"'{PREFIX[c]}' || CAST({c} AS VARCHAR)" if c in PREFIX else f"CAST({c} AS VARCHAR)"


@query(ledger_sql(STAR, ovl=overlap_sql(STAR, _prefixed)) + " SELECT source AS from_col, target AS to_col FROM l WHERE final = 'accepted'")
def join_final_disjoint(spark, sf):
    return _ledger(spark, sf, STAR, arm="disjoint").where("stage = 'accepted'").select(F.col("source").alias("from_col"), F.col("target").alias("to_col"))


@query(" UNION ALL ".join(f"SELECT '{a}.{b}->{c}.{d}' AS join_id, (SELECT count(*) FROM {a} WHERE {b} NOT IN (SELECT {d} FROM {c})) AS n_orphans, (SELECT count(*) FROM {c} WHERE {d} NOT IN (SELECT {b} FROM {a})) AS n_childless" for a, b, c, d in FOREIGN))
def join_orphans(spark, sf):
    return joins.orphans(from_parquet(spark, sf), FOREIGN)


@query(ledger_sql() + " SELECT 'overlap' AS stage, count(*) AS n_candidates FROM l UNION ALL SELECT 'not_key', count(*) FROM l WHERE final <> 'source_is_key' UNION ALL SELECT 'not_measure', count(*) FROM l WHERE final NOT IN ('source_is_key', 'measure') UNION ALL SELECT 'unambiguous', count(*) FROM l WHERE final NOT IN ('source_is_key', 'measure', 'ambiguous') UNION ALL SELECT 'accepted', count(*) FROM l WHERE final = 'accepted'")
def join_funnel(spark, sf):
    l = _ledger(spark, sf)
    steps = [("overlap", []), ("not_key", ["source_is_key"]), ("not_measure", ["source_is_key", "measure"]), ("unambiguous", ["source_is_key", "measure", "ambiguous"])]
    one = l.agg(*[F.count_if(~F.col("stage").isin(x) if x else F.lit(True)).alias(n) for n, x in steps], F.count_if(F.col("stage") == "accepted").alias("accepted"))
    return one.unpivot([], one.columns, "stage", "n_candidates")


_LANE = "(SELECT c_nationkey AS buyer_nationkey, s_nationkey AS seller_nationkey, count(*) AS n_lines, CAST(sum(CAST(l_extendedprice AS DECIMAL(18,2))) AS DOUBLE) AS revenue FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey GROUP BY ALL)"


@query(f"SELECT 'trade_lane.' || c AS from_col, 'nation.n_nationkey' AS to_col, n_common FROM (SELECT 'buyer_nationkey' AS c, count(DISTINCT buyer_nationkey) AS n_common FROM {_LANE} WHERE buyer_nationkey IN (SELECT n_nationkey FROM nation) UNION ALL SELECT 'seller_nationkey', count(DISTINCT seller_nationkey) FROM {_LANE} WHERE seller_nationkey IN (SELECT n_nationkey FROM nation))")
def join_parallel_trade_lane(spark, sf):
    b = from_parquet(spark, sf, STAR)
    two = SourceBundle({"nation": b["nation"], "trade_lane": trade_lane(b)})
    cols = [("nation", "n_nationkey"), ("trade_lane", "buyer_nationkey"), ("trade_lane", "seller_nationkey")]
    return domains.pair_overlap(domains.build(two, cols), ["nation.n_nationkey"]).select(F.col("source").alias("from_col"), F.col("target").alias("to_col"), "n_common")


_STAFF = [("S1", None, "Ann"), ("S2", "S1", "Bo"), ("S3", "S1", "Cy"), ("S4", "S2", "Di"), ("S5", "S3", "Ed")]


@query(f"WITH s AS {values(_STAFF, ['staff_id', 'parent_id', 'staff_name'])} SELECT 'staff.parent_id' AS from_col, 'staff.staff_id' AS to_col, (SELECT count(DISTINCT parent_id) FROM s WHERE parent_id IN (SELECT staff_id FROM s)) AS n_common")
def join_self_reference(spark, sf):
    """A table that refers to itself: its columns meet its own key through a second name of the table."""
    staff = spark.createDataFrame(_STAFF, "staff_id string, parent_id string, staff_name string")
    two = SourceBundle({"staff": staff.select("staff_id", "staff_name"), "boss": staff.select("parent_id")})
    st = builder.examine(two)
    hit = [(o.source.replace("boss", "staff"), o.target, o.n_common) for o in st.overlap if o.source == "boss.parent_id"]
    return spark.createDataFrame(hit, "from_col string, to_col string, n_common long")


@query(f"SELECT source, target, n_common FROM ({_OVL})")
def abl_model_only_joins(spark, sf):
    """Arm without data checks: whatever a judge that approves all is shown is accepted."""
    return _ledger(spark, sf, policy=joins.JoinPolicy(guards=False, judge="approve_all")).where("stage = 'accepted'").select("source", "target", "n_common")


@query()
def abl_sampled_overlap_misses(spark, sf):
    d = domains.build(from_parquet(spark, sf, STAR), _STAR_INTS)
    ids = arms.state(spark, sf, "typed", STAR).keys
    full, part = domains.pair_overlap(d, ids), domains.sampled_overlap(d, ids)
    return full.select("source", "target", F.col("n_common").alias("full_common")).join(part.select("source", "target", F.col("n_common").alias("sampled_common")), ["source", "target"], "left").na.fill(0, ["sampled_common"])



@query(_named(STAR)[1:-1])
def fn_pandas_judge(spark, sf):
    """The lexical judge as a vectorised function over all pairs of a column and another table's key."""
    from semcat.functions.shipping import ship
    from semcat.functions.user import judge_column

    ship(spark)
    st = arms.state(spark, sf, "stripped", STAR)
    pairs = [(f"{t}.{c}", k) for t, c in st.evidence for k in st.keys if k.split(".")[0] != t]
    return spark.createDataFrame(pairs, "source string, target string").withColumn("score", judge_column()("source", "target"))


@query("SELECT c_mktsegment, max(c_acctbal) - min(c_acctbal) AS spread FROM customer GROUP BY 1")
def fn_spread_aggregate(spark, sf):
    from semcat.functions.shipping import ship
    from semcat.functions.user import spread_aggregate

    ship(spark)
    return from_parquet(spark, sf, ["customer"])["customer"].groupBy("c_mktsegment").agg(spread_aggregate()("c_acctbal").alias("spread"))


@query("SELECT * FROM (VALUES ('l_extendedprice', 0, 'extended'), ('l_extendedprice', 1, 'price'), ('n_chars', 0, 'n'), ('n_chars', 1, 'chars'), ('ts', 0, 'ts')) v(column_name, place, word)")
def fn_name_words(spark, sf):
    from semcat.functions.shipping import ship
    from semcat.functions.user import words_function

    ship(spark)
    spark.udtf.register("name_words", words_function())
    return spark.sql("SELECT c AS column_name, place, word FROM VALUES ('l_extendedprice'), ('n_chars'), ('ts') AS v(c), LATERAL name_words(c)")
