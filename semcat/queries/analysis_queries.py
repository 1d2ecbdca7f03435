"""Consumer questions and the surrounding relational operators."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from semcat.operators import evidence
from semcat.plans import ask
from semcat.plans.ask import NotLicensed, Question
from semcat.plans.graph import JoinGraph
from semcat.queries.catalog_queries import _ROLE_ROWS, _ROLES, GRAPH, rows
from semcat.queries.profile_queries import COLUMNS, _LANE, values
from semcat.queries.registry import query
from semcat.sources.bundle import STAR, from_parquet, trade_lane


def _ask(spark, sf, q, value, tables=STAR):
    return ask.plan(q, from_parquet(spark, sf, tables).tables, _ROLES, GRAPH, value)


def _found_roles(bundle):
    """Roles by column name, from the evidence of all values."""
    return {c: r for by in evidence.roles(evidence.gather(bundle)).values() for c, r in by.items()}


_O = "orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"


@query(f"SELECT n_name, count(*) AS n_orders FROM {_O} WHERE r_name = 'ASIA' GROUP BY n_name ORDER BY 2 DESC, 1 LIMIT 5")
def ask_top5_nations_in_region(spark, sf):
    return _ask(spark, sf, Question("orders", by=("n_name",), where=("r_name = 'ASIA'",), needs=("r_name",), limit=5), "n_orders")


@query(f"SELECT count(*) AS n_orders FROM {_O} WHERE r_name = 'ASIA' AND year(o_orderdate) = 1997")
def ask_orders_in_region_year(spark, sf):
    return _ask(spark, sf, Question("orders", where=("r_name = 'ASIA'", "o_orderdate >= timestamp_ntz'1997-01-01' and o_orderdate < timestamp_ntz'1998-01-01'"), needs=("r_name",)), "n_orders")


@query(f"SELECT n_name, round(CAST(sum(CAST(o_totalprice AS DECIMAL(18,2))) AS DOUBLE) / count(*), 4) AS avg_price FROM {_O} GROUP BY 1")
def ask_avg_price_per_nation(spark, sf):
    s = _ask(spark, sf, Question("orders", "sum", "o_totalprice", ("n_name",)), "s").join(_ask(spark, sf, Question("orders", by=("n_name",)), "n"), "n_name")
    return s.select("n_name", F.round(F.col("s") / F.col("n"), 4).alias("avg_price"))


@query("SELECT s_name, count(*) AS n_lines FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1 ORDER BY 2 DESC, 1 LIMIT 1")
def ask_most_lineitems_supplier(spark, sf):
    return _ask(spark, sf, Question("lineitem", by=("s_name",), limit=1), "n_lines")


@query("SELECT c_name, count(*) AS n_orders FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1 ORDER BY 2 DESC, 1 LIMIT 1")
def ask_customer_most_orders(spark, sf):
    return _ask(spark, sf, Question("orders", by=("c_name",), limit=1), "n_orders")


@query("SELECT CAST(year(o_orderdate) AS INTEGER) AS y, CAST(quarter(o_orderdate) AS INTEGER) AS q, CAST(month(o_orderdate) AS INTEGER) AS m, count(*) AS n_orders FROM orders GROUP BY ROLLUP (1, 2, 3)")
def ask_orders_calendar_rollup(spark, sf):
    o = from_parquet(spark, sf, ["orders"])["orders"]
    return o.select(F.year("o_orderdate").alias("y"), F.quarter("o_orderdate").alias("q"), F.month("o_orderdate").alias("m")).rollup("y", "q", "m").agg(F.count("*").alias("n_orders"))


@query("SELECT CASE WHEN month(o_orderdate) IN (12,1,2) THEN 'winter' WHEN month(o_orderdate) <= 5 THEN 'spring' WHEN month(o_orderdate) <= 8 THEN 'summer' ELSE 'autumn' END AS season, count(*) AS n_orders FROM orders GROUP BY 1")
def ask_orders_by_season(spark, sf):
    m = F.month("o_orderdate")
    s = F.when(m.isin(12, 1, 2), "winter").when(m <= 5, "spring").when(m <= 8, "summer").otherwise("autumn")
    return from_parquet(spark, sf, ["orders"])["orders"].groupBy(s.alias("season")).agg(F.count("*").alias("n_orders"))


@query("SELECT strftime(l_shipdate, '%Y-%m') AS month, count(*) AS n FROM lineitem WHERE l_returnflag = 'R' GROUP BY 1")
def ask_returned_lines_per_month(spark, sf):
    return from_parquet(spark, sf, ["lineitem"])["lineitem"].where("l_returnflag = 'R'").groupBy(F.date_format("l_shipdate", "yyyy-MM").alias("month")).agg(F.count("*").alias("n"))


@query("SELECT l_suppkey AS s_suppkey, count(DISTINCT l_partkey) AS n_parts FROM lineitem GROUP BY 1")
def ask_distinct_parts_per_supplier(spark, sf):
    return _ask(spark, sf, Question("lineitem", "count_distinct", "l_partkey", ("l_suppkey",)), "n_parts").withColumnRenamed("l_suppkey", "s_suppkey")


@query("SELECT strftime(ts, '%Y-%m-%d') AS day, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY ALL")
def ask_events_by_type_day(spark, sf):
    return from_parquet(spark, sf, ["events"])["events"].groupBy(F.date_format("ts", "yyyy-MM-dd").alias("day"), "event_type").agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total"))


_DL = "documents d JOIN labels l USING (doc_id)"


@query(f"SELECT lang, count(*) AS n, count(*) FILTER (WHERE quality = 1) AS n_good, round(avg(quality), 6) AS share FROM {_DL} GROUP BY lang")
def ask_quality_by_lang(spark, sf):
    b = from_parquet(spark, sf, ["documents", "labels"])
    return b["documents"].select("doc_id", "lang").join(b["labels"], "doc_id").groupBy("lang").agg(F.count("*").alias("n"), F.count_if(F.col("quality") == 1).alias("n_good"), F.round(F.avg("quality"), 6).alias("share"))


@query(f"SELECT source, round(avg(toxic), 6) AS toxic_share FROM {_DL} GROUP BY source")
def ask_flag_share_by_source(spark, sf):
    b = from_parquet(spark, sf, ["documents", "labels"])
    return b["documents"].select("doc_id", "source").join(b["labels"], "doc_id").groupBy("source").agg(F.round(F.avg("toxic"), 6).alias("toxic_share"))


@query(f"SELECT b.n_name AS buyer, s.n_name AS seller, revenue FROM {_LANE} JOIN nation b ON b.n_nationkey = buyer_nationkey JOIN nation s ON s.n_nationkey = seller_nationkey")
def ask_lane_buyer_seller(spark, sf):
    b = from_parquet(spark, sf, STAR)
    n = b["nation"]
    return trade_lane(b).join(n.select(F.col("n_nationkey").alias("buyer_nationkey"), F.col("n_name").alias("buyer")), "buyer_nationkey").join(n.select(F.col("n_nationkey").alias("seller_nationkey"), F.col("n_name").alias("seller")), "seller_nationkey").select("buyer", "seller", "revenue")


@query(f"SELECT entity, sum(CASE role WHEN 'Numeric' THEN 4 ELSE 1 END)::BIGINT AS n_questions FROM (SELECT table_name AS entity, role FROM {values(_ROLE_ROWS, ['table_name', 'column_name', 'role'])}) GROUP BY entity")
def ask_enumerate_counts(spark, sf):
    b = from_parquet(spark, sf, STAR)
    got = ask.enumerate_questions({t: b[t].columns for t in STAR}, _found_roles(b))
    return rows(spark, got, "entity string, question string").groupBy("entity").agg(F.count("*").alias("n_questions"))


@query(f"SELECT r_name, n_name, CAST(sum(CAST(o_totalprice AS DECIMAL(18,2))) AS DOUBLE) AS total_price, CAST(GROUPING(r_name, n_name) AS BIGINT) AS gid FROM {_O} GROUP BY ROLLUP (r_name, n_name)")
def ask_context_rollup(spark, sf):
    b = from_parquet(spark, sf, STAR)
    o = b["orders"].join(b["customer"], F.col("o_custkey") == F.col("c_custkey")).join(b["nation"], F.col("c_nationkey") == F.col("n_nationkey")).join(b["region"], F.col("n_regionkey") == F.col("r_regionkey"))
    return o.rollup("r_name", "n_name").agg(F.sum(F.col("o_totalprice").cast("decimal(18,2)")).cast("double").alias("total_price"), F.grouping_id().alias("gid"))


@query("SELECT * FROM (VALUES ('avg(c_nationkey)', true), ('sum(o_totalprice)', false), ('sum(o_orderdate)', true)) v(question, refused)")
def ask_refused_operations(spark, sf):
    """The roles are those that the values of both tables give; a question that is not refused is answered."""
    b, out = from_parquet(spark, sf, ["customer", "orders"]), []
    found = _found_roles(b)
    for t, op, c in (("customer", "avg", "c_nationkey"), ("orders", "sum", "o_totalprice"), ("orders", "sum", "o_orderdate")):
        try:
            ask.plan(Question(t, op, c), b.tables, found, GRAPH, "v").collect()
            out.append((f"{op}({c})", False))
        except NotLicensed:
            out.append((f"{op}({c})", True))
    return rows(spark, out, "question string, refused boolean")


@query(f"SELECT n_name, count(*) AS n FROM {_O} GROUP BY 1")
def ask_entity_view_sql(spark, sf):
    """The SQL surface: entity views with their m:1 attributes."""
    b = from_parquet(spark, sf, ["region", "nation", "customer", "orders"])
    ask.register(b.tables, JoinGraph([j for j in GRAPH.joins if j[0] in b.tables and j[2] in b.tables]))
    return spark.sql("SELECT n_name, count(*) AS n FROM orders_entity GROUP BY n_name")


def T(spark, sf, *names):
    b = from_parquet(spark, sf, list(names))
    return [b[n] for n in names]


@query("SELECT 'with_lines' AS kind, count(*) AS n FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem) UNION ALL SELECT 'without_lines', count(*) FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)")
def op_semi_anti(spark, sf):
    o, l = T(spark, sf, "orders", "lineitem")
    k = l.select(F.col("l_orderkey").alias("o_orderkey"))
    one = lambda how, n: o.join(k, "o_orderkey", how).agg(F.count("*").alias("n")).select(F.lit(n).alias("kind"), "n")
    return one("left_semi", "with_lines").union(one("left_anti", "without_lines"))


@query("SELECT event_id, arg_max(o_orderkey, (o_orderdate, o_orderkey)) AS o_orderkey FROM events JOIN orders ON o_custkey = user_id AND o_orderdate <= ts GROUP BY event_id")
def op_asof_event_order(spark, sf):
    """Each event with the user's last order before it. Both sides are merged per user and carried forward, so the work is one
    sort and not the product of a user's events and orders."""
    e, o = T(spark, sf, "events", "orders")
    both = e.select(F.col("user_id").alias("u"), F.col("ts").alias("t"), "event_id", F.lit(None).cast("long").alias("k")).union(o.select("o_custkey", "o_orderdate", F.lit(None).cast("long"), "o_orderkey"))
    w = Window.partitionBy("u").orderBy("t", F.col("event_id").isNotNull(), "k").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn("o_orderkey", F.last("k", True).over(w)).where("event_id is not null and o_orderkey is not null").select("event_id", "o_orderkey")


@query("SELECT o_orderkey, count(*) AS n_within_30d FROM orders JOIN lineitem ON l_orderkey = o_orderkey AND l_shipdate >= o_orderdate AND l_shipdate < o_orderdate + INTERVAL 30 DAY GROUP BY 1")
def op_interval_join(spark, sf):
    o, l = T(spark, sf, "orders", "lineitem")
    return o.join(l, (F.col("l_orderkey") == F.col("o_orderkey")) & (F.col("l_shipdate") >= F.col("o_orderdate")) & (F.col("l_shipdate") < F.col("o_orderdate") + F.expr("interval 30 days"))).groupBy("o_orderkey").agg(F.count("*").alias("n_within_30d"))


@query("SELECT o_orderkey, CAST(sum(CAST(o_totalprice AS DECIMAL(18,2))) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS UNBOUNDED PRECEDING) AS DOUBLE) AS running FROM orders")
def op_window_running_total(spark, sf):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(Window.unboundedPreceding, 0)
    return T(spark, sf, "orders")[0].select("o_orderkey", F.sum(F.col("o_totalprice").cast("decimal(18,2)")).over(w).cast("double").alias("running"))


@query("SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS 6 PRECEDING), 6) AS avg7 FROM events")
def op_window_moving_avg(spark, sf):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-6, 0)
    return T(spark, sf, "events")[0].select("event_id", F.round(F.avg("value").over(w), 6).alias("avg7"))


@query("SELECT event_id, CAST(epoch(date_trunc('second', ts)) - epoch(date_trunc('second', lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id))) AS BIGINT) AS gap_seconds FROM events")
def op_window_lag_gap(spark, sf):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    sec = F.unix_seconds(F.col("ts").cast("timestamp"))
    return T(spark, sf, "events")[0].select("event_id", (sec - F.lag(sec).over(w)).alias("gap_seconds"))


@query("SELECT p_partkey, CAST(rank() OVER w AS INTEGER) AS rnk, CAST(dense_rank() OVER w AS INTEGER) AS dense, round(percent_rank() OVER w, 6) AS pct FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_size)")
def op_window_rank_parts(spark, sf):
    w = Window.partitionBy("p_brand").orderBy("p_size")
    return T(spark, sf, "part")[0].select("p_partkey", F.rank().over(w).alias("rnk"), F.dense_rank().over(w).alias("dense"), F.round(F.percent_rank().over(w), 6).alias("pct"))


@query("SELECT l_returnflag AS flag, l_linestatus AS status, CAST(GROUPING(l_returnflag, l_linestatus) AS BIGINT) AS gid, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")
def op_grouping_sets(spark, sf):
    T(spark, sf, "lineitem")[0].createOrReplaceTempView("semcat_lines")
    return spark.sql("SELECT l_returnflag AS flag, l_linestatus AS status, grouping_id(l_returnflag, l_linestatus) AS gid, count(*) AS n FROM semcat_lines GROUP BY l_returnflag, l_linestatus GROUPING SETS ((l_returnflag), (l_linestatus), ())")


@query("SELECT l_returnflag AS flag, l_linestatus AS status, sum(l_quantity) AS qty FROM lineitem GROUP BY CUBE (1, 2)")
def op_cube_flags(spark, sf):
    return T(spark, sf, "lineitem")[0].select(F.col("l_returnflag").alias("flag"), F.col("l_linestatus").alias("status"), "l_quantity").cube("flag", "status").agg(F.sum("l_quantity").alias("qty"))


@query("SELECT o_orderpriority AS priority, count(*) FILTER (WHERE o_orderstatus = 'F') AS F, count(*) FILTER (WHERE o_orderstatus = 'O') AS O, count(*) FILTER (WHERE o_orderstatus = 'P') AS P FROM orders GROUP BY 1")
def op_pivot_status(spark, sf):
    return T(spark, sf, "orders")[0].groupBy(F.col("o_orderpriority").alias("priority")).pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1))).na.fill(0)


@query("SELECT measure, CAST(sum(CAST(v AS DECIMAL(18,2))) AS DOUBLE) AS total FROM (SELECT l_quantity, l_extendedprice, l_discount, l_tax FROM lineitem) UNPIVOT (v FOR measure IN (l_quantity, l_extendedprice, l_discount, l_tax)) GROUP BY 1")
def op_unpivot_measures(spark, sf):
    m = ["l_quantity", "l_extendedprice", "l_discount", "l_tax"]
    return T(spark, sf, "lineitem")[0].unpivot([], m, "measure", "v").groupBy("measure").agg(F.sum(F.col("v").cast("decimal(18,2)")).cast("double").alias("total"))


@query("WITH a AS (SELECT o_orderkey AS k FROM orders), b AS (SELECT l_orderkey AS k FROM lineitem) SELECT 'intersect' AS op, count(*) AS n FROM (SELECT k FROM a INTERSECT SELECT k FROM b) UNION ALL SELECT 'except_all', count(*) FROM (SELECT k FROM b EXCEPT ALL SELECT k FROM a) UNION ALL SELECT 'union', count(*) FROM (SELECT k FROM a UNION SELECT k FROM b)")
def op_set_ops_keys(spark, sf):
    o, l = T(spark, sf, "orders", "lineitem")
    a, b = o.select(F.col("o_orderkey").alias("k")), l.select(F.col("l_orderkey").alias("k"))
    one = lambda df, n: df.agg(F.count("*").alias("n")).select(F.lit(n).alias("op"), "n")
    return one(a.intersect(b), "intersect").union(one(b.exceptAll(a), "except_all")).union(one(a.union(b).distinct(), "union"))


@query("SELECT CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events GROUP BY 1")
def op_json_props(spark, sf):
    return T(spark, sf, "events")[0].groupBy(F.from_json("props", "k long")["k"].alias("k")).agg(F.count("*").alias("n"))


@query("SELECT regexp_extract(url, '^[a-z]+://([^/?#:]+)', 1) AS host, count(*) AS n FROM pages GROUP BY 1")
def op_url_host(spark, sf):
    return T(spark, sf, "pages")[0].groupBy(F.parse_url("url", F.lit("HOST")).alias("host")).agg(F.count("*").alias("n"))


@query("SELECT page_id, regexp_extract(html, '<title>([^<]*)</title>', 1) AS title FROM pages")
def op_html_title(spark, sf):
    return T(spark, sf, "pages")[0].select("page_id", F.regexp_extract("html", "<title>([^<]*)</title>", 1).alias("title"))


@query("SELECT vec_id, CAST(len(embedding) AS INTEGER) AS dims, round(sqrt(list_inner_product(embedding::DOUBLE[], embedding::DOUBLE[])), 5) AS norm FROM embeddings")
def op_array_norms(spark, sf):
    sq = F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))
    return T(spark, sf, "embeddings")[0].select("vec_id", F.size("embedding").alias("dims"), F.round(F.sqrt(sq), 5).alias("norm"))


@query("WITH g AS (SELECT *, CASE WHEN lag(ts) OVER w IS NULL OR ts - lag(ts) OVER w > INTERVAL 6 HOUR THEN 1 ELSE 0 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)), s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS session FROM g) SELECT user_id, CAST(session AS BIGINT) AS session, count(*) AS n FROM s GROUP BY ALL")
def op_session_gaps(spark, sf):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    before = F.lag("ts").over(w)
    g = T(spark, sf, "events")[0].withColumn("fresh", F.when(before.isNull() | (F.col("ts") > before + F.expr("interval 6 hours")), 1).otherwise(0))
    return g.withColumn("session", F.sum("fresh").over(w.rowsBetween(Window.unboundedPreceding, 0))).groupBy("user_id", "session").agg(F.count("*").alias("n"))


@query("SELECT o_orderpriority AS priority, round(quantile_cont(o_totalprice, 0.5), 4) AS p50, round(quantile_cont(o_totalprice, 0.9), 4) AS p90 FROM orders GROUP BY 1")
def op_percentiles(spark, sf):
    return T(spark, sf, "orders")[0].groupBy(F.col("o_orderpriority").alias("priority")).agg(F.round(F.percentile("o_totalprice", 0.5), 4).alias("p50"), F.round(F.percentile("o_totalprice", 0.9), 4).alias("p90"))


@query("SELECT c_custkey, o_orderkey, CAST(rnk AS INTEGER) AS rnk FROM (SELECT o_custkey AS c_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS rnk FROM orders) WHERE rnk <= 3")
def op_topk_per_group(spark, sf):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return T(spark, sf, "orders")[0].select(F.col("o_custkey").alias("c_custkey"), "o_orderkey", F.row_number().over(w).alias("rnk")).where("rnk <= 3")


_NAMES = values([(c,) for t in STAR for c in COLUMNS[t]], ["column_name"])


@query(f"SELECT column_name, unnest(string_split(column_name, '_')) AS token FROM {_NAMES}")
def op_string_tokens(spark, sf):
    return rows(spark, [(c,) for t in STAR for c in COLUMNS[t]], "column_name string").select("column_name", F.explode(F.split("column_name", "_")).alias("token"))


@query(f"SELECT role, count(*) FILTER (WHERE left(column_name, 1) = 'o') AS o, count(*) FILTER (WHERE left(column_name, 1) = 'l') AS l FROM {values(_ROLE_ROWS, ['table_name', 'column_name', 'role'])} GROUP BY role")
def op_crosstab_role_isa(spark, sf):
    return rows(spark, _ROLE_ROWS, "table_name string, column_name string, role string").groupBy("role").pivot("table_name", ["orders", "lineitem"]).agg(F.count(F.lit(1))).na.fill(0).select("role", F.col("orders").alias("o"), F.col("lineitem").alias("l"))


