"""Rules, invariants and worked cases of the builder."""

import pytest

from pyspark.sql import functions as F

from semcat.operators import claims, domains, evidence, joins, keys, profile, typing_rules
from semcat.plans import ask, builder, graph, lexicon, model
from semcat.plans.model import dump, load
from semcat.sources import bundle as src

SF = "/root/testdata/sf0.001"


def test_catalog_round_trip_and_claims(spark):
    b = src.from_parquet(spark, SF, src.SCOPES["W2"], declared=True)
    c = builder.build(b)
    assert load(dump(c)) == c
    n = len(c.entities)
    assert len(claims.generate(c)) == 2 * n + sum(len(e.attributes) + len(e.aggregables) for e in c.entities)
    assert not claims.audit(c, b, {})


def test_faulty_proposals_never_reach_the_catalog(spark):
    b = src.from_parquet(spark, SF, ["nation", "region", "customer"], declared=True)
    c = builder.build(b, proposer=builder.FaultyProposer(builder.LexicalProposer(), 3, 0.8))
    assert c.warnings
    for e in c.entities:
        for a in e.attributes:
            assert a.src_cols[0] in b[a.src_table].columns
            assert "Metric" not in a.roles or (a.isa in ("integer", "float") and not lexicon.id_like(a.src_cols[0]))


def test_answers_are_built_in(spark):
    b = src.from_parquet(spark, SF, ["region", "nation"], declared=True)
    assert builder.build(b, answers={"table:region": "passthrough"}).lookups == ["region"]
    assert builder.build(b).lookups == []


def test_triage_rules():
    assert builder.triage("schema_migrations", 5, ["v"], (["v"], "verified"), 0, 0)[0] == "ignore"
    assert builder.triage("enrollment", 500, ["a", "b"], (["a"], "fallback"), 2, 0)[0] == "link"
    assert builder.triage("status", 3, ["code", "meaning"], (["code"], "verified"), 0, 1)[0] == "passthrough"
    assert builder.triage("people", 500, ["id", "name"], (["id"], "verified"), 0, 1)[0] == "entity"


def test_keys_names_and_nulls(spark):
    df = spark.createDataFrame([(1, "Ann", None), (2, "Ann", 5), (3, "Bo", 6)], "player_id int, name string, loose int")
    got = {r["cols"]: r["is_unique"] for r in keys.verify_many(df, [["player_id"], ["name"], ["loose"], ["name", "loose"]]).collect()}
    assert got == {"player_id": True, "name": False, "loose": False, "name|loose": False}
    assert keys.search(df, "player", {})[0] == ["player_id"]
    measures = spark.createDataFrame([(1.5, 2.5)], "score double, price double")
    assert keys.search(measures, "m", {"score": "Numeric", "price": "Numeric"})[1] == "fallback"
    assert dict(keys.verify_one_by_one(df, [["player_id"], ["name"]])) == {"player_id": True, "name": False}


def test_overlap_ways_agree(spark):
    b = src.from_parquet(spark, SF, ["region", "nation", "customer"])
    d = domains.build(b, domains.integer_columns(b))
    one = {(r["source"], r["target"]): r["n_common"] for r in domains.pair_overlap(d, ["region.r_regionkey", "nation.n_nationkey"]).collect()}
    pairs = [(s, t) for s in ("nation.n_regionkey", "customer.c_nationkey") for t in ("region.r_regionkey", "nation.n_nationkey") if s.split(".")[0] != t.split(".")[0]]
    two = {(r["source"], r["target"]): r["n_common"] for r in domains.pair_overlap_naive(d, pairs).collect()}
    assert all(one[k] == v for k, v in two.items())


def test_guards_fall_in_order(spark):
    rows = [("a.k", "b.id", 5, 5), ("a.size", "b.id", 5, 5), ("a.b_id", "b.id", 5, 5), ("a.x_id", "b.id", 1, 9), ("a.x_id", "c.id", 1, 9), ("a.x_id", "d.id", 1, 9)]
    o = spark.createDataFrame(rows, "source string, target string, n_common long, n_source long")
    got = {r["source"]: r["stage"] for r in joins.ledger(o, ["a.k"], ["a.size"]).collect()}
    assert got == {"a.k": "source_is_key", "a.size": "measure", "a.b_id": "accepted" if lexicon.name_affinity("b_id", "b", "id") >= 0.7 else "judge", "a.x_id": "ambiguous"}
    free = joins.ledger(o, ["a.k"], ["a.size"], joins.JoinPolicy(guards=False, judge="approve_all"))
    assert free.where("stage = 'accepted'").count() == 6


def test_roles_do_not_follow_digits():
    assert typing_rules.role("zip", "string") == "Categorical"
    assert typing_rules.role("c_nationkey", "int") == "Categorical"
    assert typing_rules.role("p_size", "int") == "Numeric"
    assert typing_rules.role("embedding", "array<float>") == "Opaque"


def test_parallel_joins_stay_apart():
    g = graph.JoinGraph([("lane", "buyer", "nation", "id"), ("lane", "seller", "nation", "id")])
    assert len(g.joins) == 2
    assert len(g.paths("lane", 1)) == 1
    assert len(g.paths("lane", 1, all_parallel=True)) == 2


def test_questions_need_a_licence(spark):
    b = src.from_parquet(spark, SF, ["nation", "region"])
    g = graph.JoinGraph([src.FOREIGN[0]])
    roles = {"n_name": "Categorical", "r_name": "Categorical", "n_nationkey": "Categorical", "n_regionkey": "Categorical"}
    with pytest.raises(ask.NotLicensed):
        ask.plan(ask.Question("nation", "avg", "n_nationkey"), b.tables, roles, g)
    with pytest.raises(ask.NotLicensed):
        ask.plan(ask.Question("region", by=("n_name",)), b.tables, roles, g)
    assert ask.plan(ask.Question("nation", by=("r_name",)), b.tables, roles, g).count() == 5


def test_results_do_not_depend_on_partitions(spark):
    b = src.from_parquet(spark, SF, ["nation", "customer"])
    cut = [src.SourceBundle({t: df.repartition(n) for t, df in b.tables.items()}) for n in (1, 7)]
    assert sorted(profile.samples(cut[0]).collect()) == sorted(profile.samples(cut[1]).collect())
    assert sorted(profile.fingerprint(cut[0]).collect()) == sorted(profile.fingerprint(cut[1]).collect())


def test_flat_files_round_trip(spark, tmp_path):
    b = src.from_parquet(spark, SF, ["region", "nation"])
    src.save(b, str(tmp_path), "csv")
    back = src.from_files(spark, str(tmp_path), ["region", "nation"])
    assert {f.dataType.simpleString() for f in back["nation"].schema.fields} == {"string"}
    assert sorted(back["nation"].collect()) == sorted(src.stripped(b)["nation"].collect())
    with pytest.raises(NotImplementedError):
        src.from_files(spark, str(tmp_path), ["x"], "excel")


def test_relationship_coverage_follows_the_build(spark, monkeypatch):
    """Coverage falls with the joins of the built catalog: nothing is compared with itself."""
    from semcat.queries import arms
    from semcat.queries import catalog_queries as q

    def few(spark, sf, arm, tables=None):
        st = arms_state(spark, sf, arm, tables)
        st.declared = [j for j in st.declared if j[0] == "orders"] + [("customer", "c_nationkey", "region", "r_regionkey")]
        return st

    arms_state = arms.state
    full = {(r["scope"], r["kind"]): r["n_hit"] for r in q.cov_reference(spark, SF).collect()}
    monkeypatch.setattr(q.arms, "state", few)
    less = {(r["scope"], r["kind"]): r["n_hit"] for r in q.cov_reference(spark, SF).collect()}
    assert full["W2", "relationship"] == 4 and less["W2", "relationship"] == 1
    assert less["W2", "aggregable"] < full["W2", "aggregable"] and less["W2", "attribute"] == full["W2", "attribute"]
    assert {k: r["n_hit"] for r in q.cov_relationships(spark, SF).collect() for k in [r["scope"]]} == {"W1": 0, "W2": 1, "W3": 1, "W6": 0}


@pytest.mark.parametrize("arm", ["stripped", "disjoint"])
def test_build_without_metadata(spark, arm):
    """Text alone gives storage, roles, identifiers, and the joins that the guards allow."""
    typed = src.from_parquet(spark, SF, src.SCOPES["W2"])
    c = builder.build({"stripped": src.stripped, "disjoint": src.disjoint}[arm](typed))
    by = {(e.table, a.src_cols[0]): a for e in c.entities for a in e.attributes}
    assert by["customer", "c_acctbal"].roles == ["Numeric", "Metric"] and by["customer", "c_acctbal"].isa == "float"
    assert by["orders", "o_orderdate"].isa == "date" and by["orders", "o_orderdate"].roles == ["Datetime"]
    assert by["orders", "o_custkey"].roles == ["Categorical"]
    assert {e.table: e.id_columns for e in c.entities if e.table != "lineitem"} == {"region": ["r_regionkey"], "nation": ["n_nationkey"], "customer": ["c_custkey"], "orders": ["o_orderkey"]}
    got = {(j["from_col"], j["to_col"]) for j in c.joins}
    assert got == (set() if arm == "stripped" else {("n_regionkey", "r_regionkey"), ("c_nationkey", "n_nationkey"), ("o_custkey", "c_custkey"), ("l_orderkey", "o_orderkey")})
    assert model.validate(dump(c)) == []


def test_no_table_is_named_in_the_library():
    """The builder knows no table of the tests: names occur only in sources (annotation) and queries."""
    from pathlib import Path

    root = Path(src.__file__).resolve().parent.parent
    for f in [*(root / "plans").glob("*.py"), *(root / "operators").glob("*.py")]:
        text = f.read_text()
        for word in ("lineitem", "custkey", "nationkey", "conversations", "embedding", "acctbal", "mktsegment"):
            assert word not in text, (f.name, word)


def test_evidence_classes(spark):
    rows = [("01234", "12", "20240131", "2024-01-31 10:30:00", "2024-01-31", "yes", "0", "1.5", '{"k": 1}', None, "09:15-11"), ("00501", "7", "20231105", "2024-02-01 00:00:00", "2024-02-01", "NO", "1", "-2", "[1]", None, "13:00-14:30")]
    names = ["zip", "size", "start_date", "stamp", "day", "paid_up", "member", "price", "extra", "nothing", "hours"]
    found = evidence.gather(src.SourceBundle({"t": spark.createDataFrame(rows, ", ".join(f"{n} string" for n in names))}))
    got = {c: (e.isa, e.role) for (_, c), e in found.items()}
    assert got == {"zip": ("string", "Categorical"), "size": ("integer", "Numeric"), "start_date": ("date", "Datetime"), "stamp": ("datetime", "Datetime"), "day": ("date", "Datetime"), "paid_up": ("boolean", "Categorical"), "member": ("boolean", "Categorical"), "price": ("float", "Numeric"), "extra": ("string", "Opaque"), "nothing": ("string", "Categorical"), "hours": ("string", "Categorical")}
    assert not found["t", "hours"].supports("Numeric") and not found["t", "zip"].supports("Numeric") and found["t", "stamp"].supports("Datetime")
    assert found["t", "price"].description == "e.g. -2, 1.5" and found["t", "nothing"].no_key
    empty = evidence.gather(src.SourceBundle({"t": spark.createDataFrame([], "id long, name string")}))
    assert {e.n_rows for e in empty.values()} == {0}


def test_budget_that_ends_a_search_is_told(spark):
    df = spark.createDataFrame([(1,) * 14, (1,) * 14], ", ".join(f"a{i}_id long" for i in range(14)))
    assert keys.search(df, "t", {}) == (["a0_id"], "fallback, budget spent")
    assert keys.search(df.select("a0_id"), "t", {}) == (["a0_id"], "fallback")
    c = builder.build(src.SourceBundle({"t": df}))
    assert c.warnings == ["t: fallback, budget spent"]


def test_names_are_general():
    assert lexicon.words("l_extendedprice") == ["extended", "price"] and lexicon.words("n_chars") == ["n", "chars"] and lexicon.words("homeTeamId") == ["home", "team", "id"]
    assert lexicon.label("cont_date") == "Containment Date" and lexicon.label("c_acctbal") == "Account Balance"
    assert not lexicon.id_like("valid") and not lexicon.id_like("candidate")
    assert lexicon.name_affinity("home_team_id", "teams", "team_id") == 0.9 and lexicon.name_affinity("team_id", "teams", "id") == 0.8
    assert lexicon.deduplicated([("name", "a", "x"), ("name", "b", "y"), ("key", "a", "k"), ("name", "b", "z")]) == ["a_name", "b_y", "key", "b_z"]
    assert builder.reference("p", ["p_id", "first_name", "last_name"], ["p_id"]) == "{first_name} {last_name}"
    assert builder.reference("p", ["a_id", "b_id"], ["a_id", "b_id"]) == "{a_id} {b_id}"


def test_details_that_are_names_are_called_names(spark):
    df = spark.createDataFrame([(1, "Customer#1"), (2, "Customer#2")], "id long, details string")
    c = builder.build(src.SourceBundle({"buyers": df}))
    assert [a.nicename for a in c.entities[0].attributes] == ["Id", "Customer Name"]


def test_phrases_are_grounded(spark):
    b = src.from_parquet(spark, SF, ["customer", "orders"])
    p = builder.CallableProposer(lambda d, rows: builder.Proposal([("purchase", "orders"), ("buyer", "the customer")], [("the customer", "account balance", "Numeric"), ("orders", "ghost", "Numeric"), ("orders", "key", "Categorical")]))
    c = builder.build(b, "who buys", p)
    assert {e.table: e.name for e in c.entities} == {"customer": "customer", "orders": "order"}
    assert c.warnings == ["orders.ghost: unknown column"]
    q = next(q for q in c.questions if q["kind"] == "column")
    assert q["choices"] == ["o_orderkey", "o_custkey"] and "o_custkey" in q["text"]


def test_second_routes_are_kept(spark):
    b = src.from_parquet(spark, SF, src.STAR, declared=True)
    c = builder.build(b)
    e = next(e for e in c.entities if e.table == "lineitem")
    routes = {tuple(g.path) for g in e.aggregables if g.src_table == "nation"}
    assert len(routes) == 2 and model.validate(dump(c)) == []


def test_rounds_of_questions(spark):
    st = builder.examine(src.stripped(src.from_parquet(spark, SF, ["region", "nation", "customer"])))
    yes = lambda q: "yes" if q["id"] in ("join:customer.c_nationkey->nation.n_nationkey", "join:nation.n_regionkey->region.r_regionkey") else None
    policy = joins.JoinPolicy(ambiguous="ask", min_targets=1)
    c, asked = builder.converse(st, yes, policy)
    assert len(asked) >= 2 and {(j["from_col"], j["to_col"]) for j in c.joins} == {("c_nationkey", "n_nationkey"), ("n_regionkey", "r_regionkey")}
    quiet, rounds = builder.converse(st, lambda q: None, policy)
    assert quiet.joins == [] and len(rounds) == 1 and quiet == builder.assemble(st, policy)


def test_replay_files_and_manifest(spark, tmp_path):
    f = tmp_path / "declared.json"
    f.write_text('{"primary": {"region": ["r_regionkey"]}, "foreign": [["nation", "n_regionkey", "region", "r_regionkey"]]}')
    b = src.with_manifest(src.from_parquet(spark, SF, ["region", "nation"]), str(f))
    assert b.primary == {"region": ["r_regionkey"]} and b.foreign == [("nation", "n_regionkey", "region", "r_regionkey")]
    assert builder.build(b).joins[0]["to_col"] == "r_regionkey"
    profile.freeze(b, str(tmp_path / "frozen"))
    assert spark.read.parquet(str(tmp_path / "frozen")).count() == 5


def test_path_claims_match_whole_joins(spark):
    b = src.from_parquet(spark, SF, src.STAR)
    g = graph.JoinGraph([f for f in src.FOREIGN if f[0] in src.STAR])
    for t, p in [("nation", x) for x in g.paths("nation", 3)][:12]:
        r = claims.run_paths(b, [(t, p)]).first()
        df = graph.along({k: v.select(*[F.col(c).alias(c) for c in v.columns]) for k, v in b.tables.items()}, t, p)
        assert r["rows_joined"] == df.count() and r["rows_base"] == 25


def test_value_claims_catch_a_wrong_storage(spark):
    b = src.SourceBundle({"t": spark.createDataFrame([("1", "x"), ("2", None)], "a string, b string")})
    got = {r["attribute"]: (r["n_values"], r["passed"]) for r in claims.run_values(b, [("t", "a", "a", "integer"), ("t", "b", "b", "integer"), ("t", "c", "b", "string")]).collect()}
    assert got == {"a": (2, True), "b": (1, False), "c": (1, True)}


def test_catalog_schema_finds_faults():
    c = model.Catalog(entities=[model.Entity("a", "t", ["k"], "verified", "{k}", [model.Attribute("k", "t", ["k"], "number", ["Key"], "K"), model.Attribute("k", "t", ["k"], "string", ["Categorical"], "K")])] * 2, joins=[{"from_table": "t"}])
    faults = " ".join(model.validate(dump(c)))
    for x in ("unknown storage number", "unknown role Key", "k twice", "two entities of t", "joins[0].from_col"):
        assert x in faults


def test_masks_count_as_pair_overlap_does(spark):
    """Over 63 columns take more than one mask; the pairs and counts stay those of the pair by pair way."""
    n = 40
    tables = {t: spark.range(30).select(*[F.when(F.col("id") % (i + 2) != 1, F.col("id") * (i % 3 + 1)).alias(f"c{i}") for i in range(n)]) for t in ("a", "b")}
    b = src.SourceBundle(tables)
    columns = [(t, f"c{i}") for t in tables for i in range(n)]
    targets = ["a.c0", "b.c1", "b.c39"]
    want = domains.pair_overlap(domains.build(b, columns), targets)
    got = domains.overlap_by_masks(b, columns, targets)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.select(got.columns).collect()))


def test_one_share_refutes_copies_and_keeps_keys(spark):
    """Of a large table, one share of the rows shows the copies of a composite; a key is left to the proof, and is found."""
    df = spark.range(400_000).select((F.col("id") % 2000).alias("a"), (F.col("id") / 2000).cast("long").alias("b"), (F.col("id") % 1900).alias("c"))
    p = keys.KeySearch({}, ("a", "b", "c"), rows=400_000, distinct={"a": 2000, "b": 200, "c": 1900})
    assert keys.refuted_by_share(df, [["b", "c"], ["a", "b"]], p) == {"b|c"}
    assert keys.first_composite(df, ["b", "c", "a"], p) == (["b", "a"], False)


def test_evidence_merges_tasks_and_batches(spark):
    """Partial evidence of several tasks merges to that of the whole column; NaN is the greatest and a zero has no sign."""
    df = spark.range(0, 5000, 1, 7).select(F.col("id"), F.concat(F.lit("v"), F.col("id") % 10).alias("v"), F.when(F.col("id") % 5 != 0, F.when(F.col("id") == 1, F.lit(float("nan"))).otherwise(F.lit(-0.0))).alias("x"), (F.col("id") % 2).cast("int").alias("f"), F.array("id").alias("l"))
    got = evidence.gather(src.SourceBundle({"t": df}))
    i, v, x, f, l = (got["t", c] for c in ("id", "v", "x", "f", "l"))
    assert (i.n, i.least, i.greatest) == (5000, "0", "4999") and abs(i.about_distinct - 5000) < 300 and not i.no_key
    assert (v.about_distinct, v.least, v.greatest, v.mean_length) == (10, "v0", "v9", 2.0)
    assert (x.n_rows, x.n, x.least, x.greatest) == (5000, 4000, "0.0", "nan")
    assert f.truth == ("0", "1") and f.classes["truth"] == 5000 and l.family == "opaque" and abs(l.about_distinct - 5000) < 300


def test_keys_of_several_tables_are_proved_at_once(spark):
    a = spark.createDataFrame([(i, i % 7 or None, "x") for i in range(100)], "k long, part long, same string").repartition(3)
    b = spark.createDataFrame([("p", 1), ("p", 2), ("q", 1)], "u string, v int").repartition(2)
    got = {(r["table"], r["cols"]): (r["n"], r["n_nonnull"], r["n_distinct"], r["is_unique"]) for r in keys.verify_tables([("a", a, [["k"], ["part"], ["same"]]), ("none", a, []), ("b", b, [["u"], ["u", "v"]])]).collect()}
    assert got == {("a", "k"): (100, 100, 100, True), ("a", "part"): (100, 85, 6, False), ("a", "same"): (100, 100, 1, False), ("b", "u"): (3, 3, 2, False), ("b", "u|v"): (3, 3, 3, True)}


def test_distinct_pairs_need_both_hashes():
    import numpy as np

    from semcat.operators import hashed

    a, b = (np.array(x, np.uint64) for x in ([5, 5, 5, 2, 5, 2, 2**63], [1, 1, 2, 9, 1, 9, 0]))
    assert [x.tolist() for x in hashed.distinct(a, b)] == [[2, 5, 5, 2**63], [9, 1, 2, 0]]
    assert [len(x) for x in hashed.distinct(a[:0], b[:0])] == [0, 0]


def test_arms_share_the_evidence_of_equal_columns(spark, monkeypatch):
    """A column that another arm reads in the same way is not examined again; one that differs in value, type or place is."""
    b = src.from_parquet(spark, SF, ["customer", "nation"])
    bare, own = src.stripped(b), src.disjoint(src.from_parquet(spark, SF, ["customer", "nation"]))
    found, seen, part = evidence.gather(bare), [], evidence._partial
    monkeypatch.setattr(evidence, "_partial", lambda df, t: seen.extend((t, c) for c in df.columns) or part(df, t))
    shared = evidence.gather(own, [(bare, found)])
    assert set(seen) == {("customer", "c_custkey"), ("customer", "c_nationkey"), ("nation", "n_nationkey"), ("nation", "n_regionkey")}
    assert shared == evidence.gather(own) and list(shared) == [(t, c) for t in own.tables for c in own[t].columns]
    assert evidence.shared(b, [(bare, found)]).keys() == {("customer", "c_name"), ("customer", "c_mktsegment"), ("nation", "n_name")}
    assert not evidence.shared(src.SourceBundle({"nation": bare["nation"].limit(5)}), [(bare, found)])


def test_readings_examined_together_are_those_examined_alone(spark, tmp_path, monkeypatch):
    """Types, nulls, long texts, nested values and prefixes: evidence, identifiers and overlaps of each reading are those of its own run,
    while each column is brought to its distinct values once and no key is proved twice."""
    from semcat.operators import together

    odd = [(i, i // 3, None if i % 7 == 0 else i % 5, "K" + str(i % 9), ("{" + "x" * (60 + i % 9) + "}") if i % 2 else "y" * (i % 130), [-0.0, 0.0, float("nan"), 1e9, 0.1][i % 5], i % 2 == 0, [i, None]) for i in range(300)]
    t = spark.createDataFrame(odd, "a_id long, b_id int, part int, code string, note string, x double, flag boolean, l array<int>").withColumn("day", F.expr("date_add(DATE'2020-01-31', b_id)")).withColumn("at", F.expr("timestamp_seconds(a_id * 43200)"))
    u = spark.createDataFrame([(i, f"K{i}", i * 1.5) for i in range(9)], "k_id long, code_id string, price float")
    b = src.SourceBundle({"t": t, "u": u, "nation": src.from_parquet(spark, SF, ["nation"])["nation"]})
    prefix = {"k_id": "K", "b_id": "K", "code_id": "C", "n_nationkey": "N", "n_regionkey": "R"}
    text = src.stripped(b)
    own = src.SourceBundle({n: df.select(*[(F.concat(F.lit(prefix[c]), F.col(c)) if c in prefix else F.col(c)).alias(c) for c in df.columns]) for n, df in text.tables.items()})
    readings = [together.Reading(b), together.Reading(text, True), together.Reading(own, True, prefix)]
    alone = [builder.examine(r.bundle) for r in readings]
    proved, prove = [], keys.verify_tables
    monkeypatch.setattr(keys, "verify_tables", lambda jobs: proved.extend((n, tuple(c)) for n, _, cols in jobs for c in cols) or prove(jobs))
    monkeypatch.setattr(together.domains, "MASK", 5)  # more than one mask
    for got, want in zip(builder.examine_together(b, readings), alone, strict=True):
        assert got.ids == want.ids and got.roles == want.roles and list(got.evidence) == list(want.evidence)
        for k, e in want.evidence.items():
            g = got.evidence[k]
            assert (g.n_rows, g.n, g.least, g.greatest, g.truth, g.declared, g.family, g.isa) == (e.n_rows, e.n, e.least, e.greatest, e.truth, e.declared, e.family, e.isa), (k, g, e)
            assert abs(g.mean_length - e.mean_length) < 1e-9 and {c for c in g.classes.items() if c[1]} == {c for c in e.classes.items() if c[1]} and abs(g.about_distinct - e.about_distinct) <= 0.05 * e.about_distinct + 1
        shown = lambda s: sorted((o.source, o.target, o.n_common, o.n_source) for o in s.overlap)
        assert shown(got) == shown(want)
    assert ("t.code", "u.k_id", 9, 9) in shown(builder.examine_together(b, readings)[2])  # K1 is K and 1
    assert len(proved) == len(set(proved))


def test_arms_of_one_query_are_examined_together(spark, tmp_path, monkeypatch):
    """The query examines its three arms in one go, on a folder that the session has not seen."""
    from semcat.queries import arms
    from semcat.queries import catalog_queries as q

    for n in src.TABLES:
        (tmp_path / f"{n}.parquet").symlink_to(f"{SF}/{n}.parquet")
    monkeypatch.setattr(arms, "examine", lambda *a, **k: pytest.fail("an arm was examined alone"))
    got = {(r["scope"], r["arm"]): r["recovered"] for r in q.abl_fk_recovery(spark, str(tmp_path)).collect()}
    assert len(got) == 9 and got["W3", "meta"] == 8


def test_packed_counts_are_exact(spark, monkeypatch):
    """Nulls, both zeros, NaN and the ends of the range come back from packed integers with their counts, whatever batch or task held
    them, and also where a task sends values before its end."""
    from semcat.operators import hashed

    df = spark.range(0, 3000, 1, 5).select(F.when(F.col("id") % 7 != 0, F.when(F.col("id") % 2 == 0, -(2**63)).otherwise(F.col("id") % 11)).alias("v"), F.expr("element_at(array(-0.0D, 0.0D, double('nan'), 1e300D), CAST(id % 4 AS INT) + 1)").alias("x"), F.col("id"))
    want = {(at, str(r[0])): r[1] for at, c in ((4, "v"), (9, "x")) for r in df.groupBy(F.col(c).cast("string")).count().collect()}
    for rows, held in ((hashed.ROWS, hashed.HELD), (100, 10)):
        monkeypatch.setattr(hashed, "ROWS", rows)
        monkeypatch.setattr(hashed, "HELD", held)
        got = hashed.merge_counts(hashed.pack_counts(df, [4, 9, 2], 5), [9]).selectExpr("at", "CAST(IF(at = 9, CAST(x AS STRING), CAST(v AS STRING)) AS STRING) AS t", "n").collect()
        assert {(r["at"], str(r["t"])): r["n"] for r in got if r["at"] != 2} == want
        assert sum(r["at"] == 2 and r["n"] == 1 for r in got) == 3000


def test_permuted_rows_are_dealt_without_a_sort(spark):
    """Each run has the same rows in partitions of its own; they are dealt out unsorted, and larger tables into more partitions."""
    b = src.from_parquet(spark, SF, ["lineitem", "nation"])
    runs = [src.permuted(b, k) for k in (1, 2, 3)]
    cols = b["lineitem"].columns
    assert all(sorted(map(str, r["lineitem"].select(cols).collect())) == sorted(map(str, b["lineitem"].collect())) for r in runs)
    spread = [{tuple(x[:-1]): x[-1] for x in r["lineitem"].select(*cols, F.spark_partition_id()).collect()} for r in runs]
    assert all(sum(one[k] != two[k] for k in one) > len(one) / 2 for one, two in ((spread[0], spread[1]), (spread[1], spread[2]), (spread[0], spread[2])))
    assert [r["nation"].rdd.getNumPartitions() for r in runs] == [4, 5, 6]
    assert "RoundRobinPartitioning" not in runs[0]["lineitem"]._jdf.queryExecution().executedPlan().toString()  # which sorts a task's rows first
    big = src.SourceBundle({"t": spark.range(1 << 23)})
    assert src.permuted(big, 1)["t"].rdd.getNumPartitions() == 4 + (8 << 23) // src.DEALT


def test_permuted_runs_are_examined_side_by_side(spark, tmp_path, monkeypatch):
    """Each run reads its own rows and takes nothing from another; what it finds is what examining its twin alone finds."""
    import threading

    from semcat.queries import arms

    for n in src.TABLES:
        (tmp_path / f"{n}.parquet").symlink_to(f"{SF}/{n}.parquet")
    seen, gate, run = [], threading.Barrier(3, timeout=60), arms._run
    monkeypatch.setattr(arms, "_run", lambda typed, arm: (gate.wait(), seen.append(arm), run(typed, arm))[2])  # all three are under way at once
    arms.apart(spark, str(tmp_path), ["run1", "run2", "run3"])
    got, want = arms.state(spark, str(tmp_path), "run2"), builder.examine(arms.twin(spark, SF, "run2"))
    assert sorted(seen) == ["run1", "run2", "run3"] and got.ids == want.restrict(src.TABLES).ids and got.roles == want.restrict(src.TABLES).roles
    shown = lambda s: sorted((o.source, o.target, o.n_common, o.n_source) for o in s.overlap)
    assert shown(got) == shown(want)
