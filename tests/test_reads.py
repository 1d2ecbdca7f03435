"""Queries whose rows could be had without data do read it, also when the session has examined the arm before."""

import pytest

from semcat.queries import load_all

SF = "/root/testdata/sf0.001"
QUERIES, _ = load_all()


def read_bytes(spark):
    """Bytes of input by stage."""
    sc = spark.sparkContext
    sc._jsc.sc().listenerBus().waitUntilEmpty()
    stages = sc._jsc.sc().statusStore().stageList(None, False, False, sc._gateway.new_array(sc._gateway.jvm.double, 0), None)
    return {stages.apply(i).stageId(): stages.apply(i).inputBytes() for i in range(stages.size())}


@pytest.mark.parametrize("name", ["abl_symbolic_only_roles", "ask_enumerate_counts", "ask_refused_operations", "audit_findings_seeded", "claim_attribute_mapping", "clarify_link_lends_columns", "clarify_questions", "clarify_type_answer", "cov_closure_equivalence", "cov_relationships"])
def test_reads_its_tables(name, spark):
    for _ in range(2):
        before = set(read_bytes(spark))
        assert QUERIES[name](spark, SF).collect()
        assert sum(n for k, n in read_bytes(spark).items() if k not in before) > 500
