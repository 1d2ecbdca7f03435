"""Join candidates, the three checks and the guards; every decision is a row of the ledger.

The data are read by the overlap job alone. Its result has at most columns x keys rows, whatever the size of the tables, so
guards and judge work on it on the driver.
"""

from __future__ import annotations

import json
from collections import defaultdict
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from semcat.operators import domains
from semcat.operators.evidence import ColumnEvidence
from semcat.plans.lexicon import name_affinity
from semcat.sources.bundle import SourceBundle

#: Least confidence of the judge.
TAU = 0.70


@dataclass(frozen=True)
class Overlap:
    """Two columns, how many values they share and how many the source has; what is known of either column may come along."""

    source: str
    target: str
    n_common: int
    n_source: int
    source_evidence: ColumnEvidence | None = None
    target_evidence: ColumnEvidence | None = None


class LexicalJudge:
    """Names, and types where they are known: columns that are stored as different things refer to nothing."""

    def score(self, pair: Overlap) -> float:
        a, b = pair.source_evidence, pair.target_evidence
        if a and b and a.family != b.family:
            return 0.0
        return name_affinity(pair.source.split(".")[1], *pair.target.split("."))


class ApproveAllJudge:
    """A judge that believes everything it is shown."""

    def score(self, pair: Overlap) -> float:
        return 1.0


class ReplayJudge:
    """Recorded verdicts from a JSON file: a list of [source, target, confidence]; what was not recorded is not confirmed."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            self.frozen = {(s, t): float(x) for s, t, x in json.load(f)}

    def score(self, pair: Overlap) -> float:
        return self.frozen.get((pair.source, pair.target), 0.0)


class CallableJudge:
    """Confidence from a function of the user's, for example a language model; it sees names, types and values of both columns."""

    def __init__(self, fn: Callable[[Overlap], float]):
        self.fn = fn

    def score(self, pair: Overlap) -> float:
        return float(self.fn(pair))


JUDGES = {"lexical": LexicalJudge(), "approve_all": ApproveAllJudge()}


@dataclass(frozen=True)
class JoinPolicy:
    """ambiguous: drop (default), ask, or exempt_named (keep a fully contained source whose name fits); overlap: any, or the
    least containment that counts as overlap; the guards can be switched off for the comparison arms. judge: a name of JUDGES or an
    object with ``score``."""

    ambiguous: str = "drop"
    containment: float = 0.0
    min_targets: int = 3
    guards: bool = True
    judge: object = "lexical"


def by_name(columns: list[tuple[str, str]], keys: list[str]) -> list[tuple[str, str, float]]:
    """(source, target, score) of the pairs that names alone suggest."""
    scored = ((f"{t}.{c}", k, name_affinity(c, *k.split("."))) for t, c in columns for k in keys if k.split(".")[0] != t)
    return [x for x in scored if x[2] >= TAU]


def target_counts(overlap: DataFrame, containment: float = 0.0) -> DataFrame:
    """How many keys of different tables each source overlaps, on the raw overlaps."""
    live = overlap.where(F.col("n_common") >= containment * F.col("n_source"))
    return live.groupBy("source").agg(F.countDistinct("target").alias("n_targets"))


def decide(overlap: list[Overlap], keys: list[str], measures: list[str], policy: JoinPolicy = JoinPolicy()) -> list[tuple[Overlap, float, str]]:
    """(pair, score, stage): the stage at which a candidate falls, or ``accepted``. The count of targets is taken before any guard;
    a judge is asked about every pair that is left, in a fixed order."""
    judge = JUDGES.get(policy.judge, policy.judge) if isinstance(policy.judge, str) else policy.judge
    targets: dict[str, set] = defaultdict(set)
    for o in overlap:
        if o.n_common >= policy.containment * o.n_source:
            targets[o.source].add(o.target)
    is_key, is_measure, out = set(keys), set(measures), []
    for o in sorted(overlap, key=lambda o: (o.source, o.target)):
        score = judge.score(o)
        stage = "accepted" if score >= TAU else "judge"
        if policy.guards:
            named = policy.ambiguous == "exempt_named" and score >= 0.9 and o.n_common == o.n_source
            if o.source in is_key:
                stage = "source_is_key"
            elif o.source in is_measure:
                stage = "measure"
            elif len(targets[o.source]) >= policy.min_targets and not named:
                stage = "ask" if policy.ambiguous == "ask" else "ambiguous"
        out.append((o, score, stage))
    if policy.guards:
        taken: set[str] = set()
        for k in sorted((k for k, x in enumerate(out) if x[2] == "accepted"), key=lambda k: (out[k][0].source, -out[k][1], -out[k][0].n_common, out[k][0].target)):
            o, score, _ = out[k]
            if o.source in taken:
                out[k] = (o, score, "second_referent")
            taken.add(o.source)
    return out


def ledger(overlap: DataFrame, keys: list[str], measures: list[str], policy: JoinPolicy = JoinPolicy()) -> DataFrame:
    """``decide`` on a table of overlaps: (source, target, n_common, n_source, score, stage)."""
    rows = [Overlap(r["source"], r["target"], r["n_common"], r["n_source"]) for r in overlap.select("source", "target", "n_common", "n_source").collect()]
    return as_table(overlap.sparkSession, decide(rows, keys, measures, policy))


def as_table(spark, decisions: list[tuple[Overlap, float, str]]) -> DataFrame:
    return spark.createDataFrame([(o.source, o.target, o.n_common, o.n_source, float(x), s) for o, x, s in decisions], "source string, target string, n_common long, n_source long, score double, stage string")


def overlaps(bundle: SourceBundle, keys: list[str], columns: list[tuple[str, str]] | None = None) -> DataFrame:
    return domains.overlap_by_masks(bundle, columns or domains.integer_columns(bundle), keys)


def multiplicity(bundle: SourceBundle, joins: list[tuple[str, str, str, str]]) -> DataFrame:
    """(join_id, max_per_key, kind): the most source rows of one key, and whether the target is unique."""
    out = []
    for ft, fc, tt, tc in joins:
        a = bundle[ft].where(F.col(fc).isNotNull()).groupBy(fc).count().agg(F.max("count").alias("max_per_key"))
        b = bundle[tt].where(F.col(tc).isNotNull()).groupBy(tc).count().agg(F.max("count").alias("target_max"))
        kind = F.when(F.col("target_max") > 1, "m:m").when(F.col("max_per_key") > 1, "m:1").otherwise("1:1")
        out.append(a.crossJoin(b).select(F.lit(f"{ft}.{fc}->{tt}.{tc}").alias("join_id"), "max_per_key", kind.alias("kind")))  # one row each
    from semcat.operators.profile import union_all

    return union_all(out)


def orphans(bundle: SourceBundle, joins: list[tuple[str, str, str, str]]) -> DataFrame:
    """(join_id, n_orphans, n_childless): source rows without target, target rows without source."""
    from semcat.operators.profile import union_all

    out = []
    for ft, fc, tt, tc in joins:
        s, t = bundle[ft].select(F.col(fc).cast("string").alias("k")), bundle[tt].select(F.col(tc).cast("string").alias("k"))
        a = s.join(t, "k", "left_anti").agg(F.count("*").alias("n_orphans"))
        b = t.join(s, "k", "left_anti").agg(F.count("*").alias("n_childless"))
        out.append(a.crossJoin(b).select(F.lit(f"{ft}.{fc}->{tt}.{tc}").alias("join_id"), "n_orphans", "n_childless"))
    return union_all(out)
