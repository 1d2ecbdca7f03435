"""The builder: propose, then verify; proposers and judges are pluggable and the default is offline and deterministic.

``examine`` runs every job on the data: evidence of all columns, identifiers, and one overlap of all columns with all keys.
``assemble`` makes a catalog of it without reading data again, so an answered question or another policy costs no scan.
"""

from __future__ import annotations

import json
import random
import re
from collections.abc import Callable
from dataclasses import dataclass, field

from semcat.operators import domains, evidence, joins, keys, together
from semcat.operators.evidence import ColumnEvidence
from semcat.operators.profile import inventory
from semcat.operators.typing_rules import LICENCES, symbolic_role
from semcat.plans.graph import JoinGraph, direction
from semcat.plans.lexicon import TECHNICAL, deduplicated, label, machine_name, remote_name, singular, words
from semcat.plans.model import Aggregable, Attribute, Catalog, Entity, placeholders
from semcat.sources.bundle import SourceBundle

LOOKUP_ROWS = 64


@dataclass
class Proposal:
    """Entities with a table each, attributes (table, column, role), and joins (table, column, table, column). A table or column may
    be a phrase instead of a name; grounding looks for what it means."""

    entities: list[tuple[str, str]] = field(default_factory=list)
    attributes: list[tuple[str, str, str]] = field(default_factory=list)
    joins: list[tuple[str, str, str, str]] = field(default_factory=list)


class LexicalProposer:
    """Tables become entities, columns attributes; a description only raises the tables it names to the front."""

    def propose(self, description: str | None, rows: list[tuple[str, str, str]], roles: dict) -> Proposal:
        said = set((description or "").lower().split())
        tables = sorted({t for t, _, _ in rows}, key=lambda t: (singular(t) not in said and t not in said, [r[0] for r in rows].index(t)))
        return Proposal([(singular(t), t) for t in tables], [(t, c, roles[t][c]) for t, c, _ in rows])


class NullProposer:
    """No semantics: roles by storage alone."""

    def propose(self, description, rows, roles) -> Proposal:
        return Proposal([(t, t) for t in dict.fromkeys(r[0] for r in rows)], [(t, c, symbolic_role(k)) for t, c, k in rows])


class ReplayProposer:
    """A recorded proposal from a JSON file."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            self.frozen = json.load(f)

    def propose(self, description, rows, roles) -> Proposal:
        return Proposal(*[[tuple(x) for x in self.frozen.get(k, [])] for k in ("entities", "attributes", "joins")])


class FaultyProposer:
    """Another proposer's output with seeded errors: unknown tables and columns, wrong roles, unrelated joins."""

    def __init__(self, base, seed: int = 1, rate: float = 0.3):
        self.base, self.seed, self.rate = base, seed, rate

    def propose(self, description, rows, roles) -> Proposal:
        p, rng = self.base.propose(description, rows, roles), random.Random(self.seed)
        p.entities.append(("phantom", "phantom_table"))
        out = []
        for t, c, r in p.attributes:
            x = rng.random()
            out.append((t, c + "_made_up", r) if x < self.rate / 2 else (t, c, "Numeric") if x < self.rate else (t, c, r))
        pairs = [(rng.choice(out), rng.choice(out)) for _ in range(int(self.rate * 10))]
        return Proposal(p.entities, out, p.joins + [(a[0], a[1], b[0], b[1]) for a, b in pairs])


class CallableProposer:
    """A proposal from a function of the user's, for example a language model."""

    def __init__(self, fn: Callable[[str | None, list], Proposal]):
        self.fn = fn

    def propose(self, description, rows, roles) -> Proposal:
        return self.fn(description, rows)


def reject_unknown(p: Proposal, rows: list[tuple[str, str, str]]) -> tuple[Proposal, list[tuple[str, str]]]:
    """Drop references to tables and columns that do not exist: (accepted, rejected with reason)."""
    tables, cols = {r[0] for r in rows}, {(r[0], r[1]) for r in rows}
    known = lambda j: {(j[0], j[1]), (j[2], j[3])} <= cols
    bad = [(f"{e}@{t}", "unknown table") for e, t in p.entities if t not in tables] + [(f"{t}.{c}", "unknown column") for t, c, _ in p.attributes if (t, c) not in cols]
    bad += [(f"{j[0]}.{j[1]}->{j[2]}.{j[3]}", "unknown column") for j in p.joins if not known(j)]
    return Proposal([x for x in p.entities if x[1] in tables], [x for x in p.attributes if (x[0], x[1]) in cols], [j for j in p.joins if known(j)]), bad


def merge_same_table(entities: list[tuple[str, str]]) -> list[tuple[str, str, list[str]]]:
    """(table, name, merged names): concepts grounded on one table become one entity, named by what a row is."""
    by: dict[str, list[str]] = {}
    for e, t in entities:
        by.setdefault(t, []).append(e)
    return [(t, singular(t), sorted(names)) for t, names in sorted(by.items())]


def match_entities(concepts: list[str], tables: list[str]) -> list[tuple[str, str, float]]:
    """(concept, table, score) by shared tokens of names; the best table of each concept that shares one."""
    out = []
    for c in concepts:
        w = set(c.lower().replace("_", " ").split())
        score = [(len(w & {singular(t), *words(t)}) / len(w | {singular(t)}), t) for t in tables]
        best = max(score, key=lambda x: (x[0], x[1]))
        if best[0] > 0:
            out.append((c, best[1], round(best[0], 6)))
    return out


def match_attributes(concepts: list[tuple[str, str | None, tuple[str, ...]]], columns: dict[str, ColumnEvidence]) -> list[tuple[str, list[str], float]]:
    """(concept, columns, score) for concepts (phrase, storage or None, sample values): names weigh most, a wrong storage rules a
    column out, and a sample that the column's range of values can hold adds a little. All columns of the best score are
    returned, as an attribute may be spread over several; more than one of them is a question."""
    out = []
    for phrase, isa, seen in concepts:
        w, scored = set(words(phrase.replace(" ", "_"))), []
        for c, e in columns.items():
            if isa and e.isa != isa and {isa, e.isa} != {"integer", "float"}:
                continue
            own = {x for x in words(c)} | set(machine_name(c).split("_"))
            name = len(w & own) / len(w | set(words(c))) if w & own else 0.0
            holds = e.least is not None and any(_within(x, e) for x in seen)
            scored.append((round(name + 0.1 * holds, 6), c))
        best = max((x for x, _ in scored), default=0.0)
        if best > 0.1:
            out.append((phrase, [c for x, c in scored if x == best], best))
    return out


def _within(value: str, e: ColumnEvidence) -> bool:
    """Whether a sample lies within a column's range, as numbers where the column holds numbers."""
    try:
        return float(e.least) <= float(value) <= float(e.greatest) if e.family in ("integer", "float") else e.least <= value <= e.greatest
    except ValueError:
        return False


def rename_to_row_meaning(name: str, table: str, has_key: bool) -> tuple[str, str]:
    """(name, reason): a concept that shares no word with a table that has a key of its own is named by what a row of it is."""
    if has_key and not set(words(name.replace(" ", "_"))) & {singular(table), *words(table)}:
        return singular(table), "named by the table's rows"
    return name, "kept"


def ground(p: Proposal, rows: list[tuple[str, str, str]], found: dict[tuple[str, str], ColumnEvidence]) -> tuple[Proposal, dict[str, list[str]]]:
    """Phrases replaced by the tables and columns they mean; (proposal, columns to choose from for open attributes). What
    cannot be grounded stays as it is and is rejected later."""
    tables = list(dict.fromkeys(r[0] for r in rows))
    meant = {c: t for c, t, _ in match_entities([t for _, t in p.entities if t not in tables] + [t for t, _, _ in p.attributes if t not in tables], tables)}
    put = lambda t: meant.get(t, t)
    attributes, open_ = [], {}
    for t, c, r in p.attributes:
        t = put(t)
        if t in tables and (t, c) not in found:
            hit = match_attributes([(c, None, ())], {x: e for (u, x), e in found.items() if u == t})
            if hit and len(hit[0][1]) > 1:
                open_[f"{t}.{c}"] = hit[0][1]
            if hit and hit[0][2] >= 0.5:
                c = hit[0][1][0]
        attributes.append((t, c, r))
    return Proposal([(e, put(t)) for e, t in p.entities], attributes, p.joins), open_


def choose_identifiers(bundle: SourceBundle, found: dict[tuple[str, str], ColumnEvidence] | None = None, roles: dict[str, dict[str, str]] | None = None, facts: keys.Facts | None = None) -> dict[str, tuple[list[str], str]]:
    """Identifier and status of each table; whole numbers whose role the values leave open may order the rows of a composite."""
    found = found or evidence.gather(bundle)
    roles = roles or evidence.roles(found)
    ordinals = {t: tuple(c for c in df.columns if found[t, c].unclear and roles[t][c] == "Categorical") for t, df in bundle.tables.items()}
    return keys.choose_all(bundle, roles, ordinals, found, facts)


def triage(table: str, n_rows: int, columns: list[str], key: tuple[list[str], str], outgoing: int, inbound: int) -> tuple[str, str]:
    """(class, reason) of a table: entity, link, passthrough or ignore; ignoring needs positive evidence."""
    if set(table.split("_")) & TECHNICAL and not inbound and not outgoing:
        return "ignore", "technical name, no joins"
    if outgoing >= 2 and (keys.is_weak(key[1]) or len(key[0]) > 1):
        return "link", "two or more references, no key of its own"
    if n_rows <= LOOKUP_ROWS and len(columns) <= 3 and inbound:
        return "passthrough", "small, referenced, few columns"
    return "entity", "no verified key" if keys.is_weak(key[1]) else "own key"


def reference(entity: str, columns: list[str], key: list[str]) -> str:
    """Label template of one or two attributes: first and last name, or the name column, or the identifier's first two columns."""
    names = [c for c in columns if words(c)[-1] == "name"]
    parts = [next((c for c in names if w in words(c)), None) for w in ("first", "last")]
    if all(parts):
        return f"{{{parts[0]}}} {{{parts[1]}}}"
    return "{" + names[0] + "}" if names else " ".join("{" + k + "}" for k in key[:2])


def validate_reference(template: str, columns: list[str], key: list[str]) -> tuple[str, str]:
    """(template, reason): an empty template or one with unknown placeholders falls back on the identifier."""
    ph = placeholders(template)
    if not ph:
        return "{" + key[0] + "}", "no placeholder"
    if set(ph) - set(columns):
        return "{" + key[0] + "}", "unknown placeholder"
    return template, "valid"


@dataclass
class State:
    """What the data say, gathered once; small enough for the driver."""

    tables: dict[str, list[str]]
    declared: list[tuple[str, str, str, str]]
    evidence: dict[tuple[str, str], ColumnEvidence]
    roles: dict[tuple[str, str], str]
    ids: dict[str, tuple[list[str], str]]
    overlap: list[joins.Overlap]
    names: dict[str, str] = field(default_factory=dict)
    proposed_joins: list[tuple[str, str, str, str]] = field(default_factory=list)
    open_columns: dict[str, list[str]] = field(default_factory=dict)
    rounds: list[list[str]] = field(default_factory=list)
    warnings: list[str] = field(default_factory=list)

    @property
    def keys(self) -> list[str]:
        """Columns that other tables can refer to: verified or declared identifiers of one column."""
        return [f"{t}.{k[0]}" for t, (k, s) in self.ids.items() if len(k) == 1 and not keys.is_weak(s)]

    @property
    def measures(self) -> list[str]:
        return [f"{t}.{c}" for (t, c), r in self.roles.items() if r == "Numeric"]

    def restrict(self, names: list[str]) -> State:
        """The same facts for fewer tables, as if only these had been examined."""
        keep = [t for t in names if t in self.tables]
        inside = lambda q: q.split(".")[0] in keep
        return State({t: self.tables[t] for t in keep}, [f for f in self.declared if f[0] in keep and f[2] in keep], {k: e for k, e in self.evidence.items() if k[0] in keep}, {k: r for k, r in self.roles.items() if k[0] in keep}, {t: self.ids[t] for t in keep}, [o for o in self.overlap if inside(o.source) and inside(o.target)], {t: n for t, n in self.names.items() if t in keep}, [j for j in self.proposed_joins if j[0] in keep and j[2] in keep], {k: v for k, v in self.open_columns.items() if inside(k)}, [[t for t in r if t in keep] for r in self.rounds], self.warnings)

    def decisions(self, policy: joins.JoinPolicy = joins.JoinPolicy()) -> list[tuple[joins.Overlap, float, str]]:
        """The ledger: overlapping pairs with the stage at which they fall, and what was proposed or suggested by names without a
        common value."""
        met = {(o.source, o.target) for o in self.overlap}
        suggested = {(f"{j[0]}.{j[1]}", f"{j[2]}.{j[3]}") for j in self.proposed_joins} | {(a, b) for a, b, _ in joins.by_name(list(self.evidence), self.keys)}
        none = [(joins.Overlap(a, b, 0, 0), 0.0, "no_overlap") for a, b in sorted(suggested - met) if a.split(".")[0] != b.split(".")[0]]
        return joins.decide(self.overlap, self.keys, self.measures, policy) + none


def examine(bundle: SourceBundle, description: str | None = None, proposer=None, known: list | None = None) -> State:
    """All jobs on the data. Tables that the proposal leaves out are swept afterwards, round by round, until none is left; a swept
    table gets an identifier too, so that others can refer to it. ``known`` holds bundles and their evidence from the same snapshot."""
    state = _identify(bundle, evidence.gather(bundle, known), description, proposer)
    if len(bundle.tables) > 1 and state.keys:
        met = joins.overlaps(bundle, state.keys, domains.joinable(state.evidence)).collect()
        _meet(state, [(r["source"], r["target"], r["n_common"], r["n_source"]) for r in met])
    return state


def examine_together(base: SourceBundle, readings: list[together.Reading]) -> list[State]:
    """``examine`` for several readings of the same tables, from the distinct values of these."""
    if not together.fits(base):
        return [examine(r.bundle) for r in readings]
    values = together.Together(base, readings)
    try:
        states = []
        for r, found in zip(readings, values.gather(), strict=True):
            values.facts.as_is = not r.text
            states.append(_identify(r.bundle, found, facts=values.facts))
        wanted = [(domains.joinable(s.evidence), s.keys) if len(s.tables) > 1 and s.keys else ([], []) for s in states]
        for state, met in zip(states, values.overlaps(wanted), strict=True):
            _meet(state, met)
    finally:
        values.close()
    return states


def _meet(state: State, met: list[tuple[str, str, int, int]]) -> None:
    at = lambda q: state.evidence[tuple(q.split(".", 1))]
    state.overlap = [joins.Overlap(*r, at(r[0]), at(r[1])) for r in met]


def _identify(bundle: SourceBundle, found: dict[tuple[str, str], ColumnEvidence], description: str | None = None, proposer=None, facts: keys.Facts | None = None) -> State:
    """The state of a bundle by its evidence, with identifiers and without overlaps."""
    rows = inventory(bundle)
    own = evidence.roles(found)
    proposal, open_ = ground((proposer or LexicalProposer()).propose(description, rows, own), rows, found)
    proposal, rejected = reject_unknown(proposal, rows)
    given = {(t, c): r for t, c, r in proposal.attributes}
    roles = {}
    for (t, c), e in found.items():  # a proposed role stands where the values support it; swept columns get the rules' role
        r = given.get((t, c), e.role)
        roles[t, c] = r if e.supports(r) and e.family != "opaque" else "Opaque" if e.family == "opaque" else "Categorical"
    by_table = {t: {c: roles[t, c] for c in df.columns} for t, df in bundle.tables.items()}
    named = merge_same_table(proposal.entities)
    ids: dict[str, tuple[list[str], str]] = {}
    rounds: list[list[str]] = []
    todo = [t for t, _, _ in named] or list(bundle.tables)
    while todo:
        part = bundle.scope(todo)
        ids |= choose_identifiers(part, found, by_table, facts)
        rounds.append(todo)
        todo = [t for t in bundle.tables if t not in ids]
    ids = {t: ids[t] for t in bundle.tables}
    state = State({t: df.columns for t, df in bundle.tables.items()}, [tuple(f) for f in bundle.foreign], found, roles, ids, [], {}, proposal.joins, open_, rounds, [f"{x}: {why}" for x, why in rejected])
    state.warnings += [f"{t}: {s}" for t, (_, s) in ids.items() if s == "fallback, budget spent"]
    for t, name, merged in named:
        state.names[t] = name if len(merged) > 1 else rename_to_row_meaning(merged[0], t, not keys.is_weak(ids[t][1]))[0]
    return state


def _value_label(c: str, e: ColumnEvidence) -> str:
    """A label; one that the values contradict is made from them: details that are all names of one kind are that kind's name."""
    kind = re.match(r"([A-Za-z]+)#[0-9]", e.least or "")
    if kind and e.family == "text" and (e.greatest or "").startswith(kind[1] + "#") and words(c)[-1] in ("name", "details", "detail", "info", "description"):
        return f"{kind[1].title()} Name"
    return label(c)


def assemble(state: State, policy: joins.JoinPolicy = joins.JoinPolicy(), answers: dict[str, str] | None = None, max_hops: int = 3) -> Catalog:
    """The catalog. Answers (question id to answer) go through the same checks; unanswered questions take defaults."""
    answers, found, columns = answers or {}, state.evidence, state.tables
    questions: list[dict] = []

    def ask(qid: str, kind: str, text: str, choices: list[str], default: str) -> str:
        answer = answers.get(qid, default)
        by = "user" if qid in answers else "default"
        if answer not in choices:
            answer, by = default, "default"
        questions.append({"id": qid, "kind": kind, "text": text, "choices": choices, "answer": answer, "answered_by": by})
        return answer

    roles = dict(state.roles)
    for (t, c), e in found.items():
        if e.unclear and roles[t, c] == "Categorical" and f"{t}.{c}" not in state.keys:
            r = ask(f"type:{t}.{c}", "type", f"Is {label(c)} of {singular(t)} ({e.description or 'no values'}) an amount to add up, or a code to group by?", ["Categorical", "Numeric"], "Categorical")
            roles[t, c] = r if e.supports(r) else "Categorical"
    for q, among in sorted(state.open_columns.items()):
        ask(f"column:{q}", "column", f"Which column holds {q.split('.', 1)[1]} of {singular(q.split('.')[0])}: {' or '.join(among)}?", among, among[0])
    measures = [f"{t}.{c}" for (t, c), r in roles.items() if r == "Numeric"]
    accepted = list(state.declared)
    taken = {(a, b) for a, b, _, _ in accepted}
    wanted = {tuple(j) for j in state.proposed_joins}
    for o, _, stage in joins.decide(state.overlap, state.keys, measures, policy):
        j = (*o.source.split(".", 1), *o.target.split(".", 1))
        if state.declared and j not in wanted or (j[0], j[1]) in taken:
            continue
        if stage == "ask":
            e = o.source_evidence
            says = ask(f"join:{o.source}->{o.target}", "referent", f"Does {o.source} ({e.description if e else ''}) refer to {singular(j[2])}? {o.n_common} of its {o.n_source} values are keys there.", ["no", "yes"], "no")
            stage = "accepted" if says == "yes" and policy.ambiguous == "ask" else stage
        if stage == "accepted":
            accepted.append(j)
            taken.add((j[0], j[1]))
    out = Catalog(source={"tables": sorted(columns), "rounds": state.rounds}, joins=[{"from_table": a, "from_col": b, "to_table": c, "to_col": d} for a, b, c, d in accepted], warnings=list(state.warnings))
    graph, classes = JoinGraph(accepted), {}
    for t in columns:
        n = next((e.n_rows for (u, _), e in found.items() if u == t), 0)
        kind, why = triage(t, n, columns[t], state.ids[t], sum(j[0] == t for j in accepted), sum(j[2] == t for j in accepted))
        if kind in ("passthrough", "link"):
            ends = " and ".join(sorted({singular(j[2]) for j in accepted if j[0] == t})) or "others"
            asks = f"Is {t} a lookup table, or are its rows things to analyse?" if kind == "passthrough" else f"Is {t} a standalone entity, or a junction between {ends}?"
            kind = ask(f"table:{t}", "table role", asks, ["entity", kind], kind if keys.is_weak(state.ids[t][1]) else "entity")
        classes[t] = (kind, why)
    out.ignored = [{"table": t, "reason": why} for t, (k, why) in classes.items() if k == "ignore"]
    out.links = [t for t, (k, _) in classes.items() if k == "link"]
    out.lookups = [t for t, (k, _) in classes.items() if k == "passthrough"]
    tag = lambda u, c: [roles[u, c]] + (["Metric"] if roles[u, c] == "Numeric" else [])
    for t in (t for t, (k, _) in classes.items() if k == "entity"):
        key, status = state.ids[t]
        e = Entity(state.names.get(t, singular(t)), t, key, status, validate_reference(reference(t, columns[t], key), columns[t], key)[0])
        paths = [p for p in graph.paths(t, max_hops) if classes[p[-1].far][0] != "ignore"]
        remote = [(p, c) for p in sorted(paths, key=lambda p: (p[-1].far, len(p))) for c in columns[p[-1].far]]
        via = lambda p: f"{singular(p[-1].far)}_via_{'_'.join(singular(s.far) for s in p[:-1])}" if len(p) > 1 else singular(p[-1].far)
        names = deduplicated([(machine_name(c), singular(t), c) for c in columns[t]] + [(remote_name(p[-1].far, c), via(p), c) for p, c in remote])
        e.attributes = [Attribute(n, t, [c], found[t, c].isa, tag(t, c), _value_label(c, found[t, c]), found[t, c].description) for n, c in zip(names, columns[t])]
        e.aggregables = [Aggregable(n, p[-1].far, [c], [s.text() for s in p], direction(p), tag(p[-1].far, c)) for n, (p, c) in zip(names[len(columns[t]) :], remote)]
        out.entities.append(e)
    out.questions = questions
    return out


def build(bundle: SourceBundle, description: str | None = None, proposer=None, policy: joins.JoinPolicy = joins.JoinPolicy(), answers: dict[str, str] | None = None, max_hops: int = 3) -> Catalog:
    """The whole build."""
    return assemble(examine(bundle, description, proposer), policy, answers, max_hops)


def converse(state: State, answerer: Callable[[dict], str | None], policy: joins.JoinPolicy = joins.JoinPolicy(), max_rounds: int = 10) -> tuple[Catalog, list[list[str]]]:
    """(catalog, ids asked in each round): questions are put to the answerer, answers are built in, and what they open is asked
    in the next round, until nothing new is asked. An answerer that returns None takes the default."""
    answers: dict[str, str] = {}
    asked: list[list[str]] = []
    seen: set[str] = set()
    for _ in range(max_rounds):
        c = assemble(state, policy, answers)
        fresh = [q for q in c.questions if q["id"] not in seen]
        if not fresh:
            break
        asked.append([q["id"] for q in fresh])
        seen |= {q["id"] for q in fresh}
        answers |= {q["id"]: a for q in fresh if (a := answerer(q)) is not None}
    return assemble(state, policy, answers), asked


def licence(roles: list[str]) -> set[str]:
    return {x for r in roles for x in LICENCES.get(r, "").split("|") if x}
