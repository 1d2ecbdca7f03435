"""The analytic catalog: entities, attributes, joins, remote attributes and labels, as plain data with a JSON form."""

from __future__ import annotations

import json
import re
from dataclasses import asdict, dataclass, field


@dataclass
class Attribute:
    name: str
    src_table: str
    src_cols: list[str]
    isa: str
    roles: list[str]
    nicename: str
    description: str = ""


@dataclass
class Aggregable:
    name: str
    src_table: str
    src_cols: list[str]
    path: list[str]
    direction: str
    roles: list[str]


@dataclass
class Entity:
    name: str
    table: str
    id_columns: list[str]
    id_status: str
    reference: str
    attributes: list[Attribute] = field(default_factory=list)
    aggregables: list[Aggregable] = field(default_factory=list)


@dataclass
class Catalog:
    entities: list[Entity] = field(default_factory=list)
    joins: list[dict] = field(default_factory=list)
    lookups: list[str] = field(default_factory=list)
    links: list[str] = field(default_factory=list)
    ignored: list[dict] = field(default_factory=list)
    questions: list[dict] = field(default_factory=list)
    warnings: list[str] = field(default_factory=list)
    source: dict = field(default_factory=dict)
    catalog_version: str = "1"


def dump(c: Catalog) -> str:
    return json.dumps(asdict(c), indent=1, sort_keys=True)


def load(text: str) -> Catalog:
    d = json.loads(text)
    d["entities"] = [Entity(**e | {"attributes": [Attribute(**a) for a in e["attributes"]], "aggregables": [Aggregable(**a) for a in e["aggregables"]]}) for e in d["entities"]]
    return Catalog(**d)


#: What each part of the JSON form must hold.
SCHEMA = {
    "entities": {"name": str, "table": str, "id_columns": list, "id_status": str, "reference": str, "attributes": list, "aggregables": list},
    "joins": {"from_table": str, "from_col": str, "to_table": str, "to_col": str},
    "questions": {"id": str, "kind": str, "text": str, "choices": list, "answer": str, "answered_by": str},
    "ignored": {"table": str, "reason": str},
    "attributes": {"name": str, "src_table": str, "src_cols": list, "isa": str, "roles": list, "nicename": str, "description": str},
    "aggregables": {"name": str, "src_table": str, "src_cols": list, "path": list, "direction": str, "roles": list},
}
ISAS, ROLES = {"string", "integer", "float", "date", "datetime", "boolean", "array"}, {"Categorical", "Datetime", "Numeric", "Metric", "Opaque"}


def validate(text: str) -> list[str]:
    """What is wrong with a catalog's JSON: missing or mistyped fields, unknown storage types, roles and directions, names used
    twice in an entity, and entities of one table. An empty list means that it is well formed."""
    d, out = json.loads(text), []

    def check(kind: str, item: dict, at: str) -> None:
        for k, t in SCHEMA[kind].items():
            if not isinstance(item.get(k), t):
                out.append(f"{at}.{k}: {t.__name__} expected")
        if kind in ("attributes", "aggregables"):
            out.extend(f"{at}: unknown role {r}" for r in item.get("roles", []) if r not in ROLES)
        if kind == "attributes" and item.get("isa") not in ISAS:
            out.append(f"{at}: unknown storage {item.get('isa')}")
        if kind == "aggregables" and item.get("direction") not in ("many_to_one", "one_to_many"):
            out.append(f"{at}: unknown direction {item.get('direction')}")

    for kind in ("entities", "joins", "questions", "ignored"):
        for i, item in enumerate(d.get(kind, [])):
            check(kind, item, f"{kind}[{i}]")
    tables = [e.get("table") for e in d.get("entities", [])]
    out += [f"two entities of {t}" for t in sorted({t for t in tables if tables.count(t) > 1})]
    for i, e in enumerate(d.get("entities", [])):
        names = []
        for kind in ("attributes", "aggregables"):
            for j, item in enumerate(e.get(kind, [])):
                check(kind, item, f"entities[{i}].{kind}[{j}]")
                names.append(item.get("name"))
        out += [f"entities[{i}]: {n} twice" for n in sorted({n for n in names if names.count(n) > 1})]
    return out


def placeholders(template: str) -> list[str]:
    return re.findall(r"\{([^{}]+)\}", template)
