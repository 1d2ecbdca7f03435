"""Visible word lists and name rules of the offline proposer and judge. The lists are general: no table's columns are named."""

from __future__ import annotations

import re

#: Words of column names that speak for identifiers, measures, times and flags.
ID_WORDS = {"id", "key", "code", "no", "nr"}
MEASURE_WORDS = set("price cost amount amt total subtotal balance bal quantity qty discount tax fee size weight height width length depth area volume value revenue income sales profit salary wage budget score rating rate ratio percent pct avg average mean sum count cnt min max duration distance speed temperature age population".split())
TIME_WORDS = {"date", "ts", "time", "timestamp", "month", "day", "year", "at", "dt"}
FLAG_WORDS = {"flag", "is", "has", "active", "enabled", "deleted"}
#: Abbreviations, and last parts that are split from a compound written as one word.
EXPAND = {"acct": "account", "addr": "address", "amt": "amount", "avg": "average", "bal": "balance", "cat": "category", "cd": "code", "chars": "characters", "cnt": "count", "cont": "containment", "conv": "conversation", "cust": "customer", "dept": "department", "desc": "description", "doc": "document", "dt": "date", "emp": "employee", "lang": "language", "max": "maximum", "min": "minimum", "mkt": "market", "n": "number of", "num": "number", "org": "organisation", "pct": "percent", "prod": "product", "props": "properties", "qty": "quantity", "supp": "supplier", "tel": "telephone", "ts": "timestamp", "vec": "vector"}
LAST_PARTS = "key id code price cost date name number status priority flag segment type size balance bal total qty amount time rate".split()
WHOLE = set("valid invalid paid unpaid void avoid grid solid fluid liquid rapid hybrid candidate mandate validate surname update subtotal runtime lifetime".split())
TECHNICAL = {"migration", "migrations", "log", "logs", "audit", "tmp", "temp", "backup", "schema"}


def _split(word: str) -> list[str]:
    """A compound of two words written as one, where its last part is known and at least three letters stand before it."""
    if word not in WHOLE:
        for last in LAST_PARTS:
            if word.endswith(last) and len(word) >= len(last) + 3:
                return [word[: -len(last)], last]
    return [word]


def words(column: str) -> list[str]:
    """Name tokens. A one-letter prefix is dropped, unless it is the n of a number of things (n before a plural)."""
    parts = [p for p in re.split(r"[^a-z0-9]+", re.sub(r"(?<=[a-z0-9])(?=[A-Z])", "_", column).lower()) if p]
    if len(parts) > 1 and len(parts[0]) == 1 and not (parts[0] == "n" and parts[-1].endswith("s")):
        parts = parts[1:]
    return [w for p in parts for w in _split(p)] or [column.lower()]


def stem(column: str) -> str:
    """What a key-like name names: buyerkey is buyer, user_id is user; empty for other names."""
    w = words(column)
    return "".join(w[:-1]) if w[-1] in ("key", "id") else ""


def id_like(column: str, table: str = "") -> bool:
    return words(column)[-1] in ID_WORDS


def measure_like(column: str) -> bool:
    """Whether the name speaks for a measure: its last word, or a number of things."""
    w = words(column)
    return w[-1] in MEASURE_WORDS or (w[0] == "n" and len(w) > 1)


def own_key(column: str, table: str) -> bool:
    """Whether a key-like name names the table's own rows."""
    s = stem(column)
    return id_like(column) and (not s or fits(s, table))


def singular(table: str) -> str:
    return table[:-3] + "y" if table.endswith("ies") else table[:-1] if table.endswith("s") else table


def fits(stem_: str, table: str) -> bool:
    """Whether a stem is the table's name or the beginning of it (three letters at least), abbreviations spelled out."""
    name = singular(table).replace("_", "")
    return any(name == s or len(s) >= 3 and name.startswith(s) for s in {stem_, EXPAND.get(stem_, stem_)})


def name_affinity(source: str, target_table: str, target: str) -> float:
    """How well a source column's name fits a target key: 1 same stem, 0.9 the stem ends in the key's (home_team_id and
    team_id), 0.8 the stem fits the table's name, else 0."""
    a, b = stem(source), stem(target)
    if not a:
        return 0.0
    if a == b:
        return 1.0
    if b and len(b) >= 3 and a.endswith(b):
        return 0.9
    return 0.8 if fits(a, target_table) else 0.0


def label(column: str) -> str:
    """A label for people: abbreviations spelled out, first letters large."""
    return " ".join(EXPAND.get(w, w) for w in words(column)).title()


def machine_name(column: str) -> str:
    return "_".join(" ".join(EXPAND.get(w, w) for w in words(column)).split())


def remote_name(table: str, column: str) -> str:
    """A short name of an attribute that a join brings in: the other entity, and the words that do not repeat it."""
    entity = singular(table)
    return "_".join([entity, *[x for x in machine_name(column).split("_") if x != entity]])


def deduplicated(names: list[tuple[str, str, str]]) -> list[str]:
    """Names of (name, table, column) made unique, in their order: a repeated name is qualified by its table, then by its column,
    then by a number."""
    out = [n for n, _, _ in names]
    for qualify in (lambda i: f"{names[i][1]}_{names[i][0]}", lambda i: f"{names[i][1]}_{names[i][2]}"):
        again = {n for n in out if out.count(n) > 1}
        out = [qualify(i) if n in again else n for i, n in enumerate(out)]
    seen: dict[str, int] = {}
    for i, n in enumerate(out):
        seen[n] = seen.get(n, 0) + 1
        if seen[n] > 1:
            out[i] = f"{n}_{seen[n]}"
    return out
