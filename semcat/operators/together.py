"""Several readings of the same tables (as they are, as text, as text under prefixes) examined together: each column is brought to its
distinct values once, as it is stored, and evidence, single keys and overlaps of all readings follow from these and their counts."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from semcat.functions.shipping import ship
from semcat.operators import domains, evidence, hashed, keys
from semcat.operators.evidence import CLASSES, ColumnEvidence
from semcat.operators.profile import union_all
from semcat.sources.bundle import SourceBundle

WHOLE, REAL = ("tinyint", "smallint", "int", "bigint"), ("float", "double")
#: Types whose values are brought together as packed 64-bit integers.
PACKED = (*WHOLE, *REAL, "date", "timestamp")
#: Types whose text tells the same values apart as they do.
SAME = (*WHOLE, "string", "boolean", "date")
#: A longer text is kept as its head, its length and two hashes; a worker examines so many values at a time; values of a bucket of the overlap.
LONG, ROWS, BUCKET = 64, 1 << 18, 1 << 19


def _quoted(c: str) -> str:
    return "`" + c.replace("`", "``") + "`"


@dataclass
class Reading:
    """A way to read the tables: as they are or as text, and the prefixes that text columns get. ``bundle`` holds the tables read so."""

    bundle: SourceBundle
    text: bool = False
    prefix: dict[str, str] = field(default_factory=dict)

    def of(self, column: str) -> str | None:
        """The prefix of a column's text, or None for a column read as it is."""
        return self.prefix.get(column, "") if self.text else None


def fits(base: SourceBundle) -> bool:
    """Whether all types are known to be read here as each reading would read them on its own."""
    kinds = (f.dataType.simpleString() for df in base.tables.values() for f in df.schema.fields)
    return all(k in (*SAME, *REAL, "timestamp", "timestamp_ntz") or k.startswith(("decimal", "array", "struct", "map")) for k in kinds)


class _Values(evidence._Column):
    """What a task has seen of a column's distinct values; ``d`` counts them instead of a sketch, as no value comes twice."""

    def __init__(self, kind: str):
        super().__init__(kind)
        self.distinct = 0

    def see(self, v: pa.Array, w: np.ndarray) -> None:
        self.rows, self.n, self.distinct = self.rows + int(w.sum()), self.n + int(w.sum()), self.distinct + len(v)
        if self.mode == "text":
            self.texts(v, w)
        elif self.mode == "real":
            x = v.to_numpy(zero_copy_only=False).astype(float) + 0.0  # one zero
            self.k[CLASSES.index("num")] += int(w.sum())
            numbers = x[~np.isnan(x)]
            self._range(float(numbers.min()) if len(numbers) else float("nan"), float(x.max()))  # NaN is the greatest
        else:
            x = v.to_numpy()
            self.k[CLASSES.index("int")] += int(w.sum())
            self._range(int(x.min()), int(x.max()))
            for d in (0, 1):
                some = int(w[x == d].sum())
                self.u += some
                self.truth |= {str(d)} if some else set()

    def see_long(self, heads: pa.Array, sizes: np.ndarray, json: np.ndarray, w: np.ndarray) -> None:
        """Texts of more than LONG characters."""
        self.rows, self.n, self.distinct = self.rows + int(w.sum()), self.n + int(w.sum()), self.distinct + len(heads)
        self.length += int((sizes * w).sum())
        self._range(*pc.min_max(heads).as_py().values())
        self.k[CLASSES.index("json")] += int(w[json].sum())
        self.k[CLASSES.index("other")] += int(w[~json].sum())

    def merge(self, r: dict) -> None:
        self.distinct += int.from_bytes(r["d"], "little")
        super().merge(r | {"d": self.registers.tobytes()})

    def row(self, t: str, c: str) -> dict:
        return super().row(t, c) | {"d": self.distinct.to_bytes(8, "little")}


class Together:
    """The distinct values of all columns of ``base``, kept while its readings are examined. Nested columns are left to each reading."""

    def __init__(self, base: SourceBundle, readings: list[Reading]):
        self.base, self.readings = base, readings
        self.kinds = {(t, f.name): f.dataType.simpleString() for t, df in base.tables.items() for f in df.schema.fields}
        self.flat = [k for k, kind in self.kinds.items() if evidence._mode(kind) != "deep"]
        self.at = {k: i for i, k in enumerate(self.flat)}
        packed, rows = self._packed([k for k in self.flat if self.kinds[k] in PACKED]), self._rows([k for k in self.flat if self.kinds[k] not in PACKED])
        self.kept = [x.persist(StorageLevel.MEMORY_AND_DISK) for x in (packed, *rows.values()) if x is not None]
        whole, others = [], []
        for kind in dict.fromkeys(self.kinds[k] for k in self.flat):
            found = packed.where(F.col("at").isin([self.at[k] for k in self.flat if self.kinds[k] == kind])) if kind in PACKED else rows[kind]
            (whole if kind in WHOLE else others).append(found.selectExpr("at", "n", *self._finish(kind)))
        #: (at, n, v) of whole numbers, and (at, n, real, v, size, json, a, b) of other columns.
        self.values = [union_all(x) for x in (whole, others) if x]
        self.n_values = 0
        self.facts = keys.Facts({k for k in self.flat if self.kinds[k] in SAME})

    def close(self) -> None:
        for x in self.kept:
            x.unpersist()

    def _packed(self, cols: list[tuple[str, str]]) -> DataFrame | None:
        """(at, n, v, x): the distinct values of columns of 64 bits and how often each occurs, nulls included, from one scan of each table
        and one shuffle of packed integers."""
        cut = {"date": "CAST(unix_date({}) AS LONG)", "timestamp": "unix_micros({})", **dict.fromkeys(WHOLE, "CAST({} AS LONG)"), **dict.fromkeys(REAL, "CAST({} AS DOUBLE)")}
        by: dict[str, list[str]] = {}
        for t, c in cols:
            by.setdefault(t, []).append(c)
        frames = {t: self.base[t].selectExpr(*[cut[self.kinds[t, c]].format(_quoted(c)) + f" AS c{self.at[t, c]}" for c in of]) for t, of in by.items()}
        if not by:
            return None
        bits = hashed.bits_for(frames.values())
        return hashed.merge_counts(union_all([hashed.pack_counts(frames[t], [self.at[t, c] for c in of], bits) for t, of in by.items()]), [self.at[k] for k in cols if self.kinds[k] in REAL])

    def _rows(self, cols: list[tuple[str, str]]) -> dict[str, DataFrame]:
        """The same for columns of other types, by type, from one shuffle of values."""
        by: dict[str, list[DataFrame]] = {}
        for t, c in cols:
            cut = self._text(c) if self.kinds[t, c] == "string" else [f"{_quoted(c)} AS v"]
            by.setdefault(self.kinds[t, c], []).append(self.base[t].selectExpr(f"{self.at[t, c]} AS at", *cut))
        return {kind: (every := union_all(parts)).groupBy(*every.columns).agg(F.count("*").alias("n")) for kind, parts in by.items()}

    def _text(self, c: str) -> list[str]:
        q = _quoted(c)
        long = "false" if any(r.of(c) for r in self.readings) else f"length({q}) > {LONG}"
        json = f"(startswith({q}, '{{') AND endswith({q}, '}}') OR startswith({q}, '[') AND endswith({q}, ']'))"
        whole = {"size": f"length({q})", "json": json, "a": f"xxhash64({q})", "b": f"xxhash64({hashed.SECOND}, {q})"}
        return [f"IF({long}, substring({q}, 1, {LONG}), {q}) AS v", *[f"IF({long}, {e}, NULL) AS {x}" for x, e in whole.items()]]

    def _finish(self, kind: str) -> list[str]:
        """A kept value, with its text made once for all equal ones; a negative zero is a value of its own."""
        if kind in WHOLE:
            return ["v"]
        if kind == "string":
            return ["CAST(NULL AS DOUBLE) AS real", "v", "size", "json", "a", "b"]
        given = {"date": "date_from_unix_date(CAST(v AS INT))", "timestamp": "timestamp_micros(v)", **{k: f"CAST(x AS {k})" for k in REAL}}.get(kind, "v")
        rest = ["CAST(NULL AS INT) AS size", "CAST(NULL AS BOOLEAN) AS json", "CAST(NULL AS LONG) AS a", "CAST(NULL AS LONG) AS b"]
        return [f"{'x' if kind in REAL else 'CAST(NULL AS DOUBLE)'} AS real", f"CAST({given} AS STRING) AS v", *rest]

    def _wanted(self) -> dict[int, list[tuple[str | None, str]]]:
        """(prefix or None, type) of the ways in which the readings see each column."""
        return {i: list(dict.fromkeys((r.of(c), "string" if r.text else self.kinds[t, c]) for r in self.readings if t in r.bundle.tables)) for (t, c), i in self.at.items()}

    def gather(self) -> list[dict[tuple[str, str], ColumnEvidence]]:
        """The evidence of all columns in each reading; distinct counts are exact."""
        wanted = self._wanted()

        def examine(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            seen: dict[tuple[int, str | None, str], _Values] = {}

            def add(held: list[pa.RecordBatch]) -> None:
                table = pa.Table.from_batches(held).combine_chunks()
                for at in pc.unique(table.column("at")).to_pylist():
                    part = table.filter(pc.equal(table.column("at"), at))
                    none = pc.is_null(part.column("v"))
                    nulls, part = pc.sum(part.filter(none).column("n")).as_py() or 0, part.filter(pc.invert(none)).combine_chunks()
                    get = lambda x, p: p.column(x).combine_chunks()
                    split = "size" in part.column_names
                    short = part.filter(pc.is_null(part.column("size"))) if split else part
                    long = part.filter(pc.is_valid(part.column("size"))) if split else part.slice(0, 0)
                    v, w = get("v", short), get("n", short).to_numpy()
                    text = v.cast(pa.large_string()) if any(p is not None or evidence._mode(k) == "text" for p, k in wanted[at]) else None
                    for prefix, kind in wanted[at]:
                        acc = seen.setdefault((at, prefix, kind), _Values(kind))
                        acc.rows += nulls
                        if len(v):
                            given = get("real", short) if acc.mode == "real" else v if acc.mode == "whole" else pc.binary_join_element_wise(pa.scalar(prefix, pa.large_string()), text, pa.scalar("", pa.large_string())) if prefix else text
                            acc.see(given, w)
                        if len(long):
                            acc.see_long(get("v", long).cast(pa.large_string()), get("size", long).to_numpy(), get("json", long).to_numpy(zero_copy_only=False), get("n", long).to_numpy())

            held, rows, size = [], 0, 0
            for b in batches:
                held.append(b)
                rows, size = rows + b.num_rows, size + b.nbytes
                if rows >= ROWS or size >= evidence.BYTES:
                    add(held)
                    held, rows, size = [], 0, 0
            if held:
                add(held)
            if seen:
                yield pa.RecordBatch.from_pylist([acc.row(str(at), f"{kind}|{prefix}" if prefix is not None else kind) for (at, prefix, kind), acc in seen.items()], evidence._ARROW)

        merged: dict[tuple[str, str], _Values] = {}
        ship(next(iter(self.base.tables.values())).sparkSession)
        for r in union_all([x.mapInArrow(examine, evidence._PART) for x in self.values]).collect():
            merged.setdefault((r["t"], r["c"]), _Values(r["c"].split("|")[0])).merge(r.asDict())
        self.n_values = sum({t: x.distinct for (t, _), x in merged.items()}.values())
        out, known = [], []
        for r in self.readings:
            deep = SourceBundle({t: df.select(*[f"`{c}`" for c in cols]) for t, df in r.bundle.tables.items() if (cols := [c for c in df.columns if (t, c) not in self.at])})
            found = evidence.gather(deep, known)
            known.append((deep, found))
            for t, df in r.bundle.tables.items():
                for c in df.columns:
                    if (t, c) in self.at:
                        kind, prefix = "string" if r.text else self.kinds[t, c], r.of(c)
                        x = merged.get((str(self.at[t, c]), kind if prefix is None else f"{kind}|{prefix}"), _Values(kind))
                        least, greatest = (None if y is None else str(y) for y in (x.least, x.greatest))
                        found[t, c] = ColumnEvidence(t, c, kind, x.rows, x.n, x.length / max(1, x.n), least, greatest, x.distinct, tuple(sorted(x.truth)), dict(zip(CLASSES, x.k, strict=True)) | {"truth": x.u})
                        if x.n and (t, c) in self.facts.alike:  # all rows were counted
                            self.facts.put(t, [c], x.n == x.rows == x.distinct)
            out.append({(t, c): found[t, c] for t, df in r.bundle.tables.items() for c in df.columns})
        return out

    def overlaps(self, wanted: list[tuple[list[tuple[str, str]], list[str]]]) -> list[list[tuple[str, str, int, int]]]:
        """(source, target, n_common, n_source) of each reading, for its columns and keys: a value goes through one shuffle as two hashes
        of its text and a mask of the columns that hold it; a column that several readings see alike is one."""
        places: dict[tuple[int, str], int] = {}
        groups = [[(places.setdefault((self.at[t, c], r.of(c) or ""), len(places)), f"{k}:{t}.{c}") for t, c in cols if (t, c) in self.at] for k, (r, (cols, _)) in enumerate(zip(self.readings, wanted, strict=True))]
        out: list[list[tuple[str, str, int, int]]] = [[] for _ in wanted]
        if not places:
            return out
        ways: dict[int, list[tuple[str, int]]] = {}
        for (at, prefix), i in places.items():
            ways.setdefault(at, []).append((prefix, i))
        quoted = lambda p: "'" + p.replace("\\", "\\\\").replace("'", "\\'") + "'"
        slots = ", ".join("array(" + ", ".join(f"named_struct('p', {quoted(p)}, 'i', {i})" for p, i in ways[at]) + ")" if at in ways else "NULL" for at in range(len(self.flat)))
        masks = [f"m{w}" for w in range((len(places) + domains.MASK - 1) // domains.MASK)]
        frames = []
        for x in self.values:
            held = x.where("v IS NOT NULL").where(F.col("at").isin(*ways)).selectExpr("*", f"explode(element_at(array({slots}), at + 1)) AS way").selectExpr("*", "way.i AS i", "concat(way.p, CAST(v AS STRING)) AS t")
            pair = {"a": "xxhash64(t)", "b": f"xxhash64({hashed.SECOND}, t)"}
            bits = [f"IF(i DIV {domains.MASK} = {w}, shiftleft(1L, i % {domains.MASK}), 0L) AS {m}" for w, m in enumerate(masks)]
            frames.append(held.selectExpr(*[f"coalesce({k}, {h}) AS {k}" if k in x.columns else f"{h} AS {k}" for k, h in pair.items()], *bits))
        every = union_all(frames)
        spark = every.sparkSession
        values = every.repartition(max(2 * self.n_values // BUCKET, int(spark.conf.get("spark.sql.shuffle.partitions"))), "a", "b").groupBy("a", "b").agg(*[F.bit_or(m).alias(m) for m in masks])
        counted = values.groupBy(*masks).agg(F.count("*").alias("k"))
        pairs = domains.count_pairs(counted, groups, [f"{k}:{q}" for k, (_, keys_) in enumerate(wanted) for q in keys_]).collect()
        sizes = {r["source"]: r["n"] for r in pairs if r["target"] is None}
        for r in pairs:
            (k, source), target = r["source"].split(":", 1), (r["target"] or ":").split(":", 1)[1]
            if target and source.split(".")[0] != target.split(".")[0]:
                out[int(k)].append((source, target, r["n"], sizes[r["source"]]))
        return out
