"""Evidence of every column from one scan of each table: what the values are, whatever their declared type says."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

from semcat.functions.shipping import ship
from semcat.operators.profile import union_all
from semcat.plans.lexicon import TIME_WORDS, id_like, measure_like, words
from semcat.sources.bundle import SourceBundle

#: Words of truth.
TRUTH = ("true", "false", "yes", "no", "t", "f", "y", "n")
#: Mean length from which a text is prose that no one groups by.
PROSE = 60
_NUMBER, _EIGHT = r"^[+-]?[0-9]+(\.[0-9]+)?([eE][+-]?[0-9]+)?$", r"^(19|20)[0-9]{2}(0[1-9]|1[0-2])(0[1-9]|[12][0-9]|3[01])$"
_DAY, _CLOCK = r"^[0-9]{4}-[0-9]{2}-[0-9]{2}([ T]00:00:00)?$", r"^[0-9]{4}-[0-9]{2}-[0-9]{2}[ T][0-9]{2}:[0-9]{2}(:[0-9]{2}(\.[0-9]+)?)?$"
CLASSES = "zero day8 int num day clock json other".split()


@dataclass
class ColumnEvidence:
    """Counts over all rows: values of each class, the least and the greatest value as text, the words of truth seen."""

    table: str
    column: str
    declared: str
    n_rows: int
    n: int
    mean_length: float
    least: str | None
    greatest: str | None
    about_distinct: int = 0
    truth: tuple[str, ...] = ()
    classes: dict[str, int] = field(default_factory=dict)

    def all(self, *names: str) -> bool:
        return self.n > 0 and sum(self.classes.get(c, 0) for c in names) == self.n

    @property
    def family(self) -> str:
        """What the values can be compared as: integer, float, time, text, or opaque. Numbers with a leading zero are text."""
        if self.declared.startswith(("array", "map", "struct", "binary")) or self.n and self.classes.get("json", 0) == self.n:
            return "opaque"
        if self.n and self.all("int", "day8"):
            return "integer"
        if self.all("int", "day8", "num"):
            return "float"
        if self.declared.startswith(("date", "timestamp")) or self.all("day", "clock"):
            return "time"
        return "opaque" if self.mean_length > PROSE else "text"

    @property
    def boolean(self) -> bool:
        """Two words of truth, or 0 and 1 and nothing else under a name that speaks for neither identifier nor measure."""
        if self.declared == "boolean":
            return True
        two = len(self.truth) == 2 and self.n == self.classes.get("truth", -1)
        digits = set(self.truth) <= {"0", "1"}
        return two and (not digits or not (id_like(self.column) or measure_like(self.column)))

    @property
    def isa(self) -> str:
        """Storage: the declared type where it says more than text, else what all values are."""
        if self.declared in ("tinyint", "smallint", "int", "bigint"):
            return "integer"
        if self.declared in ("float", "double") or self.declared.startswith("decimal"):
            return "float"
        if self.declared == "date" or self.declared.startswith("timestamp"):
            return "date" if self.declared == "date" or self.n and not self.classes.get("clock") else "datetime"
        if self.boolean:
            return "boolean"
        if self.family == "integer":
            return "date" if self.all("day8") and words(self.column)[-1] in TIME_WORDS else "integer"
        if self.family == "time":
            return "datetime" if self.classes.get("clock") else "date"
        if self.declared.startswith(("array", "map", "struct", "binary")):
            return "array"
        return "float" if self.family == "float" else "string"

    def supports(self, role: str) -> bool:
        """Whether a proposed role can stand: Numeric needs numbers, Datetime needs times; digits of an identifier are no measure."""
        if role == "Numeric":
            return self.isa in ("integer", "float") and not id_like(self.column)
        if role == "Datetime":
            return self.isa in ("date", "datetime")
        return True

    @property
    def role(self) -> str:
        """The rules' own role, by name and values: digits alone never make a measure."""
        if self.family == "opaque":
            return "Opaque"
        if self.isa in ("date", "datetime"):
            return "Datetime"
        if id_like(self.column) or self.isa == "boolean":
            return "Categorical"
        return "Numeric" if self.isa == "float" or self.isa == "integer" and measure_like(self.column) else "Categorical"

    @property
    def no_key(self) -> bool:
        """Whether nulls, or a sketch that stays far below the row count, rule the column out as a key on its own; a sketch may refute
        but never confirm."""
        return self.n < self.n_rows or not self.n or self.about_distinct < 0.75 * self.n

    @property
    def unclear(self) -> bool:
        """Whole numbers under a name that says neither measure nor identifier: the values leave the role open."""
        return self.isa == "integer" and not id_like(self.column) and not measure_like(self.column)

    @property
    def description(self) -> str:
        """Real values only: the least and the greatest."""
        if self.family == "opaque" or self.least is None:
            return ""
        return f"e.g. {self.least}" if self.least == self.greatest else f"e.g. {self.least}, {self.greatest}"


#: A worker examines so many rows or bytes of a table at a time.
ROWS, BYTES = 1 << 18, 1 << 25
#: Registers of the sketch of distinct values: an error of about 1.6 %.
_BITS = 12
_WORDS = (*TRUTH, "0", "1")
_PART = "t string, c string, rows long, n long, length long, p string, q string, lo long, hi long, dlo double, dhi double, truth array<string>, u long, k array<long>, d binary"
_WHOLE, _REAL = ("tinyint", "smallint", "int", "bigint"), ("float", "double")


def _mode(kind: str) -> str:
    """How a column reaches the workers: whole and real numbers as they are, nested values as a hash, all others as text."""
    return "whole" if kind in _WHOLE else "real" if kind in _REAL else "deep" if kind.startswith(("array", "map", "struct", "binary")) else "text"


def _mix(h: np.ndarray) -> np.ndarray:
    """Spreads all bits of unsigned 64-bit integers (public splitmix64 constants)."""
    h = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


def _text_hashes(values: pa.Array) -> np.ndarray:
    """64-bit hashes of distinct texts: sums of bytes weighted by their place, then mixed."""
    values = values.cast(pa.large_binary())
    offsets = np.frombuffer(values.buffers()[1], np.int64, len(values) + 1, values.offset * 8)
    data = np.frombuffer(values.buffers()[2] or b"", np.uint8)[offsets[0] : offsets[-1]]
    at = offsets - offsets[0]
    place = np.arange(len(data)) - np.repeat(at[:-1], np.diff(at))
    total = np.zeros(len(data) + 1, np.uint64)
    np.cumsum(_mix(place.astype(np.uint64) * np.uint64(256) + data + np.uint64(1)), out=total[1:])
    return _mix(total[at[1:]] - total[at[:-1]] + np.diff(at).astype(np.uint64))


def _sketch(hashes: np.ndarray, registers: np.ndarray) -> None:
    """Enter hashes into the registers of a HyperLogLog sketch."""
    rest = (hashes << np.uint64(_BITS)) >> np.uint64(_BITS)
    # the exponent of the 52 low bits, which a double holds exactly
    rank = (65 - _BITS - np.frexp(rest.astype(float))[1]).astype(np.uint8)
    np.maximum.at(registers, (hashes >> np.uint64(64 - _BITS)).astype(np.int64), rank)


def _estimate(registers: np.ndarray) -> int:
    m = len(registers)
    raw = 0.7213 / (1 + 1.079 / m) * m * m / np.sum(np.exp2(-registers.astype(float)))
    empty = int((registers == 0).sum())
    return round(m * np.log(m / empty) if raw <= 2.5 * m and empty else raw)


def _classify(v: pa.Array, w: np.ndarray, kind: str) -> list[int]:
    """How many texts are of each class, for distinct values and their counts: by declared type where that settles it, else by
    patterns; long values skip those of numbers and times."""
    out = dict.fromkeys(CLASSES, 0)
    if kind.startswith("timestamp"):
        day = np.asarray(pc.ends_with(v, " 00:00:00"))
        out |= {"day": int(w[day].sum()), "clock": int(w[~day].sum())}
    elif kind == "date" or kind.startswith("decimal"):
        out["day" if kind == "date" else "num"] = int(w.sum())
    elif kind == "boolean":
        out["other"] = int(w.sum())
    else:
        starts, ends = (lambda x: np.asarray(pc.starts_with(v, x))), (lambda x: np.asarray(pc.ends_with(v, x)))
        json = starts("{") & ends("}") | starts("[") & ends("]")
        first = np.asarray(pc.match_substring_regex(v, "^[+-]?[0-9]")) & ~json & (np.asarray(pc.utf8_length(v)) <= 40)

        def part(x: pa.Array, weight: np.ndarray, tests: list[tuple[str, str]]) -> tuple[pa.Array, np.ndarray]:
            for name, pattern in tests:
                hit = np.asarray(pc.match_substring_regex(x, pattern))
                out[name] += int(weight[hit].sum())
                x, weight = x.filter(pa.array(~hit)), weight[~hit]
            return x, weight

        x, weight = v.filter(pa.array(first)), w[first]
        number = np.asarray(pc.match_substring_regex(x, _NUMBER))
        numbers, many = x.filter(pa.array(number)), weight[number]
        whole = np.asarray(pc.match_substring_regex(numbers, "^[+-]?[0-9]+$"))
        out["num"] += int(many[~whole].sum())
        out["int"] += int(part(numbers.filter(pa.array(whole)), many[whole], [("zero", "^0[0-9]+$"), ("day8", _EIGHT)])[1].sum())
        left = part(x.filter(pa.array(~number)), weight[~number], [("day", _DAY), ("clock", _CLOCK)])[1]
        out["json"] = int(w[json].sum())
        out["other"] = int(w[~json & ~first].sum() + left.sum())
    return [out[c] for c in CLASSES]


class _Column:
    """What a task has seen of a column."""

    def __init__(self, kind: str):
        self.kind, self.mode = kind, _mode(kind)
        self.rows = self.n = self.length = self.u = 0
        self.least = self.greatest = None
        self.truth: set[str] = set()
        self.k, self.registers = [0] * len(CLASSES), np.zeros(1 << _BITS, np.uint8)

    def add(self, col: pa.ChunkedArray) -> None:
        self.rows += len(col)
        self.n += len(col) - col.null_count
        if len(col) == col.null_count:
            return
        col = col.drop_null()
        known = {"whole": "int", "real": "num", "deep": "other" if self.kind == "binary" else "json"}.get(self.mode)
        if known:
            v = col.unique().to_numpy(zero_copy_only=False)
            self.k[CLASSES.index(known)] += len(col)
            if self.mode == "real":
                v = v.astype(float) + 0.0  # one zero
                numbers = v[~np.isnan(v)]
                self._range(float(numbers.min()) if len(numbers) else float("nan"), float(v.max()))  # NaN is the greatest
            elif self.mode == "whole":
                self._range(int(v.min()), int(v.max()))
                for d in (0, 1):
                    some = pc.sum(pc.equal(col, d)).as_py() or 0
                    self.u += some
                    self.truth |= {str(d)} if some else set()
            bits = v if self.mode != "real" else v.view(np.int64)
            _sketch(_mix(bits.astype(np.int64).view(np.uint64) + np.uint64(1)) if self.mode != "deep" else bits.view(np.uint64), self.registers)
            return
        found = pc.value_counts(col.combine_chunks().cast(pa.large_string()))
        v, w = found.field(0), found.field(1).to_numpy()
        self.texts(v, w)
        _sketch(_text_hashes(v), self.registers)

    def texts(self, v: pa.Array, w: np.ndarray) -> None:
        """Distinct texts and their counts."""
        size = pc.utf8_length(v).to_numpy()
        self.length += int((size * w).sum())
        self._range(*(x[:64] for x in pc.min_max(v).as_py().values()))
        short = size <= 5
        lower = pc.utf8_lower(v.filter(pa.array(short)))
        word = np.asarray(pc.is_in(lower, pa.array(_WORDS, pa.large_string())))
        self.u += int(w[short][word].sum())
        self.truth |= set(lower.filter(pa.array(word)).to_pylist())
        self.k = [a + b for a, b in zip(self.k, _classify(v, w, self.kind), strict=True)]

    def _range(self, least, greatest) -> None:
        order = (lambda x: x.encode()) if self.mode == "text" else (lambda x: (x != x, x))  # texts by their bytes, NaN last
        self.least = least if self.least is None else min(self.least, least, key=order)
        self.greatest = greatest if self.greatest is None else max(self.greatest, greatest, key=order)

    def merge(self, r: dict) -> None:
        self.rows, self.n, self.length, self.u = self.rows + r["rows"], self.n + r["n"], self.length + r["length"], self.u + r["u"]
        ends = {"text": ("p", "q"), "whole": ("lo", "hi"), "real": ("dlo", "dhi")}.get(self.mode)
        if ends and r[ends[0]] is not None:
            self._range(r[ends[0]], r[ends[1]])
        self.truth |= set(r["truth"])
        self.k = [a + b for a, b in zip(self.k, r["k"], strict=True)]
        self.registers = np.maximum(self.registers, np.frombuffer(r["d"], np.uint8))

    def row(self, t: str, c: str) -> dict:
        ends = {"text": ("p", "q"), "whole": ("lo", "hi"), "real": ("dlo", "dhi")}.get(self.mode, ("p", "q"))
        empty = dict.fromkeys(("p", "q", "lo", "hi", "dlo", "dhi"))
        return empty | {"t": t, "c": c, "rows": self.rows, "n": self.n, "length": self.length, ends[0]: self.least, ends[1]: self.greatest, "truth": sorted(self.truth), "u": self.u, "k": self.k, "d": self.registers.tobytes()}


_ARROW = pa.schema([("t", pa.string()), ("c", pa.string()), *[(x, pa.int64()) for x in ("rows", "n", "length")], ("p", pa.string()), ("q", pa.string()), ("lo", pa.int64()), ("hi", pa.int64()), ("dlo", pa.float64()), ("dhi", pa.float64()), ("truth", pa.list_(pa.string())), ("u", pa.int64()), ("k", pa.list_(pa.int64())), ("d", pa.binary())])


def _partial(df: DataFrame, t: str) -> DataFrame:
    """One row a task and column of what the task has seen."""
    cells, kinds = [], []
    for i, f in enumerate(df.schema.fields):
        k, q = f.dataType.simpleString(), "`" + f.name.replace("`", "``") + "`"
        hashed = f"IF({q} IS NULL, NULL, {'0L' if k.startswith('map') else f'xxhash64({q})'})"
        cells.append(f"{({'deep': hashed, 'text': f'CAST({q} AS STRING)'}).get(_mode(k), q)} AS c{i}")
        kinds.append((f.name, k))

    def run(batches):
        columns, held, rows, size = [_Column(k) for _, k in kinds], [], 0, 0

        def examine() -> None:
            table = pa.Table.from_batches(held)
            for i, c in enumerate(columns):
                c.add(table.column(i))

        for b in batches:
            held.append(b)
            rows, size = rows + b.num_rows, size + b.nbytes
            if rows >= ROWS or size >= BYTES:
                examine()
                held, rows, size = [], 0, 0
        if held:
            examine()
        yield pa.RecordBatch.from_pylist([c.row(t, name) for c, (name, _) in zip(columns, kinds, strict=True)], _ARROW)

    return df.selectExpr(*cells).mapInArrow(run, _PART)


def shared(bundle: SourceBundle, known: list[tuple[SourceBundle, dict[tuple[str, str], ColumnEvidence]]]) -> dict[tuple[str, str], ColumnEvidence]:
    """The columns that a bundle examined before reads in the same way from the same files, with what was found there."""
    read = lambda df, c: df.select(f"`{c}`")._jdf.queryExecution().optimizedPlan()
    out = {}
    for before, found in known:
        for t in (t for t in bundle.tables if t in before.tables):
            for c in bundle[t].columns:
                if (t, c) not in out and c in before[t].columns and read(bundle[t], c).sameResult(read(before[t], c)):
                    out[t, c] = found[t, c]
    return out


def gather(bundle: SourceBundle, known: list[tuple[SourceBundle, dict[tuple[str, str], ColumnEvidence]]] | None = None) -> dict[tuple[str, str], ColumnEvidence]:
    """The evidence of all columns of a bundle, in Arrow batches: a value that many rows of a batch share is looked at once. A task sends
    one row a column, these are merged by column, and one row a column reaches the driver. Columns that a bundle in ``known`` reads in
    the same way are taken from there."""
    have = shared(bundle, known or [])
    tables = {t: df.select(*[f"`{c}`" for c in df.columns if (t, c) not in have]) for t, df in bundle.tables.items()}
    tables = {t: df for t, df in tables.items() if df.columns}
    kinds = {(t, f.name): f.dataType.simpleString() for t, df in tables.items() for f in df.schema.fields}

    def merge(part: pa.Table) -> pa.Table:
        first, *_ = got = part.to_pylist()
        whole = _Column(kinds[first["t"], first["c"]])
        for r in got:
            whole.merge(r)
        return pa.Table.from_pylist([whole.row(first["t"], first["c"])], _ARROW)

    out = {}
    if tables:
        ship(next(iter(tables.values())).sparkSession)
        for r in union_all([_partial(df, t) for t, df in tables.items()]).groupBy("t", "c").applyInArrow(merge, _PART).collect():
            if not r["rows"]:
                continue
            kind = kinds[r["t"], r["c"]]
            ends = {"whole": ("lo", "hi"), "real": ("dlo", "dhi")}.get(_mode(kind), ("p", "q"))
            least, greatest = (None if r[x] is None else str(r[x]) for x in ends)
            out[r["t"], r["c"]] = ColumnEvidence(r["t"], r["c"], kind, r["rows"], r["n"], r["length"] / max(1, r["n"]), least, greatest, _estimate(np.frombuffer(r["d"], np.uint8)), tuple(r["truth"]), dict(zip(CLASSES, r["k"], strict=True)) | {"truth": r["u"]})
    none = lambda t, c: ColumnEvidence(t, c, bundle[t].schema[c].dataType.simpleString(), 0, 0, 0.0, None, None)
    return {(t, c): have.get((t, c)) or out.get((t, c)) or none(t, c) for t, df in bundle.tables.items() for c in df.columns}


def roles(evidence: dict[tuple[str, str], ColumnEvidence]) -> dict[str, dict[str, str]]:
    by: dict[str, dict[str, str]] = {}
    for (t, c), e in evidence.items():
        by.setdefault(t, {})[c] = e.role
    return by
