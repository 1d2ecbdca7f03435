"""Join graph (a multigraph keyed by column pair), reachability, closure. All of it is small and lives on the driver."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

Join = tuple[str, str, str, str]


@dataclass(frozen=True)
class Step:
    join: Join
    reverse: bool

    @property
    def near(self) -> str:
        return self.join[2] if self.reverse else self.join[0]

    @property
    def far(self) -> str:
        return self.join[0] if self.reverse else self.join[2]

    def text(self) -> str:
        j = self.join
        return f"{j[2]}.{j[3]}<-{j[0]}.{j[1]}" if self.reverse else f"{j[0]}.{j[1]}->{j[2]}.{j[3]}"


class JoinGraph:
    """Verified joins, canonical from foreign key to key; parallel joins of one pair of tables stay apart."""

    def __init__(self, joins: list[Join]):
        self.joins = sorted(set(joins))

    def steps(self, table: str) -> list[Step]:
        return [Step(j, False) for j in self.joins if j[0] == table] + [Step(j, True) for j in self.joins if j[2] == table]

    def paths(self, entity: str, max_hops: int = 3, all_parallel: bool = False) -> list[tuple[Step, ...]]:
        """Simple paths from an entity, short ones first; of parallel joins only the first is walked unless asked."""
        out, front = [], [()]
        for _ in range(max_hops):
            ahead = []
            for p in front:
                at = p[-1].far if p else entity
                seen = {entity, *(s.far for s in p)}
                used = set()
                for s in self.steps(at):
                    if s.far in seen or (not all_parallel and (s.far, s.reverse) in used):
                        continue
                    used.add((s.far, s.reverse))
                    ahead.append((*p, s))
            out += ahead
            front = ahead
        return out

    def reach(self, entity: str, columns: dict[str, list[str]], max_hops: int = 3) -> list[tuple[str, str, str, int, str]]:
        """(entity, table, column, hops, direction) of other tables' columns by the shortest path; many_to_one if every step is."""
        best: dict[str, tuple[Step, ...]] = {}
        for p in self.paths(entity, max_hops):
            best.setdefault(p[-1].far, p)
        return [(entity, t, c, len(p), direction(p)) for t, p in sorted(best.items()) for c in columns[t]]

    def pruned(self, entity: str, max_hops: int = 3) -> list[tuple[str, str, str]]:
        """(entity, path, reason) of walks that are not offered: those that come back to a table they passed."""
        out, front = [], [()]
        for _ in range(max_hops):
            ahead = []
            for p in front:
                at, seen = (p[-1].far if p else entity), {entity, *(s.far for s in p)}
                for s in self.steps(at):
                    if s.far in seen:
                        out.append((entity, "/".join(x.text() for x in (*p, s)), "back to own key" if s.far == entity else "not simple"))
                    else:
                        ahead.append((*p, s))
            front = ahead
        return out

    def equivalence(self) -> list[tuple[str, str]]:
        """Pairs of columns that chains of joins equate (closure by union-find), a < b."""
        parent: dict[str, str] = {}

        def find(x: str) -> str:
            parent.setdefault(x, x)
            while parent[x] != x:
                parent[x] = parent[parent[x]]
                x = parent[x]
            return x

        for a, b, c, d in self.joins:
            x, y = find(f"{a}.{b}"), find(f"{c}.{d}")
            parent[max(x, y)] = min(x, y)
        names = sorted(parent)
        return [(a, b) for i, a in enumerate(names) for b in names[i + 1 :] if find(a) == find(b)]


def direction(path: tuple[Step, ...]) -> str:
    return "one_to_many" if any(s.reverse for s in path) else "many_to_one"


def along(tables: dict[str, DataFrame], entity: str, path: tuple[Step, ...], how: str = "left") -> DataFrame:
    """The entity joined along a path; broadcasting is left to the engine's size estimates."""
    df = tables[entity]
    for s in path:
        a, b, c, d = s.join
        df = df.join(tables[s.far], F.col(b) == F.col(d), how) if b != d else df.join(tables[s.far].withColumnRenamed(d if not s.reverse else b, "__k"), F.col(b if not s.reverse else d) == F.col("__k"), how).drop("__k")
    return df


def aggregate_along(tables: dict[str, DataFrame], join: Join, measures: dict[str, object]) -> DataFrame:
    """Aggregates of the many side per key, made before the join so that no row is multiplied: (key, measures)."""
    a, b, c, d = join
    pre = tables[a].groupBy(b).agg(*[m.alias(n) for n, m in measures.items()])
    return tables[c].select(d).join(pre, F.col(d) == F.col(b), "left").drop(b)
