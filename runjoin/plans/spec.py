"""Join queries: tables whose columns are named by variables, and the wanted output."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass
class JoinQuery:
    """An n-way equi-join. Columns of ``tables`` carry variable names: equal names are equated.

    Columns that are neither joined nor wanted are dropped. Rows with a null join variable are dropped too (a null
    equals nothing); nulls of other variables are values like any other.
    """

    tables: dict[str, DataFrame]
    output: list[str]
    order: list[str] | None = None
    scopes: dict[str, tuple[str, ...]] = field(init=False)
    joined: set[str] = field(init=False)

    def __post_init__(self) -> None:
        holders: dict[str, int] = {}
        for df in self.tables.values():
            if len(set(df.columns)) != len(df.columns):
                raise ValueError("a table has two columns of one name")
            for c in df.columns:
                holders[c] = holders.get(c, 0) + 1
        self.joined = {v for v, n in holders.items() if n > 1}
        missing = [v for v in self.output if v not in holders]
        if missing:
            raise ValueError(f"no table has {missing}")
        wanted = self.joined | set(self.output)
        pruned = {}
        for name, df in self.tables.items():
            kept = [c for c in df.columns if c in wanted]
            for c in kept:
                if df.schema[c].dataType.typeName() == "map":
                    raise TypeError(f"{c} is a map, which has no order; project its sorted entries first")
            keys = [c for c in kept if c in self.joined]
            pruned[name] = df.select(*kept).dropna(subset=keys) if keys else df.select(*kept)
        self.tables = pruned
        self.scopes = {n: tuple(df.columns) for n, df in pruned.items()}

    @property
    def variables(self) -> list[str]:
        return list(dict.fromkeys(v for s in self.scopes.values() for v in s))

    @property
    def hidden(self) -> list[str]:
        """Join variables that the output doesn't hold."""
        return [v for v in self.variables if v not in self.output]


def natural(tables: dict[str, DataFrame], output: list[str], order: list[str] | None = None) -> JoinQuery:
    """Equate columns of equal names."""
    return JoinQuery(tables, output, order)


def equated(tables: dict[str, DataFrame], equate: list[tuple[str, str]], output: list[str]) -> JoinQuery:
    """From ``alias.column`` pairs: classes of equated columns become variables, named ``alias_column`` of the first.

    Two columns of one table in one class become a filter. Output columns are named by their variable.
    """
    parent: dict[str, str] = {}

    def root(x: str) -> str:
        while parent.setdefault(x, x) != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    for a, b in equate:
        parent[root(b)] = root(a)
    used = dict.fromkeys([x for pair in equate for x in pair] + list(output))
    named = {x: root(x).replace(".", "_") for x in used}
    shaped = {}
    for alias, df in tables.items():
        own = [x for x in used if x.split(".", 1)[0] == alias]
        groups: dict[str, list[str]] = {}
        for x in own:
            groups.setdefault(named[x], []).append(x.split(".", 1)[1])
        for columns in groups.values():
            for c in columns[1:]:
                df = df.filter(F.col(columns[0]) == F.col(c))
        shaped[alias] = df.select(*[F.col(columns[0]).alias(v) for v, columns in groups.items()])
    return JoinQuery(shaped, list(dict.fromkeys(named[x] for x in output)))


def restrict(query: JoinQuery, variable: str, test) -> JoinQuery:
    """Filter every table that holds ``variable`` by ``test`` (column to condition), so each scan is cut."""
    check: Column = test(F.col(variable))
    tables = {n: df.filter(check) if variable in df.columns else df for n, df in query.tables.items()}
    return JoinQuery(tables, query.output, query.order)
