"""A small SQL front: conjunctive equi-joins go through the summary, all else is refused."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame

from ..plans.spec import JoinQuery, equated

_SHAPE = re.compile(r"^\s*select\s+(?P<out>.+?)\s+from\s+(?P<tables>.+?)(?:\s+where\s+(?P<where>.+?))?\s*;?\s*$", re.I | re.S)
_COLUMN = re.compile(r"^(\w+)\.(\w+)$")
_EQUAL = re.compile(r"^(\w+\.\w+)\s*=\s*(\w+\.\w+)$")
_REFUSED = re.compile(r"\b(group|order|having|union|distinct|limit|outer|left|right|full|or|not|exists|join)\b", re.I)


def parse(sql: str, views: dict[str, DataFrame]) -> JoinQuery:
    """``SELECT a.x, b.y FROM t a, u b WHERE a.k = b.k AND a.z > 3``: equalities of columns join, the rest filters.

    Every conjunct must be an equality of two columns or a condition on one table; BETWEEN is not understood (write
    two comparisons).
    """
    m = _SHAPE.match(sql)
    bare = re.sub(r"'(?:[^']|'')*'", "''", sql)
    if not m or _REFUSED.search(bare):
        raise ValueError("only SELECT columns FROM tables WHERE conjunctions of equalities and filters")
    tables: dict[str, DataFrame] = {}
    for item in m["tables"].split(","):
        words = [w for w in item.split() if w.lower() != "as"]
        if not 1 <= len(words) <= 2 or words[0] not in views:
            raise ValueError(f"no table {item.strip()}")
        tables[words[-1]] = views[words[0]]
    output = [x.strip() for x in m["out"].split(",")]
    if not all(_COLUMN.match(x) for x in output):
        raise ValueError("only alias.column can be selected")
    equate = []
    for part in re.split(r"\s+and\s+", (m["where"] or "").strip(), flags=re.I) if m["where"] else []:
        if e := _EQUAL.match(part.strip()):
            equate.append((e[1], e[2]))
            continue
        owners = {a for a in re.findall(r"\b(\w+)\.\w+", re.sub(r"'(?:[^']|'')*'", "''", part))}
        if len(owners) != 1 or not owners <= set(tables):
            raise ValueError(f"a filter must name columns of one table: {part}")
        alias = owners.pop()
        tables[alias] = tables[alias].filter(re.sub(rf"\b{alias}\.", "", part))
    return equated(tables, equate, output)
