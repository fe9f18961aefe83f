"""Query graphs: shapes, elimination orders, triangulation, bags and junction trees. Tens of nodes, on the driver."""

from __future__ import annotations

from collections.abc import Iterable
from itertools import combinations, permutations

Graph = dict[str, set[str]]
Scopes = dict[str, tuple[str, ...]]


def build(scopes: Scopes) -> Graph:
    """A node a variable; the variables of one table form a clique."""
    g: Graph = {v: set() for s in scopes.values() for v in s}
    for s in scopes.values():
        for a, b in combinations(s, 2):
            g[a].add(b)
            g[b].add(a)
    return g


def hyperedges(scopes: Scopes) -> dict[str, frozenset[str]]:
    return {n: frozenset(s) for n, s in scopes.items()}


def edges(g: Graph) -> set[frozenset[str]]:
    return {frozenset((a, b)) for a in g for b in g[a]}


def components(g: Graph) -> list[set[str]]:
    left, out = set(g), []
    while left:
        found, todo = set(), [min(left)]
        while todo:
            v = todo.pop()
            if v not in found:
                found.add(v)
                todo += g[v] - found
        out.append(found)
        left -= found
    return out


def classify(scopes: Scopes) -> str:
    """chain, tree, acyclic (by ear removal on the hypergraph) or cyclic."""
    g = build(scopes)
    if sum(map(len, g.values())) // 2 <= len(g) - len(components(g)):
        return "chain" if all(len(n) <= 2 for n in g.values()) else "tree"
    left = [set(s) for s in scopes.values()]
    while left:
        for i, e in enumerate(left):
            others = left[:i] + left[i + 1 :]
            shared = {v for v in e if any(v in o for o in others)}
            if not shared or any(shared <= o for o in others):
                left = others
                break
        else:
            return "cyclic"
    return "acyclic"


def tree_order(g: Graph, root: str) -> list[str]:
    """Leaves first, ``root`` last (other components before it)."""
    order: list[str] = []

    def down(v: str, above: str | None) -> None:
        for w in sorted(g[v] - {above}):
            down(w, v)
        order.append(v)

    for part in components(g):
        if root not in part:
            down(min(part), None)
    down(root, None)
    return order


def _fill(g: Graph, v: str) -> list[tuple[str, str]]:
    return [(a, b) for a, b in combinations(sorted(g[v]), 2) if b not in g[a]]


def _remove(g: Graph, v: str) -> None:
    for a, b in _fill(g, v):
        g[a].add(b)
        g[b].add(a)
    for w in g.pop(v):
        g[w].discard(v)


def min_fill(g: Graph, first: Iterable[str] = (), last: Iterable[str] = (), weight: dict[str, float] | None = None) -> list[str]:
    """Greedy order of least fill-ins; ties by ``weight`` of the bag if given, then by name.

    Nodes of ``first`` go before all others; those of ``last`` after them, in the order given.
    """
    g, last = {v: set(n) for v, n in g.items()}, [v for v in last if v in g]
    early, order = set(first) & set(g), []

    def cost(v: str) -> tuple:
        size = 1.0
        for w in g[v] | {v}:
            size *= (weight or {}).get(w, 1.0)
        return len(_fill(g, v)), size, v

    while len(order) < len(g) + len(order) and g:
        pool = (early & set(g)) or (set(g) - set(last)) or {next(v for v in last if v in g)}
        v = min(pool, key=cost)
        order.append(v)
        _remove(g, v)
    return order


def best_order(g: Graph, limit: int = 8) -> list[str]:
    """Order of the smallest largest bag, then fewest fill-ins, by trying all; up to ``limit`` nodes."""
    if len(g) > limit:
        raise ValueError(f"{len(g)} nodes are too many to try all orders; use min_fill")
    return list(min(permutations(sorted(g)), key=lambda o: (max((len(b) for b in bags_of(g, o)), default=0), len(triangulate(g, o)[1]), o)))


def bags_of(g: Graph, order: Iterable[str]) -> list[frozenset[str]]:
    """For each eliminated node, itself and its neighbours at that time."""
    g, out = {v: set(n) for v, n in g.items()}, []
    for v in order:
        out.append(frozenset(g[v] | {v}))
        _remove(g, v)
    return out


def triangulate(g: Graph, order: Iterable[str]) -> tuple[Graph, set[frozenset[str]]]:
    """The chordal graph of an order and its fill-ins (each stands for a potential of constant 1)."""
    out = {v: set(n) for v, n in g.items()}
    for bag in bags_of(g, order):
        for a, b in combinations(bag, 2):
            out[a].add(b)
            out[b].add(a)
    return out, edges(out) - edges(g)


def maxcliques(g: Graph, order: Iterable[str]) -> list[frozenset[str]]:
    """Bags that no other bag holds."""
    bags = list(dict.fromkeys(bags_of(g, order)))
    return [b for b in bags if not any(b < c for c in bags)]


def assign(bags: list[frozenset[str]], scopes: Scopes) -> dict[frozenset[str], list[str]]:
    """Each table goes to exactly one bag that holds its variables."""
    out: dict[frozenset[str], list[str]] = {b: [] for b in bags}
    for name, s in scopes.items():
        out[next(b for b in bags if set(s) <= b)].append(name)
    return out


def junction_tree(bags: list[frozenset[str]]) -> list[tuple[frozenset[str], frozenset[str]]]:
    """Maximum spanning tree (forest) of the bags by separator size."""
    ranked = sorted(combinations(bags, 2), key=lambda p: (-len(p[0] & p[1]), sorted(p[0]), sorted(p[1])))
    home, tree = {b: i for i, b in enumerate(bags)}, []
    for a, b in ranked:
        if a & b and home[a] != home[b]:
            tree.append((a, b))
            old = home[b]
            home = {k: home[a] if h == old else h for k, h in home.items()}
    return tree


def separators(tree: list[tuple[frozenset[str], frozenset[str]]]) -> list[frozenset[str]]:
    return [a & b for a, b in tree]


def has_rip(bags: list[frozenset[str]]) -> bool:
    """Running intersection: what a bag shares with all earlier ones lies in one of them."""
    return all(not i or any(b & frozenset().union(*bags[:i]) <= c for c in bags[:i]) for i, b in enumerate(bags))
