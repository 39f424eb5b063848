"""Query hypergraphs: acyclicity, join trees, free-connex rootings."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from itertools import combinations, product


class UnsupportedQuery(ValueError):
    """The query is cyclic or no rooting of its join trees is free-connex."""


@dataclass(frozen=True)
class Tree:
    """A rooted join tree: parent of each relation (None for the root)."""

    parents: tuple[tuple[str, str | None], ...]

    @property
    def parent(self) -> dict[str, str | None]:
        return dict(self.parents)

    @property
    def root(self) -> str:
        return next(r for r, p in self.parents if p is None)

    def children(self, name: str) -> list[str]:
        return [r for r, p in self.parents if p == name]

    def depth(self, name: str) -> int:
        parent, n = self.parent, 0
        while (name := parent[name]) is not None:
            n += 1
        return n

    def bottom_up(self) -> list[str]:
        return sorted((r for r, _ in self.parents), key=lambda r: (-self.depth(r), r))


def is_acyclic(edges: dict[str, frozenset[str]]) -> bool:
    """Ears are removed until one relation is left: the attributes an ear shares with others all lie in one other."""
    left = dict(edges)
    while len(left) > 1:
        for name, attrs in left.items():
            others = {k: v for k, v in left.items() if k != name}
            shared = attrs & frozenset().union(*others.values())
            if any(shared <= v for v in others.values()):
                del left[name]
                break
        else:
            return False
    return True


def undirected_trees(edges: dict[str, frozenset[str]]) -> Iterator[frozenset[frozenset[str]]]:
    """All join trees: spanning trees in which each attribute's relations are connected.

    These are the spanning trees whose shared attributes number (sum of arities - number of attributes) in total.
    """
    names = sorted(edges)
    links = list(combinations(names, 2))
    wanted = sum(map(len, edges.values())) - len(frozenset().union(*edges.values()))

    def grow(k: int, chosen: list, group: dict[str, str], weight: int):
        if len(chosen) == len(names) - 1:
            if weight == wanted:
                yield frozenset(map(frozenset, chosen))
            return
        if len(links) - k < len(names) - 1 - len(chosen):
            return
        a, b = links[k]
        if group[a] != group[b] and (edges[a] & edges[b] or True):
            merged = {n: group[a] if g == group[b] else g for n, g in group.items()}
            yield from grow(k + 1, [*chosen, (a, b)], merged, weight + len(edges[a] & edges[b]))
        yield from grow(k + 1, chosen, group, weight)

    yield from grow(0, [], {n: n for n in names}, 0)


def rooted(tree: frozenset[frozenset[str]], root: str, names: list[str]) -> Tree:
    parent: dict[str, str | None] = {root: None}
    queue = [root]
    while queue:
        here = queue.pop(0)
        for link in sorted(tree, key=sorted):
            if here in link:
                (other,) = link - {here}
                if other not in parent:
                    parent[other] = here
                    queue.append(other)
    return Tree(tuple((n, parent[n]) for n in names))


def top(tree: Tree, edges: dict[str, frozenset[str]], attr: str) -> str:
    """The relation with the attribute that is nearest to the root."""
    return min((n for n in edges if attr in edges[n]), key=lambda n: (tree.depth(n), n))


def _proper_ancestor(tree: Tree, a: str, b: str) -> bool:
    parent = tree.parent
    while (b := parent[b]) is not None:
        if b == a:
            return True
    return False


def is_free_connex(tree: Tree, edges: dict[str, frozenset[str]], outputs: frozenset[str]) -> bool:
    """No other attribute's top relation lies properly above an output attribute's."""
    attrs = frozenset().union(*edges.values())
    return not any(_proper_ancestor(tree, top(tree, edges, x), top(tree, edges, o)) for x, o in product(attrs - outputs, outputs & attrs))


def join_trees(edges: dict[str, frozenset[str]]) -> list[Tree]:
    names = sorted(edges)
    return [rooted(t, r, names) for t in undirected_trees(edges) for r in names]


def free_connex_trees(edges: dict[str, frozenset[str]], outputs: frozenset[str]) -> list[Tree]:
    if not is_acyclic(edges):
        raise UnsupportedQuery("the query is cyclic: only worst-case bounds beyond linear are known for it")
    trees = [t for t in join_trees(edges) if is_free_connex(t, edges, outputs)]
    if not trees:
        raise UnsupportedQuery("the query is acyclic but not free-connex for these outputs; adding join attributes to them may help")
    return trees
