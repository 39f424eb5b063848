"""Three-phase plans of free-connex queries, their data-independent cost, and the choice among trees and child orders."""

from __future__ import annotations

from dataclasses import dataclass, field
from itertools import permutations, product

from ..model import key_of
from .hypergraph import Tree, free_connex_trees


@dataclass(frozen=True)
class Step:
    """kind: group (relation on attrs), absorb (child into relation), semijoin (relation by other), join (relation with other)."""

    kind: str
    relation: str
    other: str | None = None
    attrs: frozenset[str] = frozenset()

    def __str__(self) -> str:
        return f"{self.kind} {self.relation}" + (f" {self.other}" if self.other else "") + (f" [{','.join(sorted(self.attrs))}]" if self.kind == "group" else "")


@dataclass
class Plan:
    tree: Tree
    reduce: list[Step] = field(default_factory=list)
    semijoins: list[Step] = field(default_factory=list)
    joins: list[Step] = field(default_factory=list)
    schemas: dict[str, frozenset[str]] = field(default_factory=dict)  # after phase 1
    keys: dict[str, set[tuple[str, ...]]] = field(default_factory=dict)  # ranks that owners attach
    n_cost: int = 0
    m_cost: int = 0

    @property
    def steps(self) -> list[Step]:
        return [*self.reduce, *self.semijoins, *self.joins]


def reduce_steps(tree: Tree, edges: dict[str, frozenset[str]], outputs: frozenset[str], bags: frozenset[str] = frozenset()) -> tuple[list[Step], dict[str, frozenset[str]]]:
    """Bottom-up: a relation is grouped on its attributes that are outputs or its parent's, and absorbed if all are the parent's.

    Relations in `bags` may hold a row more than once and are grouped even if no attribute goes.
    """
    schema, steps = dict(edges), []
    stopped: set[str] = set()
    for name in tree.bottom_up():
        parent = tree.parent[name]
        if parent is None:
            keep = outputs & schema[name]
            if keep != schema[name] or name in bags:
                steps.append(Step("group", name, attrs=keep))
                schema[name] = keep
            continue
        if name in stopped:
            continue
        keep = (outputs | schema[parent]) & schema[name]
        if keep != schema[name] or name in bags:
            steps.append(Step("group", name, attrs=keep))
            schema[name] = keep
        if keep <= schema[parent] and not any(c in schema for c in tree.children(name)):
            steps.append(Step("absorb", parent, name))
            del schema[name]
        else:
            while parent is not None:  # nothing above this branch is absorbed
                stopped |= {parent} - {tree.root}
                parent = tree.parent[parent]
    return steps, schema


def _ordered(tree: Tree, left: dict, order: dict[str, tuple[str, ...]]) -> list[str]:
    """Relations that are left, children before parents, in the given order of children."""
    out: list[str] = []

    def visit(name: str):
        for c in order.get(name, ()):
            visit(c)
        out.append(name)

    visit(tree.root)
    return [n for n in out if n in left]


def build(tree: Tree, edges: dict[str, frozenset[str]], outputs: frozenset[str], order: dict[str, tuple[str, ...]] | None = None, bags: frozenset[str] = frozenset()) -> Plan:
    """The plan a tree induces; `order` fixes the order in which a relation's children are joined."""
    reduce, schema = reduce_steps(tree, edges, outputs, bags)
    order = order or {n: tuple(c for c in tree.children(n) if c in schema) for n in schema}
    plan = Plan(tree, reduce, schemas=schema)
    visit = _ordered(tree, schema, order)
    if len(schema) > 1:
        plan.semijoins = [Step("semijoin", tree.parent[n], n) for n in visit if tree.parent[n] is not None]
        plan.semijoins += [Step("semijoin", n, tree.parent[n]) for n in reversed(visit) if tree.parent[n] is not None]
        plan.joins = [Step("join", tree.parent[n], n) for n in visit if tree.parent[n] is not None]
    plan.keys = _initial_keys(plan, edges)
    _price(plan)
    return plan


def _initial_keys(plan: Plan, edges: dict[str, frozenset[str]]) -> dict[str, set[tuple[str, ...]]]:
    """Ranks each owner attaches: keys of groupings, absorptions, semi-joins and joins that its relation takes part in."""
    keys: dict[str, set[tuple[str, ...]]] = {n: set() for n in edges}
    schema = dict(edges)
    for s in plan.reduce:
        if s.kind == "group":
            schema[s.relation] = s.attrs
            keys[s.relation].add(key_of(s.attrs))
        else:
            keys[s.relation].add(key_of(schema[s.other]))
            keys[s.other].add(key_of(schema[s.other]))
    for s in [*plan.semijoins, *plan.joins]:
        k = key_of(plan.schemas[s.relation] & plan.schemas[s.other])
        assert set(k) <= edges[s.relation] and set(k) <= edges[s.other], "join keys belong to both initial schemas"
        keys[s.relation].add(k)
        keys[s.other].add(k)
    return {n: {k for k in v if k} for n, v in keys.items()}


def _price(plan: Plan) -> None:
    """Attributes and live ranks of the inputs, times n for semi-joins (first input only) and m for joins.

    A rank lives while a later step needs it. Reduce steps are not charged: they are charged alike in plans that share them.
    """
    steps = [*plan.semijoins, *plan.joins]
    attrs = {n: set(a) for n, a in plan.schemas.items()}
    of = {n: n for n in plan.schemas}
    need = [key_of(plan.schemas[s.relation] & plan.schemas[s.other]) for s in steps]

    def ranks(name: str, at: int) -> set:
        return {need[k] for k in range(at, len(steps)) if name in (of[steps[k].relation], of[steps[k].other])}

    plan.n_cost = plan.m_cost = 0
    for at, s in enumerate(steps):
        a, b = of[s.relation], of[s.other]
        if s.kind == "semijoin":
            plan.n_cost += len(attrs[a]) + len(ranks(a, at))
        else:
            plan.m_cost += len(attrs[a]) + len(ranks(a, at)) + len(attrs[b]) + len(ranks(b, at))
            attrs[a] |= attrs[b]
            of = {n: a if r == b else r for n, r in of.items()}


def all_plans(edges: dict[str, frozenset[str]], outputs: frozenset[str], bags: frozenset[str] = frozenset()) -> list[Plan]:
    out = []
    for tree in free_connex_trees(edges, outputs):
        _, schema = reduce_steps(tree, edges, outputs, bags)
        nodes = [n for n in schema]
        choices = [list(permutations([c for c in tree.children(n) if c in schema])) for n in nodes]
        out += [build(tree, edges, outputs, dict(zip(nodes, chosen)), bags) for chosen in product(*choices)]
    return out


def choose(edges: dict[str, frozenset[str]], outputs: frozenset[str], n: float = 1.0, m: float = 1.0, bags: frozenset[str] = frozenset()) -> Plan:
    """The cheapest plan by public sizes alone; the reduce phase counts first, since an early stop saves the rest."""
    return min(all_plans(edges, outputs, bags), key=lambda p: (p.n_cost * n + p.m_cost * m, len(p.reduce), p.tree.root, [str(s) for s in p.steps]))


def priced(plan: Plan, edges: dict[str, frozenset[str]], sizes: dict[str, int], m: int, bits: dict[str, int] | None = None, rank_bits: int = 64) -> int:
    """Cost with each relation's own size: (attributes + live ranks) times rows, in words, or in bits if `bits` names widths.

    The reduce phase is charged too: a grouping its relation, an absorption the relation that absorbs. Joins are charged m rows
    of both inputs, semi-joins their first input.
    """
    attrs, of = {n: set(a) for n, a in edges.items()}, {n: n for n in edges}
    steps = plan.steps

    def key(s: Step) -> tuple[str, ...]:
        return key_of(s.attrs) if s.kind == "group" else key_of(plan_attrs[s.relation] & plan_attrs[s.other])

    plan_attrs, needed = {n: set(a) for n, a in edges.items()}, []
    for s in steps:  # the key that each step uses, as schemas shrink and grow
        needed.append(key(s))
        if s.kind == "group":
            plan_attrs[s.relation] = set(s.attrs)
        elif s.kind == "join":
            plan_attrs[s.relation] |= plan_attrs[s.other]

    def width(name: str, at: int) -> int:
        live = {needed[k] for k in range(at, len(steps)) if name in (of.get(steps[k].relation), of.get(steps[k].other)) and set(needed[k]) <= attrs[name]} - {()}
        words = sum((bits or {}).get(a, 64) for a in attrs[name]) if bits else len(attrs[name])
        return words + len(live) * (rank_bits if bits else 1)

    total = 0
    for at, s in enumerate(steps):
        a, b = of[s.relation], of.get(s.other)
        if s.kind == "join":
            total += m * (width(a, at) + width(b, at))
            attrs[a] |= attrs[b]
            of = {n: a if r == b else r for n, r in of.items()}
        else:
            total += sizes[a] * width(a, at)
            if s.kind == "group":
                attrs[a] = set(s.attrs)
            elif s.kind == "absorb":
                of = {n: a if r == b else r for n, r in of.items()}
    return total


def choose_sized(edges: dict[str, frozenset[str]], outputs: frozenset[str], sizes: dict[str, int], m: int, bags: frozenset[str] = frozenset(), bits: dict[str, int] | None = None) -> Plan:
    """The cheapest plan for these public sizes, the reduce phase included."""
    return min(all_plans(edges, outputs, bags), key=lambda p: (priced(p, edges, sizes, m, bits), p.tree.root, [str(s) for s in p.steps]))
