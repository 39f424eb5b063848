"""Queries, their oblivious and plain execution, and the output-size query."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import DEFAULT, MpcConf
from ..functions.semiring import COUNT, SUM_PRODUCT, Semiring
from ..model import LIVE, Relation, key_of, pad_to, release, reveal, scratch
from ..operators import relational as ops
from ..operators.ranks import attach
from . import planner
from .meter import Meter


@dataclass(frozen=True)
class Source:
    """One owner's relation: where it comes from, its attributes as expressions, a selection, annotations, the owner."""

    table: Callable[[SparkSession, str], DataFrame]
    attrs: dict[str, Column]
    where: Column | None = None
    anns: dict[str, Column] = field(default_factory=dict)
    owner: int = 0
    key: tuple[str, ...] | None = None  # attributes that tell rows apart; without, rows may repeat
    block: Callable[[Relation], Relation] | None = None  # operators that make the relation from its rows, before the query
    block_plain: Callable[[DataFrame], DataFrame] | None = None  # the same on a plain table


@dataclass(frozen=True)
class JoinAggQuery:
    """Aggregate over the semiring, on the outputs, of the natural join of the selected relations."""

    name: str
    sources: dict[str, Source]
    outputs: tuple[str, ...]
    semiring: Semiring | None = SUM_PRODUCT
    residual: Column | None = None  # a selection on the join's result

    @property
    def edges(self) -> dict[str, frozenset[str]]:
        return {n: frozenset(s.attrs) for n, s in self.sources.items()}

    def plan(self, n: float = 1.0, m: float = 1.0) -> planner.Plan:
        return planner.choose(self.edges, frozenset(self.outputs), n, m, self.bags)

    @property
    def bags(self) -> frozenset[str]:
        """Relations whose rows may repeat; a query without a semiring keeps repeated rows apart."""
        return frozenset(n for n, s in self.sources.items() if self.semiring and not s.key)


def locally_joined(query: JoinAggQuery, owners: dict[str, int]) -> JoinAggQuery:
    """The query after owners have joined, in the clear, their own relations that share attributes; annotations multiply."""
    from dataclasses import replace

    sources = dict(query.sources)
    for b in list(sources):
        a = next((n for n in sources if n != b and b in sources and owners[n] == owners[b] and set(sources[n].attrs) & set(sources[b].attrs)), None)
        if a is None or b not in sources:
            continue
        ring, parts = query.semiring or COUNT, [replace(query, sources={n: sources[n]}) for n in (a, b)]

        def table(spark, sf_dir, names=(a, b), parts=parts, ring=ring):
            frames = []
            for n, part in zip(names, parts):
                cols, passes = columns(part, n)
                frames.append(part.sources[n].table(spark, sf_dir).where(passes).select(*cols))
            key = sorted(set(parts[0].sources[names[0]].attrs) & set(parts[1].sources[names[1]].attrs))
            both = frames[0].join(frames[1].withColumnsRenamed({n: f"__o_{n}" for n in ring.names}), key)
            product = ring.times([F.col(n) for n in ring.names], [F.col(f"__o_{n}") for n in ring.names])
            return both.withColumns({f"__p_{n}": c for n, c in zip(ring.names, product)}).drop(*ring.names).withColumnsRenamed({f"__p_{n}": n for n in ring.names})

        attrs = {x: F.col(x) for n in (a, b) for x in sources[n].attrs}
        keys = [k for k in (sources[a].key, sources[b].key) if k]
        sources[a] = Source(table, attrs, None, {n: F.col(n) for n in ring.names} if query.semiring else {}, owners[a], tuple(dict.fromkeys(x for k in keys for x in k)) if len(keys) == 2 else None)
        del sources[b]
    return replace(query, name=f"{query.name}, local joins", sources=sources)


def columns(query: JoinAggQuery, name: str) -> tuple[list[Column], Column]:
    """The relation's attributes and annotations as columns, and whether a row passes its selection."""
    s, ring = query.sources[name], query.semiring or COUNT
    anns = {**ring.ones(), **s.anns}
    return [*(c.alias(a) for a, c in s.attrs.items()), *(c.cast("long").alias(a) for a, c in anns.items())], F.lit(True) if s.where is None else F.coalesce(s.where, F.lit(False))


def prepare(query: JoinAggQuery, spark: SparkSession, sf_dir: str, plan: planner.Plan, conf: MpcConf = DEFAULT, preselect: bool = False) -> dict[str, Relation]:
    """What the owners do: encode, mark rows that fail the local selection as dummies, attach ranks for the plan's keys.

    With `preselect` owners drop these rows instead, which reveals how many are left. A relation with a block of operators
    goes through it here, and keeps the ranks of the keys that the block keeps.
    """
    from ..operators.ranks import positions

    with scratch():
        return _prepared(query, spark, sf_dir, plan, conf, preselect, positions)


def _prepared(query: JoinAggQuery, spark: SparkSession, sf_dir: str, plan: planner.Plan, conf: MpcConf, preselect: bool, positions) -> dict[str, Relation]:
    rels, anns = {}, tuple((query.semiring or COUNT).names)
    for name, s in query.sources.items():
        cols, passes = columns(query, name)
        table = s.table(spark, sf_dir).where(passes) if preselect else s.table(spark, sf_dir)
        rows = table.select(*cols, passes.cast("long").alias(LIVE))
        placed, size = positions(rows, list(s.attrs), conf)
        rel = Relation(placed, tuple(s.attrs), (), size, anns, conf, (s.key,) if s.key and not s.block else ())
        rels[name] = rel if size else pad_to(rel, 1)
    buckets = max(r.size for r in rels.values())
    ranked = {}
    for name in list(rels):
        ranked[name] = attach(rels.pop(name), sorted(plan.keys[name]), buckets)
        release(*(r.df for r in (*rels.values(), *ranked.values())))
    return {name: query.sources[name].block(r) if query.sources[name].block else r for name, r in ranked.items()}


def _aggregate(rel: Relation, attrs, ring: Semiring) -> Relation:
    return ops.aggregate(rel, attrs, {n: (op, F.col(n)) for n, op in zip(ring.names, ring.plus)})


def reduce_phase(rels: dict[str, Relation], steps: list[planner.Step], ring: Semiring, meter: Meter, mode: str = "auto") -> dict[str, Relation]:
    rels = dict(rels)
    with scratch():
        for s in steps:
            r = rels[s.relation]
            if s.kind == "group":
                meter.aggregate(r.size, r.width, len(r.keys), len(s.attrs))
                rels[s.relation] = _aggregate(r, s.attrs, ring)
            else:
                child = rels.pop(s.other)
                meter.semijoin(r.size, child.size, r.width, len(r.keys), len(ring.names))
                rels[s.relation] = ops.reduce_join(r, child, ring, mode)
            _keep(rels)
    return rels


def _keep(rels: dict[str, Relation]) -> None:
    release(*(r.df for r in rels.values()))


def semijoin_phase(rels: dict[str, Relation], steps: list[planner.Step], meter: Meter, mode: str = "auto") -> dict[str, Relation]:
    rels = dict(rels)
    with scratch():
        for s in steps:
            r, other = rels[s.relation], rels[s.other]
            meter.semijoin(r.size, other.size, r.width, len(r.keys))
            rels[s.relation] = ops.semijoin(r, other, mode=mode)
            _keep(rels)
    return rels


def output_size(rels: dict[str, Relation], plan: planner.Plan, meter: Meter, mode: str = "auto") -> int:
    """The only data-dependent number that is opened: the join of the reduced relations, counted on no attribute."""
    edges = {n: frozenset(r.attrs) for n, r in rels.items()}
    steps, _ = planner.reduce_steps(_subtree(plan.tree, set(rels)), edges, frozenset(), frozenset(rels))
    ones = {n: r.on(r.df.withColumns(dict(COUNT.ones())), anns=COUNT.names) for n, r in rels.items()}
    with scratch():
        (root,) = reduce_phase(ones, steps, COUNT, meter, mode).values()
        m = int(root.df.where(F.col(LIVE) == 1).agg(F.coalesce(F.sum(COUNT.names[0]), F.lit(0))).first()[0])
        release(*(r.df for r in rels.values()))
    return m


def _subtree(tree, names: set[str]):
    from .hypergraph import Tree

    return Tree(tuple((n, p) for n, p in tree.parents if n in names))


def execute(query: JoinAggQuery, spark: SparkSession, sf_dir: str, m: int | None = None, conf: MpcConf = DEFAULT, meter: Meter | None = None, mode: str = "auto", pad: str = "output", size_only: bool = False, preselect: bool = False, expansion: str = "explode", plan: planner.Plan | None = None):
    """The shared result as a relation (its live rows are the answer), or the output size alone.

    With m None the output-size query runs first. pad='exact' lets intermediate joins take their own sizes, which reveals
    them: it serves as a contrast in audits.
    """
    with scratch():
        return _executed(query, spark, sf_dir, m, conf, Meter() if meter is None else meter, mode, pad, size_only, preselect, expansion, plan or query.plan())


def _executed(query: JoinAggQuery, spark: SparkSession, sf_dir: str, m: int | None, conf: MpcConf, meter: Meter, mode: str, pad: str, size_only: bool, preselect: bool, expansion: str, plan: planner.Plan):
    ring = query.semiring or COUNT
    rels = prepare(query, spark, sf_dir, plan, conf, preselect)
    rels = reduce_phase(rels, plan.reduce, ring, meter, mode)
    _keep(rels)
    if len(rels) == 1:
        (root,) = rels.values()
        return int(root.df.agg(F.coalesce(F.sum(LIVE), F.lit(0))).first()[0]) if size_only else root
    rels = semijoin_phase(rels, plan.semijoins, meter, mode)
    _keep(rels)
    if m is None:
        m = max(1, output_size(rels, plan, meter, mode))
    if size_only:
        return m if m > 1 else output_size(rels, plan, Meter(), mode)
    later = [key_of(plan.schemas[s.relation] & plan.schemas[s.other]) for s in plan.joins]
    for k, s in enumerate(plan.joins):
        a, b = ops.drop_ranks(rels[s.relation], later[k:]), ops.drop_ranks(rels.pop(s.other), later[k:])
        size = m if pad == "output" else max(1, ops.join_size(a, b))
        meter.join(a.size, b.size, size, a.width, b.width, len(a.keys), len(b.keys))
        rels[s.relation] = ops.join(a, b, size, ring, mode, expansion)
        _keep(rels)
    (root,) = rels.values()
    if query.residual is not None:
        meter.select(root.size, root.width, len(root.keys))
        root = ops.select(ops.drop_ranks(root, []), query.residual)
        _keep({query.name: root})
    return root


def answer(query: JoinAggQuery, spark: SparkSession, sf_dir: str, **options) -> DataFrame:
    """The revealed answer: outputs, and annotations if the query has a semiring."""
    with scratch():
        out = reveal(execute(query, spark, sf_dir, **options))
        release(out)
    return out.select(*query.outputs, *(query.semiring.names if query.semiring else ()))


def plain(query: JoinAggQuery, spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same plan on plain tables in Catalyst's hands: early aggregation below the joins, no dummies, no ranks."""
    plan, ring = query.plan(), query.semiring or COUNT
    dfs = {}
    for name, s in query.sources.items():
        cols, passes = columns(query, name)
        dfs[name] = s.table(spark, sf_dir).where(passes).select(*cols)
        dfs[name] = s.block_plain(dfs[name]) if s.block_plain else dfs[name]
    attrs = {n: set(s.attrs) for n, s in query.sources.items()}
    call = {"sum": F.sum, "max": F.max, "min": F.min}

    def combine(a: DataFrame, b: DataFrame, key: list[str]) -> DataFrame:
        other = b.withColumnsRenamed({n: f"__o_{n}" for n in ring.names})
        both = a.join(other, key) if key else a.crossJoin(other)
        product = ring.times([F.col(n) for n in ring.names], [F.col(f"__o_{n}") for n in ring.names])
        return both.withColumns({f"__p_{n}": c for n, c in zip(ring.names, product)}).drop(*ring.names, *(f"__o_{n}" for n in ring.names)).withColumnsRenamed({f"__p_{n}": n for n in ring.names})

    for s in [*plan.reduce, *plan.joins]:
        if s.kind == "group":
            dfs[s.relation] = dfs[s.relation].groupBy(*sorted(s.attrs)).agg(*(call[op](n).alias(n) for n, op in zip(ring.names, ring.plus)))
            attrs[s.relation] = set(s.attrs)
        else:
            dfs[s.relation] = combine(dfs[s.relation], dfs.pop(s.other), sorted(attrs[s.relation] & attrs[s.other]))
            attrs[s.relation] |= attrs.pop(s.other)
    (out,) = dfs.values()
    if query.residual is not None:
        out = out.where(query.residual)
    return out.select(*query.outputs, *(query.semiring.names if query.semiring else ()))
