"""The two-way sort-merge join that the method is compared with, and the two-party form, as runs on plain relations."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import DEFAULT, MpcConf
from ..functions.semiring import COUNT
from ..model import LIVE, POS, release, scratch, settle
from ..operators import ranks, scan
from .meter import Meter
from .query import JoinAggQuery, prepare, reduce_phase, semijoin_phase


def sort_merge_join(a: DataFrame, b: DataFrame, key: list[str], conf: MpcConf = DEFAULT) -> tuple[DataFrame, int]:
    """All matching pairs of a and b and how many there are, which this rival reveals.

    The union of both sides is sorted by key and side; a scan forward and one backward give each row the number of rows of
    the other side in its segment; both sides are expanded by it, and the copies of b are aligned with those of a by their
    number within the key. Takes no dummies and cannot pad.
    """
    tag = lambda df, side: df.select(*key, F.lit(side).alias("side"), F.struct(*(F.col(c) for c in df.columns)).alias(f"row{side}"))
    both = tag(a, 0).withColumn("row1", F.lit(None).cast(b.select(F.struct(*b.columns).alias("x")).schema["x"].dataType)).unionByName(
        tag(b, 1).withColumn("row0", F.lit(None).cast(a.select(F.struct(*a.columns).alias("x")).schema["x"].dataType)))
    seg, side = [F.col(k) for k in key], F.col("side")
    with scratch():
        placed, n = ranks.in_order(both, [*key, "side"], conf)
        ran = settle(scan.segmented(placed, seg, {"n0": ("count", F.when(side == 0, 1)), "j1": ("count", F.when(side == 1, 1))}, size=n, conf=conf))
        release(ran)
        back = ran.select("*", (F.lit(n + 1) - F.col(POS)).alias("__back"))
        ran = settle(scan.segmented(back, seg, {"n1": ("count", F.when(side == 1, 1))}, pos="__back", size=n, conf=conf))
        release(ran)
    # a row of side 0 has seen all of side 1 from behind; a row of side 1 all of side 0 from the front, and its own number is j1
    left = ran.where("side = 0").select(*key, "row0", F.col("n0").alias("j0"), "n1")
    right = ran.where("side = 1").select(*key, "row1", "j1", "n0")
    m = int(left.agg(F.coalesce(F.sum("n1"), F.lit(0))).first()[0])
    grow = lambda df, d: df.where(F.col(d) > 0).withColumn("copy", F.explode(F.sequence(F.lit(1).cast("long"), F.col(d))))
    lefts = grow(left, "n1").select(*key, "j0", F.col("copy").alias("j1"), "row0")
    rights = grow(right, "n0").select(*key, F.col("copy").alias("j0"), "j1", "row1")
    return lefts.join(rights.hint("merge"), [*key, "j0", "j1"]).select("row0.*", *(F.col(f"row1.{c}") for c in b.columns if c not in key)), m


def two_party(query: JoinAggQuery, spark: SparkSession, sf_dir: str) -> DataFrame:
    """Reduce and semi-join phases obliviously; the reduced relations are opened to the receiver, who joins them alone."""
    plan, ring, meter = query.plan(), query.semiring or COUNT, Meter()
    rels = reduce_phase(prepare(query, spark, sf_dir, plan), plan.reduce, ring, meter)
    if len(rels) > 1:
        rels = semijoin_phase(rels, plan.semijoins, meter)
    opened = {n: settle(r.df.where(F.col(LIVE) == 1).select(*r.attrs, *r.anns)) for n, r in rels.items()}
    attrs = {n: set(r.attrs) for n, r in rels.items()}
    for s in plan.joins:
        other = opened.pop(s.other).withColumnsRenamed({n: f"__o_{n}" for n in ring.names})
        met = opened[s.relation].join(other, sorted(attrs[s.relation] & attrs[s.other]))
        product = ring.times([F.col(n) for n in ring.names], [F.col(f"__o_{n}") for n in ring.names])
        opened[s.relation] = met.withColumns({f"__p_{n}": c for n, c in zip(ring.names, product)}).drop(*ring.names, *(f"__o_{n}" for n in ring.names)).withColumnsRenamed({f"__p_{n}": n for n in ring.names})
        attrs[s.relation] |= attrs.pop(s.other)
    (out,) = opened.values()
    return out.select(*query.outputs, *(query.semiring.names if query.semiring else ()))


def planned(query: JoinAggQuery, sizes: dict[str, int], m: int) -> Meter:
    """The meter of a query's run on relations of these sizes, without running it: a run's cost depends on nothing else."""
    plan, meter, ring = query.plan(), Meter(), query.semiring or COUNT
    n, width = dict(sizes), {k: len(a) + len(plan.keys[k]) for k, a in query.edges.items()}
    for s in plan.reduce:
        if s.kind == "group":
            meter.aggregate(n[s.relation], width[s.relation], len(plan.keys[s.relation]), len(s.attrs))
        else:
            meter.semijoin(n[s.relation], n[s.other], width[s.relation], len(plan.keys[s.relation]), len(ring.names))
    for s in plan.semijoins:
        meter.semijoin(n[s.relation], n[s.other], width[s.relation], len(plan.keys[s.relation]))
    for s in plan.joins:
        meter.join(n[s.relation], n[s.other], m, width[s.relation], width[s.other], len(plan.keys[s.relation]), len(plan.keys[s.other]))
        n[s.relation], width[s.relation] = m, width[s.relation] + width[s.other]
    return meter
