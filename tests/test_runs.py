"""Intersections by runs of ranks, and ranks repaired by words of bits."""

import random
from dataclasses import replace

import pytest

from mpcrel.config import MpcConf
from mpcrel.model import LIVE, POS, load, rank_col, set_dummy
from mpcrel.operators import arrays, ranks, relational
from pyspark.sql import functions as F

CONF = MpcConf(chunk=64, broadcast_rows=0)


@pytest.fixture(scope="module")
def sides(spark):
    """A key that fills several chunks, others of a few rows, some on one side alone, and dummies on both."""
    rng = random.Random(3)
    xs = [(i, 7 if i % 3 else rng.randrange(60)) for i in range(900)]
    ys = [(rng.randrange(20, 80) if j % 9 else 7, j) for j in range(120)]
    x = ranks.attach(load(spark.createDataFrame(xs, "a long, b long"), ["a", "b"], conf=CONF), ["a", "b"], 900)
    y = ranks.attach(load(spark.createDataFrame(ys, "b long, c long"), ["b", "c"], conf=CONF), ["b", "c"], 900)
    x, y = ranks.refresh(set_dummy(x, F.col("a") % 5 != 0)), ranks.refresh(set_dummy(y, F.col("c") % 4 != 0))
    return x, y, [r for r in xs if r[0] % 5], [r for r in ys if r[1] % 4]


def fine(rel):
    return all(r["violations"] == 0 for r in ranks.verify(rel).collect())


def live(rel, *cols):
    return sorted(tuple(r) for r in rel.df.where(F.col(LIVE) == 1).select(*cols).collect())


def test_partners_are_found_by_runs_of_ranks(sides):
    x, y, xs, ys = sides
    assert fine(x) and fine(y)
    keys = {b for b, _ in ys}
    for anti in (False, True):
        met = relational.semijoin(x, y, anti=anti)
        assert live(met, "a", "b") == sorted(r for r in xs if (r[1] in keys) != anti) and fine(met) and met.df.count() == 900
    degrees = relational.degrees(x, y, ("b",))
    assert {r["a"]: r["__d"] for r in degrees.collect()} == {a: sum(k == b for k, _ in ys) if a % 5 else 0 for a, b in ((r["a"], r["b"]) for r in x.df.collect())}
    pairs = sorted((a, b, c) for a, b in xs for k, c in ys if k == b)
    for mode in ("auto", "index"):
        joined = relational.join(x, y, len(pairs) + 30, mode=mode)
        assert live(joined, "a", "b", "c") == pairs and fine(joined) and joined.df.count() == len(pairs) + 30


def test_rows_do_not_move_to_be_marked_and_forms_of_repair_agree(sides):
    x, y, _, _ = sides
    runs = arrays.segments(x, ["b"]).join(arrays.segments(y, ["b"]).select("b"), ["b"])
    tagged = arrays.marked(x, ["b"], runs)
    own_side = tagged._jdf.queryExecution().executedPlan().toString().split("BroadcastExchange")[0]
    assert "BroadcastHashJoin" in own_side and "Exchange hashpartitioning" not in own_side
    dummies = replace(x, df=tagged)
    dummies = set_dummy(dummies, F.col("hit") == 1).settled()
    got = [live(ranks.refresh(dummies, form), POS, rank_col("a"), rank_col("b")) for form in ("words", "wide", "slim")]
    assert got[0] == got[1] == got[2]
