"""The registry, shares and circuits, joins of the kit."""

import random

from pyspark.sql import functions as F

import __spark_entry__
from mpcrel import relkit
from mpcrel.functions import shares


def test_registry_is_consistent():
    names, sql = __spark_entry__.queries(), __spark_entry__.oracle_sql()
    assert len(names) > 100 and set(sql) <= set(names) and all(isinstance(s, str) for s in sql.values())


def test_densest_graphs_are_registered(spark):
    sf, names = "/root/testdata/sf0.001", __spark_entry__.queries()
    assert {"graph_k125", "graph_k65"} <= set(names)
    assert names["plain_graph_k65"](spark, sf).count() == names["graph_k65"](spark, sf).count() == 2619


def test_shares_open_from_any_two_views_and_change_with_the_nonce(spark):
    rows = spark.createDataFrame([(i, v) for i, v in enumerate([0, -1, 2**62, -(2**62), 17])], "__pos long, x long")
    one, two = shares.share(rows, ["x"], "a"), shares.share(rows, ["x"], "b")
    for pair in ((0, 1), (1, 2), (0, 2)):
        got = shares.open_views({p: shares.party_view(one, ["x"], p) for p in pair}, ["x"])
        assert sorted(map(tuple, got.select("__pos", "x").collect())) == sorted(map(tuple, rows.collect()))
    assert one.select("x.s0").collect() != two.select("x.s0").collect()
    assert one.select("x.s0").collect() == shares.share(rows, ["x"], "a").select("x.s0").collect()  # a repeated task draws the same
    fresh = shares.refresh_shares(one, ["x"], "c")
    assert fresh.select("x.s0").collect() != one.select("x.s0").collect()
    assert shares.open_shares(fresh, ["x"]).select("x").collect() == rows.select("x").collect()


def test_circuits_on_extreme_words(spark):
    rng = random.Random(1)
    values = [(rng.choice([0, 1, -1, 2**62, -(2**63), 2**63 - 1, rng.randrange(-(2**63), 2**63)]), rng.choice([0, 1, -1, 5, rng.randrange(-(2**63), 2**63)])) for _ in range(40)]
    rows = spark.createDataFrame([(i, a, b) for i, (a, b) in enumerate(values)], "__pos long, a long, b long")
    c = shares.Circuit(shares.share(rows, ["a", "b"], "n", strong=False), "n")
    outs = {"add": c.add("a", "b"), "sub": c.sub("a", "b"), "lt": c.lt("a", "b"), "eq": c.eq("a", "b"), "or_": c.or_("a", "b")}
    got = shares.open_shares(c.df.select("__pos", *(F.col(w).alias(n) for n, w in outs.items())), list(outs)).orderBy("__pos").collect()
    wrap = lambda v: (v + 2**63) % 2**64 - 2**63
    for (a, b), r in zip(values, got):
        assert (r["add"], r["sub"], r["or_"]) == (wrap(a + b), wrap(a - b), a | b)
        assert r["eq"] == int(a == b)
        if abs(a - b) < 2**63:
            assert r["lt"] == int(a < b)


def test_asof_join_in_slices(spark):
    rng = random.Random(2)
    left = [(i, rng.randrange(3), rng.randrange(200)) for i in range(60)]
    right = [(rng.randrange(3), rng.randrange(200), i) for i in range(40)]
    a, b = spark.createDataFrame(left, "id long, k long, t long"), spark.createDataFrame(right, "k long, at long, v long")
    want = sorted((i, max(((at, v) for kk, at, v in right if kk == k and at <= t), default=(None, None))[1]) for i, k, t in left)
    for width in (None, 7, 1000):
        got = relkit.asof_join(a, b, ["k"], "t", "at", ["v"], slice_width=width)
        assert sorted((r["id"], r["asof_v"]) for r in got.collect()) == want
