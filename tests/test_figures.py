"""The worked examples and small property tests of primitives and operators."""

import itertools
import random

import pytest
from pyspark.sql import functions as F

from mpcrel.config import MpcConf
from mpcrel.model import LIVE, POS, Relation, pad_to, rank_col, reveal
from mpcrel.operators import arrays, ranks, relational, scan

SMALL = MpcConf(chunk=2)


def relation(spark, rows, attrs, conf=SMALL, live=None):
    data = [(i, 1 if live is None else live[i - 1], *r) for i, r in enumerate(rows, 1)]
    kinds = ", ".join(f"{a} {'string' if rows and isinstance(rows[0][k], str) else 'long'}" for k, a in enumerate(attrs))
    return Relation(spark.createDataFrame(data, f"{POS} long, {LIVE} long, {kinds}"), tuple(attrs), (), len(rows), (), conf)


def listed(df, *cols, order=POS):
    return [tuple(r) if len(cols) > 1 else r[0] for r in df.orderBy(order).select(*cols).collect()]


@pytest.mark.parametrize("chunk", [1, 2, 3, 7, 1000])
def test_scans_do_not_depend_on_chunks(spark, chunk):
    conf = MpcConf(chunk=chunk)
    rng = random.Random(chunk)
    seg, x = sorted(rng.choices(range(4), k=23)), [rng.choice([None, *range(9)]) for _ in range(23)]
    df = spark.createDataFrame([(i + 1, s, v) for i, (s, v) in enumerate(zip(seg, x))], f"{POS} long, s long, v long")
    plain = scan.prefix(df, {"a": ("sum", F.col("v")), "c": ("copy", F.col("v")), "m": ("max", F.col("v"))}, size=23, conf=conf)
    total, copied, top, want = 0, None, None, []
    for v in x:
        total, copied = total + (v or 0), v if v is not None else copied
        top = v if top is None else top if v is None else max(top, v)
        want.append((total, copied, top))
    got = listed(plain, "a", "c", "m")
    assert [(a or 0, c, m) for a, c, m in got] == want
    ran = scan.segmented(df, [F.col("s")], {"n": ("count", F.lit(1)), "a": ("sum", F.coalesce("v", F.lit(0)))}, size=23, conf=conf, last="z")
    want = []
    for k, g in itertools.groupby(zip(seg, x), lambda t: t[0]):
        g, run = list(g), 0
        for n, (_, v) in enumerate(g, 1):
            run += v or 0
            want.append((n, run, n == len(g)))
    assert listed(ran, "n", "a", "z") == want


def test_segment_example_with_dummies(spark):
    df = spark.createDataFrame([(1, 2, 10), (2, 2, 20), (3, 4, 30), (4, None, 40), (5, None, 50)], f"{POS} long, s long, x long")
    assert listed(scan.segmented(df, [F.col("s")], {"y": ("sum", F.col("x"))}, size=5, conf=SMALL), "y") == [10, 30, 30, 40, 90]


def test_consistent_sort_example(spark):
    rel = relation(spark, [("a1", 2), ("a2", 1), ("a3", 3), ("a4", 1), ("a5", 4), ("a6", 2)], ["a", "k"])
    got = ranks.consistent_order(rel, ["k"], 3, table={1: 3, 2: 3, 3: 1, 4: 3})
    assert listed(got, rank_col(["k"])) == [4, 2, 1, 3, 6, 5]


def test_consistency_between_relations(spark):
    def ranked(values):
        rel = relation(spark, [(v,) for v in values], ["B"])
        return rel.on(rel.df.withColumn(rank_col(["B"]), F.col(POS)), keys=(("B",),))

    r1 = ranked([3, 1, 1, 2])
    assert ranks.inconsistencies(r1, ranked([4, 3, 3, 1]), ["B"]).first()[0] == 0
    assert ranks.inconsistencies(r1, ranked([1, 3, 3, 4]), ["B"]).first()[0] >= 1


@pytest.mark.parametrize("mode", ["index", "lookup"])
def test_extended_intersection_example(spark, mode):
    rel = relation(spark, [("a",), ("b",), ("b",), ("x",), ("c",)], ["k"], live=[1, 1, 1, 0, 1])
    rel = rel.on(rel.df.withColumn(rank_col(["k"]), F.col(POS)), keys=(("k",),))
    y = spark.createDataFrame([(i, 1, k, i) for i, k in enumerate("bcdef", 1)], f"{POS} long, {LIVE} long, k string, v long")
    got = arrays.extended(rel, ["k"], y, ["k"], {"v": "v"}, mode=mode)
    assert listed(got, "v") == [0, 1, 1, 0, 2]


@pytest.mark.parametrize("mode", ["explode", "scan"])
def test_expansion_example(spark, mode):
    rel = relation(spark, [(3, 2, 3), (2, 4, 0), (1, 3, 2), (4, 1, 1)], ["a", "b", "d"])
    rel = rel.on(rel.df.withColumn(rank_col("a"), F.col("a")).withColumn(rank_col("b"), F.col("b")), keys=(("a",), ("b",)))
    arrays.check_degrees(rel.df, "d", 7)
    got = arrays.expand_with_ranks(rel, "d", 7, mode=mode)
    assert listed(got.df, "a", rank_col("a"), rank_col("b")) == [(3, 3, 2), (3, 4, 3), (3, 5, 4), (1, 1, 5), (1, 2, 6), (4, 6, 1), (None, 7, 7)]
    with pytest.raises(ValueError):
        arrays.check_degrees(rel.df, "d", 5)


def test_join_example(spark):
    r = relation(spark, [("a1", "b1"), ("a1", "b2"), ("a1", "b4"), ("a2", "b1"), ("a2", "b3"), ("a3", "b1"), ("a3", "b2")], ["A", "B"])
    s = relation(spark, [("b1", "c1"), ("b1", "c2"), ("b2", "c2"), ("b3", "c1"), ("b3", "c2"), ("b5", "c2"), ("b6", "c1")], ["B", "C"])
    r, s = ranks.attach(r, ["A", "B"], 7, method="sort"), ranks.attach(s, ["B", "C"], 7, method="sort")
    want = sorted((a, b, c) for a, b in [("a1", "b1"), ("a1", "b2"), ("a2", "b1"), ("a2", "b3"), ("a3", "b1"), ("a3", "b2")] for x, c in [("b1", "c1"), ("b1", "c2"), ("b2", "c2"), ("b3", "c1"), ("b3", "c2")] if x == b)
    for m in (10, 12):
        t = relational.join(r, s, m)
        assert t.size == m and t.df.count() == m
        assert sorted(map(tuple, reveal(t).select("A", "B", "C").collect())) == want
        assert {x["violations"] for x in ranks.verify(t).collect()} == {0}


def test_operators_keep_ranks_and_match_brute_force(spark):
    rng = random.Random(3)
    rows_r = [(rng.randrange(4), rng.randrange(5)) for _ in range(13)]
    rows_s = [(rng.randrange(5), rng.randrange(3)) for _ in range(9)]
    r = ranks.attach(relation(spark, rows_r, ["a", "b"], MpcConf(chunk=3)), ["a", "b", "ab"], 13)
    s = ranks.attach(relation(spark, rows_s, ["b", "c"], MpcConf(chunk=4)), ["b", "c"], 13)
    fine = lambda rel: all(x["violations"] == 0 for x in ranks.verify(rel).collect())
    picked = relational.select(r, F.col("a") > 0)
    assert fine(r) and fine(s) and fine(picked) and picked.df.count() == 13
    kept = [t for t in rows_r if t[0] > 0]
    assert sorted(map(tuple, reveal(picked).collect())) == sorted(kept)
    grouped = relational.aggregate(picked, ["a"], {"n": ("count", F.lit(1)), "t": ("sum", F.col("b"))})
    assert fine(grouped) and sorted(map(tuple, reveal(grouped).collect())) == sorted((a, len(g), sum(x[1] for x in g)) for a in {t[0] for t in kept} for g in [[t for t in kept if t[0] == a]])
    semi = relational.semijoin(picked, s, mode="index")
    assert fine(semi) and sorted(map(tuple, reveal(semi).collect())) == sorted(t for t in kept if t[1] in {b for b, _ in rows_s})
    anti = relational.semijoin(picked, s, anti=True)
    assert sorted(map(tuple, reveal(anti).collect())) == sorted(t for t in kept if t[1] not in {b for b, _ in rows_s})
    want = sorted((a, b, c) for a, b in kept for x, c in rows_s if x == b)
    assert relational.join_size(picked, s) == len(want)
    joined = relational.join(picked, s, len(want) + 3, mode="index", expansion="scan")
    assert fine(joined) and sorted(map(tuple, reveal(joined).select("a", "b", "c").collect())) == want
    padded = pad_to(picked, 20)
    assert fine(padded) and padded.df.count() == 20
    assert fine(ranks.refresh(picked, form="wide"))
    whole = relational.aggregate(picked, [], {"n": ("count", F.lit(1))})
    assert [tuple(x) for x in reveal(whole).collect()] == [(len(kept),)]
