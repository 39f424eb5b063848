"""Rules that the operators must keep beyond the worked examples: sizes, refusals, sized plans, streams' sinks, audits."""

import pytest
from pyspark.sql import functions as F

from mpcrel import model, workloads
from mpcrel.config import MpcConf
from mpcrel.functions import shares
from mpcrel.functions.semiring import SUM_PRODUCT
from mpcrel.model import LIVE, POS, Relation, rank_col, reveal
from mpcrel.operators import arrays, ranks, relational, scan
from mpcrel.plans import planner, rivals


def relation(spark, rows, attrs, live=None, anns=()):
    data = [(i, 1 if live is None else live[i - 1], *r) for i, r in enumerate(rows, 1)]
    kinds = ", ".join(f"{a} long" for a in (*attrs, *anns))
    return Relation(spark.createDataFrame(data, f"{POS} long, {LIVE} long, {kinds}"), tuple(attrs), (), len(rows), tuple(anns), MpcConf(chunk=2))


def test_absorbing_a_child_without_live_rows_keeps_the_size(spark):
    parent, child = relation(spark, [(1, 5), (2, 6), (3, 7)], ["a"], anns=["__ann"]), relation(spark, [(9,)], [], live=[0], anns=["__ann"])
    out = relational.reduce_join(parent, child, SUM_PRODUCT)
    assert out.size == out.df.count() == 3 and reveal(out).count() == 0
    full = relational.reduce_join(parent, relation(spark, [(9,)], [], anns=["__ann"]), SUM_PRODUCT)
    assert sorted(r["__ann"] for r in reveal(full).collect()) == [45, 54, 63]


@pytest.mark.parametrize("mode", ["explode", "scan"])
def test_too_small_a_bound_is_an_error(spark, mode):
    rel = relation(spark, [(1, 3), (2, 4)], ["k", "d"])
    assert arrays.expand(rel.df, "d", 7, 2, mode=mode, conf=rel.conf).where("__copy is not null").count() == 7
    with pytest.raises(Exception, match="do not fit"):
        arrays.expand(rel.df, "d", 5, 2, mode=mode, conf=rel.conf).collect()


def test_scans_of_many_chunks_have_a_third_level(spark):
    conf = MpcConf(chunk=3)
    df = spark.range(1, 41).select(F.col("id").alias(POS), (F.col("id") % 7).alias("x"))
    got = scan.prefix(df, {"a": ("sum", F.col("x")), "m": ("max", F.col("x"))}, size=40, conf=conf, totals={"a": "t"}).orderBy(POS).collect()
    values = [i % 7 for i in range(1, 41)]
    assert [(r["a"], r["m"], r["t"]) for r in got] == [(sum(values[: i + 1]), max(values[: i + 1]), sum(values)) for i in range(40)]
    before = scan.prefix(df, {"m": ("min", F.col("x"))}, size=40, conf=conf, exclusive=True).orderBy(POS).collect()
    assert [r["m"] for r in before] == [min(values[:i], default=None) for i in range(40)]
    chain = lambda f, g: F.struct((f["p"] * g["p"] % 101).alias("p"), ((f["q"] * g["p"] + g["q"]) % 101).alias("q"))
    maps = df.select(POS, (F.col("x") + 2).alias("p"), F.col("x").alias("q"))
    out, p, q = [], 1, 0
    for x in values:
        p, q = p * (x + 2) % 101, (q * (x + 2) + x) % 101
        out.append((p, q))
    assert [(r["p"], r["q"]) for r in scan.monoid(maps, ["p", "q"], chain, {"p": 1, "q": 0}, 40, conf=conf).orderBy(POS).collect()] == out


def test_plans_are_chosen_by_each_relations_size():
    edges = {"R1": frozenset("AB"), "R2": frozenset("ADE"), "R3": frozenset("BCF"), "R4": frozenset("CFG")}
    even, outputs = dict.fromkeys(edges, 100), frozenset("ABCDE")
    for p in planner.all_plans(edges, outputs):
        once, tenfold = planner.priced(p, edges, even, 100), planner.priced(p, edges, dict.fromkeys(edges, 1000), 1000)
        assert tenfold == 10 * once
        assert planner.priced(p, edges, even, 200) - once == 100 * p.m_cost
    assert planner.choose_sized(edges, outputs, {**even, "R2": 10**6}, 100).tree.root in ("R1", "R2")
    query = workloads.q3()
    sizes = {"customer": 10, "orders": 100, "lineitem": 400}
    assert planner.choose_sized(query.edges, frozenset(query.outputs), sizes, 400, query.bags).tree.root == "orders"


def test_sort_network_on_shares(spark):
    rows = [(i, k, 10 * k) for i, k in enumerate([5, 3, 9, 1, 7], 1)]
    done, comparators = shares.sort_network(spark.createDataFrame(rows, f"{POS} long, k long, v long"), "k", ["v"], 5, "t")
    assert [(r["k"], r["v"]) for r in done.orderBy(POS).collect()] == [(k, 10 * k) for k in (1, 3, 5, 7, 9)] and comparators == 4 * 6


def test_rows_are_ordered_by_one_sort_and_a_key_that_fills_blocks_is_dealt(spark):
    rows = spark.range(1200).select(F.when(F.col("id") < 700, 5).otherwise(F.col("id") % 40).alias("k"), (F.col("id") % 2).alias("side"), "id")
    placed, n = ranks.in_order(rows, ["k", "side"], MpcConf(chunk=32))
    got = sorted((r["__pos"], r["k"], r["side"], r["id"]) for r in placed.collect())
    assert n == 1200 and [g[0] for g in got] == list(range(1, 1201)) and sorted(g[3] for g in got) == list(range(1200))
    assert [g[1:3] for g in got] == sorted(g[1:3] for g in got)
    sizes = [r["count"] for r in spark.read.parquet(*placed.inputFiles()).groupBy(F.input_file_name()).count().collect()]
    assert len(sizes) > 25 and max(sizes) < 200
    a, b = rows.where("id >= 690").select("k", F.col("id").alias("x")), rows.where("id % 7 = 0").select("k", F.col("id").alias("y"))
    with model.recorded() as shapes:
        out, m = rivals.sort_merge_join(a, b, ["k"], MpcConf(chunk=32))
    want = a.join(b, "k").select("k", "x", "y")
    assert m == out.count() == want.count() and not out.exceptAll(want).count()
    assert all("__rk_k_side" not in columns for columns, _, _ in shapes) and len(shapes) == 3


def test_the_sorting_rival_joins_hot_and_missing_keys(spark):
    a, b = [(k % 3, k) for k in range(7)], [(k % 2, 100 + k) for k in range(5)]
    out, m = rivals.sort_merge_join(spark.createDataFrame(a, "k long, x long"), spark.createDataFrame(b, "k long, y long"), ["k"], MpcConf(chunk=4))
    want = sorted((k, x, y) for k, x in a for j, y in b if j == k)
    assert sorted((r["k"], r["x"], r["y"]) for r in out.collect()) == want and m == len(want)


def test_recorded_shapes_do_not_follow_the_data(spark):
    seen = []
    for keep in (0, 99):
        rel = relation(spark, [(i, i) for i in range(9)], ["a"], anns=["__ann"])
        rel = rel.on(rel.df.withColumn(rank_col("a"), F.col(POS)), keys=(("a",),))
        with model.recorded() as shapes:
            relational.aggregate(relational.select(rel, F.col("a") > keep), ["a"])
        seen.append(shapes)
    assert seen[0] == seen[1] and all(rows == 9 for _, rows, _ in seen[0])


def test_a_full_sort_deals_rows_over_a_thousand_blocks(spark):
    n = 6000
    rows = [(i, (i * 7919) % n // 2) for i in range(1, n + 1)]
    rel = Relation(spark.createDataFrame([(i, 1, k) for i, k in rows], f"{POS} long, {LIVE} long, k long"), ("k",), (), n, (), MpcConf(chunk=5))
    got = {r[POS]: r[rank_col("k")] for r in ranks.consistent_order(rel, ["k"], n, method="sort").collect()}
    assert got == {i: at for at, (i, _) in enumerate(sorted(rows, key=lambda r: (r[1], r[0])), 1)}
