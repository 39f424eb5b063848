"""Trees, plans, costs and meters: the published tables and shapes."""

import pathlib

import pytest
from pyspark.sql import functions as F

import __spark_entry__
from mpcrel import workloads
from mpcrel.config import MpcConf
from mpcrel.model import settle
from mpcrel.plans import baselines, hypergraph, meter, planner
from mpcrel.plans import query as q

FOUR = {"R1": frozenset("AB"), "R2": frozenset("ADE"), "R3": frozenset("BCF"), "R4": frozenset("CFG")}


def test_plan_costs_of_both_trees_and_child_orders():
    costs = {(p.tree.root, tuple(s.other for s in p.joins)): (p.n_cost, p.m_cost) for p in planner.all_plans(FOUR, frozenset("ABCDE"))}
    assert costs == {("R1", ("R2", "R3")): (15, 16), ("R1", ("R3", "R2")): (15, 15), ("R2", ("R3", "R1")): (15, 15)}


def test_steps_of_the_four_relation_plan():
    plan = next(p for p in planner.all_plans(FOUR, frozenset("ABCDE")) if p.tree.root == "R1" and p.joins[0].other == "R2")
    assert [str(s) for s in plan.reduce] == ["group R4 [C,F]", "absorb R3 R4", "group R3 [B,C]"]
    assert len(plan.semijoins) == 4 and len(plan.joins) == 2


def test_output_size_plan_takes_five_actions():
    plan = planner.choose(FOUR, frozenset("ABCDE"))
    schema = {"R1": frozenset("AB"), "R2": frozenset("ADE"), "R3": frozenset("BC")}
    tree = next(t for t in hypergraph.join_trees(schema) if t.root == "R1")
    steps, left = planner.reduce_steps(tree, schema, frozenset())
    assert len(steps) == 5 and set(left) == {"R1"} and not left["R1"] and plan.schemas["R3"] == frozenset("BC")


def test_roots_and_refusals(spark):
    assert [t.root for t in hypergraph.free_connex_trees(FOUR, frozenset("ABCDE"))] == ["R1", "R2"]
    assert [t.root for t in hypergraph.free_connex_trees(FOUR, frozenset("ABCD"))] == ["R1"]
    for edges, outputs in (({"a": "AB", "b": "BC", "c": "AC"}, "ABC"), ({"a": "AB", "b": "BC"}, "AC")):
        with pytest.raises(hypergraph.UnsupportedQuery):
            hypergraph.free_connex_trees({k: frozenset(v) for k, v in edges.items()}, frozenset(outputs))
    with pytest.raises(hypergraph.UnsupportedQuery):
        q5 = dict(workloads.q5f().edges)
        q5["customer"] = frozenset({"custkey", "nationkey"})
        hypergraph.free_connex_trees(q5, frozenset().union(*q5.values()))
    with pytest.raises(ValueError):
        MpcConf(adversary="malicious")


def test_workloads_have_plans_whose_rank_keys_exist_at_the_owners(spark):
    for make in workloads.WORKLOADS.values():
        query = make()
        plan = query.plan()
        for name, keys in plan.keys.items():
            assert all(set(k) <= query.edges[name] for k in keys)
        assert len(plan.reduce) + len(plan.joins) >= len(query.sources) - 1


def _chain(n, m):
    own = meter.Meter()
    own.semijoin(n, n, 4, 1)
    own.join(n, n, m, 4, 4, 1, 1)
    return own


def test_traffic_is_linear_and_the_rivals_is_not():
    for n in (10**4, 10**6, 10**8):
        assert _chain(10 * n, 10 * n).bytes / _chain(n, n).bytes == pytest.approx(10, rel=0.01)
        assert meter.sort_merge_join(10 * n, 10 * n, 10 * n, 8)[0] / meter.sort_merge_join(n, n, n, 8)[0] > 10.4
        assert meter.sort_merge_join(n, n, n, 8, bitonic=True)[0] > 3 * meter.sort_merge_join(n, n, n, 8)[0]
        assert _chain(n, n).bytes < meter.sort_merge_join(n, n, n, 8, charge_sort=False)[0]
        assert _chain(n, n).bytes > meter.plaintext([(n, 4), (n, 4)], n, 7)
    step = [_chain(24_186, m).bytes for m in (20_000, 220_000, 420_000)]
    assert step[2] - step[1] == pytest.approx(step[1] - step[0], rel=1e-9)
    assert meter.amortised_ranks(10**6, 10**6, 4, 20) <= 2 * (2 * 10**6 * 4)


def test_the_nested_loop_takes_any_number_of_combinations(spark):
    numbers = lambda n, name: q.Source(lambda s, _: s.range(n), {name: F.col("id"), "k": F.col("id") % 7})
    three = q.JoinAggQuery("three", {"a": numbers(300, "x"), "b": numbers(200, "y"), "c": numbers(40, "z")}, ("x", "y", "z"), None)
    want = sum(1 for x in range(300) for y in range(x % 7, 200, 7) for z in range(x % 7, 40, 7))
    assert baselines.nested_loop(three, spark, "").count() == want


def test_a_query_leaves_nothing_but_its_answer(spark):
    settle(spark.range(1))  # sets a folder where the session has none
    folder = pathlib.Path(spark.sparkContext.getCheckpointDir().removeprefix("file:"))
    before = set(folder.iterdir())
    out = q.answer(workloads.line3(), spark, "/root/testdata/sf0.001")
    made = set(folder.iterdir()) - before
    assert len(made) == 1 and {pathlib.Path(f.removeprefix("file:")).parent for f in out.inputFiles()} == {p.resolve() for p in made}
    assert out.count() == q.plain(workloads.line3(), spark, "/root/testdata/sf0.001").count()


@pytest.mark.parametrize("name", ["free_connex_catalogue", "join_tree_enumeration", "ownership_layouts", "plan_cost_bits", "plan_cost_table", "plan_cost_unequal"])
def test_costs_and_plans_read_the_given_tables(spark, tmp_path, name):
    run = __spark_entry__.queries()[name]
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        run(spark, str(tmp_path)).collect()
    few, more = (run(spark, f"/root/testdata/sf{x}").collect() for x in ("0.001", "0.01"))
    assert len(few) == len(more) and (name == "plan_cost_bits" or all(a[-1] < b[-1] for a, b in zip(few, more)))
