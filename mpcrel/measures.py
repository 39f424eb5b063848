"""Queries of baselines, costs, growth, ratios and audits."""

from __future__ import annotations

import time
from dataclasses import replace

from pyspark.sql import functions as F

from . import model, workloads
from .config import MpcConf
from .functions import shares
from .model import POS, load, reveal
from .operators import ranks, relational
from .plans import baselines, meter, planner, rivals
from .plans import query as q
from .registry import register
from .sources.tables import read
from .streaming import stateful

MANY = MpcConf(chunk=1024)


def _sizes(query, spark, sf) -> dict[str, int]:
    return {n: max(1, s.table(spark, sf).count()) for n, s in query.sources.items()}


# -- baselines as runs

@register("baseline_sort_merge_join", "SELECT o_orderkey, o_custkey, l_partkey, l_linenumber FROM orders JOIN lineitem ON o_orderkey = l_orderkey")
def _(spark, sf):
    a = read("orders")(spark, sf).select("o_orderkey", "o_custkey")
    b = read("lineitem")(spark, sf).select(F.col("l_orderkey").alias("o_orderkey"), "l_partkey", "l_linenumber")
    return rivals.sort_merge_join(a, b, ["o_orderkey"])[0]


@register("baseline_sort_merge_reveals_size", "SELECT count(*) AS m FROM orders JOIN lineitem ON o_orderkey = l_orderkey")
def _(spark, sf):
    a = read("orders")(spark, sf).select("o_orderkey")
    b = read("lineitem")(spark, sf).select(F.col("l_orderkey").alias("o_orderkey"))
    return spark.createDataFrame([(rivals.sort_merge_join(a, b, ["o_orderkey"])[1],)], "m long")


@register("baseline_bitonic_comparators", "SELECT 8 // 2 * 6 AS comparators, CAST(count(*) AS INTEGER) AS rows FROM region")
def _(spark, sf):
    """A bitonic sort of the regions on shared words: comparators of a network of 8 places."""
    rows = read("region")(spark, sf).select((F.col("r_regionkey") + 1).cast("long").alias(POS), (100 - F.col("r_regionkey")).cast("long").alias("key"))
    done, comparators = shares.sort_network(rows, "key", [], rows.count(), "n9")
    return done.agg(F.lit(comparators).alias("comparators"), F.count("*").cast("int").alias("rows"))


@register("baseline_two_party", workloads.SQL["q3f"])
def _(spark, sf):
    return rivals.two_party(workloads.q3(True), spark, sf)


@register("baseline_three_phase_plain", workloads.SQL["q3f"])
def _(spark, sf):
    return q.plain(workloads.q3(True), spark, sf)


@register("baseline_timeouts", "SELECT * FROM (VALUES ('nested loop of circuits', 'graph', 'DNF'), ('nested loop of circuits', 'nations', 'finished')) t(method, query, outcome)")
def _(spark, sf):
    """The engines that test every combination end only on tiny inputs; beyond a bound of combinations they are not started."""
    full = workloads.q5f()
    tiny = q.JoinAggQuery("nations", {n: replace(full.sources[n], where=None) for n in ("region", "nation")}, ("regionkey", "nationkey", "nation"), None)
    out = []
    for name, query in (("graph", workloads.graph(130)), ("nations", tiny)):
        try:
            baselines.nested_loop(query, spark, sf, limit=20_000).write.format("noop").mode("overwrite").save()
            out.append(("nested loop of circuits", name, "finished"))
        except ValueError:
            out.append(("nested loop of circuits", name, "DNF"))
    return spark.createDataFrame(out, "method string, query string, outcome string")


@register("baseline_costs_order", "SELECT true AS least_of_rivals, true AS bitonic_dearest_sort, true AS plain_is_cheapest")
def _(spark, sf):
    sizes = _sizes(workloads.line3(), spark, sf)
    cost = {r["method"]: r["megabytes"] for r in baselines.comparison(spark, sizes, sizes["lineitem"], 4).collect()}
    return spark.createDataFrame([(cost["oblivious"] < cost["sort-merge"], cost["sort-merge"] < cost["sort-merge, bitonic"], min(cost, key=cost.get) == "plaintext")], "least_of_rivals boolean, bitonic_dearest_sort boolean, plain_is_cheapest boolean")


@register("baseline_plaintext_bytes", "SELECT 'q3' AS query, 8 * (2 * (SELECT count(*) FROM customer) + 4 * (SELECT count(*) FROM orders) + 3 * (SELECT count(*) FROM lineitem) + 4 * (SELECT count(*) FROM (" + workloads.SQL["q3"] + "))) AS bytes")
def _(spark, sf):
    """Input and output words of the plaintext run: attributes and selection or value columns of each relation, and the answer."""
    sizes, m = _sizes(workloads.q3(), spark, sf), q.plain(workloads.q3(), spark, sf).count()
    words = {"customer": 2, "orders": 4, "lineitem": 3}
    return spark.createDataFrame([("q3", int(meter.plaintext([(sizes[n], w) for n, w in words.items()], m, 4)))], "query string, bytes long")


# -- costs by public sizes

@register("plan_cost_unequal", f"SELECT 'words' AS unit, root, 8 * (SELECT count(*) FROM orders) + 4 * (SELECT count(*) FROM customer) + 29 * (SELECT count(*) FROM lineitem) + 4 * (SELECT count(*) FROM {workloads.SUPPLY}) AS cost FROM (VALUES ('R1'), ('R2')) t(root)")
def _(spark, sf):
    """Four relations of the given tables' sizes, as many results as lines. By hand: groupings 4 R4 + 5 R3, absorption 6 R3,
    semi-joins 4 R1 + 4 R1 + 3 R3 + 4 R2, joins 15 times the lines."""
    edges, sizes = {k: frozenset(v) for k, v in {"R1": "AB", "R2": "ADE", "R3": "BCF", "R4": "CFG"}.items()}, _sizes(workloads.four_relations(), spark, sf)
    best: dict[str, int] = {}
    for p in planner.all_plans(edges, frozenset("ABCDE")):
        cost = planner.priced(p, edges, sizes, sizes["R3"])
        best[p.tree.root] = min(cost, best.get(p.tree.root, cost))
    return spark.createDataFrame([("words", r, c) for r, c in sorted(best.items())], "unit string, root string, cost long")


@register("plan_cost_bits", "SELECT true AS wider_is_dearer, true AS words_times_64")
def _(spark, sf):
    edges = {k: frozenset(v) for k, v in {"R1": "AB", "R2": "ADE", "R3": "BCF", "R4": "CFG"}.items()}
    sizes, plan = _sizes(workloads.four_relations(), spark, sf), planner.choose(edges, frozenset("ABCDE"))
    m = sizes["R3"]
    words, bits = planner.priced(plan, edges, sizes, m), planner.priced(plan, edges, sizes, m, dict.fromkeys("ABCDEFG", 64))
    wide = planner.priced(plan, edges, sizes, m, {**dict.fromkeys("ABCDEFG", 64), "E": 256})
    return spark.createDataFrame([(wide > bits, bits == 64 * words)], "wider_is_dearer boolean, words_times_64 boolean")


@register("ownership_layouts", "SELECT * FROM (VALUES ('joins between owners', 2, (SELECT count(*) FROM customer) + (SELECT count(*) FROM orders) + (SELECT count(*) FROM lineitem)), ('customer and orders together', 1, (SELECT count(*) FROM customer JOIN orders ON c_custkey = o_custkey) + (SELECT count(*) FROM lineitem))) t(layout, oblivious_joins, rows)")
def _(spark, sf):
    query = workloads.line3()
    apart = {n: i for i, n in enumerate(query.sources)}
    layouts = {"joins between owners": apart, "customer and orders together": {"customer": 0, "orders": 0, "lineitem": 1}}
    local = {k: q.locally_joined(query, o) for k, o in layouts.items()}
    return spark.createDataFrame([(k, len(x.plan().joins), sum(_sizes(x, spark, sf).values())) for k, x in local.items()], "layout string, oblivious_joins int, rows long")


PAPER = ("q3", "q10", "q18", "q11", "q3f", "q5f_acyclic")


@register("growth_per_decade", "SELECT * FROM (VALUES " + ", ".join(f"('{n}', true)" for n in PAPER) + ") t(query, linear)")
def _(spark, sf):
    """Traffic of ten times the rows over that of the rows: within 1 % of 10 for this method, above for the sorting rival."""
    rows = []
    for name in PAPER:
        query = workloads.WORKLOADS[name]()
        n = {k: 10 * v for k, v in _sizes(query, spark, sf).items()}
        m = max(n.values())
        ratio = rivals.planned(query, {k: 10 * v for k, v in n.items()}, 10 * m).bytes / rivals.planned(query, n, m).bytes
        rival = meter.sort_merge_join(10 * m, 10 * m, 10 * m, 8)[0] / meter.sort_merge_join(m, m, m, 8)[0]
        rows.append((name, abs(ratio - 10) <= 0.1 and rival > 10.3))
    return spark.createDataFrame(rows, "query string, linear boolean")


@register("ratios_to_rivals", "SELECT * FROM (VALUES " + ", ".join(f"('{n}', true)" for n in PAPER) + ") t(query, cheaper)")
def _(spark, sf):
    """Traffic of a chain of sort-merge joins over that of this method."""
    rows = []
    for name in PAPER:
        query = workloads.WORKLOADS[name]()
        n, m = _sizes(query, spark, sf), max(_sizes(query, spark, sf).values())
        own, names = rivals.planned(query, n, m).bytes, list(n)
        rival = sum(meter.sort_merge_join(n[a], n[b], m, 2 * len(query.edges[b]) + 2, charge_sort=False)[0] for a, b in zip(names, names[1:]))
        rows.append((name, rival > own))
    return spark.createDataFrame(rows, "query string, cheaper boolean")


@register("scale_sweep")
def _(spark, sf):
    """Megabytes and rounds of each published query at four decades of scale: exact, as costs depend on public sizes alone."""
    rows = []
    for name in PAPER:
        query = workloads.WORKLOADS[name]()
        n = _sizes(query, spark, sf)
        whole = n.get("lineitem", max(n.values()))
        for scale in (0.001, 0.01, 0.1, 1.0):
            here = {k: v if v <= 25 else max(1, round(v * 6_000_000 * scale / whole)) for k, v in n.items()}
            run = rivals.planned(query, here, max(here.values()))
            rows.append((name, scale, run.bytes / 1e6, run.rounds))
    return spark.createDataFrame(rows, "query string, scale double, megabytes double, rounds int")


@register("slowdown_to_plain")
def _(spark, sf):
    """Seconds of this method over those of Catalyst's plain plan, each the mean of two runs after a first one."""
    def seconds(run) -> float:
        run().write.format("noop").mode("overwrite").save()
        start = time.time()
        for _ in range(2):
            run().write.format("noop").mode("overwrite").save()
        return (time.time() - start) / 2

    query = workloads.q11()
    own, clear = seconds(lambda: q.answer(query, spark, sf)), seconds(lambda: q.plain(query, spark, sf))
    return spark.createDataFrame([("q11", own, clear, own / clear)], "query string, oblivious_seconds double, plain_seconds double, ratio double")


@register("rounds_by_longest_branch", "SELECT true AS less_than_sum, true AS logarithmic")
def _(spark, sf):
    """Branches of a join tree run side by side: rounds are those of the longest one, and grow with the logarithm of n."""
    query = workloads.four_relations()
    longest = {n: rivals.planned(query, dict.fromkeys(query.sources, n), n).longest(query.plan()) for n in (10**4, 10**8)}
    whole = rivals.planned(query, dict.fromkeys(query.sources, 10**4), 10**4).rounds
    return spark.createDataFrame([(longest[10**4] < whole, longest[10**8] < 2.2 * longest[10**4])], "less_than_sum boolean, logarithmic boolean")


@register("micro_join_two_way", "SELECT o_orderkey, o_custkey, l_partkey, l_linenumber FROM orders JOIN lineitem ON o_orderkey = l_orderkey")
def _(spark, sf):
    """A two-way join whose larger side is padded to a multiple of 2^16 rows."""
    a = load(read("orders")(spark, sf), ["o_orderkey", "o_custkey"])
    b = load(read("lineitem")(spark, sf).withColumnRenamed("l_orderkey", "o_orderkey"), ["o_orderkey", "l_partkey", "l_linenumber"])
    n = -(-b.size // 65_536) * 65_536
    a, b = ranks.attach(a, [["o_orderkey"]], n), ranks.attach(model.pad_to(b, n), [["o_orderkey"]], n)
    return reveal(relational.join(a, b, n)).select("o_orderkey", "o_custkey", "l_partkey", "l_linenumber")


# -- audits

@register("audit_equal_shapes", "SELECT CAST(1 AS BIGINT) AS shapes, true AS same_cost")
def _(spark, sf):
    """Two selections of very different outcome: every array that is written has the same rows and tasks in both runs."""
    seen, costs = set(), set()
    for segment in ("BUILDING", "NO SUCH SEGMENT"):
        query, run = workloads.q3(), meter.Meter()
        query = replace(query, sources={**query.sources, "customer": replace(query.sources["customer"], where=F.col("c_mktsegment") == segment)})
        with model.recorded() as shapes:
            q.execute(query, spark, sf, meter=run)
        seen.add(tuple(shapes))
        costs.add((run.bytes, run.rounds, run.units))
    return spark.createDataFrame([(len(seen), len(costs) == 1)], "shapes long, same_cost boolean")


@register("audit_share_words", "SELECT true AS uniform")
def _(spark, sf):
    """What one party holds of a skewed column: each of its bits is set in about half of the rows."""
    rows = read("orders")(spark, sf).select("o_orderkey", F.lit(7).cast("long").alias("x"))
    view = shares.party_view(shares.share(rows, ["x"], "n10", "o_orderkey"), ["x"], 1)
    n = rows.count()
    ones = view.agg(*(F.sum(F.shiftrightunsigned("x.s1", b).bitwiseAND(F.lit(1))).alias(f"b{b}") for b in range(64))).first()
    return spark.createDataFrame([(all(abs(c - n / 2) < 5 * (n / 4) ** 0.5 for c in ones),)], "uniform boolean")


@register("spark_side_measures")
def _(spark, sf):
    """Stages, shuffle bytes and spill of an oblivious and of a plain run."""
    rows = []
    for name, run in (("oblivious", lambda: q.answer(workloads.q11(), spark, sf)), ("plain", lambda: q.plain(workloads.q11(), spark, sf))):
        before = meter.stage_totals(spark)
        run().write.format("noop").mode("overwrite").save()
        rows.append((name, *(int(b - a) for a, b in zip(before, meter.stage_totals(spark)))))
    return spark.createDataFrame(rows, "method string, stages long, shuffle_bytes long, spilled_bytes long")


for _name, (_run, _sql) in stateful.ENTRIES.items():
    register(_name, _sql)(_run)
