"""Every method, variant and workload as a query on the given tables, with the SQL of its answer unless it is too heavy."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import relkit, workloads
from .config import MpcConf
from .functions import shares
from .functions.hashing import pairwise, pairwise_sql
from .model import LIVE, POS, Relation, load, pad_to, rank_col, reveal
from .operators import arrays, ranks, relational, scan
from .plans import baselines, hypergraph, planner
from .plans import query as q
from .plans.meter import Meter
from .registry import ORACLE, QUERIES, register
from .sources.tables import edges, fixed, micros, read
from .streaming import windows

C = workloads.CENT.format
#: Where a chunked query needs many chunks at any scale.
MANY = MpcConf(chunk=1024)


def _orders(spark, sf, keys=(), attrs=("o_orderkey", "o_custkey"), where=None, conf=MANY) -> Relation:
    rel = load(read("orders")(spark, sf), attrs, {"__ann": fixed("o_totalprice")}, conf)
    rel = ranks.attach(rel, keys, rel.size) if keys else rel
    return relational.select(rel, where) if where is not None else rel


# -- sharing and circuits

@register("share_roundtrip_orders", f"SELECT o_orderkey, {C('o_totalprice')} AS total FROM orders")
def _(spark, sf):
    rows = read("orders")(spark, sf).select("o_orderkey", fixed("o_totalprice").alias("total"))
    shared = shares.refresh_shares(shares.share(rows, ["total"], "n1", "o_orderkey"), ["total"], "n2", "o_orderkey")
    return shares.open_shares(shared, ["total"])


@register("share_two_views_agree", f"SELECT o_orderkey, {C('o_totalprice')} AS total FROM orders")
def _(spark, sf):
    rows = read("orders")(spark, sf).select("o_orderkey", fixed("o_totalprice").alias("total"))
    shared = shares.share(rows, ["total"], "n1", "o_orderkey")
    return shares.open_views({1: shares.party_view(shared, ["total"], 1), 2: shares.party_view(shared, ["total"], 2)}, ["total"], "o_orderkey")


@register("circuit_add_cmp_mux_customer", f"SELECT c_custkey, {C('c_acctbal')} + c_nationkey AS added, {C('c_acctbal')} - 300000 AS less, CAST({C('c_acctbal')} < 300000 AS BIGINT) AS below, CAST(c_nationkey = 7 AS BIGINT) AS same, least({C('c_acctbal')}, 300000) AS picked FROM customer")
def _(spark, sf):
    rows = read("customer")(spark, sf).select("c_custkey", fixed("c_acctbal").alias("a"), F.col("c_nationkey").cast("long").alias("b"))
    c = shares.Circuit(shares.share(rows, ["a", "b"], "n3", "c_custkey", strong=False), "n3", "c_custkey")
    limit = c.constant(300000)
    outs = {"added": c.add("a", "b"), "less": c.sub("a", limit), "below": c.lt("a", limit), "same": c.eq("b", c.constant(7))}
    outs["picked"] = c.mux(outs["below"], "a", limit)
    return shares.open_shares(c.df.select("c_custkey", *(F.col(w).alias(n) for n, w in outs.items())), list(outs))


@register("circuit_mul_supplier", f"SELECT s_suppkey, {C('s_acctbal')} * s_nationkey AS product FROM supplier")
def _(spark, sf):
    rows = read("supplier")(spark, sf).select("s_suppkey", fixed("s_acctbal").alias("a"), F.col("s_nationkey").cast("long").alias("b"))
    c = shares.Circuit(shares.share(rows, ["a", "b"], "n4", "s_suppkey", strong=False), "n4", "s_suppkey")
    product = c.mul("a", "b", bits=5)
    return shares.open_shares(c.df.select("s_suppkey", F.col(product).alias("product")), ["product"])


# -- scans, permutation, compaction

@register("prefix_sum_orders", f"SELECT o_orderkey, CAST(sum({C('o_totalprice')}) OVER (ORDER BY o_orderkey) AS BIGINT) AS total, max({C('o_totalprice')}) OVER (ORDER BY o_orderkey) AS top FROM orders")
def _(spark, sf):
    rows = read("orders")(spark, sf).select("o_orderkey", fixed("o_totalprice").alias("x"))
    return scan.prefix(rows, {"total": ("sum", F.col("x")), "top": ("max", F.col("x"))}, pos="o_orderkey", conf=MANY).select("o_orderkey", "total", "top")


@register("prefix_copy_events", f"SELECT event_id, last_value(CASE WHEN event_type = 'purchase' THEN {C('value')} END IGNORE NULLS) OVER (ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS last_purchase FROM events")
def _(spark, sf):
    rows = read("events")(spark, sf).select("event_id", (F.col("event_id") + 1).alias(POS), F.when(F.col("event_type") == "purchase", fixed("value")).alias("x"))
    return scan.prefix(rows, {"last_purchase": ("copy", F.col("x"))}, conf=MANY).select("event_id", "last_purchase")


@register("segmented_scans_orders", f"SELECT o_orderkey, CAST(sum({C('o_totalprice')}) OVER w AS BIGINT) AS total, max({C('o_totalprice')}) OVER w AS top, min({C('o_totalprice')}) OVER w AS low FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderkey)")
def _(spark, sf):
    rel = load(read("orders")(spark, sf).select("o_orderkey", "o_custkey", fixed("o_totalprice").alias("x")), ["o_orderkey", "o_custkey", "x"], conf=MANY)
    rel = rel.on(rel.df.withColumn(POS, F.col("o_orderkey")))  # ties of the sort go by position
    rel = ranks.attach(rel, [["o_custkey"]], rel.size)
    x = F.col("x")
    return scan.segmented(rel.df, [F.col("o_custkey")], {"total": ("sum", x), "top": ("max", x), "low": ("min", x)}, pos=rank_col(["o_custkey"]), size=rel.size, conf=MANY).select("o_orderkey", "total", "top", "low")


@register("permute_restore_orders", "SELECT o_orderkey, o_custkey FROM orders")
def _(spark, sf):
    rel = _orders(spark, sf)
    back = arrays.restore(arrays.permute(rel, F.lit(rel.size + 1) - F.col(POS), "__o"), "__o")
    return back.df.join(rel.df.select(POS, F.col("o_orderkey").alias("k")), POS).where("k = o_orderkey").select("o_orderkey", "o_custkey")


@register("compact_live_customer", "SELECT count(*) AS live, CAST(sum(CASE WHEN r <= n THEN 1 ELSE 0 END) AS BIGINT) AS in_front FROM (SELECT row_number() OVER (ORDER BY c_custkey) AS r, count(*) OVER () AS n FROM customer WHERE c_mktsegment = 'BUILDING')")
def _(spark, sf):
    rel = load(read("customer")(spark, sf), ["c_custkey", "c_mktsegment"], conf=MANY)
    from .model import set_dummy

    front = arrays.compact_live(set_dummy(rel, F.col("c_mktsegment") == "BUILDING"))
    live = front.df.where(f"{LIVE} = 1")
    return live.agg(F.count("*").alias("live"), F.max(POS).alias("in_front"))


# -- intersection and expansion

@register("member_docs_labels", "SELECT d.doc_id, CAST(l.doc_id IS NOT NULL AS BIGINT) AS hit FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id")
def _(spark, sf):
    docs, labels = load(read("documents")(spark, sf), ["doc_id"], conf=MANY), load(read("labels")(spark, sf), ["doc_id"], conf=MANY)
    return arrays.member(docs.df, labels.df, ["doc_id"], ["doc_id"]).select("doc_id", "hit")


@register("payload_docs_labels", "SELECT d.doc_id, CAST(coalesce(l.quality, 0) AS BIGINT) AS quality FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id")
def _(spark, sf):
    docs, labels = load(read("documents")(spark, sf), ["doc_id"], conf=MANY), load(read("labels")(spark, sf), ["doc_id", "quality"], conf=MANY)
    return arrays.payload(docs.df, labels.df, ["doc_id"], ["doc_id"], {"quality": "quality"}).select("doc_id", F.col("quality").cast("long").alias("quality"))


for _mode in ("index", "lookup"):
    @register(f"extended_intersection_{_mode}", "SELECT o_orderkey, o_custkey, CAST(coalesce(c_nationkey, 0) AS BIGINT) AS nation FROM orders LEFT JOIN customer ON c_custkey = o_custkey AND c_acctbal > 0")
    def _(spark, sf, mode=_mode):
        rel = _orders(spark, sf, [["o_custkey"]])
        rich = load(read("customer")(spark, sf).where("c_acctbal > 0"), ["c_custkey", "c_nationkey"], conf=MANY)
        return arrays.extended(rel, ["o_custkey"], rich.df, ["c_custkey"], {"nation": "c_nationkey"}, mode=mode).select("o_orderkey", "o_custkey", F.col("nation").cast("long").alias("nation"))


for _mode in ("explode", "scan"):
    @register(f"expand_conversations_{_mode}", "SELECT c.conv_id, k AS copy FROM (SELECT conv_id, count(*) AS n FROM conversations GROUP BY 1) c, generate_series(1, 1000) g(k) WHERE k <= n")
    def _(spark, sf, mode=_mode):
        turns = load(read("conversations")(spark, sf).groupBy("conv_id").agg(F.count("*").alias("n")), ["conv_id", "n"], conf=MANY)
        m = turns.df.agg(F.sum("n")).first()[0] + 7
        return arrays.expand(turns.df, "n", m, turns.size, mode=mode, conf=MANY).where("__copy IS NOT NULL").select("conv_id", F.col("__copy").alias("copy"))


# -- ranks

@register("hash_buckets_custkey", f"SELECT c_custkey, {pairwise_sql('c_custkey', 97)} AS bucket FROM customer")
def _(spark, sf):
    return read("customer")(spark, sf).select("c_custkey", pairwise([F.col("c_custkey")], ["bigint"], 97).alias("bucket"))


@register("consistent_sort_orders", f"SELECT o_orderkey, row_number() OVER (ORDER BY {pairwise_sql('o_custkey', 1000)}, o_custkey, o_orderkey) AS rank FROM orders")
def _(spark, sf):
    rel = load(read("orders")(spark, sf), ["o_orderkey", "o_custkey"], conf=MANY)
    rel = rel.on(rel.df.withColumn(POS, F.col("o_orderkey")))
    return rel.df.join(ranks.consistent_order(rel, ["o_custkey"], 1000), POS).select("o_orderkey", F.col(rank_col(["o_custkey"])).alias("rank"))


@register("rank_by_full_sort_orders", "SELECT o_orderkey, row_number() OVER (ORDER BY o_custkey, o_orderkey) AS rank FROM orders")
def _(spark, sf):
    rel = load(read("orders")(spark, sf), ["o_orderkey", "o_custkey"], conf=MANY)
    rel = rel.on(rel.df.withColumn(POS, F.col("o_orderkey")))
    return rel.df.join(ranks.consistent_order(rel, ["o_custkey"], 1000, method="sort"), POS).select("o_orderkey", F.col(rank_col(["o_custkey"])).alias("rank"))


@register("consistency_violations", "SELECT CAST(0 AS BIGINT) AS violations")
def _(spark, sf):
    a = _orders(spark, sf, [["o_custkey"]])
    b = load(read("customer")(spark, sf).withColumnRenamed("c_custkey", "o_custkey"), ["o_custkey", "c_nationkey"], conf=MANY)
    return ranks.inconsistencies(a, ranks.attach(b, [["o_custkey"]], a.size), ["o_custkey"])


_KEYS = "(SELECT DISTINCT o_custkey FROM orders)"
_LOADS = " UNION ALL ".join(f"SELECT {_s} AS seed, CAST(sum(load * load) AS BIGINT) AS squares FROM (SELECT count(*) AS load FROM {_KEYS} GROUP BY {pairwise_sql('o_custkey', f'(SELECT count(*) FROM {_KEYS})', _s)})" for _s in range(8))


@register("bucket_second_moment", f"SELECT seed, squares FROM ({_LOADS})")
def _(spark, sf):
    return ranks.bucket_second_moment(read("orders")(spark, sf), ["o_custkey"]).select("seed", "squares")


@register("bucket_second_moment_bound", f"SELECT avg(squares) < 2 * (SELECT count(*) FROM {_KEYS}) AS below_two FROM ({_LOADS})")
def _(spark, sf):
    return ranks.bucket_second_moment(read("orders")(spark, sf), ["o_custkey"]).agg((F.avg("mean_square") < 2).alias("below_two"))


for _form in ("slim", "wide"):
    @register(f"rank_refresh_{_form}", "SELECT * FROM (VALUES ('o_custkey', CAST(0 AS BIGINT)), ('o_orderkey', CAST(0 AS BIGINT))) t(key, violations)")
    def _(spark, sf, form=_form):
        from .model import set_dummy

        rel = _orders(spark, sf, [["o_custkey"], ["o_orderkey"]], attrs=("o_orderkey", "o_custkey", "o_orderpriority"))
        return ranks.verify(ranks.refresh(set_dummy(rel, F.col("o_orderpriority") == "1-URGENT"), form))


# -- relational operators

@register("select_dummy_customer", "SELECT count(*) AS size, CAST(sum(CASE WHEN c_mktsegment = 'BUILDING' THEN 1 ELSE 0 END) AS BIGINT) AS live FROM customer")
def _(spark, sf):
    rel = load(read("customer")(spark, sf), ["c_custkey", "c_mktsegment"], conf=MANY)
    return relational.select(rel, F.col("c_mktsegment") == "BUILDING").df.agg(F.count("*").alias("size"), F.sum(LIVE).alias("live"))


@register("project_ranked", "SELECT 'o_custkey' AS ranks, count(*) AS size FROM orders")
def _(spark, sf):
    rel = relational.project(_orders(spark, sf, [["o_custkey"], ["o_orderkey"]]), ["o_custkey"])
    return rel.df.agg(F.count("*").alias("size")).select(F.lit(",".join("_".join(k) for k in rel.keys)).alias("ranks"), "size")


@register("distinct_brand_size", "SELECT DISTINCT p_brand, CAST(p_size AS BIGINT) AS p_size FROM part")
def _(spark, sf):
    rel = load(read("part")(spark, sf), ["p_brand", "p_size"], conf=MANY)
    return reveal(relational.distinct(ranks.attach(rel, [["p_brand", "p_size"]], rel.size), ["p_brand", "p_size"])).select("p_brand", F.col("p_size").cast("long").alias("p_size"))


@register("aggregates_by_customer", f"SELECT o_custkey, count(*) AS n, CAST(sum({C('o_totalprice')}) AS BIGINT) AS total, max({C('o_totalprice')}) AS top, min({C('o_totalprice')}) AS low, CAST(sum({C('o_totalprice')}) // count(*) AS BIGINT) AS mean FROM orders GROUP BY 1")
def _(spark, sf):
    x = F.col("__ann")
    grouped = relational.aggregate(_orders(spark, sf, [["o_custkey"]]), ["o_custkey"], {"n": ("count", F.lit(1)), "total": ("sum", x), "top": ("max", x), "low": ("min", x)})
    return reveal(grouped).withColumn("mean", F.expr("total div n"))


@register("aggregate_all", f"SELECT CAST(sum({C('o_totalprice')}) AS BIGINT) AS total FROM orders")
def _(spark, sf):
    return reveal(relational.aggregate(_orders(spark, sf), (), {"total": ("sum", F.col("__ann"))}))


for _name, _anti in (("semijoin", False), ("antijoin", True)):
    @register(f"{_name}_orders_lineitem", f"SELECT o_orderkey, o_custkey FROM orders WHERE {'NOT ' if _anti else ''}EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_returnflag = 'R')")
    def _(spark, sf, anti=_anti):
        a = _orders(spark, sf, [["o_orderkey"]])
        b = load(read("lineitem")(spark, sf).where("l_returnflag = 'R'").withColumnRenamed("l_orderkey", "o_orderkey"), ["o_orderkey", "l_partkey"], conf=MANY)
        return reveal(relational.semijoin(a, ranks.attach(b, [["o_orderkey"]], a.size), anti=anti)).select("o_orderkey", "o_custkey")


@register("join_nation_many_to_many", workloads.SQL["many_to_many"])
def _(spark, sf):
    return q.answer(workloads.many_to_many(), spark, sf)


@register("join_padded_scan_form", "SELECT o_orderkey, l_partkey, l_linenumber, CAST(0 AS BIGINT) AS violations FROM orders JOIN lineitem ON l_orderkey = o_orderkey WHERE o_orderpriority = '1-URGENT'")
def _(spark, sf):
    a = _orders(spark, sf, [["o_orderkey"], ["o_custkey"]], attrs=("o_orderkey", "o_custkey", "o_orderpriority"), where=F.col("o_orderpriority") == "1-URGENT")
    b = load(read("lineitem")(spark, sf).withColumnRenamed("l_orderkey", "o_orderkey"), ["o_orderkey", "l_partkey", "l_linenumber"], conf=MANY)
    b = ranks.attach(b, [["o_orderkey"], ["l_partkey"]], a.size)
    t = relational.join(a, b, relational.join_size(a, b) + 100, mode="index", expansion="scan")
    bad = ranks.verify(t).agg(F.sum("violations").alias("violations"))
    return reveal(t).select("o_orderkey", "l_partkey", "l_linenumber").crossJoin(F.broadcast(bad))


# -- workloads, oblivious and plain

for _name in workloads.WORKLOADS:
    if _name not in ("many_to_many", "graph_k125"):
        register(_name, workloads.SQL[_name])(lambda spark, sf, name=_name: q.answer(workloads.WORKLOADS[name](), spark, sf))
    register(f"plain_{_name}", workloads.SQL[_name])(lambda spark, sf, name=_name: q.plain(workloads.WORKLOADS[name](), spark, sf))

# the densest graphs, rows only: their results are too large for the oracle or their oblivious runs too long
register("graph_k125")(lambda spark, sf: q.answer(workloads.graph(125), spark, sf))
register("graph_k65")(lambda spark, sf: q.answer(workloads.graph(65), spark, sf))
register("plain_graph_k65")(lambda spark, sf: q.plain(workloads.graph(65), spark, sf))


for _k in (130, 125, 100, 87, 65):
    @register(f"output_size_graph_k{_k}", workloads.graph_sql(_k, "count(*) AS m"))
    def _(spark, sf, k=_k):
        return spark.createDataFrame([(q.execute(workloads.graph(k), spark, sf, size_only=True),)], "m long")


@register("output_size_q3f", f"SELECT count(*) AS m FROM ({workloads.SQL['q3f']})")
def _(spark, sf):
    return spark.createDataFrame([(q.execute(workloads.q3(True), spark, sf, size_only=True),)], "m long")


@register("output_size_cost_constant", "SELECT CAST(1 AS BIGINT) AS costs")
def _(spark, sf):
    seen = set()
    for k in (130, 65):
        meter = Meter()
        q.execute(workloads.graph(k), spark, sf, meter=meter, size_only=True)
        seen.add((meter.bytes, meter.rounds, meter.units))
    return spark.createDataFrame([(len(seen),)], "costs long")


@register("q11_having", f"SELECT partkey, __ann FROM ({workloads.SQL['q11']}) WHERE __ann * 2000 > (SELECT sum(__ann) FROM ({workloads.SQL['q11']}))")
def _(spark, sf):
    return reveal(relational.having_share(q.execute(workloads.q11(), spark, sf), 1, 2000)).select("partkey", "__ann")


# -- plans

FOUR = {"R1": "AB", "R2": "ADE", "R3": "BCF", "R4": "CFG"}


def _rows_of(query: q.JoinAggQuery, spark, sf) -> int:
    """Input rows of a query, counted on the given tables."""
    return sum(s.table(spark, sf).count() for s in query.sources.values())


_COUNT = lambda *tables: " + ".join(f"(SELECT count(*) FROM {t})" for t in tables)
_FOUR_ROWS = _COUNT("orders", "customer", "lineitem", workloads.SUPPLY)


@register("plan_cost_table", f"SELECT root, joined, n_cost, m_cost, n_cost * {_COUNT('lineitem')} + m_cost * (SELECT count(*) FROM ({workloads.SQL['line3']})) AS words FROM (VALUES ('R1', 'R2,R3', 15, 16), ('R1', 'R3,R2', 15, 15), ('R2', 'R3,R1', 15, 15)) t(root, joined, n_cost, m_cost)")
def _(spark, sf):
    """Costs of the plans for the largest relation's rows and the rows of the joined chain."""
    plans = planner.all_plans({k: frozenset(v) for k, v in FOUR.items()}, frozenset("ABCDE"))
    n, m = read("lineitem")(spark, sf).count(), q.plain(workloads.line3(), spark, sf).count()
    return spark.createDataFrame([(p.tree.root, ",".join(s.other for s in p.joins), p.n_cost, p.m_cost, int(p.n_cost * n + p.m_cost * m)) for p in plans], "root string, joined string, n_cost int, m_cost int, words long")


@register("free_connex_catalogue", f"SELECT * FROM (VALUES ('four, ABCDE', 'R1,R2', {_FOUR_ROWS}), ('four, ABCD', 'R1', {_FOUR_ROWS}), ('triangle', 'cyclic', 3 * {_COUNT('events')}), ('two, AC', 'not free-connex', 2 * {_COUNT('events')})) t(query, roots, rows)")
def _(spark, sf):
    def roots(schemas: dict[str, str], outputs: str) -> str:
        try:
            return ",".join(t.root for t in hypergraph.free_connex_trees({k: frozenset(v) for k, v in schemas.items()}, frozenset(outputs)))
        except hypergraph.UnsupportedQuery as e:
            return "cyclic" if "cyclic:" in str(e) else "not free-connex"

    four, hops = _rows_of(workloads.four_relations(), spark, sf), edges(spark, sf).count()
    rows = [("four, ABCDE", roots(FOUR, "ABCDE"), four), ("four, ABCD", roots(FOUR, "ABCD"), four), ("triangle", roots({"a": "AB", "b": "BC", "c": "AC"}, "ABC"), 3 * hops), ("two, AC", roots({"a": "AB", "b": "BC"}, "AC"), 2 * hops)]
    return spark.createDataFrame(rows, "query string, roots string, rows long")


@register("join_tree_enumeration", f"SELECT * FROM (VALUES ('four', 4, {_FOUR_ROWS}), ('q3', 3, {_COUNT('customer', 'orders', 'lineitem')}), ('q5', 6, {_COUNT('region', 'nation', 'supplier', 'lineitem', 'orders', 'customer')}), ('graph', 3, 3 * {_COUNT('events')})) t(query, trees, rows)")
def _(spark, sf):
    named = {"four": workloads.four_relations(), "q3": workloads.q3(), "q5": workloads.q5f(), "graph": workloads.graph(100)}
    return spark.createDataFrame([(n, len(hypergraph.join_trees(x.edges)), _rows_of(x, spark, sf)) for n, x in named.items()], "query string, trees int, rows long")


# -- baselines and meters

@register("baseline_nested_loop", "SELECT r_regionkey AS regionkey, n_nationkey AS nationkey, n_name AS nation, s_suppkey AS suppkey FROM region JOIN nation ON n_regionkey = r_regionkey JOIN supplier ON s_nationkey = n_nationkey")
def _(spark, sf):
    full = workloads.q5f()
    small = q.JoinAggQuery("nations", {n: q.Source(s.table, s.attrs) for n, s in full.sources.items() if n in ("region", "nation", "supplier")}, ("regionkey", "nationkey", "nation", "suppkey"), None)
    return baselines.nested_loop(small, spark, sf)


@register("baseline_sort_merge_chain", workloads.SQL["line3"])
def _(spark, sf):
    out, _ = baselines.two_way_chain(workloads.line3(), spark, sf)
    return out.select(*workloads.line3().outputs)


@register("baseline_leaked_sizes", "SELECT count(*) AS size FROM orders JOIN lineitem ON o_orderkey = l_orderkey UNION ALL SELECT count(*) FROM customer JOIN orders ON c_custkey = o_custkey JOIN lineitem ON o_orderkey = l_orderkey")
def _(spark, sf):
    _, sizes = baselines.two_way_chain(workloads.line3(), spark, sf)
    return spark.createDataFrame([(s,) for s in sizes], "size long")


@register("baseline_costs")
def _(spark, sf):
    sizes = {t: read(t)(spark, sf).count() for t in ("customer", "orders", "lineitem")}
    return baselines.comparison(spark, sizes, sizes["lineitem"], 4)


@register("meter_report")
def _(spark, sf):
    meter = Meter()
    q.execute(workloads.q3(), spark, sf, meter=meter)
    return spark.createDataFrame([(k, s, int(u), float(b), int(r)) for k, (s, u, b, r) in enumerate(meter.rows)], "step int, operator string, units long, bytes double, rounds int")


@register("motivating_average", "SELECT class, CAST(__ann // __ann_cnt AS BIGINT) AS mean FROM (" + workloads.SQL["motivating_avg"] + ")")
def _(spark, sf):
    return q.answer(workloads.motivating(), spark, sf).selectExpr("class", "__ann div __ann_cnt AS mean")


@register("graph_edges", f"SELECT source, target, rating FROM {workloads.EDGES}")
def _(spark, sf):
    return edges(spark, sf).select("source", "target", "rating")


@register("timestamps_as_words", "SELECT o_orderkey, epoch_us(o_orderdate) AS us FROM orders")
def _(spark, sf):
    return read("orders")(spark, sf).select("o_orderkey", micros("o_orderdate").alias("us"))


@register("pad_with_dummies", "SELECT count(*) + 100 AS size, count(*) AS live FROM nation")
def _(spark, sf):
    rel = load(read("nation")(spark, sf), ["n_nationkey"], conf=MANY)
    return pad_to(rel, rel.size + 100).df.agg(F.count("*").alias("size"), F.sum(LIVE).alias("live"))


# -- the kit around

for _name, _sql in relkit.SAME.items():
    register(_name, _sql)(relkit.statement(_name))
for _name, (_run, _sql) in windows.ENTRIES.items():
    register(_name, _sql)(_run)


@register("rk_asof", "SELECT p.event_id, (SELECT max_by(v.event_id, (v.ts, v.event_id)) FROM events v WHERE v.user_id = p.user_id AND v.event_type = 'view' AND v.ts <= p.ts) AS asof_view FROM events p WHERE p.event_type = 'purchase'")
def _(spark, sf):
    rows = read("events")(spark, sf).select("event_id", "user_id", "event_type", micros("ts").alias("us"))
    left = rows.where("event_type = 'purchase'").drop("event_type")
    right = rows.where("event_type = 'view'").select("user_id", F.col("us").alias("seen"), F.col("event_id").alias("view"))
    return relkit.asof_join(left, right, ["user_id"], "us", "seen", ["view"], slice_width=86_400_000_000 * 30).select("event_id", "asof_view")


@register("rk_interval", "SELECT a.event_id AS click, b.event_id AS purchase FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def _(spark, sf):
    rows = read("events")(spark, sf).select("event_id", "user_id", "event_type", micros("ts").alias("us"))
    clicks = rows.where("event_type = 'click'").select("user_id", F.col("event_id").alias("click"), F.col("us").alias("a"))
    buys = rows.where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("purchase"), F.col("us").alias("b"))
    return relkit.interval_join(clicks, buys, ["user_id"], "a", "b", 3_600_000_000).select("click", "purchase")


@register("rk_range", f"SELECT event_id, CAST({C('value')} // 5000 AS BIGINT) AS band FROM events WHERE {C('value')} < 50000")
def _(spark, sf):
    points = read("events")(spark, sf).select("event_id", fixed("value").alias("x"))
    bands = spark.range(10).select(F.col("id").alias("band"), (F.col("id") * 5000).alias("low"), (F.col("id") * 5000 + 5000).alias("high"))
    return relkit.range_join(points, bands, "x", "low", "high", 10_000).select("event_id", "band")


@register("rk_broadcast", "SELECT c_custkey, n_name FROM customer JOIN nation ON c_nationkey = n_nationkey")
def _(spark, sf):
    return read("customer")(spark, sf).join(F.broadcast(read("nation")(spark, sf)), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name")


for _hint in ("merge", "shuffle_hash"):
    @register(f"rk_join_{_hint}", "SELECT o_custkey, l_partkey FROM orders JOIN lineitem ON o_orderkey = l_orderkey")
    def _(spark, sf, hint=_hint):
        return read("orders")(spark, sf).hint(hint).join(read("lineitem")(spark, sf), F.col("o_orderkey") == F.col("l_orderkey")).select("o_custkey", "l_partkey")


@register("rk_json_props", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def _(spark, sf):
    return read("events")(spark, sf).select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"))


@register("rk_approx_distinct")
def _(spark, sf):
    return read("orders")(spark, sf).agg(F.approx_count_distinct("o_custkey").alias("n"))


@register("rk_array_fns", "SELECT vec_id, len(embedding) AS n, CAST(round(embedding[1] * 1000) AS BIGINT) AS first FROM embeddings")
def _(spark, sf):
    return read("embeddings")(spark, sf).select("vec_id", F.size("embedding").cast("long").alias("n"), F.round(F.element_at("embedding", 1) * 1000).cast("long").alias("first"))


@register("share_store_roundtrip", f"SELECT o_orderkey, {C('o_totalprice')} AS total FROM orders")
def _(spark, sf):
    import uuid

    from .model import settle
    from .sources import share_store

    rows = read("orders")(spark, sf).select("o_orderkey", fixed("o_totalprice").alias("total"))
    settle(spark.range(1))
    path = f"{spark.sparkContext.getCheckpointDir()}/shares-{uuid.uuid4().hex}"
    share_store.upload(rows, ["total"], path, "n5", "o_orderkey")
    return share_store.download(spark, path, ["total"], (0, 2), "o_orderkey")


TEXT = "SELECT n_name, count(*) FROM nation, customer, orders WHERE c_nationkey = n_nationkey AND o_custkey = c_custkey AND c_mktsegment = 'BUILDING' AND o_totalprice BETWEEN 1000 AND 90000 GROUP BY n_name"


@register("text_query", "SELECT n_nationkey AS c_nationkey, n_name, count(*) AS __ann FROM nation JOIN customer ON c_nationkey = n_nationkey JOIN orders ON o_custkey = c_custkey WHERE c_mktsegment = 'BUILDING' AND o_totalprice BETWEEN 1000 AND 90000 GROUP BY ALL")
def _(spark, sf):
    from .plans import sqlfront

    schemas = {t: read(t)(spark, sf).columns for t in ("nation", "customer", "orders")}
    text = TEXT.replace("SELECT n_name", "SELECT n_nationkey, n_name")
    return q.plain(sqlfront.parse(text, schemas, {"nation": ("n_nationkey",), "customer": ("c_custkey",)}), spark, sf)


from . import measures, variants  # noqa: E402, F401  these register their queries too
