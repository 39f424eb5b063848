"""Queries of variants: options of the executor, small worked relations, layouts, the share store, and the kit's other entries."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F
from pyspark.sql import Window as W

from . import relkit, workloads
from .config import MpcConf
from .functions import shares
from .model import LIVE, POS, Relation, dummy_eq, load, pad_to, rank_col, reveal, set_dummy, settle
from .operators import arrays, ranks, relational, scan
from .plans import planner
from .plans import query as q
from .registry import register
from .sources import share_store, tables
from .sources.tables import fixed, micros, read

C = workloads.CENT.format
MANY = MpcConf(chunk=1024)


def _folder(spark) -> str:
    settle(spark.range(1))  # sets a folder where the session has none
    return f"{spark.sparkContext.getCheckpointDir()}/{uuid.uuid4().hex}"


def _orders(spark, sf, keys=(), where=None) -> Relation:
    rel = load(read("orders")(spark, sf), ["o_orderkey", "o_custkey", "o_orderpriority"], conf=MANY)
    rel = ranks.attach(rel, keys, rel.size) if keys else rel
    return relational.select(rel, where) if where is not None else rel


# -- options of the executor

@register("q3_scan_form", workloads.SQL["q3"])
def _(spark, sf):
    return q.answer(workloads.q3(), spark, sf, mode="index", expansion="scan")


@register("q3_lookup_form", workloads.SQL["q3"])
def _(spark, sf):
    return q.answer(workloads.q3(), spark, sf, mode="lookup")


@register("q3f_scan_form", workloads.SQL["q3f"])
def _(spark, sf):
    return q.answer(workloads.q3(True), spark, sf, mode="index", expansion="scan")


@register("q3f_given_size", workloads.SQL["q3f"])
def _(spark, sf):
    return q.answer(workloads.q3(True), spark, sf, m=max(1, read("lineitem")(spark, sf).count()))


@register("q3f_exact_padding", workloads.SQL["q3f"])
def _(spark, sf):
    return q.answer(workloads.q3(True), spark, sf, pad="exact")


@register("q3_owner_preselection", workloads.SQL["q3"])
def _(spark, sf):
    return q.answer(workloads.q3(), spark, sf, preselect=True)


@register("q3_local_join", workloads.SQL["q3"])
def _(spark, sf):
    return q.answer(q.locally_joined(workloads.q3(), {"customer": 0, "orders": 0, "lineitem": 1}), spark, sf)


@register("q3_sized_plan", workloads.SQL["q3"])
def _(spark, sf):
    query = workloads.q3()
    sizes = {n: s.table(spark, sf).count() for n, s in query.sources.items()}
    return q.answer(query, spark, sf, plan=planner.choose_sized(query.edges, frozenset(query.outputs), sizes, max(sizes.values()), query.bags))


# -- primitives

@register("permute_slim_orders", "SELECT o_orderkey, row_number() OVER (ORDER BY o_orderkey DESC) AS place FROM orders")
def _(spark, sf):
    rel = _orders(spark, sf)
    first = read("orders")(spark, sf).agg(F.min("o_orderkey")).first()[0]
    rel = rel.on(rel.df.withColumn(POS, F.col("o_orderkey") - first + 1))
    slim = arrays.permute_slim(rel, F.lit(rel.size + 1) - F.col(POS), [])
    return slim.join(rel.df.select(F.col(POS).alias("__from"), "o_orderkey"), "__from").select("o_orderkey", F.col(POS).alias("place"))


@register("order_by_rank_orders", "SELECT o_orderkey, row_number() OVER (ORDER BY o_custkey, o_orderkey) AS place FROM orders")
def _(spark, sf):
    rel = _orders(spark, sf)
    rel = rel.on(rel.df.withColumn(POS, F.col("o_orderkey")))
    ranked = ranks.attach(rel, [["o_custkey"]], rel.size, method="sort")
    return relational.order_by_rank(ranked, ["o_custkey"]).df.select("o_orderkey", F.col(POS).alias("place"))


@register("dummy_equality", "SELECT count(*) AS pairs FROM nation a JOIN nation b ON (a.n_regionkey = 0 AND b.n_regionkey = 0) OR (a.n_regionkey > 0 AND b.n_regionkey > 0 AND a.n_nationkey = b.n_nationkey)")
def _(spark, sf):
    rel = set_dummy(load(read("nation")(spark, sf), ["n_nationkey", "n_regionkey"], conf=MANY), F.col("n_regionkey") > 0)
    a, b = (rel.df.select(F.col("n_nationkey").alias(f"k{i}"), F.col(LIVE).alias(f"l{i}")) for i in (1, 2))
    return F.broadcast(a).join(b, dummy_eq(F.col("k1"), F.col("l1"), F.col("k2"), F.col("l2"))).agg(F.count("*").alias("pairs"))


@register("prefix_min_count_orders", f"SELECT o_orderkey, min({C('o_totalprice')}) OVER w AS low, count(*) OVER w AS n FROM orders WINDOW w AS (ORDER BY o_orderkey)")
def _(spark, sf):
    rows = read("orders")(spark, sf).select("o_orderkey", fixed("o_totalprice").alias("x"))
    return scan.prefix(rows, {"low": ("min", F.col("x")), "n": ("count", F.col("x"))}, pos="o_orderkey", conf=MANY).select("o_orderkey", "low", "n")


@register("prefix_any_monoid_orders", "SELECT o_orderkey, CAST(first_value(o_custkey) OVER w AS BIGINT) AS first, CAST(o_custkey AS BIGINT) AS last, CAST(bit_xor(o_custkey) OVER w AS BIGINT) AS folded FROM orders WINDOW w AS (ORDER BY o_orderkey)")
def _(spark, sf):
    """The first and the last of the rows so far, which is associative but not commutative, and their words folded by XOR."""
    rows = read("orders")(spark, sf).select("o_orderkey", *(F.col("o_custkey").cast("long").alias(n) for n in ("first", "last", "folded")))
    later = lambda f, g: F.struct(F.when(f["first"] < 0, g["first"]).otherwise(f["first"]).alias("first"), F.when(g["last"] < 0, f["last"]).otherwise(g["last"]).alias("last"), f["folded"].bitwiseXOR(g["folded"]).alias("folded"))
    return scan.monoid(rows, ["first", "last", "folded"], later, {"first": -1, "last": -1, "folded": 0}, rows.count(), pos="o_orderkey")


@register("expand_zero_degree_padded", "SELECT c_custkey, k AS copy FROM (SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON o_custkey = c_custkey GROUP BY 1) c, generate_series(1, 1000) g(k) WHERE k <= n UNION ALL SELECT NULL, NULL FROM generate_series(1, 50)")
def _(spark, sf):
    counts = read("customer")(spark, sf).join(read("orders")(spark, sf), F.col("o_custkey") == F.col("c_custkey"), "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n"))
    rel = load(counts, ["c_custkey", "n"], conf=MANY)
    m = read("orders")(spark, sf).count() + 50
    arrays.check_degrees(rel.df, "n", m)
    return arrays.expand(rel.df, "n", m, rel.size, mode="scan", conf=MANY).select("c_custkey", F.col("__copy").alias("copy"))


@register("too_many_copies_refused", "SELECT * FROM (VALUES ('explode', true), ('scan', true)) t(form, refused)")
def _(spark, sf):
    rel, rows = load(read("nation")(spark, sf).withColumn("n", F.lit(2).cast("long")), ["n_nationkey", "n"], conf=MANY), []
    for form in ("explode", "scan"):
        try:
            arrays.expand(rel.df, "n", 10, rel.size, mode=form).write.format("noop").mode("overwrite").save()
            rows.append((form, False))
        except Exception as problem:  # the error of a task arrives as one of several classes
            rows.append((form, "copies do not fit" in str(problem)))
    return spark.createDataFrame(rows, "form string, refused boolean")


# -- small worked relations, written out

def _literal(spark, rows, attrs, keys=()) -> Relation:
    data = [(i, 1, *r) for i, r in enumerate(rows, 1)]
    kinds = ", ".join(f"{a} {'string' if isinstance(rows[0][k], str) else 'long'}" for k, a in enumerate(attrs))
    rel = Relation(spark.createDataFrame(data, f"{POS} long, {LIVE} long, {kinds}"), tuple(attrs), (), len(rows))
    return ranks.attach(rel, keys, 8, method="sort") if keys else rel


@register("worked_extended_intersection", "SELECT * FROM (VALUES (1, 0), (2, 1), (3, 1), (4, 0), (5, 2)) t(place, v)")
def _(spark, sf):
    rel = _literal(spark, [("a",), ("b",), ("b",), ("x",), ("c",)], ["k"])
    rel = set_dummy(rel, F.col("k") != "x")
    rel = rel.on(rel.df.withColumn(rank_col(["k"]), F.col(POS)), keys=(("k",),))
    y = spark.createDataFrame([(i, 1, k, i) for i, k in enumerate("bcdef", 1)], f"{POS} long, {LIVE} long, k string, v long")
    return arrays.extended(rel, ["k"], y, ["k"], {"v": "v"}).select(F.col(POS).cast("int").alias("place"), F.col("v").cast("int").alias("v"))


@register("worked_join", "SELECT * FROM (VALUES ('a1','b1','c1'), ('a1','b1','c2'), ('a1','b2','c2'), ('a2','b1','c1'), ('a2','b1','c2'), ('a2','b3','c1'), ('a2','b3','c2'), ('a3','b1','c1'), ('a3','b1','c2'), ('a3','b2','c2')) t(A, B, C)")
def _(spark, sf):
    r = _literal(spark, [("a1", "b1"), ("a1", "b2"), ("a1", "b4"), ("a2", "b1"), ("a2", "b3"), ("a3", "b1"), ("a3", "b2")], ["A", "B"], ["A", "B"])
    s = _literal(spark, [("b1", "c1"), ("b1", "c2"), ("b2", "c2"), ("b3", "c1"), ("b3", "c2"), ("b5", "c2"), ("b6", "c1")], ["B", "C"], ["B", "C"])
    return reveal(relational.join(r, s, 12)).select("A", "B", "C")


@register("worked_expansion_ranks", "SELECT * FROM (VALUES (1,3,3,2), (2,3,4,3), (3,3,5,4), (4,1,1,5), (5,1,2,6), (6,4,6,1), (7,NULL,7,7)) t(place, a, rank_a, rank_b)")
def _(spark, sf):
    rel = _literal(spark, [(3, 2, 3), (2, 4, 0), (1, 3, 2), (4, 1, 1)], ["a", "b", "d"])
    rel = rel.on(rel.df.withColumn(rank_col("a"), F.col("a")).withColumn(rank_col("b"), F.col("b")), keys=(("a",), ("b",)))
    out = arrays.expand_with_ranks(rel, "d", 7, mode="scan").df
    return out.select(*(F.col(c).cast("int").alias(n) for c, n in ((POS, "place"), ("a", "a"), (rank_col("a"), "rank_a"), (rank_col("b"), "rank_b"))))


@register("rank_validity_all", "SELECT * FROM (VALUES ('aggregate', CAST(0 AS BIGINT)), ('antijoin', CAST(0 AS BIGINT)), ('join', CAST(0 AS BIGINT)), ('pad', CAST(0 AS BIGINT)), ('select', CAST(0 AS BIGINT)), ('semijoin', CAST(0 AS BIGINT))) t(operator, violations)")
def _(spark, sf):
    a = _orders(spark, sf, [["o_custkey"], ["o_orderkey"]])
    b = ranks.attach(load(read("customer")(spark, sf).withColumnRenamed("c_custkey", "o_custkey"), ["o_custkey", "c_nationkey"], conf=MANY), [["o_custkey"], ["c_nationkey"]], a.size)
    poor = relational.select(b, F.col("c_nationkey") < 5)
    made = {"select": poor, "aggregate": relational.aggregate(a, ["o_custkey"], {"n": ("count", F.lit(1))}), "semijoin": relational.semijoin(a, poor), "antijoin": relational.semijoin(a, poor, anti=True),
            "join": relational.join(a, b, a.size + 25), "pad": pad_to(poor, poor.size + 9)}
    out = None
    for name, rel in made.items():
        one = ranks.verify(rel).agg(F.sum("violations").alias("violations")).select(F.lit(name).alias("operator"), "violations")
        out = one if out is None else out.union(one)
    return out


# -- circuits and the share store

@register("circuit_le_customer", f"SELECT c_custkey, CAST({C('c_acctbal')} <= 300000 AS BIGINT) AS at_most, CAST(300000 <= {C('c_acctbal')} AS BIGINT) AS at_least FROM customer")
def _(spark, sf):
    rows = read("customer")(spark, sf).select("c_custkey", fixed("c_acctbal").alias("a"))
    c = shares.Circuit(shares.share(rows, ["a"], "n6", "c_custkey", strong=False), "n6", "c_custkey")
    limit = c.constant(300000)
    outs = {"at_most": c.le("a", limit), "at_least": c.le(limit, "a")}
    return shares.open_shares(c.df.select("c_custkey", *(F.col(w).alias(n) for n, w in outs.items())), list(outs))


@register("ranked_upload_orders", "SELECT 'o_custkey' AS key, CAST(0 AS BIGINT) AS violations, count(*) AS rows FROM orders")
def _(spark, sf):
    """Owners rank and share; what is opened again from two servers has valid ranks."""
    rel = load(read("orders")(spark, sf), ["o_orderkey", "o_custkey"], conf=MANY)
    rel = ranks.attach(rel, [["o_custkey"]], rel.size)
    path = _folder(spark)
    cols = share_store.upload_ranked(rel, path, "n7")
    opened = rel.on(settle(share_store.download(spark, path, cols, (1, 2))))
    return ranks.verify(opened).crossJoin(F.broadcast(opened.df.agg(F.count("*").alias("rows"))))


@register("servers_sort_shared_region", "SELECT row_number() OVER (ORDER BY r_regionkey DESC) AS rank, CAST(r_regionkey AS BIGINT) AS r_regionkey FROM region")
def _(spark, sf):
    """Data that came without ranks is sorted by the servers, on shared words; the positions are the ranks."""
    rows = read("region")(spark, sf).select((F.col("r_regionkey") + 1).cast("long").alias(POS), (100 - F.col("r_regionkey")).cast("long").alias("key"), F.col("r_regionkey").cast("long").alias("r_regionkey"))
    done, _ = shares.sort_network(rows, "key", ["r_regionkey"], rows.count(), "n8")
    return done.select(F.col(POS).alias("rank"), "r_regionkey")


# -- the kit: sources, sinks, aggregates, windows, functions of the user

NATION = "n_nationkey LONG, n_name STRING, n_regionkey LONG"


@register("rk_csv_roundtrip", "SELECT CAST(n_nationkey AS BIGINT) AS n_nationkey, n_name, CAST(n_regionkey AS BIGINT) AS n_regionkey FROM nation")
def _(spark, sf):
    path = _folder(spark)
    read("nation")(spark, sf).select("n_nationkey", "n_name", "n_regionkey").write.option("header", True).csv(path)
    return spark.read.schema(NATION).option("header", True).csv(path)


@register("rk_json_roundtrip", "SELECT CAST(n_nationkey AS BIGINT) AS n_nationkey, n_name, CAST(n_regionkey AS BIGINT) AS n_regionkey FROM nation")
def _(spark, sf):
    path = _folder(spark)
    read("nation")(spark, sf).select("n_nationkey", "n_name", "n_regionkey").write.json(path)
    return spark.read.schema(NATION).json(path)


@register("rk_partitioned_write", "SELECT o_orderkey, o_orderpriority FROM orders WHERE o_orderpriority = '1-URGENT'")
def _(spark, sf):
    path = _folder(spark)
    read("orders")(spark, sf).select("o_orderkey", "o_orderpriority").repartition("o_orderpriority").write.partitionBy("o_orderpriority").parquet(path)
    return spark.read.parquet(path).where("o_orderpriority = '1-URGENT'").select("o_orderkey", "o_orderpriority")


@register("rk_percentile", f"SELECT o_orderpriority, CAST(round(quantile_cont({C('o_totalprice')}, 0.5)) AS BIGINT) AS middle FROM orders GROUP BY 1")
def _(spark, sf):
    return read("orders")(spark, sf).groupBy("o_orderpriority").agg(F.round(F.percentile(fixed("o_totalprice"), 0.5)).cast("long").alias("middle"))


@register("rk_approx_distinct_bound", "SELECT true AS close")
def _(spark, sf):
    out = read("orders")(spark, sf).agg(F.approx_count_distinct("o_custkey", 0.02).alias("n"), F.count_distinct("o_custkey").alias("exact"))
    return out.select((F.abs(F.col("n") - F.col("exact")) <= 0.1 * F.col("exact")).alias("close"))


@register("rk_collect_sorted", "SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY 1")
def _(spark, sf):
    return read("nation")(spark, sf).groupBy("n_regionkey").agg(F.array_join(F.array_sort(F.collect_list("n_name")), ",").alias("names"))


@register("rk_first_last_ignore_nulls", f"SELECT event_id, first_value(CASE WHEN event_type = 'purchase' THEN {C('value')} END IGNORE NULLS) OVER w AS first_buy, last_value(CASE WHEN event_type = 'purchase' THEN {C('value')} END IGNORE NULLS) OVER w AS last_buy FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)")
def _(spark, sf):
    here = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, W.currentRow)
    bought = F.when(F.col("event_type") == "purchase", fixed("value"))
    return read("events")(spark, sf).select("event_id", F.first(bought, ignorenulls=True).over(here).alias("first_buy"), F.last(bought, ignorenulls=True).over(here).alias("last_buy"))


@register("rk_sort_limit", "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
def _(spark, sf):
    return read("orders")(spark, sf).orderBy(F.desc("o_totalprice"), "o_orderkey").select("o_orderkey").limit(20)


@register("rk_topk_per_group_operator", "SELECT o_custkey, o_orderkey, CAST(r AS INTEGER) AS rank FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) WHERE r <= 2")
def _(spark, sf):
    return relkit.top_k_per_group(read("orders")(spark, sf), ["o_custkey"], [F.desc("o_totalprice"), F.col("o_orderkey")], 2).select("o_custkey", "o_orderkey", "rank")


@register("rk_map_fns", "SELECT user_id, CAST(sum(CASE WHEN event_type = 'click' THEN 1 ELSE 0 END) AS BIGINT) AS clicks, count(DISTINCT event_type) AS kinds FROM events GROUP BY 1")
def _(spark, sf):
    counts = read("events")(spark, sf).groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    maps = counts.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return maps.select("user_id", F.coalesce(F.element_at("m", "click"), F.lit(0)).alias("clicks"), F.size(F.map_keys("m")).cast("long").alias("kinds"))


@register("rk_pandas_scan_udf", f"SELECT o_orderkey, CAST(sum({C('o_totalprice')}) OVER (PARTITION BY o_custkey ORDER BY o_orderkey) AS BIGINT) AS total FROM orders")
def _(spark, sf):
    def running(rows):
        rows = rows.sort_values("o_orderkey")
        return rows.assign(total=rows["x"].cumsum())[["o_orderkey", "total"]]

    return read("orders")(spark, sf).select("o_custkey", "o_orderkey", fixed("o_totalprice").alias("x")).groupBy("o_custkey").applyInPandas(running, "o_orderkey long, total long")


@register("rk_grouped_agg_udf", f"SELECT o_custkey, max({C('o_totalprice')}) AS top FROM orders GROUP BY 1")
def _(spark, sf):
    """The sum of a semiring as a function of the user."""
    plus = F.pandas_udf(lambda x: int(x.max()), "long", F.PandasUDFType.GROUPED_AGG)
    return read("orders")(spark, sf).groupBy("o_custkey").agg(plus(fixed("o_totalprice")).alias("top"))


@register("rk_udtf_expand", "SELECT conv_id, k AS copy FROM (SELECT conv_id, count(*) AS n FROM conversations GROUP BY 1) c, generate_series(1, 1000) g(k) WHERE k <= n")
def _(spark, sf):
    class Copies:
        def eval(self, n: int):
            for k in range(1, n + 1):
                yield (k,)

    spark.udtf.register("copies_of_row", F.udtf(Copies, returnType="copy: bigint"))
    read("conversations")(spark, sf).groupBy("conv_id").agg(F.count("*").alias("n")).createOrReplaceTempView("turns_of_conversation")
    return spark.sql("SELECT conv_id, copy FROM turns_of_conversation, LATERAL copies_of_row(n)")


@register("rk_text_as_two_words", "SELECT count(DISTINCT n_name) AS names FROM nation")
def _(spark, sf):
    return read("nation")(spark, sf).select(tables.text_tag("n_name").alias("t")).agg(F.count_distinct("t").alias("names"))


@register("text_query_oblivious", "SELECT n_nationkey AS c_nationkey, n_name, count(*) AS __ann FROM nation JOIN customer ON c_nationkey = n_nationkey JOIN orders ON o_custkey = c_custkey WHERE c_mktsegment = 'BUILDING' GROUP BY ALL")
def _(spark, sf):
    from .plans import sqlfront

    text = "SELECT n_nationkey, n_name, count(*) FROM nation, customer, orders WHERE c_nationkey = n_nationkey AND o_custkey = c_custkey AND c_mktsegment = 'BUILDING' GROUP BY n_name"
    schemas = {t: read(t)(spark, sf).columns for t in ("nation", "customer", "orders")}
    return q.answer(sqlfront.parse(text, schemas, {"nation": ("n_nationkey",), "customer": ("c_custkey",)}), spark, sf)


@register("timestamps_round_trip", "SELECT event_id, epoch_us(ts) AS us FROM events")
def _(spark, sf):
    return read("events")(spark, sf).select("event_id", micros("ts").alias("us"))
