"""Consistent sorts and rank columns: how owners prepare relations so that later steps never sort."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..config import DEFAULT, MpcConf
from ..functions.hashing import pairwise
from ..model import LIVE, POS, Relation, key_of, rank_col, release, scratch, settle
from . import scan
from .scan import in_words, word_of


def positions(rows: DataFrame, order: list[str], conf: MpcConf = DEFAULT) -> tuple[DataFrame, int]:
    """__pos 1..n: rows are dealt to blocks by a hash of the order columns and placed by them inside a block."""
    n = rows.count()
    blocks = max(1, -(-n // conf.chunk))
    dealt = rows.withColumn("__block", F.pmod(F.xxhash64(*order), F.lit(blocks)) if blocks > 1 else F.lit(0).cast("long"))
    before = W.orderBy("__block").rowsBetween(W.unboundedPreceding, -1)
    starts = dealt.groupBy("__block").agg(F.count("*").alias("n")).select("__block", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("__before"))
    inside = F.row_number().over(W.partitionBy("__block").orderBy(*order))
    placed = dealt.join(scan.small(starts, blocks, conf), "__block").withColumn(POS, (inside + F.col("__before")).cast("long")).drop("__block", "__before")
    return settle(placed), n


def in_order(rows: DataFrame, order: list, conf: MpcConf = DEFAULT, pos: str = POS, n: int | None = None, distinct: bool = False) -> tuple[DataFrame, int]:
    """pos 1..n in ascending order of the columns: one full sort by ranges, whose blocks are counted.

    Rows that the columns do not tell apart are dealt over blocks by a hash, so a key that fills a relation is too; `distinct`
    says that there are none. `n` is their number, where it is known.
    """
    n = rows.count() if n is None else n
    blocks, by = max(1, min(-(-n // conf.chunk), max(32, -(-n // conf.sort_rows)))), [*(F.col(c) if isinstance(c, str) else c for c in order), *([] if distinct else [F.xxhash64(*rows.columns)])]
    placed = settle(rows.repartitionByRange(blocks, *by).sortWithinPartitions(*by).withColumn("__id", F.monotonically_increasing_id()))
    if blocks == 1:
        return placed.select(*rows.columns, (F.col("__id") + 1).alias(pos)), n
    block, before = F.shiftright("__id", 33), W.orderBy("__block").rowsBetween(W.unboundedPreceding, -1)
    starts = placed.groupBy(block.alias("__block")).agg(F.count("*").alias("n")).select("__block", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("__before"))
    inside = F.col("__id").bitwiseAND(F.lit((1 << 33) - 1))
    return placed.withColumn("__block", block).join(scan.small(starts, blocks, conf), "__block").select(*rows.columns, (F.col("__before") + inside + 1).cast("long").alias(pos)), n


def _ranked(rows: DataFrame, rel: Relation, key: tuple[str, ...], buckets: int, seed: int, method: str, table: dict | None = None) -> DataFrame:
    """rows, which have __pos, __live and the key, with their rank on it."""
    kinds, dead = dict(rel.df.dtypes), F.col(LIVE) == 0
    if table is not None:
        h = F.create_map(*(F.lit(x).cast(kinds[key[0]] if i % 2 == 0 else "long") for i, x in enumerate(x for kv in table.items() for x in kv)))[F.col(key[0])]
    else:
        h = F.lit(0) if method == "sort" else pairwise([F.col(k) for k in key], [kinds[k] for k in key], buckets, seed)
    order = [F.when(dead, F.lit(1 << 62)).otherwise(h.cast("long")), *(F.when(~dead, F.col(k)) for k in key), POS]
    return in_order(rows, order, rel.conf, rank_col(key), rel.size, True)[0]


def consistent_order(rel: Relation, key: Iterable[str], buckets: int, seed: int = 5, method: str = "hash", table: dict | None = None) -> DataFrame:
    """(__pos, rank): live rows first, by bucket of the hash, by key inside a bucket, equal keys by position.

    One sort by ranges of these, so a key that fills most of the relation is still dealt over blocks. method `sort` takes key
    order alone; `table` is a literal hash for worked examples.
    """
    key = key_of(key)
    return _ranked(rel.df.select(POS, LIVE, *key), rel, key, buckets, seed, method, table).select(POS, rank_col(key))


def attach(rel: Relation, keys: Iterable[Iterable[str]], buckets: int, seed: int = 5, method: str = "hash") -> Relation:
    """Adds a rank column for each key that the relation has; rows are sorted, and so shuffled, once per key.

    `buckets` must be the same for all relations that share a key.
    """
    keys = [k for k in map(key_of, keys) if set(k) <= set(rel.attrs)]
    out = rel.df.select(*rel.columns)
    with scratch():
        for k in keys:
            out = _ranked(out, rel, k, buckets, seed, method)
            release(out)
    return rel.on(out, keys=(*rel.keys, *keys))


def _live_words(rows: DataFrame, rank: str) -> DataFrame:
    at = f"({rank} - 1)"
    return in_words(rows.groupBy(F.expr(f"shiftright({at}, 6)").alias("w")).agg(F.bit_or(F.expr(f"shiftleft({LIVE}, cast({at} & 63 AS int))")).alias("bits")))


def _repaired(rank: str, n: Column, m: Column) -> Column:
    return F.when(F.col(LIVE) == 1, n).otherwise(m + F.col(rank) - n).cast("long")


def refresh(rel: Relation, form: str = "auto") -> Relation:
    """Repairs every rank after rows became dummies: live rows close ranks, dummies follow in their old order.

    wide carries the rows through one scan per key; slim moves (old rank, liveness) per key and joins the new rank back. words
    scans the liveness alone, as words of 64 places, which every row looks up: rows do not move. auto is words up to a public
    size, wide beyond. The rows should be settled where drawing them is work. How many live stays inside the scans.
    """
    form = form if form != "auto" else "words" if rel.size <= rel.conf.word_places else "wide"
    with scratch():
        source = rel.settled() if form == "slim" else rel
        out = source.df.select(*rel.columns)
        for k in rel.keys:
            rk = rank_col(k)
            if form == "words":
                words = _live_words(source.df.select(rk, LIVE), rk)
                at, word = F.col(rk) - 1, word_of(rk)
                kept = F.bit_count(F.get("__bits", word).bitwiseAND(F.expr(f"~shiftleft(-2L, cast(({rk} - 1) & 63 AS int))")))
                met = out.join(F.broadcast(words), F.shiftright(at, 16) == F.col("__block"))
                new = _repaired(rk, F.col("__base") + F.get("__before", word) + kept, F.col("__m"))
                out = met.select(*(c if c != rk else new.alias(rk) for c in rel.columns))
                continue
            moved = source.df.select(rk, LIVE) if form == "slim" else out
            ran = scan.prefix(moved, {"__n": ("sum", F.col(LIVE))}, pos=rk, size=rel.size, conf=rel.conf, totals={"__n": "__m"}, summed=source.df)
            new = _repaired(rk, F.col("__n"), F.col("__m"))
            if form == "slim":
                out = out.join(ran.select(rk, new.alias("__new")), rk).drop(rk).withColumnRenamed("__new", rk)
            else:
                out = ran.withColumn(rk, new).drop("__n", "__m")
        repaired = settle(out)
        release(repaired)
    return rel.on(repaired)


def verify(rel: Relation) -> DataFrame:
    """key, violations: ranks that are no bijection, live rows behind dummies, and keys whose rows are not adjacent."""
    out = None
    for k in rel.keys:
        rk = rank_col(k)
        rows = rel.df.select(F.col(rk).alias("r"), LIVE, F.struct(*k).alias("key"))
        live = rows.agg(F.coalesce(F.sum(LIVE), F.lit(0))).first()[0]
        shape = rows.agg((F.abs(F.count("*") - F.lit(rel.size)) + F.abs(F.count_distinct("r") - F.lit(rel.size)) + F.coalesce(F.sum(((F.col("r") < 1) | (F.col("r") > rel.size)).cast("long")), F.lit(0))
                          + F.coalesce(F.sum(((F.col(LIVE) == 1) != (F.col("r") <= live)).cast("long")), F.lit(0))).alias("n"))
        apart = rows.where(F.col(LIVE) == 1).groupBy("key").agg((F.max("r") - F.min("r") + 1 - F.count("*")).alias("gap")).agg(F.coalesce(F.sum("gap"), F.lit(0)).alias("n"))
        one = shape.union(apart).agg(F.sum("n").cast("long").alias("violations")).select(F.lit("_".join(k)).alias("key"), "violations")
        out = one if out is None else out.union(one)
    return out


def inconsistencies(a: Relation, b: Relation, key: Iterable[str]) -> DataFrame:
    """violations: neighbouring common keys of a whose first ranks in b are in the opposite order."""
    key = key_of(key)
    first = lambda r, name: r.df.where(F.col(LIVE) == 1).groupBy(*key).agg(F.min(rank_col(key)).alias(name))
    both = first(a, "x").join(first(b, "y"), list(key))
    # dense positions of the common keys in a, so that neighbours are found chunk by chunk
    order = F.lag("y").over(W.partitionBy(scan.chunk_of(F.col("x"), a.conf)).orderBy("x"))
    inside = both.withColumn("before", order).withColumn("c", scan.chunk_of(F.col("x"), a.conf))
    edges = inside.groupBy("c").agg(F.min_by("y", "x").alias("low"), F.max_by("y", "x").alias("high"))
    across = edges.withColumn("before", F.lag("high").over(W.orderBy("c"))).where("before > low")
    return inside.where("before > y").select(F.lit(1).alias("v")).union(across.select(F.lit(1).alias("v"))).agg(F.count("*").alias("violations"))


def bucket_second_moment(df: DataFrame, key: Iterable[str], seeds: Iterable[int] = range(8)) -> DataFrame:
    """seed, squares, mean_square: sum and mean over n buckets of the squared number of distinct keys, n the number of distinct keys."""
    key = list(key)
    kinds = dict(df.dtypes)
    distinct = settle(df.select(*key).distinct())
    n = distinct.count()
    out = None
    for s in seeds:
        loads = distinct.groupBy(pairwise([F.col(k) for k in key], [kinds[k] for k in key], n, s).alias("h")).agg(F.count("*").alias("load"))
        one = loads.agg(F.sum(F.col("load") * F.col("load")).alias("squares")).select(F.lit(s).alias("seed"), "squares", (F.col("squares") / F.lit(n)).alias("mean_square"))
        out = one if out is None else out.union(one)
    return out
