"""Prefix scans by position in levels: windows inside chunks of fixed public size, and a scan of chunk summaries.

A giant segment is as cheap as many small ones, and no window holds more than a chunk or one row per chunk.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..config import DEFAULT, MpcConf
from ..model import POS

CHUNK = "__chunk"


def chunk_of(pos: Column, conf: MpcConf) -> Column:
    return F.floor((pos - 1) / conf.chunk).cast("long")


def small(df: DataFrame, rows: int | None, conf: MpcConf) -> DataFrame:
    """Broadcast only if the known number of chunk summaries is within the bound."""
    return F.broadcast(df) if rows is not None and rows <= conf.broadcast_chunks else df


def _running(op: str, x: Column, window) -> Column:
    if op == "copy":
        return F.last(x, ignorenulls=True).over(window)
    return {"sum": F.sum, "max": F.max, "min": F.min, "count": F.count}[op](x).over(window)


def _combine(op: str, before: Column, here: Column) -> Column:
    if op == "copy":
        return F.coalesce(here, before)
    if op in ("sum", "count"):
        return F.coalesce(before, F.lit(0)) + F.coalesce(here, F.lit(0))
    return F.greatest(before, here) if op == "max" else F.least(before, here)


def prefix(df: DataFrame, outs: dict[str, tuple[str, Column]], pos: str = POS, size: int | None = None, conf: MpcConf = DEFAULT, exclusive: bool = False, totals: dict[str, str] | None = None, summed: DataFrame | None = None) -> DataFrame:
    """Adds running results in order of pos: outs is name -> (op, column), op one of sum, max, min, count, copy.

    Nulls are neutral. With `exclusive` each row gets the result of the rows before it (null before the first for max, min and
    copy). `totals` is out -> name of a column with the result over all rows, which comes from the chunk summaries and is
    opened to nobody. Summaries of more than a chunk are scanned in chunks themselves. `summed` has the same pos and columns of
    outs as df, where these are drawn with less work.
    """
    totals = totals or {}
    rows = df.select("*", chunk_of(F.col(pos), conf).alias(CHUNK), *(x.alias(f"__x_{o}") for o, (_, x) in outs.items()))
    here = W.partitionBy(CHUNK).orderBy(pos).rowsBetween(W.unboundedPreceding, -1 if exclusive else W.currentRow)
    total = {"sum": F.sum, "max": F.max, "min": F.min, "count": F.count}
    local = rows.select("*", *(_running(op, F.col(f"__x_{o}"), here).alias(f"__l_{o}") for o, (op, _) in outs.items()))
    if size is not None and size <= conf.chunk:  # one chunk, by public size: nothing is carried
        whole = W.partitionBy(CHUNK)
        joined = local.withColumns({f"__c_{o}": F.lit(None).cast(local.schema[f"__l_{o}"].dataType) for o in outs})
        joined = joined.withColumns({f"__all_{o}": total[outs[o][0]](f"__x_{o}").over(whole) for o in totals})
    else:
        sums = [F.max(F.when(F.col(f"__x_{o}").isNotNull(), F.struct(F.col(pos), F.col(f"__x_{o}").alias("v"))))["v"].alias(f"__t_{o}") if op == "copy" else total[op](f"__x_{o}").alias(f"__t_{o}") for o, (op, _) in outs.items()]
        drawn = rows if summed is None else summed.select(pos, chunk_of(F.col(pos), conf).alias(CHUNK), *(x.alias(f"__x_{o}") for o, (_, x) in outs.items()))
        chunks = drawn.groupBy(CHUNK).agg(*sums)
        kinds = {o: "sum" if op == "count" else op for o, (op, _) in outs.items()}
        number = None if size is None else -(-size // conf.chunk)
        if number is not None and conf.chunk < number < size:
            of_chunks = chunks.withColumnRenamed(CHUNK, "__below").withColumn("__at", F.col("__below") + 1)
            tops = prefix(of_chunks, {f"__c_{o}": (k, F.col(f"__t_{o}")) for o, k in kinds.items()}, "__at", number, conf, True, {f"__c_{o}": f"__all_{o}" for o in totals}).withColumnRenamed("__below", CHUNK)
        else:
            before = W.orderBy(CHUNK).rowsBetween(W.unboundedPreceding, -1)
            every = W.orderBy(CHUNK).rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
            tops = chunks.select(CHUNK, *(_running(k, F.col(f"__t_{o}"), before).alias(f"__c_{o}") for o, k in kinds.items()), *(_running(kinds[o], F.col(f"__t_{o}"), every).alias(f"__all_{o}") for o in totals))
        joined = local.join(small(tops.select(CHUNK, *(f"__c_{o}" for o in outs), *(f"__all_{o}" for o in totals)), number, conf), CHUNK)
    made = [_combine(op, F.col(f"__c_{o}"), F.col(f"__l_{o}")).alias(o) for o, (op, _) in outs.items()]
    return joined.select(*df.columns, *made, *(F.coalesce(f"__all_{o}", F.lit(0)).alias(n) for o, n in totals.items()))


def segmented(df: DataFrame, seg: list[Column], outs: dict[str, tuple[str, Column]], pos: str = POS, size: int | None = None, conf: MpcConf = DEFAULT, last: str | None = None) -> DataFrame:
    """Running results that start anew where the segment (equal values of seg in consecutive rows) changes.

    With `last`, a column of that name tells whether the row is the last of its segment.
    """
    rows = df.select("*", chunk_of(F.col(pos), conf).alias(CHUNK), F.struct(*(s.alias(f"k{i}") for i, s in enumerate(seg))).alias("__seg"), *(x.alias(f"__x_{o}") for o, (_, x) in outs.items()))
    order = W.partitionBy(CHUNK).orderBy(pos)
    rows = rows.withColumn("__next", F.lead("__seg").over(order)).withColumn("__head", F.coalesce(~F.lag("__seg").over(order).eqNullSafe(F.col("__seg")), F.lit(True)) | (F.row_number().over(order) == 1))
    rows = rows.withColumn("__start", F.last(F.when(F.col("__head"), F.col(pos)), ignorenulls=True).over(order.rowsBetween(W.unboundedPreceding, W.currentRow)))
    inside = W.partitionBy(CHUNK, "__start").orderBy(pos).rowsBetween(W.unboundedPreceding, W.currentRow)
    rows = rows.select("*", *(_running(op, F.col(f"__x_{o}"), inside).alias(f"__l_{o}") for o, (op, _) in outs.items()))
    kinds = {o: "sum" if op == "count" else op for o, (op, _) in outs.items()}
    chunks = rows.groupBy(CHUNK).agg(F.min_by("__seg", pos).alias("first"), F.max_by("__seg", pos).alias("final"), F.min("__start").alias("start"), F.max("__start").alias("final_start"),
                                     *(F.max_by(F.struct(f"__l_{o}"), pos)[f"__l_{o}"].alias(f"__t_{o}") for o in outs))
    by_chunk = W.orderBy(CHUNK)
    chunks = chunks.withColumn("joins", F.coalesce(F.lag("final").over(by_chunk).eqNullSafe(F.col("first")) & (F.row_number().over(by_chunk) > 1), F.lit(False)))
    chunks = chunks.withColumn("run", F.sum(F.when(F.col("joins") & (F.col("start") == F.col("final_start")), 0).otherwise(1)).over(by_chunk.rowsBetween(W.unboundedPreceding, W.currentRow)))
    open_run = W.partitionBy("run").orderBy(CHUNK).rowsBetween(W.unboundedPreceding, W.currentRow)
    chunks = chunks.select("*", *(_running(kinds[o], F.col(f"__t_{o}"), open_run).alias(f"__r_{o}") for o in outs))
    carried = chunks.select(CHUNK, F.col("start").alias("__first_start"), F.lead("first").over(by_chunk).alias("__next_first"),
                            *(F.when(F.col("joins"), F.lag(f"__r_{o}").over(by_chunk)).alias(f"__c_{o}") for o in outs))
    if size is not None and size <= conf.chunk:  # one chunk, by public size: nothing is carried
        joined = rows.withColumns({"__first_start": F.lit(None).cast("long"), "__next_first": F.lit(None).cast(rows.schema["__seg"].dataType), **{f"__c_{o}": F.lit(None).cast(rows.schema[f"__l_{o}"].dataType) for o in outs}})
    else:
        joined = rows.join(small(carried, None if size is None else size // conf.chunk + 1, conf), CHUNK)
    made = [F.when(F.col("__start") == F.col("__first_start"), _combine(op, F.col(f"__c_{o}"), F.col(f"__l_{o}"))).otherwise(_combine(op, F.lit(None), F.col(f"__l_{o}"))).alias(o) for o, (op, _) in outs.items()]
    if last:
        made.append((~F.coalesce("__next", "__next_first").eqNullSafe(F.col("__seg"))).alias(last))
    return joined.select(*df.columns, *made)


def first_in_chunks(df: DataFrame, seg: list[Column], name: str, pos: str = POS, conf: MpcConf = DEFAULT) -> DataFrame:
    """df with a column of 1 at the first row of each segment in each chunk, 0 elsewhere: nothing is carried between chunks."""
    rows = df.select("*", chunk_of(F.col(pos), conf).alias(CHUNK), F.struct(*(s.alias(f"k{i}") for i, s in enumerate(seg))).alias("__seg"))
    before = F.lag("__seg").over(W.partitionBy(CHUNK).orderBy(pos))
    return rows.select(*df.columns, (~before.eqNullSafe(F.col("__seg"))).cast("long").alias(name))


def copied_in_chunks(df: DataFrame, head: str, cols: list[str], pos: str = POS, conf: MpcConf = DEFAULT) -> DataFrame:
    """Columns of the latest row marked in head replace each row's own; the first row of every chunk is marked."""
    order = W.partitionBy(CHUNK).orderBy(pos).rowsBetween(W.unboundedPreceding, W.currentRow)
    rows = df.select("*", chunk_of(F.col(pos), conf).alias(CHUNK))
    rows = rows.withColumn("__latest", F.last(F.when(F.col(head) == 1, F.struct(*cols)), ignorenulls=True).over(order))
    return rows.select(*(F.col(f"__latest.{c}").alias(c) if c in cols else c for c in df.columns))


def in_words(words: DataFrame) -> DataFrame:
    """From w and bits of every word of 64 places, one row per block of 2^16 places: marks before it, bits of its words, marks before each.

    A scan in three levels whose lowest is a word; places are found again by `word_of`.
    """
    below, every = W.orderBy("__block").rowsBetween(W.unboundedPreceding, -1), W.orderBy("__block").rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    inside = W.partitionBy("__block").orderBy("w").rowsBetween(W.unboundedPreceding, -1)
    ran = words.withColumn("__block", F.shiftright("w", 10)).withColumn("before", F.coalesce(F.sum(F.bit_count("bits")).over(inside), F.lit(0)).cast("int"))
    blocks = ran.groupBy("__block").agg(F.array_sort(F.collect_list(F.struct("w", "before", "bits"))).alias("words"), F.sum(F.bit_count("bits")).alias("n"))
    return blocks.select("__block", F.expr("transform(words, x -> x.before)").alias("__before"), F.expr("transform(words, x -> x.bits)").alias("__bits"),
                                F.coalesce(F.sum("n").over(below), F.lit(0)).alias("__base"), F.sum("n").over(every).alias("__m"))


def word_of(pos: str) -> Column:
    """Where in its block a place's word lies."""
    return F.expr(f"cast(shiftright({pos} - 1, 6) & 1023 AS int)")


def words_of_runs(runs: DataFrame, size: int) -> DataFrame:
    """The words of places 1..size in which every place of the runs, from __first to __last each, is marked."""
    low, high = F.expr("shiftright(__first - 1, 6)"), F.expr("shiftright(__last - 1, 6)")
    each = runs.select("__first", "__last", F.explode(F.sequence(low, high)).alias("w"))
    begun = F.when(F.col("w") == low, F.expr("shiftleft(-1L, cast((__first - 1) & 63 AS int))")).otherwise(F.lit(-1))
    ended = F.when(F.col("w") == high, F.expr("~shiftleft(-2L, cast((__last - 1) & 63 AS int))")).otherwise(F.lit(-1))
    marked = each.select("w", begun.bitwiseAND(ended).alias("bits"))
    every = runs.sparkSession.range(-(-size // 64)).select(F.col("id").alias("w"), F.lit(0).cast("long").alias("bits"))
    return in_words(marked.unionByName(every).groupBy("w").agg(F.bit_or("bits").alias("bits")))


def monoid(df: DataFrame, values: list[str], combine, neutral: dict[str, int], size: int, pos: str = POS, conf: MpcConf = DEFAULT) -> DataFrame:
    """pos and running results of any associative operation on the value columns (longs); combine takes two structs of them.

    A chunk's rows are folded in order within one array; the results of chunks are scanned likewise, level by level, and what
    comes before a chunk is combined into its rows. Chunks are short, since folding copies the array.
    """
    width = max(4, min(conf.chunk, 1024))
    kind = "struct<" + ",".join(f"{v}:bigint" for v in values) + ">"
    start = F.struct(*(F.lit(neutral[v]).cast("long").alias(v) for v in values)).cast(kind)
    step = lambda done, r: F.concat(done, F.array(combine(F.element_at(done, -1), F.struct(*(r[v].alias(v) for v in values))).cast(kind)))
    chunk = F.lit(0).cast("long") if size < width else F.floor((F.col(pos) - 1) / width).cast("long")
    rows = df.select(pos, *(F.col(v).cast("long").alias(v) for v in values), chunk.alias(CHUNK))
    chunks = rows.groupBy(CHUNK).agg(F.array_sort(F.collect_list(F.struct(pos, *values))).alias("rows"))
    chunks = chunks.withColumn("runs", F.aggregate("rows", F.array(start), step))
    if size < width:
        chunks = chunks.withColumn("carry", start)
    else:
        tops = chunks.select((F.col(CHUNK) + 2).alias("__top"), *(F.element_at("runs", -1)[v].alias(v) for v in values))
        before = monoid(tops, values, combine, neutral, size // width + 2, "__top", conf)
        before = before.select((F.col("__top") - 1).alias(CHUNK), F.struct(*values).cast(kind).alias("carry"))
        chunks = chunks.join(before, CHUNK, "left").withColumn("carry", F.coalesce("carry", start))
    out = combine(F.col("carry"), F.element_at("runs", F.col("i") + 2))
    return chunks.select("carry", "runs", F.posexplode("rows").alias("i", "row")).select(F.col(f"row.{pos}").alias(pos), out.alias("out")).select(pos, *(F.col(f"out.{v}").alias(v) for v in values))
