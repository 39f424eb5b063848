"""Array primitives on relations: permutation, compaction, intersection, expansion."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..config import DEFAULT, MpcConf
from ..model import LIVE, POS, Relation, rank_col, settle
from . import scan


def permute(rel: Relation, target: Column, remember: str | None = None) -> Relation:
    """Row i goes to position target; with `remember` the old position is kept in a column of that name."""
    df = rel.df.withColumn(remember, F.col(POS)) if remember else rel.df
    moved = df.withColumn(POS, target.cast("long"))
    return rel.on(moved, attrs=(*rel.attrs, remember) if remember else rel.attrs)


def restore(rel: Relation, remembered: str) -> Relation:
    """Undoes a permutation by the positions it remembered."""
    return rel.on(rel.df.withColumn(POS, F.col(remembered)), attrs=tuple(a for a in rel.attrs if a != remembered))


def permute_slim(rel: Relation, target: Column, cols: list[str]) -> DataFrame:
    """(new position, old position, cols): only the named columns move."""
    return rel.df.select(target.cast("long").alias(POS), F.col(POS).alias("__from"), *cols)


def compact(df: DataFrame, tag: Column, size: int, pos: str = POS, conf: MpcConf = DEFAULT) -> DataFrame:
    """Marked rows first, in their order; the others follow in theirs. Adds nothing but the new position."""
    ran = scan.prefix(df.withColumn("__tag", tag.cast("long")), {"__n": ("sum", F.col("__tag"))}, pos=pos, size=size, conf=conf, totals={"__n": "__m"})
    new = F.when(F.col("__tag") == 1, F.col("__n")).otherwise(F.col("__m") + F.col(pos) - F.col("__n")).cast("long")
    return ran.withColumn(pos, new).select(*df.columns)


def compact_live(rel: Relation) -> Relation:
    """Real rows before dummies; ranks stay with their rows."""
    return rel.on(compact(rel.df, F.col(LIVE) == 1, rel.size, conf=rel.conf))


def member(x: DataFrame, y: DataFrame, x_key: list[str], y_key: list[str], live_x: str = LIVE, live_y: str = LIVE) -> DataFrame:
    """x with a column `hit`: 1 where its key is among y's live keys. Keys are distinct on both sides."""
    return payload(x, y, x_key, y_key, {}, live_x, live_y)


def encode_dummies(df: DataFrame, key: list[str], live: str, side: int) -> DataFrame:
    """Adds __enc: (0, key) of a real row, (1, position, side) of a dummy, so that no dummy meets another."""
    nothing = [F.when(F.col(live) == 1, F.col(k)).alias(f"k{i}") for i, k in enumerate(key)]
    return df.withColumn("__enc", F.struct((1 - F.col(live)).alias("tag"), *nothing, F.when(F.col(live) == 1, F.lit(0)).otherwise(F.col(POS) * 2 + side).alias("at")))


def payload(x: DataFrame, y: DataFrame, x_key: list[str], y_key: list[str], values: dict[str, str], live_x: str = LIVE, live_y: str = LIVE, small: bool = False) -> DataFrame:
    """x with `hit` and, for each name -> column of y in values, the partner's value or 0. y's keys are distinct."""
    left = encode_dummies(x, x_key, live_x, 0)
    right = encode_dummies(y, y_key, live_y, 1).select(F.col("__enc").alias("__other"), *(F.col(c).alias(f"__y_{n}") for n, c in values.items()))
    joined = left.join(F.broadcast(right) if small else right, left["__enc"] == right["__other"], "left")
    return joined.select(*x.columns, F.col("__other").isNotNull().cast("long").alias("hit"), *(F.coalesce(f"__y_{n}", F.lit(0)).alias(n) for n in values))


def extended(x: Relation, key: list[str], y: DataFrame, y_key: list[str], values: dict[str, str], mode: str = "auto", y_live: str = LIVE, y_size: int | None = None) -> DataFrame:
    """Intersection for x with repeated keys, rows taken in rank order of the key: hit and values for every row of x.

    `index` lets only the first row of each key in each chunk meet its partner, and spreads what it got along the segment: a key
    that fills x meets its partner once per chunk, and chunks need nothing of each other.
    `lookup` joins each row with its partner and gives the same rows. `segments` lets each key's run of ranks meet its partner once
    and deals what it got over the chunks of the run. `auto` goes by schema and public sizes alone: the plain intersection where x
    does not repeat the key, a broadcast of y up to the bound, and `segments` beyond it, so that no key is hot.
    """
    few = y_size is not None and y_size <= x.conf.broadcast_rows
    if mode == "lookup" or (mode == "auto" and (few or x.tells_apart(key))):
        return payload(x.df, y if mode == "lookup" else y.where(F.col(y_live) == 1), key, y_key, values, LIVE, y_live, few and mode == "auto")
    if mode in ("auto", "segments"):
        live = y.where(F.col(y_live) == 1).select(*(F.col(o).alias(k) for o, k in zip(y_key, key)), *(F.col(c).alias(f"__v_{n}") for n, c in values.items()))
        return spread(x, key, segments(x, key).join(live, list(key)), {n: f"__v_{n}" for n in values})
    rk = rank_col(key)
    seg = [F.col(LIVE), *(F.when(F.col(LIVE) == 1, F.col(k)) for k in key)]
    one = scan.first_in_chunks(x.df, seg, "__head", pos=rk, conf=x.conf).withColumn("__first", F.col("__head") * F.col(LIVE))
    met = payload(one, y, key, y_key, values, "__first", y_live)
    return scan.copied_in_chunks(met, "__head", ["hit", *values], pos=rk, conf=x.conf).drop("__head", "__first")


def segments(rel: Relation, key: Iterable[str]) -> DataFrame:
    """key, __first and __last: the ranks of each key's live rows, which are consecutive."""
    rk, live = rank_col(key), rel.df.where(F.col(LIVE) == 1)
    if rel.tells_apart(key):
        return live.select(*key, F.col(rk).alias("__first"), F.col(rk).alias("__last"))
    return live.groupBy(*key).agg(F.min(rk).alias("__first"), F.max(rk).alias("__last"))


def spread(x: Relation, key: Iterable[str], runs: DataFrame, values: dict[str, str]) -> DataFrame:
    """x with `hit` and, for each name -> column of runs in values, what its key's segment has there, or 0.

    runs are segments of x. A row finds its own by key and chunk of its rank, so that a key that fills x is dealt over chunks.
    """
    each = runs.withColumn("__at", F.explode(F.sequence(scan.chunk_of(F.col("__first"), x.conf), scan.chunk_of(F.col("__last"), x.conf))))
    each = each.select(*(F.col(k).alias(f"__k{i}") for i, k in enumerate(key)), "__at", *(F.col(c).alias(f"__y_{n}") for n, c in values.items()))
    deal = F.when(F.col(LIVE) == 1, scan.chunk_of(F.col(rank_col(key)), x.conf)).otherwise(-F.col(POS))  # a dummy has a place of its own
    left = x.df.withColumn("__deal", deal)
    joined = left.join(each, [left["__deal"] == each["__at"], *(left[k] == each[f"__k{i}"] for i, k in enumerate(key))], "left")
    return joined.select(*x.df.columns, F.col("__at").isNotNull().cast("long").alias("hit"), *(F.coalesce(f"__y_{n}", F.lit(0)).alias(n) for n in values))


def marked(x: Relation, key: Iterable[str], runs: DataFrame) -> DataFrame:
    """x with `hit`, 1 where the row's rank lies in one of the runs: a bit per rank is looked up, rows do not move."""
    rk = rank_col(key)
    words = scan.words_of_runs(runs, x.size).select("__block", "__bits")
    met = x.df.join(F.broadcast(words), F.shiftright(F.col(rk) - 1, 16) == F.col("__block"))
    bit = F.expr(f"shiftright(get(__bits, cast(shiftright({rk} - 1, 6) & 1023 AS int)), cast(({rk} - 1) & 63 AS int)) & 1")
    return met.select(*x.df.columns, bit.alias("hit"))


def check_degrees(df: DataFrame, degree: str, m: int, live: str = LIVE) -> None:
    """Raises unless dummies have degree 0, degrees are not negative, and their sum is at most m; for audits, as it opens this."""
    bad, total = df.agg(F.sum((((F.col(live) == 0) & (F.col(degree) != 0)) | (F.col(degree) < 0)).cast("long")), F.sum(degree)).first()
    if bad or (total or 0) > m:
        raise ValueError(f"degrees: {bad or 0} rows break the rules, sum {total} for {m} places")


def _fits(total: Column, m: int, value: Column) -> Column:
    """value, or an error where more copies are asked for than there are places."""
    return F.when(total > m, F.raise_error(F.concat(total.cast("string"), F.lit(f" copies do not fit in {m}"))).cast("long")).otherwise(value)


def expand(df: DataFrame, degree: str, m: int, size: int, pos: str = POS, mode: str = "explode", conf: MpcConf = DEFAULT, first: str | None = None) -> DataFrame:
    """Each row `degree` times, in order of pos, then empty rows up to m: columns of df, __copy (from 1), __new (position 1..m).

    Padding rows have nulls everywhere but in __new. `explode` lists the copies of each row, heavy rows block by block;
    `scan` places each row where its first copy belongs (rows of degree 0 past m, cut off later) and copies forward. `first`
    names a column that holds the first positions already. More copies than places are an error when rows are drawn.
    """
    spark = df.sparkSession
    if first:
        placed = df.withColumns({"__first": F.col(first), "__end": F.col(first) + F.col(degree) - 1})
        placed = placed.withColumn("__first", _fits(F.when(F.col(degree) > 0, F.col("__end")).otherwise(0), m, F.col("__first")))
    else:
        placed = scan.prefix(df, {"__end": ("sum", F.col(degree))}, pos=pos, size=size, conf=conf, totals={"__end": "__sum"})
        placed = placed.withColumn("__first", _fits(F.col("__sum"), m, F.col("__end") - F.col(degree) + 1)).drop("__sum")
    if mode == "scan":
        at = F.when(F.col(degree) == 0, F.lit(m) + F.col(pos)).otherwise(F.col("__first"))
        row = F.struct(*df.columns, "__first", "__end")
        places = spark.range(1, m + 1).select(F.col("id").alias("__new"))
        marked = places.join(placed.select(at.alias("__new"), row.alias("__row")).where(F.col("__new") <= m), "__new", "left")
        filled = scan.prefix(marked, {"__row2": ("copy", F.col("__row"))}, pos="__new", size=m, conf=conf)
        inside = F.col("__new") <= F.col("__row2.__end")
        return filled.select(*(F.when(inside, F.col(f"__row2.{c}")).alias(c) for c in df.columns), F.when(inside, F.col("__new") - F.col("__row2.__first") + 1).alias("__copy"), "__new")
    block = conf.explode_block
    blocks = placed.where(F.col(degree) > 0).withColumn("__b", F.explode(F.sequence(F.lit(0).cast("long"), F.floor((F.col(degree) - 1) / block))))
    copies = blocks.withColumn("__copy", F.explode(F.sequence(F.col("__b") * block + 1, F.least((F.col("__b") + 1) * block, F.col(degree)))))
    real = copies.select(*df.columns, "__copy", (F.col("__first") + F.col("__copy") - 1).alias("__new"))
    # every place is listed, whatever the number of copies, and those behind the last copy are kept
    total = F.broadcast(df.agg(F.coalesce(F.sum(degree), F.lit(0)).alias("__sum")))
    pad = spark.range(1, m + 1).crossJoin(total).where("id > __sum").select(*(F.lit(None).cast(t).alias(c) for c, t in df.dtypes), F.lit(None).cast("long").alias("__copy"), F.col("id").alias("__new"))
    return real.unionByName(pad)


def expand_with_ranks(rel: Relation, degree: str, m: int, order: tuple[str, ...] | None = None, mode: str = "explode") -> Relation:
    """Expansion that keeps every rank valid: a row's copies get consecutive ranks after all copies of rows that rank below.

    One scan per key sums the degrees of the rows that rank below. With `order` rows are laid out in rank order of that key
    first. The result has the columns __copy and __from (the row's position before) among its attributes.
    """
    slim_attrs = (*rel.attrs, *([degree] if degree not in rel.attrs else []))
    df = source = settle(rel.df.select(*dict.fromkeys([*rel.columns, degree])))
    for k in rel.keys:
        df = scan.prefix(df, {f"__base_{rank_col(k)}": ("sum", F.col(degree))}, pos=rank_col(k), size=rel.size, conf=rel.conf, exclusive=True, summed=source)
    first = None
    if order:
        df = df.withColumns({POS: F.col(rank_col(order)), "__begin": F.col(f"__base_{rank_col(order)}") + 1})
        first = "__begin"
    df = settle(df.withColumn("__from", F.col(POS)))
    out = expand(df, degree, m, rel.size, mode=mode, conf=rel.conf, first=first)
    dead = F.col("__copy").isNull()
    ranks = {rank_col(k): F.when(dead, F.col("__new")).otherwise(F.col(f"__base_{rank_col(k)}") + F.col("__copy")).cast("long") for k in rel.keys}
    out = out.withColumns({**ranks, POS: F.col("__new"), LIVE: F.coalesce(LIVE, F.lit(0).cast("long"))})
    return rel.on(out, attrs=(*slim_attrs, "__copy", "__from"), size=m, unique=())


def zip_rows(a: DataFrame, b: DataFrame) -> DataFrame:
    """Rows of two arrays of equal length, side by side by position."""
    return a.join(b, POS)
