"""Relational operators on ranked relations. Sizes of results depend on public sizes alone; ranks stay valid."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import Column
from pyspark.sql import functions as F

from ..functions.semiring import SUM_PRODUCT, Semiring
from ..model import LIVE, POS, Relation, key_of, rank_col, set_dummy, settle
from . import arrays, scan
from .ranks import refresh


def select(rel: Relation, predicate: Column) -> Relation:
    """Rows that fail become dummies, the size stays, ranks are repaired."""
    return refresh(set_dummy(rel, predicate))


def project(rel: Relation, attrs: Iterable[str]) -> Relation:
    """Drops attributes and the ranks that lost one of theirs; moves nothing."""
    attrs = tuple(a for a in rel.attrs if a in set(attrs))
    keys = tuple(k for k in rel.keys if set(k) <= set(attrs))
    return rel.on(rel.df, attrs=attrs, keys=keys, unique=tuple(u for u in rel.unique if set(u) <= set(attrs)))


def drop_ranks(rel: Relation, keep: Iterable[Iterable[str]]) -> Relation:
    keep = set(map(key_of, keep))
    return rel.on(rel.df, keys=tuple(k for k in rel.keys if k in keep))


def aggregate(rel: Relation, key: Iterable[str], aggs: dict[str, tuple[str, Column]] | None = None) -> Relation:
    """One live row per key value, the last of its segment in rank order, with aggs as annotations; the others are dummies.

    aggs: name -> (sum, max, min or count, column); default the relation's annotations summed. An empty key is one group.
    """
    key = key_of(key)
    aggs = {a: ("sum", F.col(a)) for a in rel.anns} if aggs is None else aggs
    live = F.col(LIVE) == 1
    values = {f"__g_{n}": (op, F.when(live, c)) for n, (op, c) in aggs.items()}
    if not key:
        order = POS
        rel = arrays.compact_live(rel)
        seg = [F.col(LIVE)]
    else:
        order = rank_col(key)
        seg = [F.col(LIVE), *(F.when(live, F.col(k)) for k in key)]
    ran = scan.segmented(rel.df, seg, values, pos=order, size=rel.size, conf=rel.conf, last="__last")
    kept = ran.withColumn(LIVE, F.when(F.col("__last"), F.col(LIVE)).otherwise(F.lit(0).cast("long"))).drop(*aggs)
    kept = kept.withColumnsRenamed({f"__g_{n}": n for n in aggs})
    keys = tuple(k for k in rel.keys if set(k) <= set(key))
    return refresh(rel.on(kept, attrs=tuple(a for a in rel.attrs if a in key), keys=keys, anns=tuple(aggs), unique=(key,)).settled())


def distinct(rel: Relation, attrs: Iterable[str]) -> Relation:
    return aggregate(rel, attrs, {})


def having_share(rel: Relation, part: int, of: int) -> Relation:
    """Groups whose annotation passes part/of of the total stay, the others become dummies; the total is opened to nobody."""
    total = aggregate(project(drop_ranks(rel, []), ()), (), {rel.anns[0]: ("sum", F.col(rel.anns[0]))})
    beside = rel.df.crossJoin(_one_row(total, (rel.anns[0],)))
    return select(_with(rel, beside), F.col(rel.anns[0]) * of > F.col(f"v_{rel.anns[0]}") * part)


def _first_of_each(rel: Relation, key: tuple[str, ...]) -> Relation:
    """All but the last live row of each key value become dummies; ranks are left alone."""
    live = F.col(LIVE) == 1
    ran = scan.segmented(rel.df, [F.col(LIVE), *(F.when(live, F.col(k)) for k in key)], {}, pos=rank_col(key), size=rel.size, conf=rel.conf, last="__last")
    return rel.on(ran.withColumn(LIVE, F.when(F.col("__last"), F.col(LIVE)).otherwise(F.lit(0).cast("long"))))


def common(a: Relation, b: Relation) -> tuple[str, ...]:
    return key_of(set(a.attrs) & set(b.attrs))


def semijoin(rel: Relation, other: Relation, anti: bool = False, mode: str = "auto") -> Relation:
    """Rows without a partner on the common attributes become dummies (with `anti`, those with one)."""
    key = common(rel, other)
    if not key:
        tagged = rel.df.crossJoin(_one_row(other))
    elif mode == "auto" and rel.conf.broadcast_rows < other.size and rel.size <= rel.conf.word_places:
        tagged = arrays.marked(rel, key, arrays.segments(rel, key).join(arrays.segments(other, key).select(*key), list(key)))
    else:
        single = _first_of_each(other, key) if not other.tells_apart(key) else other
        tagged = arrays.extended(rel, list(key), single.df.select(POS, LIVE, *key), list(key), {}, mode=mode, y_size=other.size)
    return refresh(set_dummy(_with(rel, tagged), F.col("hit") == (0 if anti else 1)).settled())


def _with(rel: Relation, df) -> Relation:
    """rel over a frame with more columns, which stay visible to the next step only."""
    from dataclasses import replace

    return replace(rel, df=df)


def _one_row(rel: Relation, names: Iterable[str] = ()):
    """hit (1 if a row lives) and the annotations of the only live row, as one row whatever lives; for empty keys."""
    live = F.col(LIVE) == 1
    return F.broadcast(rel.df.agg(F.coalesce(F.max(LIVE), F.lit(0)).alias("hit"), *(F.coalesce(F.max(F.when(live, F.col(n))), F.lit(0)).alias(f"v_{n}") for n in names)))


def reduce_join(parent: Relation, child: Relation, semiring: Semiring = SUM_PRODUCT, mode: str = "auto") -> Relation:
    """Child's attributes are a key of it and belong to parent: annotations are multiplied, rows without a partner die."""
    key = key_of(child.attrs)
    names = semiring.names
    if not key:
        met = parent.df.crossJoin(_one_row(child, names))
    else:
        met = arrays.extended(parent, list(key), child.df.select(POS, LIVE, *key, *names), list(key), {f"v_{n}": n for n in names}, mode=mode, y_size=child.size)
    product = semiring.times([F.col(n) for n in names], [F.col(f"v_{n}") for n in names])
    rows = met.withColumns({f"__p_{n}": c for n, c in zip(names, product)}).drop(*names).withColumnsRenamed({f"__p_{n}": n for n in names})
    return refresh(set_dummy(_with(parent, rows), F.col("hit") == 1).settled())


def counted(rel: Relation, key: tuple[str, ...]):
    """__pos, __live, key and __n: how many live rows have the key, at the last of them; the other rows are dummies."""
    live = F.col(LIVE) == 1
    ran = scan.segmented(rel.df.select(POS, LIVE, *key, rank_col(key)), [F.col(LIVE), *(F.when(live, F.col(k)) for k in key)], {"__n": ("count", F.when(live, 1))}, pos=rank_col(key), size=rel.size, conf=rel.conf, last="__last")
    return ran.select(POS, F.when(F.col("__last"), F.col(LIVE)).otherwise(F.lit(0).cast("long")).alias(LIVE), *key, "__n")


def lengths(rel: Relation, key: tuple[str, ...]):
    """The same as counted but for the dummies, which it leaves out: how many ranks a key's live rows take."""
    return arrays.segments(rel, key).select(F.col("__first").alias(POS), F.lit(1).cast("long").alias(LIVE), *key, (F.col("__last") - F.col("__first") + 1).alias("__n"))


def degrees(rel: Relation, other: Relation, key: tuple[str, ...], mode: str = "auto"):
    """rel with __d: how many live rows of other share its key, 0 for dummies."""
    return arrays.extended(rel, list(key), (lengths if mode == "auto" else counted)(other, key), list(key), {"__d": "__n"}, mode=mode, y_size=other.size).drop("hit")


def join(r: Relation, s: Relation, m: int, semiring: Semiring | None = None, mode: str = "auto", expansion: str = "explode") -> Relation:
    """All matching pairs in rank order of the common attributes, then dummies up to the public bound m.

    Both sides are expanded by the number of their partners. The copies of s then go where the copies of r are: the c-th copy
    of the j-th of d_s rows of a key belongs in that key's (c-1)-th block of d_s places, at the j-th. Ranks of both sides stay.
    """
    key = common(r, s)
    if not key:
        raise ValueError("no common attribute")
    live = F.col(LIVE) == 1
    left = arrays.expand_with_ranks(_with(r, degrees(r, s, key, mode)), "__d", m, order=key, mode=expansion)
    seg = [F.col(LIVE), *(F.when(live, F.col(k)) for k in key)]
    rk = rank_col(key)
    if mode == "auto":  # from the ranks: how many rows a segment has, and which of them a row is
        runs = arrays.segments(s, key).join(lengths(r, key).select(*key, "__n"), list(key))
        runs = runs.withColumn("__own", F.col("__last") - F.col("__first") + 1)
        met = arrays.spread(s, key, runs, {"__d": "__n", "__own": "__own", "__begin": "__first"})
        met = met.withColumn("__j", F.col(rk) - F.col("__begin") + 1).drop("hit", "__begin")
    else:  # a row's number in its segment from the front and from behind
        own = settle(scan.segmented(s.df, seg, {"__j": ("count", F.lit(1))}, pos=rk, size=s.size, conf=s.conf))
        back = own.withColumn("__back", F.lit(s.size + 1) - F.col(rk))
        own = scan.segmented(back, seg, {"__left": ("count", F.lit(1))}, pos="__back", size=s.size, conf=s.conf)
        own = own.withColumn("__own", F.when(live, F.col("__j") + F.col("__left") - 1).otherwise(0)).drop("__back", "__left")
        met = degrees(_with(s, own), r, key, mode)
    s2 = _with(s, met).on(met, attrs=(*s.attrs, "__d", "__j", "__own"))
    right = arrays.expand_with_ranks(s2, "__d", m, order=key, mode=expansion)
    # places before this key's block: own position less the copies of the key's earlier rows and this row's earlier copies
    first = F.col(POS) - ((F.col("__j") - 1) * F.col("__d") + F.col("__copy") - 1)
    target = F.when(F.col("__copy").isNull(), F.col(POS)).otherwise(first + (F.col("__copy") - 1) * F.col("__own") + F.col("__j") - 1)
    keep = [a for a in s.attrs if a not in key]
    extra_keys = [k for k in s.keys if k not in r.keys]
    anns = tuple(r.anns)
    names = semiring.names if semiring and s.anns and r.anns else ()
    side = right.df.select(target.cast("long").alias(POS), F.col(LIVE).alias("__live_s"), *keep, *(F.col(rank_col(k)) for k in extra_keys), *(F.col(a).alias(f"__s_{a}") for a in s.anns))
    zipped = arrays.zip_rows(left.df.select(POS, LIVE, *r.attrs, *r.anns, *(rank_col(k) for k in r.keys)), side)
    zipped = zipped.withColumn(LIVE, F.col(LIVE) * F.col("__live_s"))
    if names:
        product = semiring.times([F.col(n) for n in names], [F.col(f"__s_{n}") for n in names])
        zipped = zipped.withColumns({f"__p_{n}": c for n, c in zip(names, product)}).drop(*names).withColumnsRenamed({f"__p_{n}": n for n in names})
    elif s.anns and not r.anns:
        zipped, anns = zipped.withColumnsRenamed({f"__s_{a}": a for a in s.anns}), tuple(s.anns)
    # the ranks on s's other keys follow the rows of s to their targets
    return r.on(zipped, attrs=(*r.attrs, *keep), keys=(*r.keys, *extra_keys), size=m, anns=anns, unique=()).settled()


def join_size(r: Relation, s: Relation) -> int:
    """Number of matching live pairs, the exact m of one join."""
    key = common(r, s)
    d = degrees(r, s, key)
    return int(d.agg(F.coalesce(F.sum(F.col("__d") * F.col(LIVE)), F.lit(0))).first()[0])


def order_by_rank(rel: Relation, key: Iterable[str]) -> Relation:
    return arrays.permute(rel, F.col(rank_col(key)))
