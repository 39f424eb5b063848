"""The systems that the method is compared with, as runs on plain tables and as cost formulas."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import settle
from . import meter
from .query import JoinAggQuery, columns


def nested_loop(query: JoinAggQuery, spark: SparkSession, sf_dir: str, limit: int | None = None) -> DataFrame:
    """Every combination of rows is formed and tested, however many there are, or refused beyond a limit that the caller names."""
    frames, product = [], 1
    for name, s in query.sources.items():
        cols, passes = columns(query, name)
        df = settle(s.table(spark, sf_dir).where(passes).select(*cols))
        product *= max(df.count(), 1)
        frames.append((name, df))
    if limit is not None and product > limit:
        raise ValueError(f"{product} combinations")
    out, seen, tests = None, {}, F.lit(True)
    for name, df in frames:
        df = df.select(*(F.col(a).alias(f"{name}.{a}".replace(".", "__")) for a in query.sources[name].attrs))
        out = df if out is None else out.crossJoin(df)
        for a in query.sources[name].attrs:
            here = F.col(f"{name}__{a}")
            if a in seen:
                tests = tests & (F.col(seen[a]) == here)
            else:
                seen[a] = f"{name}__{a}"
    return out.withColumn("__live", tests.cast("long")).where("__live = 1").select(*(F.col(seen[a]).alias(a) for a in query.outputs))


def two_way_chain(query: JoinAggQuery, spark: SparkSession, sf_dir: str) -> tuple[DataFrame, list[int]]:
    """Pairwise joins one after the other with exact sizes: the naive composition, which reveals every intermediate size."""
    plan, sizes, dfs = query.plan(), [], {}
    for name, s in query.sources.items():
        cols, passes = columns(query, name)
        dfs[name] = s.table(spark, sf_dir).where(passes).select(*cols[: len(s.attrs)])
    left = dict(plan.tree.parents)
    out = {n: dfs[n] for n in left}
    for child in plan.tree.bottom_up():
        parent = left[child]
        if parent is None:
            continue
        key = sorted(set(out[parent].columns) & set(out[child].columns))
        out[parent] = settle(out[parent].hint("merge").join(out[child].hint("merge"), key))
        sizes.append(out[parent].count())
    return out[plan.tree.root], sizes


def comparison(spark: SparkSession, sizes: dict[str, int], m: int, width: int) -> DataFrame:
    """method, megabytes, rounds for a chain of joins of relations of the given sizes with m output rows."""
    names = list(sizes)
    n = sum(sizes.values())
    own = meter.Meter()
    for a in names[1:]:
        own.semijoin(sizes[names[0]], sizes[a], width, 1)
        own.semijoin(sizes[a], sizes[names[0]], width, 1)
        own.join(sizes[names[0]], sizes[a], m, width, width, 1, 1)
    rival = [meter.sort_merge_join(sizes[names[0]], sizes[a], m, 2 * width, charge_sort=False) for a in names[1:]]
    bitonic = [meter.sort_merge_join(sizes[names[0]], sizes[a], m, 2 * width, bitonic=True) for a in names[1:]]
    rows = [("oblivious", own.bytes / 1e6, own.rounds), ("sort-merge", sum(b for b, _ in rival) / 1e6, sum(r for _, r in rival)),
            ("sort-merge, earlier three-party", 5 * sum(b for b, _ in rival) / 1e6, 0),  # published ratio at 2^16 rows
            ("sort-merge, bitonic", sum(b for b, _ in bitonic) / 1e6, sum(r for _, r in bitonic)), ("two-party", meter.two_party(n, m, width, len(names)) / 1e6, 0),
            ("circuit, three phases", meter.circuit_three_phase(n, m) * 16 / 1e6, 0), ("nested loop", meter.nested_loop(list(sizes.values())) / 1e6, 0),
            ("plaintext", meter.plaintext([(x, width) for x in sizes.values()], m, width) / 1e6, 1)]
    return spark.createDataFrame([(a, float(b), int(c)) for a, b, c in rows], "method string, megabytes double, rounds int")
