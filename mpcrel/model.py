"""Relations as ordered arrays of tuples with dummies, ranks and annotations."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterable
from contextlib import contextmanager
from contextvars import ContextVar
from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .config import DEFAULT, MpcConf

POS, LIVE, ANN = "__pos", "__live", "__ann"


def key_of(attrs: Iterable[str]) -> tuple[str, ...]:
    return tuple(sorted(attrs))


def rank_col(key: Iterable[str]) -> str:
    return "__rk_" + "_".join(key_of(key))


_recorders: list[list] = []


@contextmanager
def recorded():
    """Collects (columns, rows, tasks) of everything that is settled inside, for audits."""
    shapes: list = []
    _recorders.append(shapes)
    try:
        yield shapes
    finally:
        _recorders.remove(shapes)


_scope: ContextVar[list | None] = ContextVar("scope", default=None)


@contextmanager
def scratch():
    """What is settled inside can be released again; what is left at the end belongs to the scope around."""
    outer, mine = _scope.get(), []
    token = _scope.set(mine)
    try:
        yield
    finally:
        _scope.reset(token)
        if outer is not None:
            outer.extend(mine)


def release(*kept: DataFrame) -> None:
    """Deletes what was settled in the innermost scope and none of the kept frames reads."""
    mine = _scope.get()
    if not mine:
        return
    used, spark = {f.rsplit("/", 2)[1] for df in kept for f in df.inputFiles()}, kept[0].sparkSession
    for path in [p for p in mine if p.rsplit("/", 1)[1] not in used]:
        place = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        place.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(place, True)
        mine.remove(path)


#: Shuffle files of a finished write go at once instead of when the driver's memory is collected.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def settle(df: DataFrame) -> DataFrame:
    """Materialises df as Parquet in the shared folder that the session names in spark.checkpoint.dir, and cuts its lineage.

    Another folder is set only where the session names none and runs on one machine, as in tests.
    """
    spark = df.sparkSession
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        named = sc.getConf().get("spark.checkpoint.dir")
        if not named and not sc.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir names no folder that the machines share")
        sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="checkpoint-"))
    path, before = f"{sc.getCheckpointDir()}/settled-{uuid.uuid4().hex}", spark.conf.get(CLEANUP, None)
    spark.conf.set(CLEANUP, "true")
    try:
        df.write.option("compression", "zstd").parquet(path)
    finally:
        spark.conf.set(CLEANUP, before) if before is not None else spark.conf.unset(CLEANUP)
    out = spark.read.schema(df.schema).parquet(path)
    if _scope.get() is not None:
        _scope.get().append(path)
    for shapes in _recorders:
        shapes.append((tuple(out.columns), out.count(), len(out.inputFiles())))
    return out


@dataclass(frozen=True)
class Relation:
    """A DataFrame with __pos 1..size, __live (0 marks a dummy), attributes, rank columns and maybe annotations.

    Invariant: every rank column is a bijection onto 1..size in which live rows come first and equal key values are
    adjacent, in the same order of keys in every relation that has the key.
    """

    df: DataFrame
    attrs: tuple[str, ...]
    keys: tuple[tuple[str, ...], ...] = ()
    size: int = 0
    anns: tuple[str, ...] = ()
    conf: MpcConf = DEFAULT
    unique: tuple[tuple[str, ...], ...] = ()  # attributes that tell its live rows apart, as its schema says

    @property
    def width(self) -> int:
        """Attributes and ranks, the factor of a row in the plan cost."""
        return len(self.attrs) + len(self.keys)

    @property
    def columns(self) -> list[str]:
        return [POS, LIVE, *self.attrs, *self.anns, *map(rank_col, self.keys)]

    def tells_apart(self, key: Iterable[str]) -> bool:
        """Whether, by its schema, no two live rows have equal values of the key."""
        return any(set(u) <= set(key) for u in self.unique)

    def has(self, key: Iterable[str]) -> bool:
        return key_of(key) in self.keys

    def on(self, df: DataFrame, **changes) -> Relation:
        out = replace(self, df=df, **changes)
        return replace(out, df=df.select(*out.columns))

    def settled(self) -> Relation:
        return replace(self, df=settle(self.df.select(*self.columns)))


def load(df: DataFrame, attrs: Iterable[str], anns: dict[str, Column] | None = None, conf: MpcConf = DEFAULT, order: Iterable[str] | None = None) -> Relation:
    """A plain table of one owner as a relation; annotations are computed on the fly, null keys must not occur.

    Positions come from the rows' order by `order` (all attributes by default), chunk by chunk, so that they are the same
    after a lost task.
    """
    from .operators.ranks import positions

    attrs, anns = tuple(attrs), dict(anns or {})
    rows = df.select(*attrs, *(c.alias(a) for a, c in anns.items()), F.lit(1).cast("long").alias(LIVE))
    placed, size = positions(rows, list(order or attrs), conf)
    return Relation(placed, attrs, (), size, tuple(anns), conf)


def set_dummy(rel: Relation, condition: Column) -> Relation:
    """Rows for which the condition does not hold become dummies; ranks are not repaired."""
    return rel.on(rel.df.withColumn(LIVE, F.when(condition, F.col(LIVE)).otherwise(F.lit(0).cast("long"))))


def dummy_eq(a: Column, a_live: Column, b: Column, b_live: Column) -> Column:
    """Dummies equal each other and no real row."""
    return ((a_live == 0) & (b_live == 0)) | ((a_live == 1) & (b_live == 1) & (a == b))


def pad_to(rel: Relation, size: int) -> Relation:
    """Dummies are appended up to a public size; in each rank they come last, in order."""
    if size < rel.size:
        raise ValueError(f"{rel.size} rows do not fit in {size}")
    if size == rel.size:
        return rel
    spark = rel.df.sparkSession
    kinds = dict(rel.df.dtypes)
    extra = spark.range(rel.size + 1, size + 1).select(
        F.col("id").alias(POS), F.lit(0).cast("long").alias(LIVE), *(F.lit(None).cast(kinds[c]).alias(c) for c in (*rel.attrs, *rel.anns)), *(F.col("id").alias(rank_col(k)) for k in rel.keys))
    return rel.on(rel.df.select(*rel.columns).unionByName(extra), size=size)


def reveal(rel: Relation) -> DataFrame:
    """Opens the result: dummies go, behind a barrier over which no filter moves into the oblivious steps."""
    return settle(rel.df.select(*rel.columns)).where(F.col(LIVE) == 1).select(*rel.attrs, *rel.anns)
