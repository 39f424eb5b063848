"""Helpers that the operators of this subpackage share."""

from __future__ import annotations

import tempfile

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Denominator of hash-based sampling fractions.
SAMPLE_SPACE = 1 << 30


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def settle(df: DataFrame) -> DataFrame:
    """Materialises df in the folder that the session names in spark.checkpoint.dir, which all machines share.

    A folder of our own is set only where the session names none and runs on one machine, as in tests.
    """
    sc = df.sparkSession.sparkContext
    if sc.getCheckpointDir() is None:
        named = sc.getConf().get("spark.checkpoint.dir")
        if not named and not sc.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir names no folder that the machines share")
        sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="checkpoint-"))
    return df.checkpoint(eager=True)


def looked_up(rows: DataFrame, facts: DataFrame, on: list[str], n: int, bound: int, spread: Column, how: str = "left", salts: int = 16) -> DataFrame:
    """rows joined with facts, of which there are n, one at most for each value of `on`.

    Up to the bound, facts are broadcast and rows stay where they are. Beyond it the rows of one value are dealt over several
    tasks by `spread`, a hash that differs among them, since a value may hold a third of all rows.
    """
    if n <= bound:
        return rows.join(F.broadcast(facts), on, how)
    parts = facts.withColumn("__part", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return rows.withColumn("__part", F.pmod(spread, F.lit(salts)).cast("int")).join(parts, [*on, "__part"], how).drop("__part")


def held_out(doc_id: Column, modulus: int, remainder: int) -> Column:
    """Whether crc32 of doc_id as text leaves the remainder; rows without an id are held out."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % modulus == remainder, F.lit(True))


def sampled(key: Column, fraction: float, seed: int = 17) -> Column:
    """A deterministic sample by the hash of a key, alike at every size and after a lost task."""
    if fraction >= 1:
        return F.lit(True)
    return F.pmod(F.xxhash64(key, F.lit(seed)), F.lit(SAMPLE_SPACE)) < int(fraction * SAMPLE_SPACE)


def labelled_sample(documents: DataFrame, labels: DataFrame, label: str, modulus: int, remainder: int, bound: int) -> DataFrame:
    """About `bound` labelled rows (doc_id, text, label) outside the held-out fold, chosen by hash, however long.

    Only their ids travel to the driver and back as a broadcast, so its size is fixed by `bound`. Labels that are null are
    ignored; of repeated labels for one document the largest counts. Where ids are repeated in documents, rows are drawn by
    their texts as well and equal rows count once, so that the bound holds for rows.
    """
    known = (labels.where(F.col(label).isNotNull() & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id"), modulus, remainder))
             .groupBy("doc_id").agg(F.max(label).cast("int").alias("label")))
    total = known.count()
    chosen = settle(known.where(sampled(F.col("doc_id"), bound / max(total, 1))))
    rows = documents.select("doc_id", "text").join(F.broadcast(chosen), "doc_id")
    n = rows.count()
    if n > 1.5 * chosen.count() + 100:
        rows = rows.where(F.pmod(F.xxhash64("text", "doc_id"), F.lit(SAMPLE_SPACE)) < int(bound / n * SAMPLE_SPACE)).dropDuplicates()
    return rows


def in_order(table, *lists: str):
    """The list columns of an Arrow table, row by row as numpy slices, and its labels; rows ordered by doc_id."""
    import numpy as np

    table = table.combine_chunks()
    order = np.argsort(table.column("doc_id").to_numpy(), kind="stable")
    columns = []
    for name in lists:
        chunks = table.column(name).chunks
        if not chunks:
            columns.append([])
            continue
        ends, flat = chunks[0].offsets.to_numpy(), chunks[0].values.to_numpy()
        columns.append([flat[ends[i] : ends[i + 1]] for i in order])
    return columns, table.column("label").to_numpy()[order]


def _hub_joined(edges: DataFrame, low: DataFrame, bound: int = 500_000) -> DataFrame:
    """Edges (u, v) with what low tells of u; a hub's edges are dealt over several tasks."""
    low = settle(low)
    return looked_up(edges, low, ["u"], low.count(), bound, F.xxhash64("v"), "inner")


def give_back() -> None:
    """Returns memory that a model's training has freed to the machine, since the driver lives on."""
    import ctypes
    import gc

    import pyarrow as pa

    gc.collect()
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim:
        trim(0)


#: Rows that travel between the JVM and Python at once.
BATCH = 1_000


def small_batches(spark: SparkSession) -> None:
    """From now on the session sends rows to Python in small batches, whose buffers both sides hold beside their own memory."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(name)) <= BATCH:
        spark.conf.set(name, str(BATCH))


def connected_components(links: DataFrame, max_rounds: int = 60, edges_in_task: int = 200_000) -> DataFrame:
    """(node, component) for every node of links (a, b); component is the smallest node that can be reached.

    Alternates the two star operations on edges: each node's larger neighbours are hung on its smallest neighbour, then its
    smaller ones. Nothing but the number of edges and a checksum reaches the driver. Edges that fit one task by their count
    are kept in one partition, so that rounds need no exchange.
    """
    edges = links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u <> v").distinct()
    edges = settle(edges)
    small = edges.count() <= edges_in_task
    if small:
        edges = settle(edges.coalesce(1))
    before = None
    for _ in range(max_rounds):
        both = edges.select(F.explode(F.array(F.struct("u", "v"), F.struct(F.col("v").alias("u"), F.col("u").alias("v")))).alias("e")).select("e.u", "e.v")
        low = both.groupBy("u").agg(F.min("v").alias("w")).select("u", F.least("u", "w").alias("m"))
        met = both.where("v > u").join(low, "u") if small else _hub_joined(both.where("v > u"), low)
        large = met.select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        # every row hangs its node and its neighbour on the smallest
        both = large.join(low, "u") if small else _hub_joined(large, low)
        hung = both.select("m", F.explode(F.array("u", "v")).alias("u")).where("u <> m").select("u", F.col("m").alias("v")).distinct()
        edges = settle(hung)
        mark = edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if mark == before:
            break
        before = mark
    else:
        raise RuntimeError("components did not settle")
    return edges.select(F.explode(F.array("u", "v")).alias("node"), F.col("v").alias("component")).groupBy("node").agg(F.min("component").alias("component"))
