"""Canonical exact digests of documents, with built-in functions only.

The canonical text is in the Unicode compatibility form NFKC, case-folded, and has each run of white space folded to one space.
Two xxhash64 words of it, with different seeds, make the fingerprint; texts are grouped by it and inside a group of more than one
their bytes are compared, so that a group never holds two different canonical texts.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .base import looked_up, settle

#: Blocks of texts laid side by side hold about so many rows.
BLOCK_ROWS = 128
#: Shared digests up to this number are broadcast.
BROADCAST_DIGESTS = 1_000_000
#: Texts of these characters alone are in NFKC, and lower case is their case folding.
PLAIN = r"^[\x00-\x7F\xC0-\xD6\xD8-\xDE\xE0-\xF6\xF8-\xFF]*+$"
_NORMALISE, _FOLD = "com.ibm.icu.text.Normalizer", "com.ibm.icu.lang.UCharacter"


def _java(owner: str, method: str, text: Column) -> Column:
    """A static method of Spark's own Unicode library, of a text and a flag."""
    return F.reflect(F.lit(owner), F.lit(method), text, F.lit(True))


def with_canonical(df: DataFrame, names: dict[str, str]) -> DataFrame:
    """df with canonical texts: names is column of text -> name of its canonical form.

    Texts of ASCII and Latin-1 letters take a shorter way to the same result.
    """
    for source, out in names.items():
        compose = lambda c: _java(_NORMALISE, "compose", c)
        steps = [
            ("__text", F.coalesce(F.col(source), F.lit(""))),
            ("__plain", (F.length("__text") == F.octet_length("__text")) | F.col("__text").rlike(PLAIN)),
            ("__folded", F.when(F.col("__plain"), F.lower("__text")).otherwise(compose(_java(_FOLD, "foldCase", compose(F.col("__text")))))),
            ("__spaced", F.when(F.col("__plain"), F.regexp_replace("__folded", r"\s+", " ")).otherwise(F.regexp_replace("__folded", r"[\s\x{85}\x{1680}\x{2028}\x{2029}]+", " "))),
            (out, F.trim("__spaced")),
        ]
        for name, column in steps:
            df = df.withColumn(name, column)
        df = df.drop(*(name for name, _ in steps[:-1]))
    return df


def wide_hash(canon: Column) -> Column:
    """Two words of xxhash64, 32 hexadecimal digits."""
    return F.lower(F.concat(F.lpad(F.hex(F.xxhash64(canon)), 16, "0"), F.lpad(F.hex(F.xxhash64(F.lit(0x5EED), canon, F.length(canon))), 16, "0")))


def _joined(rows: DataFrame, shared: DataFrame, n: int, how: str = "left") -> DataFrame:
    """rows (with doc_id and canon) and what is known of their shared digests."""
    return looked_up(rows, shared, ["digest"], n, BROADCAST_DIGESTS, F.xxhash64("doc_id", "canon"), how)


def shared_digests(documents: DataFrame) -> tuple[DataFrame, int]:
    """digest, group_id, group_size of the digests of more than one row whose texts are all equal, how many digests are shared,
    and, in the column canon, one row for each text of a digest that several texts share.

    Only digests are shuffled for all rows. Equal texts of a shared digest are counted before they are shuffled, so a group of
    copies is one row for each task, however large it is.
    """
    texts = with_canonical(documents.select("doc_id", "text"), {"text": "canon"}).select("doc_id", "canon", wide_hash(F.col("canon")).alias("digest"))
    counts = texts.groupBy("digest").agg(F.min("doc_id").alias("first"), F.count("*").alias("n"))
    shared = settle(counts.where("n > 1"))
    many = shared.count()
    equal = _joined(texts, shared.select("digest"), many, "left_semi" if many <= BROADCAST_DIGESTS else "inner").groupBy("digest", "canon").agg(F.min("doc_id").alias("group_id"), F.count("*").alias("group_size"))
    equal = settle(equal.select("digest", "group_id", "group_size", F.sha2(F.col("canon").cast("binary"), 256).alias("sha"), "canon"))
    kinds = settle(equal.groupBy("digest").agg(F.count("*").alias("kinds")).where("kinds > 1"))
    met = equal.join(F.broadcast(kinds) if kinds.count() <= BROADCAST_DIGESTS else kinds, "digest", "left")
    return settle(met.select("digest", "group_id", "group_size", F.when(F.col("kinds").isNotNull(), F.col("canon")).alias("same"))), many


def _grouped(rows: DataFrame, shared: DataFrame, many: int) -> DataFrame:
    """rows (doc_id, digest, canon, ...) with group_id and group_size."""
    met = _joined(rows, shared.where("same is null").drop("same"), many)
    split = shared.where("same is not null").select("digest", F.col("same").alias("canon"), F.col("group_id").alias("__id"), F.col("group_size").alias("__size"))
    if not split.isEmpty():  # digests that different texts share
        met = met.join(split, ["digest", "canon"], "left").withColumns({"group_id": F.coalesce("__id", "group_id"), "group_size": F.coalesce("__size", "group_size")}).drop("__id", "__size")
    alone = F.col("group_size").isNull()
    return met.withColumns({"group_id": F.when(alone, F.col("doc_id")).otherwise(F.col("group_id")), "group_size": F.coalesce("group_size", F.lit(1))})


def exact_groups(documents: DataFrame) -> DataFrame:
    """doc_id, digest, group_id, group_size for every row: equal canonical texts share the smallest doc_id of the group.

    A digest that different texts share gives several groups. Null text counts as empty; rows without an id take part, with
    group_id null unless they have company. Repeated rows count each. An empty table gives an empty result.
    """
    shared, many = shared_digests(documents)
    rows = with_canonical(documents.select("doc_id", "text"), {"text": "canon"}).select("doc_id", "canon", wide_hash(F.col("canon")).alias("digest"))
    return _grouped(rows, shared, many).select("doc_id", "digest", "group_id", "group_size")


def with_next(documents: DataFrame, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """doc_id, text, next_text by ascending doc_id, the first document following the last; null text becomes empty.

    Rows without an id come first, by a hash of their texts. Ids are dealt into blocks of equal width, and blocks that hold many
    times block_rows are cut again by their own range, so that ids may lie anyhow. A block's first row is also sent to the
    block before it, so that one window within blocks finds every neighbour, and texts are shuffled once. Rows with one id
    are ordered by text.
    """
    rows = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    without = rows.where("doc_id is null").limit(1).count()
    at = F.coalesce("doc_id", F.shiftrightunsigned(F.xxhash64("text"), 2)) if without else F.col("doc_id")
    rows = rows.withColumns({"slot": F.col("doc_id").isNotNull().cast("int") if without else F.lit(1), "at": at})
    ids = rows.select("slot", "at")
    found = {r["slot"]: r for r in ids.groupBy("slot").agg(F.min("at").alias("low"), F.max("at").alias("high"), F.count("*").alias("n")).collect()}
    if not found:
        return rows.select("doc_id", "text", F.lit("").alias("next_text"))
    block, over = F.lit(None).cast("string"), F.lit(None).cast("string")
    for slot, r in found.items():
        width = max(1, (r["high"] - r["low"] + 1) * block_rows // r["n"])
        step = lambda w: F.concat_ws("/", F.lit(slot), F.expr(f"`at` div {min(w, 1 << 62)}L"))
        here = F.col("slot") == slot
        block, over = F.when(here, step(width)).otherwise(block), F.when(here, step(width << 14)).otherwise(over)
    finer: list[DataFrame] = []

    def dealt(df: DataFrame) -> DataFrame:
        df = df.withColumn("block", block)
        for cuts in finer:
            df = df.join(cuts.withColumnRenamed("block", "__cut"), F.col("block") == F.col("__cut"), "left")
            df = df.withColumn("block", F.when(F.col("__width").isNotNull(), F.concat_ws("/", "block", F.expr("(`at` - __low) div __width"))).otherwise(F.col("block"))).drop("__cut", "__low", "__width")
        return df

    while True:
        heads = settle(dealt(ids).withColumn("over", over).groupBy("slot", "over", "block").agg(F.min("at").alias("low"), F.max("at").alias("high"), F.count("*").alias("n")))
        crowded = heads.where((F.col("n") > 16 * block_rows) & (F.col("high") > F.col("low")))
        number = crowded.count()
        if not number:
            break
        cuts = settle(crowded.select("block", F.col("low").alias("__low"), F.greatest(F.lit(1), F.expr(f"high div greatest(n div {block_rows}, 2) - low div greatest(n div {block_rows}, 2)")).alias("__width")))
        finer.append(F.broadcast(cuts) if number <= BROADCAST_DIGESTS else cuts)
    # the block before each, within groups of blocks, and over their borders
    tops = heads.groupBy("slot", "over").agg(F.min("low").alias("top"), F.max_by("block", "low").alias("final"))
    by_top = W.orderBy("slot", "top")
    tops = tops.select("slot", "over", F.lag("final").over(by_top).alias("before_top"))
    end = heads.agg(F.max_by("block", F.struct("slot", "low"))).first()[0]
    links = heads.withColumn("before", F.lag("block").over(W.partitionBy("slot", "over").orderBy("low"))).join(tops, ["slot", "over"])
    links = settle(links.select("slot", F.col("low").alias("at"), F.coalesce("before", "before_top", F.lit(end)).alias("to")))
    heads_of = rows.join(F.broadcast(links) if links.count() <= BROADCAST_DIGESTS else links, ["slot", "at"])
    copies = heads_of.groupBy("slot", "at", "to").agg(F.min(F.struct("text", "doc_id")).alias("r")).select("slot", "at", "r.doc_id", "r.text", F.col("to").alias("block"), F.lit(1).alias("copy"))
    both = dealt(rows).select("slot", "at", "doc_id", "text", "block", F.lit(0).alias("copy")).union(copies)
    # in its block, the copy comes last: it has a larger id, or is the first document of all
    order = W.partitionBy("block").orderBy("copy", "slot", "at", "text")
    return both.withColumn("next_text", F.lead("text").over(order)).where("copy = 0").select("doc_id", "text", "next_text")


def edited(text: Column, following: Column) -> Column:
    half = F.floor(F.length(text) / 2).cast("int")
    return F.concat(F.substring(text, F.lit(1), F.length(text) - half), F.substring(following, F.lit(1), half))


def fingerprints(documents: DataFrame) -> DataFrame:
    """doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next of every document, and the group_id
    and group_size that exact_groups gives it.

    Digests are exact, so a likeness is 1 where the canonical bytes are equal and 0 elsewhere. Null text is empty. Of rows with
    one doc_id, or none, each is its own document; the order among them is that of with_next. An empty table gives an empty
    result; other columns are not read.
    """
    documents = documents.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    shared, many = shared_digests(documents)
    changed = with_next(documents).withColumn("edited", edited(F.col("text"), F.col("next_text")))
    own = with_canonical(changed, {"text": "canon", "edited": "__c1", "next_text": "__c2"})
    own = own.withColumns({f: wide_hash(F.col(c)) for f, c in (("digest", "canon"), ("edited_fingerprint", "__c1"), ("__next", "__c2"))})

    def alike(other: str, canon: str) -> Column:
        return F.when(F.col("digest") == F.col(other), F.col("canon") == F.col(canon)).otherwise(False).cast("double")

    made = own.select("doc_id", F.length("text").cast("long").alias("n_chars"), F.sha2(F.col("edited").cast("binary"), 256).alias("edited_sha256"), "digest", "canon",
                      "edited_fingerprint", alike("edited_fingerprint", "__c1").alias("near_edited"), alike("__next", "__c2").alias("near_next"))
    return _grouped(made, shared, many).withColumnRenamed("digest", "fingerprint").select(
        "doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next", "group_id", "group_size")
