"""Quality by supervised subword embeddings.

Each white-space token, each of its character n-grams and each pair of neighbouring tokens has a hashed vector (all pairs of
equal tokens the same one); a document is the average of these vectors and a softmax layer gives the classes. Both are learned by stochastic gradient descent in numpy on
a bounded sample of labelled rows. Since the layer is linear in the average, scoring needs one number for each bucket: its
vector times the difference of the two output rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import letters
from .base import give_back, held_out, in_order, labelled_sample


@dataclass(frozen=True)
class SubwordConfig:
    bits: int = 17  # of the number of buckets
    dim: int = 8
    shortest: int = 3
    longest: int = 4
    sample_rows: int = 1_000
    epochs: int = 6
    least_steps: int = 200
    batch: int = 64
    rate: float = 2.0
    seed: int = 11

    @property
    def buckets(self) -> int:
        return 1 << self.bits


def features(texts: list, conf: SubwordConfig) -> Iterator[tuple]:
    """(number of the text, bucket) of tokens, of pairs of tokens and of n-grams, array by array.

    A token of more than letters.PART characters counts as several.
    """
    import numpy as np

    own, left, right, *grams = letters.odd(4 + conf.longest, conf.seed)
    solid = letters.character_table("solid")
    for codes, owners in letters.parts(texts):
        starts, ends = letters.runs(solid[codes])
        if not len(starts):
            continue
        whose = owners[starts]
        words = letters.Stretches(codes).hashes(starts, ends)
        yield whose, letters.bucket(words * np.uint64(own), conf.bits)
        again = np.uint64(right)  # a pair of equal tokens is hashed as a pair of some token and itself
        pairs = np.where(words[:-1] == words[1:], again, words[:-1] * np.uint64(left) + words[1:] * np.uint64(right))
        beside = whose[1:] == whose[:-1]
        yield whose[1:][beside], letters.bucket((pairs ^ (pairs >> np.uint64(31)))[beside] * np.uint64(own), conf.bits)
        for run, found in letters.n_grams(codes, starts, ends, range(conf.shortest, conf.longest + 1), grams, conf.bits):
            yield whose[run], found


def fit(rows: list, labels, conf: SubwordConfig = SubwordConfig()) -> dict:
    """rows: (buckets, weights) of each document, weights summing to 1. Returns the score of each bucket and the bias."""
    import numpy as np

    y = np.asarray(labels, "int64")
    if not len(y) or not 0 < y.sum() < len(y):
        share = (y.sum() + 0.5) / (len(y) + 1)
        return {"bias": float(np.log(share / (1 - share))), "s": np.zeros(conf.buckets, "float32")}
    rng = np.random.default_rng(conf.seed)
    table = rng.uniform(-1 / conf.dim, 1 / conf.dim, (conf.buckets, conf.dim)).astype("float32")
    out, bias = rng.normal(0, 0.1, (2, conf.dim)), np.log(np.bincount(y, minlength=2) / len(y))
    order, batches = rng.permutation(len(rows)), []
    for start in range(0, len(order), conf.batch):
        pick = order[start : start + conf.batch]
        full = np.array([len(rows[i][0]) > 0 for i in pick])
        sizes = np.array([len(rows[i][0]) for i in pick[full]], "int64")
        idx = np.concatenate([rows[i][0] for i in pick]).astype("int32")
        share = np.concatenate([rows[i][1] for i in pick]).astype("float32")[:, None]
        doc = np.repeat(np.flatnonzero(full), sizes).astype("int16")
        by_bucket = np.argsort(idx, kind="stable").astype("int32")
        used, first = np.unique(idx[by_bucket], return_index=True)
        batches.append((pick, full, np.cumsum(sizes) - sizes, idx, share, doc, by_bucket, used, first.astype("int32")))
    epochs = max(conf.epochs, conf.least_steps // len(batches))
    steps, done = epochs * len(batches), 0
    for _ in range(epochs):
        for turn in rng.permutation(len(batches)):
            pick, full, begins, idx, share, doc, by_bucket, used, first = batches[turn]
            rate = conf.rate * (1 - done / steps)
            done += 1
            mean = np.zeros((len(pick), conf.dim), "float32")
            if len(idx):
                mean[full] = np.add.reduceat(table[idx] * share, begins)
            z = mean @ out.T + bias
            p = np.exp(z - z.max(1, keepdims=True))
            p /= p.sum(1, keepdims=True)
            p[np.arange(len(pick)), y[pick]] -= 1
            if len(idx):
                table[used] -= rate * np.add.reduceat(((p @ out).astype("float32")[doc] * share)[by_bucket], first)
            out -= rate * (p.T @ mean)
            bias = bias - rate * p.sum(0) / len(pick)
    return {"bias": float(bias[1] - bias[0]), "s": (table @ (out[1] - out[0])).astype("float32")}


def weighted(text: str | None, conf: SubwordConfig = SubwordConfig()):
    """Buckets of a document with their shares of the average."""
    import numpy as np

    found = [b for _, b in features([text], conf)]
    ids, times = np.unique(np.concatenate(found), return_counts=True) if found else (np.zeros(0, "int64"), np.zeros(0))
    return ids, times / max(times.sum(), 1)


def scores(texts: list, model: dict, conf: SubwordConfig = SubwordConfig()):
    """The probability of class 1 of each text."""
    import numpy as np

    total, times = np.zeros(len(texts)), np.zeros(len(texts))
    for whose, found in features(texts, conf):
        total += np.bincount(whose, model["s"][found], len(texts))
        times += np.bincount(whose, minlength=len(texts))
    return 1 / (1 + np.exp(-np.clip(model["bias"] + total / np.maximum(times, 1), -30, 30)))


def train(documents: DataFrame, labels: DataFrame, conf: SubwordConfig = SubwordConfig(), modulus: int = 5, remainder: int = 0, label: str = "quality") -> dict:
    """Trains on about conf.sample_rows labelled rows outside the held-out fold."""
    def hashed(batches):
        import pyarrow as pa

        for batch in batches:
            found = [weighted(t.as_py(), conf) for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([a for a, _ in found], pa.list_(pa.int32())), pa.array([b for _, b in found], pa.list_(pa.float32())), batch.column(2)], names=["doc_id", "ids", "shares", "label"])

    sample = labelled_sample(documents, labels, label, modulus, remainder, conf.sample_rows)
    kind = sample.schema["doc_id"].dataType.simpleString()
    rows = sample.mapInArrow(hashed, f"doc_id {kind}, ids array<int>, shares array<float>, label int").toArrow()
    (ids, shares), labels = in_order(rows, "ids", "shares")
    model = fit(list(zip(ids, shares)), labels, conf)
    del rows, ids, shares
    give_back()
    return model


def score_quality(documents: DataFrame, model: dict, conf: SubwordConfig = SubwordConfig(), modulus: int = 5, remainder: int = 0, threshold: float = 0.3) -> DataFrame:
    """doc_id, held_out, score, predicted for every row.

    Null and empty texts get the score of a text without tokens. Rows with one doc_id are scored one by one. An empty table
    gives an empty result; other columns are not read.
    """
    return with_scores(documents.select("doc_id", held_out(F.col("doc_id"), modulus, remainder).alias("held_out"), "text"), model, conf, threshold, drop_text=True)


def with_scores(rows: DataFrame, model: dict, conf: SubwordConfig = SubwordConfig(), threshold: float = 0.3, drop_text: bool = False, prefix: str = "") -> DataFrame:
    """rows with the columns score and predicted (named with the prefix) added at the end."""
    sent = rows.sparkSession.sparkContext.broadcast(model)
    kept = [c for c in rows.columns if not (drop_text and c == "text")]

    def scored(batches):
        import pyarrow as pa

        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                some = batch.slice(at, 512)
                values = scores(some.column("text").to_pylist(), sent.value, conf)
                yield pa.RecordBatch.from_arrays([*(some.column(c) for c in kept), pa.array(values), pa.array((values >= threshold).astype("int32"))], names=[*kept, f"{prefix}score", f"{prefix}predicted"])

    from pyspark.sql.types import DoubleType, IntegerType, StructType

    schema = StructType([rows.schema[c] for c in kept]).add(f"{prefix}score", DoubleType()).add(f"{prefix}predicted", IntegerType())
    return rows.mapInArrow(scored, schema)
