"""Toxicity by a factorization machine over hashed terms.

score = sigmoid(bias + sum of w[t] + sum over pairs of terms of <v[t], v[u]>), over the distinct hashed terms of a text. Unlike
linear weights, the factors learn that two terms mean more together than each alone. A text's terms are its words and their
stems, so that unseen endings of a known stem count too. The model is trained in numpy by adaptive stochastic gradient descent
on a bounded sample of labelled rows. A term takes part if it is tied to the label there, alone or in a pair: of the commonest
terms every pair is tested for what its two terms mean together beyond the sum of what each means alone. The other terms, which
would only add noise, keep weight zero.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import letters
from .base import give_back, held_out, in_order, labelled_sample


@dataclass(frozen=True)
class FmConfig:
    bits: int = 18  # of the number of buckets
    factors: int = 6
    sample_rows: int = 12_000
    stems: tuple[int, ...] = (4, 5, 6)
    min_documents: int = 6
    min_tie: float = 4.0  # standard deviations of a term's tie to the label
    pair_terms: int = 1024  # commonest terms, whose pairs are tested
    min_pair_tie: float = 6.0
    epochs: int = 40
    least_steps: int = 1500
    batch: int = 256
    rate: float = 0.1
    l2: float = 1e-4
    seed: int = 7

    @property
    def buckets(self) -> int:
        return 1 << self.bits


def terms(texts: list, conf: FmConfig):
    """(number of the text, bucket) of the distinct terms of each text, in order."""
    import numpy as np

    word = letters.character_table("word")
    own, *of_stem = letters.odd(1 + len(conf.stems), conf.seed)
    found = [np.zeros(0, "int64")]
    for codes, owners in letters.parts([(t or "").lower() for t in texts]):
        starts, ends = letters.runs(word[codes])
        stretches = letters.Stretches(codes)
        kinds = [(own, starts, ends)]
        for size, multiplier in zip(conf.stems, of_stem):
            longer = starts[ends - starts >= size]
            kinds.append((multiplier, longer, longer + size))
        codes_of = [owners[a] * np.int64(conf.buckets) + letters.bucket(stretches.hashes(a, b) * np.uint64(m), conf.bits) for m, a, b in kinds]
        found.append(np.unique(np.concatenate(codes_of)))
    both = np.unique(np.concatenate(found)) if len(found) > 2 else found[-1]
    return both >> conf.bits, both & (conf.buckets - 1)


def tied(rows: list, y, conf: FmConfig):
    """Buckets tied to the label y alone or in a pair, ascending."""
    import numpy as np

    lists = [np.asarray(r, "int64") for r in rows] or [np.zeros(0, "int64")]
    sizes, every = np.array(list(map(len, lists))), np.concatenate(lists)
    seen = np.bincount(every, minlength=conf.buckets)
    n, share = len(y), seen / max(len(y), 1)
    rest = y - y.mean() if n else y
    summed = np.bincount(every, np.repeat(rest, sizes) if n else None, conf.buckets)
    with np.errstate(divide="ignore", invalid="ignore"):
        tie = np.nan_to_num(summed / np.sqrt(np.maximum(seen * (1 - share), 0) * rest.var()), posinf=0, neginf=0) if n else summed
        alone = (seen >= conf.min_documents) & (np.abs(tie) >= conf.min_tie)
        common = np.sort(np.argsort(-seen * (1 - share), kind="stable")[: conf.pair_terms])
        common = common[(seen[common] >= conf.min_documents) & (seen[common] < n)]
        if len(common) > 1:
            place = np.full(conf.buckets, -1)
            place[common] = np.arange(len(common))
            held = np.zeros((n, len(common)), "float32")
            row, at = np.repeat(np.arange(n), sizes), place[every]
            held[row[at >= 0], at[at >= 0]] = 1
            both, together = held.T @ held, held.T @ (held * rest[:, None].astype("float32"))
            each = summed[common] / seen[common]
            beyond = (together - both * (each[:, None] + each)) / np.sqrt(both * rest.var())
            beyond[(both < conf.min_documents) | np.eye(len(common), dtype=bool)] = 0
            alone[common[np.abs(beyond).max(1) >= conf.min_pair_tie]] = True
    return np.flatnonzero(alone)


def fit(rows: list, labels, conf: FmConfig = FmConfig()) -> dict:
    """rows: arrays of distinct buckets. Returns bias, and for the buckets that carry weight their w and v."""
    import numpy as np

    y = np.asarray(labels, "float64")
    keep = tied(rows, y, conf)
    if not len(keep) or not 0 < y.sum() < len(y):
        share = (y.sum() + 0.5) / (len(y) + 1)
        return {"bias": float(np.log(share / (1 - share))), "ids": keep[:0], "w": np.zeros(0), "v": np.zeros((0, conf.factors))}
    place = np.full(conf.buckets, -1)
    place[keep] = np.arange(len(keep))
    rows = [(p := place[np.asarray(r, "int64")])[p >= 0] for r in rows]
    rng = np.random.default_rng(conf.seed)
    w, v = np.zeros(len(keep)), rng.normal(0, 0.03, (len(keep), conf.factors))
    gw, gv, gb = np.full(len(w), 1e-4), np.full(v.shape, 1e-4), 1e-4
    bias = float(np.log(y.mean() / (1 - y.mean())))
    weight = np.where(y == 1, 0.5 / y.mean(), 0.5 / (1 - y.mean())) ** 0.5
    order, batches = rng.permutation(len(rows)), []
    for start in range(0, len(order), conf.batch):
        pick = order[start : start + conf.batch]
        sizes = np.array([len(rows[i]) for i in pick])
        full = np.flatnonzero(sizes)
        idx, doc = np.concatenate([rows[i] for i in pick]), np.repeat(np.arange(len(pick)), sizes)
        by_term = np.argsort(idx, kind="stable")
        used, first = np.unique(idx[by_term], return_index=True)
        batches.append((pick, full, (np.cumsum(sizes) - sizes)[full], idx, doc[by_term], used, first))
    for _ in range(max(conf.epochs, conf.least_steps // len(batches))):
        for turn in rng.permutation(len(batches)):
            pick, full, begins, idx, doc, used, first = batches[turn]
            z, total = np.full(len(pick), bias), np.zeros((len(pick), conf.factors))
            if len(idx):
                vi = v[idx]
                total[full] = np.add.reduceat(vi, begins)
                z[full] += np.add.reduceat(w[idx], begins) + 0.5 * ((total[full] ** 2).sum(1) - np.add.reduceat((vi**2).sum(1), begins))
            err = weight[pick] * (1 / (1 + np.exp(-np.clip(z, -30, 30))) - y[pick]) / len(pick)
            gb += (err.sum()) ** 2
            bias -= conf.rate * err.sum() / gb**0.5
            if not len(idx):
                continue
            e = np.add.reduceat(err[doc], first)  # each row of a term holds the term once
            dw = e + conf.l2 * w[used]
            dv = np.add.reduceat((err[:, None] * total)[doc], first) - e[:, None] * v[used] + conf.l2 * v[used]
            gw[used] += dw**2
            gv[used] += dv**2
            w[used] -= conf.rate / np.sqrt(gw[used]) * dw
            v[used] -= conf.rate / np.sqrt(gv[used]) * dv
    return {"bias": bias, "ids": keep, "w": w, "v": v}


def scores(texts: list, model: dict, conf: FmConfig = FmConfig()):
    """The probability of class 1 of each text."""
    import numpy as np

    place = np.full(conf.buckets, -1, "int32")
    place[model["ids"]] = np.arange(len(model["ids"]))
    whose, found = terms(texts, conf)
    at = place[found]
    whose, at = whose[at >= 0], at[at >= 0]
    z = np.full(len(texts), float(model["bias"]))
    z += np.bincount(whose, model["w"][at], len(texts))
    for factor in model["v"].T:
        value = factor[at]
        z += 0.5 * (np.bincount(whose, value, len(texts)) ** 2 - np.bincount(whose, value**2, len(texts)))
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def train(documents: DataFrame, labels: DataFrame, conf: FmConfig = FmConfig(), modulus: int = 5, remainder: int = 0, label: str = "toxic") -> dict:
    """Trains on about conf.sample_rows labelled rows outside the held-out fold."""
    def hashed(batches):
        import pyarrow as pa

        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([terms([t.as_py()], conf)[1] for t in batch.column(1)], pa.list_(pa.int32())), batch.column(2)], names=["doc_id", "terms", "label"])

    sample = labelled_sample(documents, labels, label, modulus, remainder, conf.sample_rows)
    kind = sample.schema["doc_id"].dataType.simpleString()
    rows = sample.mapInArrow(hashed, f"doc_id {kind}, terms array<int>, label int").toArrow()
    (found,), labels = in_order(rows, "terms")
    model = fit(found, labels, conf)
    del rows, found
    give_back()
    return model


def score_toxicity(documents: DataFrame, model: dict, conf: FmConfig = FmConfig(), modulus: int = 5, remainder: int = 0, threshold: float = 0.5) -> DataFrame:
    """doc_id, held_out, score, predicted for every row.

    Null and empty texts get the score of a text without terms. Rows with one doc_id are scored one by one. An empty table
    gives an empty result; other columns are not read.
    """
    sent = documents.sparkSession.sparkContext.broadcast(model)

    def scored(batches):
        import pyarrow as pa

        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                some = batch.slice(at, 512)
                values = scores(some.column(2).to_pylist(), sent.value, conf)
                yield pa.RecordBatch.from_arrays([some.column(0), some.column(1), pa.array(values), pa.array((values >= threshold).astype("int32"))], names=["doc_id", "held_out", "score", "predicted"])

    kind = documents.schema["doc_id"].dataType.simpleString()
    return documents.select("doc_id", held_out(F.col("doc_id"), modulus, remainder).alias("held_out"), "text").mapInArrow(scored, f"doc_id {kind}, held_out boolean, score double, predicted int")
