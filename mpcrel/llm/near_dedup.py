"""MinHash near-deduplication with sequential Bayesian verification.

Documents with equal shingle sets form a class. Class representatives are banded by MinHash; in each bucket the member that
meets most others is compared with all of them, batch after batch of hashes, and a pair is dropped as soon as the posterior
probability that it reaches the threshold falls below the chosen miss probability. Survivors are verified on their full
shingle sets. In buckets that then still hold several components, members of different components are compared block by
block: every plausible pair whose ends no link joins yet is verified where it is found. So no pair of a bucket goes untested
although neither plausible pairs nor pairs within a component are ever listed.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .base import connected_components, looked_up, settle

#: Words that a Python worker remembers.
MEMO = 100_000
_MASK = (1 << 64) - 1
#: Fixed odd multipliers, one for each place in a shingle, repeated with changes for longer ones.
_PLACE = (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9)


@dataclass(frozen=True)
class NearConfig:
    shingle: int = 5
    percent: int = 80  # similarity of a link, at least
    rows: int = 4  # hashes in a band
    miss: float = 1e-6  # probability that a pair at the threshold shares no band
    posterior: float = 1e-5  # a pair less likely than this to be a link is dropped
    batch: int = 24  # hashes compared at a time
    block: int = 512  # members, and
    block_shingles: int = 400_000  # shingles of a block of a bucket, on average
    tile_pairs: int = 4000  # pairs whose shingle sets are verified together, and
    tile_shingles: int = 2_000_000  # the shingles of both ends of these pairs
    broadcast_ids: int = 500_000  # more ids, digests or keys are joined by a shuffle
    broadcast_sigs: int = 20_000  # more signatures are joined by a shuffle
    seed: int = 1

    @property
    def bands(self) -> int:
        return math.ceil(math.log(self.miss) / math.log1p(-((self.percent / 100) ** self.rows)))

    @property
    def hashes(self) -> int:
        return self.bands * self.rows


def bounds(conf: NearConfig) -> list[tuple[int, int]]:
    """(hashes compared, fewest equal ones with which a pair stays), under a uniform prior for the similarity.

    With m of n equal, the posterior probability of at least t is that of at most m successes in n + 1 trials of chance t.
    """
    t, out = conf.percent / 100, []
    for n in [*range(conf.batch, conf.hashes, conf.batch), conf.hashes]:
        total, m = 0.0, 0
        while m <= n:
            total += math.comb(n + 1, m) * t**m * (1 - t) ** (n + 1 - m)
            if total >= conf.posterior:
                break
            m += 1
        out.append((n, m))
    return out


class _Words(dict):
    def __missing__(self, word: bytes) -> int:
        import xxhash

        if len(self) > MEMO:
            self.clear()
        out = self[word] = xxhash.xxh64_intdigest(word)
        return out


def shingles(text: str | None, size: int, words: dict):
    """Sorted distinct 64-bit hashes of a text's word shingles; of fewer words, of the whole sequence."""
    import numpy as np

    found = (text or "").encode().lower().split()
    if not found:
        return np.zeros(0, "uint64")
    h = np.fromiter(map(words.__getitem__, found), "uint64", len(found))
    k = min(size, len(h))
    n = len(h) - k + 1
    total = np.full(n, (len(h) * _PLACE[1] if len(h) < size else 0) & _MASK, "uint64")
    for place in range(k):
        part = h[place : place + n] * np.uint64((_PLACE[place % 3] + 2 * (place // 3)) & _MASK)
        total += part ^ (part >> np.uint64(29)) if place % 2 else part
        total *= np.uint64(0xBF58476D1CE4E5B9)
        total ^= total >> np.uint64(31)
    return np.unique(total)


def _multipliers(conf: NearConfig):
    import numpy as np

    rng = np.random.default_rng(conf.seed)
    return rng.integers(0, 2**63, conf.hashes, dtype="uint64") * np.uint64(2) + np.uint64(1), rng.integers(0, 2**63, conf.hashes, dtype="uint64")


def signature(hashes, a, b):
    import numpy as np

    low = np.full(len(a), 0xFFFFFFFF, "uint64")
    for start in range(0, len(hashes), 8192):
        part = hashes[start : start + 8192]
        low = np.minimum(low, ((part[None, :] * a[:, None] + b[:, None]) >> np.uint64(32)).min(1))
    return low.astype("uint32")


def sketches(documents: DataFrame, conf: NearConfig) -> DataFrame:
    """doc_id, n, digest (of the set), sig (little-endian 32-bit words), keys (of the bands); no keys for an empty set."""
    def sketch(batches):
        import hashlib

        import numpy as np
        import pyarrow as pa

        a, b = _multipliers(conf)
        words = _Words()
        fold = np.random.default_rng(conf.seed + 1).integers(0, 2**63, conf.rows, dtype="uint64") | np.uint64(1)
        lane = np.arange(conf.bands, dtype="uint64") * np.uint64(0x9E3779B97F4A7C15)
        for batch in batches:
            n, digest, sig, keys = [], [], [], []
            for text in batch.column(1):
                s = shingles(text.as_py(), conf.shingle, words)
                n.append(len(s))
                digest.append(hashlib.blake2b(s.tobytes(), digest_size=16).digest())
                if len(s):
                    own = signature(s, a, b)
                    sig.append(own.tobytes())
                    mixed = (own.reshape(conf.bands, conf.rows).astype("uint64") + np.uint64(1)) * fold
                    key = (mixed ^ (mixed >> np.uint64(32))).sum(1, dtype="uint64") * np.uint64(0xBF58476D1CE4E5B9) + lane
                    keys.append((key ^ (key >> np.uint64(29))).view("int64"))
                else:
                    sig.append(b"")
                    keys.append([])
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(digest, pa.binary()), pa.array(sig, pa.binary()), pa.array(keys, pa.list_(pa.int64()))], names=["doc_id", "n", "digest", "sig", "keys"])

    return documents.select("doc_id", "text").mapInArrow(sketch, f"doc_id {documents.schema['doc_id'].dataType.simpleString()}, n long, digest binary, sig binary, keys array<long>")


def _plausible(pairs: DataFrame, sigs: DataFrame, conf: NearConfig) -> DataFrame:
    """Of pairs (leader, rep, weight) those that pass every batch of the sequential test, as (a, b, weight), a < b."""
    leaders = settle(pairs.select("leader").distinct().join(sigs.select(F.col("rep").alias("leader"), F.col("sig").alias("sig_a")), "leader"))
    both = pairs.join(sigs.select("rep", F.col("sig").alias("sig_b")), "rep")
    both = looked_up(both, leaders, ["leader"], leaders.count(), conf.broadcast_sigs, F.xxhash64("rep"), "inner")
    both = both.select(F.least("leader", "rep").alias("a"), F.greatest("leader", "rep").alias("b"), "weight", "sig_a", "sig_b")

    def test(batches):
        import numpy as np
        import pyarrow as pa

        for batch in batches:
            if not batch.num_rows:
                continue
            x, y = (np.frombuffer(b"".join(batch.column(c).to_pylist()), "<u4").reshape(batch.num_rows, conf.hashes) for c in ("sig_a", "sig_b"))
            live, equal, last = np.arange(batch.num_rows), np.zeros(batch.num_rows, "int64"), 0
            for n, least in bounds(conf):
                equal[live] += (x[live, last:n] == y[live, last:n]).sum(1)
                live, last = live[equal[live] >= least], n
            yield pa.RecordBatch.from_arrays([batch.column(c).take(pa.array(live)) for c in ("a", "b", "weight")], names=["a", "b", "weight"])

    return both.select("a", "b", "weight", "sig_a", "sig_b").mapInArrow(test, "a long, b long, weight long").dropDuplicates(["a", "b"])


def _sets(ids: DataFrame, documents: DataFrame, conf: NearConfig) -> DataFrame:
    """doc_id, shingles (sorted 64-bit words) of the texts with these ids; settled."""
    def sets(batches):
        import pyarrow as pa

        words = _Words()
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([shingles(t.as_py(), conf.shingle, words).tobytes() for t in batch.column(1)], pa.binary())], names=["doc_id", "shingles"])

    ids = settle(ids.distinct())
    few = F.broadcast(ids) if ids.count() <= conf.broadcast_ids else ids
    return settle(documents.select("doc_id", "text").join(few, "doc_id", "left_semi").mapInArrow(sets, "doc_id long, shingles binary").where("length(shingles) > 0"))


def _verified(pairs: DataFrame, documents: DataFrame, conf: NearConfig) -> DataFrame:
    """The pairs whose full shingle sets reach the threshold, with the two measures."""
    full = _sets(pairs.select(F.col("a").alias("doc_id")).union(pairs.select(F.col("b").alias("doc_id"))), documents, conf)
    # pairs are dealt to tiles by both ends, and crowded tiles are split, so that a set is sent once to each tile that needs
    # it and not once for each of its pairs
    load = F.greatest(F.count("*") / conf.tile_pairs, F.coalesce(F.sum("weight"), F.lit(0)) / conf.tile_shingles)
    side = max(1, math.ceil(math.sqrt(pairs.agg(load).first()[0])))
    tile = ["i", "j", "k"]
    dealt = pairs.select("a", "b", "weight", F.pmod(F.xxhash64("a"), F.lit(side)).alias("i"), F.pmod(F.xxhash64("b"), F.lit(side)).alias("j"))
    crowded = dealt.groupBy("i", "j").agg(F.ceil(load).alias("parts"))
    crowded = F.broadcast(crowded) if side * side <= conf.broadcast_ids else crowded
    dealt = dealt.join(crowded, ["i", "j"]).select("a", "b", "i", "j", F.pmod(F.xxhash64("b", F.lit(7), "a"), F.col("parts")).alias("k"))
    needed = dealt.select("i", "j", "k", F.explode(F.array("a", "b")).alias("doc_id")).distinct()
    theirs = [f"of_{t}" for t in tile]
    sent = needed.withColumnsRenamed(dict(zip(tile, theirs))).join(full, "doc_id").select(*theirs, "doc_id", "shingles")

    def measure(those, these):
        import numpy as np
        import pyarrow as pa

        held = {d: np.frombuffer(x.as_py(), "uint64") for d, x in zip(these.column("doc_id").to_pylist(), these.column("shingles"))}
        out = []
        for a, b in zip(those.column("a").to_pylist(), those.column("b").to_pylist()):
            x, y = held.get(a), held.get(b)
            if x is None or y is None:
                continue
            i = len(np.intersect1d(x, y, assume_unique=True))
            u = len(x) + len(y) - i
            if u and 100 * i >= conf.percent * u:
                out.append((a, b, i, u))
        columns = list(zip(*out)) or [[], [], [], []]
        return pa.table({name: pa.array(c, pa.int64()) for name, c in zip(("a", "b", "common", "total"), columns)})

    return dealt.groupBy(*tile).cogroup(sent.groupBy(*theirs)).applyInArrow(measure, "a long, b long, common long, total long")


def _bucket_links(members: DataFrame, components: DataFrame, sigs: DataFrame, documents: DataFrame, conf: NearConfig) -> DataFrame:
    """Links that join different components of the members of a bucket of three or more.

    The component with most members of a bucket is its main one; only the members outside it look for links, in all members.
    All members are cut into blocks and those outside into chunks, by rows and shingles, and each task holds one block and one
    chunk with signatures and full sets: a bucket with a few outsiders is sent once, whatever its size. Pairs that pass the
    sequential test in the first band they share are verified on the spot, the likeliest first, unless links found before
    already join their ends. So a group gives fewer links than it has members, however many of its pairs are plausible.
    """
    linked = looked_up(members, components.withColumnRenamed("node", "rep"), ["rep"], components.count(), conf.broadcast_ids, F.xxhash64("key"))
    labelled = settle(linked.select("key", "band", "rep", "n", F.coalesce("component", "rep").alias("component")))
    parts = labelled.groupBy("key", "component").agg(F.count("*").alias("rows"), F.sum("n").alias("weight"), F.min("n").alias("low"), F.max("n").alias("high"))
    heads = parts.groupBy("key").agg(F.sum("rows").alias("size"), F.sum("weight").alias("weight"), F.count("*").alias("kinds"), F.max(F.struct("rows", "component")).alias("main")).where("size > 2 and kinds > 1")
    outside = parts.join(heads.select("key", F.col("main.component").alias("main")), "key").where("component <> main").groupBy("key").agg(
        F.sum("rows").alias("out_rows"), F.sum("weight").alias("out_weight"), F.min("low").alias("low"), F.max("high").alias("high"))
    cut = lambda rows, weight: F.ceil(F.greatest(F.col(rows) / conf.block, F.col(weight) / conf.block_shingles)).cast("int")
    mixed = settle(heads.join(outside, "key").select("key", F.col("main.component").alias("main"), "low", "high", cut("size", "weight").alias("blocks"), cut("out_rows", "out_weight").alias("chunks")))
    near = (100 * F.col("n") >= conf.percent * F.col("low")) & (100 * F.col("high") >= conf.percent * F.col("n"))  # of a size that a link allows
    rows = looked_up(labelled, mixed, ["key"], mixed.count(), conf.broadcast_ids, F.xxhash64("rep"), "inner").where(near)
    rows = settle(rows.select("key", "band", "rep", "component", (F.col("component") == F.col("main")).alias("is_main"), F.pmod(F.xxhash64("rep", "key"), F.col("blocks")).cast("int").alias("block"),
                              F.pmod(F.xxhash64("key", "rep"), F.col("chunks")).cast("int").alias("chunk"), "blocks", "chunks"))
    full = _sets(rows.select(F.col("rep").alias("doc_id")), documents, conf).withColumnRenamed("doc_id", "rep")
    shape = ["key", "band", "rep", "component", "is_main"]
    held = rows.select(*shape, F.lit(False).alias("seeks"), F.col("block").alias("i"), F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)).alias("j"))
    seeking = rows.where("not is_main").select(*shape, F.lit(True).alias("seeks"), F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("i"), F.col("chunk").alias("j"))
    dealt = held.union(seeking).join(full.join(sigs, "rep"), "rep")

    def compare(table):
        import numpy as np
        import pyarrow as pa

        sig = np.frombuffer(b"".join(table.column("sig").to_pylist()), "<u4").reshape(table.num_rows, conf.hashes)
        sets = [np.frombuffer(x, "uint64") for x in table.column("shingles").to_pylist()]
        sizes = np.array([len(x) for x in sets])
        ends = np.cumsum(sizes)
        known, place = np.unique(np.concatenate(sets), return_inverse=True)
        marked = np.zeros(len(known), bool)
        rep, component, is_main, seeks = (table.column(c).to_numpy() for c in ("rep", "component", "is_main", "seeks"))
        band = table.column("band")[0].as_py()
        _, label = np.unique(component, return_inverse=True)
        there, out = np.flatnonzero(~seeks), []
        for x in np.flatnonzero(seeks):
            y = there[(label[there] != label[x]) & (is_main[there] | (rep[there] > rep[x]))]
            y = y[100 * np.minimum(sizes[y], sizes[x]) >= conf.percent * np.maximum(sizes[y], sizes[x])]
            if band and len(y):
                earlier = (sig[y, : band * conf.rows] == sig[x, : band * conf.rows]).reshape(len(y), band, conf.rows).all(2).any(1)
                y = y[~earlier]
            last, equal = 0, np.zeros(len(y), "int64")
            for n, least in bounds(conf):
                equal += (sig[y, last:n] == sig[x, last:n]).sum(1)
                y, equal, last = y[equal >= least], equal[equal >= least], n
            y = y[np.argsort(-equal, kind="stable")]
            mine = place[ends[x] - sizes[x] : ends[x]]
            marked[mine] = True
            while len(y):
                some, y = y[:64], y[64:]
                theirs = np.concatenate([place[ends[z] - sizes[z] : ends[z]] for z in some])
                common = np.add.reduceat(marked[theirs], np.cumsum(sizes[some]) - sizes[some], dtype="int64")
                for z in some[100 * common >= conf.percent * (sizes[some] + sizes[x] - common)]:
                    if label[z] != label[x]:
                        out.append((min(rep[x], rep[z]), max(rep[x], rep[z])))
                        label[label == label[z]] = label[x]
                y = y[label[y] != label[x]]
            marked[mine] = False
        pairs = np.array(out, "int64").reshape(-1, 2)
        return pa.table({"a": pairs[:, 0], "b": pairs[:, 1]})

    return dealt.groupBy("key", "i", "j").applyInArrow(compare, "a long, b long").distinct()


def near_duplicates(documents: DataFrame, conf: NearConfig = NearConfig()) -> DataFrame:
    """doc_id, n_shingles, component_id, kept for every row; component_id is the smallest id that links reach.

    Null and empty texts have no shingles and no links. Rows without an id are components of their own (component_id null) and
    kept. Repeated rows get the same component; kept marks each of them if it marks one. An empty table gives an empty result.
    """
    drawn = settle(sketches(documents.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), conf))
    filled = drawn.where("doc_id is not null and n > 0")
    classes = settle(filled.groupBy("digest").agg(F.min("doc_id").alias("rep"), F.count("*").alias("rows")).where("rows > 1").select("digest", "rep"))
    number, spread = classes.count(), F.xxhash64("doc_id")
    first = looked_up(filled, classes, ["digest"], number, conf.broadcast_ids, spread).where("rep is null or doc_id = rep").select(F.col("doc_id").alias("rep"), "n", "sig", "keys")
    texts = documents.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    # keys that two rows have, then the rows that have them, each once
    banded = first.select("rep", "n", F.posexplode("keys").alias("band", "key"))
    keys = settle(banded.groupBy("key").agg(F.count("*").alias("rows")).where("rows > 1").select("key"))
    met = settle(looked_up(banded, keys, ["key"], keys.count(), conf.broadcast_ids, F.xxhash64("rep"), "inner").distinct())
    active = settle(met.select("rep").distinct())
    sigs = settle(first.select("rep", "sig").join(F.broadcast(active) if active.count() <= conf.broadcast_ids else active, "rep", "left_semi").dropDuplicates(["rep"]))
    ties = met.join(met.groupBy("key").agg(F.count("*").alias("size")), "key").groupBy("rep").agg(F.sum("size").alias("ties"))
    leaders = settle(met.join(ties, "rep").groupBy("key").agg(F.max(F.struct("ties", "rep", "n")).alias("l")).select("key", F.col("l.rep").alias("leader"), F.col("l.n").alias("leader_n")))
    pairs = looked_up(met, leaders, ["key"], leaders.count(), conf.broadcast_ids, F.xxhash64("rep"), "inner").where("rep <> leader")
    pairs = settle(pairs.select("leader", "rep", (F.col("n") + F.col("leader_n")).alias("weight")).dropDuplicates(["leader", "rep"]))
    links = settle(_verified(settle(_plausible(pairs, sigs, conf)), texts, conf).select("a", "b"))
    components = settle(connected_components(links))
    rest = settle(_bucket_links(met, components, sigs, texts, conf))
    if not rest.isEmpty():
        components = settle(connected_components(links.union(rest)))
    # copies get their class's component, others their own
    of_class = classes.join(components.withColumnRenamed("node", "rep"), "rep", "left").select("digest", F.coalesce("component", "rep").alias("of_class"))
    labelled = looked_up(drawn.select("doc_id", "n", "digest"), of_class, ["digest"], number, conf.broadcast_ids, spread)
    labelled = looked_up(labelled, components.withColumnRenamed("node", "doc_id"), ["doc_id"], components.count(), conf.broadcast_ids, F.xxhash64("digest"))
    linked = (F.col("n") > 0) & F.col("doc_id").isNotNull()
    component = F.when(linked, F.coalesce("of_class", "component", "doc_id")).otherwise(F.col("doc_id"))
    return labelled.select("doc_id", F.col("n").alias("n_shingles"), component.alias("component_id"), F.coalesce(component == F.col("doc_id"), F.lit(True)).alias("kept"))


def drop_near_duplicates(documents: DataFrame, conf: NearConfig = NearConfig(), broadcast_rows: int = 200_000) -> DataFrame:
    """One row of each component stays, with all its columns: that of the smallest id. Rows without an id stay.

    Repeated rows with one id are one document, which stays or goes. The ids that go are broadcast if they are few.
    """
    gone = settle(near_duplicates(documents, conf).where("not kept").select("doc_id").distinct())
    side = F.broadcast(gone) if gone.count() <= broadcast_rows else gone
    return documents.join(side, documents["doc_id"] == side["doc_id"], "left_anti")
