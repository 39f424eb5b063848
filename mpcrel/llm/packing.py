"""Best-fit packing of token sequences, improved by a swap-based local search.

Pieces of one length are interchangeable, so the packing is found on the histogram of lengths: best fit in descending order
gives patterns (which lengths share a sequence) with a multiplicity, and the local search exchanges, moves and regroups
lengths between patterns. The work of the search depends on the capacity and not on the number of documents; the pieces
themselves are only ranked within their length and looked up in the list of slots.
"""

from __future__ import annotations

import zlib
from bisect import bisect_right
from collections import Counter, defaultdict

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

CAPACITY = 1024
END_OF_TEXT = 2
_encoders: dict = {}


def encoder(name: str):
    """text -> ids as little-endian 32-bit words, for one of the public byte-level vocabularies.

    The ids are those of the vocabulary file's own engine. A faster engine with the same ranks encodes each text whole, which
    costs less than ids that are remembered by word and looked up; texts with a special token's string are encoded by the
    file's engine, which gives it its id.
    """
    if name in _encoders:
        return _encoders[name]
    import base64
    import re

    import numpy as np
    import public_tokenizers
    import tiktoken
    from tokenizers import Tokenizer

    with open(public_tokenizers.path(name.replace(".json", ".tiktoken")), "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    bpe = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    plain = bpe.encode_ordinary
    own = Tokenizer.from_file(public_tokenizers.path(name))
    special = re.compile("|".join(re.escape(t.content) for t in own.get_added_tokens_decoder().values()) or r"(?!)").search

    def encode(text: str) -> bytes:
        if not special(text):
            try:
                return np.array(plain(text), dtype="<u4").tobytes()
            except BaseException as problem:  # the regex engine gives up on very long runs of white space
                if not isinstance(problem, Exception) and "Panic" not in type(problem).__name__:
                    raise
        return np.array(own.encode(text, add_special_tokens=False).ids, dtype="<u4").tobytes()

    _encoders[name] = encode
    return encode


def pieces(documents: DataFrame, tokenizer: str = "byte_bpe_50k.json", capacity: int = CAPACITY, end: int = END_OF_TEXT, with_ids: bool = False) -> DataFrame:
    """Token pieces of every document: doc_id, piece, start, length, ids_crc32 (and ids), and its place among equal lengths.

    Null text counts as empty. A document of more than `capacity` ids is cut into pieces of that length, of which the first
    takes the remainder. `task` and `nth` number the pieces of one length within one task.
    """
    def cut(batches):
        import numpy as np
        import pyarrow as pa
        from pyspark import TaskContext

        encode, tail = encoder(tokenizer), np.array([end], "<u4").tobytes()
        task, seen = TaskContext.get().partitionId(), [0] * (capacity + 1)
        for batch in batches:
            texts = batch.column(1)
            out = defaultdict(list)
            for row, doc in enumerate(batch.column(0).to_pylist()):
                ids = encode(texts[row].as_py() or "") + tail
                n = len(ids) // 4
                bounds = [0, *range(n % capacity or capacity, n + 1, capacity)] if n > capacity else [0, n]
                for k, (a, b) in enumerate(zip(bounds, bounds[1:])):
                    part = ids[4 * a : 4 * b]
                    for name, value in (("doc_id", doc), ("piece", k), ("start", a), ("length", b - a), ("ids_crc32", zlib.crc32(part)), ("nth", seen[b - a])):
                        out[name].append(value)
                    seen[b - a] += 1
                    if with_ids:
                        out["ids"].append(np.frombuffer(part, "<u4").astype("int32"))
            rows = len(out["piece"])
            columns = {"doc_id": pa.array(out["doc_id"], batch.schema.field(0).type), "piece": pa.array(out["piece"], pa.int32()),
                       "start": pa.array(out["start"], pa.int64()), "length": pa.array(out["length"], pa.int64()),
                       "ids_crc32": pa.array(out["ids_crc32"], pa.int64()), "task": pa.array([task] * rows, pa.int32()), "nth": pa.array(out["nth"], pa.int64())}
            if with_ids:
                columns["ids"] = pa.array(out["ids"], pa.list_(pa.int32()))
            yield pa.RecordBatch.from_pydict(columns)

    kind = documents.schema["doc_id"].dataType.simpleString()
    schema = f"doc_id {kind}, piece int, start long, length long, ids_crc32 long, task int, nth long" + ", ids array<int>" * with_ids
    return documents.select("doc_id", "text").mapInArrow(cut, schema)


def best_fit(counts: dict[int, int], capacity: int) -> Counter:
    """Patterns (descending tuples of lengths) and how often each is used: best fit in descending order, in bulk."""
    room: dict[int, Counter] = defaultdict(Counter)
    for size in sorted(counts, reverse=True):
        left = counts[size]
        while left:
            fits = min((r for r in room if r >= size), default=None)
            if fits is None:
                each = capacity // size
                full, rest = divmod(left, each)
                if full:
                    room[capacity - each * size][(size,) * each] += full
                if rest:
                    room[capacity - rest * size][(size,) * rest] += 1
                left = 0
                continue
            pattern, many = next(iter(room[fits].items()))
            # as many of this length as best fit would put in one of these bins before another becomes the better choice
            each = max(1, min(fits // size, left))
            if each > 1 and any(fits - each * size < r < fits and r >= size for r in room):
                each = 1
            used = min(many, left // each)
            room[fits][pattern] -= used
            if not room[fits][pattern]:
                del room[fits][pattern]
            if not room[fits]:
                del room[fits]
            room[fits - each * size][pattern + (size,) * each] += used
            left -= used * each
    return Counter({p: n for group in room.values() for p, n in group.items() if n})


def exchanged(a: tuple, b: tuple, capacity: int, offers: dict) -> tuple | None:
    """Lengths that leave the fuller bin a and those that leave b for it, by the largest gain of a; None if there is no gain.

    A move of one length from b comes before an exchange of one or two lengths of b for one of a.
    """
    for pattern in (a, b):
        if pattern not in offers:
            held = sorted(set(pattern))
            totals = {y + z: (y, z) for i, y in enumerate(held) for z in held[i:] if y != z or pattern.count(y) > 1} | {y: (y,) for y in held}
            offers[pattern] = held, sorted(totals), totals
    space, (held, sums, totals) = capacity - sum(a), offers[b]
    if held[0] <= space:
        return (), (held[bisect_right(held, space) - 1],)
    best, gain = None, 0
    for x in offers[a][0]:
        at = bisect_right(sums, space + x) - 1
        if at >= 0 and sums[at] - x > gain:
            best, gain = ((x,), totals[sums[at]]), sums[at] - x
    return best


def local_search(patterns: Counter, capacity: int) -> Counter:
    """Raises the sum of squared fills by moves between underfull bins until no two of them have a move that does.

    From the emptiest bins upward, one length moves to a fuller bin, or one is exchanged for a shorter one, or two for one,
    whenever the fuller bin still holds it. A bin that loses its last length is gone. Two patterns between which nothing can
    be gained are never tried again, so the work depends on the number of patterns and not on the number of bins.
    """
    bins, offers, settled = Counter(patterns), {}, set()
    changed = True
    while changed:
        changed = False
        for b in sorted((p for p in bins if sum(p) < capacity), key=lambda p: (sum(p), p)):
            for a in sorted((p for p in bins if sum(b) <= sum(p) < capacity), key=lambda p: (-sum(p), p)):
                if not bins.get(b):
                    break
                if (a, b) in settled or not bins.get(a) or (a == b and bins[a] < 2):
                    continue
                found = exchanged(a, b, capacity, offers)
                if not found:
                    settled.add((a, b))
                    continue
                out, into = found
                times = bins[a] // 2 if a == b else min(bins[a], bins[b])
                fuller, emptier = Counter(a), Counter(b)
                fuller.subtract(out)
                fuller.update(into)
                emptier.subtract(into)
                emptier.update(out)
                for gone in (a, b):
                    bins[gone] -= times
                    if not bins[gone]:
                        del bins[gone]
                for made in (fuller, emptier):
                    if pattern := tuple(sorted(made.elements(), reverse=True)):
                        bins[pattern] += times
                changed = True
    return bins


def pack_lengths(counts: dict[int, int], capacity: int = CAPACITY) -> Counter:
    return local_search(best_fit({s: n for s, n in counts.items() if n}, capacity), capacity)


def slots(patterns: Counter) -> dict[int, tuple]:
    """length -> (first rank, first sequence, offset) of each run of places for that length, by rank."""
    places, taken, sequence = defaultdict(list), Counter(), 0
    for pattern, many in sorted(patterns.items(), reverse=True):
        at = 0
        for size in pattern:
            places[size].append((taken[size], sequence, at))
            taken[size] += many
            at += size
        sequence += many
    return {size: tuple(zip(*runs)) for size, runs in places.items()}


def pack(documents: DataFrame, capacity: int = CAPACITY, tokenizer: str = "byte_bpe_50k.json", end: int = END_OF_TEXT, with_ids: bool = False) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset (and ids): every piece with its place in a sequence.

    Sequences hold at most `capacity` ids, without gaps from 0. Rows with the same doc_id or none are documents of their
    own; an empty table gives no pieces; an empty text is a piece of the end token alone.
    """
    from .base import settle

    cut = settle(pieces(documents, tokenizer, capacity, end, with_ids))
    counts = cut.groupBy("task", "length").agg(F.count("*").alias("n"))
    histogram = {r["length"]: r["n"] for r in counts.groupBy("length").agg(F.sum("n").alias("n")).collect()}  # at most `capacity` rows
    places = documents.sparkSession.sparkContext.broadcast(slots(pack_lengths(histogram, capacity)))
    before = W.partitionBy("length").orderBy("task").rowsBetween(W.unboundedPreceding, -1)
    starts = counts.select("task", "length", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("before"))
    ranked = cut.join(starts, ["task", "length"]).withColumn("rank", F.col("before") + F.col("nth"))

    def place(batches):
        import numpy as np
        import pyarrow as pa

        runs = {size: [np.array(x) for x in columns] for size, columns in places.value.items()}
        for batch in batches:
            length, rank = batch.column("length").to_numpy(), batch.column("rank").to_numpy()
            sequence, offset = np.zeros(len(rank), "int64"), np.zeros(len(rank), "int64")
            order = np.argsort(length, kind="stable")
            edges = np.flatnonzero(np.diff(length[order])) + 1
            for rows in np.split(order, edges) if len(order) else ():
                first, base, at = runs[int(length[rows[0]])]
                run = np.searchsorted(first, rank[rows], side="right") - 1
                sequence[rows] = base[run] + rank[rows] - first[run]
                offset[rows] = at[run]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in kept), pa.array(sequence), pa.array(offset)], names=[*kept, "sequence_id", "offset"])

    kept = ["doc_id", "piece", "start", "length", "ids_crc32", *["ids"] * with_ids]
    kind = documents.schema["doc_id"].dataType.simpleString()
    schema = f"doc_id {kind}, piece int, start long, length long, ids_crc32 long" + ", ids array<int>" * with_ids + ", sequence_id long, offset long"
    return ranked.select(*kept, "rank").mapInArrow(place, schema)
