"""Benchmark decontamination with a generalised suffix automaton over words.

The automaton holds every run of words of every test item. The words of a document stream through it while the length of the
longest run that ends at the current word is tracked; where that length reaches a window, the window's words are hits. Test
items are dealt into blocks of bounded size, one automaton each, so that what is broadcast does not grow with their number.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Bytes that end a word become spaces and A-Z become a-z; bytes of 0x80 and above belong to words.
_FOLD = bytes(c + 32 if 65 <= c <= 90 else c if c >= 128 or 48 <= c <= 57 or 97 <= c <= 122 else 32 for c in range(256))


@dataclass(frozen=True)
class DecontaminationConfig:
    window: int = 10
    block_words: int = 1_000_000  # words of test items in one automaton


def words_of(text: str | None) -> list[bytes]:
    return (text or "").encode().translate(_FOLD).split()


class Automaton:
    """Generalised suffix automaton of word sequences, with the items that hold each window."""

    def __init__(self, items: list[tuple[str, list[bytes]]], window: int):
        self.window = window
        vocabulary: dict[bytes, int] = {}
        nexts, links, lengths = [{}], [-1], [0]
        self.whole: dict[int, list[tuple[int, str]]] = {}  # state -> short items that end there
        holders: dict[int, set[str]] = {}
        for item, words in items:
            last, path = 0, []
            for word in words:
                last = self._extend(nexts, links, lengths, last, vocabulary.setdefault(word, len(vocabulary)))
                path.append(last)
            if 0 < len(words) < window:
                self.whole.setdefault(last, []).append((len(words), item))
            for state in path[window - 1 :]:
                holders.setdefault(state, set()).add(item)
        # later splits may have moved ends of short items: look their states up again
        self.vocabulary, self.nexts, self.links, self.lengths = vocabulary, nexts, links, lengths
        self.whole = {}
        shortest = window
        for item, words in items:
            if 0 < len(words) < window:
                state = 0
                for word in words:
                    state = nexts[state][vocabulary[word]]
                self.whole.setdefault(state, []).append((len(words), item))
                shortest = min(shortest, len(words))
        self.shortest = shortest
        # an item that ends in a state also ends in the states of its suffixes, as far as they hold a window
        order = sorted((s for s in range(len(links)) if lengths[s] >= window), key=lambda s: -lengths[s])
        for state in order:
            up = links[state]
            if up > 0 and lengths[up] >= window and state in holders:
                holders.setdefault(up, set()).update(holders[state])
        self.holders = {s: tuple(x) for s, x in holders.items()}

    @staticmethod
    def _extend(nexts, links, lengths, last, word) -> int:
        found = nexts[last].get(word)
        if found is not None and lengths[found] == lengths[last] + 1:
            return found
        if found is None:
            state = len(nexts)
            nexts.append({})
            links.append(0)
            lengths.append(lengths[last] + 1)
            at = last
            while at >= 0 and word not in nexts[at]:
                nexts[at][word] = state
                at = links[at]
            if at < 0:
                return state
            target = nexts[at][word]
        else:
            state, at, target = None, last, found
        if lengths[target] != lengths[at] + 1:
            copy = len(nexts)
            nexts.append(dict(nexts[target]))
            links.append(links[target])
            lengths.append(lengths[at] + 1)
            links[target] = copy
            while at >= 0 and nexts[at].get(word) == target:
                nexts[at][word] = copy
                at = links[at]
            target = copy
        if state is None:
            return target
        links[state] = target
        return state

    def scan(self, ids: list[int], offset: int, spans: list[tuple[int, int]], items: set[str]) -> None:
        """Adds the hit spans [start, end) and the items of a run of known words that begins at word `offset`."""
        nexts, links, lengths, window, whole, holders = self.nexts, self.links, self.lengths, self.window, self.whole, self.holders
        state = length = 0
        for at, word in enumerate(ids, offset + 1):
            while state and word not in nexts[state]:
                state = links[state]
                length = lengths[state]
            if word in nexts[state]:
                state = nexts[state][word]
                length += 1
            if length >= window:
                top = state
                while links[top] > 0 and lengths[links[top]] >= window:
                    top = links[top]
                spans.append((at - window, at))
                items.update(holders.get(top, ()))
            if whole:
                up = state
                while up > 0:
                    for n, item in whole.get(up, ()):
                        if n <= length:
                            spans.append((at - n, at))
                            items.add(item)
                    up = links[up]

    def match(self, words: list[bytes]) -> tuple[list[tuple[int, int]], set[str]]:
        """Merged hit spans by word and the items with an occurring window."""
        spans: list[tuple[int, int]] = []
        items: set[str] = set()
        get, shortest = self.vocabulary.get, self.shortest
        ids = list(map(get, words))
        at, n = 0, len(ids)
        while at + shortest <= n:
            # the last of the next `shortest` words that is unknown rules all of them out as a start
            probe = at + shortest - 1
            while probe >= at and ids[probe] is not None:
                probe -= 1
            if probe >= at:
                at = probe + 1
                continue
            end = at + shortest
            while end < n and ids[end] is not None:
                end += 1
            self.scan(ids[at:end], at, spans, items)
            at = end + 1
        return merged(spans), items


def merged(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[list[int]] = []
    for a, b in sorted(spans):
        if out and a <= out[-1][1]:
            out[-1][1] = max(out[-1][1], b)
        else:
            out.append([a, b])
    return [tuple(x) for x in out]


def _blocks(benchmark: DataFrame, conf: DecontaminationConfig):
    """Whether it is the last, and a list of (item, words) of about conf.block_words words at most; the driver holds one at a time."""
    items = (benchmark.select(F.coalesce(F.col("item_id").cast("string"), F.lit("")).alias("item"), F.coalesce("text", F.lit("")).alias("text")).distinct())
    size = items.agg(F.sum(F.length("text"))).first()[0] or 0
    n = max(1, -(-size // (6 * conf.block_words)))
    for k in range(n):
        rows = items if n == 1 else items.where(F.pmod(F.xxhash64("text"), F.lit(n)) == k)
        yield k == n - 1, [(r["item"], words_of(r["text"])) for r in rows.toLocalIterator()]


def find_hits(documents: DataFrame, benchmark: DataFrame, conf: DecontaminationConfig = DecontaminationConfig(), keep: tuple[str, ...] = ("doc_id",), finish=None) -> DataFrame:
    """The kept columns with text, __n_words, __spans (array of [start, end) word numbers, merged) and __items (sorted ids as text).

    Null or empty text has no words. Rows are scanned one by one, so repeated ids do not matter; a test item without id counts
    under the empty id, one without words is ignored. More than one block of test items means one scan per block over the
    result of the last. `finish` turns what the last scan yields into batches with the columns of documents, in the same worker.
    """
    from pyspark.sql.types import ArrayType, IntegerType, LongType, StringType, StructType

    rows = documents.select(*keep, "text")
    schema = StructType([documents.schema[c] for c in keep])
    out = None
    for last, items in _blocks(benchmark, conf):
        sent = documents.sparkSession.sparkContext.broadcast(items)

        def scan(batches, sent=sent, more=out is not None, finish=finish if last else None):
            import pyarrow as pa

            automaton = Automaton(sent.value, conf.window)
            for batch in batches:
                counts, spans, found = [], [], []
                texts = batch.column("text")
                for row in range(batch.num_rows):
                    words = words_of(texts[row].as_py())
                    hit, names = automaton.match(words)
                    if more:
                        hit = merged(hit + [tuple(x) for x in batch.column("__spans")[row].as_py()])
                        names |= set(batch.column("__items")[row].as_py())
                    counts.append(len(words))
                    spans.append([list(x) for x in hit])
                    found.append(sorted(names))
                made = pa.RecordBatch.from_arrays([*(batch.column(c) for c in keep), texts, pa.array(counts, pa.int64()), pa.array(spans, pa.list_(pa.list_(pa.int32()))), pa.array(found, pa.list_(pa.string()))], names=[*keep, "text", "__n_words", "__spans", "__items"])
                yield finish(made) if finish else made

        full = StructType([*schema, documents.schema["text"]]).add("__n_words", LongType()).add("__spans", ArrayType(ArrayType(IntegerType()))).add("__items", ArrayType(StringType()))
        out = (rows if out is None else out).mapInArrow(scan, documents.schema if finish and last else full)
    return out


def report(documents: DataFrame, benchmark: DataFrame, conf: DecontaminationConfig = DecontaminationConfig()) -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items_sha256, contaminated for every document."""
    hits = F.aggregate("__spans", F.lit(0).cast("long"), lambda n, s: n + s[1] - s[0])
    return (find_hits(documents, benchmark, conf).select(
        "doc_id", F.col("__n_words").alias("n_words"), hits.alias("n_hit"), F.size("__items").cast("long").alias("n_items"),
        F.sha2(F.array_join("__items", ",").cast("binary"), 256).alias("items_sha256"), (F.size("__spans") > 0).alias("contaminated")))


def decontaminate(documents: DataFrame, benchmark: DataFrame, conf: DecontaminationConfig = DecontaminationConfig(), max_coverage: float = 0.5) -> DataFrame:
    """Documents with hit spans removed from the text; those with more than max_coverage of their words hit are dropped.

    All columns are kept; n_chars, where there is such a column, follows the new text. Clean rows are returned untouched.
    """
    columns = documents.columns

    def cut(batch):
        import re

        import pyarrow as pa

        word = re.compile(r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+")
        texts, chars, rows = [], [], []
        for row in range(batch.num_rows):
            text, spans, n = batch.column("text")[row].as_py(), batch.column("__spans")[row].as_py(), batch.column("__n_words")[row].as_py()
            if sum(b - a for a, b in spans) > max_coverage * n:
                continue
            if spans:
                at = [m.span() for m in word.finditer(text)]
                parts, last = [], 0
                for a, b in spans:
                    parts.append(text[last : at[a][0]])
                    last = at[b - 1][1]
                text = "".join([*parts, text[last:]])
            rows.append(row)
            texts.append(text)
            chars.append(len(text) if spans else batch.column("n_chars")[row].as_py() if "n_chars" in columns else None)
        kept = batch.take(pa.array(rows, pa.int64()))
        return pa.RecordBatch.from_arrays([pa.array(texts, batch.schema.field("text").type) if c == "text" else pa.array(chars, batch.schema.field(c).type) if c == "n_chars" else kept.column(c) for c in columns], names=columns)

    return find_hits(documents, benchmark, conf, tuple(c for c in columns if c != "text"), cut)


def brute_force(documents: list[tuple], benchmark: list[tuple], window: int = 10) -> dict:
    """doc_id -> (n_words, n_hit, items): every window tried at every place, for tests."""
    out = {}
    for doc, text in documents:
        words, hit, items = words_of(text), set(), set()
        for item, t in benchmark:
            own = words_of(t)
            n = min(window, len(own))
            for k in range(len(own) - n + 1 if n else 0):
                for at in range(len(words) - n + 1):
                    if words[at : at + n] == own[k : k + n]:
                        hit.update(range(at, at + n))
                        items.add(str(item))
        out[doc] = (len(words), len(hit), hashlib.sha256(",".join(sorted(items)).encode()).hexdigest(), len(items))
    return out
