"""Language identification by cross-parsing entropy.

For each language a suffix automaton of labelled text is built. A text is parsed against it into phrases, each the longest
stretch that occurs in the labelled text; the number of phrases, times the bits that name a place there, measures how foreign
the text is, and the language with the lowest measure wins. Texts are parsed in segments of fixed length, each of which
begins a phrase, so that many segments step through the automata together in numpy.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .base import SAMPLE_SPACE, held_out

UNDETERMINED = "und"


@dataclass(frozen=True)
class CrossParseConfig:
    letters: int = 100_000  # labelled letters in all, dealt evenly over the languages
    rows: int = 60  # labelled rows of each language in the sample, about
    longest_row: int = 20_000  # of longer labelled rows the middle is learned from
    alphabet: int = 62  # letters with a class of their own
    rare: int = 61  # classes that the other letters share
    segment: int = 1024
    lanes: int = 4096


def suffix_automaton(symbols: list[int]) -> list[dict[int, int]]:
    """Transitions of the suffix automaton; state 0 is its root."""
    nexts, links, lengths, last = [{}], [-1], [0], 0
    for c in symbols:
        state = len(nexts)
        nexts.append({})
        links.append(0)
        lengths.append(lengths[last] + 1)
        at = last
        while at >= 0 and c not in nexts[at]:
            nexts[at][c] = state
            at = links[at]
        if at >= 0:
            target = nexts[at][c]
            if lengths[target] > lengths[at] + 1:
                copy = len(nexts)
                nexts.append(dict(nexts[target]))
                links.append(links[target])
                lengths.append(lengths[at] + 1)
                links[target] = copy
                while at >= 0 and nexts[at].get(c) == target:
                    nexts[at][c] = copy
                    at = links[at]
                target = copy
            links[state] = target
        last = state
    return nexts


def classes(letters: str, rare: int = 0):
    """code point -> class: 0 for what is no letter, then one class for each of `letters` from 2 on; letters outside have class 1,
    or one of `rare` further classes by their code points."""
    import sys

    import numpy as np

    out = np.fromiter((chr(c).isalpha() for c in range(sys.maxunicode + 1)), "uint8", sys.maxunicode + 1)
    if rare:
        out = np.where(out > 0, len(letters) + 2 + np.arange(len(out)) % rare, 0).astype("uint8")
    for k, c in enumerate(letters):
        out[ord(c)] = k + 2
    return out


def symbols(text: str, table):
    """Classes of a text's lower-case characters, runs of non-letters as one."""
    import numpy as np

    if not text:
        return np.zeros(0, "uint8")
    out = table[np.frombuffer(text.lower().encode("utf-32-le"), "<u4")]
    return out[np.concatenate([[True], (out[1:] != 0) | (out[:-1] != 0)])]


def parser_table(training, n_classes: int):
    """Steps of greedy parsing, flat: entry [state * classes + class] is the next row's start * 2, plus 1 where a phrase begins.

    Row 0 is the state in which no phrase is open.
    """
    import numpy as np

    nexts = suffix_automaton(training.tolist())
    start = [nexts[0].get(c) for c in range(n_classes)]
    fresh = np.array([0 if s is None else (s * n_classes) for s in start], "int32") * 2 + 1
    out = np.tile(fresh, (len(nexts), 1))
    for state in range(1, len(nexts)):
        for c, to in nexts[state].items():
            out[state, c] = to * n_classes * 2
    return out.ravel()


def fit(samples: dict[str, list[str]], conf: CrossParseConfig = CrossParseConfig()) -> dict:
    from collections import Counter

    import numpy as np

    share = max(2000, conf.letters // max(len(samples), 1))
    seen: Counter = Counter()
    for texts in samples.values():  # by its largest share in a language, so that no language's letters crowd out another's
        own = Counter(c for t in texts for c in t.lower() if c.isalpha())
        whole = sum(own.values())
        for c, count in own.items():
            seen[c] = max(seen[c], count / whole)
    rare = conf.rare if len(seen) > conf.alphabet else 0
    table = classes("".join(sorted(seen, key=lambda c: (-seen[c], c))[: conf.alphabet]), rare)
    n, models = min(len(seen), conf.alphabet) + 2 + rare, {}
    for lang in sorted(samples):
        rows = [np.concatenate([symbols(t, table), np.zeros(1, "uint8")]) for t in samples[lang]]
        left, each = share, 0
        for k, size in enumerate(sorted(map(len, rows))):  # an equal slice of each row, what short rows leave goes to the others
            each = -(-left // (len(rows) - k))
            left -= min(size, each)
        text = np.concatenate([r[:each] for r in rows] or [np.zeros(0, "uint8")])[:share]
        if (text > 0).any():
            models[lang] = (parser_table(text, n), float(np.log2(len(text) + 1)))
    return {"classes": table, "languages": models}


def classify(texts: list, model: dict, conf: CrossParseConfig = CrossParseConfig()) -> list[tuple[str, float]]:
    """(language, score) of each text; the score is the runner-up's share of the two lowest measures, 0 if undetermined."""
    import numpy as np

    names = list(model["languages"])
    parts, owner, letters = [], [], np.zeros(len(texts), bool)
    for i, text in enumerate(texts):
        own = symbols(text or "", model["classes"])
        letters[i] = own.any()
        if letters[i]:
            for a in range(0, len(own), conf.segment):
                parts.append(own[a : a + conf.segment])
                owner.append(i)
    measures = np.zeros((len(names), len(texts)))
    order = sorted(range(len(parts)), key=lambda k: -len(parts[k]))
    for begin in range(0, len(order), conf.lanes):
        lanes = order[begin : begin + conf.lanes]
        lengths = np.array([len(parts[k]) for k in lanes])
        grid = np.zeros((lengths[0], len(lanes)), "uint8")
        for column, k in enumerate(lanes):
            grid[: len(parts[k]), column] = parts[k]
        active = np.searchsorted(-lengths, -np.arange(lengths[0]), side="left")
        whose = np.array([owner[k] for k in lanes])
        for row, name in enumerate(names):
            table, bits = model["languages"][name]
            state, phrases = np.zeros(len(lanes), "int32"), np.zeros(len(lanes), "int32")
            for step in range(int(lengths[0])):
                m = active[step]
                here = table[state[:m] + grid[step, :m]]
                phrases[:m] += here & 1
                state[:m] = here >> 1
            np.add.at(measures[row], whose, phrases * bits)
    out = []
    ranks = np.argsort(measures, axis=0, kind="stable") if names else None
    for i in range(len(texts)):
        if not letters[i] or not names:
            out.append((UNDETERMINED, 0.0))
            continue
        best = measures[ranks[0, i], i]
        second = measures[ranks[1, i], i] if len(names) > 1 else best
        out.append((names[ranks[0, i]], float(second / (best + second)) if len(names) > 1 else 1.0))
    return out


def train(documents: DataFrame, conf: CrossParseConfig = CrossParseConfig(), modulus: int = 4, remainder: int = 2) -> dict:
    """Learns from a bounded sample, by hash, of rows with text and lang outside the held-out fold."""
    longer = F.length("text") > conf.longest_row
    middle = F.when(longer, F.substring("text", F.floor((F.length("text") - conf.longest_row) / 2).cast("int") + 1, F.lit(conf.longest_row))).otherwise(F.col("text"))
    known = documents.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & ~held_out(F.col("doc_id"), modulus, remainder)).select("doc_id", "lang", "text")
    counts = known.groupBy("lang").agg(F.count("*").alias("n"))
    chosen = known.join(F.broadcast(counts), "lang").where(F.pmod(F.xxhash64("doc_id", F.lit(29)), F.lit(SAMPLE_SPACE)) < F.lit(conf.rows) / F.col("n") * SAMPLE_SPACE)
    texts: dict[str, list[str]] = {}
    for r in sorted(chosen.select("doc_id", "lang", middle.alias("text")).collect(), key=lambda r: (r["doc_id"], r["text"])):
        texts.setdefault(r["lang"], []).append(r["text"])
    return fit(texts, conf)


def identify(documents: DataFrame, model: dict, conf: CrossParseConfig = CrossParseConfig(), modulus: int = 4, remainder: int = 2) -> DataFrame:
    """doc_id, held_out, lang_pred, score for every row.

    Text that is null or has no letter is undetermined with score 0. Equal measures go to the first language by name. Rows
    with one doc_id are judged one by one; an empty table gives an empty result; other columns are not read.
    """
    sent = documents.sparkSession.sparkContext.broadcast(model)

    def judge(batches):
        import pyarrow as pa

        for batch in batches:
            texts, found = batch.column(2), []
            part, size = [], 0
            for row in range(batch.num_rows):
                part.append(texts[row].as_py())
                size += len(part[-1] or "")
                if size > 4_000_000 or row == batch.num_rows - 1:
                    found += classify(part, sent.value, conf)
                    part, size = [], 0
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array([a for a, _ in found], pa.string()), pa.array([b for _, b in found], pa.float64())], names=["doc_id", "held_out", "lang_pred", "score"])

    kind = documents.schema["doc_id"].dataType.simpleString()
    return documents.select("doc_id", held_out(F.col("doc_id"), modulus, remainder).alias("held_out"), "text").mapInArrow(judge, f"doc_id {kind}, held_out boolean, lang_pred string, score double")
