"""Each operator against brute force on small fixtures, and on nulls, empty and long texts, ties, repeated rows, empty tables
and tables with other columns of clashing names."""

import hashlib
import math
import random
import re
import unicodedata
import zlib

import pytest
from pyspark.sql import functions as F

from mpcrel.llm import base, decontam, fingerprints, language, letters, licenses, near_dedup, packing, passages, pii, quality, toxicity

WORDS = [a + b + c for a in ("ba", "ko", "ri", "tu") for b in ("la", "me", "no") for c in ("", "s", "ta", "vin")]
AWKWARD = "doc_id long, text string, lang string, source string, n_chars long, score double, piece int, sig string, component string, spans string"


def prose(rng, n):
    return " ".join(rng.choices(WORDS, k=n))


@pytest.fixture(scope="module")
def corpus(spark):
    rng = random.Random(5)
    texts = [prose(rng, rng.randrange(3, 160)) for _ in range(60)]
    texts += [texts[0], texts[0].replace(texts[0].split()[3], "zebra", 1), None, "", " ", "one", "one two", prose(rng, 4000)]
    rows = [(i, t, "xx", "s", len(t or ""), 0.5, 1, "x", "y", "z") for i, t in enumerate(texts)]
    rows += [rows[1], (None, texts[2], None, None, None, None, None, None, None, None)]
    return spark.createDataFrame(rows, AWKWARD), [(r[0], r[1]) for r in rows]


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], AWKWARD)


def test_toxicity_learns_stems_and_handles_odd_rows(spark, corpus, empty):
    rng = random.Random(1)
    texts = [prose(rng, 30) + (" grumble" + rng.choice(("s", "d", "ty")) if i % 5 == 0 else "") for i in range(400)]
    docs = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string")
    labels = spark.createDataFrame([(i, int(i % 5 == 0)) for i in range(400)] + [(None, 1), (3, None)], "doc_id long, toxic int")
    model = toxicity.train(docs, labels)
    got = {r["doc_id"]: r for r in toxicity.score_toxicity(docs, model).collect()}
    assert all(got[i]["predicted"] == int(i % 5 == 0) for i in range(400))
    assert all(got[i]["held_out"] == (zlib.crc32(str(i).encode()) % 5 == 0) for i in range(400))
    odd, pairs = corpus
    rows = toxicity.score_toxicity(odd, model).collect()
    assert len(rows) == len(pairs) and all(0 <= r["score"] <= 1 for r in rows)
    assert toxicity.score_toxicity(empty, toxicity.train(empty, labels)).count() == 0


def test_factorization_machine_learns_an_interaction():
    import numpy as np

    rng = random.Random(2)
    rows, y = [], []
    for _ in range(1500):
        a, b = rng.random() < 0.5, rng.random() < 0.5
        rows.append(np.array([5] * a + [9] * b + [rng.randrange(20, 40)]))
        y.append(int(a and b))
    conf = toxicity.FmConfig(bits=6)
    model = toxicity.fit(rows, y, conf)
    w = dict(zip(model["ids"].tolist(), range(len(model["ids"]))))
    pair = float(model["v"][w[5]] @ model["v"][w[9]])
    assert pair > 0.5  # together they mean more than the sum


def test_factorization_machine_learns_an_interaction_without_marginal_effect():
    import numpy as np

    rng = random.Random(32)
    conf, rows, y = toxicity.FmConfig(bits=10), [], []
    for _ in range(6000):  # either of two terms alone marks a row, both or none do not
        a, b = rng.random() < 0.5, rng.random() < 0.5
        rows.append(np.array(sorted({*[5] * a, *[9] * b, *(rng.randrange(20, 400) for _ in range(20))})))
        y.append(int(a != b))
    model = toxicity.fit(rows[:5000], y[:5000], conf)
    assert {5, 9} <= set(model["ids"].tolist())
    ids = {k: i for i, k in enumerate(model["ids"].tolist())}
    for row, label in zip(rows[5000:], y[5000:]):
        on = [ids[t] for t in row.tolist() if t in ids]
        z = model["bias"] + sum(model["w"][on]) + sum(model["v"][i] @ model["v"][j] for k, i in enumerate(on) for j in on[:k])
        assert (z > 0) == label


def brute_terms(text, conf):
    own, *of_stem = letters.odd(1 + len(conf.stems), conf.seed)
    out = set()
    for word in re.findall(r"[^\W_]+", (text or "").lower()):
        for piece, m in [(word, own), *((word[:k], x) for k, x in zip(conf.stems, of_stem) if len(word) >= k)]:
            out.add(polynomial(piece) * m % (1 << 64) >> (64 - conf.bits))
    return sorted(out)


def test_toxicity_scores_match_explicit_pair_sums():
    import numpy as np

    rng, draw = random.Random(33), np.random.default_rng(2)
    conf = toxicity.FmConfig(bits=8)
    ids = np.sort(draw.choice(conf.buckets, 100, replace=False))
    model = {"bias": -0.4, "ids": ids, "w": draw.normal(0, 0.3, 100), "v": draw.normal(0, 0.2, (100, conf.factors))}
    place = {k: i for i, k in enumerate(ids.tolist())}
    texts = [prose(rng, rng.randrange(0, 12)) + rng.choice(["", " Ünï_x a1", " 日本語 日本語"]) for _ in range(60)] + [None, "", "_", "word " * 120_000]
    got = toxicity.scores(texts, model, conf)
    for text, score in zip(texts, got):
        on = [place[t] for t in brute_terms(text, conf) if t in place]
        z = model["bias"] + sum(model["w"][on]) + sum(model["v"][i] @ model["v"][j] for k, i in enumerate(on) for j in on[:k])
        assert score == pytest.approx(1 / (1 + math.exp(-z)))


def test_quality_reads_long_tokens_and_long_rows_whole(spark):
    rng = random.Random(21)
    ends = "".join(rng.choices("klmn", k=60))
    texts = [ends + "".join(rng.choices("abcd" if i % 2 else "wxyz", k=400)) + ends for i in range(200)]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    labels = spark.createDataFrame([(i, i % 2) for i in range(200)], "doc_id long, quality int")
    model = quality.train(docs, labels)
    assert all(r["predicted"] == r["doc_id"] % 2 for r in quality.score_quality(docs, model, threshold=0.5).collect())
    conf = quality.SubwordConfig()
    rng2 = random.Random(22)
    token = "".join(rng2.choices("abcd", k=2 * letters.PART))
    ids, shares = quality.weighted(token, conf)
    assert len(ids) > 300 and shares.sum() == pytest.approx(1)  # n-grams of every part
    long = spark.createDataFrame([(1, "word " * 10_000), (2, "word")], "doc_id long, text string")
    marks = spark.createDataFrame([(1, 1), (2, 0)], "doc_id long, quality int")
    assert {r["doc_id"] for r in base.labelled_sample(long, marks, "quality", 1000, 999, 100).collect()} == {1, 2}


def test_quality(spark, corpus, empty):
    rng = random.Random(3)
    texts = [" ".join(w + ("###" if i % 4 == 0 else "") for w in prose(rng, 25).split()) for i in range(300)]
    docs = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string")
    labels = spark.createDataFrame([(i, int(i % 4 != 0)) for i in range(300)], "doc_id long, quality int")
    model = quality.train(docs, labels)
    assert all(r["predicted"] == int(r["doc_id"] % 4 != 0) for r in quality.score_quality(docs, model).collect())
    odd, pairs = corpus
    rows = quality.with_scores(odd, model, prefix="__q_")
    assert rows.columns == [*odd.columns, "__q_score", "__q_predicted"] and rows.count() == len(pairs)
    assert quality.score_quality(empty, quality.train(empty, labels)).count() == 0


def polynomial(text):
    """The hash of a stretch, character by character."""
    total = sum((ord(c) + 1) * pow(letters._BASE, i, 1 << 64) for i, c in enumerate(text)) % (1 << 64)
    return (total ^ (total >> 32)) * 0x9E3779B97F4A7C15 % (1 << 64)


def brute_quality(text, model, conf):
    """Average of the values of tokens, pairs and n-grams, one by one, then the softmax of two classes."""
    own, left, right, *grams = letters.odd(4 + conf.longest, conf.seed)
    top = lambda h: (h % (1 << 64)) >> (64 - conf.bits)
    tokens = (text or "").split()
    found = [top(polynomial(t) * own) for t in tokens]
    for a, b in zip(tokens, tokens[1:]):
        pair = right if a == b else (polynomial(a) * left + polynomial(b) * right) % (1 << 64)
        found.append(top((pair ^ (pair >> 31)) * own))
    for t in tokens:
        mark = f"<{t}>"
        for k in range(conf.shortest, conf.longest + 1):
            for i in range(len(mark) - k + 1):
                h = (k + sum((ord(c) + 1) * m for c, m in zip(mark[i : i + k], grams))) % (1 << 64)
                found.append(top((h ^ (h >> 29)) * grams[-1]))
    z = model["bias"] + (math.fsum(float(model["s"][i]) for i in found) / len(found) if found else 0)
    return 1 / (1 + math.exp(-z))


def test_quality_scores_match_explicit_averages():
    import numpy as np

    rng = random.Random(23)
    conf = quality.SubwordConfig(bits=9)
    model = {"bias": 0.3, "s": np.random.default_rng(1).normal(0, 3, conf.buckets).astype("float32")}
    texts = [prose(rng, rng.randrange(0, 40)) + rng.choice(["", " a a a", " ünï 日本語 x", "\n\t" + "q" * 90]) for _ in range(60)] + [None, "", " ", "z"]
    assert quality.scores(texts, model, conf) == pytest.approx([brute_quality(t, model, conf) for t in texts])


def brute_components(pairs, size, percent):
    sets = []
    for _, t in pairs:
        w = (t or "").encode().lower().split()
        sets.append({tuple(w[i : i + size]) for i in range(len(w) - size + 1)} if len(w) >= size else {tuple(w)} if w else set())
    parent = list(range(len(pairs)))

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i in range(len(pairs)):
        for j in range(i):
            if pairs[i][0] is not None and pairs[j][0] is not None and sets[i] and sets[j] and 100 * len(sets[i] & sets[j]) >= percent * len(sets[i] | sets[j]):
                a, b = sorted((find(i), find(j)), key=lambda k: pairs[k][0])
                parent[b] = a
    return [pairs[find(i)][0] for i in range(len(pairs))], list(map(len, sets))


@pytest.mark.parametrize("conf", [near_dedup.NearConfig(), near_dedup.NearConfig(shingle=3, percent=85, rows=5, block=2)])
def test_near_duplicates_match_brute_force(spark, corpus, empty, conf):
    df, pairs = corpus
    rng = random.Random(9)
    base_text = prose(rng, 60).split()
    more = list(pairs)
    for k in range(25):  # a group of near copies in which some are only linked through others
        w = list(base_text)
        for _ in range(k % 5):
            w[rng.randrange(len(w))] = rng.choice(WORDS)
        more.append((1000 + k, " ".join(w)))
    docs = spark.createDataFrame(more, "doc_id long, text string")
    want, sizes = brute_components(more, conf.shingle, conf.percent)
    got = near_dedup.near_duplicates(docs, conf).collect()
    assert sorted((str(r["doc_id"]), r["n_shingles"], str(r["component_id"])) for r in got) == sorted((str(d), n, str(c)) for (d, _), n, c in zip(more, sizes, want))
    kept = near_dedup.drop_near_duplicates(df, conf)
    assert kept.columns == df.columns
    assert near_dedup.near_duplicates(empty, conf).count() == 0


def test_sequential_bounds_keep_what_is_likely():
    conf = near_dedup.NearConfig(shingle=3, percent=85, rows=5)
    n, least = near_dedup.bounds(conf)[-1]
    t = conf.percent / 100
    assert n == conf.hashes and sum(math.comb(n, k) * t**k * (1 - t) ** (n - k) for k in range(least)) < 1e-4


def brute_spans(text):
    kinds = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}

    def fine(kind, v):
        digits = re.sub("[^0-9]", "", v)
        luhn = sum(d if i % 2 == 0 else 2 * d - 9 * (d > 4) for i, d in enumerate(map(int, reversed(digits)))) % 10 == 0 if digits else False
        return {"email": True, "ip": kind != "ip" or all(int(x) <= 255 for x in v.split(".")), "card": 16 <= len(digits) <= 19 and luhn, "phone": 8 <= len(digits) <= 15}[kind]

    return [f"{k}:{m.start()}:{m.end()}" for k, p in kinds.items() for m in re.finditer(p, text or "") if fine(k, m.group())]


def test_personal_data_matches_brute_force(spark, corpus, empty):
    rng = random.Random(4)
    bits = ["a.b@c.de", "x@y.z_q@r.st", "1.2.3.4", "300.1.1.1", "001.02.255.0.7.8.9.1", "4111 1111 1111 1111", "4111-1111-1111-1112", "+1 (555) 010-9999", "+12", "+49.30.1234567890123456", "é@ü.ö", "ünï@co.uk.", "9" * 40, "..@..", "a@b", " \n"]
    texts = ["".join(rng.choice(bits) + rng.choice([" ", "", ", ", "é "]) for _ in range(rng.randrange(0, 12))) for _ in range(150)]
    texts += ["7 " * 3000, "a." * 3000 + "@", " ".join("1.2.3.%d" % (i % 256) for i in range(300)), None, ""]
    docs = spark.createDataFrame([(i, t) for i, t in enumerate(texts)] + [(None, "a@b.cd")], "doc_id long, text string")
    for r in pii.report(docs).collect():
        want = ["email:0:6"] if r["doc_id"] is None else brute_spans(texts[r["doc_id"]])
        assert r["base_sha256"] == hashlib.sha256(",".join(want).encode()).hexdigest(), texts[r["doc_id"]]
        assert set(want) <= set(r["spans"].split(",")) | {""}
    df, pairs = corpus
    assert sorted(map(str, (r["text"] for r in pii.sanitise(df).collect()))) == sorted(str(t) for _, t in pairs)
    assert pii.report(empty).count() == 0 and pii.sanitise(empty).columns == empty.columns


def test_disclosing_terms_are_found_and_generalised(spark):
    rng = random.Random(6)
    # a surname stands by one address in many contexts and nowhere else
    texts = [f"{prose(rng, 12)} wrote Quillfeather to quill@mail.example {prose(rng, 12)}" for _ in range(6)] + [prose(rng, 30) for _ in range(60)] + [f"quixotic {prose(rng, 10)}" for _ in range(30)]
    docs = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string")
    found = {r["term"]: r for r in pii.disclosures(docs).collect()}
    assert "quillfeather" in found and found["quillfeather"]["disclosure"] == pytest.approx(1.0)
    assert found["quillfeather"]["co"] == 6 and found["quillfeather"]["df_entity"] == 6
    out = {r["doc_id"]: r["text"] for r in pii.sanitise(docs).collect()}
    assert all("uillfeather" not in out[i] and "[EMAIL]" in out[i] for i in range(6))
    assert all(out[i] == texts[i] for i in range(6, len(texts)))
    spans = {r["doc_id"]: r["spans"] for r in pii.report(docs).collect()}
    at = texts[0].index("Quillfeather")
    assert f"term:{at}:{at + 12}" in spans[0]


def test_terms_far_from_their_entity_and_at_the_ends_of_texts(spark):
    rng = random.Random(31)
    filler = lambda n: prose(rng, n)
    texts = [f"Quillfeather q@x.org {filler(12 + i)} Marrowgate {filler(30)} quillfeather {filler(9)} Endlingham" for i in range(5)] + [filler(40) for _ in range(60)]
    docs = spark.createDataFrame([(i, t, len(t)) for i, t in enumerate(texts)], "doc_id long, text string, n_chars long")
    assert {r["term"]: r["co"] for r in pii.disclosures(docs).collect()} == {"quillfeather": 5, "marrowgate": 5, "endlingham": 5}
    out = [r["text"].lower() for r in pii.sanitise(docs).where("doc_id < 5").collect()]
    assert len(out) == 5 and not any(name in t for t in out for name in ("quillfeather", "marrowgate", "endlingham", "q@x.org"))


def test_removal_comes_before_generalisation_and_names_disclose(spark):
    rng = random.Random(61)
    # one word belongs to two addresses: for the first its class is safe, for the second no class is
    texts = [f"{prose(rng, 8 + i)} Marwick one@a.example {prose(rng, 9)}" for i in range(4)] + [f"{prose(rng, 7 + i)} Marwick one@a.example two@b.example {prose(rng, 9)}" for i in range(4)]
    texts += [f"{prose(rng, 20)} marble" for _ in range(3)] + [prose(rng, 30) for _ in range(150)]
    texts += [f"Ostrander {prose(rng, 12)} ostrander.7@c.example {prose(rng, 5)}"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    rows = {(r["entity"], r["term"]): r["general"] for r in pii.disclosures(docs).collect()}
    assert ("email:ostrander.7@c.example", "ostrander") in rows
    assert {rows["email:one@a.example", "marwick"], rows["email:two@b.example", "marwick"]} >= {None}
    out = {r["doc_id"]: r["text"] for r in pii.sanitise(docs).collect()}
    assert all("[TERM]" in out[i] for i in range(4, 8)) and "strander" not in out[len(texts) - 1]
    assert out[8] == texts[8]


def test_the_pipeline_sends_small_batches_to_python(spark):
    import corpus_pipeline

    name, docs = "spark.sql.execution.arrow.maxRecordsPerBatch", spark.range(2500).select(F.col("id").alias("doc_id"), F.lit("some words here").alias("text"))
    before = spark.conf.get(name)
    try:
        dict(corpus_pipeline.STAGES)["near_duplicates"](spark, docs, "")
        sizes = [r["n"] for r in docs.repartition(1).mapInArrow(lambda batches: (type(b).from_pydict({"n": [b.num_rows]}) for b in batches), "n long").collect()]
        assert max(sizes) <= base.BATCH and sum(sizes) == 2500
    finally:
        spark.conf.set(name, before)


def test_passages(spark, empty):
    rng = random.Random(8)
    shared = prose(rng, 70).split()
    fuzzy = [w if i % 12 else "changed" + str(i) for i, w in enumerate(shared)]
    unique = lambda n: [f"u{rng.randrange(10**9)}" for _ in range(n)]
    texts = {1: unique(40) + shared + unique(10), 2: unique(200), 3: shared + unique(90), 4: unique(15) + fuzzy, 5: unique(30) + shared[:20] + unique(40), 6: [], 7: ["one"]}
    docs = spark.createDataFrame([(k, " ".join(v)) for k, v in texts.items()] + [(8, None), (None, " ".join(shared))], "doc_id long, text string")
    rows = passages.passages(docs).collect()
    assert {r["doc_id"] for r in rows} == {1, 3, 4}
    first = [r for r in rows if r["doc_id"] == 1 and r["other_id"] == 3]
    assert first and first[0]["start_word"] == 40 and first[0]["end_word"] == 110 and not first[0]["repeats"]
    assert {r["doc_id"] for r in rows if r["repeats"]} == {3, 4}
    cleaned = {r["doc_id"]: r["text"] for r in passages.remove_repeats(docs).collect()}
    assert cleaned[1] == " ".join(texts[1]) and len(cleaned[3].split()) == 90 and cleaned[2] == " ".join(texts[2])
    assert passages.passages(empty).count() == 0


def test_a_text_travels_with_several_chains_and_in_small_batches(spark, tmp_path):
    from mpcrel.llm import queries

    rng = random.Random(31)
    shared = [prose(rng, 60) for _ in range(4)]
    unique = lambda n: " ".join(f"u{rng.randrange(10**9)}" for _ in range(n))
    rows = [(k, " ".join([unique(20), shared[k % 4], unique(9), shared[(k + 1) % 4], unique(5)])) for k in range(10)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    whole = [sorted(map(tuple, passages.passages(docs, passages.PassageConfig(together=n)).collect())) for n in (1, 1000)]
    assert whole[0] == whole[1] and {r[0] for r in whole[0]} == set(range(10))
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(name)
    try:
        docs.write.parquet(f"{tmp_path}/documents.parquet")
        out = queries.op4_substring_dedup(spark, str(tmp_path))
        assert int(spark.conf.get(name)) <= base.BATCH and sorted(map(tuple, out.collect())) == whole[1]
    finally:
        spark.conf.set(name, before)


def test_passages_whose_parts_have_many_other_holders(spark):
    rng = random.Random(14)
    unique = lambda n: [f"u{rng.randrange(10**9)}" for _ in range(n)]
    shared = unique(60)
    whole = {40, 61}
    texts = {i: unique(20) + (shared if i in whole else shared[:35] if i % 2 else shared[25:]) + unique(20) for i in range(100)}
    rows = passages.passages(spark.createDataFrame([(i, " ".join(t)) for i, t in texts.items()], "doc_id long, text string")).collect()
    assert {(r["doc_id"], r["start_word"], r["end_word"], r["other_id"], r["repeats"]) for r in rows} == {(40, 20, 80, 61, False), (61, 20, 80, 40, True)}


def test_a_fuzzy_passage_between_many_holders_of_its_parts(spark):
    rng = random.Random(16)
    unique = lambda n: [f"u{rng.randrange(10**9)}" for _ in range(n)]
    shared = unique(64)
    mine, other = ([w if i % 8 != 7 else f"{tag}{i}" for i, w in enumerate(shared)] for tag in ("x", "y"))
    texts = {500: unique(60) + mine + unique(60), 700: unique(80) + other + unique(40)}
    for i in range(0, 64, 8):  # each part has 90 other holders around the two by id, a third goes on as either of them
        for j in range(90):
            texts[10 * j + i // 8] = unique(60) + shared[i : i + 7] + ((mine, other, unique(99))[j % 3][i + 7 : i + 9]) + unique(60)
    texts |= {500: unique(60) + mine + unique(60), 700: unique(80) + other + unique(40)}
    texts |= {1000 + j: texts[500] for j in range(3)}
    rows = passages.passages(spark.createDataFrame([(i, " ".join(t)) for i, t in texts.items()], "doc_id long, text string")).collect()
    between = {(r["doc_id"], r["other_id"], r["partners"]) for r in rows if r["end_word"] - r["start_word"] < 100}
    assert between == {(500, 700, 1), (700, 500, 4)}
    assert {(r["doc_id"], r["start_word"], r["end_word"], r["other_id"], r["partners"], r["repeats"]) for r in rows if r["end_word"] - r["start_word"] >= 100} == {
        (500, 0, 184, 1000, 3, False), *((1000 + j, 0, 184, 500, 3, True) for j in range(3))}


def test_every_two_of_many_holders_are_partners(spark):
    rng = random.Random(18)
    unique = lambda n: [f"u{rng.randrange(10**9)}" for _ in range(n)]
    shared = unique(220)
    texts = {i: unique(20 + i) + (shared if i % 3 else shared[:180]) + unique(30) for i in range(60)}
    rows = passages.passages(spark.createDataFrame([(i, " ".join(t)) for i, t in texts.items()], "doc_id long, text string")).collect()
    short = [(i, 20 + i, 200 + i, 0 if i else 1, 59 if i % 3 == 0 else 20, i > 0) for i in range(60)]
    long = [(i, 20 + i, 240 + i, 1 if i > 1 else 2, 39, i > 1) for i in range(60) if i % 3]
    assert sorted((r["doc_id"], r["start_word"], r["end_word"], r["other_id"], r["partners"], r["repeats"]) for r in rows) == sorted(short + long)


def test_pairs_that_can_hold_a_passage_are_kept():
    import numpy as np

    rng = np.random.default_rng(19)
    conf = passages.PassageConfig()
    word = lambda n: rng.integers(0, 1 << 63, n).astype("uint64") * np.uint64(2)
    x, y, holds = [], [], []
    for trial in range(300):
        size, edges = int(rng.integers(50, 53)), [int(n) for n in rng.integers(0, 80, 4)]
        shared = word(size)
        at = int(rng.integers(0, size - 3))
        free = np.setdiff1d(np.arange(size), np.arange(at, at + conf.k))
        changes = size // 5 if trial % 2 else size // 2
        other, places = shared.copy(), np.arange(size)
        gone = rng.choice(free, changes, False)
        if trial % 3:  # words are left out of the one, and as many put into the other
            half = changes // 2
            other[gone[:half]] = word(half)
            keep = np.setdiff1d(places, gone[half : half + min(conf.shift, size - 50)] if trial % 2 else gone[half:])
            other, at_other = other[keep], int(np.searchsorted(keep, at))
        else:
            other[gone], at_other = word(changes), at
        a, b = np.concatenate([word(edges[0]), shared, word(edges[1])]), np.concatenate([word(edges[2]), other, word(edges[3])])
        x.append(passages.near_words(a, edges[0] + at, conf))
        y.append(passages.near_words(b, edges[2] + at_other, conf))
        holds.append(trial % 2 == 1)
    kept, holds = passages.can_pair(np.array(x), np.array(y), conf), np.array(holds)
    assert kept[holds].all() and (kept == passages.can_pair(np.array(y), np.array(x), conf)).all() and kept[~holds].mean() < 0.1


def test_all_pairs_of_surroundings_are_compared():
    import numpy as np

    rng = np.random.default_rng(17)
    conf = passages.PassageConfig()
    base = rng.integers(0, 1 << 63, 200).astype("uint64")
    signed = []
    for _ in range(70):
        h = base.copy()
        h[80:130][rng.choice(np.r_[0:20, 24:50], conf.errors, False)] = rng.integers(0, 1 << 63, conf.errors)
        h[:80], h[130:] = rng.integers(0, 1 << 63, 80), rng.integers(0, 1 << 63, 70)
        signed.append(passages.around(h, 100, conf))
    signed += [passages.around(rng.integers(0, 1 << 63, 200).astype("uint64"), 100, conf) for _ in range(70)]
    bits, least = [b for b, _ in signed], np.array([n for _, n in signed])
    got = {(int(i), int(j)) for x, y in passages.alike_pairs(bits, least, rows=33) for i, j in zip(x, y)}
    share = lambda i, j: (int.from_bytes(bits[i], "big") & int.from_bytes(bits[j], "big")).bit_count()
    assert got == {(i, j) for i in range(140) for j in range(i + 1, 140) if share(i, j) >= max(least[i], least[j])}
    exact = passages.around(base, 100, conf)
    assert all((int.from_bytes(exact[0], "big") & int.from_bytes(b, "big")).bit_count() >= max(exact[1], n) for b, n in signed[:70])


def test_passages_at_the_least_identity(spark):
    rng = random.Random(15)
    unique = lambda n: [f"u{rng.randrange(10**9)}" for _ in range(n)]
    rows, expected = [], set()
    for i, size in enumerate([50, 60, 80] * 20):
        shared = unique(size)
        changed = list(shared)
        for at in rng.sample(range(1, size - 1), size // 5):
            changed[at] = f"c{rng.randrange(10**9)}"
        rows += [(2 * i, " ".join(unique(70) + shared + unique(70))), (2 * i + 1, " ".join(unique(90) + changed + unique(50)))]
        expected |= {2 * i, 2 * i + 1}
    found = passages.passages(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert {r["doc_id"] for r in found} == expected and all(r["identity"] >= 0.8 for r in found)


def test_chains_match_a_quadratic_programme():
    rng = random.Random(10)
    conf = passages.PassageConfig(min_seeds=1)
    for _ in range(40):
        anchors = sorted({(rng.randrange(60), rng.randrange(60)) for _ in range(rng.randrange(1, 25))})
        best = {}
        for a, b in anchors:
            best[a, b] = conf.k + max([0.0, *(best[x, y] - conf.gap_cost * (a - x + b - y) for x, y in anchors if x < a and y < b)])
        chain = passages.chains(anchors, conf)[0]
        score = conf.k * len(chain) - sum(conf.gap_cost * (q[0] - p[0] + q[1] - p[1]) for p, q in zip(chain, chain[1:]))
        assert score == pytest.approx(max(best.values()))


def test_rare_languages_long_rows_and_many_scripts_are_learned(spark):
    rng = random.Random(41)
    pools = {f"l{k:02d}": [chr(0x4E00 + 40 * k + j) for j in range(40)] for k in range(44)}
    rows = [(lang, "".join(rng.choices(pool, k=300))) for lang, pool in pools.items() for _ in range(6)]
    rows += [("long", "".join(rng.choices("abcdefgh", k=21_000))) for _ in range(6)]
    docs = spark.createDataFrame([(i, t, lang) for i, (lang, t) in enumerate(rows)], "doc_id long, text string, lang string")
    model = language.train(docs)
    assert set(model["languages"]) == {*pools, "long"}
    right = [rows[r["doc_id"]][0] == r["lang_pred"] for r in language.identify(docs, model).collect()]
    assert sum(right) > 0.95 * len(right)


def brute_phrases(text, training):
    """Greedy phrases of symbols against a training sequence."""
    n, at = 0, 0
    while at < len(text):
        size = 1
        while at + size < len(text) and any(training[k : k + size + 1] == text[at : at + size + 1] for k in range(len(training))):
            size += 1
        at, n = at + size, n + 1
    return n


def test_language(spark, corpus, empty):
    rng = random.Random(11)
    sounds = {"aa": ["mol", "ven", "tir", "sa"], "bb": ["öx", "kwa", "nji", "u"]}
    say = lambda lang, n: " ".join("".join(rng.choices(sounds[lang], k=rng.randrange(1, 4))) for _ in range(n))
    rows = [(i, say(lang, 40), lang) for i, lang in enumerate(["aa", "bb"] * 40)] + [(500, None, "aa"), (501, "12 !?", "bb"), (502, say("aa", 900), None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    model = language.train(docs)
    got = {r["doc_id"]: r for r in language.identify(docs, model).collect()}
    assert all(got[i]["lang_pred"] == lang for i, _, lang in rows[:80]) and got[502]["lang_pred"] == "aa"
    assert got[500]["lang_pred"] == got[501]["lang_pred"] == "und" and got[501]["score"] == 0
    samples = {"aa": [say("aa", 12)], "bb": [say("bb", 12)]}
    model = language.fit(samples)
    conf = language.CrossParseConfig(segment=50)
    text = say("aa", 30)
    marks = language.symbols(text, model["classes"]).tolist()
    share = max(2000, conf.letters // 2)
    measures = {}
    for lang, t in samples.items():
        training = [*language.symbols(t[0], model["classes"]).tolist(), 0][:share]
        measures[lang] = sum(brute_phrases(marks[k : k + 50], training) for k in range(0, len(marks), 50)) * math.log2(len(training) + 1)
    lang, score = language.classify([text], model, conf)[0]
    low, high = sorted(measures.values())
    assert lang == min(measures, key=measures.get) and score == pytest.approx(high / (low + high))
    df, pairs = corpus
    assert language.identify(df, model).count() == len(pairs)
    assert language.identify(empty, language.train(empty)).count() == 0


def canonical(t):
    nfkc = lambda x: unicodedata.normalize("NFKC", x)
    return re.sub(r"\s+", " ", nfkc(nfkc(t or "").casefold())).strip()


def test_fingerprints(spark, corpus, empty):
    e_marks = "e\u0301\u0323\u0302\u0308\u0327"
    texts = {1: "Ｆｕｌｌ  width\n", 2: "full Width", 3: "café ﬁne", 4: "CAFÉ fine", 5: None, 6: " ", 9: "ệ ệ", 12: "x" * 5000, 20: "ệ Ệ", 21: "\u1112\u1161\u11ab", 22: "한", 23: e_marks,
             24: unicodedata.normalize("NFC", e_marks), 25: "Straße", 26: "STRASSE", 27: "a\u2028\u3000b", 10**15: "a b", 10**15 + 7: "full width"}
    docs = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    got = {r["doc_id"]: r for r in fingerprints.fingerprints(docs).collect()}
    ids = sorted(texts)
    for a in ids:
        t, nxt = texts[a] or "", texts[ids[(ids.index(a) + 1) % len(ids)]] or ""
        half = len(t) // 2
        changed = t[: len(t) - half] + nxt[:half]
        assert got[a]["n_chars"] == len(t) and got[a]["edited_sha256"] == hashlib.sha256(changed.encode()).hexdigest()
        assert got[a]["near_next"] == float(canonical(t) == canonical(nxt)) and got[a]["near_edited"] == float(canonical(t) == canonical(changed))
        same = [b for b in ids if canonical(texts[b]) == canonical(t)]
        assert got[a]["group_id"] == same[0] and got[a]["group_size"] == len(same)
    assert fingerprints.fingerprints(empty).count() == 0
    df, pairs = corpus
    rows = fingerprints.fingerprints(df).collect()
    assert sorted(str(r["doc_id"]) for r in rows) == sorted(str(d) for d, _ in pairs)
    order = [(d, t or "") for d, t in sorted(pairs, key=lambda p: (p[0] is not None, p[0] or 0, p[1] or ""))]
    want = []
    for (d, t), (_, nxt) in zip(order, order[1:] + order[:1]):
        half = len(t) // 2
        want.append((str(d), hashlib.sha256((t[: len(t) - half] + nxt[:half]).encode()).hexdigest()))
    assert sorted((str(r["doc_id"]), r["edited_sha256"]) for r in rows) == sorted(want)
    assert fingerprints.exact_groups(df).count() == df.count()


def test_next_documents_of_crowded_and_scattered_ids(spark):
    rng = random.Random(51)
    ids = [*range(3000), 10**15, 10**15 + 1, -(10**17), *(rng.randrange(10**17) for _ in range(500))]
    docs = spark.createDataFrame([(i, f"t{i}") for i in ids], "doc_id long, text string")
    ids.sort()
    got = {r["doc_id"]: r["next_text"] for r in fingerprints.with_next(docs, 32).collect()}
    assert got == {a: f"t{b}" for a, b in zip(ids, ids[1:] + ids[:1])}


def test_texts_that_share_a_digest_are_told_apart(spark, monkeypatch):
    monkeypatch.setattr(fingerprints, "wide_hash", lambda canon: F.substring(canon, 1, 1))
    docs = spark.createDataFrame([(1, "aa"), (2, "ab"), (3, "AA"), (4, "ab "), (5, "b"), (6, "ac")], "doc_id long, text string")
    for bound in (10, 0):
        monkeypatch.setattr(fingerprints, "BROADCAST_DIGESTS", bound)
        assert {r["doc_id"]: (r["group_id"], r["group_size"]) for r in fingerprints.exact_groups(docs).collect()} == {1: (1, 2), 3: (1, 2), 2: (2, 2), 4: (2, 2), 5: (5, 1), 6: (6, 1)}


def test_licenses(spark, corpus, empty):
    lines = {0: "x\nReleased under the MIT license!\ny", 1: "Released under a MIT Licence", 2: licenses.TEMPLATES["MIT permission"].upper(), 3: None, 4: "", 5: "license " * 2000, 6: licenses.TEMPLATES["GPL-3.0 notice"].replace(". ", ".\n")}
    got = {r["doc_id"]: r for r in licenses.scan(spark.createDataFrame(list(lines.items()), "doc_id long, text string")).collect()}
    assert got[0]["license"] == "MIT line" and got[2]["license"] == "MIT permission" and got[6]["license"] == "GPL-3.0 notice"
    assert not any(got[i]["matched"] for i in (1, 3, 4, 5))
    df, pairs = corpus
    assert licenses.scan(df).count() == len(pairs) and licenses.scan(empty).count() == 0


@pytest.mark.parametrize("block_words", [1_000_000, 20])
def test_decontamination_matches_brute_force(spark, corpus, empty, block_words):
    rng = random.Random(12)
    items = [(i, prose(rng, rng.choice([0, 1, 3, 9, 10, 11, 30]))) for i in range(25)] + [(99, None)]
    texts = []
    for _ in range(80):
        parts = [prose(rng, rng.randrange(0, 15))]
        for _ in range(rng.randrange(3)):
            w = (rng.choice(items)[1] or "").split()
            k = rng.randrange(len(w) + 1)
            parts += [" ".join(w[k:]).upper(), prose(rng, 3)]
        texts.append("; ".join(parts))
    pairs = [(i, t) for i, t in enumerate(texts)] + [(80, None), (81, "")]
    conf = decontam.DecontaminationConfig(block_words=block_words)
    docs, bench = spark.createDataFrame(pairs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")
    want = decontam.brute_force(pairs, items)
    for r in decontam.report(docs, bench, conf).collect():
        assert (r["n_words"], r["n_hit"], r["items_sha256"], r["n_items"]) == want[r["doc_id"]]
        assert r["contaminated"] == (r["n_hit"] > 0)
    df, all_pairs = corpus
    far = spark.createDataFrame([(1, "nothing like it in any of these texts at all today")], "item_id long, text string")
    clean = decontam.decontaminate(df, far)
    assert clean.columns == df.columns and sorted(map(str, (r["text"] for r in clean.collect()))) == sorted(str(t) for _, t in all_pairs)
    assert decontam.report(empty, bench, conf).count() == 0
    assert decontam.report(docs, bench.limit(0), conf).where("contaminated").count() == 0


def test_packing(spark, corpus, empty):
    import numpy as np
    import public_tokenizers
    from tokenizers import Tokenizer

    df, pairs = corpus
    extra = ["a  b\n\n c", "tab\tsep  \n x", "it's they'll", "x" * 3000, "日本語 ünï", "  nb", " lead", "trail ", "a \n b", "<|endoftext|>", "a<|endoftext|>b <|endoftext|>  c"]
    docs = spark.createDataFrame([(str(i), t) for i, t in enumerate([t for _, t in pairs] + extra)], "doc_id string, text string")
    rows = packing.pack(docs, capacity=64, with_ids=True).toPandas()
    reference = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    for d, t in [(str(i), t) for i, t in enumerate([t for _, t in pairs] + extra)]:
        own = rows[rows.doc_id == d].sort_values("piece")
        want = [*reference.encode(t or "", add_special_tokens=False).ids, 2]
        assert np.concatenate(own["ids"].tolist()).tolist() == want
        assert own["start"].tolist() == np.concatenate([[0], own["length"].cumsum()[:-1]]).tolist()
        assert all(zlib.crc32(np.array(x, "<u4").tobytes()) == c for x, c in zip(own["ids"], own["ids_crc32"]))
        assert len(own) == 1 or (own["length"].iloc[1:] == 64).all()
    rows = rows.sort_values(["sequence_id", "offset"])
    assert (rows.groupby("sequence_id")["length"].cumsum() - rows["length"] == rows["offset"]).all()
    assert rows.groupby("sequence_id")["length"].sum().max() <= 64
    assert packing.pack(empty).count() == 0


def test_texts_are_encoded_whole_and_no_word_is_remembered():
    import tracemalloc

    import numpy as np
    import public_tokenizers
    from tokenizers import Tokenizer

    rng = random.Random(23)
    texts = [" ".join("".join(rng.choices("abcdefgh", k=7)) for _ in range(1000)) + "\n" + prose(rng, 50) for _ in range(20)]
    encode, reference = packing.encoder("byte_bpe_50k.json"), Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    assert [np.frombuffer(encode(t), "<u4").tolist() for t in texts] == [reference.encode(t, add_special_tokens=False).ids for t in texts]
    fresh = ["".join(t)[::-1] for t in texts]
    tracemalloc.start()
    for t in fresh:
        encode(t)
    kept = tracemalloc.get_traced_memory()[0]
    tracemalloc.stop()
    assert kept < 500_000


def test_search_packs_no_worse_than_best_fit():
    rng = random.Random(13)
    for _ in range(15):
        counts = {s: rng.randrange(1, 6) for s in rng.sample(range(1, 101), 30)}
        start = packing.best_fit(counts, 100)
        packed = packing.local_search(start, 100)
        offers = {}
        for a in packed:  # a local optimum: every pair is tried
            for b in packed:
                if sum(b) <= sum(a) < 100 and (a != b or packed[a] > 1):
                    assert packing.exchanged(a, b, 100, offers) is None
        total = lambda bins: {s: sum(n * p.count(s) for p, n in bins.items()) for s in counts}
        assert total(start) == total(packed) == counts and all(sum(p) <= 100 for p in packed)
        assert sum(packed.values()) <= sum(start.values())
        assert sum(n * sum(p) ** 2 for p, n in packed.items()) >= sum(n * sum(p) ** 2 for p, n in start.items())


def test_components(spark):
    rng = random.Random(14)
    links = [(rng.randrange(60), rng.randrange(60)) for _ in range(45)] + [(k, k + 1) for k in range(100, 130)]
    parent = {x: x for e in links for x in e}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in links:
        a, b = sorted((find(a), find(b)))
        parent[b] = a
    got = {r["node"]: r["component"] for r in base.connected_components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert got == {x: find(x) for e in links if e[0] != e[1] for x in e}
    assert base.connected_components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_pipeline_on_the_smallest_tables(spark):
    import corpus_pipeline

    out = corpus_pipeline.run(spark, "/root/testdata/sf0.001")
    fill = out.groupBy("sequence_id").agg(F.sum("length").alias("n")).agg(F.max("n")).first()[0]
    assert fill <= 1024 and out.select("doc_id").distinct().count() > 100


def test_pipeline_matches_its_stages_by_hand_on_odd_rows(spark, tmp_path):
    import public_tokenizers
    import corpus_pipeline
    import numpy as np
    from tokenizers import Tokenizer

    rng = random.Random(71)
    item = prose(rng, 14)
    texts = [prose(rng, rng.randrange(5, 120)) for _ in range(40)] + [" ".join(w + "###" for w in prose(rng, 30).split()) for _ in range(12)]
    texts += [texts[3], texts[4].replace(texts[4].split()[0], "zebra", 1), None, "", item, "write a.b@c.example or 1.2.3.4 " + prose(rng, 8), prose(rng, 3000)]
    rows = [(i, t, "xx", "s", len(t or ""), 0.5, 1, "y") for i, t in enumerate(texts)]
    rows += [rows[7], (None, "no id " + prose(rng, 9), None, None, None, None, None, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, score double, piece int, spans string")
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    labels = spark.createDataFrame([(i, int("###" not in (t or ""))) for i, t in enumerate(texts)], "doc_id long, quality int")
    labels.write.parquet(f"{tmp_path}/labels.parquet")
    spark.createDataFrame([(1, item), (2, None)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    out = corpus_pipeline.run(spark, str(tmp_path)).toPandas()

    conf = quality.SubwordConfig()
    model = quality.train(docs, labels)
    pairs = [(r[0], r[1]) for r in rows if brute_quality(r[1], model, conf) >= 0.3]
    assert not any("###" in (t or "") for _, t in pairs) and len(pairs) > 40
    component, _ = brute_components(pairs, 5, 80)
    pairs = [p for p, c in zip(pairs, component) if c == p[0]]
    hits = decontam.brute_force([(i, t) for i, (_, t) in enumerate(pairs)], [(1, item)])
    pairs = [p for i, p in enumerate(pairs) if hits[i][1] <= 0.5 * hits[i][0]]
    clean = [(d, re.sub(r"1\.2\.3\.4", "[IP]", re.sub(r"a\.b@c\.example", "[EMAIL]", t or ""))) for d, t in pairs]
    engine = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    want = []
    for d, t in clean:
        ids = np.array([*engine.encode(t, add_special_tokens=False).ids, 2], "<u4")
        cuts = [0, *range(len(ids) % 1024 or 1024, len(ids) + 1, 1024)] if len(ids) > 1024 else [0, len(ids)]
        want += [(str(d), k, b - a, zlib.crc32(ids[a:b].tobytes())) for k, (a, b) in enumerate(zip(cuts, cuts[1:]))]
    got = [("None" if x != x else str(int(x)), p, n, c) for x, p, n, c in zip(out["doc_id"], out["piece"], out["length"], out["ids_crc32"])]
    assert sorted(got) == sorted(want)
    out = out.sort_values(["sequence_id", "offset"])
    assert (out.groupby("sequence_id")["length"].cumsum() - out["length"] == out["offset"]).all() and out.groupby("sequence_id")["length"].sum().max() <= 1024


def test_pipeline_on_empty_tables(spark, tmp_path):
    import corpus_pipeline

    for name, schema in (("documents", "doc_id long, text string, lang string, source string, n_chars long"), ("labels", "doc_id long, quality int, toxic int"), ("benchmark", "item_id long, text string")):
        spark.createDataFrame([], schema).write.parquet(f"{tmp_path}/{name}.parquet")
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0
