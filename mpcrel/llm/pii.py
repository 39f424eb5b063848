"""Information-theoretic sanitisation of personal data, with built-in functions only.

Patterns find the protected entities: e-mail and IP addresses, payment cards and phone numbers. Then the corpus tells which
words give an entity away. For an entity e and a term t anywhere in its documents, pointwise mutual information log2(N co(e,t) / (df(e) df(t)))
over documents says how much t reveals of e; the information of e itself is log2(N / df(e)). A term whose share of the
entity's information reaches the disclosure threshold is a span too wherever it stands in a document that holds the entity,
provided that more than one document's chance speaks for the tie: the entity has enough different contexts there, or the term is
part of the entity's own name (the letters before an @). In sanitised text a disclosing term is generalised to its class (its first letters) if the class is below the
threshold, and removed otherwise.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .base import settle

KINDS = ("email", "ip", "card", "phone")

#: Leftmost, non-overlapping. A run of characters that a match must take whole is entered at its start or where the match
#: before ended, so no run is tried from each of its characters.
PATTERNS = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[ -]?[0-9])++",
    "phone": r"\+[0-9][ ().0-9-]+[0-9]",
}
#: Texts that fail this test have no match that counts.
GUARDS = {"email": r"@", "ip": r"[0-9]\.[0-9]++\.[0-9]++\.[0-9]", "card": r"[0-9](?:[ -]?[0-9]){15}", "phone": r"\+[0-9]"}

_PART = "0*(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[1-9]?[0-9])"
_SPAN = "array<struct<start:int,end:int,value:string>>"
#: Prefix sums over arrays are taken in runs of this length.
_RUN = 64


@dataclass(frozen=True)
class SanitiseConfig:
    context: int = 48  # characters on either side of an entity that tell its contexts apart
    min_contexts: int = 3  # different contexts of the entity in the documents that hold the term
    threshold: float = 0.75  # share of the entity's information
    class_letters: int = 3
    broadcast_rows: int = 200_000  # above, lists of terms are joined by a shuffle


def prefix_sums(values: Column) -> Column:
    """Running sums of an int array, linear but for runs of fixed length and their number squared over 8192."""
    runs = F.transform(F.sequence(F.lit(0), F.greatest(F.floor((F.size(values) - 1) / _RUN).cast("int"), F.lit(0))), lambda k: F.slice(values, k * _RUN + 1, F.lit(_RUN)))
    total = lambda a: F.aggregate(a, F.lit(0), lambda n, x: n + x)
    totals = F.transform(runs, total)
    inside = F.transform(runs, lambda run: F.transform(run, lambda x, i: total(F.slice(run, F.lit(1), i + 1))))
    return F.flatten(F.transform(inside, lambda run, k: F.transform(run, lambda x: x + total(F.slice(totals, F.lit(1), k)))))


def matches(text: Column, pattern: str) -> Column:
    """Every match with its place: array of (start, end, value), in code points, end exclusive."""
    values = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    gaps = F.transform(F.split(text, pattern, -1), F.length)
    ends = prefix_sums(F.zip_with(F.slice(gaps, F.lit(1), F.size(values)), values, lambda g, v: g + F.length(v)))
    placed = F.zip_with(ends, values, lambda end, v: F.struct((end - F.length(v)).alias("start"), end.alias("end"), v.alias("value")))
    return F.when(F.size(values) > 0, placed).otherwise(F.array().cast(_SPAN)).cast(_SPAN)


def with_matches(df: DataFrame, text: str, pattern: str, out: str) -> DataFrame:
    """df with every match of the pattern that a column holds and its place, as `matches` gives them; for rows with many matches,
    since what is used more than once is computed once."""
    size = lambda: F.size("__values")
    total = lambda a: F.aggregate(a, F.lit(0), lambda n, x: n + x)
    steps = [
        ("__values", F.regexp_extract_all(text, F.col(pattern), F.lit(0))),
        ("__gaps", F.transform(F.split(text, F.col(pattern), -1), F.length)),
        ("__steps", F.zip_with(F.slice("__gaps", F.lit(1), size()), "__values", lambda g, v: g + F.length(v))),
        ("__runs", F.transform(F.sequence(F.lit(0), F.greatest(F.floor((size() - 1) / _RUN).cast("int"), F.lit(0))), lambda k: F.slice("__steps", k * _RUN + 1, F.lit(_RUN)))),
        ("__sums", F.transform("__runs", total)),
        ("__before", F.transform("__sums", lambda s, k: total(F.slice("__sums", F.lit(1), k)))),
        ("__ends", F.flatten(F.zip_with("__runs", "__before", lambda run, b: F.transform(run, lambda x, i: b + total(F.slice(run, F.lit(1), i + 1)))))),
        (out, F.zip_with("__ends", "__values", lambda end, v: F.struct((end - F.length(v)).alias("start"), end.alias("end"), v.alias("value"))).cast(_SPAN)),
    ]
    for name, column in steps:
        df = df.withColumn(name, column)
    return df.drop(*(name for name, _ in steps[:-1]))


def _digits(value: Column) -> Column:
    return F.regexp_replace(value, "[^0-9]", "")


def _counts(kind: str, value: Column) -> Column:
    """Whether a match of the kind's pattern is one of the kind."""
    if kind == "email":
        return F.lit(True)
    if kind == "ip":
        return value.rlike(rf"^{_PART}\.{_PART}\.{_PART}\.{_PART}$")
    digits = _digits(value)
    if kind == "phone":
        return F.length(digits).between(8, 15)
    from_right = F.transform(F.sequence(F.lit(1), F.length(digits)), lambda i: F.substring(F.reverse(digits), i, F.lit(1)).cast("int") * (F.when(i % 2 == 0, 2).otherwise(1)))
    luhn = F.aggregate(from_right, F.lit(0), lambda n, d: n + F.when(d > 9, d - 9).otherwise(d)) % 10 == 0
    return F.when(F.length(digits).between(16, 19), luhn).otherwise(False)


def base_spans(text: Column) -> Column:
    """array of (kind, start, end, value) by kind, then start."""
    shape = "array<struct<kind:string,start:int,end:int,value:string>>"

    def of(kind: str) -> Column:
        spans = F.filter(matches(text, PATTERNS[kind]), lambda m: _counts(kind, m["value"]))
        tagged = F.transform(spans, lambda m: F.struct(F.lit(kind).alias("kind"), m["start"].alias("start"), m["end"].alias("end"), m["value"].alias("value")))
        return F.when(text.rlike(GUARDS[kind]), tagged.cast(shape)).otherwise(F.array().cast(shape))

    return F.concat(*map(of, KINDS))


def _analysed(documents: DataFrame, conf: SanitiseConfig) -> DataFrame:
    """doc_id, tid (a hash of the text, for repeated ids), spans, text where there are spans; settled, since several statistics are
    taken from it."""
    text = F.coalesce("text", F.lit(""))
    rows = documents.select("doc_id", F.xxhash64(text).alias("tid"), text.alias("text")).withColumn("spans", base_spans(F.col("text")))
    around = F.transform("spans", lambda s: F.struct(
        s["kind"].alias("kind"), s["start"].alias("start"), s["end"].alias("end"), s["value"].alias("value"),
        F.substring("text", F.greatest(s["start"] - conf.context, F.lit(0)) + 1, F.least(s["start"], F.lit(conf.context))).alias("before"),
        F.substring("text", s["end"] + 1, F.lit(conf.context)).alias("after")))
    return settle(rows.select("doc_id", "tid", around.alias("spans"), F.when(F.size("spans") > 0, F.col("text")).alias("text")))


def _name(span: Column) -> Column:
    return F.concat_ws(":", span["kind"], F.when(span["kind"].isin("card", "phone"), _digits(span["value"])).otherwise(F.lower(span["value"])))


def _parts(span: Column) -> Column:
    """Words of the entity's own name."""
    local = F.when(span["kind"] == "email", F.lower(F.substring_index(span["value"], "@", 1))).otherwise("")
    return F.array_distinct(F.regexp_extract_all(local, F.lit(r"(\p{L}{3,}+)"), F.lit(1)))


def _near(analysed: DataFrame, conf: SanitiseConfig) -> DataFrame:
    """doc_id, tid, entity, contexts, parts, words: each entity of a document with its contexts there, the words of its name, and
    the document's different words outside its spans.

    Entities with fewer contexts in all than a term needs come with the words of their names and of the same classes only, and are
    left out if they have no name.
    """
    found = analysed.where(F.size("spans") > 0).dropDuplicates(["doc_id", "tid"])
    of = found.select("doc_id", "tid", F.explode("spans").alias("s")).select("doc_id", "tid", _name(F.col("s")).alias("entity"), _parts(F.col("s")).alias("parts"), F.xxhash64(F.lower("s.before"), F.lower("s.after")).alias("context"))
    enough = settle(of.select("entity", "context").distinct().groupBy("entity").agg(F.count("*").alias("n")).where(F.col("n") >= conf.min_contexts).select("entity", F.lit(True).alias("wide")))
    kept = _linked(of, enough, enough.count(), ["entity"], conf, "left").where(F.col("wide") | (F.size("parts") > 0))
    kept = kept.groupBy("doc_id", "tid", "entity").agg(F.collect_set("context").alias("contexts"), F.max("parts").alias("parts"), F.max("wide").alias("wide"))
    held = kept.groupBy("doc_id", "tid").agg(F.collect_list(F.struct("entity", "contexts", "parts", "wide")).alias("entities"))
    texts = found.join(held.withColumnsRenamed({"doc_id": "__doc", "tid": "__tid"}), F.col("doc_id").eqNullSafe(F.col("__doc")) & (F.col("tid") == F.col("__tid")))
    outside = F.aggregate("spans", F.col("text"), lambda t, s: F.replace(t, s["value"], F.lit(" ")))
    words = F.array_distinct(F.filter(F.split(F.lower(outside), r"[^\p{L}]+"), lambda w: F.length(w) >= 3))
    settled = settle(texts.select("doc_id", "tid", "entities", words.alias("words"))).select("doc_id", "tid", F.explode("entities").alias("e"), "words")
    named = F.filter("words", lambda w: F.exists("e.parts", lambda p: _class_of(p, conf) == _class_of(w, conf)))
    return settled.select("doc_id", "tid", "e.entity", "e.contexts", "e.parts", F.when(F.col("e.wide"), F.col("words")).otherwise(named).alias("words"))


def _class_of(term: Column, conf: SanitiseConfig) -> Column:
    return F.concat(F.substring(term, 1, conf.class_letters), F.lit("*"))


def _linked(rows: DataFrame, few: DataFrame, count: int, on: list[str], conf: SanitiseConfig, how: str = "inner") -> DataFrame:
    """Joins by a broadcast of `few`, whose rows were counted, or by a shuffle if there are too many."""
    return rows.join(F.broadcast(few) if count <= conf.broadcast_rows else few, on, how)


def disclosures(documents: DataFrame, conf: SanitiseConfig = SanitiseConfig(), analysed: DataFrame | None = None, near: DataFrame | None = None) -> DataFrame:
    """entity, term, co, contexts, df_entity, df_term, disclosure, general: the terms that reveal an entity.

    `general` is the class that may stand for the term, or null if that reveals too much as well. All statistics are counts of
    whole documents (rows with equal id and text count once per row that holds them).
    """
    analysed = _analysed(documents, conf) if analysed is None else analysed
    near = _near(analysed, conf) if near is None else near
    terms = F.array_distinct(F.concat("words", F.transform("words", lambda t: _class_of(t, conf))))
    names = F.concat("parts", F.transform("parts", lambda p: _class_of(p, conf)))
    held_terms = near.select("entity", "contexts", names.alias("names"), F.explode(terms).alias("term")).withColumn("named", F.array_contains("names", F.col("term")))
    classes = held_terms.select("entity", "term", "named", F.posexplode("contexts").alias("number", "context"))
    met = classes.groupBy("entity", "term", "context").agg(F.sum((F.col("number") == 0).cast("long")).alias("co"), F.max("named").alias("named"))  # a document counts at its first context
    pairs = met.groupBy("entity", "term").agg(F.sum("co").alias("co"), F.count("*").alias("contexts"), F.max("named").alias("named"))
    pairs = settle(pairs.where((F.col("contexts") >= conf.min_contexts) | F.col("named")))
    words = F.array_distinct(F.split(F.lower(F.coalesce("text", F.lit(""))), r"[^\p{L}]+"))
    held = documents.select(F.explode(F.array_distinct(F.concat(words, F.transform(words, lambda w: _class_of(w, conf))))).alias("term"))
    df_term = held.groupBy("term").agg(F.count("*").alias("df_term"))  # counted before the shuffle, whatever the number of pairs
    df_entity = (analysed.where(F.size("spans") > 0).select("doc_id", "tid", F.explode("spans").alias("s")).select("doc_id", "tid", _name(F.col("s")).alias("entity")).distinct()
                 .groupBy("entity").agg(F.count("*").alias("df_entity")))
    n = analysed.count()
    share = F.log2(F.lit(float(n)) * F.col("co") / (F.col("df_entity") * F.col("df_term"))) / F.log2(F.lit(float(n)) / F.col("df_entity"))
    rated = pairs.join(df_term, "term").join(df_entity, "entity").withColumn("disclosure", F.when(F.col("df_entity") < n, share).otherwise(0.0))
    safe = rated.where(F.col("term").endswith("*") & (F.col("disclosure") < conf.threshold)).select("entity", F.col("term").alias("general"))
    bad = rated.where(~F.col("term").endswith("*") & (F.col("disclosure") >= conf.threshold)).withColumn("class", _class_of(F.col("term"), conf))
    return bad.join(safe, (bad["entity"] == safe["entity"]) & (bad["class"] == safe["general"]), "left").select(bad["entity"], "term", "co", "contexts", "df_entity", "df_term", "disclosure", "general")


def _term_spans(documents: DataFrame, conf: SanitiseConfig, analysed: DataFrame) -> DataFrame:
    """doc_id, tid, terms: array of (start, end, general) of disclosing terms in each document that has some; settled."""
    near = _near(analysed, conf)
    bad = settle(disclosures(documents, conf, analysed, near))
    met = _linked(near.select("doc_id", "tid", "entity", F.explode("words").alias("term")), bad.select("entity", "term", "general"), bad.count(), ["entity", "term"], conf)
    # a term that must be removed for one of the entities goes, whatever others would allow
    met = met.groupBy("doc_id", "tid", "term").agg(F.when(F.count("general") == F.count("*"), F.min("general")).alias("general"))
    lists = settle(met.groupBy("doc_id", "tid").agg(F.collect_list(F.struct("term", "general")).alias("known"))).withColumnsRenamed({"doc_id": "__doc", "tid": "__tid"})
    texts = analysed.where(F.size("spans") > 0).dropDuplicates(["doc_id", "tid"])
    few = F.broadcast(lists) if lists.count() <= conf.broadcast_rows else lists
    texts = texts.join(few, F.col("doc_id").eqNullSafe(F.col("__doc")) & (F.col("tid") == F.col("__tid"))).drop("__doc", "__tid")
    pattern = F.concat(F.lit(r"(?<!\p{L})(?iu:"), F.array_join(F.transform("known", lambda k: k["term"]), "|"), F.lit(r")(?!\p{L})"))
    placed = with_matches(texts.withColumn("__pattern", pattern), "text", "__pattern", "places")
    free = F.filter("places", lambda w: ~F.exists("spans", lambda s: (s["start"] < w["end"]) & (w["start"] < s["end"])) & F.exists("known", lambda k: k["term"] == F.lower(w["value"])))
    spans = F.transform(free, lambda w: F.struct(w["start"].alias("start"), w["end"].alias("end"), F.filter("known", lambda k: k["term"] == F.lower(w["value"]))[0]["general"].alias("general")))
    return settle(placed.select("doc_id", "tid", F.array_sort(spans).alias("terms")).where(F.size("terms") > 0))


def _same_document(a: DataFrame, b: DataFrame) -> Column:
    return a["doc_id"].eqNullSafe(b["doc_id"]) & (a["tid"] == b["tid"])


def report(documents: DataFrame, conf: SanitiseConfig = SanitiseConfig()) -> DataFrame:
    """doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans for every row; null text is empty.

    Rows with one doc_id are told apart by their texts; an empty table gives an empty result; other columns are not read.
    """
    analysed = _analysed(documents, conf)
    terms = _term_spans(documents, conf, analysed)
    few = terms.count()
    joined = analysed.join(F.broadcast(terms) if few <= conf.broadcast_rows else terms, _same_document(analysed, terms), "left").select(analysed["doc_id"], "spans", "terms")
    base = F.array_join(F.transform("spans", lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])), ",")
    more = F.transform("terms", lambda t: F.concat_ws(":", F.lit("term"), t["start"], t["end"]))
    number = lambda kind: F.size(F.filter("spans", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")
    counts = [number(kind) for kind in KINDS]
    every = F.concat(F.transform("spans", lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])), F.coalesce(more, F.array().cast("array<string>")))
    return joined.select("doc_id", *counts, F.sha2(base.cast("binary"), 256).alias("base_sha256"), F.array_join(every, ",").alias("spans"))


def sanitise(documents: DataFrame, conf: SanitiseConfig = SanitiseConfig()) -> DataFrame:
    """documents with entities replaced by a mark of their kind and disclosing terms generalised or removed.

    All columns stay; n_chars, where there is such a column, follows the new text. Texts without spans are left as they are.
    """
    terms = _term_spans(documents, conf, _analysed(documents, conf))
    few = terms.count()
    rows = documents.withColumn("__tid", F.xxhash64(F.coalesce("text", F.lit(""))))
    side = terms.select(F.col("doc_id").alias("__doc"), F.col("tid").alias("__other"), "terms").withColumnRenamed("terms", "__terms")
    joined = rows.join(F.broadcast(side) if few <= conf.broadcast_rows else side, F.col("doc_id").eqNullSafe(F.col("__doc")) & (F.col("__tid") == F.col("__other")), "left")
    shape = "array<struct<start:int,end:int,put:string>>"
    own = F.transform(base_spans(F.col("text")), lambda s: F.struct(s["start"].alias("start"), s["end"].alias("end"), F.concat(F.lit("["), F.upper(s["kind"]), F.lit("]")).alias("put"))).cast(shape)
    added = F.transform("__terms", lambda t: F.struct(t["start"].alias("start"), t["end"].alias("end"), F.coalesce(t["general"], F.lit("[TERM]")).alias("put"))).cast(shape)
    spans = F.array_sort(F.concat(own, F.coalesce(added, F.array().cast(shape))))
    text = F.col("text")

    def step(done, s):
        inside = s["end"] <= done["at"]
        parts = F.concat(done["parts"], F.array(F.substring(text, done["at"] + 1, F.greatest(s["start"] - done["at"], F.lit(0))), F.when(s["start"] >= done["at"], s["put"]).otherwise("")))
        return F.struct(F.when(inside, done["at"]).otherwise(s["end"]).alias("at"), F.when(inside, done["parts"]).otherwise(parts).alias("parts"))

    clean = F.aggregate("__spans", F.struct(F.lit(0).alias("at"), F.array(F.lit("")).alias("parts")), step,
                        lambda done: F.concat(F.array_join(done["parts"], ""), F.substring(text, done["at"] + 1, F.length(text))))
    out = joined.withColumn("__spans", spans).withColumn("text", F.when(F.size("__spans") > 0, clean).otherwise(text))
    columns = [F.length("text").cast(documents.schema[c].dataType).alias(c) if c == "n_chars" else F.col(c) for c in documents.columns]
    return out.select(*[F.when(F.size("__spans") > 0, x).otherwise(F.col(c)).alias(c) if c == "n_chars" else x for c, x in zip(documents.columns, columns)])
