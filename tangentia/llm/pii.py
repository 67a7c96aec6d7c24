"""Personal data by patterns, and what else in a text would give it away (all DataFrame functions).

Base spans are matches of four patterns. Any other word of a text that holds one is a term that may disclose it. How much
a term tells of an entity (one value of one kind) is estimated from the whole corpus: with distinct texts that hold the
term, the entity, and both, the pointwise mutual information of the two is set against the entity's own information. A
term that gives away nearly all of it is removed wherever it stands in the corpus, one that gives away most of it is
generalised. Copies of one text are one piece of evidence, and a pair needs ``SUPPORT`` of them: distinct texts
that hold both, or distinct contexts (``REACH`` code points to either side of the entity) that hold the term.

The patterns are written so that Java's engine neither tries a run of characters again from each of its places nor recurses
on it: runs are possessive and begin where they can begin. They match what the plain forms match.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tangentia.session import materialise

KINDS = ("email", "ip", "card", "phone")
PATTERNS = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
NEEDS = {"email": "@", "phone": "+"}  # without which a pattern has no match
AT_MOST_255 = r"^0*(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[0-9]{1,2})$"
WORD = r"(?<![\p{L}\p{N}])\p{L}[\p{L}\p{N}]{2,39}+(?![\p{L}\p{N}])"
REACH = 120
SUPPORT = 3
GENERALISE, REMOVE = 0.85, 0.95  # shares of an entity's information
LEAST_SHARE = 0.5  # of the distinct texts that hold a term, how many must hold the entity too
FEW_TERMS = 100_000
STRIDE = 64
SPAN = "array<struct<kind:string,start:int,end:int,value:string>>"


def let(value: Column, body) -> Column:
    """body(value) with the value computed once, however often the body names it."""
    return F.element_at(F.transform(F.array(value), body), 1)


def running_sums(lengths: Column) -> Column:
    """Sums of an array up to and with each place, by sums over strides first: far from quadratic for long arrays."""
    total = lambda a: F.aggregate(a, F.lit(0), lambda x, y: x + y)
    stride = lambda i: (i / STRIDE).cast("int")

    def places(v: Column) -> Column:
        strides = F.transform(F.sequence(F.lit(0), stride(F.size(v) - 1)), lambda j: total(F.slice(v, j * STRIDE + 1, F.lit(STRIDE))))
        before = let(strides, lambda s: F.transform(F.sequence(F.lit(0), F.size(s) - 1), lambda j: total(F.slice(s, F.lit(1), j))))
        place = lambda b: lambda i: F.element_at(b, stride(i) + 1) + total(F.slice(v, stride(i) * STRIDE + 1, i % STRIDE + 1))
        return let(before, lambda b: F.transform(F.sequence(F.lit(0), F.size(v) - 1), place(b)))

    return let(lengths, places)


def found_spans(kind: str, text: Column, pattern: str) -> Column:
    """(kind, start, end, value) of the leftmost matches that don't overlap, in code points from 0."""
    none = F.array().cast(SPAN)

    def spans(m: Column) -> Column:
        values, gaps = m["values"], m["gaps"]
        steps = F.transform(values, lambda v, i: F.length(F.get(gaps, i)) + F.when(i > 0, F.length(F.get(values, i - 1))).otherwise(0))
        at = lambda starts: F.transform(values, lambda v, i: F.struct(F.lit(kind).alias("kind"), F.get(starts, i).alias("start"), (F.get(starts, i) + F.length(v)).alias("end"), v.alias("value")))
        return let(running_sums(steps), at)

    matches = lambda values: F.when(F.size(values) > 0, let(F.struct(values.alias("values"), F.split(text, pattern, -1).alias("gaps")), spans)).otherwise(none)
    found = let(F.regexp_extract_all(text, F.lit(pattern), F.lit(0)), matches)
    return F.when(F.contains(text, F.lit(NEEDS[kind])), found).otherwise(none) if kind in NEEDS else found


def passes_luhn(digits: Column) -> Column:
    """Digits from the right, every second one doubled and its digits added, sum to a multiple of 10."""

    def worth(d: Column, i: Column) -> Column:
        x = F.substring(d, F.length(d) - i + 1, F.lit(1)).cast("int")
        return F.when(i % 2 == 1, x).otherwise(2 * x - F.when(x > 4, 9).otherwise(0))

    return let(digits, lambda d: F.aggregate(F.sequence(F.lit(1), F.length(d)), F.lit(0), lambda total, i: total + worth(d, i)) % 10 == 0)


def base_spans(text: Column) -> Column:
    """All base spans, by kind as listed and start within; matches that fail their check are dropped."""
    digits = lambda v: F.regexp_replace(v, "[^0-9]", "")
    check = {
        "email": None,
        "ip": lambda s: F.forall(F.split(s["value"], r"\."), lambda p: F.rlike(p, F.lit(AT_MOST_255))),
        "card": lambda s: F.length(digits(s["value"])).between(13, 19) & passes_luhn(digits(s["value"])),
        "phone": lambda s: F.length(digits(s["value"])).between(9, 15),
    }
    parts = []
    for kind in KINDS:
        spans = found_spans(kind, text, PATTERNS[kind])
        parts.append(F.filter(spans, check[kind]) if check[kind] else spans)
    return F.concat(*parts)


def listed(spans: Column) -> Column:
    """kind:start:end, comma-joined."""
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def text_digest() -> Column:
    return F.xxhash64(F.coalesce(F.col("text").cast("string"), F.lit("")))


def overlaps(base: Column, t: Column) -> Column:
    return F.exists(base, lambda b: (b["start"] < t["end"]) & (b["end"] > t["start"]))


def terms_of(text: Column) -> Column:
    return F.transform(F.regexp_extract_all(text, F.lit(WORD), F.lit(0)), F.lower)


def find_base(docs: DataFrame) -> DataFrame:
    """(doc_id, digest, base, near, terms): a row's spans, entity and context of each, and the distinct words outside them."""
    rows = docs.select("doc_id", F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text")).withColumn("base", base_spans(F.col("text")))
    around = F.transform(
        "base",
        lambda s: F.struct(
            F.concat_ws(":", s["kind"], F.lower(s["value"])).alias("entity"),
            F.substring("text", F.greatest(s["start"] - REACH, F.lit(0)) + 1, F.least(s["start"], F.lit(REACH))).alias("left"),
            F.substring("text", s["end"] + 1, F.lit(REACH)).alias("right"),
        ),
    )
    outside = F.transform(F.filter(found_spans("term", F.col("text"), WORD), lambda t: ~overlaps(F.col("base"), t)), lambda t: F.lower(t["value"]))
    terms = F.array_distinct(F.when(F.size("base") > 0, outside).otherwise(terms_of(F.col("text"))))
    return rows.select("doc_id", text_digest().alias("digest"), "base", around.alias("near"), terms.alias("terms"))


def disclosing_terms(found: DataFrame) -> DataFrame:
    """(term, removed): the terms that give an entity away."""
    own = found.where(F.size("base") > 0)
    near = own.select("digest", F.explode("near").alias("n")).select("digest", "n.*")
    near = near.withColumn("context", F.xxhash64(F.regexp_replace("left", r"\s+", " "), F.regexp_replace("right", r"\s+", " ")))
    holders = near.select("entity", "digest").distinct()
    entity = holders.groupBy("entity").agg(F.count(F.lit(1)).alias("n_entity"))
    contexts = near.groupBy("entity", "context").agg(F.first("left").alias("left"), F.first("right").alias("right"))
    known = entity.join(contexts.groupBy("entity").agg(F.count(F.lit(1)).alias("n_contexts")), "entity").where((F.col("n_entity") >= SUPPORT) | (F.col("n_contexts") >= SUPPORT))
    known = materialise(known, "entities")

    beside = contexts.join(known.where(F.col("n_contexts") >= SUPPORT), "entity", "left_semi").select("entity", F.explode(F.array_distinct(terms_of(F.concat_ws("\n", "left", "right")))).alias("term"))
    beside = beside.groupBy("term", "entity").agg(F.count(F.lit(1)).alias("n_beside")).where(F.col("n_beside") >= SUPPORT)
    held = own.select("digest", F.explode("terms").alias("term")).distinct()
    both = holders.join(known, "entity", "left_semi").join(held, "digest").groupBy("term", "entity").agg(F.count(F.lit(1)).alias("n_both"))
    both = both.join(beside, ["term", "entity"], "left").where((F.col("n_both") >= SUPPORT) | F.col("n_beside").isNotNull())
    # a term stands in at least as many texts as together with any entity; where that already makes it common, it gives nothing away
    least = held.groupBy("term").agg(F.count(F.lit(1)).alias("n_held"))
    both = both.join(known, "entity").join(least, "term").where(F.col("n_both") >= LEAST_SHARE * F.col("n_held"))
    both = materialise(both.select("term", "entity", "n_both", "n_entity"), "term-pairs")
    terms = both.select("term").distinct()
    n_terms = terms.limit(FEW_TERMS + 1).count()
    words = found.select("digest", F.explode("terms").alias("term"))
    words = words.join(F.broadcast(terms) if n_terms <= FEW_TERMS else terms, "term", "left_semi")
    frequency = words.groupBy("term", "digest").count().groupBy("term").agg(F.count(F.lit(1)).alias("n_term"))
    n = found.select("digest").distinct().count() if n_terms else 1
    share = F.least(F.lit(1.0), F.col("n_both") / F.col("n_term"))
    information = -F.log(F.least(F.lit(1.0), F.col("n_entity") / F.lit(float(max(n, 1)))))
    told = both.join(frequency, "term").withColumn("told", F.when(information > 0, 1 + F.log(share) / information).otherwise(F.lit(0.0)))
    told = told.where((F.col("told") >= GENERALISE) & (share >= LEAST_SHARE))
    return told.groupBy("term").agg(F.max(F.col("told") >= REMOVE).alias("removed"))


def find_personal(docs: DataFrame) -> DataFrame:
    """(doc_id, digest, base, terms) for each row: spans by kind and start; a term's value is "removed" or "generalised".

    Null texts count as empty and have no spans; rows that repeat a doc_id are searched each, by their own text;
    other columns are ignored; an empty table gives an empty result.
    """
    found = materialise(find_base(docs), "base-spans")
    told = materialise(disclosing_terms(found), "told-terms")
    if told.limit(FEW_TERMS + 1).count() <= FEW_TERMS:
        told = F.broadcast(told)
    hits = found.select("doc_id", "digest", F.explode("terms").alias("term")).join(told, "term")
    hits = hits.groupBy("doc_id", "digest").agg(F.map_from_entries(F.collect_set(F.struct("term", "removed"))).alias("told")).withColumnsRenamed({"doc_id": "id2", "digest": "digest2"})
    same = F.col("doc_id").eqNullSafe(F.col("id2")) & (F.col("digest") == F.col("digest2"))
    rows = docs.select("doc_id", F.col("text").cast("string").alias("text"), text_digest().alias("digest")).join(hits, same)
    places = F.filter(found_spans("term", F.col("text"), WORD), lambda t: F.map_contains_key("told", F.lower(t["value"])))
    value = lambda t: F.when(F.element_at("told", F.lower(t["value"])), "removed").otherwise("generalised")
    terms = F.transform(places, lambda t: F.struct(t["kind"].alias("kind"), t["start"].alias("start"), t["end"].alias("end"), value(t).alias("value")))
    by_row = rows.select("id2", "digest2", terms.cast(SPAN).alias("terms")).dropDuplicates(["id2", "digest2"])
    joined = found.select("doc_id", "digest", "base").join(by_row, same, "left")
    free = F.filter("terms", lambda t: ~overlaps(F.col("base"), t))
    return joined.select("doc_id", "digest", "base", F.coalesce(free, F.array().cast(SPAN)).alias("terms"))


def report(docs: DataFrame) -> DataFrame:
    """(doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans) for each row."""
    found = find_personal(docs)
    count = lambda k: F.size(F.filter("base", lambda s: s["kind"] == k)).cast("long").alias(f"n_{k}")
    return found.select("doc_id", *[count(k) for k in KINDS], F.sha2(listed(F.col("base")).cast("binary"), 256).alias("base_sha256"), listed(F.concat("base", "terms")).alias("spans"))


def _unused(columns: list[str], *names: str) -> list[str]:
    """Names for columns of our own that ``columns`` does not have."""
    lead = "_"
    while any(c.lower().startswith(lead) for c in columns):
        lead += "_"
    return [lead + n for n in names]


def sanitise(docs: DataFrame) -> DataFrame:
    """``docs`` with each span's text replaced by its kind in brackets, or left out where a term is to be removed; n_chars follows.

    Spans that overlap are replaced as one, by the kind of the first. Rows without spans are left as they are, null texts too; other columns pass through, whatever their names.
    """
    at_id, at_digest, at_spans = _unused(docs.columns, "id", "digest", "spans")
    found = find_personal(docs).where((F.size("base") > 0) | (F.size("terms") > 0)).dropDuplicates(["doc_id", "digest"])
    found = found.select(F.col("doc_id").alias(at_id), F.col("digest").alias(at_digest), F.sort_array(F.transform(F.concat("base", "terms"), lambda s: F.struct(s["start"].alias("start"), s["end"].alias("end"), F.when(s["value"] == "removed", F.lit("")).otherwise(F.concat(F.lit("["), F.upper(s["kind"]), F.lit("]"))).alias("by")))).alias(at_spans))
    joined = docs.join(found, F.col("doc_id").eqNullSafe(F.col(at_id)) & (text_digest() == F.col(at_digest)), "left")
    start = F.struct(F.lit(0).alias("at"), F.array().cast("array<string>").alias("pieces"))

    def step(acc: Column, s: Column) -> Column:
        between = F.substring(F.col("text"), acc["at"] + 1, s["start"] - acc["at"])
        fresh = s["start"] >= acc["at"]
        return F.struct(F.greatest(acc["at"], s["end"]).alias("at"), F.when(fresh, F.concat(acc["pieces"], F.array(between, s["by"]))).otherwise(acc["pieces"]).alias("pieces"))

    rewritten = F.aggregate(at_spans, start, step, lambda acc: F.concat(F.array_join(acc["pieces"], ""), F.substring(F.col("text"), acc["at"] + 1, F.length("text"))))
    out = joined.withColumn("text", F.when(F.col(at_spans).isNull(), F.col("text")).otherwise(rewritten))
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.when(F.col(at_spans).isNull(), F.col("n_chars")).otherwise(F.length("text").cast(docs.schema["n_chars"].dataType)))
    return out.select(docs.columns)
