"""Personal data, found and sanitised with DataFrame functions only.

Base kinds are patterns with checks. What else gives a person away is learned from the corpus. A protected entity is a
base span's value, or what it has in common with others: an address' account or domain, a network, an issuer, a
dialling code. A term is a run of letters and digits, of any length. A term discloses log p(entity | term) / p(entity) of
the entity's own information -log p(entity), both estimated from the documents that hold them, wherever they stand in
them: 1 for a term that only stands in documents with the entity. Terms above the threshold, in enough documents, are
added as spans wherever they occur, in every document. For entities that aren't exact values, the information of all
documents together must also exceed what chance gives among the pairs examined, and entities of more than the share
COMMON of all documents protect nobody.

In sanitised texts base spans are replaced by their kind; terms are generalised to their class (a number, a name, a
word) or, if asked, removed.

A pattern's positions come from the lengths of the pieces around its matches, so no Python is needed. The patterns
give the contract's matches, but can't run long: quantifiers don't give back what they took where that can't matter,
and no attempt starts inside a run whose beginning has failed.

Scale: only documents with base spans give (entity, term) pairs, counted before they are shuffled; other terms are
counted only if such a pair has enough support. Which words of a text disclose is a join of its words with the terms,
by text, and comes back to the texts as a broadcast of checked size; only beyond that size are texts shuffled.

Contract: null counts as empty; rows with equal text have equal spans; positions are code points; repeated rows count
as documents of their own; an empty table gives an empty result; columns with other names are kept by `sanitised` as
they are.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from kinetrace.llm.storage import written

# The base kinds in order and their patterns.
PATTERNS = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?:\G|(?<![0-9]))[0-9]++(?:\.[0-9]++){3}",
    "card": r"[0-9](?:[\x20-]?+[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
KINDS = [*PATTERNS]
TERM = "term"
#: What every match holds, cheap to look for.
HINTS = {"email": "@", "ip": ".", "card": None, "phone": "+"}
SPAN = "array<struct<start:int,end:int,value:string>>"
WORD = r"[\p{L}\p{N}]+"
#: Least documents with both; least share disclosed; matches whose places are summed in one go.
SUPPORT, THRESHOLD, BLOCK = 3, 0.9, 512
COMMON = 0.01
#: Terms that may be broadcast, and bytes of the disclosing words of all texts that may.
BROADCAST_TERMS, BROADCAST_BYTES = 1_000_000, 32_000_000


def _let(value: Column, use) -> Column:
    """`use(value)` with the value computed once."""
    return F.transform(F.array(value), use)[0]


def positions(text: Column, pattern: str) -> Column:
    """All matches of `pattern` as (start, end, value), in order.

    Places are sums of lengths, made in blocks of matches: appending to one array for each of n matches would take n squared steps."""
    hits, gaps = F.regexp_extract_all(text, F.lit(pattern), F.lit(0)), F.split(text, pattern, -1)
    none = F.array().cast(SPAN)

    def place(acc: Column, pair: Column) -> Column:
        start = acc["at"] + F.length(pair["gap"])
        end = start + F.length(pair["hit"])
        return F.struct(end.alias("at"), F.concat(acc["found"], F.array(F.struct(start.alias("start"), end.alias("end"), pair["hit"].alias("value")))).alias("found"))

    def of_block(pairs: Column, start: Column) -> Column:
        return F.aggregate(pairs, F.struct(start.alias("at"), none.alias("found")), place, lambda acc: acc["found"])

    def longer(blocks: Column) -> Column:
        sizes = F.transform(blocks, lambda b: F.aggregate(b, F.lit(0), lambda n, p: n + F.length(p["gap"]) + F.length(p["hit"])))
        starts = lambda z: F.transform(F.sequence(F.lit(0), F.size(z) - 1), lambda i: F.aggregate(F.slice(z, F.lit(1), i), F.lit(0), lambda n, x: n + x))
        return F.flatten(F.zip_with(blocks, _let(sizes, starts), of_block))

    def placed(pairs: Column) -> Column:
        blocks = F.transform(F.sequence(F.lit(0), ((F.size(pairs) - 1) / BLOCK).cast("int")), lambda i: F.slice(pairs, i * BLOCK + 1, F.lit(BLOCK)))
        return F.when(F.size(pairs) == 0, none).when(F.size(pairs) <= BLOCK, of_block(pairs, F.lit(0))).otherwise(_let(blocks, longer))

    return _let(_let(hits, lambda h: F.zip_with(h, F.slice(gaps, F.lit(1), F.size(h)), lambda x, g: F.struct(x.alias("hit"), g.alias("gap")))), placed)


def _luhn(digits: Column) -> Column:
    def add(total: Column, i: Column) -> Column:
        d = F.substring(digits, -i, F.lit(1)).cast("int")
        twice = d * 2
        return total + F.when(i % 2 == 1, d).when(twice > 9, twice - 9).otherwise(twice)

    return F.aggregate(F.sequence(F.lit(1), F.length(digits)), F.lit(0), add) % 10 == 0


def valid(kind: str, value: Column) -> Column:
    if kind == "email":
        return F.lit(True)
    if kind == "ip":
        def small(part: Column) -> Column:
            bare = F.ltrim(part, F.lit("0"))
            return (F.length(bare) == 0) | ((F.length(bare) <= 3) & (F.when(F.length(bare) <= 3, bare).try_cast("int") <= 255))

        return F.forall(F.split(value, r"\."), lambda p: F.coalesce(small(p), F.lit(False)))
    digits = F.regexp_replace(value, "[^0-9]", "")
    if kind == "card":
        return F.length(digits).between(16, 19) & _luhn(digits)
    return F.length(digits).between(8, 15)


def base_spans(text: Column, kind: str) -> Column:
    found = F.filter(positions(text, PATTERNS[kind]), lambda s: valid(kind, s["value"]))
    hint = F.contains(text, F.lit(HINTS[kind])) if HINTS[kind] else text.rlike("[0-9]{2}|[0-9][ -][0-9]")
    return F.when(hint, found).otherwise(F.array().cast(SPAN))


def _each(kinds: list[str], make) -> list[Column]:
    """For each kind the array of what `make(kind, span)` gives."""

    def one(kind: str) -> Column:
        return F.transform(kind, lambda s: make(kind, s))

    return [one(k) for k in kinds]


def _entities(kind: str, span: Column) -> Column:
    """(exact, name) of the entities that a span stands for."""
    value = F.lower(span["value"])
    digits = F.regexp_replace(value, "[^0-9]", "")
    shared = {
        "email": [("account", F.substring_index(value, "@", 1)), ("domain", F.substring_index(value, "@", -1))], "ip": [("network", F.substring_index(value, ".", 3))],
        "card": [("issuer", F.substring(digits, 1, 6))], "phone": [("code", F.substring(digits, 1, 5))],
    }[kind]
    named = lambda exact, label, v: F.struct(F.lit(exact).alias("exact"), F.concat(F.lit(f"{label}:"), v).alias("entity"))
    return F.array(named(True, kind, value if kind in ("email", "ip") else digits), *(named(False, f"{kind}-{label}", v) for label, v in shared))


def scanned(rows: DataFrame, text: str = "_text") -> DataFrame:
    """`rows` with the spans of each base kind."""
    return rows.withColumns({k: base_spans(F.col(text), k) for k in KINDS})


def disclosing_terms(docs: DataFrame, support: int = SUPPORT, threshold: float = THRESHOLD) -> DataFrame:
    """(entity, term, disclosure): terms that give an entity away, by counts over all documents. `docs`: text."""
    rows = docs.select(F.coalesce(F.col("text").cast("string"), F.lit("")).alias("_text"))
    words = F.array_distinct(F.regexp_extract_all(F.lower(F.col("_text")), F.lit(WORD), F.lit(0)))
    entities = F.array_distinct(F.flatten(F.concat(*_each(KINDS, _entities))))
    held = scanned(rows).select("_text", entities.alias("entities")).where(F.size("entities") > 0)
    held = written(held.select("entities", words.alias("words")), "held")
    total = docs.count()
    known = held.select(F.explode("entities").alias("e")).groupBy("e.exact", "e.entity").agg(F.count("*").alias("n_entity")).where((F.col("n_entity") >= support) & (F.col("n_entity") < total))
    known = written(known, "entities")
    number = known.count()
    if number == 0:
        return known.select("entity", F.col("entity").alias("term"), F.lit(0.0).alias("disclosure")).limit(0)
    pairs = held.select(F.explode("entities").alias("e"), "words").select("e.entity", "words")
    pairs = pairs.join(F.broadcast(known.select("entity")) if number <= BROADCAST_TERMS else known.select("entity"), "entity", "left_semi")
    both = pairs.select("entity", F.explode("words").alias("term")).groupBy("entity", "term").agg(F.count("*").alias("n_both"))
    both = written(both.where(F.col("n_both") >= support).join(known, "entity"), "both")
    asked = written(both.select("term").distinct(), "asked")
    chosen = F.broadcast(asked) if asked.count() <= BROADCAST_TERMS else asked
    terms = rows.select(F.explode(words).alias("term")).join(chosen, "term", "left_semi").groupBy("term").agg(F.count("*").alias("n_term"))
    own = F.log(F.lit(float(total)) / F.col("n_entity"))
    counted = both.join(terms, "term").withColumn("disclosure", F.log(F.col("n_both") * F.lit(float(total)) / (F.col("n_entity") * F.col("n_term"))) / own)
    beyond_chance = F.col("exact") | ((F.col("n_entity") <= F.lit(COMMON * total)) & (F.col("n_both") * own >= F.log(F.lit(float(max(1, both.count()))))))
    return counted.where((F.col("disclosure") >= threshold) & beyond_chance).select("entity", "term", "disclosure")


def _hits(rows: DataFrame, flagged: DataFrame) -> DataFrame:
    """k1, k2 and hits: the words, as written, of each different text that has any of the terms."""
    terms = written(flagged.select("term").distinct(), "terms")
    words = rows.select("k1", "k2", F.explode(F.array_distinct(F.regexp_extract_all("_text", F.lit(WORD), F.lit(0)))).alias("word"))
    found = words.withColumn("term", F.lower("word")).join(F.broadcast(terms) if terms.count() <= BROADCAST_TERMS else terms, "term", "left_semi")
    return written(found.groupBy("k1", "k2").agg(F.collect_set("word").alias("hits")), "hits")


def _term_spans(text: Column, hits: Column) -> Column:
    """Places of the words of `hits` in the text; hits are looked up in buckets."""

    def among(buckets: Column) -> Column:
        return F.filter(positions(text, WORD), lambda s: F.array_contains(F.get(buckets, F.pmod(F.xxhash64(s["value"]), F.size(buckets)).cast("int")), s["value"]))

    width = (F.size(hits) / 16).cast("int")
    buckets = F.transform(F.sequence(F.lit(0), width), lambda b: F.filter(hits, lambda h: F.pmod(F.xxhash64(h), width + 1) == b))
    return _let(buckets, among)


def with_spans(docs: DataFrame, text: str = "text", support: int = SUPPORT, threshold: float = THRESHOLD) -> DataFrame:
    """`docs` (whose columns are prefixed by "of_", so no name clashes), _text, the base kinds' spans and `term`, the added ones."""
    body = F.coalesce(F.col(text).cast("string"), F.lit(""))
    flagged = written(disclosing_terms(docs.select(F.col(text).alias("text")), support, threshold), "flagged")
    rows = docs.select(body.alias("_text"), *(F.col(c).alias(f"of_{c}") for c in docs.columns))
    none = F.array().cast(SPAN)
    if flagged.isEmpty():
        return scanned(rows).withColumn(TERM, none)
    keyed = rows.withColumns({"k1": F.xxhash64("_text"), "k2": F.xxhash64(F.lit("second"), "_text")})
    hits = _hits(keyed, flagged)
    size = hits.agg(F.sum(F.aggregate("hits", F.lit(64), lambda n, w: n + 24 + F.octet_length(w)).cast("bigint"))).first()[0] or 0
    joined = keyed.join(F.broadcast(hits) if size <= BROADCAST_BYTES else hits, ["k1", "k2"], "left")
    spanned = scanned(joined).withColumn("_added", F.when(F.col("hits").isNotNull(), _term_spans(F.col("_text"), F.col("hits"))).otherwise(none))
    apart = F.filter("_added", lambda t: ~F.exists(F.concat(*KINDS), lambda s: (s["start"] < t["end"]) & (t["start"] < s["end"])))
    return spanned.select("_text", *(f"of_{c}" for c in docs.columns), *KINDS, F.when(F.size("_added") > 0, apart).otherwise(none).alias(TERM))


def _listed(kinds: list[str]) -> Column:
    return F.concat(*_each(kinds, lambda k, s: F.concat_ws(":", F.lit(k), s["start"].cast("string"), s["end"].cast("string"))))


def span_rows(docs: DataFrame) -> DataFrame:
    """doc_id, the number of spans of each base kind, base_sha256 and spans of every document."""
    counts = [F.size(k).cast("bigint").alias(f"n_{k}") for k in KINDS]
    rows = with_spans(docs.select("doc_id", "text"))
    return rows.select(F.col("of_doc_id").alias("doc_id"), *counts, F.sha2(F.array_join(_listed(KINDS), ",").cast("binary"), 256).alias("base_sha256"), F.array_join(_listed([*KINDS, TERM]), ",").alias("spans"))


def _mark(kind: str, span: Column, remove: bool) -> Column:
    if kind != TERM:
        return F.lit(f"[{kind.upper()}]")
    if remove:
        return F.lit("")
    return F.when(span["value"].rlike("[0-9]"), "[NUMBER]").when(span["value"].rlike(r"^\p{Lu}"), "[NAME]").otherwise("[WORD]")


def sanitised(docs: DataFrame, text: str = "text", remove: bool = False, support: int = SUPPORT, threshold: float = THRESHOLD) -> DataFrame:
    """`docs` with every base span of its texts replaced by its kind and every disclosing term by its class (`remove`: by nothing)."""
    rows = with_spans(docs, text, support, threshold)
    pieces = F.array_sort(F.concat(*_each([*KINDS, TERM], lambda k, s: F.struct(s["start"].alias("start"), s["end"].alias("end"), _mark(k, s, remove).alias("mark")))))
    body = F.col("_text")

    def put(acc: Column, s: Column) -> Column:
        """A span that begins inside the one before only lengthens it."""
        fresh = s["start"] >= acc["at"]
        parts = F.when(fresh, F.concat(acc["parts"], F.array(F.substring(body, acc["at"] + 1, s["start"] - acc["at"]), s["mark"]))).otherwise(acc["parts"])
        return F.struct(F.greatest(acc["at"], s["end"]).alias("at"), parts.alias("parts"))

    end = lambda acc: F.concat(F.array_join(acc["parts"], ""), F.substring(body, acc["at"] + 1, F.length(body)))
    masked = F.aggregate("_spans", F.struct(F.lit(0).alias("at"), F.array().cast("array<string>").alias("parts")), put, end)
    spanned = rows.withColumn("_spans", pieces)
    return spanned.select(*(F.when(F.size("_spans") > 0, masked).otherwise(F.col(f"of_{c}")).alias(c) if c == text else F.col(f"of_{c}").alias(c) for c in docs.columns))
