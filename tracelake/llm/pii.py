"""Personal data: pattern spans and information-theoretic sanitisation (DataFrame functions only).

Pattern spans (mail addresses, ip addresses, card and phone numbers) are the
protected entities. A *term* is a lowered run of at least ``TERM_LENGTH`` letters.
From all documents of the corpus the operator counts how often an entity, a
term, and both occur, and takes the pointwise mutual information of the two as
what the term tells about the entity. It can be at most the information content
of the entity. A term that gives away at least ``REMOVE_AT`` of it is removed, one
that gives away at least ``GENERALISE_AT`` is generalised to a neutral word, in the
texts that hold the entity. Every entity takes part, also one that a single text
holds. Whether a pair is more than chance is judged on distinct texts: the
probability that an unrelated term would be in as many of the entity's texts must
be at most ``ALPHA``. A term and an entity that both stand in one text only pass in
a corpus of at least 1 / ``ALPHA`` texts.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tracelake.llm import common

ALPHA = 0.01
REMOVE_AT = 0.95
GENERALISE_AT = 0.9
TERM_LENGTH = 3
#: Elements of an array that are folded together.
CHUNK = 64
#: Code points of a block of a text that is cut at many places.
TEXT_BLOCK = 256
#: Above this many candidate terms (8 bytes each) they are joined by a shuffle, not broadcast.
BROADCAST_TERMS = 500_000
#: Splits marked texts; never part of a pattern.
_MARK, _SPARE = "\u0001", "\u0002"
#: A letter of no living word, written over mail addresses where terms are looked for.
_FILL = "\ua66e"

KINDS = ("email", "ip", "card", "phone")
# The contract's patterns. A match may begin where the last one ended or where no
# sign of the leading run precedes; a later begin inside a run could only match
# if the run's begin did. Runs are possessive, as what follows is not part of them.
_PATTERNS = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?:\G|(?<![0-9]))[0-9]++(?:\.[0-9]++){3}",
    "card": r"[0-9](?:[0-9]|[\x20-][0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
#: A cheap test that any text with a valid match passes.
_HINTS = {
    "email": r"@[A-Za-z0-9-]+\.",
    "ip": r"[0-9]\.[0-9]+\.[0-9]+\.[0-9]",
    "card": r"[0-9](?:[\x20-]?[0-9]){12}",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
_OCTET = r"0*(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[0-9]?[0-9])"
_SPAN = "array<struct<kind:string,start:int,end:int,value:string>>"


def _digits(value: Column) -> Column:
    return F.regexp_replace(value, "[^0-9]", "")


def _luhn(value: Column) -> Column:
    """Whether the digits, doubled at every second place from the right, sum to a multiple of ten."""
    digits = F.filter(F.split(F.reverse(_digits(value)), ""), lambda d: d != "")
    each = F.transform(digits, lambda d, i: F.when(i % 2 == 0, d.cast("int")).otherwise((d.cast("int") * 2) % 10 + F.floor(d.cast("int") / 5).cast("int")))
    return F.aggregate(each, F.lit(0), lambda a, x: a + x) % 10 == 0


def _valid(kind: str, value: Column) -> Column:
    if kind == "email":
        return F.lit(True)
    if kind == "ip":
        return value.rlike(rf"^{_OCTET}(?:\.{_OCTET}){{3}}$")
    size = F.length(_digits(value))
    return size.between(9, 15) if kind == "phone" else size.between(13, 19) & _luhn(value)


def _let(value: Column, use) -> Column:
    """``use`` of a value that is computed once, however often ``use`` names it."""
    return F.get(F.transform(F.array(value), use), F.lit(0))


def _running(values: Column, fold, depth: int = 2) -> Column:
    """Running folds, from 0, of an array of int: like a window over the array.

    An array that grows by one is copied each time, so it only grows within chunks;
    the totals of the chunks are folded the same way.
    """

    def within(chunk, base):
        step = lambda a, x: F.array_append(a, fold(F.element_at(a, -1), x))
        return F.aggregate(chunk, F.array(base), step, lambda a: F.slice(a, F.lit(2), F.size(a) - 1))

    zero = F.lit(0)
    if not depth:
        return within(values, zero)

    def of_chunks(chunks):
        totals = F.transform(chunks, lambda c: F.aggregate(c, zero, fold))
        bases = lambda sums: F.slice(F.concat(F.array(zero), sums), F.lit(1), F.size(chunks))
        return F.flatten(F.zip_with(chunks, _let(_running(totals, fold, depth - 1), bases), within))

    cut = lambda v: F.transform(F.sequence(zero, ((F.size(v) - 1) / CHUNK).cast("int")), lambda c: F.slice(v, c * CHUNK + 1, F.lit(CHUNK)))
    return _let(_let(values, cut), of_chunks)


def _marked(text: Column, pattern: str) -> Column:
    """The text cut around the matches of a pattern: every second part is a match."""
    return F.split(F.regexp_replace(F.translate(text, _MARK, _SPARE), pattern, f"{_MARK}$0{_MARK}"), _MARK)


def _spans(text: Column, pattern: str, kind: str, keep) -> Column:
    """All matches of a pattern with code-point offsets."""

    def of(parts):
        ends = _running(F.transform(parts, lambda p: F.length(p)), lambda a, x: a + x)
        span = lambda p, e: F.struct(F.lit(kind).alias("kind"), (e - F.length(p)).alias("start"), e.alias("end"), p.alias("value"))
        return F.filter(F.zip_with(parts, ends, span), lambda s, i: (i % 2 == 1) & keep(s["value"]))

    return _let(_marked(text, pattern), of).cast(_SPAN)


def pattern_spans(text: Column) -> Column:
    """Valid pattern spans of a text (null: empty), by kind as listed, then start."""
    text = F.coalesce(text, F.lit(""))
    none = F.array().cast(_SPAN)
    found = [
        F.when(text.rlike(_HINTS[k]), _spans(text, _PATTERNS[k], k, lambda v, k=k: _valid(k, v))).otherwise(none) for k in KINDS
    ]
    return F.concat(*found)


def _terms(text: Column) -> Column:
    runs = F.filter(F.split(text, r"[^\p{L}]+"), lambda w: F.length(w) >= TERM_LENGTH)
    return F.array_distinct(F.transform(runs, lambda w: F.lower(w)))


def _more_than_chance() -> Column:
    """Chernoff's bound on the chance that an unrelated term is in so many of an entity's texts is at most ``ALPHA``."""
    n, k = F.col("entity_texts"), F.col("both_texts")
    # Copies within the entity's texts are taken off; other copies count, which only makes the bound stricter.
    rate = F.least((F.col("of_term") - F.col("of_both") + k) / F.col("all_texts"), F.lit(1.0))
    part = k / n
    others = F.when(k < n, (n - k) * (F.log(1 - part) - F.log(1 - rate))).otherwise(0.0)
    return (part > rate) & (k * (F.log(part) - F.log(rate)) + others >= -math.log(ALPHA))


def disclosing(holders: DataFrame, docs: DataFrame) -> DataFrame:
    """Terms that give an entity away, in the texts that hold it: text_hash, term, share (of the entity's information).

    ``holders`` has text_hash, text and entities of the texts with pattern spans;
    ``docs`` is the whole corpus. Counts are of documents; the evidence for a pair
    is judged on distinct texts, as copies of a text are no further evidence.
    Entities that the same texts hold have the same counts with every term, so they
    are one *class*: a list of many addresses costs as much as one of them. A term that
    already the holders have too often to give a class away is left
    out before pairs are made; the others are counted over the corpus.
    """
    texts = holders.select("text_hash", "entities", _terms(F.col("text")).alias("terms")).groupBy("text_hash")
    texts = common.written(texts.agg(F.count(F.lit(1)).alias("rows"), F.first("entities").alias("entities"), F.first("terms").alias("terms")), "pii-texts")
    held = texts.select("text_hash", "rows", F.explode("entities").alias("entity"))
    every = held.groupBy("entity").agg(
        F.sum("rows").alias("of_entity"), F.count(F.lit(1)).alias("entity_texts"),
        # Told by two hashes of the set of texts; the exclusive or of hashes is that of a set.
        F.struct(F.bit_xor(F.xxhash64("text_hash")).alias("x"), F.bit_xor(F.xxhash64(F.lit(1), "text_hash")).alias("y")).alias("class"),
    )
    held = common.written(held.join(every, "entity").drop("entity").distinct(), "pii-entities")
    total = docs.agg(F.count(F.lit(1)).alias("total"), F.count_distinct(F.xxhash64("text")).alias("all_texts"))
    total = F.broadcast(common.written(total, "pii-total"))  # one row
    seen = texts.select("text_hash", "rows", F.explode("terms").alias("term"))
    least = seen.groupBy("term").agg(F.sum("rows").alias("least"))
    seen = seen.drop("rows").join(least, "term")
    # share >= s means of_term <= of_both * (total / of_entity) ** (1 - s), and of_both is at most of_entity.
    most = F.pow(F.col("total").cast("double"), 1 - GENERALISE_AT) * F.pow(F.col("of_entity").cast("double"), GENERALISE_AT)
    both = held.join(seen, "text_hash").crossJoin(total).where(F.col("least") <= most * (1 + 1e-9))
    both = both.groupBy("class", "of_entity", "entity_texts", "term").agg(F.sum("rows").alias("of_both"), F.count(F.lit(1)).alias("both_texts"))
    both = common.written(both, "pii-pairs")
    wanted = common.written(both.select(F.xxhash64("term").alias("wanted")).distinct(), "pii-terms")
    # A row names a term once, so counts need no look at which rows they come from.
    hashed = docs.select(F.explode(F.transform(_terms(F.col("text")), lambda t: F.xxhash64(t))).alias("t"))
    if wanted.count() <= BROADCAST_TERMS:
        hashed = hashed.join(F.broadcast(wanted), F.col("t") == F.col("wanted"), "left_semi")
    counts = hashed.groupBy("t").agg(F.count(F.lit(1)).alias("of_term"))
    known = both.join(counts, F.xxhash64("term") == F.col("t")).crossJoin(total)
    content = F.log(F.col("total") / F.col("of_entity"))
    told = F.log(F.col("of_both") * F.col("total") / (F.col("of_entity") * F.col("of_term")))
    share = F.when(content > 0, told / content)
    known = known.where(_more_than_chance()).select("class", "term", share.alias("share")).where(F.col("share") >= GENERALISE_AT)
    return held.join(common.written(known, "pii-disclosing"), "class").groupBy("text_hash", "term").agg(F.max("share").alias("share"))


def _words(text: Column) -> Column:
    """Spans of the runs of letters that could be terms; one that a mail address has letters of is none."""
    covered = F.transform(_marked(text, _PATTERNS["email"]), lambda p, i: F.when(i % 2 == 1, F.repeat(F.lit(_FILL), F.length(p))).otherwise(p))
    return _spans(F.array_join(covered, ""), rf"\p{{L}}{{{TERM_LENGTH},}}+", "", lambda v: F.lit(True))


def _term_spans(holders: DataFrame, terms: DataFrame) -> DataFrame:
    """Per text that holds any of its ``terms``: text_hash, removed and generalised (spans by start).

    The other patterns have no letters, so only mail addresses can overlap with a term.
    """
    texts = holders.join(terms.select(F.col("text_hash").alias("s_hash")).distinct(), F.col("text_hash") == F.col("s_hash"), "left_semi")
    texts = texts.groupBy("text_hash").agg(F.first("text").alias("text"))
    words = texts.select(F.col("text_hash").alias("w_hash"), F.explode(_words(F.col("text"))).alias("w"))
    told = common.written(terms.select(F.xxhash64("term").alias("told")).distinct(), "pii-told-terms")
    if told.count() <= BROADCAST_TERMS:  # common words are no term of any text and need not be moved
        words = words.join(F.broadcast(told), F.xxhash64(F.lower("w.value")) == F.col("told"), "left_semi")
    found = words.join(terms, (F.col("w_hash") == F.col("text_hash")) & (F.lower("w.value") == F.col("term")))

    def of(kind, which):
        span = F.struct(F.col("w.start").alias("start"), F.col("w.end").alias("end"), F.col("w.value").alias("value"))
        mine = F.sort_array(F.collect_list(F.when(which, span)))
        return F.transform(mine, lambda s: F.struct(F.lit(kind).alias("kind"), s["start"].alias("start"), s["end"].alias("end"), s["value"].alias("value"))).cast(_SPAN)

    return found.groupBy("text_hash").agg(
        of("removed", F.col("share") >= REMOVE_AT).alias("removed"), of("generalised", F.col("share") < REMOVE_AT).alias("generalised")
    )


def _sanitised(text: Column, spans: Column) -> Column:
    """The text with every span replaced; of spans that overlap, the first to begin counts and is made longer."""
    labels = F.create_map(*[F.lit(x) for k in KINDS for x in (k, f"[{k.upper()}]")], F.lit("removed"), F.lit(""), F.lit("generalised"), F.lit("[TERM]"))
    order = F.sort_array(F.transform(spans, lambda s: F.struct(s["start"].alias("start"), (-s["end"]).alias("neg"), s["kind"].alias("kind"))))
    size = F.lit(TEXT_BLOCK)

    def between(blocks, begin, end):
        """A part of the text. Blocks, as finding a place in a text means to walk to it."""
        first, last = (begin / size).cast("int"), ((end - 1) / size).cast("int")

        def part(block, i):
            at = (first + i) * size
            low = F.greatest(begin - at, F.lit(0))
            return F.substring(block, low + 1, F.least(end - at, size) - low)

        return F.when(end > begin, F.array_join(F.transform(F.slice(blocks, first + 1, last - first + 1), part), "")).otherwise("")

    def put(blocks, ordered, reach):
        before = F.slice(F.concat(F.array(F.lit(0)), reach), F.lit(1), F.size(ordered))
        cuts = F.zip_with(ordered, before, lambda s, b: F.struct(s["start"].alias("start"), b.alias("begin"), s["kind"].alias("kind")))
        cuts = F.filter(cuts, lambda c: c["start"] >= c["begin"])
        parts = F.transform(cuts, lambda c: F.concat(between(blocks, c["begin"], c["start"]), labels[c["kind"]]))
        return F.array_join(F.concat(parts, F.array(between(blocks, F.element_at(reach, -1), F.length(text)))), "")

    ends = lambda o: _running(F.transform(o, lambda s: -s["neg"]), lambda a, x: F.greatest(a, x))
    all_blocks = F.regexp_extract_all(text, F.lit(f"(?s).{{1,{TEXT_BLOCK}}}"), F.lit(0))
    made = _let(all_blocks, lambda blocks: _let(order, lambda o: _let(ends(o), lambda reach: put(blocks, o, reach))))
    return F.when(F.size(spans) > 0, made).otherwise(text)


def annotate(docs: DataFrame, spans: str = "spans", clean: str = "clean_text") -> DataFrame:
    """``docs`` with its spans (kind, start, end, value) and its sanitised text.

    Needs text; other columns stay. Spans come by kind - email, ip, card, phone,
    removed, generalised - then start; offsets count code points, the end is not
    part of the span. A null text has no spans and stays null. Rows that repeat
    each other are annotated alike; an empty table gives an empty result. Texts
    without pattern spans take no part in any shuffle.
    """
    names = docs.columns
    base, text_hash, removed, generalised, known = common.fresh(docs, "base_spans", "text_hash", "removed", "generalised", "known_hash")
    scanned = docs.withColumn(base, pattern_spans(F.col("text")))
    plain = docs.where(F.size(pattern_spans(F.col("text"))) == 0)
    plain = plain.select(*names, F.array().cast(_SPAN).alias(spans), F.col("text").alias(clean))
    hit = common.written(scanned.where(F.size(base) > 0).withColumn(text_hash, F.xxhash64("text")), "pii-hit")
    entity = F.array_distinct(F.transform(base, lambda s: F.xxhash64(s["kind"], F.lower(s["value"]))))
    holders = hit.select(F.col(text_hash).alias("text_hash"), "text", entity.alias("entities"))
    terms = common.written(disclosing(holders, docs.select("text").where("text is not null")), "pii-told")
    found = common.written(_term_spans(holders.select("text_hash", "text"), terms), "pii-spans").toDF(known, removed, generalised)
    hit = hit.join(found, F.col(text_hash) == F.col(known), "left")
    none = F.array().cast(_SPAN)
    hit = hit.withColumn(base, F.concat(F.col(base), F.coalesce(F.col(removed), none), F.coalesce(F.col(generalised), none)))
    hit = hit.select(*names, F.col(base).alias(spans), _sanitised(F.col("text"), F.col(base)).alias(clean))
    return plain.unionByName(hit)


def _joined(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def report(docs: DataFrame) -> DataFrame:
    """Per row: doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans (as text)."""
    found = annotate(docs.select("doc_id", "text"), "found", "clean").select("doc_id", "found")
    base = F.filter("found", lambda s: s["kind"].isin(*KINDS))
    counts = [F.size(F.filter(F.col("found")["kind"], lambda x: x == F.lit(kind))).cast("bigint").alias(f"n_{kind}") for kind in KINDS]
    return found.select("doc_id", *counts, F.sha2(_joined(base), 256).alias("base_sha256"), _joined(F.col("found")).alias("spans"))


def sanitised(docs: DataFrame) -> DataFrame:
    """``docs`` with sanitised texts, and n_chars to match if there is such a column."""
    spans, clean = common.fresh(docs, "spans", "clean_text")
    out = annotate(docs, spans, clean).withColumn("text", F.col(clean))
    if "n_chars" in docs.columns:
        changed = F.size(spans) > 0
        out = out.withColumn("n_chars", F.when(changed, F.length("text").cast(docs.schema["n_chars"].dataType)).otherwise(F.col("n_chars")))
    return out.select(*docs.columns)
