"""Personal data: patterns with checks, and information-theoretic sanitisation of the terms that reveal them.

Patterns find e-mail addresses, IP addresses, payment cards and telephone numbers. Every value is a protected entity. How
strongly a term reveals it is estimated from co-occurrence in the whole corpus: a term that stands within a few words of
the entity is weighed by the pointwise mutual information of the documents that hold it there and of the entity, and by
the share of the term's documents that do. Terms beyond both thresholds are spans too, to be generalised or removed with
the entity. A name that stands beside an address in many letters, and in few others, is such a term, whatever else the
letters repeat; so is a rare word beside a value that stands in one text only. DataFrame functions only."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .shared import clean_text, files_for, join_by_size, stored
from .spans import SPAN, let, located, masked, written

# The patterns are linear-time forms: a run is tried at its start only, and no repetition gives back what it took.
EMAIL = r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++"
IP = r"(?:(?<![0-9])|\G)[0-9]++(?:\.[0-9]++){3}"
CARD = r"[0-9](?:[ -]?[0-9])++"
PHONE = r"\+[0-9][ ().0-9-]+[0-9]"
KINDS = ("email", "ip", "card", "phone")
WORD = r"\p{L}{3,}+"


def digits(s: Column) -> Column:
    return F.regexp_replace(s, "[^0-9]", "")


def luhn(d: Column) -> Column:
    """Of a string of at most 19 digits."""
    places = F.sequence(F.lit(1), F.greatest(F.length(d), F.lit(1)))
    value = lambda i: F.substring(d, F.length(d) - i + 1, F.lit(1)).cast("int")
    double = lambda v: F.when(v > 4, 2 * v - 9).otherwise(2 * v)
    return F.aggregate(places, F.lit(0), lambda s, i: s + F.when(i % 2 == 0, double(value(i))).otherwise(value(i))) % 10 == 0


def small_part(p: Column) -> Column:
    """A run of digits is at most 255."""
    plain = F.regexp_replace(p, "^0+", "")
    return F.when(F.length(plain) <= 3, F.concat(F.lit("0"), plain).cast("int") <= 255).otherwise(False)


def base_spans(text: Column) -> dict[str, Column]:
    digit = text.rlike("[0-9]")
    count = lambda s: F.length(digits(s.hit))
    return {
        "email": located(text, EMAIL, guard=F.contains(text, F.lit("@"))),
        "ip": F.filter(located(text, IP, guard=text.rlike(r"[0-9]\.[0-9]")), lambda s: F.forall(F.split(s.hit, r"\."), small_part)),
        "card": F.filter(located(text, CARD, guard=digit & text.rlike(r"[0-9](?:[ -]?[0-9]){12}")), lambda s: F.when(count(s).between(13, 19), luhn(digits(s.hit))).otherwise(False)),
        "phone": F.filter(located(text, PHONE, guard=F.contains(text, F.lit("+"))), lambda s: count(s).between(9, 15)),
    }


def places(kind: str) -> Column:
    return F.transform(kind, lambda s: F.struct(s.start.alias("start"), s.stop.alias("stop")))


def named_places(kind: str) -> Column:
    return F.transform(kind, lambda s: F.struct(s.start.alias("start"), s.stop.alias("stop"), F.concat(F.lit(kind + ":"), F.lower(s.hit)).alias("who")))


MARK = "\x01"  # stands for a stretch of entities between the words of a text


def stretches(spans: Column) -> Column:
    """Overlapping spans (start, stop, who) as one stretch each, in order: array of (start, stop, who array)."""
    none = F.array().cast("array<struct<start:int,stop:int,who:array<string>>>")

    def fold(acc: Column, s: Column) -> Column:
        last = F.element_at(acc, -1)
        alone = F.concat(acc, F.array(F.struct(s.start.alias("start"), s.stop.alias("stop"), F.array(s.who).alias("who"))))
        both = F.struct(last.start.alias("start"), F.greatest(last.stop, s.stop).alias("stop"), F.array_union(last.who, F.array(s.who)).alias("who"))
        return F.when(F.size(acc) == 0, alone).when(s.start < last.stop, F.concat(F.slice(acc, 1, F.size(acc) - 1), F.array(both))).otherwise(alone)

    return F.aggregate(F.array_sort(spans), none, fold)


def neighbours(text: Column, spans: Column, reach: int) -> Column:
    """Distinct (entity, term) pairs of a text: the words within `reach` words of each entity, on both sides, where another entity counts as a word."""
    parts = stretches(spans)
    clean = F.replace(text, F.lit(MARK), F.lit(" "))
    marked = masked(clean, F.transform(spans, lambda s: F.struct(s.start.alias("start"), s.stop.alias("stop"))), f" {MARK} ")
    words = F.regexp_extract_all(F.lower(marked), F.lit(WORD + "|" + MARK), F.lit(0))

    def pairs(x: Column) -> Column:
        at = F.filter(F.transform(x.words, lambda w, i: F.when(w == MARK, i + 1)), lambda i: i.isNotNull())

        def near(i: Column) -> Column:
            before = F.slice(x.words, F.greatest(i - reach, F.lit(1)), F.least(i - 1, F.lit(reach)))
            return F.filter(F.concat(before, F.slice(x.words, i + 1, F.lit(reach))), lambda w: w != MARK)

        met = F.transform(F.arrays_zip(x.parts.who.alias("who"), at.alias("at")), lambda z: F.flatten(F.transform(z["who"], lambda e: F.transform(near(z["at"]), lambda t: F.struct(e.alias("entity"), t.alias("term"))))))
        return F.array_distinct(F.flatten(met))

    return let(F.struct(parts.alias("parts"), words.alias("words")), pairs)


def found_in(docs: DataFrame, reach: int, texts: bool = False) -> DataFrame:
    """A stored table of one row a document: doc_id, the four arrays of base spans, key, and where there are spans the text, its entities and their neighbours. texts: keep all texts."""
    chosen = docs.select(F.col("doc_id").cast("long").alias("doc_id"), clean_text().alias("text"))
    based = chosen.select("doc_id", "text", *(c.alias(k) for k, c in base_spans(F.col("text")).items()))
    named = F.concat(*map(named_places, KINDS))
    holds = sum((F.size(k) for k in KINDS), F.lit(0)) > 0
    entities = F.array_distinct(F.transform(named, lambda s: s.who))
    return stored(
        based.select(
            "doc_id", *KINDS, F.xxhash64("text").alias("key"), (F.col("text") if texts else F.when(holds, F.col("text"))).alias("text"),
            F.when(holds, entities).alias("entities"), F.when(holds, neighbours(F.col("text"), named, reach)).alias("near"),
        ),
        "personal",
    )


def terms_of(found: DataFrame, docs: DataFrame, least_texts: int, bits: float, share: float) -> DataFrame:
    """(entity, term, bits, share, holding) from a table of found_in()."""
    holders = found.where(F.col("entities").isNotNull())
    held = holders.select("key", F.explode("entities").alias("entity"))
    holding = held.groupBy("entity", "key").agg(F.count(F.lit(1)).alias("rows")).groupBy("entity").agg(F.sum("rows").alias("holding"), F.count(F.lit(1)).alias("texts")).where(F.col("texts") >= least_texts)
    both = holders.select(F.explode("near").alias("x")).select("x.*").groupBy("entity", "term").agg(F.count(F.lit(1)).alias("both"))  # combined before the shuffle
    total = docs.count()
    words = F.explode(F.array_distinct(F.regexp_extract_all(F.lower(clean_text()), F.lit(WORD), F.lit(0))))
    used = docs.select(words.alias("term")).groupBy("term").agg(F.count(F.lit(1)).alias("used"))
    scored = stored(both, "together").join(used, "term").join(holding.drop("texts"), "entity")
    scored = scored.withColumn("bits", F.log2(F.lit(float(total)) * F.col("both") / (F.col("used") * F.col("holding")))).withColumn("share", F.col("both") / F.col("used"))
    return scored.where((F.col("bits") >= bits) & (F.col("share") >= share)).select("entity", "term", F.round("bits", 6).alias("bits"), F.round("share", 6).alias("share"), "holding")


REACH, LEAST_TEXTS, BITS, SHARE = 10, 1, 8.0, 0.6


def revealing_terms(docs: DataFrame, reach: int = REACH, least_texts: int = LEAST_TEXTS, bits: float = BITS, share: float = SHARE) -> DataFrame:
    """(entity, term, bits, share): terms that reveal an entity which stands in at least so many different texts.

    A term is a word of three letters or more. It reveals an entity if documents that hold it within `reach` words of the
    entity are at least `share` of the term's documents, and if seeing it tells at least `bits` about the entity:
    log2(documents * both / (used * holding)). All documents count, copies too, so what copies repeat is judged as in one
    text. An empty table has no terms."""
    return terms_of(found_in(docs, reach), docs, least_texts, bits, share).drop("holding")


def personal_spans(docs: DataFrame, reach: int = REACH, least_texts: int = LEAST_TEXTS, bits: float = BITS, share: float = SHARE, texts: bool = True) -> DataFrame:
    """doc_id, text, the four arrays of base spans and `term`, the spans of terms that reveal an entity of that document, wherever they stand in it.

    Null text is empty and has no span; null ids and repeated rows are treated row by row; an empty table gives none;
    other columns are ignored. texts=False gives a null text where a document has no base span. Documents without
    entities take part in no join, and common entities and texts are spread."""
    found = found_in(docs, reach, texts)
    no_term = F.array().cast(SPAN).alias("term")
    free = found.where(F.col("entities").isNull()).select("doc_id", "text", *KINDS, no_term)
    terms = terms_of(found, docs, least_texts, bits, share).groupBy("entity").agg(F.collect_set("term").alias("terms"), F.first("holding").alias("holding"))  # words beside one entity only
    holders = found.where(F.col("entities").isNotNull()).select("doc_id", "text", *KINDS, "key", "entities")
    held = stored(holders.groupBy("key").agg(F.first("entities").alias("entities"), F.count(F.lit(1)).alias("rows")), "entities")
    n_rows = held.agg(F.coalesce(F.sum(F.col("rows") * F.size("entities")), F.lit(0)).alias("n"), F.coalesce(F.sum("rows"), F.lit(0)).alias("k")).first()
    links = join_by_size(held.select("key", "rows", F.explode("entities").alias("entity")), stored(terms, "revealing", files_for(n_rows.n)), "entity", "holding", max(1, n_rows.n))
    told = links.groupBy("key").agg(F.array_distinct(F.flatten(F.collect_list("terms"))).alias("terms"))  # of one text
    told = stored(held.select("key", "rows").join(told, "key", "left"), "told")
    base = F.concat(*map(places, KINDS))
    apart = lambda s: F.array_contains("terms", F.lower(s.hit)) & F.forall(base, lambda b: (b.stop <= s.start) | (b.start >= s.stop))
    spans = F.when(F.col("terms").isNotNull(), F.filter(located(F.col("text"), WORD), apart)).otherwise(F.array().cast(SPAN))
    marked = join_by_size(holders, told, "key", "rows", max(1, n_rows.k))
    return free.unionByName(marked.select("doc_id", "text", *KINDS, spans.alias("term")))


GENERAL = "<personal>"


def cleared() -> Column:
    """The text with base spans and revealing terms generalised."""
    return masked(F.col("text"), F.concat(*map(places, (*KINDS, "term"))), GENERAL)


def personal_digest(docs: DataFrame, **options) -> DataFrame:
    """(doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans, n_term, sanitised_sha256) for each row; the cases are those of personal_spans().

    sanitised_sha256 is the digest of the sanitised text where it differs from the text, else null."""
    rows = personal_spans(docs, texts=False, **options)
    base = F.concat(*(written(k, F.col(k)) for k in KINDS))
    return rows.select(
        "doc_id",
        *(F.size(k).cast("long").alias(f"n_{k}") for k in KINDS),
        F.sha2(F.concat_ws(",", base).cast("binary"), 256).alias("base_sha256"),
        F.concat_ws(",", F.concat(base, written("term", F.col("term")))).alias("spans"),
        F.size("term").cast("long").alias("n_term"),
        F.when(F.size(base) > 0, F.sha2(cleared().cast("binary"), 256)).alias("sanitised_sha256"),
    )


def sanitised(docs: DataFrame, **options) -> DataFrame:
    """(doc_id, text, n_spans): base spans and revealing terms generalised to <personal>; the cases are those of personal_spans()."""
    rows = personal_spans(docs, **options)
    return rows.select("doc_id", cleared().alias("text"), sum((F.size(k) for k in (*KINDS, "term")), F.lit(0)).cast("long").alias("n_spans"))
