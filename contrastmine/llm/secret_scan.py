"""Secrets: credential patterns, and character Markov models of random strings and of ordinary identifiers.

Two bigram models over single letters are trained from labelled samples: random strings (drawn by a hash, and the values
the patterns find in a bounded sample of documents) and identifiers (words of that sample, joined words, numbers and runs
of one character). Every token of 8 characters outside the patterns' spans is scored, whatever its characters: it is a
secret if the sum of its log-likelihood ratios is beyond a threshold that grows with its length. DataFrame functions only:
the models are small literal arrays in the plan."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .shared import clean_text, drawn_share, spare
from .spans import let, located, masked

ASSIGN = r"""(?i:(password|passwd|secret|token|api_?key))["']? *[:=] *["']?([A-Za-z0-9+/_.=-]++)"""
ASSIGN_GUARD = r"(?i)password|passwd|secret|token|api_?key"
ACCESS = r"AKIA[A-Z0-9]++"
HEX = r"[0-9a-f]++"
HEX_GUARD = r"[0-9a-f]{24}"
TOKEN = r"[A-Za-z0-9+/_=-]{8,}+"
KINDS = ("assign", "access", "hex")
ALPHABET = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/_=-"
LEAST = 12.0
SAMPLE_DOCS = 2000
SAMPLE_STRINGS = 4000


def base_spans(text: Column) -> dict[str, Column]:
    return {
        "assign": F.filter(located(text, ASSIGN, 2, guard=text.rlike(ASSIGN_GUARD)), lambda s: F.length(s.part) >= 6),
        "access": F.filter(located(text, ACCESS, guard=F.contains(text, F.lit("AKIA"))), lambda s: F.length(s.hit) >= 20),
        "hex": F.filter(located(text, HEX, guard=text.rlike(HEX_GUARD)), lambda s: F.length(s.hit) >= 24),
    }


def labelled_samples(docs: DataFrame, strings: int = SAMPLE_STRINGS, sample_docs: int = SAMPLE_DOCS) -> DataFrame:
    """(token, random): hash-drawn strings in mixed alphabets against words and joined words of documents.

    The sample is bounded: so many strings, and the words and pattern values of about so many documents, drawn by a hash of
    the text at the share that their number asks for; no rows are gathered for it."""
    spark = docs.sparkSession
    drawn = spark.range(strings).select(F.explode(F.array(F.base64(F.unhex(F.substring(F.sha2(F.col("id").cast("string"), 256), 1, 48))), F.substring(F.translate(F.base64(F.unhex(F.sha2(F.concat(F.lit("s"), F.col("id").cast("string")), 256))), "+/=", "xyz"), 1, 32))).alias("token"), F.lit(1).alias("random"))
    share = min(1.0, sample_docs / max(1, docs.count()))
    chosen = docs.select(clean_text().alias("text")).where(drawn_share(share, "text"))
    words = chosen.select(F.filter(F.regexp_extract_all("text", F.lit(r"[A-Za-z0-9+/_=-]{3,}+"), F.lit(0)), lambda w: ~w.rlike(r"[0-9a-f]{12}|AKIA|[0-9].*[A-Za-z].*[0-9]")).alias("w"))
    plain = words.select(F.explode("w").alias("token"))
    pair = words.selectExpr("explode(transform(sequence(1, greatest(size(w) - 1, 1)), i -> concat_ws(substring('_-/=', 1 + i % 4, 1), get(w, i - 1), get(w, i)))) as token")
    held = chosen.select(F.explode(F.concat(*(F.transform(c, lambda s: s.part) for c in base_spans(F.col("text")).values()))).alias("token"), F.lit(1).alias("random"))
    numbers = spark.range(strings // 4).select(F.substring(F.conv(F.substring(F.sha2(F.concat(F.lit("n"), F.col("id").cast("string")), 256), 1, 15), 16, 10), -12, 12).alias("token"))
    runs = spark.createDataFrame([(c * 32,) for c in ALPHABET for _ in range(4)], "token string")
    fixed = spark.createDataFrame([(a + s + b,) for a in ("get", "set", "user", "max", "default", "config", "data", "file", "http", "value") for b in ("Name", "Value", "Count", "Index", "Handler", "Timeout", "Request", "Buffer", "Version", "Manager") for s in ("", "_", "Item", "Local")], "token string")
    return drawn.unionByName(held).unionByName(plain.unionByName(pair).unionByName(fixed).unionByName(numbers).unionByName(runs).select("token", F.lit(0).alias("random")))


def bigram_counts(samples: DataFrame) -> DataFrame:
    chars = samples.where(F.length("token") >= 2).select("random", F.expr("explode(transform(sequence(1, length(token) - 1), i -> substring(token, i, 2))) as gram"))
    return chars.groupBy("random", "gram").count()


def log_ratios(samples: DataFrame, smooth: float = 0.5) -> list[float]:
    """Log-likelihood ratio of each bigram of the alphabet, random over ordinary, in row-major order; its size is fixed."""
    n = len(ALPHABET)
    at = {c: i for i, c in enumerate(ALPHABET)}
    counts = [[smooth] * (n * n) for _ in range(2)]
    known = bigram_counts(samples).where(F.col("gram").rlike(r"^[A-Za-z0-9+/_=-]{2}$")).collect()  # at most twice the square of the alphabet
    for r in known:
        counts[r["random"]][at[r.gram[0]] * n + at[r.gram[1]]] += r["count"]
    sums = [[sum(c[i * n : i * n + n]) for i in range(n)] for c in counts]
    return [round(math.log(counts[1][k] / sums[1][k // n]) - math.log(counts[0][k] / sums[0][k // n]), 4) for k in range(n * n)]


def total_ratio(token: Column, ratios: list[float]) -> Column:
    """Log-likelihood ratio of a token over the alphabet: the sum over its bigrams."""
    n = len(ALPHABET)
    table = F.expr("array(" + ",".join(f"{r!r}D" for r in ratios) + ")")
    codes = F.transform(F.split(token, ""), lambda c: F.instr(F.lit(ALPHABET), c) - 1)
    steps = F.sequence(F.lit(0), F.greatest(F.length(token) - 2, F.lit(0)))
    return let(codes, lambda at: F.aggregate(steps, F.lit(0.0), lambda s, i: s + F.coalesce(F.get(table, F.get(at, i) * n + F.get(at, i + 1)), F.lit(0.0))))


def blanked(text: Column, spans: Column) -> Column:
    """The text with a space for every character that spans cover. spans: array of (start, stop)."""
    first = F.struct(F.lit(0).alias("at"), F.lit("").alias("out"))

    def fold(acc: Column, s: Column) -> Column:
        start = F.greatest(acc.at, s.start)
        out = F.concat(acc.out, F.substring(text, acc.at + 1, start - acc.at), F.repeat(F.lit(" "), F.greatest(s.stop - start, F.lit(0))))
        return F.struct(F.greatest(acc.at, s.stop).alias("at"), out.alias("out"))

    done = F.aggregate(F.array_sort(spans), first, fold, lambda acc: F.concat(acc.out, F.substring(text, acc.at + 1, F.length(text))))
    return F.when(F.size(spans) > 0, done).otherwise(text)


def bounds(column: str) -> Column:
    return F.transform(F.col(f"`{column}`"), lambda s: F.struct(s.start.alias("start"), s.stop.alias("stop")))


def with_spans(docs: DataFrame, names: list[str], ratios: list[float], least: float = LEAST, threshold: float = 0.8) -> DataFrame:
    """The table with five more columns of the given names: the text without null, the three arrays of base spans, and the spans of other random-looking tokens."""
    text, *kinds, markov = names
    with_base = docs.withColumn(text, clean_text())
    with_base = with_base.withColumns(dict(zip(kinds, base_spans(F.col(f"`{text}`")).values(), strict=True)))
    rest = blanked(F.col(f"`{text}`"), F.concat(*map(bounds, kinds)))
    random = lambda t: total_ratio(t, ratios) >= F.greatest(F.lit(least), threshold * (F.length(t) - 1))
    found = lambda t: F.filter(located(t, TOKEN, guard=F.exists(F.regexp_extract_all(t, F.lit(TOKEN), F.lit(0)), random)), lambda s: random(s.hit))
    return with_base.withColumn(markov, let(rest, found))


COLUMNS = ("_text", *(f"_{k}" for k in KINDS), "_markov")


def secret_spans(docs: DataFrame, **options) -> DataFrame:
    """doc_id, _text, the three arrays of base spans and `_markov`, the spans of other random-looking tokens.

    Tokens are runs of 8 characters of the alphabet or more outside base spans, so that what a span leaves of a longer run
    is scored too. The sum of log-likelihood ratios must reach `least`, the evidence against chance that a short token
    needs, and `threshold` for each bigram, which long tokens need. Null text is empty; null ids and repeated rows are
    treated row by row; an empty table gives none; other columns are ignored."""
    chosen = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    return with_spans(chosen, list(COLUMNS), log_ratios(labelled_samples(docs)), **options).drop("text")


def secret_digest(docs: DataFrame, **options) -> DataFrame:
    """(doc_id, n_assign, n_access, n_hex, base_sha256, spans, n_markov) for each row; the cases are those of secret_spans()."""
    rows = secret_spans(docs, **options)

    def ranked(kind: str, rank: int) -> Column:
        return F.transform(f"_{kind}", lambda s: F.struct(s.start.alias("start"), F.lit(rank).alias("rank"), s.stop.alias("stop"), F.lit(kind).alias("kind")))

    order = lambda kinds: F.array_sort(F.concat(*(ranked(k, i) for i, k in enumerate(kinds))))
    text = lambda kinds: F.concat_ws(",", F.transform(order(kinds), lambda s: F.concat_ws(":", s.kind, s.start.cast("string"), s.stop.cast("string"))))
    return rows.select(
        "doc_id",
        *(F.size(f"_{k}").cast("long").alias(f"n_{k}") for k in KINDS),
        F.sha2(text(KINDS).cast("binary"), 256).alias("base_sha256"),
        text((*KINDS, "markov")).alias("spans"),
        F.size("_markov").cast("long").alias("n_markov"),
    )


def redact(docs: DataFrame, mark: str = "[SECRET]", **options) -> DataFrame:
    """All documents with all their columns; secrets in the text are replaced by the mark, and n_chars, if there, counts the new text.

    Null texts stay null; null ids and repeated rows are treated row by row; an empty table gives none. What is computed
    on the way has names that no column has, so other columns come out as they went in."""
    names = spare(docs.columns, *COLUMNS)
    rows = with_spans(docs, names, log_ratios(labelled_samples(docs)), **options)
    spans = F.concat(*map(bounds, names[1:]))
    clear = rows.withColumn("text", F.when(F.col("text").isNotNull(), masked(F.col(names[0]), spans, mark)))
    if "n_chars" in docs.columns:
        clear = clear.withColumn("n_chars", F.when(F.size(spans) > 0, F.length("text").cast(docs.schema["n_chars"].dataType)).otherwise(F.col("n_chars")))
    return clear.select(*(F.col(f"`{c}`") for c in docs.columns))


def model_accuracy(docs: DataFrame, least: float = LEAST, threshold: float = 0.8) -> DataFrame:
    """(random, tokens, found): the labelled samples are parted by a hash of the token, the models learn from three parts of four, and every token of the fourth with 8 characters or more is judged."""
    samples = labelled_samples(docs)
    held = F.pmod(F.xxhash64("token", F.lit("held out")), F.lit(4)) == 0
    ratios = log_ratios(samples.where(~held))
    told = samples.where(held & F.col("token").rlike(f"^{TOKEN}$")).distinct()
    hit = total_ratio(F.col("token"), ratios) >= F.greatest(F.lit(least), threshold * (F.length("token") - 1))
    return told.groupBy("random").agg(F.count(F.lit(1)).alias("tokens"), F.count_if(hit).alias("found"))
