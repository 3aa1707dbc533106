"""The surrounding operators: joins, aggregations, windows, set operations and feature extraction, each as a declared plan."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

BROADCAST_ROWS, BROADCAST_BYTES = 1_000_000, 64 << 20


def small(df: DataFrame, most: int = BROADCAST_ROWS, most_bytes: int = BROADCAST_BYTES) -> DataFrame:
    """Mark for broadcast where both the number of rows and the bytes of their values are within bounds; beyond them, leave the choice to Spark.

    At most one row more than the bound is read; strings and binaries count by length, other values as 16 bytes."""
    wide = [c for c, t in df.dtypes if t in ("string", "binary")]
    nested = [c for c, t in df.dtypes if "<" in t]
    size = sum((F.coalesce(F.octet_length(c), F.lit(0)) for c in wide), F.lit(16 * len(df.columns)))
    size = sum((F.coalesce(F.octet_length(F.to_json(F.struct(c))), F.lit(0)) for c in nested), size)
    r = df.limit(most + 1).agg(F.count(F.lit(1)).alias("n"), F.coalesce(F.sum(size), F.lit(0)).alias("b")).first()
    return F.broadcast(df) if r.n <= most and r.b <= most_bytes else df


def join_dim(df: DataFrame, dim: DataFrame, on) -> DataFrame:
    return df.join(small(dim), on)


def join_big(left: DataFrame, right: DataFrame, on, strategy: str = "merge") -> DataFrame:
    return left.join(right.hint({"merge": "merge", "shuffle_hash": "shuffle_hash"}[strategy]), on)


def join_theta(df: DataFrame, few: DataFrame, predicate: Column, most: int = 100_000) -> DataFrame:
    """Only with a side of checked size."""
    if few.limit(most + 1).count() > most:
        raise ValueError("the smaller side of a theta join is beyond its bound")
    return df.join(F.broadcast(few), predicate)


def join_semi(df: DataFrame, other: DataFrame, on) -> DataFrame:
    return df.join(other, on, "left_semi")


def join_anti(df: DataFrame, other: DataFrame, on) -> DataFrame:
    return df.join(other, on, "left_anti")


def join_outer(left: DataFrame, right: DataFrame, on, how: str = "full") -> DataFrame:
    return left.join(right, on, how)


def join_range(df: DataFrame, intervals: DataFrame, value: str, low: str, high: str, width: float) -> DataFrame:
    """Rows with low <= value < high: both sides are cut into bins of one width, joined on the bin and checked again."""
    bins = F.sequence(F.floor(F.col(low) / width), F.floor(F.col(high) / width))
    return df.withColumn("_bin", F.floor(F.col(value) / width)).join(intervals.withColumn("_bin", F.explode(bins)), "_bin").where((F.col(value) >= F.col(low)) & (F.col(value) < F.col(high))).drop("_bin")


def join_asof(left: DataFrame, right: DataFrame, by: str, ts: str, carry: list[str]) -> DataFrame:
    """Each left row with the values of the latest right row of its key at or before its time: one union and one window."""
    from_right = right.select(by, ts, F.lit(0).alias("_side"), F.struct(*carry).alias("_seen"))
    from_left = left.withColumn("_row", F.struct(*left.columns)).select(by, ts, F.lit(1).alias("_side"), F.lit(None).cast(from_right.schema["_seen"].dataType).alias("_seen"), "_row")
    both = from_left.unionByName(from_right, allowMissingColumns=True)
    w = Window.partitionBy(by).orderBy(ts, "_side").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return both.withColumn("_seen", F.last("_seen", True).over(w)).where("_side = 1").select("_row.*", *(F.col(f"_seen.{c}").alias(c) for c in carry))


def join_subset(small_sets: DataFrame, big_sets: DataFrame) -> DataFrame:
    """Pairs of patterns where one holds the other: the smaller is filed under its rarest literal."""
    uses = big_sets.select(F.explode("pattern").alias("lit")).groupBy("lit").agg(F.count(F.lit(1)).alias("n"))
    filed = small_sets.select(F.col("pattern").alias("small"), F.explode("pattern").alias("lit")).join(uses, "lit", "left").groupBy("small").agg(F.min_by("lit", F.struct(F.coalesce("n", F.lit(0)), "lit")).alias("lit"))
    return big_sets.select(F.col("pattern").alias("big"), F.explode("pattern").alias("lit")).join(filed, "lit").where((F.size("small") < F.size("big")) & (F.size(F.array_except("small", "big")) == 0)).select("small", "big")


def class_counts(df: DataFrame, by, label: Column) -> DataFrame:
    return df.groupBy(*by).agg(F.sum(label).alias("n_pos"), F.sum(1 - label).alias("n_neg"))


def class_rollup(df: DataFrame, columns, label: Column) -> DataFrame:
    return df.rollup(*columns).agg(F.sum(label).alias("n_pos"), F.sum(1 - label).alias("n_neg"))


def class_cube(df: DataFrame, columns, label: Column) -> DataFrame:
    return df.cube(*columns).agg(F.sum(label).alias("n_pos"), F.sum(1 - label).alias("n_neg"))


def class_grouping_sets(df: DataFrame, sets, columns, label: Column) -> DataFrame:
    return df.groupingSets(sets, *columns).agg(F.sum(label).alias("n_pos"), F.sum(1 - label).alias("n_neg"))


def distinct_profile(df: DataFrame, columns, exact: bool = True) -> DataFrame:
    count = F.count_distinct if exact else F.approx_count_distinct
    return df.agg(*(count(c).alias(f"n_{c}") for c in columns))


def value_histogram(df: DataFrame, feature: str, label: Column) -> DataFrame:
    return df.groupBy(F.col(feature).alias("value")).agg(F.sum(label).alias("n_pos"), F.sum(1 - label).alias("n_neg"))


def ordered_parts(df: DataFrame, column: str, parts: int = 256) -> Column:
    """The number of a row's part: ranges of a numeric column, in its order and about equally full, so that a window over the whole order runs part by part.

    Equal values share a part; nulls come first, NaN last. Reads at most so many cut points to the driver."""
    cuts = df.agg(F.percentile_approx(column, [k / parts for k in range(1, parts)], 10_000)).first()[0]
    return F.size(F.filter(F.lit(sorted(set(cuts or [0]))), lambda c: c < F.col(column)))


def running_sums(df: DataFrame, order: str, sums: dict[str, str]) -> DataFrame:
    """The rows with running sums (new name: column) up to their own value of the order; values are distinct, as in a histogram."""
    rows = df.withColumn("_part", ordered_parts(df, order))
    totals = rows.groupBy("_part").agg(*(F.sum(c).alias(f"_t{k}") for k, c in enumerate(sums.values())))
    earlier = Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)  # one row per part
    before = totals.select("_part", *(F.coalesce(F.sum(f"_t{k}").over(earlier), F.lit(0)).alias(f"_b{k}") for k in range(len(sums))))
    within = Window.partitionBy("_part").orderBy(order).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    joined = rows.join(F.broadcast(before), "_part")
    return joined.select(*(f"`{c}`" for c in df.columns), *((F.sum(c).over(within) + F.col(f"_b{k}")).alias(n) for k, (n, c) in enumerate(sums.items())))


def cumulative_class(hist: DataFrame) -> DataFrame:
    """Running class counts over a feature's distinct values, of any number."""
    return running_sums(hist, "value", {"cum_pos": "n_pos", "cum_neg": "n_neg"}).select("value", "cum_pos", "cum_neg")


def boundary_points(hist: DataFrame) -> DataFrame:
    """Values after which the class mix changes, so a cut may lie there. The last value of a part is followed by the first of the next part."""
    point = F.struct("value", "n_pos", "n_neg")
    rows = hist.select("value", "n_pos", "n_neg", ordered_parts(hist, "value").alias("_part"))
    firsts = rows.groupBy("_part").agg(F.min(point).alias("_first"))
    after = firsts.select("_part", F.lead("_first").over(Window.orderBy("_part")).alias("_after"))  # one row per part
    follows = F.coalesce(F.lead(point).over(Window.partitionBy("_part").orderBy("value")), F.col("_after"))
    pairs = rows.join(F.broadcast(after), "_part").select("value", "n_pos", "n_neg", follows.alias("f"))
    p, q = F.col("f.n_pos"), F.col("f.n_neg")
    changes = (F.col("n_pos") * q != F.col("n_neg") * p) | ((F.col("n_pos") > 0) & (F.col("n_neg") > 0))
    return pairs.where(F.col("f.value").isNotNull() & changes).select("value", F.col("f.value").alias("next"))


def rolling_events(df: DataFrame, key: str, ts: str, seconds: int) -> DataFrame:
    w = Window.partitionBy(key).orderBy(F.unix_micros(F.col(ts).cast("timestamp"))).rangeBetween(-seconds * 1_000_000, 0)
    return df.withColumn("n_recent", F.count(F.lit(1)).over(w))


def topk_per_group(df: DataFrame, group: str, by, k: int) -> DataFrame:
    return df.withColumn("_rank", F.row_number().over(Window.partitionBy(group).orderBy(*by))).where(F.col("_rank") <= k).drop("_rank")


def rank_patterns(df: DataFrame, by, k: int) -> DataFrame:
    return df.orderBy(*by).limit(k)


def set_union(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.unionByName(b).distinct()


def set_intersect(a: DataFrame, b: DataFrame, all_: bool = False) -> DataFrame:
    return a.intersectAll(b) if all_ else a.intersect(b)


def set_except(a: DataFrame, b: DataFrame, all_: bool = False) -> DataFrame:
    return a.exceptAll(b) if all_ else a.subtract(b)


def pivot_report(df: DataFrame, index: str, column: str, value: Column, options: list) -> DataFrame:
    return df.groupBy(index).pivot(column, options).agg(value)


def unpivot_report(df: DataFrame, ids: list[str], values: list[str]) -> DataFrame:
    return df.unpivot(ids, values, "name", "value")


def text_flags(df: DataFrame, column: str) -> DataFrame:
    c = F.col(column)
    return df.select("*", c.rlike("[A-Z]{4,}").alias("caps"), c.rlike("[0-9]{3}").alias("digits"), c.contains("@").alias("at"), c.rlike("###|[$]{3}|%%%").alias("junk"))


def url_parts(df: DataFrame, column: str) -> DataFrame:
    u = F.col(column)
    return df.select("*", F.regexp_extract(u, "^([a-z]+):", 1).alias("scheme"), F.regexp_extract(u, "://([^/?#]*)", 1).alias("host"), F.regexp_extract(u, "://[^/?#]*([^?#]*)", 1).alias("path"))


def html_tags(df: DataFrame, column: str) -> DataFrame:
    """(all columns, tag, n): how often each tag opens."""
    tags = F.regexp_extract_all(F.lower(column), F.lit("<([a-z][a-z0-9]*)"), F.lit(1))
    return df.select(*(c for c in df.columns if c != column), F.explode(tags).alias("tag"))


def json_props(df: DataFrame, column: str, key: str) -> DataFrame:
    return df.withColumn(key, F.get_json_object(column, f"$.{key}").cast("long"))


def _run_of_words(k: int):
    return lambda i: F.xxhash64(F.array_join(F.slice("w", i, F.lit(k)), " "))


def _run_of_characters(k: int):
    return lambda i: F.xxhash64(F.substring(F.col("text"), i, F.lit(k)))


def contains_passage(docs: DataFrame, passages: DataFrame, n: int = 5) -> DataFrame:
    """(doc_id, item_id) of documents whose text holds a whole passage, character for character.

    Words inside a passage are words of the text as they stand, while its first and last may be parts of longer ones. So a
    passage is keyed by a hash of up to n inner words, and a text asks with its runs of as many words; a passage without
    inner words is keyed by its first characters, and a text asks with its runs of characters. What meets is checked on
    the full strings. Texts are not carried through the joins; an empty passage is in every text that is not null."""
    words = lambda c: F.regexp_extract_all(c, F.lit(r"([\p{L}\p{N}]+)"), F.lit(1))
    told = passages.where("text is not null").select("item_id", F.col("text").alias("passage"), words("text").alias("w"))
    items = told.where("passage <> ''").withColumn("by_word", F.size("w") > 2).withColumn("k", F.when(F.size("w") > 2, F.least(F.size("w") - 2, F.lit(n))).otherwise(F.least(F.length("passage"), F.lit(8))))
    key = F.when(F.col("by_word"), F.xxhash64(F.array_join(F.expr("slice(w, 2, k)"), " "))).otherwise(F.xxhash64(F.expr("substring(passage, 1, k)")))
    keyed = items.select("item_id", "by_word", "k", key.alias("h"))
    own = docs.where("text is not null").select("doc_id", "text", words("text").alias("w"))
    met = None
    for by_word, k in sorted((r.by_word, r.k) for r in keyed.select("by_word", "k").distinct().collect()):  # at most n + 8 kinds
        size = F.size("w") if by_word else F.length("text")
        gram = _run_of_words(k) if by_word else _run_of_characters(k)
        grams = own.where(size >= k).select("doc_id", F.explode(F.array_distinct(F.transform(F.sequence(F.lit(1), size - k + 1), gram))).alias("h"))
        part = grams.join(keyed.where((F.col("by_word") == by_word) & (F.col("k") == k)).select("item_id", "h"), "h").select("doc_id", "item_id")
        met = part if met is None else met.unionByName(part)
    everywhere = docs.where("text is not null").select("doc_id", F.lit(1).alias("one")).join(told.where("passage = ''").select("item_id", F.lit(1).alias("one")), "one").select("doc_id", "item_id")
    if met is None:
        return everywhere.distinct()
    checked = met.distinct().join(told.select("item_id", "passage"), "item_id").join(docs.select("doc_id", "text"), "doc_id").where(F.contains("text", F.col("passage")))
    return checked.select("doc_id", "item_id").unionByName(everywhere).distinct()


def sketch_profile(df: DataFrame, columns) -> DataFrame:
    """(n_<column>) by HyperLogLog sketches that can be stored and united: about 2 % off, in constant memory."""
    return df.agg(*(F.hll_sketch_estimate(F.hll_sketch_agg(c)).alias(f"n_{c}") for c in columns))


def sketches_by(df: DataFrame, by: str, column: str) -> DataFrame:
    """(by, sketch): one sketch a group, to be united later."""
    return df.groupBy(by).agg(F.hll_sketch_agg(column).alias("sketch"))


def united_count(sketches: DataFrame) -> DataFrame:
    """(n): distinct values over all groups, from their sketches alone."""
    return sketches.agg(F.hll_sketch_estimate(F.hll_union_agg("sketch")).alias("n"))


def quantile_sketch(df: DataFrame, column: str, shares: list[float]) -> DataFrame:
    """(share, value) from a KLL sketch of doubles."""
    drawn = df.agg(F.kll_sketch_agg_double(F.col(column).cast("double")).alias("s"))
    return drawn.select(F.explode(F.array(*(F.struct(F.lit(q).alias("share"), F.kll_sketch_get_quantile_double("s", F.lit(q)).alias("value")) for q in shares))).alias("x")).select("x.*")


def variant_props(df: DataFrame, column: str, path: str, kind: str, name: str) -> DataFrame:
    """A field of a JSON column, read as a variant; null where the text is no JSON or the field no such type."""
    return df.withColumn(name, F.try_variant_get(F.try_parse_json(column), path, kind))
