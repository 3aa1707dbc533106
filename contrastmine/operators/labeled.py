"""Labelled databases: items from declared predicates, distinct weighted rows, profiles, occurrences and supports."""

from __future__ import annotations

import re
from collections.abc import Iterable
from dataclasses import dataclass, replace

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

Pattern = tuple[int, ...]


@dataclass(frozen=True)
class Item:
    """A named predicate on a source row; a null predicate counts as absent."""

    name: str
    predicate: Column
    sql: str | None = None  # the predicate as SQL, if the item is to be saved


def item_sql(name: str, sql: str) -> Item:
    return Item(name, F.expr(sql), sql)


@dataclass(frozen=True)
class LabeledDB:
    """Distinct item sets with the number of positive and negative rows of each: `rows` has items array<int>, w_pos, w_neg.

    Literal i is item i, literal i + n its negation, if negation is on."""

    rows: DataFrame
    names: tuple[str, ...]
    negation: bool = False
    negated: tuple[int, ...] | None = None  # the items whose negation is a literal; None: all

    @property
    def n_items(self) -> int:
        return len(self.names)

    def with_negation(self, on: bool = True, only: Iterable[str] | None = None) -> LabeledDB:
        """only: names of items, or of attributes (what stands before `=`, `:`, `<` or `>`), whose negation counts."""
        wanted = None if only is None else set(only)
        some = None if wanted is None else tuple(k for k, n in enumerate(self.names) if n in wanted or re.split(r"[=:<>]", n, maxsplit=1)[0] in wanted)
        return replace(self, negation=on, negated=some)

    def literals(self) -> list[int]:
        """Ids of all literals of patterns."""
        n = self.n_items
        return [*range(n), *(i + n for i in (range(n) if self.negated is None else self.negated))] if self.negation else list(range(n))

    def literal_name(self, literal: int) -> str:
        return self.names[literal] if literal < self.n_items else "!" + self.names[literal - self.n_items]

    def text(self, pattern: Iterable[int]) -> str:
        return " & ".join(map(self.literal_name, sorted(pattern)))

    def measure(self) -> tuple[int, int, int]:
        """Positive rows, negative rows, distinct rows, in one aggregate."""
        r = self.rows.agg(F.coalesce(F.sum("w_pos"), F.lit(0)).alias("p"), F.coalesce(F.sum("w_neg"), F.lit(0)).alias("n"), F.count(F.lit(1)).alias("k")).first()
        return int(r.p), int(r.n), int(r.k)

    def sizes(self) -> tuple[int, int]:
        return self.measure()[:2]

    def persist(self) -> LabeledDB:
        return replace(self, rows=self.rows.persist())


def item_equals(attribute: str, values: Iterable, column: Column | None = None) -> list[Item]:
    c = F.col(attribute) if column is None else column
    return [Item(f"{attribute}={v}", c == F.lit(v)) for v in values]


def item_ranges(attribute: str, cuts: list[float], column: Column | None = None, sql: str | None = None) -> list[Item]:
    """Bins (-inf, c1], (c1, c2], ..., (ck, inf); sql: the column as SQL, if the items are to be saved."""
    c = F.expr(sql) if sql is not None else F.col(attribute) if column is None else column
    edges = [None, *cuts, None]
    out = []
    for low, high in zip(edges[:-1], edges[1:], strict=True):
        test = F.lit(True)
        if low is not None:
            test = test & (c > low)
        if high is not None:
            test = test & (c <= high)
        said = " and ".join(x for x in (None if low is None else f"({sql}) > {low!r}D", None if high is None else f"({sql}) <= {high!r}D") if x) or "true"
        out.append(Item(f"{attribute}:({'-inf' if low is None else low},{'inf' if high is None else high}]", test, None if sql is None else said))
    return out


def bin_width(df: DataFrame, attribute: str, k: int) -> list[float]:
    """Cut points of k bins of equal width between the least and the greatest value; none where all values are equal or null."""
    r = df.agg(F.min(attribute).cast("double").alias("a"), F.max(attribute).cast("double").alias("b")).first()
    return [] if r.a is None or r.a == r.b else [r.a + (r.b - r.a) * j / k for j in range(1, k)]


def bin_quantile(df: DataFrame, attribute: str, k: int, exact: bool = False, accuracy: int = 10_000) -> list[float]:
    """Cut points of k bins of about equal size, without repeats. exact: sorts all values, for small tables; else a sketch."""
    shares = [j / k for j in range(1, k)]
    found = df.agg((F.percentile(F.col(attribute).cast("double"), shares) if exact else F.percentile_approx(F.col(attribute).cast("double"), shares, accuracy)).alias("q")).first().q
    return sorted(set(found or []))


def item_null(attribute: str) -> Item:
    return Item(f"{attribute} is null", F.col(attribute).isNull())


def item_flag(name: str, test: Column) -> Item:
    return Item(name, test)


def item_tokens(array: Column, vocabulary: Iterable[str]) -> list[Item]:
    return [Item(f"w:{w}", F.array_contains(array, w)) for w in vocabulary]


def item_json(column: str, key: str, values: Iterable) -> list[Item]:
    got = F.get_json_object(column, f"$.{key}")
    return [Item(f"{key}={v}", got == F.lit(str(v))) for v in values]


def item_variant(column: str, path: str, kind: str, values: Iterable) -> list[Item]:
    """Items of a JSON column read as a variant: the value at the path, as the given type."""
    got = F.try_variant_get(F.try_parse_json(column), path, kind)
    return [Item(f"{path.removeprefix('$.')}={v}", got == F.lit(v)) for v in values]


def top_vocabulary(df: DataFrame, words: Column, k: int, min_df: int = 1) -> DataFrame:
    """(word, df): the k words in most rows, ties by the word."""
    return df.select(F.explode(F.array_distinct(words)).alias("word")).groupBy("word").agg(F.count(F.lit(1)).alias("df")).where(F.col("df") >= min_df).orderBy(F.desc("df"), "word").limit(k)


def build_items(df: DataFrame, attributes: list[str]) -> DataFrame:
    """The item catalogue of nominal attributes: (item_id, attr, op, value), ids in order of attribute and value."""
    long = df.select(F.explode(F.array(*(F.struct(F.lit(a).alias("attr"), F.col(a).cast("string").alias("value")) for a in attributes))).alias("x")).select("x.*").where("value is not null").distinct()
    from pyspark.sql import Window

    return long.select((F.row_number().over(Window.orderBy("attr", "value")) - 1).alias("item_id"), "attr", F.lit("=").alias("op"), "value")


def encode(df: DataFrame, items: list[Item], label: Column) -> DataFrame:
    """(items, label): sorted ids of the items that a row has; a projection, nothing is shuffled. Rows with a null label go."""
    ids = F.array_compact(F.array(*(F.when(F.coalesce(i.predicate, F.lit(False)), F.lit(k)) for k, i in enumerate(items)))) if items else F.array().cast("array<int>")
    return df.select(ids.alias("items"), label.cast("int").alias("label")).where("label is not null")


def compress(encoded: DataFrame, names: Iterable[str], negation: bool = False) -> LabeledDB:
    """Distinct item sets with their class weights: one aggregation, combined before the shuffle."""
    rows = encoded.groupBy("items").agg(F.sum("label").cast("long").alias("w_pos"), F.sum(1 - F.col("label")).cast("long").alias("w_neg"))
    return LabeledDB(rows, tuple(names), negation)


def labelled(df: DataFrame, items: list[Item], label: Column, negation: bool = False) -> LabeledDB:
    return compress(encode(df, items, label), [i.name for i in items], negation)


def distinct_semantics(db: LabeledDB) -> LabeledDB:
    """Classes as sets, not multisets: each item set counts once in each class that has it."""
    return replace(db, rows=db.rows.select("items", F.least("w_pos", F.lit(1)).alias("w_pos"), F.least("w_neg", F.lit(1)).alias("w_neg")))


def from_sets(spark, positives, negatives, names=None, negation: bool = False) -> LabeledDB:
    """A small database from Python sets of names."""
    names = tuple(names if names is not None else sorted({i for r in [*positives, *negatives] for i in r}))
    at = {n: k for k, n in enumerate(names)}
    rows = [(sorted(at[i] for i in r), y) for y, side in ((1, positives), (0, negatives)) for r in side]
    return compress(spark.createDataFrame(rows, "items array<int>, label int"), names, negation)


def merge_twins(db: LabeledDB) -> tuple[LabeledDB, dict[int, list[int]]]:
    """Items with equal columns become one; returns the smaller database and, for each new id, the old ids it stands for."""
    sums = db.rows.select(F.explode("items").alias("item"), F.xxhash64("items").alias("h"), F.xxhash64("items", F.lit(7)).alias("g")).groupBy("item").agg(F.count(F.lit(1)).alias("n"), F.bit_xor("h").alias("h"), F.bit_xor("g").alias("g")).collect()  # one row per item
    groups: dict[tuple, list[int]] = {}
    for r in sums:
        groups.setdefault((r.n, r.h, r.g), []).append(r.item)
    for i in set(range(db.n_items)) - {r.item for r in sums}:
        groups.setdefault((0, 0, 0), []).append(i)
    kept = sorted(sorted(g) for g in groups.values())
    new = {g[0]: k for k, g in enumerate(kept)}
    table = F.create_map(*(F.lit(v) for kv in new.items() for v in kv))
    rows = db.rows.select(F.array_sort(F.array_compact(F.transform("items", lambda i: table[i]))).alias("items"), "w_pos", "w_neg")
    return LabeledDB(rows.groupBy("items").agg(F.sum("w_pos").alias("w_pos"), F.sum("w_neg").alias("w_neg")), tuple("=".join(db.names[i] for i in g) for g in kept), db.negation), dict(enumerate(kept))


def occurs(items: Column, pattern: Iterable[int], n_items: int) -> Column:
    """All positive literals are there and no negated one is."""
    tests = [F.array_contains(items, i) if i < n_items else ~F.array_contains(items, i - n_items) for i in pattern]
    out = F.lit(True)
    for t in tests:
        out = out & t
    return out


def pattern_to_filter(items: list[Item], pattern: Iterable[int]) -> Column:
    """The pattern as a filter on the source table."""
    out = F.lit(True)
    for i in pattern:
        hit = F.coalesce(items[i % len(items)].predicate, F.lit(False))
        out = out & (hit if i < len(items) else ~hit)
    return out


def occurrences(db: LabeledDB, pattern: Iterable[int]) -> DataFrame:
    return db.rows.where(occurs(F.col("items"), pattern, db.n_items))


def mask_words(items: Column, n_items: int) -> list[Column]:
    """The item set as 62-bit words."""
    out = []
    for w in range(0, max(1, n_items), 62):
        out.append(F.aggregate(F.filter(items, _within(w)), F.lit(0).cast("long"), _or_bit(w)))
    return out


def _within(w: int):
    return lambda i: (i >= w) & (i < w + 62)


def _or_bit(w: int):
    return lambda acc, i: acc.bitwiseOR(F.call_function("shiftleft", F.lit(1).cast("long"), i - w))


def to_masks(db: LabeledDB) -> DataFrame:
    words = mask_words(F.col("items"), db.n_items)
    return db.rows.select(*(c.alias(f"m{k}") for k, c in enumerate(words)), "w_pos", "w_neg")


def pattern_masks(patterns: Iterable[Pattern], n_items: int) -> list[tuple]:
    words = range(0, max(1, n_items), 62)
    bits = lambda ids, w: sum(1 << (i - w) for i in ids if w <= i < w + 62)
    return [(list(p), *(bits([i for i in p if i < n_items], w) for w in words), *(bits([i - n_items for i in p if i >= n_items], w) for w in words)) for p in patterns]


def supports(db: LabeledDB, patterns: Iterable[Pattern]) -> DataFrame:
    """(pattern, sup_pos, sup_neg) by a join of distinct rows and broadcast patterns on the mask predicate, and one aggregation.

    The list of patterns comes from the driver, so its broadcast is as small as the list."""
    patterns = [tuple(sorted(p)) for p in patterns]
    words = len(range(0, max(1, db.n_items), 62))
    schema = "pattern array<int>, " + ", ".join([f"p{k} long" for k in range(words)] + [f"q{k} long" for k in range(words)])
    table = db.rows.sparkSession.createDataFrame(pattern_masks(patterns, db.n_items), schema)
    test = F.lit(True)
    for k in range(words):
        test = test & (F.col(f"m{k}").bitwiseAND(F.col(f"p{k}")) == F.col(f"p{k}")) & (F.col(f"m{k}").bitwiseAND(F.col(f"q{k}")) == 0)
    hit = to_masks(db).join(F.broadcast(table.withColumnRenamed("pattern", "hit")), test).groupBy("hit").agg(F.sum("w_pos").alias("sup_pos"), F.sum("w_neg").alias("sup_neg"))
    return table.select("pattern").distinct().join(hit, F.col("pattern") == F.col("hit"), "left").select("pattern", F.coalesce("sup_pos", F.lit(0)).alias("sup_pos"), F.coalesce("sup_neg", F.lit(0)).alias("sup_neg"))


def rows_by_literal(db: LabeledDB) -> DataFrame:
    """(literal, items, w_pos, w_neg): every row at each literal that it holds."""
    n = db.n_items
    literals = F.array(*map(F.lit, db.literals())) if db.literals() else F.array().cast("array<int>")
    holds = lambda i: F.when(i < n, F.array_contains("items", i)).otherwise(~F.array_contains("items", i - n))
    return db.rows.select(F.explode(F.filter(literals, holds)).alias("literal"), "items", "w_pos", "w_neg")


def literal_supports(db: LabeledDB) -> DataFrame:
    return supports(db, [(i,) for i in db.literals()])


def occurrence_delivery(db: LabeledDB) -> DataFrame:
    """Supports of single items by handing every row to each of its items."""
    return db.rows.select(F.explode("items").alias("item"), "w_pos", "w_neg").groupBy("item").agg(F.sum("w_pos").alias("sup_pos"), F.sum("w_neg").alias("sup_neg"))


def literal_bitmaps(db: LabeledDB) -> DataFrame:
    """(item, bucket, rows): the rows of each item as bitmaps, by Spark's bitmap aggregates; a row's number is a rank of its item set.

    Bitmaps of one bucket can be united and intersected with bitmap_or_agg and bitmap_and_agg; see bitmap_support."""
    return numbered_rows(db).select(F.explode("items").alias("item"), "row").groupBy("item", F.bitmap_bucket_number("row").alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("row")).alias("rows"))


def numbered_rows(db: LabeledDB) -> DataFrame:
    """Distinct rows with a number from 0: the rows before a range of hashes, and the rank within it, so no single window sees all rows."""
    from pyspark.sql import Window

    hashed = db.rows.withColumn("_h", F.xxhash64("items")).withColumn("_r", F.call_function("shiftright", F.col("_h"), F.lit(50)))
    before = hashed.groupBy("_r").agg(F.count(F.lit(1)).alias("_n")).withColumn("_b", F.sum("_n").over(Window.orderBy("_r")) - F.col("_n")).drop("_n")  # 16,384 ranges at most
    ranked = hashed.join(F.broadcast(before), "_r").withColumn("row", F.row_number().over(Window.partitionBy("_r").orderBy("_h", F.concat_ws(",", "items"))) - 1 + F.col("_b"))
    return ranked.drop("_h", "_r", "_b")


def bitmap_support(bitmaps: DataFrame, items: Iterable[int], union: bool = False) -> DataFrame:
    """(n_rows): distinct rows that hold all of the items, or any of them."""
    wanted = sorted(set(items))
    merge = F.bitmap_or_agg if union else F.bitmap_and_agg
    merged = bitmaps.where(F.col("item").isin(wanted)).groupBy("bucket").agg(merge("rows").alias("rows"), F.count(F.lit(1)).alias("held"))
    return merged.where(F.lit(union) | (F.col("held") == len(wanted))).agg(F.coalesce(F.sum(F.bitmap_count("rows")), F.lit(0)).alias("n_rows"))


def profile(db: LabeledDB) -> DataFrame:
    """Items, rows, classes, distinct rows and density."""
    n, literals = db.n_items, db.literals()
    away = F.array(*(F.lit(i - n) for i in literals if i >= n)).cast("array<int>")
    size = (F.size("items") + F.size(F.array_except(away, "items"))).cast("double")
    w = F.col("w_pos") + F.col("w_neg")
    return db.rows.agg(F.lit(len(literals)).alias("n_literals"), F.sum(w).alias("n_rows"), F.sum("w_pos").alias("n_pos"), F.sum("w_neg").alias("n_neg"), F.count(F.lit(1)).alias("n_distinct"), F.round(F.sum(size * w) / F.sum(w) / max(1, len(literals)), 6).alias("density"))


def class_overlap(db: LabeledDB) -> DataFrame:
    return db.rows.where("w_pos > 0 and w_neg > 0")


def split_classes(db: LabeledDB) -> tuple[DataFrame, DataFrame]:
    return db.rows.where("w_pos > 0").select("items", F.col("w_pos").alias("weight")), db.rows.where("w_neg > 0").select("items", F.col("w_neg").alias("weight"))


def arrays_of(frame) -> tuple[list[np.ndarray], list[int], list[int]]:
    return [np.asarray(i, int) for i in frame["items"]], frame["w_pos"].tolist(), frame["w_neg"].tolist()
