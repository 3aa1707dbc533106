"""N-gram Jaccard join: MinHash banding on classes of equal n-gram sets, verified on the full sets.

Texts with the same set of word n-grams form one class, so copies are never paired. Classes that share a band hash are
candidates. Instead of a row per candidate pair, classes that bands connect form candidate groups; a group is cut into
blocks by hash, and every pair of blocks is compared in one task on the full sets. A task returns, for each class, how
many rows it links to there and one row of a spanning forest of the links, so a group of n classes makes about n to the
power 1.5 rows, not n squared, and no link is lost."""

from __future__ import annotations

import hashlib
import math

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .components import connected_components
from .shared import clean_text, files_for, join_by_size, spare, stored, tidy, to_frame, whole
from .tokens import batches
from .words import hashed, mixed, numbered

SIGNED = "doc_id long, fp binary, bands array<long>"
SETS = "fp binary, grams binary"


def choose_bands(threshold: float, recall: float, most_hashes: int = 128) -> tuple[int, int]:
    """(bands, rows) with the most rows, so the fewest false candidates, that find a pair at the threshold with the wanted probability."""
    best = None
    for rows in range(1, 17):
        p = threshold**rows
        bands = max(1, math.ceil(math.log(1 - recall) / math.log(1 - p))) if p < 1 else 1
        if bands * rows <= most_hashes:
            best = bands, rows
    if best is None:
        raise ValueError("too few hashes for this recall")
    return best


def gram_sets(texts: list[str], n: int = 5) -> list[np.ndarray]:
    """Sorted distinct 64-bit hashes of the word n-grams of each text; a text of fewer words is one gram, one without words has none.

    Words are runs of letters and digits in lower case, so copies that differ in case and punctuation are copies."""
    names, codes, bounds = numbered(texts)
    words = hashed(names)[codes]
    odd = [np.uint64(2 * k * 0x9E3779B97F4A7C15 + 1 & (1 << 64) - 1) for k in range(1, n + 1)]
    total = max(0, len(words) - n + 1)
    rolled = np.zeros(total, np.uint64)
    with np.errstate(over="ignore"):
        for k in range(n):
            rolled += mixed(words[k : k + total] + odd[k])
        rolled = mixed(rolled)
        out = []
        for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True):
            if b - a >= n:
                out.append(np.unique(rolled[a : b - n + 1]))
            elif b > a:
                short = np.uint64(b - a)
                for k in range(b - a):
                    short = mixed(np.array([words[a + k] + odd[k] + short * np.uint64(31)], np.uint64))[0]
                out.append(np.array([short], np.uint64))
            else:
                out.append(np.zeros(0, np.uint64))
    return out


def fingerprint(grams: np.ndarray) -> bytes:
    return hashlib.blake2b(grams.tobytes(), digest_size=16).digest()


def band_hashes(sets: list[np.ndarray], bands: int, rows: int, seed: int = 7) -> np.ndarray:
    """(sets, bands) signed 64-bit band hashes, each with its band number mixed in; sets must not be empty."""
    rng = np.random.default_rng(seed)
    a = rng.integers(0, 1 << 63, bands * rows, np.uint64) * np.uint64(2) + np.uint64(1)
    b = rng.integers(0, 1 << 63, bands * rows, np.uint64)
    flat = np.concatenate(sets)
    starts = np.cumsum([0] + [len(s) for s in sets[:-1]])
    with np.errstate(over="ignore"):
        least = np.stack([np.minimum.reduceat(flat * x + y, starts) for x, y in zip(a, b, strict=True)], axis=1)
        keyed = np.zeros((len(sets), bands), np.uint64) + mixed(np.arange(1, bands + 1).astype(np.uint64))
        for r in range(rows):
            keyed = mixed(keyed ^ least[:, r::rows])
    return keyed.view(np.int64)


def sign(docs: DataFrame, n: int, bands: int, rows: int) -> DataFrame:
    def work(frames):
        for frame in frames:
            texts, keys = frame["text"].tolist(), whole(frame["doc_id"])
            for a, b in batches(texts, 4_000_000):
                sets = gram_sets(texts[a:b], n)
                out: list = [None] * len(sets)
                group, size = [], 0
                full = [i for i, s in enumerate(sets) if len(s)]
                for i in full:  # as many sets at once as stay in the processor's cache
                    group.append(i)
                    size += len(sets[i])
                    if size >= 30_000 or i == full[-1]:
                        for k, h in zip(group, band_hashes([sets[k] for k in group], bands, rows), strict=True):
                            out[k] = h.tolist()
                        group, size = [], 0
                yield to_frame([(k, fingerprint(s), h or []) for k, s, h in zip(keys[a:b], sets, out, strict=True)], SIGNED)

    return docs.mapInPandas(tidy(work), SIGNED)


def overlap(left: list[np.ndarray], right: list[np.ndarray], width: int = 4096) -> np.ndarray:
    """Sizes of all intersections, as products of 0/1 matrices, some columns at a time."""
    names, inverse = np.unique(np.concatenate(left + right), return_inverse=True)
    cut = np.cumsum([len(s) for s in left + right])
    columns = np.split(inverse, cut[:-1])
    rows = np.repeat(np.arange(len(columns)), [len(c) for c in columns])
    order = np.argsort(inverse, kind="stable")
    sorted_columns, sorted_rows = inverse[order], rows[order]
    common = np.zeros((len(left), len(right)), np.float32)
    for a in range(0, len(names), width):
        i, j = np.searchsorted(sorted_columns, [a, a + width])
        part = np.zeros((len(columns), width), np.float32)
        part[sorted_rows[i:j], sorted_columns[i:j] - a] = 1
        common += part[: len(left)] @ part[len(left) :].T
    return common


COUNTED = "fp binary, root binary, links long"


def count_links(keys_a, sets_a, sizes_a, keys_b, sets_b, sizes_b, threshold: float, same: bool) -> list[tuple]:
    """(class, least class it reaches within these blocks, rows it links to) for each class with a link."""
    common = overlap(sets_a, sets_b)
    na, nb = np.array([len(s) for s in sets_a]), np.array([len(s) for s in sets_b])
    near = common >= threshold * (na[:, None] + nb[None, :] - common) - 1e-6
    if same:
        np.fill_diagonal(near, False)
    keys = keys_a if same else keys_a + keys_b
    order = np.argsort(np.argsort(np.array([k.hex() for k in keys])))
    label = order.copy()
    pick_b = slice(0, len(keys_a)) if same else slice(len(keys_a), None)
    far = len(keys)
    while True:
        before = label.copy()
        label[pick_b] = np.minimum(label[pick_b], np.where(near, label[: len(keys_a), None], far).min(axis=0, initial=far))
        label[: len(keys_a)] = np.minimum(label[: len(keys_a)], np.where(near, label[pick_b][None, :], far).min(axis=1, initial=far))
        if (before == label).all():
            break
    by_rank = {int(r): k for r, k in zip(order, keys, strict=True)}
    links = np.concatenate((near @ sizes_b, [] if same else near.T @ sizes_a)).astype(np.int64)
    return [(k, by_rank[int(label[i])], int(links[i])) for i, k in enumerate(keys) if links[i]]


def jaccard_classes(docs: DataFrame, n: int = 5, threshold: float = 0.8, recall: float = 0.9999) -> DataFrame:
    """One row per document: (doc_id, class_id, copy_id, n_copies, n_links).

    class_id is the least doc_id that links reach, copy_id the least of the documents with the same n-grams, n_copies
    their number, n_links the number of other rows whose n-gram sets have a Jaccard similarity of at least the threshold.
    Null text is empty; texts without words are copies of each other; a text with fewer words than n is one gram. Rows
    that repeat a doc_id count as rows. A null doc_id takes part, and gives a null class_id only where every id of the
    class is null. An empty table gives none; other columns are ignored.
    """
    bands, rows = choose_bands(threshold, recall)
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), clean_text().alias("text"))
    signed = stored(sign(texts, n, bands, rows), "signed")
    n_docs = signed.count()
    files = files_for(n_docs)
    members = signed.select("doc_id", "fp")
    classes = stored(signed.groupBy("fp").agg(F.min("doc_id").alias("copy_id"), F.count(F.lit(1)).alias("n_copies"), F.min("bands").alias("bands")), "classes")

    banded = classes.select("fp", F.explode("bands").alias("band"))
    buckets = banded.groupBy("band").agg(F.min("fp").alias("hub"), F.count(F.lit(1)).alias("held")).where("held > 1")
    buckets = stored(buckets, "buckets", files)
    spokes = join_by_size(banded, buckets, "band", "held", max(1, n_docs * bands)).where("fp <> hub").select("fp", "hub").distinct()
    groups = stored(connected_components(spokes, "fp", "hub").select(F.col("node").alias("fp"), F.col("component").alias("grp")), "groups", files)
    sized = stored(groups.groupBy("grp").agg(F.count(F.lit(1)).alias("m")), "sizes", files)
    active = join_by_size(groups, sized, "grp", "m", max(1, n_docs)).join(classes.drop("bands"), "fp")
    parts = F.ceil(F.col("m") / F.least(F.greatest(4 * F.sqrt("m"), F.lit(128)), F.lit(1024))).cast("int")
    active = stored(active.withColumn("parts", parts), "active", files)

    def reread(frames):
        for frame in frames:
            texts = frame["text"].tolist()
            for a, b in batches(texts, 4_000_000):
                sets = gram_sets(texts[a:b], n)
                yield to_frame([(fingerprint(s), s.tobytes()) for s in sets], SETS)

    ids = active.select(F.coalesce("copy_id", F.lit(0)).alias("key"), F.col("copy_id").isNull().alias("none")).distinct()
    ids = stored(ids, "asked", files)
    wanted = texts.withColumn("key", F.coalesce("doc_id", F.lit(0))).withColumn("none", F.col("doc_id").isNull()).join(ids, ["key", "none"], "left_semi")
    sets = wanted.select("text").mapInPandas(tidy(reread), SETS).dropDuplicates(["fp"])
    rowed = active.join(sets, "fp").withColumn("part", F.pmod(F.xxhash64("fp"), F.col("parts")).cast("int"))
    dealt = rowed.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1))).select(
        "grp", F.least("part", "other").alias("low"), F.greatest("part", "other").alias("high"), "part", "fp", "n_copies", "grams"
    )

    def compare(key, frame):
        low, high = key[1], key[2]
        packed = [(p, bytes(f), np.frombuffer(g, np.uint64), c) for p, f, g, c in zip(frame["part"], frame["fp"], frame["grams"], frame["n_copies"], strict=True)]
        a = [x for x in packed if x[0] == low]
        b = a if low == high else [x for x in packed if x[0] == high]
        if not a or not b or len(packed) < 2:
            return to_frame([], COUNTED)
        take = lambda rows: ([x[1] for x in rows], [x[2] for x in rows], np.array([x[3] for x in rows], np.int64))
        return to_frame(count_links(*take(a), *take(b), threshold, low == high), COUNTED)

    counted = stored(dealt.groupBy("grp", "low", "high").applyInPandas(compare, COUNTED), "counted", files)
    joined = stored(connected_components(counted.where("fp <> root"), "fp", "root").select(F.col("node").alias("fp"), F.col("component").alias("cls")), "joined", files)
    linked = counted.groupBy("fp").agg(F.sum("links").alias("links")).join(joined, "fp").join(classes.drop("bands"), "fp")
    linked = stored(linked, "linked", files)
    named = stored(linked.groupBy("cls").agg(F.min("copy_id").alias("class_id"), F.count(F.lit(1)).alias("size")), "named", files)
    linked = join_by_size(linked, named, "cls", "size", max(1, n_docs)).select("fp", "links", "class_id")
    told = classes.select("fp", "copy_id", "n_copies").join(linked, "fp", "left")
    told = stored(told.select("fp", F.when(F.col("links").isNull(), F.col("copy_id")).otherwise(F.col("class_id")).alias("class_id"), "copy_id", "n_copies", (F.col("n_copies") - 1 + F.coalesce("links", F.lit(0))).alias("n_links")), "told")
    return join_by_size(members, told, "fp", "n_copies", max(1, n_docs)).select("doc_id", "class_id", "copy_id", "n_copies", "n_links")


def keep_one(docs: DataFrame, **options) -> DataFrame:
    """The row with the least doc_id of each class, whole and with all columns.

    Rows that repeat both id and text stay once; where all ids of a class are null, each of its distinct texts stays once.
    A null text is an empty one; an empty table gives none; columns of any name stay as they are. The ids that go are
    fewer than those that stay, so it is they that meet the texts."""
    judged = jaccard_classes(docs, **options).where("doc_id is not null")
    ids = stored(judged.groupBy("doc_id").agg(F.max(F.col("doc_id") == F.col("class_id")).alias("first"), F.count(F.lit(1)).alias("rows")), "judged")
    gone = stored(ids.where("not first").select("doc_id"), "gone")
    repeated = stored(ids.where("first and rows > 1").select("doc_id"), "repeated")
    key, named = docs["doc_id"].cast("long"), docs.where(F.col("doc_id").isNotNull())
    other = spare(docs.columns, "_other")[0]
    kept = named.join(gone.withColumnRenamed("doc_id", other), key == F.col(other), "left_anti")
    nameless = docs.where(F.col("doc_id").isNull()).dropDuplicates(["text"])
    if not repeated.limit(1).count():
        return kept.unionByName(nameless)
    again = repeated.withColumnRenamed("doc_id", other)
    single = kept.join(again, key == F.col(other), "left_anti")
    several = kept.join(again, key == F.col(other), "left_semi").dropDuplicates(["doc_id", "text"])
    return single.unionByName(several).unionByName(nameless)
