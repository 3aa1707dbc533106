"""Benchmark decontamination: n-gram seeds join documents to test items, then Smith-Waterman scores the copies.

Items come to the executors in blocks of a bounded number of words, whatever the size of the benchmark. Documents are read
once per block. Every place where a document shares an n-gram with an item is aligned, however common the n-gram is; only
places whose words cannot reach the least score are passed over, which changes no result. A copy that keeps no n-gram of
an item has no seed and is not found."""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Callable, Iterator

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import clean_text, tidy, to_frame, whole
from .tokens import batches
from .words import mixed, numbered

FOUND = "doc_id long, text_key long, item_id long, score double, matched long, first_word long, n_words long"


class ItemBlock:
    """The n-grams of some items, over the words of those items only."""

    def __init__(self, items: list[tuple[int | None, str]], n: int):
        self.n, self.ids = n, [i for i, _ in items]
        names, codes, bounds = numbered([t or "" for _, t in items])
        self.words = {w: k for k, w in enumerate(names) if w}
        self.items = [codes[a:b].astype(np.int32) for a, b in zip(bounds[:-1], bounds[1:], strict=True)]
        self.short: dict[bytes, list[int]] = {}
        for k, c in enumerate(self.items):
            if 0 < len(c) < n:
                self.short.setdefault(c.tobytes(), []).append(k)
        self.counts = [Counter(c.tolist()) for c in self.items]
        keys, owner, at = [], [], []
        for k, c in enumerate(self.items):
            g = self.grams(c)
            keys.append(g)
            owner.append(np.full(len(g), k))
            at.append(np.arange(len(g)))
        keys, owner, at = (np.concatenate(x) if x else np.zeros(0, np.int64) for x in (keys, owner, at))
        order = np.argsort(keys, kind="stable")
        self.keys, self.owner, self.at = keys[order], owner[order], at[order]

    def grams(self, codes: np.ndarray) -> np.ndarray:
        total = max(0, len(codes) - self.n + 1)
        h = np.zeros(total, np.uint64)
        with np.errstate(over="ignore"):
            for k in range(self.n):
                h = mixed(h * np.uint64(3) + codes[k : k + total].astype(np.uint64) + np.uint64(k + 1))
        return h.view(np.int64)

    def find(self, codes: np.ndarray, least: Callable[[int], float]) -> Iterator[tuple[int, int, np.ndarray]]:
        """(item, first word, words around) for each place of a document where an item's n-grams lie. codes: -1 for words of no item.

        least: the score that counts, by the words of an item. An alignment of that score takes in at most 2 * words - least
        further words of the document, so the words around hold each one that goes through a seed whole."""
        n, total = self.n, len(codes) - self.n + 1
        known = codes >= 0
        if len(codes) < n:
            for k in self.short.get(codes.astype(np.int32).tobytes(), []) if known.all() and len(codes) else []:
                yield k, 0, codes
            return
        run = np.cumsum(np.concatenate(([0], known)))
        places = np.flatnonzero(run[n:] - run[:-n] == n)[:total]
        if not len(places):
            return
        picked = np.stack([codes[places + k] for k in range(n)], axis=1)
        h = np.zeros(len(places), np.uint64)
        with np.errstate(over="ignore"):
            for k in range(n):
                h = mixed(h * np.uint64(3) + picked[:, k].astype(np.uint64) + np.uint64(k + 1))
        h = h.view(np.int64)
        low, high = np.searchsorted(self.keys, h, "left"), np.searchsorted(self.keys, h, "right")
        hit = np.flatnonzero(high > low)
        if not len(hit):
            return
        count = (high - low)[hit]
        index = np.repeat(low[hit] - (np.cumsum(count) - count), count) + np.arange(count.sum())
        where, owner = np.repeat(places[hit], count), self.owner[index]
        begin = where - self.at[index]
        order = np.lexsort((begin, owner))
        owner, begin = owner[order], begin[order]
        sizes = np.array([len(c) for c in self.items])[owner]
        new = np.concatenate(([True], (owner[1:] != owner[:-1]) | (begin[1:] - begin[:-1] > sizes[1:] // 2 + 4)))
        for a, b in zip(np.flatnonzero(new), [*np.flatnonzero(new)[1:], len(owner)], strict=True):
            k, size = int(owner[a]), int(sizes[a])
            more = max(0, math.ceil(2 * size - least(size)))
            first = max(0, int(begin[a]) - more)
            last = min(len(codes), int(begin[b - 1]) + size + more)
            yield k, first, codes[first:last]

    def read(self, texts: list[str]) -> list[np.ndarray]:
        """The words of each text as codes of this block's words, -1 for all others."""
        names, codes, bounds = numbered(texts)
        own = np.array([self.words.get(w, -1) for w in names], np.int32)[codes] if names else np.zeros(0, np.int32)
        return [own[a:b] for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True)]

    def hits(self, codes: np.ndarray, least: Callable[[int], float]) -> Iterator[tuple[int | None, float, int, int, int]]:
        """(item, score, matched words, first word, words) of each alignment in a document that is worth the least score."""
        for k, first, window in self.find(codes, least):
            item = self.items[k]
            if 2 * (self.counts[k] & Counter(window.tolist())).total() < least(len(item)):  # no alignment matches more words
                continue
            best, row, last = align(item, window)
            if best >= least(len(item)):
                ahead = last - align(item[row::-1], window[last::-1])[2]
                yield self.ids[k], best / (2 * len(item)), int(best // 2), first + ahead, last - ahead + 1


def align(item: np.ndarray, window: np.ndarray, match: float = 2, mismatch: float = 1, gap: float = 1) -> tuple[float, int, int]:
    """Smith-Waterman score of the best local alignment, and where it ends in both; unknown words (-1) match nothing.

    A row of the matrix is one vector operation: gaps along it are a running maximum."""
    m = len(window)
    slope = gap * np.arange(1, m + 1)
    above = np.zeros(m + 1)
    best, at = 0.0, (0, 0)
    for i, w in enumerate(item):
        step = np.where((window == w) & (w >= 0), match, -mismatch)
        open_ = np.maximum(np.maximum(above[:-1] + step, above[1:] - gap), 0)
        row = np.maximum(np.maximum.accumulate(open_ + slope) - slope, open_)
        above = np.concatenate(([0.0], row))
        j = int(row.argmax()) if m else 0
        if m and row[j] > best:
            best, at = float(row[j]), (i, j)
    return best, *at


def item_blocks(benchmark: DataFrame, most_words: int) -> Iterator[list[tuple[int | None, str]]]:
    block, size = [], 0
    for r in benchmark.select(F.col("item_id").cast("long").alias("item_id"), clean_text().alias("text")).toLocalIterator():
        n = r.text.count(" ") + 1
        if block and size + n > most_words:
            yield block
            block, size = [], 0
        block.append((r.item_id, r.text))
        size += n
    if block:
        yield block


def least_score(share: float, words: int) -> Callable[[int], float]:
    return lambda size: min(2 * share * size, 2 * words)


def contaminated(docs: DataFrame, benchmark: DataFrame, n: int = 4, share: float = 0.5, words: int = 40, block_words: int = 300_000) -> DataFrame:
    """(doc_id, text_key, item_id, score, matched, first_word, n_words): one row per document and item that it holds.

    score is the alignment's share of the greatest score of the item; a document counts from the given share on, or where
    the alignment is worth the given number of matched words; first_word and n_words are where it lies. An item of fewer
    than n words counts only where it is the whole document; items that repeat a text are all reported. Null texts are
    empty and hold nothing; ids may be null or repeat; an empty table gives none; other columns are ignored. text_key is
    xxhash64 of the text, which tells rows with equal or null ids apart.
    """
    spark = docs.sparkSession
    chosen = docs.select(F.col("doc_id").cast("long").alias("doc_id"), clean_text().alias("text")).withColumn("text_key", F.xxhash64("text"))
    parts = [spark.createDataFrame([], FOUND)]
    least = least_score(share, words)
    for items in item_blocks(benchmark, block_words):
        block = spark.sparkContext.broadcast(items)

        def find(frames, block=block):
            known = ItemBlock(block.value, n)
            for frame in frames:
                texts = frame["text"].tolist()
                keys, marks = whole(frame["doc_id"]), whole(frame["text_key"])
                for a, b in batches(texts, 4_000_000):
                    rows = [(keys[a + i], marks[a + i], *h) for i, codes in enumerate(known.read(texts[a:b])) for h in known.hits(codes, least)]
                    if rows:
                        yield to_frame(rows, FOUND)

        parts.append(chosen.mapInPandas(tidy(find), FOUND))
    found = parts[0]
    for p in parts[1:]:
        found = found.unionByName(p)
    best = F.max_by(F.struct("score", "matched", "first_word", "n_words"), F.struct("score", -F.col("first_word")))
    return found.groupBy("doc_id", "text_key", "item_id").agg(best.alias("b")).select("doc_id", "text_key", "item_id", "b.*")


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, n: int = 4, share: float = 0.5, words: int = 40, block_words: int = 300_000) -> DataFrame:
    """Documents that hold no benchmark item by the rules of contaminated(), with all their columns.

    Whether a document goes is told by its own text, so this is one map over the rows for each block of items: no row is
    shuffled. Null and empty texts stay; repeated rows go or stay alike; an empty table gives none; columns of any name
    stay as they are."""
    out, least, place = docs, least_score(share, words), docs.columns.index("text")
    for items in item_blocks(benchmark, block_words):
        block = docs.sparkSession.sparkContext.broadcast(items)

        def clean(tables, block=block):
            import pyarrow as pa

            known = ItemBlock(block.value, n)
            for batch in tables:
                texts = [t or "" for t in batch.column(place).to_pylist()]
                keep = [next(known.hits(codes, least), None) is None for a, b in batches(texts, 4_000_000) for codes in known.read(texts[a:b])]
                yield batch.filter(pa.array(keep, pa.bool_()))

        out = out.mapInArrow(tidy(clean), docs.schema)
    return out
