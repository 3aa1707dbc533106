"""Inclusion-minimal (and maximal) patterns of a set of candidates.

Filtering among candidates is sound: a candidate that is not minimal contains a minimal one, which is a candidate too.
Immediate subsets would not do: under growth rate a member may lie above a failing set that lies above a member."""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def key_of(pattern):
    return F.concat_ws(",", pattern)


MOST_LOCAL = 1_000_000
LONGEST_EXPLODED = 12


def extract_minimal(candidates: DataFrame, method: str = "subset_join", most_local: int = MOST_LOCAL) -> DataFrame:
    """candidates: a column `pattern` (sorted array<int>), and any others. Methods: subset_join, rarest, levelwise, set_trie, zdd.

    All give the same answer. set_trie and zdd work on the driver; with more than `most_local` candidates, and subset_join
    with patterns whose subsets would be too many, the join on the rarest literal takes their place."""
    if method == "levelwise":
        return by_level(candidates)
    if method == "rarest":
        return by_rarest_literal(candidates)
    if method == "subset_join":
        longest = candidates.agg(F.max(F.size("pattern")).alias("n")).first().n or 0
        return by_subset_join(candidates) if longest <= LONGEST_EXPLODED else by_rarest_literal(candidates)
    pick = {"set_trie": minimal_by_trie, "zdd": zdd_minimal}[method]
    rows = candidates.select("pattern").distinct().limit(most_local + 1).collect()
    if len(rows) > most_local:
        return by_rarest_literal(candidates)
    kept = candidates.sparkSession.createDataFrame([(list(p),) for p in pick([tuple(r.pattern) for r in rows])], "pattern array<int>")
    return candidates.join(kept, "pattern", "left_semi")


def proper_subsets(pattern):
    """All proper subsets of an array column of at most 20 literals, the empty one included, as an array of arrays; an error beyond."""
    places = F.sequence(F.lit(0), F.call_function("shiftleft", F.lit(1), F.size(pattern)) - 2)
    subsets = F.transform(places, lambda m: F.filter(pattern, lambda x, i: F.call_function("shiftright", m, i).bitwiseAND(F.lit(1)) == 1))
    return F.when(F.size(pattern) > 20, F.raise_error(F.lit("too many subsets")).cast("array<array<int>>")).when(F.size(pattern) > 0, subsets)


def by_subset_join(candidates: DataFrame) -> DataFrame:
    """Explode proper subsets, keep the patterns with one among the candidates, and take those away: two hash joins on the key."""
    keyed = candidates.withColumn("_key", key_of("pattern"))
    below = keyed.select("_key", F.explode(proper_subsets(F.col("pattern"))).alias("sub")).select("_key", key_of("sub").alias("_sub"))
    hit = below.join(keyed.select(F.col("_key").alias("_sub")).distinct(), "_sub", "left_semi").select("_key").distinct()
    return keyed.join(hit, "_key", "left_anti").drop("_key")


def pairs_within(small: DataFrame, big: DataFrame) -> DataFrame:
    """(small_key, big_key) where a pattern of `small` is a proper subset of one of `big`: hash joins only.

    A small pattern is filed under the literal that the big ones use least, the empty one under -1; every big one asks at
    its own literals and at -1."""
    asks = big.select(key_of("pattern").alias("big_key"), F.col("pattern").alias("big"), F.explode(F.array_append("pattern", F.lit(-1))).alias("lit"))
    uses = asks.groupBy("lit").agg(F.count(F.lit(1)).alias("n"))
    own = F.when(F.size("pattern") > 0, F.col("pattern")).otherwise(F.array(F.lit(-1)))
    spread = small.select(key_of("pattern").alias("small_key"), F.col("pattern").alias("small"), F.explode(own).alias("lit")).join(uses, "lit")
    filed = spread.groupBy("small_key").agg(F.min_by("lit", F.struct("n", "lit")).alias("lit"), F.first("small").alias("small"))
    return asks.join(filed, "lit").where((F.size("small") < F.size("big")) & (F.size(F.array_except("small", "big")) == 0)).select("small_key", "big_key")


def by_rarest_literal(candidates: DataFrame) -> DataFrame:
    """For long patterns, whose subsets cannot be listed."""
    hit = pairs_within(candidates, candidates).select(F.col("big_key").alias("_key")).distinct()
    return candidates.withColumn("_key", key_of("pattern")).join(hit, "_key", "left_anti").drop("_key")


def by_level(candidates: DataFrame) -> DataFrame:
    """Sizes in ascending order; larger patterns that hold an accepted one go."""
    sizes = sorted(r[0] for r in candidates.select(F.size("pattern")).distinct().collect())  # at most the number of literals
    out = None
    for n in sizes:
        level = candidates.where(F.size("pattern") == n)
        if out is not None:
            hit = pairs_within(out, level).select(F.col("big_key").alias("_key")).distinct()
            level = level.withColumn("_key", key_of("pattern")).join(hit, "_key", "left_anti").drop("_key")
        out = level if out is None else out.unionByName(level)
    return candidates if out is None else out


def extract_maximal(candidates: DataFrame) -> DataFrame:
    hit = pairs_within(candidates, candidates).select(F.col("small_key").alias("_key")).distinct()
    return candidates.withColumn("_key", key_of("pattern")).join(hit, "_key", "left_anti").drop("_key")


def minimal_by_trie(patterns: list[tuple[int, ...]]) -> list[tuple[int, ...]]:
    """Insert by size; skip what holds a stored set."""
    root: dict = {}

    def holds(node, pattern, k):
        if None in node:
            return True
        return any(pattern[j] in node and holds(node[pattern[j]], pattern, j + 1) for j in range(k, len(pattern)))

    out = []
    for p in sorted(set(patterns), key=lambda p: (len(p), p)):
        if not holds(root, p, 0):
            node = root
            for i in p:
                node = node.setdefault(i, {})
            node[None] = True
            out.append(p)
    return out


class Zdd:
    """Families of sets as a zero-suppressed decision diagram: node = (literal, without, with); 0 is the empty family, 1 holds the empty set."""

    def __init__(self):
        self.nodes: list[tuple[int, int, int]] = [(1 << 60, 0, 0), (1 << 60, 1, 1)]
        self.unique: dict[tuple[int, int, int], int] = {}
        self.memo: dict[tuple, int] = {}
        self.timer = None  # asked whenever a node is made

    def node(self, literal: int, without: int, with_: int) -> int:
        if with_ == 0:
            return without
        key = (literal, without, with_)
        if key not in self.unique:
            if self.timer is not None and not len(self.nodes) % 256:
                self.timer.check()
            self.unique[key] = len(self.nodes)
            self.nodes.append(key)
        return self.unique[key]

    def of(self, pattern) -> int:
        out = 1
        for i in sorted(pattern, reverse=True):
            out = self.node(i, 0, out)
        return out

    def _memo(self, name, a, b, make):
        key = (name, a, b)
        if key not in self.memo:
            self.memo[key] = make()
        return self.memo[key]

    def union(self, a: int, b: int) -> int:
        if a == b or b == 0:
            return a
        if a == 0:
            return b
        a, b = min(a, b), max(a, b)

        def make():
            (x, a0, a1), (y, b0, b1) = self.nodes[a], self.nodes[b]
            if x < y:
                return self.node(x, self.union(a0, b), a1)
            if y < x:
                return self.node(y, self.union(a, b0), b1)
            if x == 1 << 60:
                return 1
            return self.node(x, self.union(a0, b0), self.union(a1, b1))

        return self._memo("u", a, b, make)

    def without_supersets(self, a: int, b: int) -> int:
        """Members of a that hold no member of b."""
        if b == 0 or a == 0:
            return a
        if b == 1 or a == b:
            return 0

        def make():
            (x, a0, a1), (y, b0, b1) = self.nodes[a], self.nodes[b]
            if x < y:
                return self.node(x, self.without_supersets(a0, b), self.without_supersets(a1, b))
            if y < x:
                return self.without_supersets(a, b0)
            return self.node(x, self.without_supersets(a0, b0), self.without_supersets(self.without_supersets(a1, b0), b1))

        return self._memo("s", a, b, make)

    def minimal(self, a: int) -> int:
        if a < 2:
            return a

        def make():
            x, a0, a1 = self.nodes[a]
            low = self.minimal(a0)
            return self.node(x, low, self.without_supersets(self.minimal(a1), low))

        return self._memo("m", a, 0, make)

    def transversals(self, a: int) -> int:
        """Minimal sets that share a literal with every member of a."""
        if a < 2:
            return 1 - a  # no member: the empty set hits all; an empty member is never hit

        def make():
            x, a0, a1 = self.nodes[a]
            without, with_ = self.transversals(self.union(a0, a1)), self.transversals(a0)
            return self.node(x, without, self.without_supersets(with_, without))

        return self._memo("t", a, 0, make)

    def sets(self, a: int):
        todo = [(a, ())]
        while todo:
            a, got = todo.pop()
            if a == 1:
                yield got
            elif a:
                x, a0, a1 = self.nodes[a]
                todo += [(a0, got), (a1, (*got, x))]


def zdd_minimal(patterns: list[tuple[int, ...]]) -> list[tuple[int, ...]]:
    d = Zdd()
    level = [d.of(p) for p in patterns]
    while len(level) > 1:
        level = [d.union(*level[i : i + 2]) if i + 1 < len(level) else level[i] for i in range(0, len(level), 2)]
    return sorted(d.sets(d.minimal(level[0]))) if level else []


def minimal_plain(patterns):
    """Of a small list, by the definition."""
    have = set(patterns)
    return [p for p in patterns if not any(s in have for n in range(len(p)) for s in combinations(p, n))]
