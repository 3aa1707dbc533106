"""The competitors: brute force, weighted depth-first and closed sets, contrast prefix tree, frequent-pattern tree, decision diagrams.

Each is a plain function on weighted rows with a time limit, which experiments run side by side in single tasks, and an
operator that deals its work over tasks."""

from __future__ import annotations

import time
from itertools import combinations
from typing import Any

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.scratch import settled
from .constraints import Constraint
from .kernel import Side, static_rank
from .labeled import LabeledDB, arrays_of, literal_supports, rows_by_literal, supports
from .minimal import Zdd, extract_minimal

FOUND = "pattern array<int>, sup_pos long, sup_neg long"


def all_patterns(n_items: int, negation: bool, max_len: int, literals=None) -> list[tuple[int, ...]]:
    """Every consistent set of at most max_len literals, the empty one first."""
    literals = range(n_items * (1 + negation)) if literals is None else literals
    return [p for k in range(max_len + 1) for p in combinations(literals, k) if len({i % n_items for i in p}) == k]


def brute_force(db: LabeledDB, constraint: Constraint, max_len: int | None = None, minimal: bool = True) -> DataFrame:
    """Supports of every pattern by the mask join, the constraint as a filter, minimality by anti join. For small alphabets."""
    n_pos, n_neg = db.sizes()
    constraint.bind(n_pos, n_neg)
    members = supports(db, all_patterns(db.n_items, db.negation, db.n_items if max_len is None else max_len, db.literals())).where(F.expr(constraint.sql("sup_pos", "sup_neg", str(n_pos), str(n_neg))))
    return extract_minimal(members) if minimal else members


class Timer:
    """A time limit that kernels ask now and then."""

    def __init__(self, seconds: float | None = None):
        self.end = None if seconds is None else time.monotonic() + seconds

    def check(self) -> None:
        if self.end is not None and time.monotonic() > self.end:
            raise TimeoutError("beyond the time limit")


class Occurrences:
    """Weighted rows as sets of literals, and for each literal the list of its rows: the horizontal and vertical form of a depth-first miner."""

    def __init__(self, sets, w_pos, w_neg, n_items: int, literals):
        wanted = set(literals)
        self.rows = [frozenset(({*map(int, s)} | {i + n_items for i in range(n_items) if i not in s}) & wanted) for s in ({*map(int, x)} for x in sets)]
        self.w_pos, self.w_neg = np.array(w_pos, np.int64), np.array(w_neg, np.int64)
        self.at = {i: np.array([k for k, r in enumerate(self.rows) if i in r], int) for i in literals}

    def support(self, tids: np.ndarray) -> tuple[int, int]:
        return int(self.w_pos[tids].sum()), int(self.w_neg[tids].sum())

    def deliver(self, tids: np.ndarray, place: dict[int, int], after: int) -> dict[int, list[int]]:
        """Occurrence lists of the literals behind a place, by handing each row to its literals."""
        out: dict[int, list[int]] = {}
        for t in tids.tolist():
            for i in self.rows[t]:
                if place[i] > after:
                    out.setdefault(i, []).append(t)
        return out


def static_places(db: LabeledDB, order: str) -> dict[int, int]:
    """Position of each literal in a static order, from one aggregation."""
    rows = literal_supports(db).collect()  # one row per literal
    by = {r.pattern[0]: (int(r.sup_pos), int(r.sup_neg)) for r in rows}
    ids = np.array(db.literals(), int)
    rank = static_rank(order, ids, np.array([by[i][0] for i in ids.tolist()]), np.array([by[i][1] for i in ids.tolist()]))
    return {i: int(rank[i]) for i in ids.tolist()}


def weighted_patterns(occ: Occurrences, place: dict[int, int], min_pos: int, first: int | None, max_len: int | None, timer: Timer, listed: bool = True):
    """Jumping patterns whose first literal is the given one (or any), by depth-first search with delivered occurrence lists.

    A positive row weighs 1, a negative one less than minus all positives; a pattern is reported if its rows weigh min_pos
    or more, and the weight of the positives alone prunes. listed=False counts: a literal that all rows hold doubles the rest."""
    heavy = int(occ.w_pos.sum()) + 1
    by_place = sorted(place, key=place.get)
    roots = by_place if first is None else [first]
    out, total = [], 0
    for root in roots:
        todo = [((root,), occ.at[root], 1, frozenset())]
        while todo:
            pattern, tids, times, shared = todo.pop()
            timer.check()
            x, y = occ.support(tids)
            if x < min_pos:
                continue
            here = x - heavy * y >= min_pos
            if listed and here:
                out.append((tuple(sorted(pattern)), x, y))
            if max_len is not None and len(pattern) >= max_len:
                continue
            delivered = occ.deliver(tids, place, place[pattern[-1]])
            if not listed:
                fresh = {i for i, t in delivered.items() if len(t) == len(tids)} - shared
                times, shared = times << len(fresh), shared | fresh
                total += times if here else 0
            todo += [((*pattern, i), np.array(t, int), times, shared) for i, t in delivered.items() if i not in shared]
    return out if listed else total


def closed_sets_from(occ: Occurrences, place: dict[int, int], min_pos: int, first: int | None, timer: Timer) -> list[tuple]:
    """Closed sets with at least min_pos positive rows whose first literal is the given one (or any): prefix-preserving closure extension, so each comes once and nothing is kept to compare with."""
    out = []
    for root in sorted(place, key=place.get) if first is None else [first]:
        todo = [(occ.at[root], place[root], None)]
        while todo:
            tids, core, parent = todo.pop()
            timer.check()
            x, y = occ.support(tids)
            if x < min_pos or not len(tids):
                continue
            closed = frozenset.intersection(*(occ.rows[t] for t in tids.tolist()))
            if parent is None:
                if any(place[i] < core for i in closed):
                    break  # what holds this literal holds an earlier one too
            elif any(place[i] < core and i not in parent for i in closed):
                continue
            out.append((tuple(sorted(closed)), x, y))
            todo += [(np.array(t, int), place[i], closed) for i, t in occ.deliver(tids, place, core).items() if i not in closed]
    return out


def by_first_literal(db: LabeledDB, order: str, work, schema: str) -> DataFrame:
    """work(occurrences, places, first literal) for each literal, in the task that gets the rows which hold it."""
    n, literals, place = db.n_items, db.literals(), static_places(db, order)

    def task(key: tuple[Any, ...], frame: pd.DataFrame) -> pd.DataFrame:
        return work(Occurrences(*arrays_of(frame), n, literals), place, int(key[0]))

    return rows_by_literal(db).groupBy("literal").applyInPandas(task, schema)


def frame_of(found) -> pd.DataFrame:
    return pd.DataFrame([(list(p), x, y) for p, x, y in found], columns=["pattern", "sup_pos", "sup_neg"])


def closed_jeps(db: LabeledDB, min_pos: int = 1, max_len: int | None = None, order: str = "static:total_asc", timeout_s: float | None = None) -> DataFrame:
    """All non-empty jumping patterns by the weighted depth-first miner, one task per first literal."""
    return by_first_literal(db, order, lambda occ, place, i: frame_of(weighted_patterns(occ, place, min_pos, i, max_len, Timer(timeout_s))), FOUND)


def closed_sets(db: LabeledDB, min_pos: int = 1, max_neg: int | None = None, order: str = "static:total_asc", timeout_s: float | None = None) -> DataFrame:
    """Closed sets of both classes together with at least min_pos positive and at most max_neg negative rows, one task per first literal.

    The closure of the empty set is among them only if some literal is in every row; the empty set itself is not."""
    found = by_first_literal(db, order, lambda occ, place, i: frame_of(closed_sets_from(occ, place, min_pos, i, Timer(timeout_s))), FOUND)
    return found if max_neg is None else found.where(F.col("sup_neg") <= max_neg)


def count_jeps_closed(db: LabeledDB, min_pos: int = 1, order: str = "static:total_asc", timeout_s: float | None = None) -> DataFrame:
    """(n_jeps): the number of jumping patterns by the depth-first miner, the empty one included, without listing them."""
    from decimal import Decimal

    count = lambda occ, place, i: pd.DataFrame({"n": [Decimal(weighted_patterns(occ, place, min_pos, i, None, Timer(timeout_s), False))]})
    n_pos, n_neg = db.sizes()
    empty = int(n_neg == 0 and n_pos >= min_pos)
    return by_first_literal(db, order, count, "n decimal(38,0)").agg((F.coalesce(F.sum("n"), F.lit(0)) + F.lit(empty)).cast("decimal(38,0)").alias("n_jeps"))


class TreeNode:
    __slots__ = ("children", "n_neg", "n_pos")

    def __init__(self):
        self.children: dict[int, TreeNode] = {}
        self.n_pos = self.n_neg = 0

    def insert(self, items, p: int, q: int) -> None:
        node = self
        for i in items:
            node = node.children.setdefault(i, TreeNode())
            node.n_pos += p
            node.n_neg += q

    def absorb(self, other: TreeNode) -> None:
        self.n_pos += other.n_pos
        self.n_neg += other.n_neg
        for i, child in other.children.items():
            if i in self.children:
                self.children[i].absorb(child)
            else:
                self.children[i] = child.copy()

    def copy(self) -> TreeNode:
        out = TreeNode()
        out.absorb(self)
        return out


def ratio_places(x: dict[int, int], y: dict[int, int]) -> list[int]:
    """Literals by support ratio, infinite first."""
    return sorted(x, key=lambda i: (-(x[i] / y[i]) if y[i] else -float("inf") if x[i] else 0.0, i))


def tree_patterns(tree: TreeNode, path: tuple[int, ...], by_rank: list[int], min_pos: int, max_len: int | None, timer: Timer) -> list[tuple]:
    """Path-minimal jumping patterns of a contrast prefix tree: each visited subtree is merged into its siblings."""
    out: list[tuple] = []
    todo: list[tuple] = [(tree, path, False)]
    while todo:
        node, path, opened = todo.pop()
        timer.check()
        if not opened:
            if node.n_pos < min_pos:
                continue
            if node.n_neg == 0:
                out.append((tuple(sorted(by_rank[i] for i in path)), node.n_pos, 0))
                continue
            if max_len is not None and len(path) >= max_len:
                continue
        if node.children:
            i = min(node.children)
            child = node.children.pop(i)
            for j, grand in child.children.items():
                if j in node.children:
                    node.children[j].absorb(grand)
                else:
                    node.children[j] = grand.copy()
            todo += [(node, path, True), (child, (*path, i), False)]
    return out


def prefix_tree_sjeps(db: LabeledDB, min_pos: int = 1, max_len: int | None = None, timeout_s: float | None = None) -> DataFrame:
    """Minimal jumping patterns by a contrast prefix tree.

    Literals are ordered by support ratio, infinite first; a root's task gets the suffixes of the rows that hold its
    literal, builds the tree and visits it. A last pass keeps the minimal ones."""
    n, negation, literals = db.n_items, db.negation, set(db.literals())
    rows = literal_supports(db).collect()  # one row per literal
    by_rank = ratio_places({r.pattern[0]: int(r.sup_pos) for r in rows}, {r.pattern[0]: int(r.sup_neg) for r in rows})
    rank = {i: k for k, i in enumerate(by_rank)}

    def deal(frames):
        for frame in frames:
            out = []
            for items, p, q in zip(*arrays_of(frame), strict=True):
                held = set(items.tolist())
                own = sorted(rank[i] for i in [*held, *((i + n for i in range(n) if i not in held) if negation else ())] if i in literals)
                out += [(own[k], own[k + 1 :], p, q) for k in range(len(own))]
            yield pd.DataFrame(out, columns=["root", "rest", "w_pos", "w_neg"])

    def search(key: tuple[Any, ...], frame: pd.DataFrame) -> pd.DataFrame:
        root, tree = int(key[0]), TreeNode()
        for rest, p, q in zip(frame["rest"], frame["w_pos"], frame["w_neg"], strict=True):
            tree.n_pos += p
            tree.n_neg += q
            tree.insert(rest, p, q)
        return frame_of(tree_patterns(tree, (root,), by_rank, min_pos, max_len, Timer(timeout_s)))

    found = db.rows.mapInPandas(deal, "root int, rest array<int>, w_pos long, w_neg long").groupBy("root").applyInPandas(search, FOUND)
    empty = db.rows.agg(F.sum("w_pos").alias("x"), F.sum("w_neg").alias("y")).where(F.expr("x > 0 and y = 0") & (F.col("x") >= min_pos)).select(F.array().cast("array<int>").alias("pattern"), F.col("x").alias("sup_pos"), F.col("y").alias("sup_neg"))
    return extract_minimal(settled(found.unionByName(empty), "prefix-tree"))


def fpgrowth_contrast(db: LabeledDB, min_pos: int, max_neg: int = 0, max_len: int | None = None) -> DataFrame:
    """Spark's frequent-pattern growth on the positives, then the negative supports of what is frequent, then the filter. Positive literals only.

    A frequent set meets the negative rows at its item that they use least, so the join is on one item and each row is
    asked at its own items only."""
    from pyspark.ml.fpm import FPGrowth

    n_pos, _ = db.sizes()
    repeated = db.rows.where("w_pos > 0").select(F.explode(F.array_repeat("items", F.col("w_pos").cast("int"))).alias("items"))
    frequent = FPGrowth(itemsCol="items", minSupport=(min_pos - 0.5) / max(n_pos, 1), minConfidence=1.0).fit(repeated).freqItemsets
    if max_len is not None:
        frequent = frequent.where(F.size("items") <= max_len)
    candidates = frequent.select(F.array_sort("items").alias("pattern"), F.col("freq").cast("long").alias("sup_pos"))
    negative = db.rows.where("w_neg > 0").select("items", "w_neg", F.explode("items").alias("item"))
    uses = negative.groupBy("item").agg(F.count(F.lit(1)).alias("n"))
    spread = candidates.select("pattern", "sup_pos", F.explode("pattern").alias("item")).join(uses, "item", "left")
    filed = spread.groupBy("pattern", "sup_pos").agg(F.min_by("item", F.struct(F.coalesce("n", F.lit(0)).alias("n"), "item")).alias("item"))
    hit = filed.join(negative, "item").where(F.size(F.array_except("pattern", "items")) == 0).groupBy("pattern").agg(F.sum("w_neg").alias("w"))
    return filed.join(hit, "pattern", "left").select("pattern", "sup_pos", F.coalesce("w", F.lit(0)).alias("sup_neg")).where(F.col("sup_neg") <= max_neg)


def diagram_patterns(sets, w_pos, w_neg, n_items: int, negation: bool, literals, min_pos: int, timer: Timer) -> list[tuple]:
    """Minimal jumping patterns on a decision diagram with the static order of the ids.

    A pattern has no negative row if it shares a literal with what each negative row lacks; the minimal ones among those
    are the minimal transversals of the lacking literals. Those with enough positive rows are the answer."""
    pos = Side(sets, w_pos, n_items, negation)
    d, everything = Zdd(), set(literals)
    level = [d.of(everything - row) for row, w in zip(Occurrences(sets, w_pos, w_neg, n_items, literals).rows, w_neg, strict=True) if w > 0]
    while len(level) > 1:
        timer.check()
        level = [d.union(*level[i : i + 2]) if i + 1 < len(level) else level[i] for i in range(0, len(level), 2)]
    d.timer = timer
    out = []
    for p in d.sets(d.transversals(d.minimal(level[0])) if level else 1):
        timer.check()
        x = int(pos.weigh(np.bitwise_and.reduce(pos.columns[list(p)], axis=0)[None] if p else pos.full[None])[0])
        if x >= min_pos:
            out.append((p, x, 0))
    return out


def zdd_sjeps(db: LabeledDB, min_pos: int = 1, max_len: int | None = None, timeout_s: float | None = None) -> DataFrame:
    """Minimal jumping patterns by decision-diagram enumeration, in one task: for few distinct rows."""
    n, negation, literals = db.n_items, db.negation, db.literals()

    def task(frame: pd.DataFrame) -> pd.DataFrame:
        return frame_of(diagram_patterns(*arrays_of(frame), n, negation, literals, min_pos, Timer(timeout_s)))

    found = db.rows.groupBy(F.lit(0).alias("g")).applyInPandas(task, FOUND)
    return found if max_len is None else found.where(F.size("pattern") <= max_len)
