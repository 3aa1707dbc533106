"""The search inside one task, on column bitmaps.

A node is a pattern with the literals that may still extend it. Skipping literals one after another leaves pattern and
rows as they are, so a chain of skips is one node whose literals are sorted once; child k takes literal k and keeps the
literals behind it. What any descendant of step k loses in negative rows at least is read from suffix intersections."""

from __future__ import annotations

import time
from dataclasses import dataclass, field

import numpy as np

from .constraints import Constraint

STATIC = ("id", "neg_asc", "neg_desc", "total_asc", "growth_desc")


@dataclass(frozen=True)
class Rules:
    """stop: do not extend a member. lb: bounds over descendants. nc: drop literals that leave the negative support unchanged ("auto": where the constraint proves it sound). pos: cut on the positive support.

    length (an extension, off by default): with a length cap, r further literals can take away no more negative rows than the r that take most, which bounds the negative support where a literal and its negation are both left."""

    stop: bool = True
    lb: bool = True
    nc: str = "auto"
    pos: bool = True
    length: bool = False

    @staticmethod
    def none() -> Rules:
        return Rules(lb=False, nc="off")

    def use_nc(self, constraint: Constraint) -> bool:
        return self.nc == "on" or (self.nc == "auto" and constraint.grows_with_x())


@dataclass
class Counters:
    nodes: int = 0
    stop: int = 0
    lb: int = 0
    nc: int = 0
    pos: int = 0
    count_calls: int = 0
    words: int = 0
    candidates: int = 0
    timeout: bool = False

    def add(self, other: Counters) -> None:
        for k, v in vars(other).items():
            setattr(self, k, getattr(self, k) | v if isinstance(v, bool) else getattr(self, k) + v)


def pack_rows(rows: np.ndarray) -> np.ndarray:
    """(literals, words) bitmaps of a (rows, literals) 0/1 array."""
    if not len(rows):
        return np.zeros((rows.shape[1], 0), np.uint64)
    dense = np.pad(rows.T, ((0, 0), (0, -len(rows) % 64))).astype(np.uint8)
    return np.ascontiguousarray(np.packbits(dense, axis=1, bitorder="little")).view(np.uint64)


def least_by_length(y: int, ys: np.ndarray, more: int) -> np.ndarray:
    """For each place of the sorted literals, y less the `more` greatest losses from there on."""
    lost = y - ys
    out = np.empty(len(ys), np.int64)
    for k in range(len(ys)):
        out[k] = y - np.sort(lost[k:])[::-1][:more].sum()
    return np.maximum(out, 0)


class Side:
    """Rows of one class: a bitmap per literal and the rows' weights as bit planes. Negated columns are derived, not stored."""

    def __init__(self, item_sets, weights, n_items: int, negation: bool):
        keep = [k for k, w in enumerate(weights) if w > 0]
        dense = np.zeros((len(keep), n_items), np.uint8)
        for r, k in enumerate(keep):
            dense[r, np.asarray(item_sets[k], int)] = 1
        both = np.concatenate((dense, 1 - dense), axis=1) if negation else dense
        self.columns = pack_rows(both)
        w = np.array([weights[k] for k in keep], np.int64)
        self.total = int(w.sum())
        self.planes = [(1 << b, pack_rows((w >> b & 1)[:, None])[0]) for b in range(int(w.max()).bit_length() if len(w) else 0)]
        full = pack_rows(np.ones((len(keep), 1), np.uint8))
        self.full = full[0] if len(keep) else np.zeros(0, np.uint64)

    def weigh(self, masks: np.ndarray) -> np.ndarray:
        """Weight of each row mask of a (k, words) array."""
        out = np.zeros(len(masks), np.int64)
        for weight, plane in self.planes:
            out += weight * np.bitwise_count(masks & plane).sum(axis=1, dtype=np.int64)
        return out


def static_rank(order: str, ids: np.ndarray, x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Position of each literal in a static order, from its supports; indexed by literal."""
    with np.errstate(divide="ignore", invalid="ignore"):
        rate = np.where(y > 0, x / np.where(y > 0, y, 1), np.where(x > 0, np.inf, 0))
    keys = {"id": ids, "neg_asc": y, "neg_desc": -y, "total_asc": x + y, "growth_desc": -rate}[order.partition(":")[2]]
    out = np.zeros(int(ids.max(initial=-1)) + 1, int)
    out[ids[np.lexsort((ids, keys))]] = np.arange(len(ids))
    return out


@dataclass
class Search:
    constraint: Constraint
    n_items: int
    negation: bool = False
    order: str = "dynamic"
    rules: Rules = Rules()
    max_len: int | None = None
    timeout_s: float | None = None
    trace: list | None = None
    counters: Counters = field(default_factory=Counters)
    allowed: tuple[int, ...] | None = None  # the literals of patterns; None: all

    def literals(self) -> np.ndarray:
        return np.arange(self.n_items * (1 + self.negation)) if self.allowed is None else np.array(self.allowed, int)

    def rank(self, pos: Side, neg: Side) -> np.ndarray | None:
        """Position of each literal in a static order; none in the dynamic one."""
        ids = self.literals()
        return None if self.order == "dynamic" else static_rank(self.order, ids, pos.weigh(pos.columns[ids]), neg.weigh(neg.columns[ids]))

    def run(self, pos: Side, neg: Side, prefix=(), among=None, rank=None, limit: int | None = None):
        """Candidates (pattern, x, y) of the subtree of a prefix, whose rows are those given; every member that no cut hides, or with rules.stop the path-minimal ones."""
        c, rules, n, count = self.constraint, self.rules, self.n_items, self.counters
        nc = rules.use_nc(c)
        if rank is None:
            rank = self.rank(pos, neg)
        begin = time.monotonic()
        out: list[tuple[tuple[int, ...], int, int]] = []
        todo = [(tuple(prefix), self.literals() if among is None else np.asarray(among, int), pos.full, neg.full, None)]
        while todo:
            pattern, rest, mask_pos, mask_neg, known = todo.pop()
            if self.timeout_s is not None and time.monotonic() - begin > self.timeout_s:
                count.timeout = True
                break
            x, y = known or (int(pos.weigh(mask_pos[None])[0]), int(neg.weigh(mask_neg[None])[0]))
            count.nodes += 1
            note = lambda verdict, lb=None: self.trace is not None and self.trace.append((pattern, x, y, lb, verdict))  # noqa: E731, B023
            if bool(c.member(x, y)):
                out.append((pattern, x, y))
                count.candidates += 1
                if rules.stop:
                    count.stop += 1
                    note("STOP")
                    continue
                if limit is not None and len(out) >= limit:
                    break
            if rules.pos and (bool(c.cut(x, 0, y)) or (x == 0 and c.needs_positive())):
                count.pos += 1
                note("POS")
                continue
            if (self.max_len is not None and len(pattern) >= self.max_len) or not len(rest):
                note("END")
                continue
            part_neg = neg.columns[rest] & mask_neg
            part_pos = pos.columns[rest] & mask_pos
            ys, xs = neg.weigh(part_neg), pos.weigh(part_pos)
            count.count_calls += 2 * len(rest)
            count.words += part_neg.size + part_pos.size
            if nc:
                keep = ys < y
                count.nc += int((~keep).sum())
                rest, xs, ys, part_neg, part_pos = rest[keep], xs[keep], ys[keep], part_neg[keep], part_pos[keep]
                if not len(rest):
                    note("NC")
                    continue
            by = np.lexsort((rest, ys)) if rank is None else np.argsort(rank[rest], kind="stable")
            rest, xs, ys, part_neg, part_pos = rest[by], xs[by], ys[by], part_neg[by], part_pos[by]
            end = len(rest)
            least = None
            if rules.lb:
                suffix = np.bitwise_and.accumulate(part_neg[::-1], axis=0)[::-1]
                least = neg.weigh(suffix)
                count.words += suffix.size
                if rules.length and self.max_len is not None:
                    least = np.maximum(least, least_by_length(y, ys, self.max_len - len(pattern)))
                cut = np.flatnonzero(c.cut(np.full(end, x), least, np.full(end, y)))
                if len(cut):
                    end = int(cut[0])
                    count.lb += 1
            note("LB" if rules.lb and end == 0 else "OPEN", None if least is None else int(least[0]))
            for k in range(end - 1, -1, -1):
                i = int(rest[k])
                after = rest[k + 1 :]
                if self.negation:
                    after = after[after != (i + n if i < n else i - n)]
                todo.append((tuple(sorted((*pattern, i))), after, part_pos[k], part_neg[k], (int(xs[k]), int(ys[k]))))
        return out

    def count_jumping(self, pos: Side, neg: Side, min_pos: int, among=None) -> int:
        """How many patterns over the literals without negative rows have at least min_pos positive ones, without listing them: literals that all remaining positive rows share double the count of a branch."""
        n, total, begin = self.n_items, 0, time.monotonic()
        todo = [(self.literals() if among is None else np.asarray(among, int), pos.full, neg.full, 1)]
        while todo:
            rest, mask_pos, mask_neg, times = todo.pop()
            if self.timeout_s is not None and time.monotonic() - begin > self.timeout_s:
                self.counters.timeout = True
                break
            self.counters.nodes += 1
            x = int(pos.weigh(mask_pos[None])[0])
            if x < min_pos:
                continue
            xs = pos.weigh(pos.columns[rest] & mask_pos) if len(rest) else np.zeros(0, np.int64)
            if not mask_neg.any():
                total += times * self._supersets(pos, rest, xs, mask_pos, x, min_pos, begin)
                continue
            y = int(neg.weigh(mask_neg[None])[0])
            part = neg.columns[rest] & mask_neg
            ys = neg.weigh(part)
            times <<= int(((xs == x) & (ys == y)).sum())  # in all rows left: with or without, the rows are the same
            live = (xs >= min_pos) & ((xs < x) | (ys < y))
            rest, ys, part = rest[live], ys[live], part[live]
            by = np.lexsort((rest, ys))
            rest, part = rest[by], part[by]
            left = np.bitwise_and.accumulate(part[::-1], axis=0)[::-1].any(axis=1) if len(rest) else np.zeros(0, bool)
            end = int(np.flatnonzero(left)[0]) if left.any() else len(rest)  # from there on, a negative row holds all that follows
            for k in range(end):
                i = int(rest[k])
                after = rest[k + 1 :]
                if self.negation:
                    after = after[after != (i + n if i < n else i - n)]
                todo.append((after, mask_pos & pos.columns[i], mask_neg & neg.columns[i], times))
        return total

    def _supersets(self, pos: Side, rest, xs, mask, x: int, min_pos: int, begin: float) -> int:
        """Frequent sets of positives over the remaining literals, the empty one included; each literal that all rows hold is a factor of two. begin: when the search began, for its time limit."""
        total, todo = 0, [(rest, xs, mask, x, 1)]
        while todo:
            if self.timeout_s is not None and time.monotonic() - begin > self.timeout_s:
                self.counters.timeout = True
                break
            rest, xs, mask, x, times = todo.pop()
            times <<= int((xs == x).sum())
            total += times
            live = (xs >= min_pos) & (xs < x)
            rest, xs = rest[live], xs[live]
            for k in range(len(rest)):
                inner, after = mask & pos.columns[rest[k]], rest[k + 1 :]
                self.counters.nodes += 1
                todo.append((after, pos.weigh(pos.columns[after] & inner) if len(after) else np.zeros(0, np.int64), inner, int(xs[k]), times))
        return total
