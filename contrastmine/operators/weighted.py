"""Models in one process from distinct rows with their numbers: trees, forests and logistic models as Spark trains them on the single rows, and pattern models on items cut in the training rows.

A column is its ascending distinct values and each row's number among them; rows to be predicted are parts of the same
cells. Rows beyond a task's memory stay in the shared folder and are read again for each pass. Missing values (null, NaN) lie above all
cuts for trees, are the mean for logistic models, and are in no item."""

from __future__ import annotations

import math
from collections.abc import Callable, Iterable
from dataclasses import dataclass

import numpy as np

from .learning import l1_logistic, mdl_cuts, pattern_indicators, short_members

BINS = 32
BLOCK = 1 << 17  # rows at a time


@dataclass
class Cells:
    columns: list[tuple[np.ndarray, np.ndarray]]
    y: np.ndarray
    w: np.ndarray

    @staticmethod
    def of(columns: Iterable[np.ndarray], y: np.ndarray, w: np.ndarray) -> Cells:
        made = []
        for c in columns:
            values, codes = np.unique(c, return_inverse=True)
            made.append((values.astype(float), codes.ravel().astype(np.min_scalar_type(max(0, len(values) - 1)))))
        return Cells(made, y, w)

    def some(self, rows: np.ndarray) -> Cells:
        return Cells([(v, c[rows]) for v, c in self.columns], self.y[rows], self.w[rows])

    def parts(self) -> Iterable[tuple[list[np.ndarray], np.ndarray, np.ndarray]]:
        """(numbers among the columns' values, classes, weights) of some rows at a time."""
        for i in range(0, len(self.y), BLOCK):
            yield [c[i : i + BLOCK] for _, c in self.columns], self.y[i : i + BLOCK], self.w[i : i + BLOCK]

    def numbers(self, k: int) -> tuple[np.ndarray, np.ndarray]:
        """Positives and negatives of each value of a column."""
        values, codes = self.columns[k]
        return tuple(np.bincount(codes, np.where(self.y == a, self.w, 0), len(values)) for a in (1, 0))

    def dealt(self, tables: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(rows, positives, negatives) once each column's values are replaced by the table's; equal rows are added up where their number fits a word."""
        sizes = [int(t.max(initial=0)) + 1 for t in tables]
        kind, total = np.min_scalar_type(max(sizes, default=1) - 1), math.prod(sizes)
        weights = lambda y, w: [np.where(y == a, w, 0).astype(float) for a in (1, 0)]
        if total >= 1 << 62:
            small = [t.astype(kind) for t in tables]
            found = [(np.stack([t[c] for t, c in zip(small, codes, strict=True)], axis=1), *weights(y, w)) for codes, y, w in self.parts()]
            return tuple(map(np.concatenate, zip((np.zeros((0, len(tables)), kind), np.zeros(0), np.zeros(0)), *found, strict=True)))
        steps = [math.prod(sizes[:k]) for k in range(len(sizes))]
        tables = [t.astype(np.int64) * step for t, step in zip(tables, steps, strict=True)]
        keyed = ((sum((t[c] for t, c in zip(tables, codes, strict=True)), np.zeros(len(y), np.int64)), *weights(y, w)) for codes, y, w in self.parts())
        if total > 1 << 22:
            sets, held = [(np.zeros(0, np.int64), np.zeros(0), np.zeros(0))], 0
            for one in keyed:
                sets, held = [*sets, one], held + len(one[0])
                if held > max(1 << 22, len(sets[0][0])):
                    sets, held = [added(sets)], 0
            names, p, q = added(sets)
        else:
            p, q = np.zeros(total), np.zeros(total)
            for key, a, b in keyed:
                np.add.at(p, key, a)
                np.add.at(q, key, b)
            names = np.flatnonzero(p + q)
            p, q = p[names], q[names]
        out = np.empty((len(names), len(tables)), kind, order="F")
        for k, s in enumerate(sizes):
            names, out[:, k] = np.divmod(names, s)
        return out, p, q


def added(sets: list[tuple[np.ndarray, np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct keys and the sums of their numbers."""
    key, p, q = (np.concatenate(x) for x in zip(*sets, strict=True))
    names, at = np.unique(key, return_inverse=True)
    return names, *(np.bincount(at.ravel(), v, len(names)) for v in (p, q))


@dataclass
class StoredCells(Cells):
    """Cells in files: columns have no codes, and y and w are empty. read(file) gives the codes and classes of its rows."""

    files: list[str]
    read: Callable[[str], tuple[list[np.ndarray], np.ndarray]]
    known: list | None = None

    @staticmethod
    def at(values: list[np.ndarray], files: list[str], read) -> StoredCells:
        return StoredCells([(v, None) for v in values], np.zeros(0, np.int8), np.zeros(0, np.int32), files, read)

    def parts(self):
        for name in self.files:
            codes, y = self.read(name)
            for i in range(0, len(y), BLOCK):
                yield [c[i : i + BLOCK] for c in codes], y[i : i + BLOCK], np.ones(len(y[i : i + BLOCK]), np.int32)

    def held(self) -> Cells:
        """The same in memory."""
        got = [self.read(name) for name in self.files]
        y = np.concatenate([np.zeros(0, np.int8), *(y for _, y in got)])
        columns = [(v, np.concatenate([np.zeros(0, np.min_scalar_type(max(0, len(v) - 1))), *(codes[k] for codes, _ in got)])) for k, (v, _) in enumerate(self.columns)]
        return Cells(columns, y, np.ones(len(y), np.int32))

    def numbers(self, k: int):
        if self.known is None:
            self.known = [tuple(np.zeros(len(v), np.int32) for _ in (1, 0)) for v, _ in self.columns]
            for name in self.files:
                codes, y = self.read(name)
                for (p, q), c in zip(self.known, codes, strict=True):
                    for own, n in ((c[y == 1], p), (c[y == 0], q)):
                        n += np.bincount(own, minlength=len(n)).astype(np.int32)
        return tuple(n.astype(float) for n in self.known[k])


def counts_of(told: np.ndarray, p: np.ndarray, q: np.ndarray) -> list[int]:
    """tp, fp, fn, tn of yes and no over rows with class numbers."""
    return [int(round(v)) for v in (p[told].sum(), q[told].sum(), p[~told].sum(), q[~told].sum())]


def thresholds(values: np.ndarray, n: np.ndarray, bins: int = BINS) -> np.ndarray:
    """Middles between neighbouring values, all if they are few, else those nearest to equal shares of the rows."""
    seen = (n > 0) & ~np.isnan(values)
    v, n = values[seen], n[seen]
    middle = (v[:-1] + v[1:]) / 2
    if len(v) <= bins:
        return middle
    total = np.cumsum(n)
    half, step, at, out = (total[:-1] + total[1:]) / 2, total[-1] / bins, 0, []
    for k in range(1, len(half) + 1):
        at = max(at, int(np.searchsorted(half, k * step, "right")))
        if at >= len(half):
            break
        out.append(middle[at])
        at += 1
    return np.array(out)


def grow(rows: np.ndarray, p: np.ndarray, q: np.ndarray, n_bins: list[int], depth: int, least: int = 1, draw=None) -> np.ndarray:
    """Nodes (feature or -1, last bin to the left, left, right, share of positives) of a tree by Gini gain; draw() gives the features that a node may use."""
    nodes: list[list[float]] = []

    def add(own: np.ndarray, level: int) -> int:
        a, b = p[own], q[own]
        x, y = a.sum(), b.sum()
        n, at, best, found = x + y, len(nodes), 1e-12, None
        nodes.append([-1, 0, 0, 0, x / n if n else 0.0])
        if level == depth or not x or not y:
            return at
        for f in range(rows.shape[1]) if draw is None else draw():
            if n_bins[f] < 2:
                continue
            bins = rows[own, f]
            u, v = (np.cumsum(np.bincount(bins, z, n_bins[f]))[:-1] for z in (a, b))
            s = u + v
            ok = (s >= max(least, 1)) & (n - s >= max(least, 1))
            gain = np.where(ok, 2 * (x * y / n - u * v / np.maximum(s, 1) - (x - u) * (y - v) / np.maximum(n - s, 1)) / n, -1.0)
            k = int(gain.argmax())
            if gain[k] > best:
                best, found = gain[k], (f, k)
        if found is not None:
            left = rows[own, found[0]] <= found[1]
            nodes[at][:4] = [*found, add(own[left], level + 1), add(own[~left], level + 1)]
        return at

    add(np.arange(len(rows)), 0)
    return np.array(nodes)


def shares(tree: np.ndarray, rows: np.ndarray) -> np.ndarray:
    feature, last, left, right = tree[:, :4].T.astype(int)
    at, every = np.zeros(len(rows), int), np.arange(len(rows))
    while len(every := every[feature[at[every]] >= 0]):
        now = at[every]
        at[every] = np.where(rows[every, feature[now]] <= last[now], left[now], right[now])
    return tree[at, 4]


def binned(train: Cells, test: Cells) -> tuple[list[int], tuple, tuple]:
    """(bins of each column, training rows, rows to be predicted) for trees."""
    cuts = [thresholds(v, sum(train.numbers(k))) for k, (v, _) in enumerate(train.columns)]
    tables = [np.searchsorted(c, v) for c, (v, _) in zip(cuts, train.columns, strict=True)]
    return [len(c) + 1 for c in cuts], train.dealt(tables), test.dealt(tables)


def tree_counts(train: Cells, test: Cells, kind: str, maxDepth: int = 5, minInstancesPerNode: int = 1, numTrees: int = 20, seed: int = 1, binned=binned) -> list[int]:  # noqa: N803
    """tp, fp, fn, tn of a tree or a forest. A forest's trees draw each single row a Poisson number of times, and each node a root of the features."""
    n_bins, (rows, p, q), (asked, x, y) = binned(train, test)
    if kind == "tree":
        return counts_of(shares(grow(rows, p, q, n_bins, maxDepth, minInstancesPerNode), asked) > 0.5, x, y)
    rng, told, most = np.random.default_rng(seed), np.zeros(len(asked)), math.ceil(math.sqrt(len(n_bins)))
    for _ in range(numTrees):
        a, b = rng.poisson(p), rng.poisson(q)
        drawn = np.flatnonzero(a + b)
        told += shares(grow(np.asfortranarray(rows[drawn]), a[drawn], b[drawn], n_bins, maxDepth, minInstancesPerNode, lambda: rng.permutation(len(n_bins))[:most]), asked)
    return counts_of(told / numTrees > 0.5, x, y)


def logistic(train: Cells, regParam: float = 0.0, elasticNetParam: float = 0.0, most_steps: int = 50, start: tuple | None = None) -> tuple[np.ndarray, np.ndarray, float]:  # noqa: N803
    """(means, coefficients, intercept) of the least mean log loss plus the elastic net of the coefficients of standardised columns: Newton steps, with coordinate descent where absolute values count. start: such an answer to begin from."""
    n = [sum(train.numbers(k)) for k in range(len(train.columns))]
    known = [(np.where(np.isnan(v), 0, v), np.where(np.isnan(v), 0, m)) for (v, _), m in zip(train.columns, n, strict=True)]
    mean = np.array([(v @ m) / max(1, m.sum()) for v, m in known])
    total = float(n[0].sum()) if n else float(train.w.sum())
    sd = np.sqrt([m @ (v - c) ** 2 / max(1, total - 1) for (v, m), c in zip(known, mean, strict=True)])
    live = np.flatnonzero(sd > 1e-12 * np.maximum(1, np.abs(mean)))
    share = float(train.numbers(0)[0].sum() if n else (train.w * train.y).sum()) / max(1.0, total)
    if share in (0.0, 1.0):
        return mean, np.zeros(len(mean)), -math.inf if share == 0 else math.inf
    unit = [(np.where(np.isnan(v), 0, (v - mean[k]) / sd[k]), k) for k, (v, _) in enumerate(train.columns) if sd[k] > 1e-12 * max(1, abs(mean[k]))]
    l1, l2 = regParam * elasticNetParam, regParam * (1 - elasticNetParam)
    size = len(live) + 1
    pen = lambda b: l1 * np.abs(b[:-1]).sum() + l2 / 2 * (b[:-1] @ b[:-1])

    def look(beta):
        loss, slope, curve = 0.0, np.zeros(size), np.zeros((size, size))
        for codes, y, w in train.parts():
            z = np.empty((size, len(y)))
            z[-1] = 1
            for j, (v, k) in enumerate(unit):
                np.take(v, codes[k], out=z[j])
            w = w / total
            m = beta @ z
            e = np.exp(-np.abs(m))
            h = np.where(m < 0, e, 1) / (1 + e)
            loss += float(w @ (np.log1p(e) + np.maximum(m, 0) - y * m))
            slope += z @ (w * (h - y))
            curve += z @ (z * (w * h * (1 - h))).T
        return loss + pen(beta), slope, curve + 1e-10 * np.eye(size)

    beta = np.concatenate((np.zeros(len(live)), [math.log(share / (1 - share))]) if start is None else (start[1][live] * sd[live], [start[2]]))
    loss, slope, curve = look(beta)
    ridge = np.diag([l2] * len(live) + [0.0])
    for _ in range(most_steps):
        move = np.linalg.solve(curve + ridge, -(slope + ridge @ beta))
        if l1:
            move = np.zeros(size)
            full, start = curve + ridge, slope + ridge @ beta
            for _ in range(1000):
                before = move.copy()
                for j in range(size):
                    lean = beta[j] + move[j] - (start[j] + full[j] @ move) / full[j, j]
                    move[j] = (lean if j == size - 1 else np.sign(lean) * max(0.0, abs(lean) - l1 / full[j, j])) - beta[j]
                if np.abs(move - before).max() < 1e-10:
                    break
        part = 1.0
        while (new := look(beta + part * move))[0] > loss + 1e-15 and part > 1e-6:
            part /= 2
        if new[0] > loss:
            break
        beta, gain, (loss, slope, curve) = beta + part * move, loss - new[0], new
        if gain <= 1e-12 * max(1.0, loss):
            break
    out = np.zeros(len(mean))
    out[live] = beta[:-1] / sd[live]
    return mean, out, float(beta[-1])


def coarse(bins: list[int], rows: np.ndarray, p: np.ndarray, q: np.ndarray, train: Cells) -> Cells:
    """The training rows with each value replaced by the mean of its bin, a row for each combination: where a descent on all rows may start."""
    columns = []
    for k, s in enumerate(bins):
        values, codes = train.columns[k][0], rows[:, k]
        n = sum(train.numbers(k))
        own = np.searchsorted(thresholds(values, n), values)
        known = ~np.isnan(values)
        mass = np.bincount(own[known], n[known], s)
        columns.append((np.bincount(own[known], (values * n)[known], s) / np.maximum(mass, 1), np.tile(codes, 2)))
    return Cells(columns, np.repeat([1, 0], len(rows)).astype(np.int8), np.concatenate((p, q)))


def logistic_counts(train: Cells, test: Cells, start: tuple | None = None, **options) -> list[int]:
    mean, weights, intercept = logistic(train, start=start, **options)
    unit, out = [w * np.where(np.isnan(v), 0, v - m) for (v, _), m, w in zip(test.columns, mean, weights, strict=True)], np.zeros(4)
    for codes, y, w in test.parts():
        told = sum((u[c] for u, c in zip(unit, codes, strict=True)), np.full(len(y), intercept))
        out += counts_of(told > 0, *(np.where(y == a, w, 0) for a in (1, 0)))
    return [int(v) for v in out]


def item_tables(train: Cells) -> tuple[list[np.ndarray], list[int]]:
    """For each column its values' intervals (0: missing) and their number, by the discretiser's cuts; a column without cuts has none."""
    tables, sizes = [], []
    for k, (v, _) in enumerate(train.columns):
        p, q = train.numbers(k)
        seen = (p + q > 0) & ~np.isnan(v)
        cuts = mdl_cuts(v[seen], p[seen], q[seen])
        tables.append(np.where(np.isnan(v), 0, np.searchsorted(cuts, v) + 1) if cuts else np.zeros(len(v), int))
        sizes.append(len(cuts) + 1 if cuts else 0)
    return tables, sizes


def one_hot(rows: np.ndarray, sizes: list[int]) -> np.ndarray:
    out = np.zeros((len(rows), sum(sizes)), np.uint8)
    begin = 0
    for k, s in enumerate(sizes):
        for j in range(s):
            out[:, begin + j] = rows[:, k] == j + 1
        begin += s
    return out


def marginal(dense: np.ndarray, p: np.ndarray, q: np.ndarray, c, negation: bool, most_len: int, lost: float) -> bool:
    """Whether a pattern of at most most_len literals is no member, but could hold one if `lost` negative rows were taken away."""
    both = np.concatenate((dense, 1 - dense), axis=1).astype(bool) if negation else dense.astype(bool)
    n = dense.shape[1]
    todo = [((), np.ones(len(dense), bool))]
    while todo:
        pattern, own = todo.pop()
        x, y = p[own].sum(), q[own].sum()
        if x < c.least_positive() or bool(c.member(x, y)):
            continue
        if not bool(c.cut(x, max(0, y - lost), y)):
            return True
        if len(pattern) < most_len:
            todo += [((*pattern, i), own & both[:, i]) for i in range(pattern[-1] + 1 if pattern else 0, both.shape[1]) if i % n not in {j % n for j in pattern}]
    return False


def without_rare(train: Cells, items, c, negation: bool, max_len: int, spare: int = 64):
    """Items without the intervals that have too few positive rows for any member; None where one's negation might stand in a minimal member.

    A member without these literals would not do: taking away the rows of max_len such intervals, those with the most
    negative rows, must turn no other pattern into a member."""
    tables, sizes = items
    kept, counts, lost = [], [], []
    each = [[np.bincount(t, n, s + 1)[1:] for n in train.numbers(k)] for k, (t, s) in enumerate(zip(tables, sizes, strict=True))]
    light = np.sort(np.concatenate([y[x < c.least_positive()] for x, y in each]))[:-spare][-1:]  # but for the `spare` heaviest ones, which stay
    for (x, y), t in zip(each, tables, strict=True):
        enough = (x >= c.least_positive()) | (y > light.max(initial=-1))
        lost += np.sort(y[~enough])[-max_len:].tolist()
        new = np.concatenate(([0], np.where(enough, np.cumsum(enough), 0)))
        kept.append(new[t])
        counts.append(int(enough.sum()))
    rows, p, q = train.dealt(kept)
    if not c.grows_with_x() or negation and lost and marginal(one_hot(rows, counts), p, q, c, negation, max_len - 1, sum(sorted(lost)[-max_len:])):
        return None
    return kept, counts


def pattern_counts(train: Cells, test: Cells, items, constraint_of, negation: bool, max_len: int, reg: float, most: int = 1 << 24, wide: int = 1 << 10) -> tuple[list[int] | None, int | None, float | None]:
    """(counts, weights, mean length) of a pattern model; items: item_tables(train). None where candidates times rows are beyond `most`: no model, which is for Spark jobs then. With more than `wide` items, those that no minimal member holds go first."""
    n_pos, n_neg = (int(n.sum()) for n in train.numbers(0)) if items[1] else (0, 0)
    constraint = constraint_of(n_pos).bind(n_pos, n_neg)
    if sum(items[1]) > wide and (items := without_rare(train, items, constraint, negation, max_len)) is None:
        return None, None, None
    tables, sizes = items
    rows, p, q = train.dealt(tables)
    if len(rows) * sum(sizes) > most << 3:
        return None, None, None
    dense = one_hot(rows, sizes)
    try:
        patterns = short_members(dense, p.astype(np.int64), q.astype(np.int64), constraint, negation, max_len, most // max(1, len(dense))) if sum(sizes) else []
    except OverflowError:
        return None, None, None
    if len(patterns) * len(dense) > most:
        return None, None, None
    weights, intercept = l1_logistic(pattern_indicators(dense, patterns), p, q, reg)
    used = [k for k in range(len(patterns)) if weights[k]]
    asked, x, y = test.dealt(tables)
    told = pattern_indicators(one_hot(asked, sizes), [patterns[k] for k in used]) @ weights[used] + intercept > 0
    return counts_of(told, x, y), len(used), sum(len(patterns[k]) for k in used) / len(used) if used else 0.0
