"""The constraint algebra: membership, SQL, bounds over descendants, and the proof that lets the unchanged-negative rule be used.

A constraint judges a pattern by its support counts only: x of np positive and y of nn negative rows. Its methods take
numpy arrays or numbers. Growth rate is a ratio of raw counts unless it is asked to normalise by class size; x over zero is
infinite for x > 0, and zero over zero is 0."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


def chi_square(x, y, n_pos, n_neg):
    """Of the 2x2 table of pattern and class; 0 where a margin is 0."""
    x, y = np.asarray(x, float), np.asarray(y, float)
    n = n_pos + n_neg
    spread = (x + y) * (n - x - y) * (float(n_pos) * n_neg)
    with np.errstate(divide="ignore", invalid="ignore"):
        return np.where(spread > 0, n * (x * n_neg - y * n_pos) ** 2 / np.where(spread > 0, spread, 1), 0.0)


def one_sided_chi_square(x, y, n_pos, n_neg):
    return np.where(np.asarray(x, float) * n_neg >= np.asarray(y, float) * n_pos, chi_square(x, y, n_pos, n_neg), 0.0)


def entropy(a, b):
    n = np.asarray(a, float) + b
    with np.errstate(divide="ignore", invalid="ignore"):
        part = lambda k: np.where(np.asarray(k) > 0, -(k / np.where(n > 0, n, 1)) * np.log2(np.where(np.asarray(k) > 0, k / np.where(n > 0, n, 1), 1)), 0.0)
        return part(np.asarray(a, float)) + part(np.asarray(b, float))


def info_gain(x, y, n_pos, n_neg):
    x, y = np.asarray(x, float), np.asarray(y, float)
    n = float(n_pos + n_neg)
    return entropy(n_pos, n_neg) - (x + y) / n * entropy(x, y) - (n - x - y) / n * entropy(n_pos - x, n_neg - y)


def gini(a, b):
    n = np.asarray(a, float) + b
    p = np.asarray(a, float) / np.where(n > 0, n, 1)
    return np.where(n > 0, 2 * p * (1 - p), 0.0)


def gini_gain(x, y, n_pos, n_neg):
    x, y = np.asarray(x, float), np.asarray(y, float)
    n = float(n_pos + n_neg)
    return gini(n_pos, n_neg) - (x + y) / n * gini(x, y) - (n - x - y) / n * gini(n_pos - x, n_neg - y)


def weighted_accuracy(x, y, n_pos, n_neg):
    n = float(n_pos + n_neg)
    return np.asarray(x, float) / n - (np.asarray(x, float) + y) / n * (n_pos / n)


def support_difference(x, y, n_pos, n_neg):
    return np.asarray(x, float) / n_pos - np.asarray(y, float) / n_neg


SCORES = {"chi2": chi_square, "chi2_one_sided": one_sided_chi_square, "info_gain": info_gain, "gini_gain": gini_gain, "wracc": weighted_accuracy, "support_diff": support_difference}
ONE_SIDED = {"chi2_one_sided", "wracc", "support_diff"}  # never fall when x grows at fixed y


def score_sql(name: str, x="x", y="y", n_pos="np", n_neg="nn") -> str:
    """The score as SQL that Spark and DuckDB both read; counts are cast to DOUBLE."""
    x, y, p, q = (f"CAST({v} AS DOUBLE)" for v in (x, y, n_pos, n_neg))
    n = f"({p} + {q})"
    h = lambda a, b: f"(CASE WHEN {a} > 0 THEN -({a} / ({a} + {b})) * ln({a} / ({a} + {b})) / ln(2.0) ELSE 0.0 END + CASE WHEN {b} > 0 THEN -({b} / ({a} + {b})) * ln({b} / ({a} + {b})) / ln(2.0) ELSE 0.0 END)"
    g = lambda a, b: f"(CASE WHEN {a} + {b} > 0 THEN 2 * ({a} / ({a} + {b})) * ({b} / ({a} + {b})) ELSE 0.0 END)"
    if name in ("chi2", "chi2_one_sided"):
        chi = f"(CASE WHEN ({x} + {y}) > 0 AND {n} - {x} - {y} > 0 AND {p} > 0 AND {q} > 0 THEN {n} * ({x} * {q} - {y} * {p}) * ({x} * {q} - {y} * {p}) / (({x} + {y}) * ({n} - {x} - {y}) * ({p} * {q})) ELSE 0.0 END)"
        return chi if name == "chi2" else f"(CASE WHEN {x} * {q} >= {y} * {p} THEN {chi} ELSE 0.0 END)"
    if name in ("info_gain", "gini_gain"):
        f = h if name == "info_gain" else g
        rest = f"({p} - {x})", f"({q} - {y})"
        return f"({f(p, q)} - ({x} + {y}) / {n} * {f(x, y)} - ({n} - {x} - {y}) / {n} * {f(*rest)})"
    if name == "wracc":
        return f"({x} / {n} - ({x} + {y}) / {n} * ({p} / {n}))"
    return f"({x} / {p} - {y} / {q})"


class Constraint:
    def __and__(self, other: Constraint) -> Constraint:
        return Both(self, other)

    def bind(self, n_pos: int, n_neg: int) -> Constraint:
        """Fix the class sizes."""
        self.n_pos, self.n_neg = n_pos, n_neg
        return self

    def member(self, x, y):
        raise NotImplementedError

    def sql(self, x="x", y="y", n_pos="np", n_neg="nn") -> str:
        raise NotImplementedError

    def cut(self, most_x, least_y, y):
        """No descendant can be a member, whose counts lie in [0, most_x] and [least_y, y]."""
        raise NotImplementedError

    def needs_positive(self) -> bool:
        """Patterns without positive rows are never members."""
        raise NotImplementedError

    def grows_with_x(self) -> bool:
        """At fixed y, a member stays one when x grows: the proof that literals which leave y unchanged can be dropped."""
        raise NotImplementedError

    def convex(self) -> bool:
        """Testing immediate subsets suffices for minimality."""
        return False

    def least_positive(self) -> int:
        """Positive rows that every member has."""
        return 0


@dataclass
class Contrast(Constraint):
    min_pos: int = 1
    max_neg: int = 0

    def member(self, x, y):
        return (np.asarray(x) >= self.min_pos) & (np.asarray(y) <= self.max_neg)

    def sql(self, x="x", y="y", n_pos="np", n_neg="nn"):
        return f"({x} >= {self.min_pos} AND {y} <= {self.max_neg})"

    def cut(self, most_x, least_y, y):
        return (np.asarray(most_x) < self.min_pos) | (np.asarray(least_y) > self.max_neg)

    def needs_positive(self):
        return self.min_pos >= 1

    def grows_with_x(self):
        return True

    def convex(self):
        return True

    def least_positive(self):
        return max(0, self.min_pos)


def Jumping(min_pos: int = 1) -> Contrast:
    return Contrast(min_pos, 0)


@dataclass
class GrowthRate(Constraint):
    theta: float = 1.0
    normalize: bool = False

    def _theta(self) -> float:
        return self.theta * self.n_pos / self.n_neg if self.normalize and self.n_neg else self.theta

    def member(self, x, y):
        x, y = np.asarray(x, float), np.asarray(y, float)
        return np.where(y > 0, x >= self._theta() * y, (x > 0) | (self.theta <= 0))

    def sql(self, x="x", y="y", n_pos="np", n_neg="nn"):
        scale = f" * CAST({n_pos} AS DOUBLE) / CAST({n_neg} AS DOUBLE)" if self.normalize else ""
        return f"(CASE WHEN {y} > 0 THEN CAST({x} AS DOUBLE) >= {self.theta!r}{scale} * {y} ELSE {x} > 0 OR {self.theta!r} <= 0 END)"

    def cut(self, most_x, least_y, y):
        most_x, least_y = np.asarray(most_x, float), np.asarray(least_y, float)
        return (most_x < self._theta() * least_y) | ((most_x == 0) & (self.theta > 0))

    def needs_positive(self):
        return self.theta > 0

    def grows_with_x(self):
        return True


@dataclass
class Score(Constraint):
    name: str = "chi2"
    min_score: float = 0.0

    def value(self, x, y):
        return SCORES[self.name](x, y, self.n_pos, self.n_neg)

    def member(self, x, y):
        return self.value(x, y) >= self.min_score

    def sql(self, x="x", y="y", n_pos="np", n_neg="nn"):
        return f"({score_sql(self.name, x, y, n_pos, n_neg)} >= {self.min_score!r})"

    def most(self, most_x, least_y, y):
        """The bound of a convex score, which peaks at a corner of the rectangle of reachable counts."""
        zero = np.zeros_like(np.asarray(most_x, float))
        return np.maximum.reduce([self.value(a, b) for a in (zero, most_x) for b in (least_y, y)])

    def cut(self, most_x, least_y, y):
        return self.most(most_x, least_y, y) < self.min_score

    def needs_positive(self):
        return False

    def grows_with_x(self):
        return self.name in ONE_SIDED


def ChiSquare(min_score: float) -> Score:
    return Score("chi2", min_score)


@dataclass
class Both(Constraint):
    a: Constraint
    b: Constraint

    def bind(self, n_pos, n_neg):
        self.n_pos, self.n_neg = n_pos, n_neg
        self.a.bind(n_pos, n_neg)
        self.b.bind(n_pos, n_neg)
        return self

    def parts(self) -> list[Constraint]:
        return [p for c in (self.a, self.b) for p in (c.parts() if isinstance(c, Both) else [c])]

    def member(self, x, y):
        return self.a.member(x, y) & self.b.member(x, y)

    def sql(self, *names, **named):
        return f"({self.a.sql(*names, **named)} AND {self.b.sql(*names, **named)})"

    def cut(self, most_x, least_y, y):
        return self.a.cut(most_x, least_y, y) | self.b.cut(most_x, least_y, y)

    def needs_positive(self):
        return self.a.needs_positive() or self.b.needs_positive()

    def grows_with_x(self):
        """Two-sided scores of this kind vanish on the line of equal shares and rise away from it: beyond a growth rate of at least n_pos / n_neg they grow with x."""
        parts = self.parts()
        rates = [p._theta() for p in parts if isinstance(p, GrowthRate)]
        right = self.n_neg > 0 and any(t >= self.n_pos / self.n_neg for t in rates)
        return all(p.grows_with_x() or (isinstance(p, Score) and right) for p in parts)

    def convex(self):
        return self.a.convex() and self.b.convex()

    def least_positive(self):
        return max(self.a.least_positive(), self.b.least_positive())
