"""Learning on patterns: discretiser with a description-length stop, pattern features, sparse linear models, folds, measures and the model baselines."""

from __future__ import annotations

import json
import math
import random
from dataclasses import dataclass, field
from functools import reduce
from typing import Any

import numpy as np
import pandas as pd
from pyspark.ml import Estimator, Model
from pyspark.ml.classification import DecisionTreeClassifier, LogisticRegression, LogisticRegressionModel, RandomForestClassifier
from pyspark.ml.feature import StandardScaler, VectorAssembler
from pyspark.ml.functions import array_to_vector
from pyspark.ml.regression import LinearRegression, LinearRegressionModel
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .constraints import Constraint, Jumping
from .labeled import Item, LabeledDB, compress, encode, item_ranges, item_sql, mask_words, pattern_masks
from .minimal import minimal_by_trie
from .mining import mine_minimal
from .relational import running_sums

CUTS = "feature int, cuts array<double>"
ROWS_AT_ONCE = 1 << 13


def mdl_cuts(values: np.ndarray, n_pos: np.ndarray, n_neg: np.ndarray, max_cuts: int | None = None) -> list[float]:
    """Cut points of one feature from its sorted distinct values and their class counts.

    The best cut has the least weighted class entropy; it is taken if its gain is beyond the description length of the
    cut, and both sides go on until no cut is worth its description. Values that tie are never parted. max_cuts, off by
    default, stops earlier, with the cuts of the widest intervals."""

    def entropies(p, q):
        n = np.maximum(p + q, 1)
        part = lambda k: np.where(k > 0, -(k / n) * np.log2(np.where(k > 0, k / n, 1)), 0.0)
        return part(p) + part(q)

    classes = lambda p, q: (p > 0).astype(int) + (q > 0)
    n_pos, n_neg = np.asarray(n_pos), np.asarray(n_neg)
    below_p, below_q = (np.concatenate(([0], np.cumsum(n))) for n in (n_pos, n_neg))
    pure = (n_pos[:-1] * n_neg[1:] == n_neg[:-1] * n_pos[1:]) & ~((n_pos[:-1] > 0) & (n_neg[:-1] > 0))  # the same pure class on both sides
    out: list[float] = []
    a, b = np.array([0]), np.array([len(values)])
    while len(a):  # the open intervals of a level, all at once
        p, q = below_p[b] - below_p[a], below_q[b] - below_q[a]
        some = (b - a > 1) & (p > 0) & (q > 0)
        a, b, p, q = a[some], b[some], p[some], q[some]
        if not len(a):
            break
        size = b - a - 1
        begin = np.cumsum(size) - size
        own = np.repeat(np.arange(len(a)), size)
        at = np.arange(len(own)) - begin[own] + a[own]
        lp, lq = below_p[at + 1] - below_p[a][own], below_q[at + 1] - below_q[a][own]
        n, rest_p, rest_q = (p + q)[own], p[own] - lp, q[own] - lq
        e = ((lp + lq) * entropies(lp, lq) + (rest_p + rest_q) * entropies(rest_p, rest_q)) / n
        e[pure[at]] = np.inf
        best = np.minimum.reduceat(e, begin)
        first = np.minimum.reduceat(np.where(e <= best[own] + 1e-12, np.arange(len(own)), len(own)), begin)
        x, y, n = lp[first], lq[first], p + q
        whole, left, right = entropies(p, q), entropies(x, y), entropies(p - x, q - y)
        c, c1, c2 = classes(p, q), classes(x, y), classes(p - x, q - y)
        good = np.flatnonzero(np.isfinite(best) & (whole - best > (np.log2(n - 1) + np.log2(3.0**c - 2) - (c * whole - c1 * left - c2 * right)) / n))
        if max_cuts is not None:
            good = good[: max(0, max_cuts - len(out))]
        cut = at[first[good]]
        out += ((np.asarray(values, float)[cut] + np.asarray(values, float)[cut + 1]) / 2).tolist()
        if max_cuts is not None and len(out) >= max_cuts:
            break
        a, b = (np.stack(ends, axis=1).ravel() for ends in ((a[good], cut + 1), (cut + 1, b[good])))
    return sorted(out)


def histogram(df: DataFrame, features: dict[str, Column], label: Column, prebins: int | None = None) -> DataFrame:
    """(feature, value, n_pos, n_neg) of all features in one aggregation. prebins: values become the upper ends of that many approximate quantiles first."""
    cells = F.explode(F.array(*(F.struct(F.lit(k).alias("feature"), c.cast("double").alias("value")) for k, c in enumerate(features.values()))))
    long = df.select(label.cast("int").alias("label"), cells.alias("x")).select("label", "x.*").where("value is not null and not isnan(value)")
    if prebins is not None:
        ends = long.groupBy("feature").agg(F.array_distinct(F.percentile_approx("value", [k / prebins for k in range(1, prebins + 1)], 10_000)).alias("ends"))
        long = long.join(F.broadcast(ends), "feature").withColumn("value", F.coalesce(F.element_at(F.filter("ends", lambda e: e >= F.col("value")), 1), F.col("value")))
    return long.groupBy("feature", "value").agg(F.sum("label").alias("n_pos"), F.sum(1 - F.col("label")).alias("n_neg"))


@dataclass
class MdlDiscretizer:
    max_cuts: int | None = None
    prebins: int | None = None
    cuts: dict[str, list[float]] = field(default_factory=dict)

    def cut_points(self, df: DataFrame, features: dict[str, Column], label: Column) -> DataFrame:
        most = self.max_cuts

        def one(key: tuple[Any, ...], frame: pd.DataFrame) -> pd.DataFrame:
            frame = frame.sort_values("value")
            found = mdl_cuts(frame["value"].to_numpy(), frame["n_pos"].to_numpy(), frame["n_neg"].to_numpy(), most)
            return pd.DataFrame({"feature": [key[0]], "cuts": [found]})

        return histogram(df, features, label, self.prebins).groupBy("feature").applyInPandas(one, CUTS)

    def fit(self, df: DataFrame, features: dict[str, Column], label: Column) -> MdlDiscretizer:
        names = list(features)
        found = {names[r.feature]: list(r.cuts) for r in self.cut_points(df, features, label).collect()}  # one row per feature
        return MdlDiscretizer(self.max_cuts, self.prebins, {n: found.get(n, []) for n in names})

    def items(self, features: dict[str, Column], sql: dict[str, str] | None = None) -> list[Item]:
        """A feature without cuts says nothing and gives no items. sql: the features as SQL, for items that are to be saved."""
        return [i for n, c in features.items() if self.cuts[n] for i in item_ranges(n, self.cuts[n], c, (sql or {}).get(n))]

    def save(self, spark, path: str) -> None:
        """One JSON row, on any file system that Spark writes."""
        told = json.dumps({"max_cuts": self.max_cuts, "prebins": self.prebins, "cuts": self.cuts})
        spark.createDataFrame([(told,)], "told string").coalesce(1).write.mode("overwrite").text(path)

    @staticmethod
    def load(spark, path: str) -> MdlDiscretizer:
        return MdlDiscretizer(**json.loads(spark.read.text(path).first().value))


def pattern_features(df: DataFrame, items: list[Item], patterns: list[tuple[int, ...]], keep: list[str]) -> DataFrame:
    """The kept columns and `features`, a vector of 0/1 indicators.

    A row's items become mask words; the patterns' masks are a few literal arrays, so the plan does not grow with them."""
    own = F.array_compact(F.array(*(F.when(F.coalesce(i.predicate, F.lit(False)), F.lit(k)) for k, i in enumerate(items)))) if items else F.array().cast("array<int>")
    words = range(len(range(0, max(1, len(items)), 62)))
    masked = df.select(*keep, own.alias("_items")).select(*keep, *(c.alias(f"_m{w}") for w, c in enumerate(mask_words(F.col("_items"), len(items)))))
    masks = pattern_masks(patterns, len(items))
    column = lambda k: F.lit([m[k] for m in masks]).cast("array<bigint>")

    def held(k: Column) -> Column:
        test = F.lit(True)
        for w in words:
            need, lack = F.get(column(1 + w), k), F.get(column(1 + len(words) + w), k)
            test = test & (F.col(f"_m{w}").bitwiseAND(need) == need) & (F.col(f"_m{w}").bitwiseAND(lack) == 0)
        return F.when(test, 1.0).otherwise(0.0)

    flags = F.transform(F.sequence(F.lit(0), F.lit(len(patterns) - 1)), held) if patterns else F.array(F.lit(0.0))
    return masked.select(*keep, array_to_vector(flags).alias("features"))


@dataclass
class PatternClassifier:
    """Items (declared, or found by the discretiser in the training rows), minimal patterns of at most max_len literals, and an L1 linear model on their indicators.

    Without patterns the model is its intercept."""

    constraint: Constraint
    max_len: int = 5
    negation: bool = True
    family: str = "logistic"
    reg: float = 0.01
    max_cuts: int | None = None
    items: list[Item] | None = None
    patterns: list[tuple[int, ...]] = field(default_factory=list)
    texts: list[str] = field(default_factory=list)
    model: Any = None

    def fit(self, train: DataFrame, features: dict[str, Column], label: str, items: list[Item] | None = None) -> PatternClassifier:
        items = items if items is not None else MdlDiscretizer(self.max_cuts).fit(train, features, F.col(label)).items(features)
        out = PatternClassifier(self.constraint, self.max_len, self.negation, self.family, self.reg, self.max_cuts, items)
        if items:
            db: LabeledDB = compress(encode(train, items, F.col(label)), [i.name for i in items], self.negation)
            rows = mine_minimal(db, self.constraint, max_len=self.max_len).select("pattern", "pattern_text").orderBy("size", "pattern_text").collect()
            out.patterns, out.texts = [tuple(r.pattern) for r in rows], [r.pattern_text for r in rows]
        data = pattern_features(train, items, out.patterns, [label]).withColumn(label, F.col(label).cast("double"))
        if self.family == "logistic":
            out.model = LogisticRegression(labelCol=label, regParam=self.reg, elasticNetParam=1.0, maxIter=50).fit(data)
        else:
            out.model = LinearRegression(labelCol=label, regParam=self.reg, elasticNetParam=1.0, maxIter=50, solver="l-bfgs").fit(data)
        return out

    def transform(self, df: DataFrame, keep: list[str]) -> DataFrame:
        told = self.model.transform(pattern_features(df, self.items, self.patterns, keep))
        if self.family == "logistic":
            return told.select(*keep, F.col("prediction").cast("int").alias("prediction"))
        return told.select(*keep, (F.col("prediction") >= 0.5).cast("int").alias("prediction"))

    def save(self, spark, path: str) -> None:
        """Items (which must have SQL), patterns and settings as one JSON row, and the linear model beside it; any file system that Spark writes."""
        if any(i.sql is None for i in self.items):
            raise ValueError("items without SQL cannot be saved")
        told = {"max_len": self.max_len, "negation": self.negation, "family": self.family, "reg": self.reg, "items": [(i.name, i.sql) for i in self.items], "patterns": self.patterns, "texts": self.texts}
        spark.createDataFrame([(json.dumps(told),)], "told string").coalesce(1).write.mode("overwrite").text(f"{path}/patterns")
        self.model.write().overwrite().save(f"{path}/model")

    @staticmethod
    def load(spark, path: str) -> PatternClassifier:
        told = json.loads(spark.read.text(f"{path}/patterns").first().value)
        loader = LogisticRegressionModel if told["family"] == "logistic" else LinearRegressionModel
        items = [item_sql(n, s) for n, s in told["items"]]
        return PatternClassifier(Jumping(), told["max_len"], told["negation"], told["family"], told["reg"], None, items, [tuple(p) for p in told["patterns"]], told["texts"], loader.load(f"{path}/model"))

    def size(self) -> dict[str, float]:
        w = self.model.coefficients.toArray()
        used = [p for p, v in zip(self.patterns, w, strict=False) if v]
        return {"weights": len(used), "mean_length": sum(map(len, used)) / len(used) if used else 0.0}


def short_members(dense: np.ndarray, w_pos: np.ndarray, w_neg: np.ndarray, c: Constraint, negation: bool, max_len: int, most: int | None = None) -> list[tuple[int, ...]]:
    """Minimal members of at most max_len literals, from 0/1 rows with class weights and a bound constraint; the answer of Search with the same cap. most: beyond so many candidates an OverflowError, and no answer.

    Rows and literals are cut to those of a prefix, literals that no member can hold go first, and the last two literals
    of a pattern are judged together, by products of matrices. Only the prefixes of one path have rows of their own at a
    time, one byte for a value; products take a block of rows at a time."""
    n, nc = dense.shape[1], c.grows_with_x()
    kind = np.float32 if max(w_pos.sum(), w_neg.sum()) < 1 << 24 else np.float64  # sums stay exact
    if bool(c.member(int(w_pos.sum()), int(w_neg.sum()))):
        return [()]
    out: list[tuple[int, ...]] = []

    def side(w):
        own = dense[w > 0].astype(np.uint8)
        return np.concatenate((own, 1 - own), axis=1) if negation else own, w[w > 0].astype(kind)

    def blocks(a, u):
        for i in range(0, len(a), ROWS_AT_ONCE):
            yield a[i : i + ROWS_AT_ONCE].astype(kind), u[i : i + ROWS_AT_ONCE]

    def sums(a, u):
        return sum((w @ x for x, w in blocks(a, u)), np.zeros(a.shape[1], kind))

    def pairs(a, u):
        return sum((x.T @ (x * w[:, None]) for x, w in blocks(a, u)), np.zeros((a.shape[1],) * 2, kind))

    def below(prefix, rest, a, u, b, v):
        """Adds the members that one literal more (two, where two are left) makes; gives the longer prefixes, each when it is asked for."""
        y, more = int(v.sum()), max_len - len(prefix)
        xs, ys = sums(a, u), sums(b, v)
        keep = ~np.asarray(c.cut(xs, np.zeros_like(ys), ys), bool)
        if nc:
            keep &= ys < y
        hit = keep & np.asarray(c.member(xs, ys), bool)
        out.extend((*prefix, int(i)) for i in rest[hit])
        keep &= ~hit
        if more < 2 or keep.sum() < 2:
            return
        kept = np.flatnonzero(keep)
        by = kept if more == 2 else kept[np.lexsort((rest[kept], ys[kept]))]
        rest, a, b, xs, ys = rest[by], a[:, by], b[:, by], xs[by], ys[by]
        if more == 2:
            x2 = pairs(a, u)
            apart = rest[:, None] % n != rest[None, :] % n
            i, j = np.nonzero(np.triu(apart & ~np.asarray(c.cut(x2, np.zeros_like(x2), np.full_like(x2, y)), bool), 1))
            if len(i):
                y2 = pairs(b, v)
                ok = np.asarray(c.member(x2[i, j], y2[i, j]), bool)
                out.extend((*prefix, int(p), int(q)) for p, q in zip(rest[i[ok]], rest[j[ok]], strict=True))
            return
        lost = np.concatenate(([0], np.cumsum(y - ys, dtype=float)))
        k = np.arange(len(rest))
        least = np.maximum(0, ys - (lost[np.minimum(k + more, len(rest))] - lost[k + 1]))  # the literals behind lose less and less
        for k in np.flatnonzero(~np.asarray(c.cut(xs, least, ys), bool)):
            after = np.flatnonzero(rest % n != rest[k] % n)
            after = after[after > k]
            in_pos, in_neg = np.flatnonzero(a[:, k]), np.flatnonzero(b[:, k])
            yield (*prefix, int(rest[k])), rest[after], a[np.ix_(in_pos, after)], u[in_pos], b[np.ix_(in_neg, after)], v[in_neg]

    todo = [below((), np.arange(n * (1 + negation)), *side(w_pos), *side(w_neg))] if max_len else []
    while todo:
        longer = next(todo[-1], None)
        if most is not None and len(out) > most:
            raise OverflowError(f"more than {most} candidates")
        if longer is None:
            todo.pop()
        else:
            todo.append(below(*longer))
            del longer
    return minimal_by_trie([tuple(sorted(p)) for p in out])


def l1_logistic(x: np.ndarray, w_pos: np.ndarray, w_neg: np.ndarray, reg: float, most_steps: int = 20_000) -> tuple[np.ndarray, float]:
    """(coefficients, intercept) of the least mean log loss plus reg times the absolute coefficients of standardised columns, from weighted rows; equal columns share their weight.

    Accelerated proximal steps with restarts, until a step changes nothing beyond 1e-7."""
    w = w_pos + w_neg
    total, share = w.sum(), w_pos.sum() / max(1, w.sum())
    if share in (0, 1):
        return np.zeros(x.shape[1]), -np.inf if share == 0 else np.inf
    mean = w @ x / total
    sd = np.sqrt(np.maximum(w @ (x - mean) ** 2, 0) / max(1, total - 1))
    live = sd > 0
    z = (x[:, live] - mean[live]) / sd[live]
    z1 = np.concatenate((z, np.ones((len(z), 1))), axis=1)
    d, y = w / total, w_pos / w
    top = np.ones(z1.shape[1])
    for _ in range(50):
        top = z1.T @ (d * (z1 @ top))
        norm = np.linalg.norm(top)
        top /= norm
    step = 1 / (0.25 * norm * 1.05)
    now = ahead = np.concatenate((np.zeros(z.shape[1]), [np.log(share / (1 - share))]))
    pace = 1.0
    for _ in range(most_steps):
        slope = z1.T @ (d * (1 / (1 + np.exp(-np.clip(z1 @ ahead, -500, 500))) - y))
        new = ahead - step * slope
        new[:-1] = np.sign(new[:-1]) * np.maximum(np.abs(new[:-1]) - step * reg, 0)
        done = np.abs(new - ahead).max() < 1e-7
        if (ahead - new) @ (new - now) > 0:
            pace = 1.0
        after = (1 + math.sqrt(1 + 4 * pace * pace)) / 2
        ahead, now, pace = new + (pace - 1) / after * (new - now), new, after
        if done:
            break
    out = np.zeros(x.shape[1])
    out[live] = now[:-1] / sd[live]
    return out, float(now[-1] - out @ mean)


def pattern_indicators(dense: np.ndarray, patterns: list[tuple[int, ...]]) -> np.ndarray:
    """0/1 columns of patterns over 0/1 rows."""
    both = np.concatenate((dense, 1 - dense), axis=1).astype(bool)
    return np.stack([both[:, list(p)].all(axis=1) for p in patterns], axis=1).astype(float) if patterns else np.zeros((len(dense), 0))


def fit_weighted(dense: np.ndarray, y: np.ndarray, w: np.ndarray, constraint_of, negation: bool, max_len: int, reg: float) -> tuple[list[tuple[int, ...]], np.ndarray, float]:
    """The logistic pattern model of PatternClassifier with declared items, in this process, from 0/1 rows with labels and weights: (patterns, coefficients, intercept)."""
    rows, own = np.unique(dense, axis=0, return_inverse=True)
    p, q = (np.bincount(own.ravel(), np.where(y == k, w, 0), len(rows)) for k in (1, 0))
    seen = p + q > 0
    rows, p, q = rows[seen], p[seen], q[seen]
    n_pos = int(p.sum())
    patterns = short_members(rows, p, q, constraint_of(n_pos).bind(n_pos, int(q.sum())), negation, max_len)
    return patterns, *l1_logistic(pattern_indicators(rows, patterns), p, q, reg)


class PatternEstimator(Estimator):
    """The pattern classifier as an estimator for pyspark.ml pipelines: named items, a label column and options; its model adds `prediction`."""

    def __init__(self, constraint: Constraint, features: dict[str, Column], label: str, items: list[Item] | None = None, **options):
        super().__init__()
        self.settings = constraint, features, label, items, options

    def _fit(self, dataset: DataFrame) -> PatternModel:
        constraint, features, label, items, options = self.settings
        return PatternModel(PatternClassifier(constraint, **options).fit(dataset, features, label, items))


class PatternModel(Model):
    def __init__(self, fitted: PatternClassifier):
        super().__init__()
        self.fitted = fitted

    def _transform(self, dataset: DataFrame) -> DataFrame:
        return self.fitted.transform(dataset, dataset.columns)


def folds(df: DataFrame, label: str, key: str, k: int = 5, seed: int = 0) -> DataFrame:
    """A stratified fold number for each row, by the rank of a hash of its key within its class.

    A class of any size is ranked without one large window: hashes are cut into ranges, and a range's rows follow the number of rows before it."""
    hashed = df.withColumn("_h", F.xxhash64(F.col(key), F.lit(seed))).withColumn("_r", F.call_function("shiftright", F.col("_h"), F.lit(54)))
    sizes = hashed.groupBy(label, "_r").agg(F.count(F.lit(1)).alias("_n"))
    before = sizes.withColumn("_b", F.sum("_n").over(Window.partitionBy(label).orderBy("_r")) - F.col("_n")).drop("_n")
    ranked = hashed.join(F.broadcast(before), [label, "_r"]).withColumn("_k", F.row_number().over(Window.partitionBy(label, "_r").orderBy("_h", key)) - 1 + F.col("_b"))
    return ranked.withColumn("fold", (F.col("_k") % k).cast("int")).drop("_h", "_r", "_b", "_k")


def confusion(df: DataFrame, label: str = "label", prediction: str = "prediction", by: list[str] | None = None) -> DataFrame:
    y, p = F.col(label), F.col(prediction)
    counts = (F.count_if((y == 1) & (p == 1)).alias("tp"), F.count_if((y == 0) & (p == 1)).alias("fp"), F.count_if((y == 1) & (p == 0)).alias("fn"), F.count_if((y == 0) & (p == 0)).alias("tn"))
    return df.groupBy(*(by or [])).agg(*counts)


def f_value(counts: DataFrame) -> DataFrame:
    """Precision, recall, their harmonic mean and accuracy; 0 where undefined."""
    ratio = lambda a, b: F.when(b > 0, a / b).otherwise(0.0)
    tp, fp, fn, tn = (F.col(c).cast("double") for c in ("tp", "fp", "fn", "tn"))
    return counts.select("*", ratio(tp, tp + fp).alias("precision"), ratio(tp, tp + fn).alias("recall"), ratio(2 * tp, 2 * tp + fp + fn).alias("f1"), ratio(tp + tn, tp + tn + fp + fn).alias("accuracy"))


def auc(df: DataFrame, score: str, label: str) -> DataFrame:
    """Area under the curve from class counts per distinct score, of any number of scores; ties count half."""
    hist = df.groupBy(score).agg(F.sum(label).alias("p"), F.sum(1 - F.col(label)).alias("q"))
    ranked = running_sums(hist, score, {"b": "q"})
    return ranked.agg((F.sum(F.col("p") * (F.col("b") - F.col("q") / 2.0)) / (F.sum("p") * F.sum("q"))).alias("auc"))


def raw_vectors(df: DataFrame, features: dict[str, Column], keep: list[str]) -> DataFrame:
    named = df.select(*keep, *(c.cast("double").alias(f"_x{k}") for k, c in enumerate(features.values())))
    return VectorAssembler(inputCols=[f"_x{k}" for k in range(len(features))], outputCol="features", handleInvalid="keep").transform(named).select(*keep, "features")


def ml_baseline(kind: str, **options):
    """A function (train, test, features, label, keep) -> predictions, on raw reals."""

    def run(train: DataFrame, test: DataFrame, features: dict[str, Column], label: str, keep: list[str]) -> DataFrame:
        a = raw_vectors(train, features, [label]).withColumn(label, F.col(label).cast("double"))
        b = raw_vectors(test, features, keep)
        if kind == "logistic":
            scale = StandardScaler(inputCol="features", outputCol="scaled").fit(a)
            a, b = scale.transform(a), scale.transform(b)
            model = LogisticRegression(labelCol=label, featuresCol="scaled", **({"maxIter": 50} | options)).fit(a)
        elif kind == "tree":
            model = DecisionTreeClassifier(labelCol=label, seed=1, **options).fit(a)
        else:
            model = RandomForestClassifier(labelCol=label, seed=1, **({"numTrees": 20} | options)).fit(a)
        return model.transform(b).select(*keep, F.col("prediction").cast("int").alias("prediction"))

    return run


def pattern_model(constraint_of, negation: bool = True, items: list[Item] | None = None, sizes: list | None = None, **options):
    """The same kind of function for the pattern classifier; constraint_of(n_pos) gives the constraint. sizes: a list that takes each fitted model's size."""

    def run(train: DataFrame, test: DataFrame, features: dict[str, Column], label: str, keep: list[str]) -> DataFrame:
        n_pos = train.where(F.col(label) == 1).count()
        fitted = PatternClassifier(constraint_of(n_pos), negation=negation, **options).fit(train, features, label, items)
        if sizes is not None:
            sizes.append(fitted.size())
        return fitted.transform(test, keep)

    return run


def held_out(own: DataFrame, label: str, features: dict[str, Column], model, k: int, keep: tuple[str, ...] = ()) -> DataFrame:
    parts = [model(own.where(F.col("fold") != f), own.where(F.col("fold") == f), features, label, ["fold", label, *keep]) for f in range(k)]
    return reduce(DataFrame.unionByName, parts)


def predictions(df: DataFrame, key: str, label: str, features: dict[str, Column], model, k: int = 5, seed: int = 0, keep: tuple[str, ...] = ()) -> DataFrame:
    """(fold, label, prediction, kept columns) of every row, each by the model that was fitted on the other folds. The folds stay cached for the lazy result."""
    return held_out(folds(df, label, key, k, seed).persist(), label, features, model, k, keep)


def cross_validate(df: DataFrame, key: str, label: str, features: dict[str, Column], model, k: int = 5, seed: int = 0) -> DataFrame:
    """(fold, tp, fp, fn, tn, precision, recall, f1, accuracy); items and patterns are learned in the training part only. Counts at once, one row per fold, and lets the folds go."""
    own = folds(df, label, key, k, seed).persist()
    counted = confusion(held_out(own, label, features, model, k), label, "prediction", ["fold"])
    rows = counted.collect()  # one row per fold
    own.unpersist()
    return f_value(df.sparkSession.createDataFrame(rows, counted.schema))


def draws(space: dict[str, list], n_trials: int, seed: int) -> list[dict]:
    """Seeded random options, repeats left out."""
    draw = random.Random(seed)
    out = [{n: draw.choice(v) for n, v in space.items()} for _ in range(n_trials)]
    return [o for k, o in enumerate(out) if o not in out[:k]]


def tune(make_model, space: dict[str, list], df: DataFrame, key: str, label: str, features: dict[str, Column], n_trials: int = 5, inner_folds: int = 3, seed: int = 0) -> tuple[dict, float]:
    """Seeded random search without repeats: the options with the best mean F-value over inner folds, the first drawn on ties."""
    best, score = {}, -1.0
    for options in draws(space, n_trials, seed):
        got = cross_validate(df, key, label, features, make_model(**options), inner_folds, seed).agg(F.avg("f1")).first()[0] or 0.0
        if got > score:
            best, score = options, got
    return best, score
