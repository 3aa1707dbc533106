"""The experiments: ablation of rules and orders, competitors, dataset statistics, accuracy, scale-out.

The first two compare single-threaded searches, as their figures are CPU seconds: every setting of the grid is one task
over the same rows, which are broadcast within a checked bound, and tells its own CPU seconds and counters."""

from __future__ import annotations

import time
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from itertools import combinations

import numpy as np
import pandas as pd
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.scratch import clear_scratch, fresh_path, scratch_mark, stored
from ..operators import baselines, dealing, learning, mining, weighted
from ..operators.branching import search_matrices
from ..operators.constraints import Contrast, GrowthRate, Jumping
from ..operators.kernel import STATIC, Rules, Search, Side
from ..operators.labeled import Item, LabeledDB, profile
from ..operators.matrix import BACK_ENDS
from ..operators.minimal import minimal_by_trie
from ..sources.workloads import LABELLED, WORKLOADS, _bind, build, dialect, flagged_documents, min_support, read
from .meters import Meter

ANY = 1 << 40
SHARES = (0.02, 0.05, 0.1, 0.2)
ORDERS = ("dynamic", *(f"static:{s}" for s in STATIC))
CELLS = {"lb+nc": Rules(), "lb": Rules(nc="off"), "nc": Rules(lb=False), "none": Rules.none()}


def by_setting(db: LabeledDB, settings: list[tuple], work: Callable, schema: str, most_bytes: int = mining.LOCAL_BYTES) -> DataFrame:
    """work(rows, setting) -> result rows, for each setting in a task of its own. The distinct rows go to all tasks by broadcast; an error beyond the bound."""
    spark = db.rows.sparkSession
    n_distinct = db.measure()[2]
    if n_distinct * (db.n_items * (1 + db.negation) // 8 + 64) > most_bytes:
        raise ValueError("too many distinct rows for single tasks; use mine_minimal with engine='hybrid'")
    rows = [([int(i) for i in r["items"]], int(r.w_pos), int(r.w_neg)) for r in db.rows.collect()]
    held = spark.sparkContext.broadcast(tuple(zip(*rows, strict=True)) if rows else ([], [], []))

    def task(frames):
        for frame in frames:
            for k in frame["setting"]:
                out = work(held.value, settings[int(k)])
                yield pd.DataFrame(out, columns=[c.split()[0] for c in schema.split(", ")])

    return spark.createDataFrame([(k,) for k in range(len(settings))], "setting int").repartition(max(1, len(settings))).mapInPandas(task, schema)


ABLATION = "workload string, share double, order string, rules string, nc_used boolean, min_pos long, theta double, nodes long, cut_stop long, cut_lb long, dropped_nc long, cut_pos long, count_calls long, words long, candidates long, minimal long, cpu_s double, status string"


def ablation(spark: SparkSession, sf_dir: str, name: str, negation: bool = False, theta: float = 9.0, shares=SHARES, orders=ORDERS, cells=tuple(CELLS), max_len: int | None = None, timeout_s: float = 3600.0) -> DataFrame:
    """Minimal patterns of growth rate theta: every order with every set of rules, for each support share. One row per run; a run beyond its time is a row too."""
    db = build(spark, sf_dir, name, negation).persist()
    n, literals, sizes = db.n_items, tuple(db.literals()), db.sizes()

    def work(rows, setting):
        share, least, order, cell = setting
        begin = time.process_time()
        c = (Contrast(least, ANY) & GrowthRate(theta)).bind(*sizes)
        s = Search(c, n, negation, order, CELLS[cell], max_len, timeout_s, allowed=literals)
        sets, p, q = rows
        found = s.run(Side(sets, p, n, negation), Side(sets, q, n, negation))
        k = s.counters
        kept = None if k.timeout else len(minimal_by_trie([f[0] for f in found]))
        return [(name, share, order, cell, CELLS[cell].use_nc(c), least, theta, k.nodes, k.stop, k.lb, k.nc, k.pos, k.count_calls, k.words, k.candidates, kept, round(time.process_time() - begin, 4), "timeout" if k.timeout else "ok")]

    settings = [(s, min_support(db, s, 2), o, c) for s in shares for o in orders for c in cells]
    out = by_setting(db, settings, work, ABLATION)
    db.rows.unpersist()
    return out


COMPETITORS = "workload string, share double, min_pos long, task string, method string, patterns string, cpu_s double, status string"


def _ours(rows, n, negation, literals, least, timeout_s):
    s = Search(Jumping(least).bind(sum(rows[1]), sum(rows[2])), n, negation, timeout_s=timeout_s, allowed=literals)
    found = s.run(Side(rows[0], rows[1], n, negation), Side(rows[0], rows[2], n, negation))
    return None if s.counters.timeout else len(minimal_by_trie([f[0] for f in found]))


def _ours_matrix(rows, n, negation, literals, least, timeout_s):
    s = Search(Jumping(least).bind(sum(rows[1]), sum(rows[2])), n, negation, timeout_s=timeout_s, allowed=literals)
    found = search_matrices(s, *rows, "linked")
    return None if s.counters.timeout else len(minimal_by_trie([f[0] for f in found]))


def _ours_all(rows, n, negation, literals, least, timeout_s):
    s = Search(Jumping(least).bind(sum(rows[1]), sum(rows[2])), n, negation, timeout_s=timeout_s, allowed=literals)
    found = s.count_jumping(Side(rows[0], rows[1], n, negation), Side(rows[0], rows[2], n, negation), least)
    return None if s.counters.timeout else found


def _places(occ, literals) -> dict[int, int]:
    order = sorted(literals, key=lambda i: (len(occ.at[i]), i))
    return {i: k for k, i in enumerate(order)}


def _depth_first_all(rows, n, negation, literals, least, timeout_s):
    occ = baselines.Occurrences(*rows, n, literals)
    x, y = sum(rows[1]), sum(rows[2])
    return int(y == 0 and x >= least) + baselines.weighted_patterns(occ, _places(occ, literals), least, None, None, baselines.Timer(timeout_s), False)


def _prefix_tree(rows, n, negation, literals, least, timeout_s):
    timer = baselines.Timer(timeout_s)
    occ = baselines.Occurrences(*rows, n, literals)
    told = {i: occ.support(occ.at[i]) for i in literals}
    by_rank = baselines.ratio_places({i: v[0] for i, v in told.items()}, {i: v[1] for i, v in told.items()})
    rank, tree = {i: k for k, i in enumerate(by_rank)}, baselines.TreeNode()
    for row, p, q in zip(occ.rows, rows[1], rows[2], strict=True):
        tree.n_pos += p
        tree.n_neg += q
        tree.insert(sorted(rank[i] for i in row), p, q)
    return len(minimal_by_trie([f[0] for f in baselines.tree_patterns(tree, (), by_rank, least, None, timer)]))


def _diagram(rows, n, negation, literals, least, timeout_s):
    return len(baselines.diagram_patterns(*rows, n, negation, literals, least, baselines.Timer(timeout_s)))


METHODS = {
    ("minimal", "ours"): _ours, ("minimal", "ours on matrices"): _ours_matrix, ("minimal", "prefix tree"): _prefix_tree, ("minimal", "decision diagram"): _diagram,
    ("all", "ours"): _ours_all, ("all", "depth-first, weighted"): _depth_first_all,
}


def competitors(spark: SparkSession, sf_dir: str, workloads: list[str], negation: bool = False, shares=SHARES, timeout_s: float = 3600.0) -> DataFrame:
    """Minimal jumping patterns, and the number of all, by every method from the same weighted rows: patterns, CPU seconds, status, and the ratio to ours on the minimal ones.

    A method beyond its time is a row with status timeout, whose ratio is a lower bound."""
    out = None
    for name in workloads:
        db = build(spark, sf_dir, name, negation).persist()
        n, literals = db.n_items, tuple(db.literals())

        def work(rows, setting, name=name, n=n, literals=literals):
            share, least, key = setting
            begin = time.process_time()
            try:
                got = METHODS[key](rows, n, negation, literals, least, timeout_s)
            except TimeoutError:
                got = None
            return [(name, share, least, *key, None if got is None else str(got), round(time.process_time() - begin, 4), "timeout" if got is None else "ok")]

        part = by_setting(db, [(s, min_support(db, s, 2), k) for s in shares for k in METHODS], work, COMPETITORS)
        db.rows.unpersist()
        out = part if out is None else out.unionByName(part)
    ours = F.max(F.when((F.col("task") == "minimal") & (F.col("method") == "ours"), F.col("cpu_s"))).over(Window.partitionBy("workload", "share"))
    return out.withColumn("ratio_to_ours", F.round(F.col("cpu_s") / F.greatest(ours, F.lit(0.001)), 3))


def dataset_statistics(spark: SparkSession, sf_dir: str, workloads: list[str], negation: bool = False, share: float = 0.02, max_len: int | None = None) -> DataFrame:
    """Size, density, numbers of jumping and minimal jumping patterns, and their ratio, as decimal strings where numbers can be very large."""
    out = None
    for name in workloads:
        db = build(spark, sf_dir, name, negation).persist()
        least = min_support(db, share, 1)
        total = int(mining.count_jeps(db, least).first().n_jeps)
        sjeps = mining.mine_sjeps(db, least, max_len=max_len).count()
        row = profile(db).select(F.lit(name).alias("workload"), "*", F.lit(least).alias("min_pos"), F.lit(str(total)).alias("n_jeps"), F.lit(sjeps).alias("n_sjeps"), F.lit(total / sjeps if sjeps else None).cast("double").alias("reduction"))
        out = row if out is None else out.unionByName(row)
    return out


RAW = {
    "planted": {"quantity": "l_quantity", "price": "l_extendedprice", "discount": "l_discount", "tax": "l_tax", "line": "l_linenumber", "status": "case when l_linestatus = 'O' then 1 else 0 end"},
    "customers": {"orders": "n_orders", "spent": "spent", "nation": "c_nationkey", "region": "n_regionkey"},
    "embeddings": {f"d{k}": f"element_at(embedding, {k + 1})" for k in range(64)},
}


def labelled_rows(spark: SparkSession, sf_dir: str, name: str):
    """A workload's rows with a key and the label, its items (None where they are cut from real values), and numeric features for the raw baselines."""
    w = WORKLOADS[name]
    family = "embeddings" if name.startswith("embeddings") else name
    if w.source == LABELLED and family not in RAW:
        df = flagged_documents(spark, sf_dir, w)
        flags = {n: F.col(f"_b{k}") for k, (n, _) in enumerate(w.items)}
        return df.withColumn("key", F.col("doc_id")), [Item(n, c) for n, c in flags.items()], {n: c.cast("double") for n, c in flags.items()}
    df = spark.sql(f"select *, cast({dialect(w.label, True)} as int) y from {_bind(spark, sf_dir, w)}").where("y is not null")
    key = next((F.col(c) for c in ("doc_id", "vec_id", "c_custkey", "page_id") if c in df.columns), F.xxhash64(*df.columns))
    items = [Item(n, F.expr(dialect(s, True))) for n, s in w.items]
    if family in RAW:
        features = {n: F.expr(e).cast("double") for n, e in RAW[family].items()}
    else:
        features = {i.name: F.coalesce(i.predicate, F.lit(False)).cast("double") for i in items}
    return df.withColumn("key", key), None if family in ("planted", "embeddings") else items, features


SPACES = {
    "with_negation": {"reg": [0.001, 0.01, 0.03], "theta": [2.0, 3.0, 6.0], "share": [0.02, 0.05, 0.1]},
    "tree": {"maxDepth": [3, 5, 8], "minInstancesPerNode": [1, 5]},
    "logistic": {"regParam": [0.0, 0.01, 0.1], "elasticNetParam": [0.0, 1.0]},
    "forest": {"numTrees": [10, 20, 40], "maxDepth": [5, 8]},
}
SPACES["positive_only"] = SPACES["with_negation"]
MODELS = ("with_negation", "positive_only", "tree", "logistic", "forest")


def model_maker(kind: str, items: list[Item] | None, max_len: int = 5, sizes: list | None = None):
    if kind in ("tree", "logistic", "forest"):
        return lambda **options: learning.ml_baseline(kind, **options)
    return lambda reg=0.01, theta=3.0, share=0.05: learning.pattern_model(pattern_constraint(theta, share), kind == "with_negation", items, sizes, max_len=max_len, reg=reg)


COUNTED = "workload string, model string, fold int, y int, prediction int, n long"
MODEL = "workload string, model string, fold int, options string, weights int, mean_length double"
FITTED = "setting int, counts array<long>, weights int, mean_length double"
MOST_CELLS = 1 << 24  # 0/1 values that one task takes
MOST_BYTES = 3 << 26  # of distinct values, and of rows, that one task holds
FEW_ROWS = 1 << 20  # up to so many a logistic model needs no start from coarse values
OURS = ("with_negation", "positive_only")


def pattern_constraint(theta: float = 3.0, share: float = 0.05):
    return lambda n_pos: Contrast(max(2, int(share * n_pos)), ANY) & GrowthRate(theta, True)


def deal_inner(own: DataFrame, folds: int, inner_folds: int) -> DataFrame:
    """Columns _in0, _in1, ...: the inner folds of the training part of each fold, null in its test part; the same that tune() deals.

    One table is written for all folds: a rank within a range of hashes follows the number of rows in the ranges before."""
    spark = own.sparkSession
    hashes = [F.xxhash64(F.col("key"), F.lit(f)) for f in range(folds)]
    part = lambda h: F.call_function("shiftright", h, F.lit(54)).cast("int")
    each = F.explode(F.array(*(F.struct(F.lit(f).alias("_of"), part(h).alias("_r")) for f, h in enumerate(hashes))))
    sizes = own.select("y", "fold", each.alias("x")).where("fold <> x._of").groupBy("y", "x._of", "x._r").agg(F.count(F.lit(1)).alias("_n"))
    before = sizes.select("y", "_of", "_r", (F.sum("_n").over(Window.partitionBy("y", "_of").orderBy("_r")) - F.col("_n")).alias("_b"))
    before = spark.createDataFrame(before.collect(), before.schema)  # at most 1,024 ranges per class and fold
    for f, h in enumerate(hashes):
        ranked = own.withColumns({"_h": h, "_r": part(h), "_t": F.col("fold") != f}).join(F.broadcast(before.where(F.col("_of") == f).drop("_of")), ["y", "_r"], "left")
        rank = F.row_number().over(Window.partitionBy("_t", "y", "_r").orderBy("_h", "key")) - 1 + F.col("_b")
        own = ranked.withColumn(f"_in{f}", F.when(F.col("_t"), rank % inner_folds).cast("int")).drop("_h", "_r", "_t", "_b")
    return stored(own, "folds")


def fit_in_tasks(spark: SparkSession, held, settings: list[tuple]) -> list:
    """(counts, weights, mean length) of each setting (negation, fold, inner fold or None, options, length cap): a model fitted in a task of its own on the rows outside the fold; counts: tp, fp, fn, tn within it."""

    def fit(setting):
        negation, fold, inner, options, max_len = setting
        dense, y, w, dealt, ins = held.value
        train, test = (dealt != fold, dealt == fold) if inner is None else ((dealt != fold) & (ins[:, fold] != inner), (dealt != fold) & (ins[:, fold] == inner))
        o = {"theta": 3.0, "share": 0.05, "reg": 0.01} | options
        patterns, coefficients, intercept = learning.fit_weighted(dense[train], y[train], w[train], pattern_constraint(o["theta"], o["share"]), negation, max_len, o["reg"])
        used = [k for k in range(len(patterns)) if coefficients[k]]
        told = learning.pattern_indicators(dense[test], [patterns[k] for k in used]) @ coefficients[used] + intercept > 0
        counts = [int(w[test][(y[test] == a) & (told == b)].sum()) for a, b in ((1, True), (0, True), (1, False), (0, False))]
        return counts, len(used), sum(len(patterns[k]) for k in used) / len(used) if used else 0.0

    def task(frames):
        for frame in frames:
            for k in frame["id"]:
                yield pd.DataFrame([(int(k), *fit(settings[int(k)]))], columns=["setting", "counts", "weights", "mean_length"])

    got = {r.setting: (list(r.counts), r.weights, r.mean_length) for r in spark.range(0, len(settings), 1, len(settings)).mapInPandas(task, FITTED).collect()}  # one row per setting
    return [got[k] for k in range(len(settings))]


def f_of(counts: list[int]) -> float:
    tp, fp, fn, _ = counts
    return 2 * tp / (2 * tp + fp + fn) if tp + fp + fn else 0.0


def pattern_models(own: DataFrame, n_items: int, name: str, kinds: list[str], folds: int, trials: int, inner_folds: int, max_len: int) -> tuple[list, list] | None:
    """(counts, models) of the pattern models over declared items, each fitted in one task on the distinct rows with their numbers; None beyond what a task takes."""
    spark = own.sparkSession
    inner = [f"_in{f}" for f in range(folds)] if trials else []
    rows = own.groupBy("_items", "y", "fold", *inner).agg(F.count(F.lit(1)).alias("n")).limit(MOST_CELLS // max(1, n_items) + 1).toArrow()  # without an object per row
    if len(rows) * n_items > MOST_CELLS:
        return None
    dense = np.zeros((len(rows), n_items), np.uint8)
    dense[pc.list_parent_indices(rows["_items"]).to_numpy(), pc.list_flatten(rows["_items"]).to_numpy()] = 1
    column = lambda c: pc.fill_null(rows[c], -1).to_numpy().astype(np.int64)
    held = spark.sparkContext.broadcast((dense, column("y"), column("n"), column("fold"), np.stack([column(c) for c in inner], axis=1) if inner else None))
    fit = lambda settings: fit_in_tasks(spark, held, [(k == "with_negation", f, g, o, max_len) for k, f, g, o in settings])
    out = tuned(name, kinds, folds, trials, inner_folds, fit)
    held.destroy()
    return out


def tuned(name: str, kinds: list[str], folds: int, trials: int, inner_folds: int, fit) -> tuple[list, list]:
    """(counts, models) of each kind and fold: the drawn options with the best mean F-value over the inner folds, the first on ties, fitted on the whole training part. fit(settings (kind, fold, inner fold or None, options)) gives (counts, weights, mean length) of each."""
    jobs = [(k, f) for k in kinds for f in range(folds)]
    tried = [(k, f, o) for k, f in jobs for o in (learning.draws(SPACES[k], trials, f) if trials else [])]
    scored = fit([(k, f, g, o) for k, f, o in tried for g in range(inner_folds)]) if tried else []
    best: dict = {}
    for t, (k, f, o) in enumerate(tried):
        score = sum(f_of(c) for c, *_ in scored[t * inner_folds : (t + 1) * inner_folds]) / inner_folds
        if (k, f) not in best or score > best[k, f][0]:
            best[k, f] = score, o
    options = [best[j][1] if j in best else {} for j in jobs]
    final = fit([(k, f, None, o) for (k, f), o in zip(jobs, options, strict=True)])
    counts = [(name, k, f, a, b, n) for (k, f), (c, *_) in zip(jobs, final, strict=True) for (a, b), n in zip(((1, 1), (0, 1), (1, 0), (0, 0)), c, strict=True) if n]
    return counts, [(name, k, f, str(sorted(o.items())), w, m) for (k, f), o, (_, w, m) in zip(jobs, options, final, strict=True)]


def fit_cells(spark: SparkSession, path: str, files: list[str], values: str, n_rows: int, n_features: int, settings: list[tuple], max_len: int) -> list:
    """(counts, weights, mean length) of each setting (kind, fold, inner fold or None, options): models fitted in tasks that read the rows from the shared folder, once if they fit a task's memory, else once a pass. A task takes one training part, and forests, pattern models and the others apart."""
    family = lambda kind: kind if kind == "forest" else "patterns" if kind in OURS else ""
    groups: dict = {}
    for k, (kind, fold, inner, _) in enumerate(settings):
        groups.setdefault((family(kind) != "forest", family(kind), fold, inner), []).append(k)
    tasks = [groups[g] for g in sorted(groups, key=str)]
    most = MOST_BYTES

    def work(own):
        _, fold, inner, _ = settings[own[0]]
        named = [dealing.distinct_values(values, k).astype(float) for k in range(n_features)]
        kinds = [np.min_scalar_type(max(0, len(v) - 1)) for v in named]

        def rows(wanted):
            def read(name):
                table = dealing.read_file(path, name, ["y", "fold", *([] if inner is None else [f"_in{fold}"]), *(f"_f{k}" for k in range(n_features))])
                within = table["fold"].to_numpy() != fold
                held = within & (table[f"_in{fold}"].to_numpy() == inner) if inner is not None else ~within
                at = np.flatnonzero(within & ~held if wanted else held)
                return [table[f"_f{k}"].to_numpy()[at].astype(kind) for k, kind in enumerate(kinds)], table["y"].to_numpy()[at]

            out = weighted.StoredCells.at(named, files, read)
            return out.held() if n_rows * (sum(k.itemsize for k in kinds) + 5) <= most else out

        train, test = rows(True), rows(False)
        items = weighted.item_tables(train) if any(settings[k][0] in OURS for k in own) else None
        bins = None if items else weighted.binned(train, test)
        for k in own:
            kind, _, _, o = settings[k]
            if kind in OURS:
                o = {"theta": 3.0, "share": 0.05, "reg": 0.01} | o
                yield (k, *weighted.pattern_counts(train, test, items, pattern_constraint(o["theta"], o["share"]), kind == "with_negation", max_len, o["reg"]))
            elif kind == "logistic":
                start = weighted.logistic(weighted.coarse(bins[0], *bins[1], train), **o) if n_rows > FEW_ROWS and len(bins[1][0]) < n_rows // 4 else None
                yield k, weighted.logistic_counts(train, test, start, **o), None, None
            else:
                yield k, weighted.tree_counts(train, test, kind, binned=lambda *_: bins, **o), None, None

    def task(frames):
        for frame in frames:
            for t in frame["id"]:
                for row in work(tasks[int(t)]):
                    yield pd.DataFrame([row], columns=["setting", "counts", "weights", "mean_length"]).astype({"weights": "Int32", "mean_length": "Float64"})

    rows = spark.range(0, len(tasks), 1, len(tasks)).mapInPandas(task, FITTED).collect()  # one row per setting
    if any(r.counts is None for r in rows):
        raise OverflowError("too many patterns for one task")
    got = {r.setting: (list(r.counts), r.weights, r.mean_length) for r in rows}
    return [got[k] for k in range(len(settings))]


def cell_models(own: DataFrame, n_features: int, name: str, kinds: list[str], folds: int, trials: int, inner_folds: int, max_len: int) -> tuple[list, list, list[str]]:
    """(counts, models, kinds) of baselines, and of pattern models over cut items, each fitted in one task on the rows in the shared folder; kinds beyond what a task takes are left out. own: key, y and features, with folds or without."""
    spark = own.sparkSession
    codes, values, files = (dealing.coded if "fold" in own.columns else dealing.deal)(own, n_features, folds, inner_folds if trials else 0)
    n = codes.count()
    path = codes.inputFiles()[0].rpartition("/")[0] if files else ""
    if 8 * spark.read.parquet(values).count() > MOST_BYTES:
        return [], [], []
    counts, models, done = [], [], []
    for some in ([k for k in kinds if k not in OURS], *([k] for k in kinds if k in OURS)):
        try:
            told = tuned(name, some, folds, trials, inner_folds, lambda settings: fit_cells(spark, path, files, values, n, n_features, settings, max_len)) if some else ([], [])
        except OverflowError:
            continue
        counts, models, done = counts + told[0], models + told[1], done + some
    return counts, models, done


def counted(spark: SparkSession, sf_dir: str, name: str, kinds=MODELS, folds: int = 5, trials: int = 2, inner_folds: int = 2, max_len: int = 5, threads: int = 4) -> tuple[DataFrame, DataFrame]:
    """(numbers of predictions, models): every row predicted by models fitted on the other folds, and for each fold its options and size.

    For every fold, `trials` random settings are compared on inner folds of the training part, for our models and the
    baselines alike; trials=0 takes the defaults. Growth rates are normalised by the class sizes here, as the shares of
    the positive class range from a tenth to a half. Items and features are computed once; the source columns go then."""
    df, items, features = labelled_rows(spark, sf_dir, name)
    held = F.array_compact(F.array(*(F.when(F.coalesce(i.predicate, F.lit(False)), F.lit(k)) for k, i in enumerate(items)))) if items else F.array().cast("array<int>")
    slim = df.select("key", "y", held.alias("_items"), *(c.alias(f"_f{k}") for k, c in enumerate(features.values())))
    begin = scratch_mark()

    def deal():
        out = stored(learning.folds(stored(slim, "features"), "y", "key", folds), "folds")
        return deal_inner(out, folds, inner_folds) if trials else out

    dealt = deal() if items else None  # models on features alone need no table of rows with their folds
    ours = [k for k in kinds if k in OURS] if items else []
    rows, models = (pattern_models(dealt, len(items), name, ours, folds, trials, inner_folds, max_len) if ours else None) or ([], [])
    rest = [k for k in kinds if not models or k not in ours]
    if easy := [k for k in rest if k not in ours]:
        told = cell_models(slim if dealt is None else dealt, len(features), name, easy, folds, trials, inner_folds, max_len)
        rows, models, rest = rows + told[0], models + told[1], [k for k in rest if k not in told[2]]
    if not rest:
        clear_scratch(spark, begin)
        return spark.createDataFrame(rows, COUNTED), spark.createDataFrame(models, MODEL)
    dealt = deal() if dealt is None else dealt
    own = dealt.coalesce(max(1, dealt.count() // 20_000)).persist()  # models of a small fold run side by side, in one task each
    own.count()
    columns = {n: F.col(f"_f{k}") for k, n in enumerate(features)}
    flags = items and [Item(i.name, F.array_contains("_items", k)) for k, i in enumerate(items)]

    def one(job):
        kind, fold = job
        train, test, sizes = own.where(F.col("fold") != fold), own.where(F.col("fold") == fold), []
        make = model_maker(kind, flags, max_len, sizes)
        best, options = -1.0, {}
        for drawn in learning.draws(SPACES[kind], trials, fold) if trials else []:
            inner = train.withColumn("fold", F.col(f"_in{fold}"))
            told = learning.f_value(learning.confusion(learning.held_out(inner, "y", columns, make(**drawn), inner_folds), "y", "prediction", ["fold"]))
            if (score := told.agg(F.avg("f1")).first()[0] or 0.0) > best:
                best, options = score, drawn
        told = make(**options)(train, test, columns, "y", ["y"]).groupBy("y", "prediction").agg(F.count(F.lit(1)).alias("n"))
        got = [(name, kind, fold, int(r.y), int(r.prediction), r.n) for r in told.collect()]  # at most four rows
        size = sizes[-1] if sizes else {"weights": None, "mean_length": None}
        return got, (name, kind, fold, str(sorted(options.items())), size["weights"], size["mean_length"])

    with ThreadPoolExecutor(threads) as pool:
        done = list(pool.map(one, [(k, f) for k in rest for f in range(folds)]))
    own.unpersist()
    clear_scratch(spark, begin)
    rows = rows + [r for got, _ in done for r in got]
    return spark.createDataFrame(rows, COUNTED), spark.createDataFrame(models + [m for _, m in done], MODEL)


def predicted(spark: SparkSession, sf_dir: str, name: str, kinds=MODELS, **options) -> tuple[DataFrame, DataFrame]:
    """counted(), with a row for every prediction."""
    rows, models = counted(spark, sf_dir, name, kinds, **options)
    return rows.withColumn("n", F.explode(F.sequence(F.lit(1).cast("long"), "n"))).drop("n"), models


def accuracy(spark: SparkSession, sf_dir: str, names: list[str], kinds=MODELS, **options) -> DataFrame:
    """F-value of the pattern models and the baselines by target, model and fold, with the model's size and options."""
    out = None
    sums = [F.sum(F.when((F.col("y") == y) & (F.col("prediction") == p), F.col("n")).otherwise(0)).alias(c) for c, y, p in (("tp", 1, 1), ("fp", 0, 1), ("fn", 1, 0), ("tn", 0, 0))]
    for name in names:
        rows, models = counted(spark, sf_dir, name, kinds, **options)
        told = learning.f_value(rows.groupBy("workload", "model", "fold").agg(*sums))
        part = told.select("workload", "model", "fold", "tp", "fp", "fn", "tn", *(F.round(c, 6).alias(c) for c in ("precision", "recall", "f1", "accuracy"))).join(models, ["workload", "model", "fold"])
        out = part if out is None else out.unionByName(part)
    return out


def win_counts(scores: DataFrame) -> DataFrame:
    """(model, mean_f1, wins, targets): means over targets of the mean over folds; a win is the best mean of a target, ties count for all."""
    mean = scores.groupBy("workload", "model").agg(F.avg("f1").alias("f"))
    best = mean.withColumn("best", F.max("f").over(Window.partitionBy("workload")))
    return best.groupBy("model").agg(F.round(F.avg("f"), 6).alias("mean_f1"), F.count_if(F.col("f") >= F.col("best") - 1e-9).alias("wins"), F.count(F.lit(1)).alias("targets"))


SCALE = "workload string, engine string, nodes long, patterns long, seconds double, cpu_s double, jobs long, stages long, shuffle_bytes long, spill_bytes long, broadcast_bytes long"


def scale_out(spark: SparkSession, sf_dir: str, names: list[str], negation: bool = False, max_len: int | None = None, engines=(("local", None), ("frontier", 0), ("hybrid", 100), ("matrix:linked", None), ("matrix:bitset", None))) -> DataFrame:
    """The engines on each workload: same answers, nodes, and what they cost Spark."""
    rows = []
    for name in names:
        db = build(spark, sf_dir, name, negation).persist()
        least = min_support(db, 0.05, 2)
        for engine, few in engines:
            with Meter(spark) as m:
                got = mining.run(db, Jumping(least), max_len=max_len, engine=engine, hand_over=few)
                n = got.patterns.count()
            c = m.cost
            rows.append((name, engine, got.counters.nodes, n, c.seconds, c.cpu_s, c.jobs, c.stages, c.shuffle_bytes, c.spill_bytes, c.broadcast_bytes))
        db.rows.unpersist()
    return spark.createDataFrame(rows, SCALE)


def matrix_supports(db: LabeledDB) -> DataFrame:
    """Supports of all single items and pairs from both matrix back ends, in one task that fails if they differ. For few distinct rows."""
    n, names = db.n_items, db.names

    def task(frame):
        out = {}
        for back_end in BACK_ENDS.values():
            own = {}
            for side in ("w_pos", "w_neg"):
                m = back_end.create(frame["items"].tolist(), range(n), frame[side].tolist())
                for p in [*((i,) for i in range(n)), *combinations(range(n), 2)]:
                    own.setdefault(p, []).append(m.count_rows(p))
            if out and own != out:
                raise ValueError("the back ends differ")
            out = own
        return pd.DataFrame([(" & ".join(names[i] for i in p), x, y) for p, (x, y) in out.items() if x + y], columns=["pattern_text", "sup_pos", "sup_neg"])

    return db.rows.groupBy(F.lit(0).alias("g")).applyInPandas(task, "pattern_text string, sup_pos long, sup_neg long")


def one_vs_rest_patterns(spark: SparkSession, sf_dir: str, names: list[str], constraint_of, **options) -> DataFrame:
    """(workload, pattern_text, sup_pos, sup_neg): minimal patterns of each class against the rest."""
    out = None
    for name in names:
        part = mining.mine_minimal(build(spark, sf_dir, name), constraint_of(), **options).select(F.lit(name).alias("workload"), "pattern_text", "sup_pos", "sup_neg")
        out = part if out is None else out.unionByName(part)
    return out


def label_values(spark: SparkSession, sf_dir: str, table: str, label: str) -> list:
    """The classes of a table, each in turn the positive one."""
    from ..sources.workloads import one_vs_rest

    return one_vs_rest(read(spark, sf_dir, table), label)
