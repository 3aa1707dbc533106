"""Discretiser, features, folds, measures, classifier and baselines."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from contrastmine.operators import learning as K
from contrastmine.operators.constraints import Contrast, GrowthRate
from contrastmine.operators.labeled import item_flag

ANY = 1 << 40


def cuts(classes, values=None):
    values = np.arange(1, len(classes) + 1) if values is None else np.array(values)
    y = np.array(classes)
    names = np.unique(values)
    return K.mdl_cuts(names.astype(float), np.array([(y[values == v] == 1).sum() for v in names]), np.array([(y[values == v] == 0).sum() for v in names]))


def test_mdl_on_known_vectors():
    assert cuts([0, 0, 0, 0, 1, 1, 1, 1]) == [4.5] and cuts([0, 1] * 4) == [] and cuts([0, 1, 0, 1], [3] * 4) == []
    assert cuts([0] * 20 + [1] * 20 + [0] * 20) == [20.5, 40.5]
    tied = cuts([0, 0, 0, 0, 1, 1, 1, 1, 1], [1, 2, 3, 4, 4, 5, 6, 7, 8])
    assert all(c not in range(1, 9) for c in tied)


def test_mdl_in_spark_equals_plain_and_reads_training_rows_only(spark):
    rng = np.random.default_rng(3)
    x = rng.integers(0, 40, 600)
    y = ((x > 25) ^ (rng.random(600) < 0.05)).astype(int)
    df = spark.createDataFrame([(int(a), float(a) * 2, int(b)) for a, b in zip(x, y)], "a int, b double, y int")
    got = K.MdlDiscretizer().fit(df, {"a": F.col("a"), "b": F.col("b"), "c": F.lit(1.0)}, F.col("y")).cuts
    assert got["a"] == cuts(y, x) and got["b"] == [2 * c for c in got["a"]] and got["c"] == [] and 25.5 in got["a"]
    assert K.MdlDiscretizer(prebins=16).fit(df, {"a": F.col("a")}, F.col("y")).cuts["a"]


def test_folds_are_stratified_and_stable(spark):
    df = spark.createDataFrame([(k, int(k % 7 == 0)) for k in range(700)], "id long, y int")
    a = {r.id: r.fold for r in K.folds(df, "y", "id").collect()}
    assert a == {r.id: r.fold for r in K.folds(df.repartition(5), "y", "id").collect()}
    for y in (0, 1):
        counts = np.bincount([f for k, f in a.items() if (k % 7 == 0) == bool(y)], minlength=5)
        assert counts.max() - counts.min() <= 1


def test_measures(spark):
    rows = [(1, 1)] * 3 + [(0, 1)] + [(1, 0)] * 2 + [(0, 0)] * 4
    got = K.f_value(K.confusion(spark.createDataFrame(rows, "label int, prediction int"))).first()
    assert (got.tp, got.fp, got.fn, got.tn) == (3, 1, 2, 4) and got.precision == 0.75 and got.recall == 0.6 and abs(got.f1 - 2 / 3) < 1e-9 and got.accuracy == 0.7
    assert K.f_value(K.confusion(spark.createDataFrame([(1, 0)], "label int, prediction int"))).first().f1 == 0.0
    scored = spark.createDataFrame([(0.1, 0), (0.4, 0), (0.35, 1), (0.8, 1), (0.4, 1)], "s double, y int")
    assert abs(K.auc(scored, "s", "y").first().auc - 4.5 / 6) < 1e-9


@pytest.mark.parametrize("family", ["logistic", "squared"])
def test_classifier_recovers_a_planted_negated_rule(spark, family):
    rng = np.random.default_rng(5)
    rows = [(k, *map(int, rng.integers(0, 2, 5))) for k in range(800)]
    df = spark.createDataFrame([(*r, int(r[1] and not r[2])) for r in rows], "id long, a int, b int, c int, d int, e int, y int")
    items = [item_flag(n, F.col(n) == 1) for n in "abcde"]
    make = lambda neg: K.PatternClassifier(Contrast(20, ANY) & GrowthRate(5.0), negation=neg, family=family, reg=0.002)
    model = make(True).fit(df, {}, "y", items)
    assert model.texts == ["a & !b"] and model.size() == {"weights": 1, "mean_length": 2.0}
    f1 = K.f_value(K.confusion(model.transform(df, ["y"]), "y")).first().f1
    assert f1 == 1.0
    blind = make(False).fit(df, {}, "y", items)
    assert K.f_value(K.confusion(blind.transform(df, ["y"]), "y")).first().f1 < 1.0


def test_model_without_patterns_is_its_intercept(spark):
    df = spark.createDataFrame([(k, k % 2, int(k % 3 == 0)) for k in range(60)], "id long, a int, y int")
    model = K.PatternClassifier(Contrast(1000, 0)).fit(df, {}, "y", [item_flag("a", F.col("a") == 1)])
    assert model.patterns == [] and model.transform(df, ["y"]).count() == 60


def test_cross_validation_tuning_and_baselines(spark):
    rng = np.random.default_rng(6)
    x = rng.normal(size=(300, 3))
    df = spark.createDataFrame([(k, *map(float, r), int(r[0] > 0 and r[1] < 0.3)) for k, r in enumerate(x)], "id long, p double, q double, r double, y int")
    features = {n: F.col(n) for n in "pqr"}
    for kind in ("tree", "logistic", "forest"):
        out = K.cross_validate(df, "id", "y", features, K.ml_baseline(kind), 3).collect()
        assert len(out) == 3 and np.mean([r.f1 for r in out]) > 0.6
    best, score = K.tune(lambda **o: K.ml_baseline("tree", **o), {"maxDepth": [1, 5]}, df, "id", "y", features, n_trials=3, inner_folds=2)
    assert best == {"maxDepth": 5} and score > 0.8


@pytest.mark.parametrize("family", ["logistic", "squared"])
def test_models_are_saved_and_loaded(spark, tmp_path, family):
    from contrastmine.operators.labeled import item_sql

    rng = np.random.default_rng(8)
    x = rng.normal(size=(400, 2))
    df = spark.createDataFrame([(k, *map(float, r), int(r[0] > 0.2 and r[1] < 0.5)) for k, r in enumerate(x)], "id long, p double, q double, y int")
    features = {n: F.col(n) for n in "pq"}
    cuts = K.MdlDiscretizer().fit(df, features, F.col("y"))
    cuts.save(spark, str(tmp_path / "cuts.json"))
    again = K.MdlDiscretizer.load(spark, str(tmp_path / "cuts.json"))
    items = again.items(features, {"p": "p", "q": "q"})
    assert again == cuts and items and all(i.sql for i in items)
    model = K.PatternClassifier(Contrast(5, ANY) & GrowthRate(2.0), family=family).fit(df, features, "y", items)
    model.save(spark, str(tmp_path / "model"))
    back = K.PatternClassifier.load(spark, str(tmp_path / "model"))
    told = lambda m: sorted((r.id, r.prediction) for r in m.transform(df, ["id"]).collect())
    assert back.texts == model.texts and told(back) == told(model)
    with pytest.raises(ValueError):
        K.PatternClassifier(Contrast(5, ANY), family=family).fit(df, features, "y", [item_flag("p", F.col("p") > 0)]).save(spark, str(tmp_path / "no"))
    assert item_sql("a", "p > 0").sql == "p > 0"


def test_f_values_from_stored_predictions(spark, tmp_path):
    """What the experiment reports is what SQL says about its predictions."""
    import duckdb

    from contrastmine.plans import experiments as X

    rows, models = X.predicted(spark, "/root/testdata/sf0.01", "docs_flags", ("with_negation", "tree"), trials=1)
    rows.write.parquet(str(tmp_path / "predictions"))
    told = K.f_value(K.confusion(rows, "y", "prediction", ["workload", "model", "fold"]))
    want = duckdb.sql(f"select model, fold, 2.0 * count(*) filter (where y = 1 and prediction = 1) / nullif(count(*) filter (where y = 1) + count(*) filter (where prediction = 1), 0) from '{tmp_path}/predictions/*.parquet' group by 1, 2").fetchall()
    assert {(r.model, r.fold): round(r.f1, 9) for r in told.collect()} == {(m, f): round(v or 0.0, 9) for m, f, v in want} and rows.count() == 2 * 399
    assert models.count() == 10 and models.where("model = 'with_negation' and weights > 0 and mean_length >= 1").count() == 5
    wins = {r.model: r for r in X.win_counts(told).collect()}
    assert sum(r.wins for r in wins.values()) >= 1 and all(r.targets == 1 for r in wins.values())


def test_thousands_of_patterns_as_features(spark):
    from itertools import combinations

    from pyspark.ml.functions import vector_to_array

    items = [item_flag(f"i{k}", F.col("a").bitwiseAND(1 << k) > 0) for k in range(9)] + [item_flag(f"j{k}", F.col("a") == k) for k in range(60)]
    patterns = [p for p in combinations(range(9), 4)] + [(k, 69 + k) for k in range(9)] + [(0, 60 + 5), (68,)]
    df = spark.range(64).withColumnRenamed("id", "a")
    got = {r.a: r.v for r in K.pattern_features(df, items, patterns * 12, ["a"]).select("a", vector_to_array("features").alias("v")).collect()}
    has = lambda a, i: bool(a >> i & 1) if i < 9 else a == i - 9
    want = lambda a, p: all(has(a, i) if i < 69 else not has(a, i - 69) for i in p)
    assert all(got[a] == [float(want(a, p)) for p in patterns] * 12 for a in range(64))


def test_estimator_in_a_pipeline(spark):
    from pyspark.ml import Pipeline

    df = spark.range(200).selectExpr("id", "cast(id % 4 = 0 or id % 7 = 0 as int) y", "id % 4 = 0 a", "id % 7 = 0 b")
    items = [item_flag("a", F.col("a")), item_flag("b", F.col("b"))]
    fitted = Pipeline(stages=[K.PatternEstimator(Contrast(2, ANY) & GrowthRate(2.0), {}, "y", items, reg=0.001)]).fit(df)
    out = fitted.transform(df)
    assert set(out.columns) == {"id", "y", "a", "b", "prediction"} and out.where("y <> prediction").count() == 0


@pytest.mark.parametrize("seed", range(60))
def test_short_search_is_the_kernels(seed):
    from contrastmine.operators import constraints as C
    from contrastmine.operators.kernel import Search, Side
    from contrastmine.operators.minimal import minimal_by_trie

    d = random.Random(seed)
    n, negation, most = d.randint(2, 5), d.random() < 0.5, d.randint(0, 5)
    dense = np.unique(np.array([[d.random() < 0.5 for _ in range(n)] for _ in range(12)], np.uint8), axis=0)
    p, q = (np.array([d.randint(0, 3) for _ in dense]) for _ in range(2))
    sets = [list(np.flatnonzero(r)) for r in dense]
    for c in (C.Contrast(d.randint(1, 3), ANY) & C.GrowthRate(d.choice([1.0, 2.0, 3.0]), True), C.Jumping(1), C.ChiSquare(1.0)):
        c = c.bind(int(p.sum()), int(q.sum()))
        want = minimal_by_trie([f[0] for f in Search(c, n, negation, max_len=most).run(Side(sets, p, n, negation), Side(sets, q, n, negation))])
        assert sorted(K.short_members(dense, p, q, c, negation, most)) == sorted(want)


def test_short_search_holds_the_rows_of_one_path():
    """All prefixes' rows lay in memory at once, beyond an executor's; now a few times the input, and ending early does not wait for the first level."""
    import tracemalloc

    rng = np.random.default_rng(4)
    dense = (rng.random((20_000, 40)) < 0.4).astype(np.uint8)
    p = (rng.random(20_000) < 0.1).astype(int)
    c = (Contrast(100, ANY) & GrowthRate(1.5, True)).bind(int(p.sum()), int((1 - p).sum()))
    tracemalloc.start()
    with pytest.raises(OverflowError):
        K.short_members(dense, p, 1 - p, c, True, 4, most=5)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 12 * dense.nbytes


def test_weighted_model_is_that_of_spark(spark):
    d = random.Random(3)
    bits = [[int(d.random() < 0.5) for _ in range(4)] for _ in range(300)]
    labels = [int((b[0] and not b[1]) or d.random() < 0.1) for b in bits]
    df = spark.createDataFrame([(*b, y) for b, y in zip(bits, labels, strict=True)], "a int, b int, c int, d int, y int")
    items = [item_flag(c, F.col(c) == 1) for c in "abcd"]
    constraint = lambda n_pos: Contrast(5, ANY) & GrowthRate(1.5, True)
    want = K.PatternClassifier(constraint(0), max_len=3, reg=0.01).fit(df, {}, "y", items)
    patterns, weights, intercept = K.fit_weighted(np.array(bits, np.uint8), np.array(labels), np.ones(300, int), constraint, True, 3, 0.01)
    assert sorted(patterns) == sorted(want.patterns)
    told = dict(zip(want.patterns, want.model.coefficients.toArray(), strict=True))
    assert abs(intercept - want.model.intercept) < 0.05 and all(abs(told[p] - w) < 0.05 for p, w in zip(patterns, weights, strict=True))


def test_customers_with_negations_are_fitted_whole(spark):
    """86 literals and patterns of up to five: the search that goes on without a bound on lengths took minutes for a single fit."""
    from contrastmine.plans import experiments as X

    got = X.accuracy(spark, "/root/testdata/sf0.01", ["customers"], ["with_negation"], trials=1).collect()
    assert len(got) == 5 and sum(r.tp + r.fn for r in got) == 122 and sum(r.fp + r.tn for r in got) == 1378 and any(r.weights > 0 for r in got)


def cells_of(x, y, w=None):
    from contrastmine.operators.weighted import Cells

    return Cells.of(list(np.asarray(x, float).T), np.asarray(y, np.int8), np.ones(len(y), np.int32) if w is None else np.asarray(w, np.int32))


def test_models_on_distinct_rows_are_those_of_spark(spark):
    """Trees and logistic models predict what Spark's do on the single rows, forests about that; numbers count as that many rows."""
    from contrastmine.operators import weighted as W

    rng = np.random.default_rng(11)
    x = np.stack([rng.integers(0, 50, 1500), rng.integers(0, 3, 1500), np.round(rng.normal(size=1500), 2), np.ones(1500)], axis=1)
    y = ((x[:, 0] > 20) & (x[:, 2] < 0.4) ^ (rng.random(1500) < 0.1)).astype(int)
    df = spark.createDataFrame([(*map(float, r), int(c)) for r, c in zip(x, y)], "a double, b double, c double, d double, y int")
    features = {n: F.col(n) for n in "abcd"}
    train, test = df.where("b < 2"), df.where("b = 2")
    inside = x[:, 1] < 2
    ours = [cells_of(x, y).some(np.flatnonzero(m)) for m in (inside, ~inside)]

    def told(kind, **options):
        r = K.confusion(K.ml_baseline(kind, **options)(train, test, features, "y", ["y"]), "y").first()
        return [r.tp, r.fp, r.fn, r.tn]

    for o in ({"maxDepth": 3}, {"maxDepth": 8, "minInstancesPerNode": 5}):
        assert W.tree_counts(*ours, "tree", **o) == told("tree", **o)
    for o in ({}, {"regParam": 0.01, "elasticNetParam": 1.0}, {"regParam": 0.1}):
        assert np.abs(np.subtract(W.logistic_counts(*ours, **o), told("logistic", **o))).max() <= 1
    a, b = W.tree_counts(*ours, "forest", maxDepth=5), told("forest", maxDepth=5)
    assert sum(a) == sum(b) and abs((a[0] + a[3]) - (b[0] + b[3])) < 0.05 * sum(a)
    thrice, twice = np.repeat(np.arange(1500), 3), cells_of(x, y, np.full(1500, 3))
    for counts in (lambda c: W.tree_counts(c, c, "tree"), lambda c: W.logistic_counts(c, c, regParam=0.01, elasticNetParam=1.0)):
        assert counts(twice) == counts(cells_of(x[thrice], y[thrice]))


def test_rows_on_odd_inputs():
    """Missing values, one class, no features and empty parts have answers."""
    from contrastmine.operators import weighted as W

    x = np.array([[1.0, np.nan], [2.0, np.nan], [np.nan, np.nan], [4.0, 5.0]])
    some = cells_of(x, [0, 0, 1, 1])
    none = some.some(np.arange(0))
    for kind in ("tree", "forest"):
        assert sum(W.tree_counts(some, some, kind)) == 4 and W.tree_counts(some, none, kind) == [0, 0, 0, 0] and W.tree_counts(none, some, kind) == [0, 0, 2, 2]
    assert sum(W.logistic_counts(some, some)) == 4 and W.logistic_counts(cells_of(x, [0] * 4), some) == [0, 0, 2, 2] and W.logistic_counts(cells_of(x, [1] * 4), some) == [2, 2, 0, 0]


def test_inner_folds_are_those_of_tune(spark):
    from contrastmine.plans import experiments as X

    own = K.folds(spark.range(900).selectExpr("id % 850 key", "cast(id % 7 = 0 as int) y"), "y", "key", 3).persist()
    got = X.deal_inner(own, 3, 2)
    for f in range(3):
        want = K.folds(own.where(F.col("fold") != f).withColumnRenamed("fold", "_o"), "y", "key", 2, f)
        assert sorted((r.key, r.y, r.fold) for r in want.collect()) == sorted((r.key, r.y, r[f"_in{f}"]) for r in got.where(F.col("fold") != f).collect())
        assert got.where((F.col("fold") == f) & F.col(f"_in{f}").isNotNull()).count() == 0
    assert got.count() == 900


@pytest.mark.parametrize(("name", "rows"), [("planted", 6000), ("docs_flags", 399), ("embeddings_3", 500)])
def test_experiments_fit_no_model_by_spark_jobs(spark, monkeypatch, name, rows):
    """The models of a fold were trained by hundreds of jobs on single rows."""
    from contrastmine.plans import experiments as X

    def refuse(*args, **options):
        raise AssertionError("by Spark jobs")

    monkeypatch.setattr(K, "ml_baseline", refuse)
    monkeypatch.setattr(K, "pattern_model", refuse)
    sf = "/root/testdata/sf0.001" if name == "planted" else "/root/testdata/sf0.01"
    got = X.accuracy(spark, sf, [name], trials=1 if name == "planted" else 0).collect()
    assert len(got) == 25
    for model in X.MODELS:
        assert sum(r.tp + r.fp + r.fn + r.tn for r in got if r.model == model) == rows
    if name == "planted":
        assert min(r.f1 for r in got if r.model == "with_negation") > 0.9


def test_pattern_models_beyond_a_task_are_fitted_by_spark_jobs(spark, monkeypatch):
    """Too many patterns for one task are no reason to drop or cut any: the same models come from Spark jobs."""
    from contrastmine.operators import weighted as W
    from contrastmine.plans import experiments as X

    rng = np.random.default_rng(2)
    x = rng.integers(0, 2, (200, 3))
    y = (x[:, 0] & (1 - x[:, 1])).astype(int)
    cells = cells_of(x, y)
    make = lambda most: W.pattern_counts(cells, cells, W.item_tables(cells), X.pattern_constraint(), True, 3, 0.01, most)
    assert make(0) == (None, None, None) and sum(make(1 << 20)[0]) == 200
    whole = {(r.model, r.fold): (r.tp, r.fp, r.fn, r.tn) for r in X.accuracy(spark, "/root/testdata/sf0.001", ["planted"], ["with_negation", "tree"], folds=2, trials=0).collect()}
    monkeypatch.setattr(X, "MOST_BYTES", 0)
    again = {(r.model, r.fold): (r.tp, r.fp, r.fn, r.tn) for r in X.accuracy(spark, "/root/testdata/sf0.001", ["planted"], ["with_negation", "tree"], folds=2, trials=0).collect()}
    assert whole == again


def test_texts_are_judged_once_and_do_not_pass_the_join_with_labels(spark, tmp_path):
    """On larger labels the join dealt out every text, and every item was computed twice, once for patterns and once for the baselines."""
    from contrastmine.plans import experiments as X
    from contrastmine.sources import workloads as S

    texts = ["### and THE 123", None, "", "the\nA\nB\nC", "x@y 99", "AAAA the and " * 90]
    docs = [(k if k != 7 else None, texts[k % 6], "en" if k % 2 else None, len(texts[k % 6] or "")) for k in range(40)]
    spark.createDataFrame(docs, "doc_id long, text string, lang string, n_chars long").selectExpr("doc_id", "text", "lang", "'s' source", "n_chars").write.parquet(f"{tmp_path}/documents.parquet")
    labels = [(k, None if k == 4 else k % 3 % 2) for k in (*range(0, 60, 2), 6, 6, 9)] + [(None, 1)]
    spark.createDataFrame(labels, "doc_id long, quality long").selectExpr("doc_id", "quality", "0 toxic").write.parquet(f"{tmp_path}/labels.parquet")
    w = S.WORKLOADS["docs_flags"]
    sql = [f"coalesce({S.dialect(s, True)}, false)" for _, s in w.items]
    want = spark.sql(f"select doc_id, cast({w.label} as int) y, {', '.join(sql)} from {S._bind(spark, str(tmp_path), w)}").where("y is not null")
    df, items, features = X.labelled_rows(spark, str(tmp_path), "docs_flags")
    told = lambda df: sorted(map(tuple, df.collect()))
    assert told(df.select("key", "y", *(F.coalesce(i.predicate, F.lit(False)) for i in items))) == told(want) and want.count() == 22
    assert told(df.select("key", "y", *features.values())) == [(*r[:2], *map(float, r[2:])) for r in told(want)]

    def nodes(plan):
        yield plan
        for k in range(plan.children().size()):
            yield from nodes(plan.children().apply(k))

    held = F.array_compact(F.array(*(F.when(F.coalesce(i.predicate, F.lit(False)), F.lit(k)) for k, i in enumerate(items))))
    slim = df.select("key", "y", held, *features.values())
    plans = list(nodes(slim._jdf.queryExecution().optimizedPlan()))
    joins = [p for p in plans if p.nodeName() == "Join" and "Inner" in p.toString().split("\n")[0]]
    assert len(joins) == 1 and "text#" not in joins[0].output().mkString()
    assert sum(p.simpleString(1000).count("[0-9]{3}") for p in plans) == 1
    for bits in (0, 6, 8):
        assert told(S.flagged_documents(spark, str(tmp_path), w, bits).select(want.columns[:2] + [f"_b{k}" for k in range(len(items))])) == told(want)


def test_lists_of_plain_strings_are_no_regular_expressions(spark):
    """An alternation tried at every place of a text took more time than any other item."""
    from contrastmine.sources import workloads as S

    junk = dict(S.DOC_FLAGS)["junk"]
    assert S.without_lists(junk) == "(contains(text, '###') or contains(text, '$$$') or contains(text, '%%%'))"
    kept = ["a.c", "a|", "|a", "", "(a|b)", "[a-z]", "[^a]", "a+|b", "^a|b", "a$", "a{2}", "x|[ab]", "a\\.b", "[.][|]"]
    assert all(S.without_lists(f"@rx(text, @re'{k}')") == f"@rx(text, @re'{k}')" for k in kept)
    assert all(S.without_lists(s) == s for n, s in S.DOC_FLAGS if n != "junk")
    d = random.Random(5)
    texts = ["".join(d.choice("#$%[].é\n ") for _ in range(d.randint(0, 12))) for _ in range(400)] + [None]
    df = spark.createDataFrame([(t,) for t in texts], "text string")
    for sql in (junk, "not @rx(text, @re'[.]')", "@rx(text, @re'#é|[.] ')", "@rx(text, @re'%') and @rx(text, @re'[#$]')"):
        got = df.selectExpr(S.dialect(sql, True) + " a", S.dialect(S.without_lists(sql), True) + " b").collect()
        assert all(r.a == r.b for r in got) and len({r.a for r in got}) == 3


def test_folds_by_dealing_hashes_alone_are_those_of_windows(spark, monkeypatch):
    """Every fold dealt out whole rows, six times in all."""
    from contrastmine.operators import dealing as D
    from contrastmine.plans import experiments as X

    monkeypatch.setattr(D, "ROWS_A_RANGE", 300)
    monkeypatch.setattr(D, "ROWS_A_FILE", 700)
    own = spark.range(4000).selectExpr("id key", "cast(id % 7 = 0 as int) y", "cast(id % 3900 as double) _f0", "case id % 3 when 0 then null when 1 then double('NaN') else -1.5 end _f1").repartition(5).persist()
    want = X.deal_inner(K.folds(own, "y", "key", 3).persist(), 3, 2).na.fill(-1, ["_in0", "_in1", "_in2"])
    told = sorted((r.y, r.fold, r._in0, r._in1, r._in2, int(r._f0), int(r._f1 != -1.5)) for r in want.collect())
    codes, values, files = D.deal(own, 2, 3, 2)
    assert len(files) >= 5 and sorted(map(tuple, codes.collect())) == told
    assert sorted(map(tuple, D.coded(want, 2, 3, 2)[0].collect())) == told
    assert D.distinct_values(values, 1)[0] == -1.5 and np.isnan(D.distinct_values(values, 1)[1])
    assert sorted((r.y, r.fold) for r in D.deal(own, 2, 3, 0)[0].collect()) == sorted((r[0], r[1]) for r in told)


def stored_cells(cells, n_files=3):
    from contrastmine.operators.weighted import StoredCells

    deal = lambda f: np.flatnonzero(np.arange(len(cells.y)) % n_files == f)
    return StoredCells.at([v for v, _ in cells.columns], list(range(n_files)), lambda f: ([c[deal(f)] for _, c in cells.columns], cells.y[deal(f)]))


def test_models_of_rows_in_files_are_those_of_rows_in_memory():
    """Rows beyond a task's memory were left to hundreds of Spark jobs."""
    from contrastmine.operators import weighted as W
    from contrastmine.plans.experiments import pattern_constraint

    rng = np.random.default_rng(3)
    x = np.stack([rng.integers(0, 50, 1500), np.where(rng.random(1500) < 0.1, np.nan, rng.integers(0, 3, 1500)), np.round(rng.normal(size=1500), 2)], axis=1)
    y = ((x[:, 0] > 20) & (x[:, 2] < 0.4) ^ (rng.random(1500) < 0.1)).astype(int)
    near = [cells_of(x, y).some(np.flatnonzero(m)) for m in (np.arange(1500) % 3 > 0, np.arange(1500) % 3 == 0)]
    far = [stored_cells(c) for c in near]
    for kind in ("tree", "forest"):
        assert W.tree_counts(*near, kind) == W.tree_counts(*far, kind) == W.tree_counts(far[0].held(), far[1].held(), kind)
    bins = W.binned(*near)
    for o in ({}, {"regParam": 0.01, "elasticNetParam": 1.0}, {"regParam": 0.1}):
        start = W.logistic(W.coarse(bins[0], *bins[1], near[0]), **o)
        assert np.abs(np.subtract(W.logistic_counts(*near, **o), W.logistic_counts(*far, start, **o))).max() <= 1
    told = [W.pattern_counts(*c, W.item_tables(c[0]), pattern_constraint(), True, 3, 0.01) for c in (near, far)]
    assert told[0] == told[1] and told[0][1] > 0


def test_items_too_rare_for_any_member_go_first_only_where_that_changes_nothing(monkeypatch):
    from contrastmine.operators import weighted as W
    from contrastmine.plans.experiments import pattern_constraint

    rng = np.random.default_rng(8)
    seen = set()
    monkeypatch.setattr(W.without_rare, "__defaults__", (1,))
    for k in range(40):
        x = np.stack([np.where(rng.random(3000) < 0.998, 0, rng.integers(0, 30, 3000)), rng.integers(0, 2, 3000), rng.integers(0, 3, 3000)], axis=1)
        y = ((x[:, 1] == 1) & (rng.random(3000) < 0.3 + 0.1 * (k % 4))).astype(int)
        cells = cells_of(x, y)
        items = [np.arange(len(v)) + 1 for v, _ in cells.columns], [len(v) for v, _ in cells.columns]
        fit = lambda wide: W.pattern_counts(cells, cells, items, pattern_constraint((1.2, 2.5)[k % 2], 0.1), True, 3, 0.001, wide=wide)  # noqa: E731, B023
        whole, cut = fit(1 << 10), fit(0)
        seen.add(cut[0] is None)
        assert cut[0] is None or cut == whole
    assert False in seen


def test_cuts_of_many_intervals_are_found_together():
    """An interval at a time took minutes for a hundred thousand cuts."""
    import time

    p = np.repeat(np.random.default_rng(1).random(60_000) < 0.3, 2) * 24
    begin = time.process_time()
    assert len(K.mdl_cuts(np.arange(120_000.0), p, 24 - p)) > 10_000 and time.process_time() - begin < 20
