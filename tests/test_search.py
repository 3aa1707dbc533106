"""The search against the definition: random tiny databases, all constraints, orders, rules, engines; and the traps."""

import random
from itertools import combinations

import numpy as np
import pytest

from contrastmine.operators import constraints as C
from contrastmine.operators import labeled as L
from contrastmine.operators import mining as M
from contrastmine.operators.kernel import STATIC, Rules, Search, Side
from contrastmine.operators.minimal import Zdd, minimal_by_trie, minimal_plain, zdd_minimal

ANY = 1 << 40
POS, NEG = ["ab", "abc", "acd", "bd", "abd"], ["a", "bc", "bcd", "cd", "ac"]
MAKE = {
    "jumping": lambda d: C.Jumping(d.randint(1, 2)), "contrast": lambda d: C.Contrast(d.randint(1, 3), d.randint(0, 2)), "growth": lambda d: C.Contrast(d.randint(1, 2), ANY) & C.GrowthRate(d.choice([0.7, 1.0, 2.0, 3.0])),
    "normalized": lambda d: C.GrowthRate(d.choice([1.0, 2.0]), True), "chi2": lambda d: C.ChiSquare(d.choice([0.4, 1.0, 2.0])), "chi2_growth": lambda d: C.ChiSquare(d.choice([0.4, 1.0])) & C.GrowthRate(d.choice([0.3, 1.0, 2.0])),
    "one_sided": lambda d: C.Score("chi2_one_sided", d.choice([0.5, 1.5])), "info": lambda d: C.Score("info_gain", d.choice([0.05, 0.2])), "gini": lambda d: C.Score("gini_gain", 0.05), "wracc": lambda d: C.Score("wracc", 0.05), "diff": lambda d: C.Score("support_diff", 0.3),
    "composite": lambda d: C.Contrast(d.randint(1, 2), d.randint(0, 3)) & C.GrowthRate(d.choice([1.0, 2.0])) & C.ChiSquare(0.5),
}


def world(pos, neg, n, negation):
    """Every consistent pattern with its supports."""
    out = {}
    for k in range(n + 1):
        for p in combinations(range(n * (1 + negation)), k):
            if len({i % n for i in p}) == k:
                hit = lambda r: all((i in r) if i < n else (i - n not in r) for i in p)  # noqa: E731, B023
                out[p] = sum(map(hit, pos)), sum(map(hit, neg))
    return out


def sides(pos, neg, n, negation):
    return Side([sorted(r) for r in pos], [1] * len(pos), n, negation), Side([sorted(r) for r in neg], [1] * len(neg), n, negation)


@pytest.mark.parametrize("seed", range(150))
def test_kernel_equals_definition(seed):
    d = random.Random(seed)
    n, negation = d.randint(1, 4), d.random() < 0.5
    pos = [{i for i in range(n) if d.random() < 0.5} for _ in range(d.randint(1, 7))]
    neg = [{i for i in range(n) if d.random() < 0.5} for _ in range(d.randint(1, 7))]
    known = world(pos, neg, n, negation)
    name = d.choice(list(MAKE))
    c = MAKE[name](d).bind(len(pos), len(neg))
    max_len = d.choice([None, None, 1, 2])
    inside = {p for p, (x, y) in known.items() if bool(c.member(x, y)) and (max_len is None or len(p) <= max_len)}
    minimal = {p for p in inside if not any(s in inside for k in range(len(p)) for s in combinations(p, k))}
    for order in ("dynamic", *(f"static:{s}" for s in STATIC)):
        for rules in (Rules(), Rules(nc="off"), Rules(lb=False), Rules(lb=False, nc="off"), Rules(lb=False, nc="off", pos=False)):
            s = Search(c, n, negation, order, rules, max_len)
            got = s.run(*sides(pos, neg, n, negation))
            assert all(known[p] == (x, y) for p, x, y in got)
            assert set(minimal_plain([p for p, *_ in got])) == minimal, (name, order, rules)
            assert len({p for p, *_ in got}) == len(got)
    everything = Search(c, n, negation, "dynamic", Rules(stop=False, nc="off"), max_len).run(*sides(pos, neg, n, negation))
    assert {p for p, *_ in everything} == inside
    if name == "jumping":
        jumping = {p for p, (x, y) in known.items() if bool(c.member(x, y))}
        assert Search(c, n, negation).count_jumping(*sides(pos, neg, n, negation), c.min_pos) == len(jumping)
    # bounds never hide a member: the cut at a node is only taken where no superset within the rest is one
    for p, (x, y) in known.items():
        above = [q for q in known if set(q) >= set(p)]
        least = min(known[q][1] for q in above)
        if bool(c.cut(x, least, y)):
            assert not any(bool(c.member(*known[q])) for q in above)


def test_unchanged_negative_rule_needs_its_gate():
    """Two-sided chi-square breaks the rule's condition; the gate turns it off unless a growth rate of at least n+/n- is asked for too."""
    pos, neg = [{0, 1}, {0}], [{1}, {0, 1}]
    c = C.ChiSquare(1.0) & C.Contrast(1, ANY)
    c.bind(2, 2)
    right = {(0,), (1,)}
    assert not Rules().use_nc(c) and {p for p, *_ in Search(c, 2).run(*sides(pos, neg, 2, False))} == right
    assert {p for p, *_ in Search(c, 2, rules=Rules(lb=False, nc="on")).run(*sides(pos, neg, 2, False))} != right
    assert Rules().use_nc((C.ChiSquare(1.0) & C.GrowthRate(1.0)).bind(2, 2)) and not Rules().use_nc((C.ChiSquare(1.0) & C.GrowthRate(0.9)).bind(2, 2))


def test_immediate_subsets_do_not_suffice_under_growth_rate():
    pos, neg = [set(), set(), set(), {0, 1}], [{0, 2}, {1}]
    c = C.GrowthRate(2.0).bind(4, 2)
    known = world(pos, neg, 3, False)
    assert bool(c.member(*known[()])) and not bool(c.member(*known[0,])) and not bool(c.member(*known[1,])) and bool(c.member(*known[0, 1])) and not c.convex()
    assert minimal_plain([p for p, v in known.items() if bool(c.member(*v))]) == [()]


def test_growth_rate_edges():
    c = C.GrowthRate(2.0).bind(5, 5)
    assert bool(c.member(1, 0)) and not bool(c.member(0, 0)) and bool(c.member(4, 2)) and not bool(c.member(3, 2))
    assert bool(C.GrowthRate(2.0, True).bind(10, 5).member(4, 1)) and not bool(C.GrowthRate(2.0, True).bind(10, 5).member(3, 1))
    assert not bool(c.cut(5, 0, 3)) and bool(c.cut(0, 0, 3)) and bool(c.cut(3, 2, 3))


@pytest.mark.parametrize("seed", range(20))
def test_extraction_methods_agree(seed):
    d = random.Random(seed)
    family = list({tuple(sorted(d.sample(range(7), d.randint(0 if seed % 5 == 0 else 1, 5)))) for _ in range(40)})
    want = set(minimal_plain(family))
    assert set(minimal_by_trie(family)) == want and set(zdd_minimal(family)) == want
    z = Zdd()
    a = 0
    for p in family:
        a = z.union(a, z.of(p))
    assert set(z.sets(a)) == set(family)


CASES = {
    "JEP1": (lambda: C.Jumping(1), 5, {"a & b": (3, 0), "a & d": (2, 0)}, 21, {"!a & !c": (1, 0), "b & !c": (3, 0), "d & !c": (2, 0), "a & b": (3, 0), "a & d": (2, 0)}),
    "CP21": (lambda: C.Contrast(2, 1), 4, {"a & b": (3, 0), "a & c": (2, 1), "a & d": (2, 0), "b & d": (2, 1)}, 12, {"!c": (3, 1), "b & !d": (2, 1), "a & b": (3, 0), "a & c": (2, 1), "a & d": (2, 0), "b & d": (2, 1)}),
    "GR2": (lambda: C.Contrast(2, ANY) & C.GrowthRate(2.0), 6, {"a": (4, 2), "b": (4, 2)}, 14, {"!c": (3, 1), "a": (4, 2), "b": (4, 2)}),
    "CHI": (lambda: C.ChiSquare(2.5), 2, {"a & b": (3, 0), "a & d": (2, 0)}, 12, {"c & !a": (0, 3), "!b & !d": (0, 2), "b & !c": (3, 0), "d & !c": (2, 0), "a & b": (3, 0), "a & d": (2, 0)}),
    "TRIV": (lambda: C.Contrast(1, ANY) & C.GrowthRate(1.0), 11, {"": (5, 5)}, 39, {"": (5, 5)}),
}


@pytest.mark.parametrize("case", CASES)
@pytest.mark.parametrize("engine", ["local", "frontier", "hybrid"])
def test_engines_on_the_hand_fixture(spark, case, engine):
    make, n_plain, plain, n_negated, negated = CASES[case]
    db = L.from_sets(spark, POS, NEG)
    for on, n, want in ((False, n_plain, plain), (True, n_negated, negated)):
        own = db.with_negation(on)
        assert M.mine_all(own, make(), engine="local").count() == n
        got = M.run(own, make(), engine=engine, hand_over=4)
        assert {r.pattern_text: (r.sup_pos, r.sup_neg) for r in got.patterns.collect()} == want


def test_tree_is_the_same_in_every_engine(spark):
    db = L.from_sets(spark, POS, NEG).with_negation()
    trees = []
    for engine, few in (("local", None), ("frontier", 0), ("hybrid", 3)):
        got = M.run(db, C.Jumping(1), engine=engine, hand_over=few, trace=True)
        trees.append((sorted((tuple(p), x, y, v) for p, x, y, _, v in got.trace), got.counters.nodes))
    assert trees[0] == trees[1] == trees[2]


def test_weights_and_class_overlap(spark):
    rows = L.from_sets(spark, ["a", "a", "ab"], ["a", "b"])
    r = {x.pattern_text: x for x in M.mine_all(rows, C.GrowthRate(1.5)).collect()}
    assert (r["a"].sup_pos, r["a"].sup_neg, r["a"].growth_rate) == (3, 1, 3.0)
    once = {x.pattern_text: x for x in M.mine_all(L.distinct_semantics(rows), C.GrowthRate(1.5)).collect()}
    assert (once["a"].sup_pos, once["a"].growth_rate) == (2, 2.0) and L.class_overlap(rows).count() == 1


def test_degenerate_databases(spark):
    assert M.mine_sjeps(L.from_sets(spark, [], ["a"], names="ab")).count() == 0
    assert [r.pattern_text for r in M.mine_sjeps(L.from_sets(spark, ["a"], [], names="ab")).collect()] == [""]
    assert M.mine_sjeps(L.from_sets(spark, ["", ""], [""], names="a")).count() == 0
    assert M.mine_sjeps(L.from_sets(spark, ["ab", "ab"], ["ab"])).count() == 0
    twins = L.from_sets(spark, ["abc", "ab"], ["c", ""])
    assert {r.pattern_text for r in M.mine_sjeps(twins).collect()} == {"a", "b"}
    small, groups = L.merge_twins(twins)
    assert small.names == ("a=b", "c") and groups == {0: [0, 1], 1: [2]} and {r.pattern_text for r in M.mine_sjeps(small).collect()} == {"a=b"}


def test_minimality_check_topk_and_bounds(spark):
    db = L.from_sets(spark, POS, NEG)
    assert M.is_minimal(db, (0, 1), C.Jumping(1)) and not M.is_minimal(db, (0, 1, 2), C.Jumping(1))
    assert [r.pattern_text for r in M.mine_topk(db, 2).collect()] == ["a & b", "a & d"]
    told = {r.pattern_text: (r.member, r.minimal) for r in M.minimality(db, [(), (0,), (0, 1), (0, 1, 2)], C.Jumping(1)).collect()}
    assert told == {"": (False, False), "a": (False, False), "a & b": (True, True), "a & b & c": (True, False)}
    assert M.minimality(db, [], C.Jumping(1)).count() == 0
    score = M.score_bound(db, (0,), (1, 2, 3)).first()
    below = M.mine_all(db, C.Contrast(0, 1 << 40)).select("pattern_text", "sup_pos", "sup_neg").collect()
    chi2 = C.Score("chi2").bind(*db.sizes())
    assert score.most >= score.own and score.most + 1e-9 >= max(chi2.value(r.sup_pos, r.sup_neg) for r in below if r.pattern_text.startswith("a"))
    b = M.descendant_bounds(db, (0,), (2, 3)).first()
    assert (b.most_pos, b.least_neg, b.most_neg) == (4, 0, 2)


def test_sql_functions(spark):
    from contrastmine.functions.measures import register_sql, register_table_function

    register_sql(spark)
    assert spark.sql("select occurs(array(0, 2), array(0, 5), 4), round(chi2(3, 0, 5, 5), 4), growth_rate(4, 2), growth_rate(1, 0), subset_of(array(1), array(1, 2))").first()[:] == (True, 4.2857, 2.0, None, True)
    register_table_function(spark)
    at = {c: k for k, c in enumerate("abcd")}
    df = spark.createDataFrame([([at[i] for i in r], y) for y, s in ((1, POS), (0, NEG)) for r in s], "items array<int>, label int").coalesce(1)
    df.createOrReplaceTempView("t_rows")
    got = spark.sql("select * from mine_patterns(table(t_rows) with single partition, 1, 0, 0.0D, 0.0D, 4, -1, false)").collect()
    assert {tuple(r.pattern): (r.sup_pos, r.sup_neg) for r in got} == {(0, 1): (3, 0), (0, 3): (2, 0)}


def test_scores_match_their_sql(spark):
    rng = np.random.default_rng(1)
    rows = [(int(rng.integers(0, 21)), int(rng.integers(0, 31))) for _ in range(40)] + [(0, 0), (20, 30), (20, 0), (0, 30)]
    df = spark.createDataFrame(rows, "x long, y long")
    for name, f in C.SCORES.items():
        got = df.selectExpr("x", "y", f"{C.score_sql(name, 'x', 'y', '20', '30')} s").collect()
        assert np.allclose([r.s for r in got], [float(f(r.x, r.y, 20, 30)) for r in got]), name


@pytest.mark.parametrize("seed", range(25))
def test_length_bound_changes_no_answer(seed):
    d = random.Random(seed)
    n = 5
    pos = [{i for i in range(n) if d.random() < 0.6} for _ in range(12)]
    neg = [{i for i in range(n) if d.random() < 0.5} for _ in range(12)]
    for c in (C.Contrast(2, 1), C.Contrast(1, ANY) & C.GrowthRate(3.0), C.ChiSquare(4.0)):
        c.bind(len(pos), len(neg))
        runs = []
        for rules in (Rules(), Rules(length=True)):
            s = Search(c, n, True, rules=rules, max_len=2)
            runs.append((sorted(minimal_plain([p for p, *_ in s.run(*sides(pos, neg, n, True))])), s.counters.nodes))
        assert runs[0][0] == runs[1][0] and runs[1][1] <= runs[0][1]


def test_dry_run_and_bitmap_functions(spark):
    from contrastmine.functions.measures import class_support, popcount_and
    from pyspark.sql import functions as F

    db = L.from_sets(spark, POS * 3, NEG * 3)
    told = M.dry_run(db, lambda part: C.Jumping(1), max_len=2)
    assert told["share"] == 1.0 and told["nodes"] > 0 and told["candidates"] >= 2
    bits = spark.createDataFrame([(bytes([255, 1]), bytes([15, 3])), (None, b"")], "a binary, b binary")
    assert [r[0] for r in bits.select(popcount_and("a", "b")).collect()] == [5, None]
    rows = spark.createDataFrame([([0, 1], 1), ([0], 0), ([1], 1)], "items array<int>, label int")
    got = rows.agg(class_support("label", "items", (0,), 2).alias("a"), class_support("label", "items", (0, 3), 2, False).alias("b"), class_support("label", "items", (), 2).alias("c")).first()
    assert (got.a, got.b, got.c) == (1, 1, 2)


@pytest.mark.parametrize("seed", range(60))
def test_matrix_search_and_competitors_equal_definition(seed):
    from contrastmine.operators import baselines as B
    from contrastmine.operators.branching import search_matrices

    d = random.Random(seed)
    n, negation = d.randint(1, 4), d.random() < 0.5
    pos = [{i for i in range(n) if d.random() < 0.5} for _ in range(d.randint(1, 7))]
    neg = [{i for i in range(n) if d.random() < 0.5} for _ in range(d.randint(1, 7))]
    sets, p, q = [sorted(r) for r in pos + neg], [1] * len(pos) + [0] * len(neg), [0] * len(pos) + [1] * len(neg)
    literals, known, least = list(range(n * (1 + negation))), world(pos, neg, n, negation), d.randint(1, 2)
    c = MAKE[d.choice(list(MAKE))](d).bind(len(pos), len(neg))
    max_len = d.choice([None, None, 1, 2])
    inside = {k for k, v in known.items() if bool(c.member(*v)) and (max_len is None or len(k) <= max_len)}
    minimal = set(minimal_plain(list(inside)))
    for order in ("dynamic", "static:id", "static:growth_desc"):
        for rules in (Rules(), Rules(nc="off"), Rules(lb=False), Rules.none()):
            for back_end in ("linked", "bitset"):
                got = search_matrices(Search(c, n, negation, order, rules, max_len), sets, p, q, back_end)
                assert all(known[a] == (x, y) for a, x, y in got) and set(minimal_plain([a for a, *_ in got])) == minimal
    everything = search_matrices(Search(c, n, negation, "dynamic", Rules(stop=False, nc="off"), max_len), sets, p, q, "linked")
    assert {a for a, *_ in everything} == inside
    jumping = {k for k, (x, y) in known.items() if x >= least and y == 0}
    order = literals[:]
    d.shuffle(order)
    place, occ, timer = {i: k for k, i in enumerate(order)}, B.Occurrences(sets, p, q, n, literals), B.Timer()
    assert sorted(f[0] for f in B.weighted_patterns(occ, place, least, None, None, timer)) == sorted(jumping - {()})
    assert B.weighted_patterns(occ, place, least, None, None, timer, False) == len(jumping - {()})
    closure = lambda k: (lambda held: tuple(sorted(frozenset.intersection(*held))) if held else None)([r for r in occ.rows if set(k) <= r])
    assert sorted(f[0] for f in B.closed_sets_from(occ, place, least, None, timer)) == sorted({closure(k) for k, (x, _) in known.items() if x >= least} - {()})
    assert {f[0] for f in B.diagram_patterns(sets, p, q, n, negation, literals, least, timer)} == set(minimal_plain(list(jumping)))


def test_matrix_engine_leaves_matrices_as_they_were_and_counts(spark):
    db = L.from_sets(spark, POS, NEG).with_negation()
    want = {r.pattern_text for r in M.mine_sjeps(db).collect()}
    for engine in ("matrix:linked", "matrix:bitset"):
        got = M.run(db, C.Jumping(1), engine=engine, trace=True)
        assert {r.pattern_text for r in got.patterns.collect()} == want and got.counters.nodes == len(got.trace) and got.counters.lb > 0


def test_extraction_beyond_its_bounds(spark):
    """More candidates than the driver takes, and patterns whose subsets cannot be listed."""
    from contrastmine.operators import minimal as K

    family = [(0,), (0, 1), (2, 3), (2, 3, 4), (5, 6), tuple(range(2, 40))]
    df = spark.createDataFrame([(list(p),) for p in family], "pattern array<int>")
    want = {(0,), (2, 3), (5, 6)}
    for method in ("set_trie", "zdd", "subset_join", "rarest", "levelwise"):
        assert {tuple(r.pattern) for r in K.extract_minimal(df, method, most_local=2).collect()} == want
    wide = spark.createDataFrame([(list(range(33)),), ([1],)], "pattern array<int>")
    assert [r.pattern for r in K.extract_minimal(wide).collect()] == [[1]]
    with pytest.raises(Exception, match="too many subsets"):
        K.by_subset_join(wide).collect()
    empty = spark.createDataFrame([([],), ([1],)], "pattern array<int>")
    assert [r.pattern for r in K.extract_minimal(empty, "rarest").collect()] == [[]] and [r.pattern for r in K.extract_maximal(empty).collect()] == [[1]]


def test_a_search_out_of_time_gives_no_answer(spark):
    db = L.from_sets(spark, POS, NEG)
    for engine in ("local", "frontier", "hybrid", "matrix:linked", "matrix:bitset"):
        got = M.run(db, C.Jumping(1), engine=engine, timeout_s=0, hand_over=100)
        assert not got.complete
        with pytest.raises(M.IncompleteSearch):
            got.patterns  # noqa: B018
    with pytest.raises(M.IncompleteSearch):
        M.mine_sjeps(db, timeout_s=0)


def test_limit_ends_a_full_search_and_is_refused_for_a_minimal_one(spark):
    db = L.from_sets(spark, POS, NEG)
    for engine in ("local", "frontier", "matrix:linked"):
        assert M.mine_all(db, C.Jumping(1), limit=2, engine=engine).count() == 2
    with pytest.raises(ValueError):
        M.mine_sjeps(db, limit=2)


def test_topk_follows_its_score_below_zero_too(spark):
    db = L.from_sets(spark, POS, NEG)
    known = world([{"abcd".index(i) for i in r} for r in POS], [{"abcd".index(i) for i in r} for r in NEG], 4, False)
    for score in ("wracc", "support_diff", "chi2", "info_gain"):
        ranked = sorted(((-float(C.SCORES[score](x, y, 5, 5)), len(p), " & ".join("abcd"[i] for i in p)) for p, (x, y) in known.items() if x >= 1))
        for k in (3, 9, 100):
            got = M.mine_topk(db, k, score).collect()
            value = lambda r: round(-float(C.SCORES[score](r.sup_pos, r.sup_neg, 5, 5)), 9)  # noqa: E731, B023
            assert [(value(r), r.size) for r in got] == [(round(s, 9), n) for s, n, _ in ranked[:k]]


def test_negation_of_some_items_only(spark):
    db = L.from_sets(spark, POS, NEG).with_negation(True, ["c"])
    assert db.literals() == [0, 1, 2, 3, 6] and db.n_items == 4
    want = {"b & !c", "d & !c", "a & b", "a & d"}
    for engine in ("local", "frontier", "matrix:linked"):
        assert {r.pattern_text for r in M.mine_sjeps(db, engine=engine).collect()} == want
    assert M.count_jeps(db).first().n_jeps == M.mine_jeps(db).count()


def test_candidates_leave_the_driver_beyond_a_bound(spark, monkeypatch):
    from contrastmine.operators import frontier

    db = L.from_sets(spark, POS, NEG).with_negation()
    want = {tuple(r.pattern) for r in M.mine_all(db, C.Jumping(1)).collect()}
    most = M.Findings.__init__.__defaults__
    monkeypatch.setattr(M.Findings.__init__, "__defaults__", (3,))
    monkeypatch.setattr(frontier, "WAVE_NODES", 2)
    for engine, few in (("frontier", 0), ("hybrid", 4), ("local", 0)):
        assert {tuple(r.pattern) for r in M.mine_all(db, C.Jumping(1), engine=engine, hand_over=few).collect()} == want
    monkeypatch.setattr(M.Findings.__init__, "__defaults__", most)


def test_no_nested_loop_joins(spark):
    from contrastmine.operators import baselines as B

    db = L.from_sets(spark, POS, NEG)
    plans = [M.mine_maximal(db, C.Contrast(1, 1)), M.mine_minimal(db, C.Contrast(1, 1), extraction="levelwise"), M.mine_minimal(db, C.Contrast(1, 1), extraction="rarest"), B.fpgrowth_contrast(db, 1, 1)]
    for df in plans:
        df.collect()
        told = df._jdf.queryExecution().executedPlan().toString()
        assert "NestedLoop" not in told and "CartesianProduct" not in told


def test_source_is_read_once(spark):
    from contrastmine.plans.meters import Meter

    seen = spark.sparkContext.accumulator(0)
    db = L.from_sets(spark, POS, NEG)

    def touch(frames):
        for f in frames:
            seen.add(len(f))
            yield f

    counted = L.LabeledDB(db.rows.mapInPandas(touch, "items array<int>, w_pos long, w_neg long"), db.names)
    n = db.rows.count()
    with Meter(spark) as m:
        assert M.mine_sjeps(counted).count() == 2
    assert seen.value == n and m.cost.jobs > 0 and m.cost.cpu_s > 0 and m.cost.shuffle_bytes > 0


def test_time_limit_of_counting_holds_among_sets_without_negative_rows():
    n = 20
    rows = [[i for i in range(n) if i != k] for k in range(n)]
    s = Search(C.Jumping(1).bind(n, 0), n, timeout_s=0.05)
    s.count_jumping(Side(rows, [1] * n, n, False), Side(rows, [0] * n, n, False), 1)
    assert s.counters.timeout
