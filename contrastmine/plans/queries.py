"""The driver's queries, each with its DuckDB twin where SQL can say it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.measures import score_column
from ..operators import baselines, labeled, learning, mining, relational
from ..operators.constraints import ChiSquare, Constraint, Contrast, GrowthRate, Jumping, Score, score_sql
from ..operators.kernel import STATIC, Rules
from ..sources.workloads import PLANT, WORKLOADS, build, read
from ..streaming import events as stream_events
from . import experiments
from .oracles import MAXIMAL, MINIMAL, first_cut, frequent, jep_count, members, rows_of, scored_pairs, supported, unbounded

ANY = 1 << 40
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE_SQL: dict[str, str] = {}
ANSWER = ("pattern_text", "sup_pos", "sup_neg")


def query(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLE_SQL[name] = sql
        return f

    return keep


def answer(df: DataFrame) -> DataFrame:
    return df.select("pattern_text", F.col("sup_pos").cast("long").alias("sup_pos"), F.col("sup_neg").cast("long").alias("sup_neg"))


def mined(name: str, workload: str, constraint: Callable[[], Constraint], max_len: int | None = None, negation: bool = False, minimal: bool = True, only: tuple[str, ...] | None = None, **options) -> None:
    """A miner's answer set, of any length unless capped, and its twin."""

    def run(spark, sf_dir):
        db = build(spark, sf_dir, workload, negation, only)
        mine = mining.mine_minimal if minimal else mining.mine_all
        return answer(mine(db, constraint(), max_len=max_len, **options))

    QUERIES[name] = run
    ORACLE_SQL[name] = unbounded(workload, negation or only is not None, constraint(), constraint().least_positive(), *([] if minimal else [""]), only=only, max_len=max_len)


# model
for _name, _workload in (("profile_orders", "orders"), ("profile_lineitem", "lineitem"), ("profile_docs", "docs")):
    _n = len(WORKLOADS[_workload].items)
    query(_name, rows_of(_workload, f"select {_n} n_literals, sum(wp + wn)::bigint n_rows, sum(wp)::bigint n_pos, sum(wn)::bigint n_neg, count(*) n_distinct, round(sum(bit_count(m)::double * (wp + wn)) / sum(wp + wn) / {_n}, 6) density from r"))(
        lambda spark, sf_dir, w=_workload: labeled.profile(build(spark, sf_dir, w))
    )
_n = len(WORKLOADS["docs_flags"].items)
query("density_negated_docs", rows_of("docs_flags", f"select {2 * _n} n_literals, 0.5::double density, sum(wp + wn)::bigint n_rows from r"))(
    lambda spark, sf_dir: labeled.profile(build(spark, sf_dir, "docs_flags", True)).select("n_literals", "density", "n_rows")
)
MASK = lambda db: labeled.to_masks(db).select(F.col("m0").alias("mask"), "w_pos", "w_neg")
query("class_overlap_lineitem", rows_of("lineitem", "select m mask, wp w_pos, wn w_neg from r where wp > 0 and wn > 0"))(lambda spark, sf_dir: MASK(labeled.LabeledDB(labeled.class_overlap(build(spark, sf_dir, "lineitem")), build(spark, sf_dir, "lineitem").names)))
query("distinct_rows_lineitem", rows_of("lineitem", "select m mask, wp w_pos, wn w_neg from r"))(lambda spark, sf_dir: MASK(build(spark, sf_dir, "lineitem")))


@query("item_catalogue_orders", "select row_number() over (order by attr, value) - 1 item_id, attr, '=' op, value from (select distinct 'o_orderpriority' attr, o_orderpriority \"value\" from orders union select distinct 'o_orderstatus', o_orderstatus from orders)")
def item_catalogue_orders(spark, sf_dir):
    return labeled.build_items(read(spark, sf_dir, "orders"), ["o_orderstatus", "o_orderpriority"])


def named_supports(db, df):
    names = F.array(*(F.lit(db.literal_name(i)) for i in range(db.n_items * (1 + db.negation))))
    return answer(df.withColumn("pattern_text", F.concat_ws(" & ", F.transform("pattern", lambda i: F.get(names, i)))))


def pairs_of(db):
    return [p for p in baselines.all_patterns(db.n_items, db.negation, 2) if len(p) == 2]


@query("literal_supports_orders", supported("orders", False, 1) + "\nselect t pattern_text, x sup_pos, y sup_neg from sup where size = 1")
def literal_supports_orders(spark, sf_dir):
    db = build(spark, sf_dir, "orders")
    return named_supports(db, labeled.literal_supports(db)).where("sup_pos + sup_neg > 0")


@query("occurrence_delivery", supported("orders", False, 1) + "\nselect t pattern_text, x sup_pos, y sup_neg from sup where size = 1")
def occurrence_delivery(spark, sf_dir):
    db = build(spark, sf_dir, "orders")
    return named_supports(db, labeled.occurrence_delivery(db).select(F.array("item").alias("pattern"), "sup_pos", "sup_neg"))


@query("occurrences_pattern_lineitem", rows_of("lineitem", "select m mask, wp w_pos, wn w_neg from r where (m & 1) = 1 and (m & 2) = 0 and (m & 4) = 4"))
def occurrences_pattern_lineitem(spark, sf_dir):
    db = build(spark, sf_dir, "lineitem")
    return MASK(labeled.LabeledDB(labeled.occurrences(db, (0, 2, 1 + db.n_items)), db.names))


for _name, _workload in (("pattern_supports_orders", "orders"), ("pair_supports_lineitem", "lineitem")):
    query(_name, supported(_workload, False, 2) + "\nselect t pattern_text, x sup_pos, y sup_neg from sup where size = 2")(
        lambda spark, sf_dir, w=_workload: named_supports(db := build(spark, sf_dir, w), labeled.supports(db, pairs_of(db))).where("sup_pos + sup_neg > 0")
    )


@query("cube_supports_orders", "select c_mktsegment, n_regionkey, substring(o_orderpriority, 1, 1) priority, sum(case when o_orderstatus = 'F' then 1 else 0 end)::bigint n_pos, sum(case when o_orderstatus = 'F' then 0 else 1 end)::bigint n_neg from orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey group by cube(c_mktsegment, n_regionkey, priority)")
def cube_supports_orders(spark, sf_dir):
    df = read(spark, sf_dir, "orders").join(read(spark, sf_dir, "customer"), F.col("o_custkey") == F.col("c_custkey")).join(read(spark, sf_dir, "nation"), F.col("c_nationkey") == F.col("n_nationkey"))
    df = df.withColumn("priority", F.substring("o_orderpriority", 1, 1))
    return relational.class_cube(df, ["c_mktsegment", "n_regionkey", "priority"], F.when(F.col("o_orderstatus") == "F", 1).otherwise(0))


# measures
for _name, _workload, _score in (("chi2_pairs_orders", "orders", "chi2"), ("info_gain_pairs_lineitem", "lineitem", "info_gain"), ("gini_gain_pairs_lineitem", "lineitem", "gini_gain"), ("wracc_pairs_lineitem", "lineitem", "wracc"), ("support_diff_pairs_orders", "orders", "support_diff"), ("chi2_one_sided_pairs_orders", "orders", "chi2_one_sided")):

    def _scored(spark, sf_dir, w=_workload, s=_score):
        db = build(spark, sf_dir, w)
        n_pos, n_neg = db.sizes()
        return named_supports(db, labeled.supports(db, pairs_of(db))).where("sup_pos + sup_neg > 0").withColumn("score", F.round(score_column(s, "sup_pos", "sup_neg", n_pos, n_neg), 6))

    query(_name, scored_pairs(_workload, _score))(_scored)

for _name, _scale in (("growth_rate_pairs_orders", ""), ("growth_rate_normalized_orders", " * nn / np")):

    def _growth(spark, sf_dir, scaled=bool(_scale)):
        db = build(spark, sf_dir, "orders")
        n_pos, n_neg = db.sizes()
        times = n_neg / n_pos if scaled else 1.0
        return named_supports(db, labeled.supports(db, pairs_of(db))).where("sup_pos + sup_neg > 0").select("pattern_text", F.round(F.when(F.col("sup_neg") > 0, F.col("sup_pos") / F.col("sup_neg") * times), 6).alias("growth_rate"), (F.col("sup_neg") == 0).alias("is_jumping"))

    query(_name, supported("orders", False, 2) + f"\nselect t pattern_text, round(case when y > 0 then x::double / y{_scale} end, 6) growth_rate, y = 0 is_jumping from sup, tot where size = 2")(_growth)


@query("region_report_docs", supported("docs_flags", False, 2) + "\nselect t pattern_text, y sup_neg, x sup_pos, (x >= 5 and y <= 20) in_rectangle, (case when y > 0 then x::double >= 1.0 * y else x > 0 end) in_triangle, (x >= 5 and y <= 20) and (case when y > 0 then x::double >= 1.0 * y else x > 0 end) in_both from sup where size = 2")
def region_report_docs(spark, sf_dir):
    db = build(spark, sf_dir, "docs_flags")
    return mining.region_report(db, named_supports(db, labeled.supports(db, pairs_of(db))).where("sup_pos + sup_neg > 0"), Contrast(5, 20), 1.0)


@query("descendant_bounds_orders", rows_of("orders", f"select 'priority=1' pattern_text, (select sum(wp)::bigint from r where (m & 1) = 1) most_pos, (select coalesce(sum(wn), 0)::bigint from r where (m & {1 | 1 << 5 | 1 << 12}) = {1 | 1 << 5 | 1 << 12}) least_neg, (select sum(wn)::bigint from r where (m & 1) = 1) most_neg"))
def descendant_bounds_orders(spark, sf_dir):
    return mining.descendant_bounds(build(spark, sf_dir, "orders"), (0,), (5, 12))


CORNERS = ", ".join(score_sql("chi2", x, y) for x in ("0", "x") for y in ("least", "y"))


@query("score_bound_orders", rows_of("orders", f"select 'priority=1' pattern_text, {score_sql('chi2')} own, greatest({CORNERS}) most from (select sum(wp) filter ((m & 1) = 1) x, sum(wn) filter ((m & 1) = 1) y, coalesce(sum(wn) filter ((m & {1 | 1 << 5 | 1 << 12}) = {1 | 1 << 5 | 1 << 12}), 0) least from r), tot"))
def score_bound_orders(spark, sf_dir):
    return mining.score_bound(build(spark, sf_dir, "orders"), (0,), (5, 12))


MEMBER = f"{supported('docs_flags', False, 3)},\nsat as (select sup.* from sup, tot where {Contrast(5, 3).sql()})"


@query("minimality_docs", f"{MEMBER}\nselect p.t pattern_text, m.t is not null member, m.t is not null and not exists (select 1 from sat a where a.size < p.size and (a.pm & p.pm) = a.pm) minimal from pats p left join sat m on m.t = p.t and m.size = p.size")
def minimality_docs(spark, sf_dir):
    db = build(spark, sf_dir, "docs_flags")
    return mining.minimality(db, baselines.all_patterns(db.n_items, False, 3), Contrast(5, 3))


# all members
mined("contrast_all_docs", "docs_flags", lambda: Contrast(5, 3), minimal=False)
mined("jep_all_docs", "docs_flags", lambda: Jumping(5), minimal=False)
mined("ep_all_orders", "orders", lambda: Contrast(10, ANY) & GrowthRate(2.0), minimal=False)
mined("chi2_all_orders", "orders", lambda: Contrast(30, ANY) & ChiSquare(9.03), minimal=False)
mined("composite_all_lineitem", "lineitem", lambda: Contrast(200, ANY) & GrowthRate(0.6) & ChiSquare(1.01), minimal=False)
query("jep_count_docs", jep_count("docs_flags", 5))(lambda spark, sf_dir: mining.count_jeps(build(spark, sf_dir, "docs_flags"), 5).select(F.col("n_jeps").cast("long").alias("n_jeps")))

# minimal members
mined("contrast_min_docs", "docs", lambda: Contrast(5, 3))
mined("sjep_docs", "docs", lambda: Jumping(2))
mined("sjep_words_docs", "docs_words", lambda: Jumping(5), max_len=3)
mined("ep_min_theta9_docs", "docs", lambda: Contrast(3, ANY) & GrowthRate(9.0))
mined("ep_min_orders", "orders", lambda: Contrast(10, ANY) & GrowthRate(2.0))
mined("chi2_min_orders", "orders", lambda: Contrast(30, ANY) & ChiSquare(8.03))
mined("chi2_growth_min_orders", "orders", lambda: Contrast(10, ANY) & GrowthRate(0.5) & ChiSquare(10.01), max_len=4)
mined("composite_min_lineitem", "lineitem", lambda: Contrast(200, ANY) & GrowthRate(0.6) & ChiSquare(1.01))
mined("infogain_min_lineitem", "lineitem", lambda: Contrast(300, ANY) & Score("info_gain", 0.0000801))
mined("ginigain_min_docs", "docs_flags", lambda: Contrast(3, ANY) & Score("gini_gain", 0.01003))
mined("wracc_min_docs", "docs_flags", lambda: Contrast(3, ANY) & Score("wracc", 0.0151))
mined("supportdiff_min_docs", "docs_flags", lambda: Contrast(3, ANY) & Score("support_diff", 0.2003))
mined("onesided_chi2_min_docs", "docs_flags", lambda: Contrast(3, ANY) & Score("chi2_one_sided", 15.03))
mined("sjep_neg_docs", "docs_flags", lambda: Jumping(2), negation=True)
mined("sjep_some_negated_docs", "docs_flags", lambda: Jumping(2), only=("lang:en", "digits", "at"))
mined("length_cap_docs", "docs_flags", lambda: Contrast(2, ANY) & GrowthRate(9.0), max_len=2, negation=True)
mined("ep_neg_min_lineitem", "planted", lambda: Contrast(500, ANY) & GrowthRate(9.0), negation=True)
mined("planted_rules_lineitem", "planted", lambda: Jumping(500), negation=True)
mined("planted_noisy_lineitem", "planted_noisy", lambda: Contrast(500, ANY) & GrowthRate(9.0), negation=True)
mined("planted_noisy_jep", "planted_noisy", lambda: Jumping(500), negation=True)
mined("toxic_control", "toxic", lambda: Contrast(5, ANY) & GrowthRate(3.0), max_len=3)
mined("trivial_empty_pattern", "pages", lambda: Contrast(1, ANY) & GrowthRate(1.0))
mined("normalized_ep_min_docs", "docs_flags", lambda: Contrast(5, ANY) & GrowthRate(4.0, True))

# tables not yet touched
mined("contam_patterns", "contam", lambda: Contrast(2, ANY) & GrowthRate(0.05))
mined("conversation_role_patterns", "conversations", lambda: Contrast(10, ANY) & GrowthRate(5.0))
mined("embedding_sign_patterns", "embeddings", lambda: Contrast(12, ANY) & GrowthRate(0.33), max_len=3)
mined("embedding_planted_patterns", "embeddings_planted", lambda: Jumping(20), max_len=3, negation=True)
mined("customer_balance_patterns", "customers", lambda: Contrast(4, ANY) & GrowthRate(0.5))
mined("part_promo_patterns", "parts", lambda: Contrast(5, ANY) & GrowthRate(0.8))
mined("supplier_region_patterns", "suppliers", lambda: Contrast(1, ANY) & GrowthRate(0.3))
mined("event_purchase_patterns", "events", lambda: Contrast(20, ANY) & GrowthRate(2.0))
mined("page_language_patterns", "pages", lambda: Contrast(3, ANY) & GrowthRate(3.0))

LABELS = [f"embeddings_{k}" for k in range(10)]
RARE = lambda: Contrast(14, ANY) & GrowthRate(0.2)
query("one_vs_rest_embeddings", " union all ".join(f"select '{n}' workload, * from ({unbounded(n, False, RARE(), 14, max_len=2)}) q{n[-1]}" for n in LABELS))(lambda spark, sf_dir: experiments.one_vs_rest_patterns(spark, sf_dir, [f"embeddings_{k}" for k in experiments.label_values(spark, sf_dir, "embeddings", "label")], RARE, max_len=2))

# extraction variants, orders, rules, engines, back ends: one answer each
for _method in ("subset_join", "set_trie", "zdd", "levelwise", "rarest"):
    mined(f"minimal_by_{_method}", "docs", lambda: Contrast(3, 3), extraction=_method)
for _order in ("dynamic", *(f"static:{s}" for s in STATIC)):
    mined(f"order_{_order.replace(':', '_')}", "docs_flags", lambda: Contrast(2, ANY) & GrowthRate(9.0), negation=True, order=_order)
for _label, _rules in (("lb_nc", Rules()), ("lb", Rules(nc="off")), ("nc", Rules(lb=False)), ("none", Rules.none())):
    mined(f"rules_{_label}", "docs_flags", lambda: Jumping(2), negation=True, rules=_rules)
mined("engine_local", "docs_flags", lambda: Contrast(5, 3), negation=True, engine="local")
mined("engine_frontier", "docs_flags", lambda: Contrast(5, 3), negation=True, engine="frontier")
mined("engine_hybrid", "docs_flags", lambda: Contrast(5, 3), negation=True, engine="hybrid", hand_over=60)
mined("engine_hybrid_static", "docs_flags", lambda: Contrast(5, 3), negation=True, engine="hybrid", hand_over=60, order="static:growth_desc")
mined("engine_matrix_linked", "docs_flags", lambda: Contrast(5, 3), negation=True, engine="matrix:linked")
mined("engine_matrix_bitset", "docs_flags", lambda: Contrast(5, 3), negation=True, engine="matrix:bitset")


@query("maximal_patterns", unbounded("docs_flags", False, Contrast(5, 3), 5, MAXIMAL))
def maximal_patterns(spark, sf_dir):
    return answer(mining.mine_maximal(build(spark, sf_dir, "docs_flags"), Contrast(5, 3)))


@query("matrix_linked_vs_bitset", supported("docs_flags", False, 2) + "\nselect t pattern_text, x sup_pos, y sup_neg from sup where size > 0")
def matrix_linked_vs_bitset(spark, sf_dir):
    return experiments.matrix_supports(build(spark, sf_dir, "docs_flags"))


@query("bitmap_supports_lineitem", rows_of("lineitem", "select k, count(*) n_rows from r, (values ('and', 1 | 4), ('or', 1 | 4)) v(k, p) where case when k = 'and' then (m & p) = p else (m & p) <> 0 end group by k"))
def bitmap_supports_lineitem(spark, sf_dir):
    maps = labeled.literal_bitmaps(build(spark, sf_dir, "lineitem"))
    part = lambda k: labeled.bitmap_support(maps, (0, 2), k == "or").select(F.lit(k).alias("k"), "n_rows")
    return part("and").unionByName(part("or"))


# baselines
def baseline(name: str, workload: str, negation: bool, min_pos: int, run, keep: str | None) -> None:
    QUERIES[name] = lambda spark, sf_dir: named_supports(db := build(spark, sf_dir, workload, negation), run(db))
    ORACLE_SQL[name] = unbounded(workload, negation, Jumping(min_pos), min_pos, *([] if keep is None else [keep]))


baseline("closed_dfs_jep", "docs_flags", False, 5, lambda db: baselines.closed_jeps(db, 5), "")
baseline("closed_dfs_jep_neg", "docs_flags", True, 5, lambda db: baselines.closed_jeps(db, 5), "")
baseline("prefix_tree_sjep", "docs_flags", False, 3, lambda db: baselines.prefix_tree_sjeps(db, 3), None)
baseline("prefix_tree_sjep_neg", "docs_flags", True, 3, lambda db: baselines.prefix_tree_sjeps(db, 3), None)
baseline("fpgrowth_contrast", "docs_flags", False, 5, lambda db: baselines.fpgrowth_contrast(db, 5, 0).where(F.size("pattern") > 0), "")
baseline("zdd_sjep", "docs_flags", True, 3, lambda db: baselines.zdd_sjeps(db, 3), None)
QUERIES["brute_force_min"] = lambda spark, sf_dir: named_supports(db := build(spark, sf_dir, "docs_flags", True), baselines.brute_force(db, Jumping(3), 3))
ORACLE_SQL["brute_force_min"] = members("docs_flags", True, Jumping(3), 3)
query("jep_count_closed_sets", jep_count("docs_flags", 5))(lambda spark, sf_dir: baselines.count_jeps_closed(build(spark, sf_dir, "docs_flags"), 5).select(F.col("n_jeps").cast("long").alias("n_jeps")))
CLOSED = "where s.size > 0 and not exists (select 1 from sat t where t.size = s.size + 1 and (t.pm & s.pm) = s.pm and (t.nm & s.nm) = s.nm and t.x = s.x and t.y = s.y)"
for _name, _negation in (("closed_sets_docs", False), ("closed_sets_neg_docs", True)):
    query(_name, unbounded("docs_flags", _negation, Contrast(5, ANY), 5, CLOSED))(lambda spark, sf_dir, on=_negation: named_supports(db := build(spark, sf_dir, "docs_flags", on), baselines.closed_sets(db, 5)))

# experiments: one query a workload, all shares, orders and rules; runs beyond the limit are rows with status timeout
LIMIT_S = 5.0
for _name, _workload, _negation in (("ablation_orders", "orders", False), ("ablation_lineitem", "lineitem", False), ("ablation_docs", "docs", False), ("ablation_docs_negated", "docs_flags", True), ("ablation_embeddings", "embeddings", False)):
    query(_name)(lambda spark, sf_dir, w=_workload, on=_negation: experiments.ablation(spark, sf_dir, w, on, timeout_s=LIMIT_S))
query("ablation_docs_words")(lambda spark, sf_dir: experiments.ablation(spark, sf_dir, "docs_words", timeout_s=LIMIT_S, max_len=3))
for _name, _workloads, _negation in (("competitor_times", ["docs_flags", "planted"], True), ("competitor_times_sparse", ["orders", "lineitem", "docs", "events"], False), ("competitor_times_dense", ["docs_words"], False)):
    query(_name)(lambda spark, sf_dir, w=_workloads, on=_negation: experiments.competitors(spark, sf_dir, w, on, timeout_s=LIMIT_S))


def _answers(negation: bool, workload: str, constraint: Constraint) -> str:
    """Number of minimal members by support share."""
    parts = []
    for s in experiments.SHARES:
        body = unbounded(workload, negation, constraint, 2, "", "s.*")
        keep = MINIMAL.replace("sat t", "own t")
        parts.append(f"select {s}::double share, count(*) n_minimal from (with base as ({body}), own as (select * from base where x >= greatest(2, ceil({s} * np - 1e-9))) select 1 from own s {keep}) q")
    return " union all ".join(parts)


@query("ablation_answers", _answers(True, "docs_flags", Contrast(2, ANY) & GrowthRate(9.0)))
def ablation_answers(spark, sf_dir):
    """Every order and rule set finds the same number of minimal patterns."""
    runs = experiments.ablation(spark, sf_dir, "docs_flags", True)
    told = runs.groupBy("share").agg(F.min("minimal").alias("least"), F.max("minimal").alias("n_minimal"), F.count_if(F.col("status") != "ok").alias("late"))
    return told.select("share", F.when((F.col("late") == 0) & (F.col("least") == F.col("n_minimal")), F.col("n_minimal")).alias("n_minimal"))


@query("competitor_answers", _answers(True, "docs_flags", Jumping(2)))
def competitor_answers(spark, sf_dir):
    """Every method finds the same number of minimal jumping patterns."""
    runs = experiments.competitors(spark, sf_dir, ["docs_flags"], True).where("task = 'minimal'")
    told = runs.groupBy("share").agg(F.min(F.col("patterns").cast("long")).alias("least"), F.max(F.col("patterns").cast("long")).alias("n_minimal"), F.count_if(F.col("status") != "ok").alias("late"))
    return told.select("share", F.when((F.col("late") == 0) & (F.col("least") == F.col("n_minimal")), F.col("n_minimal")).alias("n_minimal"))


STATISTICS = ["orders", "lineitem", "planted", "docs_flags", "docs", "events", "pages", "conversations", "contam", "customers", "parts", "suppliers"]
query("dataset_statistics")(lambda spark, sf_dir: experiments.dataset_statistics(spark, sf_dir, STATISTICS))
query("dataset_statistics_negated")(lambda spark, sf_dir: experiments.dataset_statistics(spark, sf_dir, ["docs_flags", "planted", "conversations"], True))
query("scale_out")(lambda spark, sf_dir: experiments.scale_out(spark, sf_dir, ["docs_flags", "planted"], True))


@query("search_tree_trace")
def search_tree_trace(spark, sf_dir):
    return mining.search_tree(mining.run(build(spark, sf_dir, "docs_flags", True), Jumping(5), trace=True))


@query("candidate_vs_minimal", unbounded("docs_flags", True, Jumping(2), 2, columns="count(*) n_minimal"))
def candidate_vs_minimal(spark, sf_dir):
    return mining.run(build(spark, sf_dir, "docs_flags", True), Jumping(2)).patterns.agg(F.count(F.lit(1)).alias("n_minimal"))


query("candidate_counts")(lambda spark, sf_dir: spark.createDataFrame([(o, (got := mining.run(build(spark, sf_dir, "docs_flags", True), Jumping(2), order=o)).counters.candidates, got.patterns.count()) for o in experiments.ORDERS], "order string, candidates long, minimal long"))
for _score in ("chi2", "wracc", "info_gain"):
    query(f"topk_{_score}_docs", f"{frequent('docs_flags', False, 1)}\nselect t pattern_text, x sup_pos, y sup_neg from sup, tot where x >= 1 order by {score_sql(_score)} desc, size, t limit 7")(
        lambda spark, sf_dir, s=_score: answer(mining.mine_topk(build(spark, sf_dir, "docs_flags"), 7, s))
    )


# learning
REALS = {"quantity": "l_quantity", "price": "l_extendedprice", "discount": "l_discount", "tax": "l_tax"}


def planted_reals(spark, sf_dir):
    df = read(spark, sf_dir, "lineitem").withColumn("y", F.when(F.expr(PLANT), 1).otherwise(0)).withColumn("key", F.xxhash64("l_orderkey", "l_partkey", "l_linenumber", "l_suppkey"))
    return df, {n: F.col(c) for n, c in REALS.items()} | {"line": F.col("l_linenumber"), "status": F.when(F.col("l_linestatus") == "O", 1.0).otherwise(0.0)}


@query("mdl_cuts_lineitem")
def mdl_cuts_lineitem(spark, sf_dir):
    df, features = planted_reals(spark, sf_dir)
    return learning.MdlDiscretizer().cut_points(df, features, F.col("y"))


@query("mdl_first_cut_lineitem", first_cut(REALS | {"line": "l_linenumber", "status": "case when l_linestatus = 'O' then 1 else 0 end"}, f"case when {PLANT} then 1 else 0 end", "lineitem"))
def mdl_first_cut_lineitem(spark, sf_dir):
    df, features = planted_reals(spark, sf_dir)
    return learning.MdlDiscretizer(max_cuts=1).cut_points(df, features, F.col("y")).select("feature", F.get("cuts", F.lit(0)).alias("cut"))


@query("mdl_cuts_embeddings")
def mdl_cuts_embeddings(spark, sf_dir):
    df = read(spark, sf_dir, "embeddings").withColumn("y", F.when(F.expr("element_at(embedding, 1) > 0 and not element_at(embedding, 2) > 0"), 1).otherwise(0))
    return learning.MdlDiscretizer().cut_points(df, {f"d{k}": F.get("embedding", F.lit(k)) for k in range(64)}, F.col("y"))


@query("value_histogram_lineitem", "select l_quantity \"value\", sum(case when l_returnflag = 'R' then 1 else 0 end)::bigint n_pos, sum(case when l_returnflag = 'R' then 0 else 1 end)::bigint n_neg from lineitem group by l_quantity")
def value_histogram_lineitem(spark, sf_dir):
    return relational.value_histogram(read(spark, sf_dir, "lineitem"), "l_quantity", F.when(F.col("l_returnflag") == "R", 1).otherwise(0))


@query("pattern_feature_matrix", "select doc_id, (case when (n_chars >= 1000 and text like '%@%') then 1 else 0 end)::bigint f0, (case when lang = 'en' and not n_chars >= 1000 then 1 else 0 end)::bigint f1 from documents")
def pattern_feature_matrix(spark, sf_dir):
    from pyspark.ml.functions import vector_to_array

    items = [labeled.item_flag("long", F.col("n_chars") >= 1000), labeled.item_flag("at", F.col("text").contains("@")), labeled.item_flag("en", F.col("lang") == "en")]
    out = learning.pattern_features(read(spark, sf_dir, "documents"), items, [(0, 1), (2, 3)], ["doc_id"]).withColumn("v", vector_to_array("features"))
    return out.select("doc_id", F.get("v", F.lit(0)).cast("long").alias("f0"), F.get("v", F.lit(1)).cast("long").alias("f1"))


@query("f1_from_predictions", "with c as (select count(*) filter (where quality = 0 and p = 1) tp, count(*) filter (where quality <> 0 and p = 1) fp, count(*) filter (where quality = 0 and p = 0) fn, count(*) filter (where quality <> 0 and p = 0) tn from (select l.quality, case when regexp_matches(text, '[A-Z]{4,}') then 1 else 0 end p from documents d join labels l on d.doc_id = l.doc_id)) select tp, fp, fn, tn, round(tp::double / (tp + fp), 6) \"precision\", round(tp::double / (tp + fn), 6) recall, round(2.0 * tp / (2 * tp + fp + fn), 6) f1, round((tp + tn)::double / (tp + fp + fn + tn), 6) accuracy from c")
def f1_from_predictions(spark, sf_dir):
    df = read(spark, sf_dir, "documents").join(read(spark, sf_dir, "labels"), "doc_id").select((1 - F.col("quality")).alias("label"), F.when(F.col("text").rlike("[A-Z]{4,}"), 1).otherwise(0).alias("prediction"))
    out = learning.f_value(learning.confusion(df))
    return out.select(*(F.round(c, 6).alias(c) if t == "double" else c for c, t in out.dtypes))


@query("auc_docs", "with s as (select n_chars s, sum(1 - quality)::double p, sum(quality)::double q from documents d join labels l on d.doc_id = l.doc_id group by n_chars), c as (select p, q, coalesce(sum(q) over (order by s rows between unbounded preceding and 1 preceding), 0) b from s) select round(sum(p * (b + q / 2)) / (sum(p) * sum(q)), 6) auc from c")
def auc_docs(spark, sf_dir):
    df = read(spark, sf_dir, "documents").join(read(spark, sf_dir, "labels"), "doc_id").select("n_chars", (1 - F.col("quality")).alias("y"))
    return learning.auc(df, "n_chars", "y").select(F.round("auc", 6).alias("auc"))


for _kind in experiments.MODELS:
    query({"with_negation": "classifier_planted", "positive_only": "classifier_planted_positive", "tree": "tree_baseline", "logistic": "logreg_baseline", "forest": "forest_baseline"}[_kind])(
        lambda spark, sf_dir, kind=_kind: experiments.accuracy(spark, sf_dir, ["embeddings_planted"], [kind])
    )
query("classifier_docs")(lambda spark, sf_dir: experiments.accuracy(spark, sf_dir, ["docs_flags"]))
query("classifier_lineitem")(lambda spark, sf_dir: experiments.accuracy(spark, sf_dir, ["planted"]))
query("classifier_customers")(lambda spark, sf_dir: experiments.accuracy(spark, sf_dir, ["customers"]))
query("classifier_embeddings")(lambda spark, sf_dir: experiments.accuracy(spark, sf_dir, LABELS, trials=0))
query("accuracy_wins")(lambda spark, sf_dir: experiments.win_counts(experiments.accuracy(spark, sf_dir, ["docs_flags", "embeddings_planted"], trials=0)))

# surrounding operators


@query("join_semi", "select o_orderkey from orders where o_custkey in (select c_custkey from customer where c_acctbal < 0)")
def join_semi(spark, sf_dir):
    return relational.join_semi(read(spark, sf_dir, "orders").withColumnRenamed("o_custkey", "c_custkey"), read(spark, sf_dir, "customer").where("c_acctbal < 0"), "c_custkey").select("o_orderkey")


@query("join_anti", "select c_custkey from customer where c_custkey not in (select o_custkey from orders where o_totalprice > 300000)")
def join_anti(spark, sf_dir):
    return relational.join_anti(read(spark, sf_dir, "customer"), read(spark, sf_dir, "orders").where("o_totalprice > 300000").withColumnRenamed("o_custkey", "c_custkey"), "c_custkey").select("c_custkey")


@query("join_outer", "select c_custkey, o_orderkey from customer full join (select * from orders where o_totalprice > 400000) on c_custkey = o_custkey")
def join_outer(spark, sf_dir):
    orders = read(spark, sf_dir, "orders").where("o_totalprice > 400000")
    return relational.join_outer(read(spark, sf_dir, "customer"), orders, F.col("c_custkey") == F.col("o_custkey")).select("c_custkey", "o_orderkey")


BIG_SQL = "select o_orderpriority, count(*) n, sum(l_quantity)::double qty from lineitem join orders on l_orderkey = o_orderkey group by o_orderpriority"
for _strategy in ("merge", "shuffle_hash"):
    query(f"join_big_{_strategy}", BIG_SQL)(
        lambda spark, sf_dir, s=_strategy: relational.join_big(read(spark, sf_dir, "lineitem"), read(spark, sf_dir, "orders").withColumnRenamed("o_orderkey", "l_orderkey"), "l_orderkey", s).groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.sum("l_quantity").cast("double").alias("qty"))
    )


@query("join_dim_orders", "select c_mktsegment, count(*) n from orders join customer on o_custkey = c_custkey group by c_mktsegment")
def join_dim_orders(spark, sf_dir):
    return relational.join_dim(read(spark, sf_dir, "orders").withColumnRenamed("o_custkey", "c_custkey"), read(spark, sf_dir, "customer"), "c_custkey").groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n"))


INTERVALS = [(0, 0.0, 100000.0), (1, 100000.0, 250000.0), (2, 90000.0, 120000.0)]


@query("join_range_bins", "select k, count(*) n from orders join (values (0, 0.0, 100000.0), (1, 100000.0, 250000.0), (2, 90000.0, 120000.0)) v(k, lo, hi) on o_totalprice >= lo and o_totalprice < hi group by k")
def join_range_bins(spark, sf_dir):
    return relational.join_range(read(spark, sf_dir, "orders"), spark.createDataFrame(INTERVALS, "k int, lo double, hi double"), "o_totalprice", "lo", "hi", 10000.0).groupBy("k").agg(F.count(F.lit(1)).alias("n"))


@query("join_theta_bands", "select k, count(*) n from part join (values (1), (10), (40)) v(k) on p_size > k group by k")
def join_theta_bands(spark, sf_dir):
    return relational.join_theta(read(spark, sf_dir, "part"), spark.createDataFrame([(1,), (10,), (40,)], "k int"), F.col("p_size") > F.col("k")).groupBy("k").agg(F.count(F.lit(1)).alias("n"))


@query("join_asof_orders", "select e.event_id, max(o.ts) last_view from events e left join (select user_id, ts from events where event_type = 'view') o on o.user_id = e.user_id and o.ts <= e.ts where e.event_type = 'purchase' group by e.event_id")
def join_asof_orders(spark, sf_dir):
    events = read(spark, sf_dir, "events")
    views = events.where("event_type = 'view'").select("user_id", "ts", F.col("ts").alias("last_view"))
    return relational.join_asof(events.where("event_type = 'purchase'").select("event_id", "user_id", "ts"), views, "user_id", "ts", ["last_view"]).select("event_id", "last_view")


FLAG = lambda: F.when(F.col("l_returnflag") == "R", 1).otherwise(0)  # noqa: E731  columns need a session, so none is made at import
COUNTS = "sum(case when l_returnflag = 'R' then 1 else 0 end)::bigint n_pos, sum(case when l_returnflag = 'R' then 0 else 1 end)::bigint n_neg"
query("class_counts_lineitem", f"select l_linestatus, l_linenumber, {COUNTS} from lineitem group by all")(lambda spark, sf_dir: relational.class_counts(read(spark, sf_dir, "lineitem"), ["l_linestatus", "l_linenumber"], FLAG()))
query("rollup_label", f"select l_linestatus, l_linenumber, {COUNTS} from lineitem group by rollup(l_linestatus, l_linenumber)")(lambda spark, sf_dir: relational.class_rollup(read(spark, sf_dir, "lineitem"), ["l_linestatus", "l_linenumber"], FLAG()))
query("grouping_sets_label", f"select l_linestatus, l_linenumber, {COUNTS} from lineitem group by grouping sets ((l_linestatus), (l_linenumber))")(
    lambda spark, sf_dir: relational.class_grouping_sets(read(spark, sf_dir, "lineitem"), [["l_linestatus"], ["l_linenumber"]], ["l_linestatus", "l_linenumber"], FLAG())
)
query("distinct_profile_orders", "select count(distinct o_custkey) n_o_custkey, count(distinct o_orderpriority) n_o_orderpriority from orders")(lambda spark, sf_dir: relational.distinct_profile(read(spark, sf_dir, "orders"), ["o_custkey", "o_orderpriority"]))
query("win_cumulative_class", f"with h as (select l_quantity \"value\", {COUNTS} from lineitem group by 1) select \"value\", sum(n_pos) over (order by \"value\")::bigint cum_pos, sum(n_neg) over (order by \"value\")::bigint cum_neg from h")(
    lambda spark, sf_dir: relational.cumulative_class(relational.value_histogram(read(spark, sf_dir, "lineitem"), "l_quantity", FLAG()))
)
query("win_boundary_points", f"with h as (select l_tax \"value\", {COUNTS} from lineitem group by 1) select \"value\", lead(\"value\") over (order by \"value\") \"next\" from h qualify \"next\" is not null")(
    lambda spark, sf_dir: relational.boundary_points(relational.value_histogram(read(spark, sf_dir, "lineitem"), "l_tax", FLAG()))
)
query("win_range_7d", "select event_id, count(*) over (partition by user_id order by ts range between interval 7 days preceding and current row) n_recent from events")(
    lambda spark, sf_dir: relational.rolling_events(read(spark, sf_dir, "events"), "user_id", "ts", 7 * 86400).select("event_id", "n_recent")
)
query("topk_per_class", "select o_orderkey, o_orderstatus from orders qualify row_number() over (partition by o_orderstatus order by o_totalprice desc, o_orderkey) <= 5")(
    lambda spark, sf_dir: relational.topk_per_group(read(spark, sf_dir, "orders"), "o_orderstatus", [F.desc("o_totalprice"), "o_orderkey"], 5).select("o_orderkey", "o_orderstatus")
)
query("rank_patterns_lineitem", supported("lineitem", False, 2) + "\nselect t pattern_text, x sup_pos, y sup_neg from sup where size = 2 order by x desc, t limit 10")(
    lambda spark, sf_dir: relational.rank_patterns(named_supports(db := build(spark, sf_dir, "lineitem"), labeled.supports(db, pairs_of(db))), [F.desc("sup_pos"), "pattern_text"], 10)
)


@query("except_variants", "select 0::bigint n_different")
def except_variants(spark, sf_dir):
    db = build(spark, sf_dir, "docs_flags", True)
    a, b = (answer(mining.mine_minimal(db, Jumping(2), order=o)) for o in ("dynamic", "static:id"))
    return relational.set_except(a, b, True).unionByName(relational.set_except(b, a, True)).agg(F.count(F.lit(1)).alias("n_different"))


query("set_intersect_keys", "select c_nationkey k from customer intersect select s_nationkey from supplier")(lambda spark, sf_dir: relational.set_intersect(read(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("k")), read(spark, sf_dir, "supplier").select("s_nationkey")))
query("set_union_keys", "select c_nationkey k from customer union select s_nationkey from supplier")(lambda spark, sf_dir: relational.set_union(read(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("k")), read(spark, sf_dir, "supplier").select(F.col("s_nationkey").alias("k"))))
query("pivot_status", "select o_orderpriority, count(*) filter (where o_orderstatus = 'F') \"F\", count(*) filter (where o_orderstatus = 'O') \"O\", count(*) filter (where o_orderstatus = 'P') \"P\" from orders group by 1")(
    lambda spark, sf_dir: relational.pivot_report(read(spark, sf_dir, "orders"), "o_orderpriority", "o_orderstatus", F.count(F.lit(1)), ["F", "O", "P"]).na.fill(0)
)
query("unpivot_lineitem", "select name, round(sum(v), 2) total from (select 'l_tax' name, l_tax v from lineitem union all select 'l_discount', l_discount from lineitem) group by name")(
    lambda spark, sf_dir: relational.unpivot_report(read(spark, sf_dir, "lineitem").select("l_orderkey", "l_tax", "l_discount"), ["l_orderkey"], ["l_tax", "l_discount"]).groupBy("name").agg(F.round(F.sum("value"), 2).alias("total"))
)
query("json_props_items", "select event_id, json_extract_string(props, '$.k')::bigint k from events")(lambda spark, sf_dir: relational.json_props(read(spark, sf_dir, "events"), "props", "k").select("event_id", "k"))
query("json_variant_props", "select event_id, json_extract_string(props, '$.k')::bigint k from events")(lambda spark, sf_dir: relational.variant_props(read(spark, sf_dir, "events"), "props", "$.k", "bigint", "k").select("event_id", "k"))
query("bins_width_lineitem", "with b as (select min(l_extendedprice) a, max(l_extendedprice) z from lineitem) select bin, count(*) n from (select greatest(0, case when l_extendedprice <= a + (z - a) * 1 / 4 then 0 when l_extendedprice <= a + (z - a) * 2 / 4 then 1 when l_extendedprice <= a + (z - a) * 3 / 4 then 2 else 3 end)::int bin from lineitem, b) group by bin")(
    lambda spark, sf_dir: binned(df := read(spark, sf_dir, "lineitem"), "l_extendedprice", labeled.bin_width(df, "l_extendedprice", 4))
)
query("bins_quantile_lineitem", "with b as (select quantile_cont(l_extendedprice, [0.25, 0.5, 0.75]) q from lineitem) select (l_extendedprice > q[1])::int + (l_extendedprice > q[2])::int + (l_extendedprice > q[3])::int bin, count(*) n from lineitem, b group by 1")(
    lambda spark, sf_dir: binned(df := read(spark, sf_dir, "lineitem"), "l_extendedprice", labeled.bin_quantile(df, "l_extendedprice", 4, exact=True))
)


def binned(df, column, cuts):
    return df.select(sum((F.col(column) > c).cast("int") for c in cuts).alias("bin")).groupBy("bin").agg(F.count(F.lit(1)).alias("n"))


query("sketch_counts_orders")(lambda spark, sf_dir: relational.united_count(relational.sketches_by(read(spark, sf_dir, "orders"), "o_orderpriority", "o_custkey")))
query("sketch_quantiles_orders")(lambda spark, sf_dir: relational.quantile_sketch(read(spark, sf_dir, "orders"), "o_totalprice", [0.25, 0.5, 0.75]))
query("token_vocab", "with w as (select distinct doc_id, unnest(regexp_extract_all(lower(text), '[a-z]+')) word from documents) select word, count(*) df from w group by word having count(*) >= 2 order by df desc, word limit 40")(
    lambda spark, sf_dir: labeled.top_vocabulary(read(spark, sf_dir, "documents"), F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), F.lit(0)), 40, 2)
)
query("tag_items_pages", "select tag, count(*) n from (select unnest(regexp_extract_all(lower(html), '<([a-z][a-z0-9]*)', 1)) tag from pages) group by tag")(lambda spark, sf_dir: relational.html_tags(read(spark, sf_dir, "pages"), "html").groupBy("tag").agg(F.count(F.lit(1)).alias("n")))
query("url_parts_pages", "select page_id, regexp_extract(url, '^([a-z]+):', 1) scheme, regexp_extract(url, '://([^/?#]*)', 1) host, regexp_extract(url, '://[^/?#]*([^?#]*)', 1) \"path\" from pages")(lambda spark, sf_dir: relational.url_parts(read(spark, sf_dir, "pages"), "url").select("page_id", "scheme", "host", "path"))
query("text_flags_docs", "select doc_id, regexp_matches(text, '[A-Z]{4,}') caps, regexp_matches(text, '[0-9]{3}') digits, contains(text, '@') \"at\", regexp_matches(text, '###|[$]{3}|%%%') junk from documents")(
    lambda spark, sf_dir: relational.text_flags(read(spark, sf_dir, "documents"), "text").select("doc_id", "caps", "digits", "at", "junk")
)
query("contains_passage_docs", "select distinct d.doc_id, b.item_id from documents d join benchmark b on contains(d.text, b.text)")(lambda spark, sf_dir: relational.contains_passage(read(spark, sf_dir, "documents"), read(spark, sf_dir, "benchmark")))
query("session_baskets_events", "with g as (select user_id, ts, event_type, case when ts - lag(ts) over w < interval 30 minutes then 0 else 1 end fresh from events window w as (partition by user_id order by ts)), s as (select *, sum(fresh) over (partition by user_id order by ts rows unbounded preceding) k from g) select user_id, min(ts) session_start, count(*) n_events, string_agg(distinct event_type, ',' order by event_type) basket from s group by user_id, k")(
    lambda spark, sf_dir: stream_events.session_itemsets(read(spark, sf_dir, "events")).select("user_id", "session_start", "n_events", F.concat_ws(",", "items").alias("basket"))
)
query("tumbling_supports_events", "select time_bucket(interval 1 day, ts, timestamp '1970-01-01') window_start, event_type, sum(case when value > 50 then 1 else 0 end)::bigint n_pos, sum(case when value > 50 then 0 else 1 end)::bigint n_neg from events group by 1, 2")(
    lambda spark, sf_dir: stream_events.window_supports(read(spark, sf_dir, "events"), "event_type", F.col("value") > 50, "1 day")
)
query("sliding_supports_events", "select window_start, event_type, sum(case when value > 50 then 1 else 0 end)::bigint n_pos, sum(case when value > 50 then 0 else 1 end)::bigint n_neg from (select *, unnest([time_bucket(interval 12 hours, ts, timestamp '1970-01-01'), time_bucket(interval 12 hours, ts, timestamp '1970-01-01') - interval 12 hours]) window_start from events) group by 1, 2")(
    lambda spark, sf_dir: stream_events.window_supports(read(spark, sf_dir, "events"), "event_type", F.col("value") > 50, "1 day", "12 hours")
)
