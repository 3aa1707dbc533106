"""Plans, stores, the transactions source, relational operators and streams."""

import datetime as dt

import numpy as np
import pytest
from pyspark.sql import functions as F

from contrastmine.operators import frontier, labeled, relational
from contrastmine.sources import stores
from contrastmine.sources.workloads import build, read
from contrastmine.streaming import events as S


def plan(df):
    return df._jdf.queryExecution().toString()


def test_plans_are_as_declared(spark, sf):
    db = build(spark, sf, "orders")
    text = plan(db.rows)
    assert "BroadcastHashJoin" in text and "o_comment" not in text and "PushedFilters: [IsNotNull(o_custkey)]" in text and "Python" not in text
    supports = plan(labeled.supports(db, [(0,), (0, 1)]))
    assert "BroadcastNestedLoopJoin" in supports and "partial_sum" in supports and "Python" not in supports
    orders, lines = read(spark, sf, "orders"), read(spark, sf, "lineitem").withColumnRenamed("l_orderkey", "o_orderkey")
    assert "SortMergeJoin" in plan(relational.join_big(lines, orders, "o_orderkey", "merge"))
    assert "ShuffledHashJoin" in plan(relational.join_big(lines, orders, "o_orderkey", "shuffle_hash"))
    assert "LeftAnti" in plan(relational.join_anti(orders, lines, "o_orderkey")) and "TakeOrderedAndProject" in plan(relational.rank_patterns(orders, ["o_totalprice"], 3))


def test_blocks_round_trip(spark, sf, tmp_path):
    db = build(spark, sf, "lineitem")
    stores.write_blocks(frontier.to_blocks(db, 512), str(tmp_path / "b"))
    blocks = stores.read_blocks(spark, str(tmp_path / "b"))
    (got,) = frontier.count_nodes(blocks, [((), list(range(db.n_items)))], db.n_items, False, False)
    want = {r.pattern[0]: (r.sup_pos, r.sup_neg) for r in labeled.literal_supports(db).collect()}
    assert [tuple(map(int, c)) for c in got.T] == [want[i] for i in range(db.n_items)] and blocks.agg(F.max("n_rows")).first()[0] <= 512


def test_wide_masks(spark):
    names = [f"i{k:03d}" for k in range(150)]
    db = labeled.from_sets(spark, [["i000", "i063", "i149"], ["i149"]], [["i062", "i063"]], names=names).with_negation()
    got = {tuple(r.pattern): (r.sup_pos, r.sup_neg) for r in labeled.supports(db, [(63,), (0, 149), (149, 150 + 63), ()]).collect()}
    assert got == {(63,): (1, 1), (0, 149): (1, 0), (149, 213): (1, 0), (): (2, 1)}


def test_stores_and_transactions_source(spark, tmp_path):
    rows = [[3, 1, 2], [], [7], list(range(40))] * 50
    df = spark.createDataFrame([(sorted(r),) for r in rows], "items array<int>").coalesce(1)
    stores.write_transactions(df, str(tmp_path / "t"))
    back = sorted(map(tuple, (r.items for r in stores.read_transactions(spark, str(tmp_path / "t")).collect())))
    assert back == sorted(tuple(sorted(r)) for r in rows)
    (part,) = (tmp_path / "t").glob("part-*")
    spark.dataSource.register(stores.TransactionDataSource)
    for size in (64, 1000, 1 << 20):
        got = spark.read.format("transactions").option("rangebytes", str(size)).load(f"file://{part}")
        assert sorted(tuple(r.items) for r in got.collect()) == back
    (tmp_path / "s.txt").write_text("1 3:1 1:0.5 2:0\n-1 4:1\n\n")
    assert [(r.label, r["items"]) for r in stores.read_libsvm(spark, str(tmp_path / "s.txt")).collect()] == [(1, [1, 3]), (-1, [4])]
    tag = stores.write_items(spark, ("a", "b"), str(tmp_path / "i"))
    assert stores.read_items(spark, str(tmp_path / "i")) == (("a", "b"), tag)
    stores.write_patterns(df.limit(2), str(tmp_path / "p"), "r1")
    assert stores.read_patterns(spark, str(tmp_path / "p"), "r1").count() == 2 and stores.read_patterns(spark, str(tmp_path / "p")).columns == ["items", "run_id"]


def test_asof_range_and_subset_joins(spark):
    at = lambda s: dt.datetime(2024, 1, 1, 0, 0, s)
    left = spark.createDataFrame([("u", at(5), 1), ("u", at(1), 2), ("v", at(9), 3)], "k string, ts timestamp, id int")
    right = spark.createDataFrame([("u", at(1), 10), ("u", at(4), 11), ("u", at(6), 12)], "k string, ts timestamp, v int")
    assert {r.id: r.v for r in relational.join_asof(left, right, "k", "ts", ["v"]).collect()} == {1: 11, 2: 10, 3: None}
    bins = relational.join_range(spark.range(20).toDF("x"), spark.createDataFrame([(0, 3.0, 7.0), (1, 6.5, 30.0)], "k int, lo double, hi double"), "x", "lo", "hi", 4.0)
    assert {(r.x, r.k) for r in bins.collect()} == {(x, 0) for x in range(3, 7)} | {(x, 1) for x in range(7, 20)}
    sets = spark.createDataFrame([([1],), ([1, 2],), ([2, 3],), ([1, 2, 3],)], "pattern array<int>")
    assert {(tuple(r.small), tuple(r.big)) for r in relational.join_subset(sets, sets).collect()} == {((1,), (1, 2)), ((1,), (1, 2, 3)), ((1, 2), (1, 2, 3)), ((2, 3), (1, 2, 3))}


def stream_of(spark, tmp_path, rows, schema):
    for k, r in enumerate(rows):
        spark.createDataFrame(r, schema).coalesce(1).write.parquet(str(tmp_path / f"in/{k}"))
    (tmp_path / "flat").mkdir()
    for k in range(len(rows)):
        (part,) = (tmp_path / f"in/{k}").glob("part-*")
        part.rename(tmp_path / f"flat/{k}.parquet")
    return S.read_events(spark, str(tmp_path / "flat"), schema)


def drain(df, name, mode):
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination(120)
    return q


def test_windows_drop_late_rows_and_match_the_batch(spark, tmp_path):
    at = lambda h, m=0: dt.datetime(2024, 1, 1, h, m)
    schema = "ts timestamp, event_type string, value double"
    rows = [[(at(0, 5), "a", 60.0), (at(0, 50), "b", 1.0)], [(at(5), "a", 70.0)], [(at(5, 10), "c", 1.0)], [(at(0, 10), "a", 99.0), (at(6), "b", 2.0)], [(at(20), "z", 0.0)]]
    stream = stream_of(spark, tmp_path, rows, schema)
    q = drain(S.window_supports(stream, "event_type", F.col("value") > 50, "1 hour", watermark="1 hour"), "w1", "append")
    got = {(r.window_start, r.event_type): (r.n_pos, r.n_neg) for r in spark.table("w1").collect()}
    kept = spark.createDataFrame([r for part in rows for r in part if r[2] not in (99.0, 0.0)], schema)
    assert got == {(r.window_start, r.event_type): (r.n_pos, r.n_neg) for r in S.window_supports(kept, "event_type", F.col("value") > 50, "1 hour").collect()}
    assert sum(int(s["numRowsDroppedByWatermark"]) for p in q.recentProgress for s in p["stateOperators"]) >= 1


def test_patterns_drift_sessions_and_dedup_on_streams(spark, tmp_path):
    at = lambda m: dt.datetime(2024, 1, 1, m // 60, m % 60)
    schema = "id long, ts timestamp, user_id long, event_type string, value double"
    rows = [[(1, at(0), 1, "a", 60.0), (1, at(0), 1, "a", 60.0), (2, at(10), 1, "b", 1.0)], [(3, at(100), 2, "a", 70.0), (4, at(101), 2, "a", 1.0)], [(5, at(600), 9, "c", 0.0)]]
    stream = stream_of(spark, tmp_path, rows, schema)
    items = [labeled.item_flag("a", F.col("event_type") == "a"), labeled.item_flag("early", F.hour("ts") < 1)]
    batch = spark.createDataFrame([r for part in rows for r in part], schema)
    got = {(r.pattern, r.n_pos, r.n_neg) for r in S.pattern_window_supports(batch, items, {"a": (0,), "a & !early": (0, 3)}, F.col("value") > 50, "1 day").collect()}
    assert got == {("a", 3, 1), ("a & !early", 1, 1)}
    drain(S.session_itemsets(stream, watermark="10 minutes"), "s1", "append")
    assert {(r.user_id, r.n_events, tuple(r["items"])) for r in spark.table("s1").collect()} == {(1, 3, ("a", "b")), (2, 2, ("a",))}
    drain(S.dedup(stream, "id"), "d1", "append")
    assert spark.table("d1").count() == 5
    counts = stream.select(F.col("event_type").alias("pattern"), (F.col("value") > 50).cast("long").alias("n_pos"), (F.col("value") <= 50).cast("long").alias("n_neg"))
    drain(S.drift(counts, lambda x, y: x >= 3 and y <= 1), "r1", "append")
    assert [(r.pattern, r.inside) for r in spark.table("r1").collect()] == [("a", True)]


def test_mining_again_when_due(spark, tmp_path):
    schema = "ts timestamp, event_type string, value double"
    rows = [[(dt.datetime(2024, 1, 1), "a", 60.0)], [(dt.datetime(2024, 1, 2), "a", 70.0), (dt.datetime(2024, 1, 2), "b", 1.0)]]
    stream = stream_of(spark, tmp_path, rows, schema)
    seen = []
    items = [labeled.item_flag("a", F.col("event_type") == "a")]
    due = lambda held: (held.agg(F.sum("w_pos")).first()[0] or 0) >= 2
    q = S.mine_again(stream, items, F.col("value") > 50, str(tmp_path / "rows"), due, lambda held: seen.append(sorted((tuple(r["items"]), r.w_pos, r.w_neg) for r in held.collect()))).trigger(availableNow=True).start()
    q.awaitTermination(120)
    assert seen == [[((), 0, 1), ((0,), 2, 0)]]


def test_whole_passages_beside_other_characters(spark):
    """Passages that touch punctuation or letters, short ones, repeats, nulls and empties, against the plain test."""
    from contrastmine.operators.relational import contains_passage

    texts = ["say (alpha beta gamma delta eps) now", "xalpha beta gammay", "alpha beta", "", None, "a-b", "zz a", "Alpha beta gamma", "one two three four five six seven eight", "say (alpha beta gamma delta eps) now"]
    passages = ["alpha beta gamma", "alpha beta gamma delta eps", "(alpha", "a", "-b", "", None, "two three four five six seven", "lpha beta gam", "beta", "alpha beta gamma"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    items = spark.createDataFrame(list(enumerate(passages)), "item_id long, text string")
    got = contains_passage(docs, items)
    assert sorted((r.doc_id, r.item_id) for r in got.collect()) == sorted((i, j) for i, t in enumerate(texts) for j, p in enumerate(passages) if t is not None and p is not None and p in t)
    assert contains_passage(docs.limit(0), items).count() == contains_passage(docs, items.limit(0)).count() == 0


def test_broadcast_bound_counts_bytes(spark):
    from pyspark.sql import functions as F

    from contrastmine.operators.relational import small

    plan = lambda df: df._jdf.queryExecution().optimizedPlan().toString()
    wide = spark.range(50).select("id", F.repeat(F.lit("x"), 1000).alias("t"))
    assert "ResolvedHint" not in plan(small(wide, most_bytes=1000)) and small(wide, most_bytes=1000) is wide and small(wide) is not wide


def test_scratch_tables_are_removed(spark):
    import os

    from contrastmine.functions.scratch import clear_scratch, scratch_mark, settled, stored

    mark = scratch_mark()
    df = spark.range(10)
    a, b = stored(df, "a"), settled(df, "b", most=3)
    assert a.count() == b.count() == 10 and settled(df, "c").count() == 10
    paths = [f.removeprefix("file:") for t in (a, b) for f in t.inputFiles()]
    assert all(map(os.path.exists, paths)) and clear_scratch(spark, mark) == 2 and not any(map(os.path.exists, paths))


def test_sketches_are_close_and_unite(spark):
    from contrastmine.operators import relational as R

    df = spark.range(20000).selectExpr("id % 5000 as a", "id % 7 as g", "cast(id as double) as v")
    assert abs(R.sketch_profile(df, ["a"]).first().n_a - 5000) < 250 and abs(R.united_count(R.sketches_by(df, "g", "a")).first().n - 5000) < 250
    got = {r.share: r.value for r in R.quantile_sketch(df, "v", [0.25, 0.5]).collect()}
    assert abs(got[0.25] - 5000) < 500 and abs(got[0.5] - 10000) < 500


@pytest.mark.parametrize("n", [0, 1, 5, 3000])
def test_windows_over_a_whole_order_run_part_by_part(spark, n):
    rng = np.random.default_rng(n)
    rows = [(float(v), int(p), int(q)) for v, p, q in zip(rng.permutation(n), rng.integers(0, 3, n), rng.integers(0, 3, n), strict=True)] + [(None, 2, 1)] * (n > 1)
    hist = spark.createDataFrame(rows, "value double, n_pos long, n_neg long")
    order = sorted(rows, key=lambda r: (r[0] is not None, r[0]))
    sums = [(r[0], sum(s[1] for s in order[: k + 1]), sum(s[2] for s in order[: k + 1])) for k, r in enumerate(order)]
    got = [tuple(r) for r in relational.cumulative_class(hist).collect()]
    assert sorted(got, key=lambda r: (r[0] is not None, r[0])) == sums
    cuts = {(a[0], b[0]) for a, b in zip(order, order[1:], strict=False) if a[1] * b[2] != a[2] * b[1] or (a[1] and a[2])}
    assert {tuple(r) for r in relational.boundary_points(hist).collect()} == cuts
    assert n < 3000 or hist.select(relational.ordered_parts(hist, "value").alias("p")).distinct().count() > 200
