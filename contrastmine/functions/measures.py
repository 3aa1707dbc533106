"""Scalar measures and set helpers as columns, and the same as SQL functions."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

from ..operators.constraints import score_sql


def growth_rate_column(x: str, y: str) -> Column:
    """Raw counts; null where the negative support is 0 (see is_jumping)."""
    return F.when(F.col(y) > 0, F.col(x).cast("double") / F.col(y))


def score_column(name: str, x: str, y: str, n_pos: int, n_neg: int) -> Column:
    return F.expr(score_sql(name, x, y, str(n_pos), str(n_neg)))


def chi2_column(x: str, y: str, n_pos: int, n_neg: int) -> Column:
    return score_column("chi2", x, y, n_pos, n_neg)


def pattern_key(pattern) -> Column:
    return F.concat_ws(",", pattern)


def subset_of(small, big) -> Column:
    return F.size(F.array_except(small, big)) == 0


def register_sql(spark: SparkSession) -> None:
    """occurs, growth_rate, chi2, info_gain, gini_gain, wracc, support_diff as temporary SQL functions; their bodies are inlined."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION occurs(items ARRAY<INT>, pattern ARRAY<INT>, n INT) RETURNS BOOLEAN RETURN forall(pattern, l -> IF(l < n, array_contains(items, l), NOT array_contains(items, l - n)))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION growth_rate(x BIGINT, y BIGINT) RETURNS DOUBLE RETURN CASE WHEN y > 0 THEN CAST(x AS DOUBLE) / y END")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION subset_of(a ARRAY<INT>, b ARRAY<INT>) RETURNS BOOLEAN RETURN size(array_except(a, b)) = 0")
    for name in ("chi2", "info_gain", "gini_gain", "wracc", "support_diff"):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}(x BIGINT, y BIGINT, np BIGINT, nn BIGINT) RETURNS DOUBLE RETURN {score_sql(name)}")


def class_support(label, items, pattern, n_items: int, positive: bool = True) -> Column:
    """An aggregate: rows of one class in which the pattern occurs. label: 0/1; pattern: literals."""
    hit = F.forall(F.array(*map(F.lit, pattern)), lambda i: F.when(i < n_items, F.array_contains(items, i)).otherwise(~F.array_contains(items, i - n_items))) if len(pattern) else F.lit(True)
    return F.count_if(hit & (F.col(label) == int(positive)))


def popcount_and(a, b) -> Column:
    """Bits that two bitmaps of equal length share: an Arrow-batched function on binary columns."""
    @F.pandas_udf("long")
    def shared_bits(x: pd.Series, y: pd.Series) -> pd.Series:
        import numpy as np

        count = lambda p, q: None if p is None or q is None else int(np.bitwise_count(np.frombuffer(p, np.uint8) & np.frombuffer(q, np.uint8)).sum())
        return pd.Series([count(p, q) for p, q in zip(x, y, strict=True)], dtype="Int64")

    return shared_bits(a, b)


def register_table_function(spark: SparkSession) -> None:
    """mine_patterns(TABLE(t), min_pos, max_neg, theta, min_score, n_items, max_len, negation): minimal patterns of a table
    (items array<int>, label int) with a chi-square of at least min_score, searched in one task per partition of the table.

    A negative max_len is no cap; a partition with more than two million distinct item sets is refused."""
    from pyspark.sql.functions import udtf

    from ..operators.constraints import ChiSquare, Contrast, GrowthRate
    from ..operators.kernel import Search, Side
    from ..operators.minimal import minimal_by_trie

    @udtf(returnType="pattern array<int>, sup_pos bigint, sup_neg bigint")
    class MinePatterns:
        def __init__(self):
            self.rows = {}
            self.options = None

        def eval(self, row, min_pos: int, max_neg: int, theta: float, min_score: float, n_items: int, max_len: int, negation: bool):
            self.options = min_pos, max_neg, theta, min_score, n_items, max_len, negation
            cell = self.rows.setdefault(tuple(row["items"]), [0, 0])
            cell[0 if row["label"] == 1 else 1] += 1
            if len(self.rows) > 2_000_000:
                raise ValueError("too many distinct rows for one task; use mine_minimal")

        def terminate(self):
            if self.options is None:
                return
            min_pos, max_neg, theta, min_score, n, max_len, negation = self.options
            sets, p, q = list(self.rows), [c[0] for c in self.rows.values()], [c[1] for c in self.rows.values()]
            c = Contrast(min_pos, max_neg) & GrowthRate(theta)
            c = (c if min_score <= 0 else c & ChiSquare(min_score)).bind(sum(p), sum(q))
            got = {g[0]: g for g in Search(c, n, negation, max_len=None if max_len < 0 else max_len).run(Side(sets, p, n, negation), Side(sets, q, n, negation))}
            for k in minimal_by_trie(list(got)):
                yield list(k), got[k][1], got[k][2]

    spark.udtf.register("mine_patterns", MinePatterns)
