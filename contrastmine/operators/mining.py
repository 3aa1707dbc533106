"""Mining: minimal and full answers, presets for each constraint, counting without listing, and reports."""

from __future__ import annotations

import json
import time
from dataclasses import dataclass, replace
from itertools import combinations
from typing import Any

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.measures import chi2_column, growth_rate_column, score_column
from ..functions.scratch import settled, stored
from .constraints import SCORES, Both, ChiSquare, Constraint, Contrast, GrowthRate, Jumping, Score
from .frontier import FOUND, search_handed, search_levels, search_one_task
from .kernel import Counters, Rules, Search, Side
from .labeled import LabeledDB, arrays_of, rows_by_literal, supports
from .minimal import extract_maximal, extract_minimal

__all__ = ["Both", "ChiSquare", "Constraint", "Contrast", "GrowthRate", "IncompleteSearch", "Jumping", "Rules", "Score", "mine_minimal", "mine_all", "mine_sjeps", "mine_jeps", "mine_eps", "mine_contrast", "mine_chi2", "mine_score", "mine_maximal", "mine_topk"]

LOCAL_BYTES = 256 << 20
HAND_OVER = 200_000
CANDIDATES = "pattern array<int>, sup_pos long, sup_neg long"


class IncompleteSearch(RuntimeError):
    """The time limit ended a search: its candidates are some of the members, and no answer."""


@dataclass
class Mined:
    """candidates: pattern, sup_pos, sup_neg; patterns: the answer in the result schema, an error if the search did not end; counters and engine of the run."""

    db: LabeledDB
    candidates: DataFrame
    minimal: bool
    extraction: str
    counters: Counters
    engine: str
    nc_used: bool
    trace: list
    sizes: tuple[int, int]

    @property
    def complete(self) -> bool:
        return not self.counters.timeout

    @property
    def patterns(self) -> DataFrame:
        if not self.complete:
            raise IncompleteSearch("the search ran out of time; its candidates are not an answer")
        kept = extract_minimal(self.candidates, self.extraction) if self.minimal else self.candidates
        return finish(self.db, kept, self.sizes)


def finish(db: LabeledDB, found: DataFrame, sizes: tuple[int, int]) -> DataFrame:
    """The result schema of every miner."""
    names = F.array(*(F.lit(db.literal_name(i)) for i in range(db.n_items * (1 + db.negation)))) if db.n_items else F.array().cast("array<string>")
    text = F.concat_ws(" & ", F.transform("pattern", lambda i: F.get(names, i)))
    negated = F.size(F.filter("pattern", lambda i: i >= db.n_items))
    return found.select(
        "pattern", text.alias("pattern_text"), F.size("pattern").alias("size"), (F.size("pattern") - negated).alias("n_pos_literals"), negated.alias("n_neg_literals"),
        "sup_pos", "sup_neg", growth_rate_column("sup_pos", "sup_neg").alias("growth_rate"), (F.col("sup_neg") == 0).alias("is_jumping"), chi2_column("sup_pos", "sup_neg", *sizes).alias("chi2"),
    )


def choose_engine(db: LabeledDB, n_distinct: int) -> str:
    """One task while the bitmaps of all distinct rows stay within a bound, else the cluster with hand-over."""
    return "local" if n_distinct * db.n_items * (1 + db.negation) / 8 <= LOCAL_BYTES else "hybrid"


class Findings:
    """Candidates as they come: on the driver up to a bound, beyond it in tables of the shared folder; and the tasks' reports."""

    def __init__(self, db: LabeledDB, search: Search, most: int = 50_000):
        self.spark, self.search, self.most = db.rows.sparkSession, search, most
        self.rows: list[tuple] = []
        self.tables: list[DataFrame] = []

    def add(self, rows: list[tuple]) -> None:
        self.rows += rows
        if len(self.rows) > self.most:
            self.tables.append(stored(self.spark.createDataFrame(self.rows, CANDIDATES), "candidates"))
            self.rows = []

    def add_tasks(self, found: DataFrame) -> None:
        held = found.persist()
        for r in held.where("report is not null").select("report").collect():  # one row per task
            told = json.loads(r.report)
            self.search.counters.add(Counters(**told["counters"]))
            if self.search.trace is not None:
                self.search.trace += [tuple(t) for t in told["trace"] or []]
        self.tables.append(settled(held.where("report is null").drop("report"), "candidates", self.most))
        held.unpersist()

    def frame(self) -> DataFrame:
        parts = ([self.spark.createDataFrame(self.rows, CANDIDATES)] if self.rows or not self.tables else []) + self.tables
        out = parts[0]
        for p in parts[1:]:
            out = out.unionByName(p)
        return out


def run(db: LabeledDB, constraint: Constraint, order: str = "dynamic", rules: Rules | None = None, max_len: int | None = None, engine: str = "auto", minimal: bool = True, extraction: str = "subset_join", timeout_s: float | None = None, trace: bool = False, hand_over: int | None = None, limit: int | None = None) -> Mined:
    """Search now, and return candidates, counters and a lazy answer. The source is read once.

    engine: local (one task), frontier, hybrid, matrix:linked, matrix:bitset (one task on reducible matrices), or auto.
    timeout_s: seconds for the whole search; beyond them, candidates stay readable and `patterns` is an error.
    limit: stop after so many members; only where every member is asked for."""
    if limit is not None and minimal:
        raise ValueError("a limit would make minimality wrong; ask for all members")
    rules = rules or Rules()
    begin = time.monotonic()
    cached = db.rows.storageLevel.useMemory or db.rows.storageLevel.useDisk
    held = db if cached else db.persist()
    n_pos, n_neg, n_distinct = held.measure()
    constraint.bind(n_pos, n_neg)
    search = Search(constraint, db.n_items, db.negation, order, rules, max_len, timeout_s, [] if trace else None, allowed=tuple(db.literals()))
    engine = choose_engine(db, n_distinct) if engine == "auto" else engine
    found = Findings(db, search)
    if engine in ("local", "matrix:linked", "matrix:bitset"):
        if n_distinct:
            found.add_tasks(search_one_task(held, search, limit, engine.partition(":")[2] or None))
        elif bool(constraint.member(0, 0)):
            found.add([([], 0, 0)])
    else:

        def hand(nodes, rank):
            left = None if timeout_s is None else max(0.0, timeout_s - (time.monotonic() - begin))
            found.add_tasks(search_handed(held, replace(search, timeout_s=left), nodes, rank))

        few = 0 if engine == "frontier" else HAND_OVER if hand_over is None else hand_over
        search_levels(held, search, (n_pos, n_neg), found.add, hand, hand_over=few)
    if not cached:
        held.rows.unpersist()
    candidates = found.frame() if limit is None else found.frame().limit(limit)
    return Mined(db, candidates, minimal, extraction, search.counters, engine, rules.use_nc(constraint), search.trace or [], (n_pos, n_neg))


def mine_minimal(db: LabeledDB, constraint: Constraint, **options) -> DataFrame:
    return run(db, constraint, **options).patterns


def all_rules(constraint: Constraint) -> Rules:
    return Rules(stop=False, lb=True, nc="off")


def mine_all(db: LabeledDB, constraint: Constraint, **options) -> DataFrame:
    """Every member, minimal or not: members are extended, and no literal is dropped for leaving the negative support unchanged."""
    return run(db, constraint, rules=all_rules(constraint), minimal=False, **options).patterns


def mine_maximal(db: LabeledDB, constraint: Constraint, **options) -> DataFrame:
    found = run(db, constraint, rules=all_rules(constraint), minimal=False, **options)
    return finish(db, extract_maximal(found.patterns.select("pattern", "sup_pos", "sup_neg")), found.sizes)


def mine_jeps(db: LabeledDB, min_pos: int = 1, **options) -> DataFrame:
    return mine_all(db, Jumping(min_pos), **options)


def mine_sjeps(db: LabeledDB, min_pos: int = 1, **options) -> DataFrame:
    return mine_minimal(db, Jumping(min_pos), **options)


def mine_contrast(db: LabeledDB, min_pos: int, max_neg: int, **options) -> DataFrame:
    return mine_minimal(db, Contrast(min_pos, max_neg), **options)


def mine_eps(db: LabeledDB, theta: float, min_pos: int = 1, **options) -> DataFrame:
    return mine_minimal(db, Contrast(min_pos, 1 << 62) & GrowthRate(theta), **options)


def mine_score(db: LabeledDB, score: str, min_score: float, min_pos: int = 0, **options) -> DataFrame:
    return mine_minimal(db, Contrast(min_pos, 1 << 62) & Score(score, min_score), **options)


def mine_chi2(db: LabeledDB, min_score: float, min_pos: int = 0, **options) -> DataFrame:
    return mine_score(db, "chi2", min_score, min_pos, **options)


def count_jeps(db: LabeledDB, min_pos: int = 1) -> DataFrame:
    """The number of jumping patterns, as one row of decimal(38,0); whole sub-lattices are counted at once.

    Each non-empty pattern is counted in the task of its first literal, which has the rows that hold it."""
    n, negation, literals = db.n_items, db.negation, db.literals()
    n_pos, n_neg = db.sizes()

    def task(key: tuple[Any, ...], frame: pd.DataFrame) -> pd.DataFrame:
        from decimal import Decimal

        first = key[0]
        later = [i for i in literals if i > first and i % n != first % n]
        sets, p, q = arrays_of(frame)
        total = Search(Jumping(min_pos), n, negation).count_jumping(Side(sets, p, n, negation), Side(sets, q, n, negation), min_pos, later)
        return pd.DataFrame({"n": [Decimal(total)]})

    counted = rows_by_literal(db).groupBy("literal").applyInPandas(task, "n decimal(38,0)")
    empty = int(n_neg == 0 and n_pos >= min_pos)
    return counted.agg((F.coalesce(F.sum("n"), F.lit(0)) + F.lit(empty)).cast("decimal(38,0)").alias("n_jeps"))


def mine_topk(db: LabeledDB, k: int, score: str = "chi2", max_len: int | None = None, start: float | None = None, **options) -> DataFrame:
    """The k best patterns with a positive row by any score, ties by size and text: a threshold falls from the greatest value that counts can give until k members are found."""
    n_pos, n_neg = db.sizes()
    corners = [float(SCORES[score](x, y, n_pos, n_neg)) for x in (0, n_pos) for y in (0, n_neg)] if n_pos and n_neg else [0.0]
    top = max(corners)
    least = start if start is not None else top / 4 if top > 0 else float("-inf")
    while True:
        found = run(db, Contrast(1, 1 << 62) & Score(score, least), rules=all_rules(None), minimal=False, max_len=max_len, **options)
        if least == float("-inf") or found.candidates.count() >= k:
            ranked = found.patterns.withColumn("_score", score_column(score, "sup_pos", "sup_neg", n_pos, n_neg))
            return ranked.orderBy(F.desc("_score"), "size", "pattern_text").limit(k).drop("_score")
        least = least / 4 if least > 1e-9 * top else float("-inf")


def dry_run(db: LabeledDB, constraint_of, share: float = 0.001, least_rows: int = 2000, **options) -> dict:
    """Size of a search before a full run: the same search on a hash-drawn share of the distinct rows, at least so many of them expected.

    constraint_of(scale) gives the constraint with its counts scaled down. Says how many nodes and candidates to expect;
    answers of a full run never depend on it."""
    rows = db.measure()[2]
    part = min(1.0, max(share, least_rows / max(1, rows)))
    drawn = LabeledDB(db.rows.where(F.pmod(F.xxhash64("items", F.lit("dry run")), F.lit(1 << 30)) < int(part * (1 << 30))), db.names, db.negation, db.negated)
    got = run(drawn, constraint_of(part), engine="local", **options)
    return {"share": part, "distinct_rows": rows, "nodes": got.counters.nodes, "candidates": got.counters.candidates, "timeout": got.counters.timeout}


def region_report(db: LabeledDB, patterns: DataFrame, contrast: Contrast, theta: float) -> DataFrame:
    """Each pattern as a point of the two supports, with flags for the rectangle, the triangle and both."""
    x, y = F.col("sup_pos"), F.col("sup_neg")
    inside, steep = F.expr(contrast.sql("sup_pos", "sup_neg")), F.expr(GrowthRate(theta).sql("sup_pos", "sup_neg"))
    return patterns.select("pattern_text", y.alias("sup_neg"), x.alias("sup_pos"), inside.alias("in_rectangle"), steep.alias("in_triangle"), (inside & steep).alias("in_both"))


def descendant_bounds(db: LabeledDB, pattern, rest) -> DataFrame:
    """Least negative and greatest positive support that descendants within the remaining literals can have."""
    whole = tuple(sorted({*pattern, *rest}))
    got = {tuple(r.pattern): r for r in supports(db, [tuple(sorted(pattern)), whole]).collect()}
    own, least = got[tuple(sorted(pattern))], got[whole]
    return db.rows.sparkSession.createDataFrame([(db.text(pattern), own.sup_pos, least.sup_neg, own.sup_neg)], "pattern_text string, most_pos long, least_neg long, most_neg long")


def score_bound(db: LabeledDB, pattern, rest, score: str = "chi2") -> DataFrame:
    """(pattern_text, own, most): the score of a pattern, and the bound on the scores of its descendants within the remaining literals."""
    c = Score(score).bind(*db.sizes())
    b = descendant_bounds(db, pattern, rest).first()
    return db.rows.sparkSession.createDataFrame([(b.pattern_text, float(c.value(b.most_pos, b.most_neg)), float(c.most(b.most_pos, b.least_neg, b.most_neg)))], "pattern_text string, own double, most double")


def minimality(db: LabeledDB, patterns, constraint: Constraint) -> DataFrame:
    """(pattern_text, member, minimal) of listed patterns; a minimal one is a member none of whose proper subsets is a member.

    The supports of all subsets come from one pass; the list and its subsets are held by the driver, which has them from the caller."""
    patterns = [tuple(sorted(p)) for p in patterns]
    c = constraint.bind(*db.sizes())
    below = {p: [s for k in range(len(p)) for s in combinations(p, k)] for p in patterns}
    told = {tuple(r.pattern): bool(c.member(r.sup_pos, r.sup_neg)) for r in supports(db, {s for p in patterns for s in (*below[p], p)}).collect()}
    rows = [(db.text(p), told[p], told[p] and not any(told[s] for s in below[p])) for p in patterns]
    return db.rows.sparkSession.createDataFrame(rows, "pattern_text string, member boolean, minimal boolean")


def is_minimal(db: LabeledDB, pattern, constraint: Constraint) -> bool:
    return minimality(db, [pattern], constraint).first().minimal


def search_tree(mined: Mined) -> DataFrame:
    """Visited nodes with counts, the bound and the verdict."""
    rows = [(mined.db.text(p), mined.db.text(sorted(p)[:-1]) if p else None, len(p), int(x), int(y), lb, v) for p, x, y, lb, v in mined.trace]
    return mined.db.rows.sparkSession.createDataFrame(rows, "pattern_text string, without_last string, size int, sup_pos long, sup_neg long, least_neg long, verdict string")
