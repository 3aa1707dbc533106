"""The search across a cluster: level by level on blocks of column bitmaps, with hand-over of small subtrees to single tasks.

A block holds up to 65,536 distinct rows as one bitmap per item, with the rows' weights as bit planes for each class.
Counting a batch of nodes is one pass over the blocks: tasks keep sums per node and the sums of all tasks are added. The
driver judges a batch at a time, last batch first, so it holds one path of batches and never a whole level; candidates
and subtrees to hand over leave it in waves of a bounded size. A node with few rows is handed over: its rows go to one
task, which searches its subtree."""

from __future__ import annotations

import json
import time
from collections.abc import Callable, Iterator
from dataclasses import replace
from typing import Any

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .branching import search_matrices
from .kernel import Counters, Search, Side, least_by_length, pack_rows, static_rank
from .labeled import LabeledDB, arrays_of

BLOCKS = "block_id string, n_rows long, columns binary, pos_planes array<binary>, neg_planes array<binary>"
FOUND = "pattern array<int>, sup_pos long, sup_neg long, report string"
MOST_ROWS = 65536
WAVE_NODES, WAVE_ROWS = 2000, 8_000_000


def _planes(weights: np.ndarray) -> list[bytes]:
    return [pack_rows((weights >> b & 1)[:, None])[0].tobytes() for b in range(int(weights.max(initial=0)).bit_length())]


def to_blocks(db: LabeledDB, rows_per_block: int = MOST_ROWS) -> DataFrame:
    """Narrow: each task packs its own rows."""
    n = db.n_items

    def pack(frames: Iterator[pd.DataFrame]):
        import uuid

        held: list[tuple] = []

        def block():
            dense = np.zeros((len(held), n), np.uint8)
            for r, (items, _, _) in enumerate(held):
                dense[r, items] = 1
            p, q = (np.array([h[k] for h in held], np.int64) for k in (1, 2))
            return pd.DataFrame({"block_id": [uuid.uuid4().hex], "n_rows": [len(held)], "columns": [pack_rows(dense).tobytes()], "pos_planes": [_planes(p)], "neg_planes": [_planes(q)]})

        for frame in frames:
            for row in zip(*arrays_of(frame), strict=True):
                held.append(row)
                if len(held) == rows_per_block:
                    yield block()
                    held = []
        if held:
            yield block()

    return db.rows.mapInPandas(pack, BLOCKS)


def _open(block, n_items: int, negation: bool):
    words = -(-block.n_rows // 64)
    columns = np.frombuffer(block.columns, np.uint64).reshape(n_items, words)
    full = pack_rows(np.ones((block.n_rows, 1), np.uint8))[0]
    if negation:
        columns = np.concatenate((columns, ~columns & full))
    planes = [[(1 << b, np.frombuffer(p, np.uint64)) for b, p in enumerate(side)] for side in (block.pos_planes, block.neg_planes)]
    return columns, full, planes


def _weigh(masks: np.ndarray, planes) -> np.ndarray:
    out = np.zeros(len(masks), np.int64)
    for weight, plane in planes:
        out += weight * np.bitwise_count(masks & plane).sum(axis=1, dtype=np.int64)
    return out


def count_nodes(blocks: DataFrame, nodes: list[tuple[tuple[int, ...], np.ndarray]], n_items: int, negation: bool, suffix: bool) -> list[np.ndarray]:
    """For each node (pattern, literals): class supports of the pattern with each literal, as a (2, k) array; with suffix=True, the negative support of the pattern with all literals from each place on, as (1, k)."""
    plain = [(list(p), np.asarray(rest, int).tolist()) for p, rest in nodes]

    def count(frames: Iterator[pd.DataFrame]):
        sums = None
        for frame in frames:
            for block in frame.itertuples(index=False):
                columns, full, (pos, neg) = _open(block, n_items, negation)
                got = []
                for pattern, rest in plain:
                    mask = np.bitwise_and.reduce(columns[pattern], axis=0) if pattern else full
                    part = columns[rest] & mask
                    if suffix:
                        got.append(_weigh(np.bitwise_and.accumulate(part[::-1], axis=0)[::-1], neg)[None])
                    else:
                        got.append(np.stack((_weigh(part, pos), _weigh(part, neg))))
                sums = got if sums is None else [a + b for a, b in zip(sums, got, strict=True)]
        if sums is not None:
            yield pd.DataFrame({"node": range(len(sums)), "sums": [s.ravel().tolist() for s in sums]})

    added = blocks.mapInPandas(count, "node int, sums array<long>").select("node", F.posexplode("sums").alias("at", "v")).groupBy("node", "at").agg(F.sum("v").alias("v"))
    out = [np.zeros((1 if suffix else 2) * len(rest), np.int64) for _, rest in plain]
    for r in added.collect():  # as many as the batch has literals
        out[r.node][r.at] = r.v
    return [o.reshape(1 if suffix else 2, -1) for o in out]


def search_levels(db: LabeledDB, search: Search, sizes: tuple[int, int], emit: Callable[[list[tuple]], None], hand: Callable[[list[tuple], np.ndarray | None], None], batch: int = 512, hand_over: int = 0) -> None:
    """Search from the root. Candidates go to emit(list) batch by batch; nodes with at most `hand_over` rows are not searched here but go to hand(nodes, rank) in waves."""
    c, rules, n, count = search.constraint, search.rules, db.n_items, search.counters
    nc = rules.use_nc(c)
    begin = time.monotonic()
    blocks = to_blocks(db).persist()
    words = blocks.agg(F.coalesce(F.sum(F.ceil(F.col("n_rows") / 64)), F.lit(0)).alias("w")).first().w
    literals, rank = search.literals(), None
    if search.order != "dynamic" and len(literals):
        rank = static_rank(search.order, literals, *count_nodes(blocks, [((), literals)], n, db.negation, False)[0])
    note = search.trace.append if search.trace is not None else lambda step: None
    todo = [((), literals, *sizes)]
    wave: list[tuple] = []
    waiting = 0
    while todo:
        if search.timeout_s is not None and time.monotonic() - begin > search.timeout_s:
            count.timeout = True
            break
        now, todo = todo[-batch:], todo[:-batch]
        live, found = [], []
        for pattern, rest, x, y in now:
            if 0 < x + y <= hand_over:
                wave.append((pattern, rest, x, y))
                waiting += x + y
                if len(wave) >= WAVE_NODES or waiting >= WAVE_ROWS:
                    hand(wave, rank)
                    wave, waiting = [], 0
                continue
            count.nodes += 1
            if bool(c.member(x, y)):
                found.append((list(pattern), x, y))
                count.candidates += 1
                if rules.stop:
                    count.stop += 1
                    note((pattern, x, y, None, "STOP"))
                    continue
            if rules.pos and (bool(c.cut(x, 0, y)) or (x == 0 and c.needs_positive())):
                count.pos += 1
                note((pattern, x, y, None, "POS"))
            elif (search.max_len is not None and len(pattern) >= search.max_len) or not len(rest):
                note((pattern, x, y, None, "END"))
            else:
                live.append((pattern, rest, x, y))
        emit(found)
        if not live:
            continue
        sorted_nodes = []
        for (pattern, rest, x, y), (xs, ys) in zip(live, count_nodes(blocks, [v[:2] for v in live], n, db.negation, False), strict=True):
            count.count_calls += 2 * len(rest)
            count.words += words * len(rest)
            if nc:
                keep = ys < y
                count.nc += int((~keep).sum())
                rest, xs, ys = rest[keep], xs[keep], ys[keep]
            if not len(rest):
                note((pattern, x, y, None, "NC"))
                continue
            by = np.lexsort((rest, ys)) if rank is None else np.argsort(rank[rest], kind="stable")
            sorted_nodes.append((pattern, rest[by], x, y, xs[by], ys[by]))
        least = count_nodes(blocks, [v[:2] for v in sorted_nodes], n, db.negation, True) if rules.lb and sorted_nodes else [None] * len(sorted_nodes)
        for (pattern, rest, x, y, xs, ys), low in zip(sorted_nodes, least, strict=True):
            end = len(rest)
            if low is not None:
                count.words += words * len(rest)
                if rules.length and search.max_len is not None:
                    low = np.maximum(low, least_by_length(y, ys, search.max_len - len(pattern))[None])
                cut = np.flatnonzero(c.cut(np.full(end, x), low[0], np.full(end, y)))
                if len(cut):
                    end = int(cut[0])
                    count.lb += 1
            note((pattern, x, y, None if low is None else int(low[0][0]), "LB" if low is not None and end == 0 else "OPEN"))
            for k in range(end - 1, -1, -1):
                i, after = int(rest[k]), rest[k + 1 :]
                if db.negation:
                    after = after[after != (i + n if i < n else i - n)]
                todo.append((tuple(sorted((*pattern, i))), after, int(xs[k]), int(ys[k])))
    if wave:
        hand(wave, rank)
    blocks.unpersist()


def told(own: Search, got: list[tuple]) -> pd.DataFrame:
    """A task's candidates, and a last row that reports on its search."""
    report = json.dumps({"counters": vars(own.counters), "trace": own.trace})
    return pd.DataFrame({"pattern": [list(g[0]) for g in got] + [None], "sup_pos": [g[1] for g in got] + [0], "sup_neg": [g[2] for g in got] + [0], "report": [None] * len(got) + [report]})


def local_task(search: Search, n_items: int, negation: bool, nodes: dict[int, tuple] | None = None, limit: int | None = None):
    """A grouped-map function: searches the rows of one group, below the group's node if there are nodes."""

    def task(key: tuple[Any, ...], frame: pd.DataFrame) -> pd.DataFrame:
        own = replace(search, counters=Counters(), trace=[] if search.trace is not None else None)
        sets, p, q = arrays_of(frame)
        pos, neg = Side(sets, p, n_items, negation), Side(sets, q, n_items, negation)
        prefix, rest, rank = nodes[key[0]] if nodes is not None else ((), None, None)
        return told(own, own.run(pos, neg, prefix, rest, rank, limit))

    return task


def matrix_task(search: Search, n_items: int, negation: bool, back_end: str, limit: int | None = None):
    """The same on a pair of reducible matrices, branching on one literal at a time."""

    def task(frame: pd.DataFrame) -> pd.DataFrame:
        own = replace(search, counters=Counters(), trace=[] if search.trace is not None else None)
        return told(own, search_matrices(own, *arrays_of(frame), back_end, limit))

    return task


def search_one_task(db: LabeledDB, search: Search, limit: int | None = None, back_end: str | None = None) -> DataFrame:
    """All rows in one task: for databases whose distinct rows are known to be few."""
    task = local_task(search, db.n_items, db.negation, None, limit) if back_end is None else matrix_task(search, db.n_items, db.negation, back_end, limit)
    return db.rows.groupBy(F.lit(0).alias("g")).applyInPandas(task, FOUND)


def search_handed(db: LabeledDB, search: Search, handed: list[tuple], rank=None) -> DataFrame:
    """The subtrees of a wave of handed nodes, each in one task that gets the rows of its node: a map over the rows and one shuffle by node."""
    n, negation = db.n_items, db.negation
    nodes = {k: (p, np.asarray(rest, int), rank) for k, (p, rest, _, _) in enumerate(handed)}
    patterns = [list(v[0]) for v in nodes.values()]

    def deal(frames: Iterator[pd.DataFrame]):
        for frame in frames:
            sets, _, _ = arrays_of(frame)
            dense = np.zeros((len(sets), n), np.uint8)
            for r, items in enumerate(sets):
                dense[r, items] = 1
            columns = pack_rows(np.concatenate((dense, 1 - dense), axis=1) if negation else dense)
            full = pack_rows(np.ones((len(sets), 1), np.uint8))[0]
            for k, pattern in enumerate(patterns):
                mask = np.bitwise_and.reduce(columns[pattern], axis=0) if pattern else full
                if mask.any():
                    hit = np.flatnonzero(np.unpackbits(mask.view(np.uint8), bitorder="little")[: len(sets)])
                    part = frame.iloc[hit]
                    yield pd.DataFrame({"node": k, "items": part["items"].tolist(), "w_pos": part["w_pos"].tolist(), "w_neg": part["w_neg"].tolist()})

    dealt = db.rows.mapInPandas(deal, "node int, items array<int>, w_pos long, w_neg long")
    return dealt.groupBy("node").applyInPandas(local_task(search, n, negation, nodes), FOUND)
