"""The search on a pair of reducible matrices, one literal at a time: first without it, then with it.

The live columns are the literals that may still extend the pattern, the live rows those that hold it. Every step makes a
checkpoint before it deletes and undoes it when its subtree is done, so both branches start from the same matrices and a
call leaves them as it found them. Steps wait on a stack of their own, so depth is not bounded by Python's."""

from __future__ import annotations

import time

from .kernel import Search
from .matrix import BACK_ENDS


def search_matrices(search: Search, sets, w_pos, w_neg, back_end: str = "linked", limit: int | None = None) -> list[tuple]:
    """Candidates (pattern, x, y) of weighted rows, with the counters and the trace of the search."""
    c, rules, n, count = search.constraint, search.rules, search.n_items, search.counters
    literals = search.literals().tolist()
    full = [{*map(int, s)} for s in sets]
    if search.negation:
        full = [s | {i + n for i in range(n) if i not in s} for s in full]
    wanted = frozenset(literals)
    make = lambda weights: BACK_ENDS[back_end].create([full[k] & wanted for k, w in enumerate(weights) if w], literals, [w for w in weights if w])
    pos, neg = make(w_pos), make(w_neg)
    both = (pos, neg)
    place = None
    if search.order != "dynamic":
        rate = lambda i: (lambda x, y: x / y if y else float("inf") if x else 0.0)(pos.count_rows((i,)), neg.count_rows((i,)))
        key = {"id": lambda i: i, "neg_asc": lambda i: neg.count_rows((i,)), "neg_desc": lambda i: -neg.count_rows((i,)), "total_asc": lambda i: pos.count_rows((i,)) + neg.count_rows((i,)), "growth_desc": lambda i: -rate(i)}[search.order.partition(":")[2]]
        place = {i: k for k, i in enumerate(sorted(literals, key=lambda i: (key(i), i)))}
    use_nc, begin = rules.use_nc(c), time.monotonic()
    out: list[tuple] = []
    steps: list[tuple] = [("visit", (), None, False)]
    while steps:
        if search.timeout_s is not None and time.monotonic() - begin > search.timeout_s:
            count.timeout = True
            break
        kind, pattern, item, skipped = steps.pop()
        if kind == "undo":
            for m in both:
                m.undo()
            continue
        for m in both:
            m.checkpoint()
            if item is not None:
                if not skipped:
                    m.keep_rows(item)
                    other = item + n if item < n else item - n
                    if other in m.columns:
                        m.delete_column(other)
                m.delete_column(item)
        steps.append(("undo", (), None, False))
        x, y = pos.count_rows(), neg.count_rows()
        count.nodes += 1
        note = lambda verdict, low=None: search.trace is not None and search.trace.append((pattern, x, y, low, verdict))  # noqa: E731, B023
        if not skipped and bool(c.member(x, y)):
            out.append((pattern, x, y))
            count.candidates += 1
            if rules.stop:
                count.stop += 1
                note("STOP")
                continue
            if limit is not None and len(out) >= limit:
                break
        if rules.pos and (bool(c.cut(x, 0, y)) or (x == 0 and c.needs_positive())):
            count.pos += 1
            note("POS")
            continue
        rest = neg.columns_left()
        if (search.max_len is not None and len(pattern) >= search.max_len) or not rest:
            note("END")
            continue
        count.count_calls += len(rest)
        ys = {i: neg.count_rows((i,)) for i in rest}
        if use_nc and not skipped:  # a skip leaves rows and counts as they are
            same = [i for i in rest if ys[i] == y]
            count.nc += len(same)
            for i in same:
                for m in both:
                    m.delete_column(i)
            rest = [i for i in rest if ys[i] != y]
            if not rest:
                note("NC")
                continue
        least = None
        if rules.lb:
            count.count_calls += 1
            least = neg.count_rows(rest)
            if bool(c.cut(x, least, y)):
                count.lb += 1
                note("LB", least)
                continue
        note("OPEN", least)
        chosen = min(rest, key=lambda i: (ys[i], i)) if place is None else min(rest, key=place.__getitem__)
        steps.append(("visit", tuple(sorted((*pattern, chosen))), chosen, False))
        steps.append(("visit", pattern, chosen, True))
    return out
