"""Both matrix back ends against a plain set model, the worked sequence and random operations."""

import random

import pytest

from contrastmine.operators.matrix import BACK_ENDS

ROWS = ["a", "bc", "bcd", "cd", "ac"]


@pytest.mark.parametrize("kind", BACK_ENDS)
def test_worked_sequence(kind):
    m = BACK_ENDS[kind].create(ROWS)
    assert m.count_rows() == 5 and m.count_rows("c") == 4
    m.checkpoint()
    m.delete_row(0)
    m.delete_column("b")
    assert m.count_rows("c") == 4 and m.count_rows() == 4
    m.checkpoint()
    m.delete_row(4)
    assert m.count_rows("c") == 3 and m.count_rows("cd") == 2
    m.undo(1)
    assert m.count_rows("c") == 4 and not m.live("b")
    m.undo(1)
    assert m.count_rows() == 5 and m.count_rows("b") == 2
    m.checkpoint(), m.delete_row(1), m.checkpoint(), m.delete_row(2)
    m.undo(2)
    assert m.count_rows() == 5 and sorted(m.rows_of("c")) == [1, 2, 3, 4]


@pytest.mark.parametrize("kind", BACK_ENDS)
@pytest.mark.parametrize("seed", range(15))
def test_random_operations(kind, seed):
    draw = random.Random(seed)
    columns = "abcdef"
    rows = [{c for c in columns if draw.random() < 0.5} for _ in range(draw.randint(0, 90))]
    m = BACK_ENDS[kind].create(rows, columns)
    live, cols, stack = set(range(len(rows))), set(columns), []
    for _ in range(120):
        act = draw.choice(["row", "row", "column", "mark", "undo", "count", "count"])
        if act == "row" and rows:
            r = draw.randrange(len(rows))
            m.delete_row(r)
            live.discard(r)
        elif act == "column":
            c = draw.choice(columns)
            m.delete_column(c)
            cols.discard(c)
        elif act == "mark":
            m.checkpoint()
            stack.append((set(live), set(cols)))
        elif act == "undo" and stack:
            k = draw.randint(1, len(stack))
            m.undo(k)
            for _ in range(k):
                live, cols = stack.pop()
        else:
            want = [c for c in cols if draw.random() < 0.4]
            assert m.count_rows(want) == sum(set(want) <= rows[r] for r in live)
            assert all(m.live(c) == (c in cols) for c in columns) and sorted(m.columns_left()) == sorted(cols)


@pytest.mark.parametrize("kind", BACK_ENDS)
def test_weights_and_keeping_the_rows_of_a_column(kind):
    m = BACK_ENDS[kind].create(ROWS, "abcd", [1, 2, 4, 8, 16])
    assert m.count_rows() == 31 and m.count_rows("c") == 30 and m.count_rows("bc") == 6
    m.checkpoint(), m.keep_rows("b"), m.delete_column("b")
    assert m.count_rows() == 6 and m.count_rows("d") == 4 and m.columns_left() == ["a", "c", "d"]
    m.undo()
    assert m.count_rows() == 31 and m.count_rows("b") == 6


def test_a_deleted_row_leaves_its_links_and_comes_back():
    m = BACK_ENDS["linked"].create(ROWS)
    before = (m.up[:], m.down[:], m.left[:], m.right[:])
    m.checkpoint(), m.delete_column("c"), m.delete_row(1), m.delete_row(3), m.delete_column("a")
    assert list(m.row_ring) == [0, 2, 4] and [m.names[k] for k in m.column_ring] == ["b", "d"] and m.right[m.row_head[4]] == m.row_head[4]
    m.undo()
    assert (m.up, m.down, m.left, m.right) == before
