"""Reducible binary matrices: rows and columns can be deleted and the deletions undone, snapshot by snapshot.

Two back ends with one contract. `LinkedMatrix` links each cell to its neighbours in its column and in its row, over flat
index arrays, and the heads of live rows and columns to each other; deleting unlinks, undoing relinks in reverse order.
`BitsetMatrix` keeps one bitmap per column and masks of live rows and columns; a snapshot is a copy of the masks. Rows may
carry weights, which count_rows adds up."""

from __future__ import annotations

import numpy as np


class Ring:
    """Numbers 0 to n-1 in a circle with an anchor; leaving and coming back take constant time."""

    def __init__(self, n: int):
        self.after, self.before = [*range(1, n + 1), 0], [n, *range(n)]

    def leave(self, k: int) -> None:
        a, b = self.before[k], self.after[k]
        self.after[a], self.before[b] = b, a

    def come_back(self, k: int) -> None:
        self.after[self.before[k]] = self.before[self.after[k]] = k

    def __iter__(self):
        end = len(self.after) - 1
        k = self.after[end]
        while k != end:
            yield k
            k = self.after[k]


class LinkedMatrix:
    """Cells 0 to columns-1 are the columns' heads, the next ones the rows' heads, and the others the ones of the matrix."""

    def __init__(self, rows: list, columns, weights=None):
        self.names = list(columns)
        self.columns = {c: k for k, c in enumerate(self.names)}
        n, heads = len(rows), len(self.names)
        self.weight = [1] * n if weights is None else [int(w) for w in weights]
        self.held = [frozenset(self.columns[c] for c in items) for items in rows]
        self.live_rows, self.live_columns = [True] * n, [True] * heads
        self.row_ring, self.column_ring = Ring(n), Ring(heads)
        self.count, self.size = sum(self.weight), [0] * heads
        self.row_head = [heads + r for r in range(n)]
        total = heads + n
        self.up, self.down, self.left, self.right = (list(range(total)) for _ in range(4))
        self.cell_row, self.cell_column = [-1] * heads + list(range(n)), [*range(heads)] + [-1] * n
        for r, own in enumerate(self.held):
            for h in sorted(own):
                self._add(r, h)
        self.log: list[tuple[bool, int]] = []
        self.marks: list[int] = []

    def _add(self, r: int, h: int) -> None:
        cell, side = len(self.up), self.row_head[r]
        self.up.append(self.up[h])
        self.down.append(h)
        self.left.append(self.left[side])
        self.right.append(side)
        self.down[self.up[h]] = self.up[h] = cell
        self.right[self.left[side]] = self.left[side] = cell
        self.cell_row.append(r)
        self.cell_column.append(h)
        self.size[h] += self.weight[r]

    @classmethod
    def create(cls, rows, columns=None, weights=None):
        rows = list(rows)
        return cls(rows, columns if columns is not None else sorted({c for r in rows for c in r}), weights)

    def _circle(self, links: list[int], head: int):
        cell = links[head]
        while cell != head:
            yield cell
            cell = links[cell]

    def delete_row(self, r: int) -> None:
        if self.live_rows[r]:
            self.live_rows[r] = False
            self.row_ring.leave(r)
            self.count -= self.weight[r]
            for cell in self._circle(self.right, self.row_head[r]):
                self.down[self.up[cell]], self.up[self.down[cell]] = self.down[cell], self.up[cell]
                self.size[self.cell_column[cell]] -= self.weight[r]
            self.log.append((True, r))

    def delete_column(self, c) -> None:
        k = self.columns[c]
        if self.live_columns[k]:
            self.live_columns[k] = False
            self.column_ring.leave(k)
            for cell in self._circle(self.down, k):
                self.right[self.left[cell]], self.left[self.right[cell]] = self.right[cell], self.left[cell]
            self.log.append((False, k))

    def checkpoint(self) -> None:
        self.marks.append(len(self.log))

    def undo(self, i: int = 1) -> None:
        for _ in range(i):
            mark = self.marks.pop()
            while len(self.log) > mark:
                is_row, k = self.log.pop()
                if is_row:
                    for cell in self._circle(self.left, self.row_head[k]):
                        self.down[self.up[cell]] = self.up[self.down[cell]] = cell
                        self.size[self.cell_column[cell]] += self.weight[k]
                    self.live_rows[k] = True
                    self.row_ring.come_back(k)
                    self.count += self.weight[k]
                else:
                    for cell in self._circle(self.up, k):
                        self.right[self.left[cell]] = self.left[self.right[cell]] = cell
                    self.live_columns[k] = True
                    self.column_ring.come_back(k)

    def live(self, c) -> bool:
        return self.live_columns[self.columns[c]]

    def columns_left(self) -> list:
        return [self.names[k] for k in self.column_ring]

    def rows_of(self, c) -> list[int]:
        return [self.cell_row[cell] for cell in self._circle(self.down, self.columns[c])]

    def keep_rows(self, c) -> None:
        """Delete every row without the column."""
        k = self.columns[c]
        for r in [r for r in self.row_ring if k not in self.held[r]]:
            self.delete_row(r)

    def count_rows(self, cols=()) -> int:
        """Weight of the live rows that hold all the given columns: constant time for none or one, else the smallest column is walked."""
        heads = [self.columns[c] for c in cols]
        if not heads:
            return self.count
        if not all(self.live_columns[h] for h in heads):
            raise KeyError("a column is deleted")
        if len(heads) == 1:
            return self.size[heads[0]]
        least, wanted = min(heads, key=self.size.__getitem__), frozenset(heads)
        return sum(self.weight[self.cell_row[cell]] for cell in self._circle(self.down, least) if wanted <= self.held[self.cell_row[cell]])


class BitsetMatrix:
    def __init__(self, rows: list, columns, weights=None):
        self.names = list(columns)
        self.columns = {c: k for k, c in enumerate(self.names)}
        self.n = len(rows)
        words = max(1, -(-self.n // 64))
        dense = np.zeros((len(self.names), words * 64), np.uint8)
        for r, items in enumerate(rows):
            for c in items:
                dense[self.columns[c], r] = 1
        pack = lambda x: np.packbits(x, axis=-1, bitorder="little").view(np.uint64)
        self.bits = pack(dense) if len(self.names) else np.zeros((0, words), np.uint64)
        full, heavy = np.zeros(words * 64, np.uint8), np.zeros(words * 64, np.int64)
        full[: self.n], heavy[: self.n] = 1, 1 if weights is None else np.asarray(weights, np.int64)
        self.mask = pack(full)
        self.planes = [(1 << b, pack((heavy >> b & 1).astype(np.uint8))) for b in range(int(heavy.max(initial=0)).bit_length())]
        self.live_columns = np.ones(len(self.names), bool)
        self.stack: list[tuple[np.ndarray, np.ndarray]] = []

    @classmethod
    def create(cls, rows, columns=None, weights=None):
        rows = list(rows)
        return cls(rows, columns if columns is not None else sorted({c for r in rows for c in r}), weights)

    def delete_row(self, r: int) -> None:
        self.mask = self.mask.copy()
        self.mask[r >> 6] &= ~(np.uint64(1) << np.uint64(r & 63))

    def delete_column(self, c) -> None:
        self.live_columns = self.live_columns.copy()
        self.live_columns[self.columns[c]] = False

    def checkpoint(self) -> None:
        self.stack.append((self.mask, self.live_columns))

    def undo(self, i: int = 1) -> None:
        for _ in range(i):
            self.mask, self.live_columns = self.stack.pop()

    def live(self, c) -> bool:
        return bool(self.live_columns[self.columns[c]])

    def columns_left(self) -> list:
        return [c for c, on in zip(self.names, self.live_columns, strict=True) if on]

    def rows_of(self, c) -> list[int]:
        bits = np.unpackbits((self.bits[self.columns[c]] & self.mask).view(np.uint8), bitorder="little")
        return np.flatnonzero(bits).tolist()

    def keep_rows(self, c) -> None:
        self.mask = self.mask & self.bits[self.columns[c]]

    def count_rows(self, cols=()) -> int:
        mask = self.mask
        for c in cols:
            if not self.live(c):
                raise KeyError("a column is deleted")
            mask = mask & self.bits[self.columns[c]]
        return sum(w * int(np.bitwise_count(mask & plane).sum()) for w, plane in self.planes)


BACK_ENDS = {"linked": LinkedMatrix, "bitset": BitsetMatrix}
