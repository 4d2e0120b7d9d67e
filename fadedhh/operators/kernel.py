"""Numpy kernel of the faded sketch: arrays of two-counter cells.

A batch of cells is four arrays i1, f1, i2, f2; a counter of frequency 0 is absent and holds the item 0. The
heavier counter comes first, ties by item.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa

from .params import SketchParams

Cells = tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]


def merge_cells(a: Cells, b: Cells) -> Cells:
    """Cell-wise merge. Combination: shared items add up, others get the other side's minimum; of the at most
    four counters the two heaviest stay."""
    (ai1, af1, ai2, af2), (bi1, bf1, bi2, bf2) = a, b
    a1, a2, b1, b2 = af1 > 0, af2 > 0, bf1 > 0, bf2 > 0
    s11, s12 = a1 & b1 & (ai1 == bi1), a1 & b2 & (ai1 == bi2)
    s21, s22 = a2 & b1 & (ai2 == bi1), a2 & b2 & (ai2 == bi2)
    f = [
        np.where(a1, af1 + np.where(s11, bf1, bf2), 0.0),
        np.where(a2, af2 + np.where(s21, bf1, bf2), 0.0),
        np.where(b1 & ~s11 & ~s21, bf1 + af2, 0.0),
        np.where(b2 & ~s12 & ~s22, bf2 + af2, 0.0),
    ]
    # unshared items of a meet b's minimum: that is bf2 in every case but an item shared with b's first counter
    i = [ai1, ai2, bi1, bi2]
    bi, bf = i[0], f[0]
    si, sf = np.zeros_like(bi), np.zeros_like(bf)
    for ci, cf in zip(i[1:], f[1:]):
        first = (cf > bf) | ((cf == bf) & (cf > 0) & (ci < bi))
        ni, nf = np.where(first, bi, ci), np.where(first, bf, cf)
        bi, bf = np.where(first, ci, bi), np.where(first, cf, bf)
        second = (nf > sf) | ((nf == sf) & (nf > 0) & (ni < si))
        si, sf = np.where(second, ni, si), np.where(second, nf, sf)
    return np.where(bf > 0, bi, 0), bf, np.where(sf > 0, si, 0), sf


def reduce_by_key(key: np.ndarray, cells: Cells) -> tuple[np.ndarray, Cells]:
    """Merges cells of equal key in order, as a balanced tree: log2 of the longest run rounds."""
    order = np.argsort(key, kind="stable")
    key, cells = key[order], tuple(x[order] for x in cells)
    while len(key):
        head = np.concatenate([[True], key[1:] != key[:-1]])
        start = np.flatnonzero(head)
        if len(start) == len(key):
            break
        place = np.arange(len(key)) - np.repeat(start, np.diff(np.append(start, len(key))))
        left = np.flatnonzero(place % 2 == 0)
        has = np.zeros(len(key), bool)
        has[:-1] = (place[1:] % 2 == 1) & (key[1:] == key[:-1])
        has = has[left]
        pick = np.minimum(left + 1, len(key) - 1)
        other = tuple(np.where(has, x[pick], 0) for x in cells)
        cells = merge_cells(tuple(x[left] for x in cells), other)
        key = key[left]
    return key, cells


def add_up(item: np.ndarray, weight: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct items with their summed weights, by Arrow's hash aggregation."""
    got = pa.table({"i": item, "w": weight}).group_by("i", use_threads=False).aggregate([("w", "sum")])
    return got.column("i").to_numpy(), got.column("w_sum").to_numpy()


class NumpySketch:
    """One local sketch of d x w cells, with the raw decayed count."""

    def __init__(self, params: SketchParams):
        self.params = params
        n = params.d * params.w
        self.cells: Cells = (np.zeros(n, np.int64), np.zeros(n), np.zeros(n, np.int64), np.zeros(n))
        self.count = 0.0

    def scale(self, factor: float) -> None:
        """Multiplies all frequencies and the count; counters that vanish become free."""
        i1, f1, i2, f2 = self.cells
        f1, f2 = f1 * factor, f2 * factor
        self.cells = (np.where(f1 > 0, i1, 0), f1, np.where(f2 > 0, i2, 0), f2)
        self.count *= factor

    def absorb(self, key: np.ndarray, cells: Cells) -> None:
        """Merges further cells (keys distinct) into the grid."""
        mine = tuple(x[key] for x in self.cells)
        for x, y in zip(self.cells, merge_cells(mine, cells)):
            x[key] = y

    def update(self, item: np.ndarray, weight: np.ndarray, combine: bool = True, hashed: np.ndarray | None = None) -> None:
        """Takes in a batch. With ``combine`` equal items add up first and each cell merges its batch as a
        tree; without it every cell replays its items in the given order."""
        live = weight > 0
        if not live.all():
            item, weight = item[live], weight[live]
            hashed = hashed[:, live] if hashed is not None else None
        if not len(item):
            return
        self.count += float(weight.sum())
        p = self.params
        if combine and hashed is None:
            item, weight = add_up(item, weight)
        elif combine:
            item, first, back = np.unique(item, return_index=True, return_inverse=True)
            weight, hashed = np.bincount(back, weight), hashed[:, first]
        at = p.hashes.arrays(item) if hashed is None else hashed
        key = (at + np.arange(p.d)[:, None] * p.w).reshape(-1)
        items, weights = np.tile(item, p.d), np.tile(weight, p.d)
        none = np.zeros(len(items), np.int64)
        if combine:
            key, cells = reduce_by_key(key, (items, weights, none, none.astype(float)))
            self.absorb(key, cells)
            return
        order = np.argsort(key, kind="stable")
        key, items, weights = key[order], items[order], weights[order]
        start = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
        size = np.diff(np.append(start, len(key)))
        for r in range(int(size.max())):
            on = start[size > r] + r
            none = np.zeros(len(on), np.int64)
            self.absorb(key[on], (items[on], weights[on], none, none.astype(float)))

    def rows(self, shard: int) -> pa.RecordBatch:
        """Occupied cells, and one row -1 that carries the count."""
        on = np.flatnonzero(self.cells[1] > 0)
        i1, f1, i2, f2 = (x[on] for x in self.cells)
        w = self.params.w
        n = len(on) + 1
        second = np.append(f2 == 0, True)
        return pa.RecordBatch.from_arrays(
            [
                pa.array(np.full(n, shard, np.int32)), pa.array(np.append(on // w, -1).astype(np.int32)), pa.array(np.append(on % w, 0).astype(np.int32)),
                pa.array(np.append(i1, 0)), pa.array(np.append(f1, self.count)), pa.array(np.append(i2, 0), mask=second), pa.array(np.append(f2, 0.0)),
            ],
            names=["shard", "row", "col", "i1", "f1", "i2", "f2"],
        )
