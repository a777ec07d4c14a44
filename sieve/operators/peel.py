"""Peeling a key-cell graph and assigning cells, in numpy.

A round takes every cell with one live key. Two keys of one round never touch each
other's own cell (it would hold both), so a whole round is assigned at once when the
rounds are walked backwards. A key alone in several cells owns the lowest; with that
rule the cells are a function of the key set and seed, whatever the input order.
"""

from __future__ import annotations

import numpy as np


def accumulate(loc: np.ndarray, cells: int) -> tuple[np.ndarray, np.ndarray]:
    """Keys of every cell: their number and the xor of their row numbers."""
    count = np.zeros(cells, np.int32)
    mask = np.zeros(cells, np.int32)
    rows = np.arange(len(loc), dtype=np.int32)
    for j in range(loc.shape[1]):
        count += np.bincount(loc[:, j], minlength=cells).astype(np.int32)
        np.bitwise_xor.at(mask, loc[:, j], rows)
    return count, mask


def key_masks(loc: np.ndarray, keys: np.ndarray, cells: int) -> tuple[np.ndarray, np.ndarray]:
    """The same with the xor of the keys themselves; a singleton's mask is its key."""
    count = np.bincount(loc.ravel(), minlength=cells)
    mask = np.zeros(cells, np.int64)
    for j in range(loc.shape[1]):
        np.bitwise_xor.at(mask, loc[:, j], keys)
    return count, mask


#: One key in the packed count of a cell: the count stands above the sum of row numbers.
ONE = np.int64(1) << np.int64(32)
ROW = ONE - 1


def packed(loc: np.ndarray, cells: int) -> np.ndarray:
    """Number and row sum of every cell's keys in one word; with one key the sum is its row.

    A sum that runs over its half only adds to the count, so one key is still told.
    """
    weight = np.arange(len(loc), dtype=np.float64) + float(ONE)  # exact below 2**20 keys a cell
    out = np.bincount(loc[:, 0], weights=weight, minlength=cells)
    for j in range(1, loc.shape[1]):
        out += np.bincount(loc[:, j], weights=weight, minlength=cells)
    return out.astype(np.int64)


#: Cells of a region, as a power of two: its packed words stay in cache.
REGION_LOG2 = 15


def packed_by_region(loc: np.ndarray, cells: int) -> np.ndarray:
    """``packed``, with each column's cells put in a buffer for their region first, so that the array is walked forwards."""
    weight = np.arange(len(loc), dtype=np.float64) + float(ONE)
    out = np.zeros(cells)
    for at in loc.T:
        buffers = np.argsort((at >> REGION_LOG2).astype(np.uint16), kind="stable")  # a radix sort, as regions are few
        out += np.bincount(at.take(buffers), weights=weight.take(buffers), minlength=cells)
    return out.astype(np.int64)


def single(held: np.ndarray) -> np.ndarray:
    """Mask of packed cells with exactly one key."""
    return (held >> np.int64(32)) == 1


#: Of the late cells that wait, one in so many is taken at a time, and so many at least.
PATIENCE, LEAST_LATE = 8, 16

Layers = list[tuple[np.ndarray, np.ndarray]]


def peel_layers(loc: np.ndarray, cells: int, late: int | None = None, buffered: bool = False) -> Layers:
    """Rounds of (rows, own cells); all rows are there exactly if peeling succeeds.

    ``late``: cells from this one on are owned only in rounds that find no other cell,
    and then some of them only: what they free may spare the rest.
    """
    held, arity = (packed_by_region if buffered else packed)(loc, cells), loc.shape[1]
    owner = np.empty(len(loc), np.int64)  # of each row, the cell written last
    frontier = np.flatnonzero(single(held))
    waiting = np.zeros(0, np.int64)
    layers: Layers = []
    while len(frontier) or len(waiting):
        if late is not None:
            waiting = np.concatenate((waiting, frontier[frontier >= late]))
            frontier = frontier[frontier < late]
            if not len(frontier):
                waiting = np.unique(waiting[single(held[waiting])])
                take = max(len(waiting) // PATIENCE, min(len(waiting), LEAST_LATE))
                frontier, waiting = waiting[:take], waiting[take:]
                if not len(frontier):
                    continue
        rows = held[frontier] & ROW
        owner[rows[::-1]] = frontier[::-1]  # frontier is in order: a row keeps its lowest cell
        first = owner[rows] == frontier
        if not first.all():
            rows, frontier = rows[first], frontier[first]
        layers.append((rows, frontier))
        touched = loc.take(rows, axis=0).ravel()
        np.subtract.at(held, touched, np.repeat(rows + ONE, arity))
        frontier = touched[single(held.take(touched))]
        frontier.sort()
        if len(frontier) > 1:
            frontier = frontier[np.concatenate(([True], frontier[1:] != frontier[:-1]))]
    return layers


def peel_stack(loc: np.ndarray, cells: int) -> Layers:
    """One key at a time, last found first: the reference for the rounds above."""
    count, mask = accumulate(loc, cells)
    count, mask, places = count.tolist(), mask.tolist(), loc.tolist()
    stack = [c for c in range(cells) if count[c] == 1]
    rows, own = [], []
    while stack:
        cell = stack.pop()
        if count[cell] != 1:
            continue
        row = mask[cell]
        rows.append(row)
        own.append(cell)
        for c in places[row]:
            count[c] -= 1
            mask[c] ^= row
            if count[c] == 1:
                stack.append(c)
    return [(np.array([r]), np.array([c])) for r, c in zip(rows, own, strict=True)]


def peel(loc: np.ndarray, cells: int, order: str = "layer", late: int | None = None, buffered: bool = False) -> Layers:
    return peel_layers(loc, cells, late, buffered) if order == "layer" else peel_stack(loc, cells)


def peeled(layers: Layers) -> int:
    return sum(len(rows) for rows, _ in layers)


def assign(layers: Layers, loc: np.ndarray, prints: np.ndarray, cells: int) -> np.ndarray:
    """The cell values: last round first, every key's cells then xor to its fingerprint."""
    out = np.zeros(cells, prints.dtype)
    for rows, own in reversed(layers):
        value, at = prints.take(rows), loc.take(rows, axis=0)
        for j in range(loc.shape[1]):
            value ^= out.take(at[:, j])
        out[own] = value
    return out


def lookup(out: np.ndarray, loc: np.ndarray) -> np.ndarray:
    value = out[loc[:, 0]]
    for j in range(1, loc.shape[1]):
        value = value ^ out[loc[:, j]]
    return value
