"""Peeling of sparse systems, shared by XOR and fuse gates, perfect hashing and the linear system of coded maps."""

from __future__ import annotations

import numpy as np


def peel(cells: np.ndarray, slots: int) -> tuple[list[tuple[np.ndarray, np.ndarray]], np.ndarray]:
    """Layers of (row, cell) where the cell is in no other row left, and the rows that cannot be peeled.

    ``cells`` has distinct cells in each row. A layer takes all cells of degree one at once.
    """
    m, k = cells.shape
    flat = cells.ravel()
    degree = np.bincount(flat, minlength=slots)
    owner = np.zeros(slots, np.int64)  # sum of the rows that hold the cell: the row itself at degree one
    np.add.at(owner, flat, np.repeat(np.arange(m), k))
    alive = np.ones(m, bool)
    layers = []
    ready = np.flatnonzero(degree == 1)
    while len(ready):
        rows, first = np.unique(owner[ready], return_index=True)
        layers.append((rows, ready[first]))
        alive[rows] = False
        gone = cells[rows].ravel()
        np.subtract.at(degree, gone, 1)
        np.subtract.at(owner, gone, np.repeat(rows, k))
        ready = np.unique(gone)
        ready = ready[degree[ready] == 1]
    return layers, np.flatnonzero(alive)


def assign(layers, cells: np.ndarray, targets: np.ndarray, values: np.ndarray) -> None:
    """Set each layer's cell, last layer first, so that the XOR over a row's cells is its target."""
    for rows, own in reversed(layers):
        values[own] = 0
        values[own] = targets[rows] ^ np.bitwise_xor.reduce(values[cells[rows]], axis=1)


def _grouped(cells: np.ndarray, slots: int) -> tuple[np.ndarray, np.ndarray]:
    """Rows by cell: those of cell c are ``rows[edges[c]:edges[c + 1]]``."""
    flat = cells.ravel()
    order = np.argsort(flat, kind="stable")
    return order // cells.shape[1], np.concatenate([[0], np.cumsum(np.bincount(flat, minlength=slots))])


def _members(edges: np.ndarray, some: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Places in the rows by cell of all rows of some cells, and which of the cells each is of."""
    size = edges[some + 1] - edges[some]
    own = np.repeat(np.arange(len(some)), size)
    return np.repeat(edges[some] - (np.cumsum(size) - size), size) + np.arange(len(own)), own


def solve(cells: np.ndarray, targets: np.ndarray, system: np.ndarray, slot_system: np.ndarray, systems: int, words: int = 2) -> tuple[np.ndarray, np.ndarray]:
    """Bits of all slots such that the XOR over a row's cells is its target, for many systems side by side.

    ``system`` tells each row's system and ``slot_system`` each slot's; rows have distinct cells. Rows that can be
    peeled are left for the end. Of the others, those with one unknown cell left give that cell in terms of the others and are put into the rows that share it. When a system
    has no such row, its heaviest unknown cell is set aside, to be found at the end; rows keep the
    set-aside cells they depend on as a bit set. What is left are small dense systems over the cells set aside.
    All steps are taken for all systems at once. Returns the bits, and which systems are solved; the
    others are singular or set more than ``64 * words`` cells aside.
    """
    layers, core = peel(cells, len(slot_system))
    value, solved = _lazy(cells[core], targets[core], system[core], slot_system, systems, words)
    assign(layers, cells, targets.astype(np.uint8), value)
    return value, solved


def _lazy(cells: np.ndarray, targets: np.ndarray, system: np.ndarray, slot_system: np.ndarray, systems: int, words: int) -> tuple[np.ndarray, np.ndarray]:
    """``solve`` without peeling."""
    m, k = cells.shape
    slots = len(slot_system)
    value, solved = np.zeros(slots, np.uint8), np.ones(systems, bool)
    if not m:
        return value, solved
    by_cell, edges = _grouped(cells, slots)
    unknown = np.full(m, k, np.int8)
    rest = cells.sum(1)  # sum of the unknown cells: the cell itself when one is left
    const = targets.astype(np.uint8).copy()
    dense = np.zeros((m, words), np.uint64)
    state = np.zeros(slots, np.int8)  # 0 unknown, 1 set aside, 2 given by a row
    pivot = np.zeros(m, bool)
    left = np.bincount(system, minlength=systems)  # rows with an unknown cell that give none yet
    aside = np.zeros(systems, np.int64)
    place = np.zeros(slots, np.int64)
    degree = np.diff(edges)
    heavy = np.lexsort((-degree, slot_system))
    at = np.searchsorted(slot_system[heavy], np.arange(systems))
    ends = np.searchsorted(slot_system[heavy], np.arange(systems), "right")
    given: list[tuple[np.ndarray, np.ndarray]] = []
    ready = np.zeros(0, np.int64)
    while True:
        while len(ready):
            own, first = np.unique(rest[ready], return_index=True)
            rows = ready[first]
            pivot[rows], state[own] = True, 2
            given.append((rows, own))
            np.subtract.at(left, system[rows], 1)
            found, which = _members(edges, own)
            row = by_cell[found]
            other = row != rows[which]
            row, which = row[other], which[other]
            np.subtract.at(unknown, row, 1)
            np.subtract.at(rest, row, own[which])
            np.bitwise_xor.at(const, row, const[rows[which]])
            for w in range(words):
                np.bitwise_xor.at(dense[:, w], row, dense[rows[which], w])
            row = np.unique(row)
            np.subtract.at(left, system[row[(unknown[row] == 0) & ~pivot[row]]], 1)
            ready = row[(unknown[row] == 1) & ~pivot[row]]
        busy = np.flatnonzero(left > 0)
        if not len(busy):
            break
        over = busy[aside[busy] >= 64 * words]
        if len(over):
            solved[over], left[over] = False, 0
            busy = busy[aside[busy] < 64 * words]
        open_ = busy
        while len(open_):  # the heaviest cell that is still unknown
            passed = state[heavy[at[open_]]] != 0
            open_ = open_[passed]
            at[open_] += 1
        one = heavy[at[busy]] if len(busy) else busy
        state[one], place[one] = 1, aside[busy]
        aside[busy] += 1
        found, which = _members(edges, one)
        row = by_cell[found]
        unknown[row] -= 1
        rest[row] -= one[which]
        dense[row, place[one][which] >> 6] ^= np.uint64(1) << (place[one][which] & 63).astype(np.uint64)
        gone = (unknown[row] == 0) & ~pivot[row]
        np.subtract.at(left, system[row[gone]], 1)
        ready = row[(unknown[row] == 1) & ~pivot[row]]
    assert (at <= ends).all()
    # Dense systems: rows without an unknown cell that give none.
    over = np.flatnonzero(~pivot & (unknown == 0) & solved[system])
    over = over[np.argsort(system[over], kind="stable")]
    used, count = np.unique(system[over], return_counts=True)
    x = np.zeros((systems, words), np.uint64)
    if len(over):
        tall = int(count.max())
        box = np.zeros((len(used), tall, words + 1), np.uint64)
        group = np.repeat(np.arange(len(used)), count)
        inside = np.arange(len(over)) - np.repeat(np.cumsum(count) - count, count)
        box[group, inside, :words], box[group, inside, words] = dense[over], const[over]
        x[used], good = _dense(box, int(aside[used].max(initial=0)))
        solved[used[~good]] = False
    one = np.flatnonzero(state == 1)
    value[one] = (x[slot_system[one], place[one] >> 6] >> (place[one] & 63).astype(np.uint64)) & np.uint64(1)
    if given:
        rows, own = (np.concatenate(z) for z in zip(*given))
        parity = np.bitwise_count(dense[rows] & x[system[rows]]).sum(1) & 1
        value[own] = const[rows] ^ parity.astype(np.uint8)
    return value, solved


def _dense(box: np.ndarray, columns: int) -> tuple[np.ndarray, np.ndarray]:
    """Gauss-Jordan elimination of many small systems at once: rows are bit sets with the target in the last word."""
    n, tall, width = box.shape
    x = np.zeros((n, width - 1), np.uint64)
    lead = np.full((n, columns), -1)
    used = np.zeros((n, tall), bool)
    each = np.arange(n)
    for c in range(columns):
        w, bit = c >> 6, np.uint64(1) << np.uint64(c & 63)
        hit = (box[:, :, w] & bit) != 0
        free = hit & ~used
        row = free.argmax(1)
        some = each[free[each, row]]
        if not len(some):
            continue
        row = row[some]
        used[some, row], lead[some, c] = True, row
        hit[some, row] = False
        a, b = np.nonzero(hit[some])
        box[some[a], b] ^= box[some[a], row[a]]
    good = ~((box[:, :, -1] != 0) & ~used).any(1)
    for c in range(columns):  # free cells are 0
        some = each[lead[:, c] >= 0]
        x[some, c >> 6] |= (box[some, lead[some, c], -1] & np.uint64(1)) << np.uint64(c & 63)
    return x, good
