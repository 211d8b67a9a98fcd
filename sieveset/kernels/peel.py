"""Peeling: an order in which every key has a cell of its own that no later key touches.

``cells`` has three rows, one for each part of the table; the result is (keys, cells) in order of removal and the round of
each, or None when a core is left that cannot be peeled.
"""

from __future__ import annotations

from collections import deque

import numpy as np

Peeled = tuple[np.ndarray, np.ndarray, np.ndarray]


def peel_rounds(cells: np.ndarray, capacity: int, partly: bool = False) -> Peeled | None:
    """All keys with a cell to themselves go at once; each takes the least such cell.

    The result does not depend on the order of keys. Cells keep a count and the exclusive-or of their keys' indices.
    With ``partly``, what comes off a core that is left is given as well.
    """
    n = cells.shape[1]
    flat = cells.ravel()
    degree = np.bincount(flat, minlength=capacity)
    mask = np.zeros(capacity, np.int64)
    index = np.arange(n)
    for row in cells:
        np.bitwise_xor.at(mask, row, index)
    order, own, rounds = [], [], []
    single = np.flatnonzero(degree == 1)
    mark = np.empty(max(n, capacity), np.int64)
    done, step = 0, 0
    while len(single):
        keys = mask[single]
        mark[keys] = np.arange(len(keys))  # of a key's several cells one keeps its mark
        keys = keys[mark[keys] == np.arange(len(keys))]
        c0, c1, c2 = cells[:, keys]
        order.append(keys)
        own.append(np.where(degree[c0] == 1, c0, np.where(degree[c1] == 1, c1, c2)))
        rounds.append(np.full(len(keys), step))
        done += len(keys)
        step += 1
        touched = np.concatenate([c0, c1, c2])
        np.subtract.at(degree, touched, 1)
        np.bitwise_xor.at(mask, touched, np.tile(keys, 3))
        touched = touched[degree[touched] == 1]
        mark[touched] = np.arange(len(touched))
        single = touched[mark[touched] == np.arange(len(touched))]
    if done < n and not partly:
        return None
    empty = [np.zeros(0, np.int64)]
    return np.concatenate(order or empty), np.concatenate(own or empty), np.concatenate(rounds or empty)


#: From so many keys on the priority peel works in batches; of the free cells of the last part a batch takes one in LAST_SHARE.
BATCHED_KEYS, LAST_SHARE = 100_000, 32


def peel_priority(cells: np.ndarray, capacity: int, seg2: int) -> Peeled | None:
    """A cell of the last part is taken only when no other is free, which leaves that part emptiest: one cell at a time, or for large
    sets a small share of those that are free, which leaves half a percent less of the part empty and runs in vectors."""
    return _priority_batches(cells, capacity, seg2) if cells.shape[1] >= BATCHED_KEYS else _priority_steps(cells, capacity, seg2)


def _priority_batches(cells: np.ndarray, capacity: int, seg2: int, share: int = LAST_SHARE) -> Peeled | None:
    n = cells.shape[1]
    degree = np.bincount(cells.ravel(), minlength=capacity)
    mask = np.zeros(capacity, np.int64)
    for row in cells:
        np.bitwise_xor.at(mask, row, np.arange(n))
    mark = np.empty(max(n, capacity), np.int64)
    single = np.flatnonzero(degree == 1)
    near, last = single[single < seg2], single[single >= seg2]
    order, own, rounds, done = [], [], [], 0
    while len(near) or len(last := last[degree[last] == 1]):
        if len(near):
            now = near
        else:
            take = max(1, len(last) // share)
            now, last = last[:take], last[take:]
        keys = mask[now]
        mark[keys] = np.arange(len(keys))  # of a key's several cells one keeps its mark
        kept = mark[keys] == np.arange(len(keys))
        keys = keys[kept]
        rounds.append(np.full(len(keys), len(order)))
        order.append(keys)
        own.append(now[kept])
        done += len(keys)
        touched = cells[:, keys].ravel()
        np.subtract.at(degree, touched, 1)
        np.bitwise_xor.at(mask, touched, np.tile(keys, 3))
        free = touched[degree[touched] == 1]
        mark[free] = np.arange(len(free))
        free = free[mark[free] == np.arange(len(free))]
        near, last = free[free < seg2], np.concatenate([last, free[free >= seg2]])
    return (np.concatenate(order), np.concatenate(own), np.concatenate(rounds)) if done == n else None


def _priority_steps(cells: np.ndarray, capacity: int, seg2: int) -> Peeled | None:
    n = cells.shape[1]
    degree = np.bincount(cells.ravel(), minlength=capacity)
    mask = np.zeros(capacity, np.int64)
    for row in cells:
        np.bitwise_xor.at(mask, row, np.arange(n))
    single = np.flatnonzero(degree == 1).tolist()
    a, b, c = (row.tolist() for row in cells)
    count, held = degree.tolist(), mask.tolist()
    near, last = [x for x in single if x < seg2], [x for x in single if x >= seg2]
    order, own = [], []
    while True:
        if near:
            i = near.pop()
        elif last:
            i = last.pop()
        else:
            break
        if count[i] != 1:
            continue
        k = held[i]
        order.append(k)
        own.append(i)
        for j in (a[k], b[k], c[k]):
            count[j] -= 1
            held[j] ^= k
            if count[j] == 1:
                (near if j < seg2 else last).append(j)
    if len(order) < n:
        return None
    return np.array(order, np.int64), np.array(own, np.int64), np.arange(len(order))


def peel_queue(cells: np.ndarray, capacity: int) -> Peeled | None:
    """One queue, one cell at a time, with count and mask."""
    n = cells.shape[1]
    count, held = [0] * capacity, [0] * capacity
    rows = [row.tolist() for row in cells]
    for row in rows:
        for k, i in enumerate(row):
            count[i] += 1
            held[i] ^= k
    queue = deque(i for i in range(capacity) if count[i] == 1)
    order, own = [], []
    while queue:
        i = queue.popleft()
        if count[i] == 1:
            k = held[i]
            order.append(k)
            own.append(i)
            for row in rows:
                count[row[k]] -= 1
                held[row[k]] ^= k
                if count[row[k]] == 1:
                    queue.append(row[k])
    return (np.array(order, np.int64), np.array(own, np.int64), np.arange(n)) if len(order) == n else None


def peel_sets(cells: np.ndarray, capacity: int) -> Peeled | None:
    """With real sets of keys in the cells: plain, slow, for checking the others."""
    n = cells.shape[1]
    held: list[set[int]] = [set() for _ in range(capacity)]
    for k in range(n):
        for i in cells[:, k]:
            held[i].add(k)
    order, own, alive = [], [], True
    while alive:
        alive = False
        for i in range(capacity):
            if len(held[i]) == 1:
                k = next(iter(held[i]))
                order.append(k)
                own.append(i)
                for j in cells[:, k]:
                    held[j].discard(k)
                alive = True
    return (np.array(order, np.int64), np.array(own, np.int64), np.arange(n)) if len(order) == n else None


def assign(cells: np.ndarray, values: np.ndarray, peeled: Peeled, capacity: int) -> np.ndarray:
    """Cell values whose exclusive-or over a key's three cells is its value. Last removed, first written.

    Keys of one round cannot hold each other's own cell, so a round is written at once.
    """
    order, own, rounds = peeled
    table = np.zeros(capacity, values.dtype)
    if not len(order):
        return table
    if rounds[-1] == len(order) - 1 and len(order) > 64:  # one key a round
        a, b, c = (row[order].tolist() for row in cells)
        out, wanted = [0] * capacity, values[order].tolist()
        for t in range(len(order) - 1, -1, -1):
            out[int(own[t])] = 0
            out[int(own[t])] = wanted[t] ^ out[a[t]] ^ out[b[t]] ^ out[c[t]]
        return np.array(out, dtype=values.dtype)
    starts = np.flatnonzero(np.r_[True, rounds[1:] != rounds[:-1]])
    ends = np.r_[starts[1:], len(order)]
    for s, e in zip(starts[::-1], ends[::-1], strict=True):
        k = order[s:e]
        at = cells[:, k]
        table[own[s:e]] = values[k] ^ table[at[0]] ^ table[at[1]] ^ table[at[2]]
    return table
