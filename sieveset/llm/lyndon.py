"""Suffix array in linear time by grouping suffixes on their Lyndon prefixes.

First phase: suffixes start in groups by first symbol. Groups are taken from the largest down. For each member the closest
earlier suffix of a smaller group is found by following the pointers of members already done; that suffix's prefix grows by the
group's, once for each member that points to it, and so it moves up out of its group. In the end each group shares its longest
Lyndon prefix. Second phase: the order is emitted from the least suffix on; each suffix that comes out settles those whose
Lyndon prefix ends where it starts. Names are never recomputed.
"""

from __future__ import annotations


def suffix_array(symbols: list[int]) -> list[int]:
    """Starts of all suffixes in order. ``symbols``: numbers from 1 on; a shorter suffix sorts before one that it begins."""
    text = [*symbols, 0]
    n = len(text)
    first = [0] * n
    prev = [-1] * n
    slots = [0] * n
    where = [0] * n
    size = [0] * n
    places: dict[int, list[int]] = {}
    for s, c in enumerate(text):
        places.setdefault(c, []).append(s)
    at = 0
    for c in sorted(places):
        size[at] = len(places[c])
        for k, s in enumerate(places[c]):
            slots[at + k] = s
            where[s] = at + k
            first[s] = at
        at += len(places[c])

    end = n
    while end > 0:
        begin = first[slots[end - 1]]
        if end - begin == 1:
            s = slots[begin]
            p = s - 1
            while p >= 0 and first[p] >= begin:
                p = prev[p]
            prev[s] = p
            if p >= 0:
                a = first[p]
                if size[a] > 1:  # p becomes a group of its own at the end of its old one
                    size[a] -= 1
                    last = a + size[a]
                    i, q = where[p], slots[last]
                    slots[i], where[q] = q, i
                    slots[last], where[p] = p, last
                    first[p] = last
                    size[last] = 1
        else:
            members = sorted(slots[begin:end])
            count: dict[int, int] = {}
            for s in members:  # rising, so a member's own pointer is known when a later one meets it
                p = s - 1
                while p >= 0 and first[p] >= begin:
                    p = prev[p]
                prev[s] = p
                if p >= 0:
                    count[p] = count.get(p, 0) + 1
            by_count: dict[int, list[int]] = {}
            for p, k in count.items():
                by_count.setdefault(k, []).append(p)
            for k in sorted(by_count, reverse=True):
                moved: dict[int, list[int]] = {}
                for p in by_count[k]:
                    moved.setdefault(first[p], []).append(p)
                for a, ps in moved.items():
                    if len(ps) == size[a]:
                        continue  # the whole group moves together
                    new = a + size[a] - len(ps)
                    size[a] -= len(ps)
                    last = a + size[a] + len(ps)
                    for p in ps:
                        last -= 1
                        i, q = where[p], slots[last]
                        slots[i], where[q] = q, i
                        slots[last], where[p] = p, last
                        first[p] = new
                    size[new] = len(ps)
        end = begin

    out = [-1] * n
    done = [False] * n
    fill = list(range(n))
    out[0] = n - 1
    done[n - 1] = True
    for i in range(n):
        s = out[i] - 1
        while s >= 0 and not done[s]:
            a = first[s]
            out[fill[a]] = s
            fill[a] += 1
            done[s] = True
            s = prev[s]
    return out[1:]
