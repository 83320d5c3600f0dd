"""Suffix arrays by linear grouping.

First every suffix joins the group of its longest Lyndon prefix: groups are taken
in descending order, each suffix of a group finds the nearest suffix before it
that lies in a lower group, and the suffixes found move, by how often they were
found, to a new group just above the rest of their own.  Then one ascending pass
emits the order: the suffix before each emitted one, and the chain of its
previous-smaller pointers, take the next free places of their groups.  Nothing is
renamed or solved again.
"""

from __future__ import annotations

import numpy as np


def suffix_array(text: np.ndarray) -> np.ndarray:
    """Start positions of all suffixes of an integer sequence, in ascending order."""
    n = len(text)
    if n < 2:
        return np.arange(n)
    # group of a suffix = first place of its group; place[] lists members group by group
    order = np.argsort(text, kind="stable")
    ranked = text[order]
    new = np.concatenate([[True], ranked[1:] != ranked[:-1]])
    first = np.maximum.accumulate(np.where(new, np.arange(n), 0))
    group_of = np.empty(n, np.int64)
    group_of[order] = first
    group = group_of.tolist()
    place = order.tolist()
    where = np.empty(n, np.int64)
    where[order] = np.arange(n)
    where = where.tolist()
    starts = np.flatnonzero(new)
    size = [0] * n
    for s, k in zip(starts.tolist(), np.diff(np.append(starts, n)).tolist()):
        size[s] = k
    previous = [-1] * n
    top = n
    while top > 0:
        g = group[place[top - 1]]
        members = place[g:top]
        if top - g > 1:
            members.sort()
            found: dict[int, int] = {}
            for s in members:
                p = s - 1
                while p >= 0 and group[p] >= g:
                    p = previous[p]
                previous[s] = p
                if p >= 0:
                    found[p] = found.get(p, 0) + 1
            if found:
                most = max(found.values())
                if most == 1:
                    levels = [found]
                else:
                    by: dict[int, list[int]] = {}
                    for p, k in found.items():
                        by.setdefault(k, []).append(p)
                    levels = [by[k] for k in sorted(by, reverse=True)]
                for level in levels:
                    moved: dict[int, int] = {}
                    for p in level:  # to the end of its group
                        h = group[p]
                        k = moved.get(h, 0) + 1
                        moved[h] = k
                        at, to = where[p], h + size[h] - k
                        q = place[to]
                        place[at], where[q] = q, at
                        place[to], where[p] = p, to
                    for h, k in moved.items():
                        rest = size[h] - k
                        if rest:
                            size[h] = rest
                            size[h + rest] = k
                            for q in place[h + rest : h + rest + k]:
                                group[q] = h + rest
        else:
            s = members[0]
            p = s - 1
            while p >= 0 and group[p] >= g:
                p = previous[p]
            previous[s] = p
            if p >= 0:
                h = group[p]
                k = size[h]
                if k > 1:
                    at, to = where[p], h + k - 1
                    q = place[to]
                    place[at], where[q] = q, at
                    place[to], where[p] = p, to
                    size[h] = k - 1
                    size[to] = 1
                    group[p] = to
        top = g
    out = [-1] * n
    free = list(range(n))  # next free place of each group, by its first place

    def emit(s: int) -> None:
        while s >= 0:
            g = group[s]
            at = free[g]
            if done[s]:
                break
            out[at] = s
            done[s] = True
            free[g] = at + 1
            s = previous[s]

    done = [False] * n
    emit(n - 1)
    for i in range(n):
        s = out[i] - 1
        if s >= 0 and not done[s]:
            emit(s)
    return np.array(out)
