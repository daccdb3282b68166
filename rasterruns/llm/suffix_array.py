"""Suffix arrays in linear time by grouping.

Suffixes stand in groups by a common prefix that grows to their longest Lyndon
prefix.  Groups are taken from the highest down: each member finds the nearest
suffix before it that stands in a lower group, by jumping over pointers already
known, and that suffix's prefix grows by the members that point to it; those
that grow alike form a new group just above the one they leave.  Afterwards one
ascending pass emits the order: the suffix in hand releases, along the same
pointers, the suffixes whose Lyndon prefix ends where it begins, each to the
next free place of its group.  No names are recomputed and nothing recurses.
"""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np


def suffix_array(text: bytes | Sequence[int]) -> list[int]:
    """Starts of all suffixes in ascending order; an end sorts before any symbol."""
    n = len(text)
    if n < 2:
        return list(range(n))
    symbols = np.frombuffer(text, np.uint8) if isinstance(text, bytes) else np.asarray(text)
    layout = np.argsort(symbols, kind="stable")
    heads = np.flatnonzero(np.concatenate([[True], np.diff(symbols[layout]) != 0]))
    sizes = np.diff(np.append(heads, n))
    place = np.empty(n, np.int64)
    place[layout] = np.arange(n)
    head_of = np.empty(n, np.int64)
    head_of[layout] = np.repeat(heads, sizes)
    sa, where, group = layout.tolist(), place.tolist(), head_of.tolist()
    size = [0] * n  # members of the group that starts at a place
    for h, s in zip(heads.tolist(), sizes.tolist(), strict=True):
        size[h] = s
    lower = [-1] * n  # nearest earlier suffix in a lower group
    top = n  # end of the places not yet taken
    while top > 0:
        start = group[sa[top - 1]]
        if top - start == 1:
            s = sa[start]
            p = s - 1
            while p >= 0 and group[p] > start:
                p = lower[p]
            lower[s] = p
            if p >= 0:
                g = group[p]
                last = g + size[g] - 1
                if last > g:  # p leaves for a group of its own at the end of its group
                    w = where[p]
                    q = sa[last]
                    sa[w], sa[last] = q, p
                    where[q], where[p] = w, last
                    size[g] -= 1
                    size[last] = 1
                    group[p] = last
            top = start
            continue
        members = sa[start:top]
        members.sort()
        count: dict[int, int] = {}
        for s in members:
            p = s - 1
            while p >= 0 and group[p] >= start:
                p = lower[p]
            lower[s] = p
            if p >= 0:
                count[p] = count.get(p, 0) + 1
        if count:
            if len(count) == sum(count.values()):
                levels = [list(count)]
            else:
                by: dict[int, list[int]] = {}
                for p, c in count.items():
                    by.setdefault(c, []).append(p)
                levels = [by[c] for c in sorted(by, reverse=True)]
            for level in levels:
                opened: dict[int, int] = {}
                for p in level:
                    g = group[p]
                    last = g + size[g] - 1
                    w = where[p]
                    q = sa[last]
                    sa[w], sa[last] = q, p
                    where[q], where[p] = w, last
                    size[g] -= 1
                    opened[g] = opened.get(g, 0) + 1
                for g, c in opened.items():
                    new = g + size[g]
                    size[new] = c
                    if c == 1:
                        group[sa[new]] = new
                    else:
                        for p in sa[new : new + c]:
                            group[p] = new
        top = start
    free = list(range(n))  # next free place of each group
    done = [False] * n
    # the end of the text releases first: suffixes whose Lyndon prefix ends there
    p = n - 1
    while p >= 0:
        g = group[p]
        sa[free[g]] = p
        free[g] += 1
        done[p] = True
        p = lower[p]
    for i in range(n):
        p = sa[i] - 1
        while p >= 0 and not done[p]:
            g = group[p]
            sa[free[g]] = p
            free[g] += 1
            done[p] = True
            p = lower[p]
    return sa
