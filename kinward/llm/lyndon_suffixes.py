"""Suffix sorting in two linear passes by Lyndon-prefix groups, and the common prefixes.

First pass: suffixes start out grouped by first symbol. Groups are taken from the greatest down;
each member points at the last position before it that belongs to a lower group, and positions
that collect more pointers move to a new group right above their old one. In the end suffixes are
grouped by their longest Lyndon prefix. Second pass: in suffix order, each suffix settles those
whose Lyndon prefix it follows, at the front of their groups. Nothing is renamed or recursed.
"""

from __future__ import annotations

import numpy as np


def suffix_order(symbols) -> list[int]:
    """Suffix array of a sequence whose last symbol is its unique least one."""
    s = np.asarray(symbols)
    n = len(s)
    if n < 2:
        return list(range(n))
    order = np.argsort(s, kind="stable")
    head = np.append(0, np.flatnonzero(np.diff(s[order])) + 1)
    size_at = np.diff(np.append(head, n))
    at = np.empty(n, np.int64)
    at[order] = np.arange(n)
    group = np.empty(n, np.int64)
    group[order] = np.repeat(head, size_at)
    order, at, group = order.tolist(), at.tolist(), group.tolist()
    size = [0] * n
    for h, z in zip(head.tolist(), size_at.tolist()):
        size[h] = z
    below = [-1] * n
    hi = n
    while hi > 0:
        g = group[order[hi - 1]]
        members = order[g:hi]
        if len(members) > 1:
            members.sort()
        hits: dict[int, int] = {}
        for i in members:
            p = i - 1
            while p >= 0 and group[p] >= g:
                p = below[p]
            below[i] = p
            if p >= 0:
                hits[p] = hits.get(p, 0) + 1
        hi = g
        if not hits:
            continue
        levels: dict[int, list[int]] = {}
        for p, c in hits.items():
            levels.setdefault(c, []).append(p)
        for c in sorted(levels, reverse=True):
            fresh: dict[int, int] = {}
            for p in levels[c]:  # to the tail of the block
                b = group[p]
                k = fresh.get(b, 0)
                end = b + size[b] - 1 - k
                here, other = at[p], order[end]
                order[here], order[end] = other, p
                at[other], at[p] = here, end
                fresh[b] = k + 1
            for b, k in fresh.items():
                if k == size[b]:
                    continue
                size[b] -= k
                new = b + size[b]
                size[new] = k
                for x in range(new, new + k):
                    group[order[x]] = new
    # where the Lyndon prefix ends: the next position of the same or a lower group
    waits: list[list[int] | None] = [None] * n
    stack: list[int] = []
    for i in range(n):
        gi = group[i]
        while stack and group[stack[-1]] >= gi:
            j = stack.pop()
            if waits[i] is None:
                waits[i] = [j]
            else:
                waits[i].append(j)
        stack.append(i)
    front = list(range(n))  # next free place of each group
    out = [0] * n
    out[0] = n - 1
    for r in range(n):
        for j in waits[out[r]] or ():
            b = group[j]
            out[front[b]] = j
            front[b] += 1
    return out


def common_prefixes(symbols: list[int], order: list[int]) -> list[int]:
    """Length of the common prefix of each suffix with the one before it in order."""
    n = len(symbols)
    rank = [0] * n
    for r, i in enumerate(order):
        rank[i] = r
    out, h = [0] * n, 0
    for i in range(n):
        r = rank[i]
        if r:
            j = order[r - 1]
            top = n - max(i, j)
            while h < top and symbols[i + h] == symbols[j + h]:
                h += 1
            out[r] = h
            if h:
                h -= 1
        else:
            h = 0
    return out
