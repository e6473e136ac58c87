"""Suffix array by linear grouping (no recursion, no renaming).

Suffixes start grouped by first symbol. Groups are closed from the highest down. When a group is
closed, the longest Lyndon prefix of each of its suffixes is final; each suffix points to the nearest
suffix before it that stands in a lower group, and those pointed to move up within their own group, by
how many of the closed group point to them: their Lyndon prefix has just grown by as many copies. After
that, one ascending pass emits the order inside each group: a suffix that is out lets the suffixes
whose Lyndon prefix ends where it starts follow, found along the same pointers.
"""

from __future__ import annotations


def suffix_array(t: list[int]) -> list[int]:
    """Start positions in lexicographic order. The last symbol must be smaller than all others."""
    n = len(t)
    order = sorted(range(n), key=t.__getitem__)
    place, group, size, lower = [0] * n, [0] * n, [0] * n, [-1] * n
    g = 0
    for i, s in enumerate(order):
        if t[s] != t[order[g]]:
            g = i
        place[s] = i
        group[s] = g
        size[g] += 1
    end = n - 1
    while end > 0:
        g = group[order[end]]
        members = (order[end],) if g == end else sorted(order[g : end + 1])
        end = g - 1
        hits: dict[int, int] = {}
        for s in members:
            p = s - 1
            while p >= 0 and group[p] >= g:
                p = lower[p]
            lower[s] = p
            if p >= 0:
                hits[p] = hits.get(p, 0) + 1
        if not hits:
            continue
        if len(hits) == 1 or max(hits.values()) == 1:
            levels = [list(hits)]
        else:
            by: dict[int, list[int]] = {}
            for p, c in hits.items():
                by.setdefault(c, []).append(p)
            levels = [by[c] for c in sorted(by, reverse=True)]
        for level in levels:
            for p in level:  # to the end of their group
                q = group[p]
                last = size[q] - 1
                other, at = order[q + last], place[p]
                if other != p:
                    order[q + last], order[at] = p, other
                    place[p], place[other] = q + last, at
                size[q] = last
            fresh = [group[p] + size[group[p]] for p in level]
            for p, q in zip(level, fresh):
                group[p] = q
                size[q] += 1
    out, front, placed = [0] * n, list(range(n)), bytearray(n)
    if n:
        out[0] = n - 1
        placed[n - 1] = 1
    for i in range(n):
        s = out[i] - 1
        while s >= 0 and not placed[s]:
            q = group[s]
            out[front[q]] = s
            front[q] += 1
            placed[s] = 1
            s = lower[s]
    return out
