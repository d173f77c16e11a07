"""Suffix array by linear grouping.

Suffixes stand in groups, ordered, at first one group for each first symbol. Groups are taken from the
last to the first. Each member's previous-smaller pointer leads to the nearest suffix to its left that
stands in a lower group; the group's text follows that suffix's own once for every member that points
to it. So those pointed at move up within their group, further the more members point at them, and in
the end a group holds the suffixes with the same longest Lyndon prefix. The order within groups comes
from one walk over the array being built: the suffix before an emitted one, and what its pointers lead
to, take the next places of their groups. No names are made and nothing recurs.
"""

from __future__ import annotations

from collections.abc import Sequence


def _groups(text: Sequence[int]) -> tuple[list[int], list[int]]:
    """Final group (its first place) of every suffix, and the previous-smaller pointers."""
    n = len(text)
    order = sorted(range(n), key=text.__getitem__)
    place, group, size = [0] * n, [0] * n, [0] * n
    start, last = 0, None
    for k, i in enumerate(order):
        if text[i] != last:
            start, last = k, text[i]
        place[i], group[i] = k, start
        size[start] += 1
    before = [-2] * n
    end = n
    while end:
        low = group[order[end - 1]]
        members: dict[int, int] = {}
        for k in range(low, end):
            i = order[k]
            if before[i] != -2:
                p = before[i]
            else:
                path, p = [i], i - 1
                while p >= 0 and group[p] >= low:
                    if before[p] != -2:
                        p = before[p]
                    else:
                        path.append(p)
                        p -= 1
                for x in path:
                    before[x] = p
            if p >= 0:
                members[p] = members.get(p, 0) + 1
        end = low
        if not members:
            continue
        levels: dict[int, list[int]] = {}
        for p, n_points in members.items():
            levels.setdefault(n_points, []).append(p)
        for level in sorted(levels, reverse=True):  # most pointed-at first: they take the top places
            moved: dict[int, int] = {}
            for p in levels[level]:
                g = group[p]
                top = g + size[g] - 1 - moved.get(g, 0)
                other = order[top]
                at = place[p]
                order[at], order[top] = other, p
                place[other], place[p] = at, top
                moved[g] = moved.get(g, 0) + 1
            for g, m in moved.items():
                size[g] -= m
                first = g + size[g]
                if m and first != g:
                    size[first] = m
                    for k in range(first, first + m):
                        group[order[k]] = first
                else:
                    size[g] = m  # all members moved: the group stays one
    return group, before


def suffix_array(text: Sequence[int]) -> list[int]:
    """Start positions of the suffixes of ``text`` in lexicographic order; a suffix precedes what it is a prefix of."""
    n = len(text)
    if not n:
        return []
    group, before = _groups(text)
    free = list(range(n))  # next free place of the group that begins here
    out, placed = [-1] * n, [False] * n
    for k in range(-1, n):
        j = (out[k] if k >= 0 else n) - 1
        while j >= 0 and not placed[j]:
            g = group[j]
            out[free[g]] = j
            free[g] += 1
            placed[j] = True
            j = before[j]
    return out
