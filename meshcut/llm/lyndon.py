"""Suffix order by Lyndon prefixes, without renaming or recursion; linear but for sorting symbols and groups by place.

First the suffixes are grouped by their Lyndon prefix (the longest Lyndon word a suffix starts with). Groups begin as equal
first symbols and are settled from the greatest down: each member finds the closest earlier suffix of a smaller group by
following previous-smaller pointers, and every suffix that was found by `c` members is known to go on with `c` copies of
the settled word, so it moves behind those of its group that were found less often. Then each group's order is emitted:
a suffix ranks in its group as the suffix after its Lyndon prefix does, which is smaller and so already has its place.
"""

from __future__ import annotations


def lyndon_groups(text) -> list[int]:
    """For each suffix the first place of its group in the suffix order."""
    n = len(text)
    order = sorted(range(n), key=text.__getitem__)
    at = [0] * n
    group = [0] * n
    stop = [0] * (n + 1)
    begin = 0
    for k, s in enumerate(order):
        if text[s] != text[order[begin]]:
            stop[begin] = k
            begin = k
        at[s] = k
        group[s] = begin
    stop[begin] = n
    smaller = [-1] * n
    end = n
    while end:
        g = group[order[end - 1]]
        found: dict[int, int] = {}
        for s in order[g:end] if end - g == 1 else sorted(order[g:end]):
            p = s - 1
            while p >= 0 and group[p] > g:
                p = smaller[p]
            if p >= 0 and group[p] == g:
                p = smaller[p]
            smaller[s] = p
            if p >= 0:
                found[p] = found.get(p, 0) + 1
        end = g
        if not found:
            continue
        by_count: dict[int, list[int]] = {}
        for p, c in found.items():
            by_count.setdefault(c, []).append(p)
        for c in sorted(by_count, reverse=True):
            limits: dict[int, int] = {}
            moved = by_count[c]
            for p in moved:
                h = group[p]
                last = stop[h] - 1
                limits.setdefault(h, last + 1)
                q, k = order[last], at[p]
                order[k], at[q] = q, k
                order[last], at[p] = p, last
                stop[h] = last
            starts = {h: stop[h] for h in limits}
            for p in moved:
                group[p] = starts[group[p]]
            for h, limit in limits.items():
                stop[starts[h]] = limit
    return group


def suffix_order(text) -> list[int]:
    """Starts of the suffixes of a sequence of comparable symbols, in ascending order."""
    n = len(text)
    group = lyndon_groups(text)
    waiting: list = [None] * (n + 1)
    stack: list[int] = []
    for i in range(n - 1, -1, -1):
        g = group[i]
        while stack and group[stack[-1]] > g:
            stack.pop()
        j = stack[-1] if stack else n
        if waiting[j] is None:
            waiting[j] = [i]
        else:
            waiting[j].append(i)
        stack.append(i)
    out = [0] * n
    free = list(range(n))
    for i in waiting[n] or ():
        g = group[i]
        out[free[g]] = i
        free[g] += 1
    for k in range(n):
        for i in waiting[out[k]] or ():
            g = group[i]
            out[free[g]] = i
            free[g] += 1
    return out
