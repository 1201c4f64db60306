"""Suffix sorting by grouping: suffixes are grouped by Lyndon prefix, groups are visited from the greatest down, and a last sweep orders each group."""

from __future__ import annotations


def suffix_array(symbols: list[int]) -> list[int]:
    """Suffix array of integers whose last one is the only least one. Linear but for the first bucketing; nothing is renamed or sorted again."""
    n = len(symbols)
    counts: dict[int, int] = {}
    for c in symbols:
        counts[c] = counts.get(c, 0) + 1
    begin, at = {}, 0
    for c in sorted(counts):
        begin[c] = at
        at += counts[c]
    start = [begin[c] for c in symbols]  # a suffix's group is named by the group's first slot, so names compare as groups do
    stop = {begin[c]: begin[c] + counts[c] for c in counts}
    fill = dict(begin)
    slot, place = [0] * n, [0] * n
    for i, c in enumerate(symbols):
        slot[fill[c]], place[i] = i, fill[c]
        fill[c] += 1
    smaller = [-2] * n  # nearest earlier suffix of a lower group, once known

    end = n
    while end > 0:
        group = start[slot[end - 1]]
        members = slot[group:end]
        children: dict[int, int] = {}
        for i in members:
            if smaller[i] == -2:
                trail, j = [i], i - 1
                while j >= 0 and start[j] >= group:
                    if smaller[j] == -2:  # of the same group: it has the same answer
                        trail.append(j)
                        j -= 1
                    else:
                        j = smaller[j]
                for k in trail:
                    smaller[k] = j
            if smaller[i] >= 0:
                children[smaller[i]] = children.get(smaller[i], 0) + 1
        by_count: dict[int, list[int]] = {}
        for j, c in children.items():
            by_count.setdefault(c, []).append(j)
        for c in sorted(by_count, reverse=True):  # more repeats of the group's prefix make a greater prefix
            moved: dict[int, int] = {}
            for j in by_count[c]:
                old = start[j]
                stop[old] -= 1
                last = stop[old]
                other, here = slot[last], place[j]
                slot[here], place[other] = other, here
                slot[last], place[j] = j, last
                moved[old] = moved.get(old, 0) + 1
            for j in by_count[c]:
                start[j], old = stop[start[j]], start[j]
            for old, k in moved.items():
                stop[stop[old]] = stop[old] + k
        end = group

    order = [-1] * n
    order[0] = n - 1
    placed = [False] * n
    placed[n - 1] = True
    free: dict[int, int] = {}
    for at in range(n):
        i = order[at] - 1
        while i >= 0 and not placed[i]:
            g = start[i]
            k = free.get(g, g)
            order[k] = i
            free[g] = k + 1
            placed[i] = True
            i = smaller[i]
    return order


def common_prefixes(symbols: list[int], order: list[int]) -> list[int]:
    """How many symbols each suffix in order shares with the one before it."""
    n = len(symbols)
    rank = [0] * n
    for k, i in enumerate(order):
        rank[i] = k
    out, h = [0] * n, 0
    for i in range(n):
        if rank[i]:
            j = order[rank[i] - 1]
            while i + h < n and j + h < n and symbols[i + h] == symbols[j + h]:
                h += 1
            out[rank[i]] = h
            h = max(0, h - 1)
        else:
            h = 0
    return out
