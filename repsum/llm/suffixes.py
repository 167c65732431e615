"""Suffix sorting by linear grouping: Lyndon-prefix groups first, then the order within them.

First phase. Every suffix starts with its longest Lyndon prefix. That prefix is the suffix's
first symbol followed by the Lyndon prefixes of the suffixes whose previous smaller suffix it
is. Groups start as buckets of equal first symbols and are finished from the largest down.
When a group is finished its members leave a linked list of open positions; the open position
left of a leaving member is its previous smaller suffix, and that parent moves up within its
bucket, further the more members of the group it has. Second phase. Suffixes of one group are
ordered by what follows their Lyndon prefix, so reading the finished part of the array from
the left places, for each suffix, those that are waiting for it, following previous-smaller
pointers. No symbols are renamed and nothing recurses.
"""

from __future__ import annotations

import numpy as np


def lyndon_groups(symbols: list[int]) -> tuple[list[list[int]], list[int]]:
    """Groups of positions in ascending order of their Lyndon prefixes, and previous smaller suffixes (-1: none)."""
    n = len(symbols)
    buckets: dict[int, list[int]] = {}
    for i, s in enumerate(symbols):
        buckets.setdefault(s, []).append(i)
    members = [buckets[s] for s in sorted(buckets)]
    below = list(range(-1, len(members) - 1))  # the group next below, by group number
    over = list(range(1, len(members) + 1))  # the group next above; the highest has itself
    over[-1] = len(members) - 1
    own = [0] * n
    for g, positions in enumerate(members):
        for i in positions:
            own[i] = g
    left = list(range(-1, n))
    right = list(range(1, n + 2))  # one more slot: right[-1] takes writes for "none"
    parent = [-1] * n
    finished: list[list[int]] = []
    g = len(members) - 1
    while g >= 0:
        group = [i for i in members[g] if own[i] == g]
        moved: dict[int, dict[int, list[int]]] = {}
        last, count = -1, 0
        for i in group:
            a, b = left[i], right[i]
            parent[i] = a
            right[a] = b
            left[b] = a
            if a == last:
                count += 1
                continue
            if last >= 0:
                moved.setdefault(own[last], {}).setdefault(count, []).append(last)
            last, count = a, 1
        if last >= 0:
            moved.setdefault(own[last], {}).setdefault(count, []).append(last)
        finished.append(group)
        for b, by_count in moved.items():
            under, top = b, over[b]
            for k in sorted(by_count):  # more members of the finished group stand higher
                new = len(members)
                members.append(by_count[k])
                below.append(under)
                over.append(top)
                over[under] = new
                for i in by_count[k]:
                    own[i] = new
                under = new
            below[top] = under
        g = below[g]
    finished.reverse()
    return [x for x in finished if x], parent


def suffix_array(symbols: list[int]) -> list[int]:
    """Order of all suffixes of a sequence of integers."""
    if not symbols:
        return []
    text = [*symbols, min(symbols) - 1]  # an end below every symbol
    groups, parent = lyndon_groups(text)
    n = len(text)
    number, free = [0] * n, []
    at = 0
    for g, positions in enumerate(groups):
        free.append(at)
        at += len(positions)
        for i in positions:
            number[i] = g
    order, placed = [-1] * n, [False] * n
    order[0], placed[n - 1] = n - 1, True
    for i in range(n):
        j = order[i] - 1
        while j >= 0 and not placed[j]:
            g = number[j]
            order[free[g]] = j
            free[g] += 1
            placed[j] = True
            j = parent[j]
    return order[1:]


def common_prefixes(symbols: list[int], order: list[int]) -> np.ndarray:
    """Length shared by each suffix in order with the one before it; 0 for the first."""
    n = len(symbols)
    rank = [0] * n
    for r, i in enumerate(order):
        rank[i] = r
    out, same = [0] * n, 0
    for i in range(n):
        r = rank[i]
        if r == 0:
            same = 0
            continue
        j = order[r - 1]
        while i + same < n and j + same < n and symbols[i + same] == symbols[j + same]:
            same += 1
        out[r] = same
        if same:
            same -= 1
    return np.array(out, np.int64)
