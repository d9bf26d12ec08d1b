"""Suffix arrays by linear grouping construction.

Suffixes are first grouped by their Lyndon prefix. Groups are taken in descending order; for each member the pointer
to the previous suffix in a lower group is found, and the suffixes pointed at move into a new group just above
their old one, since their prefix is now followed by this group's. Then the order within every group falls out of
one ascending pass: a suffix takes the next free place of its group when the suffix behind its Lyndon prefix is reached.
Nothing is renamed and nothing recurses.
"""

from __future__ import annotations

import itertools
from collections.abc import Sequence

UNSET = -2


def suffix_array(symbols: Sequence[int]) -> list[int]:
    """Starts of the suffixes in ascending order. Symbols are small numbers from 0 on, the last smaller than any other."""
    n = len(symbols)
    if n < 2:
        return list(range(n))
    of_symbol: list[list[int]] = [[] for _ in range(max(symbols) + 1)]  # symbols are small numbers: sorted by counting
    for i, s in enumerate(symbols):
        of_symbol[s].append(i)
    order = [*itertools.chain.from_iterable(of_symbol)]
    first = [0] * n  # of a suffix: where its group begins in ``order``
    place = [0] * n  # of a suffix: where it stands in ``order``
    size = [0] * n  # of a group, by where it begins
    begin = 0
    for i, s in enumerate(order):
        if symbols[s] != symbols[order[begin]]:
            begin = i
        first[s], place[s] = begin, i
        size[begin] += 1
    lower = [UNSET] * n  # of a suffix: the previous suffix in a lower group, -1 if there is none
    end = n
    while end > 0:
        s = order[end - 1]
        begin = first[s]
        if begin == end - 1:  # a group of one needs no tallies
            end = begin
            j = s - 1
            while j >= 0 and first[j] > begin:
                j = lower[j]
            lower[s] = j
            if j >= 0:
                group = first[j]
                left = size[group] - 1
                if left:
                    size[group] = left
                    to = group + left
                    at = place[j]
                    if at != to:
                        other = order[to]
                        order[to], order[at] = j, other
                        place[j], place[other] = to, at
                    first[j] = to
                    size[to] = 1
            continue
        members = order[begin:end]
        end = begin
        pointed: dict[int, int] = {}
        for s in members:
            if lower[s] == UNSET:
                chain, j = [s], s - 1
                while True:
                    while j >= 0 and first[j] > begin:
                        j = lower[j]
                    if j >= 0 and first[j] == begin:
                        if lower[j] == UNSET:
                            chain.append(j)
                            j -= 1
                            continue
                        j = lower[j]
                    break
                for c in chain:
                    lower[c] = j
            p = lower[s]
            if p >= 0:
                pointed[p] = pointed.get(p, 0) + 1
        if not pointed:
            continue
        by_count: dict[int, list[int]] = {}
        for p, count in pointed.items():
            by_count.setdefault(count, []).append(p)
        for count in range(max(by_count), 0, -1):  # at most as many steps as the group has members
            moved = by_count.get(count)
            if not moved:
                continue
            touched: dict[int, int] = {}
            for p in moved:
                group = first[p]
                left = size[group] - 1
                size[group] = left
                touched[group] = touched.get(group, 0) + 1
                at, to = place[p], group + left
                other = order[to]
                order[to], order[at] = p, other
                place[p], place[other] = to, at
            for p in moved:
                first[p] += size[first[p]]
            for group, n_moved in touched.items():
                size[group + size[group]] = n_moved
    free = [0] * n  # of a group, by where it begins: places taken
    order[0] = n - 1
    for i in range(n):
        s = order[i]
        j, stop = s - 1, lower[s]
        while j > stop:
            group = first[j]
            order[group + free[group]] = j
            free[group] += 1
            j = lower[j]
    return order
