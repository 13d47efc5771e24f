"""Linear-time suffix arrays by Lyndon-prefix groups."""

from __future__ import annotations


def suffix_array(text: list[int]) -> list[int]:
    """Order of all suffixes of a sequence of non-negative integers; the end counts as smaller than any symbol.

    First suffixes are grouped by their longest Lyndon prefix: groups start as those of equal first symbols and are taken in
    descending order. Each member of the group at hand finds the nearest suffix before it of a smaller group (its previous-smaller
    pointer; pointers of larger groups are jumped along). That suffix's Lyndon prefix goes on with the group's, once for each member
    that points to it, so it moves to a new group just above its old one, those with more repeats higher. Then one scan emits the
    order: as suffixes come out in ascending order, the suffixes whose next smaller one has just come out take the next place of
    their group.
    """
    n = len(text)
    if n < 2:
        return list(range(n))
    order = sorted(range(n), key=text.__getitem__)
    place = [0] * n  # of each suffix in `order`
    group = [0] * n  # start of its group in `order`
    size = [0] * n  # by start
    start, last = 0, -1
    for k, s in enumerate(order):
        place[s] = k
        if text[s] != last:
            start, last = k, text[s]
        group[s] = start
        size[start] += 1
    back = [-1] * n
    top = n
    while top:
        start = group[order[top - 1]]
        members = order[start:top]
        top = start
        if len(members) == 1:
            s = members[0]
            p = s - 1
            while p >= 0 and group[p] > start:
                p = back[p]
            back[s] = p
            if p >= 0:
                g = group[p]
                k = size[g] - 1
                if k:
                    # to the end of its group, which is the new group's only place
                    e, at = g + k, place[p]
                    q = order[e]
                    order[at], order[e] = q, p
                    place[q], place[p] = at, e
                    group[p], size[g], size[e] = e, k, 1
            continue
        members.sort()
        times: dict[int, int] = {}
        for s in members:
            p = s - 1
            while p >= 0 and group[p] >= start:
                p = back[p]
            back[s] = p
            if p >= 0:
                times[p] = times.get(p, 0) + 1
        if not times:
            continue
        by_times: dict[int, list[int]] = {}
        for p, k in times.items():
            by_times.setdefault(k, []).append(p)
        for k in sorted(by_times, reverse=True):
            moved: dict[int, int] = {}
            for p in by_times[k]:
                g = group[p]
                m = moved[g] = moved.get(g, 0) + 1
                e, at = g + size[g] - m, place[p]
                q = order[e]
                order[at], order[e] = q, p
                place[q], place[p] = at, e
            for g, m in moved.items():
                left = size[g] - m
                if left:
                    new = g + left
                    size[g], size[new] = left, m
                    for x in order[new : new + m]:
                        group[x] = new
    free = list(range(n))  # next place of each group, by its start
    out = [-1] * n
    done = bytearray(n)
    s = n - 1
    while s >= 0:
        g = group[s]
        out[free[g]] = s
        free[g] += 1
        done[s] = 1
        s = back[s]
    for k in range(n):
        s = out[k] - 1
        while s >= 0 and not done[s]:
            g = group[s]
            out[free[g]] = s
            free[g] += 1
            done[s] = 1
            s = back[s]
    return out
