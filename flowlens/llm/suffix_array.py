"""Suffix arrays by grouping, in linear time and without recursion on renamed strings.

Phase one sorts suffixes by their longest Lyndon prefix: groups are processed in descending order, and every member extends the prefix
of its previous smaller suffix, which may move up into a new group. Phase two emits the order inside groups from left to right: a placed
suffix fixes the place of the one before it and of that one's chain of previous smaller suffixes.
"""

from __future__ import annotations

from collections.abc import Sequence


def suffix_array(text: Sequence[int]) -> list[int]:
    """Start positions of the non-empty suffixes of a sequence of whole numbers, in lexicographic order."""
    n = len(text)
    if not n:
        return []
    rank = {c: k for k, c in enumerate(sorted(set(text)))}
    members: list[set[int]] = [set() for _ in rank]  # by group
    below = list(range(-1, len(rank) - 1))  # the next lower group
    group = [rank[c] for c in text]
    for i, g in enumerate(group):
        members[g].add(i)
    top = len(rank) - 1
    done = bytearray(n + 1)
    skip = list(range(-1, n))  # towards the nearest position to the left that is not processed
    smaller = [-1] * n
    above = list(range(1, len(rank))) + [-1]

    g = top
    while g >= 0:
        batch = members[g]
        for i in batch:
            done[i] = 1
        count: dict[int, int] = {}
        for i in batch:
            j = skip[i]
            path = []
            while j >= 0 and done[j]:
                path.append(j)
                j = skip[j]
            for p in path:
                skip[p] = j
            skip[i] = smaller[i] = j
            if j >= 0:
                count[j] = count.get(j, 0) + 1
        # parents leave their groups by how many members extend them: more members, higher group
        moves: dict[int, dict[int, list[int]]] = {}
        for p, c in count.items():
            moves.setdefault(group[p], {}).setdefault(c, []).append(p)
        for h, by_count in moves.items():
            moved = sum(map(len, by_count.values()))
            counts = sorted(by_count)
            if moved == len(members[h]):  # the least extended ones keep the group
                counts = counts[1:]
            at = h
            for c in counts:
                new = len(members)
                members.append(set(by_count[c]))
                members[h].difference_update(by_count[c])
                for p in by_count[c]:
                    group[p] = new
                over = above[at]
                above.append(over)
                below.append(at)
                above[at] = new
                if over >= 0:
                    below[over] = new
                at = new
        g = below[g]

    lowest = 0
    while below[lowest] >= 0:
        lowest = below[lowest]
    front, at, g = [0] * len(members), 0, lowest
    while g >= 0:
        front[g] = at
        at += len(members[g])
        g = above[g]
    order = [-1] * n
    placed = bytearray(n)

    def place(j: int) -> None:
        while j >= 0 and not placed[j]:
            placed[j] = 1
            h = group[j]
            order[front[h]] = j
            front[h] += 1
            j = smaller[j]

    place(n - 1)  # the empty suffix comes first
    for k in range(n):
        place(order[k] - 1)
    return order


def common_prefixes(text: Sequence[int], order: Sequence[int]) -> list[int]:
    """Length of the common prefix of every suffix with its predecessor in the order (0 for the first)."""
    n = len(text)
    where = [0] * n
    for k, i in enumerate(order):
        where[i] = k
    out, h = [0] * n, 0
    for i in range(n):
        k = where[i]
        if k:
            j = order[k - 1]
            while i + h < n and j + h < n and text[i + h] == text[j + h]:
                h += 1
            out[k] = h
            h = max(0, h - 1)
        else:
            h = 0
    return out
