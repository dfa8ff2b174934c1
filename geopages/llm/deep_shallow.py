"""Deep-shallow sorting of suffixes.

Suffixes are split by multikey quicksort on four-byte characters down to a
shallow depth. Groups that still agree there have long common prefixes, on
which character-wise splitting wastes its time; a blind trie orders each: an
insertion walks down by branching characters alone, compares with one leaf, and
so reads a long common prefix once.
"""

from __future__ import annotations

CHARACTER = 4


def deep_shallow_order(strings: list[bytes], start: int = 0, shallow: int = 24) -> list[int]:
    """Indices of ``strings`` in lexicographic order; equal strings keep theirs. The first ``start`` bytes need not be equal."""
    order: list[int] = []
    todo: list[tuple[list[int], int]] = [(list(range(len(strings))), 0 if not _same(strings, start) else start)]
    while todo:
        items, depth = todo.pop()
        if len(items) < 2:
            order += items
        elif depth >= shallow:
            order += blind_trie_order(strings, items)
        else:
            end = depth + CHARACTER
            pivot = strings[items[len(items) // 2]][depth:end]
            less, same, more = [], [], []
            for i in items:
                c = strings[i][depth:end]
                (same if c == pivot else less if c < pivot else more).append(i)
            todo.append((more, depth))
            if len(pivot) < CHARACTER:  # these end here and are equal
                todo += [([i], depth) for i in reversed(same)]
            else:
                todo.append((same, end))
            todo.append((less, depth))
    return order


def _same(strings: list[bytes], n: int) -> bool:
    head = strings[0][:n] if strings else b""
    return len(head) == n and all(s.startswith(head) for s in strings)


def common_prefix(a: bytes, b: bytes) -> int:
    n = min(len(a), len(b))
    if a[:n] == b[:n]:
        return n
    lo, hi = 0, n  # a and b agree before lo, differ before hi
    while hi - lo > 1:
        mid = (lo + hi) // 2
        if a[lo:mid] == b[lo:mid]:
            lo = mid
        else:
            hi = mid
    return lo


def blind_trie_order(strings: list[bytes], items: list[int]) -> list[int]:
    """``items`` in the order of their strings. A node is [depth, {byte or -1 at the end: child}], a leaf a list of equal items."""
    root: tuple | list = ("leaf", [items[0]])
    for i in items[1:]:
        s = strings[i]
        node = root
        while node[0] != "leaf":
            depth, kids = node
            c = s[depth] if depth < len(s) else -1
            node = kids[c] if c in kids else next(iter(kids.values()))
        t = strings[node[1][0]]
        if s == t:
            node[1].append(i)
            continue
        agree = common_prefix(s, t)
        c, parent, edge, node = s[agree] if agree < len(s) else -1, None, None, root
        while node[0] != "leaf" and node[0] < agree:
            parent, edge = node, s[node[0]] if node[0] < len(s) else -1
            node = node[1][edge]
        if node[0] != "leaf" and node[0] == agree:
            node[1][c] = ("leaf", [i])
            continue
        other = t[agree] if agree < len(t) else -1
        fork = (agree, {other: node, c: ("leaf", [i])})
        if parent is None:
            root = fork
        else:
            parent[1][edge] = fork
    out: list[int] = []
    stack = [root]
    while stack:
        node = stack.pop()
        if node[0] == "leaf":
            out += node[1]
        else:
            stack += [node[1][c] for c in sorted(node[1], reverse=True)]
    return out
