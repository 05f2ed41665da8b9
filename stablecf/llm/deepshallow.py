"""Deep-shallow sorting of many short strings that lie in one buffer.

Shallow: multikey quicksort with eight-byte characters, a level at a time over
all groups at once, to ``shallow`` bytes.  Deep: what still shares that prefix
goes, group by group, into a blind trie, which looks at branching bytes only
and compares each new string with one stored string.
"""

from __future__ import annotations

import numpy as np

from stablecf.llm import kernels as K


class BlindTrie:
    """Compact trie over equal-length byte strings; inner nodes keep a depth and the children's branching bytes."""

    def __init__(self) -> None:
        self.root = None

    def insert(self, s: bytes, item: int) -> None:
        if self.root is None:
            self.root = (s, [item])
            return
        node, path = self.root, []
        while isinstance(node, list):  # blind descent: only branching bytes are read
            path.append(node)
            kids = node[1]
            node = kids.get(s[node[0]]) or next(iter(kids.values()))
        other = node[0]
        if other == s:
            node[1].append(item)
            return
        n = len(s)
        diff = int.from_bytes(s, "big") ^ int.from_bytes(other, "big")
        lcp = n - (diff.bit_length() + 7) // 8
        up = None
        node = self.root
        while isinstance(node, list) and node[0] < lcp:
            up, node = node, node[1].get(s[node[0]])
        if isinstance(node, list) and node[0] == lcp:
            node[1][s[lcp]] = (s, [item])
            return
        new = [lcp, {other[lcp]: node, s[lcp]: (s, [item])}]
        if up is None:
            self.root = new
        else:
            up[1][s[up[0]]] = new

    def groups(self) -> list[list[int]]:
        """Items in string order; equal strings together."""
        out, stack = [], [self.root] if self.root is not None else []
        while stack:
            node = stack.pop()
            if isinstance(node, list):
                stack.extend(node[1][c] for c in sorted(node[1], reverse=True))
            else:
                out.append(node[1])
        return out


def sort_strings(buf: np.ndarray, starts: np.ndarray, length: int, shallow: int = 32) -> tuple[np.ndarray, np.ndarray]:
    """(order, class): the strings ``buf[s : s + length]`` in order, and for each place of the order the number of its class of equal strings.

    ``buf`` must hold ``length`` bytes after every start.
    """
    n = len(starts)
    order = np.arange(n)
    if n < 2:
        return order, np.zeros(n, dtype=np.int64)
    shallow = min(shallow, length) // 8 * 8
    e8 = K.eights(buf)
    group = np.zeros(n, dtype=np.int64)  # at each place, the first place of its group
    active = np.arange(n)  # places in groups of more than one
    for level in range(0, shallow, 8):
        key = e8[starts[order[active]] + level]
        o = np.argsort(key) if level == 0 else np.lexsort((key, group[active]))
        order[active] = order[active][o]
        key, g = key[o], group[active]  # groups occupy the same places before and after
        new = np.ones(len(active), dtype=bool)
        new[1:] = (key[1:] != key[:-1]) | (g[1:] != g[:-1])
        first = active[np.flatnonzero(new)]
        size = np.diff(np.append(np.flatnonzero(new), len(active)))
        group[active] = np.repeat(first, size)
        active = active[np.repeat(size > 1, size)]
        if not len(active):
            break
    if len(active) and shallow < length:
        _deep(buf, e8, starts, order, group, active, shallow, length)
    new = np.ones(n, dtype=np.int64)
    new[0] = 0
    new[1:] = group[1:] != group[:-1]
    return order, np.cumsum(new)


def _deep(buf, e8, starts, order, group, active, shallow, length) -> None:
    """Orders the groups that share ``shallow`` bytes; ``order`` and ``group`` are changed in place."""
    at = starts[order[active]]
    h = np.zeros(len(at), dtype=np.uint64)
    tails = [min(i, length - 8) for i in range(shallow, length, 8)] if length >= 8 else []
    for i in tails:
        h = K.mix(h ^ e8[at + i])
    o = np.lexsort((h, group[active]))  # equal strings together, and one of each goes into the trie
    order[active], h = order[active][o], h[o]
    at, g = at[o], group[active]
    new = np.ones(len(at), dtype=bool)
    new[1:] = (h[1:] != h[:-1]) | (g[1:] != g[:-1])
    for i in tails:  # a hash alone never makes strings equal
        k = e8[at + i]
        new[1:] |= k[1:] != k[:-1]
    leaf = np.flatnonzero(new)
    size = np.diff(np.append(leaf, len(at)))
    gl = g[leaf]
    edge = np.flatnonzero(np.append(True, gl[1:] != gl[:-1]))
    many = np.diff(np.append(edge, len(gl)))
    raw = buf.tobytes()
    for e, m in zip(edge[many > 1].tolist(), many[many > 1].tolist(), strict=True):
        trie, place = BlindTrie(), active[leaf[e]]
        members = []
        for q in range(e, e + m):
            a = int(at[leaf[q]])
            trie.insert(raw[a + shallow : a + length], q - e)
            members.append(order[active[leaf[q]] : active[leaf[q]] + size[q]].copy())
        for same in trie.groups():
            first = place
            for q in same:
                order[place : place + len(members[q])] = members[q]
                place += len(members[q])
            group[first:place] = first
