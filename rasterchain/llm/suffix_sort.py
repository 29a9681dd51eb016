"""Deep-shallow sorting of many short byte strings, and the classes of equal prefixes it yields."""

from __future__ import annotations

import numpy as np

SHALLOW_WORDS = 12


def padded(strings: list[bytes], width: int) -> tuple[np.ndarray, np.ndarray]:
    """Strings as rows of a zero-padded byte matrix of a whole number of 8-byte words, and their lengths."""
    words = -(-width // 8)
    flat = np.frombuffer(b"".join(s.ljust(8 * words, b"\0") for s in strings), dtype=np.uint8)
    return flat.reshape(len(strings), 8 * words), np.fromiter(map(len, strings), np.int64, len(strings))


class BlindTrie:
    """Orders strings by a trie that stores branching depths only.

    A search follows one byte per branching node without looking at what lies between, so
    it may end at a wrong leaf; one comparison with that leaf gives the true common length,
    and a second descent to that depth finds the place of the new leaf.
    """

    def __init__(self, strings: list[bytes]):
        self.strings = strings
        self.root: list | None = None

    def add(self, i: int) -> None:
        s = self.strings[i]
        if self.root is None:
            self.root = [len(s), None, [i]]
            return
        node = self.root
        while node[1] is not None:
            nxt = node[1].get(s[node[0]] if node[0] < len(s) else -1)
            node = nxt if nxt is not None else next(iter(node[1].values()))
        other = self.strings[node[2][0]]
        if s == other:
            node[2].append(i)
            return
        depth = common_length(s, other)
        parent, node = None, self.root
        while node[1] is not None and node[0] < depth:
            parent, node = node, node[1][s[node[0]] if node[0] < len(s) else -1]
        key = s[depth] if depth < len(s) else -1
        leaf = [len(s), None, [i]]
        if node[1] is not None and node[0] == depth:
            node[1][key] = leaf
            return
        branch = [depth, {other[depth] if depth < len(other) else -1: node, key: leaf}, None]
        if parent is None:
            self.root = branch
        else:
            parent[1][s[parent[0]] if parent[0] < len(s) else -1] = branch

    def order(self) -> list[int]:
        out: list[int] = []
        stack = [self.root] if self.root else []
        while stack:
            node = stack.pop()
            if node[1] is None:
                out += node[2]
            else:
                stack += [node[1][k] for k in sorted(node[1], reverse=True)]
        return out


def common_length(a: bytes, b: bytes) -> int:
    n = min(len(a), len(b))
    differ = int.from_bytes(a[:n], "big") ^ int.from_bytes(b[:n], "big")
    return n - (differ.bit_length() + 7) // 8


def deep_shallow_order(strings: list[bytes], group: np.ndarray, width: int, shallow_words: int = SHALLOW_WORDS) -> tuple[np.ndarray, np.ndarray]:
    """Order of the strings by (group, bytes), and each one's common length with its predecessor (0 at a group's start).

    Multikey quicksort takes one 8-byte word at a time and only the groups still tied, down
    to the shallow depth; blind tries order what is tied beyond it.
    """
    n = len(strings)
    rows, length = padded(strings, width)
    words = np.ascontiguousarray(rows).view(">u8")
    order = np.argsort(group, kind="stable")
    tied = np.cumsum(np.concatenate([[0], group[order][1:] != group[order][:-1]])) if n else np.empty(0, np.int64)
    for depth in range(min(shallow_words, words.shape[1])):
        start = np.concatenate([[True], tied[1:] != tied[:-1]])
        alone = start & np.concatenate([start[1:], [True]])
        live = np.flatnonzero(~alone)
        if not len(live):
            break
        w = words[order[live], depth].astype(np.uint64)
        by = np.lexsort((w, tied[live]))
        order[live] = order[live][by]
        cut = np.zeros(n, bool)
        cut[live[1:]] = w[by][1:] != w[by][:-1]
        tied = np.cumsum(start | cut) - 1
    start = np.flatnonzero(np.concatenate([[True], tied[1:] != tied[:-1]]))
    for a, b in zip(start, np.append(start[1:], n), strict=True):
        if b - a > 1:
            trie = BlindTrie(strings)
            for i in order[a:b].tolist():
                trie.add(i)
            order[a:b] = trie.order()
    lcp = np.zeros(n, np.int64)
    for at in range(1, n, 100_000):
        x, y = order[at - 1 : at + 99_999], order[at : at + 100_000]
        x = x[: len(y)]
        differ = rows[x] != rows[y]
        first = np.where(differ.any(axis=1), differ.argmax(axis=1), rows.shape[1])
        lcp[at : at + 100_000] = np.where(group[x] == group[y], np.minimum(first, np.minimum(length[x], length[y])), 0)
    return order, lcp


def repeated_windows(left: list[bytes], right: list[bytes], group: np.ndarray, window: int, first: np.ndarray, last: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For each place, the least and greatest offset first..last at which the window around it occurs elsewhere in its group; -1 if none.

    left: the bytes before the place, nearest first; right: those from the place on. The
    window at offset o takes o bytes before the place and window - o from it.
    """
    n = len(left)
    reach = int(last.max())
    left = [x[:reach] for x in left]
    n_left, n_right = np.fromiter(map(len, left), np.int64, n), np.fromiter(map(len, right), np.int64, n)
    by_r, lcp_r = deep_shallow_order(right, group, window)
    by_l, lcp_l = deep_shallow_order(left, group, reach)
    least, most = np.full(n, -1, np.int64), np.full(n, -1, np.int64)
    a, b = np.empty(n, np.int64), np.empty(n, np.int64)
    for o in range(int(first.min()), reach + 1):
        a[by_r] = np.cumsum(lcp_r < window - o)
        if o:
            b[by_l] = np.cumsum(lcp_l < o)
            key = a * (n + 1) + b
        else:
            key = a * (n + 1) + group_ids(group)
        fits = np.flatnonzero((n_left >= o) & (n_right >= window - o) & (first <= o) & (o <= last))
        if len(fits) < 2:
            continue
        k = key[fits]
        s = np.sort(k)
        twice = s[1:][s[1:] == s[:-1]]
        if len(twice):
            at = np.searchsorted(twice, k)
            hit = fits[(at < len(twice)) & (twice[np.minimum(at, len(twice) - 1)] == k)]
            most[hit] = o
            least[hit[least[hit] < 0]] = o
    return least, most


def group_ids(group: np.ndarray) -> np.ndarray:
    return np.unique(group, return_inverse=True)[1]
