"""N best paths of many small piece lattices at once.

The lattices of a batch of short strings stand side by side in flat arrays, one node for each place of each string.
Edges come from a trie that all places walk in step; forward Viterbi goes place by place; then the N best paths come
out of backward A-star searches in step, one path of every string a round. The forward score of a place completes
any path back from the end to it exactly, so an agenda entry is an edge that leaves a path already taken, with what the
whole path loses against the best; the entry of least loss is the next best path, and only the edges that enter
the part of a path walked anew become entries.
"""

from __future__ import annotations

import numpy as np

_MULTIPLIER = np.uint64(0x9E3779B97F4A7C15)
_SHIFT = np.uint64(21)


class Trie:
    """Steps (node, character) -> node in one open-addressing table; node 0 is the root."""

    def __init__(self, pieces: dict[str, int]):
        steps: dict[tuple[int, int], int] = {}
        self.longest, ends = max(map(len, pieces), default=1), {}
        for text, number in pieces.items():
            node = 0
            for c in text:
                node = steps.setdefault((node, ord(c)), len(steps) + 1)
            ends[node] = number
        self.piece = np.full(len(steps) + 1, -1, np.int32)
        self.piece[list(ends)] = list(ends.values())
        self.inner = np.zeros(len(steps) + 1, bool)
        self.inner[[n for n, _ in steps]] = True
        bits = max(8, (4 * len(steps)).bit_length())
        self.down = np.uint64(64 - bits)
        self.keys, self.to = np.zeros((1 << bits) + 64, np.uint64), np.zeros((1 << bits) + 64, np.int32)
        self.probes = 1
        self.first = np.zeros(0x110000, np.int32)  # the root's steps by code point
        for (node, c), child in steps.items():
            if node == 0:
                self.first[c] = child
            key = (node << 21 | c) + 1
            at = (key * int(_MULTIPLIER) & (1 << 64) - 1) >> (64 - bits)
            probe = 0
            while self.keys[at + probe]:
                probe += 1
            self.keys[at + probe], self.to[at + probe] = key, child
            self.probes = max(self.probes, probe + 1)

    def step(self, nodes: np.ndarray, codes: np.ndarray) -> np.ndarray:
        """The nodes reached; 0 where there is no such step."""
        key = (nodes.astype(np.uint64) << _SHIFT | codes) + np.uint64(1)
        at = (key * _MULTIPLIER >> self.down).astype(np.int64)
        out, left = np.zeros(len(key), np.int32), np.arange(len(key))
        for _ in range(self.probes):
            seen = self.keys[at]
            hit = seen == key
            out[left[hit]] = self.to[at[hit]]
            on = ~hit & (seen != 0)
            if not on.any():
                break
            left, key, at = left[on], key[on], at[on] + 1
        return out


def utf8_bytes(codes: np.ndarray) -> np.ndarray:
    return 1 + (codes >= 0x80).astype(np.int64) + (codes >= 0x800) + (codes >= 0x10000)


class Layout:
    """Strings side by side, longest first, place by place: the first characters of all, then the second ones of those that have
    one, and so on. The node of string w before its character d is ``node[d] + w``, the place of that character ``place[d] + w``."""

    def __init__(self, texts: list[str], sizes: np.ndarray):
        self.sizes = sizes
        most = int(sizes[0])
        flat = np.frombuffer("".join(texts).encode("utf-32-le", "replace"), "<u4")
        first = np.cumsum(sizes) - sizes
        holds = np.searchsorted(-sizes, -np.arange(most + 2), side="right")  # strings of d characters or more
        self.node = np.cumsum(holds) - holds
        self.place = np.cumsum(holds[1:]) - holds[1:]
        self.codes = np.concatenate([flat[first[: holds[d + 1]] + d] for d in range(most)]).astype(np.uint64)
        self.word = np.concatenate([np.arange(holds[d + 1], dtype=np.int32) for d in range(most)])
        self.deep = np.repeat(np.arange(most, dtype=np.int32), holds[1 : most + 1])
        self.node_word = np.concatenate([np.arange(holds[d], dtype=np.int32) for d in range(most + 1)])
        self.node_deep = np.repeat(np.arange(most + 1, dtype=np.int32), holds[: most + 1])


def edges_by_length(trie: Trie, weights: np.ndarray, unknown: float, at: Layout) -> list[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(place, weight, piece) of the edges of 1, 2, .. characters, by place; a character without a piece is an edge whose piece is
    its code point beyond the vocabulary's size."""
    left = at.sizes[at.word] - at.deep
    places = np.arange(len(at.codes), dtype=np.int32)
    nodes = trie.first[at.codes]
    found = np.where(nodes > 0, trie.piece[nodes], -1)
    raw = np.flatnonzero(found < 0)
    weight, piece = weights[found], found.astype(np.int64)
    weight[raw], piece[raw] = unknown * utf8_bytes(at.codes[raw]), at.codes[raw].astype(np.int64) + len(weights)
    out = [(places, weight, piece)]
    for length in range(2, trie.longest + 1):
        on = (nodes > 0) & trie.inner[nodes] & (left[places] >= length)
        places, nodes = places[on], nodes[on]
        if not len(places):
            break
        nodes = trie.step(nodes, at.codes[at.place[at.deep[places] + (length - 1)] + at.word[places]])
        found = trie.piece[nodes]
        hit = (nodes > 0) & (found >= 0)
        out.append((places[hit], weights[found[hit]], found[hit].astype(np.int64)))
    return out


def nbest(trie: Trie, weights: np.ndarray, unknown: float, texts: list[str], n: int) -> list[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """For each rank up to ``n``: scores of the strings (-inf where there is no such path), pieces of all strings in order, and how many
    of them each string has. Strings are not empty."""
    sizes = np.fromiter(map(len, texts), np.int64, len(texts))
    turn_to = np.argsort(-sizes, kind="stable")
    at = Layout([texts[i] for i in turn_to.tolist()], sizes[turn_to])
    lengths = edges_by_length(trie, weights, unknown, at)
    starts = [at.node[at.deep[p]] + at.word[p] for p, _, _ in lengths]
    ends = [at.node[at.deep[p] + (k + 1)] + at.word[p] for k, (p, _, _) in enumerate(lengths)]
    cuts = [np.searchsorted(p, np.append(at.place[: at.sizes[0]], len(at.codes))).tolist() for p, _, _ in lengths]

    ahead = np.full(len(at.node_word), -np.inf)
    ahead[: len(texts)] = 0.0
    for d in range(int(at.sizes[0])):
        for (_, w, _), s, e, cut in zip(lengths, starts, ends, cuts):
            a, b = cut[d], cut[d + 1]
            if a < b:  # the ends of edges of one length from one depth differ
                ahead[e[a:b]] = np.maximum(ahead[e[a:b]], ahead[s[a:b]] + w[a:b])
    start, end = np.concatenate(starts), np.concatenate(ends)
    weight, piece = (np.concatenate([x[k] for x in lengths]) for k in (1, 2))
    gap = ahead[end] - (ahead[start] + weight)
    exact = np.flatnonzero(gap == 0.0)
    way = np.full(len(at.node_word), -1)
    way[end[exact]] = exact  # the longest, where several are as good

    tails = at.node[at.sizes] + np.arange(len(texts))
    total, out, taken = ahead[tails], [], []
    lost, now_at, alive = np.zeros(len(texts)), tails, np.ones(len(texts), bool)
    pool: list[np.ndarray] = [np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)]  # edge, rank of the path it leaves, loss
    used = np.full(len(at.node_word), -1)
    for rank in range(n):
        walked = np.zeros(len(at.node_word), bool)
        now = now_at[alive]
        while len(now := now[now >= len(texts)]):  # nodes below are the strings' starts
            walked[now] = True
            used[now] = way[now]
            now = start[way[now]]
        taken.append(used)
        flat = used[used >= 0]
        whose = turn_to[at.node_word[end[flat]]]
        flat = flat[np.argsort(whose, kind="stable")]
        scores = np.full(len(texts), -np.inf)
        scores[turn_to] = np.where(alive, total - lost, -np.inf)
        out.append((scores, piece[flat], np.bincount(whose, minlength=len(texts))))
        if rank + 1 == n:
            break
        new = np.flatnonzero(walked[end])
        new = new[used[end[new]] != new]
        pool = [np.concatenate(x) for x in zip(pool, (new, np.full(len(new), rank), lost[at.node_word[end[new]]] + gap[new]))]
        if not len(pool[0]):
            break
        edge, left_path, loss = pool
        owner = at.node_word[end[edge]]
        least = np.full(len(texts), np.inf)
        np.minimum.at(least, owner, loss)
        hit = np.flatnonzero(loss == least[owner])[::-1]
        pick = np.full(len(texts), -1)
        pick[owner[hit]] = hit  # the first of each string
        pick = pick[pick >= 0]
        word, leaves = owner[pick], edge[pick]
        alive, lost = np.zeros(len(texts), bool), np.zeros(len(texts))
        alive[word], lost[word] = True, loss[pick]
        source, turn = np.zeros(len(texts), np.int64), np.full(len(texts), 1 << 30)
        source[word], turn[word] = left_path[pick], at.node_deep[end[leaves]]
        used = np.full(len(at.node_word), -1)
        beyond = at.node_deep > turn[at.node_word]
        for r, path in enumerate(taken):
            same = beyond & (source[at.node_word] == r)
            used[same] = path[same]
        used[end[leaves]] = leaves
        now_at = np.zeros(len(texts), np.int64)
        now_at[word] = start[leaves]
        rest = np.ones(len(edge), bool)
        rest[pick] = False
        pool = [x[rest] for x in pool]
    return out
