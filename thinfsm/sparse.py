"""Dictionary automata of more states than a task holds full rows of.

A state's row is kept as the cells in which it differs from the start's row: its children and
what its longest proper suffix has besides.  Draws, similarities, forests and defaults are those
of ``kernels`` (but for different keys of equal 64-bit hash); every part works in pieces.
"""

from __future__ import annotations

import heapq

import numpy as np

from . import kernels

SIGMA = 256
#: Draws handled at a time.
PIECE = 1 << 16


def dictionary(words: list[bytes]) -> dict[str, np.ndarray]:
    """The automaton of ``rules.dictionary`` (states by length and then bytes): the start's row, and each state's cells that differ from it, in order of (state, symbol)."""
    words = sorted(words)
    size = np.fromiter(map(len, words), np.int64, len(words))
    flat, off = np.frombuffer(b"".join(words), np.uint8), np.cumsum(size) - size
    cur, live = np.zeros(len(words), np.int64), np.flatnonzero(size > 0)
    parents, chars, bounds, d = [], [], [0, 1], 0
    while len(live):
        p, c = cur[live], flat[off[live] + d]
        new = np.concatenate([[True], (p[1:] != p[:-1]) | (c[1:] != c[:-1])])
        cur[live] = bounds[-1] + np.cumsum(new) - 1
        parents.append(p[new].astype(np.int32))
        chars.append(c[new])
        bounds.append(bounds[-1] + int(new.sum()))
        d += 1
        live = live[size[live] > d]
    n, parent, char = bounds[-1], np.concatenate([np.zeros(0, np.int32), *parents]), np.concatenate([np.zeros(0, np.uint8), *chars])
    key = parent.astype(np.int64) * SIGMA + char  # ascending: the place of (state, symbol) gives the child

    def child(state, symbol):
        want = state.astype(np.int64) * SIGMA + symbol
        i = np.minimum(np.searchsorted(key, want), max(len(key) - 1, 0))
        return np.where(key[i] == want, i + 1, 0) if len(key) else np.zeros(len(want), np.int64)

    fail = np.zeros(n, np.int32)
    for a, b in zip(bounds[2:-1], bounds[3:]):
        f, c, todo = fail[parent[a - 1 : b - 1]], char[a - 1 : b - 1], np.arange(b - a)
        while len(todo):
            t = child(f[todo], c[todo])
            fail[a + todo] = t
            todo = todo[(t == 0) & (f[todo] > 0)]
            f[todo] = fail[f[todo]]
    first = np.zeros(SIGMA, np.int64)
    if len(bounds) > 2:
        first[char[: bounds[2] - 1]] = np.arange(1, bounds[2])
    at, sym, to = np.zeros(n + 1, np.int64), np.zeros(2 * n, np.uint8), np.zeros(2 * n, np.int32)
    for a, b, e in zip(bounds[1:], bounds[2:], [*bounds[3:], n]):
        f = fail[a:b]
        m = at[f + 1] - at[f]
        src = np.repeat(at[f] - np.cumsum(m) + m, m) + np.arange(m.sum())
        state, s, t = np.repeat(np.arange(a, b), m), sym[src], to[src]
        keep = child(state, s) == 0
        state, s, t = np.concatenate([parent[b - 1 : e - 1], state[keep]]), np.concatenate([char[b - 1 : e - 1], s[keep]]), np.concatenate([np.arange(b, e), t[keep]])
        order = np.argsort(state.astype(np.int64) * SIGMA + s)
        end = int(at[a]) + len(order)
        if end > len(sym):
            sym, to = np.resize(sym, 2 * end), np.resize(to, 2 * end)
        sym[at[a] : end], to[at[a] : end] = s[order], t[order]
        at[a + 1 : b + 1] = at[a] + np.cumsum(np.bincount(state - a, minlength=b - a))
    depth = np.repeat(np.arange(len(bounds) - 1, dtype=np.int32), np.diff(bounds))
    return {"first": first, "count": np.diff(at).astype(np.uint16), "sym": sym[: at[-1]].copy(), "to": to[: at[-1]].copy(), "depth": depth.astype(np.int16 if len(bounds) < 1 << 15 else np.int32)}


class Sparse:
    def __init__(self, first, count, sym, to, depth):
        self.n, self.first, self.sym, self.to, self.depth = len(count), first, sym, to, depth
        self.state = np.repeat(np.arange(self.n, dtype=np.int32), count)
        used = np.flatnonzero(np.bincount(sym, minlength=SIGMA))
        self.used, bit = used, np.zeros(SIGMA, np.int64)
        bit[used] = np.arange(len(used))
        self.bit, some = bit, np.flatnonzero(count)
        begin = (np.cumsum(count, dtype=np.int64) - count)[some]
        self.masks = []
        for j in range(max(1, -(-len(used) // 64))):
            own = np.where(bit[sym] // 64 == j, np.uint64(1) << (bit[sym] % 64).astype(np.uint64), np.uint64(0))
            m = np.zeros(self.n, np.uint64)
            if len(some):
                m[some] = np.bitwise_or.reduceat(own, begin)
            self.masks.append(m)
        # Cells whose target more than one state has: only these can be equal in two rows.
        twice = np.bincount(to, minlength=self.n)[to] > 1 if self.n else np.zeros(0, bool)
        self.alike = np.bincount(self.state[twice], minlength=self.n).astype(np.uint16)
        self.alike_at = (np.cumsum(self.alike, dtype=np.int64) - self.alike).astype(np.int32 if len(to) < 1 << 31 else np.int64)
        self.alike_cell = to[twice].astype(np.int64) * SIGMA + sym[twice]
        self.sharing = np.flatnonzero(self.alike)
        own = np.flatnonzero(self.alike[self.state])
        self.own = self.state[own], sym[own], to[own]

    def agree(self, u, v) -> np.ndarray:
        """Cells other than the start's that the rows of u and v share."""
        out, cu, cv = np.zeros(len(u), np.int64), self.alike[u], self.alike[v]
        for i in range(int(cu.max(initial=0))):
            a = np.flatnonzero((cu > i) & (cv > 0))
            x, y = self.alike_cell[self.alike_at[u[a]] + i], self.alike_at[v[a]]
            for j in range(int(cv[a].max(initial=0))):
                b = np.flatnonzero(cv[a] > j)
                out[a[b]] += x[b] == self.alike_cell[y[b] + j]
        return out

    def similarity(self, u, v) -> np.ndarray:
        w = SIGMA - sum(np.bitwise_count(m[u] | m[v]).astype(np.int64) for m in self.masks)
        both = np.flatnonzero((self.alike[u] > 0) & (self.alike[v] > 0))
        if len(both):
            w[both] += self.agree(u[both], v[both])
        return w

    def pieces(self, u, v):
        """Similarity of many pairs, a piece at a time."""
        return np.concatenate([np.zeros(0, np.int64), *(self.similarity(u[i : i + PIECE], v[i : i + PIECE]) for i in range(0, len(u), PIECE))])

    def to_start(self, u) -> np.ndarray:
        return SIGMA - sum(np.bitwise_count(m[u]).astype(np.int64) for m in self.masks)

    def column(self, c: int) -> np.ndarray:
        out = np.full(self.n, self.first[c], np.int32)
        own = self.sym == c
        out[self.state[own]] = self.to[own]
        return out

    def draws(self, i: int, k: int, seed: int, only: np.ndarray | None = None, lo: int = 0):
        """u, v of round i as ``kernels.proposals`` draws them, in pieces; only: the states u (ascending) that are asked for; lo: the least of them."""
        symbols, off = kernels.sample_symbols(SIGMA, k, range(i, i + 1), seed)[0], np.zeros(self.n, bool)
        asked = self.bit[np.intersect1d(symbols, self.used)]
        for j, m in enumerate(self.masks):
            if (asked // 64 == j).any():
                off |= (m & np.bitwise_or.reduce(np.uint64(1) << (asked[asked // 64 == j] % 64).astype(np.uint64))) != 0
        # Apart from the start's key: a state with a target that no other has stands alone in its bucket.
        apart, (state, sym, to) = self.sharing[off[self.sharing]], self.own
        if len(apart) > 1:
            cols = []
            for c in symbols:
                col, own = np.full(len(apart), self.first[c], np.int64), np.flatnonzero(sym == c)
                col[np.searchsorted(apart, state[own])] = to[own]
                cols.append(col)
            u, v = kernels.partners(kernels.xxhash64(*cols), seed, i, ids=apart)
            if only is not None or lo:
                x = u >= lo if only is None else np.isin(u, only)
                u, v = u[x], v[x]
            for p in range(0, len(u), PIECE):
                yield u[p : p + PIECE], v[p : p + PIECE]
        member = np.flatnonzero(~off).astype(np.int32)
        size = len(member)
        if size < 2:
            return
        ask = None if only is None else only[~off[only]]
        for p in range(int(np.searchsorted(member, lo)) if ask is None else 0, size if ask is None else len(ask), PIECE):
            if ask is None:
                pos = np.arange(p, min(p + PIECE, size))
                u = member[p : p + PIECE].astype(np.int64)
            else:
                u = ask[p : p + PIECE]
                pos = np.searchsorted(member, u)
            at = kernels.draw(size - 1, np.int64(seed), np.int64(i), u)
            at += pos
            at += 1
            np.subtract(at, size, out=at, where=at >= size)
            yield u, member.take(at).astype(np.int64)


# Forest


def forest(s: Sparse, key: np.ndarray, every: bool = False):
    """Of edges (u * n + v, distinct) those that stand in the maximum spanning forest of them and the star; every: all edges of that forest as u, v, w."""
    u, v = key // s.n, key % s.n
    nodes = kernels.distinct(np.concatenate([[0], u, v]).astype(np.int64))
    a = np.concatenate([np.zeros(len(nodes) - 1, np.int64), np.searchsorted(nodes, u)])
    b = np.concatenate([np.arange(1, len(nodes)), np.searchsorted(nodes, v)])
    w = np.concatenate([s.to_start(nodes[1:]), s.pieces(u, v)])
    kept = kernels.max_spanning_forest(len(nodes), a, b, w)
    if not every:
        return key[kept[kept >= len(nodes) - 1] - (len(nodes) - 1)]
    rest = np.ones(s.n, bool)
    rest[nodes] = False
    rest = np.flatnonzero(rest)
    return np.concatenate([nodes[a[kept]], np.zeros(len(rest), np.int64)]), np.concatenate([nodes[b[kept]], rest]), np.concatenate([w[kept], s.to_start(rest)])


def tree_edges(s: Sparse, rounds, k: int, seed: int, most: int = 1 << 22) -> np.ndarray:
    """Drawn edges of the rounds that stand in their forest with the star.

    Rows that share no cell besides the start's are no more alike than each is to the start, and
    the star's edges come first among equals: only states with a cell of more states are drawn for."""
    key, fresh, size, ask = np.zeros(0, np.int64), [], 0, np.flatnonzero(s.alike)
    for i in rounds:
        for u, v in s.draws(i, k, seed, ask):
            x = s.alike[v] > 0
            u, v = u[x], v[x]
            x = s.similarity(u, v) > np.minimum(s.to_start(u), s.to_start(v))
            fresh.append(np.minimum(u[x], v[x]) * s.n + np.maximum(u[x], v[x]))
            size += len(fresh[-1])
        if size > most:
            key, fresh, size = forest(s, kernels.distinct(np.concatenate([key, *fresh]))), [], 0
    return forest(s, kernels.distinct(np.concatenate([key, *fresh])))


def pruned(n: int, u: np.ndarray, v: np.ndarray):
    """The forest without the leaves of a node beyond its two least (what a search for centres can meet), and those leaves with their nodes."""
    degree = np.bincount(u, minlength=n) + np.bincount(v, minlength=n)
    a, b = np.flatnonzero((degree[u] == 1) & (degree[v] > 1)), np.flatnonzero((degree[v] == 1) & (degree[u] > 1))
    leaf, hub = np.concatenate([u[a], v[b]]), np.concatenate([v[a], u[b]])
    order = np.lexsort((leaf, hub))
    leaf, hub = leaf[order], hub[order]
    more = np.zeros(len(leaf), bool)
    more[2:] = hub[2:] == hub[:-2]
    leaf, hub = leaf[more], hub[more]
    gone = np.zeros(n, bool)
    gone[leaf] = True
    x = ~(gone[u] | gone[v])
    return u[x], v[x], leaf, hub


def centre(n: int, u: np.ndarray, v: np.ndarray) -> int:
    """The first of ``kernels.centres``, of a tree over all states."""
    if n == 1:
        return 0
    u, v, _, _ = pruned(n, u, v)
    nodes = kernels.distinct(np.concatenate([u, v]))
    return int(nodes[kernels.centres(len(nodes), np.searchsorted(nodes, u), np.searchsorted(nodes, v))[0]])


def orient(n: int, u: np.ndarray, v: np.ndarray) -> np.ndarray:
    """``kernels.orient``'s parents."""
    u, v, leaf, hub = pruned(n, u, v)
    out = np.full(n, -1, np.int64)
    out[leaf] = hub
    nodes = kernels.distinct(np.concatenate([u, v]))
    if len(nodes):
        parent = kernels.orient(len(nodes), np.searchsorted(nodes, u), np.searchsorted(nodes, v))[0]
        out[nodes] = np.where(parent >= 0, nodes[parent], -1)
    return out


# Matching delay


def depth_best(s: Sparse, rounds, k: int, seed: int, drop: int = 1) -> np.ndarray:
    """For each state its best offer as similarity and least partner in one number (0: none)."""
    best = np.zeros(s.n, np.int64)
    for i in rounds:
        for u, v in s.draws(i, k, seed):
            x = np.flatnonzero(s.depth[v] + drop <= s.depth[u])
            u, v = u[x], v[x]
            w = s.similarity(u, v)
            best[u] = np.maximum(best[u], np.where(w > 0, (w << 40) + ((1 << 40) - 1 - v), 0))
    return best


def best_default(best: np.ndarray) -> np.ndarray:
    return np.where(best > 0, (1 << 40) - 1 - (best & ((1 << 40) - 1)), -1)


# Distinct edges, and the edges of some states


def bounds(n: int, parts: int) -> np.ndarray:
    """Lesser ends at which the parts of the edges begin, of about as many edges each."""
    return np.floor(n * (1 - np.sqrt(1 - np.arange(parts) / parts))).astype(np.int64)


def packed(key: np.ndarray) -> bytes:
    """Ascending numbers by their gaps: three bytes each, and the rest where there is more."""
    gap = np.diff(key, prepend=0)
    wide = np.flatnonzero(gap >> 24)
    low = gap.astype("<u4").view(np.uint8).reshape(-1, 4)[:, :3]
    return np.array([len(key), len(wide)], np.int64).tobytes() + wide.tobytes() + (gap[wide] >> 24).tobytes() + low.tobytes()


def unpacked(data: bytes) -> np.ndarray:
    m, w = np.frombuffer(data, np.int64, 2)
    wide, high = np.frombuffer(data, np.int64, w, 16), np.frombuffer(data, np.int64, w, 16 + 8 * w)
    low = np.zeros((m, 4), np.uint8)
    low[:, :3] = np.frombuffer(data, np.uint8, 3 * m, 16 + 16 * w).reshape(-1, 3)
    gap = low.view("<u4").ravel().astype(np.int64)
    gap[wide] += high << 24
    return np.cumsum(gap, out=gap)


def listed(s: Sparse, rounds, k: int, seed: int, lo: int, hi: int, ask: np.ndarray | None = None):
    """Distinct drawn edges without the star's whose lesser end is in lo..hi-1, and the drawn edges of the states asked for, both ascending as u * n + v."""
    keys, own, mine = [], [], np.zeros(s.n, bool)
    if ask is not None:
        mine[ask] = True
    lo = max(lo, 1)
    for i in rounds:
        for u, v in s.draws(i, k, seed, lo=lo if ask is None else 0):
            if ask is not None:
                x = mine[u] | mine[v]
                own.append(np.minimum(u[x], v[x]) * s.n + np.maximum(u[x], v[x]))
            a = np.minimum(u, v)
            x = np.flatnonzero((a >= lo) & (a < hi))
            a = a[x]
            keys.append(a * s.n + (u[x] + v[x] - a))
    join = lambda x: kernels.distinct(np.concatenate([np.zeros(0, np.int64), *x]))
    return join(keys), join(own)


# Growth


class Missing(Exception):
    """States whose edges the growth asks for."""


def shallow_tree(s: Sparse, at: int, key: np.ndarray, known: np.ndarray, penalty: str = "pow2"):
    """``kernels.shallow_tree`` over the star and the drawn edges, of which those of the ``known`` states are given (u * n + v): parent, level, weight.

    Once the start is in, each state has its offer; a state offers more than that at most by the
    cells that it shares with others, less what its depth loses.  Where that can't be more, its
    edges aren't asked for."""
    n, pen = s.n, lambda d: kernels.penalised(d, penalty)
    u, v = key // n, key % n
    w = s.pieces(u, v)
    src, dst, wt = np.concatenate([u, v]), np.concatenate([v, u]), np.concatenate([w, w])
    order = np.lexsort((dst, src))
    src, dst, wt = src[order], dst[order], wt[order]
    have = np.zeros(n, bool)
    have[known] = True
    parent, level, weight = np.full(n, -1, np.int64), np.full(n, -1, np.int64), np.zeros(n, np.int64)
    #: Best offers that stand in the heap.  Once the start is in, a state without one has the start's.
    best: dict[int, int] = {}
    heap: list[tuple[int, int, int]] = []
    star, least = s.to_start(slice(None)), -(1 << 62)
    base, last, lacking = None, (least, 0, 0), []

    def offer(x: int, t: int, value: int):
        if value > best.get(t, least):
            best[t] = value
            heapq.heappush(heap, (-value, x, t))

    def enter(x: int):
        nonlocal base
        down = pen(int(level[x]) + 1)
        if x == 0:
            base = down
            for t in [t for t, value in best.items() if value < int(star[t]) - base]:
                del best[t]
            # States whose own offers may count are popped one by one, the others stand by.
            for t in np.flatnonzero((level < 0) & (s.alike > pen(int(level[0]) + 2) - base)).tolist():
                offer(0, t, int(star[t]) - base)
            return
        if base is not None and int(s.alike[x]) <= down - base:
            return
        if not have[x]:
            lacking.append(x)
            return
        a, b = np.searchsorted(src, [x, x + 1])
        if base is None:
            offer(x, 0, int(star[x]) - down)
        for t, value in zip(dst[a:b].tolist(), (wt[a:b] - down).tolist()):
            # Of states that have the start's offer alone those are in whose turn was before the last state popped.
            if t and level[t] < 0 and (base is None or t in best or value > int(star[t]) - base and (base - int(star[t]), 0, t) > last):
                offer(x, t, value)

    level[at] = 0
    enter(at)
    while heap and not lacking:
        val, x, t = heapq.heappop(heap)
        if level[t] >= 0 or base is not None and t not in best:
            continue
        if base is not None:
            last = max(last, (val, x, t))
        parent[t], level[t] = x, level[x] + 1
        weight[t] = -val + pen(int(level[t]))
        enter(t)
    if lacking:
        near = [t for _, x, t in heap if level[t] < 0 and not have[t] and (base is None or s.alike[t] > pen(int(level[x]) + 2) - base)]
        raise Missing(sorted({*lacking, *near}))
    rest = np.flatnonzero(level < 0)
    parent[rest], level[rest], weight[rest] = 0, level[0] + 1, star[rest]
    return parent, level, weight


def cut_tree(n: int, parent: np.ndarray, level: np.ndarray, L: int) -> tuple[np.ndarray, np.ndarray]:
    """``compress.cut_tree`` by fewest cuts."""
    gone = kernels.cut_fewest(parent, level, L)
    parent = parent.copy()
    parent[gone] = -1
    kept = np.flatnonzero(parent >= 0)
    return orient(n, np.minimum(kept, parent[kept]), np.maximum(kept, parent[kept])), gone


# Results


def measure(s: Sparse, default: np.ndarray) -> dict:
    """``kernels.measure`` and ``kernels.differing``, a column at a time."""
    u, level = np.flatnonzero(default >= 0), kernels.chain(default)
    same = sum(int(s.similarity(u[i : i + PIECE], default[u[i : i + PIECE]]).sum()) for i in range(0, len(u), PIECE))
    cells, deepest, wrong = s.n * SIGMA, int(level.max(initial=0)), 0
    delay, layers = deepest if len(s.used) < SIGMA else 0, [np.flatnonzero(level == d) for d in range(1, deepest + 1)]
    for c in s.used:
        col = s.column(c)
        back, hops = col.copy(), np.zeros(s.n if len(s.used) == SIGMA else 0, np.int32)
        for x in layers:
            given = col[x] == col[default[x]]
            back[x[given]] = back[default[x[given]]]
            if len(hops):
                hops[x] = np.where(given, hops[default[x]] + 1, 0)
        wrong += int((back != col).sum())
        delay = max(delay, int(hops.max(initial=0)))
    labelled = cells - same
    return {"n": s.n, "sigma": SIGMA, "t_in": cells, "t_out": labelled + len(u), "labelled": labelled, "defaults": len(u), "size_pct": 100.0 * (labelled + len(u)) / cells, "longest_chain": deepest, "longest_delay": delay, "different": wrong}
