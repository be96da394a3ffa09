"""Array kernels for one automaton that fits a task.

An automaton is a matrix ``rows`` (states x symbol classes) of target states with ``mult``, the
number of symbols in each class.  All choices are keyed hashes of (seed, round, id), the same
64-bit hash that Spark's ``xxhash64`` computes on bigints, so the relational tier makes them
alike.  Edges follow one strict order: greater similarity, then lesser (u, v); trees are thus
unique.
"""

from __future__ import annotations

import heapq

import numpy as np

U = np.uint64
_P1, _P2, _P3, _P4, _P5 = (U(x) for x in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))  # fixed values of XXH64


def _rotl(x, r):
    return (x << U(r)) | (x >> U(64 - r))


def xxhash64(*cols) -> np.ndarray:
    """Spark's xxhash64 of bigint columns, as int64."""
    h = np.array([42], np.uint64)
    for c in cols:
        v = np.atleast_1d(np.asarray(c, np.int64)).view(np.uint64)
        with np.errstate(over="ignore"):
            x = h + _P5 + U(8)
            x = x ^ (_rotl(v * _P2, 31) * _P1)
            x = _rotl(x, 27) * _P1 + _P4
            x = (x ^ (x >> U(33))) * _P2
            x = (x ^ (x >> U(29))) * _P3
            h = x ^ (x >> U(32))
    return h.view(np.int64)


def draw(most, *cols) -> np.ndarray:
    """Numbers in 0..most-1 (arrays allowed), by hash."""
    return np.mod(xxhash64(*cols), most)


def symbol_classes(table: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct columns of a full table, class of each symbol, multiplicities."""
    _, first, inverse = np.unique(table.T, axis=0, return_index=True, return_inverse=True)
    order = np.argsort(first)
    place = np.empty_like(order)
    place[order] = np.arange(len(order))
    cls = place[inverse.ravel()]
    return table[:, first[order]], cls, np.bincount(cls)


def shared(a: np.ndarray, b: np.ndarray, mult: np.ndarray) -> np.ndarray:
    """Symbols on which rows a and b agree, by one product; single precision holds every such number."""
    return ((a == b).astype(np.float32) @ mult.astype(np.float32)).astype(np.int32)


def similarity(rows: np.ndarray, mult: np.ndarray, u, v, chunk: int = 1 << 13) -> np.ndarray:
    u, v = np.asarray(u), np.asarray(v)
    out = np.empty(len(u), np.int32)
    for i in range(0, len(u), chunk):
        out[i : i + chunk] = shared(rows[u[i : i + chunk]], rows[v[i : i + chunk]], mult)
    return out


def one_to_all(rows: np.ndarray, mult: np.ndarray, u: int) -> np.ndarray:
    return shared(rows, rows[u], mult)


def edge_order(w: np.ndarray, u: np.ndarray, v: np.ndarray) -> np.ndarray:
    """Indices from the best edge to the worst; u < v.  Edges that come in order of (u, v) are sorted by weight alone."""
    du = np.diff(u)
    if not ((du > 0) | (du == 0) & (np.diff(v) >= 0)).all():
        return np.lexsort((v, u, -w))
    small = w.max(initial=0) < 1 << 15 and w.min(initial=0) > -(1 << 15)
    return np.argsort((-w).astype(np.int16) if small else -w, kind="stable")


def distinct(x: np.ndarray) -> np.ndarray:
    """Sorted distinct values (by sorting: the hash table of np.unique is far slower on long arrays)."""
    x = np.sort(x)
    return x[np.concatenate([[True], x[1:] != x[:-1]])] if len(x) else x


# Sampled candidates


def sample_symbols(sigma: int, k: int, rounds: range, seed: int, sampler: str = "distinct") -> np.ndarray:
    """rounds x k symbols.  distinct: k different ones a round; replacement: k draws; rotating: shuffled alphabets consumed k by k."""
    if k > sigma and sampler != "replacement":
        raise ValueError(f"{k} distinct symbols of {sigma}")
    r = np.array(rounds, np.int64)
    if sampler == "replacement":
        return draw(sigma, np.int64(seed), np.repeat(r, k), np.tile(np.arange(k), len(r)) + sigma).reshape(len(r), k)
    if sampler == "distinct":
        h = xxhash64(np.int64(seed), np.repeat(r, sigma), np.tile(np.arange(sigma), len(r))).reshape(len(r), sigma)
        return np.argsort(h, axis=1, kind="stable")[:, :k]
    if sampler == "rotating":
        at = r[:, None] * k + np.arange(k)
        lap, place = at // sigma, at % sigma
        laps = {x: np.argsort(xxhash64(np.int64(seed), np.full(sigma, x), np.arange(sigma)), kind="stable") for x in np.unique(lap)}
        return np.array([[laps[a][b] for a, b in zip(x, y)] for x, y in zip(lap, place)])
    raise ValueError(sampler)


def bucket_key(rows: np.ndarray, cls: np.ndarray, symbols: np.ndarray, seed: int, round_: int, sampler: str) -> np.ndarray:
    """Hash of the targets on the sampled symbols; for minhash of the least permuted (symbol, target) pairs."""
    if sampler.startswith("minhash"):
        n, sigma = len(rows), len(cls)
        pair = rows[:, cls].astype(np.int64) + (np.arange(sigma, dtype=np.int64) << 40)
        k = 1 if sampler == "minhash1" else len(symbols)
        mins = [xxhash64(np.int64(seed), np.int64(round_), np.int64(j), pair.ravel()).reshape(n, sigma).min(1) for j in range(k)]
        return xxhash64(*mins)
    return xxhash64(*(rows[:, cls[s]] for s in symbols))


def partners(key: np.ndarray, seed: int, round_: int, pairing: str = "uniform", ids: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Every state that shares its bucket, and the bucket-mate it draws: never itself, each other equally likely.  ids: the states (ascending) if not all."""
    order = np.argsort(key, kind="stable")
    if pairing == "ring":
        order = order[np.lexsort((order, xxhash64(np.int64(seed), np.int64(round_), order), key[order]))]
    s = key[order]
    order = order if ids is None else ids[order]
    cut = np.concatenate([[0], np.flatnonzero(np.diff(s)) + 1, [len(s)]])
    size = np.repeat(np.diff(cut), np.diff(cut))
    start = np.repeat(cut[:-1], np.diff(cut))
    some = size > 1
    u, size, start, pos = order[some], size[some], start[some], (np.arange(len(s)) - np.repeat(cut[:-1], np.diff(cut)))[some]
    step = np.zeros(len(u), np.int64) if pairing == "ring" else draw(np.maximum(size - 1, 1), np.int64(seed), np.int64(round_), u)
    return u, order[start + (pos + 1 + step) % size]


def proposals(rows, cls, sigma, *, k, r, seed, sampler="distinct", pairing="uniform", first_round=0):
    """Directed candidate pairs (u, v) of each round."""
    rounds = range(first_round, first_round + r)
    symbols = sample_symbols(sigma, k, rounds, seed, "distinct" if sampler.startswith("minhash") else sampler) if r else np.zeros((0, k), int)
    for i, x in zip(rounds, symbols):
        yield partners(bucket_key(rows, cls, x, seed, i, sampler), seed, i, pairing)


#: Proposals gathered before a forest is taken.
GATHERED = 1 << 22


class EdgeSet:
    """Distinct undirected edges, gathered round by round; sorted anew only when the fresh ones outnumber the rest."""

    def __init__(self, n: int):
        self.n, self.kept, self.fresh, self.size = n, np.zeros(0, np.int64), [], 0

    def add(self, u: np.ndarray, v: np.ndarray) -> None:
        self.fresh.append(np.minimum(u, v).astype(np.int64) * self.n + np.maximum(u, v))
        self.size += len(u)
        if self.size > max(1 << 21, len(self.kept)):
            self.merge()

    def merge(self) -> None:
        self.kept, self.fresh, self.size = distinct(np.concatenate([self.kept, *self.fresh])), [], 0

    def edges(self) -> tuple[np.ndarray, np.ndarray]:
        self.merge()
        u = self.kept // self.n
        return u, self.kept - u * self.n


def unique_edges(u: np.ndarray, v: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    e = EdgeSet(n)
    e.add(u, v)
    return e.edges()


def star(n: int, start: int) -> tuple[np.ndarray, np.ndarray]:
    v = np.delete(np.arange(n), start)
    return np.minimum(v, start), np.maximum(v, start)


def sampled_graph(rows, cls, mult, start, *, k=8, r=512, seed=42, sampler="distinct", pairing="uniform", with_star=True, forest=False, batch=None, patience=0, eps=0.0):
    """Edges u < v with weights.

    forest: keep only the maximum spanning forest between batches of rounds (the same tree in
    the end; a batch has GATHERED proposals if its size isn't given).  patience (with forest): stop after so many batches in a row that raise the
    forest's value by a share of ``eps`` at most; 0 runs all rounds."""
    n, all_ = len(rows), EdgeSet(len(rows))
    batch = batch or max(8, GATHERED // max(n, 1))
    if with_star:
        all_.add(*star(n, start))
    value, idle = -1, 0
    for b in range(0, max(r, 1), batch):
        for x, y in proposals(rows, cls, len(cls), k=k, r=min(batch, r - b), seed=seed, sampler=sampler, pairing=pairing, first_round=b) if r else ():
            all_.add(x, y)
        if forest:
            eu, ev = all_.edges()
            w = similarity(rows, mult, eu, ev)
            kept = max_spanning_forest(n, eu, ev, w)
            all_ = EdgeSet(n)
            all_.add(eu[kept], ev[kept])
            now = int(w[kept].sum())
            idle = idle + 1 if value >= 0 and now - value <= eps * max(value, 1) else 0
            value = now
            if patience and idle >= patience:
                break
    eu, ev = all_.edges()
    return eu, ev, similarity(rows, mult, eu, ev)


def dense_graph(rows, mult, block: int = 512):
    """All pairs u < v with weights, block by block."""
    n = len(rows)
    for i in range(0, n, block):
        for j in range(i, n, block):
            s = np.zeros((min(block, n - i), min(block, n - j)), np.int32)
            for c in range(rows.shape[1]):
                s += mult[c] * (rows[i : i + block, c][:, None] == rows[j : j + block, c][None, :])
            a, b = np.nonzero((np.arange(i, i + s.shape[0])[:, None] < np.arange(j, j + s.shape[1])[None, :]))
            yield a + i, b + j, s[a, b]


# Spanning trees


def max_spanning_forest(n: int, u: np.ndarray, v: np.ndarray, w: np.ndarray) -> np.ndarray:
    """Indices of the edges of the maximum spanning forest, by rounds in which every component takes its best edge."""
    order = edge_order(w, u, v)
    rank = np.empty(len(order), np.int64)
    rank[order] = np.arange(len(order))
    comp, chosen, alive = np.arange(n), [], np.arange(len(u))
    while len(alive):
        a, b = comp[u[alive]], comp[v[alive]]
        keep = a != b
        alive, a, b = alive[keep], a[keep], b[keep]
        if not len(alive):
            break
        best = np.full(n, len(u), np.int64)
        np.minimum.at(best, a, rank[alive])
        np.minimum.at(best, b, rank[alive])
        pick = distinct(order[best[best < len(u)]])
        chosen.append(pick)
        parent = np.arange(n)
        # Each component points over its best edge; of the two-cycles the lesser end is the root.
        own = np.flatnonzero(best < len(u))
        e = order[best[own]]
        ca, cb = comp[u[e]], comp[v[e]]
        parent[own] = np.where(ca == own, cb, ca)
        two = parent[parent] == np.arange(n)
        parent = np.where(two, np.minimum(parent, np.arange(n)), parent)
        while True:
            up = parent[parent]
            if np.array_equal(up, parent):
                break
            parent = up
        comp = parent[comp]
    return np.sort(np.concatenate(chosen)) if chosen else np.zeros(0, np.int64)


def dense_tree(rows, mult, start: int = 0):
    """The maximum spanning tree over all pairs, adding the best crossing edge at a time; O(n) memory."""
    n = len(rows)
    inside = np.zeros(n, bool)
    best_w, best_u = np.full(n, -1, np.int64), np.full(n, n, np.int64)
    ids = np.arange(n)
    out = []
    x = start
    inside[x] = True
    for _ in range(n - 1):
        w = one_to_all(rows, mult, x)
        lo, hi = np.minimum(x, ids), np.maximum(x, ids)
        blo, bhi = np.minimum(best_u, ids), np.maximum(best_u, ids)
        better = (w > best_w) | (w == best_w) & ((lo < blo) | (lo == blo) & (hi < bhi))
        best_w, best_u = np.where(better, w, best_w), np.where(better, x, best_u)
        top = np.where(inside, -1, best_w)
        tie = np.flatnonzero(top == top.max())
        tie = tie[~inside[tie]]
        x = int(tie[np.lexsort((np.maximum(best_u[tie], tie), np.minimum(best_u[tie], tie)))[0]])
        out.append((min(x, best_u[x]), max(x, best_u[x]), best_w[x]))
        inside[x] = True
    e = np.array(sorted(out), np.int64).reshape(-1, 3)
    return e[:, 0], e[:, 1], e[:, 2]


def neighbours(n, u, v):
    src, dst = np.concatenate([u, v]), np.concatenate([v, u])
    order = np.argsort(src, kind="stable")
    at = np.concatenate([[0], np.cumsum(np.bincount(src, minlength=n))])
    return at, dst[order], order % max(len(u), 1)


def sweep(n, at, dst, roots) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distance, parent and root of every node that the roots reach in a forest, level by level."""
    dist, parent, root = np.full(n, -1, np.int64), np.full(n, -1, np.int64), np.full(n, -1, np.int64)
    front = np.asarray(roots)
    dist[front], root[front], d = 0, front, 0
    while len(front):
        count = at[front + 1] - at[front]
        src = np.repeat(front, count)
        nxt = dst[np.repeat(at[front], count) + np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)]
        new = dist[nxt] < 0
        nxt, src, d = nxt[new], src[new], d + 1
        dist[nxt], parent[nxt], root[nxt] = d, src, root[src]
        front = nxt
    return dist, parent, root


def centres(n, u, v) -> np.ndarray:
    """A centre of every tree of the forest (node of least eccentricity, the lesser id of two)."""
    at, dst, _ = neighbours(n, u, v)
    # A root for each tree: the least node of its component.
    comp = np.arange(n)
    while True:
        m = comp.copy()
        np.minimum.at(m, u, comp[v])
        np.minimum.at(m, v, comp[u])
        m = m[m]
        if np.array_equal(m, comp):
            break
        comp = m
    first = distinct(comp)

    def farthest(dist, root):
        order = np.lexsort((np.arange(n), -dist, root))
        return order[np.concatenate([[True], np.diff(root[order]) != 0])]

    dist, _, root = sweep(n, at, dst, first)
    a = farthest(dist, root)
    da, pa, ra = sweep(n, at, dst, a)
    b = farthest(da, ra)
    out = []
    for x in b:
        length, half = int(da[x]), int(da[x]) // 2
        for _ in range(half):
            x = pa[x]
        out.append(min(x, pa[x]) if length % 2 else x)
    return np.array(sorted(out), np.int64)


def orient(n, u, v) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Parents towards a centre of each tree (-1 at it), levels, roots."""
    at, dst, _ = neighbours(n, u, v)
    dist, parent, root = sweep(n, at, dst, centres(n, u, v))
    return parent, dist, root


# Bounded longest delay


DEEPEST = 40


def penalised(depth: int, kind: str) -> int:
    """What an offer to a node at this depth loses.  Beyond DEEPEST every loss outweighs any similarity."""
    return {"pow2": 1 << min(depth, DEEPEST), "none": 0, "linear": depth}[kind]


def shallow_tree(n, u, v, w, start: int, penalty: str = "pow2") -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Tree grown from ``start`` by the best offer similarity - penalty(depth of the receiving end): parent, level, weight."""
    at, dst, eid = neighbours(n, u, v)
    parent, level, weight = np.full(n, -1, np.int64), np.full(n, -1, np.int64), np.zeros(n, np.int64)
    best = np.full(n, np.iinfo(np.int64).min)
    heap: list[tuple[int, int, int]] = []

    def enter(x: int):
        s = slice(at[x], at[x + 1])
        to, wt = dst[s], w[eid[s]]
        value = wt - penalised(int(level[x]) + 1, penalty)
        new = (level[to] < 0) & (value > best[to])
        for t, val in zip(to[new].tolist(), value[new].tolist()):
            best[t] = val
            heapq.heappush(heap, (-val, x, t))

    level[start] = 0
    enter(start)
    while heap:
        val, x, t = heapq.heappop(heap)
        if level[t] >= 0:
            continue
        parent[t], level[t] = x, level[x] + 1
        weight[t] = -val + penalised(int(level[t]), penalty)
        enter(t)
    return parent, level, weight


def dense_shallow_tree(rows, mult, start: int, penalty: str = "pow2"):
    """The same over all pairs, without a stored graph."""
    n = len(rows)
    parent, level, weight = np.full(n, -1, np.int64), np.full(n, -1, np.int64), np.zeros(n, np.int64)
    best, via, wt = np.full(n, np.iinfo(np.int64).min), np.full(n, n, np.int64), np.zeros(n, np.int64)
    x, level[start] = start, 0
    for _ in range(n - 1):
        s = one_to_all(rows, mult, x).astype(np.int64)
        value = s - penalised(int(level[x]) + 1, penalty)
        better = (level < 0) & (value > best)
        best, via, wt = np.where(better, value, best), np.where(better, x, via), np.where(better, s, wt)
        open_ = np.flatnonzero(level < 0)
        top = open_[best[open_] == best[open_].max()]
        x = int(top[np.lexsort((top, via[top]))[0]])
        parent[x], level[x], weight[x] = via[x], level[via[x]] + 1, wt[x]
    return parent, level, weight


def cut_fewest(parent: np.ndarray, level: np.ndarray, L: int) -> np.ndarray:
    """Nodes whose edge to the parent is cut: fewest cuts so that every piece has diameter 2L at most."""
    n = len(parent)
    height, cut = np.zeros(n, np.int64), np.zeros(n, bool)
    for d in range(int(level.max(initial=0)), 0, -1):
        x = np.flatnonzero(level == d)
        offer = height[x] + 1
        p = parent[x]
        low, high = np.zeros(n, np.int64), np.full(n, np.iinfo(np.int64).max)
        small = offer <= L
        np.maximum.at(low, p[small], offer[small])
        # Of the offers above L one may stay, the least (ties: least node), if it fits beside the tallest other.
        big = x[~small]
        order = np.lexsort((big, offer[~small], parent[big]))
        first = big[order][np.concatenate([[True], np.diff(parent[big][order]) != 0])] if len(big) else big
        np.minimum.at(high, p[~small], offer[~small])
        stays = first[height[first] + 1 + low[parent[first]] <= 2 * L]
        cut[big] = True
        cut[stays] = False
        height = np.maximum(height, low)
        height[parent[stays]] = np.maximum(height[parent[stays]], height[stays] + 1)
    return np.flatnonzero(cut)


def cut_lightest(parent: np.ndarray, level: np.ndarray, weight: np.ndarray, L: int) -> np.ndarray:
    """Cuts of least total similarity for the same bound."""
    n, D = len(parent), 2 * L
    kids: list[list[int]] = [[] for _ in range(n)]
    for x in np.flatnonzero(parent >= 0).tolist():
        kids[parent[x]].append(x)
    cost = np.zeros((n, D + 1), np.int64)
    pick: dict[tuple[int, int], tuple[int, int]] = {}  # (node, height) -> height used, child that reaches it
    order = np.argsort(-level, kind="stable")

    def kept(c: int, h: int):
        return cost[c, h - 1] if h >= 1 else None

    def cheaper(c: int, h: int) -> int:
        k, off = kept(c, h), int(weight[c] + cost[c, D])
        return off if k is None or off < k else int(k)

    for x in order.tolist():
        for h in range(D + 1):
            lim = min(h, D - h)
            base = [cheaper(c, lim) for c in kids[x]]
            gain, who = 0, -1
            for c, b in zip(kids[x], base):
                g = b - cheaper(c, h)
                if g > gain:
                    gain, who = g, c
            cost[x, h] = sum(base) - gain
            pick[x, h] = (h, who)
            if h and cost[x, h - 1] <= cost[x, h]:
                cost[x, h], pick[x, h] = cost[x, h - 1], pick[x, h - 1]
    cut, todo = [], [(int(r), D) for r in np.flatnonzero(parent < 0)]
    while todo:
        x, h = todo.pop()
        h, who = pick[x, h]
        for c in kids[x]:
            lim = h if c == who else min(h, D - h)
            k, off = kept(c, lim), weight[c] + cost[c, D]
            if k is None or off < k:
                cut.append(c)
                todo.append((c, D))
            else:
                todo.append((c, lim - 1))
    return np.array(sorted(cut), np.int64)


def grow_forest(n, u, v, w, L: int, max_states: int = 5000) -> np.ndarray:
    """Kruskal with a diameter bound 2L; of equal weights the least rise of a diameter.  Rises are re-scored when taken (lazy mode).  Quadratic by nature."""
    if n > max_states:
        raise ValueError(f"bounded merging is quadratic: {n} states, at most {max_states}")
    D = 2 * L
    comp, members, diam = list(range(n)), [[i] for i in range(n)], [0] * n
    ecc, adj, chosen = [0] * n, [[] for _ in range(n)], []
    order = edge_order(w, u, v)
    bounds = np.concatenate([[0], np.flatnonzero(np.diff(w[order])) + 1, [len(order)]]) if len(order) else np.zeros(1, int)

    def rise(a, b):
        ca, cb = comp[a], comp[b]
        new = max(diam[ca], diam[cb], ecc[a] + 1 + ecc[b])
        return new - max(diam[ca], diam[cb]), new

    def refresh(nodes):
        """Eccentricities of a tree from the distances to the two ends of a longest path."""

        def far(s):
            dist, todo = {s: 0}, [s]
            for x in todo:
                for y in adj[x]:
                    if y not in dist:
                        dist[y] = dist[x] + 1
                        todo.append(y)
            return dist, todo[-1]

        _, a = far(nodes[0])
        da, b = far(a)
        db, _ = far(b)
        for x in nodes:
            ecc[x] = max(da[x], db[x])

    for i, j in zip(bounds[:-1], bounds[1:]):
        heap = []
        for e in order[i:j].tolist():
            a, b = int(u[e]), int(v[e])
            if comp[a] != comp[b]:
                up, new = rise(a, b)
                if new <= D:
                    heap.append((up, a, b, e))
        heapq.heapify(heap)
        while heap:
            up, a, b, e = heapq.heappop(heap)
            if comp[a] == comp[b]:
                continue
            now, new = rise(a, b)
            if new > D:
                continue
            if now > up:
                heapq.heappush(heap, (now, a, b, e))
                continue
            ca, cb = comp[a], comp[b]
            if len(members[ca]) < len(members[cb]):
                ca, cb = cb, ca
            for x in members[cb]:
                comp[x] = ca
            members[ca] += members[cb]
            members[cb] = []
            diam[ca] = new
            adj[a].append(b)
            adj[b].append(a)
            chosen.append(e)
            refresh(members[ca])
    return np.array(sorted(chosen), np.int64)


# Bounded matching delay


def bfs_depth(rows: np.ndarray, start: int) -> np.ndarray:
    depth = np.full(len(rows), -1, np.int64)
    front, d = np.array([start]), 0
    while len(front):
        depth[front] = d
        nxt = distinct(rows[front].ravel())
        front, d = nxt[depth[nxt] < 0], d + 1
    return depth


def dense_depth(rows, mult, depth, drop: int = 1) -> np.ndarray:
    """For each state the most similar one that is ``drop`` levels above at least (ties: least id), -1 without."""
    n = len(rows)
    out = np.full(n, -1, np.int64)
    ids = np.arange(n)
    for u in range(n):
        s = np.where(depth <= depth[u] - drop, one_to_all(rows, mult, u), -1)
        if s.max() >= 0:
            out[u] = ids[s == s.max()][0]
    return out


def sampled_depth(rows, cls, mult, depth, *, k=8, r=512, seed=42, sampler="distinct", pairing="uniform", drop=1, fallback=None) -> np.ndarray:
    """The best of the proposed states that are high enough (ties: the least id), -1 without."""
    n = len(rows)
    best, sim = np.full(n, -1, np.int64), np.zeros(n, np.int64)
    offers = proposals(rows, cls, len(cls), k=k, r=r, seed=seed, sampler=sampler, pairing=pairing)
    if fallback is not None:
        offers = [(np.delete(np.arange(n), fallback), np.full(n - 1, fallback)), *offers]
    for u, v in offers:
        ok = depth[v] <= depth[u] - drop
        u, v = u[ok], v[ok]
        s = similarity(rows, mult, u, v)
        win = (s > sim[u]) | (s == sim[u]) & (s > 0) & (v < best[u])
        best[u[win]], sim[u[win]] = v[win], s[win]
    return best


# Results


def measure(rows, mult, default: np.ndarray, levels: np.ndarray | None = None) -> dict:
    """Transitions of the delayed automaton and its delays."""
    n, sigma = len(rows), int(mult.sum())
    has = default >= 0
    u = np.flatnonzero(has)
    same = similarity(rows, mult, u, default[u])
    labelled = n * sigma - int(same.sum())
    if levels is None:
        levels = chain(default)
    return {"n": n, "sigma": sigma, "t_in": n * sigma, "t_out": labelled + len(u), "labelled": labelled, "defaults": len(u), "size_pct": 100.0 * (labelled + len(u)) / (n * sigma), "longest_chain": int(levels.max(initial=0)), "longest_delay": longest_delay(rows, default, levels)}


def chain(default: np.ndarray) -> np.ndarray:
    """Defaults from each state to its root; raises on a cycle."""
    n = len(default)
    level, at = np.zeros(n, np.int64), default.copy()
    for _ in range(n + 1):
        on = at >= 0
        if not on.any():
            return level
        level[on] += 1
        at[on] = default[at[on]]
    raise ValueError("a cycle of defaults")


def differing(table: np.ndarray, default: np.ndarray) -> int:
    """Cells that the delayed automaton, run from its labelled transitions and defaults alone, gives back wrongly or not at all."""
    level = chain(default)
    has = default >= 0
    labelled = np.ones(table.shape, bool)
    labelled[has] = table[has] != table[default[has]]
    back = np.where(labelled, table, -1)
    for d in range(1, int(level.max(initial=0)) + 1):
        x = np.flatnonzero(level == d)
        back[x] = np.where(labelled[x], back[x], back[default[x]])
    return int((back != table).sum())


def longest_delay(rows: np.ndarray, default: np.ndarray, levels: np.ndarray) -> int:
    """Most defaults that any state follows on any symbol."""
    hops = np.zeros(rows.shape, np.int64)
    for d in range(1, int(levels.max(initial=0)) + 1):
        x = np.flatnonzero(levels == d)
        hops[x] = np.where(rows[x] == rows[default[x]], hops[default[x]] + 1, 0)
    return int(hops.max(initial=0))
