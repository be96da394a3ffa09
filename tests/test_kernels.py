"""Array kernels: the worked example, brute force on small inputs, invariants of all eight algorithms."""

import itertools

import numpy as np
import pytest

from thinfsm import compress, kernels as K, rules as R
from thinfsm.plans.workloads import EXAMPLE_ROWS, EXAMPLE_RULE
from thinfsm.sources.ladder import random_table


def small(seed, n=6, sigma=4):
    return np.random.default_rng(seed).integers(0, 3, (n, sigma)).astype(np.int32) % n


def value_of_best_tree(rows, mult):
    n = len(rows)
    pairs = list(itertools.combinations(range(n), 2))
    w = {p: int(((rows[p[0]] == rows[p[1]]) * mult).sum()) for p in pairs}
    best = -1
    for t in itertools.combinations(pairs, n - 1):
        comp = list(range(n))
        ok = True
        for a, b in t:
            ca, cb = comp[a], comp[b]
            if ca == cb:
                ok = False
                break
            comp = [ca if c == cb else c for c in comp]
        if ok:
            best = max(best, sum(w[p] for p in t))
    return best


def test_worked_example_automaton():
    t, accept = R.determinise([(0, EXAMPLE_RULE)])
    assert t[:, [97, 98, 99, 100, 101]].tolist() == EXAMPLE_ROWS
    assert [i for i, a in enumerate(accept) if a] == [6, 7, 8]
    assert len(set(R.minimise(t, accept))) == 9


def test_worked_example_measures():
    rows, cls, mult = K.symbol_classes(np.array(EXAMPLE_ROWS, np.int32))
    w = np.concatenate([x[2] for x in K.dense_graph(rows, mult)])
    assert {k: int((w == k).sum()) for k in (5, 4, 3, 2)} == {5: 2, 4: 13, 3: 13, 2: 8}
    u, v, w = K.dense_tree(rows, mult)
    assert w.sum() == 33
    parent, level, _ = K.orient(9, u, v)
    m = K.measure(rows, mult, parent, level)
    assert (m["t_in"], m["labelled"], m["defaults"], m["t_out"]) == (45, 12, 8, 20)
    depth = K.bfs_depth(rows, 0)
    assert depth.tolist() == [0, 1, 1, 1, 2, 2, 2, 3, 3]
    assert K.measure(rows, mult, K.dense_depth(rows, mult, depth))["t_out"] == 20


@pytest.mark.parametrize("seed", range(8))
def test_dense_tree_is_the_best_tree(seed):
    rows, _, mult = K.symbol_classes(small(seed))
    u, v, w = K.dense_tree(rows, mult)
    assert w.sum() == value_of_best_tree(rows, mult)
    g = [np.concatenate(x) for x in zip(*K.dense_graph(rows, mult))]
    keep = K.max_spanning_forest(len(rows), *g)
    assert list(zip(u, v)) == list(zip(g[0][keep], g[1][keep]))


def random_tree(n, rng):
    parent = np.array([-1] + [int(rng.integers(0, i)) for i in range(1, n)])
    level = np.zeros(n, int)
    for i in range(1, n):
        level[i] = level[parent[i]] + 1
    return parent, level


def diameters_ok(parent, cut, D):
    n = len(parent)
    adj = [[] for _ in range(n)]
    for i, p in enumerate(parent):
        if p >= 0 and i not in cut:
            adj[i].append(p)
            adj[p].append(i)
    for s in range(n):
        dist, todo = {s: 0}, [s]
        for x in todo:
            for y in adj[x]:
                if y not in dist:
                    dist[y] = dist[x] + 1
                    todo.append(y)
        if max(dist.values()) > D:
            return False
    return True


@pytest.mark.parametrize("seed", range(25))
def test_cuts_against_brute_force(seed):
    rng = np.random.default_rng(seed)
    parent, level = random_tree(int(rng.integers(2, 9)), rng)
    if seed % 3 == 0:
        parent, level = np.arange(-1, 7), np.arange(8)
    weight = np.where(parent >= 0, rng.integers(0, 5, len(parent)), 0)
    nodes = [i for i in range(len(parent)) if parent[i] >= 0]
    for L in (1, 2):
        fits = [c for k in range(len(nodes) + 1) for c in itertools.combinations(nodes, k) if diameters_ok(parent, set(c), 2 * L)]
        few = K.cut_fewest(parent, level, L)
        assert diameters_ok(parent, set(few.tolist()), 2 * L) and len(few) == min(map(len, fits))
        light = K.cut_lightest(parent, level, weight, L)
        assert diameters_ok(parent, set(light.tolist()), 2 * L)
        assert weight[light].sum() == min(sum(weight[list(c)]) for c in fits)


@pytest.mark.parametrize("name", compress.ALGORITHMS)
@pytest.mark.parametrize("seed", range(3))
def test_algorithms_keep_language_and_bounds(name, seed):
    graph, variant = name.split("_")
    t = random_table(40, 12, seed)
    default, _ = compress.run(t, variant, graph, L=2, k=3, r=40)
    rows, _, mult = K.symbol_classes(t)
    level = K.chain(default)  # raises on a cycle
    m = K.measure(rows, mult, default, level)
    assert m["labelled"] + m["defaults"] == m["t_out"] and m["longest_delay"] <= m["longest_chain"]
    if variant in ("grow", "cut"):
        assert m["longest_chain"] <= 2
    # What the labelled rest and the defaults give back is the table.
    back = np.full(t.shape, -1)
    for u in np.argsort(level, kind="stable"):
        own = np.ones(t.shape[1], bool) if default[u] < 0 else t[u] != t[default[u]]
        back[u] = np.where(own, t[u], back[default[u]])
    assert (back == t).all()
    if variant == "depth":
        d = K.bfs_depth(t, 0)
        u = np.flatnonzero(default >= 0)
        assert (d[default[u]] < d[u]).all()


def test_sampled_against_dense():
    t = random_table(60, 16, 5)
    rows, cls, mult = K.symbol_classes(t)
    dense = K.dense_tree(rows, mult)[2].sum()
    values = []
    for r in (0, 8, 64, 512):
        u, v, w = K.sampled_graph(rows, cls, mult, 0, k=2, r=r)
        assert len(u) <= r * 60 + 59 and (u < v).all()
        keep = K.max_spanning_forest(60, u, v, w)
        assert len(keep) == 59  # the star connects
        values.append(int(w[keep].sum()))
    assert values == sorted(values) and values[-1] <= dense


def test_batched_forest_is_the_forest():
    rows, cls, mult = K.symbol_classes(random_table(50, 10, 2))
    u, v, w = K.sampled_graph(rows, cls, mult, 0, k=2, r=40)
    keep = K.max_spanning_forest(50, u, v, w)
    a, b, c = K.sampled_graph(rows, cls, mult, 0, k=2, r=40, forest=True, batch=7)
    assert set(zip(u[keep], v[keep])) == set(zip(a, b)) and w[keep].sum() == c.sum()


def plain_growth(n, w, start, penalty):
    """Growth by one best offer at a time (of a node's equal offers the first stands; of equal nodes the one of the least parent), over a table of weights."""
    level, parent, best = {start: 0}, {}, {}
    x = start
    while True:
        for t in range(n):
            if t not in level and (min(x, t), max(x, t)) in w:
                d = level[x] + 1
                v = w[min(x, t), max(x, t)] - {"pow2": 2**d, "none": 0, "linear": d}[penalty]
                if t not in best or v > best[t][0]:
                    best[t] = (v, -x)
        if not best:
            return parent, level
        t = max(best, key=lambda t: (*best[t], -t))
        parent[t] = -best.pop(t)[1]
        level[t] = level[parent[t]] + 1
        x = t


@pytest.mark.parametrize("penalty", ["pow2", "none", "linear"])
@pytest.mark.parametrize("seed", range(6))
def test_growth_against_brute_force(seed, penalty):
    t = random_table(30, 9, seed)
    rows, cls, mult = K.symbol_classes(t)
    for u, v, w in (K.sampled_graph(rows, cls, mult, 0, k=2, r=6), [np.concatenate(x) for x in zip(*K.dense_graph(rows, mult))]):
        parent, level, weight = K.shallow_tree(30, u, v, w, 3, penalty)
        table = dict(zip(zip(u.tolist(), v.tolist()), w.tolist()))
        want, at = plain_growth(30, table, 3, penalty)
        assert {i: p for i, p in enumerate(parent.tolist()) if p >= 0} == want and level.tolist() == [at[i] for i in range(30)]
        assert all(weight[i] == table[min(i, p), max(i, p)] for i, p in want.items())
    same = K.dense_shallow_tree(rows, mult, 3, penalty)
    assert all((a == b).all() for a, b in zip(same, (parent, level, weight)))


def test_early_stop_keeps_the_star_and_the_bound():
    rows, cls, mult = K.symbol_classes(random_table(50, 10, 2))
    every = K.sampled_graph(rows, cls, mult, 0, k=2, r=400, forest=True, batch=4)
    early = K.sampled_graph(rows, cls, mult, 0, k=2, r=400, forest=True, batch=4, patience=3)
    assert len(early[0]) == 49 and early[2].sum() <= every[2].sum()


@pytest.mark.parametrize("sampler", ["distinct", "replacement", "rotating", "minhash1", "minhashk"])
def test_samplers_collide_as_often_as_they_should(sampler):
    from math import comb

    sigma, same, k, r = 20, 14, 3, 4000
    t = np.stack([np.arange(sigma), np.where(np.arange(sigma) < same, np.arange(sigma), 99)]).astype(np.int32)
    rows, cls, _ = K.symbol_classes(t)
    symbols = K.sample_symbols(sigma, k, range(r), 3, "distinct" if sampler.startswith("min") else sampler)
    keys = [K.bucket_key(rows, cls, s, 3, i, sampler) for i, s in enumerate(symbols)]
    got = np.mean([a[0] == a[1] for a in keys])
    jac = same / (2 * sigma - same)
    want = {"distinct": comb(same, k) / comb(sigma, k), "replacement": (same / sigma) ** k, "rotating": comb(same, k) / comb(sigma, k), "minhash1": jac, "minhashk": jac**k}[sampler]
    assert abs(got - want) < 5 * np.sqrt(want * (1 - want) / r) + 0.01


@pytest.mark.parametrize("pairing", ["uniform", "ring"])
def test_partners_are_other_members_of_the_bucket(pairing):
    key = np.array([5, 5, 7, 5, 8, 7], np.int64)
    for r in range(20):
        u, v = K.partners(key, 1, r, pairing)
        assert set(u.tolist()) == {0, 1, 2, 3, 5} and (key[u] == key[v]).all() and (u != v).all()


def test_edge_cases():
    one = np.zeros((1, 4), np.int32)
    for name in compress.ALGORITHMS:
        g, v = name.split("_")
        default, _ = compress.run(one, v, g, k=1, r=2) if v != "grow" else (np.array([-1]), {})
        assert default.tolist() == [-1]
    with pytest.raises(ValueError):
        K.sample_symbols(3, 4, range(2), 1)
    t = np.zeros((5, 1), np.int32)  # all rows equal, one symbol
    default, _ = compress.run(t, "tree", "sampled", k=1, r=0)
    assert (default >= 0).sum() == 4
    default, _ = compress.run(random_table(12, 5, 1), "cut", "sampled", L=0, k=2, r=5)
    assert (default < 0).all()


def test_rules_subset():
    assert R.supported("a{2,3}[^x]|(?:b.)*c") is None
    for bad in ("a(?=b)", r"(a)\1", "^a", "a*?", "a)", "(a"):
        assert R.supported(bad) is not None
    import re

    for pattern in ("ab{2,3}c", "(ab|cd)+e", "x[0-9]{2}", "a.?b", r"\d\d-\w", "(a|b)*abb"):
        t, accept = R.determinise([(0, pattern)])
        rng = np.random.default_rng(1)
        for _ in range(200):
            s = bytes(rng.choice(list(b"abcdex0123-"), rng.integers(0, 9)).tolist())
            state, hit = 0, bool(accept[0])
            for c in s:
                state = t[state][c]
                hit |= bool(accept[state])
            assert hit == bool(re.search(pattern.encode(), s)), (pattern, s)


def test_matcher_counts_hops_and_ends():
    from thinfsm.match import Matcher

    words = [b"he", b"she", b"his", b"hers"]
    t, accept, depth = R.dictionary(words)
    default, _ = compress.run(t, "depth", "dense", depth=depth)
    for resolved in (0, 3, 99):  # the same whatever is resolved beforehand
        m = Matcher(t, np.array([len(a) for a in accept]), default, resolved)
        got = m.run([b"ushers", b"", b"xyz"])
        rng = np.random.default_rng(4)
        texts = [bytes(rng.choice(list(b"hisers"), rng.integers(0, 90)).tolist()) for _ in range(200)]
        runs = m.run(texts)  # in step, then one by one
        for i, x in enumerate(texts):
            state, hops, found = 0, [], 0
            for c in x:
                h, at = 0, state
                while default[at] >= 0 and t[at][c] == t[default[at]][c]:
                    h, at = h + 1, default[at]
                state = t[state][c]
                hops.append(h)
                found += len(accept[state])
            assert (runs["hops"][i], runs["max_hops"][i], runs["matches"][i], runs["end_state"][i]) == (sum(hops), max(hops, default=0), found, state)
    assert Matcher(t, np.array([len(a) for a in accept]), default, 0).nbytes < t.nbytes
    got = m.run([b"ushers", b"", b"xyz"])
    assert got["matches"].tolist() == [3, 0, 0] and (got["hops"] <= got["length"]).all()
    a = m.run([b"ush"])
    b = m.run([b"ers"], a["end_state"])
    assert b["end_state"][0] == got["end_state"][0] and a["hops"][0] + b["hops"][0] == got["hops"][0]
