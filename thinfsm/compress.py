"""The eight compression algorithms, {dense|sampled}_{tree|grow|cut|depth}, over many automata.

Automata are grouped by id and each is compressed by array kernels in one task (``exec
'local'``); an automaton whose rows exceed ``task_bytes`` goes to the relational tier
(``giant``), which draws the same symbols and partners and gives the same defaults.  All-pairs
graphs and bounded merging are quadratic by nature and exist in the first tier only.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import giant, kernels
from .model import Automaton, DelayedAutomaton, to_wide
from .scratch import store

ALGORITHMS = tuple(f"{g}_{v}" for v in ("tree", "grow", "cut", "depth") for g in ("dense", "sampled"))
DENSE_MOST = 20_000
FOREST = "automaton_id string, state long, default long, w int, level int, root long"
MEASURED = "automaton_id string, algorithm string, n long, sigma long, t_in long, t_out long, labelled long, defaults long, size_pct double, longest_delay long, longest_chain long, edges long, tree_value long, cuts long, cut_similarity long, different long, seconds double, status string"


def run(table: np.ndarray, variant: str = "tree", graph: str = "sampled", *, start: int = 0, depth: np.ndarray | None = None, L: int = 2, k: int = 8, r: int = 512, seed: int = 42, sampler: str = "distinct", pairing: str = "uniform", star: bool = True, cut: str = "fewest", min_depth_drop: int = 1, min_gain: int = 0, root: str = "centre", penalty: str = "pow2", fallback_start: bool = False, batch: int | None = None, patience: int = 0, eps: float = 0.0, grow_most: int = 5000) -> tuple[np.ndarray, dict]:
    """Defaults (-1: none) of an automaton given as a full table, and what was measured on the way."""
    rows, cls, mult = kernels.symbol_classes(table)
    n, info = len(rows), {"edges": 0, "tree_value": 0, "cuts": 0, "cut_similarity": 0}
    sample = {"k": k, "r": r, "seed": seed, "sampler": sampler, "pairing": pairing}
    if graph not in ("dense", "sampled") or variant not in ("tree", "grow", "cut", "depth"):
        raise ValueError(f"{graph}_{variant}")
    if graph == "dense" and n > DENSE_MOST:
        raise ValueError(f"dense graph of {n} states, at most {DENSE_MOST}")
    if variant == "grow" and n > grow_most:
        raise ValueError(f"bounded merging is quadratic: {n} states, at most {grow_most}")
    if variant == "depth":
        d = kernels.bfs_depth(rows, start) if depth is None else depth
        if graph == "dense":
            default = kernels.dense_depth(rows, mult, d, min_depth_drop)
        else:
            default = kernels.sampled_depth(rows, cls, mult, d, drop=min_depth_drop, fallback=start if fallback_start else None, **sample)
        return weak_off(rows, mult, default, min_gain), info
    if graph == "dense":
        info["edges"] = n * (n - 1) // 2
        u, v, w = kernels.dense_tree(rows, mult) if variant != "grow" else (np.concatenate(x) for x in zip(*kernels.dense_graph(rows, mult)))
    else:
        u, v, w = kernels.sampled_graph(rows, cls, mult, start, with_star=star, forest=variant == "tree", batch=batch, patience=patience if variant == "tree" else 0, eps=eps, **sample)
        info["edges"] = len(u)
        if variant == "tree":
            info["edges"] = None  # only the forest is kept between batches
    if variant == "grow":
        keep = kernels.grow_forest(n, u, v, w, L, grow_most)
    elif graph == "dense" and variant in ("tree", "cut"):
        keep = np.arange(len(u))
    else:
        keep = kernels.max_spanning_forest(n, u, v, w)
    info["tree_value"] = int(w[keep].sum())
    if variant in ("tree", "grow"):
        parent, level, _ = kernels.orient(n, u[keep], v[keep])
        return weak_off(rows, mult, parent, min_gain), info
    at = growth_start(n, u[keep], v[keep], start, root)
    if graph == "dense":
        parent, level, weight = kernels.dense_shallow_tree(rows, mult, at, penalty)
    else:
        parent, level, weight = kernels.shallow_tree(n, u, v, w, at, penalty)
    parent, gone = cut_tree(n, parent, level, weight, L, cut)
    info["cuts"], info["cut_similarity"] = len(gone), int(weight[gone].sum())
    return weak_off(rows, mult, parent, min_gain), info


def weak_off(rows, mult, default: np.ndarray, min_gain: int) -> np.ndarray:
    """Without the defaults that share fewer than ``min_gain`` transitions."""
    if not min_gain:
        return default
    u = np.flatnonzero(default >= 0)
    out = default.copy()
    out[u[kernels.similarity(rows, mult, u, default[u]) < min_gain]] = -1
    return out


def _table(pdf: pd.DataFrame) -> np.ndarray:
    pdf = pdf.sort_values("state")
    return np.stack(pdf["row"].to_numpy()).astype(np.int32)


def defaults_of(rows: DataFrame, algorithm: str, **params) -> DataFrame:
    """rows: ROWS.  state, default of every state of every automaton (null without)."""
    graph, variant = algorithm.split("_")

    def go(pdf: pd.DataFrame) -> pd.DataFrame:
        default, _ = run(_table(pdf), variant, graph, **params)
        out = pd.DataFrame({"automaton_id": pdf["automaton_id"].iloc[0], "state": np.arange(len(default))})
        out["default"] = pd.array(np.where(default < 0, None, default), dtype="Int64")
        return out

    return rows.groupBy("automaton_id").applyInPandas(go, "automaton_id string, state long, default long")


def measures_of(rows: DataFrame, algorithms: tuple[str, ...] = ALGORITHMS, **params) -> DataFrame:
    """One row per automaton and algorithm: size, delays, graph, cells given back wrongly (none), seconds of the construction alone.  Pairs of automaton and algorithm are dealt out, so that a task runs one."""
    import time

    todo = rows.join(rows.sparkSession.createDataFrame([(a,) for a in algorithms], "algorithm string").hint("broadcast"))

    def go(pdf: pd.DataFrame) -> pd.DataFrame:
        table, name = _table(pdf), pdf["algorithm"].iloc[0]
        graph, variant = name.split("_")
        head = {"automaton_id": pdf["automaton_id"].iloc[0], "algorithm": name}
        if graph == "dense" and len(table) > DENSE_MOST:
            return pd.DataFrame([head | {"n": len(table), "status": "skipped: too many states for all pairs"}])
        t = time.perf_counter()
        try:
            default, info = run(table, variant, graph, **params)
        except ValueError as e:
            return pd.DataFrame([head | {"n": len(table), "status": f"skipped: {e}"}])
        seconds = time.perf_counter() - t
        rows_, _, mult = kernels.symbol_classes(table)
        return pd.DataFrame([head | kernels.measure(rows_, mult, default) | info | {"different": kernels.differing(rows_, default), "seconds": seconds, "status": "done"}])

    names = [x.split()[0] for x in MEASURED.split(", ")]
    whole = {"n", "sigma", "t_in", "t_out", "labelled", "defaults", "longest_delay", "longest_chain", "edges", "tree_value", "cuts", "cut_similarity", "different"}

    def typed(pdf: pd.DataFrame) -> pd.DataFrame:
        out = go(pdf).reindex(columns=names)
        return out.astype({c: "Int64" for c in whole})

    return todo.groupBy("automaton_id", "algorithm").applyInPandas(typed, MEASURED)


def compress(a: Automaton, variant: str = "tree", graph: str = "sampled", *, exec: str = "auto", task_bytes: int = 1 << 30, **params) -> DelayedAutomaton:
    """The delayed automata.  'local' compresses each in one task, 'giant' each by DataFrame plans;
    'auto' sends those whose rows exceed ``task_bytes`` to the second and the rest to the first.
    Both draw the same partners and give the same defaults."""
    ids = a.transitions.groupBy("automaton_id").agg((F.count("*") * 4).alias("bytes"))
    large = [] if exec == "local" else [r[0] for r in (ids if exec == "giant" else ids.filter(F.col("bytes") > task_bytes)).select("automaton_id").collect()]  # each of them takes a plan of its own
    out = None
    if exec != "giant":
        out = defaults_of(a.rows().filter(~F.col("automaton_id").isin(large)) if large else a.rows(), f"{graph}_{variant}", **params)
    for name in large:
        own = F.col("automaton_id") == name
        d = giant_defaults(a.states.filter(own), a.transitions.filter(own), variant, graph, **params).select(F.lit(name).alias("automaton_id"), "state", "default")
        out = d if out is None else out.unionByName(d)
    return DelayedAutomaton(a.states, emit(a.transitions, out), out)


def emit(transitions: DataFrame, defaults: DataFrame) -> DataFrame:
    """giant.emit_labelled over many automata at once."""
    d = defaults.filter("default is not null").select("automaton_id", "state", "default")
    other = transitions.select("automaton_id", F.col("state").alias("default"), "symbol", F.col("target").alias("given"))
    joined = transitions.join(d, ["automaton_id", "state"], "left").join(other, ["automaton_id", "default", "symbol"], "left")
    return joined.filter(F.col("default").isNull() | (F.col("target") != F.col("given"))).select("automaton_id", "state", "symbol", "target")


def cut_tree(n: int, parent: np.ndarray, level: np.ndarray, weight: np.ndarray, L: int, cut: str = "fewest") -> tuple[np.ndarray, np.ndarray]:
    """Parents in the pieces that the cuts leave, each turned to its centre, and the states that were cut off."""
    gone = kernels.cut_fewest(parent, level, L) if cut == "fewest" else kernels.cut_lightest(parent, level, weight, L)
    parent = parent.copy()
    parent[gone] = -1
    kept = np.flatnonzero(parent >= 0)
    return kernels.orient(n, np.minimum(kept, parent[kept]), np.maximum(kept, parent[kept]))[0], gone


def growth_start(n: int, u: np.ndarray, v: np.ndarray, start: int, root: str) -> int:
    """Where the growth begins: a centre of the tree (u, v), the initial state, or the state of most neighbours."""
    if root == "initial":
        return start
    return int(kernels.centres(n, u, v)[0]) if root == "centre" else int(np.bincount(np.concatenate([u, v]), minlength=n).argmax())


def _grown(n: int, start: int, root: str, penalty: str, L: int):
    def run(batches):
        parts = [np.stack([b.column(c).to_numpy().astype(np.int64) for c in ("u", "v", "w")]) for b in batches]
        u, v, w = np.concatenate([np.zeros((3, 0), np.int64), *parts], 1)
        order = np.lexsort((v, u))
        u, v, w = u[order], v[order], w[order]
        keep = kernels.max_spanning_forest(n, u, v, w)
        parent, level, weight = kernels.shallow_tree(n, u, v, w, growth_start(n, u[keep], v[keep], start, root), penalty)
        parent, _ = cut_tree(n, parent, level, weight, L)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(n)), pa.array(parent, mask=parent < 0)], names=["state", "parent"])

    return run


def giant_defaults(states: DataFrame, transitions: DataFrame, variant: str = "tree", graph: str = "sampled", *, k: int = 8, r: int = 512, seed: int = 42, start: int = 0, depth: DataFrame | None = None, L: int = 2, sampler: str = "distinct", pairing: str = "uniform", star: bool = True, cut: str = "fewest", root: str = "centre", penalty: str = "pow2", fallback_start: bool = False, batch: int | None = None, parts: int = 64, min_depth_drop: int = 1, min_gain: int = 0, growth_edges: int = 1 << 25) -> DataFrame:
    """state, default of one automaton that fits no task; equal to what run() gives for the same parameters.

    Rounds go in batches; between them only the forest (tree) or each state's best default
    (depth) is kept, and all edges where the growth needs them (cut).  Of a graph of more than
    ``growth_edges`` edges the growth sees a union of edge-disjoint maximum spanning forests of
    that size: from there on its result may differ from run()'s."""
    if graph != "sampled" or variant == "grow":
        raise ValueError(f"{graph}_{variant} compares all pairs or merges one edge at a time: automata of one task only")
    if cut != "fewest":
        raise ValueError(f"cut {cut!r}: automata of one task only")
    spark, states = states.sparkSession, states.select("state")
    rows = store(to_wide(transitions).select("state", "row"))
    n, sigma = states.count(), transitions.select("symbol").distinct().count()
    drawn = kernels.sample_symbols(sigma, k, range(r), seed, "distinct" if sampler.startswith("minhash") else sampler) if r else []
    batch = batch or max(8, (1 << 28) // max(n, 1))
    pairs, best, kept, every = None, None, None, None
    if variant == "depth":
        depth = store(giant.bfs_depth(transitions, start) if depth is None else depth)
    if star and variant != "depth":
        every = store(giant.pair_similarity(rows, giant.undirected(giant.star_edges(states, start))))
        kept = every
    if fallback_start and variant == "depth":
        best = store(giant.best_defaults(states.filter(F.col("state") != start).select(F.col("state").alias("u"), F.lit(start).cast("long").alias("v")), depth, rows, drop_by=min_depth_drop, min_gain=1))
    for b in range(0, r, batch):
        sample = spark.createDataFrame([(i, [int(x) for x in drawn[i]]) for i in range(b, min(b + batch, r))], "round long, at array<int>")
        pairs = giant.fast_proposals(giant.fast_buckets(rows, sample, seed, sampler), seed, n, pairing=pairing, parts=parts).select("u", "v").distinct()
        if variant == "depth":
            new = giant.best_defaults(pairs, depth, rows, drop_by=min_depth_drop, min_gain=1)
            both = new if best is None else best.unionByName(new)
            best = store(both.groupBy("state").agg(F.max(F.struct("w", (-F.col("default")).alias("d"))).alias("b")).select("state", (-F.col("b.d")).alias("default"), F.col("b.w").alias("w")))
            continue
        new = giant.undirected(pairs)
        new = new if kept is None else new.join(kept.select("u", "v"), ["u", "v"], "left_anti")
        new = store(giant.pair_similarity(rows, new))
        if variant == "cut":
            every = new if every is None else store(every.unionByName(new).dropDuplicates(["u", "v"]))
        kept = giant.spanning_forest(new if kept is None else kept.unionByName(new))
    if variant == "depth":
        out = states if best is None else states.join(best.filter(F.col("w") >= min_gain), "state", "left")
        return out.select("state", "default") if best is not None else out.withColumn("default", F.lit(None).cast("long"))
    if kept is None:
        return states.withColumn("default", F.lit(None).cast("long"))
    if variant == "tree":
        tree = giant.orient(kept, states)
    else:
        # The growth takes one offer after another: a task of its own, over arrays of the graph's edges.
        if every.count() > growth_edges:
            if n > growth_edges // 4:
                raise ValueError(f"growth of {n} states: its task holds {growth_edges} edges")
            every = store(giant.sparsified(every, growth_edges // n))
        tree = every.select("u", "v", "w").coalesce(1).mapInArrow(_grown(n, start, root, penalty, L), "state long, parent long")
    d = tree.withColumnRenamed("parent", "default")
    if min_gain:
        pairs = d.filter("default is not null").select(F.col("state").alias("u"), F.col("default").alias("v"))
        weak = giant.pair_similarity(rows, pairs).filter(F.col("w") < min_gain).select(F.col("u").alias("state"), F.lit(True).alias("weak"))
        d = d.join(weak, "state", "left").select("state", F.when(F.col("weak").isNull(), F.col("default")).alias("default"))
    return d.select("state", "default")
