"""Relational tier: equal to the array kernels for the same choices, and to SQL."""

import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from conftest import SF
from thinfsm import compress, giant, kernels as K
from thinfsm.functions import sql
from thinfsm.model import Automaton, numbered, to_long, to_wide, validate
from thinfsm.operators import catalogue
from thinfsm.plans import dictionary, workloads
from thinfsm.sources.ladder import random_table, read_automaton, write_automaton


@pytest.fixture(scope="module")
def auto(spark):
    t = random_table(30, 6, 3)
    rows = spark.createDataFrame([("a", i, r.tolist()) for i, r in enumerate(t)], "automaton_id string, state long, row array<int>")
    depth = K.bfs_depth(t, 0)
    states = spark.createDataFrame([("a", i, i == 0, False, int(d)) for i, d in enumerate(depth)], "automaton_id string, state long, is_start boolean, is_accept boolean, depth int")
    return t, rows, Automaton(states, to_long(rows))


def test_hash_is_sparks(spark):
    rows = [(-5, 3), (0, 0), (2**40, -1), (7, 123456789)]
    got = [r[0] for r in spark.createDataFrame(rows, "a long, b long").coalesce(1).select(F.xxhash64("a", "b")).collect()]
    assert got == K.xxhash64(*np.array(rows).T).tolist()


def test_layouts_and_numbers(spark, auto):
    t, rows, a = auto
    assert sorted(map(tuple, to_wide(a.transitions).select("state", F.col("row").cast("string")).collect())) == sorted(map(tuple, rows.select("state", F.col("row").cast("string")).collect()))
    assert validate(a).first()[1:] == (True, True, True, True)
    n = numbered(spark.range(100).select((F.col("id") * 37 % 100).alias("x")), ["x"], "i").filter("i <> x").count()
    assert n == 0


def test_spanning_forest_equals_kernel(spark, auto):
    t, rows, a = auto
    r, _, mult = K.symbol_classes(t)
    u, v, w = K.dense_tree(r, mult)
    edges = giant.pair_similarity(rows, spark.createDataFrame([(i, j) for i in range(30) for j in range(i + 1, 30)], "u long, v long"))
    got = sorted(map(tuple, giant.spanning_forest(edges).collect()))
    assert got == sorted(zip(u.tolist(), v.tolist(), w.tolist()))
    parent, level, _ = K.orient(30, u, v)
    got = {r[0]: r[1] for r in giant.orient(spark.createDataFrame(list(zip(u.tolist(), v.tolist())), "u long, v long"), a.states).collect()}
    assert got == {i: (None if p < 0 else p) for i, p in enumerate(parent.tolist())}
    tree = giant.levels(giant.orient(spark.createDataFrame(list(zip(u.tolist(), v.tolist())), "u long, v long"), a.states))
    for L in (1, 2):
        assert sorted(r[0] for r in giant.cut_fewest(tree, L).collect()) == K.cut_fewest(parent, level, L).tolist()


def test_giant_bucket_positions(spark):
    b = spark.range(500).select(F.lit(0).alias("round"), F.when(F.col("id") < 480, "big").otherwise("small").alias("key"), F.col("id").alias("state"))
    for parts in (1, 7):
        p = giant.positions(b, parts)
        assert sorted(r[0] for r in p.filter("key = 'big'").select("pos").collect()) == list(range(480))
        e = giant.propose(b, 1, parts=parts)
        assert e.count() == 500 and e.filter("u = v").isEmpty()
    assert giant.ring(b, 1, parts=3).filter("u = v").isEmpty()


@pytest.mark.parametrize("variant,how", [("tree", {"batch": 3, "sampler": "rotating"}), ("depth", {"sampler": "minhashk", "fallback_start": True, "pairing": "ring"}), ("cut", {"sampler": "replacement", "root": "degree", "penalty": "linear", "min_gain": 2, "L": 1})])
def test_tiers_give_the_same_defaults(spark, variant, how):
    """Two automata with the same state numbers, each by its own."""
    tables = {"a": random_table(12, 6, 3), "b": random_table(9, 6, 4)}
    rows = spark.createDataFrame([(x, i, r.tolist()) for x, t in tables.items() for i, r in enumerate(t)], "automaton_id string, state long, row array<int>").repartition(3)
    states = rows.select("automaton_id", "state", (F.col("state") == 0).alias("is_start"), F.lit(False).alias("is_accept"), F.lit(0).alias("depth"))
    a = Automaton(states, to_long(rows))
    how = {"k": 2, "r": 5, **how}
    got = compress.compress(a, variant, "sampled", exec="giant", parts=3, **how)
    for name, t in tables.items():
        default, _ = compress.run(t, variant, "sampled", **how)
        own = {r["state"]: r["default"] for r in got.defaults.filter(F.col("automaton_id") == name).collect()}
        assert own == {i: (None if d < 0 else d) for i, d in enumerate(default.tolist())}
        r, _, mult = K.symbol_classes(t)
        assert got.labelled.filter(F.col("automaton_id") == name).count() == K.measure(r, mult, default)["labelled"]


def test_auto_splits_by_size(spark):
    tables = {"big": random_table(30, 6, 3), "small": random_table(10, 6, 4)}
    rows = spark.createDataFrame([(x, i, r.tolist()) for x, t in tables.items() for i, r in enumerate(t)], "automaton_id string, state long, row array<int>")
    a = Automaton(rows.select("automaton_id", "state"), to_long(rows))
    got = compress.compress(a, "depth", "sampled", task_bytes=10 * 6 * 4, k=2, r=4)
    for name, t in tables.items():
        default, _ = compress.run(t, "depth", "sampled", k=2, r=4)
        assert {r["state"]: r["default"] for r in got.defaults.filter(F.col("automaton_id") == name).collect()} == {i: (None if d < 0 else d) for i, d in enumerate(default.tolist())}
    for bad in ({"variant": "grow"}, {"graph": "dense"}, {"variant": "cut", "cut": "lightest"}):
        with pytest.raises(ValueError):
            compress.compress(a, **{"variant": "tree", "graph": "sampled", "exec": "giant"} | bad)


def test_local_tier_and_round_trip(spark, auto, tmp_path):
    t, rows, a = auto
    d = compress.compress(a, "tree", "dense")
    r, _, mult = K.symbol_classes(t)
    default, _ = compress.run(t, "tree", "dense")
    assert d.labelled.count() == K.measure(r, mult, default)["labelled"]
    write_automaton(a, str(tmp_path / "x"))
    assert read_automaton(spark, str(tmp_path / "x")).transitions.count() == a.transitions.count()


FAST = ["redundant_transitions", "well_defined", "rank_states", "replacement_buckets", "minhash_k_buckets", "dict_states", "dict_transitions", "dict_accepting", "symbol_classes", "pair_similarity", "similarity_histogram", "sampled_symbols", "sampled_buckets", "sampled_proposals", "ring_proposals", "sampled_edges", "depth_defaults", "depth_size", "sampled_depth_defaults", "suffix_defaults", "match_names", "collision_probability", "top_pairs", "sampled_tree_size"]


@pytest.mark.parametrize("name", FAST)
def test_dictionary_queries(spark, same, name):
    same(dictionary.QUERIES[name](spark, SF), dictionary.ORACLES[name])


@pytest.mark.parametrize("name", sorted(catalogue.ORACLES))
def test_catalogue(spark, same, name):
    same(catalogue.QUERIES[name](spark, SF), catalogue.ORACLES[name])


@pytest.mark.parametrize("name", sorted(sql.ORACLES))
def test_sql_surface(spark, same, name):
    same(sql.QUERIES[name](spark, SF), sql.ORACLES[name])


@pytest.mark.parametrize("name", ["worked_example_tree", "cut_forest_check", "url_ladder"])
def test_workloads(spark, same, name):
    same(workloads.QUERIES[name](spark, SF), workloads.ORACLES[name])


def test_plans(spark):
    plan = catalogue.QUERIES["scan_project_filter"](spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert re.search(r"PushedFilters: .*In\(p_brand.*GreaterThanOrEqual\(p_size", plan) and re.search(r"ReadSchema: struct<p_partkey:bigint,p_name:string,p_brand:string,p_size:int>", plan)
    a = dictionary.base(spark, SF)
    plan = dictionary._edges(a)._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan
