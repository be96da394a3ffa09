"""Cases in which the engine's queries once did less than the whole job."""

import random

import numpy as np
import pytest

from conftest import SF
from thinfsm import compress, dealt, kernels, match, rules, sparse
from thinfsm.functions import sql
from thinfsm.operators import catalogue
from thinfsm.plans import dictionary, workloads
from thinfsm.sources import ladder
from thinfsm.streaming import flows


def test_range_join_of_all_lines(spark, tmp_path):
    lines = [(o, 1, float(o % 5), 1.5) for o in (1, 400, 401, 9000)]
    parts = [(p, p % 4) for p in (1, 40, 41, 777)]
    spark.createDataFrame(lines, "l_orderkey long, l_linenumber int, l_quantity double, l_extendedprice double").write.parquet(f"{tmp_path}/lineitem.parquet")
    spark.createDataFrame(parts, "p_partkey long, p_size int").write.parquet(f"{tmp_path}/part.parquet")
    got = {r["p_partkey"]: r["lines"] for r in catalogue.range_join_quantity(spark, str(tmp_path)).collect()}
    want = {p: sum(s <= q <= s + 1 for _, _, q, _ in lines) for p, s in parts}
    assert got == {p: n for p, n in want.items() if n}


@pytest.mark.parametrize("module,name", [(dictionary, "match_benchmark_docs"), (flows, "stream_match")])
def test_whole_passages(spark, same, module, name):
    same(module.QUERIES[name](spark, SF), module.ORACLES[name])


def test_a_head_is_no_passage(spark, tmp_path):
    head = "x" * 45
    spark.createDataFrame([(1, head + " one"), (2, head + " two")], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    spark.createDataFrame([(7, f"a {head} one b"), (8, head)], "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    ids = lambda df: sorted(r[0] for r in df.collect())
    at = str(tmp_path)
    assert ids(dictionary.match_benchmark_docs(spark, at)) == [7]
    assert ids(catalogue.semi_matched_rules(spark, at)) == [1] and ids(catalogue.anti_unmatched_rules(spark, at)) == [2]


def test_groups_of_words_match_as_one(spark, same, monkeypatch):
    whole = {r["p_partkey"]: r for r in dictionary.match_names(spark, SF).collect()}
    flow = {r["flow_id"]: r["matches"] for r in flows.QUERIES["flow_match"](spark, SF).collect()}
    monkeypatch.setattr(match, "GROUP_BYTES", 200)
    assert len(dictionary._matcher(spark, SF).parts) > 2
    assert {r["p_partkey"]: r for r in dictionary.match_names(spark, SF).collect()} == whole
    same(dictionary.page_matches(spark, SF), dictionary.ORACLES["page_matches"])
    same(sql.QUERIES["udtf_matches"](spark, SF), sql.ORACLES["udtf_matches"])
    assert {r["flow_id"]: r["matches"] for r in flows.QUERIES["stream_flow_match"](spark, SF).collect()} == flow


def test_url_ladder_builds_no_rows(spark, same, duck, tmp_path, monkeypatch):
    monkeypatch.setattr(workloads, "dictionary_rows", None)
    same(workloads.url_ladder(spark, SF), workloads.ORACLES["url_ladder"])
    pages = [(1, None), (2, ""), (3, "ab"), (4, "ab"), (9, "ac"), (16, "b")]
    spark.createDataFrame(pages, "page_id long, url string").write.parquet(f"{tmp_path}/pages.parquet")
    got = {r["automaton_id"]: r["states"] for r in workloads.url_ladder(spark, str(tmp_path)).collect()}
    assert got == {"urls_1/8": 1, "urls_1/4": 3, "urls_1/2": 3, "urls_1/1": 5}


def test_worked_example_runs_the_given_events(spark, same):
    same(workloads.worked_example_tree(spark, SF), workloads.ORACLES["worked_example_tree"])
    got = workloads.worked_example(spark, SF).collect()
    n = spark.read.parquet(f"{SF}/events.parquet").count()
    assert len(got) == 8 and {r["events"] for r in got} == {n} and len({r["found"] for r in got}) == 1 and all(r["hops"] > 0 for r in got)


def test_ladder_of_the_given_orders(spark, same):
    same(ladder.ladder_source(spark, SF), ladder.ORACLES["ladder_source"])
    ladder.register(spark)
    assert spark.read.format("fsm_ladder").option("automata", 4).option("states", 50).option("sigma", 8).load().count() == 200


@pytest.mark.parametrize("trial", range(12))
def test_rows_kept_as_differences(trial):
    """Draws, forests, defaults, edges, growth and measures of the sparse form are those of the kernels, from any start of the growth."""
    rnd = random.Random(trial)
    letters = "abcdefghij"[: (2, 3, 5, 10)[trial % 4]]
    words = sorted({"".join(rnd.choices(letters, k=rnd.randint(1, 9))).encode() for _ in range(60)} | {b"http" + bytes(rnd.choices(b"ht/xy", k=8)) for _ in range(20 * (trial % 2))})
    t, _, depth = rules.dictionary(words)
    s, n, (k, r, seed) = sparse.Sparse(**sparse.dictionary(words)), len(t), (8, 24, 7)
    assert (np.stack([s.column(c) for c in range(256)], 1) == t).all() and (s.depth == depth).all()
    rows, cls, mult = kernels.symbol_classes(t)
    drawn = [{(int(a), int(b)) for u, v in s.draws(i, k, seed) for a, b in zip(u, v)} for i in range(r)]
    assert drawn == [set(zip(u.tolist(), v.tolist())) for u, v in kernels.proposals(rows, cls, 256, k=k, r=r, seed=seed)]
    u, v, w = kernels.sampled_graph(rows, cls, mult, 0, k=k, r=r, seed=seed)
    kept = kernels.max_spanning_forest(n, u, v, w)
    tree = sparse.forest(s, kernels.distinct(np.concatenate([sparse.tree_edges(s, range(a, r, 3), k, seed, most=50) for a in range(3)])), every=True)
    assert set(zip(*(x.tolist() for x in tree))) == set(zip(u[kept].tolist(), v[kept].tolist(), w[kept].tolist()))
    parent = kernels.orient(n, u[kept], v[kept])[0]
    assert (sparse.orient(n, *tree[:2]) == parent).all()
    got = sparse.measure(s, parent)
    assert got == kernels.measure(rows, mult, parent) | {"different": 0}
    best = np.maximum.reduce([sparse.depth_best(s, range(a, r, 3), k, seed) for a in range(3)])
    assert (sparse.best_default(best) == kernels.sampled_depth(rows, cls, mult, depth, k=k, r=r, seed=seed)).all()
    begin = [*sparse.bounds(n, 4), n]
    parts = [np.concatenate([sparse.unpacked(sparse.packed(sparse.listed(s, range(c, r, 3), k, seed, a, b)[0])) for c in range(3)]) for a, b in zip(begin, begin[1:])]
    assert sum(len(np.unique(x)) for x in parts) + n - 1 == len(u)
    for at in {sparse.centre(n, *tree[:2]), 0, n // 2, n - 1}:
        for penalty in ("pow2", "linear", "none"):
            known = [at]
            while True:
                try:
                    got = sparse.shallow_tree(s, at, sparse.listed(s, range(r), k, seed, 0, 0, np.array(known))[1], np.array(known), penalty)
                    break
                except sparse.Missing as e:
                    known = sorted({*known, *e.args[0]})
            want = kernels.shallow_tree(n, u, v, w, at, penalty)
            assert all((a == b).all() for a, b in zip(got, want))
            assert all((a == b).all() for a, b in zip(sparse.cut_tree(n, got[0], got[1], 2), compress.cut_tree(n, *want, 2)))


@pytest.mark.parametrize("name", ["url_tree", "url_times"])
def test_large_url_automata_have_no_full_rows(spark, monkeypatch, name):
    """A large automaton's measures are the same, its rounds dealt out, and no task builds its rows of 256 cells."""
    drop = ("dense_seconds", "sampled_seconds", "speed_up")
    of = lambda: sorted((tuple(r) for r in workloads.QUERIES[name](spark, SF).drop(*drop).collect()), key=str)
    monkeypatch.setattr(workloads, "literals", few_urls)
    monkeypatch.setattr(workloads, "GROW_MOST", 0)
    monkeypatch.setattr(compress, "DENSE_MOST", 0)
    want, seen = of(), []
    monkeypatch.setattr(dealt, "MOST", 0)
    monkeypatch.setattr(workloads, "dictionary_rows", lambda words: seen.extend(words.select("word").collect()) or spark.createDataFrame([], "automaton_id string, state long, row array<int>"))
    assert of() == want and not seen


def few_urls(spark, sf_dir, name):
    words = spark.read.parquet(f"{sf_dir}/pages.parquet").orderBy("page_id").limit(12).selectExpr("url as word")
    return words.selectExpr("'urls_1/1' as automaton_id", "word").unionByName(words.limit(5).selectExpr("'urls_1/2' as automaton_id", "word"))
