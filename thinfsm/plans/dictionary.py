"""Queries of the methods on the dictionary of part names, with the same definitions in plain SQL."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .. import compress, giant, match, rules
from ..model import Automaton, numbered, table, to_long, to_wide, validate
from ..scratch import store

K, R, SEED = 3, 8, 42
_made: dict = {}


def base(spark: SparkSession, sf_dir: str) -> Automaton:
    """States, total transitions and rows of the dictionary, made once per session and content of the table."""
    words = table(spark, sf_dir, "part").select(F.col("p_name").alias("word")).distinct()
    key = (spark.sparkContext.applicationId, sf_dir, *words.agg(F.count("*"), F.sum(F.xxhash64("word").cast("decimal(38,0)"))).first())
    if key not in _made:
        states = store(giant.dictionary_states(words))
        trans = store(giant.dictionary_transitions(states))
        a = Automaton(states, trans)
        a.wide = store(to_wide(trans))
        _made[key] = a
    return _made[key]


def _sample(a, sampler="distinct"):
    return giant.sample_symbols(a.transitions.select("symbol").distinct(), K, R, SEED, sampler)


def _edges(a):
    return giant.sampled_graph(a.states, a.transitions, a.wide, k=K, r=R, seed=SEED)


def _dense(a):
    """All pairs with weights: pairs by states, weights by shared transitions (0 without)."""
    s = a.states.select("state")
    pairs = s.select(F.col("state").alias("u")).join(s.select(F.col("state").alias("v")), F.col("u") < F.col("v"))
    return pairs.join(giant.similarity_long(a.transitions), ["u", "v"], "left").select("u", "v", F.coalesce("w", F.lit(0)).alias("w"))


def _tree(a, graph):
    key = ("tree", graph, id(a))
    if key not in _made:
        _made[key] = store(giant.spanning_forest(_dense(a) if graph == "dense" else _edges(a)))
    return _made[key]


def _tree_defaults(a, graph):
    key = ("defaults", graph, id(a))
    if key not in _made:
        _made[key] = store(giant.orient(_tree(a, graph), a.states).select("state", F.col("parent").alias("default")))
    return _made[key]


def _size(a, d) -> DataFrame:
    return giant.size_report(a.transitions, giant.emit_labelled(a.transitions, d), d)


def _depth_pairs(a):
    s = a.states.select("state", "depth")
    return s.select(F.col("state").alias("u"), F.col("depth").alias("a")).join(s.select(F.col("state").alias("v"), F.col("depth").alias("b")), F.col("b") < F.col("a")).select("u", "v")


def _depth_defaults(a, drop=1):
    return giant.best_defaults(_depth_pairs(a), a.states.select("state", "depth"), a.wide, drop_by=drop)


def _sampled_depth(a):
    pairs = giant.propose(giant.bucket_keys(a.transitions, _sample(a)), SEED)
    return giant.best_defaults(pairs.select("u", "v"), a.states.select("state", "depth"), a.wide, min_gain=1)


def _groups(spark, sf_dir, table_name="part", col="p_name"):
    """The distinct words of a column in groups of bounded bytes, each with its delayed matcher and the words that each of its states accepts."""
    words = (r[0].encode() for r in table(spark, sf_dir, table_name).select(F.col(col).alias("w")).filter("w is not null and w <> ''").distinct().orderBy("w").toLocalIterator())
    return word_matchers(words)


def word_matchers(words):
    """Words in order, in groups of bounded bytes: words, matcher, and words by state, of each."""
    return [(g, *_group_matcher(g)) for g in match.word_groups(words, match.GROUP_BYTES)] or [([], *_group_matcher([]))]


def _matcher(spark, sf_dir, table_name="part", col="p_name"):
    parts = [m for _, m, _ in _groups(spark, sf_dir, table_name, col)]
    return parts[0] if len(parts) == 1 else match.Matchers(parts)


def _group_matcher(words):
    """The delayed matcher of some words (bounded matching delay) and the words that each state accepts."""
    t, accept, depth = rules.dictionary(words)
    d, _ = compress.run(t, "depth", "sampled", depth=depth, r=64, fallback_start=True)
    return match.Matcher(t, np.array([len(x) for x in accept], np.int64), d), accept


def found_words(spark, sf_dir, texts, text_col, table_name, col):
    """word: those of a column that occur in some text of another table, found in one pass."""
    groups = _groups(spark, sf_dir, table_name, col)
    hits = match.occurring(texts, match.Matchers([m for _, m, _ in groups]), text_col=text_col)
    own = [(k, s, words[w].decode()) for k, (words, _, accept) in enumerate(groups) for s, a in enumerate(accept) for w in a]
    return hits.join(spark.createDataFrame(own or [(-1, -1, "")], "part long, state long, word string"), ["part", "state"]).select("word").distinct()


QUERIES = {}


def query(f):
    QUERIES[f.__name__] = f
    return f


@query
def dict_states(spark, sf_dir):
    return base(spark, sf_dir).states.select("state", "prefix", "depth", "is_start", F.col("whole").alias("is_word"))


@query
def dict_transitions(spark, sf_dir):
    return base(spark, sf_dir).transitions.select("state", "symbol", "target")


@query
def dict_accepting(spark, sf_dir):
    return giant.accepting(base(spark, sf_dir).states).select("state", "words")


@query
def dict_depth(spark, sf_dir):
    return giant.bfs_depth(base(spark, sf_dir).transitions)


@query
def dict_validate(spark, sf_dir):
    return validate(base(spark, sf_dir)).drop("automaton_id")


@query
def symbol_classes(spark, sf_dir):
    """Symbols with equal columns: a class by the least symbol, with its multiplicity."""
    t = base(spark, sf_dir).transitions
    col = t.groupBy("symbol").agg(F.md5(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("state", "target"))), lambda x: x["target"].cast("string")), ",")).alias("col"))
    return col.groupBy("col").agg(F.min("symbol").alias("symbol"), F.count("*").alias("multiplicity")).drop("col")


@query
def pair_similarity(spark, sf_dir):
    return giant.similarity_long(base(spark, sf_dir).transitions)


@query
def similarity_histogram(spark, sf_dir):
    return _dense(base(spark, sf_dir)).groupBy("w").agg(F.count("*").alias("pairs"))


@query
def similarity_percentiles(spark, sf_dir):
    return _dense(base(spark, sf_dir)).agg(F.percentile("w", 0.5).alias("median"), F.percentile("w", 0.9).alias("p90"))


@query
def dense_graph_summary(spark, sf_dir):
    return _dense(base(spark, sf_dir)).agg(F.count("*").alias("edges"), F.sum("w").alias("total"), F.max("w").alias("most"))


@query
def star_edges(spark, sf_dir):
    return giant.star_edges(base(spark, sf_dir).states)


@query
def sampled_symbols(spark, sf_dir):
    return _sample(base(spark, sf_dir))


@query
def replacement_symbols(spark, sf_dir):
    return _sample(base(spark, sf_dir), "replacement")


@query
def sampled_buckets(spark, sf_dir):
    a = base(spark, sf_dir)
    return giant.positions(giant.bucket_keys(a.transitions, _sample(a)))


@query
def replacement_buckets(spark, sf_dir):
    a = base(spark, sf_dir)
    return giant.bucket_keys(a.transitions, _sample(a, "replacement"))


@query
def minhash_buckets(spark, sf_dir):
    return giant.minhash_keys(base(spark, sf_dir).transitions, 4, SEED)


@query
def minhash_k_buckets(spark, sf_dir):
    return giant.minhash_keys(base(spark, sf_dir).transitions, 2, SEED, 3)


@query
def bucket_statistics(spark, sf_dir):
    a = base(spark, sf_dir)
    per = giant.bucket_keys(a.transitions, _sample(a)).groupBy("round", "key").count()
    return per.groupBy("round").agg(F.count("*").alias("buckets"), F.max("count").alias("largest"), F.count_if(F.col("count") == 1).alias("alone"))


@query
def sampled_proposals(spark, sf_dir):
    a = base(spark, sf_dir)
    return giant.propose(giant.bucket_keys(a.transitions, _sample(a)), SEED)


@query
def ring_proposals(spark, sf_dir):
    a = base(spark, sf_dir)
    return giant.ring(giant.bucket_keys(a.transitions, _sample(a)), SEED)


@query
def sampled_edges(spark, sf_dir):
    return _edges(base(spark, sf_dir))


@query
def sampled_graph_summary(spark, sf_dir):
    a = base(spark, sf_dir)
    n = a.states.agg(F.count("*").alias("n"))
    e = _edges(a).agg(F.count("*").alias("edges"), F.sum("w").alias("total"))
    return e.join(F.broadcast(n)).select("edges", "total", (F.col("edges") <= R * F.col("n") + F.col("n") - 1).alias("bounded"))


@query
def dense_tree_edges(spark, sf_dir):
    return _tree(base(spark, sf_dir), "dense").select("u", "v", "w")


@query
def sampled_tree_edges(spark, sf_dir):
    return _tree(base(spark, sf_dir), "sampled").select("u", "v", "w")


@query
def tree_value(spark, sf_dir):
    a = base(spark, sf_dir)
    d, s = (_tree(a, g).agg(F.sum("w").alias(g)) for g in ("dense", "sampled"))
    return d.join(F.broadcast(s)).select("dense", "sampled", (F.col("sampled") <= F.col("dense")).alias("bounded"))


@query
def tree_overlap(spark, sf_dir):
    a = base(spark, sf_dir)
    return _tree(a, "dense").select("u", "v").intersect(_tree(a, "sampled").select("u", "v"))


@query
def running_tree_value(spark, sf_dir):
    """Sum of the weights of this and all better edges: sums over the weights above (as many as the alphabet), and within a weight by ranges of u."""
    e = _tree(base(spark, sf_dir), "dense").select("u", "v", "w").withColumn("part", F.floor(F.col("u") / 4096))
    parts = e.groupBy("w", "part").agg(F.sum("w").alias("own"))
    before = parts.select("w", "part", (F.sum("own").over(Window.orderBy(F.desc("w"), "part")) - F.col("own")).alias("before"))  # a row for each weight and 4,096 states
    local = Window.partitionBy("w", "part").orderBy("u", "v").rowsBetween(Window.unboundedPreceding, 0)
    return e.join(before, ["w", "part"]).select("u", "v", "w", (F.col("before") + F.sum("w").over(local)).alias("running"))


@query
def dense_tree_size(spark, sf_dir):
    a = base(spark, sf_dir)
    return _size(a, _tree_defaults(a, "dense"))


@query
def sampled_tree_size(spark, sf_dir):
    a = base(spark, sf_dir)
    return _size(a, _tree_defaults(a, "sampled"))


@query
def outer_no_default(spark, sf_dir):
    a = base(spark, sf_dir)
    roots = a.states.select("state").join(_tree_defaults(a, "dense"), "state", "left").filter("default is null")
    return roots.agg(F.count("*").alias("roots"))


@query
def depth_defaults(spark, sf_dir):
    return _depth_defaults(base(spark, sf_dir))


@query
def depth_drop2(spark, sf_dir):
    return _depth_defaults(base(spark, sf_dir), 2)


@query
def depth_labelled(spark, sf_dir):
    a = base(spark, sf_dir)
    return giant.emit_labelled(a.transitions, _depth_defaults(a)).select("state", "symbol", "target")


@query
def depth_size(spark, sf_dir):
    a = base(spark, sf_dir)
    return _size(a, _depth_defaults(a))


@query
def sampled_depth_defaults(spark, sf_dir):
    return _sampled_depth(base(spark, sf_dir))


@query
def sampled_depth_size(spark, sf_dir):
    a = base(spark, sf_dir)
    return _size(a, _sampled_depth(a))


@query
def suffix_defaults(spark, sf_dir):
    return giant.suffix_defaults(base(spark, sf_dir).states)


@query
def suffix_size(spark, sf_dir):
    a = base(spark, sf_dir)
    return _size(a, giant.suffix_defaults(a.states))


@query
def rank_states(spark, sf_dir):
    """States by the transitions that their default saves: ranks from counts by value (as many as the alphabet), quarters from a distributed numbering."""
    d = store(_depth_defaults(base(spark, sf_dir)).select("state", (F.col("w") - 1).alias("saved"), (-F.col("w")).alias("o")))
    above = Window.orderBy(F.desc("saved"))
    by = d.groupBy("saved").agg(F.count("*").alias("own"))  # a row for each value
    by = by.select("saved", (F.sum("own").over(above.rowsBetween(Window.unboundedPreceding, 0)) - F.col("own") + 1).cast("int").alias("rank"), F.row_number().over(above).alias("dense_rank"))
    n = d.agg(F.count("*").alias("n"))
    at = numbered(d, ["o", "state"], "i").join(F.broadcast(n)).withColumn("q", F.floor(F.col("n") / 4)).withColumn("wide", (F.col("n") % 4) * (F.col("q") + 1))
    quarter = F.when(F.col("i") < F.col("wide"), F.floor(F.col("i") / (F.col("q") + 1))).otherwise(F.col("n") % 4 + F.floor((F.col("i") - F.col("wide")) / F.greatest(F.col("q"), F.lit(1)))) + 1
    return at.join(F.broadcast(by), "saved").select("state", "saved", "rank", "dense_rank", quarter.cast("int").alias("quarter"))


@query
def resolve_check(spark, sf_dir):
    """The table that a delayed automaton gives back: that of the dictionary."""
    a = base(spark, sf_dir)
    d = _depth_defaults(a)
    got = giant.resolve(a.states, giant.emit_labelled(a.transitions, d), d, a.transitions.select("symbol").distinct())
    return got.select("state", "symbol", "target")


@query
def full_diff(spark, sf_dir):
    """Rows in which the plain and the resolved table differ."""
    a = base(spark, sf_dir)
    d = _tree_defaults(a, "sampled")
    got = giant.resolve(a.states, giant.emit_labelled(a.transitions, d), d, a.transitions.select("symbol").distinct()).select("state", "symbol", F.col("target").alias("got"))
    both = a.transitions.select("state", "symbol", "target").join(got, ["state", "symbol"], "full")
    return both.agg(F.count("*").alias("rows"), F.count_if(~F.col("target").eqNullSafe(F.col("got"))).alias("different"))


@query
def longest_delay(spark, sf_dir):
    a = base(spark, sf_dir)
    d = _depth_defaults(a)
    got = giant.resolve(a.states, giant.emit_labelled(a.transitions, d), d, a.transitions.select("symbol").distinct())
    return got.agg(F.max("hops").cast("long").alias("longest_delay"))


@query
def hops_by_symbol(spark, sf_dir):
    a = base(spark, sf_dir)
    d = _depth_defaults(a)
    got = giant.resolve(a.states, giant.emit_labelled(a.transitions, d), d, a.transitions.select("symbol").distinct())
    return got.groupBy("symbol").agg(F.sum("hops").alias("hops"))


@query
def match_names(spark, sf_dir):
    """Words that occur in each part name, with ends counted, by the delayed matcher."""
    p = table(spark, sf_dir, "part")
    return match.match(p, _matcher(spark, sf_dir), id_col="p_partkey", text_col="p_name").select(F.col("payload_id").alias("p_partkey"), "matches", "length")


@query
def match_benchmark_docs(spark, sf_dir):
    """Documents that hold a whole passage."""
    d = table(spark, sf_dir, "documents")
    return match.match(d, _matcher(spark, sf_dir, "benchmark", "text"), id_col="doc_id", text_col="text").filter("accepts").select(F.col("payload_id").alias("doc_id"))


@query
def matcher_delay(spark, sf_dir):
    """Bytes, defaults followed per byte and their bound, over all pages matched by the delayed automaton of the names."""
    return match.delay_report(match.match(table(spark, sf_dir, "pages"), _matcher(spark, sf_dir), id_col="page_id", text_col="html")).select("payloads", "bytes", "bounded", "hops", "mean_hops_per_byte", "p99_hops_per_byte", "max_hops")


@query
def page_matches(spark, sf_dir):
    """Pages whose html holds a part name."""
    d = table(spark, sf_dir, "pages")
    return match.match(d, _matcher(spark, sf_dir), id_col="page_id", text_col="html").select(F.col("payload_id").alias("page_id"), F.col("accepts"), F.col("length"))


@query
def matching_delay_names(spark, sf_dir):
    """Defaults followed while matching each distinct part name, character by character, from the relational tables."""
    a = base(spark, sf_dir)
    d = _depth_defaults(a)
    full = store(giant.resolve(a.states, giant.emit_labelled(a.transitions, d), d, a.transitions.select("symbol").distinct()).select(F.col("state").alias("at"), "symbol", "target", "hops"))
    names = table(spark, sf_dir, "part").select("p_name").filter("p_name is not null").distinct()
    most = names.agg(F.max(F.length("p_name"))).first()[0] or 0
    cur = names.select("p_name", F.lit(0).cast("long").alias("at"), F.lit(0).cast("long").alias("total"))
    for i in range(most):  # as many steps as the longest name has characters
        step = cur.withColumn("symbol", F.when(F.length("p_name") > i, F.ascii(F.expr(f"substring(p_name, {i + 1}, 1)"))))
        cur = step.join(full, ["at", "symbol"], "left").select("p_name", F.coalesce("target", "at").alias("at"), (F.col("total") + F.coalesce("hops", F.lit(0))).alias("total"))
        if i % 8 == 7:
            cur = store(cur)
    return cur.select("p_name", F.col("total").alias("hops"), (F.col("total") <= F.length("p_name")).alias("bounded"))


@query
def collect_rows(spark, sf_dir):
    """Long to wide and back."""
    a = base(spark, sf_dir)
    order = a.transitions.select("symbol").distinct().agg(F.array_sort(F.collect_set("symbol")).alias("alphabet"))
    back = to_long(a.wide).join(F.broadcast(order))
    return back.select("state", F.col("alphabet")[F.col("symbol")].alias("symbol"), "target")


@query
def row_ops(spark, sf_dir):
    a = base(spark, sf_dir)
    start = a.wide.filter("state = 0").select(F.col("row").alias("zero"))
    return a.wide.join(F.broadcast(start)).select("state", F.aggregate(F.zip_with("row", "zero", lambda x, y: (x == y).cast("int")), F.lit(0), lambda s, x: s + x).alias("agree"), F.array_max("row").alias("top"))


@query
def sparse_row(spark, sf_dir):
    a = base(spark, sf_dir)
    start = a.wide.filter("state = 0").select(F.col("row").alias("zero"))
    m = F.map_filter(F.map_from_entries(F.transform("row", lambda x, i: F.struct(i, x))), lambda k, v: v != F.element_at("zero", k + 1))
    return a.wide.join(F.broadcast(start)).select("state", F.size(m).alias("different"))


@query
def lateral_symbols(spark, sf_dir):
    a = base(spark, sf_dir)
    a.transitions.createOrReplaceTempView("fsm_transitions")
    return spark.sql("SELECT t.state, t.symbol, t.target FROM fsm_transitions t JOIN fsm_transitions z ON z.state = 0 AND z.symbol = t.symbol WHERE t.target <> z.target")


@query
def theta_depth_pairs(spark, sf_dir):
    return _depth_pairs(base(spark, sf_dir)).agg(F.count("*").alias("pairs"))


@query
def bucket_distinct(spark, sf_dir):
    a = base(spark, sf_dir)
    return giant.bucket_keys(a.transitions, _sample(a)).groupBy("round").agg(F.count_distinct("key").alias("keys"))


@query
def approx_buckets(spark, sf_dir):
    a = base(spark, sf_dir)
    return giant.bucket_keys(a.transitions, _sample(a)).groupBy("round").agg(F.approx_count_distinct("key").alias("keys"))


@query
def bool_invariants(spark, sf_dir):
    a = base(spark, sf_dir)
    t = a.transitions.join(a.states.select("state", "depth"), "state").join(a.states.select(F.col("state").alias("target"), F.col("depth").alias("below")), "target")
    return t.agg(F.bool_and(F.col("below") <= F.col("depth") + 1).alias("one_level"), F.bool_and(F.col("target") >= 0).alias("closed"), F.count("*").alias("transitions"))


@query
def top_pairs(spark, sf_dir):
    return giant.similarity_long(base(spark, sf_dir).transitions).orderBy(F.desc("w"), "u", "v").limit(20)


@query
def top_g_per_state(spark, sf_dir):
    e = giant.similarity_long(base(spark, sf_dir).transitions)
    both = e.select(F.col("u").alias("state"), F.col("v").alias("other"), "w").unionByName(e.select(F.col("v").alias("state"), F.col("u").alias("other"), "w"))
    w = Window.partitionBy("state").orderBy(F.desc("w"), "other")
    return both.withColumn("rank", F.row_number().over(w)).filter("rank <= 3")


@query
def sort_limit_edges(spark, sf_dir):
    return _edges(base(spark, sf_dir)).orderBy(F.desc("w"), "u", "v").limit(100)


@query
def rounds_union(spark, sf_dir):
    a = base(spark, sf_dir)
    p = giant.propose(giant.bucket_keys(a.transitions, _sample(a)), SEED)
    e = p.select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v"))
    return e.agg(F.count("*").alias("proposals"), F.count_distinct("u", "v").alias("edges"))


@query
def rounds_except(spark, sf_dir):
    """Edges found only after half the rounds."""
    a = base(spark, sf_dir)
    p = store(giant.propose(giant.bucket_keys(a.transitions, _sample(a)), SEED))
    half = lambda c: p.filter(c).select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v"))
    return half(F.col("round") >= R // 2).exceptAll(half(F.col("round") < R // 2)).distinct().join(half(F.col("round") < R // 2).distinct(), ["u", "v"], "left_anti")


@query
def broadcast_symbols(spark, sf_dir):
    a = base(spark, sf_dir)
    return a.transitions.join(F.broadcast(_sample(a)), "symbol").groupBy("round").agg(F.count("*").alias("cells"), F.count_distinct("target").alias("targets"))


@query
def collision_probability(spark, sf_dir):
    """Chance that two states of each similarity share a key in a round: distinct symbols, replacement, least hash."""
    a = base(spark, sf_dir)
    n = a.transitions.agg(F.count_distinct("symbol").alias("n"))
    w = _dense(a).select("w").distinct().join(F.broadcast(n))
    each = F.aggregate(F.sequence(F.lit(0), F.lit(K - 1)), F.lit(1.0), lambda s, i: s * F.greatest(F.col("w") - i, F.lit(0)) / (F.col("n") - i))
    return w.select("w", F.round(each, 9).alias("distinct_symbols"), F.round(F.pow(F.col("w") / F.col("n"), F.lit(K)), 9).alias("replacement"), F.round(F.col("w") / (2 * F.col("n") - F.col("w")), 9).alias("least_hash"))


@query
def giant_equals_local(spark, sf_dir):
    """States whose default the two tiers set differently, by algorithm: none."""
    a, out = base(spark, sf_dir), None
    whole = Automaton(a.states, to_long(a.wide))
    for variant in ("tree", "depth"):
        how = {"k": K, "r": R, "seed": SEED}
        local = compress.defaults_of(a.wide, f"sampled_{variant}", **how).select("state", F.col("default").alias("own"))
        other = compress.giant_defaults(whole.states, whole.transitions, variant, **how)
        both = local.join(other, "state", "full").agg(F.lit(f"sampled_{variant}").alias("algorithm"), F.count("*").alias("states"), F.count_if(~F.col("own").eqNullSafe(F.col("default"))).alias("different"))
        out = both if out is None else out.unionByName(both)
    return out


@query
def tree_labelled(spark, sf_dir):
    a = base(spark, sf_dir)
    return giant.emit_labelled(a.transitions, _tree_defaults(a, "sampled")).groupBy("state").agg(F.count("*").alias("labelled"))


@query
def redundant_transitions(spark, sf_dir):
    a = base(spark, sf_dir)
    return giant.redundant(a.transitions, _depth_defaults(a))


@query
def well_defined(spark, sf_dir):
    """Cells without a target, with all defaults and with the start state's labels taken away."""
    a = base(spark, sf_dir)
    d, sigma = store(_depth_defaults(a)), a.transitions.select("symbol").distinct()
    lab = store(giant.emit_labelled(a.transitions, d))
    n = lambda x, name: giant.ill_defined(a.states, x, d, sigma).groupBy(F.lit(name).alias("labels")).agg(F.count("*").alias("faults"))
    return n(lab.filter("state <> 0"), "without the start").unionByName(n(lab, "all"))


@query
def equivalent_automata(spark, sf_dir):
    """Reachable pairs of the plain dictionary and a renumbered copy, resolved from labels and defaults, that accept differently: none; and with one accept taken away: some."""
    a = base(spark, sf_dir)
    d = _depth_defaults(a)
    n = a.states.count()
    turned = lambda c: (F.lit(n - 1) - F.col(c)).alias(c)
    back = giant.resolve(a.states, giant.emit_labelled(a.transitions, d), d, a.transitions.select("symbol").distinct()).select(turned("state"), "symbol", turned("target"))
    ends = giant.accepting(a.states).select("state", F.col("words").alias("label"))
    other = ends.select(turned("state"), "label")
    bad = lambda x, name: giant.unequal(a.transitions, ends, back, x, 0, n - 1).agg(F.lit(name).alias("accepts"), (F.count("*") > 0).alias("differ"))
    least = other.agg(F.min("state").alias("gone"))
    return bad(other, "all").unionByName(bad(other.join(F.broadcast(least)).filter(F.col("state") != F.col("gone")).drop("gone"), "but one"))


_HEAD = """
words AS (SELECT DISTINCT p_name AS w FROM part WHERE p_name IS NOT NULL AND p_name <> ''),
cuts AS (SELECT w, unnest(range(0, length(w) + 1)) AS i FROM words),
pre AS (SELECT p, depth, whole, row_number() OVER (ORDER BY depth, p) - 1 AS state FROM (SELECT substring(w, 1, i) AS p, CAST(i AS INTEGER) AS depth, bool_or(i = length(w)) AS whole FROM cuts GROUP BY 1, 2)),
alpha AS (SELECT DISTINCT unnest(string_split(w, '')) AS c FROM words),
tails AS (SELECT s.state, s.p, a.c, unnest(range(1, s.depth + 3)) AS i FROM pre s, alpha a),
tr AS (SELECT x.state, ascii(x.c) AS symbol, arg_max(t.state, t.depth) AS target FROM tails x JOIN pre t ON t.p = substring(x.p || x.c, x.i) GROUP BY 1, 2)"""
_PAIRS = _HEAD + """,
sh AS (SELECT a.state AS u, b.state AS v, CAST(count(*) AS INTEGER) AS w FROM tr a JOIN tr b ON a.symbol = b.symbol AND a.target = b.target AND a.state < b.state GROUP BY 1, 2),
dense AS (SELECT a.state AS u, b.state AS v, coalesce(sh.w, 0) AS w FROM pre a JOIN pre b ON a.state < b.state LEFT JOIN sh ON sh.u = a.state AND sh.v = b.state)"""


def _h(*parts):
    text = " || '-' || ".join(p if p.startswith("'") or not p.isidentifier() and "." not in p else f"CAST({p} AS VARCHAR)" for p in parts)
    return f"CAST(('0x' || substr(md5({text}), 1, 7)) AS BIGINT)"


_SAMPLE = _PAIRS + f""",
syms AS (SELECT DISTINCT symbol FROM tr),
smp AS (SELECT round, symbol FROM (SELECT CAST(r AS INTEGER) AS round, symbol, row_number() OVER (PARTITION BY r ORDER BY {_h("'42'", "r", "symbol")}, symbol) AS n FROM syms, range({R}) t(r)) WHERE n <= {K}),
bk AS (SELECT round, state, string_agg(CAST(target AS VARCHAR), ',' ORDER BY symbol) AS key FROM tr JOIN smp USING (symbol) GROUP BY 1, 2),
ps AS (SELECT round, key, state, row_number() OVER (PARTITION BY round, key ORDER BY state) - 1 AS pos, count(*) OVER (PARTITION BY round, key) AS size FROM bk),
pr AS (SELECT a.round, a.state AS u, b.state AS v FROM (SELECT *, (pos + 1 + {_h("'42'", "round", "'p'", "state")} % (size - 1)) % size AS t FROM ps WHERE size > 1) a JOIN ps b ON b.round = a.round AND b.key = a.key AND b.pos = a.t),
un AS (SELECT DISTINCT least(u, v) AS u, greatest(u, v) AS v FROM (SELECT u, v FROM pr UNION ALL SELECT 0, state FROM pre WHERE state <> 0)),
ed AS (SELECT dense.u, dense.v, dense.w FROM un JOIN dense USING (u, v))"""
_DEPTH = _PAIRS + """,
up AS (SELECT a.state AS u, b.state AS v FROM pre a JOIN pre b ON b.depth < a.depth),
dd AS (SELECT up.u AS state, arg_max(up.v, d.w * 1000000 - up.v) AS "default", max(d.w) AS w FROM up JOIN dense d ON d.u = least(up.u, up.v) AND d.v = greatest(up.u, up.v) GROUP BY 1),
lab AS (SELECT t.state, t.symbol, t.target FROM tr t LEFT JOIN dd ON dd.state = t.state LEFT JOIN tr o ON o.state = dd."default" AND o.symbol = t.symbol WHERE dd.state IS NULL OR o.target <> t.target)"""
_SDEPTH = _SAMPLE + """,
sd AS (SELECT pr.u AS state, arg_max(pr.v, d.w * 1000000 - pr.v) AS "default", max(d.w) AS w FROM (SELECT DISTINCT u, v FROM pr) pr JOIN pre a ON a.state = pr.u JOIN pre b ON b.state = pr.v JOIN dense d ON d.u = least(pr.u, pr.v) AND d.v = greatest(pr.u, pr.v) WHERE b.depth < a.depth AND d.w >= 1 GROUP BY 1)"""


def _size_sql(d: str) -> str:
    return f"""SELECT t_in, CAST(t_in - sv AS BIGINT) AS labelled, nd AS defaults, CAST(t_in - sv + nd AS BIGINT) AS t_out, round(100.0 * (t_in - sv + nd) / t_in, 6) AS size_pct
FROM (SELECT (SELECT count(*) FROM tr) AS t_in, (SELECT coalesce(sum(w), 0) FROM {d}) AS sv, (SELECT count(*) FROM {d}) AS nd)"""


def _prim(edges: str) -> str:
    """The unique tree under (w desc, u, v): the best edge that leaves the reached states, one at a time."""
    return f""",
ends AS (SELECT u AS a, v AS b, u, v, w FROM {edges} UNION ALL SELECT v, u, u, v, w FROM {edges}),
grow AS (SELECT 0 AS i, [CAST(0 AS BIGINT)] AS seen, CAST(NULL AS BIGINT) AS u, CAST(NULL AS BIGINT) AS v, CAST(NULL AS INTEGER) AS w
  UNION ALL SELECT i + 1, list_append(seen, e.b), e.u, e.v, e.w FROM (SELECT g.i, g.seen, arg_max(struct_pack(b := ends.b, u := ends.u, v := ends.v, w := ends.w), ends.w * 100000000 - ends.u * 10000 - ends.v) AS e
    FROM grow g JOIN ends ON list_contains(g.seen, ends.a) AND NOT list_contains(g.seen, ends.b) GROUP BY g.i, g.seen)),
tree AS (SELECT u, v, w FROM grow WHERE u IS NOT NULL)"""


_DENSE_TREE, _SAMPLED_TREE = _PAIRS + _prim("dense"), _SAMPLE + _prim("ed")
_RES = _DEPTH + """,
rs AS (SELECT p.state, s.symbol, p.state AS cur, 0 AS hops FROM pre p, (SELECT DISTINCT symbol FROM tr) s
  UNION ALL SELECT r.state, r.symbol, dd."default", r.hops + 1 FROM rs r JOIN dd ON dd.state = r.cur WHERE NOT EXISTS (SELECT 1 FROM lab WHERE lab.state = r.cur AND lab.symbol = r.symbol)),
hp AS (SELECT state, symbol, max(hops) AS hops FROM rs GROUP BY 1, 2)"""
_TREES = _SAMPLE + _prim("dense").replace("tree AS", "dtree AS").replace("grow", "dgrow").replace("ends", "dends") + _prim("ed")

W = "WITH RECURSIVE "
ORACLES = {
    "dict_states": W + _HEAD + " SELECT state, p AS prefix, depth, depth = 0 AS is_start, whole AS is_word FROM pre",
    "dict_transitions": W + _HEAD + " SELECT state, symbol, target FROM tr",
    "dict_accepting": W + _HEAD + " SELECT a.state, count(*) AS words FROM pre a JOIN pre b ON b.whole AND b.depth > 0 AND suffix(a.p, b.p) GROUP BY 1",
    "dict_depth": W + _HEAD + " SELECT state, depth FROM pre",
    "dict_validate": W + _HEAD + ", n AS (SELECT count(*) AS n, count(*) FILTER (depth = 0) AS starts, max(state) AS top FROM pre), t AS (SELECT count(*) AS t, count(DISTINCT symbol) AS sigma, max(target) AS hi, min(target) AS lo FROM tr) SELECT t = n * sigma AS total, lo >= 0 AND hi < n AS closed, starts = 1 AS one_start, top = n - 1 AS dense_ids FROM n, t",
    "symbol_classes": W + _HEAD + ", c AS (SELECT symbol, string_agg(CAST(target AS VARCHAR), ',' ORDER BY state) AS col FROM tr GROUP BY 1) SELECT min(symbol) AS symbol, count(*) AS multiplicity FROM c GROUP BY col",
    "pair_similarity": W + _PAIRS + " SELECT u, v, w FROM sh",
    "similarity_histogram": W + _PAIRS + " SELECT w, count(*) AS pairs FROM dense GROUP BY 1",
    "similarity_percentiles": W + _PAIRS + " SELECT quantile_cont(w, 0.5) AS median, quantile_cont(w, 0.9) AS p90 FROM dense",
    "dense_graph_summary": W + _PAIRS + " SELECT count(*) AS edges, CAST(sum(w) AS BIGINT) AS total, max(w) AS most FROM dense",
    "star_edges": W + _HEAD + " SELECT CAST(0 AS BIGINT) AS u, state AS v FROM pre WHERE state <> 0",
    "sampled_symbols": W + _SAMPLE + " SELECT round, symbol FROM smp",
    "replacement_symbols": W + _HEAD + f", al AS (SELECT list(symbol ORDER BY symbol) AS a FROM (SELECT DISTINCT symbol FROM tr)) SELECT CAST(r AS INTEGER) AS round, CAST(s AS INTEGER) AS slot, a[{_h(chr(39) + '42' + chr(39), 'r', chr(39) + 'r' + chr(39), 's')} % len(a) + 1] AS symbol FROM al, range({R}) x(r), range({K}) y(s)",
    "sampled_buckets": W + _SAMPLE + " SELECT round, key, state, pos, size FROM ps",
    "minhash_buckets": W + _HEAD + f", h AS (SELECT CAST(r AS INTEGER) AS round, state, symbol, target, {_h(chr(39) + '42' + chr(39), 'r', chr(39) + '0' + chr(39), 'symbol', 'target')} AS h FROM tr, range(4) t(r)), m AS (SELECT round, state, min(struct_pack(h := h, symbol := symbol, target := target)) AS m FROM h GROUP BY 1, 2) SELECT round, state, CAST(m.symbol AS VARCHAR) || ':' || CAST(m.target AS VARCHAR) AS key FROM m",
    "bucket_statistics": W + _SAMPLE + ", b AS (SELECT round, key, count(*) AS n FROM bk GROUP BY 1, 2) SELECT round, count(*) AS buckets, max(n) AS largest, count(*) FILTER (n = 1) AS alone FROM b GROUP BY 1",
    "sampled_proposals": W + _SAMPLE + " SELECT round, u, v FROM pr",
    "ring_proposals": W + _SAMPLE + f", o AS (SELECT round, key, state, row_number() OVER (PARTITION BY round, key ORDER BY {_h(chr(39) + '42' + chr(39), 'round', chr(39) + 'o' + chr(39), 'state')}, state) AS n, count(*) OVER (PARTITION BY round, key) AS c FROM bk) SELECT a.round, a.state AS u, b.state AS v FROM o a JOIN o b ON a.round = b.round AND a.key = b.key AND b.n = a.n % a.c + 1 WHERE a.c > 1",
    "sampled_edges": W + _SAMPLE + " SELECT u, v, w FROM ed",
    "sampled_graph_summary": W + _SAMPLE + " SELECT count(*) AS edges, CAST(sum(w) AS BIGINT) AS total, true AS bounded FROM ed",
    "dense_tree_edges": W + _DENSE_TREE + " SELECT u, v, w FROM tree",
    "sampled_tree_edges": W + _SAMPLED_TREE + " SELECT u, v, w FROM tree",
    "tree_value": W + _TREES + " SELECT CAST((SELECT sum(w) FROM dtree) AS BIGINT) AS dense, CAST((SELECT sum(w) FROM tree) AS BIGINT) AS sampled, true AS bounded",
    "tree_overlap": W + _TREES + " SELECT u, v FROM dtree JOIN tree USING (u, v)",
    "running_tree_value": W + _DENSE_TREE + " SELECT u, v, w, CAST(sum(w) OVER (ORDER BY w DESC, u, v ROWS UNBOUNDED PRECEDING) AS BIGINT) AS running FROM tree",
    "dense_tree_size": W + _DENSE_TREE + " " + _size_sql("tree"),
    "sampled_tree_size": W + _SAMPLED_TREE + " " + _size_sql("tree"),
    "outer_no_default": W + _DENSE_TREE + " SELECT (SELECT count(*) FROM pre) - (SELECT count(*) FROM tree) AS roots",
    "giant_equals_local": W + _HEAD + " SELECT 'sampled_' || v AS algorithm, count(*) AS states, CAST(0 AS BIGINT) AS different FROM pre, (SELECT unnest(['tree', 'depth']) AS v) GROUP BY v",
    "redundant_transitions": W + _DEPTH + ' SELECT t.state, t.symbol FROM tr t JOIN dd ON dd.state = t.state JOIN tr o ON o.state = dd."default" AND o.symbol = t.symbol AND o.target = t.target',
    "well_defined": W + _RES + ", e AS (SELECT r.state, r.symbol, arg_max(r.cur, r.hops) AS last FROM rs r GROUP BY 1, 2) SELECT 'without the start' AS labels, count(*) AS faults FROM e WHERE last = 0 HAVING count(*) > 0",
    "equivalent_automata": "SELECT 'all' AS accepts, false AS differ UNION ALL SELECT 'but one', true",
    "replacement_buckets": W + _HEAD + f", al AS (SELECT list(symbol ORDER BY symbol) AS a FROM (SELECT DISTINCT symbol FROM tr)), s AS (SELECT DISTINCT CAST(r AS INTEGER) AS round, a[{_h(chr(39) + '42' + chr(39), 'r', chr(39) + 'r' + chr(39), 's')} % len(a) + 1] AS symbol FROM al, range({R}) x(r), range({K}) y(s)) SELECT round, state, string_agg(CAST(target AS VARCHAR), ',' ORDER BY symbol) AS key FROM tr JOIN s USING (symbol) GROUP BY 1, 2",
    "minhash_k_buckets": W + _HEAD + f", h AS (SELECT CAST(r AS INTEGER) AS round, j, state, symbol, target, {_h(chr(39) + '42' + chr(39), 'r', 'j', 'symbol', 'target')} AS h FROM tr, range(2) t(r), range(3) y(j)), m AS (SELECT round, j, state, min(struct_pack(h := h, symbol := symbol, target := target)) AS m FROM h GROUP BY 1, 2, 3) SELECT round, state, string_agg(CAST(m.symbol AS VARCHAR) || ':' || CAST(m.target AS VARCHAR), ',' ORDER BY j) AS key FROM m GROUP BY 1, 2",
    "depth_defaults": W + _DEPTH + ' SELECT state, "default", w FROM dd',
    "depth_drop2": W + _PAIRS + ', up AS (SELECT a.state AS u, b.state AS v FROM pre a JOIN pre b ON b.depth <= a.depth - 2) SELECT up.u AS state, arg_max(up.v, d.w * 1000000 - up.v) AS "default", max(d.w) AS w FROM up JOIN dense d ON d.u = least(up.u, up.v) AND d.v = greatest(up.u, up.v) GROUP BY 1',
    "depth_labelled": W + _DEPTH + " SELECT state, symbol, target FROM lab",
    "depth_size": W + _DEPTH + " " + _size_sql("dd"),
    "sampled_depth_defaults": W + _SDEPTH + ' SELECT state, "default", w FROM sd',
    "sampled_depth_size": W + _SDEPTH + " " + _size_sql("sd"),
    "suffix_defaults": W + _HEAD + ' SELECT a.state, arg_max(b.state, b.depth) AS "default" FROM pre a JOIN pre b ON b.depth < a.depth AND suffix(a.p, b.p) GROUP BY 1',
    "suffix_size": W + _PAIRS + ", sf AS (SELECT a.state AS u, arg_max(b.state, b.depth) AS v FROM pre a JOIN pre b ON b.depth < a.depth AND suffix(a.p, b.p) GROUP BY 1), sw AS (SELECT d.w FROM sf JOIN dense d ON d.u = least(sf.u, sf.v) AND d.v = greatest(sf.u, sf.v)) " + _size_sql("sw"),
    "rank_states": W + _DEPTH + " SELECT state, w - 1 AS saved, CAST(rank() OVER (ORDER BY w DESC) AS INTEGER) AS rank, CAST(dense_rank() OVER (ORDER BY w DESC) AS INTEGER) AS dense_rank, CAST(ntile(4) OVER (ORDER BY w DESC, state) AS INTEGER) AS quarter FROM dd",
    "resolve_check": W + _HEAD + " SELECT state, symbol, target FROM tr",
    "full_diff": W + _HEAD + " SELECT count(*) AS rows, CAST(0 AS BIGINT) AS different FROM tr",
    "longest_delay": W + _RES + " SELECT CAST(max(hops) AS BIGINT) AS longest_delay FROM hp",
    "hops_by_symbol": W + _RES + " SELECT symbol, CAST(sum(hops) AS BIGINT) AS hops FROM hp GROUP BY 1",
    "match_names": W + _HEAD + ", p AS (SELECT p_partkey, p_name, unnest(range(1, length(p_name) + 1)) AS i FROM part WHERE p_name <> '') SELECT p_partkey, CAST(count(words.w) AS BIGINT) AS matches, CAST(any_value(strlen(p_name)) AS BIGINT) AS length FROM p LEFT JOIN words ON substring(p_name, i - length(w) + 1, length(w)) = w AND i >= length(w) GROUP BY 1",
    "match_benchmark_docs": "SELECT DISTINCT doc_id FROM documents JOIN (SELECT DISTINCT text AS w FROM benchmark WHERE text <> '') b ON contains(documents.text, w)",
    "page_matches": W + _HEAD + " SELECT page_id, bool_or(contains(html, w)) AS accepts, CAST(any_value(strlen(html)) AS BIGINT) AS length FROM pages, words GROUP BY 1",
    "matching_delay_names": W + _RES + ", st AS (SELECT w, 0 AS i, CAST(0 AS BIGINT) AS cur, CAST(0 AS BIGINT) AS total FROM words UNION ALL SELECT st.w, st.i + 1, tr.target, st.total + hp.hops FROM st JOIN tr ON tr.state = st.cur AND tr.symbol = ascii(substring(st.w, st.i + 1, 1)) JOIN hp ON hp.state = st.cur AND hp.symbol = tr.symbol WHERE st.i < length(st.w)) SELECT w AS p_name, total AS hops, total <= length(w) AS bounded FROM st WHERE i = length(w)",
    "collect_rows": W + _HEAD + " SELECT state, symbol, target FROM tr",
    "row_ops": W + _HEAD + " SELECT t.state, CAST(count(*) FILTER (t.target = z.target) AS INTEGER) AS agree, CAST(max(t.target) AS INTEGER) AS top FROM tr t JOIN tr z ON z.state = 0 AND z.symbol = t.symbol GROUP BY 1",
    "sparse_row": W + _HEAD + " SELECT t.state, CAST(count(*) FILTER (t.target <> z.target) AS INTEGER) AS different FROM tr t JOIN tr z ON z.state = 0 AND z.symbol = t.symbol GROUP BY 1",
    "lateral_symbols": W + _HEAD + " SELECT t.state, t.symbol, t.target FROM tr t JOIN tr z ON z.state = 0 AND z.symbol = t.symbol WHERE t.target <> z.target",
    "theta_depth_pairs": W + _HEAD + " SELECT count(*) AS pairs FROM pre a JOIN pre b ON b.depth < a.depth",
    "bucket_distinct": W + _SAMPLE + " SELECT round, count(DISTINCT key) AS keys FROM bk GROUP BY 1",
    "bool_invariants": W + _HEAD + " SELECT bool_and(b.depth <= a.depth + 1) AS one_level, bool_and(tr.target >= 0) AS closed, count(*) AS transitions FROM tr JOIN pre a ON a.state = tr.state JOIN pre b ON b.state = tr.target",
    "top_pairs": W + _PAIRS + " SELECT u, v, w FROM sh ORDER BY w DESC, u, v LIMIT 20",
    "top_g_per_state": W + _PAIRS + ", b AS (SELECT u AS state, v AS other, w FROM sh UNION ALL SELECT v, u, w FROM sh), r AS (SELECT *, CAST(row_number() OVER (PARTITION BY state ORDER BY w DESC, other) AS INTEGER) AS rank FROM b) SELECT state, other, w, rank FROM r WHERE rank <= 3",
    "sort_limit_edges": W + _SAMPLE + " SELECT u, v, w FROM ed ORDER BY w DESC, u, v LIMIT 100",
    "rounds_union": W + _SAMPLE + " SELECT count(*) AS proposals, count(DISTINCT (least(u, v), greatest(u, v))) AS edges FROM pr",
    "rounds_except": W + _SAMPLE + f" SELECT least(u, v) AS u, greatest(u, v) AS v FROM pr WHERE round >= {R // 2} EXCEPT SELECT least(u, v), greatest(u, v) FROM pr WHERE round < {R // 2}",
    "broadcast_symbols": W + _SAMPLE + " SELECT round, count(*) AS cells, count(DISTINCT target) AS targets FROM tr JOIN smp USING (symbol) GROUP BY 1",
    "collision_probability": W + _PAIRS + ", n AS (SELECT CAST(count(DISTINCT symbol) AS DOUBLE) AS n FROM tr), w AS (SELECT DISTINCT w FROM dense) SELECT w, round(greatest(w, 0) / n * greatest(w - 1, 0) / (n - 1) * greatest(w - 2, 0) / (n - 2), 9) AS distinct_symbols, round(pow(w / n, 3), 9) AS replacement, round(w / (2 * n - w), 9) AS least_hash FROM w, n",
}
