"""Relational forms of the methods, for automata whose rows don't fit one task.

Every step is a DataFrame plan; iterations cut lineage by tables in the shared folder.  Choices
are keyed hashes: ``fast_*`` take xxhash64 of (seed, round, id), as the array kernels do, so both
tiers draw the same partners; the others are ``portable``, md5 of the ids' text, which any SQL
engine computes alike.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .scratch import drop, store


def digest(*parts) -> Column:
    """First 28 bits of md5 over the parts joined by '-'."""
    text = F.concat_ws("-", *[p.cast("string") if isinstance(p, Column) else F.lit(str(p)) for p in parts])
    return F.conv(F.substring(F.md5(text), 1, 7), 16, 10).cast("long")


# Construction


def dictionary_states(words: DataFrame, *, automaton_id: str = "dict") -> DataFrame:
    """state, prefix, depth, is_start, is_accept: a state per distinct prefix, numbered by length and then text."""
    from .model import numbered

    words = words.select(F.col("word").cast("string").alias("word")).filter("word is not null and word <> ''").distinct()
    cut = words.select("word", F.explode(F.sequence(F.lit(0), F.length("word"))).alias("depth"))
    prefixes = cut.groupBy(F.expr("substring(word, 1, depth)").alias("prefix"), "depth").agg(F.bool_or(F.col("depth") == F.length("word")).alias("whole"))
    n = numbered(prefixes, ["depth", "prefix"], "state")
    return n.select(F.lit(automaton_id).alias("automaton_id"), "state", "prefix", "depth", (F.col("depth") == 0).alias("is_start"), "whole")


def dictionary_transitions(states: DataFrame, alphabet: DataFrame | None = None) -> DataFrame:
    """automaton_id, state, symbol, target: the longest suffix of prefix + symbol that is a prefix."""
    if alphabet is None:
        alphabet = states.select(F.explode(F.split("prefix", "")).alias("c")).filter("c <> ''").distinct()  # characters of the words
    p = states.select("automaton_id", "state", "prefix")
    wide = p.join(F.broadcast(alphabet), how="cross").select("automaton_id", "state", F.ascii("c").cast("int").alias("symbol"), F.concat("prefix", "c").alias("text"))
    tails = wide.select("automaton_id", "state", "symbol", "text", F.explode(F.sequence(F.lit(1), F.length("text") + 1)).alias("i"))
    tails = tails.select("automaton_id", "state", "symbol", F.expr("substring(text, i)").alias("prefix"))
    hit = tails.join(p.select(F.col("state").alias("target"), "prefix"), "prefix")
    return hit.groupBy("automaton_id", "state", "symbol").agg(F.max_by("target", F.length("prefix")).alias("target"))


def accepting(states: DataFrame) -> DataFrame:
    """state, words: the words that end wherever the state is reached."""
    tails = states.select("automaton_id", "state", "prefix", F.explode(F.sequence(F.lit(1), F.length("prefix") + 1)).alias("i")).select("automaton_id", "state", F.expr("substring(prefix, i)").alias("prefix"))
    return tails.join(states.filter("whole and depth > 0").select("prefix"), "prefix").groupBy("automaton_id", "state").agg(F.count("*").alias("words"))


def bfs_depth(transitions: DataFrame, start: int = 0, most: int = 1000, cut_every: int = 8) -> DataFrame:
    """state, depth by a frontier of joins."""
    hops = store(transitions.select("state", "target").distinct())
    seen = front = hops.select(F.lit(start).cast("long").alias("state"), F.lit(0).alias("depth")).limit(1)
    for d in range(1, most):
        nxt = front.select("state").join(hops, "state").select(F.col("target").alias("state")).distinct().join(seen.select("state"), "state", "left_anti")
        front = store(nxt.withColumn("depth", F.lit(d)))
        if front.isEmpty():
            return seen
        seen = seen.unionByName(front)
        if d % cut_every == 0:
            seen = store(seen)
    raise RuntimeError(f"bfs_depth: no end after {most} levels")


# Similarity and graphs


def similarity_long(transitions: DataFrame) -> DataFrame:
    """u < v, w: pairs that share a transition, by a self-join on (symbol, target)."""
    a, b = transitions.alias("a"), transitions.alias("b")
    return a.join(b, (F.col("a.symbol") == F.col("b.symbol")) & (F.col("a.target") == F.col("b.target")) & (F.col("a.state") < F.col("b.state"))).groupBy(F.col("a.state").alias("u"), F.col("b.state").alias("v")).agg(F.count("*").cast("int").alias("w"))


def pair_similarity(rows: DataFrame, pairs: DataFrame) -> DataFrame:
    """u, v, w of given pairs; rows: state, row (array).  Two equi-joins bring the rows, the comparison is one expression."""
    left = pairs.join(rows.select(F.col("state").alias("u"), F.col("row").alias("x")), "u")
    both = left.join(rows.select(F.col("state").alias("v"), F.col("row").alias("y")), "v")
    same = F.aggregate(F.zip_with("x", "y", lambda a, b: (a == b).cast("int")), F.lit(0), lambda s, x: s + x)
    return both.select("u", "v", same.alias("w"))


def star_edges(states: DataFrame, start: int = 0) -> DataFrame:
    return states.filter(F.col("state") != start).select(F.lit(start).cast("long").alias("u"), F.col("state").alias("v"))


def sample_symbols(symbols: DataFrame, k: int, rounds: int, seed: int, sampler: str = "distinct") -> DataFrame:
    """round, symbol[, slot]: k symbols for each round, portable choice."""
    each = symbols.select("symbol").crossJoin(symbols.sparkSession.range(rounds).select(F.col("id").cast("int").alias("round"))) if sampler == "distinct" else None  # alphabet x rounds
    if sampler == "distinct":
        w = Window.partitionBy("round").orderBy(digest(seed, F.col("round"), F.col("symbol")), "symbol")
        return each.withColumn("n", F.row_number().over(w)).filter(F.col("n") <= k).select("round", "symbol")
    listed = symbols.agg(F.array_sort(F.collect_set("symbol")).alias("all"))  # the alphabet
    slots = symbols.sparkSession.range(rounds * k).select((F.col("id") / k).cast("int").alias("round"), (F.col("id") % k).cast("int").alias("slot"))
    return slots.join(F.broadcast(listed)).select("round", "slot", F.expr("all")[(digest(seed, F.col("round"), F.lit("r"), F.col("slot")) % F.size("all")).cast("int")].alias("symbol"))


def bucket_keys(transitions: DataFrame, sample: DataFrame) -> DataFrame:
    """round, state, key: the targets on the round's symbols, in order of the symbols.  The sample is small and broadcast."""
    hit = transitions.join(F.broadcast(sample.select("round", "symbol").distinct()), "symbol")
    return hit.groupBy("round", "state").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("symbol", "target"))), lambda x: x["target"].cast("string")), ",").alias("key"))


def minhash_keys(transitions: DataFrame, rounds: int, seed: int, functions: int = 1) -> DataFrame:
    """round, state, key: least portable hash of the (symbol, target) pairs, by 1 or more permutations."""
    r = transitions.sparkSession.range(rounds * functions).select((F.col("id") / functions).cast("int").alias("round"), (F.col("id") % functions).cast("int").alias("j"))
    hashed = transitions.join(F.broadcast(r)).groupBy("round", "j", "state").agg(F.min(F.struct(digest(seed, F.col("round"), F.col("j"), F.col("symbol"), F.col("target")).alias("h"), "symbol", "target")).alias("m"))
    part = F.concat_ws(":", F.col("m.symbol").cast("string"), F.col("m.target").cast("string"))
    return hashed.groupBy("round", "state").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("j", part.alias("p")))), lambda x: x["p"]), ",").alias("key"))


def positions(buckets: DataFrame, parts: int = 1) -> DataFrame:
    """pos (0-based) and size of every state in its bucket.  A giant bucket is numbered in ``parts``
    hashed parts, whose offsets come from a small aggregate; ``parts`` of 1 numbers by state."""
    if parts == 1:
        w = Window.partitionBy("round", "key").orderBy("state")
        return buckets.withColumn("pos", (F.row_number().over(w) - 1).cast("long")).withColumn("size", F.count("*").over(Window.partitionBy("round", "key")))
    salted = buckets.withColumn("salt", F.pmod(F.xxhash64("state"), F.lit(parts)))
    sizes = salted.groupBy("round", "key", "salt").count()
    w = Window.partitionBy("round", "key").orderBy("salt")
    offsets = sizes.withColumn("offset", F.sum("count").over(w) - F.col("count")).withColumn("size", F.sum("count").over(Window.partitionBy("round", "key"))).drop("count")
    local = salted.withColumn("n", F.row_number().over(Window.partitionBy("round", "key", "salt").orderBy("state")) - 1)
    return local.join(offsets, ["round", "key", "salt"]).select("round", "key", "state", (F.col("n") + F.col("offset")).cast("long").alias("pos"), "size")


def propose(buckets: DataFrame, seed: int, *, parts: int = 1) -> DataFrame:
    """round, u, v (directed): each state draws another member of its bucket.  The join key (round, key, position) is unique, so a giant bucket doesn't skew it."""
    at = positions(buckets, parts).filter("size > 1")
    drawn = at.withColumn("to", (F.col("pos") + 1 + digest(seed, F.col("round"), F.lit("p"), F.col("state")) % (F.col("size") - 1)) % F.col("size"))
    mate = at.select("round", "key", F.col("pos").alias("to"), F.col("state").alias("v"))
    return drawn.join(mate, ["round", "key", "to"]).select("round", F.col("state").alias("u"), "v")


def ring(buckets: DataFrame, seed: int, parts: int = 1) -> DataFrame:
    """round, u, v: the successor in a keyed order of the bucket (a part of it), the last one taking the first."""
    salted = buckets.withColumn("salt", F.pmod(F.xxhash64("state"), F.lit(parts)))
    w = Window.partitionBy("round", "key", "salt").orderBy(digest(seed, F.col("round"), F.lit("o"), F.col("state")), "state")
    first = F.first("state").over(w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    return salted.select("round", F.col("state").alias("u"), F.coalesce(F.lead("state").over(w), first).alias("v")).filter("u <> v")


def fast_buckets(rows: DataFrame, samples: DataFrame, seed: int, sampler: str = "distinct") -> DataFrame:
    """round, state, key of wide rows: one expression per row and round, no aggregation.  samples: round, at (positions in the row); small and broadcast."""
    each = rows.select("state", "row").join(F.broadcast(samples))
    if not sampler.startswith("minhash"):
        return each.select("round", "state", F.xxhash64(F.transform("at", lambda x: F.get("row", x))).alias("key"))
    pair = F.transform("row", lambda t, i: t.cast("long") + F.shiftleft(i.cast("long"), 40))
    least = lambda j: F.array_min(F.transform(pair, lambda x: F.xxhash64(F.lit(seed).cast("long"), "round", j.cast("long"), x)))
    k = F.lit(1) if sampler == "minhash1" else F.size("at")
    return each.select("round", "state", F.xxhash64(F.transform(F.sequence(F.lit(0), k - 1), least)).alias("key"))


def fast_proposals(buckets: DataFrame, seed: int, n: int, *, pairing: str = "uniform", parts: int = 64) -> DataFrame:
    """u, v (directed), round: the partners that the array kernels draw.

    States stand in a bucket in order of their number (ring: of their hash).  A giant bucket is
    numbered in ``parts`` ranges of that order, whose offsets come from a small aggregate; the
    join key (round, key, position) is unique."""
    hashed = F.xxhash64(F.lit(seed).cast("long"), "round", "state")
    order = hashed if pairing == "ring" else F.col("state")
    part = F.floor((F.shiftright(order, 33) + (1 << 30)) * parts / (1 << 31)) if pairing == "ring" else F.floor(F.col("state") * parts / max(n, 1))
    b = buckets.withColumn("o", order).withColumn("part", part.cast("long"))
    sizes = b.groupBy("round", "key", "part").agg(F.count("*").alias("own"))
    w = Window.partitionBy("round", "key").orderBy("part")
    sizes = sizes.withColumn("offset", F.sum("own").over(w) - F.col("own")).withColumn("size", F.sum("own").over(Window.partitionBy("round", "key")))
    local = b.withColumn("r", F.row_number().over(Window.partitionBy("round", "key", "part").orderBy("o", "state")) - 1)
    at = local.join(sizes.filter("size > 1"), ["round", "key", "part"]).select("round", "key", "state", (F.col("r") + F.col("offset")).alias("pos"), "size")
    step = F.lit(0) if pairing == "ring" else F.pmod(hashed, F.greatest(F.col("size") - 1, F.lit(1)))
    mate = at.select("round", "key", F.col("pos").alias("to"), F.col("state").alias("v"))
    return at.withColumn("to", (F.col("pos") + 1 + step) % F.col("size")).join(mate, ["round", "key", "to"]).select("round", F.col("state").alias("u"), "v")


def undirected(pairs: DataFrame) -> DataFrame:
    return pairs.select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).distinct()


def sampled_graph(states: DataFrame, transitions: DataFrame, rows: DataFrame, *, k: int, r: int, seed: int = 42, start: int = 0, star: bool = True, parts: int = 1) -> DataFrame:
    """u < v, w: the star and the proposals of r rounds, weighed."""
    sample = sample_symbols(transitions.select("symbol").distinct(), k, r, seed)
    pairs = propose(bucket_keys(transitions, sample), seed, parts=parts).select("u", "v")
    if star:
        pairs = pairs.unionByName(star_edges(states, start))
    return pair_similarity(rows, undirected(pairs))


# Trees


def spanning_forest(edges: DataFrame, most: int = 64) -> DataFrame:
    """u, v, w of the unique maximum spanning forest (w desc, u, v), by rounds in which every component takes its best edge.

    A round: best edge by an associative max, components merged by pointer jumping, edges
    relabelled and reduced to the best one per pair of components."""
    live = store(edges.filter("u <> v").select("u", "v", "w", F.col("u").alias("cu"), F.col("v").alias("cv")))
    out = live.select("u", "v", "w").limit(0)
    rank = lambda: F.struct(F.col("w").alias("w"), (-F.col("u")).alias("a"), (-F.col("v")).alias("b"), "u", "v", "cu", "cv")
    for _ in range(most):
        if live.isEmpty():
            return out
        ends = live.select(F.col("cu").alias("c"), rank().alias("e")).unionByName(live.select(F.col("cv").alias("c"), rank().alias("e")))
        best = store(ends.groupBy("c").agg(F.max("e").alias("e")))
        out = store(out.unionByName(best.select("e.u", "e.v", "e.w").distinct()))
        up = best.select("c", F.when(F.col("e.cu") == F.col("c"), F.col("e.cv")).otherwise(F.col("e.cu")).alias("p"))
        back = up.select(F.col("c").alias("p"), F.col("p").alias("pp"))
        up = up.join(back, "p", "left").select("c", F.when((F.col("pp") == F.col("c")) & (F.col("c") < F.col("p")), F.col("c")).otherwise(F.col("p")).alias("p"))
        up = store(up)
        for _ in range(most):
            back = up.select(F.col("c").alias("p"), F.col("p").alias("pp"))
            nxt = store(up.join(back, "p", "left").select("c", F.coalesce("pp", "p").alias("p"), (F.coalesce("pp", "p") != F.col("p")).alias("moved")))
            moved = not nxt.filter("moved").isEmpty()
            up = nxt.select("c", "p")
            if not moved:
                break
        a, b = up.select(F.col("c").alias("cu"), F.col("p").alias("pu")), up.select(F.col("c").alias("cv"), F.col("p").alias("pv"))
        joined = live.join(a, "cu").join(b, "cv").filter("pu <> pv")
        lo, hi = F.least("pu", "pv"), F.greatest("pu", "pv")
        nxt = joined.select("u", "v", "w", lo.alias("cu"), hi.alias("cv"))
        nxt = nxt.groupBy("cu", "cv").agg(F.max(rank()).alias("e")).select("e.u", "e.v", "e.w", "e.cu", "e.cv")
        old, live = live, store(nxt)
        drop(old)
    raise RuntimeError("spanning_forest: no end")


def orient(edges: DataFrame, states: DataFrame, most: int = 100_000) -> DataFrame:
    """state, parent (null at the centre): leaves are taken off layer by layer; what is left last is the centre (the lesser of two)."""
    live = store(edges.select("u", "v"))
    done = None
    for _ in range(most):
        if live.isEmpty():
            break
        ends = live.select(F.col("u").alias("s"), F.col("v").alias("t")).unionByName(live.select(F.col("v").alias("s"), F.col("u").alias("t")))
        leaf = ends.groupBy("s").agg(F.count("*").alias("d"), F.first("t").alias("t")).filter("d = 1")
        other = leaf.select(F.col("s").alias("t"), F.lit(True).alias("both"))
        leaf = leaf.join(other, "t", "left").filter(F.col("both").isNull() | (F.col("s") > F.col("t"))).select(F.col("s").alias("state"), F.col("t").alias("parent"))
        leaf = store(leaf)
        done = leaf if done is None else done.unionByName(leaf)
        gone = leaf.select(F.least("state", "parent").alias("u"), F.greatest("state", "parent").alias("v"))
        live = store(live.join(gone, ["u", "v"], "left_anti"))
    every = states.select("state")
    return every.join(done, "state", "left") if done is not None else every.withColumn("parent", F.lit(None).cast("long"))


def levels(tree: DataFrame, most: int = 64) -> DataFrame:
    """state, parent, level: every state's pointer is doubled until it is at a root, so rounds are as the logarithm of the height."""
    now = store(tree.select("state", "parent", F.coalesce("parent", "state").alias("up"), F.col("parent").isNotNull().cast("int").alias("level")))
    for _ in range(most):
        above = now.select(F.col("state").alias("up"), F.col("up").alias("next"), F.col("level").alias("more"))
        nxt = store(now.join(above, "up").select("state", "parent", F.col("next").alias("up"), (F.col("level") + F.col("more")).alias("level"), (F.col("more") > 0).alias("moved")))
        drop(now)
        now = nxt.select("state", "parent", "up", "level")
        now._thinfsm_path = nxt._thinfsm_path
        if nxt.filter("moved").isEmpty():
            return now.select("state", "parent", "level")
    raise RuntimeError("levels: a cycle")


def sparsified(edges: DataFrame, forests: int) -> DataFrame:
    """The union of so many edge-disjoint maximum spanning forests, best first: at most ``forests`` edges per state, and every cut keeps its best ones."""
    rest, out = edges.select("u", "v", "w"), None
    for _ in range(max(1, forests)):
        best = spanning_forest(rest)
        out = best if out is None else out.unionByName(best)
        rest = store(rest.join(best.select("u", "v"), ["u", "v"], "left_anti"))
        if rest.isEmpty():
            break
    return out


def cut_fewest(tree: DataFrame, L: int) -> DataFrame:
    """tree: state, parent, level.  The states whose edge to the parent is cut, level by level from the deepest.

    Of a parent's children only the tallest height up to L and the least one above L matter, so
    each level is one associative aggregate."""
    top = tree.agg(F.max("level")).first()[0] or 0
    tree = store(tree)
    heights = tree.filter(F.col("level") == top).select("state", F.lit(0).cast("long").alias("h"))
    out = tree.select("state").limit(0)
    for d in range(top, 0, -1):
        kids = store(tree.filter(F.col("level") == d).select("state", "parent").join(heights, "state").withColumn("h", F.col("h") + 1))
        per = kids.groupBy("parent").agg(F.coalesce(F.max(F.when(F.col("h") <= L, F.col("h"))), F.lit(0)).alias("low"), F.min(F.when(F.col("h") > L, F.struct("h", "state"))).alias("high"))
        per = per.withColumn("stays", F.when(F.col("high.h") + F.col("low") <= 2 * L, F.col("high.state")))
        out = out.unionByName(kids.join(per, "parent").filter((F.col("h") > L) & ~F.col("state").eqNullSafe(F.col("stays"))).select("state"))
        reach = per.select(F.col("parent").alias("state"), F.when(F.col("stays").isNotNull(), F.col("high.h")).otherwise(F.col("low")).alias("r"))
        heights = store(tree.filter(F.col("level") == d - 1).select("state").join(reach, "state", "left").select("state", F.coalesce("r", F.lit(0)).cast("long").alias("h")))
    return store(out)


# Depth variant


def best_defaults(pairs: DataFrame, depth: DataFrame, rows: DataFrame, *, drop_by: int = 1, min_gain: int = 0) -> DataFrame:
    """state, default, w: of directed pairs (u, v) the most similar v that is higher by ``drop_by`` (ties: least v).  Depths are filtered before rows are joined."""
    du, dv = depth.select(F.col("state").alias("u"), F.col("depth").alias("du")), depth.select(F.col("state").alias("v"), F.col("depth").alias("dv"))
    high = pairs.select("u", "v").distinct().join(du, "u").join(dv, "v").filter(F.col("dv") <= F.col("du") - drop_by).select("u", "v")
    weighed = pair_similarity(rows, high).filter(F.col("w") >= min_gain)
    return weighed.groupBy("u").agg(F.max(F.struct("w", (-F.col("v")).alias("v"))).alias("b")).select(F.col("u").alias("state"), (-F.col("b.v")).alias("default"), F.col("b.w").alias("w"))


def suffix_defaults(states: DataFrame) -> DataFrame:
    """state, default: the longest proper suffix that is a prefix (the multi-string matcher's failure link)."""
    tails = states.filter("depth > 0").select("state", "prefix", F.explode(F.sequence(F.lit(2), F.length("prefix") + 1)).alias("i")).select("state", F.expr("substring(prefix, i)").alias("prefix"))
    return tails.join(states.select("prefix", F.col("state").alias("t")), "prefix").groupBy("state").agg(F.max_by("t", F.length("prefix")).alias("default"))


# Results


def emit_labelled(transitions: DataFrame, defaults: DataFrame) -> DataFrame:
    """The transitions that the default doesn't give."""
    d = defaults.filter("default is not null").select("state", "default")
    with_d = transitions.join(d, "state", "left")
    other = transitions.select(F.col("state").alias("default"), "symbol", F.col("target").alias("given"))
    return with_d.join(other, ["default", "symbol"], "left").filter(F.col("default").isNull() | (F.col("target") != F.col("given"))).select("automaton_id", "state", "symbol", "target")


def resolve(states: DataFrame, labelled: DataFrame, defaults: DataFrame, alphabet: DataFrame, most: int = 1000) -> DataFrame:
    """state, symbol, target, hops: the full table of a delayed automaton, by following defaults step by step."""
    open_ = store(states.select("state").crossJoin(F.broadcast(alphabet.select("symbol"))).select("state", "symbol", F.col("state").alias("at"), F.lit(0).alias("hops")))  # states x alphabet: the size of the result
    done = None
    lab = labelled.select(F.col("state").alias("at"), "symbol", "target")
    links = defaults.filter("default is not null").select(F.col("state").alias("at"), "default")
    for _ in range(most):
        got = store(open_.join(lab, ["at", "symbol"], "left"))
        hit = got.filter("target is not null").select("state", "symbol", "target", "hops")
        done = hit if done is None else done.unionByName(hit)
        miss = got.filter("target is null").join(links, "at", "left")
        if miss.isEmpty():
            return done
        if not miss.filter("default is null").isEmpty():
            raise ValueError("a symbol leads nowhere: not well defined")
        open_ = miss.select("state", "symbol", F.col("default").alias("at"), (F.col("hops") + 1).alias("hops"))
    raise ValueError("a cycle of defaults without an exit")


def redundant(transitions: DataFrame, defaults: DataFrame) -> DataFrame:
    """state, symbol: transitions that the state's default gives as well."""
    d = defaults.filter("default is not null").select("state", "default")
    given = transitions.select(F.col("state").alias("default"), "symbol", "target")
    return transitions.join(d, "state").join(given, ["default", "symbol", "target"]).select("state", "symbol")


def ill_defined(states: DataFrame, labelled: DataFrame, defaults: DataFrame, alphabet: DataFrame, most: int = 64) -> DataFrame:
    """state, symbol, fault of every cell that has no target: its defaults run in a cycle, or end at a state without the label.

    Pointers over the default links are doubled for all symbols at once, so rounds are as the
    logarithm of the longest chain."""
    cells = states.select("state").crossJoin(F.broadcast(alphabet.select("symbol")))  # states x alphabet: the size of a full table
    own = labelled.select("state", "symbol", F.lit(True).alias("here"))
    links = defaults.filter("default is not null").select("state", "default")
    now = store(cells.join(own, ["state", "symbol"], "left").join(links, "state", "left").select("state", "symbol", F.when(F.col("here").isNull(), F.col("default")).alias("up"), F.coalesce("here", F.lit(False)).alias("found")))
    n = states.count()
    for k in range(most):
        open_ = now.filter("not found and up is not null")
        if (1 << k) > n or open_.isEmpty():
            return now.filter("not found").select("state", "symbol", F.when(F.col("up").isNull(), "no target").otherwise("cycle").alias("fault"))
        above = now.select(F.col("state").alias("up"), "symbol", F.col("up").alias("next"), F.col("found").alias("there"))
        moved = open_.select("state", "symbol", "up").join(above, ["up", "symbol"]).select("state", "symbol", "next", "there")
        nxt = store(now.filter("found or up is null").unionByName(moved.select("state", "symbol", F.col("next").alias("up"), F.col("there").alias("found"))))
        drop(now)
        now = nxt
    raise RuntimeError("ill_defined: no end")


def unequal(transitions: DataFrame, accepting: DataFrame, other: DataFrame, other_accepting: DataFrame, start: int = 0, other_start: int = 0, most: int = 100_000) -> DataFrame:
    """state, twin: pairs of states that some text reaches in the two automata and of which one accepts (state, label) and the other doesn't; none if both are equivalent.

    The automata may number their states differently: the walk goes over pairs of states, a frontier at a time."""
    a = transitions.select("state", "symbol", "target")
    b = other.select(F.col("state").alias("twin"), "symbol", F.col("target").alias("twin_target"))
    seen = front = store(a.sparkSession.createDataFrame([(start, other_start)], "state long, twin long"))
    for k in range(most):
        nxt = front.join(a, "state").join(b, ["twin", "symbol"]).select(F.col("target").alias("state"), F.col("twin_target").alias("twin")).distinct()
        front = store(nxt.join(seen, ["state", "twin"], "left_anti"))
        if front.isEmpty():
            break
        seen = seen.unionByName(front)
        if k % 8 == 7:
            seen = store(seen)
    sets = lambda t, c: t.groupBy(F.col("state").alias(c)).agg(F.array_sort(F.collect_set("label")).alias(f"{c}_labels"))  # noqa: E731  the rules of one state
    both = seen.join(sets(accepting, "state"), "state", "left").join(sets(other_accepting, "twin"), "twin", "left")
    return both.filter(~F.col("state_labels").eqNullSafe(F.col("twin_labels"))).select("state", "twin")


def size_report(transitions: DataFrame, labelled: DataFrame, defaults: DataFrame) -> DataFrame:
    t = transitions.agg(F.count("*").alias("t_in"))
    a = labelled.agg(F.count("*").alias("labelled"))
    d = defaults.agg(F.count("default").alias("defaults"))
    out = t.join(F.broadcast(a)).join(F.broadcast(d))  # one row each
    return out.select("t_in", "labelled", "defaults", (F.col("labelled") + F.col("defaults")).alias("t_out"), F.round(100.0 * (F.col("labelled") + F.col("defaults")) / F.col("t_in"), 6).alias("size_pct"))
