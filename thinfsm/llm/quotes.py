r"""Quotation linking for conversations, with DataFrame functions.

A line is quoted at level n if it begins with n '>' signs (blanks between them allowed).  Every
quoted line is normalised (signs off, blanks folded, lower case) and hashed, as are all unquoted
lines of all messages.  A quoted line is linked to the latest earlier message of the same
conversation that has the line as its own, else to the earliest message of any conversation that
has it.  A message replies to the one that most of its least-nested linked lines come from (ties:
the latest).  Its own text is what is left without quoted lines and without the introductions
("... wrote:") right before them.

The same-conversation link is a window over (conversation, line hash), the other a join with one
row per line hash, so neither grows with the square of a common line's count.  Threads follow
the reply links to a root, across conversations, and order messages by a walk below it.

Cases: null text is empty; a null conversation or turn has no earlier messages but may link
elsewhere; messages with the same conversation and turn are one message for links; empty lines
link nothing; repeated rows give a row each; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .base import store

QUOTED = r"^\s*(?:>\s?)+"
INTRODUCTION = r"(?i)^.{0,200}\b(?:wrote|writes|schrieb|escribió|a écrit)\s*:\s*$"


def lines(messages: DataFrame, conv_col: str, turn_col: str, text_col: str) -> DataFrame:
    """conv, turn, row, i, level, line, hash; a row per line."""
    rows = messages.select(F.col(conv_col).cast("long").alias("conv"), F.col(turn_col).cast("long").alias("turn"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    cut = rows.select("conv", "turn", F.posexplode(F.split("text", "\n", -1)).alias("i", "raw"))
    sign = F.regexp_extract("raw", QUOTED, 0)
    cut = cut.select("conv", "turn", "i", F.length(F.regexp_replace(sign, "[^>]", "")).alias("level"), F.when(F.length(sign) > 0, F.expr("substring(raw, length(regexp_extract(raw, '^\\\\s*(?:>\\\\s?)+', 0)) + 1)")).otherwise(F.col("raw")).alias("line"))
    norm = F.lower(F.trim(F.regexp_replace("line", r"\s+", " ")))
    return cut.withColumn("norm", norm).withColumn("hash", F.when(F.length("norm") > 0, F.xxhash64("norm")))


def links(own: DataFrame) -> DataFrame:
    """conv, turn, to_conv, to_turn, level, n: linked lines of each message by the message they come from."""
    marked = own.filter("hash is not null").groupBy("conv", "turn", "hash", (F.col("level") > 0).alias("quoted")).agg(F.min("level").alias("level"), F.count("*").alias("n"))
    w = Window.partitionBy("conv", "hash").orderBy("turn").rangeBetween(Window.unboundedPreceding, -1)
    near = marked.withColumn("near", F.max(F.when(~F.col("quoted"), F.col("turn"))).over(w)).filter("quoted")
    near = near.withColumn("near", F.when(F.col("conv").isNotNull() & F.col("turn").isNotNull(), F.col("near")))
    first = marked.filter("not quoted").groupBy("hash").agg(F.min(F.struct("conv", "turn")).alias("far"))
    # Only lines without a near match look elsewhere; the others get a key of their own, so a common line doesn't gather them in one task.
    near = near.withColumn("key", F.when(F.col("near").isNull(), F.col("hash")).otherwise(F.xxhash64("conv", "turn", "hash")))
    both = near.join(first.withColumnRenamed("hash", "key"), "key", "left")
    here = F.col("near").isNotNull()
    far = F.when(~(F.col("far.conv").eqNullSafe(F.col("conv")) & F.coalesce(F.col("far.turn") >= F.col("turn"), F.lit(False))), F.col("far"))
    out = both.select("conv", "turn", "level", "n", F.when(here, F.col("conv")).otherwise(far["conv"]).alias("to_conv"), F.when(here, F.col("near")).otherwise(far["turn"]).alias("to_turn"))
    return out.filter("to_turn is not null").groupBy("conv", "turn", "to_conv", "to_turn").agg(F.min("level").alias("level"), F.sum("n").alias("n"))


def link(messages: DataFrame, *, conv_col: str = "conv_id", turn_col: str = "turn", text_col: str = "text") -> DataFrame:
    """conv_id, turn, reply_conv, reply_turn, n_quoted, n_linked, depth, own_text of every message."""
    every = lines(messages, conv_col, turn_col, text_col)
    linked = links(every)
    best = linked.groupBy("conv", "turn").agg(F.max(F.struct((-F.col("level")).alias("level"), "n", "to_turn", "to_conv")).alias("b"), F.sum("n").alias("n_linked"))
    keyed = messages.select(F.col(conv_col).cast("long").alias("conv_id"), F.col(turn_col).cast("long").alias("turn"), F.split(F.coalesce(F.col(text_col).cast("string"), F.lit("")), "\n", -1).alias("raw"))
    level = F.transform("raw", lambda x: F.length(F.regexp_replace(F.regexp_extract(x, QUOTED, 0), "[^>]", "")))
    keyed = keyed.withColumn("level", level)
    kept = F.expr(f"filter(transform(raw, (x, i) -> IF(level[i] = 0 AND NOT (i + 1 < size(raw) AND level[least(i + 1, size(raw) - 1)] > 0 AND x RLIKE '{INTRODUCTION.replace(chr(92), chr(92) * 2)}'), x, CAST(NULL AS string))), x -> x IS NOT NULL)")
    keyed = keyed.select("conv_id", "turn", F.expr("CAST(size(filter(level, x -> x > 0)) AS bigint)").alias("n_quoted"), F.array_max("level").alias("depth"), F.trim(F.array_join(kept, "\n")).alias("own_text"))
    best = best.select(F.col("conv").alias("c"), F.col("turn").alias("t"), F.col("b.to_conv").alias("reply_conv"), F.col("b.to_turn").alias("reply_turn"), "n_linked")
    out = keyed.join(best, keyed["conv_id"].eqNullSafe(best["c"]) & keyed["turn"].eqNullSafe(best["t"]), "left")
    return out.select("conv_id", "turn", "reply_conv", "reply_turn", "n_quoted", F.coalesce("n_linked", F.lit(0)).cast("long").alias("n_linked"), F.col("depth").cast("int").alias("depth"), "own_text")


def converse(messages: DataFrame, **how) -> DataFrame:
    """link() with the thread of every message and its position there: reply-ordered conversations without quotes."""
    return thread_order(store(link(messages, **how)))


def key(conv: str, turn: str) -> Column:
    """A message's conversation and turn as one text, also where they are null."""
    return F.concat_ws(":", *[F.coalesce(F.col(c).cast("string"), F.lit("-")) for c in (conv, turn)])


def without_cycles(nodes: DataFrame) -> DataFrame:
    """node, conv, turn, parent: messages that answer each other in a ring lose one link, that of the least of them."""
    live = nodes.filter("parent is not null").select("node", F.col("parent").alias("jump"), F.struct("conv", "turn", "node").alias("low"))
    before, reach = -1, 1
    while True:  # a round leaves the nodes with that many ancestors; with all their ancestors' counts in a row, an equal count means rings only
        live = store(live)
        n = live.count()
        if not n:
            return nodes
        if n == before and reach >= n:
            break
        before, reach = n, 2 * reach
        far = live.select(F.col("node").alias("jump"), F.col("jump").alias("next"), F.col("low").alias("more"))
        live = live.join(far, "jump").select("node", F.col("next").alias("jump"), F.least("low", "more").alias("low"))
    up = nodes.filter("parent is not null").select(F.col("node").alias("own"), "parent").join(live.select(F.col("node").alias("parent"), F.col("low.node").alias("low")), "parent")
    cut = up.filter("low = own").select(F.col("own").alias("node"), F.lit(True).alias("cut"))
    return nodes.join(cut, "node", "left").select("node", "conv", "turn", F.when(F.col("cut").isNull(), F.col("parent")).alias("parent"))


def thread_order(linked: DataFrame) -> DataFrame:
    """Adds thread_conv, thread_turn (the root its reply links lead to, across conversations) and position (from 0, an answer below what it
    answers, before the next answer to the same message; those of its own conversation first) to every message.

    The walk around each tree is a list of two steps per message, ranked by pointer jumping, so a round
    reads two rows per message however deep or broad the threads are."""
    rows = linked.withColumn("__node", key("conv_id", "turn"))
    nodes = rows.groupBy("__node").agg(F.first("conv_id").alias("conv"), F.first("turn").alias("turn"), F.first(F.when(F.col("reply_turn").isNotNull(), key("reply_conv", "reply_turn"))).alias("parent"))
    nodes = store(nodes.select(F.col("__node").alias("node"), "conv", "turn", F.when(F.col("parent") != F.col("__node"), F.col("parent")).alias("parent")))
    tree = store(without_cycles(nodes))
    home = F.coalesce(F.split("parent", ":")[0] != F.coalesce(F.col("conv").cast("string"), F.lit("-")), F.lit(False))
    w = Window.partitionBy("parent").orderBy(home, "conv", "turn")
    kids = tree.filter("parent is not null").select("node", "parent", F.lead("node").over(w).alias("sibling"), F.row_number().over(w).alias("k"))
    first = kids.filter("k = 1").select(F.col("parent").alias("node"), F.col("node").alias("child"))
    walk = tree.select("node").join(first, "node", "left").join(kids.select("node", "parent", "sibling"), "node", "left")
    into, out = lambda c: F.concat(F.lit("+"), F.col(c)), lambda c: F.concat(F.lit("-"), F.col(c))
    steps = F.array(F.struct(into("node").alias("at"), F.coalesce(into("child"), out("node")).alias("next"), F.lit(1).cast("long").alias("n")), F.struct(out("node").alias("at"), F.coalesce(into("sibling"), out("parent")).alias("next"), F.lit(0).cast("long").alias("n")))
    steps = store(walk.select(F.inline(steps)).withColumn("last", F.when(F.col("next").isNull(), F.col("at"))))
    while not steps.filter("next is not null").isEmpty():
        t = steps.select(F.col("at").alias("next"), F.col("next").alias("then"), F.col("n").alias("more"), F.col("last").alias("end"))
        moved = steps.filter("next is not null").drop("last").join(t, "next").select("at", F.col("then").alias("next"), (F.col("n") + F.col("more")).alias("n"), F.col("end").alias("last"))
        steps = store(steps.filter("next is null").unionByName(moved))
    entered = steps.filter("startswith(at, '+')").select(F.substring("at", 2, 1 << 20).alias("__node"), F.substring("last", 2, 1 << 20).alias("root"), "n")
    size = entered.filter("__node = root").select("root", F.col("n").alias("size"))
    roots = tree.select(F.col("node").alias("root"), F.col("conv").alias("thread_conv"), F.col("turn").alias("thread_turn")).join(size, "root")
    placed = entered.join(roots, "root").select("__node", "thread_conv", "thread_turn", (F.col("size") - F.col("n")).alias("position"))
    return rows.join(placed, "__node").drop("__node")


def threads(linked: DataFrame) -> DataFrame:
    """conv_id, turns: own texts without quotes, an answer below what it answers, in the order of thread_order."""
    turns = F.array_sort(F.collect_list(F.struct("thread_conv", "thread_turn", "position", "turn", F.coalesce(F.when(F.col("reply_conv") == F.col("conv_id"), F.col("reply_turn")), F.lit(-1)).alias("reply_turn"), "own_text")))
    return thread_order(linked).groupBy("conv_id").agg(F.transform(turns, lambda x: F.struct(x["turn"].alias("turn"), x["reply_turn"].alias("reply_turn"), x["own_text"].alias("own_text"))).alias("turns"))


def as_mail(messages: DataFrame) -> DataFrame:
    """The conversations as a mailing list would hold them: each turn above its quoted predecessor, which quotes its own in turn."""
    w = Window.partitionBy("conv_id").orderBy("turn")
    lag = lambda k: F.lag("text", k).over(w)
    quote = lambda t, sign: F.concat(F.lit(sign), F.regexp_replace(t, "\n", "\n" + sign))
    rows = messages.select("conv_id", "turn", "text", lag(1).alias("p"), lag(2).alias("pp"))
    return rows.select("conv_id", "turn", F.concat_ws("\n", "text", F.when(F.col("p").isNotNull(), F.concat(F.lit("They wrote:\n"), quote(F.col("p"), "> "))), F.when(F.col("pp").isNotNull(), F.concat(F.lit("> They wrote:\n"), quote(F.col("pp"), ">> ")))).alias("text"))


ORACLE = """
WITH RECURSIVE m AS (SELECT conv_id, turn, text, lag(turn) OVER w AS p, lag(turn, 2) OVER w AS pp, lag(text) OVER w AS pt, lag(text, 2) OVER w AS ppt FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)),
l AS (SELECT conv_id, turn, unnest(string_split(text, chr(10))) AS line FROM conversations),
o AS (SELECT conv_id, turn, lower(trim(regexp_replace(line, '\\s+', ' ', 'g'))) AS norm FROM l WHERE trim(line) <> ''),
q AS (SELECT conv_id, turn, 1 AS level, unnest(string_split(pt, chr(10))) AS line FROM m WHERE p IS NOT NULL
      UNION ALL SELECT conv_id, turn, 1, 'They wrote:' FROM m WHERE pp IS NOT NULL
      UNION ALL SELECT conv_id, turn, 2, unnest(string_split(ppt, chr(10))) FROM m WHERE pp IS NOT NULL),
n AS (SELECT conv_id, turn, norm, min(level) AS level, count(*) AS n FROM (SELECT conv_id, turn, level, lower(trim(regexp_replace(line, '\\s+', ' ', 'g'))) AS norm FROM q) WHERE norm <> '' GROUP BY 1, 2, 3),
i AS (SELECT conv_id, turn, norm FROM o UNION ALL SELECT conv_id, turn, 'they wrote:' FROM m WHERE p IS NOT NULL),
h AS (SELECT n.conv_id, n.turn, n.norm, n.level, n.n, max(i.turn) AS t FROM n LEFT JOIN i ON i.conv_id = n.conv_id AND i.norm = n.norm AND i.turn < n.turn GROUP BY 1, 2, 3, 4, 5),
f AS (SELECT norm, min(struct_pack(conv_id := conv_id, turn := turn)) AS f FROM i GROUP BY norm),
k AS (SELECT h.conv_id, h.turn, h.level, h.n, CASE WHEN t IS NOT NULL THEN h.conv_id WHEN NOT (f.f.conv_id = h.conv_id AND f.f.turn >= h.turn) THEN f.f.conv_id END AS c, CASE WHEN t IS NOT NULL THEN t WHEN NOT (f.f.conv_id = h.conv_id AND f.f.turn >= h.turn) THEN f.f.turn END AS tt FROM h LEFT JOIN f USING (norm)),
g AS (SELECT conv_id, turn, c, tt, min(level) AS level, sum(n) AS n FROM k WHERE tt IS NOT NULL GROUP BY 1, 2, 3, 4),
b AS (SELECT conv_id, turn, max(struct_pack(a := -level, n := n, t := tt, c := c)) AS b, sum(n) AS n_linked FROM g GROUP BY 1, 2),
lk AS (SELECT m.conv_id, m.turn, b.b.c AS reply_conv, b.b.t AS reply_turn, CAST(coalesce(len(string_split(pt, chr(10))), 0) + CASE WHEN pp IS NULL THEN 0 ELSE 1 + len(string_split(ppt, chr(10))) END AS BIGINT) AS n_quoted,
  CAST(coalesce(n_linked, 0) AS BIGINT) AS n_linked, CAST(CASE WHEN pp IS NOT NULL THEN 2 WHEN p IS NOT NULL THEN 1 ELSE 0 END AS INTEGER) AS depth, trim(text, ' ') AS own_text
  FROM m LEFT JOIN b USING (conv_id, turn)),
rt AS (SELECT conv_id, turn, conv_id AS thread_conv, turn AS thread_turn, [struct_pack(away := false, c := conv_id, t := turn)] AS path FROM lk WHERE reply_turn IS NULL
  UNION ALL SELECT lk.conv_id, lk.turn, rt.thread_conv, rt.thread_turn, list_append(path, struct_pack(away := lk.conv_id <> rt.conv_id, c := lk.conv_id, t := lk.turn)) FROM lk JOIN rt ON lk.reply_conv = rt.conv_id AND lk.reply_turn = rt.turn)
SELECT lk.*, thread_conv, thread_turn, row_number() OVER (PARTITION BY thread_conv, thread_turn ORDER BY path) - 1 AS position FROM lk JOIN rt USING (conv_id, turn)
"""
