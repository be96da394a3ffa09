"""Relational operators around the methods, over the given tables, each with the same query in SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..model import numbered, table
from ..plans.dictionary import found_words

QUERIES, ORACLES = {}, {}


def query(sql: str | None = None):
    def keep(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return keep


@query("SELECT p_partkey, p_name, p_size FROM part WHERE p_brand IN ('Brand#11', 'Brand#12', 'Brand#13') AND p_size BETWEEN 5 AND 30")
def scan_project_filter(spark, sf_dir):
    return table(spark, sf_dir, "part").filter(F.col("p_brand").isin("Brand#11", "Brand#12", "Brand#13") & F.col("p_size").between(5, 30)).select("p_partkey", "p_name", "p_size")


@query("WITH w AS (SELECT p_name, row_number() OVER (ORDER BY p_name) AS i, count(*) OVER () AS n FROM (SELECT DISTINCT p_name FROM part WHERE p_name IS NOT NULL)) SELECT '1/' || d AS share, count(*) AS rules, CAST(sum(length(p_name)) AS BIGINT) AS characters FROM w, (SELECT unnest([8, 4, 2, 1]) AS d) WHERE i * d <= n GROUP BY d")
def rule_prefix_ladder(spark, sf_dir):
    """Rules and characters of the first 1/8, 1/4, 1/2 and all of the rules in order of text."""
    w = numbered(table(spark, sf_dir, "part").select("p_name").filter("p_name is not null").distinct(), ["p_name"], "i")
    n = w.agg(F.count("*").alias("n"))
    d = F.explode(F.array(*[F.lit(x) for x in (8, 4, 2, 1)]))
    return w.join(F.broadcast(n)).select("p_name", "i", "n", d.alias("d")).filter((F.col("i") + 1) * F.col("d") <= F.col("n")).groupBy(F.concat(F.lit("1/"), "d").alias("share")).agg(F.count("*").alias("rules"), F.sum(F.length("p_name")).cast("long").alias("characters"))


@query(r"SELECT doc_id, regexp_matches(text, '\(\?|\\[1-9]') AS rejected, length(text) AS length FROM documents WHERE text IS NOT NULL")
def rule_reject(spark, sf_dir):
    """Texts taken as rules: those with look-around or back references are split off."""
    return table(spark, sf_dir, "documents").filter("text is not null").select("doc_id", F.col("text").rlike(r"\(\?|\\[1-9]").alias("rejected"), F.length("text").cast("long").alias("length"))


@query("SELECT page_id, regexp_extract(url, '^https?://([^/]+)', 1) AS host, upper(substring(url, 1, 5)) AS head, CAST(length(url) AS BIGINT) AS n, CAST(len(string_split(url, '/')) AS BIGINT) AS parts, CAST(instr(url, 'example') AS BIGINT) AS at, replace(url, 'http', 'HTTP') AS changed FROM pages WHERE url IS NOT NULL")
def string_ops(spark, sf_dir):
    u = F.col("url")
    return table(spark, sf_dir, "pages").filter("url is not null").select("page_id", F.regexp_extract(u, "^https?://([^/]+)", 1).alias("host"), F.upper(F.substring(u, 1, 5)).alias("head"), F.length(u).cast("long").alias("n"), F.size(F.split(u, "/", -1)).cast("long").alias("parts"), F.instr(u, "example").cast("long").alias("at"), F.replace(u, F.lit("http"), F.lit("HTTP")).alias("changed"))


@query("WITH h AS (SELECT hex(encode(text)) AS h FROM benchmark WHERE text IS NOT NULL), b AS (SELECT substring(h, i * 2 + 1, 2) AS byte FROM h, range(100000) t(i) WHERE i * 2 < length(h)) SELECT byte, count(*) AS n FROM b GROUP BY 1")
def byte_histogram(spark, sf_dir):
    h = table(spark, sf_dir, "benchmark").filter("text is not null and text <> ''").select(F.hex(F.encode("text", "UTF-8")).alias("h"))
    return h.select(F.explode(F.expr("transform(sequence(0, CAST(length(h) / 2 AS int) - 1), i -> substring(h, i * 2 + 1, 2))")).alias("byte")).groupBy("byte").agg(F.count("*").alias("n"))


@query("SELECT event_type, date_trunc('hour', ts) AS hour, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1, 2")
def events_by_hour(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy("event_type", F.date_trunc("hour", F.col("ts").cast("timestamp")).cast("timestamp_ntz").alias("hour")).agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total"))


@query("SELECT event_type, CAST(sum(CAST(json_extract_string(props, '$.k') AS BIGINT)) AS BIGINT) AS total, count(DISTINCT json_extract_string(props, '$.k')) AS kinds FROM events GROUP BY 1")
def event_props(spark, sf_dir):
    k = F.get_json_object("props", "$.k")
    return table(spark, sf_dir, "events").groupBy("event_type").agg(F.sum(k.cast("long")).alias("total"), F.count_distinct(k).alias("kinds"))


@query("SELECT c_mktsegment, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
def equi_join_hint(spark, sf_dir):
    o = table(spark, sf_dir, "orders").groupBy("o_custkey").agg(F.count("*").alias("k"), F.sum("o_totalprice").alias("t"))
    return o.join(table(spark, sf_dir, "customer").select("c_custkey", "c_mktsegment").hint("shuffle_hash"), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.sum("k").alias("n"), F.round(F.sum("t"), 2).alias("total"))


@query("SELECT p_partkey, count(*) AS lines, round(sum(l_extendedprice), 2) AS price FROM lineitem JOIN part ON l_quantity BETWEEN p_size AND p_size + 1 GROUP BY 1")
def range_join_quantity(spark, sf_dir):
    """Lines in the band of each part: lines are added up by quantity, then an equi-join on bins of the quantity, then the bounds."""
    width = 2
    li = table(spark, sf_dir, "lineitem").groupBy("l_quantity").agg(F.count("*").alias("n"), F.sum(F.col("l_extendedprice").cast("decimal(18,2)")).alias("t")).withColumn("bin", F.floor(F.col("l_quantity") / width))
    p = table(spark, sf_dir, "part").select("p_partkey", "p_size", F.explode(F.sequence(F.floor(F.col("p_size") / width), F.floor((F.col("p_size") + 1) / width))).alias("bin"))
    banded = li.join(p, "bin").filter(F.col("l_quantity").between(F.col("p_size"), F.col("p_size") + 1))
    return banded.groupBy("p_partkey").agg(F.sum("n").alias("lines"), F.round(F.sum("t").cast("double"), 2).alias("price"))


@query("SELECT a.event_id AS click_id, b.event_id AS error_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'error' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 5 MINUTE")
def interval_join_events(spark, sf_dir):
    e = table(spark, sf_dir, "events").select("event_id", "user_id", "event_type", "ts")
    a, b = e.filter("event_type = 'click'").alias("a"), e.filter("event_type = 'error'").alias("b")
    return a.join(b, (F.col("a.user_id") == F.col("b.user_id")) & (F.col("b.ts") > F.col("a.ts")) & (F.col("b.ts") <= F.col("a.ts") + F.expr("INTERVAL 5 MINUTES"))).select(F.col("a.event_id").alias("click_id"), F.col("b.event_id").alias("error_id"))


@query("SELECT e.event_id, (SELECT arg_max(p.event_id, (p.ts, p.event_id)) FROM events p WHERE p.user_id = e.user_id AND p.event_type <> 'error' AND (p.ts, p.event_id) < (e.ts, e.event_id)) AS previous FROM events e WHERE e.event_type = 'error'")
def asof_last_event(spark, sf_dir):
    """The latest other event of the user before each error: one window, no join."""
    e = table(spark, sf_dir, "events")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    return e.select("event_id", "event_type", F.last(F.when(F.col("event_type") != "error", F.col("event_id")), ignorenulls=True).over(w).alias("previous")).filter("event_type = 'error'").select("event_id", "previous")


@query("SELECT item_id FROM benchmark b WHERE text <> '' AND EXISTS (SELECT 1 FROM documents d WHERE contains(d.text, b.text))")
def semi_matched_rules(spark, sf_dir):
    """Passages that occur whole: documents are read once by the delayed matcher, which reports the passages that it found."""
    found = found_words(spark, sf_dir, table(spark, sf_dir, "documents").select("text"), "text", "benchmark", "text")
    return table(spark, sf_dir, "benchmark").select("item_id", F.col("text").alias("word")).join(found, "word", "left_semi").select("item_id")


@query("SELECT item_id FROM benchmark b WHERE text <> '' AND NOT EXISTS (SELECT 1 FROM documents d WHERE contains(d.text, b.text))")
def anti_unmatched_rules(spark, sf_dir):
    found = found_words(spark, sf_dir, table(spark, sf_dir, "documents").select("text"), "text", "benchmark", "text")
    return table(spark, sf_dir, "benchmark").filter("text <> ''").select("item_id", F.col("text").alias("word")).join(found, "word", "left_anti").select("item_id")


_HIT = "SELECT d.lang, d.source, l.quality, l.toxic, contains(d.text, 'licen') AS hit FROM documents d LEFT JOIN labels l USING (doc_id)"


def _hits(spark, sf_dir):
    d, lab = table(spark, sf_dir, "documents").select("doc_id", "lang", "source", F.contains("text", F.lit("licen")).alias("hit")), table(spark, sf_dir, "labels")
    return d.join(lab, "doc_id", "left")


@query(f"SELECT lang, source, count(*) AS documents, count(*) FILTER (hit) AS hits, CAST(grouping(lang) * 2 + grouping(source) AS BIGINT) AS level FROM ({_HIT}) GROUP BY ROLLUP (lang, source)")
def match_rollup(spark, sf_dir):
    return _hits(spark, sf_dir).rollup("lang", "source").agg(F.count("*").alias("documents"), F.count_if("hit").alias("hits"), F.grouping_id().alias("level"))


@query(f"SELECT lang, quality, count(*) AS documents, count(*) FILTER (hit) AS hits, CAST(grouping(lang) * 2 + grouping(quality) AS BIGINT) AS level FROM ({_HIT}) GROUP BY CUBE (lang, quality)")
def match_cube(spark, sf_dir):
    return _hits(spark, sf_dir).cube("lang", "quality").agg(F.count("*").alias("documents"), F.count_if("hit").alias("hits"), F.grouping_id().alias("level"))


@query(f"SELECT lang, quality, toxic, count(*) AS documents FROM ({_HIT}) GROUP BY GROUPING SETS ((lang), (quality, toxic), ())")
def match_grouping_sets(spark, sf_dir):
    _hits(spark, sf_dir).createOrReplaceTempView("fsm_hits")
    return spark.sql("SELECT lang, quality, toxic, count(*) AS documents FROM fsm_hits GROUP BY GROUPING SETS ((lang), (quality, toxic), ())")


@query(f"SELECT lang, count(*) FILTER (quality = 0) AS q0, count(*) FILTER (quality = 1) AS q1 FROM ({_HIT}) GROUP BY 1")
def quality_toxic_pivot(spark, sf_dir):
    p = _hits(spark, sf_dir).groupBy("lang").pivot("quality", [0, 1]).agg(F.count(F.lit(1)))
    return p.select("lang", F.coalesce("0", F.lit(0)).alias("q0"), F.coalesce("1", F.lit(0)).alias("q1"))


@query(f"SELECT source, count(*) FILTER (hit) AS hits FROM ({_HIT}) GROUP BY 1 HAVING count(*) FILTER (hit) > 1")
def having_heavy_sources(spark, sf_dir):
    return _hits(spark, sf_dir).groupBy("source").agg(F.count_if("hit").alias("hits")).filter("hits > 1")


@query("SELECT conv_id, turn, lag(role) OVER w AS previous, length(text) - lag(length(text)) OVER w AS longer, first_value(role) OVER w AS first_role, nth_value(role, 2) OVER (PARTITION BY conv_id ORDER BY turn ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second_role FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)")
def turn_lag(spark, sf_dir):
    w = Window.partitionBy("conv_id").orderBy("turn")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    n = F.length("text").cast("long")
    return table(spark, sf_dir, "conversations").select("conv_id", "turn", F.lag("role").over(w).alias("previous"), (n - F.lag(n).over(w)).alias("longer"), F.first("role").over(w).alias("first_role"), F.nth_value("role", 2).over(whole).alias("second_role"))


@query("SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 HOUR PRECEDING AND CURRENT ROW), 4) AS last_hour FROM events")
def events_range_frame(spark, sf_dir):
    at = F.unix_micros(F.col("ts").cast("timestamp"))
    w = Window.partitionBy("user_id").orderBy("us").rangeBetween(-3_600_000_000, 0)
    return table(spark, sf_dir, "events").withColumn("us", at).select("event_id", F.round(F.sum("value").over(w), 4).alias("last_hour"))


@query("SELECT a.p_partkey AS a, b.p_partkey AS b, CAST((a.p_type = b.p_type)::INT + (a.p_size = b.p_size)::INT + (a.p_name = b.p_name)::INT AS INTEGER) AS w FROM part a JOIN part b ON a.p_brand = b.p_brand AND a.p_partkey < b.p_partkey WHERE (a.p_type = b.p_type)::INT + (a.p_size = b.p_size)::INT + (a.p_name = b.p_name)::INT >= 2")
def part_row_similarity(spark, sf_dir):
    """Rows as states: pairs of one brand that share two attributes at least; joined on each pair of attributes, so no brand is squared."""
    p = table(spark, sf_dir, "part").select("p_partkey", "p_brand", "p_type", "p_size", "p_name")
    out = None
    for x, y in (("p_type", "p_size"), ("p_type", "p_name"), ("p_size", "p_name")):
        a, b = p.alias("a"), p.alias("b")
        j = a.join(b, (F.col("a.p_brand") == F.col("b.p_brand")) & (F.col(f"a.{x}") == F.col(f"b.{x}")) & (F.col(f"a.{y}") == F.col(f"b.{y}")) & (F.col("a.p_partkey") < F.col("b.p_partkey")))
        same = sum(((F.col(f"a.{c}") == F.col(f"b.{c}")).cast("int") for c in ("p_type", "p_size", "p_name")), F.lit(0))
        j = j.select(F.col("a.p_partkey").alias("a"), F.col("b.p_partkey").alias("b"), same.alias("w"))
        out = j if out is None else out.unionByName(j)
    return out.distinct()


@query("SELECT doc_id, CASE WHEN lang IN ('en', 'de') THEN 'kept' WHEN lang IS NOT DISTINCT FROM 'fr' THEN 'later' ELSE 'left' END AS lot FROM documents WHERE length(text) BETWEEN 100 AND 5000")
def payload_filter(spark, sf_dir):
    lang = F.col("lang")
    return table(spark, sf_dir, "documents").filter(F.length("text").between(100, 5000)).select("doc_id", F.when(lang.isin("en", "de"), "kept").when(lang.eqNullSafe(F.lit("fr")), "later").otherwise("left").alias("lot"))


@query("SELECT p_partkey FROM part WHERE p_type IN (SELECT min(p_type) FROM part) OR p_size BETWEEN 1 AND 3")
def rule_filter(spark, sf_dir):
    p = table(spark, sf_dir, "part")
    first = p.agg(F.min("p_type").alias("t"))
    return p.join(F.broadcast(first)).filter((F.col("p_type") == F.col("t")) | F.col("p_size").between(1, 3)).select("p_partkey")


@query("SELECT w AS word, count(*) FILTER (p_name LIKE '%' || w || '%') AS parts FROM part, (SELECT DISTINCT unnest(string_split(p_name, ' ')) AS w FROM part) GROUP BY 1")
def pattern_like(spark, sf_dir):
    """Parts per word: a word is joined to the substrings of its length of the folded names, never to every name."""
    p = table(spark, sf_dir, "part").filter("p_name is not null").groupBy("p_name").count()
    w = p.select(F.explode(F.split("p_name", " ")).alias("word")).distinct()
    lengths = w.select(F.length("word").alias("k")).distinct().agg(F.collect_set("k").alias("ks"))  # as many as lengths of words
    cut = p.join(F.broadcast(lengths)).select("p_name", "count", F.explode("ks").alias("k")).filter(F.col("k") <= F.length("p_name"))
    subs = cut.select("p_name", "count", F.explode(F.expr("array_distinct(transform(sequence(1, length(p_name) - k + 1), i -> substring(p_name, i, k)))")).alias("word"))
    return subs.join(w, "word").groupBy("word").agg(F.sum("count").alias("parts"))


@query("SELECT date_trunc('month', o_orderdate) AS month, count(*) AS n, count(*) FILTER (o_orderdate + INTERVAL 30 DAY >= date_trunc('month', o_orderdate) + INTERVAL 2 MONTH) AS late FROM orders GROUP BY 1")
def orders_by_month(spark, sf_dir):
    d = F.col("o_orderdate").cast("timestamp_ntz")
    o = table(spark, sf_dir, "orders").select(d.alias("d")).withColumn("m", F.date_trunc("month", "d").cast("timestamp_ntz"))
    return o.groupBy(F.col("m").alias("month")).agg(F.count("*").alias("n"), F.count_if(F.expr("d + INTERVAL 30 DAYS >= m + INTERVAL 2 MONTHS")).alias("late"))


@query("SELECT l_returnflag, l_linestatus, CAST(sum(CAST(l_extendedprice AS DECIMAL(15, 2))) AS DOUBLE) AS total, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY 1, 2")
def decimal_totals(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.sum(F.col("l_extendedprice").cast("decimal(15,2)")).cast("double").alias("total"), F.count_distinct("l_suppkey").alias("suppliers"))


@query("SELECT event_type, count(DISTINCT user_id) AS users, count(*) FILTER (value > 50) AS high, avg(value) FILTER (value > 50) IS NOT NULL AS any_high FROM events GROUP BY 1")
def distinct_filter_agg(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy("event_type").agg(F.count_distinct("user_id").alias("users"), F.count_if(F.col("value") > 50).alias("high"), F.max(F.col("value") > 50).alias("any_high"))


@query("SELECT user_id, count(*) AS n FROM events GROUP BY 1 ORDER BY n DESC, user_id LIMIT 10")
def top_users(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy("user_id").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "user_id").limit(10)


@query("SELECT n_name, r_name, count(c_custkey) AS customers, coalesce(round(sum(c_acctbal), 2), 0) AS balance FROM nation JOIN region ON n_regionkey = r_regionkey LEFT JOIN customer ON c_nationkey = n_nationkey GROUP BY 1, 2")
def nation_customers(spark, sf_dir):
    c = table(spark, sf_dir, "customer").groupBy("c_nationkey").agg(F.count("*").alias("k"), F.sum("c_acctbal").alias("b"))
    n = table(spark, sf_dir, "nation").join(F.broadcast(table(spark, sf_dir, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return n.join(c, F.col("n_nationkey") == F.col("c_nationkey"), "left").select("n_name", "r_name", F.coalesce("k", F.lit(0)).alias("customers"), F.coalesce(F.round("b", 2), F.lit(0.0)).alias("balance"))
