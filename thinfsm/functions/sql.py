"""Functions and views for SQL: similarity of rows, bucket keys, matches of a text; tables of an automaton."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import IntegerType, LongType, StringType

from .. import giant
from ..match import Matcher, Matchers
from ..model import Automaton, table
from ..plans.dictionary import _DEPTH, _HEAD, W, _depth_defaults, _matcher, base
from ..scratch import store

QUERIES, ORACLES = {}, {}


@pandas_udf(IntegerType())
def fsm_similarity(a: pd.Series, b: pd.Series) -> pd.Series:
    """Positions on which two rows agree."""
    return pd.Series([None if x is None or y is None else int((x == y).sum()) for x, y in zip(a, b)], dtype="Int32").astype(object)


@pandas_udf(StringType())
def fsm_bucket_key(row: pd.Series, symbols: pd.Series) -> pd.Series:
    """Targets on the given positions, joined."""
    return pd.Series([None if x is None or s is None else ",".join(str(int(x[i])) for i in s) for x, s in zip(row, symbols)])


@pandas_udf(LongType())
def fsm_modal_target(target: pd.Series) -> int:
    """Aggregate: the target that most transitions of the group have (of equal counts the least); null for none."""
    n = target.dropna().value_counts()
    return int(n.index[n == n.max()].min()) if len(n) else None


def matches_udtf(matcher: Matcher | Matchers):
    """Table function: a row (end_pos) for every position at which a word ends."""

    @udtf(returnType="end_pos: int, words: int")
    class FsmMatches:
        def eval(self, text: str):
            parts = matcher.parts if isinstance(matcher, Matchers) else [matcher]
            raw = (text or "").encode()
            for i, steps in enumerate(zip(*(m.walk(raw) for m in parts))):
                if n := sum(found for _, _, found in steps):
                    yield i + 1, n

    return FsmMatches


def register(spark: SparkSession, matcher: Matcher | Matchers | None = None) -> None:
    spark.udf.register("fsm_similarity", fsm_similarity)
    spark.udf.register("fsm_bucket_key", fsm_bucket_key)
    spark.udf.register("fsm_modal_target", fsm_modal_target)
    if matcher is not None:
        spark.udtf.register("fsm_matches", matches_udtf(matcher))


def publish(a: Automaton, defaults: DataFrame | None = None) -> None:
    """Views fsm_states, fsm_transitions, fsm_edges, fsm_forest (of those edges) and, with defaults, fsm_defaults, fsm_labelled and fsm_measures."""
    a.states.createOrReplaceTempView("fsm_states")
    a.transitions.createOrReplaceTempView("fsm_transitions")
    edges = store(giant.similarity_long(a.transitions))
    edges.createOrReplaceTempView("fsm_edges")
    giant.spanning_forest(edges).createOrReplaceTempView("fsm_forest")
    if defaults is not None:
        defaults.createOrReplaceTempView("fsm_defaults")
        labelled = giant.emit_labelled(a.transitions, defaults)
        labelled.createOrReplaceTempView("fsm_labelled")
        giant.size_report(a.transitions, labelled, defaults).createOrReplaceTempView("fsm_measures")


def udtf_matches(spark, sf_dir):
    register(spark, _matcher(spark, sf_dir))
    table(spark, sf_dir, "part").select("p_partkey", "p_name").createOrReplaceTempView("fsm_payloads")
    return spark.sql("SELECT p.p_partkey, CAST(sum(m.words) AS bigint) AS matches FROM fsm_payloads p, LATERAL fsm_matches(p.p_name) m GROUP BY 1")


def sql_surface(spark, sf_dir):
    a = base(spark, sf_dir)
    publish(a, _depth_defaults(a))
    return spark.sql("SELECT s.depth, count(*) AS states, count(d.default) AS defaults, CAST(sum(d.w) AS bigint) AS shared FROM fsm_states s LEFT JOIN fsm_defaults d ON d.state = s.state GROUP BY 1")


def udf_similarity(spark, sf_dir):
    register(spark)
    base(spark, sf_dir).wide.createOrReplaceTempView("fsm_rows")
    return spark.sql("SELECT a.state, fsm_similarity(a.row, z.row) AS agree, fsm_bucket_key(a.row, array(0, 2, 4)) AS key FROM fsm_rows a JOIN fsm_rows z ON z.state = 0")


def udaf_modal_target(spark, sf_dir):
    register(spark)
    base(spark, sf_dir).transitions.createOrReplaceTempView("fsm_transitions")
    return spark.sql("SELECT symbol, fsm_modal_target(target) AS target FROM fsm_transitions GROUP BY symbol")


def sql_measures(spark, sf_dir):
    a = base(spark, sf_dir)
    publish(a, _depth_defaults(a))
    return spark.sql("SELECT t_in, t_out, (SELECT count(*) FROM fsm_labelled) AS labelled, (SELECT count(*) FROM fsm_edges) AS edges FROM fsm_measures")


QUERIES |= {f.__name__: f for f in (udtf_matches, sql_surface, sql_measures, udf_similarity, udaf_modal_target)}
ORACLES |= {
    "udtf_matches": W + _HEAD + ", p AS (SELECT p_partkey, p_name, unnest(range(1, length(p_name) + 1)) AS i FROM part WHERE p_name <> '') SELECT p_partkey, CAST(count(words.w) AS BIGINT) AS matches FROM p JOIN words ON substring(p_name, i - length(w) + 1, length(w)) = w AND i >= length(w) GROUP BY 1",
    "sql_surface": W + _DEPTH + ' SELECT pre.depth, count(*) AS states, count(dd."default") AS defaults, CAST(sum(dd.w) AS BIGINT) AS shared FROM pre LEFT JOIN dd ON dd.state = pre.state GROUP BY 1',
    "udaf_modal_target": W + _HEAD + ", c AS (SELECT symbol, target, count(*) AS n FROM tr GROUP BY 1, 2), m AS (SELECT *, row_number() OVER (PARTITION BY symbol ORDER BY n DESC, target) AS r FROM c) SELECT symbol, target FROM m WHERE r = 1",
    "sql_measures": W + _DEPTH + " SELECT t_in, t_in - sv + nd AS t_out, t_in - sv AS labelled, (SELECT count(*) FROM sh) AS edges FROM (SELECT (SELECT count(*) FROM tr) AS t_in, (SELECT CAST(sum(w) AS BIGINT) FROM dd) AS sv, (SELECT count(*) FROM dd) AS nd)",
    "udf_similarity": W + _HEAD + ", o AS (SELECT symbol, row_number() OVER (ORDER BY symbol) - 1 AS i FROM (SELECT DISTINCT symbol FROM tr)) SELECT t.state, CAST(count(*) FILTER (t.target = z.target) AS INTEGER) AS agree, string_agg(CAST(t.target AS VARCHAR), ',' ORDER BY o.i) FILTER (o.i IN (0, 2, 4)) AS key FROM tr t JOIN tr z ON z.state = 0 AND z.symbol = t.symbol JOIN o ON o.symbol = t.symbol GROUP BY 1",
}
