"""Tables of automata and their fixed schemas.

An automaton is total over its alphabet: one target per state and symbol.  Long layout
(TRANSITIONS) serves SQL, wide layout (ROWS) moves a state's row as one array.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .scratch import store

RULES = "rule_set string, rule_id long, pattern string, kind string, ord int"
STATES = "automaton_id string, state long, is_start boolean, is_accept boolean, depth int"
TRANSITIONS = "automaton_id string, state long, symbol int, target long"
ROWS = "automaton_id string, state long, row array<int>"
EDGES = "automaton_id string, u long, v long, w int"
FOREST = "automaton_id string, state long, parent long, w int, level int, root long"
DEFAULTS = "automaton_id string, state long, default long"
MEASURES = "automaton_id string, algorithm string, n long, sigma long, t_in long, t_out long, labelled long, defaults long, size_pct double, longest_delay long, longest_chain long, edges long, tree_value long, cuts long"


@dataclass
class Automaton:
    """states: STATES; transitions: TRANSITIONS, total."""

    states: DataFrame
    transitions: DataFrame

    def rows(self) -> DataFrame:
        return to_wide(self.transitions)


@dataclass
class DelayedAutomaton:
    """states, the labelled transitions that are left, and defaults."""

    states: DataFrame
    labelled: DataFrame
    defaults: DataFrame


def to_wide(transitions: DataFrame) -> DataFrame:
    packed = transitions.groupBy("automaton_id", "state").agg(F.array_sort(F.collect_list(F.struct("symbol", "target"))).alias("s"))  # one row's symbols
    return packed.select("automaton_id", "state", F.col("s.target").cast("array<int>").alias("row"))


def to_long(rows: DataFrame) -> DataFrame:
    return rows.select("automaton_id", "state", F.posexplode("row").alias("symbol", "target")).select("automaton_id", "state", "symbol", F.col("target").cast("long").alias("target"))


def numbered(df: DataFrame, order: list[str], name: str) -> DataFrame:
    """Dense numbers from 0 in the order given, without bringing the rows to one task.

    A range sort deals out the rows and each partition numbers its own; that is stored, since a
    second evaluation may draw other bounds.  The partitions' sizes (a few numbers) give the
    offsets."""
    rows = store(df.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("__m", F.monotonically_increasing_id()))
    part, at = F.shiftright("__m", 33), F.col("__m").bitwiseAND(F.lit((1 << 33) - 1))
    size = rows.groupBy(part.alias("__p")).agg(F.count("*").alias("n"))
    offsets = size.select(F.col("__p").alias("__q"), (F.sum("n").over(Window.orderBy("__p")) - F.col("n")).alias("__o"))
    return rows.join(F.broadcast(offsets), part == F.col("__q")).withColumn(name, (at + F.col("__o")).cast("long")).drop("__m", "__q", "__o")


def validate(a: Automaton) -> DataFrame:
    """One row per automaton: totality, closed targets, one start, dense ids."""
    t = a.transitions.groupBy("automaton_id").agg(F.count("*").alias("t"), F.countDistinct("symbol").alias("sigma"), F.max("target").alias("hi"), F.min("target").alias("lo"))
    s = a.states.groupBy("automaton_id").agg(F.count("*").alias("n"), F.count_if("is_start").alias("starts"), F.max("state").alias("top"))
    return t.join(s, "automaton_id").select("automaton_id", (F.col("t") == F.col("n") * F.col("sigma")).alias("total"), ((F.col("lo") >= 0) & (F.col("hi") < F.col("n"))).alias("closed"), (F.col("starts") == 1).alias("one_start"), (F.col("top") == F.col("n") - 1).alias("dense_ids"))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
