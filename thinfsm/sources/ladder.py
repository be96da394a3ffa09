"""Data source ``fsm_ladder``: automata made on the fly, for scale tests; rules and automata on disk.

``spark.read.format("fsm_ladder").option("automata", 1000).option("states", 5000)`` yields ROWS of
random automata whose rows are near copies of a few patterns, a partition per run of automata.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from .. import rules
from ..model import ROWS, RULES, Automaton


def read_payload_files(spark: SparkSession, path: str) -> DataFrame:
    """payload_id, path, body of the files below a folder (captured traffic): any store that Spark reads; body is read only where it is selected; Spark leaves out empty files."""
    files = spark.read.format("binaryFile").option("recursiveFileLookup", "true").load(path)
    return files.select(F.xxhash64("path").alias("payload_id"), "path", F.col("content").alias("body"))


class _Run(InputPartition):
    def __init__(self, lo: int, hi: int):
        self.lo, self.hi = lo, hi


class LadderReader(DataSourceReader):
    def __init__(self, options):
        get = lambda k, d: int(options.get(k, d))
        self.automata, self.states, self.sigma, self.seed, self.parts = get("automata", 8), get("states", 1000), get("sigma", 64), get("seed", 1), get("partitions", 8)

    def partitions(self):
        cut = [self.automata * i // self.parts for i in range(self.parts + 1)]
        return [_Run(a, b) for a, b in zip(cut, cut[1:]) if a < b]

    def read(self, part: _Run) -> Iterator[pa.RecordBatch]:
        for a in range(part.lo, part.hi):
            t = random_table(self.states, self.sigma, self.seed + a)
            yield pa.RecordBatch.from_arrays([pa.array([f"a{a}"] * len(t)), pa.array(np.arange(len(t))), pa.array(list(t), pa.list_(pa.int32()))], names=["automaton_id", "state", "row"])


class LadderSource(DataSource):
    @classmethod
    def name(cls):
        return "fsm_ladder"

    def schema(self):
        return ROWS

    def reader(self, schema):
        return LadderReader(self.options)


def random_table(n: int, sigma: int, seed: int, patterns: int = 8, noise: float = 0.05) -> np.ndarray:
    """Total automaton in which every state is reached: rows are few patterns with noise, and a path through all states."""
    r = np.random.default_rng(seed)
    base = r.integers(0, n, (patterns, sigma))
    t = base[r.integers(0, patterns, n)]
    other = r.random((n, sigma)) < noise
    t[other] = r.integers(0, n, int(other.sum()))
    t[np.arange(n - 1), r.integers(0, sigma, n - 1)] = np.arange(1, n)
    return t.astype(np.int32)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(LadderSource)


def read_rules(spark: SparkSession, path: str, fmt: str = "text", rule_set: str = "rules") -> DataFrame:
    """RULES from lines of text, CSV or JSON with a pattern column; order by text."""
    raw = spark.read.text(path).withColumnRenamed("value", "pattern") if fmt == "text" else spark.read.format(fmt).option("header", True).load(path).select("pattern")
    from ..model import numbered

    out = numbered(raw.filter("pattern is not null and pattern <> ''").distinct(), ["pattern"], "rule_id")
    return out.select(F.lit(rule_set).alias("rule_set"), "rule_id", "pattern", F.lit("regex").alias("kind"), F.col("rule_id").cast("int").alias("ord"))


def split_supported(rules_df: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Rules inside the subset, and the others with the reason."""

    def check(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array([rules.supported(p) for p in b.column("pattern").to_pylist()], pa.string())], names=[*b.schema.names, "reason"])

    out = rules_df.mapInArrow(check, f"{RULES}, reason string")
    return out.filter("reason is null").drop("reason"), out.filter("reason is not null")


def write_automaton(a: Automaton, path: str) -> None:
    """Parquet by automaton, sorted by state inside, so that row joins read runs."""
    a.states.write.mode("overwrite").partitionBy("automaton_id").parquet(f"{path}/states")
    a.transitions.repartition("automaton_id").sortWithinPartitions("automaton_id", "state", "symbol").write.mode("overwrite").partitionBy("automaton_id").parquet(f"{path}/transitions")


def read_automaton(spark: SparkSession, path: str) -> Automaton:
    return Automaton(spark.read.parquet(f"{path}/states"), spark.read.parquet(f"{path}/transitions"))


def compact(rows: DataFrame, defaults: DataFrame) -> DataFrame:
    """automaton_id, state, default, blob: the labelled transitions of a state as packed (symbol byte, target int32) pairs, for deployment."""
    both = rows.join(defaults.select("automaton_id", "state", "default"), ["automaton_id", "state"]).join(rows.select("automaton_id", F.col("state").alias("default"), F.col("row").alias("given")), ["automaton_id", "default"], "left")

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for row, given in zip(b.column("row").to_pylist(), b.column("given").to_pylist()):
                row = np.array(row, np.int32)
                at = np.arange(len(row)) if given is None else np.flatnonzero(row != np.array(given, np.int32))
                out.append(at.astype(np.uint8).tobytes() + row[at].tobytes())
            yield pa.RecordBatch.from_arrays([b.column("automaton_id"), b.column("state"), b.column("default"), pa.array(out, pa.binary())], names=["automaton_id", "state", "default", "blob"])

    return both.select("automaton_id", "state", "default", "row", "given").mapInArrow(pack, "automaton_id string, state long, default long, blob binary")


QUERIES, ORACLES = {}, {}


def ladder_of_orders(spark: SparkSession, sf_dir: str, sigma: int = 8) -> DataFrame:
    """ROWS of an automaton per customer, a state per order: rows are near copies of the priorities' patterns, and a path leads through all states."""
    from ..model import table

    o = table(spark, sf_dir, "orders").filter("o_custkey is not null and o_orderkey is not null and o_orderpriority is not null")
    own = Window.partitionBy("o_custkey")
    o = o.select(F.concat(F.lit("a"), "o_custkey").alias("automaton_id"), (F.row_number().over(own.orderBy("o_orderkey", "o_orderpriority")) - 1).cast("long").alias("state"), F.count("*").over(own).alias("n"), F.pmod("o_orderkey", F.lit(sigma)).alias("on"), F.ascii("o_orderpriority").alias("p"))
    row = F.transform(F.sequence(F.lit(0), F.lit(sigma - 1)), lambda s: F.when(s == F.col("on"), F.col("state") + 1).otherwise(F.col("p") * (s + 1)) % F.col("n"))
    return o.select("automaton_id", "state", row.cast("array<int>").alias("row"))


def ladder_source(spark: SparkSession, sf_dir: str) -> DataFrame:
    """States, alphabet and distinct rows of each customer's automaton."""
    return ladder_of_orders(spark, sf_dir).groupBy("automaton_id").agg(F.count("*").alias("states"), F.min(F.size("row")).alias("sigma"), F.count_distinct("row").alias("kinds"))


ORACLES["ladder_source"] = """
WITH o AS (SELECT 'a' || o_custkey AS automaton_id, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderkey, o_orderpriority) - 1 AS state, count(*) OVER (PARTITION BY o_custkey) AS n, o_orderkey % 8 AS on_, ascii(o_orderpriority) AS p
           FROM orders WHERE o_custkey IS NOT NULL AND o_orderkey IS NOT NULL AND o_orderpriority IS NOT NULL),
r AS (SELECT automaton_id, list_transform(range(8), lambda s: CASE WHEN s = on_ THEN state + 1 ELSE p * (s + 1) END % n) AS row FROM o)
SELECT automaton_id, count(*) AS states, CAST(min(len(row)) AS INTEGER) AS sigma, count(DISTINCT row) AS kinds FROM r GROUP BY 1
"""


def compact_size(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bytes of the packed names dictionary: 5 per labelled transition."""
    from .. import compress
    from ..plans.workloads import workload

    rows = workload(spark, sf_dir, "names")
    d = compress.defaults_of(rows, "dense_depth")
    return compact(rows, d).agg(F.sum(F.length("blob")).alias("bytes"), F.count("default").alias("defaults"))


QUERIES |= {"ladder_source": ladder_source, "compact_size": compact_size}
