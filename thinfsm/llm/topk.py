"""Exact top-k by integer inner product, with block-at-a-time pruning.

Vectors are put in order of their nearest pivot (a bounded sample of vectors), cut into shards
of bounded size, and each shard into blocks of like vectors, by halving it along the term
(dimension) of greatest spread.  A block keeps a forward index (its whole vectors) and, for each
term, the greatest and the least value in it.  For a query the bound of a block is the sum over
the terms of the query's value times the greatest or the least one, whichever gives more.

Queries go in groups of bounded size, in the same order as the shards.  A group meets its home
shard first, then ever wider rings of shards around it; between the rings its thresholds (each
query's k-th best score so far) are drawn together.  In a shard the group visits the blocks in
descending order of the bounds; a query scores a block only if the bound reaches its threshold,
which rises as it goes.  Ties go to the lesser id, so a bound equal to the threshold is scored too.

A task holds one shard while groups stream past it, and sends at most k rows per query, only
those that reach the threshold.  Neither queries nor vectors are broadcast.  Vectors travel in
two bytes a term where that holds them, and shards grow with the table (up to LARGEST rows), so
that the queries are sent SHARDS times at most up to there.

Cases: null vectors and vectors with null or non-finite components take no part, nor do null
ids.  Vectors of different lengths: only those of the commonest length take part (of equal
counts the least length), or (``every``) all of them, terms that one lacks counting 0.  Rows
that repeat an id are all candidates, and a query never returns its own id; of a query that
repeats an id the first vector in order asks, or (``every``) each of them, for the k best of
all.  Fewer than k candidates: all of them.  An empty table: none.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..model import numbered
from .base import drop, store

#: Vectors in the sample that gives the order.
PIVOTS = 1024
#: Shards that a table is cut into, while they hold between ``shard`` and LARGEST rows.
SHARDS, LARGEST = 256, 1 << 17
LOWEST = np.iinfo(np.int64).min
FOUND = "query_id long, vec_id long, score long, scored long, pairs long"


def quantised(vectors: DataFrame, id_col: str, vec_col: str, empty: bool = False) -> DataFrame:
    """id, v (floor(256 x), x as double) of the vectors that take part."""
    v = F.col("v")
    rows = vectors.select(F.col(id_col).cast("long").alias("id"), F.col(vec_col).cast("array<double>").alias("v")).filter("id is not null and v is not null")
    rows = rows.filter(F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & (F.lit(empty) | (F.size(v) > 0)))
    return rows.select("id", F.transform(v, lambda x: F.floor(x * 256).cast("long")).alias("v"))


def fitted(rows: DataFrame, width: int, every: bool) -> DataFrame:
    """The rows of that length, or all of them, filled up with zeros or cut."""
    if not every:
        return rows.filter(F.size("v") == width)
    return rows.withColumn("v", F.slice(F.concat("v", F.array_repeat(F.lit(0).cast("long"), width)), 1, width))


def matrix(raw: bytes, rows: int) -> np.ndarray:
    """Packed vectors: in two bytes a term, or in eight after a mark of one byte."""
    raw = np.frombuffer(raw, np.uint8)
    return raw[1:].view(np.int16 if raw[0] == 2 else np.int64).reshape(rows, -1) if rows else np.zeros((0, 0), np.int64)


def packed(v: list[np.ndarray]) -> bytes:
    narrow = all(x.dtype == np.int16 for x in v)
    return bytes([2 if narrow else 8]) + b"".join(np.ascontiguousarray(x, np.int16 if narrow else np.int64).tobytes() for x in v)


def narrowed(v: np.ndarray) -> np.ndarray:
    return v.astype(np.int16) if v.max(initial=0) < 1 << 15 and v.min(initial=0) >= -(1 << 15) else v


def listed(col: pa.Array) -> np.ndarray:
    """A column of lists of one length as a matrix."""
    return col.flatten().to_numpy(zero_copy_only=False).astype(np.int64).reshape(len(col), -1)


def exact_type(a: np.ndarray, b: np.ndarray) -> type:
    """The fastest type in which a @ b is exact: floats while they hold every sum, else integers."""
    top = lambda x: max(abs(float(x.max(initial=0))), abs(float(x.min(initial=0))))
    most = top(a) * top(b) * a.shape[1]
    return np.float32 if most < 2**24 else np.float64 if most < 2**52 else np.int64


def with_cells(rows: DataFrame, pivots: np.ndarray) -> DataFrame:
    """Adds the number of the pivot with the greatest cosine; only the order of rows depends on it."""
    sent = rows.sparkSession.sparkContext.broadcast(pivots / np.maximum(np.linalg.norm(pivots, axis=1, keepdims=True), 1e-9))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                cell = (listed(b.column("v")).astype(np.float64) @ sent.value.T).argmax(1)
                yield pa.RecordBatch.from_arrays([*b.columns, pa.array(cell, pa.int32())], names=["id", "v", "cell"])

    return rows.select("id", "v").mapInArrow(run, "id long, v array<long>, cell int")


def cut(rows: DataFrame, size: int) -> DataFrame:
    """rows: numbered as i.  at (number in order), ids, v (packed): runs of ``size`` rows, whatever the number of partitions."""
    placed = rows.select(F.expr(f"i div {size}").alias("at"), "i", "id", "v")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, ids, vs = None, [], []

        def emit() -> Iterator[pa.RecordBatch]:
            if ids:
                yield pa.RecordBatch.from_arrays([pa.array([last], pa.int64()), pa.array([np.concatenate(ids).tobytes()], pa.binary()), pa.array([packed(vs)], pa.binary())], names=["at", "ids", "v"])

        for b in batches:
            at = b.column("at").to_numpy()
            for k in dict.fromkeys(at.tolist()):
                own = b.filter(pa.array(at == k))
                if k != last:
                    yield from emit()
                    last, ids, vs = k, [], []
                ids.append(own.column("id").to_numpy().astype(np.int64))
                vs.append(narrowed(listed(own.column("v"))))
        yield from emit()

    return placed.repartition("at").sortWithinPartitions("at", "i").select("at", "id", "v").mapInArrow(run, "at long, ids binary, v binary")


def halved(v: np.ndarray, size: int) -> list[np.ndarray]:
    """Row numbers in blocks of at most ``size`` rows, by halving along the term of greatest spread."""
    out, todo = [], [np.arange(len(v))]
    while todo:
        rows = todo.pop()
        if len(rows) <= size:
            out.append(rows)
            continue
        term = int(v[rows[:: -(-len(rows) // 4096)]].std(0).argmax())
        rows = rows[np.argsort(v[rows, term], kind="stable")]
        todo += [rows[: len(rows) // 2], rows[len(rows) // 2 :]]
    return out


class Shard:
    """The blocks of a shard: forward indexes, and greatest and least values by term."""

    def __init__(self, ids: np.ndarray, v: np.ndarray, block: int):
        parts, self.type, self.terms = halved(v, block), None, []
        self.ids, self.v = [ids[p] for p in parts], [v[p] for p in parts]
        self.hi, self.lo = np.stack([x.max(0) for x in self.v]), np.stack([x.min(0) for x in self.v])

    def search(self, qids: np.ndarray, q: np.ndarray, cut: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, int]:
        """Query numbers, ids and scores of at most k rows per query that reach the thresholds; pairs of query and block scored."""
        t = exact_type(q, np.stack([self.hi, self.lo]))  # blocks lie between these
        if t is not self.type:
            self.type, self.terms = t, [np.ascontiguousarray(x.T, t) for x in self.v]
        exact = np.float64 if t is np.float32 else t  # a bound is a sum of two
        bound = (np.maximum(q, 0).astype(exact) @ self.hi.T.astype(exact) + np.minimum(q, 0).astype(exact) @ self.lo.T.astype(exact)).astype(np.int64)
        cut, scored, q = cut.copy(), 0, q.astype(t)
        who, ids, score = (np.zeros(0, np.int64) for _ in range(3))
        for b in np.argsort(-bound.max(0), kind="stable"):
            rows = np.flatnonzero(bound[:, b] >= cut)
            if not len(rows):
                continue
            scored += len(rows)
            s = (q if len(rows) == len(q) else q[rows]) @ self.terms[b]
            least = cut[rows]
            r, c = np.nonzero(s >= (least if t is np.int64 else np.maximum(least, -(1 << 53)).astype(t))[:, None])
            other = self.ids[b][c] != qids[rows[r]]
            r, c = r[other], c[other]
            if not len(r):
                continue
            new = s[r, c].astype(np.int64)
            who, ids, score = np.concatenate([who, rows[r]]), np.concatenate([ids, self.ids[b][c]]), np.concatenate([score, new])
            order = np.lexsort((ids, -score, who))
            who, ids, score = who[order], ids[order], score[order]
            first = np.concatenate([[True], who[1:] != who[:-1]])
            rank = np.arange(len(who)) - np.maximum.accumulate(np.where(first, np.arange(len(who)), 0))
            keep = rank < k
            who, ids, score, rank = who[keep], ids[keep], score[keep], rank[keep]
            last = rank == k - 1
            cut[who[last]] = np.maximum(cut[who[last]], score[last])
        keep = score >= cut[who]
        return who[keep], ids[keep], score[keep], scored


def meet(groups: DataFrame, shards: DataFrame, k: int, block: int) -> DataFrame:
    """groups: at of a shard, qids, qv, cut (each with its thresholds), once for every shard they are to meet.  FOUND rows.

    A shard and its groups come to one task in a row: the shard is held, the groups stream."""
    none = F.lit(None).cast("binary")
    first = shards.select("at", F.lit(0).alias("kind"), "ids", "v", none.alias("cut"))
    rest = groups.select("at", F.lit(1).alias("kind"), F.col("qids").alias("ids"), F.col("qv").alias("v"), "cut")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shard, held = None, None
        for b in batches:
            for at, kind, ids, v, cuts in zip(*(b.column(c) for c in ("at", "kind", "ids", "v", "cut"))):
                ids = np.frombuffer(ids.as_buffer(), np.int64)
                v = matrix(v.as_buffer(), len(ids))
                if not kind.as_py():
                    shard, held = None, None  # before the next takes its place in memory
                    shard, held = Shard(ids, v, block), at.as_py()
                    continue
                if at.as_py() != held:
                    raise RuntimeError(f"shard {at} of a group is missing")
                who, found, score, scored = shard.search(ids, v, np.frombuffer(cuts.as_buffer(), np.int64), k)
                pad = lambda x, y: pa.array(np.append(x, y), mask=np.append(np.zeros(len(x), bool), True))
                yield pa.RecordBatch.from_arrays(
                    [pad(ids[who], 0), pad(found, 0), pad(score, 0), pa.array(np.append(np.zeros(len(who), np.int64), scored)), pa.array(np.append(np.zeros(len(who), np.int64), len(ids) * len(shard.ids)))], names=["query_id", "vec_id", "score", "scored", "pairs"]
                )

    return first.unionByName(rest).repartition("at").sortWithinPartitions("at", "kind").mapInArrow(run, FOUND)


def best(found: DataFrame, k: int) -> DataFrame:
    w = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k)


def thresholds(asked: DataFrame, top: DataFrame | None, k: int) -> DataFrame:
    """asked (q, qids, qv) with cut: each query's k-th best score so far, or the least number."""
    lowest = lambda b: pa.array([np.full(len(x) // 8, LOWEST).tobytes() for x in b.column("qids").to_pylist()], pa.binary())
    schema = "q long, qids binary, qv binary, cut binary"
    if top is None:
        return asked.mapInArrow(lambda it: (pa.RecordBatch.from_arrays([b.column("q"), b.column("qids"), b.column("qv"), lowest(b)], names=["q", "qids", "qv", "cut"]) for b in it), schema)
    cut = top.groupBy("query_id").agg(F.when(F.count("*") >= k, F.min("score")).alias("cut")).filter("cut is not null")

    def unpacked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for q, raw in zip(b.column("q").to_pylist(), b.column("qids").to_pylist()):
                ids = np.frombuffer(raw, np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(ids), q)), pa.array(ids)], names=["q", "query_id"])

    def packed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            cuts = []
            for raw, known in zip(b.column("qids").to_pylist(), b.column("cuts").to_pylist()):
                own = {c["query_id"]: c["cut"] for c in known or ()}
                cuts.append(np.array([own.get(i, LOWEST) for i in np.frombuffer(raw, np.int64).tolist()], np.int64).tobytes())
            yield pa.RecordBatch.from_arrays([b.column("q"), b.column("qids"), b.column("qv"), pa.array(cuts, pa.binary())], names=["q", "qids", "qv", "cut"])

    known = asked.select("q", "qids").mapInArrow(unpacked, "q long, query_id long").join(cut, "query_id").groupBy("q").agg(F.collect_list(F.struct("query_id", "cut")).alias("cuts"))  # a group's queries at most
    return asked.join(known, "q", "left").select("q", "qids", "qv", "cuts").mapInArrow(packed, schema)


def search(vectors: DataFrame, queries: Column | DataFrame, *, id_col: str = "vec_id", vec_col: str = "embedding", k: int = 5, block: int = 64, shard: int = 4096, group: int = 512, every: bool = False, report: bool = False) -> DataFrame:
    """query_id, rank, vec_id, score.  queries: a condition on id ``id``, or a table like the vectors.

    report: instead, by ring, the pairs of query and block, and those that were scored."""
    spark = vectors.sparkSession
    rows = quantised(vectors, id_col, vec_col, every)
    empty = spark.createDataFrame([], "ring int, pairs long, scored long" if report else "query_id long, rank int, vec_id long, score long")
    widths = rows.groupBy(F.size("v").alias("w")).count()
    first = widths.orderBy(*([F.desc("w")] if every else [F.desc("count"), "w"])).first()
    if first is None:
        return empty
    width = max(1, first[0])
    rows = fitted(rows, width, every)
    pivots = np.array([r[0] for r in rows.orderBy(F.xxhash64("id"), "id", "v").limit(PIVOTS).select("v").collect()], np.float64)  # PIVOTS vectors
    rows = numbered(with_cells(rows, pivots), ["cell", "id"], "i")
    asked = with_cells(fitted(quantised(queries, id_col, vec_col, every), width, every), pivots) if isinstance(queries, DataFrame) else rows.filter(queries).select("id", "v", "cell")
    if not every:
        asked = asked.groupBy("id").agg(F.min(F.struct("v", "cell")).alias("x")).select("id", "x.v", "x.cell")
    shard = max(shard, min(LARGEST, rows.count() // SHARDS))
    shards = store(cut(rows, shard))
    asked = store(cut(numbered(asked, ["cell", "id"], "i"), group).select(F.col("at").alias("q"), F.col("ids").alias("qids"), F.col("v").alias("qv")))
    n, m = shards.count(), asked.count()
    if not m:
        return empty
    home = F.floor((F.col("q") + 0.5) * n / m).cast("long")
    top, rings, lo, hi = None, [], 0, 0
    while lo < n:
        near = F.sequence(F.greatest(home - hi, F.lit(0)), F.least(home + hi, F.lit(n - 1)))
        out = F.filter(near, lambda x: F.abs(x - home) >= lo)
        ring = thresholds(asked, top, k).withColumn("at", F.explode(out))
        found = store(meet(ring, shards, k, block))
        if report:
            rings.append(found.groupBy(F.lit(len(rings)).alias("ring")).agg(F.sum("pairs").alias("pairs"), F.sum("scored").alias("scored")))
        new = found.filter("query_id is not null").select("query_id", "vec_id", "score")
        old, top = top, store(best(new if top is None else top.unionByName(new), k).select("query_id", "vec_id", "score"))
        if old is not None:
            drop(old)
        if not report:
            drop(found)
        lo, hi = hi + 1, 4 * hi + 4
    if report:
        out = rings[0]
        for r in rings[1:]:
            out = out.unionByName(r)
        return out
    return best(top, k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


ORACLE = """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(256 * CAST(x AS DOUBLE)) AS BIGINT)) AS v FROM embeddings
           WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (SELECT q.vec_id AS query_id, d.vec_id AS vec_id, CAST(list_sum(list_transform(list_zip(q.v, d.v), lambda p: p[1] * p[2])) AS BIGINT) AS score
      FROM v q JOIN v d ON q.vec_id <> d.vec_id WHERE q.vec_id % 50 = 0),
r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM s)
SELECT query_id, CAST(rank AS INTEGER) AS rank, vec_id, score FROM r WHERE rank <= 5
"""
