"""Toxicity from the nearest labelled examples, by exact TF-IDF cosine over a block-max
inverted index.

Terms are chosen on the labelled sample: those that depend on the label.  The chance of a term
without bearing to divide as it does is at most exp(-rows * divergence from the label's
share); it has to be below ``risk`` over the number of terms tested.  Every term that passes is
kept; the others say nothing about the label and would drown those that do (a cosine over all
words finds texts of one subject, not of one tone).  Vectors hold (1 + log tf) * idf of the chosen terms of
the whole text, idf counted over all documents, and have length 1.  The labelled examples form
an inverted index cut into ranges of ``block`` examples; each term knows its greatest weight
in each range.  For a document the ranges are visited in descending order of the summed
products with those maxima, until the next bound is below the k-th cosine found: the k
nearest examples are exact, ties going to the lesser example id.

The vote is the cosine-weighted share of toxic examples among the neighbours.  A logistic
function of the vote, fitted on leave-one-out votes of the examples, gives the score; the
neighbours are the evidence.

The sample is bounded by ``sample_rows``, hence the index that is sent to the executors is.

Cases: null and empty texts and texts without any chosen term have no neighbours and get the
share of toxic examples among the examples without terms; without both labels in the sample
every score is that of the one label (0.5 if there is none); repeated rows give a row each.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .base import LETTER_BYTES, chunks, fold_of, lean, rows_of, sample_ids, text_buffer


def words(raw: bytes) -> list[bytes]:
    return raw.translate(LETTER_BYTES).split()


def labelled(docs: DataFrame, labels: DataFrame, *, id_col: str, text_col: str, label_col: str, folds: int, held: int, sample_rows: int) -> DataFrame:
    """Text and label of a bounded sample of the labelled rows outside the held-out fold."""
    fold = fold_of("id", folds)
    rows = labels.select(F.col(id_col).cast("long").alias("id"), F.col(label_col).cast("string").alias("label")).filter(F.col("label").isin("0", "1")).filter((fold != held) & (fold >= 0))
    ids = sample_ids(rows, "id", "label", sample_rows).collect()  # at most sample_rows small rows
    ids = docs.sparkSession.createDataFrame(ids, "__id long, __label string")
    return docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text")).join(F.broadcast(ids), F.col("id") == F.col("__id")).select("id", F.col("__label").cast("int").alias("label"), "text")


@dataclass
class Index:
    """Postings of the examples' unit vectors by term, cut into ranges of ``block`` examples, with the greatest weight of each term in each range."""

    ids: np.ndarray
    labels: np.ndarray
    vectors: list[tuple[np.ndarray, np.ndarray]] | np.ndarray  # terms and weights of each example, or a matrix of terms x examples
    block: int
    terms: int = 0
    owner: np.ndarray = field(init=False)  # examples, by term and number
    weight: np.ndarray = field(init=False)
    cut: np.ndarray = field(init=False)  # terms x (ranges + 1): where a term's postings of a range begin
    most: np.ndarray = field(init=False)  # terms x ranges

    def __post_init__(self):
        if isinstance(self.vectors, np.ndarray):
            self.terms, self.vectors = len(self.vectors), [(np.flatnonzero(w), w[np.flatnonzero(w)]) for w in self.vectors.T]
        term = np.concatenate([np.zeros(0, int), *(t for t, _ in self.vectors)])
        owner = np.repeat(np.arange(len(self.vectors)), [len(t) for t, _ in self.vectors])
        weight = np.concatenate([np.zeros(0), *(w for _, w in self.vectors)])
        order = np.lexsort((owner, term))
        term, self.owner, self.weight, self.vectors = term[order], owner[order], weight[order], []
        ranges = -(-len(self.ids) // self.block)
        place = term * ranges + self.owner // self.block
        count = np.bincount(place, minlength=self.terms * ranges).reshape(self.terms, ranges)
        ends = np.cumsum(count).reshape(count.shape)
        self.cut = np.concatenate([(ends - count)[:, :1], ends], 1) if ranges else np.zeros((self.terms, 1), int)
        self.most = np.zeros(self.terms * ranges)
        np.maximum.at(self.most, place, self.weight)
        self.most = self.most.reshape(self.terms, ranges)

    def cosines(self, terms: np.ndarray, q: np.ndarray, r: int) -> np.ndarray:
        """Cosines of a range's examples."""
        lo = r * self.block
        n = self.cut[terms, r + 1] - self.cut[terms, r]
        at = np.repeat(self.cut[terms, r] - np.cumsum(n) + n, n) + np.arange(n.sum())
        return np.round(np.bincount(self.owner[at] - lo, weights=np.repeat(q, n) * self.weight[at], minlength=min(self.block, len(self.ids) - lo)), 12)

    def nearest(self, terms: np.ndarray, q: np.ndarray, k: int, but: int = -1) -> tuple[np.ndarray, np.ndarray, int]:
        """Positions and cosines of the k nearest examples with a shared term, and ranges visited.  ``but``: a position to leave out."""
        bound = q @ self.most[terms]
        at, cos, seen = np.zeros(0, int), np.zeros(0), 0
        for r in np.argsort(-bound, kind="stable"):
            if bound[r] <= 0 or len(at) == k and bound[r] < cos[-1] - 1e-12:
                break
            seen += 1
            lo, c = r * self.block, self.cosines(terms, q, r)
            own = np.flatnonzero(c > 0)
            own = own[own != but - lo]
            at, cos = np.concatenate([at, own + lo]), np.concatenate([cos, c[own]])
            best = np.lexsort((self.ids[at], -cos))[:k]
            at, cos = at[best], cos[best]
        return at, cos, seen


@dataclass
class Model:
    terms: dict[bytes, int]
    idf: np.ndarray
    index: Index
    k: int
    prior: float
    a: float = 0.0
    b: float = 0.0

    def vector(self, counts: Counter) -> tuple[np.ndarray, np.ndarray]:
        t = np.array(sorted(counts), int)
        w = (1 + np.log([counts[x] for x in t])) * self.idf[t] if len(t) else np.zeros(0)
        return t, w / max(np.linalg.norm(w), 1e-12)

    def vote(self, counts: Counter, but: int = -1) -> tuple[float | None, np.ndarray, np.ndarray]:
        t, q = self.vector(counts)
        at, cos, _ = self.index.nearest(t, q, self.k, but) if len(t) else (np.zeros(0, int), np.zeros(0), 0)
        return (float(cos @ self.index.labels[at] / cos.sum()) if len(at) else None), at, cos

    def score(self, vote: float | None) -> float:
        return self.prior if vote is None else float(1 / (1 + np.exp(-np.clip(self.a * vote + self.b, -40, 40))))


def choose_terms(rows: DataFrame, risk: float) -> tuple[dict[bytes, int], int, int]:
    """Terms of the sample that depend on the label; numbers of toxic and other rows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            data, off = text_buffer(b.column("text"))
            y = b.column("label").to_pylist()
            for i, j in chunks(off):
                by = (Counter(), Counter())
                for k, raw in enumerate(rows_of(data, off, i, j)):
                    by[y[i + k]].update(set(words(raw)))
                for label in (0, 1):
                    yield pa.RecordBatch.from_arrays([pa.array(list(by[label]), pa.binary()), pa.array([label] * len(by[label]), pa.int32()), pa.array(list(by[label].values()), pa.int64())], names=["term", "label", "n"])

    size = {r[0]: r[1] for r in rows.groupBy("label").count().collect()}
    n1, n0 = size.get(1, 0), size.get(0, 0)
    if not n1 or not n0:
        return {}, n1, n0
    found = rows.mapInArrow(lean(run), "term binary, label int, n long").groupBy("term").agg(*[F.sum(F.when(F.col("label") == y, F.col("n")).otherwise(0)).cast("double").alias(c) for c, y in (("a", 1), ("b", 0))])
    found = found.persist()
    p, n = n1 / (n1 + n0), F.col("a") + F.col("b")
    part = lambda x, share: F.when(x > 0, x * F.log(x / (n * share))).otherwise(0.0)
    gain = part(F.col("a"), p) + part(F.col("b"), 1 - p)
    least = float(np.log(max(1, found.count()) / risk))
    best = found.withColumn("gain", gain).filter(F.col("gain") >= least).orderBy(F.desc("gain"), "term")  # terms of the bounded sample
    terms = {bytes(r[0]): k for k, r in enumerate(best.select("term").collect())}
    found.unpersist()
    return terms, n1, n0


def term_counts(raw: bytes, terms: dict[bytes, int]) -> Counter:
    return Counter(terms[w] for w in words(raw) if w in terms)


def corpus_frequencies(docs: DataFrame, terms: dict[bytes, int]) -> tuple[np.ndarray, int]:
    """Documents that hold each chosen term, and documents, over the whole table."""
    sent = docs.sparkSession.sparkContext.broadcast(terms)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        df, n, own = np.zeros(len(sent.value), np.int64), 0, sent.value
        for b in batches:
            data, off = text_buffer(b.column("text"))
            n += len(off) - 1
            for i, j in chunks(off):
                for raw in rows_of(data, off, i, j):
                    for t in {own[w] for w in own.keys() & set(words(raw))}:
                        df[t] += 1
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(-1, len(df))), pa.array(np.concatenate([[n], df]))], names=["t", "n"])

    got = {r[0]: r[1] for r in docs.select("text").mapInArrow(lean(run), "t long, n long").groupBy("t").agg(F.sum("n")).collect()}
    return np.array([got.get(t, 0) for t in range(len(terms))], float), int(got.get(-1, 0))


def train(docs: DataFrame, labels: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", folds: int = 5, held: int = 0, sample_rows: int = 4000, risk: float = 0.05, k: int = 15, block: int = 64) -> Model:
    rows = labelled(docs, labels, id_col=id_col, text_col=text_col, label_col=label_col, folds=folds, held=held, sample_rows=sample_rows).persist()
    chosen, n1, n0 = choose_terms(rows, risk)
    none = Index(np.zeros(0, int), np.zeros(0), [], block, len(chosen))
    if not chosen:
        rows.unpersist()
        return Model({}, np.zeros(0), none, k, n1 / (n1 + n0) if n1 + n0 else 0.5)
    df, n = corpus_frequencies(docs.select(F.col(text_col).cast("string").alias("text")), chosen)
    idf = np.log((1 + n) / (1 + df)) + 1e-3

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            data, off = text_buffer(b.column("text"))
            for i, j in chunks(off):
                got = [term_counts(raw, chosen) for raw in rows_of(data, off, i, j)]
                yield pa.RecordBatch.from_arrays([b.column("id").slice(i, j - i), b.column("label").slice(i, j - i), pa.array([list(g) for g in got], pa.list_(pa.int32())), pa.array([list(g.values()) for g in got], pa.list_(pa.int32()))], names=["id", "label", "t", "n"])

    got = sorted(rows.mapInArrow(lean(run), "id long, label int, t array<int>, n array<int>").collect())
    rows.unpersist()
    empty = [r[1] for r in got if not r[2]]
    own = [(r[0], r[1], Counter(dict(zip(r[2], r[3])))) for r in got if r[2]]
    model = Model(chosen, idf, none, k, (sum(empty) + 0.5 * n1 / (n1 + n0)) / (len(empty) + 0.5))
    model.index = Index(np.array([o[0] for o in own], np.int64), np.array([o[1] for o in own], float), [model.vector(c) for _, _, c in own], block, len(chosen))
    votes = [(model.vote(c, e)[0], y) for e, (_, y, c) in enumerate(own)]
    v = np.array([[x, y] for x, y in votes if x is not None]).reshape(-1, 2)
    model.a, model.b = calibrate(v[:, 0], v[:, 1])
    return model


def calibrate(v: np.ndarray, y: np.ndarray, l2: float = 1e-3) -> tuple[float, float]:
    """Logistic function of the vote, rising (or flat), by Newton steps."""
    z, w = np.stack([v, np.ones_like(v)], 1), np.array([4.0, -2.0])
    for _ in range(60 if len(v) else 0):
        p = 1 / (1 + np.exp(-np.clip(z @ w, -40, 40)))
        g, h = z.T @ (p - y) / len(v) + l2 * w, (z * (p * (1 - p))[:, None]).T @ z / len(v) + l2 * np.eye(2)
        w = w - np.clip(np.linalg.solve(h, g), -2, 2)
    return float(max(0.0, w[0])), float(w[1])


def score(docs: DataFrame, model: Model, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, score, vote, and as evidence the nearest examples: ids, cosines, labels."""
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m: Model = sent.value
        for b in batches:
            data, off = text_buffer(b.column("text"))
            for i, j in chunks(off):
                got = [m.vote(term_counts(raw, m.terms)) if m.terms else (None, [], []) for raw in rows_of(data, off, i, j)]
                evidence = [[{"doc_id": int(m.index.ids[a]), "cosine": float(c), "toxic": int(m.index.labels[a])} for a, c in zip(at, cos)] for _, at, cos in got]
                yield pa.RecordBatch.from_arrays(
                    [b.column("doc_id").slice(i, j - i), pa.array([m.score(g[0]) for g in got], pa.float64()), pa.array([g[0] for g in got], pa.float64()), pa.array(evidence, pa.list_(pa.struct([("doc_id", pa.int64()), ("cosine", pa.float64()), ("toxic", pa.int32())])))],
                    names=["doc_id", "score", "vote", "evidence"],
                )

    return rows.mapInArrow(lean(run), "doc_id long, score double, vote double, evidence array<struct<doc_id:bigint,cosine:double,toxic:int>>")


def detect(docs: DataFrame, labels: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", folds: int = 5, held: int = 0, decision: float = 0.5, **how) -> DataFrame:
    model = train(docs, labels, id_col=id_col, text_col=text_col, folds=folds, held=held, **how)
    return score(docs, model, id_col=id_col, text_col=text_col).select("doc_id", (fold_of("doc_id", folds) == held).alias("held_out"), "score", (F.col("score") >= decision).cast("int").alias("predicted"), "vote", "evidence")
