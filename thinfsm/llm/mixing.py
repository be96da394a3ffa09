"""Soft-membership mixing of documents to target domain weights.

A softmax classifier, learned from a labelled table, gives every document posteriors p over the
domains.  With n tokens per document and N in all, document rates r >= 0 are fitted so that the
expected token share of each domain, m = sum(n/N * r * p), meets its target:

    minimise  1/2 |m - target|^2 + ridge/2 * sum(n/N * (r - 1)^2)   over r >= 0

by projected gradients with momentum, in the metric that weighs a document by its tokens.  The
gradient of a document depends on others only through m - target, a handful of numbers, so an
iteration is one pass with a small sum, and a document's rate is replayed from the few numbers
of each past iteration: no vector of rates is ever shuffled or stored between iterations.

Learning uses at most ``sample_rows`` labelled rows; posteriors, tokens and rates cover every
document whole.

Cases: null and empty texts have no tokens: they have the posteriors of an empty text and the
rate that follows from them; without labelled rows there is one domain, "all"; domains
without a target get target 0, targets without a domain are ignored; no documents give no
rows; repeated rows get equal rates; of the columns to keep those with the name of a result give way to it.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .base import chunks, drop, lean, rows_of, sample_ids, store, text_buffer, trigram_counts, unit_roots
from .quality import N_FEATURES, features

RESULT = ("n_tokens", "posteriors", "domain", "rate")
#: Target token shares by domain of the labels: the production mix of the registered query.
TARGETS = {"plain": 0.9, "low": 0.05, "toxic": 0.05}


def domains_of(labels: DataFrame) -> DataFrame:
    """doc_id, domain from the labels of quality and toxicity; one row per id (the least domain of several)."""
    d = F.when(F.col("toxic") == 1, "toxic").when(F.col("quality") == 0, "low").when(F.col("quality") == 1, "plain")
    return labels.select("doc_id", d.alias("domain")).filter("domain is not null and doc_id is not null").groupBy("doc_id").agg(F.min("domain").alias("domain"))


@dataclass
class Model:
    domains: list[str]
    mean: np.ndarray
    scale: np.ndarray
    w: np.ndarray
    b: np.ndarray
    dims: int

    def inputs(self, data: np.ndarray, off: np.ndarray, i: int, j: int) -> np.ndarray:
        return inputs(data, off, i, j, self.dims)

    def posteriors(self, x: np.ndarray) -> np.ndarray:
        s = (x - self.mean) / self.scale @ self.w + self.b
        e = np.exp(s - s.max(1, keepdims=True))
        return e / e.sum(1, keepdims=True)


def inputs(data: np.ndarray, off: np.ndarray, i: int, j: int, dims: int) -> np.ndarray:
    """Byte trigram profile and the features of form."""
    return np.concatenate([unit_roots(trigram_counts(data, off, i, j, dims)), features(data, off, i, j).astype(np.float32)], 1)


def fit_softmax(x: np.ndarray, y: np.ndarray, k: int, rounds: int = 150, l2: float = 1e-3) -> tuple[np.ndarray, np.ndarray]:
    n, hot = len(x), np.eye(k, dtype=np.float32)[y]
    v = np.ones(x.shape[1], np.float32)
    for _ in range(12):  # largest curvature by power iteration
        v = x.T @ (x @ v)
        v /= max(float(np.linalg.norm(v)), 1e-12)
    step = 1 / (0.5 * (float(np.linalg.norm(x @ v)) ** 2 / n + 1) + l2)
    w, b = np.zeros((x.shape[1], k), np.float32), np.zeros(k, np.float32)
    vw, vb, t = w, b, 1.0
    for _ in range(rounds):
        s = x @ vw + vb
        e = np.exp(s - s.max(1, keepdims=True))
        g = (e / e.sum(1, keepdims=True) - hot) / n
        nw, nb = vw - step * (x.T @ g + l2 * vw), vb - step * g.sum(0)
        u = (1 + np.sqrt(1 + 4 * t * t)) / 2
        vw, vb = nw + (t - 1) / u * (nw - w), nb + (t - 1) / u * (nb - b)
        w, b, t = nw, nb, u
    return w, b


def train(docs: DataFrame, labelled: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", domain_col: str = "domain", sample_rows: int = 3000, dims: int = 2048) -> Model:
    """labelled: id and domain."""
    lab = labelled.select(F.col(id_col).alias("id"), F.col(domain_col).cast("string").alias("label"))
    ids = docs.sparkSession.createDataFrame(sample_ids(lab, "id", "label", sample_rows).collect(), "__id long, __label string")  # at most sample_rows small rows
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text")).join(F.broadcast(ids), F.col("id") == F.col("__id")).select("id", "__label", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            data, off = text_buffer(b.column("text"))
            for i, j in chunks(off):
                x = inputs(data, off, i, j, dims)
                yield pa.RecordBatch.from_arrays([b.column("id").slice(i, j - i), b.column("__label").slice(i, j - i), pa.array([r.astype(np.float16).tobytes() for r in x], pa.binary())], names=["id", "label", "x"])

    got = sorted(rows.mapInArrow(lean(run), "id long, label string, x binary").collect(), key=lambda r: (r[0], r[1], bytes(r[2])))
    width = dims + N_FEATURES
    x = np.array([np.frombuffer(r[2], np.float16) for r in got], np.float32).reshape(len(got), width)
    names = sorted({r[1] for r in got}) or ["all"]
    mean, scale = np.zeros(width, np.float32), np.full(width, 0.05, np.float32)
    if not len(got) or len(names) == 1:
        return Model(names, mean, scale, np.zeros((width, len(names)), np.float32), np.zeros(len(names), np.float32), dims)
    mean = x.mean(0)
    scale[dims:] = np.maximum(x[:, dims:].std(0), 1e-3)
    w, b = fit_softmax((x - mean) / scale, np.array([names.index(r[1]) for r in got]), len(names))
    # The sample has even shares; priors go back to those of the labelled table.
    share = {r[0]: r[1] for r in lab.groupBy("label").count().collect()} if len(names) <= 1000 else {}
    size = {v: sum(r[1] == v for r in got) for v in names}
    total = sum(share.values())
    if total:
        b = b + np.log(np.array([share[v] / total / (size[v] / len(got)) for v in names], np.float32))
    return Model(names, mean, scale, w, b, dims)


@dataclass
class Rates:
    """The past of the fit: what every document's rate is replayed from."""

    ridge: float
    step: float
    gradients: list[np.ndarray] = field(default_factory=list)  # m - target at each look-ahead point
    momenta: list[float] = field(default_factory=list)

    def replay(self, p: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Rates and look-ahead points of documents with posteriors p."""
        r = v = np.ones(len(p))
        for g, beta in zip(self.gradients, self.momenta):
            new = np.maximum(0.0, v - self.step * (p @ g + self.ridge * (v - 1)))
            r, v = new, new + beta * (new - r)
        return r, v


def fit_rates(members: DataFrame, target: np.ndarray, *, ridge: float = 0.003, rounds: int = 60, tolerance: float = 1e-4) -> Rates:
    """members: n (tokens), p (posteriors) of every document."""
    k = len(target)
    total = members.agg(F.sum("n")).first()[0] or 0
    past = Rates(ridge, 1.0 / (1.0 + ridge))
    if not total:
        return past
    t = 1.0
    for _ in range(rounds):

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            m = np.zeros(2 * k)
            for b in batches:
                p = np.array(b.column("p").flatten()).reshape(-1, k)
                w = b.column("n").to_numpy() / total
                r, v = past.replay(p)
                m += np.concatenate([(w * v) @ p, (w * r) @ p])
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(2 * k)), pa.array(m)], names=["d", "m"])

        # Added up as decimals, so the sum doesn't depend on the order of the tasks.
        parts = members.mapInArrow(lean(run), "d long, m double").groupBy("d").agg(F.sum(F.col("m").cast("decimal(38,24)")).cast("double").alias("m"))
        m = np.zeros(2 * k)
        for d, x in parts.collect():  # two numbers for each domain
            m[d] = x
        ahead, now = m[:k], m[k:]
        if past.gradients and np.abs(now - last).max() < tolerance:
            break
        last, u = now, (1 + np.sqrt(1 + 4 * t * t)) / 2
        past.gradients.append(ahead - target)
        past.momenta.append((t - 1) / u)
        t = u
    return past


def mix(docs: DataFrame, labelled: DataFrame, targets: dict[str, float], *, id_col: str = "doc_id", text_col: str = "text", tokens: float = 1.0, keep: tuple = (), model: Model | None = None, **how) -> DataFrame:
    """The columns in ``keep``, n_tokens, posteriors (by domain, in order of name), domain (likeliest) and rate of every document.

    targets: token shares by domain; tokens: tokens wanted in all, as a share of those there are."""
    model = model or train(docs, labelled, id_col=id_col, text_col=text_col)
    whole = sum(targets.get(d, 0.0) for d in model.domains) or 1.0
    target = np.array([targets.get(d, 0.0) / whole * tokens for d in model.domains])
    keep = [c for c in keep if c not in RESULT]
    kept = [F.col(f"`{c}`").alias(f"__k{i}") for i, c in enumerate(keep)]
    rows = docs.select(*kept, F.col(text_col).cast("string").alias("__text"))
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(rates: Rates | None):
        def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            m: Model = sent.value
            for b in batches:
                data, off = text_buffer(b.column("__text"))
                for i, j in chunks(off):
                    p = m.posteriors(m.inputs(data, off, i, j)).astype(np.float64)
                    n = pa.array([len(t.split()) for t in rows_of(data, off, i, j)], pa.int64())
                    ps = pa.array(list(p), pa.list_(pa.float64()))
                    if rates is None:
                        yield pa.RecordBatch.from_arrays([n, ps], names=["n", "p"])
                        continue
                    own = [c for c in b.schema.names if c != "__text"]
                    yield pa.RecordBatch.from_arrays(
                        [*(b.column(c).slice(i, j - i) for c in own), n, ps, pa.array([m.domains[d] for d in p.argmax(1)]), pa.array(rates.replay(p)[0])],
                        names=[*own, "n_tokens", "posteriors", "domain", "rate"],
                    )

        return go

    members = store(rows.select("__text").mapInArrow(lean(run(None)), "n long, p array<double>"))
    rates = fit_rates(members, target, **how)
    drop(members)
    schema = rows.drop("__text").schema.add("n_tokens", "long").add("posteriors", T.ArrayType(T.DoubleType())).add("domain", "string").add("rate", "double")
    out = rows.mapInArrow(lean(run(rates)), schema)
    return out.select(*[F.col(f"__k{i}").alias(c) for i, c in enumerate(keep)], *RESULT)
