"""Quality classifier: Bradley-Terry ranking from preference pairs.

Labelled documents of quality 1 are preferred to those of quality 0.  The chance of a preference
is the logistic function of the difference of the two documents' scores, a score being linear in
features of the text; weights are fitted by logistic loss on feature differences.  The cut
between the classes is the quantile of the training scores at the share of low-quality training
rows; it is mapped to the given decision point, so that ``score >= decision`` is
``latent >= cut``.

Features (of whole texts): shares of byte kinds, word lengths, distinct words and lines,
capitalised words, words that end in signs, log length.  Labels, language, source and id are
no inputs.

Learning uses every labelled row outside the held-out fold.  The rows are dealt by a hash of the
id into bins of about ``size`` rows, and in a bin every good row is preferred to every bad one;
where one class is rare its rows go to several bins, so that each bin has about RARE of them.
A bin's features are one stored row.  Newton steps for the weights and the slope, and the
narrowing of the quantile, are passes over the bins that give sums of fixed size.

Cases: null and empty texts have the features of a text without words and are scored; without
both labels in the training rows every score is 0.5; labels that are null are left out; a
document with several label rows counts once per label; repeated rows give a row each.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .base import LOWER_BYTES, chunks, fold_of, lean, rows_of, store, text_buffer

#: Kinds of bytes: 0 lower-case letter or beyond ASCII, 1 capital, 2 digit, 3 blank, 4 line feed, 5 point or comma, 6 '!' or '?', 7 '|', 8 other signs, 9 control characters.
KINDS = np.array([9 if c < 32 and c not in (9, 10, 13) or c == 127 else 4 if c == 10 else 3 if c in (9, 13, 32) else 2 if 48 <= c <= 57 else 1 if 65 <= c <= 90 else 0 if 97 <= c <= 122 or c > 127 else 5 if chr(c) in ".," else 6 if chr(c) in "!?" else 7 if chr(c) == "|" else 8 for c in range(256)], np.int64)
N_KINDS = 10
N_FEATURES = N_KINDS + 8
#: Rows of a rare class in a bin; parts of the range in a pass for the quantile.
RARE, PARTS = 16, 1024


def features(data: np.ndarray, off: np.ndarray, i: int, j: int) -> np.ndarray:
    n, lens = j - i, np.diff(off[i : j + 1])
    kind = KINDS[data[off[i] : off[j]]]
    kind += np.repeat(np.arange(n, dtype=np.int64) * N_KINDS, lens)
    x = np.zeros((n, N_FEATURES))
    x[:, :N_KINDS] = np.sqrt(np.bincount(kind, minlength=n * N_KINDS).reshape(n, N_KINDS) / np.maximum(lens, 1)[:, None])
    for k, raw in enumerate(rows_of(data, off, i, j)):
        words = raw.translate(LOWER_BYTES).split()
        lines = raw.split(b"\n")
        m = max(1, len(words))
        own = set(words)
        ends = sum(1 for w in own if w[-1] < 48 and w[-1] not in b".,'\")") / max(1, len(own))
        x[k, N_KINDS:] = len(own) / m, np.log1p(len(words)) / 8, len(own) / np.sqrt(m) / 8, sum(map(len, words)) / m / 10, len(set(lines)) / len(lines), ends, sum(map(len, own)) / max(1, len(own)) / 10, len(raw) > 0
    return x


@dataclass
class Model:
    mean: np.ndarray
    scale: np.ndarray
    w: np.ndarray
    cut: float
    slope: float
    decision: float

    def latent(self, x: np.ndarray) -> np.ndarray:
        return (x - self.mean) / self.scale @ self.w

    def score(self, x: np.ndarray) -> np.ndarray:
        at = np.log(self.decision / (1 - self.decision))
        return 1 / (1 + np.exp(-np.clip(self.slope * (self.latent(x) - self.cut) + at, -40, 40)))


def blank() -> Model:
    return Model(np.zeros(N_FEATURES), np.ones(N_FEATURES), np.zeros(N_FEATURES), 0.0, 0.0, 0.5)


def passed(bins: DataFrame, kernel, join=np.add) -> np.ndarray | None:
    """What ``kernel(x, y, once)`` gives for each bin, joined over all bins; a task sends one array."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out, first = None, None
        for b in batches:
            for k, x, y, once in zip(*(b.column(c) for c in ("bin", "x", "y", "once"))):
                y = np.frombuffer(y.as_buffer(), np.uint8)
                new = kernel(np.frombuffer(x.as_buffer()).reshape(len(y), -1), y, np.frombuffer(once.as_buffer(), np.uint8).astype(bool))
                out, first = (new, k.as_py()) if out is None else (join(out, new), first)
        if out is not None:
            yield pa.RecordBatch.from_arrays([pa.array([first], pa.int64()), pa.array([out.tobytes()], pa.binary())], names=["first", "sums"])

    got = sorted((r[0], bytes(r[1])) for r in bins.mapInArrow(lean(run), "first long, sums binary").collect())  # a row for each task
    out = None
    for _, raw in got:
        new = np.frombuffer(raw)
        out = new if out is None else join(out, new)
    return out


def preferences(w: np.ndarray, mean: np.ndarray, scale: np.ndarray):
    """Kernel: pairs, loss, gradient and curvature of the Bradley-Terry loss over a bin's pairs."""

    def kernel(x: np.ndarray, y: np.ndarray, once: np.ndarray) -> np.ndarray:
        z = (x - mean) / scale
        good, bad = z[y == 1], z[y == 0]
        n, loss, g, h = len(good) * len(bad), 0.0, np.zeros(len(w)), np.zeros((len(w), len(w)))
        for i in range(0, len(good), 1024):
            a = good[i : i + 1024]
            m = np.clip((a @ w)[:, None] - bad @ w, -500, 500)
            p = 1 / (1 + np.exp(m))
            q = p * (1 - p)
            loss += np.logaddexp(0, -m).sum()
            g += p.sum(0) @ bad - p.sum(1) @ a
            cross = a.T @ q @ bad
            h += (a.T * q.sum(1)) @ a + (bad.T * q.sum(0)) @ bad - cross - cross.T
        return np.concatenate([[n, loss], g, h.ravel()])

    return kernel


def weights(bins: DataFrame, mean: np.ndarray, scale: np.ndarray, l2: float, rounds: int) -> np.ndarray:
    """Newton steps, halved where the loss would rise."""
    k = len(mean)

    def at(w: np.ndarray) -> tuple[float, np.ndarray, np.ndarray]:
        s = passed(bins, preferences(w, mean, scale))
        n = max(1.0, s[0])
        return s[1] / n + l2 * float(w @ w) / 2, s[2 : 2 + k] / n + l2 * w, s[2 + k :].reshape(k, k) / n + l2 * np.eye(k)

    w = np.zeros(k)
    loss, g, h = at(w)
    step = np.linalg.solve(h, g)
    for _ in range(rounds):
        new = at(w - step)
        if new[0] > loss + 1e-12:
            step = step / 2
        else:
            w, (loss, g, h) = w - step, new
            step = np.linalg.solve(h, g)
        if np.abs(step).max() < 1e-6:
            break
    return w


def ranked(bins: DataFrame, latent, rank: int) -> tuple[float, float | None]:
    """The value with ``rank`` values below it in order, and the next greater one: counts over a range that narrows until one value is left."""
    ends = passed(bins, lambda x, y, once: np.array([-latent(x)[once].min(initial=np.inf), latent(x)[once].max(initial=-np.inf)]), np.maximum)
    lo, hi, above = -ends[0], ends[1], None
    while lo < hi:
        def kernel(x, y, once, lo=lo, hi=hi):
            v = latent(x)[once]
            below = (v < lo).sum()
            v = v[(v >= lo) & (v <= hi)]
            at = np.minimum((v - lo) / (hi - lo) * PARTS, PARTS - 1).astype(int)
            least, most = np.full(PARTS, np.inf), np.full(PARTS, -np.inf)
            np.minimum.at(least, at, v)
            np.maximum.at(most, at, v)
            return np.concatenate([[below], np.bincount(at, minlength=PARTS), least, most])

        def join(a, b):
            n = PARTS + 1
            return np.concatenate([a[:n] + b[:n], np.minimum(a[n : n + PARTS], b[n : n + PARTS]), np.maximum(a[n + PARTS :], b[n + PARTS :])])

        s = passed(bins, kernel, join)
        count, least, most = s[1 : PARTS + 1], s[PARTS + 1 : 2 * PARTS + 1], s[2 * PARTS + 1 :]
        k = int(np.searchsorted(s[0] + np.cumsum(count), rank, side="right"))
        later = least[k + 1 :][count[k + 1 :] > 0]
        above = float(later[0]) if len(later) else above
        lo, hi = float(least[k]), float(most[k])
    return lo, above


def fit(bins: DataFrame, *, decision: float, rounds: int = 40, l2: float = 1e-3) -> Model:
    """Bradley-Terry weights, cut and slope from every row of the bins."""
    s = passed(bins, lambda x, y, once: np.concatenate([[once.sum(), (y[once] == 0).sum()], x[once].sum(0)]))
    if s is None or not 0 < s[1] < s[0]:
        return blank()
    n, bad, mean = s[0], int(s[1]), s[2:] / s[0]
    scale = np.maximum(np.sqrt(passed(bins, lambda x, y, once: ((x[once] - mean) ** 2).sum(0)) / n), 1e-6)
    w = weights(bins, mean, scale, l2, rounds)
    latent = lambda x: (x - mean) / scale @ w
    # Between the two classes the cut is as far from either as it can be at that quantile.
    cut, above = ranked(bins, latent, bad - 1)
    cut = cut if above is None else (cut + above) / 2
    slope, at = 1.0, np.log(decision / (1 - decision))
    for _ in range(50):  # one-parameter calibration by Newton steps
        def kernel(x, y, once, slope=slope):
            v = latent(x)[once] - cut
            p = 1 / (1 + np.exp(-np.clip(slope * v + at, -40, 40)))
            return np.array([((p - y[once]) * v).sum(), (p * (1 - p) * v**2).sum()])

        g, h = passed(bins, kernel) / n
        old, slope = slope, float(np.clip(slope - (g + 1e-3 * slope) / (h + 1e-3), 0.05, 50))
        if abs(slope - old) < 1e-6:
            break
    return Model(mean, scale, w, cut, slope, decision)


def featured(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, x (features) of every document."""
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            data, off = text_buffer(b.column("text"))
            for i, j in chunks(off):
                x = features(data, off, i, j)
                yield pa.RecordBatch.from_arrays([b.column("doc_id").slice(i, j - i), pa.array([r.tobytes() for r in x], pa.binary())], names=["doc_id", "x"])

    return rows.mapInArrow(lean(run), "doc_id long, x binary")


def binned(feats: DataFrame, labels: DataFrame, *, id_col: str = "doc_id", label_col: str = "quality", folds: int = 5, held: int = 0, size: int = 512) -> DataFrame:
    """bin, x, y, once: features and labels of every labelled row outside the held-out fold; ``once`` marks each row in one of its bins."""
    fold = fold_of("id", folds)
    rows = labels.select(F.col(id_col).cast("long").alias("id"), F.col(label_col).cast("string").alias("label")).filter(F.col("label").isin("0", "1")).filter((fold != held) & (fold >= 0)).distinct()
    rows = store(feats.join(rows, F.col("doc_id") == F.col("id")).select("id", F.col("label").cast("int").alias("y"), "x"))
    count = dict(rows.groupBy("y").count().collect())
    bins = max(1, -(-sum(count.values()) // size))
    times = {y: min(bins, max(1, -(-RARE * bins // n))) for y, n in count.items()}
    copies = F.when(F.col("y") == 1, F.lit(times.get(1, 1))).otherwise(F.lit(times.get(0, 1)))
    dealt = rows.withColumn("k", F.explode(F.sequence(F.lit(0), copies - 1))).withColumn("bin", F.pmod(F.pmod(F.xxhash64("id"), F.lit(bins)) + F.col("k"), F.lit(bins)))

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, last = [], None

        def sent() -> Iterator[pa.RecordBatch]:
            if own:
                x, y, once = zip(*own)
                yield pa.RecordBatch.from_arrays([pa.array([last], pa.int64()), *(pa.array([v], pa.binary()) for v in (b"".join(x), bytes(y), bytes(once)))], names=["bin", "x", "y", "once"])

        for b in batches:
            for k, x, y, once in zip(*(b.column(c).to_pylist() for c in ("bin", "x", "y", "k"))):
                if k != last:
                    yield from sent()
                    own, last = [], k
                own.append((x, y, int(once == 0)))
        yield from sent()

    return store(dealt.select("bin", "x", "y", "k", "id").repartition("bin").sortWithinPartitions("bin", "id", "y", "x", "k").mapInArrow(lean(pack), "bin long, x binary, y binary, once binary"))


def train(docs: DataFrame, labels: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality", folds: int = 5, held: int = 0, decision: float = 0.3) -> Model:
    feats = featured(docs, id_col=id_col, text_col=text_col)
    return fit(binned(feats, labels, id_col=id_col, label_col=label_col, folds=folds, held=held), decision=decision)


def scored(feats: DataFrame, model: Model) -> DataFrame:
    """doc_id, latent (Bradley-Terry score), score of every document."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                x = np.frombuffer(b"".join(b.column("x").to_pylist())).reshape(b.num_rows, -1)
                yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(model.latent(x)), pa.array(model.score(x))], names=["doc_id", "latent", "score"])

    return feats.mapInArrow(lean(run), "doc_id long, latent double, score double")


def score(docs: DataFrame, model: Model, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, latent, score of every document."""
    return scored(featured(docs, id_col=id_col, text_col=text_col), model)


def rank(docs: DataFrame, labels: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality", folds: int = 5, held: int = 0, decision: float = 0.3) -> DataFrame:
    """doc_id, held_out, score, predicted, latent of every document."""
    feats = store(featured(docs, id_col=id_col, text_col=text_col))  # texts are read once
    model = fit(binned(feats, labels, id_col=id_col, label_col=label_col, folds=folds, held=held), decision=decision)
    return scored(feats, model).select("doc_id", (fold_of("doc_id", folds) == held).alias("held_out"), "score", (F.col("score") >= decision).cast("int").alias("predicted"), "latent")
