"""Language identification by error-correcting output codes.

Each language has a codeword of +1/-1 bits.  For every bit a binary logistic classifier over
hashed byte trigrams (lower-cased letters; everything else a blank) predicts whether a text's
language has +1 there.  Decoding adds up, for each codeword, the logistic losses of the bits,
weighted by how well each bit does on the training rows; the least loss wins, and a text whose
two best codewords are closer than ``ambiguous_margin`` is flagged.

Learning uses a sample of at most ``sample_rows`` labelled rows (even shares per language);
prediction uses the whole of every text, whatever its length.

Cases: null text, or text without a letter, is ``und`` with score 0 and not ambiguous; an
empty training set gives ``und`` for everything; with one language every text with a letter is
that language; repeated rows give a row each; a null id is never held out nor learned from.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .base import chunks, fold_of, lean, rows_of, sample_ids, text_buffer, trigram_counts, unit_roots

UNKNOWN = "und"
_LETTER = regex.compile(r"\p{L}")
_ASCII_LETTER = regex.compile(rb"[A-Za-z]")


def codewords(k: int, seed: int = 7) -> np.ndarray:
    """k rows of +1/-1.  Up to 6 classes: every split of the classes once.  Beyond: the best of random codes."""
    if k <= 1:
        return np.ones((k, 1), np.float32)
    if k <= 6:
        splits = [[1 if (s >> c) & 1 else -1 for c in range(k)] for s in range(1, 1 << (k - 1))]
        return np.array(splits, np.float32).T
    rng, bits, best, code = np.random.default_rng(seed), int(10 * np.ceil(np.log2(k))), -1, None
    for _ in range(200):
        c = rng.choice([-1.0, 1.0], (k, bits)).astype(np.float32)
        apart = (bits - c @ c.T) / 2 + bits * np.eye(k)
        if apart.min() > best and np.all(np.abs(c.sum(0)) < k):
            best, code = apart.min(), c
    return code


def fit_logistic(x: np.ndarray, y: np.ndarray, *, rounds: int = 80, l2: float = 1e-4) -> tuple[np.ndarray, np.ndarray]:
    """Logistic regressions for all columns of y (+1/-1) at once, by accelerated gradient descent."""
    n, d = x.shape
    step = 4.0 / (1.25 + l2)  # rows have length 1, the intercept adds up to 1/4 of curvature
    w, b = np.zeros((d, y.shape[1]), np.float32), np.zeros(y.shape[1], np.float32)
    vw, vb, t = w.copy(), b.copy(), 1.0
    for _ in range(rounds):
        g = -y / (1 + np.exp(np.clip(y * (x @ vw + vb), -30, 30))) / n
        nw, nb = vw - 6 * step * (x.T @ g + l2 * vw), vb - step * g.sum(0)
        s = (1 + np.sqrt(1 + 4 * t * t)) / 2
        vw, vb = nw + (t - 1) / s * (nw - w), nb + (t - 1) / s * (nb - b)
        w, b, t = nw, nb, s
    return w, b


@dataclass
class Model:
    languages: list[str]
    code: np.ndarray
    weight: np.ndarray  # of the bits
    w: np.ndarray
    b: np.ndarray
    dims: int
    ambiguous_margin: float

    def losses(self, x: np.ndarray) -> np.ndarray:
        f = np.clip(x @ self.w + self.b, -30, 30)
        return np.log1p(np.exp(-f[:, None, :] * self.code[None])) @ self.weight

    def decode(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Number of the nearest codeword, its share among the codewords, ambiguity."""
        loss = self.losses(x)
        best = loss.argmin(1)
        e = np.exp(-(loss - loss.min(1, keepdims=True)) * self.code.shape[1])
        two = np.sort(loss, 1)
        tight = (two[:, 1] - two[:, 0] < self.ambiguous_margin) if loss.shape[1] > 1 else np.zeros(len(x), bool)
        return best, 1 / e.sum(1), tight


def features_of(docs: DataFrame, ids: DataFrame, dims: int) -> tuple[list, np.ndarray]:
    """Labels and trigram features of the sampled rows; texts stay on the executors."""
    rows = docs.join(F.broadcast(ids), docs["id"] == ids["__id"]).select("__label", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            data, off = text_buffer(b.column("text"))
            for i, j in chunks(off):
                x = unit_roots(trigram_counts(data, off, i, j, dims))
                at = [np.flatnonzero(r) for r in x]
                yield pa.RecordBatch.from_arrays([b.column("__label").slice(i, j - i), pa.array([a.astype(np.int16).tobytes() for a in at], pa.binary()), pa.array([r[a].astype(np.float16).tobytes() for r, a in zip(x, at)], pa.binary())], names=["label", "at", "x"])

    got = rows.mapInArrow(lean(run), "label string, at binary, x binary").collect()
    got.sort(key=lambda r: (r[0], bytes(r[1]), bytes(r[2])))
    x = np.zeros((len(got), dims), np.float32)
    for k, r in enumerate(got):
        x[k, np.frombuffer(r[1], np.int16)] = np.frombuffer(r[2], np.float16)
    return [r[0] for r in got], x


def train(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", label_col: str = "lang", sample_rows: int = 3000, dims: int = 4096, ambiguous_margin: float = 0.1) -> Model:
    """docs: the labelled rows to learn from."""
    assert dims <= 1 << 15, "positions are sent as 16-bit numbers"
    docs = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"), F.col(label_col).cast("string").alias("label")).filter("id is not null and label is not null")
    ids = sample_ids(docs, "id", "label", sample_rows)
    ids = docs.sparkSession.createDataFrame(ids.collect(), "__id long, __label string")  # at most sample_rows small rows
    labels, x = features_of(docs, ids, dims)
    names = sorted(set(labels))
    code = codewords(len(names))
    if len(names) < 2:
        return Model(names, code, np.ones(1, np.float32), np.zeros((dims, 1), np.float32), np.ones(1, np.float32), dims, 0.0)
    y = code[[names.index(v) for v in labels]]
    w, b = fit_logistic(x, y)
    right = (np.sign(x @ w + b) == y).mean(0)
    weight = np.maximum(2 * right - 1, 0.01).astype(np.float32)
    return Model(names, code, weight / weight.sum(), w, b, dims, ambiguous_margin)


def predict(docs: DataFrame, model: Model, *, id_col: str = "doc_id", text_col: str = "text", keep: tuple = ()) -> DataFrame:
    """doc_id, lang_pred, score, ambiguous, and the columns in ``keep``."""
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("__text"), *[F.col(c) for c in keep])
    schema = rows.drop("__text").schema.add("lang_pred", "string").add("score", "double").add("ambiguous", "boolean")
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m: Model = sent.value
        for b in batches:
            data, off = text_buffer(b.column("__text"))
            for i, j in chunks(off):
                letter = np.array([bool(_ASCII_LETTER.search(t)) or bool(_LETTER.search(t.decode("utf-8", "replace"))) for t in rows_of(data, off, i, j)], bool)
                if m.languages:
                    best, share, tight = m.decode(unit_roots(trigram_counts(data, off, i, j, m.dims)))
                else:
                    letter, best, share, tight = np.zeros(j - i, bool), np.zeros(j - i, int), np.zeros(j - i), np.zeros(j - i, bool)
                cols = [b.column(k).slice(i, j - i) for k, c in enumerate(b.schema.names) if c != "__text"]
                yield pa.RecordBatch.from_arrays(
                    [*cols, pa.array([m.languages[c] if ok else UNKNOWN for c, ok in zip(best, letter)], pa.string()), pa.array(np.where(letter, share, 0.0).astype(np.float64)), pa.array(tight & letter)],
                    names=[*(c for c in b.schema.names if c != "__text"), "lang_pred", "score", "ambiguous"],
                )

    return rows.mapInArrow(lean(run), schema)


def identify(docs: DataFrame, *, id_col: str = "doc_id", folds: int = 4, held: int = 2, **how) -> DataFrame:
    """Learn from the rows outside the held-out fold and predict every row."""
    fold = fold_of(id_col, folds)
    model = train(docs.filter((fold != held) & (fold >= 0)), id_col=id_col, **how)
    out = predict(docs, model, id_col=id_col)
    return out.select("doc_id", (fold_of("doc_id", folds) == held).alias("held_out"), "lang_pred", "score", "ambiguous")


def keep_known(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", label_col: str = "lang", least_score: float = 0.0, **how) -> DataFrame:
    """The documents that have a language, with their columns as they are: rejected are those
    without a letter and those whose winning codeword has a share below ``least_score``."""
    model = train(docs, id_col=id_col, text_col=text_col, label_col=label_col, **how)
    rest = [c for c in docs.columns]
    renamed = docs.select(*[F.col(f"`{c}`").alias(f"__c{k}") for k, c in enumerate(rest)])
    k_id, k_text = rest.index(id_col), rest.index(text_col)
    out = predict(renamed, model, id_col=f"__c{k_id}", text_col=f"__c{k_text}", keep=tuple(renamed.columns))
    out = out.filter((F.col("lang_pred") != UNKNOWN) & (F.col("score") >= least_score))
    return out.select(*[F.col(f"__c{k}").alias(c) for k, c in enumerate(rest)])
