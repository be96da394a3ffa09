"""Benchmark decontamination: one Aho-Corasick automaton over the windows of normalised
test items, run once over every text, with offsets mapped back to the original.

A word is a run of digits, letters a-z (A-Z lower-cased) and characters beyond ASCII.  A
window is ``width`` consecutive words of an item; an item of fewer words is one window.  Text
is normalised to its words joined by blanks, as UTF-8 bytes, and the automaton runs over
those bytes.

Cases: null or wordless text has no words and no hits; a null, empty or wordless item gives
no window; items with a null id are left out; equal items count one each; repeated documents
give a row each; other columns are ignored.

The automaton is sent to the executors.  Its patterns are at most ``group_bytes`` bytes; a
larger benchmark is cut into groups, each scanned by an automaton of its own, and the hits of
a document are merged, so memory is bounded whatever the benchmark's size.
"""

from __future__ import annotations

import itertools
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .base import WORD_BYTES, chunks, lean, rows_of, store, text_buffer

SCHEMA = "doc_id long, n_words long, hits array<int>, items array<string>, spans array<struct<start:int,end:int>>"


def normal(text: bytes) -> bytes:
    return b" ".join(text.translate(WORD_BYTES).split())


def windows(text: bytes, width: int) -> set[bytes]:
    w = text.translate(WORD_BYTES).split()
    return {b" ".join(w[i : i + width]) for i in range(max(1, len(w) - width + 1))} if w else set()


def automaton(patterns: dict[bytes, list[str]]):
    import ahocorasick

    a = ahocorasick.Automaton()
    for p, items in patterns.items():
        a.add_word(f" {p.decode('latin-1')} ", (p.count(b" ") + 1, tuple(items)))
    a.make_automaton()
    return a


def word_spans(raw: bytes) -> np.ndarray:
    """Code point offsets (start, end) of the words of a text."""
    b = np.frombuffer(raw, np.uint8)
    inside = np.frombuffer(WORD_BYTES, np.uint8)[b] != 32
    edge = np.flatnonzero(np.diff(np.concatenate([[False], inside, [False]]).astype(np.int8)))
    points = np.concatenate([[0], np.cumsum((b & 0xC0) != 0x80)])
    return points[edge].reshape(-1, 2)


def scan(raw: bytes, a) -> tuple[int, list[int], list[str], list[dict]]:
    """Words, numbers of hit words, items found, and spans of runs of hit words in the text as given."""
    text = normal(raw)
    n = text.count(b" ") + 1 if text else 0
    if not n:
        return 0, [], [], []
    found, items = [], set()
    for end, (k, own) in a.iter(f" {text.decode('latin-1')} "):
        found.append((end, k))
        items.update(own)
    if not found:
        return n, [], [], []
    blanks = np.flatnonzero(np.frombuffer(b" " + text + b" ", np.uint8) == 32)
    edge = np.zeros(n + 1, np.int64)
    for end, k in set(found):
        last = int(np.searchsorted(blanks, end))
        edge[last - k] += 1
        edge[last] -= 1
    hit = np.flatnonzero(np.cumsum(edge[:-1]) > 0)
    return n, hit.tolist(), sorted(items), hit_spans(raw, hit)


def hit_spans(raw: bytes, hit: np.ndarray) -> list[dict]:
    """Runs of hit words as code point offsets in the text as given."""
    first = hit[np.concatenate([[True], np.diff(hit) > 1])]
    last = hit[np.concatenate([np.diff(hit) > 1, [True]])]
    at = word_spans(raw)
    return [{"start": int(at[x][0]), "end": int(at[y][1])} for x, y in zip(first, last)]


def groups_of(bench: DataFrame, id_col: str, text_col: str, width: int, group_bytes: int) -> Iterator[dict[bytes, list[str]]]:
    """The benchmark's windows with their items, read row by row, in groups of bounded size."""
    own, size = {}, 0
    for item, text in bench.select(F.col(id_col).cast("string"), F.col(text_col).cast("string")).dropna().toLocalIterator():
        for w in windows(text.encode(), width):
            if w not in own:
                size += len(w) + 64
            own.setdefault(w, []).append(item)
        if size > group_bytes:
            yield own
            own, size = {}, 0
    if own:
        yield own


def find_leaks(docs: DataFrame, bench: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", width: int = 10, group_bytes: int = 64 << 20) -> DataFrame:
    """doc_id, n_words, hits (numbers of hit words), items, spans (code points of the original) of every document."""
    docs = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))

    def scanned(patterns: dict[bytes, list[str]], source: DataFrame) -> DataFrame:
        sent = source.sparkSession.sparkContext.broadcast(patterns)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            a = automaton(sent.value) if sent.value else None
            for b in batches:
                data, off = text_buffer(b.column("text"))
                for i, j in chunks(off):
                    got = [scan(t, a) if a else (normal(t).count(b" ") + bool(normal(t)), [], [], []) for t in rows_of(data, off, i, j)]
                    cols = list(zip(*got))
                    yield pa.RecordBatch.from_arrays(
                        [b.column("doc_id").slice(i, j - i), pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.list_(pa.int32())), pa.array(cols[2], pa.list_(pa.string())), pa.array(cols[3], pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32())])))],
                        names=["doc_id", "n_words", "hits", "items", "spans"],
                    )

        return source.mapInArrow(lean(run), SCHEMA)

    groups = groups_of(bench, item_col, item_text_col, width, group_bytes)
    first = next(groups, {})
    second = next(groups, None)
    if second is None:
        return scanned(first, docs)
    # Several automata, made one at a time: rows get a number that joins their hits again, and spans follow from all hits of a text.
    docs = store(docs.withColumn("__row", F.monotonically_increasing_id()))
    parts = None
    for g in itertools.chain([first, second], groups):
        one = scanned(g, docs.select(F.col("__row").alias("doc_id"), "text")).filter(F.size("hits") > 0)
        parts = one if parts is None else parts.unionByName(one)
    merged = parts.groupBy(F.col("doc_id").alias("__row")).agg(F.array_sort(F.array_distinct(F.flatten(F.collect_list("hits")))).alias("hits"), F.array_sort(F.array_distinct(F.flatten(F.collect_list("items")))).alias("items"))

    def spanned(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            spans = [hit_spans(t.encode(), np.array(h)) for t, h in zip(b.column("text").to_pylist(), b.column("hits").to_pylist())]
            yield pa.RecordBatch.from_arrays([b.column(c) for c in ("__row", "hits", "items")] + [pa.array(spans, pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32())])))], names=["__row", "hits", "items", "spans"])

    merged = docs.select("__row", "text").join(merged, "__row").select("__row", "text", "hits", "items").mapInArrow(lean(spanned), "__row long, hits array<int>, items array<string>, spans array<struct<start:int,end:int>>")
    words = scanned({}, docs.select(F.col("__row").alias("doc_id"), "text")).select(F.col("doc_id").alias("__row"), "n_words")
    none = lambda c, kind: F.coalesce(F.col(c), F.array().cast(kind)).alias(c)
    return docs.select("__row", "doc_id").join(words, "__row").join(merged, "__row", "left").select("doc_id", "n_words", none("hits", "array<int>"), none("items", "array<string>"), none("spans", "array<struct<start:int,end:int>>"))


def report(leaks: DataFrame) -> DataFrame:
    return leaks.select(
        "doc_id",
        "n_words",
        F.size("hits").cast("long").alias("n_hit"),
        F.size("items").cast("long").alias("n_items"),
        F.sha2(F.array_join(F.array_sort("items"), ",").cast("binary"), 256).alias("items_sha256"),
        (F.size("hits") > 0).alias("contaminated"),
    )


def remove_contaminated(docs: DataFrame, bench: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", width: int = 10, group_bytes: int = 64 << 20) -> DataFrame:
    """The documents without a hit, with all their columns: rows are dropped where they are read, by one scan for each group of patterns."""
    out = docs
    for patterns in groups_of(bench, item_col, item_text_col, width, group_bytes):
        sent = docs.sparkSession.sparkContext.broadcast(list(patterns))

        def run(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
            a = automaton(dict.fromkeys(sent.value, ()))
            for b in batches:
                data, off = text_buffer(b.column(text_col).cast(pa.string()))
                clean = [next(a.iter(f" {normal(t).decode('latin-1')} "), None) is None for i, j in chunks(off) for t in rows_of(data, off, i, j)]
                yield b.filter(pa.array(clean, pa.bool_()))

        out = out.mapInArrow(lean(run), docs.schema)
    return out


_UP, _LOW = "".join(map(chr, range(65, 91))), "".join(map(chr, range(97, 123)))
ORACLE = rf"""
WITH d AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), '{_UP}', '{_LOW}'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws FROM documents),
b AS (SELECT CAST(item_id AS VARCHAR) AS item, regexp_extract_all(translate(text, '{_UP}', '{_LOW}'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws FROM benchmark WHERE item_id IS NOT NULL AND text IS NOT NULL),
bw AS (SELECT DISTINCT item, least(10, len(ws)) AS k, array_to_string(ws[i:i + least(10, len(ws)) - 1], ' ') AS win
       FROM (SELECT item, ws, unnest(range(1, greatest(len(ws) - 10, 0) + 2)) AS i FROM b WHERE len(ws) > 0)),
ks AS (SELECT DISTINCT k FROM bw),
dw AS (SELECT doc_id, k, i, array_to_string(ws[i:i + k - 1], ' ') AS win
       FROM (SELECT doc_id, ws, k, unnest(range(1, CAST(len(ws) - k + 2 AS BIGINT))) AS i FROM d, ks WHERE len(ws) >= k)),
m AS (SELECT doc_id, item, k, i FROM dw JOIN bw USING (k, win)),
h AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + k)) AS p FROM m) GROUP BY 1),
it AS (SELECT doc_id, count(DISTINCT item) AS n_items, string_agg(DISTINCT item, ',' ORDER BY item) AS items FROM m GROUP BY 1)
SELECT doc_id, CAST(len(ws) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items,
       sha256(coalesce(items, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN h USING (doc_id) LEFT JOIN it USING (doc_id)
"""
