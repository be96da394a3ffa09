"""Matchers over text tables: delayed automata (plain ones without defaults), in Arrow batches.

What is shipped and run is the compressed form: labelled transitions and defaults.  It is
broadcast behind a check of its size; rules beyond it go in groups, one pass each.  The texts of
a batch step together, one byte column at a time, until few are left.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BROADCAST_BYTES = 256 << 20
#: Bytes of the words of one group: an automaton has at most one state more, 1 KB each, so it stays within BROADCAST_BYTES.
GROUP_BYTES = 200_000
#: States whose rows are resolved beforehand; texts below which stepping together doesn't pay; bytes of text that step together.
RESOLVED, FEW, LANE_BYTES = 1024, 48, 32 << 20
RUNS = "payload_id long, length long, hops long, max_hops long, accepts boolean, end_state long, matches long, first_end long"


class Matcher:
    """The delayed automaton as it is shipped and run: labelled transitions, defaults, accepts.

    Made from a full byte table (which it doesn't keep), defaults (-1: none; without defaults it
    is the plain automaton) and the number of words that end at each state.  Labelled
    transitions are sorted by (state, symbol).  The first states in breadth-first order, where
    texts mostly are, have their whole rows resolved beforehand, as have states without a default."""

    def __init__(self, table: np.ndarray, accept: np.ndarray, default: np.ndarray | None = None, resolved: int = RESOLVED):
        n, self.sigma = table.shape
        self.accept = np.asarray(accept, np.int64)
        self.default = np.full(n, -1, np.int64) if default is None else np.asarray(default, np.int64)
        whole = np.flatnonzero((self.default < 0) | (np.arange(n) < resolved))
        self.whole = np.full(n, -1, np.int32)
        self.whole[whole] = np.arange(len(whole))
        self.target, self.hops = table[whole].astype(np.int32), np.zeros((len(whole), self.sigma), np.int16)
        at = np.repeat(whole[:, None], self.sigma, 1)
        symbol = np.arange(self.sigma)
        while True:
            on = self.default[at] >= 0
            on &= table[at, symbol] == table[np.where(on, self.default[at], 0), symbol]
            if not on.any():
                break
            self.hops += on
            at = np.where(on, self.default[at], at)
        self.key, self.to = [np.zeros(0, np.int64)], [np.zeros(0, np.int32)]
        rest = np.flatnonzero(self.whole < 0)
        for i in range(0, len(rest), 1 << 14):
            u = rest[i : i + (1 << 14)]
            s, c = np.nonzero(table[u] != table[self.default[u]])
            self.key.append(u[s] * self.sigma + c)
            self.to.append(table[u[s], c].astype(np.int32))
        self.key, self.to = np.concatenate(self.key), np.concatenate(self.to)
        self.plain = None
        if self.nbytes > BROADCAST_BYTES:
            raise ValueError(f"matcher of {self.nbytes} bytes, at most {BROADCAST_BYTES}: split the rules into groups")

    @property
    def nbytes(self) -> int:
        return sum(x.nbytes for x in (self.accept, self.default, self.whole, self.target, self.hops, self.key, self.to))

    def __getstate__(self):
        return self.__dict__ | {"plain": None}

    def step(self, state: np.ndarray, symbol: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Next states and the defaults followed, for arrays of states and bytes."""
        row = self.whole[state]
        if (row >= 0).all():
            return self.target[row, symbol], self.hops[row, symbol]
        target, hops = np.empty(len(state), np.int32), np.zeros(len(state), np.int64)
        todo, at, c = np.arange(len(state)), state, symbol
        while len(todo):
            row = self.whole[at]
            known = row >= 0
            t, r = todo[known], row[known]
            target[t] = self.target[r, c[known]]
            hops[t] += self.hops[r, c[known]]
            todo, at, c = todo[~known], at[~known], c[~known]
            if not len(todo):
                break
            want = at * self.sigma + c
            pos = np.minimum(np.searchsorted(self.key, want), max(0, len(self.key) - 1))
            hit = self.key[pos] == want if len(self.key) else np.zeros(len(want), bool)
            target[todo[hit]] = self.to[pos[hit]]
            todo, at, c = todo[~hit], self.default[at[~hit]], c[~hit]
            hops[todo] += 1
        return target, hops

    def tables(self) -> tuple:
        """The same arrays as Python objects, for the last long texts of a batch (kept by the worker)."""
        if self.plain is None:
            self.plain = dict(zip(self.key.tolist(), self.to.tolist())), self.default.tolist(), self.whole.tolist(), self.target.tolist(), self.hops.tolist(), self.accept.tolist()
        return self.plain

    def walk(self, text: bytes, state: int = 0) -> Iterator[tuple[int, int, int]]:
        """state, defaults followed and words that end, byte by byte."""
        label, default, whole, target, jumps, accept = self.tables()
        sigma = self.sigma
        for c in text:
            hops = 0
            while True:
                row = whole[state]
                if row >= 0:
                    hops += jumps[row][c]
                    state = target[row][c]
                    break
                to = label.get(state * sigma + c)
                if to is not None:
                    state = to
                    break
                state = default[state]
                hops += 1
            yield state, hops, accept[state]

    def run(self, texts: list[bytes], states: np.ndarray | None = None, seen: np.ndarray | None = None) -> dict[str, np.ndarray]:
        """All texts in step while many are left, then the longest one by one.  seen: marks the accepting states that were reached."""
        n = len(texts)
        length = np.array([len(t) for t in texts], np.int64)
        order = np.argsort(-length, kind="stable")
        state = (np.zeros(n, np.int64) if states is None else states.astype(np.int64))[order]
        out = {c: np.zeros(n, np.int64) for c in ("hops", "max_hops", "matches")}
        first = np.full(n, -1, np.int64)
        hit = self.accept[state] > 0
        data = np.frombuffer(b"".join(texts[i] for i in order), np.uint8) if n else np.zeros(0, np.uint8)
        at = np.concatenate([[0], np.cumsum(length[order])])[:-1]
        sorted_len = -length[order]
        k, live = 0, int(np.searchsorted(sorted_len, 0))
        while live >= FEW:
            state[:live], h = self.step(state[:live], data[at[:live] + k])
            out["hops"][:live] += h
            np.maximum(out["max_hops"][:live], h, out=out["max_hops"][:live])
            m = self.accept[state[:live]]
            k += 1
            if m.any():
                out["matches"][:live] += m
                first[:live] = np.where((first[:live] < 0) & (m > 0), k, first[:live])
                hit[:live] |= m > 0
                if seen is not None:
                    seen[state[:live][m > 0]] = True
            live = int(np.searchsorted(sorted_len, -k))  # texts longer than k
        for i in range(live):
            s, hops, most, found, head = int(state[i]), 0, int(out["max_hops"][i]), 0, int(first[i])
            for j, (s, h, m) in enumerate(self.walk(texts[order[i]][k:], s), k + 1):
                if h:
                    hops += h
                    most = max(most, h)
                if m:
                    found += m
                    head = j if head < 0 else head
                    if seen is not None:
                        seen[s] = True
            state[i], out["max_hops"][i], first[i] = s, most, head
            out["hops"][i] += hops
            out["matches"][i] += found
            hit[i] |= found > 0
        back = np.empty(n, np.int64)
        back[order] = np.arange(n)
        return {c: x[back] for c, x in (out | {"end_state": state, "first_end": first, "accepts": hit}).items()} | {"length": length}


@dataclass
class Matchers:
    """One matcher for each group of rules; hits and hops of all groups add up, end_state has a column for each."""

    parts: list[Matcher]

    def run(self, texts: list[bytes], states: np.ndarray | None = None) -> dict[str, np.ndarray]:
        every = [m.run(texts, None if states is None else states.reshape(len(texts), -1)[:, k]) for k, m in enumerate(self.parts)]
        first = np.stack([np.where(g["first_end"] < 0, np.iinfo(np.int64).max, g["first_end"]) for g in every]).min(0)
        out = {c: np.sum([g[c] for g in every], axis=0) for c in ("hops", "matches")} | {"max_hops": np.max([g["max_hops"] for g in every], axis=0)}
        return out | {"end_state": np.stack([g["end_state"] for g in every], 1), "first_end": np.where(first == np.iinfo(np.int64).max, -1, first), "accepts": np.any([g["accepts"] for g in every], axis=0), "length": every[0]["length"]}


def word_groups(words: Iterable[bytes], most: int = GROUP_BYTES) -> Iterator[list[bytes]]:
    """The words in order, cut into groups of at most ``most`` bytes (a longer word is a group of its own)."""
    group, size = [], 0
    for w in words:
        if group and size + len(w) > most:
            yield group
            group, size = [], 0
        group.append(w)
        size += len(w)
    if group:
        yield group


def match(payloads: DataFrame, matcher: Matcher | Matchers, *, id_col: str = "payload_id", text_col: str = "body") -> DataFrame:
    """RUNS of every payload (end_state null with several groups of rules).  Narrow: no shuffle, only id and text are read.  Runs of texts of LANE_BYTES bound the memory."""
    groups = matcher.parts if isinstance(matcher, Matchers) else [matcher]
    sent = [payloads.sparkSession.sparkContext.broadcast(m) for m in groups]
    rows = payloads.select(F.col(id_col).cast("long").alias("payload_id"), F.coalesce(F.encode(F.col(text_col), "UTF-8") if dict(payloads.dtypes)[text_col] == "string" else F.col(text_col), F.lit(b"")).alias("body"))

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = sent[0].value if len(sent) == 1 else Matchers([x.value for x in sent])
        for b in batches:
            ends = np.cumsum(pc.binary_length(b.column("body")).to_numpy())
            cuts = np.flatnonzero(np.diff(ends // LANE_BYTES)) + 1
            for i, j in zip([0, *cuts], [*cuts, b.num_rows]):
                if i == j:
                    continue
                part = b.slice(i, j - i)
                got = m.run(part.column("body").to_pylist())
                end = pa.array(got["end_state"]) if got["end_state"].ndim == 1 else pa.nulls(part.num_rows, pa.int64())
                first = pa.array(got["first_end"], mask=got["first_end"] < 0)
                yield pa.RecordBatch.from_arrays([part.column("payload_id"), pa.array(got["length"]), pa.array(got["hops"]), pa.array(got["max_hops"]), pa.array(got["accepts"]), end, pa.array(got["matches"]), first], names=["payload_id", "length", "hops", "max_hops", "accepts", "end_state", "matches", "first_end"])

    return rows.mapInArrow(go, RUNS)


def occurring(payloads: DataFrame, matcher: Matcher | Matchers, *, text_col: str) -> DataFrame:
    """part, state: the accepting states that any payload reaches, by group of rules.  A task sends each once; their number is that of the rules at most."""
    groups = matcher.parts if isinstance(matcher, Matchers) else [matcher]
    sent = [payloads.sparkSession.sparkContext.broadcast(m) for m in groups]

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = [np.zeros(len(m.value.accept), bool) for m in sent]
        for b in batches:
            ends = np.cumsum(pc.binary_length(b.column("body")).to_numpy())
            cuts = np.flatnonzero(np.diff(ends // LANE_BYTES)) + 1
            for i, j in zip([0, *cuts], [*cuts, b.num_rows]):
                texts = b.column("body").slice(i, j - i).to_pylist()
                for m, x in zip(sent, seen):
                    m.value.run(texts, None, x)
        for k, x in enumerate(seen):
            at = np.flatnonzero(x)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(at), k)), pa.array(at)], names=["part", "state"])

    body = payloads.select(F.coalesce(F.encode(F.col(text_col), "UTF-8"), F.lit(b"")).alias("body"))
    return body.mapInArrow(go, "part long, state long").distinct()


def delay_report(runs: DataFrame) -> DataFrame:
    """Hops per byte: mean, p99, greatest; and whether hops never exceed the length."""
    per = F.col("hops") / F.greatest(F.col("length"), F.lit(1))
    return runs.agg(F.count("*").alias("payloads"), F.sum("length").alias("bytes"), F.sum("hops").alias("hops"), F.round(F.avg(per), 6).alias("mean_hops_per_byte"), F.round(F.percentile_approx(per, 0.99), 6).alias("p99_hops_per_byte"), F.max("max_hops").alias("max_hops"), F.bool_and(F.col("hops") <= F.col("length")).alias("bounded"))
