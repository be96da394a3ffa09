"""Exact n-gram Jaccard self-join with set-relation skipping: links, their number, and components.

A document's set holds its distinct shingles of ``width`` words (A-Z lower-cased, words parted
by white space); with fewer words the whole sequence is the one shingle; without words the set
is empty and linked with nothing.  Shingles are 64-bit hashes.  Two documents link if the
intersection is at least ``percent`` per cent of the union.

1. Equal sets are folded into one node, so copies cost a row each and no pair.
2. Shingles get one global order: those that are frequent by a fixed-size count over the whole
   corpus go last, the rest goes by hash.  The first (100 - percent) per cent of a set, plus
   one, are its index entries (prefix filter: linked sets share one at least).  Entries travel
   as packed arrays, a row for each task and bucket.
3. The index list of a shingle is sorted by set size and cut into blocks.  A block is skipped
   if its sizes or its positions exclude a link (index-level skipping).  Entries that remain
   are compared by parity signatures: their Hamming distance never exceeds the size of the
   symmetric difference, so no link is lost.  A long list is cut into parts, and each pair of
   parts is a list of its own.
4. Lists give families: sets joined by chains of pairs that may link.  Close sets are joined
   first, by a few entries of each set that carry its signature of full length; that decides
   every pair where it is met, so a list yields a spanning forest and no more.  Then the whole
   index is searched for pairs of different families: a list yields a spanning forest of its
   likely pairs, and every doubtful pair that crosses its trees, which the longer signatures
   then decide.  Every link is inside a family, and no pair inside a close family is sent again.
5. A family is joined exactly, in pairs of blocks of bounded size.  The overlaps of one set with
   a block are counted by the block's lists; those of every other set are derived from them, by
   the lists of the few shingles in which the two sets differ (answer-level skipping).  A pair
   of blocks gives the number of links of each set and a spanning forest of the links.
6. Components by alternating star contraction over these forests.

Cases: a null or wordless text has n_shingles 0 and is its own component; a null id links with
nothing and has a null component; rows that share an id are one document for components, also
with different texts; repeated rows give a row each; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .base import LOWER_BYTES, chunks, drop, lean, store, text_buffer

U = np.uint64
SLOTS, SLICES = 1 << 20, 64
MARKS = 1 << 23
BITS = 4  # 64-bit words of a signature
BLOCK = 256
#: A pair whose short signatures differ in so many bits at most surely has much in common: two random long sets differ in 128 (deviation 8).
STRONG = 80
UNSURE = 1 << 40
#: Entries of a part of a long list; the heaviest LONG lists are cut, so any other holds at most a LONG-th of all entries.
PART, LONG = 4096, 1 << 20
#: Sets and shingles of a block of a family.
MEMBERS, VOLUME = 256, 1 << 20
#: Buckets of lists for each shuffle partition; a task holds one bucket at a time.
FINE = 24
#: Bytes of text that are hashed at a time: their arrays take about 50 times that.
TEXT_BYTES = 1 << 18
#: Index entries of a set by which close sets are found first.
HEADS = 4
#: Bytes of index entries that a task gathers before it sends them.
GATHER = 4 << 20
_rng = np.random.default_rng(20240607)
_BYTE = _rng.integers(1, 1 << 63, 256, dtype=np.uint64) * U(2) + U(1)
_BASE = 0x9E3779B97F4A7C15
_INVERSE = pow(_BASE, -1, 1 << 64)
_SPACE = np.zeros(256, bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True
_powers = [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_powers[0]) <= n:
        m = 1 << int(n).bit_length()
        for k, b in enumerate((_BASE, _INVERSE)):
            x = np.full(m + 1, U(b))
            x[0] = U(1)
            _powers[k] = np.multiply.accumulate(x)
    return _powers[0], _powers[1]


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit numbers that spreads every bit."""
    x = (x ^ (x >> U(30))) * U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> U(27))) * U(0x94D049BB133111EB)
    return x ^ (x >> U(31))


def shingles(data: np.ndarray, off: np.ndarray, i: int, j: int, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all shingles of rows i..j-1 in order of text, and the offsets of the rows."""
    lo = off[i]
    d = np.frombuffer(LOWER_BYTES, np.uint8)[data[lo : off[j]]]
    cuts = off[i : j + 1] - lo
    inside = ~_SPACE[d]
    before = np.concatenate([[False], inside[:-1]]) if len(d) else np.zeros(0, bool)
    before[cuts[:-1][cuts[:-1] < len(d)]] = False
    after = np.concatenate([inside[1:], [False]]) if len(d) else np.zeros(0, bool)
    last = cuts[1:][np.diff(cuts) > 0] - 1
    after[last] = False
    start, end = np.flatnonzero(inside & ~before), np.flatnonzero(inside & ~after) + 1
    up, down = _power_tables(len(d) + 1)
    total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(_BYTE[d] * up[: len(d)], dtype=np.uint64)])
    h = mix((total[end] - total[start]) * down[start] + (end - start).astype(np.uint64))
    words = np.searchsorted(start, cuts)  # offsets of the rows' words
    count = np.diff(words)
    n = np.where(count >= width, count - width + 1, (count > 0).astype(np.int64))
    at = np.concatenate([[0], np.cumsum(n)])
    first = np.repeat(words[:-1] - at[:-1], n) + np.arange(at[-1])
    s = np.full(len(first), U(width))
    short = np.repeat(count < width, n)
    for k in range(width):
        inner = ~short | (k < np.repeat(count, n))
        w = h[np.minimum(first + k, max(0, len(h) - 1))] if len(h) else np.zeros(0, np.uint64)
        s = np.where(inner, mix(s * U(0xD6E8FEB86659FD93) + w), s)
    return s, at


def sets(data: np.ndarray, off: np.ndarray, i: int, j: int, width: int) -> Iterator[np.ndarray]:
    """Sorted distinct shingle hashes of each row."""
    s, at = shingles(data, off, i, j, width)
    for a, b in zip(at.tolist(), at[1:].tolist()):
        own = np.sort(s[a:b])  # np.unique hashes, which is slower here
        yield own[np.concatenate([[True], own[1:] != own[:-1]])] if b > a else own


def counted(percent: int) -> int:
    """Hashes below 2 to this power are counted: a range of more than twice the share of a set that becomes index entries."""
    return 64 - max(0, int(np.floor(np.log2(100 / max(1, 100 - percent)))) - 1)


def frequency_levels(texts: DataFrame, width: int, percent: int) -> np.ndarray:
    """For each of SLOTS hash slots how far its count over the whole corpus is above the usual (in steps of half a power of two, 0 for the usual).

    A task counts into one array of fixed size and sends it in slices; slices of the same
    number are added up as a stream.  Only the order of shingles depends on it, no result."""

    top = U((1 << counted(percent)) - 1)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n = np.zeros(SLOTS, np.int64)
        for b in batches:
            data, off = text_buffer(b.column("text"))
            for i, j in chunks(off, TEXT_BYTES):
                s, _ = shingles(data, off, i, j, width)
                n += np.bincount((s[s <= top] & U(SLOTS - 1)).astype(np.int64), minlength=SLOTS)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(SLICES)), pa.array([x.astype(np.uint32).tobytes() for x in np.minimum(n, 0xFFFFFFFF).reshape(SLICES, -1)], pa.binary())], names=["slice", "n"])

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own: dict[int, np.ndarray] = {}
        for b in batches:
            for k, x in zip(b.column("slice").to_pylist(), b.column("n")):
                own[k] = own.get(k, 0) + np.frombuffer(x.as_buffer(), np.uint32).astype(np.uint64)
        yield pa.RecordBatch.from_arrays([pa.array(list(own), pa.int64()), pa.array([x.tobytes() for x in own.values()], pa.binary())], names=["slice", "n"])

    parts = texts.mapInArrow(lean(count), "slice long, n binary").repartition("slice").mapInArrow(lean(add), "slice long, n binary").collect()  # SLOTS numbers
    n = np.zeros((SLICES, SLOTS // SLICES))
    for k, x in parts:
        n[k] += np.frombuffer(x, np.uint64)
    n = n.reshape(-1)
    return np.clip(np.floor(2 * np.log2(np.maximum(n, 1) / (n.mean() + 1))), 0, 31).astype(np.uint8)


def least_overlap(a, b, percent: int):
    """Shared shingles that two sets of these sizes need."""
    return -(-percent * (a + b) // (100 + percent))


def signature(s: np.ndarray) -> np.ndarray:
    """Parities of the set's members by hash slot: slices(n) runs of 64 BITS slots."""
    bits = BITS * 64 * int(slices(np.array(len(s))))
    return (np.bincount((mix(s) & U(bits - 1)).astype(np.int64), minlength=bits) & 1).astype(np.uint8)


def slices(n: np.ndarray) -> np.ndarray:
    """Slices of the full signature of a set of n: one up to 64 BITS members, then a power of two that leaves 2 to 4 slots for each member."""
    return np.where(n <= BITS * 64, 1, np.left_shift(1, np.frexp(2.0 * n - 1)[1].astype(np.int64)) // (BITS * 64))


def shown(n: np.ndarray, percent: int) -> np.ndarray:
    """Slices into which the signature is cut for the index: one, folded, as long as linked sets of n differ in less than unrelated ones do there (half of the bits, deviation 8)."""
    return np.where(2 * (n - least_overlap(n, n, percent)) <= BITS * 32 + 16, 1, slices(n))


def fold(sig: np.ndarray, bits: int) -> np.ndarray:
    """The signature of fewer slots of the same set."""
    return sig if len(sig) == bits else (sig.reshape(-1, bits).sum(0) & 1).astype(np.uint8)


ENTRY = "doc_id long, n long, f1 long, f2 long, sig binary, wide binary, keys binary"
ITEM = np.dtype([("list", "<u8"), ("node", "<i8"), ("family", "<i8"), ("n", "<i4"), ("pos", "<i4"), ("sig", "<u8", (BITS,))])
#: An entry on its way: lists by 48 bits (two that fall together only make pairs that are rejected), positions up to 65,535 (a lesser one excludes less).
WIRE = np.dtype([("list", "u1", (6,)), ("pos", "<u2"), ("n", "<u4"), ("node", "<i8"), ("family", "<i8"), ("sig", "<u8", (BITS,))])
KEY_BITS = 43


def six(x: np.ndarray) -> np.ndarray:
    """The low 48 bits of 64-bit numbers, six bytes each."""
    return np.ascontiguousarray(x, "<u8").view(np.uint8).reshape(-1, 8)[:, :6]


def unsix(x: np.ndarray) -> np.ndarray:
    out = np.zeros((len(x), 8), np.uint8)
    out[:, :6] = x
    return out.view("<u8").ravel()


def sealed(e: np.ndarray) -> np.ndarray:
    out = np.empty(len(e), WIRE)
    out["list"], out["pos"] = six(e["list"]), np.minimum(e["pos"], 65_535)
    for c in ("n", "node", "family", "sig"):
        out[c] = e[c]
    return out


def opened(w: np.ndarray) -> np.ndarray:
    out = np.empty(len(w), ITEM)
    out["list"] = unsix(w["list"])
    for c in ("pos", "n", "node", "family", "sig"):
        out[c] = w[c]
    return out


def fingerprints(s: np.ndarray) -> tuple[int, int]:
    """Two 64-bit numbers that tell sets of one size apart."""
    m = mix(s ^ U(0xA5A5A5A5A5A5A5A5))
    both = np.array([np.bitwise_xor.reduce(m) if len(s) else 0, m.sum(dtype=np.uint64)], np.uint64).view(np.int64)
    return int(both[0]), int(both[1])


def index_entries(docs: DataFrame, levels: np.ndarray, width: int, percent: int) -> DataFrame:
    """Per document: size, two fingerprints of the set, its signatures (the long one where it is longer) and its index keys in the global order."""
    sent, top = docs.sparkSession.sparkContext.broadcast(levels), U((1 << counted(percent)) - 1)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        level = sent.value.astype(np.uint64)
        for b in batches:
            data, off = text_buffer(b.column("text"))
            for i, j in chunks(off, TEXT_BYTES):
                n, prints, sig, wide, keys = [], [], [], [], []
                for s in sets(data, off, i, j, width):
                    n.append(len(s))
                    prints.append(fingerprints(s))
                    parity = signature(s)
                    sig.append(np.packbits(fold(parity, BITS * 64)).tobytes())
                    wide.append(np.packbits(parity).tobytes() if len(parity) > BITS * 64 else None)
                    key = (np.where(s <= top, level[(s & U(SLOTS - 1)).astype(np.int64)], U(0)) << U(KEY_BITS)) | (s >> U(64 - KEY_BITS))
                    k = len(s) - int(-(-percent * len(s) // 100)) + 1 if len(s) else 0
                    keys.append(six(np.sort(np.partition(key, k - 1)[:k] if 0 < k < len(key) else key)).tobytes())
                f1, f2 = zip(*prints)
                yield pa.RecordBatch.from_arrays([b.column("doc_id").slice(i, j - i), pa.array(n, pa.int64()), pa.array(f1, pa.int64()), pa.array(f2, pa.int64()), *(pa.array(x, pa.binary()) for x in (sig, wide, keys))], names=["doc_id", "n", "f1", "f2", "sig", "wide", "keys"])

    return docs.mapInArrow(lean(run), ENTRY)


def exploded(b: pa.RecordBatch, percent: int) -> Iterator[np.ndarray]:
    """Index entries of a batch of nodes, a bounded number of bytes at a time; ``sig`` of a long set is a slice of its full signature, which the key tells."""
    node, family, n = (b.column(c).to_numpy() for c in ("node", "family", "n"))
    keys, off = bytes_of(b.column("keys"))
    sig, _ = bytes_of(b.column("sig"))
    sig = sig.view(np.uint64).reshape(-1, BITS)
    wide, begin = bytes_of(b.column("wide"))
    wide, begin = wide.view(np.uint64).reshape(-1, BITS), begin // (8 * BITS)
    for i, j in chunks(off, GATHER * 6 // ITEM.itemsize, len(off)):
        count = np.diff(off[i : j + 1]) // 6
        out = np.empty(int(count.sum()), ITEM)
        out["list"] = unsix(keys[off[i] : off[j]].reshape(-1, 6))
        row = np.repeat(np.arange(i, j), count)
        out["node"], out["family"], out["n"], out["sig"] = node[row], family[row], n[row], sig[row]
        out["pos"] = np.arange(len(out)) - np.repeat(np.cumsum(count) - count, count)
        of = shown(n, percent)[row]
        at = np.flatnonzero(of > 1)
        out["sig"][at] = wide[begin[row[at]] + (mix(out["list"][at]) & (of[at] - 1).astype(np.uint64)).astype(np.int64)]
        yield out


def bytes_of(col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    col = col.cast(pa.large_binary())
    off = np.frombuffer(col.buffers()[1], np.int64)[col.offset : col.offset + len(col) + 1]
    return np.frombuffer(col.buffers()[2], np.uint8)[off[0] : off[-1]].copy(), off - off[0]


def long_lists(nodes: DataFrame, least: int = PART // 64) -> tuple[np.ndarray, np.ndarray]:
    """The keys of the heaviest lists of more than PART entries and the number of their parts; tasks report what is heavy in them."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = [unsix(bytes_of(b.column("keys"))[0].reshape(-1, 6)) for b in batches if b.num_rows]
        key, n = np.unique(np.concatenate(own), return_counts=True) if own else (np.zeros(0, np.uint64), np.zeros(0, int))
        yield pa.RecordBatch.from_arrays([pa.array(key[n >= least].view(np.int64)), pa.array(n[n >= least], pa.int64())], names=["key", "n"])

    found = nodes.select("keys").mapInArrow(lean(count), "key long, n long").groupBy("key").agg(F.sum("n").alias("n")).filter(F.col("n") > PART).orderBy(F.desc("n"), "key").limit(LONG).toPandas()  # LONG rows at most
    key, parts = found["key"].to_numpy(np.int64).view(np.uint64), -(-found["n"].to_numpy(np.int64) // PART)
    rank = np.argsort(key)
    return key[rank], parts[rank]


def dealt(e: np.ndarray, long: tuple[np.ndarray, np.ndarray]) -> np.ndarray:
    """Entries of long lists go to one list for each pair of parts that theirs is in."""
    if not len(long[0]) or not len(e):
        return e
    at = np.minimum(np.searchsorted(long[0], e["list"]), len(long[0]) - 1)
    hot = long[0][at] == e["list"]
    if not hot.any():
        return e
    parts = long[1][at[hot]]
    own = np.repeat(e[hot], parts)
    other = np.arange(len(own)) - np.repeat(np.cumsum(parts) - parts, parts)
    part = (mix(own["node"].view(np.uint64)) % np.repeat(parts, parts).astype(np.uint64)).astype(np.int64)
    lo, hi = np.minimum(part, other), np.maximum(part, other)
    own["list"] = mix(own["list"] + mix((lo * (1 << 31) + hi + 1).astype(np.uint64))) >> U(16)
    return np.concatenate([e[~hot], own])


class Lists:
    """Pairs of index lists that may link and are of different families: (a, b, strong), families if strong and nodes if not."""

    #: Bits in which the signatures of a strong pair may differ.
    strong = STRONG

    def __init__(self, percent: int):
        self.percent, self.seen = percent, np.zeros((0, 3), np.int64)

    def apart(self, e: np.ndarray, i, j) -> np.ndarray:
        """Bits in which the signatures of entries i and j (arrays) differ (UNSURE if they are slices); -1 if sizes, positions or these bits exclude a link.

        The members in which two linked sets differ fall into slices at random, so a slice has more
        of them than Bernstein's bound allows with a probability below 2^-60."""
        n, m, far, ok = self.reach(e, i, j)
        s, other = shown(n, self.percent), shown(m, self.percent)
        bits = np.bitwise_count(e["sig"][i] ^ e["sig"][j]).sum(-1, dtype=np.int64)
        mean, c = far / s, 60 * np.log(2)
        most = np.where(s == 1, far, mean + c / 3 + np.sqrt(c * c / 9 + 2 * c * mean))
        return np.where(ok & ((s != other) | (bits <= most)), np.where((s == 1) & (other == 1), bits, UNSURE), -1)

    def reach(self, e: np.ndarray, i, j) -> tuple:
        """Sizes of entries i and j, the members in which linked sets of these sizes may differ, and whether sizes and positions allow a link."""
        n, m = e["n"][i].astype(np.int64), e["n"][j].astype(np.int64)
        need = least_overlap(n, m, self.percent)
        ok = (100 * np.minimum(n, m) >= self.percent * np.maximum(n, m)) & (np.minimum(n - e["pos"][i], m - e["pos"][j]) >= need)
        return n, m, n + m - 2 * need, ok

    def told(self, e: np.ndarray, i, j, d: np.ndarray) -> list[tuple]:
        """Rows for the pairs of entries i and j that are d bits apart."""
        sure = d <= self.strong
        return [(e[c][i[x]], e[c][j[x]], np.full(x.sum(), s)) for c, s, x in (("family", True, sure), ("node", False, ~sure))]

    def small(self, e: np.ndarray, first: np.ndarray, size: np.ndarray) -> list[tuple]:
        """All pairs of lists of a few entries, for all lists at once."""
        out = []
        at = np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size)
        left, row = np.repeat(size, size) - 1 - at, np.repeat(first, size) + at
        for gap in range(1, int(size.max(initial=0))):
            i = row[left >= gap]
            i = i[e["family"][i] != e["family"][i + gap]]
            d = self.apart(e, i, i + gap)
            i, d = i[d >= 0], d[d >= 0]
            out += self.told(e, i, i + gap, d)
        return out

    def large(self, e: np.ndarray) -> list[tuple]:
        """A spanning forest of the strong pairs of a list sorted by size, over its families, and the other pairs that cross its trees."""
        n, pos, out, weak = e["n"].astype(np.int64), e["pos"].astype(np.int64), [], []
        starts = np.arange(0, len(e), BLOCK)
        top, low, least = np.maximum.reduceat(n, starts), np.minimum.reduceat(n, starts), np.minimum.reduceat(pos, starts)
        part, tested = np.unique(e["family"], return_inverse=True)[1], np.zeros(len(e), bool)

        def look(i: int, fresh: bool) -> None:
            """Entry i against those of other trees: all of them, or (fresh) those of which none was compared yet."""
            # Blocks whose sizes are out of reach, or whose first position leaves too little.
            need = least_overlap(n[i], np.maximum(low, n[i] * self.percent // 100), self.percent)
            live = (100 * top >= self.percent * n[i]) & (100 * n[i] >= self.percent * low) & (np.minimum(n[i] - pos[i], top - least) >= need)
            j = (np.flatnonzero(live)[:, None] * BLOCK + np.arange(BLOCK)).ravel()
            j = j[j < len(e)]
            j = j[~tested[j] & (part[j] != part[i])] if fresh else j[part[j] != part[i]]
            d = self.apart(e, i, j)
            j, d = j[d >= 0], d[d >= 0]
            strong = d <= self.strong
            if (~strong).any():
                weak.append((np.full((~strong).sum(), i), j[~strong]))
            j = j[strong]
            if not len(j):
                return
            if fresh:  # a star
                tested[j] = True
            own, at = np.unique(part[j], return_index=True)
            j = j[at]
            part[np.isin(part, own)] = part[i]
            out.append((np.full(len(j), e["family"][i]), e["family"][j], np.ones(len(j), bool)))

        order = np.argsort(e["node"], kind="stable")  # the same centres in every list
        for i in order.tolist():
            if not tested[i]:
                look(i, True)
        member = tested.copy()
        for i in order.tolist():
            if member[i] and (part != part[i]).any():
                look(i, False)
        if weak:
            i, j = (np.concatenate(x) for x in zip(*weak))
            i, j = i[part[i] != part[j]], j[part[i] != part[j]]
            out.append((e["node"][i], e["node"][j], np.zeros(len(i), bool)))
        return out

    def pairs(self, e: np.ndarray) -> np.ndarray:
        """Of all lists in e: rows a < b, strong; none twice in a task, as far as memory for that goes."""
        e = e[np.lexsort((e["node"], e["n"], e["list"]))]
        cut = np.flatnonzero(np.diff(e["list"])) + 1
        first, end = np.concatenate([[0], cut]), np.concatenate([cut, [len(e)]])
        size = end - first
        few = (size > 1) & (size <= 8)
        out = self.small(e, first[few], size[few])
        for k in np.flatnonzero(size > 8):
            out += self.large(e[first[k] : end[k]])
        p = np.concatenate([np.stack([np.minimum(a, b), np.maximum(a, b), s], 1) for a, b, s in out]) if out else np.zeros((0, 3), np.int64)
        p = np.unique(p[p[:, 0] != p[:, 1]], axis=0)
        fresh = p[~rows_in(p, self.seen)]
        if len(self.seen) < 500_000:  # only saves repeats
            self.seen = np.unique(np.concatenate([self.seen, fresh]), axis=0)
        return fresh


def rows_in(p: np.ndarray, seen: np.ndarray) -> np.ndarray:
    """Which rows of p are rows of seen; both are sorted and hold none twice."""
    both = np.concatenate([seen, p])
    order = np.lexsort(both.T[::-1])
    same = (both[order[1:]] == both[order[:-1]]).all(1)
    hit = np.zeros(len(both), bool)
    hit[order[1:][same]] = True  # the sort is stable: a row of p comes second
    return hit[len(seen) :]


class Close(Lists):
    """The same over entries whose ``sig`` holds the words and the row of a signature of full length; these decide every pair that is not strong."""

    strong = UNSURE

    def __init__(self, percent: int):
        super().__init__(percent)
        self.full: dict[int, np.ndarray] = {}

    def apart(self, e: np.ndarray, i, j) -> np.ndarray:
        n, _, far, ok = self.reach(e, i, j)
        bits, short = self.bits(e, i, j)
        return np.where(ok & ((bits <= far) | (shown(n, self.percent) == 1) & (short <= np.minimum(STRONG, far))), bits, -1)

    def bits(self, e: np.ndarray, i, j) -> tuple[np.ndarray, np.ndarray]:
        """Bits in which the signatures of entries i and j differ, in full and folded."""
        x, y = np.broadcast_arrays(e["sig"][i][..., :2], e["sig"][j][..., :2])
        out, short = np.zeros(len(x), np.int64), np.zeros(len(x), np.int64)
        size = np.stack([x[:, 0], y[:, 0]], 1).astype(np.int64)
        for v, w in np.unique(size, axis=0).tolist():
            at, least = np.flatnonzero((size == (v, w)).all(1)), min(v, w)
            a, b = (np.bitwise_xor.reduce(self.full[k][z[at, 1].astype(np.int64)].reshape(len(at), -1, least), axis=1) for k, z in ((v, x), (w, y)))
            out[at] = np.bitwise_count(a ^ b).sum(-1, dtype=np.int64)
            short[at] = np.bitwise_count(np.bitwise_xor.reduce((a ^ b).reshape(len(at), -1, BITS), axis=1)).sum(-1, dtype=np.int64)
        return out, short

    def of(self, b: pa.Table) -> np.ndarray:
        """Pairs of the lists in b: list, node, n, pos, sig."""
        e = np.empty(b.num_rows, ITEM)
        for c in ("list", "node", "n", "pos"):
            e[c] = b.column(c).to_numpy()
        e["family"] = e["node"]
        raw, off = bytes_of(b.column("sig").combine_chunks())
        words = np.diff(off) // 8
        self.full = {}
        for w in np.unique(words).tolist():
            at = np.flatnonzero(words == w)
            self.full[w] = raw[off[at][:, None] + np.arange(8 * w)].view(np.uint64)
            e["sig"][at, 0], e["sig"][at, 1] = w, np.arange(len(at))
        return self.pairs(e)


def close(nodes: DataFrame, long: tuple[np.ndarray, np.ndarray], percent: int) -> DataFrame:
    """nodes: node, n, sig, wide, keys.  Pairs (a, b) that may link by signatures of full length and share one of HEADS index entries of each, drawn by a hash of their own: in the global order those that no other set has come first.

    What is missed here, candidates() finds; so the parts of a long list are not compared with each other."""
    sent = nodes.sparkSession.sparkContext.broadcast(long)

    def heads(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, parts = sent.value
        for b in batches:
            node = b.column("node").to_numpy()
            raw, off = bytes_of(b.column("keys"))
            for i, j in chunks(off, GATHER * 6 // ITEM.itemsize, len(off)):
                key, count = unsix(raw[off[i] : off[j]].reshape(-1, 6)), np.diff(off[i : j + 1]) // 6
                start = np.cumsum(count) - count
                order = np.lexsort((mix(key & U((1 << KEY_BITS) - 1)), np.repeat(np.arange(i, j), count)))
                at = order[np.arange(len(key)) - np.repeat(start, count) < HEADS]
                row = np.searchsorted(start, at, side="right") - 1
                pos, own, row = at - start[row], key[at], row + i
                if len(keys):
                    k = np.minimum(np.searchsorted(keys, own), len(keys) - 1)
                    of = np.where(keys[k] == own, parts[k], 1).astype(np.uint64)
                    own = own + (mix(node[row].view(np.uint64) ^ mix(own)) % of << U(48))
                yield pa.RecordBatch.from_arrays([pa.array(own.view(np.int64)), b.column("node").take(pa.array(row)), b.column("n").take(pa.array(row)), pa.array(pos, pa.int64()), pc.coalesce(b.column("wide"), b.column("sig")).take(pa.array(row))], names=["list", "node", "n", "pos", "sig"])

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        work, own = Close(percent), []

        def found() -> Iterator[pa.RecordBatch]:
            p = work.of(pa.Table.from_batches(own)) if own else ()
            if len(p):
                yield pa.RecordBatch.from_arrays([pa.array(p[:, 0]), pa.array(p[:, 1])], names=["a", "b"])

        for b in batches:
            lists = b.column("list").to_numpy()
            if not len(lists):
                continue
            last = int(np.searchsorted(lists, lists[-1]))  # its last list may go on
            if last or own and own[-1].column("list")[-1].as_py() != lists[-1]:
                own.append(b.slice(0, last))
                yield from found()
                own = []
            own.append(b.slice(last))
        yield from found()

    each = nodes.select("node", "n", "sig", "wide", "keys").mapInArrow(lean(heads), "list long, node long, n long, pos long, sig binary")
    return each.repartition("list").sortWithinPartitions("list").mapInArrow(lean(search), "a long, b long").distinct()


def candidates(nodes: DataFrame, long: tuple[np.ndarray, np.ndarray], percent: int) -> DataFrame:
    """nodes: node, family, n, sig, wide, keys.  Pairs a < b that connect every two nodes of different families which may link, with ``strong``."""
    spark = nodes.sparkSession
    sent = spark.sparkContext.broadcast(long)
    buckets = FINE * int(spark.conf.get("spark.sql.shuffle.partitions"))

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, size = [], 0

        def send() -> pa.RecordBatch:
            e = np.concatenate(own)
            bucket = (mix(e["list"]) >> U(16)) % U(buckets)
            e = sealed(e[np.argsort(bucket, kind="stable")])
            got, n = np.unique(bucket, return_counts=True)
            at = np.concatenate([[0], np.cumsum(n)])
            return pa.RecordBatch.from_arrays([pa.array(got.astype(np.int64)), pa.array([e[x:y].tobytes() for x, y in zip(at, at[1:])], pa.binary())], names=["bucket", "entries"])

        for b in batches:
            for e in exploded(b, percent) if b.num_rows else ():
                own.append(dealt(e, sent.value))
                size += own[-1].nbytes
                if size > GATHER:
                    yield send()
                    own, size = [], 0
        if size:
            yield send()

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        work, own, last = Lists(percent), [], None

        def found() -> Iterator[pa.RecordBatch]:
            p = work.pairs(opened(np.concatenate(own))) if own else ()
            if len(p):
                yield pa.RecordBatch.from_arrays([pa.array(p[:, 0]), pa.array(p[:, 1]), pa.array(p[:, 2] > 0)], names=["a", "b", "strong"])

        for b in batches:
            for k, x in zip(b.column("bucket").to_pylist(), b.column("entries")):
                if k != last:
                    yield from found()
                    own, last = [], k
                own.append(np.frombuffer(x.as_buffer(), WIRE))
        yield from found()

    packed = nodes.select("node", "family", "n", "sig", "wide", "keys").mapInArrow(lean(pack), "bucket long, entries binary").repartition("bucket").sortWithinPartitions("bucket")
    return packed.mapInArrow(lean(search), "a long, b long, strong boolean").distinct()


def sharpened(pairs: DataFrame, nodes: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b) that the signatures of full length leave."""
    long = nodes.filter("wide is not null")
    side = lambda c: long.select(F.col("node").alias(c), F.col("n").alias(f"n{c}"), F.col("wide").alias(f"w{c}"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            keep = np.ones(b.num_rows, bool)
            for k, (n, m, x, y) in enumerate(zip(*(b.column(c).to_pylist() for c in ("na", "nb", "wa", "wb")))):
                if x and y:
                    bits = 8 * min(len(x), len(y))
                    apart = fold(np.unpackbits(np.frombuffer(x, np.uint8)), bits) != fold(np.unpackbits(np.frombuffer(y, np.uint8)), bits)
                    keep[k] = int(apart.sum()) <= n + m - 2 * least_overlap(n, m, percent)
            yield b.select(["a", "b"]).filter(pa.array(keep))

    both = pairs.join(side("a"), "a", "left").join(side("b"), "b", "left").select("a", "b", "na", "nb", "wa", "wb")
    return both.mapInArrow(lean(run), "a long, b long")


def presence(nodes: DataFrame, salt: int = 0) -> np.ndarray:
    """A bit for each hash slot that holds a node: a filter of fixed size, whatever the number of nodes."""

    def mark(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bits = np.zeros(MARKS, bool)
        for b in batches:
            bits[slot_of(b.column("node").to_numpy(), salt)] = True
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(SLICES)), pa.array([x.tobytes() for x in np.packbits(bits).reshape(SLICES, -1)], pa.binary())], names=["slice", "bits"])

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own: dict[int, np.ndarray] = {}
        for b in batches:
            for k, x in zip(b.column("slice").to_pylist(), b.column("bits")):
                own[k] = own.get(k, 0) | np.frombuffer(x.as_buffer(), np.uint8)
        yield pa.RecordBatch.from_arrays([pa.array(list(own), pa.int64()), pa.array([x.tobytes() for x in own.values()], pa.binary())], names=["slice", "bits"])

    bits = np.zeros((SLICES, MARKS // SLICES // 8), np.uint8)
    for k, x in nodes.mapInArrow(lean(mark), "slice long, bits binary").repartition("slice").mapInArrow(lean(merge), "slice long, bits binary").collect():  # MARKS bits
        bits[k] |= np.frombuffer(x, np.uint8)
    return bits.reshape(-1)


def slot_of(node: np.ndarray, salt: int = 0) -> np.ndarray:
    return ((mix(node.astype(np.int64).view(np.uint64)) >> U(24 * salt)) & U(MARKS - 1)).astype(np.int64)


def sets_of(docs: DataFrame, wanted: DataFrame, width: int) -> DataFrame:
    """wanted: nodes with doc, n, f1, f2 of a document that has the set, and other columns.  Adds members (sorted shingles, 8 bytes each).

    Most other documents are dropped where they are read, by the filter of presence()."""
    sent = docs.sparkSession.sparkContext.broadcast(presence(wanted.select(F.col("doc").alias("node"))))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bits = np.unpackbits(sent.value).astype(bool)
        for b in batches:
            b = b.filter(b.column("doc_id").is_valid())
            b = b.filter(pa.array(bits[slot_of(b.column("doc_id").to_numpy())]))
            data, off = text_buffer(b.column("text"))
            for i, j in chunks(off, TEXT_BYTES):
                own = list(sets(data, off, i, j, width))
                f1, f2 = zip(*map(fingerprints, own))
                yield pa.RecordBatch.from_arrays([b.column("doc_id").slice(i, j - i), pa.array([len(s) for s in own], pa.int64()), pa.array(f1, pa.int64()), pa.array(f2, pa.int64()), pa.array([s.tobytes() for s in own], pa.binary())], names=["doc", "n", "f1", "f2", "members"])

    few = docs.mapInArrow(lean(run), "doc long, n long, f1 long, f2 long, members binary")
    return few.join(wanted, ["doc", "n", "f1", "f2"])


def answers(rows: list[np.ndarray], cols: list[np.ndarray], percent: int) -> Iterator[np.ndarray]:
    """For each set of rows, the numbers of the sets of cols that link with it.

    The overlaps of the first set are counted by the lists of its shingles; those of another
    set follow from them by the lists of the shingles that only one of the two has."""
    m, size = len(cols), np.array([len(s) for s in cols])
    words, ids = np.unique(np.concatenate(cols), return_inverse=True)
    owner = np.repeat(np.arange(m), size)[np.argsort(ids, kind="stable")]
    at = np.concatenate([[0], np.cumsum(np.bincount(ids, minlength=len(words)))])

    def overlaps(x: np.ndarray) -> np.ndarray:
        n = at[x + 1] - at[x]
        return np.bincount(owner[np.repeat(at[x] - np.cumsum(n) + n, n) + np.arange(n.sum())], minlength=m)

    def known(s: np.ndarray) -> np.ndarray:
        x = np.minimum(np.searchsorted(words, s), len(words) - 1)
        return x[words[x] == s]

    base = known(rows[0])
    of_base, in_base, own = overlaps(base), np.zeros(len(words), bool), np.zeros(len(words), bool)
    in_base[base] = True
    for s in rows:
        x = known(s)
        own[x] = True
        more, less = x[~in_base[x]], base[~own[base]]
        own[x] = False
        both = of_base + overlaps(more) - overlaps(less) if len(more) + len(less) < len(x) else overlaps(x)
        yield np.flatnonzero(100 * both >= percent * (len(s) + size - both))


def block_links(node: np.ndarray, right: np.ndarray, weight: np.ndarray, own: list[np.ndarray], percent: int, crossed: bool) -> tuple[np.ndarray, list[tuple[int, int]]]:
    """Links of every set with those of the other block (crossed) or of the same one, by weight, and a spanning forest of them."""
    count, edges, label = np.zeros(len(node), np.int64), [], np.arange(len(node))
    cols = np.flatnonzero(right) if crossed else np.arange(len(node))
    rows = np.flatnonzero(~right) if crossed else cols
    if not len(rows) or not len(cols):
        return count, edges
    for x, linked in zip(rows.tolist(), answers([own[k] for k in rows], [own[k] for k in cols], percent)):
        y = cols[linked]
        y = y[y != x]
        count[x] += weight[y].sum()
        if crossed:
            count[y] += weight[x]
        fresh, first = np.unique(label[y], return_index=True)
        for k in y[first[fresh != label[x]]].tolist():
            edges.append((int(node[x]), int(node[k])))
        label[np.isin(label, fresh)] = label[x]
    return count, edges


def links_within(families: DataFrame, docs: DataFrame, width: int, percent: int) -> DataFrame:
    """families: node, family, doc, n, f1, f2, weight.  Rows (a, null, links) that add up to the number of links of a node, and rows (a, b, null): a forest of the links of each pair of blocks."""
    size = families.groupBy("family").agg(F.greatest(F.ceil(F.count("*") / MEMBERS), F.ceil(F.sum("n") / VOLUME)).alias("blocks"))
    dealt = families.join(size, "family").withColumn("block", F.pmod(F.xxhash64("node", F.lit(7)), "blocks"))
    each = sets_of(docs, store(dealt), width).withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)))
    each = each.select("family", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), "block", "node", "weight", "members")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, last = [], None

        def found() -> list[tuple]:
            got = sorted({r[0]: r for r in own}.values())  # a repeated document comes once
            if len(got) < 2:
                return []
            node, block, weight, members = zip(*got)
            sets_ = [np.frombuffer(x, np.uint64) for x in members]
            if len(got) == 2 and (last[1] == last[2] or block[0] != block[1]):
                both = len(np.intersect1d(*sets_, assume_unique=True))
                if 100 * both < percent * (len(sets_[0]) + len(sets_[1]) - both):
                    return []
                return [(node[0], None, weight[1]), (node[1], None, weight[0]), (node[0], node[1], None)]
            node, right = np.array(node), np.array(block) == last[2]
            count, edges = block_links(node, right, np.array(weight), sets_, percent, last[1] != last[2])
            return [(int(x), None, int(c)) for x, c in zip(node, count) if c] + [(x, y, None) for x, y in edges]

        def sent(rows: list[tuple]) -> Iterator[pa.RecordBatch]:
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows)], names=["a", "b", "links"])

        rows: list[tuple] = []
        for b in batches:
            for f, i, j, *r in zip(*(b.column(c).to_pylist() for c in ("family", "i", "j", "node", "block", "weight", "members"))):
                if (f, i, j) != last:
                    rows += found()
                    own, last = [], (f, i, j)
                own.append(tuple(r))
            if len(rows) > 10_000:
                yield from sent(rows)
                rows = []
        yield from sent(rows + found())

    return store(each.repartition("family", "i", "j").sortWithinPartitions("family", "i", "j").mapInArrow(lean(run), "a long, b long, links long"))


def components(edges: DataFrame, most: int = 60) -> DataFrame:
    """node, part (least node of its component) for every node of the edges (a, b); alternating large and small stars."""
    e = edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).filter("u <> v").distinct()
    for _ in range(most):
        both = e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
        large = both.join(least, "u").filter("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).filter("u <> v").distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u")
        old, e = e, store(small.filter("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(least.select("u", F.col("m").alias("v"))).distinct())
        drop(old)
        # Done when all is stars: every node has one edge, and it leads to a node without.
        ends = e.select(F.col("u").alias("x"), F.lit(1).alias("out"), F.lit(0).alias("into")).unionByName(e.select(F.col("v").alias("x"), F.lit(0).alias("out"), F.lit(1).alias("into")))
        if ends.groupBy("x").agg(F.sum("out").alias("out"), F.max("into").alias("into")).filter("out > 1 or out = 1 and into = 1").isEmpty():
            return e.select(F.col("u").alias("node"), F.col("v").alias("part")).unionByName(e.select(F.col("v").alias("node"), F.col("v").alias("part")).distinct())
    raise RuntimeError(f"components: no end after {most} rounds")


def join(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", width: int = 3, percent: int = 90) -> DataFrame:
    """doc_id, n_shingles, component_id and n_links (other rows that link with it) of every document."""
    docs = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    same = ["n", "f1", "f2"]
    levels = frequency_levels(docs.select("text"), width, percent)
    whole = store(index_entries(docs, levels, width, percent))
    entries = store(whole.select("doc_id", *same))
    sets_ = whole.filter("n > 0 and doc_id is not null").withColumn("rid", F.col("doc_id"))
    # Ids that stand beside several sets; their rows get numbers of their own, and edges for the id.
    torn = store(entries.filter("n > 0 and doc_id is not null").groupBy("doc_id").agg(F.min(F.struct(*same)).alias("lo"), F.max(F.struct(*same)).alias("hi")).filter("lo <> hi").select("doc_id"))
    clash = not torn.isEmpty()
    if clash:
        sets_ = sets_.join(torn.withColumn("torn", F.lit(True)), "doc_id", "left").withColumn("rid", F.when(F.col("torn"), F.xxhash64("doc_id", *same)).otherwise(F.col("doc_id")))
    folded = sets_.groupBy(*same).agg(F.min(F.struct("rid", "doc_id", "sig", "wide", "keys")).alias("x"), F.min("doc_id").alias("least"), F.count("*").alias("weight"))
    nodes = store(folded.select(F.col("x.rid").alias("node"), F.col("x.doc_id").alias("doc"), *same, "least", "weight", "x.sig", "x.wide", "x.keys"))
    if clash:
        sets_ = store(sets_.filter("torn").select("doc_id", *same))
    drop(whole)
    long = long_lists(nodes)
    near = store(close(nodes, long, percent))
    near_parts = store(components(near))
    pairs = store(candidates(nodes.join(near_parts, "node", "left").withColumn("family", F.coalesce("part", "node")), long, percent))
    may = store(near_parts.select(F.col("node").alias("a"), F.col("part").alias("b")).unionByName(pairs.filter("strong").select("a", "b")).unionByName(sharpened(pairs.filter("not strong").select("a", "b"), nodes, percent)))
    families = store(components(may).join(nodes.select("node", "doc", *same, "weight"), "node").withColumnRenamed("part", "family"))
    found = links_within(families, docs, width, percent)
    edges = found.filter("b is not null").select("a", "b")
    who = nodes.select(*same, "node", "least", "weight")
    if clash:
        ids = sets_.join(who.select(*same, "node"), same).select("doc_id", "node")
        edges = edges.unionByName(ids.join(ids.groupBy("doc_id").agg(F.min("node").alias("b")), "doc_id").select(F.col("node").alias("a"), "b"))
    parts = store(components(edges))
    label = parts.join(who.select("node", "least"), "node").groupBy("part").agg(F.min("least").alias("component"))
    links = found.filter("b is null").groupBy(F.col("a").alias("node")).agg(F.sum("links").alias("links"))
    classes = who.join(parts.join(label, "part"), "node", "left").join(links, "node", "left")
    classes = store(classes.select(*same, F.coalesce("component", "least").alias("component"), (F.coalesce("links", F.lit(0)) + F.col("weight") - 1).alias("links")))
    for t in (near, near_parts, pairs, may, families, found, parts, nodes):
        drop(t)
    out = entries.select("doc_id", *same).join(classes, same, "left")
    no_id = F.col("doc_id").isNull()
    return out.select("doc_id", F.col("n").alias("n_shingles"), F.when(no_id, None).otherwise(F.coalesce("component", "doc_id")).cast("long").alias("component_id"), F.when(no_id, 0).otherwise(F.coalesce("links", F.lit(0))).cast("long").alias("n_links"))


def keep_one(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", **how) -> DataFrame:
    """The documents with the least id of each component, once each (of an id's rows the one with the first text), with all their columns; rows with a null id stay."""
    found = store(join(docs, id_col=id_col, text_col=text_col, **how))
    ids = store(found.filter("doc_id is not null").groupBy("doc_id").agg(F.min("component_id").alias("c"), F.count("*").alias("rows")))
    # Texts meet the list of ids only where two filters of fixed size can't decide: one marks the ids that may go, the other those among them that may stay.
    doubtful = ids.filter("doc_id <> c or rows > 1")
    sent = docs.sparkSession.sparkContext.broadcast(presence(doubtful.select(F.col("doc_id").alias("node"))))

    def marked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bits = np.unpackbits(sent.value).astype(bool)
        for b in batches:
            yield b.filter(pa.array(bits[slot_of(b.column("node").to_numpy())]))

    staying = ids.filter("doc_id = c").select(F.col("doc_id").alias("node")).mapInArrow(lean(marked), "node long")
    again = docs.sparkSession.sparkContext.broadcast(presence(staying, 1))

    def part(sure: bool):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            one, two = np.unpackbits(sent.value).astype(bool), np.unpackbits(again.value).astype(bool)
            for b in batches:
                own = b.column(id_col).cast(pa.int64())
                known, own = own.is_valid().to_numpy(zero_copy_only=False), own.fill_null(0).to_numpy()
                hit = known & one[slot_of(own)]
                yield b.filter(pa.array(~hit if sure else hit & two[slot_of(own, 1)]))

        return docs.mapInArrow(lean(run), docs.schema)

    once = ids.filter("doc_id = c").select(F.col("doc_id").alias("__keep"), F.col("rows").alias("__rows"))
    some = part(False)
    some = some.join(once, some[id_col] == F.col("__keep")).drop("__keep")
    if not ids.filter("rows > 1 and doc_id = c").isEmpty():
        others = [F.col(f"`{c}`") for c in docs.columns if c not in (id_col, text_col)]
        order = Window.partitionBy(id_col).orderBy(F.col(text_col).asc_nulls_last(), *[F.xxhash64(c) for c in others])
        twice = some.filter("__rows > 1").withColumn("__rank", F.row_number().over(order)).filter("__rank = 1").drop("__rank")
        some = some.filter("__rows = 1").unionByName(twice)
    return part(True).unionByName(some.drop("__rows"))


ORACLE = r"""
WITH RECURSIVE w AS (SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS ws FROM documents),
s AS (SELECT doc_id, list_distinct(CASE WHEN len(ws) = 0 THEN [] WHEN len(ws) < 3 THEN [array_to_string(ws, ' ')]
             ELSE list_transform(range(1, len(ws) - 1), lambda i: ws[i] || ' ' || ws[i + 1] || ' ' || ws[i + 2]) END) AS sh FROM w),
t AS (SELECT doc_id, len(sh) AS n, md5(array_to_string(list_sort(sh), chr(10))) AS k, sh FROM s),
u AS (SELECT min(doc_id) AS node, count(*) AS weight, n, k, any_value(sh) AS sh FROM t WHERE n > 0 GROUP BY n, k),
x AS (SELECT node, n, unnest(sh) AS g FROM u),
p AS (SELECT a.node AS a, b.node AS b FROM x a JOIN x b ON a.g = b.g AND a.node < b.node GROUP BY a.node, b.node, a.n, b.n HAVING 100 * count(*) >= 90 * (a.n + b.n - count(*))),
e AS (SELECT a, b FROM p UNION ALL SELECT b, a FROM p),
r(node, root) AS (SELECT node, node FROM u UNION SELECT e.b, r.root FROM r JOIN e ON e.a = r.node WHERE r.root < e.b),
c AS (SELECT node, min(root) AS root FROM r GROUP BY node),
l AS (SELECT e.a AS node, sum(u.weight) AS links FROM e JOIN u ON u.node = e.b GROUP BY e.a)
SELECT t.doc_id, CAST(t.n AS BIGINT) AS n_shingles, coalesce(c.root, t.doc_id) AS component_id, CAST(coalesce(l.links, 0) + coalesce(u.weight, 1) - 1 AS BIGINT) AS n_links
FROM t LEFT JOIN u ON u.n = t.n AND u.k = t.k LEFT JOIN c ON c.node = u.node LEFT JOIN l ON l.node = u.node
"""
