"""Cases in which the training-data operators once did less than the whole job."""

import random
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from test_operators import docs
from thinfsm.llm import pii, quality, queries, quotes, setjoin, topk
from thinfsm.llm.base import chunks, store
from thinfsm.model import numbered

PLANTED = ["bob.lee (at) host (dot) org", "ann [at] mail [dot] site [dot] net", "555-123-4567", "(555) 123-4567", "4111.1111.1111.1111", "10[.]0[.]0[.]1"]
CLEAN = ["see you (at) noon . Then home", "look @ home. Then go", "4111.1111.1111.1112", "part 12345-123-45678", "rows 123 456 7890 here", "id 99-555-123-4567-1", "700[.]1[.]1[.]1"]


@pytest.mark.parametrize("times,base", [(1, 0), (1, 3000), (400, 0), (400, 40)])
def test_planted_personal_data_is_added_at_any_frequency(spark, times, base):
    rows = [f"Note {i}: {p}. Next one" for i in range(times) for p in PLANTED] + [f"Note {i}: {c}." for i in range(max(times, 200)) for c in CLEAN]
    rows += [f"write to a{i}@b.com or +1 (017) 555-7713" for i in range(base)]
    d = docs(spark, list(enumerate(rows)))
    got = {r["doc_id"]: r["text"] for r in pii.redact(d).collect()}
    kinds = ["[EMAIL]", "[EMAIL]", "[PHONE]", "[PHONE]", "[CARD]", "[IP]"]
    for i, t in enumerate(rows[: 6 * times]):
        assert got[i] == t.replace(PLANTED[i % 6], kinds[i % 6])
    for i in range(6 * times, len(rows) - base):
        assert got[i] == rows[i]
    for i in range(len(rows) - base, len(rows)):
        assert got[i] == "write to [EMAIL] or [PHONE]"


def walked(parent):
    """node: (root, position) by a plain walk; parent: node to node or None; the least node of a ring is its root."""
    parent = dict(parent)
    for v in sorted(parent):
        seen, x = [], v
        while x is not None and x not in seen:
            seen.append(x)
            x = parent[x]
        if x is not None:
            parent[min(seen[seen.index(x) :])] = None
    out = {}

    def visit(v, root, n):
        out[v] = (root, n)
        for c in sorted((c for c, p in parent.items() if p == v), key=lambda c: (c[0] != v[0], c)):
            n = visit(c, root, n + 1)
        return n

    for v in [v for v, p in parent.items() if p is None]:
        visit(v, v, 0)
    return out


def test_threads_follow_replies(spark):
    rng = random.Random(9)
    nodes = [(c, t) for c in range(12) for t in range(8)] + [(50, t) for t in range(70)]
    parent = {v: rng.choice([None, *nodes]) for v in nodes} | {(50, t): (50, t - 1) if t else (3, 3) for t in range(70)}
    parent = {v: None if p == v else p for v, p in parent.items()}
    rows = [(*v, *(p or (None, None)), f"{v}") for v, p in parent.items()]
    d = spark.createDataFrame([*rows, rows[5], (None, None, 1, 1, "none")], "conv_id long, turn long, reply_conv long, reply_turn long, own_text string")
    got = quotes.thread_order(d).collect()
    want = walked(parent)
    assert len(got) == len(rows) + 2
    by_thread = {}
    for r in got:
        if r["conv_id"] is not None:
            by_thread.setdefault((r["thread_conv"], r["thread_turn"]), {})[r["conv_id"], r["turn"]] = r["position"]
    for v, (root, _) in want.items():
        assert v in by_thread[root]
    for root, at in by_thread.items():
        assert sorted(at, key=at.get) == sorted((v for v in at), key=lambda v: want[v][1])
    some = {r["conv_id"]: [x["turn"] for x in r["turns"]] for r in quotes.threads(spark.createDataFrame([(1, 0, None, None, "a"), (1, 1, 1, 0, "b"), (1, 2, 1, 0, "c"), (1, 3, 1, 1, "d")], d.schema)).collect()}
    assert some == {1: [0, 1, 3, 2]}


def test_thread_query_keeps_every_message(spark):
    got = queries.op4_quotation(spark, "/root/testdata/sf0.001").toPandas()
    assert len(got) == spark.read.parquet("/root/testdata/sf0.001/conversations.parquet").count()
    assert got.groupby(["thread_conv", "thread_turn"])["position"].apply(lambda x: sorted(x) == list(range(len(x)))).all()


def test_topk_over_every_row(spark, duck, same, tmp_path):
    rng = np.random.default_rng(5)
    vecs = [(i, rng.normal(size=8).tolist()) for i in range(-100, 400)] + [(500, [0.5] * 3), (501, [2.0] * 5), (502, [1.5] * 12), (550, [0.25] * 8), (550, [-0.25] * 8), (503, [3.0, None]), (None, [9.0] * 8), (600, [300.0] * 8)]
    spark.createDataFrame(vecs, "vec_id long, embedding array<float>").repartition(3).write.parquet(f"{tmp_path}/embeddings.parquet")
    duck.execute(f"create schema odd; create view odd.embeddings as select * from '{tmp_path}/embeddings.parquet/*.parquet'")
    duck.execute("set schema = 'odd'")
    try:
        same(queries.op3_top_k(spark, str(tmp_path)), topk.ORACLE)
    finally:
        duck.execute("set schema = 'main'")


def test_topk_over_many_partitions(spark):
    """Each row is in one shard, whatever Spark does with the partitions of the range sort."""
    old = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", "64")
    try:
        wide = store(spark.range(0, 300_000, 1, 8).select((F.xxhash64("id") % 1024).alias("c"), "id", F.array("id").alias("v")))
        n = store(numbered(wide, ["c", "id"], "i")).agg(F.count("*"), F.count_distinct("i"), F.max("i")).first()
        assert tuple(n) == (300_000, 300_000, 299_999)
        t = spark.range(0, 60_000, 1, 6).select(F.col("id").alias("vec_id"), F.array(*[F.sin(F.col("id") * (k + 1)).alias("x") for k in range(16)]).alias("embedding"))
        got = topk.search(t, F.col("id") % 20_000 == 0).toPandas()
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", old)
    p = t.toPandas()
    v = np.floor(256 * np.stack(p["embedding"].to_numpy())).astype(np.int64)
    for q in (0, 20_000, 40_000):
        s = sorted(zip((-v @ v[q]).tolist(), range(60_000)))
        want = [x for x in s if x[1] != q][:5]
        own = got[got["query_id"] == q].sort_values("rank")
        assert [(-a, b) for a, b in want] == list(zip(own["score"], own["vec_id"]))


def test_pieces_are_bounded_by_rows_and_bytes():
    off = np.cumsum([0] + [3] * 5000 + [1 << 22] + [1 << 15] * 100)
    got = list(chunks(off))
    assert [i for i, _ in got[1:]] == [j for _, j in got[:-1]] and got[0][0] == 0 and got[-1][1] == len(off) - 1
    assert all(j - i <= 512 and (j - i == 1 or off[j] - off[i] <= 1 << 20) for i, j in got)


def test_pairs_come_once():
    rng = np.random.default_rng(6)
    p, seen = (np.unique(rng.integers(0, 9, (60, 3)), axis=0) for _ in range(2))
    known = set(map(tuple, seen.tolist()))
    assert setjoin.rows_in(p, seen).tolist() == [tuple(x) in known for x in p.tolist()]
    assert not setjoin.rows_in(p, seen[:0]).any() and not len(setjoin.rows_in(p[:0], seen))


def test_quality_learns_from_every_labelled_row(spark):
    rng = np.random.default_rng(8)
    x = rng.normal(size=(9000, quality.N_FEATURES))
    y = (x[:, 0] + 0.3 * rng.normal(size=9000) > 2).astype(int)  # the good ones are rare
    feats = spark.createDataFrame([(i, r.tobytes()) for i, r in enumerate(x)], "doc_id long, x binary")
    lab = spark.createDataFrame([(i, int(v)) for i, v in enumerate(y)], "doc_id long, quality int")
    bins = quality.binned(feats, lab)
    own = np.array([zlib.crc32(str(i).encode()) % 5 != 0 for i in range(9000)])
    n = quality.passed(bins, lambda x, y, once: np.array([once.sum(), y[once].sum(), len(y) > y.sum() > 0, 1], float))
    assert n[0] == own.sum() and n[1] == y[own].sum() and n[2] == n[3] > 10
    m = quality.fit(bins, decision=0.3)
    assert np.allclose(m.mean, x[own].mean(0)) and np.allclose(m.scale, x[own].std(0))
    low = np.sort(m.latent(x[own]))
    k = (y[own] == 0).sum()
    assert np.isclose(m.cut, (low[k - 1] + low[k]) / 2, rtol=0, atol=1e-9)
    assert ((m.score(x) >= 0.3) == y)[~own].mean() > 0.97
