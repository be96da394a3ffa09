"""Training-data operators against brute force, on planted and on odd inputs."""

import hashlib
import importlib
import random
import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from conftest import SF
from thinfsm.llm import decontaminate, fixity, langid, mixing, pii, quality, queries, quotes, setjoin, topk, toxicity

DOC = "doc_id long, text string, lang string, source string, n_chars long, n long, node string, score string, __row string"


def docs(spark, rows):
    """Documents with further columns whose names an operator might use inside."""
    return spark.createDataFrame([(i, t, "en", "s", len(t or ""), 1, "x", "y", "z") for i, t in rows], DOC)


ODD = [(1, None), (2, ""), (3, "   \n\t"), (4, "a"), (5, "a b"), (6, "e " * 30000), (7, "x" * 50000), (8, "1 2 3 !!"), (9, "dup dup dup dup"), (9, "dup dup dup dup"), (None, "no id here at all"), (10, "éè \U0001f600 你好")]


@pytest.mark.parametrize("name", sorted(queries.ORACLES))
def test_queries_equal_sql(spark, same, name):
    same(queries.QUERIES[name](spark, SF), queries.ORACLES[name])


# Set join


def brute_components(rows, percent=90, width=3):
    def shingles(t):
        w = [x for x in re.split("[ \t\n\x0b\x0c\r]+", (t or "").translate({c: c + 32 for c in range(65, 91)})) if x]
        return {tuple(w[i : i + width]) for i in range(max(1, len(w) - width + 1))} if w else set()

    ids, sets = [i for i, _ in rows], [shingles(t) for _, t in rows]
    comp = {i: i for i in ids if i is not None}
    links = [0] * len(rows)

    def find(x):
        while comp[x] != x:
            x = comp[x]
        return x

    for a in range(len(rows)):
        for b in range(a):
            if ids[a] is None or ids[b] is None or not sets[a] or not sets[b]:
                continue
            both = len(sets[a] & sets[b])
            if 100 * both >= percent * (len(sets[a]) + len(sets[b]) - both):
                links[a], links[b] = links[a] + 1, links[b] + 1
                x, y = find(ids[a]), find(ids[b])
                comp[max(x, y)] = min(x, y)
    return sorted(((i, len(s), None if i is None else find(i), k) for i, s, k in zip(ids, sets, links)), key=str)


def near_copies(seed, n=160):
    """Chains and stars of copies at about the threshold, with shared passages and long texts."""
    rng = random.Random(seed)
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(3))
    line, out = [word() for _ in range(12)], []
    while len(out) < n:
        base = [word() for _ in range(rng.choice([5, 40, 60, 90, 700]))] + line
        for _ in range(rng.choice([1, 2, 12, 30])):
            t = list(base)
            for _ in range(rng.choice([0, 1, 1, 2, 2])):
                t[rng.randrange(len(t))] = word()
            out.append(" ".join(t))
            if rng.random() < 0.3:
                base = t
    return list(enumerate(out))


@pytest.mark.parametrize("seed,width,percent", [(1, 3, 90), (2, 3, 90), (3, 5, 80)])
def test_set_join_against_brute_force(spark, seed, width, percent):
    rows = near_copies(seed)
    got = sorted(map(tuple, setjoin.join(docs(spark, rows), width=width, percent=percent).collect()), key=str)
    assert got == brute_components(rows, percent, width)


def test_set_join_in_parts_and_blocks(spark, monkeypatch):
    """Long lists in parts, families in blocks: the same links."""
    rng = random.Random(5)
    base = [f"w{i}" for i in range(80)]
    rows = []
    for i in range(120):
        t = list(base)
        for _ in range(rng.choice([0, 1, 1, 2, 3])):
            t[rng.randrange(len(t))] = f"x{rng.randrange(9)}"
        rows.append((i, " ".join(t)))
    nodes = []
    monkeypatch.setattr(setjoin, "MEMBERS", 16)
    found = sorted(map(tuple, setjoin.join(docs(spark, rows)).collect()), key=str)
    assert found == brute_components(rows)
    entries = np.zeros(300, setjoin.ITEM)
    entries["list"], entries["node"] = np.repeat([7, 8], 150), np.arange(300)
    cut = setjoin.dealt(entries, (np.array([7], np.uint64), np.array([4])))
    assert len(cut) == 150 + 150 * 4 and (cut["list"] == 8).sum() == 150
    for x in np.unique(cut["list"]):
        nodes.append(set(cut["node"][cut["list"] == x].tolist()))
    assert all(any({a, b} <= s for s in nodes) for a in range(0, 150, 7) for b in range(0, 150, 11))


def test_set_join_sends_no_square_of_a_group(spark, monkeypatch):
    """Long near copies, whose short signatures decide nothing, give a forest and not all their pairs."""
    rng = random.Random(8)
    base = [f"w{i}" for i in range(1500)]
    rows = []
    for i in range(120):
        t = list(base)
        for _ in range(12):
            t[rng.randrange(len(t))] = f"x{rng.randrange(10**6)}"
        rows.append((i, " ".join(t)))
    sent, store = [], setjoin.store

    def counted(table):
        out = store(table)
        if "strong" in out.columns:
            sent.append(out.count())
        return out

    monkeypatch.setattr(setjoin, "store", counted)
    found = sorted(map(tuple, setjoin.join(docs(spark, rows), width=5, percent=80).collect()), key=str)
    assert found == brute_components(rows, 80, 5)
    assert len({r[2] for r in found}) == 1 and len(sent) == 1 and sent[0] <= len(rows)


def test_set_join_with_repeated_ids(spark):
    a, b, c = "one two three four", "five six seven eight", "nine ten eleven twelve"
    rows = [(3, a), (5, a), (5, b), (7, b), (7, b), (9, c), (9, None), (11, c)]
    got = sorted(map(tuple, setjoin.join(docs(spark, rows)).collect()), key=str)
    assert got == brute_components(rows)
    kept = {r["doc_id"]: r["text"] for r in setjoin.keep_one(docs(spark, rows)).collect()}
    assert kept == {3: a, 9: c}


def test_set_join_odd(spark):
    got = sorted(map(tuple, setjoin.join(docs(spark, ODD)).collect()), key=str)
    assert got == brute_components(ODD)
    assert setjoin.join(docs(spark, ODD).limit(0)).collect() == []
    kept = setjoin.keep_one(docs(spark, [*ODD, (11, "A"), (12, "dup dup dup dup")]))
    assert sorted(str(r[0]) for r in kept.collect()) == sorted(map(str, [1, 2, 3, 4, 5, 6, 7, 8, 9, 10, None]))
    assert kept.columns == docs(spark, []).columns


def test_components_of_a_long_chain(spark):
    e = spark.createDataFrame([(i, i + 1) for i in range(200)] + [(500, 501)], "a long, b long")
    got = {r[0]: r[1] for r in setjoin.components(e).collect()}
    assert set(got.values()) == {0, 500} and len(got) == 203


# Decontamination


def test_leaks_and_offsets(spark):
    item = "One two three four five six seven eight nine ten eleven"
    bench = spark.createDataFrame([("a", item), ("b", "short item"), ("c", None), (None, "null id"), ("d", "!!"), ("e", item)], "item_id string, text string")
    text = "été: TWO, three four five six seven-eight nine ten eleven! Then SHORT item; short itemx"
    rows = [*ODD, (20, text)]
    got = {r["doc_id"]: r for r in decontaminate.find_leaks(docs(spark, rows), bench).collect()}
    r = got[20]
    assert r["items"] == ["a", "b", "e"] and len(r["hits"]) == 12
    assert [text[s["start"] : s["end"]] for s in r["spans"]] == ["TWO, three four five six seven-eight nine ten eleven", "SHORT item"]
    many = {r["doc_id"]: r for r in decontaminate.find_leaks(docs(spark, rows), bench, group_bytes=10).collect()}
    assert {k: tuple(v) for k, v in many.items()} == {k: tuple(v) for k, v in got.items()}
    for size in (10, 64 << 20):
        kept = decontaminate.remove_contaminated(docs(spark, [*rows, (None, text)]), bench, group_bytes=size)
        assert kept.columns == docs(spark, []).columns and kept.count() == len(ODD) and kept.filter("doc_id = 20").isEmpty()
    assert decontaminate.find_leaks(docs(spark, rows).limit(0), bench).collect() == [] == decontaminate.remove_contaminated(docs(spark, rows).limit(0), bench).collect()
    assert decontaminate.remove_contaminated(docs(spark, rows), bench.limit(0)).count() == len(rows)
    assert decontaminate.find_leaks(docs(spark, rows), bench.limit(0)).filter(F.size("hits") > 0).isEmpty()


# Language


def test_languages(spark):
    q = queries.op7_language(spark, SF).toPandas()
    d = spark.read.parquet(f"{SF}/documents.parquet").toPandas().set_index("doc_id")["lang"]
    held = q[q["held_out"]]
    assert (held["lang_pred"].to_numpy() == d.loc[held["doc_id"]].to_numpy()).mean() > 0.9
    assert q["score"].between(0, 1).all()


def test_language_odd(spark):
    got = {r["doc_id"]: r for r in langid.identify(docs(spark, ODD)).collect()}
    assert all(got[i]["lang_pred"] == "und" and got[i]["score"] == 0 for i in (1, 2, 3, 8))
    assert got[10]["lang_pred"] == "en"
    kept = langid.keep_known(docs(spark, ODD))
    assert kept.columns == docs(spark, []).columns and kept.filter("doc_id in (1, 2, 3, 8)").isEmpty() and kept.count() == len(ODD) - 4
    empty = docs(spark, ODD).withColumn("lang", F.lit(None).cast("string"))
    assert {r["lang_pred"] for r in langid.identify(empty).collect()} == {"und"}


def test_codewords_are_apart():
    for k in (2, 4, 6, 12):
        c = langid.codewords(k)
        apart = [(c[a] != c[b]).sum() for a in range(k) for b in range(a)]
        assert min(apart) >= (1 if k == 2 else 2)


# Quality and toxicity


def test_quality_ranks(spark):
    at = "/root/testdata/sf0.1"
    q = queries.op9_quality(spark, at).toPandas().set_index("doc_id")
    lab = spark.read.parquet(f"{at}/labels.parquet").toPandas().set_index("doc_id")["quality"]
    q = q.loc[lab.index]
    held = q["held_out"]  # rows that it hasn't learned from
    assert held.sum() > 500 and (q["predicted"] == lab)[held].mean() > 0.9 and ((q["score"] >= 0.3).astype(int) == q["predicted"]).all()


def labels(spark, rows):
    return spark.createDataFrame(rows, "doc_id long, quality int, toxic int")


def test_classifiers_odd(spark):
    none = labels(spark, [])
    for f in (lambda d, x: quality.rank(d, x), lambda d, x: toxicity.detect(d, x)):
        got = f(docs(spark, ODD), none).collect()
        assert len(got) == len(ODD) and {r["score"] for r in got} == {0.5}
        one = f(docs(spark, ODD), labels(spark, [(4, 1, 1), (5, None, None), (99, 1, 0)])).collect()
        assert len(one) == len(ODD) and all(0 <= r["score"] <= 1 for r in one)
        assert f(docs(spark, ODD).limit(0), none).collect() == []


def test_toxic_examples(spark):
    rng = random.Random(3)
    word = lambda: "".join(rng.choice("abcdefghij") for _ in range(5))
    rows, lab = [], []
    for i in range(400):
        t = [word() for _ in range(40)]
        bad = i % 4 == 0
        if bad:
            t[7], t[30] = rng.choice(["vile", "foul"]), "Foul!"
        rows.append((i, " ".join(t)))
        lab.append((i, 1, int(bad)))
    got = toxicity.detect(docs(spark, rows), labels(spark, lab)).toPandas().set_index("doc_id")
    want = np.array([x[2] for x in lab])
    assert (got.loc[range(400), "predicted"].to_numpy() == want).mean() == 1.0
    assert len(got.loc[0, "evidence"]) > 0 and all(e["toxic"] == 1 for e in got.loc[0, "evidence"])


def test_nearest_is_exact():
    rng = np.random.default_rng(4)
    for _ in range(20):
        w = rng.random((30, 203)) * (rng.random((30, 203)) < 0.2)
        w = np.round(w / np.maximum(np.linalg.norm(w, axis=0), 1e-9), 3)
        ix = toxicity.Index(rng.permutation(203), rng.integers(0, 2, 203).astype(float), w, 16)
        t = np.sort(rng.choice(30, 4, replace=False))
        q = rng.random(4)
        at, cos, seen = ix.nearest(t, q, 7)
        full = np.round(q @ w[t], 12)
        order = np.lexsort((ix.ids, -full))
        order = order[full[order] > 0][:7]
        assert at.tolist() == order.tolist() and np.allclose(cos, full[order])


# Top-k


def test_topk_odd(spark):
    rng = np.random.default_rng(1)
    vecs = [(i, rng.normal(size=8).tolist()) for i in range(300)] + [(300, None), (301, [1.0] * 7 + [None]), (302, [float("nan")] * 8), (303, [float("inf")] * 8), (None, [1.0] * 8), (304, [1.0] * 3), (305, [0.5] * 8), (306, [0.5] * 8)]
    t = spark.createDataFrame(vecs, "vec_id long, embedding array<float>").withColumn("id", F.lit("x"))
    got = topk.search(t, F.col("id") % 50 == 0, block=16, shard=40, group=4).collect()
    ok = {i: [int(np.floor(256 * float(np.float32(x)))) for x in v] for i, v in vecs if i is not None and v is not None and len(v) == 8 and all(x is not None and np.isfinite(x) for x in v)}
    for q in (0, 50, 100, 250):
        s = sorted(((-sum(a * b for a, b in zip(ok[q], v)), i) for i, v in ok.items() if i != q))[:5]
        assert [(r["score"], r["vec_id"]) for r in sorted((r for r in got if r["query_id"] == q), key=lambda r: r["rank"])] == [(-a, b) for a, b in s]
    assert topk.search(t.limit(0), F.col("id") % 50 == 0).collect() == []
    assert len(topk.search(t.filter("vec_id in (0, 1, 2)"), F.col("id") % 50 == 0).collect()) == 2


def test_topk_prunes_like_vectors_and_keeps_ties(spark):
    rng = np.random.default_rng(2)
    heart = rng.normal(size=(12, 16))
    vecs = [(i, (heart[i % 12] * 2 + 0.05 * rng.normal(size=16)).tolist()) for i in range(1200)]
    vecs += [(2000 + i, vecs[0][1]) for i in range(9)] + [(50, vecs[7][1]), (100, vecs[100][1])]  # ties at the last rank, repeated ids
    t = spark.createDataFrame(vecs, "vec_id long, embedding array<float>").repartition(5)
    how = {"block": 16, "shard": 128, "group": 8}
    got = {}
    for r in topk.search(t, F.col("id") % 50 == 0, **how).orderBy("rank").collect():
        got.setdefault(r["query_id"], []).append((-r["score"], r["vec_id"]))
    q = {i: [] for i, _ in vecs if i % 50 == 0}
    v = np.array([[int(np.floor(256 * float(np.float32(x)))) for x in e] for _, e in vecs])
    ids = np.array([i for i, _ in vecs])
    for i in q:
        own = v[ids == i]
        want = [sorted((-int(s), int(j)) for s, j in zip(v @ a, ids) if j != i)[:5] for a in own]
        assert got[i] in want
    seen = topk.search(t, F.col("id") % 50 == 0, report=True, **how).toPandas()
    assert seen["pairs"].sum() % len(q) == 0 and seen["scored"].sum() < 0.5 * seen["pairs"].sum()  # every query meets every block once
    table = spark.createDataFrame([(5000, vecs[3][1])], "vec_id long, embedding array<float>")
    assert [r["vec_id"] for r in topk.search(t, table, **how).filter("rank = 1").collect()][0] % 12 == 3


# Personal data

PATTERNS = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}


def plain_spans(text):
    def luhn(d):
        return sum(int(c) if k % 2 == 0 else 2 * int(c) - 9 * (int(c) > 4) for k, c in enumerate(reversed(d))) % 10 == 0

    def ok(kind, m):
        d = re.sub("[^0-9]", "", m)
        return {"email": True, "ip": kind == "ip" and all(int(x) <= 255 for x in m.split(".")), "card": 16 <= len(d) <= 19 and luhn(d), "phone": 8 <= len(d) <= 15}[kind]

    return [(k, m.start(), m.end()) for k, p in PATTERNS.items() for m in re.finditer(p, text or "") if ok(k, m.group(0))]


PII = ["a@b.c_d@e.f x@y.z", "1.2.3.4.5.6.7.8 256.1.1.1 001.02.3.4 999999999999.1.1.1", "4111 1111 1111 1111 4111-1111-1111-1112 12 34", "+1 (017) 555-7713 +12 +1234567890123456", "é@b.co ü+49 30 1234567)", "a" * 20000, "1 " * 3000, "me@x.com" * 3 + " 10.0.0.1" * 700, "a@b@c.d e@f.g.h.i", "+49(0)30.12.34.56 and 1.2.3", "\U0001f600 x@y.org"]


def test_personal_data_against_regex(spark):
    rng = random.Random(5)
    made = ["".join(rng.choice("0123456789.@+- ()abé") for _ in range(60)) for _ in range(150)]
    rows = [*ODD, *((100 + i, t) for i, t in enumerate(PII + made))]
    got = {}
    for r in pii.report(pii.find(docs(spark, rows), keep=("doc_id",))).collect():
        got.setdefault(r["doc_id"], r)
    for i, t in rows:
        s, r = plain_spans(t), got[i]
        assert tuple(r[1:5]) == tuple(sum(k == kind for k, _, _ in s) for kind in PATTERNS), t
        text = ",".join(f"{k}:{a}:{b}" for k, a, b in s)
        assert r["base_sha256"] == hashlib.sha256(text.encode()).hexdigest(), t
        assert set(filter(None, text.split(","))) <= set(r["spans"].split(","))


def test_redaction(spark):
    rows = [(1, "mail a.b@c.org, call +1 (017) 555-7713"), (2, "nothing"), (3, None), (4, "é 10.0.0.1\U0001f600 4111 1111 1111 1111")]
    got = {r["doc_id"]: r for r in pii.redact(docs(spark, rows)).collect()}
    assert got[1]["text"] == "mail [EMAIL], call [PHONE]" and got[1]["n_chars"] == len(got[1]["text"])
    assert got[2]["text"] == "nothing" and got[3]["text"] is None and got[4]["text"] == "é [IP]\U0001f600 [CARD]"
    plan = pii.report(pii.find(docs(spark, rows), keep=("doc_id",)))._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan and "Pandas" not in plan


# Mixing


def test_mixture_meets_targets(spark):
    d, lab = spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/labels.parquet")
    got = mixing.mix(d, mixing.domains_of(lab), {"plain": 0.8, "low": 0.1, "toxic": 0.1}, keep=("doc_id",), ridge=1e-3, rounds=80).toPandas()
    p, w = np.stack(got["posteriors"]), got["n_tokens"] / got["n_tokens"].sum()
    share = (w * got["rate"]).to_numpy() @ p
    assert np.abs(share - np.array([0.1, 0.8, 0.1])).max() < 0.03 and (got["rate"] >= 0).all()


def test_rates_against_plain_descent(spark):
    rng = np.random.default_rng(2)
    p, n = rng.dirichlet([0.5] * 3, 200), rng.integers(1, 100, 200)
    rows = spark.createDataFrame([(int(a), b.tolist()) for a, b in zip(n, p)], "n long, p array<double>")
    target = np.array([0.2, 0.5, 0.3])
    got = mixing.fit_rates(rows, target, ridge=0.05, rounds=100, tolerance=1e-7).replay(p)[0]
    w, r = n / n.sum(), np.ones(200)
    for _ in range(5000):
        r = np.maximum(0, r - (p @ ((w * r) @ p - target) + 0.05 * (r - 1)) / 1.05)
    assert np.abs(got - r).max() < 1e-2


def test_mixing_odd(spark):
    got = mixing.mix(docs(spark, ODD), labels(spark, []).select("doc_id", F.lit("x").alias("domain")), mixing.TARGETS, keep=("doc_id", "n"))
    assert got.count() == len(ODD) and got.columns[:2] == ["doc_id", "n"]
    assert mixing.mix(docs(spark, ODD).limit(0), labels(spark, []).select("doc_id", F.lit("x").alias("domain")), mixing.TARGETS).collect() == []


# Fixity and quotations


def test_fixity_finds_every_change(spark):
    base = [(i, f"http://x/{i}", f"<p>{i}</p>" * (i % 7)) for i in range(400)] + [(None, "u", "h"), (7, "again", "twice")]
    one = spark.createDataFrame(base, "page_id long, url string, html string")
    assert fixity.audit(one, one, per_file=64, fanout=4).collect() == []
    other = spark.createDataFrame([(i, u, h.replace("<", "[") if i in (10, 333) else h) for i, u, h in base if i != 399], "page_id long, url string, html string")
    got = {(r["page_id"], r["status"]) for r in fixity.audit(one, other, per_file=64, fanout=4).collect()}
    assert got == {(10, "changed"), (333, "changed"), (399, "missing")}
    assert fixity.audit(one.limit(0), one.limit(0)).collect() == []
    assert {r["status"] for r in fixity.audit(one.limit(3), one.limit(0)).collect()} == {"missing"}


def test_quotations(spark):
    rows = [(1, 0, "Hello there\nSecond line"), (1, 1, "They wrote:\n> hello   THERE\nAnswer"), (1, 2, ">> Hello there\n> Answer\nMore"), (2, 0, "> Answer\nelsewhere"), (3, 0, None), (None, None, "> Hello there"), (4, 0, ">"), (4, 0, ">")]
    d = spark.createDataFrame(rows, "conv_id long, turn long, text string").withColumn("level", F.lit(1))
    got = {(r["conv_id"], r["turn"]): r for r in quotes.link(d).collect()}
    assert (got[1, 1]["reply_turn"], got[1, 1]["own_text"]) == (0, "Answer")
    assert (got[1, 2]["reply_turn"], got[1, 2]["depth"], got[1, 2]["own_text"]) == (1, 2, "More")
    assert (got[2, 0]["reply_conv"], got[2, 0]["reply_turn"]) == (1, 1)
    assert got[None, None]["reply_conv"] == 1 and got[3, 0]["own_text"] == "" and quotes.link(d).count() == len(rows)
    assert quotes.threads(quotes.link(d)).count() == 5


# Pipeline


def test_pipeline_stages(spark):
    pipeline = importlib.import_module("corpus_pipeline")
    d = spark.read.parquet(f"{SF}/documents.parquet")
    rows = {name: None for name, _ in pipeline.STAGES}
    for k, (name, stage) in enumerate(pipeline.STAGES):
        out = stage(spark, d, SF)
        if k < len(pipeline.STAGES) - 1:
            assert out.columns == d.columns
        d = setjoin.store(out)
        rows[name] = d.toPandas()
    brute = brute_components(list(rows["language"][["doc_id", "text"]].itertuples(index=False, name=None)), percent=80, width=5)
    assert sorted(rows["near_duplicates"]["doc_id"]) == sorted({c for _, _, c, _ in brute})
    assert not any(plain_spans(t) for t in rows["personal_data"]["text"])
    assert len(rows["mixture"]) == len(rows["personal_data"]) == len(rows["decontamination"]) and (rows["mixture"]["rate"] >= 0).all()


def test_pipeline_on_odd_documents(spark):
    """Nulls, empty and very long texts, repeated ids, ties, clashing columns, an empty table, from stage to stage."""
    pipeline = importlib.import_module("corpus_pipeline")
    mail = "please write to some.one@example.org about the garden and the long way home today"
    leak = spark.read.parquet(f"{SF}/benchmark.parquet").first()["text"]
    rows = [*ODD, (20, mail), (21, mail), (22, None), (None, mail), (23, f"some words before {leak} and some after"), (20, mail + " again"), (24, "word " * 60000 + "me@x.com")]
    schema = "doc_id long, text string, lang string, source string, n_chars long, rate string, node long, family string, __row long"
    d = spark.createDataFrame([(i, t, "en", "s", 1, "r", 7, "f", 8) for i, t in rows], schema)
    for table_ in (d, d.limit(0)):
        out = table_
        for k, (name, stage) in enumerate(pipeline.STAGES):
            out = setjoin.store(stage(spark, out, SF))
            if k < len(pipeline.STAGES) - 1:
                assert out.columns == d.columns, name
        assert set(d.columns) <= set(out.columns) and dict(out.dtypes)["rate"] == "double"
        got = {(r["doc_id"], r["text"]) for r in out.collect()}
        if table_ is d:
            clean = mail.replace("some.one@example.org", "[EMAIL]")
            assert (20, clean) in got and (None, clean) in got and not any(i in (1, 2, 3, 8, 21, 22, 23) for i, _ in got)
            assert [t[-8:] for i, t in got if i == 24] == [" [EMAIL]"] and len(got) == out.count()
        else:
            assert not got


def test_fixity_odd(spark):
    pages = spark.createDataFrame([(1, "u", "x" * 300_000, 5), (2, None, None, 6), (3, "", "", 7), (3, "", "", 7)], "page_id long, url string, html string, path long")
    assert fixity.audit(pages, pages).collect() == []
    other = pages.withColumn("html", F.when(F.col("page_id") == 1, F.concat("html", F.lit("y"))).otherwise(F.col("html")))
    assert [(r["page_id"], r["status"]) for r in fixity.audit(pages, other).orderBy("pos").collect()] == [(1, "changed"), (2, "moved"), (3, "moved"), (3, "moved")]
    assert fixity.audit(pages.limit(0), pages.limit(0)).collect() == []


def test_personal_data_empty_and_many(spark):
    assert pii.report(pii.find(docs(spark, []), keep=("doc_id",))).collect() == []
    many = " ".join(f"a{i}@b.com" for i in range(3000))
    got = pii.redact(docs(spark, [(1, many), (2, None), (3, "")])).collect()
    assert {r["doc_id"]: r["text"] for r in got}[1] == " ".join(["[EMAIL]"] * 3000)
