"""Merkle fixity audit of two replicas of a web archive.

Records lie in archive files at offsets, as in WARC: a record is a header and a payload, a file
holds a run of record ids, and a record's offset is the sum of the lengths before it.  The leaf
hash of a record covers its offset, length and content.  Leaves in order of offset form a tree
of the given fan-out per file; the hash of an inner node covers its children's hashes in order;
file roots in order form the tree of the replica.  Nodes of a level above are few, so each
level is one grouped aggregate of bounded groups (``fanout`` hashes).

The audit compares the replica roots; only below a mismatching node are its children looked at,
level by level, until records are reached.  A record counts as changed (other bytes), moved
(same bytes elsewhere in the file), missing or surplus.

Cases: a null payload counts as empty; a null id is left out of both replicas; repeated rows of
an id are records of their own, told apart by their order; empty replicas have the root of no
children; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .base import store


def records(pages: DataFrame, *, id_col: str = "page_id", url_col: str = "url", body_col: str = "html", per_file: int = 4096) -> DataFrame:
    """file, pos, id, offset, length, leaf of each record.  A file holds at most about ``per_file`` ids, so the running sum stays in small groups."""
    rows = pages.select(F.col(id_col).cast("long").alias("id"), F.coalesce(F.col(url_col).cast("string"), F.lit("")).alias("url"), F.coalesce(F.col(body_col).cast("string"), F.lit("")).alias("body")).filter("id is not null")
    head = F.concat(F.lit("WARC/1.1\r\nWARC-Type: response\r\nWARC-Target-URI: "), "url", F.lit("\r\nContent-Length: "), F.octet_length("body").cast("string"), F.lit("\r\n\r\n"))
    rows = rows.select(F.floor(F.col("id") / per_file).alias("file"), "id", (F.octet_length(head) + F.octet_length("body") + 4).cast("long").alias("length"), F.sha2(F.concat(head, "body").cast("binary"), 256).alias("content"))
    w = Window.partitionBy("file").orderBy("id", "content", "length")
    rows = rows.withColumn("pos", (F.row_number().over(w) - 1).cast("long")).withColumn("offset", F.sum("length").over(w) - F.col("length"))
    leaf = F.sha2(F.concat_ws("|", F.col("offset").cast("string"), F.col("length").cast("string"), "content").cast("binary"), 256)
    return rows.select("file", "pos", "id", "offset", "length", "content", leaf.alias("leaf"))


def parents(nodes: DataFrame, keys: list[str | Column], fanout: int) -> DataFrame:
    """One level up: node number, hash over the children's hashes in order, number of children."""
    up = nodes.groupBy(*keys, F.floor(F.col("node") / fanout).alias("up")).agg(F.array_sort(F.collect_list(F.struct("node", "hash"))).alias("c"))
    joined = F.array_join(F.transform("c", lambda x: F.concat(x["node"].cast("string"), F.lit(":"), x["hash"])), ",")
    return up.select(*keys, F.col("up").alias("node"), F.sha2(joined.cast("binary"), 256).alias("hash"))


def root(levels: dict) -> str | None:
    """The hash of a replica; None if it is empty."""
    top = max(k for name, k in levels if name == "replica")
    row = levels["replica", top].select("hash").first()
    return row[0] if row else None


def differing(a: DataFrame, b: DataFrame, keys: list[str], within: DataFrame | None, fanout: int) -> DataFrame:
    """Nodes of a level whose hashes differ or that one side lacks, below the mismatching nodes of the level above."""
    if within is not None:
        up = within.withColumnRenamed("node", "up")
        a, b = (x.withColumn("up", F.floor(F.col("node") / fanout)).join(up, [*keys, "up"], "left_semi") for x in (a, b))
    both = a.select(*keys, "node", F.col("hash").alias("h1")).join(b.select(*keys, "node", F.col("hash").alias("h2")), [*keys, "node"], "full")
    return both.filter(~F.col("h1").eqNullSafe(F.col("h2"))).select(*keys, "node")


def audit(one: DataFrame, other: DataFrame, *, fanout: int = 16, per_file: int = 4096, **cols) -> DataFrame:
    """file, pos, page_id, offset, length, status, path of every record that differs between the replicas."""
    sides = [store(records(x, per_file=per_file, **cols)) for x in (one, other)]
    extent = sides[0].unionByName(sides[1]).agg(F.min("file"), F.max("file"), F.max("pos")).first()
    trees = [levels_of(x, extent, fanout) for x in sides]
    if root(trees[0]) == root(trees[1]):
        wrong, order = sides[0].select("file", F.col("pos").alias("node")).limit(0), []
    else:
        wrong, order = None, sorted(trees[0], key=lambda x: (x[0] == "file", -x[1]))
    for name, k in order:
        if name == "file" and wrong is not None and "file" not in wrong.columns:
            wrong = wrong.select((F.col("node") + (extent[0] or 0)).alias("file"), F.lit(0).cast("long").alias("node"))
            if k == max(j for n, j in trees[0] if n == "file"):
                continue  # file roots are the leaves of the replica's tree
        wrong = differing(trees[0][name, k], trees[1][name, k], ["file"] if name == "file" else [], wrong, fanout)
    # In reached files, records by position: what was there and what is.
    a, b = (x.join(wrong.withColumnRenamed("node", "pos"), ["file", "pos"], "left_semi") for x in sides)
    a = a.select("file", "pos", F.col("id").alias("id1"), F.col("offset").alias("o1"), F.col("length").alias("l1"), F.col("content").alias("c1"))
    b = b.select("file", "pos", F.col("id").alias("id2"), F.col("offset").alias("o2"), F.col("length").alias("l2"), F.col("content").alias("c2"))
    d = a.join(b, ["file", "pos"], "full")
    status = F.when(F.col("id2").isNull(), "missing").when(F.col("id1").isNull(), "surplus").when(F.col("id1") != F.col("id2"), "replaced").when(F.col("c1") != F.col("c2"), "changed").otherwise("moved")
    path = F.concat_ws("/", *[F.floor(F.col("pos") / fanout**k).cast("string") for k in range(max(j for n, j in trees[0] if n == "file"), 0, -1)], F.col("pos").cast("string"))
    return d.select("file", "pos", F.coalesce("id1", "id2").alias("page_id"), F.coalesce("o1", "o2").alias("offset"), F.coalesce("l1", "l2").alias("length"), status.alias("status"), path.alias("path"))


def levels_of(leaves: DataFrame, extent, fanout: int) -> dict[tuple[str, int], DataFrame]:
    """The levels of one replica's tree, of heights that both replicas share."""
    low, high = extent[0] or 0, extent[1] or 0
    out = {("file", 0): leaves.select("file", F.col("pos").alias("node"), F.col("leaf").alias("hash"))}
    height = 0
    while fanout**height < (extent[2] or 0) + 1:
        height += 1
        out["file", height] = store(parents(out["file", height - 1], ["file"], fanout))
    out["replica", 0] = out["file", height].select((F.col("file") - low).alias("node"), "hash")
    k = 0
    while fanout**k < high - low + 1:
        k += 1
        out["replica", k] = store(parents(out["replica", k - 1], [], fanout))
    return out


def damaged(pages: DataFrame) -> DataFrame:
    """A replica in which the first character of some payloads was overwritten (same length): what the query audits."""
    hit = (F.col("page_id") % 97 == 13) & (F.length("html") > 0)
    return pages.withColumn("html", F.when(hit, F.concat(F.lit("#"), F.expr("substring(html, 2)"))).otherwise(F.col("html")))


ORACLE = """
WITH r AS (SELECT page_id, html, page_id // 4096 AS file,
  strlen('WARC/1.1' || chr(13) || chr(10) || 'WARC-Type: response' || chr(13) || chr(10) || 'WARC-Target-URI: ' || coalesce(url, '') || chr(13) || chr(10) || 'Content-Length: '
    || CAST(strlen(coalesce(html, '')) AS VARCHAR) || chr(13) || chr(10) || chr(13) || chr(10)) + strlen(coalesce(html, '')) + 4 AS length FROM pages),
o AS (SELECT *, row_number() OVER (PARTITION BY file ORDER BY page_id) - 1 AS pos, sum(length) OVER (PARTITION BY file ORDER BY page_id) - length AS off FROM r)
SELECT CAST(file AS BIGINT) AS file, CAST(pos AS BIGINT) AS pos, page_id, CAST(off AS BIGINT) AS "offset", CAST(length AS BIGINT) AS length, 'changed' AS status
FROM o WHERE page_id % 97 = 13 AND html <> ''
"""
