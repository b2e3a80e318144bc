"""Operator 2: Merkle fixity audit of web archives.

An archive file is a sequence of records. Records are hashed (leaves); ordered offset ranges of FANOUT nodes are hashed
into the next level until one root stands for the file. Replicas whose roots agree are equal. Where roots differ, the
audit descends: at each level only the children of mismatching nodes are compared, down to the corrupt records.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import checkpointed, table

FANOUT = 16
#: Records of one archive file when pages are written to archives.
FILE_RECORDS = 4096


def record(url: Column, body: Column) -> Column:
    """A page as one archive record: version line, headers, blank line, payload, two line ends. Null parts are empty."""
    body = F.coalesce(body, F.lit("")).cast("binary")
    head = F.concat(F.lit("WARC/1.0\r\nWARC-Type: resource\r\nWARC-Target-URI: "), F.coalesce(url, F.lit("")), F.lit("\r\nContent-Length: "), F.octet_length(body).cast("string"), F.lit("\r\n\r\n"))
    return F.concat(head.cast("binary"), body, F.lit("\r\n\r\n").cast("binary"))


def archive(pages: DataFrame, per_file: int = FILE_RECORDS) -> DataFrame:
    """file, seq, start, n_bytes, leaf (sha256 of the record) and page_id of each page's record.

    Files hold the pages of an id range in order of id, then url and leaf, so repeated rows and ties have a fixed order. Pages
    without an id are dealt over files below 0. Null urls and bodies are empty. An empty table gives no records. Only page_id, url and html are read.
    """
    pid = pages["page_id"].cast("long")
    file = F.coalesce(F.floor(pid / per_file).cast("long"), -1 - F.pmod(F.xxhash64("url", "html"), F.lit(per_file)))
    raw = record(pages["url"], pages["html"])
    rows = pages.select(pid.alias("page_id"), file.alias("file"), F.coalesce(pages["url"], F.lit("")).alias("url"), F.octet_length(raw).cast("long").alias("n_bytes"), F.sha2(raw, 256).alias("leaf"))
    order = Window.partitionBy("file").orderBy("page_id", "url", "leaf")
    before = F.sum("n_bytes").over(order.rowsBetween(Window.unboundedPreceding, -1))
    return rows.select("page_id", "file", (F.row_number().over(order) - 1).cast("long").alias("seq"), F.coalesce(before, F.lit(0)).cast("long").alias("start"), "n_bytes", "leaf")


def parents(level: DataFrame, fanout: int = FANOUT) -> DataFrame:
    """The next level up of (file, node, first, past, hash): each node hashes its offset range and its children's hashes in order."""
    kids = F.array_sort(F.collect_list(F.struct("node", "hash")))
    up = level.groupBy("file", F.floor(F.col("node") / fanout).cast("long").alias("node")).agg(F.min("first").alias("first"), F.max("past").alias("past"), kids.alias("kids"))
    return up.select("file", "node", "first", "past", F.sha2(F.concat_ws("|", F.col("first").cast("string"), F.col("past").cast("string"), F.concat_ws("|", F.transform("kids", lambda k: k["hash"]))), 256).alias("hash"))


def tree(records: DataFrame, fanout: int = FANOUT) -> list[DataFrame]:
    """Levels from the leaves up; the last has one node per file. There are about log(records of a file) levels."""
    leaf = records.select("file", F.col("seq").alias("node"), F.col("start").alias("first"), (F.col("start") + F.col("n_bytes")).alias("past"), F.sha2(F.concat_ws("|", F.col("start").cast("string"), (F.col("start") + F.col("n_bytes")).cast("string"), "leaf"), 256).alias("hash"))
    levels = [leaf]
    top = leaf.agg(F.max("node")).first()[0]
    while top:
        levels.append(checkpointed(parents(levels[-1], fanout)))
        top //= fanout
    return levels


def audit(one: DataFrame, other: DataFrame, fanout: int = FANOUT) -> tuple[DataFrame, DataFrame]:
    """(roots: file, root_one, root_other, equal; corrupt: file, node of records whose branches mismatch all the way down).

    Files or records that only one replica has mismatch too.
    """
    a, b = tree(one, fanout), tree(other, fanout)
    while len(a) < len(b):
        a.append(parents(a[-1], fanout))
    while len(b) < len(a):
        b.append(parents(b[-1], fanout))

    def compare(k: int, only: DataFrame | None) -> DataFrame:
        x, y = (t[k].select("file", "node", F.col("hash").alias(h)) for t, h in ((a, "ha"), (b, "hb")))
        if only is not None:  # children of mismatching nodes
            x, y = (t.withColumn("up", F.floor(F.col("node") / fanout).cast("long")).join(only.select(F.col("file"), F.col("node").alias("up")), ["file", "up"], "left_semi").drop("up") for t in (x, y))
        return x.join(y, ["file", "node"], "full")

    roots = compare(len(a) - 1, None)
    wrong = checkpointed(roots.filter(~F.col("ha").eqNullSafe(F.col("hb"))).select("file", "node"))
    for k in range(len(a) - 2, -1, -1):
        wrong = checkpointed(compare(k, wrong).filter(~F.col("ha").eqNullSafe(F.col("hb"))).select("file", "node"))
    return roots.select("file", F.col("ha").alias("root_one"), F.col("hb").alias("root_other"), F.col("ha").eqNullSafe(F.col("hb")).alias("equal")), wrong


def damaged(pages: DataFrame) -> DataFrame:
    """A replica in which the last character of about one page in 256 is another one: a stand-in for bit rot."""
    hit = F.substring(F.sha2(F.coalesce(pages["page_id"].cast("string"), F.lit("")), 256), 1, 2) == "00"
    rot = F.concat(F.expr("left(html, char_length(html) - 1)"), F.when(F.expr("right(html, 1)") == "~", "!").otherwise("~"))
    return pages.select("page_id", "url", F.when(hit & (F.char_length("html") > 0), rot).otherwise(F.col("html")).alias("html"))


def op2_fixity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every record of the pages' archives, with whether the audit against a damaged replica finds it corrupt."""
    pages = table(spark, sf_dir, "pages")
    one, other = checkpointed(archive(pages)), checkpointed(archive(damaged(pages)))
    wrong = audit(one, other)[1].withColumn("corrupt", F.lit(True))
    out = one.join(wrong, (one["file"] == wrong["file"]) & (one["seq"] == wrong["node"]), "left")
    return out.select("page_id", one["file"], "seq", "start", "n_bytes", F.col("leaf").alias("record_sha256"), F.coalesce("corrupt", F.lit(False)).alias("corrupt"))


ORACLE = """
WITH rec AS (
  SELECT page_id, page_id // 4096 AS file, coalesce(url, '') AS url, html,
    'WARC/1.0' || chr(13) || chr(10) || 'WARC-Type: resource' || chr(13) || chr(10) || 'WARC-Target-URI: ' || coalesce(url, '') || chr(13) || chr(10)
    || 'Content-Length: ' || strlen(coalesce(html, '')) || chr(13) || chr(10) || chr(13) || chr(10) || coalesce(html, '') || chr(13) || chr(10) || chr(13) || chr(10) AS v
  FROM pages)
SELECT page_id, file, CAST(row_number() OVER w - 1 AS BIGINT) AS seq, CAST(coalesce(sum(strlen(v)) OVER (w ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS start,
  CAST(strlen(v) AS BIGINT) AS n_bytes, sha256(v) AS record_sha256, (substr(sha256(CAST(page_id AS VARCHAR)), 1, 2) = '00' AND length(coalesce(html, '')) > 0) AS corrupt
FROM rec WINDOW w AS (PARTITION BY file ORDER BY page_id, url, sha256(v))
"""
