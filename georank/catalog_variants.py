"""Variants beside the main ways: kNN membership by bounds, longer retention of shared values, block search, the regular grid."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from .catalog import CTES, ORACLES, RUN, SLACK, W_, B, T, base, continuous, newest, query, sql
from .catalog_measures import differing, differing_sql
from .catalog_ranks import BLOCK, MODES, _leaves, _list, knn, knn_sql
from .functions.lattice import box

K = 10


def _members(spark, d):
    """(seq, oid, lo_rank) of a kNN query's members by bounds: in if surely among the nearest, out if surely not, else by estimated rank."""
    o, q = base(spark, d)
    leaf = _leaves(spark, d)
    bounds = B.rank_bounds(B.cell_distances(o, leaf.select(*B.CELL).distinct()))
    held = bounds.filter((F.col("hi_rank") <= K) | ((F.col("lo_rank") <= K) & ((2 + SLACK) * F.col("lo_rank") <= 2 * K)))
    return q.select("seq", "x", "y").join(leaf, ["x", "y"]).join(held, B.CELL).select("seq", "oid", "lo_rank")


MEMBERS = f", kb AS MATERIALIZED (SELECT seq, oid, 2 * (n + 1) - {2 + SLACK} * lo_rank AS num FROM q JOIN lc USING (x, y) JOIN rl USING (lvl, cx, cy), nn WHERE hi_rank <= {K} OR (lo_rank <= {K} AND {2 + SLACK} * lo_rank <= {2 * K}))"


@query()
def knn_bounds_topm(spark, d):
    """The continuous top m of estimates of kNN queries whose members are told by bounds too."""
    n = F.broadcast(T.objects_part(spark, d).agg(F.count("*").alias("n")))
    c = _members(spark, d).crossJoin(n).select("seq", "oid", (2 * (F.col("n") + 1) - (2 + SLACK) * F.col("lo_rank")).alias("num"))
    return continuous(c, newest(spark, d)).withColumn("pop", F.col("num") / F.lit(2.0 * W_))


ORACLES["knn_bounds_topm"] = sql("q", "lc", "rl", "nn", then="").rstrip() + MEMBERS + "," + RUN.format(c="kb", q="q") + f"SELECT win, pos, oid, num, num / {2 * W_}.0::DOUBLE AS pop FROM tp"


@query()
def knn_bounds_error(spark, d):
    """Members of all kNN queries: exact ones, those by bounds, and those that are both."""
    exact = knn(spark, d).select("seq", "oid", F.lit(1).alias("e"))
    both = _members(spark, d).select("seq", "oid", F.lit(1).alias("b")).join(exact, ["seq", "oid"], "full")
    return both.agg(F.count("e").alias("exact"), F.count("b").alias("by_bounds"), F.count(F.col("e") + F.col("b")).alias("agreed"))


ORACLES["knn_bounds_error"] = knn_sql("", "lc", "rl", "nn").rstrip() + MEMBERS + " SELECT (SELECT count(*) FROM km) AS exact, (SELECT count(*) FROM kb) AS by_bounds, (SELECT count(*) FROM km JOIN kb USING (seq, oid)) AS agreed"


RETAINED = {"third": W_ // 3, "two_thirds": 2 * W_ // 3, "none": 0}


@query()
def retention_differ(spark, d):
    """Windows of the literal monitor by how long it keeps values for reuse, and those whose result differs from the set form's."""
    return differing(spark, d, {k: MODES["literal"] | {"retain": v} for k, v in RETAINED.items()})


ORACLES["retention_differ"] = differing_sql(RETAINED)


@query()
def asof_block(spark, d):
    """Per block of each list, the greatest distance between its members' rectangle and the cell, and the first block that begins no nearer.

    One ordered pass a cell: blocks and questions are sorted together from far to near, and each question takes the last block before it.
    """
    o, listed = _list(spark, d)
    blk = box(B.blocks(listed, o).drop("cnt"))
    reach = F.pow(F.greatest(F.col("xmax") - F.col("x0"), F.col("x1") - F.col("xmin")), 2) + F.pow(F.greatest(F.col("ymax") - F.col("y0"), F.col("y1") - F.col("ymin")), 2)
    heads = blk.select(*B.CELL, F.col("min_d2").alias("at"), F.col("blk").alias("head"), F.lit(None).cast("long").alias("blk"))
    asks = blk.select(*B.CELL, reach.cast("long").alias("at"), F.lit(None).cast("long").alias("head"), "blk")
    back = Window.partitionBy(*B.CELL).orderBy(F.desc("at"), F.desc_nulls_last("head")).rowsBetween(Window.unboundedPreceding, -1)
    found = heads.unionByName(asks).withColumn("found", F.last("head", True).over(back))
    return found.filter("blk is not null").select(*B.CELL, "blk", F.col("at").alias("reach"), "found")


ORACLES["asof_block"] = sql("rl", "o", then="").rstrip() + f""",
bx AS (SELECT lvl, cx, cy, (pos - 1) // {BLOCK} AS blk, min(mind2) AS near, min(x) AS x0, max(x) AS x1, min(y) AS y0, max(y) AS y1 FROM rl JOIN o USING (oid) GROUP BY ALL),
bs AS (SELECT lvl, cx, cy, blk, near, CAST(greatest(x1 - cx * (1024 >> lvl), (cx + 1) * (1024 >> lvl) - 1 - x0) ** 2 + greatest(y1 - cy * (1024 >> lvl), (cy + 1) * (1024 >> lvl) - 1 - y0) ** 2 AS BIGINT) AS reach FROM bx)
SELECT a.lvl, a.cx, a.cy, a.blk, a.reach, min(b.blk) AS found FROM bs a LEFT JOIN bs b ON a.lvl = b.lvl AND a.cx = b.cx AND a.cy = b.cy AND b.near >= a.reach GROUP BY ALL"""


@query("vi", then="SELECT lvl, count(*) AS cells, CAST(sum(CASE WHEN bad > 0 THEN 1 ELSE 0 END) AS BIGINT) AS failing, CAST(pow(4, lvl) AS BIGINT) AS grid_cells FROM vi GROUP BY lvl")
def grid_levels(spark, d):
    """Per level of a regular grid: the cells that hold queries, those that fail the condition, and the grid's cells in all."""
    o, q = base(spark, d)
    bad = B.violations(B.rank_bounds(B.cell_distances(o, B.ancestors(q).select(*B.CELL).distinct())), SLACK)
    return bad.groupBy("lvl").agg(F.count("*").alias("cells"), F.count_if(F.col("bad") > 0).alias("failing")).withColumn("grid_cells", F.pow(F.lit(4.0), "lvl").cast("long"))


# SQL of queries that stand elsewhere.
ORACLES["grid_vs_quad_cells"] = sql("lc", then="SELECT count(DISTINCT (lvl, cx, cy)) AS quad_leaves, pow(4.0::DOUBLE, max(lvl)) AS grid_cells FROM lc")
ORACLES["index_size"] = sql("rl", then="SELECT count(*) AS n_entries, count(DISTINCT (lvl, cx, cy)) AS n_leaves, count(*) * 24 AS bytes FROM rl")
_TREE = ", ".join(f"{k} AS MATERIALIZED ({CTES[k]})" for k in ("cd", "ds", "mk", "mw", "rb", "vi"))
ORACLES["quad_leaves_small"] = sql("f", then="").rstrip() + f""", o AS (SELECT fid AS oid, x, y FROM f),
cl AS (SELECT lvl, cx, cy, cx * (1024 >> lvl) AS x0, cy * (1024 >> lvl) AS y0, (cx + 1) * (1024 >> lvl) - 1 AS x1, (cy + 1) * (1024 >> lvl) - 1 AS y1 FROM (SELECT CAST(l AS INT) AS lvl, i AS cx, j AS cy FROM range(5) a(l), range(16) b(i), range(16) c(j) WHERE i < (1 << l) AND j < (1 << l))),
{_TREE}
SELECT lvl, cx, cy, bad > 0 AS capped FROM vi v WHERE (bad = 0 OR lvl = 4) AND NOT EXISTS (SELECT 1 FROM vi u WHERE u.lvl < v.lvl AND u.cx = v.cx >> (v.lvl - u.lvl) AND u.cy = v.cy >> (v.lvl - u.lvl) AND u.bad = 0)"""
