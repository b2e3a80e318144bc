"""Rank bounds per space cell, the quadtree's leaves and the cell rank index."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.lattice import BITS, box, max_d2, min_d2

CELL = ["lvl", "cx", "cy"]


def cell_distances(objects: DataFrame, cells: DataFrame, bits: int = BITS) -> DataFrame:
    """(cell, oid, mind2, maxd2) of every object and cell. Cells go to all tasks in blocks of the plan's choosing; objects are read once."""
    c = box(cells.select(*CELL), bits=bits)
    d = objects.select("oid", "x", "y").crossJoin(c)
    return d.select(*CELL, "oid", min_d2("x", "y", "x0", "y0", "x1", "y1").alias("mind2"), max_d2("x", "y", "x0", "y0", "x1", "y1").alias("maxd2"))


def rank_bounds(distances: DataFrame) -> DataFrame:
    """Add lo_rank and hi_rank.

    Each object puts two marks on its cell's line: its least and its greatest distance, both with its id. The greatest
    marks before its least one are of objects surely nearer; the least marks before its greatest one are of objects
    possibly nearer (its own not counted). One sort per cell, no comparison of all pairs.
    """
    marks = distances.select(*CELL, "oid", "mind2", "maxd2", F.explode(F.array(F.struct(F.col("mind2").alias("d"), F.lit(0).alias("far")), F.struct(F.col("maxd2").alias("d"), F.lit(1).alias("far")))).alias("e")).select(*CELL, "oid", "mind2", "maxd2", "e.*")
    before = Window.partitionBy(*CELL).orderBy("d", "oid", "far").rowsBetween(Window.unboundedPreceding, -1)
    n = marks.select("*", F.coalesce(F.sum("far").over(before), F.lit(0)).alias("fars"), F.coalesce(F.sum(1 - F.col("far")).over(before), F.lit(0)).alias("nears"))
    lo = F.max(F.when(F.col("far") == 0, F.col("fars") + 1))
    hi = F.max(F.when(F.col("far") == 1, F.col("nears")))  # its own least mark is among them and stands for the one to add
    return n.groupBy(*CELL, "oid", "mind2", "maxd2").agg(lo.cast("long").alias("lo_rank"), hi.cast("long").alias("hi_rank"))


def violations(bounds: DataFrame, slack: int) -> DataFrame:
    """(cell, bad): objects whose bounds are further apart than slack times the lower one."""
    return bounds.groupBy(*CELL).agg(F.sum((F.col("hi_rank") - F.col("lo_rank") > slack * F.col("lo_rank")).cast("long")).alias("bad"))


def ancestors(places: DataFrame, bits: int = BITS) -> DataFrame:
    """(x, y, cell) for every level."""
    p = places.select("x", "y").distinct().withColumn("lvl", F.explode(F.sequence(F.lit(0), F.lit(bits))))
    return p.select("x", "y", "lvl", F.expr(f"shiftright(x, {bits} - lvl)").alias("cx"), F.expr(f"shiftright(y, {bits} - lvl)").alias("cy"))


def leaves_for(places: DataFrame, objects: DataFrame, slack: int, bits: int = BITS) -> DataFrame:
    """(x, y, cell): the largest cell around each place that meets the condition. Bounds tighten as cells shrink, so that is the eager tree's leaf."""
    up = ancestors(places, bits)
    ok = violations(rank_bounds(cell_distances(objects, up.select(*CELL).distinct(), bits)), slack).filter("bad = 0").select(*CELL)
    best = up.join(ok, CELL).groupBy("x", "y").agg(F.min_by(F.struct(*CELL), "lvl").alias("c"))
    return best.select("x", "y", "c.*")


def partition(objects: DataFrame, slack: int, bits: int = BITS, max_level: int | None = None) -> DataFrame:
    """(cell, capped): the eager tree's leaves, level by level. Only objects that failed are checked again below; counts are against all.

    The number of jobs is the number of levels. Cells that still fail at max_level are leaves marked as capped.
    """
    spark = objects.sparkSession
    live = spark.createDataFrame([(0, 0, 0)], "lvl int, cx long, cy long")
    done = None
    top = bits if max_level is None else max_level
    for lvl in range(top + 1):
        bad = violations(rank_bounds(cell_distances(objects, live, bits)), slack).persist()
        leaf = bad.filter("bad = 0" if lvl < top else "true").select(*CELL, (F.col("bad") > 0).alias("capped"))
        done = leaf if done is None else done.union(leaf)
        if lvl == top or bad.filter("bad > 0").isEmpty():
            break
        live = split(bad.filter("bad > 0"))
    return done


def split(cells: DataFrame) -> DataFrame:
    kids = F.explode(F.array(*[F.struct((2 * F.col("cx") + i).alias("cx"), (2 * F.col("cy") + j).alias("cy")) for i in (0, 1) for j in (0, 1)]))
    return cells.select((F.col("lvl") + 1).alias("lvl"), kids.alias("k")).select("lvl", "k.*")


def locate(points: DataFrame, leaves: DataFrame, bits: int = BITS) -> DataFrame:
    """Each point with its leaf, by an equi-join on the cell of every level."""
    return ancestors(points, bits).join(leaves.select(*CELL), CELL).select("x", "y", *CELL)


def rank_list(bounds: DataFrame, block: int = 128) -> DataFrame:
    """(cell, pos, blk, oid, lo_rank, hi_rank, mind2) in the order of (mind2, oid), which is ascending in lo_rank."""
    pos = F.row_number().over(Window.partitionBy(*CELL).orderBy("mind2", "oid")).cast("long")
    return bounds.withColumn("pos", pos).select(*CELL, "pos", F.expr(f"(pos - 1) div {block}").alias("blk"), "oid", "lo_rank", "hi_rank", "mind2")


def blocks(listed: DataFrame, objects: DataFrame) -> DataFrame:
    """(cell, blk, first_lo, max_hi, min_d2, bounding box, cnt)."""
    j = listed.join(objects.select("oid", "x", "y"), "oid")
    return j.groupBy(*CELL, "blk").agg(F.min_by("lo_rank", "pos").alias("first_lo"), F.max("hi_rank").alias("max_hi"), F.min("mind2").alias("min_d2"), F.min("x").alias("xmin"), F.max("x").alias("xmax"), F.min("y").alias("ymin"), F.max("y").alias("ymax"), F.count("*").cast("int").alias("cnt"))


def est_contributions(matches: DataFrame, queries: DataFrame, objects: DataFrame, slack: int, bits: int = BITS) -> DataFrame:
    """(seq, oid, num, lo_rank): twice the estimated contribution 2(n+1) - (2+slack)*lo_rank of each match, from the leaf of the query's place."""
    leaf = leaves_for(queries, objects, slack, bits)
    b = rank_bounds(cell_distances(objects, leaf.select(*CELL).distinct(), bits))
    est = leaf.join(b, CELL).select("x", "y", "oid", "lo_rank", "hi_rank")
    n = F.broadcast(objects.agg(F.count("*").alias("n")))
    m = matches.join(queries.select("seq", "x", "y"), "seq").join(est, ["x", "y", "oid"]).crossJoin(n)
    return m.select("seq", "oid", (2 * (F.col("n") + 1) - (2 + slack) * F.col("lo_rank")).alias("num"), "lo_rank", "hi_rank")
