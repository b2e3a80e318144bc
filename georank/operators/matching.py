"""Range and kNN membership and ranks, exact."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.lattice import dist2

#: Objects times queries up to which a nested-loop join is taken when asked to choose.
NAIVE = 50_000_000


def range_matches(objects: DataFrame, queries: DataFrame, strategy: str = "grid", side: int | None = None) -> DataFrame:
    """(seq, oid, d2) of objects within each query's radius.

    grid: queries that are alike are matched once; each is copied to the cells of a uniform grid that it touches, and an
    equi-join on the cell with a residual test finds its objects, each of which is in one cell. naive: a nested loop.
    """
    q = queries.select("seq", F.col("x").alias("qx"), F.col("y").alias("qy"), "r2")
    o = objects.select("oid", "x", "y")
    d2 = dist2("x", "y", "qx", "qy")
    if strategy == "naive":
        return q.join(o, d2 <= F.col("r2")).select("seq", "oid", d2.alias("d2"))
    cell = side or 64
    r = F.ceil(F.sqrt(F.col("r2").cast("double"))).cast("long")
    # A place carries its queries along: an object is in one cell, so a match is made in one task and not moved to find them.
    cells = q.groupBy("qx", "qy", "r2").agg(F.collect_list("seq").alias("seqs"))
    cells = cells.withColumn("gx", F.explode(F.sequence(F.floor((F.col("qx") - r) / cell), F.floor((F.col("qx") + r) / cell))))
    cells = cells.withColumn("gy", F.explode(F.sequence(F.floor((F.col("qy") - r) / cell), F.floor((F.col("qy") + r) / cell))))
    o = o.withColumns({"gx": F.floor(F.col("x") / cell), "gy": F.floor(F.col("y") / cell)})
    near = cells.join(o, ["gx", "gy"]).filter(d2 <= F.col("r2"))
    return near.select("seqs", "oid", d2.alias("d2")).select(F.explode("seqs").alias("seq"), "oid", "d2")


def non_match_counts(objects: DataFrame, queries: DataFrame) -> DataFrame:
    """(seq, outside): how many objects each query does not reach."""
    n = objects.agg(F.count("*").alias("n"))
    hit = range_matches(objects, queries).groupBy("seq").agg(F.count("*").alias("hit"))
    return queries.select("seq").join(hit, "seq", "left").crossJoin(F.broadcast(n)).select("seq", (F.col("n") - F.coalesce("hit", F.lit(0))).alias("outside"))


def knn_matches(objects: DataFrame, queries: DataFrame, k: int, strategy: str = "ring", cell: int = 64) -> DataFrame:
    """(seq, oid, d2, rnk) of each query's k nearest, ties by oid.

    ring: the radius that surely holds k objects comes from counts per grid cell (cells by greatest distance, until k are
    counted); then the range join. sort: every object is ranked for every place.
    """
    places = queries.select("x", "y").distinct()
    if strategy == "ring":
        hist = objects.groupBy(F.floor(F.col("x") / cell).alias("gx"), F.floor(F.col("y") / cell).alias("gy")).agg(F.count("*").alias("c"))
        far = F.greatest(F.abs(F.col("x") - F.col("gx") * cell), F.abs(F.col("x") - F.col("gx") * cell - cell + 1))
        fay = F.greatest(F.abs(F.col("y") - F.col("gy") * cell), F.abs(F.col("y") - F.col("gy") * cell - cell + 1))
        # The histogram has at most (side / cell)**2 rows, whatever the number of objects.
        rings = places.crossJoin(F.broadcast(hist)).select("x", "y", "c", (far * far + fay * fay).cast("long").alias("m"))
        upto = rings.withColumn("n", F.sum("c").over(Window.partitionBy("x", "y").orderBy("m").rangeBetween(Window.unboundedPreceding, 0)))
        reach = upto.groupBy("x", "y").agg(F.coalesce(F.min(F.when(F.col("n") >= k, F.col("m"))), F.max("m")).alias("r2"))
        near = range_matches(objects, reach.withColumn("seq", F.struct("x", "y")), side=cell).select("seq.x", "seq.y", "oid", "d2")
    else:
        near = places.crossJoin(objects.select("oid", F.col("x").alias("ox"), F.col("y").alias("oy"))).select("x", "y", "oid", dist2("ox", "oy", "x", "y").alias("d2"))
    top = near.withColumn("rnk", F.row_number().over(Window.partitionBy("x", "y").orderBy("d2", "oid")).cast("long")).filter(F.col("rnk") <= k)
    return queries.select("seq", "x", "y").join(top, ["x", "y"]).select("seq", "oid", "d2", "rnk")


def rank_matches(matches: DataFrame, ties: str = "total") -> DataFrame:
    """Add rnk: by (d2, oid), or with shared ranks of equal distances. A range or kNN keeps a prefix by distance, so this is the rank in the whole set."""
    by = Window.partitionBy("seq")
    rnk: Column = F.row_number().over(by.orderBy("d2", "oid")) if ties == "total" else F.rank().over(by.orderBy("d2"))
    return matches.withColumn("rnk", rnk.cast("long"))
