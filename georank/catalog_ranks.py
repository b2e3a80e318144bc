"""Queries for the ranking methods, baselines, bounds, index, monitors and measures."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from .catalog import BLOCK, M_, ORACLES, R_, RUN, SLACK, W_, B, L, M, P, R, T, base, continuous, contribs, expanded, lattice, last_ranked, last_window, newest, query, ranked, run_sql, sql

OUT = "SELECT oid, x, y FROM {}"


@query("o", then=OUT.format("o"))
def objects_part(spark, d):
    return T.objects_part(spark, d)


@query("oo", then=OUT.format("oo"))
def objects_orders(spark, d):
    return T.objects_orders(spark, d)


@query("oe", then=OUT.format("oe"))
def objects_embed(spark, d):
    return T.objects_embed(spark, d)


@query("f", then="SELECT fid, x, y FROM f")
def facilities(spark, d):
    return T.facilities(spark, d)


@query("q", then="SELECT seq, x, y FROM q")
def gen_uniform(spark, d):
    return T.queries_uniform(spark, d).select("seq", "x", "y")


@query("qs", then="SELECT seq, x, y FROM qs")
def gen_skewed(spark, d):
    return T.queries_skewed(spark, d).select("seq", "x", "y")


@query("qe", then="SELECT seq, x, y FROM qe")
def gen_events(spark, d):
    return T.queries_events(spark, d).select("seq", "x", "y")


@query("qc", then="SELECT seq, x, y, CAST(r2 AS BIGINT) AS r2 FROM qc")
def gen_checkin(spark, d):
    return T.queries_checkin(spark, d).select("seq", "x", "y", "r2")


@query("o", "q", then="SELECT gx, gy, CAST(sum(a) AS BIGINT) AS n_objects, CAST(sum(b) AS BIGINT) AS n_queries FROM (SELECT x // 32 AS gx, y // 32 AS gy, 1 AS a, 0 AS b FROM o UNION ALL SELECT x // 32, y // 32, 0, 1 FROM q) GROUP BY gx, gy")
def location_density(spark, d):
    o, q = base(spark, d)
    cell = [F.expr("x div 32").alias("gx"), F.expr("y div 32").alias("gy")]
    both = o.select(*cell, F.lit(1).alias("a"), F.lit(0).alias("b")).unionAll(q.select(*cell, F.lit(0), F.lit(1)))
    return both.groupBy("gx", "gy").agg(F.sum("a").alias("n_objects"), F.sum("b").alias("n_queries"))


@query("o", "pl", then="SELECT pl.x, pl.y, oid, (o.x - pl.x) * (o.x - pl.x) + (o.y - pl.y) * (o.y - pl.y) AS d2 FROM pl, o")
def dist2_projection(spark, d):
    o, q = base(spark, d)
    p = q.select("x", "y").distinct()
    return p.crossJoin(o.select("oid", F.col("x").alias("ox"), F.col("y").alias("oy"))).select("x", "y", "oid", lattice.dist2("ox", "oy", "x", "y").alias("d2"))


@query("m", then="SELECT seq, oid, d2 FROM m")
def range_match(spark, d):
    return M.range_matches(*base(spark, d), strategy="naive")


@query("m", then="SELECT seq, oid, d2 FROM m")
def range_match_grid(spark, d):
    return M.range_matches(*base(spark, d), strategy="grid")


@query("m", "nn", then="SELECT q.seq, n - count(m.oid) AS outside FROM q LEFT JOIN m USING (seq), nn GROUP BY q.seq, n")
def range_nonmatch_count(spark, d):
    return M.non_match_counts(*base(spark, d))


KNN = "kp AS (SELECT pl.x, pl.y, oid, (o.x - pl.x) * (o.x - pl.x) + (o.y - pl.y) * (o.y - pl.y) AS d2 FROM pl, o), kr AS (SELECT *, row_number() OVER (PARTITION BY x, y ORDER BY d2, oid) AS rnk FROM kp QUALIFY rnk <= 10), km AS MATERIALIZED (SELECT seq, oid, d2, rnk FROM q JOIN kr USING (x, y))"


def knn_sql(then: str, *names: str) -> str:
    return sql("pl", "o", "q", *names, then="").rstrip() + ", " + KNN + " " + then


def knn(spark, d, strategy: str = "ring"):
    return M.knn_matches(*base(spark, d), 10, strategy)


@query()
def knn_match(spark, d):
    return knn(spark, d)


@query()
def knn_match_sort(spark, d):
    return knn(spark, d, "sort")


ORACLES["knn_match"] = ORACLES["knn_match_sort"] = knn_sql("SELECT seq, oid, d2, rnk FROM km")


@query("r", then="SELECT seq, oid, d2, rnk FROM r")
def rank_in_query(spark, d):
    return expanded(spark, d)


@query("m", then="SELECT seq, oid, d2, CAST(rank() OVER (PARTITION BY seq ORDER BY d2) AS BIGINT) AS rnk FROM m")
def rank_shared_ties(spark, d):
    return expanded(spark, d, ties="shared")


@query("c", then="SELECT seq, oid, num FROM c")
def contribution(spark, d):
    return P.contributions(expanded(spark, d), T.objects_part(spark, d))


@query("pop", then="SELECT oid, num, pop FROM pop")
def popularity_last_window(spark, d):
    return last_window(spark, d)


TOP = f"SELECT row_number() OVER (ORDER BY num DESC, oid) AS pos, oid, num, pop FROM {{}} QUALIFY pos <= {M_}"


@query("pop", then=TOP.format("pop"))
def topm_last_window(spark, d):
    return P.topm(last_window(spark, d), M_).withColumn("pos", F.col("pos").cast("long"))


@query("pop", "o", then=TOP.format("(SELECT oid, coalesce(num, 0) AS num, coalesce(pop, 0.0) AS pop FROM o LEFT JOIN pop USING (oid))"))
def topm_padded(spark, d):
    return P.topm(last_window(spark, d), M_, T.objects_part(spark, d)).withColumn("pos", F.col("pos").cast("long"))


@query()
def continuous_topm_count(spark, d):
    """The flagship: the exact top m of every full window."""
    return window_tops(*base(spark, d))


def window_tops(o, q):
    return L.window_tops(o, q, W_, M_).select("win", "pos", "oid", "num", (F.col("num") / F.lit(float(W_))).alias("pop"))


ORACLES["continuous_topm_count"] = run_sql("c")


@query()
def topm_changes(spark, d):
    return P.result_changes(continuous_topm_count(spark, d))


ORACLES["topm_changes"] = run_sql("c", then="SELECT win FROM (SELECT win, l, lag(l) OVER (ORDER BY win) AS b FROM (SELECT win, list(oid ORDER BY pos) AS l FROM tp GROUP BY win)) WHERE b IS NULL OR b <> l")


@query()
def topm_skewed(spark, d):
    return window_tops(T.objects_part(spark, d), T.queries_skewed(spark, d))


ORACLES["topm_skewed"] = run_sql("c").replace("fid = (user_id * 100 + pk) % n", "fid = least(n - 1, CAST(round(value * 100) AS BIGINT) * n // 50000)")


@query()
def baseline_topm(spark, d):
    """The exact baseline as a replay: every arrival is ranked, added, the expired one subtracted, all touched objects sorted."""
    o, q = base(spark, d)
    c = contribs(spark, d).withColumn("o", -F.col("num"))
    n = o.count()
    out = R.replay(R.prepare(c, q, "o"), n, W_, M_, n, {"baseline": {"block_level": False, "object_level": False, "reuse": False}}, BLOCK)
    return out.select("win", F.col("pos").cast("long").alias("pos"), "oid", "num", (F.col("num") / F.lit(float(W_))).alias("pop"))


ORACLES["baseline_topm"] = run_sql("c")


@query()
def recompute_topm(spark, d):
    """Every window from scratch."""
    c = contribs(spark, d)
    q = T.queries_uniform(spark, d).select(F.col("seq").alias("win")).filter(F.col("win") >= W_ - 1)
    bucket = q.withColumn("b", F.explode(F.sequence(F.expr(f"(win - {W_ - 1}) div {W_}"), F.expr(f"win div {W_}"))))
    rows = bucket.join(c.withColumn("b", F.expr(f"seq div {W_}")), "b").filter((F.col("seq") <= F.col("win")) & (F.col("seq") > F.col("win") - W_))
    pop = rows.groupBy("win", "oid").agg(F.sum("num").alias("num"))
    pos = F.row_number().over(Window.partitionBy("win").orderBy(F.desc("num"), "oid"))
    return pop.withColumn("pos", pos.cast("long")).filter(F.col("pos") <= M_).select("win", "pos", "oid", "num", (F.col("num") / F.lit(float(W_))).alias("pop"))


ORACLES["recompute_topm"] = run_sql("c")


@query()
def rknn_count(spark, d):
    """The rival notion of importance: how many recent queries have the object among their k nearest."""
    last = newest(spark, d)
    return knn(spark, d).crossJoin(F.broadcast(last)).filter(F.col("seq") > F.col("last") - W_).groupBy("oid").agg(F.count("*").alias("n"))


ORACLES["rknn_count"] = knn_sql(f"SELECT oid, count(*) AS n FROM km WHERE seq > (SELECT max(seq) FROM q) - {W_} GROUP BY oid")


@query()
def knn_topm(spark, d):
    return continuous(P.contributions(knn(spark, d), T.objects_part(spark, d)), newest(spark, d))


ORACLES["knn_topm"] = knn_sql(", kc AS (SELECT seq, oid, n - rnk + 1 AS num FROM km, nn)", "nn") + "," + RUN.format(c="kc", q="q") + f"SELECT win, pos, oid, num, num / {W_}.0::DOUBLE AS pop FROM tp"


def _timed(spark, d, size, slide=None):
    o, q = base(spark, d)
    q = q.withColumn("w", F.window("ts", size, slide) if slide else F.window("ts", size)).withColumn("seq", F.unix_micros("w.start")).drop("w")
    n = F.broadcast(o.agg(F.count("*").alias("objects")))
    g = L.tile_sums(o, q, M_).groupBy("seq", "oid").agg(F.sum("n").alias("n"), F.sum("s1").alias("s1")).crossJoin(n)
    g = g.select("seq", "oid", F.expr("n * (objects + 1) - s1").alias("num"))
    pos = F.row_number().over(Window.partitionBy("seq").orderBy(F.desc("num"), "oid")).cast("long")
    return g.withColumn("pos", pos).filter(F.col("pos") <= M_).select(F.col("seq").alias("start_us"), "pos", "oid", "num")


@query("c", "q", then=f"SELECT epoch_us(date_trunc('day', ts)) AS start_us, row_number() OVER (PARTITION BY epoch_us(date_trunc('day', ts)) ORDER BY sum(num) DESC, oid) AS pos, oid, CAST(sum(num) AS BIGINT) AS num FROM c JOIN q USING (seq) GROUP BY 1, oid QUALIFY pos <= {M_}")
def time_window_topm(spark, d):
    return _timed(spark, d, "1 day")


@query("c", "q", then=f"SELECT st AS start_us, row_number() OVER (PARTITION BY st ORDER BY num DESC, oid) AS pos, oid, num FROM (SELECT st, oid, CAST(sum(num) AS BIGINT) AS num FROM (SELECT oid, num, unnest([epoch_us(date_trunc('day', ts)), epoch_us(date_trunc('day', ts)) - 86400000000]) AS st FROM c JOIN q USING (seq)) GROUP BY st, oid) QUALIFY pos <= {M_}")
def sliding_time_topm(spark, d):
    return _timed(spark, d, "2 days", "1 day")


def _aggregate(name: str, spark_agg, sql_agg: str):
    def f(spark, d):
        return last_ranked(spark, d).crossJoin(F.broadcast(T.objects_part(spark, d).agg(F.count("*").alias("n")))).groupBy("oid").agg(spark_agg().alias("v"))

    f.__name__ = name
    query("r", "q", "nn", then=f"SELECT oid, {sql_agg} AS v FROM r, nn WHERE seq > (SELECT max(seq) FROM q) - {W_} GROUP BY oid")(f)


_aggregate("agg_sum_rank", lambda: F.sum("rnk"), "CAST(sum(rnk) AS BIGINT)")
_aggregate("agg_borda", lambda: F.sum(F.col("n") - F.col("rnk")), "CAST(sum(n - rnk) AS BIGINT)")
_aggregate("agg_avg_rank", lambda: F.avg("rnk"), "avg(rnk)")
_aggregate("agg_median_rank", lambda: F.expr("percentile(rnk, 0.5)"), "quantile_cont(rnk, 0.5)")
_aggregate("agg_quantile_rank", lambda: F.expr("percentile(rnk, 0.9)"), "quantile_cont(rnk, 0.9)")
_aggregate("agg_majority", lambda: F.sum((F.col("rnk") == 1).cast("long")), "CAST(sum(CASE WHEN rnk = 1 THEN 1 ELSE 0 END) AS BIGINT)")


@query("r", "q", then=f"SELECT a.oid AS winner, b.oid AS loser, count(*) AS wins FROM r a JOIN r b ON a.seq = b.seq AND a.rnk < b.rnk WHERE a.seq > (SELECT max(seq) FROM q) - {W_} GROUP BY a.oid, b.oid")
def pairwise_wins(spark, d):
    r = ranked(spark, d).crossJoin(F.broadcast(newest(spark, d))).filter(F.col("seq") > F.col("last") - W_)
    return _wins(r)


def _wins(r):
    a, b = (r.select("seq", F.col("oid").alias(k), F.col("rnk").alias(f"r{k}")) for k in ("winner", "loser"))
    return a.join(b, "seq").filter("rwinner < rloser").groupBy("winner", "loser").agg(F.count("*").alias("wins"))


@query()
def kemeny_small(spark, d):
    """The order of the top 6 objects that the fewest pairwise preferences contradict, by trying all orders."""
    import itertools

    import pandas as pd

    top = P.topm(last_window(spark, d), 6).select("oid")
    wins = _wins(last_ranked(spark, d).join(F.broadcast(top), "oid"))
    rows = wins.unionByName(top.select(F.col("oid").alias("winner"), F.col("oid").alias("loser"), F.lit(0).cast("long").alias("wins")))

    def best(pdf: pd.DataFrame) -> pd.DataFrame:
        w = {(a, b): n for a, b, n in zip(pdf.winner, pdf.loser, pdf.wins)}
        ids = sorted(set(pdf.winner))
        cost = lambda p: sum(w.get((p[j], p[i]), 0) for i in range(len(p)) for j in range(i + 1, len(p)))
        order = min(itertools.permutations(ids), key=lambda p: (cost(p), p))
        return pd.DataFrame({"pos": range(1, len(order) + 1), "oid": order})

    return rows.withColumn("g", F.lit(1)).groupBy("g").applyInPandas(best, "pos int, oid long")


# Bounds, leaves, index.
def _cells(spark, d):
    o, q = base(spark, d)
    return o, B.ancestors(q).select(*B.CELL).distinct()


@query("ds", then="SELECT lvl, cx, cy, oid, mind2, maxd2 FROM ds")
def cell_distances(spark, d):
    return B.cell_distances(*_cells(spark, d))


@query("rb", then="SELECT lvl, cx, cy, oid, lo_rank, hi_rank FROM rb")
def rank_bounds(spark, d):
    return B.rank_bounds(cell_distances(spark, d)).select(*B.CELL, "oid", "lo_rank", "hi_rank")


@query("vi", then="SELECT lvl, cx, cy, bad FROM vi")
def partition_condition(spark, d):
    return B.violations(B.rank_bounds(cell_distances(spark, d)), SLACK)


def _leaves(spark, d):
    o, q = base(spark, d)
    return B.leaves_for(q, o, SLACK)


@query("lc", then="SELECT x, y, lvl, cx, cy FROM lc")
def leaf_of_query(spark, d):
    return _leaves(spark, d)


@query("lc", then="SELECT x, y, lvl, cx, cy FROM lc")
def leaf_lookup(spark, d):
    leaves = _leaves(spark, d)
    return B.locate(leaves.select("x", "y"), leaves.select(*B.CELL).distinct())


def _list(spark, d):
    o = T.objects_part(spark, d)
    return o, B.rank_list(B.rank_bounds(B.cell_distances(o, _leaves(spark, d).select(*B.CELL).distinct())), BLOCK)


@query("rl", then=f"SELECT lvl, cx, cy, pos, (pos - 1) // {BLOCK} AS blk, oid, lo_rank, hi_rank, mind2 FROM rl")
def rank_list(spark, d):
    return _list(spark, d)[1]


BLK = f"SELECT lvl, cx, cy, (pos - 1) // {BLOCK} AS blk, arg_min(lo_rank, pos) AS first_lo, max(hi_rank) AS max_hi, min(mind2) AS min_d2, min(x) AS xmin, max(x) AS xmax, min(y) AS ymin, max(y) AS ymax, CAST(count(*) AS INT) AS cnt FROM rl JOIN o USING (oid) GROUP BY ALL"


@query("rl", "o", then=BLK)
def rank_blocks(spark, d):
    o, listed = _list(spark, d)
    return B.blocks(listed, o)


@query("rl", then=f"SELECT lvl, cx, cy, pos, oid, lo_rank, mind2 FROM rl WHERE mind2 <= {R_ * R_}")
def rank_list_horizon(spark, d):
    return _list(spark, d)[1].filter(F.col("mind2") <= R_ * R_).select(*B.CELL, "pos", "oid", "lo_rank", "mind2")


@query("rl", then=f"SELECT lvl, cx, cy, oid, (pos - 1) // {BLOCK} AS blk, pos FROM rl")
def locate_entry(spark, d):
    """Each object's block and place by its distance: an as-of join on block minima, then the entry in the block."""
    _, listed = _list(spark, d)
    heads = listed.groupBy(*B.CELL, "blk").agg(F.min(F.struct("mind2", "oid")).alias("k"))
    marks = heads.select(*B.CELL, "k", "blk", F.lit(None).cast("long").alias("oid")).unionByName(listed.select(*B.CELL, F.struct("mind2", "oid").alias("k"), F.lit(None).cast("long").alias("blk"), "oid"))
    found = F.last("blk", True).over(Window.partitionBy(*B.CELL).orderBy("k", F.col("oid").asc_nulls_first()).rowsBetween(Window.unboundedPreceding, 0))
    at = marks.withColumn("blk", found).filter(F.col("oid").isNotNull()).select(*B.CELL, "oid", "blk")
    return at.join(listed.select(*B.CELL, "blk", "oid", "pos"), [*B.CELL, "blk", "oid"])


@query()
def index_size(spark, d):
    _, listed = _list(spark, d)
    return listed.groupBy().agg(F.count("*").alias("n_entries"), F.countDistinct(*B.CELL).alias("n_leaves"), (F.count("*") * 24).alias("bytes"))


# Estimates.
def est(spark, d, slack: int = SLACK):
    o, q = base(spark, d)
    return B.est_contributions(M.range_matches(o, q), q, o, slack)


@query("ec", then=f"SELECT seq, oid, {2 + SLACK} * lo_rank AS est2, num FROM ec")
def est_rank(spark, d):
    return est(spark, d).select("seq", "oid", P.est_rank2("lo_rank", SLACK).alias("est2"), "num")


@query("ec", "q", then=f"SELECT oid, CAST(sum(num) AS BIGINT) AS num, sum(num) / {2 * W_}.0::DOUBLE AS pop FROM ec WHERE seq > (SELECT max(seq) FROM q) - {W_} GROUP BY oid")
def est_popularity(spark, d):
    c = est(spark, d).crossJoin(F.broadcast(newest(spark, d))).filter(F.col("seq") > F.col("last") - W_)
    return c.groupBy("oid").agg(F.sum("num").alias("num")).withColumn("pop", F.col("num") / F.lit(2.0 * W_))


@query()
def approx_topm_batch(spark, d):
    return continuous(est(spark, d).select("seq", "oid", "num"), newest(spark, d)).withColumn("pop", F.col("num") / F.lit(2.0 * W_))


ORACLES["approx_topm_batch"] = run_sql("ec", c="ec", scale=f"{2 * W_}.0")

MODES = {
    "literal": {"by_value": False}, "aging": {"aging": True, "buffer": 10}, "buffer": {"buffer": 10}, "no_block": {"block_level": False},
    "no_object": {"object_level": False}, "no_reuse": {"reuse": False}, "naive_gain": {"naive": True}, "recompute": {"block_level": False, "object_level": False, "reuse": False},
}


def monitors(spark, d, modes, block: int = BLOCK, slack: int = SLACK):
    o, q = base(spark, d)
    n = o.count()
    return R.replay(R.prepare(est(spark, d, slack), q), n, W_, M_, 2 * (n + 1) - (2 + slack), modes, block)


@query()
def approx_monitor_topm(spark, d):
    out = monitors(spark, d, {"aging": MODES["aging"]})
    return out.select("win", F.col("pos").cast("long").alias("pos"), "oid", "num", (F.col("num") / F.lit(2.0 * W_)).alias("pop"))


ORACLES["approx_monitor_topm"] = ORACLES["approx_topm_batch"]


@query()
def monitor_modes_agree(spark, d):
    """For each variant and ablation: windows, windows whose result differs from the literal monitor's, and mean cost."""
    out = monitors(spark, d, MODES)
    per = out.groupBy("monitor", "win").agg(F.array_sort(F.collect_list(F.struct("pos", "oid"))).alias("r"), F.first("opq_validation").alias("v"), F.first("opq_total").alias("t"))
    lit = per.filter("monitor = 'literal'").select("win", F.col("r").alias("r0"))
    return per.join(lit, "win").groupBy("monitor").agg(F.count("*").alias("windows"), F.sum((F.col("r") != F.col("r0")).cast("long")).alias("differ"), F.avg("v").alias("opq_validation"), F.avg("t").alias("opq_total"))


@query()
def shift_outcomes(spark, d):
    """How often a shift is settled by the block threshold, the object threshold, an empty validation, or an update."""
    out = monitors(spark, d, {k: MODES[k] for k in ("literal", "aging")}).select("monitor", "win", "outcome").distinct()
    return out.groupBy("monitor", "outcome").agg(F.count("*").alias("n"))


@query("m", "q", then=f"SELECT seq, count(DISTINCT oid) AS opq FROM (SELECT q.seq, m.oid FROM q LEFT JOIN m ON m.seq = q.seq UNION ALL SELECT m.seq + {W_}, m.oid FROM m WHERE m.seq + {W_} <= (SELECT max(seq) FROM q)) t WHERE seq >= {W_} GROUP BY seq")
def opq_baseline(spark, d, r: int = R_):
    return shift_sizes(*base(spark, d, r), W_)


def shift_sizes(o, q, w: int):
    """(seq, opq): how many objects the new or the expired query of each shift reaches."""
    last = F.broadcast(q.agg(F.max("seq").alias("last")))
    late = q.select((F.col("seq") + w).alias("seq"), "x", "y", "r2", F.lit(0).alias("own")).crossJoin(last).filter("seq <= last").drop("last")
    discs = q.select("seq", "x", "y", "r2", F.lit(1).alias("own")).unionByName(late).filter(F.col("seq") >= w)
    return L.union_sizes(o, discs).filter("own = 1 or n > 0").select("seq", F.col("n").alias("opq"))


@query("r", "ec", then=f"SELECT seq, oid, rnk, lo_rank, hi_rank, {2 + SLACK} * lo_rank - 2 * rnk AS err2, {SLACK} * lo_rank AS bound2 FROM r JOIN ec USING (seq, oid)")
def rank_error(spark, d):
    e = est(spark, d).select("seq", "oid", "lo_rank", "hi_rank")
    return ranked(spark, d).join(e, ["seq", "oid"]).select("seq", "oid", "rnk", "lo_rank", "hi_rank", ((2 + SLACK) * F.col("lo_rank") - 2 * F.col("rnk")).alias("err2"), (SLACK * F.col("lo_rank")).alias("bound2"))


@query("r", "ec", then=f"SELECT count(*) AS n, CAST(sum(CASE WHEN abs({2 + SLACK} * lo_rank - 2 * rnk) > {SLACK} * lo_rank OR rnk < lo_rank OR rnk > hi_rank THEN 1 ELSE 0 END) AS BIGINT) AS violations FROM r JOIN ec USING (seq, oid)")
def error_bound_holds(spark, d):
    e = rank_error(spark, d)
    wrong = (F.abs("err2") > F.col("bound2")) | (F.col("rnk") < F.col("lo_rank")) | (F.col("rnk") > F.col("hi_rank"))
    return e.groupBy().agg(F.count("*").alias("n"), F.sum(wrong.cast("long")).alias("violations"))


def _both(spark, d):
    a = approx_topm_batch(spark, d).select("win", "pos", F.col("oid").alias("a_oid"), F.col("pop").alias("a_pop"))
    return a.join(continuous_topm_count(spark, d).select("win", "pos", "oid", "pop"), ["win", "pos"])


@query()
def approx_ratio(spark, d):
    """Mean over windows and positions of the larger quotient of approximate and exact popularity; positions with a 0 are counted apart."""
    j = _both(spark, d)
    ok = (F.col("a_pop") > 0) & (F.col("pop") > 0)
    ratio = F.when(ok, F.greatest(F.col("a_pop") / F.col("pop"), F.col("pop") / F.col("a_pop")))
    return j.groupBy("win").agg(F.avg(ratio).alias("r"), F.sum((~ok).cast("long")).alias("s")).groupBy().agg(F.round(F.avg("r"), 9).alias("ratio"), F.sum("s").alias("skipped"))


@query()
def overlap_at_k(spark, d):
    """For each m and k, the mean over windows of how many of the approximate top m are in the exact top k (ties by oid), by m and by min(m, k)."""
    ms, ks = (10, 50, 100), tuple(range(10, 201, 10))
    last = newest(spark, d)
    a = continuous(est(spark, d).select("seq", "oid", "num"), last, m=max(ms)).select("win", "oid", F.col("pos").alias("a_pos"))
    e = continuous(contribs(spark, d), last, m=max(ks)).select("win", "oid", F.col("pos").alias("e_pos"))
    # As the exact side lists at least as many objects, every window is in it.
    wins = e.agg(F.count_distinct("win").alias("windows"))
    both = a.join(e, ["win", "oid"]).groupBy("a_pos", "e_pos").agg(F.count("*").alias("n"))
    grid = spark.createDataFrame([(m, k) for m in ms for k in ks], "m int, k int")
    hit = grid.join(F.broadcast(both), (F.col("a_pos") <= F.col("m")) & (F.col("e_pos") <= F.col("k")), "left").groupBy("m", "k").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("hits"))
    mean = lambda by: F.round(F.col("hits") / F.col("windows") / by, 9)
    return hit.crossJoin(F.broadcast(wins)).select("m", "k", mean(F.col("m")).alias("overlap_over_m"), mean(F.least("m", "k")).alias("overlap_over_min_mk"))


@query()
def exact_pruned_topm(spark, d):
    """The monitor's machinery on exact contributions: thresholds, aging bound and validation, no estimates."""
    o, q = base(spark, d)
    n = o.count()
    c = contribs(spark, d).withColumn("o", -F.col("num"))
    out = R.replay(R.prepare(c, q, "o"), n, W_, M_, n, {"exact": {"aging": True, "buffer": 10}}, BLOCK)
    return out.select("win", F.col("pos").cast("long").alias("pos"), "oid", "num", (F.col("num") / F.lit(float(W_))).alias("pop"))


ORACLES["exact_pruned_topm"] = run_sql("c")

GAIN = f"g AS (SELECT seq, oid, CAST(sum(num) AS BIGINT) AS gain FROM (SELECT seq, oid, num FROM ec UNION ALL SELECT seq + {W_}, oid, -num FROM ec) WHERE seq BETWEEN {W_} AND (SELECT max(seq) FROM q) GROUP BY seq, oid)"


def _gains(spark, d):
    e = est(spark, d).select("seq", "oid", "num")
    both = e.unionAll(e.select(F.col("seq") + W_, "oid", -F.col("num"))).crossJoin(F.broadcast(newest(spark, d)))
    return both.filter((F.col("seq") >= W_) & (F.col("seq") <= F.col("last"))).groupBy("seq", "oid").agg(F.sum("num").alias("gain"))


@query()
def object_gain(spark, d):
    """What each object reached by the new or the expired query gains at each shift, doubled."""
    return _gains(spark, d)


@query()
def max_gain_per_shift(spark, d):
    return _gains(spark, d).groupBy("seq").agg(F.greatest(F.max("gain"), F.lit(0)).alias("gain"))


ORACLES["object_gain"] = sql("ec", "q", then="").rstrip() + ", " + GAIN + " SELECT seq, oid, gain FROM g"
ORACLES["max_gain_per_shift"] = sql("ec", "q", then="").rstrip() + ", " + GAIN + " SELECT seq, greatest(max(gain), 0) AS gain FROM g GROUP BY seq"


@query("ec", "q", then=f"SELECT oid, CAST(sum(num) AS BIGINT) AS num FROM ec WHERE seq > (SELECT max(seq) FROM q) - {W_} GROUP BY oid")
def reuse_equals_scratch(spark, d):
    """The newest window's numerators from those of a third of a window ago, by what came and what went since."""
    back = W_ // 3
    e = est(spark, d).select("seq", "oid", "num").crossJoin(F.broadcast(newest(spark, d)))
    age = F.col("last") - F.col("seq")
    old = e.filter((age >= back) & (age < W_ + back)).select("oid", "num", F.lit(1).alias("t"))
    came = e.filter(age < back).select("oid", "num", F.lit(1))
    went = e.filter((age >= W_) & (age < W_ + back)).select("oid", -F.col("num"), F.lit(-1))
    return old.unionAll(came).unionAll(went).groupBy("oid").agg(F.sum("num").alias("num"), F.sum("t").alias("t")).filter("t > 0").drop("t")


@query("ec", "q", then=f"SELECT oid, CAST(sum(num) AS BIGINT) AS num, CAST(sum(lo_rank) AS BIGINT) AS lo_sum FROM ec WHERE seq > (SELECT max(seq) FROM q) - {W_} GROUP BY oid")
def candidate_scratch(spark, d):
    """Every candidate's numerator over all live queries, and the sum that bounds its error."""
    e = est(spark, d).crossJoin(F.broadcast(newest(spark, d))).filter(F.col("seq") > F.col("last") - W_)
    return e.groupBy("oid").agg(F.sum("num").alias("num"), F.sum("lo_rank").alias("lo_sum"))


PAIRS = f"""bk AS MATERIALIZED ({BLK}),
lq AS (SELECT seq, lvl, cx, cy FROM q JOIN lc USING (x, y)),
pr AS (SELECT DISTINCT a.lvl, a.cx, a.cy, b.lvl AS olvl, b.cx AS ocx, b.cy AS ocy FROM lq a JOIN lq b ON a.seq = b.seq + {W_}),
nb AS (SELECT pr.*, blk, first_lo, greatest(abs(xmin - ocx * (1024 >> olvl)), abs(xmax - ocx * (1024 >> olvl)), abs(xmin - ((ocx + 1) * (1024 >> olvl) - 1)), abs(xmax - ((ocx + 1) * (1024 >> olvl) - 1))) AS ax,
  greatest(abs(ymin - ocy * (1024 >> olvl)), abs(ymax - ocy * (1024 >> olvl)), abs(ymin - ((ocy + 1) * (1024 >> olvl) - 1)), abs(ymax - ((ocy + 1) * (1024 >> olvl) - 1))) AS ay FROM pr JOIN bk USING (lvl, cx, cy))
SELECT nb.lvl, nb.cx, nb.cy, nb.olvl, nb.ocx, nb.ocy, nb.blk, {2 + SLACK} * nb.first_lo AS low2, {2 + SLACK} * coalesce(min(ob.first_lo), (SELECT n FROM nn)) AS high2
FROM nb LEFT JOIN bk ob ON ob.lvl = nb.olvl AND ob.cx = nb.ocx AND ob.cy = nb.ocy AND ob.min_d2 > nb.ax * nb.ax + nb.ay * nb.ay
GROUP BY nb.lvl, nb.cx, nb.cy, nb.olvl, nb.ocx, nb.ocy, nb.blk, nb.first_lo"""


@query()
def block_bounds(spark, d):
    """For each pair of new and expired leaf: of each block of the new one, doubled estimates at most (new) and at least (expired).

    The block of the expired leaf's list whose least distance first exceeds the block's greatest one bounds its members' ranks from above.
    """
    o, listed = _list(spark, d)
    blk = B.blocks(listed, o)
    q = T.queries_uniform(spark, d)
    leaf = q.select("seq", "x", "y").join(_leaves(spark, d), ["x", "y"]).select("seq", *B.CELL)
    old = leaf.select((F.col("seq") + W_).alias("seq"), *[F.col(c).alias(f"o{c}") for c in B.CELL])
    pair = leaf.join(old, "seq").select(*B.CELL, "olvl", "ocx", "ocy").distinct()
    pair = lattice.box(pair, "olvl", "ocx", "ocy")
    far = lambda lo, hi, a, b: F.greatest(*[F.abs(F.col(i) - F.col(j)) for i in (lo, hi) for j in (a, b)])
    ax, ay = far("xmin", "xmax", "x0", "x1"), far("ymin", "ymax", "y0", "y1")
    new = pair.join(blk, B.CELL).select(*B.CELL, "olvl", "ocx", "ocy", "blk", "first_lo", (ax * ax + ay * ay).alias("far"))
    heads = blk.select(*[F.col(c).alias(f"o{c}") for c in B.CELL], F.col("first_lo").alias("olo"), "min_d2")
    hit = F.min(F.when(F.col("min_d2") > F.col("far"), F.col("olo")))
    n = F.broadcast(o.agg(F.count("*").alias("n")))
    out = new.join(heads, ["olvl", "ocx", "ocy"]).groupBy(*B.CELL, "olvl", "ocx", "ocy", "blk", "first_lo").agg(hit.alias("hit")).crossJoin(n)
    return out.select(*B.CELL, "olvl", "ocx", "ocy", "blk", ((2 + SLACK) * F.col("first_lo")).alias("low2"), ((2 + SLACK) * F.coalesce("hit", "n")).alias("high2"))


ORACLES["block_bounds"] = sql("rl", "o", "q", "lc", "nn", then="").rstrip() + ", " + PAIRS


@query()
def knn_est_topm(spark, d):
    o, q = base(spark, d)
    c = B.est_contributions(knn(spark, d).drop("rnk"), q, o, SLACK)
    return continuous(c.select("seq", "oid", "num"), newest(spark, d)).withColumn("pop", F.col("num") / F.lit(2.0 * W_))


ORACLES["knn_est_topm"] = knn_sql(f", kc AS MATERIALIZED (SELECT seq, oid, 2 * (n + 1) - {2 + SLACK} * lo_rank AS num FROM km JOIN q USING (seq) JOIN lc USING (x, y) JOIN rl USING (lvl, cx, cy, oid), nn)", "nn", "lc", "rl") + "," + RUN.format(c="kc", q="q") + f"SELECT win, pos, oid, num, num / {2 * W_}.0::DOUBLE AS pop FROM tp"


@query()
def grid_vs_quad_cells(spark, d):
    """Cells of the queries' leaves, against those of the uniform grid that is fine enough for all of them."""
    leaf = _leaves(spark, d)
    return leaf.groupBy().agg(F.countDistinct(*B.CELL).alias("quad_leaves"), F.pow(F.lit(4.0), F.max("lvl")).alias("grid_cells"))


@query()
def quad_leaves_small(spark, d):
    """The eager tree over the facilities as objects, to level 4; cells that would split further are marked."""
    f = T.facilities(spark, d).select(F.col("fid").alias("oid"), "x", "y")
    return B.partition(f, SLACK, max_level=4)


def _sweep(spark, d, modes):
    out = monitors(spark, d, modes).select("monitor", "win", "opq_validation", "opq_total", "outcome").distinct()
    return out.groupBy("monitor").agg(F.count("*").alias("windows"), F.avg("opq_validation").alias("opq_validation"), F.avg("opq_total").alias("opq_total"), F.avg((F.col("outcome").isin("block", "object")).cast("double")).alias("kept"))


@query()
def sweep_window(spark, d):
    return _sweep(spark, d, {f"w{w}": {"w": w, "aging": True, "buffer": 10} for w in (100, 200, 400, 800, 1600)})


@query()
def sweep_m(spark, d):
    return _sweep(spark, d, {f"m{m}": {"m": m, "aging": True, "buffer": 10} for m in (1, 5, 10, 20, 50, 100)})


@query()
def sweep_block_size(spark, d):
    """The number of objects computed doesn't depend on the block size."""
    return _sweep(spark, d, {f"b{b}": {"block": b, "aging": True, "buffer": 10} for b in (32, 64, 128, 256, 512)})


@query()
def sweep_radius(spark, d):
    """Mean number of objects that the exact baseline computes per shift, by radius (1 to 16 % of the side)."""
    out = None
    for r in (10, 20, 41, 82, 164):
        m = opq_baseline(spark, d, r).groupBy().agg(F.lit(r).alias("r"), F.avg("opq").alias("opq"))
        out = m if out is None else out.unionAll(m)
    return out
