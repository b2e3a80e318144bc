"""Safe ranks in set form, measures over parameter grids, and the experiments' sweeps over streams."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import functions as F

from .catalog import M_, ORACLES, QUERIES, R_, RUN, SLACK, W_, B, M, P, R, T, continuous, contribs, newest, query, sql
from .catalog_ranks import MODES, _gains, _list, block_bounds, est, monitors, shift_sizes
from .sources import files

#: Parameter grids of the experiments.
WINDOWS, MS, KS, SLACKS, RADII = (100, 200, 400, 800, 1600), (1, 5, 10, 20, 50, 100), tuple(range(10, 201, 10)), (1, 2, 3, 4, 5), (10, 20, 41, 82, 164)


def union(frames):
    return reduce(lambda a, b: a.unionByName(b), frames)


def tops(c: str, m: int, *names: str, slack: int = SLACK) -> str:
    """SQL of the first m of every window from the contributions c; slack replaces the default in bounds and estimates."""
    text = sql(c, "q", *names, then="").rstrip() + "," + RUN.format(c=c, q="q").replace(f"pos <= {M_}", f"pos <= {m}")
    return text.replace(f"> {SLACK} * lo_rank", f"> {slack} * lo_rank").replace(f"- {2 + SLACK} * lo_rank", f"- {2 + slack} * lo_rank")


# Safe ranks: what a held object's new rank estimate must stay below, from a bound on what any outsider gains.
HELD = f""",
hd AS (SELECT win + 1 AS shift, tp.num - coalesce(a.num, 0) AS minus, tp.num - coalesce(a.num, 0) + coalesce(b.num, 0) AS plus FROM tp
  LEFT JOIN ec a ON a.seq = win + 1 - {W_} AND a.oid = tp.oid LEFT JOIN ec b ON b.seq = win + 1 AND b.oid = tp.oid
  WHERE pos <= {M_} AND win < (SELECT max(seq) FROM q)),
nx AS (SELECT win + 1 AS shift, num FROM tp WHERE pos = {M_ + 1}),
sh AS (SELECT shift, min(minus) AS floor2, min(plus) AS pop2, CAST(greatest(coalesce(max(nx.num), 0), 0) AS BIGINT) AS ub2 FROM hd LEFT JOIN nx USING (shift) GROUP BY shift),
g AS (SELECT seq, oid, CAST(sum(num) AS BIGINT) AS gain FROM (SELECT seq, oid, num FROM ec UNION ALL SELECT seq + {W_}, oid, -num FROM ec) WHERE seq BETWEEN {W_} AND (SELECT max(seq) FROM q) GROUP BY seq, oid)"""


def thresholds(spark, d):
    """Per shift: the m-th value after the expired query left (floor2) and with the new query (pop2), and the best outsider's value before (ub2); all doubled."""
    e = est(spark, d).select("seq", "oid", "num")
    top = continuous(e, newest(spark, d), m=M_ + 1).select((F.col("win") + 1).alias("shift"), "pos", "oid", "num").crossJoin(F.broadcast(newest(spark, d))).filter("shift <= last")
    old = e.select((F.col("seq") + W_).alias("shift"), "oid", F.col("num").alias("lost"))
    new = e.select(F.col("seq").alias("shift"), "oid", F.col("num").alias("won"))
    held = top.join(old, ["shift", "oid"], "left").join(new, ["shift", "oid"], "left")
    minus = F.col("num") - F.coalesce("lost", F.lit(0))
    inside = F.col("pos") <= M_
    return held.groupBy("shift").agg(
        F.min(F.when(inside, minus)).alias("floor2"),
        F.min(F.when(inside, minus + F.coalesce("won", F.lit(0)))).alias("pop2"),
        F.greatest(F.coalesce(F.max(F.when(~inside, F.col("num"))), F.lit(0)), F.lit(0)).alias("ub2"),
    )


def safe_ranks(spark, d, gains):
    """gains: shift, gain. The doubled rank estimate below which a held object can't be overtaken, and whether the shift is settled by value."""
    n = F.broadcast(T.objects_part(spark, d).agg(F.count("*").alias("n")))
    j = thresholds(spark, d).join(gains, "shift").crossJoin(n)
    rank2 = 2 * (F.col("n") + 1) - (F.col("ub2") + F.col("gain") - F.col("floor2"))
    return j.select("shift", "ub2", "floor2", "gain", rank2.alias("safe_rank2"), (F.col("pop2") > F.col("ub2") + F.col("gain")).alias("settled"))


SAFE = " SELECT shift, ub2, floor2, CAST(gain AS BIGINT) AS gain, CAST(2 * (n + 1) - (ub2 + gain - floor2) AS BIGINT) AS safe_rank2, pop2 > ub2 + gain AS settled FROM sh JOIN ({}) gg USING (shift), nn"


@query()
def naive_safe_rank(spark, d):
    """Every outsider may gain the greatest contribution there is."""
    n = T.objects_part(spark, d).agg(F.count("*").alias("n"))
    return safe_ranks(spark, d, thresholds(spark, d).select("shift").crossJoin(F.broadcast(n)).select("shift", (2 * (F.col("n") + 1) - (2 + SLACK)).alias("gain")))


ORACLES["naive_safe_rank"] = tops("ec", M_ + 1, "nn") + HELD + SAFE.format(f"SELECT shift, 2 * (n + 1) - {2 + SLACK} AS gain FROM sh, nn")


@query()
def object_safe_rank(spark, d):
    """The greatest gain of any object, 0 if all lose."""
    g = _gains(spark, d).groupBy(F.col("seq").alias("shift")).agg(F.greatest(F.max("gain"), F.lit(0)).alias("gain"))
    return safe_ranks(spark, d, g)


ORACLES["object_safe_rank"] = tops("ec", M_ + 1, "nn") + HELD + SAFE.format("SELECT seq AS shift, greatest(max(gain), 0) AS gain FROM g GROUP BY seq")

BLOCK_GAIN = f""",
lq AS (SELECT seq, x, y, lvl, cx, cy FROM q JOIN lc USING (x, y)),
bk AS MATERIALIZED (SELECT lvl, cx, cy, (pos - 1) // 128 AS blk, arg_min(lo_rank, pos) AS first_lo, min(mind2) AS min_d2, min(x) AS xmin, max(x) AS xmax, min(y) AS ymin, max(y) AS ymax FROM rl JOIN o USING (oid) GROUP BY ALL),
pr AS (SELECT DISTINCT a.lvl, a.cx, a.cy, b.lvl AS olvl, b.cx AS ocx, b.cy AS ocy FROM lq a JOIN lq b ON a.seq = b.seq + {W_}),
nb AS (SELECT pr.*, blk, first_lo, greatest(abs(xmin - ocx * (1024 >> olvl)), abs(xmax - ocx * (1024 >> olvl)), abs(xmin - ((ocx + 1) * (1024 >> olvl) - 1)), abs(xmax - ((ocx + 1) * (1024 >> olvl) - 1))) AS ax,
  greatest(abs(ymin - ocy * (1024 >> olvl)), abs(ymax - ocy * (1024 >> olvl)), abs(ymin - ((ocy + 1) * (1024 >> olvl) - 1)), abs(ymax - ((ocy + 1) * (1024 >> olvl) - 1))) AS ay FROM pr JOIN bk USING (lvl, cx, cy)),
bb AS MATERIALIZED (SELECT nb.lvl, nb.cx, nb.cy, nb.olvl, nb.ocx, nb.ocy, nb.blk, {2 + SLACK} * nb.first_lo AS low2, {2 + SLACK} * coalesce(min(ob.first_lo), (SELECT n FROM nn)) AS high2 FROM nb
  LEFT JOIN bk ob ON ob.lvl = nb.olvl AND ob.cx = nb.ocx AND ob.cy = nb.ocy AND ob.min_d2 > nb.ax * nb.ax + nb.ay * nb.ay GROUP BY nb.lvl, nb.cx, nb.cy, nb.olvl, nb.ocx, nb.ocy, nb.blk, nb.first_lo),
bg AS (SELECT a.seq AS shift, bb.blk,
  CASE WHEN greatest(xmin - a.x, 0, a.x - xmax) ** 2 + greatest(ymin - a.y, 0, a.y - ymax) ** 2 <= {R_ * R_} THEN 2 * (n + 1) - low2 ELSE 0 END
  - CASE WHEN greatest(abs(xmin - b.x), abs(xmax - b.x)) ** 2 + greatest(abs(ymin - b.y), abs(ymax - b.y)) ** 2 <= {R_ * R_} THEN greatest(2 * (n + 1) - high2, 0) ELSE 0 END AS gain
  FROM lq a JOIN lq b ON a.seq = b.seq + {W_} JOIN bb ON bb.lvl = a.lvl AND bb.cx = a.cx AND bb.cy = a.cy AND bb.olvl = b.lvl AND bb.ocx = b.cx AND bb.ocy = b.cy
  JOIN bk ON bk.lvl = a.lvl AND bk.cx = a.cx AND bk.cy = a.cy AND bk.blk = bb.blk, nn)"""


@query()
def block_gain(spark, d):
    """Per shift and block of the new query's list, doubled: the most that a member can gain by the new query, less what all members surely lose by the expired one."""
    o, listed = _list(spark, d)
    q = T.queries_uniform(spark, d).select("seq", "x", "y")
    places = q.join(listed_leaves(spark, d), ["x", "y"])
    old = places.select((F.col("seq") + W_).alias("seq"), F.col("x").alias("ox"), F.col("y").alias("oy"), *[F.col(c).alias(f"o{c}") for c in B.CELL])
    blk = B.blocks(listed, o).select(*B.CELL, "blk", "xmin", "xmax", "ymin", "ymax")
    j = places.join(old, "seq").join(block_bounds(spark, d), [*B.CELL, "olvl", "ocx", "ocy"]).join(blk, [*B.CELL, "blk"])
    off = lambda lo, hi, v: F.greatest(F.col(lo) - F.col(v), F.lit(0), F.col(v) - F.col(hi))
    far = lambda lo, hi, v: F.greatest(F.abs(F.col(lo) - F.col(v)), F.abs(F.col(hi) - F.col(v)))
    square = lambda f, x, y: f("xmin", "xmax", x) * f("xmin", "xmax", x) + f("ymin", "ymax", y) * f("ymin", "ymax", y)
    n = F.broadcast(o.agg((2 * (F.count("*") + 1)).alias("whole")))
    won = F.when(square(off, "x", "y") <= R_ * R_, F.col("whole") - F.col("low2")).otherwise(0)
    lost = F.when(square(far, "ox", "oy") <= R_ * R_, F.greatest(F.col("whole") - F.col("high2"), F.lit(0))).otherwise(0)
    return j.crossJoin(n).select(F.col("seq").alias("shift"), "blk", (won - lost).cast("long").alias("gain"))


def listed_leaves(spark, d):
    return B.leaves_for(T.queries_uniform(spark, d), T.objects_part(spark, d), SLACK)


ORACLES["block_gain"] = sql("ec", "rl", "o", "q", "lc", "nn", then="").rstrip() + BLOCK_GAIN + " SELECT shift, blk, CAST(gain AS BIGINT) AS gain FROM bg"


@query()
def block_safe_rank(spark, d):
    """The greatest gain of any block, 0 if all lose."""
    g = block_gain(spark, d).groupBy("shift").agg(F.greatest(F.max("gain"), F.lit(0)).alias("gain"))
    return safe_ranks(spark, d, g)


ORACLES["block_safe_rank"] = tops("ec", M_ + 1, "rl", "o", "lc", "nn") + HELD + BLOCK_GAIN + SAFE.format("SELECT shift, greatest(max(gain), 0) AS gain FROM bg GROUP BY shift")


@query()
def block_gain_dominates(spark, d):
    """Shifts, and those at which some object gains more than the best block is said to (must be none)."""
    b = block_gain(spark, d).groupBy("shift").agg(F.greatest(F.max("gain"), F.lit(0)).alias("block"))
    g = _gains(spark, d).groupBy(F.col("seq").alias("shift")).agg(F.greatest(F.max("gain"), F.lit(0)).alias("object"))
    return b.join(g, "shift").groupBy().agg(F.count("*").alias("shifts"), F.sum((F.col("object") > F.col("block")).cast("long")).alias("violations"))


ORACLES["block_gain_dominates"] = sql("ec", "q", then="").rstrip() + f" SELECT count(DISTINCT seq) AS shifts, 0::BIGINT AS violations FROM (SELECT seq FROM ec UNION ALL SELECT seq + {W_} FROM ec) WHERE seq BETWEEN {W_} AND (SELECT max(seq) FROM q)"


@query()
def validation_superset(spark, d):
    """Per shift with new result objects: how many, and how many of them the bound (best outsider's value and own gain) would have missed (must be 0)."""
    e = est(spark, d).select("seq", "oid", "num")
    top = continuous(e, newest(spark, d)).select("win", "oid")
    first = F.lit(W_ - 1)
    new = top.filter(F.col("win") > first).join(top.select((F.col("win") + 1).alias("win"), "oid"), ["win", "oid"], "left_anti").withColumnRenamed("win", "shift")
    j = new.join(thresholds(spark, d), "shift").join(_gains(spark, d).withColumnRenamed("seq", "shift"), ["shift", "oid"], "left")
    missed = (F.col("ub2") + F.coalesce("gain", F.lit(0)) < F.col("pop2")).cast("long")
    return j.groupBy("shift").agg(F.count("*").alias("entrants"), F.sum(missed).alias("missed"))


ORACLES["validation_superset"] = tops("ec", M_ + 1, "nn") + HELD + f""",
en AS (SELECT a.win AS shift, a.oid FROM tp a LEFT JOIN tp b ON b.win = a.win - 1 AND b.oid = a.oid AND b.pos <= {M_} WHERE a.pos <= {M_} AND a.win >= {W_} AND b.oid IS NULL)
SELECT shift, count(*) AS entrants, CAST(sum(CASE WHEN ub2 + coalesce(gain, 0) < pop2 THEN 1 ELSE 0 END) AS BIGINT) AS missed FROM en JOIN sh USING (shift) LEFT JOIN g ON g.seq = en.shift AND g.oid = en.oid GROUP BY shift"""


def differing(spark, d, modes):
    """Windows of each named monitor, and those whose result differs from the set form's."""
    lists = lambda df, *by: df.groupBy(*by).agg(F.array_sort(F.collect_list(F.struct(F.col("pos").cast("int").alias("pos"), "oid", "num"))).alias("r"))
    want = lists(continuous(est(spark, d).select("seq", "oid", "num"), newest(spark, d)), "win").withColumnRenamed("r", "want")
    got = lists(monitors(spark, d, modes), "monitor", "win")
    return got.join(want, "win", "left").groupBy("monitor").agg(F.count("*").alias("windows"), F.sum(F.coalesce(F.col("r") != F.col("want"), F.lit(True)).cast("long")).alias("differ"))


def differing_sql(names) -> str:
    """Every monitor gives a result for each window, and none differs."""
    return sql("q", then=f"SELECT unnest({list(names)}) AS monitor, (SELECT max(seq) + 1 - {W_ - 1} FROM q) AS windows, 0::BIGINT AS differ")


COMPARED = ("literal", "aging", "buffer", "no_block", "no_object", "no_reuse", "naive_gain", "recompute")


@query()
def monitor_modes_differ(spark, d):
    """Windows of each monitor variant and ablation, and those whose result differs from the set form's (must be none)."""
    return differing(spark, d, {k: MODES[k] for k in COMPARED})


ORACLES["monitor_modes_differ"] = differing_sql(COMPARED)

# Quality of the estimates over m, k, slack.
RATIO = "greatest(a.num / {a}.0::DOUBLE / (e.num / {e}.0::DOUBLE), e.num / {e}.0::DOUBLE / (a.num / {a}.0::DOUBLE))"


def ratios(spark, d, slack: int = SLACK, m: int = M_):
    """Per window and place the larger quotient of approximate and exact popularity, null where either isn't positive."""
    last = newest(spark, d)
    a = continuous(est(spark, d, slack).select("seq", "oid", "num"), last, m=m).select("win", "pos", (F.col("num") / F.lit(2.0 * W_)).alias("a"))
    e = continuous(contribs(spark, d), last, m=m).select("win", "pos", F.col("pop").alias("e"))
    return a.join(e, ["win", "pos"]).select("win", "pos", F.when((F.col("a") > 0) & (F.col("e") > 0), F.greatest(F.col("a") / F.col("e"), F.col("e") / F.col("a"))).alias("ratio"))


def ratio_sql(m: int, slack: int = SLACK) -> str:
    a, e = (f"({tops(c, m, slack=slack)} SELECT win, pos, num FROM tp)" for c in ("ec", "c"))
    r = RATIO.format(a=2 * W_, e=W_)
    return f"SELECT win, pos, CASE WHEN a.num > 0 AND e.num > 0 THEN {r} END AS ratio FROM {a} a JOIN {e} e USING (win, pos)"


ORACLES["approx_ratio"] = f"SELECT round(avg(r), 9) AS ratio, CAST(sum(s) AS BIGINT) AS skipped FROM (SELECT win, avg(ratio) AS r, sum(CASE WHEN ratio IS NULL THEN 1 ELSE 0 END) AS s FROM ({ratio_sql(M_)}) GROUP BY win)"


@query()
def ratio_by_m(spark, d):
    """The approximation ratio, averaged over the first m places and then over windows, for each m."""
    grid = spark.createDataFrame([(m,) for m in MS], "m int")
    per = ratios(spark, d, m=max(MS)).join(F.broadcast(grid), F.col("pos") <= F.col("m")).groupBy("m", "win").agg(F.avg("ratio").alias("r"))
    return per.groupBy("m").agg(F.round(F.avg("r"), 8).alias("ratio"))


ORACLES["ratio_by_m"] = f"SELECT CAST(m AS INT) AS m, round(avg(r), 8) AS ratio FROM (SELECT m, win, avg(ratio) AS r FROM ({ratio_sql(max(MS))}) JOIN (SELECT unnest({list(MS)}) AS m) ON pos <= m GROUP BY m, win) GROUP BY m"

OVERLAP_M = (10, 50, 100)
ORACLES["overlap_at_k"] = f"""WITH b AS MATERIALIZED (SELECT a.pos AS ap, e.pos AS ep, count(*) AS n FROM ({tops("ec", 100)} SELECT win, pos, oid FROM tp) a JOIN ({tops("c", 200)} SELECT win, pos, oid FROM tp) e USING (win, oid) GROUP BY a.pos, e.pos),
ws AS (SELECT count(DISTINCT win) AS windows FROM ({tops("c", 1)} SELECT win FROM tp)),
g AS (SELECT CAST(m AS INT) AS m, CAST(k AS INT) AS k FROM (SELECT unnest({list(OVERLAP_M)}) AS m), (SELECT unnest({list(KS)}) AS k)),
h AS (SELECT m, k, coalesce(sum(n), 0) AS hits FROM g LEFT JOIN b ON ap <= m AND ep <= k GROUP BY m, k)
SELECT m, k, round(hits / windows / m, 9) AS overlap_over_m, round(hits / windows / least(m, k), 9) AS overlap_over_min_mk FROM h, ws"""


@query()
def slack_tradeoff(spark, d):
    """For each slack: leaves of the queries' places, the index's entries and bytes (rank, id and distance of 8 bytes each), and the ratio at m 10."""
    out = []
    for s in SLACKS:
        o, q = T.objects_part(spark, d), T.queries_uniform(spark, d)
        leaf = B.leaves_for(q, o, s).select(*B.CELL).distinct().agg(F.count("*").alias("n_leaves"))
        size = leaf.crossJoin(o.agg(F.count("*").alias("n"))).select("n_leaves", (F.col("n_leaves") * F.col("n")).alias("n_entries"), (24 * F.col("n_leaves") * F.col("n")).alias("bytes"))
        r = ratios(spark, d, s).groupBy("win").agg(F.avg("ratio").alias("r")).agg(F.round(F.avg("r"), 8).alias("ratio"))
        out.append(size.crossJoin(r).select(F.lit(s).alias("slack"), "n_leaves", "n_entries", "bytes", "ratio"))
    return union(out)


def _slack_sql(s: int) -> str:
    leaves = sql("lc", "nn", then="SELECT count(*) AS n_leaves, any_value(n) AS n FROM (SELECT DISTINCT lvl, cx, cy FROM lc), nn").replace(f"> {SLACK} * lo_rank", f"> {s} * lo_rank")
    return f"SELECT {s} AS slack, n_leaves, n_leaves * n AS n_entries, 24 * n_leaves * n AS bytes, round((SELECT avg(r) FROM (SELECT win, avg(ratio) AS r FROM ({ratio_sql(M_, s)}) GROUP BY win)), 8) AS ratio FROM ({leaves})"


ORACLES["slack_tradeoff"] = " UNION ALL ".join(_slack_sql(s) for s in SLACKS)

# Sweeps of the exact baseline's cost: objects whose popularity changes, per shift.
STREAMS = {"uniform": T.queries_uniform, "skewed": T.queries_skewed, "checkin": lambda spark, d, r=R_: T.queries_checkin(spark, d)}


def _opq(spark, d, name: str, w: int, r: int = R_):
    q = STREAMS[name](spark, d, r)
    per = shift_sizes(T.objects_part(spark, d), q, w)
    return per.agg(F.count("*").alias("shifts"), F.coalesce(F.sum("opq"), F.lit(0)).alias("opq")).select(F.lit(name).alias("stream"), F.lit(w).alias("w"), F.lit(r).alias("r"), "shifts", "opq")


def _opq_sql(name: str, w: int, r: int = R_) -> str:
    q, r2 = {"uniform": ("q", r * r), "skewed": ("qs", r * r), "checkin": ("qc", "r2")}[name]
    rows = f"SELECT seq, oid FROM {q} q0 JOIN o ON (o.x - q0.x) * (o.x - q0.x) + (o.y - q0.y) * (o.y - q0.y) <= {r2}"
    return sql(q, "o", then="").rstrip() + f""", mm AS MATERIALIZED ({rows}),
pp AS (SELECT seq, count(DISTINCT oid) AS opq FROM (SELECT s.seq, mm.oid FROM {q} s LEFT JOIN mm ON mm.seq = s.seq UNION ALL SELECT seq + {w}, oid FROM mm WHERE seq + {w} <= (SELECT max(seq) FROM {q})) WHERE seq >= {w} GROUP BY seq)
SELECT '{name}' AS stream, {w} AS w, {r} AS r, count(*) AS shifts, CAST(coalesce(sum(opq), 0) AS BIGINT) AS opq FROM pp"""


def _opq_sweep(name: str, doc: str, settings) -> None:
    def run(spark, d):
        return union([_opq(spark, d, *s) for s in settings])

    run.__name__, run.__doc__ = name, doc
    QUERIES[name] = run
    ORACLES[name] = " UNION ALL ".join(f"SELECT * FROM ({_opq_sql(*s)})" for s in settings)


_opq_sweep("opq_by_window", "Objects that the baseline computes over all shifts, by window, on the uniform and the skewed stream.", [(n, w) for n in ("uniform", "skewed") for w in WINDOWS])
_opq_sweep("opq_by_window_checkin", "The same on the check-in stream, whose queries have radii of their own.", [("checkin", w) for w in WINDOWS[:4]])
_opq_sweep("opq_by_radius", "The same by radius (1 to 16 % of the side), on both streams.", [(n, W_, r) for n in ("uniform", "skewed") for r in RADII])


# Sweeps of the monitor's cost beside the baseline's.
def _costs(out):
    per = out.select("monitor", "win", "opq_validation", "opq_total", "outcome").distinct()
    return per.groupBy("monitor").agg(F.count("*").alias("windows"), F.avg("opq_validation").alias("opq_validation"), F.avg("opq_total").alias("opq_total"), F.avg(F.col("outcome").isin("block", "object").cast("double")).alias("kept"))


@query()
def sweep_slack(spark, d):
    """Mean objects that the monitor computes per shift, by slack."""
    return union([_costs(monitors(spark, d, {f"slack{s}": MODES["aging"]}, slack=s)) for s in SLACKS])


@query()
def sweep_window_skewed(spark, d):
    """By window on the skewed stream, exact contributions."""
    return _costs(exact_monitors(spark, d, "skewed", {f"w{w}": {"w": w} | MODES["aging"] for w in WINDOWS}))


@query()
def sweep_window_checkin(spark, d):
    """By window on the check-in stream, exact contributions."""
    return _costs(exact_monitors(spark, d, "checkin", {f"w{w}": {"w": w} | MODES["aging"] for w in WINDOWS[:4]}))


@query()
def sweep_m_checkin(spark, d):
    return _costs(exact_monitors(spark, d, "checkin", {f"m{m}": {"m": m} | MODES["aging"] for m in MS}))


def exact_monitors(spark, d, stream: str, modes):
    o, q = T.objects_part(spark, d), STREAMS[stream](spark, d)
    c = P.contributions(M.rank_matches(M.range_matches(o, q)), o).withColumn("o", -F.col("num"))
    n = o.count()
    return R.replay(R.prepare(c, q, "o"), n, W_, M_, n, modes)


@query()
def runtime_breakdown(spark, d):
    """Seconds per 1,000 shifts of the monitor by block size: in all, and in block thresholds, object thresholds and validation. Times differ from run to run."""
    out = monitors(spark, d, {f"b{b}": {"block": b} | MODES["aging"] for b in (32, 64, 128, 256, 512)}).filter("outcome <> 'first'")
    per = out.select("monitor", "win", "t_block", "t_object", "t_valid").distinct()
    return per.groupBy("monitor").agg(F.count("*").alias("shifts"), *[(1000 * F.avg(c)).alias(c) for c in ("t_block", "t_object", "t_valid")], (1000 * F.avg(F.col("t_block") + F.col("t_object") + F.col("t_valid"))).alias("t_all"))


# File formats.
def _round_trip(fmt: str) -> None:
    def run(spark, d):
        return files.round_trip(T.objects_part(spark, d), fmt)

    run.__name__, run.__doc__ = f"{fmt}_round_trip", f"The objects written as {fmt} and read with their schema."
    QUERIES[run.__name__] = run
    ORACLES[run.__name__] = sql("o", then="SELECT oid, x, y FROM o")


for _fmt in ("csv", "json", "orc"):
    _round_trip(_fmt)
