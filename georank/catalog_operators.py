"""Queries for the surrounding operators: scans, joins, aggregates, windows, set operations, scalars, SQL and user-defined functions."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from .catalog import R_, W_, B, L, M, P, T, base, contribs, expanded, lattice, listed, newest, query, ranked


@query("o", then="SELECT oid, x, y, x * 1024 + y AS code FROM o")
def project_lattice(spark, d):
    return T.objects_part(spark, d).withColumn("code", F.col("x") * 1024 + F.col("y"))


@query(then="SELECT p_partkey, p_retailprice, p_size FROM part")
def scan_objects(spark, d):
    return T.read_table(spark, d, "part").select("p_partkey", "p_retailprice", "p_size")


@query("o", then="SELECT oid, x, y FROM o WHERE x BETWEEN 100 AND 600 AND y BETWEEN 200 AND 800")
def filter_box(spark, d):
    return T.objects_part(spark, d).filter(F.col("x").between(100, 600) & F.col("y").between(200, 800))


@query(then="SELECT event_id FROM events WHERE event_type IN ('view', 'click') AND regexp_matches(event_type, '^[cv]') AND value IS NOT NULL")
def filter_event_type(spark, d):
    e = T.read_table(spark, d, "events")
    return e.filter(F.col("event_type").isin("view", "click") & F.col("event_type").rlike("^[cv]") & F.col("value").isNotNull()).select("event_id")


@query(then="SELECT l_partkey, epoch_us(min(l_shipdate)) AS first_us FROM lineitem GROUP BY l_partkey")
def dedup_first_sale(spark, d):
    li = T.read_table(spark, d, "lineitem").select("l_partkey", F.col("l_shipdate").cast("timestamp").alias("t"))
    first = F.row_number().over(Window.partitionBy("l_partkey").orderBy("t"))
    return li.withColumn("k", first).filter("k = 1").select("l_partkey", F.unix_micros("t").alias("first_us"))


@query("e", then="SELECT c_mktsegment, count(*) AS n FROM e JOIN customer ON c_custkey = user_id GROUP BY c_mktsegment")
def join_user_dim(spark, d):
    e, c = T.read_table(spark, d, "events"), T.read_table(spark, d, "customer")
    return e.join(c, e["user_id"] == c["c_custkey"]).groupBy("c_mktsegment").agg(F.count("*").alias("n"))


@query("q", "f", then="SELECT coalesce(a.fid, b.fid) AS fid, coalesce(n, 0) AS n FROM f a FULL JOIN (SELECT fid, count(*) AS n FROM f JOIN q USING (x, y) GROUP BY fid) b ON a.fid = b.fid")
def join_full_counts(spark, d):
    f, q = T.facilities(spark, d), T.queries_uniform(spark, d)
    n = f.join(q, ["x", "y"]).groupBy("fid").agg(F.count("*").alias("n"))
    return f.select("fid").join(n, "fid", "full").select("fid", F.coalesce("n", F.lit(0)).alias("n"))


@query("m", "o", then="SELECT oid FROM o WHERE oid IN (SELECT oid FROM m)")
def touched_objects(spark, d):
    o, q = base(spark, d)
    return o.select("oid").join(M.range_matches(o, q), "oid", "left_semi")


@query("m", "o", then="SELECT oid FROM o WHERE oid NOT IN (SELECT oid FROM m)")
def untouched_objects(spark, d):
    o, q = base(spark, d)
    return o.select("oid").join(M.range_matches(o, q), "oid", "left_anti")


@query("c", "q", then=f"SELECT q.seq AS win, count(*) AS n FROM q JOIN c ON c.seq BETWEEN q.seq - {W_ - 1} AND q.seq GROUP BY q.seq")
def interval_lifetime(spark, d):
    """Live contributions at each arrival: an interval join by buckets of the window's length with a residual test."""
    q = T.queries_uniform(spark, d).select(F.col("seq").alias("win"))
    b = q.withColumn("b", F.explode(F.array(F.expr(f"win div {W_}"), F.expr(f"win div {W_} - 1"))))
    per = contribs(spark, d).groupBy("seq").agg(F.count("*").alias("k")).withColumn("b", F.expr(f"seq div {W_}"))
    return b.join(per, "b").filter((F.col("seq") <= F.col("win")) & (F.col("seq") > F.col("win") - W_)).groupBy("win").agg(F.sum("k").alias("n"))


@query("e", then="SELECT a.seq, max(b.seq) AS before FROM e a JOIN e b ON b.user_id = a.user_id AND b.ts < a.ts AND b.event_type = 'purchase' WHERE a.event_type = 'error' GROUP BY a.seq")
def asof_event(spark, d):
    e = T.read_table(spark, d, "events").select("event_id", "user_id", "ts", "event_type")
    last = F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), True).over(Window.partitionBy("user_id").orderBy("ts").rowsBetween(Window.unboundedPreceding, -1))
    return e.withColumn("before", last).filter("event_type = 'error' and before is not null").select(F.col("event_id").alias("seq"), "before")


@query("q", then=f"SELECT a.seq, b.seq AS expired FROM q a JOIN q b ON a.seq = b.seq + {W_}")
def expired_pair(spark, d):
    q = T.queries_uniform(spark, d).select("seq")
    return q.join(q.select((F.col("seq") + W_).alias("seq"), F.col("seq").alias("expired")), "seq")


@query("cl", then="SELECT CAST(lvl + 1 AS INT) AS lvl, 2 * cx + i AS cx, 2 * cy + j AS cy FROM cl, (VALUES (0), (1)) a(i), (VALUES (0), (1)) b(j)")
def split_children(spark, d):
    return B.split(B.ancestors(T.queries_uniform(spark, d)).select(*B.CELL).distinct())


@query("m", then="SELECT seq // 100 AS b, count(DISTINCT oid) AS n FROM m GROUP BY 1")
def distinct_touched(spark, d):
    o, q = base(spark, d)
    discs = q.select(F.expr("seq div 100").alias("seq"), "x", "y", "r2", F.lit(1).alias("own")).distinct()
    return L.union_sizes(o, discs, 500).filter("n > 0").select(F.col("seq").alias("b"), "n")


@query()
def distinct_touched_approx(spark, d):
    return M.range_matches(*base(spark, d)).groupBy(F.expr("seq div 100").alias("b")).agg(F.approx_count_distinct("oid", 0.02).alias("n"))


@query("r", then="SELECT seq, array_to_string(list(oid ORDER BY rnk), ',') AS oids FROM r GROUP BY seq")
def ranked_list_array(spark, d):
    # A list is joined once per place; queries that reach nothing have no row.
    g = listed(spark, d).filter(F.size("oids") > 0).select("seqs", F.array_join(F.col("oids").cast("array<string>"), ",").alias("oids"))
    return g.select(F.explode("seqs").alias("seq"), "oids")


def _metrics(spark, d):
    e = T.read_table(spark, d, "events")
    return contribs(spark, d).join(e.select(F.col("event_id").alias("seq"), "event_type", F.expr("user_id % 4").alias("tenant")), "seq")


def _query_metrics(spark, d):
    """Per query that reaches k of n objects: k as reached, and the sum of its contributions n, n - 1, ..., n - k + 1."""
    o, q = base(spark, d)
    k = L.place_counts(o, q).crossJoin(F.broadcast(o.agg(F.count("*").alias("objects"))))
    k = k.select("x", "y", "r2", "reached", F.expr("reached * objects - reached * (reached - 1) div 2").alias("num"))
    e = T.read_table(spark, d, "events").select(F.col("event_id").alias("seq"), "event_type", F.expr("user_id % 4").alias("tenant"))
    return q.join(k, ["x", "y", "r2"]).join(e, "seq")


def _grouped(name: str, how: str, make):
    def f(spark, d):
        return make(_query_metrics(spark, d)).agg(F.coalesce(F.sum("reached"), F.lit(0)).alias("n"), F.sum("num").alias("num"))

    f.__name__ = name
    query("c", "e", then=f"SELECT event_type, user_id % 4 AS tenant, count(*) AS n, CAST(sum(num) AS BIGINT) AS num FROM c JOIN e USING (seq) GROUP BY {how}")(f)


_grouped("rollup_metrics", "ROLLUP (event_type, user_id % 4)", lambda x: x.rollup("event_type", "tenant"))
_grouped("cube_metrics", "CUBE (event_type, user_id % 4)", lambda x: x.cube("event_type", "tenant"))
_grouped("grouping_sets_metrics", "GROUPING SETS ((event_type), (user_id % 4))", lambda x: x.groupingSets([["event_type"], ["tenant"]], "event_type", "tenant"))


@query("r", then="SELECT oid, count(*) AS n, CAST(max(rnk) AS BIGINT) AS worst, round(stddev_samp(rnk), 6) AS sd, arg_max(seq, (rnk, seq)) AS worst_seq FROM r GROUP BY oid")
def rank_stats(spark, d):
    """Tiles give each object's count and sums of ranks and of their squares; the deviation comes from these, which are exact."""
    g = L.tile_stats(*base(spark, d)).groupBy("oid").agg(F.sum("n").alias("n"), F.max("worst").alias("worst"), F.sum("s1").alias("s1"), F.sum("s2").alias("s2"), F.max_by("worst_seq", F.struct("worst", "worst_seq")).alias("worst_seq"))
    wide = lambda c: F.col(c).cast("decimal(19,0)")
    var = (wide("n") * wide("s2") - wide("s1") * wide("s1")).cast("double") / F.col("n") / (F.col("n") - 1)
    return g.select("oid", "n", "worst", F.round(F.when(F.col("n") > 1, F.sqrt(var)), 6).alias("sd"), "worst_seq")


@query("c", "e", then="SELECT user_id % 4 AS tenant, count(*) FILTER (event_type = 'view') AS view, count(*) FILTER (event_type = 'click') AS click FROM c JOIN e USING (seq) GROUP BY 1")
def pivot_radius(spark, d):
    return _metrics(spark, d).groupBy("tenant").pivot("event_type", ["view", "click"]).agg(F.count(F.lit(1))).fillna(0)


@query("m", then="SELECT seq, oid, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(4) OVER v AS nt, percent_rank() OVER w AS pr FROM m WINDOW w AS (PARTITION BY seq ORDER BY d2), v AS (PARTITION BY seq ORDER BY d2, oid)")
def rank_variants(spark, d):
    w, v = Window.partitionBy("seq").orderBy("d2"), Window.partitionBy("seq").orderBy("d2", "oid")
    return M.range_matches(*base(spark, d)).select("seq", "oid", F.rank().over(w).cast("long").alias("rk"), F.dense_rank().over(w).cast("long").alias("dr"), F.ntile(4).over(v).cast("long").alias("nt"), F.percent_rank().over(w).alias("pr"))


@query("c", then="SELECT oid, seq, CAST(sum(num) OVER (PARTITION BY oid ORDER BY seq ROWS BETWEEN 9 PRECEDING AND CURRENT ROW) AS BIGINT) AS num FROM c")
def rows_frame_pop(spark, d):
    return contribs(spark, d).select("oid", "seq", F.sum("num").over(Window.partitionBy("oid").orderBy("seq").rowsBetween(-9, 0)).alias("num"))


@query("c", then=f"SELECT oid, seq, count(*) OVER (PARTITION BY oid ORDER BY seq RANGE BETWEEN {W_ - 1} PRECEDING AND CURRENT ROW) AS n FROM c")
def range_frame_count(spark, d):
    return contribs(spark, d).select("oid", "seq", F.count("*").over(Window.partitionBy("oid").orderBy("seq").rangeBetween(-(W_ - 1), 0)).alias("n"))


def _two(spark, d):
    """Objects reached in the newest window and in the one before it."""
    m = M.range_matches(*base(spark, d)).crossJoin(F.broadcast(newest(spark, d)))
    return m.filter(F.col("seq") > F.col("last") - W_).select("oid"), m.filter((F.col("seq") <= F.col("last") - W_) & (F.col("seq") > F.col("last") - 2 * W_)).select("oid")


NOW, PAST = (f"SELECT oid FROM m WHERE seq > (SELECT max(seq) FROM q) - {W_}", f"SELECT oid FROM m WHERE seq <= (SELECT max(seq) FROM q) - {W_} AND seq > (SELECT max(seq) FROM q) - {2 * W_}")


@query("m", "q", then=f"{NOW} EXCEPT {PAST}")
def entrants(spark, d):
    a, b = _two(spark, d)
    return a.subtract(b)


@query("m", "q", then=f"{PAST} EXCEPT {NOW}")
def leavers(spark, d):
    a, b = _two(spark, d)
    return b.subtract(a)


@query("m", "q", then=f"{NOW} INTERSECT {PAST}")
def keepers(spark, d):
    a, b = _two(spark, d)
    return a.intersect(b)


@query("q", "qs", then="SELECT seq, x, y, 'U' AS stream FROM q UNION ALL SELECT seq, x, y, 'S' FROM qs")
def union_streams(spark, d):
    u, s = T.queries_uniform(spark, d), T.queries_skewed(spark, d)
    return u.select("seq", "x", "y", F.lit("U").alias("stream")).unionAll(s.select("seq", "x", "y", F.lit("S")))


KEY = " + ".join(f"((x >> {i}) & 1) * {1 << 2 * i} + ((y >> {i}) & 1) * {2 << 2 * i}" for i in range(10))


@query("o", then=f"SELECT oid, {KEY} AS qk FROM o")
def quadkey(spark, d):
    return T.objects_part(spark, d).select("oid", lattice.quadkey("x", "y").alias("qk"))


@query("o", then=f"SELECT oid, substr(lpad(CAST({KEY} AS VARCHAR), 8, '0'), 1, 4) || '/' || substr(lpad(CAST({KEY} AS VARCHAR), 8, '0'), 5, 4) AS name FROM o")
def quadkey_string(spark, d):
    key = F.lpad(lattice.quadkey("x", "y").cast("string"), 8, "0")
    return T.objects_part(spark, d).select("oid", F.concat_ws("/", F.substring(key, 1, 4), F.substring(key, 5, 4)).alias("name"))


@query("cu", then="SELECT usr AS user, date_diff('day', CAST(ts AS DATE), CAST((SELECT max(ts) FROM cu) AS DATE)) AS days, epoch_us(date_trunc('month', ts)) AS month_us FROM cu")
def checkin_recency(spark, d):
    u = T.checkins(spark, d).groupBy("user").agg(F.max("ts").alias("ts"))
    last = F.broadcast(u.agg(F.max("ts").alias("last")))
    return u.crossJoin(last).select("user", F.datediff("last", "ts").cast("long").alias("days"), F.unix_micros(F.date_trunc("month", "ts")).alias("month_us"))


@query("r", then="SELECT seq, CAST(sum(oid) AS BIGINT) AS s, count(*) AS n FROM r WHERE rnk BETWEEN 2 AND 4 GROUP BY seq")
def array_ranklist_slice(spark, d):
    part = F.slice("oids", 2, 3)
    return listed(spark, d).select("seqs", F.aggregate(part, F.lit(0).cast("long"), lambda a, x: a + x).alias("s"), F.size(part).cast("long").alias("n")).filter("n > 0").select(F.explode("seqs").alias("seq"), "s", "n")


@query("c", "nn", then="SELECT seq, oid, num FROM c, nn WHERE num > n - 3")
def map_contribs(spark, d):
    n = F.broadcast(T.objects_part(spark, d).agg(F.count("*").alias("n")))
    g = contribs(spark, d).groupBy("seq").agg(F.map_from_entries(F.collect_list(F.struct("oid", "num"))).alias("m")).crossJoin(n)
    return g.select("seq", F.explode(F.map_filter("m", lambda k, v: v > F.col("n") - 3)).alias("oid", "num"))


@query("e", then="SELECT seq, pk FROM e")
def json_props_location(spark, d):
    e = T.read_table(spark, d, "events")
    return e.select(F.col("event_id").alias("seq"), F.from_json("props", "k long")["k"].alias("pk"))


@query("q", then="SELECT seq FROM q WHERE seq * 2654435761 % 1000 < 100")
def hash_sample(spark, d):
    """A reproducible tenth of the queries: sampling is the feature here."""
    return T.queries_uniform(spark, d).filter(F.expr("seq * 2654435761L % 1000 < 100")).select("seq")


@query("e", then="SELECT user_id, epoch_us(min(ts)) AS start_us, count(*) AS n FROM (SELECT *, sum(CASE WHEN b IS NULL OR epoch_us(ts) - epoch_us(b) >= 86400000000 THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts) AS s FROM (SELECT *, lag(ts) OVER (PARTITION BY user_id ORDER BY ts) AS b FROM e)) GROUP BY user_id, s")
def session_users(spark, d):
    e = T.read_table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return e.groupBy("user_id", F.session_window("ts", "1 day").alias("w")).agg(F.count("*").alias("n")).select("user_id", F.unix_micros("w.start").alias("start_us"), "n")


@query("r", "nn", then="SELECT seq, oid, n - rnk + 1 AS num FROM r, nn")
def sql_contribution(spark, d):
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION popularity_contribution(n BIGINT, r BIGINT) RETURNS BIGINT RETURN n - r + 1")
    expanded(spark, d).createOrReplaceTempView("georank_ranked")
    T.objects_part(spark, d).createOrReplaceTempView("georank_objects")
    return spark.sql("SELECT seq, oid, popularity_contribution(n, rnk) AS num FROM georank_ranked, (SELECT count(*) AS n FROM georank_objects)")


@query("m", "o", then="SELECT oid FROM o WHERE EXISTS (SELECT 1 FROM m WHERE m.oid = o.oid AND m.d2 < 400)")
def sql_exists(spark, d):
    o, q = base(spark, d)
    o.createOrReplaceTempView("georank_objects")
    M.range_matches(o, q).createOrReplaceTempView("georank_matches")
    return spark.sql("SELECT oid FROM georank_objects o WHERE EXISTS (SELECT 1 FROM georank_matches m WHERE m.oid = o.oid AND m.d2 < 400)")


@query("c", "q", then=f"SELECT oid, CAST(sum(num) AS BIGINT) AS num FROM c WHERE seq > (SELECT max(seq) FROM q) - {W_} GROUP BY oid ORDER BY num DESC, oid LIMIT 10")
def sql_topm(spark, d):
    contribs(spark, d).createOrReplaceTempView("georank_contribs")
    newest(spark, d).createOrReplaceTempView("georank_last")
    return spark.sql("SELECT oid, sum(num) AS num FROM georank_contribs, georank_last WHERE seq > last - :w GROUP BY oid ORDER BY num DESC, oid LIMIT 10", args={"w": W_})


@query("r", "nn", then="SELECT oid, CAST(sum(n - rnk) AS BIGINT) AS score FROM r, nn GROUP BY oid")
def udaf_borda(spark, d):
    from pyspark.sql.functions import PandasUDFType

    borda_score = F.pandas_udf(lambda rnk, n: int((n - rnk).sum()), "long", PandasUDFType.GROUPED_AGG)
    n = F.broadcast(T.objects_part(spark, d).agg(F.count("*").alias("n")))
    return ranked(spark, d).crossJoin(n).groupBy("oid").agg(borda_score("rnk", "n").alias("score"))


@query("up", then="SELECT x, y, lvl, cx, cy FROM up")
def udtf_ancestors(spark, d):
    from pyspark.sql.functions import udtf

    @udtf(returnType="lvl int, cx bigint, cy bigint")
    class AncestorsOf:
        def eval(self, x: int, y: int):
            for lvl in range(11):
                yield lvl, x >> (10 - lvl), y >> (10 - lvl)

    spark.udtf.register("ancestors_of", AncestorsOf)
    T.queries_uniform(spark, d).select("x", "y").distinct().createOrReplaceTempView("georank_places")
    return spark.sql("SELECT p.x, p.y, a.lvl, a.cx, a.cy FROM georank_places p, LATERAL ancestors_of(p.x, p.y) a")
