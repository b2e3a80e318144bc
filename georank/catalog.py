"""All queries of the engine by name, with the SQL that gives the same rows where there is such SQL.

Streams and objects are whole tables. Defaults of the experiments: window 400, m 10, radius 41 of 1,024 (4 %), slack 3, blocks of 128.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .functions import lattice
from .operators import bounds as B
from .operators import lists as L
from .operators import matching as M
from .operators import popularity as P
from .plans import replay as R
from .sources import tables as T

FLAGSHIP = "continuous_topm_count"
QUERIES: dict = {}
ORACLES: dict[str, str] = {}
W_, M_, R_, SLACK, BLOCK = 400, 10, 41, 3, 128

CTES = {
    "pb": "SELECT p_partkey AS oid, CAST(round(p_retailprice * 100) AS BIGINT) AS c, CAST(p_size AS BIGINT) AS s FROM part",
    "o": "SELECT oid, (c - lo) * 1023 // span AS x, (s - 1) * 1023 // 49 AS y FROM pb, (SELECT min(c) AS lo, greatest(max(c) - min(c), 1) AS span FROM pb)",
    "oo": "SELECT o_orderkey AS oid, CAST(round(o_totalprice * 100) AS BIGINT) * 65535 // 50000000 AS x, CAST(date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS BIGINT) * 65535 // 2405 AS y FROM orders",
    "oe": "SELECT vec_id AS oid, CAST(floor((greatest(-0.6::DOUBLE, least(0.6::DOUBLE, CAST(embedding[1] AS DOUBLE))) + 0.6::DOUBLE) * 1023 / 1.2::DOUBLE) AS BIGINT) AS x, CAST(floor((greatest(-0.6::DOUBLE, least(0.6::DOUBLE, CAST(embedding[2] AS DOUBLE))) + 0.6::DOUBLE) * 1023 / 1.2::DOUBLE) AS BIGINT) AS y FROM embeddings",
    "f": "SELECT s_suppkey - (SELECT min(s_suppkey) FROM supplier) AS fid, (s_suppkey * 389 + 17) % 1024 AS x, (CAST(round(s_acctbal * 100) AS BIGINT) + 100000) * 1024 // 1100000 AS y FROM supplier",
    "e": "SELECT event_id AS seq, ts, user_id, event_type, value, CAST(json_extract_string(props, '$.k') AS BIGINT) AS pk, (SELECT count(*) FROM supplier) AS n FROM events",
    "q": "SELECT seq, ts, x, y FROM e JOIN f ON fid = (user_id * 100 + pk) % n",
    "qs": "SELECT seq, ts, x, y FROM e JOIN f ON fid = least(n - 1, CAST(round(value * 100) AS BIGINT) * n // 50000)",
    "qe": "SELECT seq, ts, pk * 1023 // 99 AS x, least(1023, CAST(round(value * 100) AS BIGINT) * 1023 // 50000) AS y FROM e",
    "ci": "SELECT o_custkey AS usr, l_shipdate AS ts, o.x, o.y FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN o ON o.oid = l_partkey WHERE l_quantity >= 49",
    "cu": "SELECT usr, max(ts) AS ts, count(*) AS c, CAST(sum(x) AS BIGINT) // count(*) AS x, CAST(sum(y) AS BIGINT) // count(*) AS y FROM ci GROUP BY usr",
    "cr": "SELECT cu.usr, cu.ts, cu.c, cu.x, cu.y, max((ci.x - cu.x) * (ci.x - cu.x) + (ci.y - cu.y) * (ci.y - cu.y)) AS own FROM cu JOIN ci ON ci.usr = cu.usr GROUP BY ALL",
    "qc": "SELECT CAST(row_number() OVER (ORDER BY ts, usr) - 1 AS BIGINT) AS seq, ts, x, y, coalesce(first_value(CASE WHEN c > 1 THEN own END IGNORE NULLS) OVER (ORDER BY usr ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING), (SELECT arg_min(own, usr) FROM cr WHERE c > 1), 0) AS r2 FROM cr",
    "pl": "SELECT DISTINCT x, y FROM q",
    "pm": f"SELECT pl.x, pl.y, oid, (o.x - pl.x) * (o.x - pl.x) + (o.y - pl.y) * (o.y - pl.y) AS d2 FROM pl, o WHERE (o.x - pl.x) * (o.x - pl.x) + (o.y - pl.y) * (o.y - pl.y) <= {R_ * R_}",
    "m": "SELECT seq, oid, d2 FROM q JOIN pm USING (x, y)",
    "r": "SELECT seq, oid, d2, CAST(row_number() OVER (PARTITION BY seq ORDER BY d2, oid) AS BIGINT) AS rnk FROM m",
    "nn": "SELECT count(*) AS n FROM o",
    "c": "SELECT seq, oid, n - rnk + 1 AS num FROM r, nn",
    "pop": f"SELECT oid, CAST(sum(num) AS BIGINT) AS num, sum(num) / {W_}.0::DOUBLE AS pop FROM c WHERE seq > (SELECT max(seq) FROM q) - {W_} GROUP BY oid",
    "lv": "SELECT CAST(unnest(range(0, 11)) AS INT) AS lvl",
    "up": "SELECT x, y, lvl, x >> (10 - lvl) AS cx, y >> (10 - lvl) AS cy FROM pl, lv",
    "cl": "SELECT DISTINCT lvl, cx, cy, cx * (1024 >> lvl) AS x0, cy * (1024 >> lvl) AS y0, (cx + 1) * (1024 >> lvl) - 1 AS x1, (cy + 1) * (1024 >> lvl) - 1 AS y1 FROM up",
    "cd": "SELECT lvl, cx, cy, oid, greatest(x0 - x, 0, x - x1) ** 2 AS a, greatest(y0 - y, 0, y - y1) ** 2 AS b, greatest(abs(x - x0), abs(x - x1)) ** 2 AS u, greatest(abs(y - y0), abs(y - y1)) ** 2 AS v FROM cl, o",
    "ds": "SELECT lvl, cx, cy, oid, CAST(a + b AS BIGINT) AS mind2, CAST(u + v AS BIGINT) AS maxd2 FROM cd",
    "mk": "SELECT *, mind2 AS d, 0 AS far FROM ds UNION ALL SELECT *, maxd2, 1 FROM ds",
    "mw": "SELECT *, coalesce(sum(far) OVER w, 0) AS fars, coalesce(sum(1 - far) OVER w, 0) AS nears FROM mk WINDOW w AS (PARTITION BY lvl, cx, cy ORDER BY d, oid, far ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)",
    "rb": "SELECT lvl, cx, cy, oid, mind2, maxd2, CAST(max(CASE WHEN far = 0 THEN fars + 1 END) AS BIGINT) AS lo_rank, CAST(max(CASE WHEN far = 1 THEN nears END) AS BIGINT) AS hi_rank FROM mw GROUP BY ALL",
    "vi": f"SELECT lvl, cx, cy, CAST(sum(CASE WHEN hi_rank - lo_rank > {SLACK} * lo_rank THEN 1 ELSE 0 END) AS BIGINT) AS bad FROM rb GROUP BY ALL",
    "lf": "SELECT x, y, min(lvl) AS lvl FROM up JOIN vi USING (lvl, cx, cy) WHERE bad = 0 GROUP BY x, y",
    "lc": "SELECT x, y, lvl, x >> (10 - lvl) AS cx, y >> (10 - lvl) AS cy FROM lf",
    "rl": f"SELECT lvl, cx, cy, row_number() OVER (PARTITION BY lvl, cx, cy ORDER BY mind2, oid) AS pos, oid, lo_rank, hi_rank, mind2 FROM rb JOIN (SELECT DISTINCT lvl, cx, cy FROM lc) USING (lvl, cx, cy)",
    "ec": f"SELECT seq, oid, 2 * (n + 1) - {2 + SLACK} * lo_rank AS num, lo_rank, hi_rank FROM m JOIN q USING (seq) JOIN lc USING (x, y) JOIN rl USING (lvl, cx, cy, oid), nn",
}
NEEDS = {"o": ["pb"], "q": ["e", "f"], "qs": ["e", "f"], "qe": ["e"], "ci": ["o"], "cu": ["ci"], "cr": ["cu", "ci"], "qc": ["cr"], "pl": ["q"], "pm": ["pl", "o"], "m": ["q", "pm"], "r": ["m"], "nn": ["o"], "c": ["r", "nn"], "pop": ["c", "q"], "up": ["pl", "lv"], "cl": ["up"], "cd": ["cl", "o"], "ds": ["cd"], "mk": ["ds"], "mw": ["mk"], "rb": ["mw"], "vi": ["rb"], "lf": ["up", "vi"], "lc": ["lf"], "rl": ["rb", "lc"], "ec": ["m", "q", "lc", "rl", "nn"]}


def sql(*names: str, then: str) -> str:
    """`then` after the named common table expressions and all that they need, in order."""
    need: set[str] = set()
    todo = list(names)
    while todo:
        k = todo.pop()
        if k not in need:
            need.add(k)
            todo += NEEDS.get(k, [])
    once = {"rb", "m", "c", "r", "ds", "vi", "q", "o", "ec"}
    return "WITH " + ",\n".join(f"{k} AS {'MATERIALIZED ' if k in once else ''}({v})" for k, v in CTES.items() if k in need) + "\n" + then


def query(*names: str, then: str | None = None):
    """Register a query under its function's name, with its SQL if `then` is given."""

    def add(f):
        QUERIES[f.__name__] = f
        if then:
            ORACLES[f.__name__] = sql(*names, then=then) if names else then
        return f

    return add


def base(spark: SparkSession, sf_dir: str, r: int = R_):
    return T.objects_part(spark, sf_dir), T.queries_uniform(spark, sf_dir, r)


def ranked(spark: SparkSession, sf_dir: str) -> DataFrame:
    o, q = base(spark, sf_dir)
    return M.rank_matches(M.range_matches(o, q))


def listed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ranked lists of the places; all places' queries ride along."""
    return L.place_lists(*base(spark, sf_dir))


def expanded(spark: SparkSession, sf_dir: str, ties: str = "total") -> DataFrame:
    """Ranked matches of all queries, of the lists' pieces."""
    return L.expand(L.place_lists(*base(spark, sf_dir), most=L.PIECE), ties)


def contribs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return P.contributions(ranked(spark, sf_dir), T.objects_part(spark, sf_dir))


def newest(spark: SparkSession, sf_dir: str, name: str = "last") -> DataFrame:
    return T.queries_uniform(spark, sf_dir).agg(F.max("seq").alias(name))


def last_ranked(spark: SparkSession, sf_dir: str, w: int = W_) -> DataFrame:
    """Ranked matches of the newest window. Its end is read from the stream, in the plan; only its queries are matched and ranked."""
    o, q = base(spark, sf_dir)
    q = q.crossJoin(F.broadcast(newest(spark, sf_dir))).filter(F.col("seq") > F.col("last") - w)
    return M.rank_matches(M.range_matches(o, q))


def last_window(spark: SparkSession, sf_dir: str, w: int = W_) -> DataFrame:
    """The newest window's popularity."""
    c = P.contributions(last_ranked(spark, sf_dir, w), T.objects_part(spark, sf_dir))
    return c.groupBy("oid").agg(F.sum("num").alias("num")).withColumn("pop", F.col("num") / F.lit(float(w)))


def continuous(c: DataFrame, last: DataFrame, w: int = W_, m: int = M_) -> DataFrame:
    return P.continuous_topm(c, w, m, last).select("win", F.col("pos").cast("long").alias("pos"), "oid", "num", "pop")


#: Every window's values by running sums of contributions that come and go.
RUN = f"""
dl AS (SELECT oid, tm, sum(d) AS d, sum(t) AS t FROM (SELECT oid, seq AS tm, num AS d, 1 AS t FROM {{c}} UNION ALL SELECT oid, seq + {W_}, -num, -1 FROM {{c}}) GROUP BY oid, tm),
iv AS (SELECT oid, tm AS since, lead(tm, 1, (SELECT max(seq) + 1 FROM {{q}})) OVER w AS until, sum(d) OVER (w ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS num, sum(t) OVER (w ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS t FROM dl WINDOW w AS (PARTITION BY oid ORDER BY tm)),
wv AS (SELECT oid, CAST(num AS BIGINT) AS num, unnest(range(greatest(since, {W_ - 1}), least(until, (SELECT max(seq) + 1 FROM {{q}})))) AS win FROM iv WHERE t > 0),
tp AS (SELECT win, row_number() OVER (PARTITION BY win ORDER BY num DESC, oid) AS pos, oid, num FROM wv QUALIFY pos <= {M_})
"""


def run_sql(*names: str, c: str = "c", q: str = "q", scale: str = f"{W_}.0", then: str | None = None) -> str:
    head = sql(*names, q, then="")
    return head.rstrip() + "," + RUN.format(c=c, q=q) + (then or f"SELECT win, pos, oid, num, num / {scale}::DOUBLE AS pop FROM tp")


from . import catalog_operators, catalog_ranks, catalog_measures, catalog_variants  # noqa: E402,F401
