"""How much of the work grows with the stream: what must not be matched, ranked or moved."""

import pytest

from georank import catalog
from georank.operators import matching as M


def matched(spark, monkeypatch, sf, name):
    """Queries that each range join of the named query is given."""
    counts, inner = [], M.range_matches

    def spy(objects, queries, *args, **kw):
        counts.append(queries.count())
        return inner(objects, queries, *args, **kw)

    monkeypatch.setattr(M, "range_matches", spy)
    assert catalog.QUERIES[name](spark, sf).count()
    return counts


@pytest.mark.parametrize("name", ["agg_avg_rank", "agg_borda", "agg_majority", "agg_median_rank", "agg_quantile_rank", "agg_sum_rank"])
def test_only_the_newest_window_is_matched(spark, monkeypatch, sf, name):
    counts = matched(spark, monkeypatch, sf, name)
    assert counts and max(counts) <= catalog.W_ < catalog.T.queries_uniform(spark, sf).count()


def test_kemeny_pairs_only_the_top(spark, monkeypatch, sf):
    import itertools

    from georank import catalog_ranks as C

    top = [r.oid for r in C.P.topm(catalog.last_window(spark, sf), 6).collect()]
    won = {(r.winner, r.loser): r.wins for r in C.pairwise_wins(spark, sf).collect()}
    cost = lambda p: sum(won.get((p[j], p[i]), 0) for i in range(6) for j in range(i + 1, 6))
    want = list(min(itertools.permutations(sorted(top)), key=lambda p: (cost(p), p)))
    paired, inner = set(), C._wins
    monkeypatch.setattr(C, "_wins", lambda r: paired.update(x.oid for x in r.collect()) or inner(r))
    assert [r.oid for r in C.kemeny_small(spark, sf).orderBy("pos").collect()] == want
    assert paired and paired <= set(top)


def plan(df) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def test_range_matches_are_not_joined_again(spark, sf):
    assert plan(M.range_matches(*catalog.base(spark, sf))).count("Join [q") == 0


def same_as_sql(spark, sf, name):
    import duckdb

    db = duckdb.connect()
    for t in ("part", "supplier", "events"):
        db.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    plain = lambda rows: sorted(repr(tuple(r)) for r in rows)
    df = catalog.QUERIES[name](spark, sf)
    assert plain(df.collect()) == plain(db.execute(catalog.ORACLES[name]).fetchall())
    return df


@pytest.mark.parametrize("name", ["rank_in_query", "sql_contribution", "rank_shared_ties", "ranked_list_array", "array_ranklist_slice", "contribution"])
def test_lists_are_expanded_where_they_are_made(spark, sf, name):
    """A list's matches go to its queries without a shuffle."""
    text = plan(same_as_sql(spark, sf, name))
    text = text[text.index("Initial Plan") :] if "Initial Plan" in text else text
    assert "FlatMapGroupsInArrow" in text and "Exchange hashpartitioning" not in text[: text.index("FlatMapGroupsInArrow")]


@pytest.mark.parametrize("name", ["rank_in_query", "sql_contribution", "rank_shared_ties", "contribution"])
@pytest.mark.parametrize("most", [1, 50])
def test_a_row_stands_for_few_matches(spark, monkeypatch, sf, name, most):
    """Spark keeps all that is exploded from one row in memory, so lists come in pieces."""
    from georank.operators import lists as L

    monkeypatch.setattr(L, "PIECE", most)
    sizes, inner = [], L.expand
    monkeypatch.setattr(L, "expand", lambda lists, *a, **kw: sizes.append(lists.selectExpr("max(size(seqs) * size(oids))").first()[0]) or inner(lists, *a, **kw))
    same_as_sql(spark, sf, name)
    assert sizes and 0 < max(sizes) <= most


@pytest.mark.parametrize("name", ["rollup_metrics", "grouping_sets_metrics", "cube_metrics", "time_window_topm", "rank_stats", "distinct_touched", "opq_by_radius"])
def test_counts_and_sums_without_matches(spark, monkeypatch, sf, name):
    """What the SQL says, though no match is made a row."""
    monkeypatch.setattr(M, "range_matches", None)
    same_as_sql(spark, sf, name)


def test_sweep_radius_without_matches(spark, monkeypatch, sf):
    from georank import catalog_ranks as C

    small = {r.seq: r.opq for r in C.opq_baseline(spark, sf, 10).collect()}
    monkeypatch.setattr(M, "range_matches", None)
    got = {r.r: r.opq for r in C.sweep_radius(spark, sf).collect()}
    assert sorted(got) == [10, 20, 41, 82, 164] and abs(got[10] - sum(small.values()) / len(small)) < 1e-9


@pytest.mark.parametrize("chunk", [16, 50])
def test_window_tops_in_chunks_equal_intervals(spark, chunk):
    import random

    from georank.operators import lists as L
    from georank.operators import popularity as P

    rnd = random.Random(chunk)
    o = spark.createDataFrame([(i, rnd.randrange(60), rnd.randrange(60)) for i in range(80)], "oid long, x long, y long")
    q = spark.createDataFrame([(i, rnd.randrange(60), rnd.randrange(60), rnd.choice([0, 50, 400])) for i in range(130) if i % 7], "seq long, x long, y long, r2 long")
    c = P.contributions(M.rank_matches(M.range_matches(o, q)), o)
    want = P.continuous_topm(c, 9, 4, q.selectExpr("max(seq) AS last"))
    rows = lambda df: sorted(tuple(r) for r in df.select("win", "pos", "oid", "num").collect())
    assert rows(L.window_tops(o, q, 9, 4, chunk)) == rows(want)


@pytest.mark.parametrize("name", ["topm_skewed", "topm_changes"])
def test_window_tops_without_matches(spark, monkeypatch, sf, name):
    monkeypatch.setattr(M, "range_matches", None)
    same_as_sql(spark, sf, name)


def window_case(spark, seed, side=6):
    """Many objects at few points, many points as far away as others."""
    import random

    rnd = random.Random(seed)
    o = spark.createDataFrame([(i, rnd.randrange(side), rnd.randrange(side)) for i in rnd.sample(range(10_000), 300)], "oid long, x long, y long")
    q = spark.createDataFrame([(i, rnd.randrange(side), rnd.randrange(side), rnd.choice([0, 2, 5, 25])) for i in range(90) if i % 7], "seq long, x long, y long, r2 long")
    return o, q


@pytest.mark.parametrize("m", [1, 4, 30])
def test_window_tops_keep_sums_of_points(spark, m):
    """No sum is kept of each object: chunks get a row for each point."""
    from georank.operators import lists as L
    from georank.operators import popularity as P

    o, q = window_case(spark, m)
    want = P.continuous_topm(P.contributions(M.rank_matches(M.range_matches(o, q)), o), 9, m, q.selectExpr("max(seq) AS last"))
    top = L.window_tops(o, q, 9, m, 16)
    rows = lambda df: sorted(tuple(r) for r in df.select("win", "pos", "oid", "num").collect())
    assert rows(top) == rows(want)
    assert "collect_list(oid" in plan(top)


def test_copies_of_objects_stay_in_proportion(spark):
    """Chunks are longer where there are more objects."""
    from georank.operators import lists as L

    o, q = window_case(spark, 1)
    o = o.selectExpr("explode(sequence(oid, oid + 900000, 10000)) AS oid", "x", "y")
    sizes, inner = [], type(q).groupBy
    type(q).groupBy = lambda self, *keys: (sizes.append(self) if keys == ("tx", "size", "last") else None) or inner(self, *keys)
    try:
        L.window_tops(o, q, 9, 4, 16)
    finally:
        type(q).groupBy = inner
    points, n = o.select("x", "y").distinct().count(), o.count()
    assert n > 16 * 90 and sizes[-1].filter("r2 IS NULL").count() == points


@pytest.mark.parametrize("chunk", [1, 5, 8192])
def test_result_changes_make_the_results_once(spark, chunk):
    import random

    from georank.operators import popularity as P

    rnd = random.Random(chunk)
    lists = {win: rnd.choice([[1, 2], [2, 1], [1], [1, 2, 3]]) for win in range(60) if win % 11}
    top = spark.createDataFrame([(w, k + 1, o) for w, oids in lists.items() for k, o in enumerate(oids)], "win long, pos int, oid long").repartition(3)
    got = P.result_changes(top, chunk)
    assert sorted(r.win for r in got.collect()) == [w for w in lists if lists[w] != lists.get(w - 1)]
    text = plan(got)
    assert "Join" not in text[text.index("Initial Plan") :] if "Initial Plan" in text else "Join" not in text
