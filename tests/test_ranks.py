"""Worked examples, decisions on ties, and properties of bounds, windows and monitors."""

import random

from pyspark.sql import functions as F

from georank.operators import bounds as B
from georank.operators import matching as M
from georank.operators import popularity as P
from georank.operators.monitor import Monitor, reached

F1 = [(1, 65, 65), (2, 56, 65), (3, 65, 85), (4, 78, 65), (5, 90, 65), (6, 110, 65), (7, 65, 120), (8, 5, 65)]
WANT = {1: (0, 50, 1, 2), 2: (16, 221, 1, 3), 3: (225, 650, 3, 5), 4: (64, 349, 2, 4), 5: (400, 925, 4, 5), 6: (1600, 2525, 6, 7), 7: (2500, 3625, 6, 8), 8: (3025, 4250, 7, 8)}


def box_bounds(spark, objects, x0, y0, x1, y1):
    from georank.functions.lattice import max_d2, min_d2

    o = spark.createDataFrame(objects, "oid long, x long, y long")
    box = [F.lit(v).cast("long") for v in (x0, y0, x1, y1)]
    d = o.select(F.lit(0).alias("lvl"), F.lit(0).cast("long").alias("cx"), F.lit(0).cast("long").alias("cy"), "oid", min_d2("x", "y", *box).alias("mind2"), max_d2("x", "y", *box).alias("maxd2"))
    return B.rank_bounds(d)


def test_bounds_of_worked_example(spark):
    got = {r.oid: (r.mind2, r.maxd2, r.lo_rank, r.hi_rank) for r in box_bounds(spark, F1, 60, 60, 70, 70).collect()}
    assert got == WANT


def test_rank_list_order(spark):
    rows = B.rank_list(box_bounds(spark, F1, 60, 60, 70, 70), 2).orderBy("pos").collect()
    assert [r.oid for r in rows] == [1, 2, 4, 3, 5, 6, 7, 8]
    assert [r.blk for r in rows] == [0, 0, 1, 1, 2, 2, 3, 3]


def test_ties_by_id(spark):
    objects = [(3, 5, 5), (1, 5, 5), (2, 5, 5), (5, 5, 8), (4, 8, 5)]
    got = {r.oid: (r.lo_rank, r.hi_rank) for r in box_bounds(spark, objects, 5, 5, 5, 5).collect()}
    assert got == {i: (i, i) for i in range(1, 6)}


def test_split_condition(spark):
    rows = [(0, 0, 0, 1, 10, 20), (1, 0, 0, 1, 100, 120)]
    b = spark.createDataFrame(rows, "lvl int, cx long, cy long, oid long, lo_rank long, hi_rank long")
    assert {r.lvl: r.bad for r in B.violations(b, 1).collect()} == {0: 0, 1: 0}
    assert {r.lvl: r.bad for r in B.violations(b.withColumn("hi_rank", F.col("hi_rank") + 1), 1).collect()} == {0: 1, 1: 0}


def test_popularity_by_hand(spark):
    ranked = spark.createDataFrame([(0, 1, 1), (0, 2, 2), (1, 2, 1)], "seq long, oid long, rnk long")
    pop = P.window_popularity(P.contributions(ranked, 4), 1, 2)
    assert {r.oid: (r.num, r.pop) for r in pop.collect()} == {1: (4, 2.0), 2: (7, 3.5)}


def test_eager_leaves_contain_lazy_ones(spark):
    o = spark.createDataFrame([(1, 1, 1), (2, 6, 2), (3, 3, 7), (4, 7, 7)], "oid long, x long, y long")
    q = spark.createDataFrame([(1, 2), (6, 6), (3, 3)], "x long, y long")
    eager = {tuple(r)[:3] for r in B.partition(o, 1, bits=3).collect()}
    lazy = {(r.lvl, r.cx, r.cy) for r in B.leaves_for(q, o, 1, bits=3).collect()}
    assert lazy <= eager


def test_grid_and_ring_equal_naive(spark):
    rnd = random.Random(5)
    o = spark.createDataFrame([(i, rnd.randrange(1024), rnd.randrange(1024)) for i in range(150)], "oid long, x long, y long")
    q = spark.createDataFrame([(i, rnd.randrange(1024), rnd.randrange(1024), rnd.choice([0, 900, 40000])) for i in range(40)], "seq long, x long, y long, r2 long")
    rows = lambda df: sorted(map(tuple, df.collect()))
    assert rows(M.range_matches(o, q)) == rows(M.range_matches(o, q, "naive"))
    assert rows(M.knn_matches(o, q, 7)) == rows(M.knn_matches(o, q, 7, "sort"))


def brute(stream, w, m):
    for i in range(w - 1, len(stream)):
        total = {}
        for q in stream[i - w + 1 : i + 1]:
            for o, c in q:
                total[o] = total.get(o, 0) + c
        yield sorted(total.items(), key=lambda e: (-e[1], e[0]))[:m]


def test_monitor_variants_equal_recomputation():
    rnd = random.Random(11)
    for trial in range(60):
        n, w, m = rnd.randint(3, 30), rnd.randint(1, 8), rnd.randint(1, 5)
        stream = [[(o, n - i) for i, o in enumerate(rnd.sample(range(n), rnd.randint(0, n // 2)))] for _ in range(60)]
        for mode in ({}, {"aging": True, "buffer": 3}, {"block_level": False}, {"object_level": False}, {"reuse": False}, {"naive": True}, {"retain": 0}, {"retain": 2 * w // 3}, {"retain": w + 5}):
            mon = Monitor(n, w, m, n, rnd.choice([1, 2, 4]), **mode)
            qs = [reached([o for o, _ in q], [c for _, c in q], mon.block) for q in stream]
            got = [mon.start(qs[:w])] + [mon.step(q)[0] for q in qs[w:]]
            assert got == list(brute(stream, w, m)), (trial, mode)


def test_expiry_and_gain_zero_entrants():
    for stream, want in (([[1], [1], [2], [2]], [1, 1, 2]), ([[1], [2], []], [1, 2])):
        mon = Monitor(4, 2, 1, 4)
        qs = [reached(q, [4] * len(q), 2) for q in stream]
        got = [mon.start(qs[:2])] + [mon.step(q)[0] for q in qs[2:]]
        assert [r[0][0] for r in got] == want


def test_continuous_equals_brute_force(spark):
    rnd = random.Random(3)
    stream = [[(o, 20 - i) for i, o in enumerate(rnd.sample(range(20), rnd.randint(0, 6)))] for _ in range(70)]
    c = spark.createDataFrame([(s, o, n) for s, q in enumerate(stream) for o, n in q], "seq long, oid long, num long")
    last = spark.createDataFrame([(69,)], "last long")
    rows = P.continuous_topm(c, 7, 4, last, epoch=8).orderBy("win", "pos").collect()
    got = {}
    for r in rows:
        got.setdefault(r.win, []).append((r.oid, r.num))
    assert [got.get(i, []) for i in range(6, 70)] == list(brute(stream, 7, 4))


def test_overlap_at_every_m_and_k_equals_brute_force(spark, sf):
    from georank import catalog
    from georank import catalog_ranks as C

    def tops(rows, m):
        by, out, sums, touched = {}, {}, {}, {}
        for seq, oid, num in rows:
            by.setdefault(seq, []).append((oid, num))
        for seq in range(last + 1):
            for at, sign in ((seq, 1), (seq - catalog.W_, -1)):
                for oid, num in by.get(at, ()):
                    sums[oid] = sums.get(oid, 0) + sign * num
                    touched[oid] = touched.get(oid, 0) + sign
            if seq >= catalog.W_ - 1:
                out[seq] = [oid for _, oid in sorted((-sums[o], o) for o in sums if touched[o])[:m]]
        return out

    last = catalog.newest(spark, sf).first()["last"]
    read = lambda df: [tuple(r) for r in df.select("seq", "oid", "num").collect()]
    a, e = tops(read(C.est(spark, sf)), 100), tops(read(catalog.contribs(spark, sf)), 200)
    got = {(r.m, r.k): (r.overlap_over_m, r.overlap_over_min_mk) for r in C.overlap_at_k(spark, sf).collect()}
    assert set(got) == {(m, k) for m in (10, 50, 100) for k in range(10, 201, 10)}
    for (m, k), (by_m, by_min) in got.items():
        hits = sum(len(set(a[w][:m]) & set(e[w][:k])) for w in e) / len(e)
        assert abs(by_m - hits / m) < 1e-8 and abs(by_min - hits / min(m, k)) < 1e-8


def test_sweep_radius_is_the_baselines_mean_per_shift(spark, sf):
    from georank import catalog
    from georank import catalog_ranks as C

    got = {r.r: r.opq for r in C.sweep_radius(spark, sf).collect()}
    assert sorted(got) == [10, 20, 41, 82, 164]
    for radius in (10, 41):
        o, q = catalog.base(spark, sf, radius)
        reach = {}
        for r in M.range_matches(o, q).collect():
            reach.setdefault(r.seq, set()).add(r.oid)
        shifts = [len(reach.get(s, set()) | reach.get(s - catalog.W_, set())) for s in range(catalog.W_, q.count())]
        assert abs(got[radius] - sum(shifts) / len(shifts)) < 1e-9
