"""The count window in streaming state equals recomputation for any cut into micro-batches; repeats and late rows go."""

import random

from georank.streaming import windows as S


def test_count_window_equals_batch(spark, tmp_path):
    rnd = random.Random(9)
    stream = [[(o, 15 - i) for i, o in enumerate(rnd.sample(range(15), rnd.randint(0, 5)))] for _ in range(40)]
    rows = [("a", s, [o for o, _ in q], [c for _, c in q]) for s, q in enumerate(stream)]
    at, k = 0, 0
    while at < len(rows):
        n = rnd.randint(1, 9)
        spark.createDataFrame(rows[at : at + n], "monitor string, seq long, oids array<long>, nums array<long>").coalesce(1).write.parquet(str(tmp_path / "in" / f"b={k:03d}"))
        at, k = at + n, k + 1
    src = spark.readStream.schema("monitor string, seq long, oids array<long>, nums array<long>").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in" / "*"))
    q = S.count_window_topm(src, 6, 3).writeStream.format("memory").queryName("topm_stream").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    q.awaitTermination(120)
    got = {}
    for r in sorted(spark.table("topm_stream").collect()):
        got.setdefault(r.win, []).append((r.oid, r.num))
    for i in range(5, 40):
        total = {}
        for qy in stream[i - 5 : i + 1]:
            for o, c in qy:
                total[o] = total.get(o, 0) + c
        assert got.get(i, []) == sorted(total.items(), key=lambda e: (-e[1], e[0]))[:3]


def test_repeats_go(spark, tmp_path):
    spark.createDataFrame([(1, 0), (1, 1), (2, 2)], "seq long, s long").selectExpr("seq", "timestamp_seconds(1704067200 + s) as ts").write.parquet(str(tmp_path / "in"))
    src = S.source(spark, str(tmp_path / "in"), "seq long, ts timestamp")
    q = S.on_time(src).writeStream.format("memory").queryName("once_stream").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    q.awaitTermination(120)
    assert sorted(r.seq for r in spark.table("once_stream").collect()) == [1, 2]


def test_stream_joins_and_sink(spark, tmp_path):
    """A stream against a table equals the batch join; two streams pair within the time given; the sink keeps the newest window once a batch."""
    from georank.operators import matching as M
    from georank.streaming import joins as J

    rnd = random.Random(3)
    objects = spark.createDataFrame([(i, rnd.randrange(300), rnd.randrange(300)) for i in range(80)], "oid long, x long, y long")
    queries = [(i, 1704067200 + 60 * i, rnd.randrange(300), rnd.randrange(300), 900) for i in range(20)]
    q = spark.createDataFrame(queries, "seq long, t long, x long, y long, r2 long").selectExpr("seq", "timestamp_seconds(t) as ts", "x", "y", "r2", "seq % 3 as k")
    q.write.parquet(str(tmp_path / "q"))
    src = lambda: S.source(spark, str(tmp_path / "q"), "seq long, ts timestamp, x long, y long, r2 long, k long")

    def drained(df, name):
        w = df.writeStream.format("memory").queryName(name).option("checkpointLocation", str(tmp_path / name)).trigger(availableNow=True).start()
        w.awaitTermination(120)
        return spark.table(name).collect()

    got = {(r.seq, r.oid, r.d2) for r in drained(J.match_stream(src(), objects), "matched")}
    assert got == {(r.seq, r.oid, r.d2) for r in M.range_matches(objects, q).collect()} and got
    pairs = {(r.a_seq, r.b_seq) for r in drained(J.pair_streams(src(), src(), "k", "3 MINUTES"), "paired")}
    assert pairs == {(a, b) for a in range(20) for b in range(20) if a % 3 == b % 3 and abs(a - b) <= 3}
    J.keep_newest(src().selectExpr("seq as win", "x as oid"), str(tmp_path / "kept"), str(tmp_path / "kc")).awaitTermination(120)
    assert [r.win for r in spark.read.parquet(str(tmp_path / "kept")).collect()] == [19]


def test_formats_and_bucketed_table(spark, tmp_path):
    from georank.sources import files

    df = spark.createDataFrame([(1, 2, 3), (4, None, 6)], "oid long, x long, y long")
    for fmt in files.FORMATS:
        assert sorted(files.round_trip(df, fmt).collect(), key=str) == sorted(df.collect(), key=str)
    a = files.write_bucketed(df, "georank_bucketed_a", ["oid"], 4)
    b = files.write_bucketed(df, "georank_bucketed_b", ["oid"], 4)
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    plan = a.join(b, "oid")._jdf.queryExecution().executedPlan().toString()
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)
    assert "Exchange" not in plan
    spark.sql("DROP TABLE georank_bucketed_a")
    spark.sql("DROP TABLE georank_bucketed_b")
