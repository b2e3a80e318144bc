"""Readers with fixed schemas, and the object sets and query streams made from the tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

L = T.LongType()
#: Users of a range of keys: windows within ranges, and one over ranges, take the place of one over all users.
RANGE = 1000
OBJECT_SCHEMA = T.StructType([T.StructField("oid", L), T.StructField("x", L), T.StructField("y", L)])
QUERY_SCHEMA = T.StructType([T.StructField("seq", L), T.StructField("ts", T.TimestampType()), T.StructField("x", L), T.StructField("y", L), T.StructField("kind", T.StringType()), T.StructField("r2", L), T.StructField("k", T.IntegerType())])
RESULT_SCHEMA = T.StructType([T.StructField("win", L), T.StructField("pos", T.IntegerType()), T.StructField("oid", L), T.StructField("num", L), T.StructField("pop", T.DoubleType())])


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def checked(df: DataFrame, schema: T.StructType) -> DataFrame:
    """df with the schema's columns in its order; raises if one is missing or of another type."""
    have = {f.name: f.dataType for f in df.schema}
    for f in schema:
        if have.get(f.name) != f.dataType:
            raise TypeError(f"column {f.name}: {have.get(f.name)} where {f.dataType} is needed")
    return df.select(*schema.fieldNames())


def scaled(df: DataFrame, c: str, out: str, top: int) -> DataFrame:
    """Add c scaled to 0..top by its least and greatest value, which come from a one-row aggregate joined to all rows."""
    ends = df.agg(F.min(c).alias("__lo"), F.greatest(F.max(c) - F.min(c), F.lit(1)).alias("__span"))
    return df.crossJoin(F.broadcast(ends)).withColumn(out, F.expr(f"({c} - __lo) * {top} div __span")).drop("__lo", "__span")


def objects_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = read_table(spark, sf_dir, "part").select(F.col("p_partkey").alias("oid"), F.round(F.col("p_retailprice") * 100).cast("long").alias("c"), F.col("p_size").cast("long").alias("s"))
    return checked(scaled(p, "c", "x", 1023).withColumn("y", F.expr("(s - 1) * 1023 div 49")), OBJECT_SCHEMA)


def objects_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = read_table(spark, sf_dir, "orders")
    return checked(o.select(F.col("o_orderkey").alias("oid"), F.expr("cast(round(o_totalprice * 100) as bigint) * 65535 div 50000000").alias("x"), F.expr("cast(datediff(o_orderdate, date'1995-01-01') as bigint) * 65535 div 2405").alias("y")), OBJECT_SCHEMA)


def objects_embed(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = read_table(spark, sf_dir, "embeddings")

    def axis(i: int):
        v = F.greatest(F.lit(-0.6), F.least(F.lit(0.6), F.element_at("embedding", i).cast("double")))
        return F.floor((v + 0.6) * 1023 / 1.2).cast("long")

    return checked(e.select(F.col("vec_id").alias("oid"), axis(1).alias("x"), axis(2).alias("y")), OBJECT_SCHEMA)


def facilities(spark: SparkSession, sf_dir: str) -> DataFrame:
    """fid counts facilities from 0 in the order of their keys; places follow from key and balance."""
    s = read_table(spark, sf_dir, "supplier")
    low = s.agg(F.min("s_suppkey").alias("lo"))
    return s.crossJoin(F.broadcast(low)).select((F.col("s_suppkey") - F.col("lo")).alias("fid"), F.expr("(s_suppkey * 389 + 17) % 1024").alias("x"), F.expr("(cast(round(s_acctbal * 100) as bigint) + 100000) * 1024 div 1100000").alias("y"))


def _stream(spark: SparkSession, sf_dir: str, fid: str, r: int) -> DataFrame:
    fac = facilities(spark, sf_dir)
    n = fac.agg(F.count("*").alias("n"))
    e = read_table(spark, sf_dir, "events").select(F.col("event_id").alias("seq"), F.col("ts").cast("timestamp").alias("ts"), "user_id", "value", F.get_json_object("props", "$.k").cast("long").alias("pk"))
    e = e.crossJoin(F.broadcast(n)).withColumn("fid", F.expr(fid))
    q = e.join(fac, "fid").select("seq", "ts", "x", "y", F.lit("range").alias("kind"), F.lit(r * r).cast("long").alias("r2"), F.lit(None).cast("int").alias("k"))
    return checked(q, QUERY_SCHEMA)


def queries_uniform(spark: SparkSession, sf_dir: str, r: int = 41) -> DataFrame:
    return _stream(spark, sf_dir, "(user_id * 100 + pk) % n", r)


def queries_skewed(spark: SparkSession, sf_dir: str, r: int = 41) -> DataFrame:
    return _stream(spark, sf_dir, "least(n - 1, cast(round(value * 100) as bigint) * n div 50000)", r)


def queries_events(spark: SparkSession, sf_dir: str, r: int = 41) -> DataFrame:
    e = read_table(spark, sf_dir, "events").withColumn("pk", F.get_json_object("props", "$.k").cast("long"))
    q = e.select(F.col("event_id").alias("seq"), F.col("ts").cast("timestamp").alias("ts"), F.expr("pk * 1023 div 99").alias("x"), F.expr("least(1023, cast(round(value * 100) as bigint) * 1023 div 50000)").alias("y"), F.lit("range").alias("kind"), F.lit(r * r).cast("long").alias("r2"), F.lit(None).cast("int").alias("k"))
    return checked(q, QUERY_SCHEMA)


def checkins(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(user, ts, x, y) of check-ins, with multiplicity."""
    li = read_table(spark, sf_dir, "lineitem").filter("l_quantity >= 49").select("l_orderkey", "l_partkey", F.col("l_shipdate").cast("timestamp").alias("ts"))
    o = read_table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), F.col("o_custkey").alias("user"))
    p = objects_part(spark, sf_dir).select(F.col("oid").alias("l_partkey"), "x", "y")
    return li.join(o, "l_orderkey").join(p, "l_partkey").select("user", "ts", "x", "y")


def queries_checkin(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per user the mean place of its check-ins and the radius that covers them; a user with one check-in borrows the radius of the next user by key that has several, cyclically."""
    c = checkins(spark, sf_dir)
    u = c.groupBy("user").agg(F.max("ts").alias("ts"), F.count("*").alias("c"), F.expr("sum(x) div count(*)").alias("x"), F.expr("sum(y) div count(*)").alias("y"))
    d = c.select("user", F.col("x").alias("px"), F.col("y").alias("py")).join(u, "user")
    u = d.groupBy("user", "ts", "c", "x", "y").agg(F.max((F.col("px") - F.col("x")) * (F.col("px") - F.col("x")) + (F.col("py") - F.col("y")) * (F.col("py") - F.col("y"))).alias("own"))
    # The next user with several check-ins: within a range of keys by a running window, across ranges by the ranges' first ones.
    u = u.withColumns({"r": F.when(F.col("c") > 1, F.col("own")), "part": F.expr(f"user div {RANGE}")})
    down = Window.partitionBy("part").orderBy(F.desc("user")).rowsBetween(Window.unboundedPreceding, 0)
    heads = u.filter("c > 1").groupBy("part").agg(F.min_by("own", "user").alias("head"))
    later = Window.orderBy(F.desc("part")).rowsBetween(Window.unboundedPreceding, -1)
    carried = u.select("part").distinct().join(heads, "part", "left").select("part", F.last("head", True).over(later).alias("carried"))
    whole = u.filter("c > 1").agg(F.min_by("own", "user").alias("head"))
    u = u.withColumn("after", F.last("r", True).over(down)).join(carried, "part").crossJoin(F.broadcast(whole)).withColumn("r2", F.coalesce("after", "carried", "head", F.lit(0)).cast("long"))
    # Numbers in order of time and user: days' counts come first, then places within days.
    u = u.withColumn("day", F.to_date("ts"))
    days = u.groupBy("day").agg(F.count("*").alias("n"))
    days = days.select("day", F.coalesce(F.sum("n").over(Window.orderBy("day").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"))
    seq = (F.col("before") + F.row_number().over(Window.partitionBy("day").orderBy("ts", "user")) - 1).cast("long")
    return checked(u.join(days, "day").select(seq.alias("seq"), "ts", "x", "y", F.lit("range").alias("kind"), "r2", F.lit(None).cast("int").alias("k")), QUERY_SCHEMA)
