"""Operator 4: quality rules by robust multivariate outliers, in DataFrame functions alone.

Each document has a vector of transformed statistics. For each language and source, a minimum-covariance-determinant
estimate of centre and scatter is found by concentration steps from deterministic starts, and documents whose robust
Mahalanobis distance exceeds a chi-square cutoff are rejected.

Statistics are integers (STEP-ths of a unit), so their sums are exact and the verdicts don't depend on the order in
which rows are added up.
"""

from __future__ import annotations

import math
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import checkpointed, table, words

NAMES = ("word_length", "symbols", "dup_lines", "repeats")
STEP = 4096
#: Least standard deviation of each statistic, for groups in which it hardly varies: one phrase said twice, one repeated line or
#: one symbol in the shortest text that the base rules leave isn't by itself an outlier there. Larger scatter is left as it is.
FLOOR = (0.01, 0.16, 0.1, 0.1)
#: Chi-square quantile of 4 degrees of freedom at 0.99.
CUTOFF = 13.277
STARTS, ROUNDS, SALTS = 2, 5, 32


def consistency(p: int, share: float) -> float:
    """What the scatter of a normal sample's central `share` in p dimensions is multiplied by to estimate the whole sample's."""
    if share >= 1:
        return 1.0

    def below(k: int, x: float) -> float:
        out, at = (math.erf(math.sqrt(x / 2)), 1) if k % 2 else (1 - math.exp(-x / 2), 2)
        while at < k:
            out -= (x / 2) ** (at / 2) * math.exp(-x / 2) / math.gamma(at / 2 + 1)
            at += 2
        return out

    low, high = 0.0, 200.0
    for _ in range(100):
        mid = (low + high) / 2
        low, high = (mid, high) if below(p, mid) < share else (low, mid)
    return share / below(p + 2, low)


def base(docs: DataFrame) -> DataFrame:
    """row (its monotonically_increasing_id in docs), n_words, word_chars, n_symbols, n_dup_lines and n_repeat_words of whole texts; null texts have no words."""
    text = F.coalesce(docs["text"], F.lit(""))
    df = docs.select(F.monotonically_increasing_id().alias("row"), docs["doc_id"].cast("long").alias("doc_id"), docs["lang"].alias("lang"), docs["source"].alias("source"), words(text).alias("w"), F.regexp_count(text, F.lit(r"[#*$%&|<>]")).cast("long").alias("n_symbols"), F.filter(F.split(text, "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]")).alias("lines"))
    df = df.select("*", F.size("w").cast("long").alias("n_words"), F.char_length(F.array_join("w", "")).cast("long").alias("word_chars"), (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines"))
    n = F.col("n_words").cast("int")
    # Windows of three words with their place, sorted: equal windows stand side by side.
    m = F.greatest(n - 2, F.lit(0))
    win = F.arrays_zip(F.slice("w", 1, m).alias("a"), F.slice("w", 2, m).alias("b"), F.slice("w", 3, m).alias("c"), F.when(m > 0, F.sequence(F.lit(0), m - 1)).otherwise(F.array().cast("array<int>")).alias("i"))
    df = df.withColumn("win", F.sort_array(win))
    same = lambda x, y: (x["a"] == y["a"]) & (x["b"] == y["b"]) & (x["c"] == y["c"])
    m = F.size("win")
    pairs = F.zip_with(F.slice("win", 1, F.greatest(m - 1, F.lit(0))), F.slice("win", 2, F.greatest(m - 1, F.lit(0))), lambda x, y: F.when(same(x, y), F.array(x["i"], y["i"])).otherwise(F.array().cast("array<int>")))
    df = df.withColumn("hits", F.sort_array(F.array_distinct(F.flatten(pairs))))
    k = F.size("hits")
    gaps = F.zip_with(F.slice("hits", 1, F.greatest(k - 1, F.lit(0))), F.slice("hits", 2, F.greatest(k - 1, F.lit(0))), lambda x, y: F.least(F.lit(3), y - x))
    covered = F.when(k > 0, F.aggregate(gaps, F.lit(3), lambda s, x: s + x)).otherwise(0)
    df = df.withColumn("n_repeat_words", covered.cast("long"))
    failed = (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    return df.select("row", "doc_id", "lang", "source", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", failed.alias("base_failed"))


def _vector() -> list[Column]:
    n = F.greatest("n_words", F.lit(1)).cast("double")
    raw = (
        F.log1p(F.col("word_chars") / n),
        F.log1p(100 * F.col("n_symbols") / n) / 2,
        F.sqrt(20 * F.col("n_dup_lines") / n) / 2,
        F.sqrt(F.col("n_repeat_words") / n),
    )
    return [F.round(x * STEP).cast("long") for x in raw]


def _estimate(rows: DataFrame, keys: list[str], share: float) -> DataFrame:
    """Exact sums of a subset per group, as count, means m0.. and the lower Cholesky factor l00, l10, l11 .. of the scatter.

    The subset's covariance is made consistent for a normal sample in as many dimensions as vary by more than the floor; only
    variances that are below the floor then are raised to it.
    """
    d = len(NAMES)
    salted = rows.groupBy(*keys, "salt").agg(F.count("*").alias("n"), *[F.sum(F.col(f"x{i}").cast("decimal(20,0)")).alias(f"s{i}") for i in range(d)], *[F.sum((F.col(f"x{i}") * F.col(f"x{j}")).cast("decimal(20,0)")).alias(f"p{i}{j}") for i in range(d) for j in range(i + 1)])
    total = salted.groupBy(*keys).agg(F.sum("n").alias("n"), *[F.sum(c).cast("double").alias(c) for c in salted.columns if c[0] in "sp" and c[1:].isdigit()])
    df = total.select(*keys, "n", *[(F.col(f"s{i}") / F.col("n")).alias(f"m{i}") for i in range(d)], *[F.col(f"p{i}{j}") for i in range(d) for j in range(i + 1)])
    least = [F.lit((FLOOR[i] * STEP) ** 2) for i in range(d)]
    df = df.select("*", *[(F.col(f"p{i}{j}") / F.col("n") - F.col(f"m{i}") * F.col(f"m{j}")).alias(f"c{i}{j}") for i in range(d) for j in range(i + 1)])
    live = reduce(lambda a, b: a + b, [(F.col(f"c{i}{i}") > least[i]).cast("int") for i in range(d)])
    df = df.withColumn("factor", F.array(*[F.lit(consistency(max(k, 1), share)) for k in range(d + 1)])[live])
    for i in range(d):
        for j in range(i + 1):
            cov = F.col("factor") * F.col(f"c{i}{j}")
            cov = F.greatest(cov, least[i]) if i == j else cov
            rest = reduce(lambda a, b: a - b, [F.col(f"l{i}{k}") * F.col(f"l{j}{k}") for k in range(j)], cov)
            df = df.withColumn(f"l{i}{j}", F.sqrt(F.greatest(rest, F.lit(1.0))) if i == j else rest / F.col(f"l{j}{j}"))
    return df.withColumn("logdet", reduce(lambda a, b: a + b, [F.log(F.col(f"l{i}{i}")) for i in range(d)])).drop("factor", *[f"{c}{i}{j}" for c in "pc" for i in range(d) for j in range(i + 1)])


def _distances(rows: DataFrame, est: DataFrame, keys: list[str]) -> DataFrame:
    """Squared Mahalanobis distances by forward substitution; estimates are copied to each salt, so no group meets in one task."""
    d = len(NAMES)
    df = rows.join(est.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1)))), [*keys, "salt"])
    for i in range(d):
        rest = reduce(lambda a, b: a - b, [F.col(f"l{i}{k}") * F.col(f"z{k}") for k in range(i)], F.col(f"x{i}") - F.col(f"m{i}"))
        df = df.withColumn(f"z{i}", rest / F.col(f"l{i}{i}"))
    return df.withColumn("d2", reduce(lambda a, b: a + b, [F.col(f"z{i}") * F.col(f"z{i}") for i in range(d)]))


def _bin(x: Column) -> Column:
    return F.floor(F.log1p(x) * 256)


def _least(df: DataFrame, keys: list[str], by: Column, share: float = 0.75) -> DataFrame:
    """The rows of each group whose `by` is in the least bins that hold `share` of the group."""
    df = df.withColumn("bin", by)
    bins = df.groupBy(*keys, "bin").agg(F.count("*").alias("c"))
    w = Window.partitionBy(*keys)
    bins = bins.select(*keys, "bin", (F.sum("c").over(w.orderBy("bin")) - F.col("c")).alias("below"), F.sum("c").over(w).alias("all"))
    cut = bins.filter(F.col("below") < F.ceil(share * F.col("all"))).groupBy(*keys).agg(F.max("bin").alias("cut"))
    cut = cut.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    return df.join(cut, [*keys, "salt"]).filter("bin <= cut").drop("bin", "cut")


def judge(docs: DataFrame, share: float = 0.75, cutoff: float = CUTOFF, rounds: int = ROUNDS) -> DataFrame:
    """base() with distance (squared, robust) and kept; documents that fail the base rules aren't kept and shape no estimate.

    A null language or source is a group of its own. Small groups need no special case: the scatter's floor keeps their
    estimates regular, and a group of one has distance 0. Repeated rows count as often as they occur. An empty table
    gives an empty result. Columns other than doc_id, text, lang and source aren't read.
    """
    d = len(NAMES)
    stats = checkpointed(base(docs))
    group = F.xxhash64(F.coalesce("lang", F.lit("")), F.col("lang").isNull(), F.coalesce("source", F.lit("")), F.col("source").isNull())
    named = stats.select("*", *[x.alias(f"x{i}") for i, x in enumerate(_vector())], group.alias("grp"), F.pmod(F.xxhash64("row"), F.lit(SALTS)).cast("int").alias("salt"))
    xs = [f"x{i}" for i in range(d)]
    good = named.filter(~F.col("base_failed")).select("grp", "salt", *xs)
    keys = ["grp", "start"]
    # Starts: coordinatewise medians, then the rows nearest to them by the sum, or by the largest, of floored deviations.
    bins = good.select("grp", F.explode(F.array(*[F.struct(F.lit(i).alias("i"), F.col(f"x{i}").alias("v")) for i in range(d)])).alias("e")).groupBy("grp", "e.i", "e.v").agg(F.count("*").alias("c"))
    w = Window.partitionBy("grp", "i")
    med = bins.select("grp", "i", "v", F.sum("c").over(w.orderBy("v")).alias("upto"), F.sum("c").over(w).alias("all")).filter(2 * F.col("upto") >= F.col("all")).groupBy("grp").agg(*[F.min(F.when(F.col("i") == i, F.col("v"))).alias(f"c{i}") for i in range(d)])
    med = med.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    off = [F.abs(F.col(f"x{i}") - F.col(f"c{i}")) / (FLOOR[i] * STEP) for i in range(d)]
    begin = good.join(med, ["grp", "salt"]).select("grp", "salt", *xs, F.posexplode(F.array(reduce(lambda a, b: a + b, off), F.greatest(*off))).alias("start", "far"))
    est = checkpointed(_estimate(_least(begin, keys, _bin(F.col("far")), share), keys, share))
    many = good.select("*", F.explode(F.sequence(F.lit(0), F.lit(STARTS - 1))).alias("start"))
    for _ in range(rounds):
        est = checkpointed(_estimate(_least(_distances(many, est, keys), keys, _bin(F.col("d2")), share), keys, share))
    best = est.groupBy("grp").agg(F.min_by(F.struct(*[c for c in est.columns if c not in keys]), F.struct("logdet", "start")).alias("b")).select("grp", "b.*")
    far = named.join(best.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1)))), ["grp", "salt"], "left").withColumnRenamed("n", "h")
    for i in range(d):
        rest = reduce(lambda a, b: a - b, [F.col(f"l{i}{k}") * F.col(f"z{k}") for k in range(i)], F.col(f"x{i}") - F.col(f"m{i}"))
        far = far.withColumn(f"z{i}", rest / F.col(f"l{i}{i}"))
    d2 = reduce(lambda a, b: a + b, [F.col(f"z{i}") * F.col(f"z{i}") for i in range(d)])
    return far.select(*stats.columns, F.coalesce(d2, F.lit(0.0)).alias("distance")).withColumn("kept", ~F.col("base_failed") & (F.col("distance") <= cutoff))


def op4_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(table(spark, sf_dir, "documents")).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", F.round("distance", 3).alias("distance"))
