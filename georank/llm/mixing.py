"""Operator 9: mix sources to target weights by blocks.

Each source's words, document after document in a pseudorandom order, form one stream that is cut into blocks of a
fixed length. An output shard draws how many of its blocks each source gives; its slots are numbered through per
source, and slot j is the block that the source's pseudorandom permutation for epoch j div (number of blocks) puts at
place j mod (number of blocks). Blocks are joined by index.

Shards draw without replacement from the targets' blocks (a multivariate hypergeometric draw): that is the multinomial
draw given that all shards together meet the targets, so each source's total is its target to within a block.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import checkpointed, n_words, table

#: Words of a block, blocks of an output shard, documents of an ordering bucket.
BLOCK, SHARD, BUCKET = 32, 4096, 4096
LIMIT = 3


def sizes(docs: DataFrame) -> DataFrame:
    return docs.select(F.monotonically_increasing_id().alias("row"), docs["doc_id"].cast("long").alias("doc_id"), docs["source"].alias("source"), n_words(docs["text"]).alias("size"))


def targets(sized: DataFrame, limit: int = LIMIT) -> DataFrame:
    """src (1, 2, ... by code point, null last), source, source_size, target.

    The sources with the least limit*size/weight are those that stop at their limit. With them taken in that order,
    the k first stop if the rest's fair share per weight still exceeds the next one's ratio.
    """
    per = sized.groupBy("source").agg(F.sum("size").alias("source_size"))
    src = F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())).cast("long")
    per = per.withColumn("src", src).withColumn("weight", ((F.col("src") - 1) % 3 + 1).cast("double")).withColumn("cap", F.lit(float(limit)) * F.col("source_size"))
    whole = Window.partitionBy()
    ordered = Window.orderBy(F.col("cap") / F.col("weight"), "src")
    before = ordered.rowsBetween(Window.unboundedPreceding, -1)
    per = per.select("*", F.sum("source_size").over(whole).cast("double").alias("total"), F.coalesce(F.sum("cap").over(before), F.lit(0.0)).alias("held"), (F.sum("weight").over(whole) - F.coalesce(F.sum("weight").over(before), F.lit(0.0))).alias("open"))
    share = (F.col("total") - F.col("held")) / F.col("open")
    free = F.when(share * F.col("weight") < F.col("cap"), F.struct((F.col("cap") / F.col("weight")).alias("ratio"), "src", share.alias("share")))
    per = per.withColumn("level", F.min(free).over(whole)["share"])
    target = F.coalesce(F.least(F.col("cap"), F.col("level") * F.col("weight")), F.col("cap"))
    return per.select("src", "source", "source_size", target.alias("target"))


def permute(index: np.ndarray, n: np.ndarray, seed: np.ndarray) -> np.ndarray:
    """For each element a pseudorandom permutation, keyed by its seed, of 0..n-1 at index: a Feistel network with cycle walking."""
    from .common import mix

    half = np.maximum(1, (np.ceil(np.log2(np.maximum(n, 2))).astype(np.int64) + 1) // 2).astype(np.uint64)
    low = (np.uint64(1) << half) - np.uint64(1)
    out, todo = index.astype(np.uint64), np.arange(len(index))
    while len(todo):
        x, h, m = out[todo], half[todo], low[todo]
        left, right = x >> h, x & m
        for r in range(4):
            left, right = right, left ^ (mix(right + seed[todo] + np.uint64(r * 0x9E3779B9)) & m)
        out[todo] = (left << h) | right
        todo = todo[out[todo] >= n[todo].astype(np.uint64)]
    return out.astype(np.int64)


#: From so many on, numpy refuses exact hypergeometric draws.
MANY = 10**9


def deal(rng: np.random.Generator, quota: np.ndarray, n: int) -> np.ndarray:
    """n blocks drawn without replacement from the sources' quotas: exactly below MANY, from there on by the draw's normal limit, kept within what is possible."""
    out, left = np.zeros(len(quota), np.int64), int(quota.sum())
    if left < MANY:
        return rng.multivariate_hypergeometric(quota, n, method="marginals")
    for i, have in enumerate(quota.tolist()):
        rest = left - have
        if left < MANY:
            got = int(rng.hypergeometric(have, rest, n)) if n else 0
        else:
            share = have / left
            spread = (n * share * (1 - share) * (left - n) / max(1, left - 1)) ** 0.5
            got = min(max(round(n * share + spread * rng.standard_normal()), n - rest, 0), have, n)
        out[i] = got
        left, n = rest, n - got
    return out


def draws(quota: np.ndarray, shard: int, seed: int, low: int, high: int):
    """(shard, blocks of each source) for the shards low..high-1; first, under shard -1, sums of those before them.

    The quota is halved over the shards again and again, each time by a draw seeded by the range halved, so that any
    range can be drawn alone and gives what a draw of all gives.
    """
    stack = [(0, max(1, -(-int(quota.sum()) // shard)), quota.astype(np.int64))]
    while stack:
        a, b, q = stack.pop()
        if a >= high:
            continue
        if b <= low:
            yield -1, q
        elif b - a == 1:
            yield a, q
        else:
            mid = (a + b) // 2
            left = deal(np.random.default_rng([seed, a, b]), q, min(int(q.sum()), (mid - a) * shard))
            stack += [(mid, b, q - left), (a, mid, left)]


def mix_blocks(docs: DataFrame, block: int = BLOCK, shard: int = SHARD, seed: int = 1, limit: int = LIMIT) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(taken words per document, the mix's slots in order, targets).

    Per document: row (its monotonically_increasing_id in docs), doc_id, source, size, source_size, target, taken. Slots: shard, src, slot,
    epoch, block. A null or wordless text has size 0 and is never taken; a null source is a source; repeated rows are
    documents of their own; an empty table gives an empty mix. Reruns agree: order and draws depend on rows alone.
    """
    spark = docs.sparkSession
    sized = sizes(docs)
    goals = checkpointed(targets(sized, limit))
    key = F.when(F.col("doc_id").isNull(), F.xxhash64("row", F.lit(~seed))).otherwise(F.xxhash64("doc_id", F.lit(seed)))
    sized = sized.join(goals, sized["source"].eqNullSafe(goals["source"])).select("row", "doc_id", sized["source"], "size", "src", "source_size", "target", key.alias("key"))
    rows = checkpointed(sized)
    buckets = max(64, rows.count() // BUCKET)
    rows = rows.withColumn("bucket", F.pmod("key", F.lit(buckets)))
    inside = Window.partitionBy("src", "bucket").orderBy("key", "doc_id", "size", "row").rowsBetween(Window.unboundedPreceding, -1)
    rows = rows.withColumn("inside", F.coalesce(F.sum("size").over(inside), F.lit(0)))
    base = rows.groupBy("src", "bucket").agg(F.sum("size").alias("held"))
    base = base.select("src", "bucket", F.coalesce(F.sum("held").over(Window.partitionBy("src").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    rows = checkpointed(rows.join(base, ["src", "bucket"]).select("row", "doc_id", "source", "size", "src", "source_size", "target", (F.col("base") + F.col("inside")).alias("start")))

    # One small row per source: the shards' draws need the quotas of all sources together.
    per = goals.orderBy("src").select("src", "source_size", "target").collect()
    size, goal = np.array([r[1] for r in per], np.int64), np.array([r[2] for r in per])
    blocks = -(-size // block)
    # A block has `block` words but for the last of a source: by its mean length, quotas meet the targets in words.
    quota = np.minimum(np.rint(goal * blocks / np.maximum(size, 1)).astype(np.int64), limit * blocks)
    shards = max(1, -(-int(quota.sum()) // shard)) if len(per) else 0
    first = np.array([r[0] for r in per], np.int64)

    # A source's place in its own stream: the slots before each range of shards follow from drawing those ranges' sums.
    ranges = max(1, min(shards, 4 * spark.sparkContext.defaultParallelism))
    edges = [shards * i // ranges for i in range(ranges + 1)]

    def slots(batches):
        import pyarrow as pa

        for batch in batches:
            for low, high in zip(*(batch.column(i).to_pylist() for i in range(2))):
                done = np.zeros(len(quota), np.int64)
                for k, counts in draws(quota, shard, seed, low, high):
                    if k >= 0 and counts.sum():
                        at = np.repeat(np.arange(len(quota)), counts)
                        j = np.arange(len(at)) - np.repeat(np.cumsum(counts) - counts, counts) + done[at]
                        epoch = j // blocks[at]
                        where = permute(j - epoch * blocks[at], blocks[at], (first[at] * 1_000_003 + epoch * 7_919 + seed).astype(np.uint64))
                        yield pa.RecordBatch.from_pydict({"shard": np.full(len(at), k), "src": first[at], "slot": j, "epoch": epoch, "block": where})
                    done += counts

    ranged = spark.createDataFrame([(edges[i], edges[i + 1]) for i in range(ranges)] if shards else [], "low long, high long").repartition(ranges)
    mixed = ranged.mapInArrow(slots, "shard long, src long, slot long, epoch long, block long")

    uses = mixed.groupBy("src", "block").agg(F.count("*").alias("uses"))
    cover = rows.filter("size > 0").select("src", "start", "size", F.explode(F.sequence(F.floor(F.col("start") / block), F.floor((F.col("start") + F.col("size") - 1) / block))).alias("block"))
    words = F.least(F.col("start") + F.col("size"), (F.col("block") + 1) * block) - F.greatest("start", F.col("block") * block)
    taken = cover.join(uses, ["src", "block"]).groupBy(F.col("src").alias("t_src"), F.col("start").alias("t_start")).agg(F.sum(words * F.col("uses")).alias("taken"))
    # Documents with words have different starts; the others start where another does, and take nothing.
    out = rows.join(taken, (F.col("src") == F.col("t_src")) & (F.col("start") == F.col("t_start")) & (F.col("size") > 0), "left")
    out = out.select("row", "doc_id", "source", "src", "size", "source_size", "target", F.coalesce("taken", F.lit(0)).alias("taken"))
    return out, mixed, goals


def copies(mixed: DataFrame) -> DataFrame:
    """(row, copies) of the documents that a mix of whole documents holds, so that each source's words stay within a few of its largest texts of the target.

    A document's share taken / size is rounded to whole copies systematically: along each source's documents, by classes of size, shares are added
    up and a copy is given wherever the sum passes a whole number. Shares are counted in 2**-20ths, so sums are exact and reruns agree.
    """
    unit = 1 << 20
    rows = checkpointed(mixed.filter("size > 0").select("row", "src", "size", F.floor(F.col("taken") * F.lit(unit) / F.col("size")).cast("long").alias("share"), F.floor(F.log2("size") * 8).cast("int").alias("kind")))
    subs = max(1, rows.count() // BUCKET)
    rows = rows.withColumn("sub", F.pmod(F.xxhash64("row"), F.lit(subs)))
    held = rows.groupBy("src", "kind", "sub").agg(F.sum("share").alias("held"))
    base = held.select("src", "kind", "sub", F.coalesce(F.sum("held").over(Window.partitionBy("src").orderBy("kind", "sub").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    inside = F.sum("share").over(Window.partitionBy("src", "kind", "sub").orderBy("size", "row").rowsBetween(Window.unboundedPreceding, Window.currentRow))
    upto = rows.withColumn("inside", inside).join(base, ["src", "kind", "sub"]).withColumn("upto", F.col("base") + F.col("inside") + F.lit(unit // 2))
    whole = F.floor(F.col("upto") / unit) - F.floor((F.col("upto") - F.col("share")) / unit)
    return upto.select("row", whole.cast("long").alias("copies")).filter("copies > 0")


def op9_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = mix_blocks(table(spark, sf_dir, "documents"))[0]
    return out.select("doc_id", "size", "source_size", "target", "taken")
