"""Operator 6: nearest neighbours by multi-index hashing of learned rotated binary codes.

Codes come from rotations learned on a bounded sample: principal axes, then a rotation that brings the projections
near the corners of a cube; several such frames give a code longer than the vectors. A code is cut into substrings, each
indexed by value. If two codes differ in at most r bits, one of m substrings differs in at most r div m: probing all
substring values within that distance retrieves every code within the radius. What is retrieved is ranked by the
vectors themselves.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import checkpointed, table

#: Vectors that the rotations are learned on, at most about; frames; vectors of a shard.
SAMPLE, FRAMES, SHARD = 8_000, 4, 20_000
#: Share of the sample's true neighbours that the radius must cover.
COVER = 0.97


def valid(vectors: DataFrame, vec: str = "embedding", vid: str = "vec_id") -> DataFrame:
    """vec_id and vector as doubles, without vectors that are null, empty, zero or hold null or non-finite components, and without rows that have no id."""
    v = vectors[vec].cast("array<double>")
    df = vectors.select(vectors[vid].cast("long").alias("vec_id"), v.alias("v")).filter("vec_id is not null and size(v) > 0")
    bad = F.exists("v", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return df.filter(~F.coalesce(bad, F.lit(True)) & F.exists("v", lambda x: x != 0))


def learn(x: np.ndarray, frames: int = FRAMES, k: int = 20, cover: float = COVER, steps: int = 25, seed: int = 7) -> dict:
    """centre, projection (d x bits) and radius. Vectors are scaled to length 1 for codes only."""
    x = x / np.linalg.norm(x, axis=1, keepdims=True)
    centre = x.mean(0)
    axes = np.linalg.eigh((x - centre).T @ (x - centre))[1].T[::-1]
    p = (x - centre) @ axes.T
    rng, parts = np.random.default_rng(seed), []
    for _ in range(frames):
        r = np.linalg.qr(rng.normal(size=(p.shape[1],) * 2))[0]
        for _ in range(steps):
            a, _, b = np.linalg.svd(np.where(p @ r > 0, 1.0, -1.0).T @ p)
            r = (a @ b).T
        parts.append(axes.T @ r)
    project = np.hstack(parts)
    code = (x - centre) @ project > 0
    apart = []
    for i in range(0, len(x), max(1, len(x) // 200)):
        near = x @ x[i]
        near[i] = -np.inf
        apart.append((code[i] != code[np.argsort(-near)[: min(k, len(x) - 1)]]).sum(1))
    apart = np.concatenate(apart)
    radius = int(np.quantile(apart, cover, method="higher")) if apart.size else project.shape[1]
    return {"centre": centre, "project": project, "radius": radius}


def codes(x: np.ndarray, model: dict) -> np.ndarray:
    x = x / np.linalg.norm(x, axis=1, keepdims=True)
    return np.packbits((x - model["centre"]) @ model["project"] > 0, axis=1)


class MultiIndex:
    """Codes of bytes, indexed by each byte."""

    APART = np.bitwise_count(np.arange(256, dtype=np.uint8)[:, None] ^ np.arange(256, dtype=np.uint8)[None]).astype(np.uint8)

    def __init__(self, code: np.ndarray):
        self.m = code.shape[1]
        self.words = self.wide(code)
        self.order = [np.argsort(code[:, j], kind="stable") for j in range(self.m)]
        self.edge = [np.searchsorted(code[:, j][o], np.arange(257)) for j, o in enumerate(self.order)]

    @staticmethod
    def wide(code: np.ndarray) -> np.ndarray:
        """Codes as whole 64-bit numbers, filled up with zero bytes."""
        return np.pad(code, [(0, 0), (0, -code.shape[1] % 8)]).view(np.uint64)

    def probed(self, query: np.ndarray, radius: int) -> np.ndarray:
        """Marks what the substrings reach: the first radius mod m + 1 are probed to radius div m, the others to one less."""
        marked = np.zeros(len(self.words), bool)
        for j in range(self.m):
            reach = radius // self.m - (j > radius % self.m)
            if reach < 0 or marked.all():
                break
            edge = self.edge[j]
            for value in np.flatnonzero((self.APART[query[j]] <= reach) & (edge[:-1] < edge[1:])):
                marked[self.order[j][edge[value] : edge[value + 1]]] = True
        return marked

    def within(self, query: np.ndarray, radius: int) -> np.ndarray:
        """Every indexed code at most radius bits away."""
        found = np.flatnonzero(self.probed(query, radius))
        return found[np.bitwise_count(self.words[found] ^ self.wide(query[None])).sum(1) <= radius]


def inner(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Row-wise inner products in double precision, added up in the order of components."""
    out = np.zeros(np.broadcast_shapes(a.shape, b.shape)[:-1])
    for i in range(b.shape[-1]):
        out += a[..., i] * b[..., i]
    return out


def matrix(lists: pa.Array, d: int) -> np.ndarray:
    """Lists of numbers as rows of d numbers; shorter ones end in zeros."""
    size = lists.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
    flat = lists.flatten().to_numpy(zero_copy_only=False)
    out = np.zeros((len(size), d))
    out[np.repeat(np.arange(len(size)), size), np.arange(len(flat)) - np.repeat(np.cumsum(size) - size, size)] = flat
    return out


def _nearest(index: MultiIndex, ids: np.ndarray, x: np.ndarray, qid: int, q: np.ndarray, code: np.ndarray, radius: int, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Ids and scores of the k best of a shard, by a radius that grows until it holds k others or all."""
    most, others = index.m * 8, int((ids != qid).sum())
    while True:
        found = index.within(code, radius)
        found = found[ids[found] != qid]
        if len(found) >= min(k, others) or radius >= most:
            break
        radius = min(most, radius + 8)
    score = inner(x[found], q)
    best = np.lexsort((ids[found], -score))[:k]
    return ids[found][best], score[best]


def search(base: DataFrame, queries: DataFrame, k: int = 20, sample: int = SAMPLE, shard: int = SHARD) -> DataFrame:
    """query_id, rank, vec_id, score: the k nearest found of each query, by inner product, ties to the smaller id.

    base and queries have vec_id and v (see `valid`); a query's own id isn't among its neighbours. Base rows are dealt to shards
    by their place; each shard's rows come to their task once, are indexed once, and the queries then pass by in Arrow batches, so a task holds
    a shard and a batch. The radius starts at the learned one and grows until a shard that has k others gives k.

    Rows that repeat an id are one candidate, and one query, each. Vectors shorter than the longest count as if filled up
    with zeros. Without base rows or queries there are no results.
    """
    spark = base.sparkSession
    base, queries = checkpointed(base.select("vec_id", "v")), checkpointed(queries.select("vec_id", "v", F.monotonically_increasing_id().alias("ask")))
    n, d = base.agg(F.count("*"), F.max(F.size("v"))).first()
    longest = queries.agg(F.max(F.size("v"))).first()[0]
    if not n or longest is None:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    d = max(d, longest)
    draw = F.pmod(F.xxhash64("vec_id", F.lit(3)), F.lit(1 << 30)) < int((1 << 30) * min(1.0, sample / n))
    rows = base.filter(draw).orderBy("vec_id").select("v").limit(2 * sample).collect() or base.limit(1).select("v").collect()
    model = learn(matrix(pa.array([r[0] for r in rows], pa.list_(pa.float64())), d))
    shards = -(-n // shard)
    dealt = base.select(F.pmod(F.xxhash64(F.monotonically_increasing_id()), F.lit(shards)).alias("shard"), F.lit(0).alias("asks"), F.lit(0).cast("long").alias("ask"), "vec_id", "v")
    asked = queries.select(F.explode(F.sequence(F.lit(0).cast("long"), F.lit(shards - 1).cast("long"))).alias("shard"), F.lit(1).alias("asks"), "ask", "vec_id", "v")
    schema = pa.schema([("ask", pa.int64()), ("query_id", pa.int64()), ("vec_id", pa.int64()), ("score", pa.float64())])

    def answer(batches):
        at, have, index = None, [], None
        for batch in batches:
            if not batch.num_rows:
                continue
            shard_of, asks = batch.column("shard").to_numpy(), batch.column("asks").to_numpy()
            cuts = np.flatnonzero((shard_of[1:] != shard_of[:-1]) | (asks[1:] != asks[:-1])) + 1
            for lo, hi in zip([0, *cuts], [*cuts, len(asks)]):
                if shard_of[lo] != at:
                    at, have, index = shard_of[lo], [], None
                ids, v = batch.column("vec_id").to_numpy()[lo:hi], matrix(batch.column("v").slice(lo, hi - lo), d)
                if not asks[lo]:
                    have.append((ids, v))
                    continue
                if index is None and have:
                    own, x = (np.concatenate(part) for part in zip(*have))
                    have, index = [], MultiIndex(codes(x, model))
                if index is None:
                    continue
                best = [_nearest(index, own, x, qid, q, c, model["radius"], k) for qid, q, c in zip(ids, v, codes(v, model))]
                size = [len(b[0]) for b in best]
                yield pa.record_batch([np.repeat(batch.column("ask").to_numpy()[lo:hi], size), np.repeat(ids, size), np.concatenate([b[0] for b in best]), np.concatenate([b[1] for b in best])], schema=schema)

    each = dealt.unionByName(asked).repartitionById(shards, F.col("shard").cast("int")).sortWithinPartitions("shard", "asks")
    found = each.mapInArrow(answer, "ask long, query_id long, vec_id long, score double")
    rank = F.row_number().over(Window.partitionBy("query_id", "ask").orderBy(F.desc("score"), "vec_id"))
    return found.withColumn("rank", rank).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op6_hashing(spark: SparkSession, sf_dir: str) -> DataFrame:
    base = valid(table(spark, sf_dir, "embeddings"))
    return search(base, base.filter("vec_id % 20 = 0"))
