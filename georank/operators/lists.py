"""Ranked lists of places. A list is made once per place, in one task, and expanded to the place's queries there, so that no match is moved."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Entries of lists that are handed on at once.
BATCH = 500_000
#: Matches that a row of pieces stands for at most: Spark keeps all rows that come of one row in memory before it hands on the first.
PIECE = 16_384


def place_lists(objects: DataFrame, queries: DataFrame, tile: int = 64, most: int | None = None) -> DataFrame:
    """(qx, qy, r2, first, seqs, oids, d2s, shared): per place its queries, and its objects by (d2, oid) with their distances and shared ranks.

    A place belongs to one tile; objects are copied to the tiles that the greatest radius reaches from them. Places that
    reach nothing have empty lists. most: a place has several rows, pieces of its list for some of its queries, each of so many matches at most;
    first is where a piece begins in the list, from 0.
    """

    def lists(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from _lists(batches, most)

    return _tiles(objects, queries, tile).applyInArrow(lists, "qx long, qy long, r2 long, first long, seqs array<long>, oids array<long>, d2s array<long>, shared array<int>")


def place_counts(objects: DataFrame, queries: DataFrame) -> DataFrame:
    """(x, y, r2, reached): how many objects each place reaches, also none."""
    q = queries.select("x", "y", "r2").distinct().withColumn("seq", F.lit(0).cast("long"))
    return _tiles(objects, q, 64).applyInArrow(_counts, "x long, y long, r2 long, reached long")


def union_sizes(objects: DataFrame, discs: DataFrame, chunk: int = 50_000) -> DataFrame:
    """(seq, n, own): for the discs (seq, x, y, r2, own) of each seq, how many different objects lie in any of them, and the largest own.

    Seqs are taken in chunks, which get the number of objects at each point and no ids; points don't grow with the objects.
    """
    d = discs.withColumn("tx", F.expr(f"seq div {chunk}"))
    ends = F.broadcast(d.select(F.col("tx").alias("c")).distinct())
    o = objects.groupBy("x", "y").agg(F.count("*").alias("id")).crossJoin(ends)
    nil = F.lit(None).cast("long")
    o = o.select(F.col("c").alias("tx"), "x", "y", "id", nil.alias("r2"), nil.alias("own"))
    q = d.select("tx", "x", "y", F.col("seq").alias("id"), "r2", F.col("own").cast("long").alias("own"))
    return o.unionByName(q).groupBy("tx").applyInArrow(_unions, "seq long, n long, own long")


def tile_stats(objects: DataFrame, queries: DataFrame, tile: int = 128) -> DataFrame:
    """(oid, n, s1, s2, worst, worst_seq): an object's matches from a tile's places: their number, sums of ranks and squares, the worst rank and the latest query with it."""
    return _tiles(objects, queries, tile).applyInArrow(_stats, "oid long, n long, s1 long, s2 long, worst long, worst_seq long")


def tile_sums(objects: DataFrame, queries: DataFrame, m: int, tile: int = 128) -> DataFrame:
    """(seq, oid, n, s1): an object's matches from a tile's places by seq, which stands for groups of queries here, and their sum of ranks.

    Objects at one point are matched together, and ranked by oid there: of these only the first m can be among a group's first m, others have no rows.
    """

    def sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from _sums(batches, m)

    return _tiles(objects, queries, tile).applyInArrow(sums, "seq long, oid long, n long, s1 long")


def _tiles(objects: DataFrame, queries: DataFrame, tile: int):
    far = F.broadcast(queries.agg(F.ceil(F.sqrt(F.max("r2").cast("double"))).cast("long").alias("far")))
    span = lambda c: F.explode(F.sequence(F.floor((F.col(c) - F.col("far")) / tile), F.floor((F.col(c) + F.col("far")) / tile)))
    o = objects.crossJoin(far).withColumn("tx", span("x")).withColumn("ty", span("y")).select("tx", "ty", "x", "y", F.col("oid").alias("id"), F.lit(None).cast("long").alias("r2"))
    q = queries.select(F.floor(F.col("x") / tile).alias("tx"), F.floor(F.col("y") / tile).alias("ty"), "x", "y", F.col("seq").alias("id"), "r2")
    return o.unionByName(q).groupBy("tx", "ty")


def columns(batches, names):
    """The named columns of all batches as arrays; nulls are -1."""
    parts = [[b.column(n).fill_null(-1).to_numpy(zero_copy_only=False) for n in names] for b in batches]
    return [np.concatenate(p) for p in zip(*parts)]


def split(batches) -> tuple[tuple, tuple]:
    """Objects (x, y, oid) by x, and queries (x, y, seq, r2), of rows that are objects if r2 is null."""
    x, y, i, r2 = columns(batches, ("x", "y", "id", "r2"))
    o = np.flatnonzero(r2 < 0)
    o = o[np.argsort(x[o], kind="stable")]
    q = np.flatnonzero(r2 >= 0)
    return (x[o], y[o], i[o]), (x[q], y[q], i[q], r2[q])


class Near:
    """Objects near a place, by (d2, oid)."""

    def __init__(self, x, y, oid):
        self.x, self.y, self.n = x, y, max(1, len(oid))
        by = np.argsort(oid, kind="stable")
        self.oids = oid[by]
        self.at = np.empty(len(oid), np.int64)
        self.at[by] = np.arange(len(oid))

    def __call__(self, x: int, y: int, r2: int):
        """(places in oids, d2), in order."""
        r = int(np.sqrt(r2)) + 1
        a, b = np.searchsorted(self.x, (x - r, x + r + 1))
        d2 = (self.x[a:b] - x) ** 2 + (self.y[a:b] - y) ** 2
        hit = np.flatnonzero(d2 <= r2)
        d2, at = d2[hit], self.at[a:b][hit]
        if r2 < (1 << 62) // self.n:
            key = np.sort(d2 * self.n + at)
            return key % self.n, key // self.n
        by = np.lexsort((at, d2))
        return at[by], d2[by]


def places(qx, qy, r2):
    """Rows by place, and where each place begins."""
    by = np.lexsort((r2, qy, qx))
    new = np.ones(len(by), bool)
    new[1:] = (np.diff(qx[by]) != 0) | (np.diff(qy[by]) != 0) | (np.diff(r2[by]) != 0)
    return by, np.append(np.flatnonzero(new), len(by))


def _lists(batches: Iterator[pa.RecordBatch], most: int | None) -> Iterator[pa.RecordBatch]:
    (ox, oy, oid), (qx, qy, seq, r2) = split(batches)
    near = Near(ox, oy, oid)
    by, cuts = places(qx, qy, r2)
    rows, held = [], 0
    for a, b in zip(cuts[:-1], cuts[1:]):
        i = by[a]
        at, d2 = near(int(qx[i]), int(qy[i]), int(r2[i]))
        shared = np.searchsorted(d2, d2, "left") + 1
        seqs, oids = seq[by[a:b]], near.oids[at]
        some = len(seqs) if most is None else min(len(seqs), most)
        step = max(1, len(oids) if most is None else most // some)
        for c in range(0, len(seqs), some):
            for k in range(0, max(1, len(oids)), step):
                rows.append((qx[i], qy[i], r2[i], k, seqs[c : c + some], oids[k : k + step], d2[k : k + step], shared[k : k + step]))
                held += len(rows[-1][4]) + len(rows[-1][5])
                if held > BATCH:
                    yield _batch(rows)
                    rows, held = [], 0
    if rows:
        yield _batch(rows)


def _counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    (ox, oy, _), (qx, qy, _, r2) = split(batches)
    n = np.zeros(len(qx), np.int64)
    for i in range(len(qx)):
        r = int(np.sqrt(r2[i])) + 1
        a, b = np.searchsorted(ox, (qx[i] - r, qx[i] + r + 1))
        n[i] = np.count_nonzero((ox[a:b] - qx[i]) ** 2 + (oy[a:b] - qy[i]) ** 2 <= r2[i])
    if len(n):
        yield _flat(x=qx, y=qy, r2=r2, reached=n)


def _unions(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    x, y, i, r2, own = columns(batches, ("x", "y", "id", "r2", "own"))
    o, q = np.flatnonzero(r2 < 0), np.flatnonzero(r2 >= 0)
    ox, oy, count = x[o], y[o], i[o]
    q = q[np.argsort(i[q], kind="stable")]
    qx, qy, r2, own = x[q], y[q], r2[q], own[q]
    seqs, at = np.unique(i[q], return_inverse=True)
    n, mine = np.zeros(len(seqs), np.int64), np.zeros(len(seqs), np.int64)
    np.maximum.at(mine, at, own)
    for row in np.unique(oy):
        here = np.flatnonzero(oy == row)
        here = here[np.argsort(ox[here])]
        px, upto = ox[here], np.append(0, np.cumsum(count[here]))
        left = r2 - (qy - row) ** 2
        d = np.flatnonzero(left >= 0)
        if not len(d):
            continue
        w = np.sqrt(left[d].astype(np.float64)).astype(np.int64)
        w -= w * w > left[d]
        w += (w + 1) * (w + 1) <= left[d]
        # Intervals of objects along the row, by seq: what an interval adds lies beyond the farthest end before it.
        lo, hi = upto[np.searchsorted(px, qx[d] - w)], upto[np.searchsorted(px, qx[d] + w, "right")]
        base = at[d] * (upto[-1] + 1)
        by = np.argsort(base + lo, kind="stable")
        base, lo, hi = base[by], (base + lo)[by], (base + hi)[by]
        far = np.maximum.accumulate(np.append(-1, hi))[:-1]
        n += np.bincount(at[d][by], np.maximum(0, hi - np.maximum(lo, far)), len(seqs)).astype(np.int64)
    if len(seqs):
        yield _flat(seq=seqs, n=n, own=mine)


def _stats(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    (ox, oy, oid), (qx, qy, seq, r2) = split(batches)
    near = Near(ox, oy, oid)
    n, s1, s2, worst, late = (np.zeros(len(oid), np.int64) for _ in range(5))
    by, cuts = places(qx, qy, r2)
    for a, b in zip(cuts[:-1], cuts[1:]):
        i = by[a]
        at, _ = near(int(qx[i]), int(qy[i]), int(r2[i]))
        rnk, last = np.arange(1, len(at) + 1), seq[by[a:b]].max()
        n[at] += b - a
        s1[at] += (b - a) * rnk
        s2[at] += (b - a) * rnk * rnk
        old = worst[at]
        more = (rnk > old) | ((rnk == old) & (last > late[at]))
        worst[at[more]], late[at[more]] = rnk[more], last
    hit = n > 0
    yield _flat(oid=near.oids[hit], n=n[hit], s1=s1[hit], s2=s2[hit], worst=worst[hit], worst_seq=late[hit])


def _sums(batches: Iterator[pa.RecordBatch], m: int, cells: int = 20_000_000) -> Iterator[pa.RecordBatch]:
    (ox, oy, oid), (qx, qy, seq, r2) = split(batches)
    near = Near(ox, oy, oid)
    # Places among the objects at the same point, by oid.
    by = np.lexsort((oid, oy, ox))
    first = np.ones(len(by), bool)
    first[1:] = (np.diff(ox[by]) != 0) | (np.diff(oy[by]) != 0)
    nth = np.arange(len(by)) - np.maximum.accumulate(np.where(first, np.arange(len(by)), 0))
    keep = np.zeros(len(by), bool)
    keep[near.at[by]] = nth < m
    groups = np.unique(seq)
    step = max(1, cells // near.n)
    for g in range(0, len(groups), step):
        some = groups[g : g + step]
        now = np.flatnonzero((seq >= some[0]) & (seq <= some[-1]))
        n, s1 = (np.zeros((len(some), near.n), np.int64) for _ in range(2))
        by, cuts = places(qx[now], qy[now], r2[now])
        for a, b in zip(cuts[:-1], cuts[1:]):
            i = now[by[a]]
            at, _ = near(int(qx[i]), int(qy[i]), int(r2[i]))
            kept = np.flatnonzero(keep[at])
            at = at[kept]
            for t, k in zip(*np.unique(np.searchsorted(some, seq[now[by[a:b]]]), return_counts=True)):
                n[t, at] += k
                s1[t, at] += k * (kept + 1)
        for t in range(len(some)):
            hit = np.flatnonzero(n[t])
            yield _flat(seq=np.full(len(hit), some[t]), oid=near.oids[hit], n=n[t, hit], s1=s1[t, hit])


def _flat(**cols) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(np.asarray(c, np.int64)) for c in cols.values()], list(cols))


def _list(arrays, kind):
    ends = np.cumsum([0] + [len(a) for a in arrays]).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(arrays), kind))


def _batch(rows) -> pa.RecordBatch:
    qx, qy, r2, first, seqs, oids, d2s, shared = zip(*rows)
    flat = [pa.array(np.array(c, np.int64)) for c in (qx, qy, r2, first)]
    return pa.RecordBatch.from_arrays([*flat, _list(seqs, pa.int64()), _list(oids, pa.int64()), _list(d2s, pa.int64()), _list(shared, pa.int32())], ["qx", "qy", "r2", "first", "seqs", "oids", "d2s", "shared"])


def expand(lists: DataFrame, ties: str = "total") -> DataFrame:
    """(seq, oid, d2, rnk) of all queries, as matching.rank_matches gives them."""
    each = lists.select("first", "seqs", "d2s", "shared", F.posexplode("oids").alias("pos", "oid"))
    rnk = F.col("first") + F.col("pos") + 1 if ties == "total" else F.expr("shared[pos]")
    return each.select(F.explode("seqs").alias("seq"), "oid", F.expr("d2s[pos]").alias("d2"), rnk.cast("long").alias("rnk"))


def window_tops(objects: DataFrame, queries: DataFrame, w: int, m: int, chunk: int = 50_000) -> DataFrame:
    """(win, pos, oid, num) for every full window: the m greatest sums of contributions, ties by oid.

    Windows are taken in chunks. A chunk gets the objects, by point, and its queries with the w - 1 before them; no match is moved, and
    sums are kept of points (`_tops`). A chunk is no shorter than a sixteenth of the objects, so that copies of objects stay in proportion to
    the queries. `win` runs to the last seq of the queries.
    """
    q = queries.select("x", "y", "seq", "r2")
    ends = F.broadcast(q.agg(F.max("seq").alias("last")).crossJoin(objects.agg(F.greatest(F.lit(chunk).cast("long"), F.expr("count(*) div 16")).alias("size"))))
    span = F.sequence(F.expr(f"greatest(seq, {w - 1}) div size"), F.expr(f"least(seq + {w - 1}, last) div size"))
    q = q.crossJoin(ends).filter(f"least(seq + {w - 1}, last) >= {w - 1}").withColumn("tx", F.explode(span))
    chunks = F.broadcast(q.groupBy("tx", "size", "last").agg(F.lit(None).cast("long").alias("nil")))
    keys = ["tx", "size", "last"]
    o = objects.groupBy("x", "y").agg(F.array_sort(F.collect_list("oid")).alias("oids")).crossJoin(chunks)
    o = o.select(*keys, "x", "y", F.col("nil").alias("id"), F.col("nil").alias("r2"), "oids")
    rows = o.unionByName(q.select(*keys, "x", "y", F.col("seq").alias("id"), "r2", F.lit(None).cast("array<long>").alias("oids")))

    def tops(key: tuple, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tx, size, last = (k.as_py() for k in key)
        yield from _tops(max(tx * size, w - 1), min((tx + 1) * size, last + 1), batches, w, m)

    # A number of partitions that is asked for stays: chunks take long for their size, so few of them should share a task.
    rows = rows.repartition(int(queries.sparkSession.conf.get("spark.sql.shuffle.partitions")), *keys)
    return rows.groupBy(*keys).applyInArrow(tops, "win long, pos long, oid long, num long")


def _root(v):
    """Whole square roots, rounded down."""
    r = np.sqrt(v.astype(np.float64)).astype(np.int64)
    r -= r * r > v
    return r + ((r + 1) * (r + 1) <= v)


def _spread(a, b):
    """(i, k): every k of a[i]..b[i]-1, for every i."""
    size = np.maximum(b - a, 0)
    i = np.repeat(np.arange(len(size)), size)
    return i, np.arange(len(i)) - np.repeat(np.cumsum(size) - size, size) + a[i]


class Points:
    """Objects by point, points by (y, x). An object is known by its point and its place there by oid, from 0."""

    def __init__(self, x, y, size, oids):
        by = np.lexsort((x, y))
        self.x, self.y, self.size = x[by], y[by], size[by]
        _, at = _spread((np.cumsum(size) - size)[by], np.cumsum(size)[by])
        self.oids, self.n = oids[at], len(oids)
        self.begin = np.cumsum(self.size) - self.size
        self.order = np.empty(self.n, np.int64)
        self.order[np.argsort(self.oids, kind="stable")] = np.arange(self.n)
        self.keys = np.repeat(np.arange(len(by)), self.size) * self.n + self.order
        self.rows, row = np.unique(self.y, return_inverse=True)
        self.west, self.span = self.x.min(), self.x.max() - self.x.min() + 1
        self.cell = row * self.span + self.x - self.west

    def find(self, row, x):
        """Where x lies, or would lie, among a row's points."""
        return np.searchsorted(self.cell, row * self.span + np.clip(x - self.west, 0, self.span))

    def below(self, point, order):
        """How many objects of a point precede the given order by oid."""
        return np.searchsorted(self.keys, point * self.n + order) - self.begin[point]

    def near_rows(self, y, r):
        return _spread(np.searchsorted(self.rows, y - r), np.searchsorted(self.rows, y + r, "right"))

    def ranks(self, x, y, r2):
        """(cuts, points, ranks): per place the points reached, and the ranks of the points' first objects."""
        who, row = self.near_rows(y, _root(r2))
        dy = self.rows[row] - y[who]
        wide = _root(r2[who] - dy * dy)
        k, at = _spread(self.find(row, x[who] - wide), self.find(row, x[who] + wide + 1))
        who, d2 = who[k], (self.x[at] - x[who[k]]) ** 2 + dy[k] ** 2
        top = int(d2.max(initial=0)) + 1
        by = np.argsort(who * top + d2) if len(x) < (1 << 62) // top else np.lexsort((d2, who))
        who, d2, at = who[by], d2[by], at[by]
        cuts, index = np.searchsorted(who, np.arange(len(x) + 1)), np.arange(len(at))
        new = np.ones(len(at), bool)
        new[1:] = (who[1:] != who[:-1]) | (d2[1:] != d2[:-1])
        run = np.maximum.accumulate(np.where(new, index, 0))
        before = np.append(0, np.cumsum(self.size[at]))
        rank = before[run] - before[cuts[who]] + 1
        # Of two points as far away the one whose first object comes later by oid has some of the other's before it.
        first, ahead = self.order[self.begin[at]], 1
        while len(i := np.flatnonzero(run[ahead:] == run[:-ahead])):
            late = np.where(first[i] > first[i + ahead], i, i + ahead)
            np.add.at(rank, late, self.below(at[2 * i + ahead - late], first[late]))
            ahead += 1
        return cuts, at, rank

    def level(self, x, y, d2, own):
        """(i, point): points other than own[i] as far from the place i as d2[i]."""
        i, row = self.near_rows(y, _root(d2))
        rest = d2[i] - (self.rows[row] - y[i]) ** 2
        dx = _root(rest)
        ok = np.flatnonzero(dx * dx == rest)
        i, row, dx = i[ok], row[ok], dx[ok]
        both = np.flatnonzero(dx > 0)
        i, row, px = np.append(i, i[both]), np.append(row, row[both]), np.append(x[i] + dx, x[i[both]] - dx[both])
        at = np.minimum(self.find(row, px), len(self.x) - 1)
        ok = (self.x[at] == px) & (self.y[at] == self.rows[row]) & (at != own[i])
        return i[ok], at[ok]


def _best(value, oid, m):
    """Columns of the m greatest values of each row, greatest first; of equal ones that with the lesser oid."""
    by = np.argsort(oid, kind="stable")
    value, n = value[:, by], len(by)
    if n and value.max(initial=0) < (1 << 62) // n:
        key = value * n + np.arange(n)[::-1]
        if n > 4 * m:
            key = np.partition(key, n - m, 1)[:, n - m :]
        return by[n - 1 - np.sort(key, 1)[:, ::-1][:, :m] % n]
    return by[np.argsort(-value, 1, kind="stable")[:, :m]]


def _tops(begin: int, end: int, batches, w: int, m: int, step: int = 64, held: int = 12_000_000) -> Iterator[pa.RecordBatch]:
    """The windows begin..end-1.

    Of objects at one point the first by oid is the best, so an object can be among the m best only if its point's first object is. Sums
    are kept of first objects. At each shift the m best of these are found, and only their points' further objects are looked at.
    """
    points, (qx, qy, seq, r2) = _split_points(batches)
    if points is None or begin >= end:
        return
    n, count = points.n, len(points.x)
    place, which = np.unique(np.stack([qx, qy, r2], 1), axis=0, return_inverse=True)
    which, kind = which.reshape(-1), np.int32 if n < 1 << 31 else np.int64
    lists: dict = {}
    size = 0

    def matches(a: int, b: int):
        """Points, their first objects' contributions, and times of queries with seq in a..b-1."""
        nonlocal size
        lo, hi = np.searchsorted(seq, (a, b))
        ids = which[lo:hi].tolist()
        if size > held:
            lists.clear()
            size = 0
        new = [i for i in dict.fromkeys(ids) if i not in lists]
        for c in range(0, len(new), step):
            some = place[new[c : c + step]]
            cuts, at, rank = points.ranks(some[:, 0], some[:, 1], some[:, 2])
            at, num = at.astype(kind), (n + 1 - rank).astype(kind)
            size += len(at)
            for k, i in enumerate(new[c : c + step]):
                lists[i] = at[cuts[k] : cuts[k + 1]], num[cuts[k] : cuts[k + 1]]
        if not ids:
            return (np.zeros(0, np.int64),) * 3
        ats, nums = zip(*[lists[i] for i in ids])
        return np.concatenate(ats), np.concatenate(nums), np.repeat(seq[lo:hi], [len(x) for x in ats])

    # Before the first window: all its queries but the newest.
    at, num, _ = matches(begin - w + 1, begin)
    total, touch = np.bincount(at, num, count).astype(np.int64), np.bincount(at, minlength=count)
    index, out, rows = np.full(count, -1), [], 0
    for a in range(begin, end, step):
        b = min(a + step, end)
        at, num, when = matches(a, b)
        old, lost, then = matches(a - w, b - w) if a >= w else matches(0, b - w)
        if a == begin:
            # The query that left before this window isn't in the sums.
            here = then > a - w
            old, lost, then = old[here], lost[here], then[here]
        come, gone = np.bincount(at, num, count).astype(np.int64), np.bincount(old, lost, count).astype(np.int64)
        # m first objects never fall below the m-th largest of the least values: what stays below it isn't looked at.
        low = total - gone
        bar = max(1, np.partition(low, count - m)[count - m] if count >= m else 1)
        cand = np.flatnonzero(total + come >= bar)
        index[cand] = np.arange(len(cand))
        value, hits = np.zeros((b - a, len(cand)), np.int64), np.zeros((b - a, len(cand)), np.int64)
        for who, by, t, sign in ((at, num, when, 1), (old, lost, then + w, -1)):
            ok = np.flatnonzero(index[who] >= 0)
            k = index[who[ok]]
            np.add.at(value, (t[ok] - a, k), sign * by[ok].astype(np.int64))
            np.add.at(hits, (t[ok] - a, k), sign)
        index[cand] = -1
        value, hits = total[cand] + np.cumsum(value, 0), touch[cand] + np.cumsum(hits, 0)
        got = _windows(points, a, cand, value, hits, m, w, *(c[slice(*np.searchsorted(seq, (a - w + 1, b)))] for c in (qx, qy, seq, r2)))
        out.append(got)
        rows += len(got[0])
        if rows >= 1 << 14 or b == end:
            yield _flat(**dict(zip(("win", "pos", "oid", "num"), (np.concatenate(c) for c in zip(*out)))))
            out, rows = [], 0
        total += come - gone
        touch += np.bincount(at, minlength=count) - np.bincount(old, minlength=count)


def _windows(points, a, cand, value, hits, m, w, qx, qy, seq, r2):
    """(win, pos, oid, num) of the windows from a on, of their first objects' values and touches by candidate point."""
    first = points.oids[points.begin[cand]]
    best = _best(value, first, m)
    own = np.unique(best)
    cand, first, value, hits = cand[own], first[own], value[:, own], hits[:, own]
    best = np.searchsorted(own, best)
    shifts = np.arange(len(value))[:, None]
    val, hit = value[shifts, best], hits[shifts, best]
    # The i-th best point has m - i places left at most, and an object falls by a rank at least at each touch for each object before it.
    bar = val[:, m - 1 :] if val.shape[1] == m else 0
    more = np.minimum(np.where(hit > 0, (val - bar) // np.maximum(hit, 1), 0), m - 1 - np.arange(best.shape[1]))
    most = np.zeros(len(cand), np.int64)
    np.maximum.at(most, best, more)
    p, j = _spread(np.ones(len(cand), np.int64), np.minimum(most + 1, points.size[cand]))
    if len(p):
        extra = np.zeros((len(value), len(p)), np.int64)
        kept = np.unique(p)
        d2 = (qx[:, None] - points.x[cand[kept]]) ** 2 + (qy[:, None] - points.y[cand[kept]]) ** 2
        q, c = np.nonzero(d2 <= r2[:, None])
        i, other = points.level(qx[q], qy[q], d2[q, c], cand[kept[c]])
        q, c = q[i], kept[c[i]]
        # Objects as far away that come between the point's first object and this one.
        i, k = _spread(np.searchsorted(p, c), np.searchsorted(p, c, "right"))
        begin = points.begin[cand[c]]
        between = points.below(other[i], points.order[begin[i] + j[k]]) - points.below(other, points.order[begin])[i]
        q = seq[q[i]]
        np.add.at(extra, (np.maximum(q - a, 0), k), between)
        left = np.flatnonzero(q + w - a < len(extra))
        np.subtract.at(extra, (q[left] + w - a, k[left]), between[left])
        later = value[:, p] - j * hits[:, p] - np.cumsum(extra, 0)
        value, first = np.concatenate([value, later], 1), np.append(first, points.oids[points.begin[cand[p]] + j])
        best = _best(value, first, m)
    num = value[shifts, best]
    t, pos = np.nonzero(num > 0)
    return a + t, pos + 1, first[best[t, pos]], num[t, pos]


def _split_points(batches):
    """Points, none if there are no objects, and queries (x, y, seq, r2) by seq, of rows that are points if r2 is null."""
    cols, sizes, oids = [], [], []
    for b in batches:
        cols.append([b.column(c).fill_null(-1).to_numpy(zero_copy_only=False) for c in ("x", "y", "id", "r2")])
        sizes.append(pc.fill_null(pc.list_value_length(b.column("oids")), 0).to_numpy(zero_copy_only=False))
        oids.append(b.column("oids").flatten().to_numpy(zero_copy_only=False))
    x, y, i, r2 = (np.concatenate(c) for c in zip(*cols))
    size, o, q = np.concatenate(sizes).astype(np.int64), np.flatnonzero(r2 < 0), np.flatnonzero(r2 >= 0)
    q = q[np.argsort(i[q], kind="stable")]
    return Points(x[o], y[o], size[o], np.concatenate(oids)) if len(o) else None, (x[q], y[q], i[q], r2[q])
