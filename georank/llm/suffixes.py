"""Operator 5: removal of repeated byte strings by column-wise construction of a collection's suffix order.

Many short reads are put in order at once, column by column from the right: a round puts one more symbol before each
read's suffix, carries the Burrows-Wheeler permutation of the suffixes on by a stable sort of that column's symbols, and the
common prefixes of neighbours by range minima. Rounds are as many as the longest read is long, so whole texts can't be
the reads (20,000 words would mean 120,000 rounds over all of them). Instead:

1. Every window of `length` bytes has an anchor: its least 32-byte hash, the first of equals. Consecutive windows with one
   anchor make a read. Equal windows have equal anchors, so only reads with the same anchor hash need be compared.
2. Reads whose anchor hash occurs once hold no repeated window. Equal reads are one read with a multiplicity.
3. Equal windows also stand alike to their anchor. Reads are laid side by side by their anchors, so that equal windows begin
   in one column: a round then needs the order of the column before and no other, and its state is one entry for each read
   instead of one for each suffix so far. Windows whose common prefix reaches `length` occur more than once.
4. Reads are dealt to buckets by anchor hash. An anchor with more than `HOT` kinds of read is dealt again: its reads are cut
   where the least hashes under other seeds change, and, if that leaves too many with one key, into single windows.

The column files of the external method are the bucket's symbols, stored column after column and read once in sequence; they
and the state are held in memory, bounded by BUCKET and HOT. Executors must not share local files, so none are written.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Hasher, dropped, mix, sliced, stored, table, text_bytes

LENGTH, GRAM = 200, 32
#: Reads of a bucket, about; kinds of read from which an anchor is dealt again; seeds of the second deal.
BUCKET, HOT, SEEDS = 3000, 6000, 3


def anchors(grams: np.ndarray, width: int) -> np.ndarray:
    """For each window of `width` entries, the place of its least entry, the first of equals."""
    at, best, span = np.arange(len(grams), dtype=np.int64), grams, 1
    while 2 * span <= width:
        right = best[span:] < best[:-span]
        at = np.where(right, at[span:], at[:-span])
        best = np.where(right, best[span:], best[:-span])
        span *= 2
    if width > span:
        gap = width - span
        right = best[gap:] < best[:-gap]
        at = np.where(right, at[gap:], at[:-gap])
    return at


def reads_of(col, length: int):
    """(row, start in row, windows, place of the anchor in the read, anchor hash, read hash) of each text's reads, as arrays."""
    data, off = text_bytes(col)
    none = [np.zeros(0, np.int64)] * 6
    if len(data) < length:
        return none
    place = np.arange(len(data) - GRAM + 1)
    grams = Hasher(data)(place, place + GRAM)
    anchor = anchors(grams, length - GRAM + 1)
    ok = np.zeros(len(anchor), bool)
    for a, b in zip(off[:-1], off[1:]):
        ok[a : max(a, b - length + 1)] = True
    starts = np.flatnonzero(ok)
    if not len(starts):
        return none
    own = anchor[starts]
    row = np.searchsorted(off, starts, "right") - 1
    new = np.flatnonzero(np.concatenate([[True], (own[1:] != own[:-1]) | (row[1:] != row[:-1]) | (starts[1:] != starts[:-1] + 1)]))
    begin, count = starts[new], np.diff(np.append(new, len(starts)))
    return row[new], begin - off[row[new]], count, own[new] - begin, grams[own[new]].view(np.int64), Hasher(data, 1)(begin, begin + count + length - 1).view(np.int64)


def cut_again(data: bytes, windows: int, anchor: int, length: int, fine: bool):
    """(start, windows, key, hash) of the parts of a read whose windows have the same least hashes under all seeds; if fine, of its windows."""
    raw = np.frombuffer(data, np.uint8)
    if fine:
        start, count = np.arange(windows), np.ones(windows, np.int64)
        key = Hasher(raw)(start, start + length)
    else:
        place = np.arange(len(raw) - GRAM + 1)
        grams = Hasher(raw)(place, place + GRAM)
        least = [anchors(mix(grams + np.uint64(seed)), length - GRAM + 1)[:windows] for seed in range(1, SEEDS + 1)]
        new = np.zeros(windows, bool)
        new[0] = True
        for x in least:
            new[1:] |= x[1:] != x[:-1]
        start = np.flatnonzero(new)
        count = np.diff(np.append(start, windows))
        key = np.full(len(start), np.uint64(anchor & (1 << 64) - 1))
        for x in least:
            key = mix(key * np.uint64(3) + grams[x[start]])
    return start, count, key.view(np.int64), Hasher(raw, 1)(start, start + count + length - 1).view(np.int64)


def ordered_columns(reads: list[bytes], at: np.ndarray):
    """For each column from the last, (column, order, common prefix with the one before) of the suffixes that begin there.

    Reads lie with their places `at` in one column, number max(at). A suffix goes to its read's end.
    """
    size = np.array([len(r) for r in reads], np.int64)
    first = int(at.max(initial=0)) - at
    past = first + size
    wide = int(past.max(initial=0))
    column = np.concatenate([np.arange(a, b) for a, b in zip(first, past)]) if len(reads) else np.zeros(0, np.int64)
    owner = np.repeat(np.arange(len(reads)), size)
    by = np.argsort(column, kind="stable")
    # The column file: all symbols of a column side by side, in the order of reads.
    symbols, owner = np.frombuffer(b"".join(reads), np.uint8)[by], owner[by]
    edge = np.concatenate([[0], np.cumsum(np.bincount(column, minlength=wide))])
    entering = np.argsort(past, kind="stable")
    enter = np.searchsorted(past[entering], np.arange(wide + 2))
    order, lcp = np.zeros(0, np.int64), np.zeros(0, np.int32)
    symbol = np.zeros(len(reads), np.uint8)
    for j in range(wide - 1, -1, -1):
        stay = first[order] <= j
        if not stay.all():  # what stood before a read that is gone now stands before its successor
            kept = np.flatnonzero(stay)
            lcp = np.minimum.reduceat(lcp[: kept[-1] + 1], np.concatenate([[0], kept[:-1] + 1])) if len(kept) else lcp[:0]
            order = order[kept]
        fresh = entering[enter[j + 1] : enter[j + 2]]
        if len(fresh):
            order = np.concatenate([fresh, order])
            lcp = np.concatenate([np.zeros(len(fresh), np.int32), lcp])
            lcp[len(fresh) : len(fresh) + 1] = 0
        symbol[owner[edge[j] : edge[j + 1]]] = symbols[edge[j] : edge[j + 1]]
        now = symbol[order]
        rank = np.argsort(now, kind="stable")
        now = now[rank]
        value = np.zeros(len(rank), np.int32)
        same = np.flatnonzero(now[1:] == now[:-1]) + 1
        if len(same):
            cut = np.empty(2 * len(same), np.int64)
            cut[::2], cut[1::2] = rank[same - 1] + 1, rank[same] + 1
            value[same] = np.minimum.reduceat(np.append(lcp, np.int32(0)), cut)[::2] + 1
        order, lcp = order[rank], value
        yield j, order, lcp


def repeated(reads: list[bytes], at: list[int], times: list[int], length: int) -> list[tuple[list[int], list[int]]]:
    """For each read, the runs (starts, past) of offsets whose `length` bytes occur more than once in the collection."""
    at, weight = np.array(at, np.int64), np.array(times, np.float64)
    size = np.array([len(r) for r in reads], np.int64)
    first = int(at.max(initial=0)) - at
    whose, where = [], []
    for j, order, lcp in ordered_columns(reads, at):
        long = first[order] + size[order] - j >= length
        if long.any():
            group = np.cumsum(lcp < length)
            hit = order[long & (np.bincount(group, weight[order] * long)[group] > 1)]
            if len(hit):
                whose.append(hit)
                where.append(j - first[hit])
    out: list[tuple[list[int], list[int]]] = [([], []) for _ in reads]
    if whose:
        r, k = np.concatenate(whose), np.concatenate(where)
        by = np.lexsort((k, r))
        r, k = r[by], k[by]
        start = np.flatnonzero(np.concatenate([[True], (r[1:] != r[:-1]) | (k[1:] != k[:-1] + 1)]))
        past = np.append(start[1:], len(r)) - 1
        for i, a, b in zip(r[start].tolist(), k[start].tolist(), (k[past] + 1).tolist()):
            out[i][0].append(a)
            out[i][1].append(b)
    return out


KIND = "anchor long, ident long, windows int"
MARK = f"{KIND}, a array<int>, b array<int>"


def marks(kinds: DataFrame, length: int, level: int = 0, hot: int = HOT) -> DataFrame:
    """For each kind of read (anchor, ident, windows, at, times, bytes) that has any, the runs of repeated windows."""
    spark = kinds.sparkSession
    total = kinds.count()
    buckets = max(1, total // BUCKET)

    def build(t: pa.Table) -> pa.Table:
        runs = repeated(t.column("bytes").to_pylist(), t.column("at").to_pylist(), t.column("times").to_pylist(), length)
        keep = [i for i, r in enumerate(runs) if r[0]]
        part = t.select(["anchor", "ident", "windows"]).take(pa.array(keep, pa.int64()))
        return part.append_column("a", pa.array([runs[i][0] for i in keep], pa.list_(pa.int32()))).append_column("b", pa.array([runs[i][1] for i in keep], pa.list_(pa.int32())))

    many = kinds.groupBy("anchor").agg(F.count("*").alias("n")).filter(F.col("n") > hot).select("anchor")
    crowded = level < 2 and total > hot and bool(many.limit(1).collect())
    cool = kinds.join(many, "anchor", "left_anti") if crowded else kinds
    found = cool.withColumn("bucket", F.pmod(F.xxhash64("anchor"), F.lit(buckets))).groupBy("bucket").applyInArrow(build, MARK)
    if not crowded:
        return found

    def again(batches):
        for batch in batches:
            for i in range(batch.num_rows):
                key = [batch.column(c)[i].as_py() for c in range(5)]
                data = batch.column(5)[i].as_py()
                start, count, new, ident = cut_again(data, key[2], key[0], length, level == 1)
                n = len(start)
                cols = [pa.array([v] * n, k) for v, k in zip((key[0], key[1], key[2], key[4]), (pa.int64(), pa.int64(), pa.int32(), pa.int64()))]
                cols += [pa.array(start.astype(np.int32)), pa.array(new), pa.array(ident), pa.array(count.astype(np.int32)), pa.array([data[a : a + c + length - 1] for a, c in zip(start.tolist(), count.tolist())], pa.binary())]
                yield pa.RecordBatch.from_arrays(cols, ["anchor", "ident", "windows", "times", "start", "key", "part", "n", "bytes"])

    warm = kinds.join(many, "anchor", "left_semi").select("anchor", "ident", "windows", "at", "times", "bytes")
    parts = stored(warm.mapInArrow(again, f"{KIND}, times long, start int, key long, part long, n int, bytes binary"))
    # A key's reads lie alike to their anchor in bytes before; within one key the parts begin at their least hash, so `at` follows from it.
    new = parts.groupBy("key", "part", "n").agg(F.sum("times").alias("times"), F.first("bytes").alias("bytes"))
    shared = new.groupBy("key").agg(F.sum("times").alias("t")).filter("t > 1").select("key")
    new = new.join(shared, "key").select(F.col("key").alias("anchor"), F.col("part").alias("ident"), F.col("n").alias("windows"), "times", "bytes")
    new = stored(new.mapInArrow(lambda batches: _placed(batches, length, level == 1), f"{KIND}, at int, times long, bytes binary"))
    runs = marks(new, length, level + 1, hot).select(F.col("anchor").alias("key"), F.col("ident").alias("part"), F.col("windows").alias("n"), "a", "b")
    back = parts.drop("bytes", "times").join(runs, ["key", "part", "n"])
    shift = lambda c: F.transform(c, lambda x: x + F.col("start"))
    back = back.select("anchor", "ident", "windows", shift("a").alias("a"), shift("b").alias("b"))
    return found.unionByName(back.groupBy("anchor", "ident", "windows").agg(F.flatten(F.collect_list("a")).alias("a"), F.flatten(F.collect_list("b")).alias("b")))


def _placed(batches, length: int, fine: bool):
    """Adds `at`: where the least hash under the first seed stands in a part; single windows all begin alike."""
    for batch in batches:
        at = []
        for x in batch.column(4).to_pylist():
            if fine:
                at.append(0)
                continue
            raw = np.frombuffer(x, np.uint8)
            place = np.arange(length - GRAM + 1)
            at.append(int(np.argmin(mix(Hasher(raw)(place, place + GRAM) + np.uint64(1)))))
        cols = [batch.column(0), batch.column(1), batch.column(2), pa.array(at, pa.int32()), batch.column(3), batch.column(4)]
        yield pa.RecordBatch.from_arrays(cols, ["anchor", "ident", "windows", "at", "times", "bytes"])


def spans(docs: DataFrame, length: int = LENGTH, hot: int = HOT) -> DataFrame:
    """(rid, spans): each row's byte ranges [start, past) that are covered by repeated strings; rows without any are left out. docs has rid, text."""

    def cut(batches):
        for batch in sliced(batches, "text", 1 << 20):
            row, start, count, at, anchor, ident = reads_of(batch.column(1), length)
            rid = batch.column(0).to_numpy()[row]
            yield pa.RecordBatch.from_pydict({"anchor": pa.array(anchor), "ident": pa.array(ident), "rid": pa.array(rid), "start": pa.array(start.astype(np.int32)), "windows": pa.array(count.astype(np.int32)), "at": pa.array(at.astype(np.int32))})

    reads = stored(docs.select("rid", "text").mapInArrow(cut, "anchor long, ident long, rid long, start int, windows int, at int"))
    many = reads.groupBy("anchor").agg(F.count("*").alias("n")).filter("n > 1").select("anchor")
    shared = stored(reads.join(many, "anchor", "left_semi"))
    dropped(reads)
    kinds = shared.groupBy("anchor", "ident", "windows", "at").agg(F.count("*").alias("times"), F.min(F.struct("rid", "start")).alias("from"))
    asked = kinds.groupBy(F.col("from.rid").alias("rid")).agg(F.collect_list(F.struct("anchor", "ident", "windows", "at", "times", F.col("from.start").alias("start"))).alias("asked"))

    def take(batches):
        for batch in batches:
            for i in range(batch.num_rows):
                data = (batch.column(0)[i].as_py() or "").encode()
                some = batch.column(1)[i].values
                f = {n: some.field(n) for n in ("anchor", "ident", "windows", "at", "times", "start")}
                text = [data[s : s + w + length - 1] for s, w in zip(f["start"].to_pylist(), f["windows"].to_pylist())]
                yield pa.RecordBatch.from_pydict({"anchor": f["anchor"], "ident": f["ident"], "windows": f["windows"], "at": f["at"], "times": f["times"], "bytes": pa.array(text, pa.binary())})

    texts = stored(docs.join(asked, "rid").select("text", "asked").mapInArrow(take, f"{KIND}, at int, times long, bytes binary"))
    runs = stored(marks(texts, length, hot=hot))
    dropped(texts)
    hits = shared.join(runs, ["anchor", "ident", "windows"]).select("rid", F.explode(F.arrays_zip("a", "b")).alias("r"), "start")
    return hits.groupBy("rid").agg(F.collect_list(F.struct((F.col("start") + F.col("r.a")).alias("a"), (F.col("start") + F.col("r.b") + length - 1).alias("b"))).alias("spans"))


def remove(docs: DataFrame, length: int = LENGTH, digests: bool = False, hot: int = HOT) -> DataFrame:
    """All columns of docs, with the text that is left (invalid UTF-8 at cuts is replaced), n_bytes, n_removed and n_spans; or doc_id and digests.

    Null and empty texts have no bytes and stay as they are. Texts of any length are cut into reads as a whole. Repeated rows of
    `length` bytes or more lose all that is repeated, as every copy is judged on the input. An empty table gives no rows. Rows are
    told apart by their place in the input, which must read the same each time (a table or files), not by doc_id. Columns of docs
    keep their values whatever their names: a count whose name docs has is left out.
    """
    taken = docs.columns
    counts = [c for c in ("n_bytes", "n_removed", "n_spans") if c not in taken]
    packed = docs.select(F.monotonically_increasing_id().alias("rid"), docs["text"].alias("text"), docs["doc_id"].cast("long").alias("doc_id"), *([] if digests else [F.struct(*[docs[c].alias(f"c{i}") for i, c in enumerate(taken)]).alias("whole")]))
    found = spans(packed.select("rid", "text"), length, hot)
    made = "n_bytes long, n_removed long, n_spans long, kept_sha256 string" + ", kept binary" * (not digests)

    def strip(batches):
        for batch in sliced(batches, "text", 4 << 20):
            n, gone, runs, digest, left = [], [], [], [], []
            for t, s in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist()):
                data = (t or "").encode()
                out, at, lost, k = [], 0, 0, 0
                for a, b in sorted((x["a"], x["b"]) for x in s or ()):
                    if a > at or not k:
                        out.append(data[at:a])
                        k += 1
                        lost += b - a
                    else:
                        lost += max(0, b - at)
                    at = max(at, b)
                out.append(data[at:])
                rest = b"".join(out)
                n.append(len(data))
                gone.append(lost)
                runs.append(k)
                digest.append(hashlib.sha256(rest).hexdigest())
                left.append(rest)
            cols = [batch.column(0), pa.array(n, pa.int64()), pa.array(gone, pa.int64()), pa.array(runs, pa.int64()), pa.array(digest, pa.string())]
            yield pa.RecordBatch.from_arrays([*cols, *([] if digests else [pa.array(left, pa.binary())]), batch.column(3)], [*names, last])

    names = ["doc_id" if digests else "rid", "n_bytes", "n_removed", "n_spans", "kept_sha256", *([] if digests else ["kept"])]
    joined = packed.join(found, "rid", "left")
    if digests:
        last = "rid"
        return joined.select("doc_id", "text", "spans", "rid").mapInArrow(strip, f"doc_id long, {made}, rid long").drop("rid")
    last = "whole"
    kind = packed.schema["whole"].dataType.simpleString()
    got = joined.select("rid", "text", "spans", "whole").mapInArrow(strip, f"rid long, {made}, whole {kind}")
    cut = F.when(F.col("n_removed") > 0, F.expr("make_valid_utf8(cast(kept as string))")).otherwise(F.col(f"whole.c{taken.index('text')}"))
    return got.select(*[(cut if c == "text" else F.col(f"whole.c{i}")).alias(c) for i, c in enumerate(taken)], *counts)


def op5_suffixes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove(table(spark, sf_dir, "documents").select("doc_id", "text"), digests=True)
