"""Operator 3: n-gram Jaccard self-join by vertical partitioning.

A document is its set of distinct shingles, put in one global order: rare shingles first, as far as a sketch of fixed
size tells, then by hash (any order gives right results; this one gives few candidates). The order is cut into fragments that
hold equal shares of all shingles. Linked documents share `SHARE` of their first shingles, so those prefixes alone are listed
to find candidates. Candidates' sets are cut at the fragments' borders; each fragment's overlaps are counted by themselves,
side by side with the others, and summed per pair.

Only classes are asked for, so pairs within one class needn't be looked at: documents with the same words are one node, and
nodes that share a list are first measured against one or two hubs of that list, so many times as it is long. After that, all pairs of
nodes that share a list and are still in different classes are counted, without exception.

Many copies of one text that aren't near enough to its hub would still pair each with each. Two sets x, y that have o(x), o(y)
shingles of hub h share at most min(o(x), o(y)) of h's, so if a link needs more, they must share shingles that aren't h's; h may as well be any other set, such as what most copies beside the hub have.
Such pairs are found through those few shingles alone.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import Hasher, dropped, lowered, mix, sliced, stored, table, text_bytes, word_spans
from .components import components

#: Prefix shingles that linked documents share at least; fragments; log2 of the sketch's counters.
SHARE, FRAGMENTS, SKETCH_BITS = 3, 4, 22
#: Hubs of a list; hubs that a node is measured against; a node with at least this share of its shingles in its hub's set is near it.
HUBS, TRIES, NEAR = 2, 3, 0.7
#: A hub of fewer nodes is measured against those alone with which it shares as many lists as linked sets do: so few nodes make few pairs.
FEW = 8
#: Of the nodes near a hub, the nearest ones that all others are compared with.
NEAREST = 16
CHUNK = 1 << 16
#: Log2 of the bits of the filter that keeps texts without candidates out of a pass; it only saves work.
FILTER_BITS = 24


def shingle_sets(col, width: int):
    """For each text of the column: sorted distinct 64-bit shingles, and two sums that identify its word sequence."""
    data, off = text_bytes(col)
    starts, ends, first = word_spans(data, off)
    if not len(starts):
        for _ in range(len(off) - 1):
            yield np.zeros(0, np.uint64), 0, 0
        return
    h = Hasher(lowered(data))(starts, ends)
    place = np.arange(len(h)) - np.repeat(first[:-1], np.diff(first))
    with np.errstate(over="ignore"):
        sums = [np.concatenate([[np.uint64(0)], np.cumsum(mix(h + mix(place.astype(np.uint64) + np.uint64(salt))))]) for salt in (1, 1 << 40)]
        ids = [(x[first[1:]] - x[first[:-1]]).view(np.int64) for x in sums]
        gram = h[: max(0, len(h) - width + 1)].copy()
        for k in range(1, width):
            gram = mix(gram + np.uint64(k)) + h[k : k + len(gram)]
        gram = mix(gram)
    for i in range(len(off) - 1):
        a, b = int(first[i]), int(first[i + 1])
        if b - a >= width:
            own = np.unique(gram[a : b - width + 1])
        elif b > a:
            with np.errstate(over="ignore"):
                one = np.array([b - a], np.uint64)
                for x in h[a:b]:
                    one = mix(one * np.uint64(0x9E3779B97F4A7C15) + x)
            own = one
        else:
            own = np.zeros(0, np.uint64)
        yield own, int(ids[0][i]), int(ids[1][i])


def frequency_classes(docs: DataFrame, width: int) -> np.ndarray:
    """log2 of how often shingles fall to each counter of a sketch. Its size is fixed, 2**SKETCH_BITS bytes; it goes to all tasks."""
    import zstandard

    def count(batches):
        total = np.zeros(1 << SKETCH_BITS, np.uint32)
        for batch in sliced(batches, "text"):
            sets = [s for s, _, _ in shingle_sets(batch.column(0), width)]
            if sets:
                total += np.bincount((np.concatenate(sets) >> np.uint64(64 - SKETCH_BITS)).astype(np.int64), minlength=len(total)).astype(np.uint32)
        if total.any():
            z = zstandard.ZstdCompressor(level=1)
            for k in range(0, len(total), CHUNK):
                planes = np.ascontiguousarray(total[k : k + CHUNK].view(np.uint8).reshape(-1, 4).T)
                yield pa.RecordBatch.from_pydict({"chunk": pa.array([k // CHUNK], pa.int32()), "counts": pa.array([z.compress(planes.tobytes())], pa.binary())})

    def add(t: pa.Table) -> pa.Table:
        z, total = zstandard.ZstdDecompressor(), np.zeros(CHUNK, np.uint64)
        for x in t.column("counts").to_pylist():
            total += np.ascontiguousarray(np.frombuffer(z.decompress(x), np.uint8).reshape(4, -1).T).view("<u4").ravel()
        return pa.table({"chunk": t.column("chunk")[:1], "classes": pa.array([np.floor(2 * np.log2(total + 1.0)).astype(np.uint8).tobytes()], pa.binary())})

    found = docs.select("text").mapInArrow(count, "chunk int, counts binary").groupBy("chunk").applyInArrow(add, "chunk int, classes binary")
    out = np.zeros(1 << SKETCH_BITS, np.uint8)
    for chunk, classes in found.collect():
        out[chunk * CHUNK : (chunk + 1) * CHUNK] = np.frombuffer(classes, np.uint8)
    return out


def borders(freq: np.ndarray, fragments: int = FRAGMENTS) -> tuple[np.ndarray, np.ndarray]:
    """For each frequency class, the share of all shingles before it and its own, so that a shingle's place in the order is known."""
    mass = np.bincount(freq, 2.0 ** (freq / 2.0), 256)
    before = np.cumsum(mass) - mass
    return before / mass.sum() * fragments, mass / mass.sum() * fragments


def fragment_of(own: np.ndarray, freq: np.ndarray, edge) -> np.ndarray:
    """The fragment of each shingle: its place in the order by class, then by the hash's bits that the sketch doesn't use."""
    k = freq[(own >> np.uint64(64 - SKETCH_BITS)).astype(np.int64)]
    inside = (own & np.uint64(0xFFFFFFFF)).astype(np.float64) / 2.0**32
    return np.minimum((edge[0][k] + inside * edge[1][k]).astype(np.int64), FRAGMENTS - 1)


def prefixes(docs: DataFrame, width: int, percent: int, classes) -> DataFrame:
    """row, doc_id, n (set size), d1, d2 (identity of the word sequence) and the prefix of each document."""

    def run(batches):
        freq = classes.value
        for batch in sliced(batches, "text"):
            n, d1, d2, pre = [], [], [], []
            for own, a, b in shingle_sets(batch.column(2), width):
                most = len(own) - -(-percent * len(own) // 100) + SHARE
                order = np.argsort(freq[(own >> np.uint64(64 - SKETCH_BITS)).astype(np.int64)], kind="stable")[:most]
                n.append(len(own))
                d1.append(a)
                d2.append(b)
                pre.append(own[order].view(np.int64))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(n, pa.int32()), pa.array(d1, pa.int64()), pa.array(d2, pa.int64()), pa.array(pre, pa.list_(pa.int64()))], ["row", "doc_id", "n", "d1", "d2", "prefix"])

    return docs.select("row", "doc_id", "text").mapInArrow(run, "row long, doc_id long, n int, d1 long, d2 long, prefix array<long>")


def fragments(docs: DataFrame, wanted: DataFrame, width: int, classes) -> DataFrame:
    """(node, frag, part): the wanted nodes' sets, and now and then others', cut at the fragments' borders. A node is the row of one of its documents.

    A bit filter of fixed size lets most texts of no candidate go by unhashed. What passes it by chance does no harm: joins are by node.
    """
    spark = docs.sparkSession
    bit = F.shiftrightunsigned(F.xxhash64(F.col("node")), 64 - FILTER_BITS)

    def lay(t: pa.Table) -> pa.Table:
        out = np.zeros(CHUNK, np.uint8)
        out[t.column("byte").to_numpy() % CHUNK] = t.column("v").to_numpy()
        return pa.table({"chunk": pa.array([t.column("byte")[0].as_py() // CHUNK], pa.int32()), "bits": pa.array([out.tobytes()], pa.binary())})

    bits = np.zeros((1 << FILTER_BITS) // 8, np.uint8)
    flat = wanted.select(F.floor(bit / 8).cast("long").alias("byte"), F.pmod(bit, F.lit(8)).cast("int").alias("b")).groupBy("byte").agg(F.bit_or(F.expr("shiftleft(1, b)")).cast("long").alias("v"))
    for chunk, x in flat.groupBy(F.floor(F.col("byte") / CHUNK).cast("int").alias("chunk")).applyInArrow(lay, "chunk int, bits binary").collect():
        bits[chunk * CHUNK : (chunk + 1) * CHUNK] = np.frombuffer(x, np.uint8)
    shared = spark.sparkContext.broadcast(bits.tobytes())

    def run(batches):
        mask, freq = np.frombuffer(shared.value, np.uint8), classes.value
        edge = borders(freq)
        for batch in batches:
            at = batch.column(1).to_numpy()
            keep = (mask[at >> 3] >> (at & 7).astype(np.uint8)) & 1
            for part in sliced([batch.filter(pa.array(keep.astype(bool)))], "text"):
                rows: dict[str, list] = {"node": [], "frag": [], "part": []}
                for node, (own, _, _) in zip(part.column(0).to_pylist(), shingle_sets(part.column(2), width)):
                    frag = fragment_of(own, freq, edge)
                    for f in range(FRAGMENTS):
                        for k, v in zip(rows, (node, f, own[frag == f].view(np.int64))):
                            rows[k].append(v)
                kinds = [pa.int64(), pa.int32(), pa.list_(pa.int64())]
                yield pa.RecordBatch.from_arrays([pa.array(v, k) for v, k in zip(rows.values(), kinds)], list(rows))

    at = F.shiftrightunsigned(F.xxhash64(F.col("row")), 64 - FILTER_BITS)
    return docs.select("row", at.alias("at"), "text").mapInArrow(run, "node long, frag int, part array<long>")


def least_overlap(na, nb, percent: int):
    """Shingles that sets of these sizes have in common if they are linked."""
    return F.ceil(percent * (F.col(na) + F.col(nb)) / (100 + percent)).cast("long")


def cut_sets(pairs: DataFrame, docs: DataFrame, width: int, classes) -> DataFrame:
    """The fragments of all sets in the pairs, stored."""
    ends = pairs.select(F.col("a").alias("node")).union(pairs.select(F.col("b").alias("node"))).distinct()
    return stored(fragments(docs, ends, width, classes), "fragments")


def overlaps(pairs: DataFrame, cut: DataFrame, lacks: bool = False) -> DataFrame:
    """(a, na, b, nb, o): each pair's overlap, counted fragment by fragment and summed; with lacks, also the shingles of one that the other has not."""
    left = pairs.join(cut.select(F.col("node").alias("a"), "frag", F.col("part").alias("x")), "a")
    both = left.join(cut.select(F.col("node").alias("b"), "frag", F.col("part").alias("y")), ["b", "frag"])
    count = F.size(F.array_intersect("x", "y")).alias("common")
    part = both.select("a", "na", "b", "nb", count, *([F.array_except("x", "y").alias("rest"), F.array_except("y", "x").alias("gone")] if lacks else []))
    more = [F.flatten(F.collect_list(c)).alias(c) for c in ("rest", "gone")] if lacks else []
    return part.groupBy("a", "na", "b", "nb").agg(F.sum("common").alias("o"), *more)


def to_likeliest(pairs: DataFrame, cut: DataFrame, percent: int) -> tuple[DataFrame, DataFrame]:
    """Overlaps of nodes with their hubs: first with the hub that most nodes have, then, for nodes not linked to it, with the others."""
    turn = F.row_number().over(Window.partitionBy("a").orderBy(F.desc("many"), "b"))
    many = stored(pairs.withColumn("k", turn), "turns")
    cols = ("a", "na", "b", "nb")
    first = stored(overlaps(many.filter("k = 1").select(*cols), cut, lacks=True), "measured")
    again = many.filter("k > 1").join(linked(first, percent).select("a"), "a", "left_anti").select(*cols)
    second = stored(overlaps(again, cut, lacks=True), "measured")
    dropped(many)
    return first, second


def linked(found: DataFrame, percent: int) -> DataFrame:
    return found.filter(100 * F.col("o") >= percent * (F.col("na") + F.col("nb") - F.col("o"))).select("a", "b")


def by_prefix(pairs: DataFrame, nodes: DataFrame, percent: int) -> DataFrame:
    """The pairs whose prefixes share as many shingles as those of linked sets of their sizes do."""
    pair = pairs.join(nodes.select(F.col("node").alias("a"), F.col("prefix").alias("pa")), "a").join(nodes.select(F.col("node").alias("b"), F.col("prefix").alias("pb")), "b")
    need = least_overlap("na", "nb", percent) + F.least(F.size("pa") - F.col("na"), F.size("pb") - F.col("nb"))
    return pair.filter(F.size(F.array_intersect("pa", "pb")) >= need).select("a", "na", "b", "nb")


def to_hubs(shared: DataFrame, fits) -> DataFrame:
    """Pairs (a, na, b, nb, many) of a node and those hubs of its lists with which it shares most lists; many: the hub's nodes.

    A list's hubs are the node whose own lists are longest, so one with few shingles that others lack, and some by hash.
    Texts that have a shingle in common by chance are pairs of their own mostly, and more of them in larger tables: they are left to `by_prefix`.
    """
    hash_ = [F.min(F.struct(F.xxhash64("node", F.lit(i)).alias("h"), "node", "n")).alias(f"h{i}") for i in range(1, HUBS)]
    hubs = shared.groupBy("token").agg(F.max(F.struct("weight", "node", "n")).alias("h0"), *hash_)
    hubs = hubs.select("token", F.explode(F.array_distinct(F.array(*[F.struct(f"h{i}.node", f"h{i}.n") for i in range(HUBS)]))).alias("h"))
    rows = shared.select("token", "node", "n").join(hubs, "token").filter("h.node != node").groupBy("node", "n", "h").agg(F.count("*").alias("c"))
    rows = rows.filter(fits(F.col("n"), F.col("h.n")))
    best = F.row_number().over(Window.partitionBy("node").orderBy(F.desc("c"), "h.node"))
    rows = rows.withColumn("k", best).filter(F.col("k") <= TRIES).select(F.col("node").alias("a"), F.col("n").alias("na"), F.col("h.node").alias("b"), F.col("h.n").alias("nb"), "c")
    rows = rows.join(rows.groupBy("b").agg(F.count("*").alias("many")), "b")
    return rows.filter((F.col("many") >= FEW) | (F.col("c") >= F.least(F.lit(SHARE), "na", "nb"))).select("a", "na", "b", "nb", "many")


def candidates(own: DataFrame, percent: int, fits) -> DataFrame:
    """Every pair (a, na, b, nb) of nodes of different classes that may be linked, but for those that `beside_hub` finds.

    A linked pair has a shingle in common among the first of each set: for the smaller set those that it can lack in a
    set of its size, for the larger those that it can lack in any. own has token, at, node, n, comp, and hub and o where the
    node is near a hub.
    """
    small = own.filter(F.col("at") <= F.col("n") - F.ceil(2 * percent * F.col("n") / (100 + percent)))
    large = own.filter(F.col("at") <= F.col("n") - F.ceil(percent * F.col("n") / 100))
    x, y = (df.select("token", *[F.col(c).alias(f"{c}_{i}") for c in ("node", "n", "comp", "hub", "o")]) for df, i in ((small, "a"), (large, "b")))
    need = least_overlap("n_a", "n_b", percent)
    first = (F.col("n_a") < F.col("n_b")) | ((F.col("n_a") == F.col("n_b")) & (F.col("node_a") < F.col("node_b")))
    open_ = F.coalesce(F.col("hub_a") != F.col("hub_b"), F.lit(True)) | (F.least("o_a", "o_b") >= need)
    pair = x.join(y, "token").filter(first & (F.col("comp_a") != F.col("comp_b")) & fits(F.col("n_a"), F.col("n_b")) & open_)
    return pair.select(F.col("node_a").alias("a"), F.col("n_a").alias("na"), F.col("node_b").alias("b"), F.col("n_b").alias("nb")).distinct()


def centred(near: DataFrame) -> DataFrame:
    """near, measured against each hub with what most nodes beside it have besides and without what most of them lack.

    A hub is one copy among others: its own changes would be what all others have in common. What most nodes have is no longer than
    twice what a node has on average, so a hub's two lists are no longer than a few sets.
    """
    size = near.groupBy("hub").agg(F.count("*").alias("size"))
    both = near.select("hub", F.explode(F.concat(F.transform("rest", lambda t: F.struct(t.alias("token"), F.lit(True).alias("has"))), F.transform("gone", lambda t: F.struct(t.alias("token"), F.lit(False).alias("has"))))).alias("e"))
    most = both.groupBy("hub", "e.token", "e.has").agg(F.count("*").alias("c")).filter("c > 1").join(size, "hub").filter("2 * c > size")
    pick = lambda has: F.array_sort(F.collect_list(F.when(F.col("has") == has, F.col("token"))))
    most = most.groupBy("hub").agg(pick(True).alias("more"), pick(False).alias("less"))
    none = F.array().cast("array<bigint>")
    out = near.join(most, "hub", "left").withColumns({c: F.coalesce(c, none) for c in ("more", "less")})
    rest = F.concat(F.array_except("rest", "more"), F.array_except("less", "gone"))
    gone = F.concat(F.array_except("gone", "less"), F.array_except("more", "rest"))
    nh = (F.col("nh") + F.size("more") - F.size("less")).cast("long").alias("nh")
    out = out.select("node", "n", "hub", nh, rest.alias("rest"), gone.alias("gone"))
    return out.withColumn("o", F.col("n") - F.size("rest"))


def beside_hub(near: DataFrame, percent: int, fits) -> DataFrame:
    """Pairs (a, na, b, nb) of nodes of one hub, of different classes, that may be linked and must then share shingles which the hub lacks."""
    # Of the `rest` that the hub lacks, any link of the node takes at least `least` shingles: only the others' number, plus one, is indexed.
    least = F.greatest(F.lit(1), F.ceil(percent * (F.col("n") + F.ceil(percent * F.col("n") / 100)) / (100 + percent)) - F.col("o"))
    near = near.withColumn("least", least.cast("long"))
    rows = near.select("hub", F.explode("rest").alias("token"), "node")
    often = rows.groupBy("hub", "token").agg(F.count("*").alias("times")).filter("times > 1")
    rows = rows.join(often, ["hub", "token"]).groupBy("node").agg(F.array_sort(F.collect_list(F.struct("times", "token"))).alias("order"))
    # Shingles that no other node of the hub has would come first in the order, so they count as indexed.
    rows = near.drop("rest").withColumn("extra", F.col("n") - F.col("o")).join(rows, "node")
    rows = rows.withColumn("keep", F.size("order") - F.col("least") + 1).filter("keep > 0").select("*", F.explode(F.slice("order", F.lit(1), F.col("keep").cast("int"))).alias("e"))
    x, y = (rows.select("hub", F.col("e.token").alias("token"), *[F.col(c).alias(f"{c}_{i}") for c in ("node", "n", "o", "extra", "comp")]) for i in "ab")
    need = least_overlap("n_a", "n_b", percent) - F.least("o_a", "o_b")
    pair = x.join(y, ["hub", "token"]).filter((F.col("node_a") < F.col("node_b")) & (F.col("comp_a") != F.col("comp_b")) & fits(F.col("n_a"), F.col("n_b")) & (need <= F.least("extra_a", "extra_b")) & (need > 0))
    pair = pair.select(F.col("node_a").alias("a"), F.col("node_b").alias("b")).distinct()
    x, y = (near.select(F.col("node").alias(i), *[F.col(c).alias(f"{c}_{i}") for c in ("n", "nh", "rest", "gone")]) for i in "ab")
    return linked(by_hub(pair.join(x, "a").join(y, "b")), percent)


def by_hub(pairs: DataFrame) -> DataFrame:
    """(a, na, b, nb, o) of pairs beside one hub: of the hub's nh shingles, two sets share those that neither lacks, and besides what both have more than the hub."""
    o = F.col("nh_a") - F.size("gone_a") - F.size("gone_b") + F.size(F.array_intersect("gone_a", "gone_b")) + F.size(F.array_intersect("rest_a", "rest_b"))
    return pairs.select("a", F.col("n_a").alias("na"), "b", F.col("n_b").alias("nb"), o.alias("o"))


def to_nearest(near: DataFrame, percent: int, fits) -> DataFrame:
    """Links of nodes with those few that are nearest to their hub."""
    best = F.row_number().over(Window.partitionBy("hub").orderBy(F.desc("o"), "node"))
    few = near.withColumn("k", best).filter(F.col("k") <= NEAREST)
    x, y = (df.select("hub", F.col("node").alias(i), *[F.col(c).alias(f"{c}_{i}") for c in ("n", "nh", "comp", "rest", "gone")]) for df, i in ((near, "a"), (few, "b")))
    return linked(by_hub(x.join(y, "hub").filter((F.col("comp_a") != F.col("comp_b")) & fits(F.col("n_a"), F.col("n_b")))), percent)


def classes(docs: DataFrame, width: int = 3, percent: int = 90) -> DataFrame:
    """doc_id, n_shingles, component_id of each row; also row (its monotonically_increasing_id in docs) and first, true for one row of each class.

    Texts without words have no shingles and are their own class. Rows whose words are the same, repeated rows included,
    are one node. A class is named after its smallest doc_id; null ids are passed over unless a class has no other. Its first row is
    that with this id, of several the first in docs. An empty table gives no rows. Only doc_id and text are read, whatever else
    docs has; docs must read the same each time. Very long texts are cut into fragments like others.
    """
    spark = docs.sparkSession
    docs = docs.select(F.monotonically_increasing_id().alias("row"), docs["doc_id"].cast("long").alias("doc_id"), docs["text"].alias("text"))
    freq = spark.sparkContext.broadcast(frequency_classes(docs, width))
    whole = stored(prefixes(docs, width, percent, freq), "prefixes")
    every = stored(whole.drop("prefix"), "rows")
    names = every.filter("n > 0").groupBy("d1", "d2").agg(F.min("row").alias("node"))
    nodes = stored(names.select("node").join(whole.select(F.col("row").alias("node"), "n", "prefix"), "node"), "nodes")
    dropped(whole)
    listed = nodes.select("node", "n", F.posexplode("prefix").alias("at", "token"))
    lists = listed.groupBy("token").agg(F.count("*").alias("many")).filter("many > 1")
    index = stored(listed.join(lists, "token"), "lists")
    # Nodes that share fewer shingles with all others together than linked ones do with one another have no link.
    able = index.groupBy("node").agg(F.count("*").alias("c"), F.first("n").alias("n"), (F.sum("many") / F.first("n")).alias("weight")).filter(F.col("c") >= F.least(F.lit(SHARE), "n")).select("node", "weight")
    shared = stored(index.join(able, "node"), "able")
    dropped(index)
    fits = lambda a, b: 100 * F.least(a, b) >= percent * F.greatest(a, b)

    # Prefixes don't thin these out: a node that has no link with its hub can be near it all the same, and is then compared beside it.
    pairs = stored(to_hubs(shared, fits), "pairs")
    cut = cut_sets(pairs, docs, width, freq)
    measured = to_likeliest(pairs, cut, percent)
    found = measured[0].union(measured[1])
    dropped(cut, pairs)
    links = linked(found, percent)
    comp = stored(components(links), "classes")
    # Of the hubs that a node is near, the one that most are near: nodes beside one hub are compared by what that hub lacks.
    near = found.filter(F.col("o") >= NEAR * F.col("na"))
    near = near.join(near.groupBy("b").agg(F.count("*").alias("size")), "b")
    near = near.groupBy("a", "na").agg(F.max_by(F.struct("b", "nb", "o", "rest", "gone"), F.struct("size", "b")).alias("h"))
    near = near.select(F.col("a").alias("node"), F.col("na").cast("long").alias("n"), F.col("h.b").alias("hub"), F.col("h.nb").alias("nh"), F.col("h.o").alias("o"), F.col("h.rest").alias("rest"), F.col("h.gone").alias("gone"))
    beside = stored(near, "beside")
    near = stored(centred(beside), "near")
    dropped(beside)
    classed = lambda df: df.join(comp, "node", "left").withColumn("comp", F.coalesce("comp", "node"))
    links = stored(links.union(to_nearest(classed(near), percent, fits)), "links")
    dropped(*measured)
    first, comp = comp, stored(components(links), "classes")
    links = stored(links.union(beside_hub(classed(near), percent, fits)), "links")
    own = classed(shared)
    # A list whose nodes are all of one class has no pair left.
    mixed = own.groupBy("token").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi")).filter("lo < hi").select("token")
    own = stored(own.join(mixed, "token").join(near.select("node", "hub", "o"), "node", "left"), "open")
    dropped(shared, near)
    rest = candidates(own, percent, fits)
    pairs = stored(by_prefix(rest, nodes, percent), "pairs")
    dropped(own, nodes)
    cut = cut_sets(pairs, docs, width, freq)
    links = stored(links.union(linked(overlaps(pairs, cut), percent)), "links")
    dropped(cut, pairs, first, comp)
    comp = stored(components(links), "classes")
    named = every.filter("n > 0").select("row", "doc_id", "n", "d1", "d2").join(names, ["d1", "d2"]).join(comp, "node", "left").withColumn("comp", F.coalesce("comp", "node"))
    name = named.groupBy("comp").agg(F.min(F.struct(F.col("doc_id").isNull(), "doc_id", "row")).alias("f")).select("comp", F.col("f.doc_id").alias("component_id"), F.col("f.row").alias("head"))
    named = named.join(name, "comp").select("doc_id", F.col("n").cast("long").alias("n_shingles"), "component_id", "row", (F.col("row") == F.col("head")).alias("first"))
    none = every.filter("n = 0").select("doc_id", F.col("n").cast("long").alias("n_shingles"), F.col("doc_id").alias("component_id"), "row", F.lit(True).alias("first"))
    return named.union(none)


def op3_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return classes(table(spark, sf_dir, "documents")).select("doc_id", "n_shingles", "component_id")
