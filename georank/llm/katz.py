"""Operator 7: language-model scoring with Katz backoff, of any order.

Seen n-grams have Good-Turing discounted relative frequencies; what the discounts free goes to unseen successors in
proportion to the model of the next lower order, by a backoff weight per history that makes each history's probabilities add
up to 1. The recursion runs by orders: texts are cut into chunks, of which only the packed numbers of their words are kept; in round k a chunk asks the partitioned tables of order k for
its distinct k-grams, and sends with each one the probability that round k - 1 gave its last word. A partition adds up
what all chunks have counted, stores its table, and answers with probabilities that are final for order k. The last
round's answers are sums for each document.

What moves are sorted, zstd-packed blocks of integers, one for each chunk and partition: a chunk adds up its own repeats
first, so a frequent n-gram weighs no more than once a chunk. N-grams are dealt by their history; histories that hold a large share
of all words (there can be few of them) are dealt by their successors too, and their sums are put together beforehand.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Hasher, dropped, id_crc, lowered, mix, parts, released, sliced, stored, table, text_bytes, word_spans

#: Counts up to K are discounted.
K = 5
#: Order of the model; bytes of text in a chunk; a history is split if it has more than this part of a partition's even share of all words.
ORDER, CHUNK, SHARE = 2, 8 << 20, 0.125
#: Bytes of text whose words are hashed at once: the hashes' sums and powers take some 40 times as many.
SLICE = 1 << 20
#: Stands for a text's end among the words' hashes; number of the place before a text.
END, BEGIN = 2, 0


def pack(x) -> bytes:
    """Integers from 0, as compressed byte planes."""
    import zstandard

    x = np.ascontiguousarray(x, "<u8")
    wide = max(1, (int(x.max(initial=0)).bit_length() + 7) // 8)
    planes = np.ascontiguousarray(x.view(np.uint8).reshape(-1, 8)[:, :wide].T)
    return wide.to_bytes(1, "little") + len(x).to_bytes(8, "little") + zstandard.ZstdCompressor(level=1).compress(planes.tobytes())


def unpack(b: bytes) -> np.ndarray:
    import zstandard

    wide, n = b[0], int.from_bytes(b[1:9], "little")
    out = np.zeros((n, 8), np.uint8)
    if n:
        out[:, :wide] = np.frombuffer(zstandard.ZstdDecompressor().decompress(b[9:]), np.uint8).reshape(wide, n).T
    return out.reshape(-1).view("<u8")


def steps(x: np.ndarray) -> np.ndarray:
    return np.diff(x, prepend=x.dtype.type(0))


def pack_values(x: np.ndarray) -> bytes:
    """Doubles with few distinct values."""
    values, at = np.unique(x, return_inverse=True)
    head = pack(values.view("<u8"))
    return len(head).to_bytes(8, "little") + head + pack(at)


def unpack_values(b: bytes) -> np.ndarray:
    n = int.from_bytes(b[:8], "little")
    return unpack(b[8 : 8 + n]).view("<f8")[unpack(b[8 + n :]).astype(np.int64)]


def tokens(col) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all texts' lower-cased words, each text's followed by END, and each text's first place."""
    data, off = text_bytes(col)
    out, first, row = [np.zeros(0, np.uint64)], [np.zeros(1, np.int64)], 0
    while row < len(off) - 1:  # whole texts, as many as SLICE holds, or one
        end = max(row + 1, int(np.searchsorted(off, off[row] + SLICE, "right")) - 1)
        some = data[off[row] : off[end]]
        starts, ends, own = word_spans(some, off[row : end + 1] - off[row])
        words = Hasher(lowered(some))(starts, ends) if len(starts) else np.zeros(0, np.uint64)
        out.append(np.insert(words, own[1:], np.uint64(END)))
        first.append(first[-1][-1] + (own + np.arange(len(own)))[1:])
        row = end
    return np.concatenate(out), np.concatenate(first)


def discounts(of: dict[int, int], k: int = K) -> list[float]:
    """Good-Turing discount ratios of counts 1..k from the numbers of n-grams by count; 1, so none, where they can't be formed."""
    out = []
    n1, last = of.get(1, 0), (k + 1) * of.get(k + 1, 0)
    for r in range(1, k + 1):
        n, up = of.get(r, 0), of.get(r + 1, 0)
        d = 0.0
        if n and n1 and n1 > last:
            d = ((r + 1) * up / (r * n) - last / n1) / (1 - last / n1)
        out.append(d if 0 < d < 1 else 1.0)
    return out


def held(c: np.ndarray, ratios: list[float]) -> np.ndarray:
    """What is left of counts after discounting."""
    return c * np.array([1.0, *ratios, 1.0])[np.minimum(c, len(ratios) + 1).astype(np.int64)]


def backoff(total, kept, low):
    """(denominator, weight of the lower order) of histories with these sums of counts, discounted counts and lower probabilities of what is seen.

    A history without any discount counts one more than it has, so that its unseen successors have something.
    """
    total = np.where(total - kept < 1e-9 * total, total + 1, total)
    with np.errstate(invalid="ignore", divide="ignore"):
        weight = (1 - kept / total) / np.maximum(1 - low, 1e-300)
    return total, np.where(total > 0, weight, 1.0)


def distinct(history: np.ndarray, word: np.ndarray, hot: np.ndarray, n: int):
    """Distinct (history, word) in order of partition, history and word; their partitions; each token's place among them."""
    (h, hi), (w, wi) = np.unique(history, return_inverse=True), np.unique(word, return_inverse=True)
    pair, at = np.unique(hi.astype(np.uint64) << np.uint64(32) | wi.astype(np.uint64), return_inverse=True)
    h, w = h[(pair >> np.uint64(32)).astype(np.int64)], w[(pair & np.uint64(0xFFFFFFFF)).astype(np.int64)]
    own = mix(h)
    if len(hot):
        own = np.where(np.isin(h, hot), mix(own + w), own)
    part = (own % np.uint64(n)).astype(np.int32)
    by = np.argsort(part, kind="stable")
    rank = np.empty(len(by), np.int64)
    rank[by] = np.arange(len(by))
    return h[by], w[by], part[by], rank[at]


def runs(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Values and lengths of runs."""
    at = np.flatnonzero(np.concatenate([np.ones(min(1, len(x)), bool), x[1:] != x[:-1]]))
    return x[at], np.diff(np.append(at, len(x)))


ASK = "part int, chunk long, h binary, hn binary, w binary, c binary, low binary, docs binary, dn binary, dc binary, ids array<long>, train array<boolean>, n_tokens array<long>, n_known array<long>, base array<double>"
TABLE = "part int, h binary, hn binary, w binary, c binary, low binary, of array<long>, hot array<long>, sums array<double>"
ANSWER = "part int, chunk long, a binary, b binary"
WORDS = ANSWER + ", at binary, sizes binary, ids array<long>, train array<boolean>"


def words_asked(docs: DataFrame, n: int, size: int) -> DataFrame:
    """Round 1's questions, docs (doc_id, train, text) being cut into chunks of `size` bytes in the same task: a chunk's distinct words and how often it trains on them; with part -1, the chunk itself: each token's place among those words, texts' lengths, ids and whether they train."""

    def ask(batches):
        kinds = (pa.int32(), pa.int64(), *[pa.binary()] * 4, pa.list_(pa.int64()), pa.list_(pa.bool_()))
        for k, batch in enumerate(sliced(batches, "text", size)):
            chunk, ids, train = (TaskContext.get().partitionId() << 32) + k, batch.column(0).to_pylist(), batch.column(1).to_pylist()
            tok, first = tokens(batch.column(2))
            keys, at = np.unique(tok, return_inverse=True)
            c = np.bincount(at, np.repeat(np.array(train, float), np.diff(first)))
            part = ((keys >> np.uint64(32)) * np.uint64(n) >> np.uint64(32)).astype(np.int64)
            own, many = runs(part)
            ends = np.cumsum(many)
            rows = [(int(p), chunk, pack(steps(keys[e - m : e])), pack(c[e - m : e]), None, None, None, None) for p, m, e in zip(own.tolist(), many.tolist(), ends.tolist())]
            rows.append((-1, chunk, None, None, pack(at), pack(np.diff(first)), ids, train))
            yield pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(zip(*rows), kinds)], [c.split()[0] for c in WORDS.split(", ")])

    return docs.mapInArrow(ask, WORDS)


def words_table(asked: DataFrame, n: int) -> DataFrame:
    """Round 1: (part, chunk, a, b) answers with numbers and training counts of a chunk's words; with chunk null, a partition's table and its sums."""

    def serve(t: pa.Table) -> pa.Table:
        part = t.column("part")[0].as_py()
        keys = [np.cumsum(unpack(x), dtype=np.uint64) for x in t.column("a").to_pylist()]
        every, at = np.unique(np.concatenate(keys), return_inverse=True)
        c = np.rint(np.bincount(at, np.concatenate([unpack(x) for x in t.column("b").to_pylist()]).astype(float))).astype(np.uint64)
        # Frequent words have small numbers: what moves later packs closer so.
        order = np.argsort(-c.astype(np.int64), kind="stable")
        ids = np.empty(len(every), np.uint64)
        ids[order] = np.arange(len(every), dtype=np.uint64) * np.uint64(n) + np.uint64(part + 1)
        edge = np.cumsum([0, *map(len, keys)])
        a = [pack(ids[at[i:j]]) for i, j in zip(edge[:-1], edge[1:])]
        b = [pack(c[at[i:j]]) for i, j in zip(edge[:-1], edge[1:])]
        released()
        return pa.table({"part": pa.array([part] * (len(a) + 1), pa.int32()), "chunk": pa.array([*t.column("chunk").to_pylist(), None], pa.int64()), "a": pa.array([*a, pack(steps(every[order]))], pa.binary()), "b": pa.array([*b, pack(c[order])], pa.binary())})

    return asked.select("part", "chunk", "a", "b").filter("part >= 0").groupBy("part").applyInArrow(serve, ANSWER)


def asks(chunks: DataFrame, answers: list[DataFrame], n: int, hot: list[np.ndarray], known: tuple[int, int], last: bool) -> DataFrame:
    """Round k's questions from the chunks' words and the answers of all rounds before it; if it is the last, by document, and a row of base figures."""
    total, kinds = known
    floor, rounds = total + 0.1 * (kinds + 1), len(answers)

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        right = right.sort_by([("round", "ascending"), ("part", "ascending")])
        chunk, at, sizes, owners, train = (left.column(c)[0].as_py() for c in ("chunk", "at", "sizes", "ids", "train"))
        at = unpack(at).astype(np.int64)
        first = np.concatenate([[0], np.cumsum(unpack(sizes).astype(np.int64))])
        doc = np.repeat(np.arange(len(first) - 1), np.diff(first))
        round_ = right.column("round").to_numpy()

        def answer(k):
            rows = right.filter(pa.array(round_ == k))
            return [np.concatenate([f(x) for x in rows.column(c).to_pylist()]) for c, f in (("a", unpack), ("b", unpack if k == 1 else unpack_plain))]

        ids, counts = answer(1)
        word, c = ids[at], counts[at].astype(np.float64)
        gram, p = word, (c + 0.1) / floor
        base = np.log10(p)
        opening = first[:-1]
        for k in range(2, rounds + 2):
            history = np.concatenate([[np.uint64(BEGIN)], gram[:-1]])
            history[opening] = BEGIN
            h, w, part, at = distinct(history, word, hot[k - 2], n)
            if k <= rounds:
                ids, values = answer(k)
                gram, p = ids[at], values[at]
        counted = np.rint(np.bincount(at, np.array(train, float)[doc], len(h))).astype(np.uint64)
        low = np.empty(len(h))
        low[at] = p
        rows: dict[str, list] = {c.split()[0]: [] for c in ASK.split(", ")}
        if last:
            both, times = np.unique(at.astype(np.uint64) << np.uint64(32) | doc.astype(np.uint64), return_counts=True)
            owner, whose = (both >> np.uint64(32)).astype(np.int64), both & np.uint64(0xFFFFFFFF)
            many = np.bincount(owner, minlength=len(h))
            upto = np.concatenate([[0], np.cumsum(many)])
        own, sizes = runs(part)
        ends = np.cumsum(sizes)
        for q, m, e in zip(own.tolist(), sizes.tolist(), ends.tolist()):
            s = slice(e - m, e)
            value, length = runs(h[s])
            new = {"part": q, "chunk": chunk, "h": pack(steps(value)), "hn": pack(length), "w": pack(w[s]), "c": pack(counted[s]), "low": pack_values(low[s])}
            if last:
                d = slice(upto[e - m], upto[e])
                new |= {"docs": pack(whose[d]), "dn": pack(many[s]), "dc": pack(times[d])}
            for name, column in rows.items():
                column.append(new.get(name))
        if last:
            new = {"part": -1, "chunk": chunk, "ids": owners, "train": train, "n_tokens": np.diff(first).tolist()}
            new |= {"n_known": np.bincount(doc, c > 0, len(first) - 1).astype(int).tolist(), "base": np.bincount(doc, base, len(first) - 1).tolist()}
            for name, column in rows.items():
                column.append(new.get(name))
        del doc, at, base, p, word, gram, c, counts, ids, history, h, w, part, low, counted
        released()
        kinds_ = [pa.int32(), pa.int64(), *[pa.binary()] * 8, pa.list_(pa.int64()), pa.list_(pa.bool_()), pa.list_(pa.int64()), pa.list_(pa.int64()), pa.list_(pa.float64())]
        return pa.table([pa.array(x, k) for x, k in zip(rows.values(), kinds_)], list(rows))

    every = None
    for k, df in enumerate(answers, 1):
        df = df.select(F.lit(k).alias("round"), "part", "chunk", "a", "b")
        every = df if every is None else every.unionByName(df)
    return chunks.groupBy("chunk").cogroup(every.groupBy("chunk")).applyInArrow(run, ASK)


def pack_plain(x: np.ndarray) -> bytes:
    return pack(np.ascontiguousarray(x, "<f8").view("<u8"))


def unpack_plain(b: bytes) -> np.ndarray:
    return unpack(b).view("<f8")


def _pairs(h: bytes, hn: bytes, w: bytes):
    return np.repeat(np.cumsum(unpack(h), dtype=np.uint64), unpack(hn).astype(np.int64)), unpack(w)


def merged(asked: DataFrame, hot: np.ndarray, k: int) -> DataFrame:
    """The tables of one order: each partition's n-grams with counts, numbers of n-grams by count, and sums of the histories that are split."""

    def run(t: pa.Table) -> pa.Table:
        part = t.column("part")[0].as_py()
        cols = {c: t.column(c).to_pylist() for c in ("h", "hn", "w", "c", "low")}
        del t
        # One column after another, so that few whole ones are held at once.
        h = np.concatenate([np.repeat(np.cumsum(unpack(x), dtype=np.uint64), unpack(y).astype(np.int64)) for x, y in zip(cols.pop("h"), cols.pop("hn"))])
        w = np.concatenate([unpack(x) for x in cols.pop("w")])
        by = np.lexsort((w, h))
        h, w = h[by], w[by]
        new = np.flatnonzero(np.concatenate([[True], (h[1:] != h[:-1]) | (w[1:] != w[:-1])]))
        h, w = h[new], w[new]
        c = np.add.reduceat(np.concatenate([unpack(x) for x in cols.pop("c")])[by], new)
        low = np.concatenate([unpack_values(x) for x in cols.pop("low")])[by[new]]
        del by, new
        of = np.bincount(np.minimum(c, k + 2).astype(np.int64), minlength=k + 3)[1 : k + 2]
        value, length = runs(h)
        split = np.isin(h, hot)
        names, at = np.unique(h[split], return_inverse=True)
        sums = np.zeros((len(names), k + 2))
        cs, ls = c[split], low[split]
        for r in range(1, k + 1):
            sums[:, r - 1] = np.bincount(at, (cs == r) * r, len(names))
        sums[:, k] = np.bincount(at, cs * (cs > k), len(names))
        sums[:, k + 1] = np.bincount(at, ls * (cs > 0), len(names))
        row = {"part": [part], "h": [pack(steps(value))], "hn": [pack(length)], "w": [pack(w)], "c": [pack(c)], "low": [pack_values(low)], "of": [of.tolist()], "hot": [names.astype(np.int64).tolist()], "sums": [sums.ravel().tolist()]}
        kinds = [pa.int32(), *[pa.binary()] * 5, pa.list_(pa.int64()), pa.list_(pa.int64()), pa.list_(pa.float64())]
        del h, w, c, low, value, length, split, at, cs, ls
        released()
        return pa.table([pa.array(x, y) for x, y in zip(row.values(), kinds)], list(row))

    return asked.select("part", "h", "hn", "w", "c", "low").groupBy("part").applyInArrow(run, TABLE)


def answered(asked: DataFrame, tables: DataFrame, n: int, ratios: list[float], whole: dict[int, list[float]], last: bool) -> DataFrame:
    """Answers of one order: numbers and probabilities of a chunk's n-grams or, if it is the last, the documents' sums of log10 probabilities."""
    k = len(ratios)
    names = np.array(sorted(whole), np.uint64)
    sums = np.array([whole[x] for x in sorted(whole)]).reshape(-1, k + 2)

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        part = right.column("part")[0].as_py()
        h, w = _pairs(*[right.column(c)[0].as_py() for c in ("h", "hn", "w")])
        c, low = unpack(right.column("c")[0].as_py()), unpack_values(right.column("low")[0].as_py())
        value, length = runs(h)
        at = np.cumsum(length) - length
        kept = held(c, ratios)
        total, mass, seen = (np.add.reduceat(x, at) for x in (c.astype(float), kept, low * (c > 0)))
        if len(names):  # sums of a split history are those of all partitions
            place = np.minimum(np.searchsorted(names, value), len(names) - 1)
            split = names[place] == value
            s = sums[place[split]]
            total[split], mass[split], seen[split] = s[:, : k + 1].sum(1), s[:, :k] @ np.array(ratios) + s[:, k], s[:, k + 1]
        total, weight = backoff(total, mass, seen)
        of = np.repeat(np.arange(len(value)), length)
        p = np.where(c > 0, kept / np.maximum(total[of], 1), weight[of] * low)
        every = np.unique(w)
        key = of.astype(np.uint64) << np.uint64(32) | np.searchsorted(every, w).astype(np.uint64)
        a, b = [], []
        for i in range(left.num_rows):
            hs, ws = _pairs(*[left.column(x)[i].as_py() for x in ("h", "hn", "w")])
            row = np.searchsorted(key, np.searchsorted(value, hs).astype(np.uint64) << np.uint64(32) | np.searchsorted(every, ws).astype(np.uint64))
            if last:
                docs, many, times = (unpack(left.column(x)[i].as_py()) for x in ("docs", "dn", "dc"))
                ids, place = np.unique(docs, return_inverse=True)
                a.append(pack(steps(ids)))
                b.append(np.bincount(place, np.repeat(np.log10(p[row]), many.astype(np.int64)) * times).tobytes())
            else:
                a.append(pack(row.astype(np.uint64) * np.uint64(n) + np.uint64(part + 1)))
                b.append(pack_plain(p[row]))
        del h, w, c, low, kept, of, p, key
        released()
        return pa.table({"part": pa.array([part] * len(a), pa.int32()), "chunk": left.column("chunk"), "a": pa.array(a, pa.binary()), "b": pa.array(b, pa.binary())})

    # Counts and lower probabilities are in the tables by now; questions go without them.
    left = asked.select("part", "chunk", "h", "hn", "w", *["docs", "dn", "dc"] * last)
    right = tables.select("part", "h", "hn", "w", "c", "low")
    return left.groupBy("part").cogroup(right.groupBy("part")).applyInArrow(run, ANSWER)


def score(docs: DataFrame, train: Column, order: int = ORDER, k: int = K, chunk: int = CHUNK) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score and score (log10 probability) of each row.

    Null and empty texts are one end token. Rows are scored one by one, so repeated rows and ids get results of their own. A
    very long text is a chunk by itself. With nothing to train on, the only unigram probability is that of an unknown token. An
    empty table gives no rows; only doc_id and text are read, whatever else docs has. docs must read the same each time.
    Words are 64-bit hashes; A-Z are lower-cased. An order of 1 would be the base score; orders from 2 on are meant.
    """
    spark = docs.sparkSession
    n = parts(spark)
    docs = docs.select(docs["doc_id"].cast("long").alias("doc_id"), F.coalesce(train, F.lit(False)).alias("train"), docs["text"].alias("text"))
    held_ = stored(words_asked(docs, n, chunk), "chunks")
    first = stored(words_table(held_, n), "words")
    chunks = held_.filter("part < 0").select("chunk", "at", "sizes", "ids", "train")
    # A table's words and counts, added up: one row a partition.
    sums = first.filter("chunk is null").select("part", "b").mapInArrow(_count_words(n, SHARE), "total long, kinds long, ids array<long>, counts array<long>").collect()
    total, kinds = sum(r[0] for r in sums), sum(r[1] for r in sums)
    hot = [[i for r in sums for i, c in zip(r[2], r[3]) if c > SHARE * total / n] + [BEGIN]]
    answers = [first.filter("chunk is not null")]
    steps_ = [first]
    for level in range(2, order + 1):
        last = level == order
        names = [np.array(sorted(x), np.uint64) for x in hot]
        asked = stored(asks(chunks, answers, n, names, (total, kinds), last), "asks")
        if last:
            dropped(held_, *steps_)  # no round is left that reads them
        questions = asked.filter("part >= 0")
        tables = stored(merged(questions, names[-1], k), f"order-{level}")
        got = tables.select("of").collect()
        of = {r: sum(x[0][r - 1] for x in got) for r in range(1, k + 2)}
        split = tables.select(F.explode(F.arrays_zip("hot", F.expr(f"transform(sequence(0, size(hot) - 1), i -> slice(sums, i * {k + 2} + 1, {k + 2}))").alias("s"))).alias("x")).filter("x.hot is not null") if len(names[-1]) else None
        whole = {r[0]: list(r[1:]) for r in split.groupBy("x.hot").agg(*[F.sum(F.col("x.s")[i]).alias(f"s{i}") for i in range(k + 2)]).collect()} if split is not None else {}
        reply = stored(answered(questions, tables, n, discounts(of, k), whole, last), "answers")
        dropped(tables)
        if not last:
            dropped(asked)
            answers.append(reply)
            steps_.append(reply)
            hot.append([BEGIN])  # the place before a text is the one history known to be everywhere
    facts = asked.filter("part < 0")

    def finish(t: pa.Table) -> pa.Table:
        i = t.column("ids").is_valid().to_pylist().index(True)
        ids, flags, tokens_, known, base = (t.column(x)[i].as_py() for x in ("ids", "train", "n_tokens", "n_known", "base"))
        out = np.zeros(len(ids))
        for a, b in zip(t.column("a").to_pylist(), t.column("b").to_pylist()):
            if a is not None:
                out[np.cumsum(unpack(a)).astype(np.int64)] += np.frombuffer(b, "<f8")
        return pa.table({"doc_id": pa.array(ids, pa.int64()), "held_out": pa.array([not x for x in flags], pa.bool_()), "n_tokens": pa.array(tokens_, pa.int64()), "n_known": pa.array(known, pa.int64()), "train_tokens": pa.array([total] * len(ids), pa.int64()), "base_score": pa.array(base, pa.float64()), "score": pa.array(out)})

    both = facts.select("chunk", "ids", "train", "n_tokens", "n_known", "base").unionByName(reply.select("chunk", "a", "b"), allowMissingColumns=True)
    return both.groupBy("chunk").applyInArrow(finish, "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double")


def _count_words(n: int, share: float):
    """Sums of each partition's table, and its words that may be hot: those with a share of the partition's own sum that all words' sum would need."""

    def run(batches):
        for batch in batches:
            for part, b in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                c = unpack(b)
                own = np.flatnonzero(c > share * c.sum() / n)  # at most n / share words; the sum of all is no less than a partition's
                ids = own.astype(np.uint64) * np.uint64(n) + np.uint64(part + 1)
                yield pa.RecordBatch.from_arrays([pa.array([int(c.sum())]), pa.array([int((c > 0).sum())]), pa.array([ids.astype(np.int64).tolist()], pa.list_(pa.int64())), pa.array([c[own].astype(np.int64).tolist()], pa.list_(pa.int64()))], ["total", "kinds", "ids", "counts"])

    return run


def op7_katz(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score(table(spark, sf_dir, "documents"), F.pmod(id_crc(F.col("doc_id")), F.lit(10)) != 0)
