"""Each operator against brute force on a small fixture with nulls, empty and long texts, ties, repeats and clashing columns."""

import collections
import hashlib
import math
import random
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from georank.llm import bpe, common, components, fixity, hashing, jaccard, katz, language, mixing, pieces, planes, quality, suffixes

P = pytest.importorskip("public_tokenizers")
WORD = re.compile(r"[^\x20\x09-\x0D]+")
LOW = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


@pytest.fixture(scope="module")
def rows():
    rnd = random.Random(2)
    vocab = ["The", "the", "fox,", "jumps", "É", "niño", "x", "über", "a|b", "dog."]
    passage = " ".join(rnd.choice(vocab) + str(i % 7) for i in range(70))
    texts = [None, "", " \n\t", "one", "Two words", passage, passage, passage.upper(), passage + " tail", "pre " + passage, "ab" * 300]
    texts += [" ".join(rnd.choice(vocab) + str(rnd.randrange(40)) for _ in range(rnd.choice([3, 60, 200]))) for _ in range(20)]
    texts += [" ".join(rnd.choice(vocab) for _ in range(6000)) + "\nline\nline", "  odd　spaces <|endoftext|> \n\n here"]
    return [(i, t, ["en", "fr", None][i % 3], [None, "b", "a", "é"][i % 4], 7, "clash") for i, t in enumerate(texts)]


SCHEMA = "doc_id long, text string, lang string, source string, n_words int, rid string"


@pytest.fixture(scope="module")
def docs(spark, rows, tmp_path_factory):
    path = str(tmp_path_factory.mktemp("docs") / "d")
    spark.createDataFrame(rows, SCHEMA).repartition(3).write.parquet(path)
    return spark.read.parquet(path)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


def by_id(df):
    return {r.doc_id: r for r in df.collect()}


def test_planes_round_trip_and_library(spark, rows, docs, none, tmp_path):
    from tokenizers import Tokenizer

    path = P.path("byte_bpe_50k.json")
    lib, start = Tokenizer.from_file(path), 0
    for bits in (False, True):
        out = str(tmp_path / f"f{bits}")
        planes.write(docs, out, path, bits=bits)
        got, start = by_id(planes.read(spark, out)), 0
        for i, t, *_ in rows:
            ids = lib.encode(t or "", add_special_tokens=False).ids + [2]
            assert (got[i].ids, got[i].start, got[i].ids_crc32) == (ids, start, zlib.crc32(np.array(ids, "<u4").tobytes()))
            start += len(ids)
    planes.write(none, str(tmp_path / "none"), path)
    assert planes.read(spark, str(tmp_path / "none")).count() == 0


def test_pieces_equal_library_on_odd_texts():
    from tokenizers import Tokenizer

    rnd = random.Random(1)
    alphabet = [" ", "  ", "\n", "\t", "a", "bc", "'s", "12", "é", "é", "ΑΣ", "<|endoftext|>", "\xa0", "\x1c", "\x85", "İ", "!?", "日本", "🙂", "</w>"]
    byte, word = open(P.path("byte_bpe_50k.json")).read(), open(P.path("word_bpe_49k.json")).read()
    a, b = pieces.LibraryPieces(byte), pieces.RankArrayPieces(word)
    la, lb = Tokenizer.from_str(byte), Tokenizer.from_str(word)
    for _ in range(1500):
        s = "".join(rnd.choice(alphabet) for _ in range(rnd.randint(0, 10)))
        assert np.frombuffer(a.encode(s), "<u4").tolist() == la.encode(s, add_special_tokens=False).ids
        ids = lb.encode(s, add_special_tokens=False).ids
        assert b.encode(s) == ids and b.decode(ids) == lb.decode(ids, skip_special_tokens=False)


def test_bpe(spark, rows, docs, none):
    from tokenizers import Tokenizer

    path = P.path("word_bpe_49k.json")
    lib = Tokenizer.from_file(path)
    got = by_id(bpe.decode(bpe.encode(docs, path), path))
    for i, t, *_ in rows:
        ids = lib.encode(t or "", add_special_tokens=False).ids
        assert got[i].ids == ids and got[i].decoded == lib.decode(ids, skip_special_tokens=False)
    assert bpe.encode(none, path).count() == 0


def test_fixity_finds_changed_records(spark):
    pages = [(i, f"u{i}", f"<p>{i}</p>" * (i % 5 + 1)) for i in range(400)] + [(7, "u7", "again"), (None, None, None)]
    one = spark.createDataFrame(pages, "page_id long, url string, html string")
    other = one.withColumn("html", F.when(F.col("page_id").isin(33, 399), F.translate("html", "p", "q")).otherwise(F.col("html")))
    roots, wrong = fixity.audit(fixity.archive(one, 100), fixity.archive(other, 100), 4)
    assert {r.file for r in roots.filter("not equal").collect()} == {0, 3}
    assert {(r.file, r.node) for r in wrong.collect()} == {(0, 34), (3, 99)}
    assert fixity.archive(one.limit(0)).count() == 0


def test_jaccard(rows, docs, none):
    sets = {}
    for i, t, *_ in rows:
        w = WORD.findall((t or "").translate(LOW))
        sets[i] = {tuple(w[k : k + 3]) for k in range(max(1, len(w) - 2))} if w else set()
    root = {i: i for i in sets}
    find = lambda i: i if root[i] == i else find(root[i])
    for i in sets:
        for j in range(i):
            if sets[i] and 100 * len(sets[i] & sets[j]) >= 90 * len(sets[i] | sets[j]):
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    got = by_id(jaccard.classes(docs))
    assert {i: (r.n_shingles, r.component_id) for i, r in got.items()} == {i: (len(s), find(i)) for i, s in sets.items()}
    assert jaccard.classes(none).count() == 0


@pytest.mark.parametrize("width,percent", [(3, 90), (5, 80)])
def test_jaccard_long_lists(spark, tmp_path, width, percent):
    """Hundreds of copies with few edits, some of them alike, so that lists are long, hubs miss some, and links go beside them; repeated and null ids."""
    rnd = random.Random(21)
    base, other = ([f"w{rnd.randrange(10**6)}" for _ in range(n)] for n in (150, 90))
    texts = []
    for k in range(260):
        w = list(base if k % 3 else other)
        for _ in range(rnd.choice([1, 2, 2, 3, 4, 5])):
            w[rnd.randrange(len(w))] = rnd.choice(["alpha", "beta", "gamma"])
        texts.append(" ".join(w))
    texts += texts[:9] + [None, "", "alpha", "Alpha", "alpha beta"]
    texts += [" ".join(base[:60] + [f"z{rnd.randrange(10**6)}" for _ in range(3)]) for _ in range(30)]
    ids = [None if k in (5, 7, 265) else k // 2 if k < 20 else k for k in range(len(texts))]
    path = str(tmp_path / "d")
    spark.createDataFrame([(i, t, k, "clash") for k, (i, t) in enumerate(zip(ids, texts))], "doc_id long, text string, place int, row string").repartition(1).sortWithinPartitions("place").write.parquet(path)
    got = sorted(jaccard.classes(spark.read.parquet(path), width, percent).collect(), key=lambda r: r.row)
    want = near_classes(texts, width, percent)
    assert [r.doc_id for r in got] == ids and len(set(want)) > 20
    for c in set(want):
        mine = [k for k, x in enumerate(want) if x == c]
        name = min((ids[k] for k in mine if ids[k] is not None), default=None)
        assert all(got[k].component_id == name for k in mine)
        assert [k for k in mine if got[k].first] == [min(mine, key=lambda k: (ids[k] is None, ids[k] or 0, k))]


def test_steps_give_the_driver_s_garbage_back(spark, monkeypatch):
    """After a step the driver's heap doesn't hold what earlier steps left."""
    monkeypatch.setattr(common, "_rested", [-1e9])
    jvm, runtime = spark._jvm, spark._jvm.java.lang.Runtime.getRuntime()
    used = lambda: runtime.totalMemory() - runtime.freeMemory()
    jvm.System.gc()
    before, some = used(), spark.range(5).coalesce(1)
    gateway = spark.sparkContext._gateway
    gateway.detach(gateway.new_array(jvm.long, 13 << 20))
    assert used() > before + (60 << 20)
    out = common.stored(some)
    assert used() < before + (60 << 20) and out.count() == 5


def test_jaccard_drops_steps_when_done(docs, monkeypatch):
    """When sets are laid out to be measured, what took part in earlier steps alone is gone."""
    import os

    made, at, inner = [], [], jaccard.stored

    def spy(df, name):
        out = inner(df, name)
        made.append((name, out.stored_at.removeprefix("file:")))
        if name == "fragments":
            at.append({n for n, path in made if os.path.exists(path)})
        return out

    monkeypatch.setattr(jaccard, "stored", spy)
    assert jaccard.classes(docs).count() == docs.count()
    assert len(at) == 2 and at[0] == {"rows", "nodes", "able", "pairs", "fragments"}
    assert not at[1] & {"prefixes", "nodes", "able", "open", "near", "measured"}


def test_jaccard_measures_no_chance_pairs(spark):
    """Texts with one shingle in common aren't measured against a hub, unless it has many nodes."""
    lists = [(t, n) for t in range(6) for n in (t, t + 1)] + [(100 + t, n) for t in range(3) for n in (50, 51)] + [(200, n) for n in range(60, 80)]
    shared = spark.createDataFrame([(t, n, 40, float(n)) for t, n in lists], "token long, node long, n int, weight double")
    got = {(r.a, r.b) for r in jaccard.to_hubs(shared, lambda a, b: 100 * F.least(a, b) >= 90 * F.greatest(a, b)).collect()}
    assert {(50, 51), (51, 50)} <= got and {a for a, b in got if b == 79} == set(range(60, 79))
    assert not [p for p in got if p[0] < 10]


def test_jaccard_centred_keeps_overlaps(spark):
    """What two nodes share by what they lack of the hub stays their true overlap, and changes of the hub alone are no longer common to all."""
    rnd = random.Random(5)
    base = set(range(100))
    hubs = {1: base - {0, 1, 2} | {200, 201, 202}, 2: set(range(300, 340)), 3: base}
    sets = {k: (k % 2 and 1 or 2, hubs[2] - {300 + k % 7} | {400 + k % 5} if k % 2 == 0 else base - set(rnd.sample(range(3, 100), k % 6)) | {500 + rnd.randrange(9) for _ in range(k % 4)}) for k in range(10, 60)}
    sets[5] = (3, base - {50} | {999})
    near = [(k, len(x), h, len(hubs[h]), len(x & hubs[h]), sorted(x - hubs[h]), sorted(hubs[h] - x)) for k, (h, x) in sets.items()]
    got = {r.node: r for r in jaccard.centred(spark.createDataFrame(near, "node long, n long, hub long, nh long, o long, rest array<long>, gone array<long>")).collect()}
    assert set(got) == set(sets) and not any({0, 1, 2} & set(r.rest) for r in got.values())
    pairs = [(a, len(sets[a][1]), b, len(sets[b][1]), got[a].nh, sorted(got[a].rest), sorted(got[b].rest), sorted(got[a].gone), sorted(got[b].gone)) for a in sets for b in sets if a < b and sets[a][0] == sets[b][0]]
    out = jaccard.by_hub(spark.createDataFrame(pairs, "a long, n_a long, b long, n_b long, nh_a long, rest_a array<long>, rest_b array<long>, gone_a array<long>, gone_b array<long>")).collect()
    assert len(out) == len(pairs) and all(r.o == len(sets[r.a][1] & sets[r.b][1]) for r in out)
    assert all(r.o == r.n - len(r.rest) and len(r.rest) + r.nh - len(r.gone) == r.n for r in got.values())


def test_components(spark):
    edges = [(i, i + 1) for i in range(30)] + [(100, 101), (5, 5)]
    got = {r.node: r.comp for r in components.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {**{i: 0 for i in range(31)}, 100: 100, 101: 100}


def test_quality_base(rows, docs, none):
    got = by_id(quality.judge(docs))
    for i, t, *_ in rows:
        w = WORD.findall(t or "")
        lines = [x for x in (t or "").split("\n") if WORD.search(x)]
        grams = collections.Counter(zip(w, w[1:], w[2:]))
        hit = {k + d for k, g in enumerate(zip(w, w[1:], w[2:])) if grams[g] > 1 for d in range(3)}
        r = got[i]
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == (len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in t or ""), len(lines) - len(set(lines)), len(hit))
        assert r.base_failed == (len(w) < 50 or 100 * len(hit) > 50 * len(w)) and not (r.base_failed and r.kept)
    assert quality.judge(none).count() == 0


def test_quality_rejects_outliers(spark):
    rnd = random.Random(4)
    text = lambda sign: " ".join("".join(rnd.choice("abcdefgh") for _ in range(rnd.randint(2, 8))) + (" |" if rnd.random() < sign else "") for _ in range(150))
    rows = [(i, text(0.9 if i % 25 == 0 else 0.0), "en", "s", 0, "") for i in range(200)]
    got = by_id(quality.judge(spark.createDataFrame(rows, SCHEMA)))
    assert {i for i, r in got.items() if not r.kept} == set(range(0, 200, 25))


def test_suffixes(rows, docs, none):
    data = {i: (t or "").encode() for i, t, *_ in rows}
    seen = collections.Counter(x[k : k + 200] for x in data.values() for k in range(len(x) - 199))
    got = by_id(suffixes.remove(docs.select("doc_id", "text"), digests=True))
    for i, x in data.items():
        gone = np.zeros(len(x), bool)
        for k in range(len(x) - 199):
            if seen[x[k : k + 200]] > 1:
                gone[k : k + 200] = True
        left = bytes(np.frombuffer(x, np.uint8)[~gone])
        runs = int((np.diff(np.concatenate([[0], gone.astype(int)])) == 1).sum())
        assert (got[i].n_bytes, got[i].n_removed, got[i].n_spans, got[i].kept_sha256) == (len(x), int(gone.sum()), runs, hashlib.sha256(left).hexdigest())
    assert suffixes.remove(none).count() == 0


def test_suffix_columns_equal_sorting():
    rnd = random.Random(6)
    for _ in range(60):
        reads = [bytes(rnd.choice(b"ab") for _ in range(rnd.randint(1, 12))) for _ in range(rnd.randint(1, 8))]
        at = np.array([rnd.randrange(len(r)) for r in reads])
        first = at.max() - at
        seen = 0
        for j, order, lcp in suffixes.ordered_columns(reads, at):
            text = [reads[r][j - first[r] :] for r in order]
            assert sorted(text) == text and {r for r in range(len(reads)) if first[r] <= j < first[r] + len(reads[r])} == set(order.tolist())
            for k in range(1, len(text)):
                same = next((i for i, (p, q) in enumerate(zip(text[k - 1], text[k])) if p != q), min(len(text[k - 1]), len(text[k])))
                assert lcp[k] == same
            seen += len(text)
        assert seen == sum(map(len, reads))


def brute_suffixes(data, length=200):
    seen = collections.Counter(x[k : k + length] for x in data for k in range(len(x) - length + 1))
    for x in data:
        gone = np.zeros(len(x), bool)
        for k in range(len(x) - length + 1):
            if seen[x[k : k + length]] > 1:
                gone[k : k + length] = True
        yield gone


@pytest.mark.parametrize("hot", [2, 8])
def test_suffixes_split_hot_anchors(spark, tmp_path, hot):
    """A common line in many contexts, a common passage, and copies of a text: anchors with more kinds of read than the limit."""
    rnd = random.Random(9)
    noise = lambda n: "".join(rnd.choice("abcdefgh ") for _ in range(n))
    line, passage, text = noise(60), noise(230), noise(500)
    texts = [noise(rnd.randrange(260)) + line + noise(rnd.randrange(260)) for _ in range(40)] + [noise(rnd.randrange(30)) + passage + noise(rnd.randrange(30)) for _ in range(40)] + [text] * 5 + [text[k:] for k in range(12)] + [line * 5]
    path = str(tmp_path / "d")
    spark.createDataFrame([(None if i == 3 else i % 50, t, "kept", i) for i, t in enumerate(texts)], "doc_id long, text string, spans string, n_bytes int").write.parquet(path)
    got = {r.n_bytes: r for r in suffixes.remove(spark.read.parquet(path), hot=hot).collect()}
    for i, (t, gone) in enumerate(zip(texts, brute_suffixes([t.encode() for t in texts]))):
        assert (got[i].text, got[i].n_removed, got[i].spans) == (bytes(np.frombuffer(t.encode(), np.uint8)[~gone]).decode(), int(gone.sum()), "kept")


def test_hashing(spark):
    rng = np.random.default_rng(0)
    centres = rng.normal(size=(20, 16))
    x = centres[rng.integers(0, 20, 600)] + 0.3 * rng.normal(size=(600, 16))
    rows = [(i, [float(v) for v in r]) for i, r in enumerate(x)] + [(600, None), (601, [0.0] * 16), (602, [None] * 16), (603, [float("nan")] * 16)]
    base = hashing.valid(spark.createDataFrame(rows, "vec_id long, embedding array<double>"))
    assert base.count() == 600
    got = hashing.search(base, base.filter("vec_id % 20 = 0"), shard=250).collect()
    hit = 0
    for i in range(0, 600, 20):
        own = sorted((r for r in got if r.query_id == i), key=lambda r: r.rank)
        assert [r.rank for r in own] == list(range(1, 21)) and all(r.vec_id != i for r in own)
        s = x @ x[i]
        s[i] = -9e9
        hit += len({r.vec_id for r in own} & set(np.argsort(-s)[:20].tolist()))
        assert all(abs(r.score - float(x[i] @ x[r.vec_id])) < 1e-9 for r in own)
    assert hit / 600 >= 0.9
    assert hashing.search(base.limit(0), base.limit(0)).count() == 0
    few = base.filter("vec_id < 5")
    assert hashing.search(few, few).count() == 20


def nearest_ids(x, ids, i, k=20):
    """Brute force: ids of the k largest inner products with row i, other rows of its id too left out."""
    s = np.array([sum(float(a) * float(b) for a, b in zip(r, x[i])) for r in x])
    s[np.array(ids) == ids[i]] = -np.inf
    return sorted(zip(-s, ids))[: min(k, int((np.array(ids) != ids[i]).sum()))]


def test_hashing_on_the_table(spark, sf):
    base = hashing.valid(spark.read.parquet("/root/testdata/sf0.01/embeddings.parquet"))
    rows = base.orderBy("vec_id").collect()
    x, ids = np.array([r.v for r in rows]), np.array([r.vec_id for r in rows])
    got = {}
    for r in hashing.search(base, base.filter("vec_id % 20 = 0"), shard=200).collect():
        got.setdefault(r.query_id, {})[r.vec_id] = r.score
    asked = [i for i, v in enumerate(ids) if v % 20 == 0]
    hit = 0
    for i in asked:
        s = x @ x[i]
        s[i] = -np.inf
        hit += len(set(ids[np.argsort(-s)[:20]].tolist()) & set(got[ids[i]]))
    assert len(got) == len(asked) and hit / (20 * len(asked)) >= 0.9


def test_hashing_lengths_ties_repeats_and_names(spark):
    """Vectors of several lengths, equal vectors, ids that repeat or are null, infinite numbers, columns with the operator's names."""
    rng = np.random.default_rng(3)
    rows = [(i % 30 if i < 40 else i, [float(v) for v in rng.integers(-3, 4, 3 if i % 7 == 0 else 5)] , "x", 1, 2) for i in range(60)]
    rows = [(i, v if any(v) else [1.0] * len(v), *more) for i, v, *more in rows] + [(None, [1.0] * 5, "x", 1, 2), (99, [float("inf")] * 5, "x", 1, 2), (98, [], "x", 1, 2)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>, shard string, ask int, asks int")
    base = hashing.valid(df)
    assert base.count() == 60
    got = hashing.search(base, base.filter("vec_id % 20 = 0"), k=70, shard=25).collect()
    full = [r[1] + [0.0] * (5 - len(r[1])) for r in rows[:60]]
    ids = [r[0] for r in rows[:60]]
    want = sorted((ids[i], rank, v, -s) for i in range(60) if ids[i] % 20 == 0 for rank, (s, v) in enumerate(nearest_ids(full, ids, i, 70), 1))
    assert sorted((r.query_id, r["rank"], r.vec_id, r.score) for r in got) == want
    assert hashing.search(base, base.limit(0)).count() == 0


def test_radius_search_is_complete():
    rng = np.random.default_rng(1)
    code = rng.integers(0, 256, (400, 4)).astype(np.uint8)
    index = hashing.MultiIndex(code)
    for r in (0, 3, 4, 9, 14):
        for q in code[:10]:
            assert set(index.within(q, r)) == set(np.flatnonzero(np.bitwise_count(code ^ q).sum(1) <= r))


class BruteKatz:
    """Katz backoff by dictionaries, word by word."""

    def __init__(self, texts, order):
        self.c = [collections.Counter() for _ in range(order + 1)]
        for ts in texts:
            for i in range(len(ts)):
                for k in range(1, order + 1):
                    if (g := self.gram(ts, i, k)) is not None:
                        self.c[k][g] += 1
        self.n, self.v = sum(self.c[1].values()), len(self.c[1])
        self.d = [None, None, *[katz.discounts(collections.Counter(self.c[k].values())) for k in range(2, order + 1)]]
        self.after = [None, None, *[collections.defaultdict(list) for _ in range(2, order + 1)]]
        for k in range(2, order + 1):
            for g in self.c[k]:
                self.after[k][g[:-1]].append(g[-1])
        self.memo = {}

    @staticmethod
    def gram(ts, i, k):
        """The k-gram that ends at i; before a text stands one beginning, and nothing before that."""
        if i - k + 1 >= 0:
            return tuple(ts[i - k + 1 : i + 1])
        return (" ",) + tuple(ts[: i + 1])

    def held(self, k, r):
        return r * (self.d[k][r - 1] if r <= katz.K else 1.0)

    def weights(self, h, k):
        if (k, h) not in self.memo:
            seen = self.after[k].get(h, [])
            total = sum(self.c[k][h + (w,)] for w in seen)
            kept = sum(self.held(k, self.c[k][h + (w,)]) for w in seen)
            if total - kept < 1e-9 * total:
                total += 1
            low = sum(self.p(h[1:] if h[0] != " " else h, w, k - 1) for w in seen)
            self.memo[k, h] = (total, (1 - kept / total) / (1 - low)) if seen else (0, 1.0)
        return self.memo[k, h]

    def p(self, h, w, k):
        if k == 1:
            return (self.c[1][w,] + 0.1) / (self.n + 0.1 * (self.v + 1))
        h = h[-(k - 1) :]
        total, alpha = self.weights(h, k)
        r = self.c[k][h + (w,)]
        return self.held(k, r) / total if r else alpha * self.p(h[1:] if h[0] != " " else h, w, k - 1)


@pytest.mark.parametrize("order,chunk", [(2, 1 << 20), (3, 3000), (2, 500)])
def test_katz(spark, rows, docs, none, order, chunk, monkeypatch):
    monkeypatch.setattr(katz, "SHARE", 0.02)  # so that many histories are split
    got = by_id(katz.score(docs, F.pmod(common.id_crc(F.col("doc_id")), F.lit(10)) != 0, order=order, chunk=chunk))
    tokens = {i: WORD.findall((t or "").translate(LOW)) + ["\n"] for i, t, *_ in rows}
    train = {i for i in tokens if zlib.crc32(str(i).encode()) % 10}
    model = BruteKatz([tokens[i] for i in train], order)
    for h in list(model.after[order])[:20]:  # exactly normalised, the unknown token included
        assert abs(sum(model.p(h, w, order) for (w,) in model.c[1]) + model.p(h, "unknown", order) - 1) < 1e-9
    for i, ts in tokens.items():
        want = sum(math.log10(model.p((" ",) + tuple(ts[:j]), w, order)) for j, w in enumerate(ts))
        assert math.isclose(got[i].score, want, rel_tol=1e-9) and math.isclose(got[i].base_score, sum(math.log10(model.p((), w, 1)) for w in ts), rel_tol=1e-9)
        assert (got[i].n_tokens, got[i].n_known, got[i].train_tokens, got[i].held_out) == (len(ts), sum((w,) in model.c[1] for w in ts), model.n, i not in train)
    assert katz.score(none, F.lit(True)).count() == 0


def test_katz_repeated_and_null_ids(spark, tmp_path):
    path = str(tmp_path / "d")
    spark.createDataFrame([(None, "a b a", "x"), (None, "a b a", "y"), (1, None, "z"), (1, "zz", "z"), (1, "zz", "z")], "doc_id long, text string, chunk string").repartition(1).write.parquet(path)
    got = katz.score(spark.read.parquet(path), F.lit(True)).collect()
    assert sorted((r.doc_id or 0, r.n_tokens) for r in got) == [(0, 4), (0, 4), (1, 1), (1, 2), (1, 2)]
    assert len({r.score for r in got if r.doc_id is None}) == 1 and all(r.train_tokens == 13 for r in got)
    assert all(r.n_known == 0 and r.train_tokens == 0 for r in katz.score(spark.read.parquet(path), F.lit(False)).collect())


def test_katz_hashes_slices_of_a_chunk(rows, monkeypatch):
    """A chunk's words are hashed a few texts at a time, with the same hashes and places as all at once."""
    import pyarrow as pa

    texts, sizes = pa.array([t for _, t, *_ in rows] + [None, ""]), []
    whole = katz.tokens(texts)

    class Spy(katz.Hasher):
        def __init__(self, data, *args):
            sizes.append(len(data))
            super().__init__(data, *args)

    monkeypatch.setattr(katz, "Hasher", Spy)
    monkeypatch.setattr(katz, "SLICE", 5000)
    assert all(np.array_equal(a, b) for a, b in zip(katz.tokens(texts), whole))
    assert len(sizes) > 1 and max(sizes) <= max(5000, *(len((t or "").encode()) for _, t, *_ in rows))


def test_katz_moves_no_texts(docs, monkeypatch):
    """Rounds get the numbers of a chunk's words, not its texts."""
    seen, inner = [], katz.asks
    monkeypatch.setattr(katz, "asks", lambda chunks, *args: seen.append(chunks.columns) or inner(chunks, *args))
    assert katz.score(docs, F.lit(True)).count() == docs.count()
    assert seen and all("text" not in c for c in seen)


def test_katz_numbers_frequent_words_low(docs):
    """A partition's table runs from its most frequent word on, so that numbers pack well."""
    d = docs.select("doc_id", F.lit(True).alias("train"), "text")
    rows = katz.words_table(katz.words_asked(d, 4, 1 << 20), 4).filter("chunk is null").collect()
    assert rows and all(x == sorted(x, reverse=True) for x in (katz.unpack(r.b).tolist() for r in rows))


def test_mixing(rows, docs, none):
    out, slots, _ = mixing.mix_blocks(docs, block=4, shard=16)
    got, again = out.collect(), {r.doc_id: r.taken for r in mixing.mix_blocks(docs, block=4, shard=16)[0].collect()}
    assert {r.doc_id: r.taken for r in got} == again and len(got) == len(rows)
    size = {i: len(WORD.findall(t or "")) for i, t, *_ in rows}
    assert all(r["size"] == size[r.doc_id] and 0 <= r.taken <= 3 * r["size"] for r in got)
    for source in {r.source for r in got}:
        mine = [r for r in got if r.source == source]
        assert abs(sum(r.taken for r in mine) - mine[0].target) <= 13 and mine[0].target <= 3 * mine[0].source_size + 1e-6
    assert abs(sum({r.source: r.target for r in got}.values()) - sum(size.values())) < 1e-6
    assert mixing.mix_blocks(none)[0].count() == 0


def test_permutation():
    for n in (1, 2, 7, 100, 1000):
        assert sorted(mixing.permute(np.arange(n), np.full(n, n), np.full(n, 9, np.uint64)).tolist()) == list(range(n))


def test_language(spark, none):
    rnd = random.Random(8)
    parts = {"aa": ["ka", "to", "mi", "ra"], "bb": ["sch", "ung", "ein", "er"]}
    make = lambda k: " ".join("".join(rnd.choice(parts[k]) for _ in range(rnd.randint(1, 4))) for _ in range(30))
    rows = [(i, make("ab"[i % 2] * 2), "ab"[i % 2] * 2, "s", 0, "") for i in range(200)] + [(200, None, "aa", "s", 0, ""), (201, "12 !!", None, "s", 0, "")]
    docs = spark.createDataFrame(rows, SCHEMA)
    got = by_id(language.predict(docs, language.train(docs.filter(~language.held_out()))))
    assert all(got[i].lang_pred == "ab"[i % 2] * 2 and 0 <= got[i].score <= 1 for i in range(200))
    assert got[200].lang_pred == got[201].lang_pred == "und"
    assert language.predict(docs, language.train(none)).filter("lang_pred <> 'und'").count() == 0


def test_language_letters(spark, none):
    """What is no letter is no language, though Python counts it as alphanumeric; null and repeated ids; a word seen once counts."""
    rows = [(i, t, lang, "s", 0, "") for i, (t, lang) in enumerate([("alpha beta", "aa"), ("gamma delta", "bb")] * 6)]
    model = language.train(spark.createDataFrame(rows + [(99, "unique", "bb", "s", 0, "")], SCHEMA))
    asked = spark.createDataFrame([(None, "²", "x", "s", 0, ""), (1, "½ Ⅷ ①", "x", "s", 0, ""), (1, "unique", "x", "s", 0, ""), (None, "beta " * 50_000, "x", "s", 0, "")], SCHEMA)
    assert sorted((r.lang_pred, r.score > 0.5) for r in language.predict(asked, model).collect()) == [("aa", True), ("bb", True), ("und", False), ("und", False)]


def test_bpe_long_word_equals_scan(monkeypatch):
    """Beyond SHORT characters a heap finds the merges that scanning finds; a megabyte of letters takes seconds."""
    enc = pieces.RankArrayPieces(open(P.path("word_bpe_49k.json")).read())
    rnd = random.Random(3)
    words = ["".join(rnd.choice("aabcdeinorst") for _ in range(n)) for n in (129, 200, 1000)] + ["ab" * 300, "a" * 257]
    long = [enc.word(w) for w in words]
    assert len(enc.word("".join(rnd.choice("aabcdeinorst") for _ in range(1_000_000)))) > 100_000
    monkeypatch.setattr(pieces, "SHORT", 10**9)
    assert [enc.word(w) for w in words] == long


def test_mixing_deals_large_quotas():
    """Above what numpy draws exactly, a deal still adds up, stays within the quotas, and is near its mean."""
    quota = np.array([7 * 10**9, 10**9, 5, 0, 3 * 10**8], np.int64)
    for n in (0, 1, 10**6, int(quota.sum()) - 3, int(quota.sum())):
        got = mixing.deal(np.random.default_rng(n % 97), quota, n)
        assert got.sum() == n and (got >= 0).all() and (got <= quota).all()
    share = mixing.deal(np.random.default_rng(1), quota, 10**8) / 1e8
    assert np.allclose(share, quota / quota.sum(), atol=1e-3)
    assert sum(c.sum() for k, c in mixing.draws(quota // 1000, 10**5, 1, 0, 5)) > 0


def test_mixing_copies_keep_targets(spark, tmp_path):
    """Sources of few very long texts keep their words near the target; null and shared ids are documents of their own."""
    rows = [(i % 5 if i % 7 else None, "w " * (4000 if i < 6 else 20 + i % 9), "few" if i < 6 else "many", 0, "x") for i in range(400)]
    path = str(tmp_path / "d")
    spark.createDataFrame(rows, "doc_id long, text string, source string, src int, row string").write.parquet(path)
    out = mixing.mix_blocks(spark.read.parquet(path))[0]
    got = out.join(mixing.copies(out), "row", "left").groupBy("source").agg(F.sum(F.coalesce("copies", F.lit(0)) * F.col("size")).alias("words"), F.first("target").alias("target"), F.max("size").alias("most")).collect()
    assert len(got) == 2 and all(abs(r.words - r.target) <= 1.5 * r.most for r in got)


def test_pipeline_stages_equal_brute_force(spark, docs, none, tmp_path):
    """Every stage's rows against brute force or the operator's own rows on that stage's input: shared and null ids, clashing names."""
    import corpus_pipeline as c

    rnd = random.Random(14)
    texts = [" ".join(f"w{rnd.randrange(5000)}" for _ in range(80)) for _ in range(24)]
    texts += [texts[0], texts[1] + " tail", None, "", "too short"]
    rows = [([1, None, i][i % 3] if i < 12 else i, t, "en", "s" if i % 2 else None, i, "clash", i * 2, "own") for i, t in enumerate(texts)]
    path = str(tmp_path / "docs")
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, place int, row string, n_bytes long, spans string").write.parquet(path)
    cur = spark.read.parquet(path)
    for k, (name, stage) in enumerate(c.STAGES):
        out = stage(spark, cur, "")
        have = {r.place: r for r in cur.collect()} if k < 4 else {}
        if k < len(c.STAGES) - 1:
            assert out.columns == cur.columns, name
        out.write.parquet(str(tmp_path / str(k)))
        new = spark.read.parquet(str(tmp_path / str(k)))
        got = new.collect()
        if name == "quality rules":  # nothing here is an outlier, so the base rules decide
            assert {r.place for r in got} == {p for p, r in have.items() if len(WORD.findall(r.text or "")) >= 50}
        if name == "near duplicates":
            order = sorted(have, key=lambda p: (have[p].doc_id is None, have[p].doc_id or 0, p))
            first = near_classes([have[p].text for p in order])
            assert {r.place for r in got} == {order[i] for i in set(first)} and len(got) == 24
        if name == "repeated passages":
            order = sorted(have)
            left = [bytes(np.frombuffer((have[p].text or "").encode(), np.uint8)[~g]).decode() for p, g in zip(order, brute_suffixes([(have[p].text or "").encode() for p in order]))]
            assert [r.text for r in sorted(got, key=lambda r: r.place)] == left
        if name == "source mix":
            assert all(r == have[r.place] for r in got) and len(got) >= 12
        cur = new
    assert cur.columns == ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"] and cur.count() == len(got) > 0
    empty = none
    for k, (name, stage) in enumerate(c.STAGES):
        stage(spark, empty, "").write.parquet(str(tmp_path / f"none{k}"))
        empty = spark.read.parquet(str(tmp_path / f"none{k}"))
        assert empty.count() == 0, name


def near_classes(texts, width=5, percent=80):
    """By brute force, for each row the first row of its class of near duplicates; wordless texts stand alone."""
    sets = []
    for t in texts:
        w = WORD.findall((t or "").translate(LOW))
        sets.append({tuple(w[k : k + width]) for k in range(max(1, len(w) - width + 1))} if w else set())
    root = list(range(len(sets)))
    find = lambda i: i if root[i] == i else find(root[i])
    for i in range(len(sets)):
        for j in range(i):
            if sets[i] and 100 * len(sets[i] & sets[j]) >= percent * len(sets[i] | sets[j]):
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    return [find(i) for i in range(len(sets))]


def near_copies(rnd):
    """Texts of 200 words with copies that five-word shingles and 0.8 link, that three-word shingles and 0.9 don't, and that neither does."""
    out = []
    for edits, tail in ((4, 0), (0, 30), (2, 0), (6, 0), (0, 60), (1, 10), (5, 0)):
        w = [f"w{rnd.randrange(10**6)}" for _ in range(200)]
        copy = list(w)
        for k in range(edits):
            copy[20 + 30 * k] = f"e{k}"
        out += [" ".join(w), " ".join(copy + [f"t{rnd.randrange(10**6)}" for _ in range(tail)])]
    return out


def test_pipeline_near_duplicates_equal_brute_force(spark, rows):
    import corpus_pipeline as c

    copies = near_copies(random.Random(11))
    texts = [t for _, t, *_ in rows] + copies
    docs = spark.createDataFrame([(i, t, "en", "s", 0, "") for i, t in enumerate(texts)], SCHEMA)
    want = {i for i, first in enumerate(near_classes(texts)) if i == first}
    got = c.near_duplicates(spark, docs, "").collect()
    assert len(got) == len(want) and {r.doc_id: r.text for r in got} == {i: texts[i] for i in want}
    at = len(rows)
    assert [at + 2 * k + 1 in want for k in range(7)] == [False, False, False, True, True, False, True]


def robust_distances(x, floor=quality.FLOOR, share=0.75):
    """Squared robust distances of one group's rows of statistics, by numpy: concentration from two starts, least determinant."""
    x = np.rint(np.asarray(x) * quality.STEP)
    least = (np.array(floor) * quality.STEP) ** 2
    need = math.ceil(share * len(x))

    def nearest(far):
        bins = np.floor(np.log1p(far) * 256)
        return x[bins <= np.sort(bins)[need - 1]]

    def fit(part):
        cov = np.cov(part.T, bias=True)
        cov = cov * quality.consistency(max(1, int((np.diag(cov) > least).sum())), share)
        return part.mean(0), cov + np.diag(np.maximum(least - np.diag(cov), 0))

    def distance(m, cov):
        return np.einsum("ij,ij->i", x - m, np.linalg.solve(cov, (x - m).T).T)

    off = np.abs(x - np.sort(x, 0)[(len(x) + 1) // 2 - 1]) / np.sqrt(least)
    ends = []
    for far in (off.sum(1), off.max(1)):
        est = fit(nearest(far))
        for _ in range(quality.ROUNDS):
            est = fit(nearest(distance(*est)))
        ends.append((np.linalg.slogdet(est[1])[1], distance(*est)))
    return min(ends, key=lambda e: e[0])[1]


def test_quality_consistency():
    # For p = 2 and share a: a / (a + (1 - a) ln(1 - a)).
    assert math.isclose(quality.consistency(2, 0.75), 0.75 / (0.75 + 0.25 * math.log(0.25)), rel_tol=1e-9)
    x = np.random.default_rng(0).normal(size=(400_000, 4))
    far = (x**2).sum(1)
    assert math.isclose(1 / x[far <= np.quantile(far, 0.75)].var(), quality.consistency(4, 0.75), rel_tol=0.01)


def test_quality_each_statistic_rejects_by_itself(spark):
    """Texts beside the cutoff in one statistic each: the nearer one stays, the farther one goes; distances equal numpy's."""
    from statistics import NormalDist

    rnd, n = random.Random(5), 100
    long = [NormalDist(math.log1p(5), 0.05).inv_cdf((i + 0.5) / 300) for i in range(300)]

    def text(mean, repeat=0, symbols=0, lines=0):
        chars = round(math.expm1(mean) * n)
        sizes = [chars // n + (k < chars % n) for k in range(n)]
        rnd.shuffle(sizes)
        w = ["".join(rnd.choice("abcdefghijklmnop") for _ in range(size)) for size in sizes]
        w[50 : 50 + repeat] = w[:repeat]
        for k in range(symbols):
            w[70 + k] = "#" + w[70 + k][1:]
        for k in range(lines + 1 if lines else 0):
            w[60 + 10 * k] = "\nqqqqq\n"
        return " ".join(w)

    mid = math.log1p(5)
    edge = [text(mid + 3.2 * 0.05), text(mid + 4.1 * 0.05), text(mid - 3.2 * 0.05), text(mid - 4.1 * 0.05)]
    edge += [text(mid, repeat=6), text(mid, repeat=7), text(mid, symbols=2), text(mid, symbols=3), text(mid, lines=2), text(mid, lines=3)]
    docs = spark.createDataFrame([(i, t, "en", "s", 0, "") for i, t in enumerate([text(m) for m in long] + edge)], SCHEMA)
    got = by_id(quality.judge(docs))
    assert not any(r.base_failed for r in got.values())
    assert [got[300 + i].kept for i in range(10)] == [True, False] * 5
    x = [[math.log1p(r.word_chars / r.n_words), math.log1p(100 * r.n_symbols / r.n_words) / 2, math.sqrt(20 * r.n_dup_lines / r.n_words) / 2, math.sqrt(r.n_repeat_words / r.n_words)] for r in (got[i] for i in range(310))]
    assert np.allclose([got[i].distance for i in range(310)], robust_distances(x), rtol=1e-6, atol=1e-6)
