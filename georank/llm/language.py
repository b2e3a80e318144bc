"""Operator 10: language identification by words first, then by ever shorter character n-grams.

A word that training saw is scored by its log frequency in each language. An unseen word backs off: to the longest
character n-grams of which at least one is known, and from those to shorter ones.
"""

from __future__ import annotations

import math
from collections import Counter

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import checkpointed, id_crc, sliced, table

#: Training documents of a language (a bounded sample by hash), longest n-gram.
SAMPLE, LONGEST = 1500, 4
#: A run of letters is a word, in training and prediction alike; a text without one has no language.
WORD = r"\p{L}+"
LETTERS = regex.compile(WORD)
CACHE = 300_000
#: Languages up to which their sizes are broadcast.
FEW = 10_000


def held_out(folds: int = 5):
    return F.pmod(id_crc(F.col("doc_id")), F.lit(folds)) == 0


def train(docs: DataFrame, sample: int = SAMPLE, longest: int = LONGEST) -> dict:
    """The model: languages, and for words and for n-grams of each length a table of log frequencies by language.

    It is fitted on about `sample` documents of each language, drawn by a hash of the id (null ids: of the text); all their words and n-grams
    are kept, so the sample's bound is the model's. Rows with null text or null lang don't train.
    """
    rows = docs.select(docs["doc_id"].cast("long").alias("doc_id"), docs["text"].alias("text"), docs["lang"].alias("lang")).filter("text is not null and lang is not null")
    sizes = checkpointed(rows.groupBy("lang").agg(F.count("*").alias("n")))
    sizes = F.broadcast(sizes) if sizes.count() <= FEW else sizes
    share = F.least(F.lit(1.0), F.lit(float(sample)) / F.col("n"))
    draw = F.pmod(F.coalesce(F.when(F.col("doc_id").isNotNull(), F.xxhash64("doc_id", F.lit(17))), F.xxhash64("text", F.lit(17))), F.lit(1 << 30)) / float(1 << 30)
    chosen = rows.select("lang", "text", draw.alias("draw")).join(sizes, "lang").filter(F.col("draw") < share).select("lang", "text")
    tokens = chosen.select("lang", F.explode(F.regexp_extract_all(F.lower("text"), F.lit(WORD), F.lit(0))).alias("w")).groupBy("lang", "w").agg(F.count("*").alias("c"))
    tokens = checkpointed(tokens)
    padded = F.concat(F.lit(" "), "w", F.lit(" "))
    gram = tokens.select("lang", "c", F.explode(F.array(*[F.lit(n) for n in range(1, longest + 1)])).alias("n"), padded.alias("p"))
    gram = gram.filter(F.char_length("p") >= F.col("n")).select("lang", "c", "n", F.explode(F.transform(F.sequence(F.lit(1), F.char_length("p") - F.col("n") + 1), lambda i: F.substring(F.col("p"), i, F.col("n")))).alias("g")).groupBy("lang", "n", "g").agg(F.sum("c").alias("c"))
    totals = {r[0]: r[1] for r in tokens.groupBy("lang").agg(F.sum("c")).collect()}
    langs = sorted(totals)

    def table_of(counts: list[tuple[str, str, int]]) -> tuple[dict[str, int], np.ndarray]:
        """Each item's row in a table of its log frequencies by language."""
        at: dict[str, int] = {}
        for _, item, _ in counts:
            at.setdefault(item, len(at))
        have = np.zeros((len(at), len(langs)))
        for lang, item, c in counts:
            have[at[item], langs.index(lang)] = c
        return at, np.log((have + 0.5) / (have.sum(0) + 0.5 * len(at)))

    model = {"langs": langs, "words": table_of([(r.lang, r.w, r.c) for r in tokens.select("lang", "w", "c").orderBy("w", "lang").collect()]), "grams": {}}
    found: dict[int, list] = {}
    for r in gram.select("lang", "n", "g", "c").orderBy("g", "lang").collect():
        found.setdefault(r.n, []).append((r.lang, r.g, r.c))
    model["grams"] = {n: table_of(v) for n, v in sorted(found.items(), reverse=True)}
    return model


def score_word(model: dict, word: str) -> list[float] | None:
    """Log scores by language; None if nothing of the word is known."""
    known, scores = model["words"]
    if (i := known.get(word)) is not None:
        return scores[i].tolist()
    padded = f" {word} "
    for n, (known, scores) in model["grams"].items():
        hits = [known[g] for i in range(len(padded) - n + 1) if (g := padded[i : i + n]) in known and g != " "]
        if hits:
            return scores[hits].mean(0).tolist()
    return None


def predict(docs: DataFrame, model: dict) -> DataFrame:
    """doc_id, lang_pred and score (0 to 1, the languages' posterior under even priors).

    Null texts and texts without a letter, and all texts under an empty model, get `und` and 0. Ties go to the language
    that comes first. Rows are taken one by one, so repeated rows and ids get equal results; whole texts count, however long. Only doc_id and text
    are read, whatever else docs has.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        m = shared.value
        langs = m["langs"]
        cache: dict[str, list | None] = {}
        for batch in sliced(batches, "text"):
            pred, score = [], []
            for t in batch.column(1).to_pylist():
                counts = Counter(LETTERS.findall((t or "").lower()))
                total = [0.0] * len(langs)
                for w, c in counts.items():
                    s = cache.get(w, 0)
                    if s == 0:
                        if len(cache) >= CACHE:
                            cache.clear()
                        s = cache[w] = score_word(m, w)
                    if s:
                        total = [a + c * b for a, b in zip(total, s)]
                if not counts or not langs:
                    pred.append("und")
                    score.append(0.0)
                    continue
                top = max(total)
                pred.append(langs[total.index(top)])
                score.append(1 / sum(math.exp(max(-700.0, x - top)) for x in total))
            yield pa.RecordBatch.from_pydict({"doc_id": batch.column(0), "lang_pred": pa.array(pred, pa.string()), "score": pa.array(score, pa.float64())})

    return docs.select(docs["doc_id"].cast("long").alias("doc_id"), docs["text"].alias("text")).mapInArrow(run, "doc_id long, lang_pred string, score double")


def op10_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = train(docs.filter(~held_out()))
    return predict(docs, model).select("doc_id", held_out().alias("held_out"), "lang_pred", "score")
