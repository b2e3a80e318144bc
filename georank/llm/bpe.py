"""Operator 8: BPE encoding and decoding by a contiguous rank array."""

from __future__ import annotations

import hashlib

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from .common import sliced, table
from .pieces import RankArrayPieces, opened, packed


def encode(df: DataFrame, path: str, text: str = "text", keep: tuple[str, ...] = ("doc_id",), digests: bool = False) -> DataFrame:
    """The `keep` columns of each row, n_tokens, and ids (array of int) or, with digests, ids_sha256 and decoded_sha256.

    Null and empty texts give no ids. Rows are taken one by one: repeated rows give repeated results, an empty table
    none, and other columns than `text` and `keep` aren't read, whatever their names.
    """
    spec = packed(path)
    kept = [df.schema[c] for c in keep]

    def run(batches):
        bpe = opened(RankArrayPieces, spec)
        for batch in sliced(batches, "__text"):
            cols = {c: batch.column(i) for i, c in enumerate(keep)}
            n, ids, decoded = [], [], []
            for parts in bpe.entries_all([t or "" for t in batch.column(len(keep)).to_pylist()]):
                n.append(sum([e[0] for e in parts]))
                if digests:
                    ids.append(hashlib.sha256(" ".join([e[1] for e in parts]).encode()).hexdigest())
                    decoded.append(hashlib.sha256(" ".join([e[2] for e in parts]).encode()).hexdigest())
                else:
                    ids.append([int(i) for e in parts for i in e[1].split(" ")])
            cols["n_tokens"] = pa.array(n, pa.int64())
            cols |= {"ids_sha256": pa.array(ids), "decoded_sha256": pa.array(decoded)} if digests else {"ids": pa.array(ids, pa.list_(pa.int32()))}
            yield pa.RecordBatch.from_pydict(cols)

    made = "n_tokens long, ids_sha256 string, decoded_sha256 string" if digests else "n_tokens long, ids array<int>"
    schema = ", ".join([f"`{f.name}` {f.dataType.simpleString()}" for f in kept] + [made])
    return df.select(*[df[c] for c in keep], df[text].alias("__text")).mapInArrow(run, schema)


def decode(df: DataFrame, path: str, ids: str = "ids") -> DataFrame:
    """All columns and decoded: the tokens of `ids` as the library's decode(skip_special_tokens=False) joins them; null ids give null."""
    from pyspark.sql import functions as F

    spec = packed(path)

    @F.pandas_udf("string")
    def text(col):
        bpe = opened(RankArrayPieces, spec)
        return col.map(lambda x: None if x is None else bpe.decode(x))

    return df.withColumn("decoded", text(ids))


def op8_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return encode(table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"), digests=True)
