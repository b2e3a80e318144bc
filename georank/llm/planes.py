"""Operator 1: token ids in files of compressed byte or bit planes.

A file's rows are record groups: whole documents in ascending order. A group's ids are cut into blocks of a fixed
size; a block is transposed into planes, each plane is compressed with zstandard, and the group's chunk index holds
every plane's compressed length. The container is Parquet, so any store that Spark reaches will do and a lost
executor's files are written again by the commit protocol.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import parts, shared_path, sliced, table
from .pieces import LibraryPieces, opened, packed

BLOCK = 16_384
GROUP = 131_072
FORMAT = "part int, group_no long, bits boolean, n_ids long, doc_ids array<long>, doc_tokens array<long>, chunk_index array<int>, payload binary"


def to_planes(block: np.ndarray, bits: bool) -> list[bytes]:
    """Planes of a block of unsigned 32-bit ids, lowest first; planes above the highest id are left out."""
    width = max(1, int(block.max(initial=0)).bit_length())
    if bits:
        return [np.packbits((block >> np.uint32(k)).astype(np.uint8) & 1).tobytes() for k in range(width)]
    return [(block >> np.uint32(k)).astype(np.uint8).tobytes() for k in range(0, width, 8)]


def from_planes(planes: list[bytes], n: int, bits: bool) -> np.ndarray:
    out = np.zeros(n, "<u4")
    for i, p in enumerate(planes):
        p = np.frombuffer(p, np.uint8)
        out |= (np.unpackbits(p, count=n) if bits else p).astype("<u4") << np.uint32(i if bits else 8 * i)
    return out


def pack(ids: np.ndarray, bits: bool = False, level: int = 1) -> tuple[list[int], bytes]:
    """The chunk index (for each block the number of planes, then their lengths) and the payload."""
    import zstandard

    z, index, out = zstandard.ZstdCompressor(level=level), [], []
    for at in range(0, len(ids), BLOCK):
        planes = [z.compress(p) for p in to_planes(ids[at : at + BLOCK], bits)]
        index += [len(planes), *map(len, planes)]
        out += planes
    return index, b"".join(out)


def unpack(index: list[int], payload: bytes, n_ids: int, bits: bool = False) -> np.ndarray:
    import zstandard

    z, at, k, out = zstandard.ZstdDecompressor(), 0, 0, []
    for done in range(0, n_ids, BLOCK):
        planes = []
        for size in index[k + 1 : k + 1 + index[k]]:
            planes.append(z.decompress(payload[at : at + size]))
            at += size
        k += 1 + index[k]
        out.append(from_planes(planes, min(BLOCK, n_ids - done), bits))
    return np.concatenate(out) if out else np.zeros(0, "<u4")


def write(df: DataFrame, out: str, path: str, end_id: int | None = 2, bits: bool = False, text: str = "text") -> None:
    """Encode every text and write its ids, then end_id, in ascending doc_id order (null ids first; ties by text).

    Null texts count as empty: with an end id they have that id alone. Repeated rows are all written.
    An empty table gives an empty folder of the format. Other columns aren't read, whatever their names. A text is encoded as a
    whole, however long; a very long one makes its record group longer, as a group holds whole documents.
    """
    spec = packed(path)

    def run(batches):
        enc, part, number = opened(LibraryPieces, spec), TaskContext.get().partitionId(), 0
        ids: list[np.ndarray] = []
        docs: list[pa.Array] = []
        counts: list[np.ndarray] = []
        held = 0

        def group():
            joined = np.concatenate(ids)
            index, payload = pack(joined, bits)
            n = pa.array(np.concatenate(counts))
            cols = [pa.array([part], pa.int32()), pa.array([number], pa.int64()), pa.array([bits]), pa.array([len(joined)], pa.int64())]
            cols += [pa.ListArray.from_arrays(pa.array([0, len(n)], pa.int32()), pa.concat_arrays(docs)), pa.ListArray.from_arrays(pa.array([0, len(n)], pa.int32()), n)]
            cols += [pa.array([index], pa.list_(pa.int32())), pa.array([payload], pa.binary())]
            return pa.RecordBatch.from_arrays(cols, ["part", "group_no", "bits", "n_ids", "doc_ids", "doc_tokens", "chunk_index", "payload"])

        for batch in sliced(batches, "text", 8 << 20):
            got, off = enc.encode_column(batch.column(1))
            if end_id is not None:
                got, off = np.insert(got, off[1:], end_id), off + np.arange(len(off))
            at = 0
            while at < batch.num_rows:  # a group ends with the document that fills it
                upto = min(batch.num_rows, int(np.searchsorted(off, off[at] + GROUP - held)))
                upto = max(upto, at + 1)
                ids.append(got[off[at] : off[upto]])
                docs.append(batch.column(0).slice(at, upto - at))
                counts.append(np.diff(off[at : upto + 1]))
                held += int(off[upto] - off[at])
                at = upto
                if held >= GROUP:
                    yield group()
                    ids, docs, counts, held, number = [], [], [], 0, number + 1
        if docs:
            yield group()

    ordered = df.select(df["doc_id"].cast("long").alias("doc_id"), df[text].alias("text")).repartitionByRange(parts(df.sparkSession), F.col("doc_id").asc_nulls_first())
    ordered.sortWithinPartitions(F.col("doc_id").asc_nulls_first(), "text").mapInArrow(run, FORMAT).write.option("compression", "none").parquet(out)


def read(spark: SparkSession, path: str, ids: bool = True) -> DataFrame:
    """One row per document from the files: doc_id, start (ids of all documents before it), n_tokens, ids_crc32 and, if asked for, ids."""
    files = spark.read.schema(FORMAT).parquet(path)
    head = files.groupBy("part").agg(F.sum("n_ids").alias("n"))
    head = head.select("part", (F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1))).alias("before"))
    start = files.select("part", "group_no", F.coalesce(F.sum("n_ids").over(Window.partitionBy("part").orderBy("group_no").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("inside"))
    start = start.join(head, "part").select("part", "group_no", (F.coalesce("before", F.lit(0)) + F.col("inside")).alias("base"))

    def run(batches):
        for batch in batches:
            for row in (r for i in range(batch.num_rows) for r in batch.slice(i, 1).to_pylist()):
                got = unpack(row["chunk_index"], row["payload"], row["n_ids"], row["bits"])
                ends = np.cumsum(row["doc_tokens"])
                cols = {"part": [], "group_no": [], "doc_id": row["doc_ids"], "offset": [], "n_tokens": row["doc_tokens"], "ids_crc32": []}
                lists = []
                for e, n in zip(ends.tolist(), row["doc_tokens"]):
                    cols["part"].append(row["part"])
                    cols["group_no"].append(row["group_no"])
                    cols["offset"].append(e - n)
                    cols["ids_crc32"].append(zlib.crc32(got[e - n : e].tobytes()))
                    if ids:
                        lists.append(got[e - n : e].astype(np.int32))
                kinds = [pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int64()]
                arrays = [pa.array(v, k) for v, k in zip(cols.values(), kinds)]
                yield pa.RecordBatch.from_arrays(arrays + ([pa.array(lists, pa.list_(pa.int32()))] if ids else []), [*cols, *["ids"] * ids])

    docs = files.mapInArrow(run, "part int, group_no long, doc_id long, offset long, n_tokens long, ids_crc32 long" + ", ids array<int>" * ids)
    return docs.join(start, ["part", "group_no"]).select("doc_id", (F.col("base") + F.col("offset")).alias("start"), "n_tokens", "ids_crc32", *["ids"] * ids)


def op1_bit_planes(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    out = shared_path(spark, "planes")
    write(table(spark, sf_dir, "documents"), out, public_tokenizers.path("byte_bpe_50k.json"))
    return read(spark, out, ids=False)
