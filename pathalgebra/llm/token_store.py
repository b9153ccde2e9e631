"""Token ids of a corpus as binary segments with Elias-Fano document borders.

File format.  A store is a folder of Parquet files whose rows are segments.  A
segment holds the ids of consecutive documents (ascending doc_id), one behind
the other, without separators other than the end id:

* ``part``, ``seg``: the range partition and the segment's number in it;
* ``base``: ids of the same part before this segment;
* ``n_docs``, ``n_tokens``; ``width``: bytes of an id, 2 if the vocabulary fits,
  else 4, little-endian; ``ids``: the ids;
* ``ends``: Elias-Fano block of the documents' ends in ``ids``;
* ``n_null``: how many documents at the beginning have no doc_id; they come first;
* ``keys``, ``key_base``, ``key_last``: Elias-Fano block of ``doc_id - key_base`` of
  the others, the first doc_id and the last one, null if there is none.

Parquet through Spark's own writer is the container, so a store may lie in any
file system that Spark reads, and a task that is run again replaces its files.
"""

from __future__ import annotations

import zlib
from bisect import bisect_left, bisect_right
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from pathalgebra.llm.elias_fano import EliasFano
from pathalgebra.llm.tokens import shared_encoder, tokenizer_path
from pathalgebra.runtime import fresh_path

SEGMENT = "part int, seg int, base long, n_docs int, n_tokens long, width int, n_null int, key_base long, key_last long, keys binary, ends binary, ids binary"
_SEGMENT_ARROW = pa.schema([
    ("part", pa.int32()), ("seg", pa.int32()), ("base", pa.int64()), ("n_docs", pa.int32()), ("n_tokens", pa.int64()),
    ("width", pa.int32()), ("n_null", pa.int32()), ("key_base", pa.int64()), ("key_last", pa.int64()), ("keys", pa.binary()), ("ends", pa.binary()), ("ids", pa.binary()),
])
_READ = "doc_id long, part int, local_start long, n_tokens long, ids_crc32 long"
_READ_ARROW = pa.schema([("doc_id", pa.int64()), ("part", pa.int32()), ("local_start", pa.int64()), ("n_tokens", pa.int64()), ("ids_crc32", pa.int64())])


#: Ids of a segment lie within this range, so that their differences are whole numbers of 64 bits.
_KEY_RANGE = 1 << 62


def pack_segment(part: int, seg: int, base: int, doc_ids: list[int | None], ids: list[np.ndarray], width: int) -> dict:
    ends = np.cumsum([len(x) for x in ids])
    keys = np.array([x for x in doc_ids if x is not None], np.int64)
    first, last = (int(keys[0]), int(keys[-1])) if len(keys) else (None, None)
    payload = np.concatenate(ids).astype("<u2" if width == 2 else "<u4").tobytes()
    return {
        "part": part, "seg": seg, "base": base, "n_docs": len(ids), "n_tokens": int(ends[-1]), "width": width,
        "n_null": len(doc_ids) - len(keys), "key_base": first, "key_last": last, "keys": EliasFano.encode(keys - (first or 0)).to_bytes(), "ends": EliasFano.encode(ends).to_bytes(), "ids": payload,
    }


def write_token_store(documents: DataFrame, path: str, tokenizer: str | None = None, end_id: int = 1, segment_tokens: int = 1 << 20) -> None:
    """Encode every text and write the store, ascending by doc_id.

    Null texts count as empty: such a document holds its end id only.  Rows that
    share a doc_id follow each other in the order of their texts; rows without a
    doc_id come first.  One shuffle, of the texts.
    """
    tokenizer = tokenizer or tokenizer_path()

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = shared_encoder(tokenizer, end_id)
        width = 2 if encoder.tokenizer.get_vocab_size() <= 1 << 16 else 4
        part = TaskContext.get().partitionId()
        seg, base, held = 0, 0, 0
        keys: list[int | None] = []
        first: int | None = None
        ids: list[np.ndarray] = []
        for batch in batches:
            doc_ids = batch.column(0).to_pylist()
            for doc_id, x in zip(doc_ids, encoder.encode(batch.column(1)), strict=True):
                if doc_id is not None:
                    first = doc_id if first is None else first
                    if doc_id - first >= _KEY_RANGE:
                        yield pa.RecordBatch.from_pylist([pack_segment(part, seg, base, keys, ids, width)], _SEGMENT_ARROW)
                        seg, base, held, keys, ids, first = seg + 1, base + held, 0, [], [], doc_id
                keys.append(doc_id)
                ids.append(x)
                held += len(x)
                if held >= segment_tokens:
                    yield pa.RecordBatch.from_pylist([pack_segment(part, seg, base, keys, ids, width)], _SEGMENT_ARROW)
                    seg, base, held, keys, ids, first = seg + 1, base + held, 0, [], [], None
        if ids:
            yield pa.RecordBatch.from_pylist([pack_segment(part, seg, base, keys, ids, width)], _SEGMENT_ARROW)

    docs = documents.select(F.col("doc_id").cast("long"), "text")
    ordered = docs.repartitionByRange("doc_id").sortWithinPartitions("doc_id", "text")
    ordered.mapInArrow(encode, SEGMENT).write.option("compression", "zstd").parquet(path)


def read_token_store(documents_path: str, spark) -> DataFrame:
    """Per document, from the files: doc_id, start, n_tokens, ids_crc32."""

    def decode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(len(batch)):
                row = batch.slice(k, 1).to_pylist()[0]
                ends = EliasFano.from_bytes(row["ends"]).select_many(np.arange(row["n_docs"]))
                named = row["n_docs"] - row["n_null"]
                keys = EliasFano.from_bytes(row["keys"]).select_many(np.arange(named)) + (row["key_base"] or 0)
                keys = pa.concat_arrays([pa.nulls(row["n_null"], pa.int64()), pa.array(keys, pa.int64())])
                starts = np.concatenate([[0], ends[:-1]])
                ids = np.frombuffer(row["ids"], "<u2" if row["width"] == 2 else "<u4").astype("<u4")
                crcs = [zlib.crc32(ids[a:b]) for a, b in zip(starts.tolist(), ends.tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays(
                    [keys, pa.array(np.full(len(keys), row["part"], np.int32)), pa.array(starts + row["base"]), pa.array(ends - starts), pa.array(crcs, pa.int64())],
                    schema=_READ_ARROW,
                )

    segments = spark.read.schema(SEGMENT).parquet(documents_path)
    # One row for each range partition of the writer, so both sides of this are bounded by the number of its tasks.
    offsets = segments.groupBy("part").agg(F.sum("n_tokens").alias("tokens"))
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = offsets.select("part", F.coalesce(F.sum("tokens").over(before), F.lit(0)).alias("offset"))
    rows = segments.mapInArrow(decode, _READ)
    return rows.join(F.broadcast(offsets), "part").select("doc_id", (F.col("offset") + F.col("local_start")).alias("start"), "n_tokens", "ids_crc32")


def tokens_of(spark, path: str, doc_ids: list[int]) -> DataFrame:
    """(doc_id, ids) of the asked documents, one row for each that the store holds.

    Only segments whose range of ids holds one are read; select finds a document
    and its two borders, so nothing else of a segment is decoded.
    """
    asked = sorted(set(doc_ids))

    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(len(batch)):
                row = batch.slice(k, 1).to_pylist()[0]
                ends, keys = EliasFano.from_bytes(row["ends"]), EliasFano.from_bytes(row["keys"])
                said, found = [], []
                for want in asked[bisect_left(asked, row["key_base"]) : bisect_right(asked, row["key_last"])]:
                    at = keys.place_of(want - row["key_base"])
                    while at < keys.n and keys.select(at) == want - row["key_base"]:
                        place = at + row["n_null"]
                        begin, end = ends.select(place - 1) if place else 0, ends.select(place)
                        ids = np.frombuffer(row["ids"], "<u2" if row["width"] == 2 else "<u4", end - begin, begin * row["width"])
                        said.append(want)
                        found.append(ids.astype(np.int64))
                        at += 1
                yield pa.RecordBatch.from_arrays([pa.array(said, pa.int64()), pa.array(found, pa.list_(pa.int64()))], names=["doc_id", "ids"])

    segments = spark.read.schema(SEGMENT).parquet(path)
    if not asked:
        return segments.limit(0).mapInArrow(find, "doc_id long, ids array<long>")
    near = segments.where((F.col("key_last") >= asked[0]) & (F.col("key_base") <= asked[-1]))
    return near.mapInArrow(find, "doc_id long, ids array<long>")


def encode_corpus(documents: DataFrame, tokenizer: str | None = None, path: str | None = None) -> DataFrame:
    """Write a store of ``documents`` in the shared folder and read it back.

    An empty table gives an empty store and no rows.  Other columns are ignored.
    """
    spark = documents.sparkSession
    path = path or fresh_path(spark, "token-store")
    write_token_store(documents, path, tokenizer)
    return read_token_store(path, spark)
