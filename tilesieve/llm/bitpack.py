"""Token ids as fixed-width bit-packed blocks.

A block holds whole documents in order. Its bytes: ``MAGIC``, version, bits an id, number of
documents and of ids, then the documents' lengths (unsigned 32 bit) and the ids, each in the fewest
bits that hold the vocabulary, lowest bit first. Id i of a block begins at bit i * bits, so any range
unpacks with numpy alone and any single id is one shift away. Blocks are rows of Parquet files, the
only files that every store Spark writes to can hold; ``block_index`` gives where each begins.
"""

from __future__ import annotations

import json
import os
import struct
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.errors import AnalysisException
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from tilesieve.llm.common import arrow_batches, frugal, scratch_root, ship, text_bytes, text_slices
from tilesieve.llm.wordbpe import WordBPE

ship(__name__)

MAGIC = b"TSBP"
HEADER = "<4sBBHIQ"
#: A block closes with the document that brings it to so many ids.
BLOCK_IDS = 1 << 17
#: Bytes of text encoded at once: a word that they repeat is merged once.
SLICE_BYTES = 4 << 20


def width(vocabulary: int) -> int:
    """Fewest bits that hold ids 0 to vocabulary - 1."""
    return max(1, int(vocabulary - 1).bit_length())


def pack(ids: np.ndarray, bits: int) -> bytes:
    """Ids (below 2**bits) one after another, ``bits`` each."""
    ids = np.ascontiguousarray(ids, "<u4")
    if bits in (8, 16, 32):
        return ids.astype(f"<u{bits // 8}").tobytes()
    lanes = np.unpackbits(ids.view(np.uint8).reshape(-1, 4), axis=1, bitorder="little")[:, :bits]
    return np.packbits(lanes.reshape(-1), bitorder="little").tobytes()


def unpack(data: bytes | memoryview, bits: int, start: int, count: int) -> np.ndarray:
    """Ids ``start`` to ``start + count`` of packed data, reading only the bytes that hold them."""
    if bits in (8, 16, 32):
        return np.frombuffer(data, f"<u{bits // 8}", count, start * bits // 8).astype(np.uint32)
    first, last = start * bits // 8, -(-(start + count) * bits // 8)
    raw = np.unpackbits(np.frombuffer(data, np.uint8, last - first, first), bitorder="little")
    skip = start * bits - first * 8
    lanes = np.zeros((count, 32), np.uint8)
    lanes[:, :bits] = raw[skip : skip + count * bits].reshape(count, bits)
    return np.packbits(lanes, axis=1, bitorder="little").view("<u4").reshape(-1)


def encode_block(lengths: list[int], ids: np.ndarray, bits: int) -> bytes:
    return struct.pack(HEADER, MAGIC, 1, bits, 0, len(lengths), len(ids)) + np.asarray(lengths, "<u4").tobytes() + pack(ids, bits)


class Block:
    """Random access to a packed block."""

    def __init__(self, data: bytes):
        magic, version, self.bits, _, docs, self.n_ids = struct.unpack_from(HEADER, data)
        if magic != MAGIC or version != 1:
            raise ValueError("not a packed block")
        self.lengths = np.frombuffer(data, "<u4", docs, struct.calcsize(HEADER)).astype(np.int64)
        self.ends = np.cumsum(self.lengths)
        self.data = memoryview(data)[struct.calcsize(HEADER) + 4 * docs :]

    def document(self, k: int) -> np.ndarray:
        return unpack(self.data, self.bits, int(self.ends[k] - self.lengths[k]), int(self.lengths[k]))

    def token(self, i: int) -> int:
        return int(unpack(self.data, self.bits, i, 1)[0])


class ColumnEncoder:
    """Encodes a column of texts: in numpy where the definition allows, else by the library, loaded only then."""

    def __init__(self, path: str):
        self.path, self._library = path, None
        with open(path, encoding="utf-8") as f:
            definition = json.load(f)
        self.vocabulary = 1 + max([*definition["model"]["vocab"].values(), *(t["id"] for t in definition.get("added_tokens", []))])
        fast = WordBPE(definition, self.library) if WordBPE.fits(definition) else None
        self.fast = fast if fast is not None and fast.orderly else None

    def library(self) -> Tokenizer:
        if self._library is None:
            os.environ["TOKENIZERS_PARALLELISM"] = "false"
            self._library = Tokenizer.from_file(self.path)
        return self._library

    def encode(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Flat ids, and how many each text has."""
        if self.fast is not None:
            return self.fast.encode(*text_bytes(column))
        found = [e.ids for e in self.library().encode_batch_fast([t or "" for t in column.to_pylist()], add_special_tokens=False)]
        return np.array([i for ids in found for i in ids], np.uint32), np.array([len(ids) for ids in found], np.int64)


FILE_SCHEMA = "part int, block int, n_docs int, n_ids bigint, bits int, doc_ids array<bigint>, payload binary"


def stored_order(df: DataFrame) -> list[Column] | None:
    """The order of the rows of a frame read from files, by file name and place in it; None for any other frame."""
    try:
        df.select("_metadata.file_name", "_metadata.row_index")
    except AnalysisException:
        return None
    return [F.col("_metadata.file_name"), F.col("_metadata.row_index")]


def write_ids(df: DataFrame, path: str, tokenizer: str, *, end_id: int = 1, block_ids: int = BLOCK_IDS, order: list[Column] | None = None) -> None:
    """Encode every whole text and write packed blocks in ascending ``doc_id`` order (null first), or by ``order``.

    ``tokenizer`` is a path that executors can open (an installed file). ``end_id`` ends each
    document; null and empty texts are that id alone. Equal ids keep an order by text; an empty table
    writes no block. Documents never span blocks, and files never span range partitions.
    """

    @frugal
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        encoder = ColumnEncoder(tokenizer)
        bits, part, block = width(max(encoder.vocabulary, end_id + 1)), TaskContext.get().partitionId(), 0
        keys: list[int | None] = []
        lengths: list[int] = []
        held: list[np.ndarray] = []

        def close() -> pa.RecordBatch:
            ids = np.concatenate(held)
            row = [[part], [block], [len(keys)], [len(ids)], [bits], [list(keys)], [encode_block(lengths, ids, bits)]]
            kinds = [pa.int32(), pa.int32(), pa.int32(), pa.int64(), pa.int32(), pa.list_(pa.int64()), pa.binary()]
            return pa.RecordBatch.from_arrays([pa.array(v, k) for v, k in zip(row, kinds, strict=True)], names=["part", "block", "n_docs", "n_ids", "bits", "doc_ids", "payload"])

        total = 0
        for batch in batches:
            for rows in text_slices(batch, most=SLICE_BYTES):
                flat, counts = encoder.encode(rows.column(1))
                ids = np.insert(flat, np.cumsum(counts), np.uint32(end_id))
                ends = np.cumsum(counts + 1)
                names, at = rows.column(0).to_pylist(), 0
                while at < len(names):
                    begin = int(ends[at - 1]) if at else 0
                    to = min(int(np.searchsorted(ends, begin + block_ids - total)) + 1, len(names))
                    keys += names[at:to]
                    lengths += (counts[at:to] + 1).tolist()
                    held.append(ids[begin : int(ends[to - 1])])
                    total += int(ends[to - 1]) - begin
                    at = to
                    if total >= block_ids:
                        yield close()
                        block, total = block + 1, 0
                        keys.clear(), lengths.clear(), held.clear()
        if keys:
            yield close()

    keys_of = order or [F.col("doc_id").cast("bigint"), F.col("text")]
    names_of = [f"_o{i}" for i in range(len(keys_of))]
    rows = df.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text").alias("text"), *[c.alias(n) for c, n in zip(keys_of, names_of, strict=True)] if order else [])
    by = [F.col(n).asc_nulls_first() for n in (names_of if order else ("doc_id", "text"))]
    ordered = rows.repartitionByRange(*(by if order else by[:1])).sortWithinPartitions(*by).select("doc_id", "text")
    with arrow_batches(df.sparkSession, SLICE_BYTES):
        ordered.mapInArrow(run, FILE_SCHEMA).write.mode("errorifexists").option("compression", "zstd").parquet(path)


def block_index(spark: SparkSession, path: str) -> DataFrame:
    """Where each block begins: ``part``, ``block``, ``block_start`` (ids of all blocks before it).

    Reads block counts alone, not payloads; sums run by file, then over files.
    """
    blocks = spark.read.schema(FILE_SCHEMA).parquet(path).select("part", "block", "n_ids")
    upto = lambda w: w.rowsBetween(Window.unboundedPreceding, -1)
    parts = blocks.groupBy("part").agg(F.sum("n_ids").alias("n"))
    files = parts.select("part", F.coalesce(F.sum("n").over(upto(Window.orderBy("part"))), F.lit(0)).alias("file_start"))
    inner = F.coalesce(F.sum("n_ids").over(upto(Window.partitionBy("part").orderBy("block"))), F.lit(0))
    return blocks.withColumn("inner", inner).join(files, "part").select("part", "block", (F.col("file_start") + F.col("inner")).alias("block_start"))


READ_SCHEMA = "doc_id bigint, start bigint, n_tokens bigint, ids_crc32 bigint"


def read_ids(spark: SparkSession, path: str) -> DataFrame:
    """A row for each document of packed files: where its ids begin, how many, and their crc32."""

    @frugal
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(batch.num_rows):
                block = Block(batch.column(2)[k].as_py())
                begin = batch.column(0)[k].as_py() + block.ends - block.lengths
                crc = [zlib.crc32(block.document(i).astype("<u4").tobytes()) for i in range(len(block.lengths))]
                yield pa.RecordBatch.from_arrays([pa.array(batch.column(1)[k].as_py(), pa.int64()), pa.array(begin, pa.int64()), pa.array(block.lengths, pa.int64()), pa.array(crc, pa.int64())], names=["doc_id", "start", "n_tokens", "ids_crc32"])

    blocks = spark.read.schema(FILE_SCHEMA).parquet(path)
    placed = blocks.join(block_index(spark, path), ["part", "block"])
    return placed.select("block_start", "doc_ids", "payload").mapInArrow(run, READ_SCHEMA)


def packed_documents(df: DataFrame, tokenizer: str, *, end_id: int = 1, path: str | None = None, order: list[Column] | None = None) -> DataFrame:
    """Write the ids of all documents to ``path`` (a new shared folder unless given) and read them back.

    Documents are packed by ``order``, or by id. Nulls, ties, repeated rows and empty tables are as in
    ``write_ids``; other columns are left out.
    """
    spark = df.sparkSession
    path = path or f"{scratch_root(spark)}/packed-{uuid.uuid4().hex}"
    write_ids(df, path, tokenizer, end_id=end_id, order=order)
    return read_ids(spark, path)
