"""Token-id files of directly addressable codes: any token can be read without decoding its block.

An id is cut into chunks of a fixed number of bits, lowest first. Level 0 holds the first chunk of every id, level k the next
chunk of those ids that need it; a bitmap per level says which go on, and a directory of ranks, one for every 512 bits, leads from a place in a level
to its place in the next. One byte string holds a segment of consecutive documents.

The files are Parquet tables of segments, written by Spark's own writer so that a lost task is done again whole, into any store Spark writes to:
(part, seq, doc_ids, lengths, codes), in ascending order of documents by (part, seq). Documents are dealt by ranges of their ids and sorted in each; places in the whole
stream are sums of the segments' counts, first within a part, then over the parts.

Edge cases: a null or empty text has only the end id; a null doc_id sorts first; rows with equal ids stand in the order of their texts; texts of any
length are encoded in parts and a document never spans segments; an empty table gives files without rows; other columns are not stored.
"""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from graphslices.llm.bpe import encoder
from graphslices.llm.common import shared_path, written
from graphslices.session import ship

MAGIC, BITS, STEP = b"DAC1", 8, 512
SEGMENT_SCHEMA = "part long, seq long, doc_ids array<bigint>, lengths array<bigint>, codes binary"
SEGMENT_TOKENS = 1 << 20
MOST_SENT = 1 << 20


def pack(ids: np.ndarray) -> bytes:
    """Header (magic, count of levels), then for each level its size, bitmap, rank directory and chunks."""
    rest, levels = np.asarray(ids, dtype=np.uint32), []
    while True:
        more = rest >> BITS
        on = more > 0
        bitmap = np.packbits(on, bitorder="little")
        bitmap = np.concatenate([bitmap, np.zeros(-len(bitmap) % (STEP // 8), np.uint8)])
        ranks = np.concatenate([[0], np.cumsum(np.bitwise_count(bitmap.reshape(-1, STEP // 8)).sum(axis=1, dtype=np.int64))])[:-1].astype("<u4")
        levels.append(struct.pack("<QQ", len(rest), len(bitmap)) + bitmap.tobytes() + ranks.tobytes() + (rest & (2**BITS - 1)).astype(np.uint8).tobytes())
        if not on.any():
            break
        rest = more[on]
    return MAGIC + struct.pack("<I", len(levels)) + b"".join(levels)


class Reader:
    def __init__(self, codes: bytes):
        if codes[:4] != MAGIC:
            raise ValueError("not a token file")
        at, self.levels = 8, []
        for _ in range(struct.unpack_from("<I", codes, 4)[0]):
            n, size = struct.unpack_from("<QQ", codes, at)
            at += 16
            bitmap = np.frombuffer(codes, np.uint8, size, at)
            ranks = np.frombuffer(codes, "<u4", size * 8 // STEP, at + size)
            at += size + ranks.nbytes
            self.levels.append((bitmap, ranks, np.frombuffer(codes, np.uint8, n, at)))
            at += n
        self.n = len(self.levels[0][2])

    @staticmethod
    def _rank(bitmap: np.ndarray, ranks: np.ndarray, i: int) -> int:
        """Set bits before place i."""
        block = i // STEP
        if block >= len(ranks):
            block = len(ranks) - 1
        if block < 0:
            return 0
        whole, bits = divmod(i - block * STEP, 8)
        at = block * STEP // 8
        out = int(ranks[block]) + int(np.bitwise_count(bitmap[at : at + whole]).sum(dtype=np.int64))
        return out + (int(bitmap[at + whole]) & ((1 << bits) - 1)).bit_count() if bits else out

    def __getitem__(self, i: int) -> int:
        """The id at place i: one chunk, one bit and at most one rank a level."""
        if not 0 <= i < self.n:
            raise IndexError(i)
        value = 0
        for k, (bitmap, ranks, chunks) in enumerate(self.levels):
            value |= int(chunks[i]) << (BITS * k)
            if not bitmap[i >> 3] >> (i & 7) & 1:
                break
            i = self._rank(bitmap, ranks, i)
        return value

    def slice(self, i: int, j: int) -> np.ndarray:
        """The ids at places i to j - 1; what stands outside is not decoded."""
        out, places, k = np.zeros(j - i, np.uint32), np.arange(j - i), 0
        while j > i and k < len(self.levels):
            bitmap, ranks, chunks = self.levels[k]
            out[places] |= chunks[i:j].astype(np.uint32) << (BITS * k)
            on = np.unpackbits(bitmap[i >> 3 : (j + 7) >> 3], bitorder="little")[(i & 7) : (i & 7) + j - i].astype(bool)
            places = places[on]
            i = self._rank(bitmap, ranks, i)
            j, k = i + len(places), k + 1
        return out


def in_order(docs: DataFrame, text: str = "text") -> DataFrame:
    """(doc_id, text) dealt by ranges of doc_id, each range sorted."""
    return docs.select("doc_id", F.col(text).alias("text")).repartitionByRange("doc_id").sortWithinPartitions("doc_id", "text")


def token_batches(batches: Iterator, tokenizer: str, end_id: int) -> Iterator[tuple[int | None, bytes]]:
    """(doc_id, ids as bytes) for each row of Arrow batches of (doc_id, text)."""
    enc, end = encoder(tokenizer), np.array([end_id], "<u4").tobytes()
    for batch in (b.slice(at, 1024) for b in batches for at in range(0, len(b), 1024)):
        ids, at = enc.encode_arrow(batch.column(1))
        raw = ids.astype("<u4", copy=False).tobytes()
        places = (4 * at).tolist()
        for doc, a, b in zip(batch.column(0).to_pylist(), places, places[1:], strict=False):
            yield doc, raw[a:b] + end


def write_tokens(docs: DataFrame, path: str, tokenizer: str, end_id: int = 0, text: str = "text") -> None:
    def segments(batches: Iterator) -> Iterator:
        import pyarrow as pa
        from pyspark import TaskContext

        part, seq, ids, sizes, held, n = TaskContext.get().partitionId(), 0, [], [], [], 0

        def row() -> pa.RecordBatch:
            codes = pack(np.frombuffer(b"".join(held), "<u4"))
            return pa.RecordBatch.from_arrays(
                [pa.array([part], pa.int64()), pa.array([seq], pa.int64()), pa.array([ids], pa.list_(pa.int64())), pa.array([sizes], pa.list_(pa.int64())), pa.array([codes], pa.binary())],
                names=["part", "seq", "doc_ids", "lengths", "codes"],
            )

        for doc, got in token_batches(batches, tokenizer, end_id):
            ids.append(doc)
            sizes.append(len(got) // 4)
            held.append(got)
            n += sizes[-1]
            if n >= SEGMENT_TOKENS:
                yield row()
                seq, ids, sizes, held, n = seq + 1, [], [], [], 0
        if ids:
            yield row()

    ship(docs.sparkSession)
    in_order(docs, text).mapInArrow(segments, SEGMENT_SCHEMA).write.option("compression", "uncompressed").parquet(path)


def segments_at(spark: SparkSession, path: str) -> DataFrame:
    """The segments of token files with `start`, the number of ids before each."""
    files = spark.read.schema(SEGMENT_SCHEMA).parquet(path)
    counts = files.select("part", "seq", F.aggregate("lengths", F.lit(0).cast("long"), lambda a, x: a + x).alias("n"))
    # One row a part, that is a task of the writer: a window over them needs no split.
    parts = counts.groupBy("part").agg(F.sum("n").alias("n"))
    before = Window.rowsBetween(Window.unboundedPreceding, -1)
    parts = parts.select("part", F.coalesce(F.sum("n").over(before.orderBy("part")), F.lit(0)).alias("base"))
    own = F.coalesce(F.sum("n").over(before.partitionBy("part").orderBy("seq")), F.lit(0))
    starts = counts.select("part", "seq", own.alias("own")).join(parts, "part").select("part", "seq", (F.col("own") + F.col("base")).alias("start"))
    starts = written(starts, "starts")
    # a row a segment of a million ids: sent to the codes while that is small, else the codes come to them
    return files.join(F.broadcast(starts) if starts.count() <= MOST_SENT else starts, ["part", "seq"])


def read_documents(spark: SparkSession, path: str) -> DataFrame:
    """Per document of token files: doc_id, start, n_tokens and the checksum of its ids."""

    def read(batches: Iterator) -> Iterator:
        import pyarrow as pa

        for batch in batches:
            for r in batch.to_pylist():
                codes, at, rows = Reader(r["codes"]), 0, []
                for doc, n in zip(r["doc_ids"], r["lengths"], strict=True):
                    rows.append((doc, r["start"] + at, n, zlib.crc32(codes.slice(at, at + n).astype("<u4").tobytes())))
                    at += n
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows, strict=True)], names=["doc_id", "start", "n_tokens", "ids_crc32"])

    ship(spark)
    found = segments_at(spark, path).select("doc_ids", "lengths", "codes", "start")
    return found.mapInArrow(read, "doc_id long, start long, n_tokens long, ids_crc32 long")


def round_trip(docs: DataFrame, tokenizer: str, end_id: int = 0, path: str | None = None) -> DataFrame:
    """Writes docs as token files (to a new folder of the shared one, if no path is given) and reads them back."""
    path = path or shared_path(docs.sparkSession, "tokens")
    write_tokens(docs, path, tokenizer, end_id)
    return read_documents(docs.sparkSession, path)
