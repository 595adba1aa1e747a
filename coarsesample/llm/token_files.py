"""Token files of directly addressable codes.

Ids are cut into chunks of eight bits, lowest first. Level 0 holds the first chunk of every id, level
l+1 the next chunk of those ids that go on; a bitmap at each level says which do, and a rank
directory holds the number of set bits before every 512-bit stretch. So id i is found by one chunk
read and one rank per level, without decoding its neighbours.

A file set is a Parquet dataset of blocks in document order: Spark's commit protocol and any Hadoop
file system carry it, and a block's payload is one self-contained binary.

Defined results: null text counts as empty, so a document has its end id at least; null keys come
first; repeated keys keep one entry each, ordered by text; an empty table gives an empty file set.
"""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from coarsesample.llm.tokens import END_BYTES, encoder

MAGIC = b"DAC1"
STRETCH = 512
BLOCK_SCHEMA = "shard int, block int, first_token long, n_tokens long, doc_ids array<string>, lengths array<long>, payload binary"


def dac_encode(ids: np.ndarray) -> bytes:
    """Payload of a block: header, then for each level its chunks, bitmap and rank directory."""
    rest, levels = np.asarray(ids, dtype=np.uint32), []
    while True:
        chunks, rest = (rest & 255).astype(np.uint8), rest >> 8
        goes_on = rest > 0
        bitmap = np.packbits(goes_on, bitorder="little")
        ones = np.add.reduceat(goes_on, np.arange(0, len(goes_on), STRETCH), dtype=np.uint32) if len(goes_on) else np.zeros(0, np.uint32)
        directory = np.concatenate([[0], np.cumsum(ones)]).astype("<u4")
        levels.append((chunks.tobytes(), bitmap.tobytes(), directory.tobytes()))
        rest = rest[goes_on]
        if not len(rest):
            break
    out = [MAGIC, struct.pack("<B", len(levels))]
    for parts in levels:
        out.append(struct.pack("<QQQ", *map(len, parts)))
    return b"".join(out + [p for parts in levels for p in parts])


class DacReader:
    """Random access to a payload; nothing is decoded but what is asked for."""

    def __init__(self, payload: bytes):
        if payload[:4] != MAGIC:
            raise ValueError("not a DAC block")
        n, at = payload[4], 5 + 24 * payload[4]
        self.levels = []
        for i in range(n):
            sizes = struct.unpack_from("<QQQ", payload, 5 + 24 * i)
            parts = []
            for size, kind in zip(sizes, (np.uint8, np.uint8, "<u4"), strict=True):
                parts.append(np.frombuffer(payload, kind, size // np.dtype(kind).itemsize, at))
                at += size
            self.levels.append(tuple(parts))

    def __len__(self) -> int:
        return len(self.levels[0][0])

    def __getitem__(self, i: int) -> int:
        if not 0 <= i < len(self):
            raise IndexError(i)
        value = 0
        for depth, (chunks, bitmap, directory) in enumerate(self.levels):
            value |= int(chunks[i]) << (8 * depth)
            if not bitmap[i >> 3] >> (i & 7) & 1:
                break
            first = i // STRETCH * STRETCH
            head = bitmap[first >> 3 : i >> 3]
            i = int(directory[i // STRETCH]) + int(np.bitwise_count(head).sum()) + int(np.bitwise_count(bitmap[i >> 3] & ((1 << (i & 7)) - 1)))
        return value

    def decode(self) -> np.ndarray:
        """All ids."""
        out = np.zeros(len(self), np.uint32)
        alive = np.arange(len(self))
        for depth, (chunks, bitmap, _) in enumerate(self.levels):
            out[alive] |= chunks.astype(np.uint32) << np.uint32(8 * depth)
            alive = alive[np.unpackbits(bitmap, count=len(chunks), bitorder="little").astype(bool)]
        return out


def _blocks(vocabulary: str, spaces: bool, block_tokens: int):
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        coder, shard = encoder(vocabulary, spaces), TaskContext.get().partitionId()
        block, first, held, docs, lengths = 0, 0, [], [], []

        def seal():
            ids = np.frombuffer(b"".join(held), "<u4")
            return pd.DataFrame({"shard": [shard], "block": [block], "first_token": [first], "n_tokens": [len(ids)], "doc_ids": [docs], "lengths": [lengths], "payload": [dac_encode(ids)]})

        total = 0
        for batch in batches:
            for doc, text in zip(batch["doc_id"].tolist(), batch["text"], strict=True):
                ids = coder.ids_bytes(text) + END_BYTES
                held.append(ids)
                docs.append(None if pd.isna(doc) else str(doc))
                lengths.append(len(ids) // 4)
                total += lengths[-1]
                if total >= block_tokens:
                    yield seal()
                    block, first, total, held, docs, lengths = block + 1, first + total, 0, [], [], []
        if docs:
            yield seal()

    return run


def write_token_files(docs: DataFrame, path: str, vocabulary: str = "word_bpe_49k.json", spaces: bool = False, block_tokens: int = 262_144, key: str = "doc_id", text: str = "text") -> None:
    """Encode every text, add the end id, and write the blocks in ascending key order.

    One range shuffle orders the documents; a partition becomes a shard of the file set.
    """
    ordered = (
        docs.select(F.col(key).cast("long").alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("text"))
        .repartitionByRange(F.col("doc_id").asc_nulls_first())
        .sortWithinPartitions(F.col("doc_id").asc_nulls_first(), "text")
    )
    ordered.select(F.col("doc_id").cast("string").alias("doc_id"), "text").mapInPandas(_blocks(vocabulary, spaces, block_tokens), BLOCK_SCHEMA).write.parquet(path)


def shard_bases(spark: SparkSession, path: str) -> DataFrame:
    """Ids before each shard: one row per shard, as many as the write had partitions."""
    totals = sorted(tuple(r) for r in spark.read.parquet(path).groupBy("shard").agg(F.sum("n_tokens")).collect())
    rows, at = [], 0
    for shard, n in totals:
        rows.append((shard, at))
        at += n
    return spark.createDataFrame(rows, "shard int, base long")


def _documents(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    for batch in batches:
        for row in batch.itertuples(index=False):
            ids = DacReader(row.payload).decode().astype("<u4")
            ends = np.cumsum(np.asarray(row.lengths, np.int64))
            starts = ends - np.asarray(row.lengths, np.int64)
            crcs = [zlib.crc32(ids[a:b].tobytes()) for a, b in zip(starts, ends, strict=True)]
            yield pd.DataFrame({"doc_id": list(row.doc_ids), "start": row.base + row.first_token + starts, "n_tokens": ends - starts, "ids_crc32": crcs})


def read_token_files(spark: SparkSession, path: str) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of each document, from the files alone."""
    blocks = spark.read.schema(BLOCK_SCHEMA).parquet(path)
    found = blocks.join(F.broadcast(shard_bases(spark, path)), "shard").mapInPandas(_documents, "doc_id string, start long, n_tokens long, ids_crc32 long")
    return found.withColumn("doc_id", F.col("doc_id").cast("long"))
