"""Lexical retrieval packing.

Documents are dealt to shards of bounded bytes by a hash of key and row; each shard holds a BM25
inverted index over its documents' token ids. Whole windows of a document longer than a sequence
leave at once. Of the rest, a seed document opens a sequence, its best unused BM25 neighbours, scored
with all of the seed's distinct ids, fill it in order of score, and the document that meets the border
is cut there; its tail opens the next sequence. So every sequence of a shard is full but its last,
which is padded to a power of two: one in about 500 at ``shard_bytes``.

A shard is one task's memory and its scoring grows with the square of its documents, so shards stay
small and their number follows the table. Rows that repeat a key and text spread over all shards.

Defined results: null or empty text is one end id; repeated rows are packed once each; ties in score
go to the lower place in the shard; an empty table gives no pieces. Only key and text are read.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coarsesample.llm.tokens import END_BYTES, encoder

PIECE_SCHEMA = "doc_id long, start long, length long, doc_tokens long, sequence_id long, offset long, padded long, ids binary"


class ShardIndex:
    """BM25 over short documents of token ids; documents leave the index once used."""

    def __init__(self, docs: list[np.ndarray], k1: float = 1.2, b: float = 0.75):
        n = len(docs)
        sizes = np.fromiter(map(len, docs), np.int64, n)
        owner = np.repeat(np.arange(n, dtype=np.int64), sizes)
        terms = np.concatenate(docs).astype(np.int64) if n else np.zeros(0, np.int64)
        pairs, counts = np.unique(terms * n + owner if n else terms, return_counts=True)
        del terms, owner
        term, self.doc = (pairs // n, pairs % n) if n else (pairs, pairs)
        del pairs
        _, at, df = np.unique(term, return_inverse=True, return_counts=True)
        del term
        self.span = np.append(0, np.cumsum(df))
        idf = np.log(1 + (n - df + 0.5) / (df + 0.5))
        norm = k1 * (1 - b + b * sizes / max(1.0, sizes.mean() if n else 1.0))
        tf = counts.astype(np.float64)
        self.impact = tf * (k1 + 1) / (tf + norm[self.doc]) * np.repeat(idf, df)
        self.of_doc = at[np.argsort(self.doc, kind="stable")].astype(np.int32)
        self.doc_span = np.append(0, np.cumsum(np.bincount(self.doc, minlength=n)))
        self.free = np.ones(n, bool)
        self.listed = n

    def _forget_used(self) -> None:
        """Take used documents out of the lists; weights stay those of the whole shard."""
        left = self.free[self.doc]
        self.span = np.append(0, np.cumsum(left))[self.span]
        self.doc, self.impact = self.doc[left], self.impact[left]
        self.listed = int(self.free.sum())

    def scores(self, seed: int) -> np.ndarray:
        """BM25 of every document still listed for all distinct terms of the seed."""
        terms = self.of_doc[self.doc_span[seed] : self.doc_span[seed + 1]]
        spans = list(zip(self.span[terms].tolist(), self.span[terms + 1].tolist(), strict=True))
        if not spans:
            return np.zeros(len(self.free))
        where = np.concatenate([self.doc[i:j] for i, j in spans])
        return np.bincount(where, np.concatenate([self.impact[i:j] for i, j in spans]), len(self.free))

    def neighbours(self, seed: int, first: int = 32) -> Iterator[int]:
        """Unused documents that share a term with the seed, best first; the tail is only sorted if it is asked for."""
        if self.free.sum() < 0.8 * self.listed:
            self._forget_used()
        scores = self.scores(seed)
        found = np.flatnonzero((scores > 0) & self.free)
        scores = scores[found]
        least = np.partition(scores, len(scores) - first)[len(scores) - first] if len(scores) > first else 0.0
        for part in (scores >= least, scores < least):
            docs, own = found[part], scores[part]
            yield from docs[np.lexsort((docs, -own))].tolist()


def _next_power(n: int, most: int) -> int:
    return min(most, 1 << max(0, (n - 1).bit_length()))


def pack_shard(shard: int, doc_ids: list, ids: list[np.ndarray], budget: int) -> pd.DataFrame:
    """Pieces of one shard's documents. Sequence ids count up inside the shard."""
    base, sequence, rows = shard << 32, 0, []
    tails: list[tuple[int, int]] = []
    for d, doc in enumerate(ids):
        for start in range(0, len(doc) - budget + 1, budget):
            rows.append((d, start, budget, sequence, 0, budget))
            sequence += 1
        if len(doc) % budget:
            tails.append((d, len(doc) - len(doc) % budget))
    index = ShardIndex([ids[d][start:] for d, start in tails])
    waiting, opened, filled, members = 0, -1, 0, []

    def place(tail: int) -> bool:
        """Put a tail at the end of the open sequence; true once a sequence has been closed."""
        nonlocal sequence, filled, members
        d, start = tails[tail]
        index.free[tail] = False
        left, closed = len(ids[d]) - start, False
        while left:
            take = min(left, budget - filled)
            members.append((d, start, take, sequence, filled))
            start, left, filled = start + take, left - take, filled + take
            if filled == budget:
                rows.extend((*m, budget) for m in members)
                sequence, filled, members, closed = sequence + 1, 0, [], True
        return closed

    seed = -1
    while True:
        if seed < 0 or not filled:
            while waiting < len(tails) and not index.free[waiting]:
                waiting += 1
            if waiting == len(tails):
                break
            seed = waiting
            if place(seed):
                continue
        closed = False
        for near in index.neighbours(seed):
            if place(near):
                closed, seed = True, near
                break
        if not closed:
            opened = seed
            seed = -1
            while waiting < len(tails) and not index.free[waiting]:
                waiting += 1
            if waiting < len(tails):
                seed = waiting
                place(seed)
            elif opened >= 0:
                break
    if members:
        rows.extend((*m, _next_power(filled, budget)) for m in members)
    return pd.DataFrame(
        {
            "doc_id": pd.array([doc_ids[r[0]] for r in rows], dtype="Int64"),
            "start": [r[1] for r in rows],
            "length": [r[2] for r in rows],
            "doc_tokens": [len(ids[r[0]]) for r in rows],
            "sequence_id": [base + r[3] for r in rows],
            "offset": [r[4] for r in rows],
            "padded": [r[5] for r in rows],
            "ids": [ids[r[0]][r[1] : r[1] + r[2]].tobytes() for r in rows],
        }
    )


def pack(docs: DataFrame, vocabulary: str = "byte_bpe_50k.json", spaces: bool = True, budget: int = 2048, shard_bytes: int = 4_000_000, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Pieces with their ids. The count of shards follows the bytes, so a shard's size doesn't grow."""
    held = docs.select(F.col(key).cast("long").alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    total = held.agg(F.sum(F.octet_length("text") + F.lit(64)).alias("bytes")).first()["bytes"] or 0
    shards = max(1, math.ceil(total / shard_bytes))
    dealt = held.withColumn("doc_id", F.col("doc_id").cast("string")).withColumn("shard", F.pmod(F.xxhash64("doc_id", F.monotonically_increasing_id()), F.lit(shards)).cast("int"))

    def run(group: pd.DataFrame) -> pd.DataFrame:
        coder = encoder(vocabulary, spaces)
        group = group.assign(at=[-(1 << 63) if pd.isna(k) else int(k) for k in group["doc_id"]]).sort_values(["at", "text"], kind="stable")
        ids = [np.frombuffer(coder.ids_bytes(t) + END_BYTES, "<u4") for t in group["text"]]
        keys = [None if pd.isna(k) else int(k) for k in group["doc_id"]]
        return pack_shard(int(group["shard"].iloc[0]), keys, ids, budget)

    return dealt.groupBy("shard").applyInPandas(run, PIECE_SCHEMA)
