"""Concatenate and cut: all token streams, one after another, cut into windows of fixed length.

Pass one tokenizes each partition once, stores ids (16 bits each) and a running offset within the
partition. Prefix sums over the partitions' totals, one row for each, turn these into global offsets;
pass two cuts at multiples of the window. Documents that cross a window give several boundary records.
Edge cases: null text is empty (only the separator); equal rows are packed each; an empty table gives
no rows; a text that holds the vocabulary's special string goes through the reference tokenizer, so ids
always equal its own.
"""

from __future__ import annotations

import base64
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphmoves.llm.common import snapshot, utf8

VOCABULARY = "byte_bpe_50k"
SPECIAL = "<|endoftext|>"


def encoder(vocabulary: str = VOCABULARY):
    """text -> ids. The rank file of the same vocabulary gives the reference tokenizer's ids several times faster."""
    import public_tokenizers
    import tiktoken

    with open(public_tokenizers.path(f"{vocabulary}.tiktoken"), "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    fast = tiktoken.Encoding("ranks", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    exact = []

    def encode(text: str) -> list[int]:
        if SPECIAL not in text:
            return fast.encode_ordinary(text)
        if not exact:
            from tokenizers import Tokenizer

            exact.append(Tokenizer.from_file(public_tokenizers.path(f"{vocabulary}.json")))
        return exact[0].encode(text, add_special_tokens=False).ids

    return encode


def tokenize(docs: DataFrame, vocabulary: str = VOCABULARY, end_id: int = 1) -> DataFrame:
    """doc_id, part, before (tokens of the partition's earlier documents), n, ids (little-endian uint16)."""
    def run(batches):
        from pyspark import TaskContext

        encode, part, before = encoder(vocabulary), TaskContext.get().partitionId(), 0
        for b in batches:
            data, off = utf8(b.column(1))
            for lo in range(0, b.num_rows, 256):
                hi = min(lo + 256, b.num_rows)
                ids = [np.array([*encode(data[off[i] : off[i + 1]].tobytes().decode("utf-8", "replace")), end_id], "<u2").tobytes() for i in range(lo, hi)]
                n = np.array([len(x) // 2 for x in ids], np.int64)
                yield pa.RecordBatch.from_arrays(
                    [b.column(0).slice(lo, hi - lo), pa.array(np.full(hi - lo, part)), pa.array(before + np.cumsum(n) - n), pa.array(n), pa.array(ids, pa.binary())],
                    names=["doc_id", "part", "before", "n", "ids"])
                before += int(n.sum())

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text")).mapInArrow(
        run, "doc_id long, part long, before long, n long, ids binary")


def pack_documents(docs: DataFrame, window: int = 2048, vocabulary: str = VOCABULARY, end_id: int = 1) -> DataFrame:
    """A row for each piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset. Only the last sequence is short."""
    tokens = snapshot(tokenize(docs, vocabulary, end_id))
    totals = tokens.groupBy("part").agg(F.sum("n").alias("t"))
    earlier = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    starts = totals.select("part", F.coalesce(F.sum("t").over(earlier), F.lit(0)).alias("base"))  # a row for each partition

    def cut(batches):
        for b in batches:
            doc, at = b.column(0), np.asarray(b.column(1))
            ids, off = utf8(b.column(2))
            n = np.diff(off) // 2
            rows = []
            for i in range(b.num_rows):
                own, g, done = ids[off[i] : off[i + 1]].view("<u2").astype("<u4") if off[i] % 2 == 0 else np.frombuffer(ids[off[i] : off[i + 1]].tobytes(), "<u2").astype("<u4"), int(at[i]), 0
                while done < n[i]:
                    take = min(int(n[i]) - done, window - (g + done) % window)
                    rows.append((i, done, take, zlib.crc32(own[done : done + take].tobytes()), int(n[i]), (g + done) // window, (g + done) % window))
                    done += take
            cols = np.array(rows, np.int64).reshape(-1, 7).T
            yield pa.RecordBatch.from_arrays([doc.take(pa.array(cols[0])), *(pa.array(c) for c in cols[1:])],
                                             names=["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"])

    placed = tokens.join(F.broadcast(starts), "part").select("doc_id", (F.col("base") + F.col("before")).alias("at"), "ids")
    return placed.mapInArrow(cut, "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long")
