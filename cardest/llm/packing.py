"""Harmonic packing of token sequences.

Lengths are parted into reciprocal-capacity classes: class k holds pieces of which k fit into one sequence, and every
sequence of the class is filled with exactly k of them, whatever the other pieces are. So a piece's sequence follows from
its rank in its class alone, and workers need only the counts of earlier workers. Documents may be cut: full sequences
first, then at most ``CUTS`` pieces of exactly one k-th of the capacity, so that only a small rest has to be rounded up to
its class. The last, incomplete sequence of every class holds fewer than k pieces; those few thousand pieces at most,
whatever the data, are packed first-fit by falling length.
"""

from __future__ import annotations

import json
import zlib
from array import array
from collections.abc import Iterator
from pathlib import Path

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from cardest.llm.common import salt, salts, stored
from cardest.llm.tokens import ChunkEncoder, led_chunks

#: Exact pieces cut from what is left after full sequences.
CUTS = 2
#: A rest of fewer tokens is not cut any more.
LEAST = 32
#: Id that ends every document.
END_ID = 1


def byte_ranks(path: str) -> dict[bytes, int] | None:
    """Token bytes with their ids, or None unless the file's merges are numbered in order after the 256 single bytes."""
    file = json.loads(Path(path).read_text())
    vocabulary, special = file["model"]["vocab"], {t["content"] for t in file["added_tokens"]}
    pairs = [m if isinstance(m, list) else m.split(" ") for m in file["model"]["merges"]]
    if any(vocabulary.get(a + b) != 256 + i for i, (a, b) in enumerate(pairs)) or file["normalizer"] or not file["pre_tokenizer"].get("use_regex"):
        return None
    # byte-level files write a byte that is not printable as the next free character from 256 on
    printable = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or b >= 174]
    others = [b for b in range(256) if b not in set(printable)]
    byte = {chr(b): b for b in printable} | {chr(256 + i): b for i, b in enumerate(others)}
    return {bytes(byte[c] for c in token): i for token, i in vocabulary.items() if token not in special}


class ByteEncoder(ChunkEncoder):
    """Packed ids of byte-level chunks; new ones go through a pair-rank encoder over the very same vocabulary file.

    Where ranks and ids agree (``byte_ranks``) it gives the library's ids several times faster. Chunks in which a special
    token could hide, and files numbered otherwise, go through the library itself.
    """

    def __init__(self, path: str) -> None:
        super().__init__(path, led_chunks, lambda e: array("I", e.ids).tobytes())
        import public_tokenizers
        import tiktoken

        ranks = byte_ranks(path)
        self.quick = ranks and tiktoken.Encoding("ranks", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={}).encode_ordinary

    def fresh(self, chunks: list[str]) -> Iterator[tuple]:
        slow = chunks if not self.quick else [c for c in chunks if "<" in c]
        yield from super().fresh(slow)
        if self.quick:
            yield from ((c, array("I", self.quick(c)).tobytes()) for c in chunks if "<" not in c)


def cut_lengths(n: int, capacity: int, cuts: int = CUTS, least: int = LEAST) -> list[int]:
    """Lengths of a document's pieces, in order."""
    full, rest = divmod(n, capacity)
    out = [capacity] * full
    while rest and cuts and rest >= least:
        piece = capacity // -(-capacity // rest)
        if piece == rest:
            break
        out.append(piece)
        rest -= piece
        cuts -= 1
    return [*out, rest] if rest else out


def pieces_of(docs: DataFrame, vocabulary: str, capacity: int, id_col: str, text_col: str) -> DataFrame:
    """``doc_id, start, length, ids_crc32, doc_tokens`` of every piece."""
    names = ["doc_id", "start", "length", "ids_crc32", "doc_tokens"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = ByteEncoder(vocabulary)
        end = array("I", [END_ID]).tobytes()
        for b in batches:
            rows: list[list] = [[], [], [], [], []]
            for doc, chunks in zip(b.column(0).to_pylist(), encoder.encode([t or "" for t in b.column(1).to_pylist()]), strict=True):
                ids = b"".join(chunks) + end
                n, at = len(ids) // 4, 0
                for length in cut_lengths(n, capacity):
                    for column, value in zip(rows, (doc, at, length, zlib.crc32(ids[4 * at : 4 * (at + length)]), n), strict=True):
                        column.append(value)
                    at += length
            yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in rows], names=names)

    rows = docs.selectExpr(f"cast(`{id_col}` as bigint) as doc_id", f"`{text_col}` as text")
    return rows.mapInArrow(run, ", ".join(f"{n} bigint" for n in names))


def pack(docs: DataFrame, vocabulary: str, capacity: int = 2048, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Pack all documents: ``doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset``, one row per piece.

    A document's ids are those of the tokenizer file at ``vocabulary`` (a byte-level encoding) followed by ``END_ID``; a
    null text is empty and has that one id. Sequence ids are gapless from 0, offsets gapless from 0 in each sequence.
    Repeated rows and null identifiers are documents of their own. An empty table gives an empty result.
    """
    n = salts(docs.sparkSession)
    pieces = pieces_of(docs, vocabulary, capacity, id_col, text_col)
    pieces = stored(pieces.withColumn("k", F.expr(f"{capacity} div length")).withColumn("part", salt(n, F.col("doc_id"), F.col("start"))), "pack-pieces")
    counts = stored(pieces.groupBy("k", "part").agg(F.count("*").alias("n")), "pack-counts")
    earlier = F.coalesce(F.sum("n").over(W.partitionBy("k").orderBy("part").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    parts = counts.withColumn("before", earlier).select("k", "part", "before")
    # one row per class, of which there are at most 2 * sqrt(capacity)
    classes = counts.groupBy("k").agg(F.expr("sum(n) div k").alias("full"))
    classes = classes.withColumn("first", F.coalesce(F.sum("full").over(W.orderBy("k").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)))
    total = classes.agg(F.coalesce(F.sum("full"), F.lit(0))).first()[0]
    starts = parts.join(F.broadcast(classes), "k")
    turn = F.row_number().over(W.partitionBy("k", "part").orderBy("doc_id", "start", "ids_crc32")) - 1
    ranked = pieces.withColumn("turn", turn).join(starts, ["k", "part"]).withColumn("rank", F.col("before") + F.col("turn")).withColumn("bin", F.expr("rank div k"))
    ranked = stored(ranked.select("doc_id", "start", "length", "ids_crc32", "doc_tokens", "k", "rank", (F.col("bin") < F.col("full")).alias("whole"), (F.col("first") + F.col("bin")).alias("sequence_id")), "pack-ranked")
    names = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]
    within = F.coalesce(F.sum("length").over(W.partitionBy("sequence_id").orderBy("rank").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    whole = ranked.where("whole").withColumn("offset", F.when(F.col("k") == 1, F.lit(0).cast("long")).otherwise(within)).select(*names)

    def fit(rest: pd.DataFrame) -> pd.DataFrame:
        rest = rest.sort_values(["length", "k", "rank"], ascending=[False, True, True], ignore_index=True)
        used: list[int] = []
        put, at = [], []
        for length in rest["length"].tolist():
            for i, u in enumerate(used):
                if u + length <= capacity:
                    break
            else:
                i = len(used)
                used.append(0)
            put.append(total + i)
            at.append(used[i])
            used[i] += length
        return rest.assign(sequence_id=put, offset=at)[names]

    rest = ranked.where("not whole").drop("sequence_id", "whole").groupBy().applyInPandas(fit, ", ".join(f"{x} bigint" for x in names))
    return whole.unionByName(rest)
