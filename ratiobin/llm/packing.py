"""Best-fit packing planned on a histogram of lengths.

Documents are tokenised once; documents longer than a sequence are cut into full pieces with one shorter first piece.
Best fit decreasing runs over the counts of the (at most 1024) lengths, never over documents: sequences with the same free
space form runs, and one step places a whole run of equal pieces.  Pieces then take planned slots by joining on their rank
within their length, which comes from per-task counters and a prefix sum over tasks, so equal lengths never meet in one
task.

Defined cases: null texts are empty (one end token); empty tables give no rows; repeated rows are packed once each.
"""

from __future__ import annotations

import json
import os
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ratiobin.llm import textgrid as tg
from ratiobin.llm.common import saved, table

SEQUENCE = 1024
END_ID = 2
TOKENIZER = "byte_bpe_50k.json"
_encoders: dict = {}


#: Fixed value: the published pattern of byte-level pre-tokens.
PRE_TOKENS = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
PROBES = ("It's 12 o'clock,  isn't it?\n\n\tNaïve señor – 東京 123abc\u00a0 x  ", " ", "\n \n", "a\u2003\u2003b 'S 'll 9９ ½ e\u0301 🙂🙂", "a <|endoftext|> b  <|endoftext|>\n<|endoftext|")


def byte_letters() -> dict[str, int]:
    """The letter that stands for each byte in byte-level vocabularies: printable Latin-1 as itself, the rest from 256 up."""
    shown = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    rest = [b for b in range(256) if b not in shown]
    return {chr(b): b for b in shown} | {chr(256 + i): b for i, b in enumerate(rest)}


class TextEncoder:
    """Token ids of texts as little-endian 32-bit bytes, by a `tokenizers` file.

    A byte-level BPE file whose ids follow its merges is run by the rank engine of `tiktoken`, built from the same file,
    which gives the same ids about three times as fast; both are compared on probe texts when a worker loads the file, and
    any other file is run by `tokenizers`.
    """

    def __init__(self, path: str):
        self._path, self._tokenizer = path, None
        self._ranks = self._rank_engine(path)
        if self._ranks is not None and any(self._slow(t) != self._fast(t) for t in PROBES):
            self._ranks = None
        if self._ranks is not None:
            self._tokenizer = None  # loaded again if it is asked for; one vocabulary in memory is enough

    @staticmethod
    def _rank_engine(path: str):
        import tiktoken

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        if spec["model"].get("type") != "BPE" or (spec.get("pre_tokenizer") or {}).get("type") != "ByteLevel" or spec.get("normalizer"):
            return None
        if any(t.get(flag) for t in spec.get("added_tokens", []) for flag in ("single_word", "lstrip", "rstrip", "normalized")):
            return None
        letters, added = byte_letters(), {t["content"]: t["id"] for t in spec.get("added_tokens", [])}
        try:
            ranks = {bytes(letters[c] for c in token): i for token, i in spec["model"]["vocab"].items() if token not in added}
            return tiktoken.Encoding("file", pat_str=PRE_TOKENS, mergeable_ranks=ranks, special_tokens=added)
        except (KeyError, ValueError):
            return None

    def _slow(self, text: str) -> bytes:
        if self._tokenizer is None:
            os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
            from tokenizers import Tokenizer

            self._tokenizer = Tokenizer.from_file(self._path)
        return np.array(self._tokenizer.encode(text, add_special_tokens=False).ids, dtype="<u4").tobytes()

    def _fast(self, text: str) -> bytes:
        return self._ranks.encode_to_numpy(text, allowed_special="all").astype("<u4", copy=False).tobytes()

    def encode(self, texts: list[str | None]) -> list[bytes]:
        one = self._slow if self._ranks is None else self._fast
        return [one(t) if t else b"" for t in texts]


def encoder(path: str | None = None) -> TextEncoder:
    """This worker's encoder of a tokenizer file (by default the installed byte-level one)."""
    if path is None:
        import public_tokenizers

        path = public_tokenizers.path(TOKENIZER)
    if path not in _encoders:
        _encoders[path] = TextEncoder(path)
    return _encoders[path]


def piece_bounds(n: int, size: int = SEQUENCE) -> list[tuple[int, int]]:
    """(start, length) of the pieces of n tokens: all but the first have the full size."""
    if n <= size:
        return [(0, n)]
    head = n % size
    return [(0, head)] * (head > 0) + [(at, size) for at in range(head, n, size)]


def pieces(docs: DataFrame, size: int = SEQUENCE, end_id: int = END_ID, path: str | None = None) -> DataFrame:
    """(doc_id, text) to one row a piece, with its task and its rank among the task's pieces of that length."""
    end = np.array([end_id], dtype="<u4").tobytes()

    def run(batches):
        from pyspark import TaskContext

        task, met = TaskContext.get().partitionId(), Counter()
        encode = encoder(path).encode
        for batch in tg.slices(batches, limit=1 << 20):
            rows: dict[str, list] = {c: [] for c in ("doc_id", "piece", "start", "length", "ids_crc32", "rank")}
            ids = batch.column(batch.schema.get_field_index("doc_id")).to_pylist()
            for doc_id, body in zip(ids, encode(batch.column(batch.schema.get_field_index("text")).to_pylist()), strict=True):
                stream = body + end
                for k, (start, length) in enumerate(piece_bounds(len(stream) // 4, size)):
                    rows["doc_id"].append(doc_id)
                    rows["piece"].append(k)
                    rows["start"].append(start)
                    rows["length"].append(length)
                    rows["ids_crc32"].append(zlib.crc32(stream[4 * start : 4 * (start + length)]))
                    rows["rank"].append(met[length])
                    met[length] += 1
            yield pa.RecordBatch.from_arrays(
                [pa.array(v, pa.int32() if c == "piece" else pa.int64()) for c, v in rows.items()] + [pa.array([task] * len(rows["rank"]), pa.int32())],
                [*rows, "task"],
            )

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, piece int, start long, length long, ids_crc32 long, rank long, task int")


def best_fit_plan(histogram: dict[int, int], size: int = SEQUENCE) -> tuple[list[tuple[int, int, int, int, int, int]], int]:
    """Best fit decreasing on counts: rows (length, rank from, rank to, first sequence, offset, pieces a sequence), sequences used.

    Rank r of a length sits in sequence first + (r - from) // pieces at offset + (r - from) % pieces * length.
    """
    free: list[list[tuple[int, int]]] = [[] for _ in range(size + 1)]  # runs (first sequence, how many) by free space
    plan, used = [], 0
    for length in sorted(histogram, reverse=True):
        rank, left = 0, histogram[length]
        space = length
        while left:
            while space <= size and not free[space]:
                space += 1
            if space <= size:
                first, many = free[space].pop()
                room = space
            else:
                room = size
                per = size // length
                first, many = used, -(-left // per)
                used += many
            per = room // length
            whole = min(many, left // per)
            if whole:
                plan.append((length, rank, rank + whole * per, first, size - room, per))
                free[room - length * per].append((first, whole))
                rank, left = rank + whole * per, left - whole * per
            if whole < many and left:
                plan.append((length, rank, rank + left, first + whole, size - room, left))
                free[room - length * left].append((first + whole, 1))
                if many - whole > 1:
                    free[room].append((first + whole + 1, many - whole - 1))
                left = 0
            elif whole < many:
                free[room].append((first + whole, many - whole))
    return plan, used


def pack(docs: DataFrame, size: int = SEQUENCE, end_id: int = END_ID, path: str | None = None) -> DataFrame:
    spark = docs.sparkSession
    cut = saved(pieces(docs, size, end_id, path), "pieces")
    by_task = cut.groupBy("task", "length").agg(F.count("*").alias("n"))
    histogram = {r["length"]: r["n"] for r in by_task.groupBy("length").agg(F.sum("n").alias("n")).collect()}  # `size` rows at most
    plan, _ = best_fit_plan(histogram, size)
    slots = spark.createDataFrame(plan or [(0, 0, 0, 0, 0, 1)], "length long, lo long, hi long, first long, at long, per long")
    before = Window.partitionBy("length").orderBy("task").rowsBetween(Window.unboundedPreceding, -1)
    base = by_task.select("task", "length", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))
    ranked = cut.join(base, ["task", "length"]).withColumn("rank", F.col("rank") + F.col("base"))
    placed = ranked.join(F.broadcast(slots), (ranked["length"] == slots["length"]) & (ranked["rank"] >= slots["lo"]) & (ranked["rank"] < slots["hi"])).drop(slots["length"])
    return placed.select(
        "doc_id", "piece", "start", "length", "ids_crc32",
        F.expr("first + (rank - lo) div per").alias("sequence_id"), F.expr("at + (rank - lo) % per * length").alias("offset"),
    )


def op10_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents"))
