"""Benchmark decontamination by winnowing.

Texts become word sequences.  Of every w consecutive k-gram hashes the smallest is kept, so any shared run of k + w - 1
words (13 with the values here) leaves a common fingerprint on both sides.  Items shorter than 13 words are one window of
their own length n and are fingerprinted with k = n, w = 1 in both tables, which keeps every gram.

A benchmark whose size is checked to fit in a task's memory is made into an index that is broadcast: its fingerprints, and
its distinct windows with the items that have them.  Documents are then read once and moved nowhere: those with a common
fingerprint are extended by looking up all their windows, so a passage that many documents and many items share costs each
document its own words.  A larger benchmark is joined: fingerprints to candidate (document, item) pairs, then each document
with its items' texts.

Defined cases: null or wordless texts have no words and are clean; null ids or texts of items are left out; repeated item
ids count once; repeated documents each get their row.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ratiobin.llm import textgrid as tg
from ratiobin.llm.common import saved, table

WINDOW = 13
GRAM = 5
#: A benchmark with more fingerprint rows (16 bytes each), or more bytes of text, is joined by shuffle; below, it is an index in
#: the memory of each task.
BROADCAST_ROWS = 2_000_000
INDEX_BYTES = 32 << 20
#: Contaminated: at least one word in SHARE is hit.
SHARE = 20


def winnow(grams: np.ndarray, n_grams: np.ndarray, w: int) -> np.ndarray:
    """Positions of the smallest gram of each run of w grams that lies in one document (the last one on ties).

    grams: gram hashes of all documents one after the other; n_grams: how many each document has.
    """
    if not len(grams):
        return np.zeros(0, dtype=np.int64)
    if w == 1:
        return np.arange(len(grams))
    first = np.cumsum(n_grams) - n_grams
    n_windows = np.maximum(n_grams - w + 1, 0)
    at = np.repeat(first - (np.cumsum(n_windows) - n_windows), n_windows) + np.arange(n_windows.sum())
    if not len(at):
        return at
    view = np.lib.stride_tricks.sliding_window_view(grams, w)[:, ::-1]
    chosen = np.zeros(len(grams), dtype=bool)
    for a in range(0, len(at), 1 << 17):
        part = at[a : a + (1 << 17)]
        chosen[part + w - 1 - np.argmin(view[part], axis=1)] = True
    return np.flatnonzero(chosen)


def doc_grams(words: tg.Words, hashes: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """k-gram hashes that stay in one document, their first words, and how many each document has."""
    grams = tg.gram_hashes(hashes, k)
    n_grams = np.maximum(words.counts - k + 1, 0)
    at = np.repeat(words.first[:-1] - (np.cumsum(n_grams) - n_grams), n_grams) + np.arange(n_grams.sum())
    return (grams[at] if len(at) else np.zeros(0, dtype=np.uint64)), at, n_grams


def batch_prints(words: tg.Words, short: list[int]) -> tuple[np.ndarray, np.ndarray]:
    """(document index, fingerprint) of a batch, distinct; fingerprints of different gram lengths are told apart."""
    hashes = words.hashes()
    docs, prints = [], []
    for k, w in [(GRAM, WINDOW - GRAM + 1), *((n, 1) for n in short)]:
        grams, _, n_grams = doc_grams(words, hashes, k)
        kept = winnow(grams, n_grams, w)
        docs.append(np.repeat(np.arange(words.n_docs), n_grams)[kept])
        prints.append(tg.pair_hash(grams[kept], np.full(len(kept), 100 * w + k, dtype=np.uint64)))
    docs, prints = np.concatenate(docs), np.concatenate(prints)
    order = np.lexsort((prints, docs))
    docs, prints = docs[order], prints[order]
    new = np.ones(len(docs), dtype=bool)
    new[1:] = (docs[1:] != docs[:-1]) | (prints[1:] != prints[:-1])
    return docs[new], prints[new]


def winnowed(rows: DataFrame, short: list[int], own_length: bool = False) -> DataFrame:
    """(keys..., text) to one row (keys..., print) for each kept fingerprint.

    own_length: a text of fewer than WINDOW words gives only its own single window, as items do.
    """
    keys = [c for c in rows.columns if c != "text"]

    def run(batches):
        for batch in tg.slices(batches):
            words = tg.Words(batch.column(batch.schema.get_field_index("text")), tg.NOT_ALNUM)
            docs, prints = batch_prints(words, short)
            if own_length:
                tiny = words.counts[docs] < WINDOW
                own = np.zeros(len(docs), dtype=bool)
                hashes = words.hashes()
                for i in np.flatnonzero((words.counts > 0) & (words.counts < WINDOW)):
                    n = int(words.counts[i])
                    mine = tg.pair_hash(tg.gram_hashes(hashes[words.first[i] : words.first[i] + n], n), np.array([100 + n], dtype=np.uint64))
                    own |= (docs == i) & (prints == mine)
                full = batch_prints(words, [])
                long_ = np.isin(tg.pair_hash(docs.astype(np.uint64), prints), tg.pair_hash(full[0].astype(np.uint64), full[1]))
                docs, prints = docs[(tiny & own) | (~tiny & long_)], prints[(tiny & own) | (~tiny & long_)]
            yield pa.RecordBatch.from_arrays([*(batch.column(batch.schema.get_field_index(c)).take(pa.array(docs)) for c in keys), pa.array(prints.view(np.int64))], [*keys, "print"])

    return rows.select(*keys, "text").mapInArrow(run, rows.select(*keys).schema.add("print", "long"))


def covered(doc: np.ndarray, items: dict[int, list[np.ndarray]]) -> tuple[int, list[int]]:
    """Words of a document (hashes) inside windows of the items (word hashes by item), and the items that occur."""
    edge = np.zeros(len(doc) + 1, dtype=np.int64)
    grams: dict[int, np.ndarray] = {}
    found = []
    for item, versions in items.items():
        for words in versions:
            n = min(WINDOW, len(words))
            if not n or n > len(doc):
                continue
            if n not in grams:
                grams[n] = tg.gram_hashes(doc, n)
            at = np.flatnonzero(np.isin(grams[n], tg.gram_hashes(words, n)))
            if len(at):
                np.add.at(edge, at, 1)
                np.add.at(edge, at + n, -1)
                found.append(item)
    return int((np.cumsum(edge)[:-1] > 0).sum()), sorted(set(found))


def extend(rows: DataFrame, text: str, keep: list[str]) -> DataFrame:
    """Rows with a text column and `_items` array<struct<item_id, text>> to the kept columns, _n_words, _n_hit, _item_ids."""

    def run(batches):
        known: dict[str, np.ndarray] = {}
        for batch in tg.slices(batches, text):
            words = tg.Words(batch.column(batch.schema.get_field_index(text)), tg.NOT_ALNUM)
            items = batch.column(batch.schema.get_field_index("_items"))
            n_hit, ids = np.zeros(words.n_docs, dtype=np.int64), [[] for _ in range(words.n_docs)]
            some = np.flatnonzero(~items.is_null().to_numpy(zero_copy_only=False))
            hashes = words.hashes() if len(some) else None
            for i in some.tolist():
                wanted: dict[int, list[np.ndarray]] = {}
                for item in items[i].as_py():
                    if item["text"] not in known:
                        if len(known) > 50_000:
                            known.clear()
                        known[item["text"]] = tg.Words(pa.array([item["text"]]), tg.NOT_ALNUM).hashes()
                    wanted.setdefault(item["item_id"], []).append(known[item["text"]])
                n_hit[i], ids[i] = covered(hashes[words.first[i] : words.first[i + 1]], wanted)
            yield pa.RecordBatch.from_arrays(
                [*(batch.column(batch.schema.get_field_index(c)) for c in keep), pa.array(words.counts.astype(np.int64)), pa.array(n_hit), pa.array(ids, pa.list_(pa.int64()))],
                [*keep, "_n_words", "_n_hit", "_item_ids"],
            )

    return rows.mapInArrow(run, rows.select(*keep).schema.add("_n_words", "long").add("_n_hit", "long").add("_item_ids", T.ArrayType(T.LongType())))


class WindowIndex:
    """Fingerprints and windows of a benchmark: for each window length the distinct window hashes and the items with them."""

    def __init__(self, items: list[tuple[int, str]], short: list[int]):
        self.ids, place = np.unique(np.array([i for i, _ in items], dtype=np.int64), return_inverse=True)
        words = tg.Words(pa.array([t for _, t in items], pa.large_string()), tg.NOT_ALNUM)
        hashes = words.hashes()
        self.prints = np.unique(np.concatenate([p for _, p in self._own_prints(words, hashes)] or [np.zeros(0, np.uint64)]))
        self.windows: dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]] = {}
        for n in (WINDOW, *short):
            mine = [i for i in range(words.n_docs) if words.counts[i] == n or (n == WINDOW and words.counts[i] > n)]
            if not mine:
                continue
            grams = [np.unique(tg.gram_hashes(hashes[words.first[i] : words.first[i + 1]], n)) for i in mine]
            pair = np.unique(np.stack((np.concatenate(grams), np.repeat(place[mine], [len(g) for g in grams]).astype(np.uint64))), axis=1)
            keys, first = np.unique(pair[0], return_index=True)
            self.windows[n] = (keys, np.append(first, pair.shape[1]), pair[1].astype(np.int64))

    @staticmethod
    def _own_prints(words: tg.Words, hashes: np.ndarray):
        for i in range(words.n_docs):
            n = int(words.counts[i])
            if not n:
                continue
            k, w = (GRAM, WINDOW - GRAM + 1) if n >= WINDOW else (n, 1)
            grams = tg.gram_hashes(hashes[words.first[i] : words.first[i + 1]], k)
            kept = winnow(grams, np.array([len(grams)]), w)
            yield i, tg.pair_hash(grams[kept], np.full(len(kept), 100 * w + k, dtype=np.uint64))

    def candidates(self, docs: np.ndarray, prints: np.ndarray) -> np.ndarray:
        """Documents that have a fingerprint of the benchmark."""
        if not len(self.prints):
            return np.zeros(0, dtype=np.int64)
        at = np.minimum(np.searchsorted(self.prints, prints), len(self.prints) - 1)
        return np.unique(docs[self.prints[at] == prints])

    def extend(self, doc: np.ndarray) -> tuple[int, list[int]]:
        """Words of a document (hashes) inside windows of the benchmark, and the items whose windows occur."""
        edge, found = np.zeros(len(doc) + 1, dtype=np.int64), []
        for n, (keys, first, owner) in self.windows.items():
            grams = tg.gram_hashes(doc, n)
            if not len(grams):
                continue
            at = np.minimum(np.searchsorted(keys, grams), len(keys) - 1)
            hit = np.flatnonzero(keys[at] == grams)
            np.add.at(edge, hit, 1)
            np.add.at(edge, hit + n, -1)
            found += [owner[first[k] : first[k + 1]] for k in np.unique(at[hit]).tolist()]
        ids = self.ids[np.unique(np.concatenate(found))].tolist() if found else []
        return int((np.cumsum(edge)[:-1] > 0).sum()), ids


def index_hits(rows: DataFrame, text: str, keep: list[str], index: WindowIndex, short: list[int]) -> DataFrame:
    """Rows with a text column to the kept columns, _n_words, _n_hit, _item_ids, by a broadcast index."""
    shared = rows.sparkSession.sparkContext.broadcast(index)

    def run(batches):
        for batch in tg.slices(batches, text):
            words = tg.Words(batch.column(batch.schema.get_field_index(text)), tg.NOT_ALNUM)
            n_hit, ids = np.zeros(words.n_docs, dtype=np.int64), [[] for _ in range(words.n_docs)]
            some = shared.value.candidates(*batch_prints(words, short))
            hashes = words.hashes() if len(some) else None
            for i in some.tolist():
                n_hit[i], ids[i] = shared.value.extend(hashes[words.first[i] : words.first[i + 1]])
            yield pa.RecordBatch.from_arrays(
                [*(batch.column(batch.schema.get_field_index(c)) for c in keep), pa.array(words.counts.astype(np.int64)), pa.array(n_hit), pa.array(ids, pa.list_(pa.int64()))],
                [*keep, "_n_words", "_n_hit", "_item_ids"],
            )

    return rows.mapInArrow(run, rows.select(*keep).schema.add("_n_words", "long").add("_n_hit", "long").add("_item_ids", T.ArrayType(T.LongType())))


def joined_hits(keyed: DataFrame, items: DataFrame, keep: list[str], item_prints: DataFrame, short: list[int]) -> DataFrame:
    """The same, where the benchmark is too large for a task: fingerprints and then texts are joined."""
    prints = winnowed(keyed.select("_id", "_key", F.col("_text").alias("text")), short)
    pairs = prints.join(item_prints, "print").select("_id", "_key", "item_id").distinct()
    wanted = pairs.join(items, "item_id").groupBy(F.col("_id").alias("_id2"), F.col("_key").alias("_key2")).agg(F.collect_set(F.struct("item_id", "text")).alias("_items"))
    whole = keyed.join(wanted, F.col("_id").eqNullSafe(F.col("_id2")) & (F.col("_key") == F.col("_key2")), "left").drop("_id", "_id2", "_key", "_key2")
    return extend(whole, "_text", keep)


def hits(docs: DataFrame, benchmark: DataFrame, keep: list[str] | None = None, broadcast_rows: int = BROADCAST_ROWS) -> DataFrame:
    """The kept columns (doc_id alone by default), n_words, n_hit, item_ids and contaminated for each document row.

    Kept columns come first and may have any names.
    """
    keep = ["doc_id"] if keep is None else keep
    items = benchmark.where("item_id IS NOT NULL AND text IS NOT NULL").select("item_id", "text").distinct()

    def lengths(batches):
        for batch in tg.slices(batches):
            counts = tg.Words(batch.column(0), tg.NOT_ALNUM).counts
            yield pa.RecordBatch.from_arrays([pa.array(np.unique(counts[(counts > 0) & (counts < WINDOW)]).astype(np.int64))], ["n"])

    short = sorted(r["n"] for r in items.select("text").mapInArrow(lengths, "n long").distinct().collect())  # 12 values at most
    kept = [f"_c{i}" for i in range(len(keep))]
    keyed = docs.select(F.col("doc_id").alias("_id"), F.xxhash64("text").alias("_key"), F.col("text").alias("_text"), *[F.col(c).alias(k) for c, k in zip(keep, kept, strict=True)])
    item_prints = saved(winnowed(items, short, own_length=True).distinct(), "item-prints")
    few = item_prints.count() <= broadcast_rows and (items.agg(F.sum(F.octet_length("text"))).first()[0] or 0) <= INDEX_BYTES
    if few:
        index = WindowIndex([(r["item_id"], r["text"]) for r in items.collect()], short)  # INDEX_BYTES of text at most
        found = index_hits(keyed.select("_text", *kept), "_text", kept, index, short)
    else:
        found = joined_hits(keyed, items, kept, item_prints, short)
    return found.select(
        *[F.col(k).alias(c) for c, k in zip(keep, kept, strict=True)], F.col("_n_words").alias("n_words"), F.col("_n_hit").alias("n_hit"), F.col("_item_ids").alias("item_ids"),
        F.expr(f"_n_hit > 0 AND {SHARE} * _n_hit >= _n_words").alias("contaminated"),
    )


def clean_documents(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """docs without contaminated rows, all their columns as they were."""
    n = len(docs.columns)
    plain = docs.toDF(*[f"c{i}" for i in range(n)])
    plain = plain.withColumn("doc_id", F.col(f"c{docs.columns.index('doc_id')}")).withColumn("text", F.col(f"c{docs.columns.index('text')}"))
    found = hits(plain, benchmark, keep=[f"c{i}" for i in range(n)])
    return found.where("NOT contaminated").select(*[F.col(f"c{i}").alias(c) for i, c in enumerate(docs.columns)])


def op9_winnowing(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = hits(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    names = F.array_sort(F.transform("item_ids", lambda i: i.cast("string")))
    return found.select(
        "doc_id", "n_words", "n_hit", F.size("item_ids").cast("long").alias("n_items"),
        F.sha2(F.concat_ws(",", names), 256).alias("items_sha256"), "contaminated",
    )


def sha_of(ids: list[int]) -> str:
    """Digest of item ids as the query writes it."""
    return hashlib.sha256(",".join(sorted(map(str, ids))).encode()).hexdigest()
