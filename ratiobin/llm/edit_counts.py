"""Edit-aware token counts.

A document is a sequence of chunks that byte-level pre-tokens never cross, held in blocks; a segment tree over the blocks
keeps their sums of characters and tokens.  An edit is found by walking down the tree by character position; only the
blocks it touches and one chunk of context on either side are cut into chunks and encoded again, and the sums on the path
to the root are updated.  Chunks met before are not encoded again.

Defined cases: null texts count as empty; edits are applied in order, positions and lengths are clipped to the text as it
then is; null insertions insert nothing; documents without edits keep their count; repeated rows each get their row.
"""

from __future__ import annotations

import re

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ratiobin.llm.common import table
from ratiobin.llm.packing import TextEncoder, encoder

BLOCK_CHUNKS = 32
#: Chunk counts that a Python worker remembers.
MEMO = 300_000

PLAIN = (" ", "\t", "\n", "\r")
#: A chunk begins where a character that is no space of any kind meets one of four plain spaces; after other spaces (no-break,
#: ideographic, control) borders are not safe, so a chunk goes on over a run of spaces that begins with such a one.
CHUNKS = re.compile(r"\s*\S+(?:[^\S \t\n\r]\s*(?:\S+|\Z))*|\s+")
#: Chunks of a block after which all blocks are cut anew, from the chunks and counts that they hold.
MOST_BLOCK = 16 * BLOCK_CHUNKS


class ChunkCounter:
    """Token counts of chunks, remembered up to a bound."""

    def __init__(self, encode: TextEncoder):
        self._encode = encode.encode
        self._memo: dict[str, int] = {}

    def __call__(self, chunks: list[str]) -> list[int]:
        new = list(set(chunks).difference(self._memo))
        if len(self._memo) + len(new) > MEMO:
            self._memo.clear()
            new = list(set(chunks))
        self._memo.update(zip(new, (len(x) // 4 for x in self._encode(new)), strict=True))
        return [self._memo[c] for c in chunks]


class TokenTree:
    """Chunks of one text in blocks under a segment tree of (characters, tokens)."""

    def __init__(self, text: str, count: ChunkCounter):
        self._count = count
        self.encoded = 0
        self._fill(text)

    def _fill(self, text: str) -> None:
        chunks = CHUNKS.findall(text)
        self._build(list(zip(chunks, self._count(chunks), strict=True)))

    def _build(self, held: list[tuple[str, int]]) -> None:
        self.blocks = [held[i : i + BLOCK_CHUNKS] for i in range(0, len(held), BLOCK_CHUNKS)] or [[]]
        self.size = 1 << (len(self.blocks) - 1).bit_length()
        self.chars, self.tokens = [0] * (2 * self.size), [0] * (2 * self.size)
        for i, block in enumerate(self.blocks):
            self.chars[self.size + i], self.tokens[self.size + i] = sum(len(c) for c, _ in block), sum(n for _, n in block)
        for i in range(self.size - 1, 0, -1):
            self.chars[i] = self.chars[2 * i] + self.chars[2 * i + 1]
            self.tokens[i] = self.tokens[2 * i] + self.tokens[2 * i + 1]

    @property
    def n_tokens(self) -> int:
        return self.tokens[1]

    @property
    def n_chars(self) -> int:
        return self.chars[1]

    def text(self) -> str:
        return "".join(c for block in self.blocks for c, _ in block)

    def _find(self, at: int) -> tuple[int, int]:
        """Block that holds character `at` (the last one with text beyond the end) and the block's first character."""
        node, before = 1, 0
        while node < self.size:
            left = self.chars[2 * node]
            if at < before + left or not self.chars[2 * node + 1]:
                node = 2 * node
            else:
                before, node = before + left, 2 * node + 1
        return node - self.size, before

    def _set(self, i: int, block: list[tuple[str, int]]) -> None:
        self.blocks[i] = block
        node = self.size + i
        self.chars[node], self.tokens[node] = sum(len(c) for c, _ in block), sum(n for _, n in block)
        while node > 1:
            node //= 2
            self.chars[node] = self.chars[2 * node] + self.chars[2 * node + 1]
            self.tokens[node] = self.tokens[2 * node] + self.tokens[2 * node + 1]

    def edit(self, at: int, delete: int, insert: str) -> None:
        """Replace `delete` characters from `at` by `insert`."""
        at = min(max(at, 0), self.n_chars)
        delete = min(max(delete, 0), self.n_chars - at)
        first, begin = self._find(max(at - 1, 0))
        last, _ = self._find(at + delete)
        held = [(c, n, i) for i in range(first, last + 1) for c, n in (self.blocks[i] if i < len(self.blocks) else [])]
        # Chunks that the edit touches, and one more on either side as context.
        edges = [begin]
        for c, _, _ in held:
            edges.append(edges[-1] + len(c))
        a = next((k for k in range(len(held)) if edges[k + 1] >= at), max(len(held) - 1, 0))
        b = next((k for k in range(len(held) - 1, -1, -1) if edges[k] <= at + delete), 0)
        a, b = max(a - 1, 0), min(b + 1, len(held) - 1)
        old = "".join(c for c, _, _ in held[a : b + 1])
        lead, tail = held[:a], held[b + 1 :]
        new = old[: at - edges[a]] + insert + old[at - edges[a] + delete :] if held else insert
        chunks = CHUNKS.findall(new)
        fresh = list(zip(chunks, self._count(chunks), strict=True))
        self.encoded += len(new)
        # A chunk that now lacks its leading space joins the one before; the context keeps this inside the region unless
        # the region begins its block, so the neighbour before it joins in.
        while first > 0 and not lead and (not fresh or fresh[0][0][:1] not in PLAIN):
            first -= 1
            if self.blocks[first]:
                *lead, (c, _) = self.blocks[first]
                lead = [(x, n, first) for x, n in lead]
                chunks = CHUNKS.findall(c + "".join(x for x, _ in fresh))
                fresh = list(zip(chunks, self._count(chunks), strict=True))
                self.encoded += len(c)
        if tail or last + 1 < len(self.blocks):
            fresh, tail, last = self._join_after(fresh, tail, last)
        self._set(first, [(c, n) for c, n, _ in lead] + fresh + [(c, n) for c, n, _ in tail])
        for i in range(first + 1, last + 1):
            if i < len(self.blocks) and self.blocks[i]:
                self._set(i, [])
        if len(self.blocks[first]) > MOST_BLOCK:
            self._build([c for block in self.blocks for c in block])

    def _join_after(self, fresh: list, tail: list, last: int) -> tuple[list, list, int]:
        """A region that ends in spaces, or is followed by a chunk without a leading space, takes the next chunk in."""
        while True:
            if not tail:
                while last + 1 < len(self.blocks) and not self.blocks[last + 1]:
                    last += 1
                if last + 1 >= len(self.blocks):
                    return fresh, tail, last
            following = tail[0][0] if tail else self.blocks[last + 1][0][0]
            spaces_end = bool(fresh) and fresh[-1][0][-1:].isspace()
            if fresh and not spaces_end and following[:1] in PLAIN:
                return fresh, tail, last
            if not tail:
                last += 1
                tail = [(c, n, last) for c, n in self.blocks[last]]
            chunks = CHUNKS.findall("".join(c for c, _ in fresh[-1:]) + following)
            self.encoded += len(following)
            fresh, tail = fresh[:-1] + list(zip(chunks, self._count(chunks), strict=True)), tail[1:]


_counters: dict = {}


def recount(docs: DataFrame, path: str | None = None) -> DataFrame:
    """(doc_id, text, edits array<struct<at, remove, put>>) to token counts before and after the edits and the work done."""

    def run(frames):
        if path not in _counters:
            _counters[path] = ChunkCounter(encoder(path))
        count = _counters[path]
        for frame in frames:
            rows = []
            for doc_id, text, edits in zip(frame["doc_id"], frame["text"], frame["edits"], strict=True):
                tree = TokenTree(text or "", count)
                before, chars = tree.n_tokens, tree.n_chars
                todo = [] if edits is None else list(edits)
                for e in todo:
                    tree.edit(int(e["at"]), int(e["remove"]), e["put"] or "")
                rows.append((doc_id, chars, before, len(todo), tree.n_chars, tree.n_tokens, tree.encoded))
            yield pd.DataFrame(rows, columns=["doc_id", "n_chars_before", "n_tokens_before", "n_edits", "n_chars_after", "n_tokens_after", "chars_reencoded"])

    return docs.select("doc_id", "text", "edits").mapInPandas(run, "doc_id long, n_chars_before long, n_tokens_before long, n_edits long, n_chars_after long, n_tokens_after long, chars_reencoded long")


def with_edits(docs: DataFrame, edits: DataFrame) -> DataFrame:
    """docs joined to their edits (doc_id, seq, at, remove, put), in order of seq."""
    listed = edits.groupBy("doc_id").agg(F.array_sort(F.collect_list(F.struct("seq", "at", "remove", "put"))).alias("edits"))
    return docs.select("doc_id", "text").join(listed, "doc_id", "left").withColumn("edits", F.transform("edits", lambda e: F.struct(e["at"].alias("at"), e["remove"].alias("remove"), e["put"].alias("put"))))


def drawn_edits(doc_id: Column, text: Column, n: int = 4) -> Column:
    """n edits of a text that its id fixes: places over the whole text, small deletions, insertions with and without spaces."""
    size = F.greatest(F.length(F.coalesce(text, F.lit(""))), F.lit(1))
    puts = ["", " new words", "\n", "joined", "  ", "tail of line.\nNext"]
    picks = []
    for k in range(n):
        draw = F.xxhash64(doc_id, F.lit(k))
        put = F.element_at(F.array(*map(F.lit, puts)), (F.pmod(F.shiftright(draw, 40), F.lit(len(puts))) + 1).cast("int"))
        picks.append(F.struct(F.pmod(draw, size).alias("at"), F.pmod(F.shiftright(draw, 20), F.lit(12)).alias("remove"), put.alias("put")))
    return F.array(*picks)


def op5_edit_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return recount(docs.withColumn("edits", drawn_edits(F.col("doc_id"), F.col("text"))))
