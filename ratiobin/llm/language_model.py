"""Language-model scores from a weighted backoff automaton over words.

Smoothed n-grams are states and arcs: a state for each history of up to order - 1 words (and one for the empty history), an
arc for each word seen after it, and a failure arc that carries the history's discounted mass to the history without its
first word.  One left-to-right traversal of a text carries the state: where no arc has the next word it follows failure arcs
until one does, and adds up the log-probabilities of all arcs taken.  `BackoffAutomaton` is that machine in plain Python.

The automaton of a corpus has an arc for every n-gram, which no task can hold.  It is dealt to shards by history.  Texts are
cut into parts of consecutive rows; each part sends every shard its distinct n-grams with their training counts (arrays, 6
to 8 bytes a key), the shard adds up all parts, and answers each part with the counts of just the states and arcs that the
part can reach.  From these the part builds its sub-automaton (`SubAutomaton`) and traverses its texts with it, all texts of
the part in step with each other; long texts are cut into segments, which start in the state that the order - 1 words before
them lead to, since a state depends on nothing else.

A history that is found often in a bounded sample has its arcs dealt to several shards by the next word, in proportion to
its share, so no shard grows with a frequent word.  The sample changes where arcs are counted, never a count.

Absolute discounts (by order, from counts of counts), interpolated with the shorter history; a Good-Turing share for the
unknown word.  The next word of an arc is told apart by 48 bits of its hash within its history: among a million words that
follow one history, two share them with a chance of 0.002.

Defined cases: null and empty texts are one end token; null ids are never held out (their crc32 is null); repeated rows
count and score each; with no training text the unknown word has probability one.
"""

from __future__ import annotations

import math
from collections import Counter, defaultdict
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ratiobin.llm import textgrid as tg
from ratiobin.llm.common import crc_mod, placed, saved, table

HELD_OUT_MOD = 10
#: Rows of a file that form at most one part, and text bytes after which a part is closed earlier.
SLAB_ROWS = 4096
PART_BYTES = 2 << 20
#: Parts (24 bytes each) up to which their bounds are broadcast.
BROADCAST_PARTS = 500_000
#: Input bytes a shard of the automaton stands for.
SHARD_BYTES = 4 << 20
#: Input bytes of a task that adds up shards (it holds one shard at a time), and most such tasks.
TASK_BYTES = 6 << 20
MOST_TASKS = 1 << 17
#: Text bytes of the sample that tells frequent histories, and most of them that are told.
SAMPLE_BYTES = 16 << 20
MOST_FREQUENT = 1 << 16
#: A history's arcs are split where it has more than this share of what a shard stands for.
SPLIT_SHARE = 0.25
#: Tokens of a text that one lane of the traversal walks.
SEGMENT = 256
ORDER = 2
BASE_SMOOTHING = 0.1

#: Stand-ins of the text's start (a history only) and end (a token); words never hash to them but by chance of 2**-64.
START, END = np.uint64(1), np.uint64(2)
LOW48 = np.uint64((1 << 48) - 1)


@dataclass(frozen=True)
class Totals:
    """Sizes of the training text, and how many n-grams of each length (1, 2, ...) occur once and twice in it."""

    tokens: int
    words: int
    docs: int
    once: tuple[int, ...]
    twice: tuple[int, ...]

    def discount(self, n: int) -> float:
        once, twice = self.once[n - 1], self.twice[n - 1]
        return min(max(once / (once + 2 * twice), 0.05), 0.95) if once else 0.1

    def base(self, count: np.ndarray) -> np.ndarray:
        return np.log10((count + BASE_SMOOTHING) / (self.tokens + BASE_SMOOTHING * (self.words + 1)))

    def word(self, count: np.ndarray) -> np.ndarray:
        """Probability of words by their training count; zero is the one unknown word."""
        if not self.tokens:
            return np.ones(len(count))
        d = self.discount(1)
        return np.where(count > 0, count - d, d * self.words) / self.tokens


class BackoffAutomaton:
    """Backoff automaton of any order over token sequences, for models that fit one process.

    Arcs hold log10 probabilities of a word after a history, interpolated with the shorter history; failure arcs hold the
    log10 of the mass left to it.  The state after a word is the longest known history that ends there.
    """

    def __init__(self, sentences: list[list[str]], order: int = 2):
        self.order = order
        counts: list[dict[tuple, Counter]] = [defaultdict(Counter) for _ in range(order)]
        for words in sentences:
            padded = ["<s>", *words, "</s>"]
            for i in range(1, len(padded)):
                for n in range(min(order - 1, i) + 1):
                    counts[n][tuple(padded[i - n : i])][padded[i]] += 1
        words = counts[0].get((), Counter())
        ones = [Counter(c for after in level.values() for c in after.values()) for level in counts]
        self.totals = Totals(sum(words.values()), len(words), len(sentences), tuple(o[1] for o in ones), tuple(o[2] for o in ones))
        self.counts = words
        self.arcs: dict[tuple, dict[str, float]] = {(): {}}
        self.fail: dict[tuple, float] = {}
        lower = dict(zip(words, self.totals.word(np.array(list(words.values()), dtype=float)).tolist(), strict=True))
        self.unknown = math.log10(self.totals.word(np.array([0.0]))[0]) if words or not sentences else 0.0
        self.arcs[()] = {w: math.log10(p) for w, p in lower.items()}
        for n in range(1, order):
            d = self.totals.discount(n + 1)
            for history, after in counts[n].items():
                total = sum(after.values())
                back = d * len(after) / total
                self.fail[history] = math.log10(back)
                self.arcs[history] = {w: math.log10((c - d) / total + back * 10 ** self._walk(history[1:], w)) for w, c in after.items()}

    def _walk(self, state: tuple, word: str) -> float:
        total = 0.0
        while True:
            if word in self.arcs.get(state, ()):
                return total + self.arcs[state][word]
            if not state:
                return total + self.unknown
            total += self.fail.get(state, 0.0)
            state = state[1:]

    def score(self, words: list[str]) -> float:
        state: tuple = ("<s>",) if self.order > 1 else ()
        total = 0.0
        for word in [*words, "</s>"]:
            total += self._walk(state, word)
            state = (*state, word)[-(self.order - 1) :] if self.order > 1 else ()
            while state and state not in self.arcs:
                state = state[1:]
        return total


@dataclass(frozen=True)
class Frequent:
    """Hashes of frequent histories, ascending, and the number of shards that each one's arcs are dealt to."""

    hashes: np.ndarray
    shards: np.ndarray

    def splits(self, hashes: np.ndarray) -> np.ndarray:
        """For each history the number of its shards; one for those that are not frequent."""
        if not len(self.hashes):
            return np.ones(len(hashes), dtype=np.int64)
        at = np.minimum(np.searchsorted(self.hashes, hashes), len(self.hashes) - 1)
        return np.where(self.hashes[at] == hashes, self.shards[at], 1)


NONE_FREQUENT = Frequent(np.zeros(0, np.uint64), np.zeros(0, np.int64))


def _shard(hashes: np.ndarray, n_shards: int) -> np.ndarray:
    return (hashes >> np.uint64(40)).astype(np.int64) * n_shards >> 24


class Level:
    """Distinct n-grams of one length in a part: their history, last word, suffix, and each position's n-gram.

    Histories and suffixes are n-grams one word shorter, by their place in the level below.
    """

    def __init__(self, history: np.ndarray, word: np.ndarray, suffix: np.ndarray, valid: np.ndarray, below: np.ndarray, words: np.ndarray):
        keys = (history[valid].astype(np.uint64) << np.uint64(32)) | word[valid].astype(np.uint64)
        found, first, inverse = np.unique(keys, return_index=True, return_inverse=True)
        self.history, self.word = (found >> np.uint64(32)).astype(np.int64), (found & np.uint64(0xFFFFFFFF)).astype(np.int64)
        self.suffix = suffix[valid][first]
        self.at = np.full(len(word), -1, dtype=np.int64)
        self.at[valid] = inverse
        with np.errstate(over="ignore"):
            self.history_hash = below[self.history]
            self.hashes = tg.pair_hash(self.history_hash, words[self.word])

    def deal(self, words: np.ndarray, n_shards: int, frequent: Frequent) -> None:
        """Order the n-grams by shard and history, and note the borders of shards and of histories."""
        splits = frequent.splits(self.history_hash)
        lane = (tg.mix64(words[self.word]) % splits.astype(np.uint64)).astype(np.uint64)
        spread = tg.pair_hash(self.history_hash, lane)
        shard = _shard(np.where(splits > 1, spread, self.history_hash), n_shards)
        self.order = np.argsort(shard, kind="stable")
        shard, history = shard[self.order], self.history[self.order]
        new = np.ones(len(shard), dtype=bool)
        new[1:] = (shard[1:] != shard[:-1]) | (history[1:] != history[:-1])
        self.runs = np.flatnonzero(new)
        self.edges = np.searchsorted(shard, np.arange(n_shards + 1))
        self.run_edges = np.searchsorted(self.runs, self.edges)


class Part:
    """Distinct words and n-grams of a run of texts.

    A text is its start, its words and its end; position 0 of each text is the start, which is a history and no token.
    """

    def __init__(self, column: pa.Array, order: int = ORDER):
        words = tg.Words(column, tg.SPACES)
        self.n_docs, self.n_tokens = words.n_docs, words.counts + 1
        size = words.counts + 2
        self.first = np.cumsum(size) - size
        hashes = np.empty(int(size.sum()), dtype=np.uint64)
        self.is_token = np.ones(len(hashes), dtype=bool)
        self.is_token[self.first] = False
        inner = self.is_token.copy()
        inner[self.first + size - 1] = False
        hashes[inner] = words.hashes()
        hashes[self.first], hashes[self.first + size - 1] = START, END
        del words
        self.words, self.token = np.unique(np.concatenate((hashes, [START, END])), return_inverse=True)
        self.start, self.end = int(self.token[-2]), int(self.token[-1])
        self.token = self.token[:-2]
        place = np.arange(len(self.token)) - np.repeat(self.first, size)
        self.levels: list[Level] = []
        below, hash_below = self.token, self.words
        for n in range(2, order + 1):
            history = np.concatenate((below[:1], below[:-1]))
            level = Level(history, self.token, below, place >= n - 1, hash_below, self.words)
            self.levels.append(level)
            below, hash_below = level.at, level.hashes

    def deal(self, n_shards: int, frequent: Frequent) -> None:
        self.word_edges = np.searchsorted(_shard(self.words, n_shards), np.arange(n_shards + 1))
        for level in self.levels:
            level.deal(self.words, n_shards, frequent)

    def training_counts(self, train: np.ndarray) -> list[np.ndarray]:
        """Counts of words and of the n-grams of each level in the texts that are trained on."""
        used = np.repeat(train, self.n_tokens + 1) & self.is_token
        out = [np.bincount(self.token[used], minlength=len(self.words))]
        for level in self.levels:
            at = level.at[used]
            out.append(np.bincount(at[at >= 0], minlength=len(level.word)))
        return out


def _pack(x: np.ndarray) -> bytes:
    """Counts as the narrowest unsigned type that holds them, tagged by its width."""
    most = int(x.max()) if len(x) else 0
    kind = "u1" if most < 1 << 8 else "<u2" if most < 1 << 16 else "<u4" if most < 1 << 32 else "<u8"
    return bytes([np.dtype(kind).itemsize]) + x.astype(kind).tobytes()


def _unpack(data: bytes) -> np.ndarray:
    return np.frombuffer(data, dtype=f"<u{data[0]}", offset=1).astype(np.int64)


def _low48(x: np.ndarray) -> bytes:
    return np.ascontiguousarray((x & LOW48).astype("<u8").view(np.uint8).reshape(-1, 8)[:, :6]).tobytes()


def _from_low48(data: bytes) -> np.ndarray:
    wide = np.zeros((len(data) // 6, 8), dtype=np.uint8)
    wide[:, :6] = np.frombuffer(data, dtype=np.uint8).reshape(-1, 6)
    return wide.view("<u8").ravel()


REQUEST = "level int, shard int, slab long, lo long, hi long, histories binary, fans binary, words binary, counts binary"
ANSWER = "level int, shard int, slab long, lo long, hi long, counts binary, fans binary, n_tokens long, n_words long, once long, twice long, frequent binary, frequent_fans binary"


def parts(batches, most: int):
    """Runs of consecutive rows of one slab, as (slab, lo, hi, batch)."""
    held, held_bytes = [], 0

    def close():
        whole = pa.Table.from_batches(held).combine_chunks().to_batches()[0]
        rows = whole.column(whole.schema.get_field_index("row_index"))
        return whole.column(whole.schema.get_field_index("slab"))[0].as_py(), rows[0].as_py(), rows[len(rows) - 1].as_py(), whole

    for batch in tg.slices(batches):
        slab = batch.column(batch.schema.get_field_index("slab")).to_numpy()
        cuts = [0, *(np.flatnonzero(slab[1:] != slab[:-1]) + 1).tolist(), len(slab)]
        for a, b in zip(cuts, cuts[1:], strict=False):
            piece = batch.slice(a, b - a)
            size = piece.nbytes
            if held and (held[-1].column(held[-1].schema.get_field_index("slab"))[0].as_py() != slab[a] or held_bytes + size > most):
                yield close()
                held, held_bytes = [], 0
            held.append(piece)
            held_bytes += size
    if held:
        yield close()


def ask(n_shards: int, order: int, frequent: Frequent, part_bytes: int = PART_BYTES):
    """mapInArrow: what each part of the corpus has and wants to know, by level and shard."""

    def run(batches):
        for slab, lo, hi, batch in parts(batches, part_bytes):
            part = Part(batch.column(batch.schema.get_field_index("text")), order)
            part.deal(n_shards, frequent)
            train = ~batch.column(batch.schema.get_field_index("held_out")).to_numpy(zero_copy_only=False).astype(bool)
            counts = part.training_counts(train)
            rows: dict[str, list] = {c.split()[0]: [] for c in REQUEST.split(", ")}
            for s in np.flatnonzero(np.diff(part.word_edges)).tolist():
                a, b = part.word_edges[s], part.word_edges[s + 1]
                row = (1, s, slab, lo, hi, b"", b"", part.words[a:b].astype("<u8").tobytes(), _pack(counts[0][a:b]))
                for values, v in zip(rows.values(), row, strict=True):
                    values.append(v)
            for n, (level, count) in enumerate(zip(part.levels, counts[1:], strict=True), 2):
                words, count = part.words[level.word[level.order]], count[level.order]
                hashes = level.history_hash[level.order[level.runs]]
                fans = np.diff(np.append(level.runs, len(level.order)))
                for s in np.flatnonzero(np.diff(level.edges)).tolist():
                    a, b, p, q = level.edges[s], level.edges[s + 1], level.run_edges[s], level.run_edges[s + 1]
                    row = (n, s, slab, lo, hi, hashes[p:q].astype("<u8").tobytes(), _pack(fans[p:q]), _low48(words[a:b]), _pack(count[a:b]))
                    for values, v in zip(rows.values(), row, strict=True):
                        values.append(v)
            del part
            kinds = [pa.int32(), pa.int32(), *[pa.int64()] * 3, *[pa.binary()] * 4]
            yield pa.RecordBatch.from_arrays([pa.array(rows[c], k) for c, k in zip(rows, kinds, strict=True)], list(rows))

    return run


def add_up(frequent: Frequent):
    """applyInArrow: one shard of one level, counts over all parts, answered part by part."""

    def run(shard: pa.Table) -> pa.Table:
        n = shard.num_rows
        column = {c: shard.column(c).to_pylist() for c in shard.schema.names}
        given = np.concatenate([_unpack(x) for x in column["counts"]])
        out: dict[str, list] = {c: column[c] for c in ("level", "shard", "slab", "lo", "hi")}
        sums = dict.fromkeys(("n_tokens", "n_words", "once", "twice"), 0)
        told, told_fans = b"", b""
        if column["level"][0] == 1:
            keys = [np.frombuffer(x, dtype="<u8") for x in column["words"]]
            known, place = np.unique(np.concatenate(keys), return_inverse=True)
            count = np.bincount(place, weights=given, minlength=len(known)).astype(np.int64)
            sums |= {"n_tokens": count.sum(), "n_words": (count > 0).sum()}
            out["fans"] = [b""] * n
        else:
            histories = [np.frombuffer(x, dtype="<u8") for x in column["histories"]]
            keys = [_from_low48(x) for x in column["words"]]
            known, owner = np.unique(np.concatenate(histories), return_inverse=True)
            of = np.repeat(owner, np.concatenate([_unpack(x) for x in column["fans"]]))
            arcs, first, place = np.unique(tg.pair_hash(known[of], np.concatenate(keys)), return_index=True, return_inverse=True)
            count = np.bincount(place, weights=given, minlength=len(arcs)).astype(np.int64)
            fan = np.bincount(of[first][count > 0], minlength=len(known))
            at = np.cumsum([0, *map(len, histories)])
            out["fans"] = [_pack(fan[owner[at[i] : at[i + 1]]]) for i in range(n)]
            often = frequent.splits(known) > 1
            told, told_fans = known[often].astype("<u8").tobytes(), fan[often].astype("<i8").tobytes()
        sums |= {"once": (count == 1).sum(), "twice": (count == 2).sum()}
        at = np.cumsum([0, *map(len, keys)])
        out["counts"] = [_pack(count[place[at[i] : at[i + 1]]]) for i in range(n)]
        out |= {c: [int(v)] + [0] * (n - 1) for c, v in sums.items()}
        out |= {"frequent": [told] + [None] * (n - 1), "frequent_fans": [told_fans] + [None] * (n - 1)}
        kinds = dict(zip((c.split()[0] for c in ANSWER.split(", ")), [pa.int32(), pa.int32(), *[pa.int64()] * 3, *[pa.binary()] * 2, *[pa.int64()] * 4, *[pa.binary()] * 2], strict=True))
        return pa.table([pa.array(out[c], k) for c, k in kinds.items()], names=list(kinds))

    return run


class SubAutomaton:
    """The states and arcs of the corpus's automaton that a part's texts can reach.

    State 0 is the empty history.  Arcs lie sorted by state and word; each has a weight and the state it leads to.  Every
    word of the part has an arc from state 0, that of the unknown word if training lacks it.
    """

    def __init__(self, part: Part, answers: list[dict], totals: Totals, frequent: Frequent, frequent_fans: np.ndarray):
        order = len(part.levels) + 1
        by_level: dict[int, list[dict]] = {n: [] for n in range(1, order + 1)}
        for r in sorted(answers, key=lambda r: (r["level"], r["shard"])):
            by_level[r["level"]].append(r)
        self.n_words = len(part.words)
        self.count = np.concatenate([_unpack(r["counts"]) for r in by_level[1]]).astype(np.float64)
        p = totals.word(self.count)
        mass = self.count.copy()  # of a history: how often a token follows it
        mass[part.start], mass[part.end] = totals.docs, 0.0
        hashes, state_of_below = part.words, None
        root = np.arange(self.n_words)
        arcs = [(np.zeros(self.n_words, np.int64), root, np.log10(p))]
        leads, self.fail_to, self.fail_weight, n_states = [], [np.zeros(1, np.int64)], [np.zeros(1)], 1
        for n, level in enumerate(part.levels, 2):
            told = by_level[n]
            count, fan = np.empty(len(level.word)), np.zeros(len(hashes))
            count[level.order] = np.concatenate([_unpack(r["counts"]) for r in told]) if told else np.zeros(0)
            runs = level.history[level.order[level.runs]]
            fan[runs] = np.concatenate([_unpack(r["fans"]) for r in told]) if told else np.zeros(0)
            if len(frequent.hashes):  # a split history's shards each know a part of its arcs
                at = np.minimum(np.searchsorted(frequent.hashes, hashes), len(frequent.hashes) - 1)
                hit = frequent.hashes[at] == hashes
                fan[hit] = frequent_fans[at[hit]]
            d, known = totals.discount(n), mass > 0
            safe = np.where(known, mass, 1.0)
            back = np.where(known, d * fan / safe, 1.0)
            state = np.where(known, n_states + np.cumsum(known) - 1, -1)
            suffix = None if n == 2 else part.levels[n - 3].suffix
            self.fail_to.append(np.zeros(int(known.sum()), np.int64) if n == 2 else state_of_below[suffix[known]])
            with np.errstate(divide="ignore"):
                self.fail_weight.append(np.log10(back[known]))
            n_states += int(known.sum())
            leads.append(np.maximum(state, 0))
            h = level.history
            p = np.where(known[h], np.where(count > 0, count - d, 0.0) / safe[h], 0.0) + back[h] * p[level.suffix]
            seen = count > 0
            arcs.append((state[h[seen]], np.flatnonzero(seen), np.log10(p[seen])))
            hashes, state_of_below = level.hashes, np.maximum(state, 0)
            ends = level.word == part.end
            mass = np.where(ends, 0.0, count)
        self.fail_to, self.fail_weight = np.concatenate(self.fail_to), np.concatenate(self.fail_weight)
        self.start = int(leads[0][part.start]) if leads else 0
        keys, weights, targets = [], [], []
        for n, (state, gram, weight) in enumerate(arcs, 1):
            word = gram if n == 1 else part.levels[n - 2].word[gram]
            if n <= len(leads):
                target = leads[n - 1][gram]
            else:
                target = np.zeros(len(gram), np.int64) if order == 1 else leads[-1][part.levels[n - 2].suffix[gram]]
            keys.append(state * self.n_words + word)
            weights.append(weight)
            targets.append(target)
        keys = np.concatenate(keys)
        sort = np.argsort(keys)
        self.keys, self.weight, self.target = keys[sort], np.concatenate(weights)[sort], np.concatenate(targets)[sort]

    def step(self, state: np.ndarray, word: np.ndarray, total: np.ndarray) -> None:
        """Each lane takes the arc of its word, after as many failure arcs as it needs; state and total are changed."""
        todo = np.arange(len(state))
        while len(todo):
            key = state[todo] * self.n_words + word[todo]
            at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
            hit = self.keys[at] == key
            done, arc = todo[hit], at[hit]
            total[done] += self.weight[arc]
            state[done] = self.target[arc]
            todo = todo[~hit]
            total[todo] += self.fail_weight[state[todo]]
            state[todo] = self.fail_to[state[todo]]

    def traverse(self, part: Part, segment: int = SEGMENT) -> np.ndarray:
        """Log-probability of each text, from its start to its end."""
        before = len(part.levels)
        lanes = -(-part.n_tokens // segment)
        doc = np.repeat(np.arange(part.n_docs), lanes)
        rank = np.arange(len(doc)) - np.repeat(np.cumsum(lanes) - lanes, lanes)
        begin = part.first[doc] + 1 + rank * segment
        stop = np.minimum(begin + segment, part.first[doc] + 1 + part.n_tokens[doc])
        state = np.where(rank == 0, self.start, 0)
        total = np.zeros(len(doc))
        for back in range(before, 0, -1):  # lead segments inside a text to their state
            inside = np.flatnonzero((rank > 0) & (begin - back > part.first[doc]))
            some, ignored = state[inside], np.zeros(len(inside))
            self.step(some, part.token[begin[inside] - back], ignored)
            state[inside] = some
        alive = np.argsort(begin - stop, kind="stable")  # the longest first
        sizes = (stop - begin)[alive]
        state, total, at = state[alive], total[alive], begin[alive]
        for i in range(int(sizes[0]) if len(sizes) else 0):
            n = int(np.searchsorted(-sizes, -i, side="left"))
            self.step(state[:n], part.token[at[:n] + i], total[:n])
        return np.bincount(doc[alive], weights=total, minlength=part.n_docs)


def walk(part: Part, answers: list[dict], totals: Totals, frequent: Frequent, frequent_fans: np.ndarray) -> dict[str, np.ndarray]:
    """Scores of the part's texts: one traversal of the sub-automaton, and the sums over single words."""
    if not part.n_docs:
        return {}
    machine = SubAutomaton(part, answers, totals, frequent, frequent_fans)
    tokens = part.token[part.is_token]
    first = np.cumsum(part.n_tokens) - part.n_tokens
    return {
        "n_tokens": part.n_tokens, "n_known": np.add.reduceat((machine.count[tokens] > 0).astype(np.int64), first),
        "base_score": np.add.reduceat(totals.base(machine.count)[tokens], first), "score": machine.traverse(part),
    }


def numbered(docs: DataFrame) -> DataFrame:
    """docs with the slab of rows of a file that each row belongs to, and its place in the file."""
    return placed(docs, "_file", "row_index").withColumn("slab", F.xxhash64("_file", F.expr(f"row_index div {SLAB_ROWS}"))).drop("_file")


def frequent_histories(rows: DataFrame, n_bytes: int, n_shards: int, order: int, split_share: float) -> Frequent:
    """Histories that hold more than `split_share` of a shard's share of the tokens in a sample of SAMPLE_BYTES."""
    if order < 2 or not n_bytes:
        return NONE_FREQUENT
    share = min(1.0, SAMPLE_BYTES / n_bytes)
    some = rows.where(F.pmod(F.xxhash64("slab", "row_index"), F.lit(1_000_000)) < max(int(share * 1_000_000), 1))

    def run(batches):
        for batch in tg.slices(batches):
            part = Part(batch.column(batch.schema.get_field_index("text")), order)
            for n, level in enumerate(part.levels, 2):
                at = level.at[level.at >= 0]
                count = np.bincount(level.history[at], minlength=1)
                found = np.flatnonzero(count)
                hashes = part.words if n == 2 else part.levels[n - 3].hashes
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(found), n)), pa.array(hashes[found].view(np.int64)), pa.array(count[found])], ["level", "history", "n"])

    counts = saved(some.select("text").mapInArrow(run, "level long, history long, n long").groupBy("level", "history").agg(F.sum("n").alias("n")), "histories")
    whole = {r["level"]: r["n"] for r in counts.groupBy("level").agg(F.sum("n").alias("n")).collect()}  # one row a level
    if not whole:
        return NONE_FREQUENT
    least = split_share / n_shards * max(whole.values())
    often = counts.where(F.col("n") > least).groupBy("history").agg(F.max("n").alias("n")).orderBy(F.desc("n"), "history").limit(MOST_FREQUENT).collect()
    hashes = np.array([r["history"] for r in often], dtype=np.int64).view(np.uint64)
    splits = np.minimum(np.ceil(np.array([r["n"] for r in often], dtype=float) / least), n_shards).astype(np.int64)
    sort = np.argsort(hashes)
    return Frequent(hashes[sort], np.maximum(splits[sort], 2)) if len(often) else NONE_FREQUENT


def frequent_fans(answers: DataFrame, frequent: Frequent) -> np.ndarray:
    """For each frequent history the number of words that follow it, summed over its shards."""
    fans = np.zeros(len(frequent.hashes))
    if not len(fans):
        return fans

    def run(batches):
        for batch in batches:
            for told, fan in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                yield pa.RecordBatch.from_arrays([pa.array(np.frombuffer(told, dtype="<i8")), pa.array(np.frombuffer(fan, dtype="<i8"))], ["history", "fan"])

    rows = answers.where("length(frequent) > 0").select("frequent", "frequent_fans").mapInArrow(run, "history long, fan long")
    for r in rows.groupBy("history").agg(F.sum("fan").alias("fan")).collect():  # MOST_FREQUENT rows at most
        fans[np.searchsorted(frequent.hashes, np.array([r["history"]]).view(np.uint64)[0])] = r["fan"]
    return fans


def lm_scores(docs: DataFrame, part_bytes: int = PART_BYTES, order: int = ORDER, split_share: float = SPLIT_SHARE, shard_bytes: int = SHARD_BYTES) -> DataFrame:
    """(doc_id, text) rows of a file source to their scores under a model of the rows that are not held out."""
    rows = numbered(docs.select("doc_id", "text")).withColumn("held_out", F.coalesce(crc_mod("doc_id", HELD_OUT_MOD) == 0, F.lit(False)))
    n_bytes, n_docs = rows.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0)), F.count(F.when(~F.col("held_out"), 1))).first()
    n_shards = int(min(max(n_bytes // shard_bytes, 8), 1 << 20))
    frequent = frequent_histories(rows, n_bytes, n_shards, order, split_share)
    asked = rows.select("slab", "row_index", "held_out", "text").mapInArrow(ask(n_shards, order, frequent, part_bytes), REQUEST)
    tasks = int(min(max(n_bytes // TASK_BYTES, 8), MOST_TASKS))
    answers = saved(asked.repartition(tasks, "level", "shard").groupBy("level", "shard").applyInArrow(add_up(frequent), ANSWER), "automaton")
    sums = {r["level"]: r for r in answers.groupBy("level").agg(*[F.sum(c).alias(c) for c in ("n_tokens", "n_words", "once", "twice")]).collect()}  # one row a level
    of = lambda c: tuple(sums[n][c] if n in sums else 0 for n in range(1, order + 1))
    totals = Totals(of("n_tokens")[0], of("n_words")[0], n_docs, of("once"), of("twice"))
    fans = frequent_fans(answers, frequent)

    def run(texts: pa.Table, told: pa.Table) -> pa.Table:
        texts = texts.sort_by("row_index")
        part = Part(texts.column("text"), order)
        part.deal(n_shards, frequent)
        found = walk(part, told.to_pylist(), totals, frequent, fans)
        names = ["n_tokens", "n_known", "base_score", "score"]
        return pa.table([texts.column("doc_id"), pc.cast(texts.column("held_out"), pa.bool_()), *(pa.array(found[c]) for c in names)], names=["doc_id", "held_out", *names])

    # Rows meet the answers of their own part, so a task holds PART_BYTES of text (or one longer text), whatever the slab's.
    bounds = answers.select(F.col("slab").alias("_slab"), F.col("lo").alias("_lo"), F.col("hi").alias("_hi")).distinct()
    few = bounds.limit(BROADCAST_PARTS + 1).count() <= BROADCAST_PARTS
    inside = (F.col("slab") == F.col("_slab")) & (F.col("row_index") >= F.col("_lo")) & (F.col("row_index") <= F.col("_hi"))
    dealt = rows.join(F.broadcast(bounds) if few else bounds, inside).select("slab", F.col("_lo").alias("lo"), "row_index", "doc_id", "held_out", "text")
    right = answers.select("slab", "lo", "level", "shard", "counts", "fans").groupBy("slab", "lo")
    scored = dealt.groupBy("slab", "lo").cogroup(right).applyInArrow(run, "doc_id long, held_out boolean, n_tokens long, n_known long, base_score double, score double")
    return scored.withColumn("train_tokens", F.lit(totals.tokens).cast("long"))


def op2_backoff_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = lm_scores(table(spark, sf_dir, "documents"))
    return found.select("doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score")
