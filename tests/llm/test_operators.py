"""Operators against brute force on small tables with odd rows, and on empty tables."""

import hashlib
import math
import re
import zlib
from pathlib import Path

import numpy as np
import pytest
import xxhash

from ratiobin.llm import decontam, edit_counts, entry, language_model, nn_descent, packing, resampling, secrets, simhash, toxicity
from ratiobin.llm.graph import connected_components


def lower(text):
    return re.sub("[A-Z]", lambda m: m[0].lower(), text or "")


def space_words(text):
    return re.findall(r"[^\x20\x09-\x0D]+", lower(text))


def alnum_words(text):
    return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", lower(text))


def key(r):
    return (r["doc_id"] is not None, r["doc_id"] or 0)


@pytest.mark.parametrize("name", list(entry.QUERIES))
def test_empty_tables_give_empty_results(spark, empty_tables, name):
    assert entry.QUERIES[name](spark, empty_tables).collect() == []


@pytest.mark.parametrize("name", ["op2_backoff_lm", "op3_toxicity", "op5_edit_counts", "op6_resampling", "op7_secrets", "op8_simhash", "op9_winnowing"])
def test_one_row_for_each_document(spark, tables, corpus, name):
    rows = entry.QUERIES[name](spark, tables).collect()
    assert sorted(map(key, rows)) == sorted((i is not None, i or 0) for i, _ in corpus[0])


def test_simhash(spark, tables, corpus):
    def fingerprint(text):
        w = space_words(text)
        shingles = [" ".join(w[k : k + 3]) for k in range(max(1, len(w) - 2))] if w else []
        h = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
        return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))

    docs = [(i, t) for i, t in corpus[0] if i != 406]
    prints = {i: fingerprint(t) for i, t in docs}
    rows = {r["doc_id"]: r for r in simhash.op8_simhash(spark, tables).collect()}
    prints[406] = int(rows[406]["fingerprint"], 16)
    assert all(rows[i]["fingerprint"] == f"{p:016x}" for i, p in prints.items())
    group = {i: i for i in prints}
    for _ in range(len(group)):
        for a in prints:
            for b in prints:
                if (prints[a] ^ prints[b]).bit_count() <= 3:
                    group[a] = group[b] = min((group[a], group[b]), key=lambda x: math.inf if x is None else x)
        if all(group[a] == group[b] for a in prints for b in prints if (prints[a] ^ prints[b]).bit_count() <= 3):
            break
    assert {i: rows[i]["component_id"] for i in prints} == group
    assert rows[400]["fingerprint"] == "0" * 16 and rows[400]["component_id"] == 400 == rows[402]["component_id"]


def test_crowded_shards_lose_no_link(spark):
    rng = np.random.default_rng(0)
    base = [int(x) for x in rng.integers(0, 1 << 62, 40)]
    values = sorted({b ^ sum(1 << int(i) for i in rng.choice(64, k, replace=False)) for b in base for k in (0, 1, 2, 3) for _ in range(6)})
    df = spark.createDataFrame([(int(np.uint64(v).view(np.int64)),) for v in values], "fp long")

    def sets(crowded):
        groups = {}
        for r in simhash.components(df, crowded=crowded).collect():
            groups.setdefault(r["component"], set()).add(r["fp"])
        return sorted(map(sorted, groups.values()))

    signed = {v: int(np.uint64(v).view(np.int64)) for v in values}
    left, want = set(values), []
    while left:
        todo, found = [left.pop()], set()
        while todo:
            a = todo.pop()
            found.add(a)
            near = {b for b in left if (a ^ b).bit_count() <= 3}
            left -= near
            todo += near
        want.append(sorted(signed[v] for v in found))
    assert sets(10_000) == sets(2) == sorted(want)


@pytest.mark.parametrize("broadcast_edges", [500_000, 0])
def test_components_of_a_long_path(spark, broadcast_edges):
    n = 300
    edges = spark.createDataFrame([(i, i + 1) for i in range(n)] + [(1000, 1001), (5000, 5000)], "src long, dst long")
    found = {r["node"]: r["component"] for r in connected_components(edges, broadcast_edges).collect()}
    assert found == {**dict.fromkeys(range(n + 1), 0), 1000: 1000, 1001: 1000}


def test_decontamination(spark, tables, corpus):
    docs, items = corpus
    windows = {}
    for i, t in items:
        w = alnum_words(t)
        n = min(13, len(w))
        for k in range(len(w) - n + 1) if n else ():
            windows.setdefault(tuple(w[k : k + n]), set()).add(i)
    lengths = {len(w) for w in windows}
    for r, (_, t) in zip(sorted(decontam.op9_winnowing(spark, tables).collect(), key=key), sorted(docs, key=lambda d: (d[0] is not None, d[0] or 0)), strict=True):
        w, hit, found = alnum_words(t), set(), set()
        for n in lengths:
            for k in range(len(w) - n + 1):
                if tuple(w[k : k + n]) in windows:
                    found |= windows[tuple(w[k : k + n])]
                    hit |= set(range(k, k + n))
        assert (r["n_words"], r["n_hit"], r["n_items"], r["items_sha256"]) == (len(w), len(hit), len(found), decontam.sha_of(list(found)))
        assert r["contaminated"] == (len(hit) > 0 and 20 * len(hit) >= len(w))
    assert r is not None


def test_shuffled_benchmark_join_is_the_same(spark, tables):
    docs, items = spark.read.parquet(f"{tables}/documents.parquet"), spark.read.parquet(f"{tables}/benchmark.parquet")
    a, b = (sorted(map(str, decontam.hits(docs, items, broadcast_rows=n).collect())) for n in (0, 10_000))
    assert a == b
    clean = decontam.clean_documents(docs, items)
    assert clean.columns == docs.columns and 0 < clean.count() < docs.count()


def test_winnowing_keeps_a_gram_of_every_long_span():
    rng = np.random.default_rng(1)
    grams = rng.integers(0, 50, 500).astype(np.uint64)
    kept = set(decontam.winnow(grams, np.array([200, 5, 295]), 9).tolist())
    assert all(any(i in kept for i in range(a, a + 9)) for a in [*range(192), *range(205, 492)])
    assert not kept & set(range(200, 205))


BASE = [
    ("assign", re.compile(r"""(?a:(?i:(password|passwd|secret|token|api_?key)))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""), lambda m: len(m[2]) >= 6),
    ("access", re.compile("AKIA[A-Z0-9]+"), lambda m: len(m[0]) >= 20),
    ("hex", re.compile("[0-9a-f]+"), lambda m: len(m[0]) >= 24),
]


def test_secrets(spark, tables, corpus):
    rows = secrets.op7_secrets(spark, tables).collect()
    texts = dict(corpus[0])
    for r in rows:
        found = sorted((m.start(), k, m.end()) for k, (_, e, good) in enumerate(BASE) for m in e.finditer(texts[r["doc_id"]] or "") if good(m))
        assert r["base_sha256"] == hashlib.sha256(",".join(f"{BASE[k][0]}:{a}:{b}" for a, k, b in found).encode()).hexdigest()
        assert [r["n_assign"], r["n_access"], r["n_hex"]] == [sum(k == j for _, k, _ in found) for j in range(3)]
    assert sum(r["n_assign"] for r in rows) == 4


def test_checksummed_tokens():
    body = "0123456789abcdefghijABCDEFGHIJ"
    good = f"x ghp_{body}{secrets.checksum62(body)} y"
    assert secrets.find_spans(good) == [("checked", 2, 42)]
    assert secrets.find_spans(good[:41] + ("a" if good[41] != "a" else "b") + " y") == []
    assert secrets.blanked(good, "#") == "x # y" and secrets.blanked("plain", "#") == "plain" and secrets.blanked(None, "#") is None


def test_packing(spark, tables, corpus):
    rows = packing.op10_packing(spark, tables).collect()
    encode = packing.encoder()
    by_doc, by_sequence = {}, {}
    for r in rows:
        by_doc.setdefault(r["doc_id"], []).append(r)
        by_sequence.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for i, t in corpus[0]:
        ids = encode._slow(t or "") + np.array([2], dtype="<u4").tobytes()
        parts = sorted(by_doc[i], key=lambda r: (r["piece"], r["sequence_id"]))
        parts = parts[:: 2 if i == 50 else 1]
        at = 0
        for k, r in enumerate(parts):
            assert (r["piece"], r["start"]) == (k, at) and r["ids_crc32"] == zlib.crc32(ids[4 * at : 4 * (at + r["length"])])
            at += r["length"]
        assert at == len(ids) // 4 and all(r["length"] == 1024 for r in parts[1:])
    for places in by_sequence.values():
        at = 0
        for offset, length in sorted(places):
            assert offset == at
            at += length
        assert at <= 1024


def test_best_fit_plan_places_every_piece_once():
    rng = np.random.default_rng(3)
    histogram = {int(n): int(c) for n, c in zip(*np.unique(rng.integers(1, 1025, 5000), return_counts=True), strict=True)}
    plan, used = packing.best_fit_plan(histogram)
    fill = np.zeros(used, dtype=int)
    spans = {}
    for length, lo, hi, first, at, per in plan:
        for r in range(lo, hi):
            s, o = first + (r - lo) // per, at + (r - lo) % per * length
            spans.setdefault(s, []).append((o, length))
            fill[s] += length
    assert {n: sum(h - a for m, a, h, *_ in plan if m == n) for n in histogram} == histogram
    for places in spans.values():
        ends = [0] + [o + n for o, n in sorted(places)]
        assert [o for o, _ in sorted(places)] == ends[:-1] and ends[-1] <= 1024
    total = sum(n * c for n, c in histogram.items())
    assert used <= math.ceil(total / 1024) * 1.01 + 1


def test_language_model_equals_the_automaton(spark, tables, corpus):
    docs = corpus[0]
    words = [(i, space_words(t)) for i, t in docs]
    held = lambda i: i is not None and zlib.crc32(str(i).encode()) % 10 == 0
    machine = language_model.BackoffAutomaton([w for i, w in words if not held(i)], 2)
    n, v = machine.totals.tokens, machine.totals.words
    want = {i: w for i, w in words}
    for r in language_model.op2_backoff_lm(spark, tables).collect():
        tokens = [*want[r["doc_id"]], "</s>"]
        base = sum(math.log10((machine.counts.get(w, 0) + 0.1) / (n + 0.1 * (v + 1))) for w in tokens)
        assert r["base_score"] == pytest.approx(base, abs=1e-6) and r["score"] == pytest.approx(machine.score(tokens[:-1]), abs=1e-6)
        assert (r["n_tokens"], r["n_known"], r["train_tokens"], r["held_out"]) == (len(tokens), sum(w in machine.counts for w in tokens), n, held(r["doc_id"]))


@pytest.mark.parametrize("order, split", [(1, 0.25), (2, 1e-4), (3, 1e-4)])
def test_language_model_of_any_order_with_split_histories(spark, tables, corpus, order, split):
    docs = spark.read.parquet(f"{tables}/documents.parquet")
    words = {i: space_words(t) for i, t in corpus[0]}
    machine = language_model.BackoffAutomaton([space_words(t) for i, t in corpus[0] if i is None or zlib.crc32(str(i).encode()) % 10], order)
    rows = language_model.lm_scores(docs, 20_000, order, split, 4000).collect()
    assert len(rows) == len(corpus[0]) and all(r["score"] == pytest.approx(machine.score(words[r["doc_id"]]), abs=1e-6) for r in rows)


@pytest.mark.parametrize("order", [1, 2, 3, 4])
@pytest.mark.parametrize("splits", [1, 3])
def test_traversal_in_segments_equals_the_automaton(order, splits):
    import random

    import pyarrow as pa

    rng = random.Random(order)
    docs = [" ".join(f"w{rng.randrange(25)}" if rng.random() < 0.9 else f"r{rng.randrange(10**6)}" for _ in range(rng.randrange(60))) for _ in range(60)] + ["", None, "w1 w2 w3 " * 400]
    train = np.array([i % 5 != 0 for i in range(len(docs))])
    machine = language_model.BackoffAutomaton([(d or "").split() for d, t in zip(docs, train, strict=True) if t], order)
    part = language_model.Part(pa.array(docs), order)
    often = np.unique(np.concatenate([part.words, *(x.hashes for x in part.levels[:-1])]))[::3]
    frequent = language_model.Frequent(often, np.full(len(often), splits)) if splits > 1 else language_model.NONE_FREQUENT
    rows = pa.RecordBatch.from_pydict({"slab": [0] * len(docs), "row_index": list(range(len(docs))), "held_out": ~train, "text": docs})
    asked = pa.Table.from_batches(language_model.ask(8, order, frequent)([rows])).to_pandas()
    answers = []
    for _, shard in asked.groupby(["level", "shard"]):
        answers += language_model.add_up(frequent)(pa.Table.from_pandas(shard, preserve_index=False)).to_pylist()
    of = lambda c, n: sum(a[c] for a in answers if a["level"] == n)
    totals = language_model.Totals(of("n_tokens", 1), of("n_words", 1), int(train.sum()), *(tuple(of(c, n) for n in range(1, order + 1)) for c in ("once", "twice")))
    assert totals == machine.totals
    fans = np.zeros(len(frequent.hashes))
    for a in answers:
        if a["frequent"]:
            np.add.at(fans, np.searchsorted(frequent.hashes, np.frombuffer(a["frequent"], dtype="<u8")), np.frombuffer(a["frequent_fans"], dtype="<i8"))
    part.deal(8, frequent)
    for segment in (7, 256):
        scores = language_model.SubAutomaton(part, answers, totals, frequent, fans).traverse(part, segment)
        assert scores.tolist() == pytest.approx([machine.score((d or "").split()) for d in docs])


def test_parts_of_any_size_give_the_same_scores(spark, tables):
    docs = spark.read.parquet(f"{tables}/documents.parquet")
    few, many = (sorted((r["doc_id"] or -1, round(r["base_score"], 6), round(r["score"], 6)) for r in language_model.lm_scores(docs, n).collect()) for n in (1 << 30, 2000))
    assert few == many


@pytest.mark.parametrize("order", [1, 2, 3])
def test_automaton_probabilities_add_up_to_one(order):
    machine = language_model.BackoffAutomaton([list("abcab"), list("abd"), list("ba")], order)
    for state in machine.arcs:
        total = sum(10 ** machine._walk(state, w) for w in [*machine.counts, "<never seen>"])
        assert total == pytest.approx(1.0)


def test_toxicity_finds_misspellings_it_never_saw():
    rng = np.random.default_rng(0)
    plain = ["".join(rng.choice(list("abcdefghijklmnop"), rng.integers(3, 9))) for _ in range(300)]
    bad = ["zorgwat", "quxblot"]
    texts, labels = [], []
    for i in range(400):
        words = list(rng.choice(plain, rng.integers(5, 120)))
        if i % 2:
            words.insert(rng.integers(len(words)), bad[i % 4 // 2])
        texts.append(" ".join(words))
        labels.append(i % 2)
    model = toxicity.train(texts, labels)
    import pyarrow as pa

    scores = toxicity.doc_scores(pa.array([" ".join(plain[:40]), " ".join([*plain[:40], "zorgwaat"]), None, "", "ZORGWAT!"]), model)
    assert scores[0] < 0.7 <= min(scores[1], scores[4]) and max(scores[2:4]) < 0.7


def test_toxicity_without_labels_is_undecided(spark, tables):
    docs = spark.read.parquet(f"{tables}/documents.parquet")
    model = toxicity.fit(docs, spark.read.parquet(f"{tables}/labels.parquet").limit(0))
    assert {r["score"] for r in toxicity.score(docs.select("doc_id", "text"), model).collect()} == {0.5}


def test_resampling_takes_the_largest_keys(spark, tables):
    rows = resampling.op6_resampling(spark, tables).collect()
    keys = sorted((r["key"] for r in rows), reverse=True)
    least = keys[round(len(rows) * resampling.FRACTION) - 1]
    assert all(r["selected"] == (r["key"] >= least) for r in rows)
    docs, ids = spark.read.parquet(f"{tables}/documents.parquet"), spark.read.parquet(f"{tables}/labels.parquet").where("quality = 1").select("doc_id")
    assert {r["log_weight"] for r in resampling.resample(docs, ids.limit(0)).collect()} == {0.0}


def test_kth_largest(spark):
    values = [float(x) for x in np.random.default_rng(2).normal(size=3000)] + [5.0] * 50
    df = spark.createDataFrame([(v,) for v in values], "x double")
    for k in (1, 49, 50, 51, 1500, 3050):
        assert resampling.kth_largest(df, "x", k, bins=7, few=20) == sorted(values, reverse=True)[k - 1]


def test_edit_counts_equal_a_full_count(spark, tables, corpus):
    from pyspark.sql import functions as F

    docs = spark.read.parquet(f"{tables}/documents.parquet").select("doc_id", "text")
    edits = {r["doc_id"]: r["e"] for r in docs.select("doc_id", edit_counts.drawn_edits(F.col("doc_id"), F.col("text")).alias("e")).collect()}
    encode, texts = packing.encoder(), dict(corpus[0])
    for r in edit_counts.op5_edit_counts(spark, tables).collect():
        text = texts[r["doc_id"]] or ""
        assert r["n_tokens_before"] == len(encode._slow(text)) // 4
        for e in edits[r["doc_id"]]:
            at = min(e["at"], len(text))
            text = text[:at] + e["put"] + text[at + e["remove"] :]
        assert (r["n_tokens_after"], r["n_chars_after"]) == (len(encode._slow(text)) // 4, len(text))


def test_many_edits_of_one_tree():
    import random

    rng = random.Random(4)
    encode = packing.encoder()
    count = edit_counts.ChunkCounter(encode)
    for trial in range(30):
        text = "".join(rng.choice(["word", " ", "\n", "é", ".", "it's", "  ", " " if trial % 7 == 0 else "x"]) for _ in range(rng.randrange(300)))
        tree = edit_counts.TokenTree(text, count)
        for _ in range(15):
            at, cut, put = rng.randrange(len(text) + 3), rng.randrange(9), rng.choice(["", " ", "a", "\n\n", "new one ", "'ll"])
            tree.edit(at, cut, put)
            a = min(at, len(text))
            text = text[:a] + put + text[a + cut :]
            assert tree.text() == text and tree.n_tokens == len(encode._slow(text)) // 4


def test_rank_engine_gives_the_tokenizer_ids(corpus):
    encode = packing.encoder()
    assert encode._ranks is not None
    texts = [t or "" for _, t in corpus[0]] + list(packing.PROBES)
    assert encode.encode(texts) == [encode._slow(t) if t else b"" for t in texts]


@pytest.fixture(scope="session")
def vectors():
    rng = np.random.default_rng(9)
    base = rng.normal(size=(40, 16))
    rows = [base[i] + rng.normal(scale=s, size=16) for i in range(40) for s in (0.0, 0.1, 0.3, 0.5)]
    clique = rng.normal(size=16)
    rows += [clique + rng.normal(scale=0.02, size=16) for _ in range(60)] + [clique] * 30
    out = [(i, [float(x) for x in r]) for i, r in enumerate(rows)]
    nan = float("nan")
    return out + [(900, None), (901, [0.0] * 16), (902, [nan] + [1.0] * 15), (903, [None] + [1.0] * 15), (904, [float("inf")] + [1.0] * 15), (905, []), (906, [1.0, 2.0]), (907, [2.0, 4.0]), (5, out[5][1])]


def test_nn_descent(spark, vectors, tmp_path):
    spark.createDataFrame([(i, v, 0) for i, v in vectors], "vec_id long, embedding array<double>, label int").coalesce(2).write.parquet(f"{tmp_path}/embeddings.parquet")
    rows = nn_descent.op1_nn_descent(spark, str(tmp_path)).collect()
    usable = [(i, np.array(v) / np.linalg.norm(v)) for i, v in vectors if v and all(c is not None and np.isfinite(c) for c in v) and any(v)]
    links = [[b for b, (j, y) in enumerate(usable) if a != b and len(x) == len(y) and x @ y >= 0.9] for a, (i, x) in enumerate(usable)]
    true = sum(map(len, links))
    found = sum(r["n_links"] for r in rows)
    assert 0.98 * true <= found <= true and {r["vec_id"]: r["n_links"] for r in rows}[906] == 1
    assert all(r["n_links"] == 0 and r["component_id"] == r["vec_id"] for r in rows if 900 <= r["vec_id"] <= 905)
    assert all(r["kept"] == (r["vec_id"] == r["component_id"]) for r in rows) and len(rows) == len(vectors)


def around(rng, centre, n, spread):
    """Unit vectors close to a centre."""
    x = centre + spread * rng.normal(size=(n, len(centre)))
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def brute(x):
    return (x @ x.T >= 0.9).sum(1) - 1


def near_rows(spark, x):
    rows = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>")
    return {r["vec_id"]: r for r in nn_descent.near_vectors(rows).collect()}


def test_nn_descent_links_two_dense_groups(spark):
    rng = np.random.default_rng(8)
    a, b = np.linalg.qr(rng.normal(size=(64, 2)))[0].T
    x = np.concatenate((around(rng, a, 40, 0.005), around(rng, 0.94 * a + math.sqrt(1 - 0.94**2) * b, 40, 0.005), around(rng, -a, 5, 0.005)))
    got = near_rows(spark, x)
    assert brute(x)[0] == 79 and [got[i]["n_links"] for i in range(len(x))] == brute(x).tolist()
    assert {got[i]["component_id"] for i in range(80)} == {0} and {got[i]["component_id"] for i in range(80, 85)} == {80}


def test_cross_links_in_small_blocks_equal_brute_force(spark):
    rng = np.random.default_rng(9)
    centres = around(rng, np.ones(16), 12, 0.5)
    x = np.concatenate([around(rng, c, 20, 0.05) for c in centres])
    component, weight = np.arange(len(x)) // 10, np.arange(len(x)) % 3 + 1
    rows = spark.createDataFrame([(i, int(c), int(w), v.tobytes()) for i, (c, w, v) in enumerate(zip(component, weight, x, strict=True))], "node long, component long, weight long, unit binary")
    linked = (x @ x.T >= 0.9) & (component[:, None] != component)
    degrees, joins = nn_descent.cross_links(rows, 0.9, rows=32)
    want = {i: (int(d), int(o)) for i, (d, o) in enumerate(zip(linked @ weight, linked.sum(1), strict=True)) if o}
    assert {r["node"]: (r["degree"], r["others"]) for r in degrees.collect()} == want
    pairs = {(int(component[i]), int(component[j])) for i, j in zip(*np.nonzero(linked), strict=True)}
    got = {(r["src"], r["dst"]) for r in joins.collect()}
    whole = spark.createDataFrame(sorted(pairs), "src long, dst long")
    assert got <= pairs and sorted(connected_components(joins).collect()) == sorted(connected_components(whole).collect())


def test_comparing_blocks_shuffles_no_pairs_of_them(spark, monkeypatch):
    rng = np.random.default_rng(14)
    x = around(rng, np.zeros(64), 1500, 1.0)
    x[1::5] = around(rng, np.zeros(64), 300, 1.0) * 0.3 + x[::5]
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    rows = spark.createDataFrame([(i, i, 1, v.tobytes()) for i, v in enumerate(x)], "node long, component long, weight long, unit binary")
    folders = [d.getPath() for d in spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().localDirs()]
    written = lambda: sum(f.stat().st_size for d in folders for f in Path(d).rglob("shuffle_*"))
    monkeypatch.setattr(nn_descent, "HELD_BYTES", 300_000, raising=False)
    before = written()
    degrees, _ = nn_descent.cross_links(rows, 0.9, rows=32)
    assert {r["node"]: r["others"] for r in degrees.collect()} == {i: n for i, n in enumerate(brute(x).tolist()) if n}
    assert written() - before < 4 * x.nbytes


def test_vectors_of_floats_are_kept_as_floats_and_decided_in_doubles(spark):
    rng = np.random.default_rng(15)
    x = around(rng, np.zeros(32), 300, 1.0).astype(np.float32)
    x[100:200] = 7 * (x[:100] + rng.normal(scale=0.06, size=(100, 32)))
    x[200:] = 4 * x[:100]
    rows = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<float>")
    assert nn_descent.stored_form(rows) == "<f4" and {len(r["unit"]) for r in nn_descent.classes_of(rows, "<f4").collect()} == {128}
    unit = x.astype(float) / np.linalg.norm(x.astype(float), axis=1, keepdims=True)
    got = {r["vec_id"]: r["n_links"] for r in nn_descent.near_vectors(rows).collect()}
    assert [got[i] for i in range(300)] == brute(unit).tolist()


def test_cells_part_vectors_with_a_common_direction(spark):
    rng = np.random.default_rng(10)
    x = around(rng, np.full(64, 0.5), 6000, 0.2)
    nodes = spark.createDataFrame([(i, nn_descent.code(v)) for i, v in enumerate(x)], "node long, code binary")
    rows = nn_descent.cells(nodes, len(x), 0, nn_descent.cell_sample(nodes, len(x))).groupBy("cell").count().collect()
    assert sum(r["count"] for r in rows) == len(x) and max(r["count"] for r in rows) <= 4 * nn_descent.CELL


def test_audit_counts_vectors_alike_and_grows(spark):
    truth = {0: 5000} | {i: 1 for i in range(1, 50)}
    assert nn_descent.audited_recall(truth, {0: 5000}) == 0.0 and nn_descent.audited_recall(truth, truth) == 1.0 and nn_descent.audited_recall({}, {}) is None
    rng = np.random.default_rng(11)
    x = around(rng, np.zeros(64), 1000, 1.0)
    x[1::25] = around(rng, np.zeros(64), 40, 1.0) * 0.2 + x[::25]
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    nodes = spark.createDataFrame([(i, v.tobytes()) for i, v in enumerate(x)], "node long, unit binary")
    assert nn_descent.audited_links(nodes, len(x), 0.9) == {i: n for i, n in enumerate(brute(x).tolist()) if n}


def test_audit_recall_is_unknown_without_links(spark):
    assert {r["audit_recall"] for r in near_rows(spark, np.eye(8)).values()} == {None}


def test_nn_descent_finds_isolated_pairs_in_many_cells(spark, monkeypatch):
    monkeypatch.setattr(nn_descent, "CELL", 4)
    monkeypatch.setattr(nn_descent, "CROSS_ROWS", 300)
    rng = np.random.default_rng(12)
    x = around(rng, np.zeros(64), 2000, 1.0)
    side = around(rng, np.zeros(64), 400, 1.0)
    side -= (side * x[:400]).sum(1, keepdims=True) * x[:400]
    side /= np.linalg.norm(side, axis=1, keepdims=True)
    cos = rng.uniform(0.9001, 0.93, size=(400, 1))
    x[400:800] = cos * x[:400] + np.sqrt(1 - cos**2) * side
    got = near_rows(spark, x)
    assert [got[i]["n_links"] for i in range(len(x))] == brute(x).tolist() and got[0]["audit_recall"] == 1.0
    assert all(got[400 + i]["component_id"] == i for i in range(400))


def test_added_tokens_get_their_own_id():
    import public_tokenizers
    from tokenizers import Tokenizer

    plain, encode = Tokenizer.from_file(public_tokenizers.path(packing.TOKENIZER)), packing.encoder()
    texts = ["a <|endoftext|> b", "<|endoftext|>", "x  <|endoftext|>\n\n<|endoftext|>y <|endoftext|", "İ<|endoftext|>東京 <|ENDOFTEXT|>"]
    want = [plain.encode(t, add_special_tokens=False).ids for t in texts]
    assert encode._ranks is not None and [np.frombuffer(e, dtype="<u4").tolist() for e in encode.encode(texts)] == want and want[0] == [64, 220, 50256, 275]
    tree = edit_counts.TokenTree("w <|endoftext b c", edit_counts.ChunkCounter(encode))
    tree.edit(13, 0, "|>")
    assert tree.text() == "w <|endoftext|> b c" and tree.n_tokens == len(plain.encode(tree.text(), add_special_tokens=False).ids)


def test_edits_of_texts_with_odd_spaces_encode_little():
    import random

    rng = random.Random(7)
    encode = packing.encoder()
    count = edit_counts.ChunkCounter(encode)
    pieces = ["word", " ", "\n", "é", ".", "it's", "  ", "\u00a0", "\u3000", "\x1c", "\x0b", "\x85", "\u2003 ", "x", "12", "\t"]
    for _ in range(60):
        text = "".join(rng.choice(pieces) for _ in range(rng.randrange(120)))
        tree = edit_counts.TokenTree(text, count)
        for _ in range(12):
            at, cut, put = rng.randrange(len(text) + 3), rng.randrange(9), rng.choice(["", " ", "a", "\n\n", "new one ", "'ll", "\u00a0", "\u3000 ", "b\u00a0", "lots of words " * 40])
            tree.edit(at, cut, put)
            a = min(at, len(text))
            text = text[:a] + put + text[a + cut :]
            assert tree.text() == text and tree.n_tokens == len(encode._slow(text)) // 4
    tree = edit_counts.TokenTree("some words\u00a0here and there " * 2000, count)
    tree.edit(30_000, 3, "\u00a0new ")
    assert tree.encoded < 200
    tree.edit(100, 0, "and more " * 5000)
    assert max(map(len, tree.blocks)) <= edit_counts.MOST_BLOCK


def test_shared_passage_of_many_items_and_documents(spark):
    passage = " ".join(f"p{i}" for i in range(20))
    items = spark.createDataFrame([(i, f"{passage} own{i} " + " ".join(f"i{i}x{k}" for k in range(15))) for i in range(50)] + [(90, "p3 p4 p5")], "item_id long, text string")
    docs = spark.createDataFrame([(i, f"a b c {passage} d e" if i % 2 else f"clean words {i} p3 p4 P5") for i in range(40)], "doc_id long, text string")
    for rows in (0, 10_000):
        for r in decontam.hits(docs, items, broadcast_rows=rows).collect():
            assert (r["n_hit"], r["item_ids"]) == ((20, [*range(50), 90]) if r["doc_id"] % 2 else (3, [90])) and r["contaminated"]


def test_toxicity_scores_against_brute_force(spark, tables, corpus):
    docs, labels = spark.read.parquet(f"{tables}/documents.parquet"), spark.read.parquet(f"{tables}/labels.parquet")
    model = toxicity.fit(docs, labels)
    import pyarrow as pa

    def buckets(word):
        raw = b" " + word.encode() + b" "
        return [int(tg.SpanHasher(np.frombuffer(raw[i : i + n], dtype=np.uint8)).spans(np.array([0]), np.array([n]))[0] >> np.uint64(64 - toxicity.BUCKET_BITS)) for n in toxicity.GRAM_SIZES for i in range(len(raw) - n + 1)]

    from ratiobin.llm import textgrid as tg

    want = []
    for i, t in corpus[0]:
        w = [x for k, x in enumerate(alnum_words(t)) if not k or x != alnum_words(t)[k - 1]] if i != 406 else ["x"]
        step = toxicity.WINDOW_WORDS // 2
        logits = []
        for a in range(0, max(len(w) - step, 1) if len(w) > toxicity.WINDOW_WORDS else 1, step):
            grams = [g for x in w[a : a + toxicity.WINDOW_WORDS] for g in buckets(x)]
            logits.append(sum(float(model.weights[g]) for g in grams) / max(len(grams), 1) + model.bias)
        want.append(1 / (1 + math.exp(-max(logits))) if w else model.empty_score)
    assert toxicity.doc_scores(pa.array([t for _, t in corpus[0]]), model).tolist() == pytest.approx(want, abs=1e-6)
    rows = toxicity.op3_toxicity(spark, tables).collect()
    held = {i: (None if i is None else zlib.crc32(str(i).encode()) % 3 == 1) for i, _ in corpus[0]}
    assert all(r["held_out"] == held[r["doc_id"]] and r["predicted"] == int(r["score"] >= 0.7) for r in rows)
    by_id = {}
    for (i, _), s in zip(corpus[0], want, strict=True):
        by_id.setdefault(i, []).append(s)
    assert all(any(r["score"] == pytest.approx(s, abs=1e-6) for s in by_id[r["doc_id"]]) for r in rows)


def test_importance_weights_against_brute_force(spark, tables, corpus):
    from ratiobin.llm import textgrid as tg

    good = {r["doc_id"] for r in spark.read.parquet(f"{tables}/labels.parquet").where("quality = 1 AND doc_id IS NOT NULL").collect()}
    size = 1 << resampling.BUCKET_BITS

    def grams(text):
        h = [tg.SpanHasher(np.frombuffer(w.encode(), dtype=np.uint8)).spans(np.array([0]), np.array([len(w.encode())])) for w in alnum_words(text)]
        return [int(x[0]) >> (64 - resampling.BUCKET_BITS) for x in [tg.mix64(a) for a in h] + [tg.pair_hash(a, b) for a, b in zip(h, h[1:], strict=False)]]

    docs = [(i, grams(t) if i != 406 else grams("x x")[:1] * 30_000 + grams("x x")[2:] * 29_999) for i, t in corpus[0]]
    raw, target = np.zeros(size), np.zeros(size)
    for i, g in docs:
        np.add.at(raw, g, 1)
        if i in good:
            np.add.at(target, g, 1)
    ratio = np.log((target + 1) / (target.sum() + size)) - np.log((raw + 1) / (raw.sum() + size))
    want = sorted((i is not None, i or 0, round(float(ratio[g].sum()) if g else 0.0, 6)) for i, g in docs)
    rows = resampling.op6_resampling(spark, tables).collect()
    got = sorted((r["doc_id"] is not None, r["doc_id"] or 0, round(r["log_weight"], 6)) for r in rows)
    assert [x[:2] for x in got] == [x[:2] for x in want] and [x[2] for x in got] == pytest.approx([x[2] for x in want], abs=1e-4)


def test_best_fit_plan_equals_best_fit_of_single_pieces():
    rng = np.random.default_rng(5)
    for _ in range(40):
        lengths = sorted(rng.integers(1, 65, rng.integers(1, 80)).tolist(), reverse=True)
        free: list[int] = []
        for n in lengths:
            fits = [(f, i) for i, f in enumerate(free) if f >= n]
            if fits:
                free[min(fits)[1]] -= n
            else:
                free.append(64 - n)
        histogram = {n: lengths.count(n) for n in set(lengths)}
        assert packing.best_fit_plan(histogram, 64)[1] == len(free)


def test_near_copies_of_a_hub_and_of_one_tight_group(spark, monkeypatch):
    monkeypatch.setattr(nn_descent, "MEMBERS", 32)
    rng = np.random.default_rng(13)
    a = around(rng, np.zeros(32), 1, 1.0)[0]
    x = np.concatenate((around(rng, a, 150, 0.002), around(rng, a, 100, 0.08), around(rng, np.zeros(32), 50, 1.0)))
    got = near_rows(spark, x)
    assert [got[i]["n_links"] for i in range(len(x))] == brute(x).tolist()
    star = spark.createDataFrame([(5000, i) for i in range(2000)] + [(1, 9000 + i) for i in range(2000)], "src long, dst long")
    assert {r["component"] for r in connected_components(star).collect()} == {0}
    assert sorted(connected_components(star, 0).collect()) == sorted(connected_components(star).collect())


def test_clashing_column_names_of_vectors_and_captures(spark):
    rows = spark.createDataFrame([(i, [1.0, float(i % 2)], 7, b"x", 3, 4) for i in range(6)], "vec_id long, embedding array<double>, node int, unit binary, code int, component int")
    assert {r["n_links"] for r in nn_descent.near_vectors(rows).collect()} == {2}


def test_texts_of_several_megabytes(spark, tmp_path_factory):
    path = tmp_path_factory.mktemp("long")
    long = " ".join(f"word{i % 5000} and {i}" for i in range(180_000)) + " token = hunter2hunter"
    spark.createDataFrame([(1, long, "en", "s", len(long)), (2, "short text", "en", "s", 10), (2, "other text of that id", "en", "s", 21)], "doc_id long, text string, lang string, source string, n_chars long").coalesce(1).write.parquet(f"{path}/documents.parquet")
    spark.createDataFrame([(1, " ".join(long.split()[1000:1020]))], "item_id long, text string").write.parquet(f"{path}/benchmark.parquet")
    spark.createDataFrame([(1, 1, 0), (2, 1, 1)], "doc_id long, quality int, toxic int").write.parquet(f"{path}/labels.parquet")
    n = len(long.split())
    found = {name: sorted(entry.QUERIES[name](spark, str(path)).collect()) for name in ("op2_backoff_lm", "op3_toxicity", "op5_edit_counts", "op6_resampling", "op7_secrets", "op8_simhash", "op9_winnowing", "op10_packing")}
    assert all(len(v) == 3 for k, v in found.items() if k != "op10_packing")
    assert found["op2_backoff_lm"][0]["n_tokens"] == n + 1 and found["op7_secrets"][0]["n_assign"] == 1
    assert (found["op9_winnowing"][0]["n_words"], found["op9_winnowing"][0]["n_hit"] >= 20) == (len(alnum_words(long)), True)
    assert sum(r["length"] for r in found["op10_packing"] if r["doc_id"] == 1) == found["op5_edit_counts"][0]["n_tokens_before"] + 1
