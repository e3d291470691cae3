"""The pipeline against a brute-force version of its stages."""

import re

import corpus_pipeline
from ratiobin.llm import packing, secrets, toxicity
from ratiobin.llm.simhash import simhash


def words(text):
    return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))


def test_stage_order():
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "simhash_near_dedup", "benchmark_decontamination", "secret_scans", "best_fit_packing"]


def test_pipeline(spark, tables, corpus):
    import pyarrow as pa

    docs, items = corpus
    table = spark.read.parquet(f"{tables}/documents.parquet")
    model = toxicity.fit(table, spark.read.parquet(f"{tables}/labels.parquet"))
    scores = toxicity.doc_scores(pa.array([t for _, t in docs]), model)
    left = [d for d, s in zip(docs, scores, strict=True) if s < toxicity.THRESHOLD]
    prints = [simhash((t or "").encode()) for _, t in left]
    group = list(range(len(left)))
    for _ in left:
        before = list(group)
        for a in range(len(left)):
            for b in range(len(left)):
                if (prints[a] ^ prints[b]).bit_count() <= 3:
                    group[a] = group[b] = min(group[a], group[b])
        if group == before:
            break
    best = {}
    for (i, t), g in zip(left, group, strict=True):
        if g not in best or (i is None, i or 0) < (best[g][0] is None, best[g][0] or 0):
            best[g] = (i, t)
    windows = set()
    for _, t in items:
        w = words(t)
        n = min(13, len(w))
        windows |= {tuple(w[k : k + n]) for k in range(len(w) - n + 1)} if n else set()
    lengths = {len(w) for w in windows}
    kept = []
    for i, t in best.values():
        w, hit = words(t), set()
        for n in lengths:
            for k in range(len(w) - n + 1):
                if tuple(w[k : k + n]) in windows:
                    hit |= set(range(k, k + n))
        if not (hit and 20 * len(hit) >= len(w)):
            kept.append((i, secrets.blanked(t, "[SECRET]")))
    encode = packing.encoder()
    want = sorted((i is not None, i or 0, len(encode._slow(t or "")) // 4 + 1) for i, t in kept)
    rows = corpus_pipeline.run(spark, tables).collect()
    sums = {}
    for r in rows:
        sums[r["doc_id"]] = sums.get(r["doc_id"], 0) + r["length"]
    assert sorted((i is not None, i or 0, n) for i, n in sums.items()) == want
    for name, stage in corpus_pipeline.STAGES[:-1]:
        assert stage(spark, table, tables).columns == table.columns, name


def test_pipeline_of_empty_tables(spark, empty_tables):
    assert corpus_pipeline.run(spark, empty_tables).collect() == []


def test_of_equal_ids_with_different_texts_one_row_of_each_group_stays(spark, tmp_path_factory):
    from ratiobin.llm.simhash import one_of_each_group

    path = str(tmp_path_factory.mktemp("ids") / "documents.parquet")
    rows = [(7, "alpha beta gamma delta epsilon"), (7, "quite another text with other words"), (7, "alpha beta gamma delta epsilon"), (None, "alpha beta gamma delta epsilon"), (9, "quite another text with other words")]
    spark.createDataFrame(rows, "doc_id long, text string").coalesce(1).write.parquet(path)
    docs = spark.read.parquet(path)
    for table in (docs, docs.repartition(3), docs.distinct().unionAll(docs)):
        assert sorted(one_of_each_group(table).collect()) == [(7, rows[0][1]), (7, rows[1][1])]
