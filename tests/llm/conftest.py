import random

import pytest

WORDS = [f"w{i}" for i in range(400)]


def prose(rng: random.Random, n: int) -> str:
    return " ".join(rng.choice(WORDS) for _ in range(n)) + "."


@pytest.fixture(scope="session")
def corpus():
    """Small documents with copies, benchmark passages, insults, secrets and odd rows: (doc_id, text) and items."""
    rng = random.Random(5)
    items = [(i, prose(rng, 30)) for i in range(6)] + [(6, "tiny item of six words here"), (7, None), (8, "...")]
    docs = [(i, prose(rng, rng.randrange(20, 200))) for i in range(60)]
    docs += [(100 + i, docs[i][1]) for i in range(5)]  # exact copies
    docs += [(110 + i, docs[i][1] + " tail") for i in range(10, 14)]  # near copies
    docs += [(200 + i, prose(rng, 40) + " " + items[i][1] + " " + prose(rng, 10)) for i in range(5)]
    docs += [(210, "Some text with TINY item, of six words here - and more"), (211, " ".join(items[0][1].split()[3:20]))]
    docs += [(300, f'key password = "hunter2hunter" and token:abc then AKIA{"A1" * 9} {"0f" * 16}'), (301, "secret: token=abcdef apikey=123456"), (302, "İ PASSWD='geheim99' ſecret=abcdefgh")]
    docs += [(400, None), (401, ""), (402, " \t\n "), (403, "one"), (404, "one two"), (405, "naïve café 東京 naïve café 東京"), (406, "x " * 30_000), (None, "a row without an id"), (50, docs[50][1])]
    return docs, items


@pytest.fixture(scope="session")
def tables(spark, corpus, tmp_path_factory):
    """The corpus as tables in a folder, with columns whose names clash with the operators' own."""
    docs, items = corpus
    path = tmp_path_factory.mktemp("tables")
    rows = [(i, t, "en", "s", None if t is None else len(t), 0.5, 1, "x") for i, t in docs]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, score double, fp int, item_id string").coalesce(1).write.parquet(f"{path}/documents.parquet")
    spark.createDataFrame(items, "item_id long, text string").coalesce(1).write.parquet(f"{path}/benchmark.parquet")
    labels = [(i, i % 2, int(i % 5 == 0)) for i in range(60)] + [(3, 1, 0), (None, 1, 1), (7, None, None)]
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").coalesce(1).write.parquet(f"{path}/labels.parquet")
    return str(path)


@pytest.fixture(scope="session")
def empty_tables(spark, tables, tmp_path_factory):
    path = tmp_path_factory.mktemp("empty")
    for name in ("documents", "benchmark", "labels"):
        spark.read.parquet(f"{tables}/{name}.parquet").limit(0).coalesce(1).write.parquet(f"{path}/{name}.parquet")
    spark.createDataFrame([], "vec_id long, embedding array<float>, label int").write.parquet(f"{path}/embeddings.parquet")
    spark.createDataFrame([], "page_id long, url string, html string").write.parquet(f"{path}/pages.parquet")
    return str(path)
