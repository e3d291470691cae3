"""Revisit resolution against a direct reading of its rules."""

import random

import pytest

from ratiobin.llm import revisits
from pyspark.sql import functions as F

SCHEMA = "capture_id long, url string, ts long, status int, etag string, last_modified string, headers map<string,string>, digest string"


@pytest.fixture(scope="module")
def captures():
    rng = random.Random(1)
    rows = []
    for i in range(400):
        url = "http://hot.example.org/a" if i % 3 else f"https://www.Site{rng.randrange(20)}.example.org:443/p/?b=1&utm_source=x#top"
        status = rng.choice([200, 304, 304, 404])
        headers = {"etag": f"e{rng.randrange(3)}", "content-type": f"t{i}", "date": f"d{i}"}
        rows.append((i, url, rng.randrange(150), status, rng.choice([None, "a", "W/a", "b"]), rng.choice([None, "m", "n"]), headers if rng.random() < 0.9 else None, f"sha{i}" if status == 200 else None))
    return rows + [(1000, None, 5, 304, None, None, None, None), (1001, "http://none.example.org/", 5, 304, None, None, {}, None), (1002, "http://hot.example.org/a", None, 304, "a", None, {}, None), (7, "http://hot.example.org/a", 149, 304, "a", None, {}, None)]


def test_resolution(spark, captures):
    found = sorted((r["capture_id"], r["state"], r["response_id"], r["digest"], tuple(sorted((r["headers"] or {}).items()))) for r in revisits.resolve(spark.createDataFrame(captures, SCHEMA).repartition(7)).collect())
    canon = {r["url"]: r["c"] for r in spark.createDataFrame([(u,) for u in {c[1] for c in captures}], "url string").select("url", revisits.canonical_url(F.col("url")).alias("c")).collect()}
    want = []
    for c in captures:
        if c[3] != 304:
            continue
        if canon[c[1]] is None or c[2] is None:
            want.append((c[0], "no_url", None, None, ()))
            continue
        full = [x for x in captures if x[3] == 200 and canon[x[1]] == canon[c[1]] and x[2] is not None and x[2] < c[2]]
        if not full:
            want.append((c[0], "orphan", None, None, ()))
            continue
        best = max(full, key=lambda x: (x[2], x[0]))
        strong = lambda e: e.removeprefix("W/")
        if c[4] and best[4]:
            bad = strong(c[4]) != strong(best[4])
        else:
            bad = bool(c[5] and best[5] and c[5] != best[5])
        merged = {**(best[6] or {}), **{k: v for k, v in (c[6] or {}).items() if k in revisits.PERMITTED}}
        want.append((c[0], "mismatch", best[0], None, ()) if bad else (c[0], "resolved", best[0], best[7], tuple(sorted(merged.items()))))
    assert found == sorted(want, key=lambda x: (x[0], x[1], x[2] or 0, x[3] or "", x[4]))


def test_canonical_urls(spark):
    spellings = ["http://www.A.example.org/x/?utm_source=f#t", "https://a.example.org/x", "https://a.example.org:443/x/index.html?", "http://A.EXAMPLE.org/x?ref=q&utm_medium=z"]
    rows = spark.createDataFrame([(u,) for u in spellings], "url string").select(revisits.canonical_url(F.col("url")).alias("c")).collect()
    assert {r["c"] for r in rows} == {"https://a.example.org/x"}
