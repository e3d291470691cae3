"""Coding with frozen centres."""

import numpy as np
import pytest

from ratiobin.operators import chunks
from ratiobin.session import new_path
from ratiobin.streaming.frozen import code_chunk, compress_frozen
from ratiobin.streaming.steps import run_to_end


def test_nearest_centre_within_the_bound():
    prev = np.array([1.0, 1.0, 1.0, 0.0, np.nan, 2.0])
    cur = np.array([1.01, 1.0105, 1.05, 3.0, 4.0, 2.0, 7.0])
    idx, hat = code_chunk(prev, cur, np.array([0.0, 0.01]), 0.001)
    assert idx.tolist() == [1, 1, 2, 2, 2, 0, 2] and hat.tolist() == pytest.approx([1.01, 1.01, 1.05, 3.0, 4.0, 2.0, 7.0])
    assert code_chunk(prev, cur, np.array([0.01]), 0.001)[0].tolist() == [0, 0, 1, 1, 1, 1, 1]


def test_stream_keeps_the_bound(spark):
    rng = np.random.default_rng(0)
    x, rows = rng.normal(50, 5, 500), []
    for s in range(4):
        rows += [("x", s, p, float(v)) for p, v in enumerate(x)]
        x = x * (1 + rng.choice([0.0, 0.02, 0.3], 500))
    df = spark.createDataFrame(rows, "var string, step int, pos bigint, value double")
    source = new_path(spark, "test-chunks")
    packed = chunks.to_chunks(df, 8192)
    for step in range(4):
        packed.where(f"step = {step}").coalesce(1).write.mode("append").parquet(source)
    stream = spark.readStream.schema(packed.schema).option("maxFilesPerTrigger", 1).parquet(source)
    out = {r["step"]: r for r in run_to_end(compress_frozen(stream, [0.0, 0.02]), "test-frozen", "append").collect()}
    truth = {(s, p): v for _, s, p, v in rows}
    assert sorted(out) == [0, 1, 2, 3] and len(out[0]["exact"]) == 500
    for s in (1, 2, 3):
        assert len(out[s]["exact"]) < 250
        for p, v in enumerate(out[s]["hat"]):
            assert abs(v - truth[s, p]) <= 0.001 * abs(out[s - 1]["hat"][p]) * (1 + 1e-9)
