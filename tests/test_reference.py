"""Queries that SQL can't express against a plain NumPy version of the codec, on the smallest tables."""

import zlib

import duckdb
import numpy as np
import pytest

import __spark_entry__ as entry
from ratiobin.operators import baselines
from ratiobin.operators.binning import lloyd
from ratiobin.sources.series import ELEM_BYTES, SERIES_SQL

SF = "/root/testdata/sf0.001"
E = 0.001
SIX = ("embedding_field", "customer_balance", "part_volume", "user_activity", "price_states", "drift_field")


@pytest.fixture(scope="module")
def values():
    """{series: {step: {pos: value}}} as DuckDB derives them."""
    con, out = duckdb.connect(), {}
    for table in ("lineitem", "orders", "customer", "part", "events", "embeddings"):
        con.execute(f"CREATE VIEW {table} AS SELECT * FROM '{SF}/{table}.parquet'")
    for name in (*SIX, "supplier_month"):
        steps = out.setdefault(name, {})
        for step, pos, value in con.sql(f"SELECT step, pos, value FROM ({SERIES_SQL[name]})").fetchall():
            steps.setdefault(step, {})[pos] = value
    return out


@pytest.fixture(scope="module")
def run(spark):
    held = {}

    def rows(name):
        if name not in held:
            held[name] = entry.queries()[name](spark, SF).collect()
        return held[name]

    return rows


def ratios(prev, cur):
    """Positions, and ratios with NaN where they are undefined."""
    pos = np.array(sorted(cur))
    a, b = np.array([prev.get(p, np.nan) for p in pos.tolist()], dtype=float), np.array([cur[p] for p in pos.tolist()], dtype=float)
    with np.errstate(all="ignore"):
        r = np.where(np.isfinite(a) & np.isfinite(b) & (a != 0), (b - a) / a, np.nan)
    return pos, np.where(np.isfinite(r), r, np.nan)


def pack(idx, bits):
    text = "".join(format(i, f"0{bits}b") for i in idx)
    return int(text + "0" * (-len(text) % 8), 2).to_bytes(-(-len(text) // 8), "big")


class Step:
    """One step of the reference codec."""

    def __init__(self, prev, cur, size):
        self.pos, self.r = ratios(prev, cur)
        self.n, self.size = len(self.pos), size
        good = ~np.isnan(self.r)
        self.lo = self.r[good].min() if good.any() else 0.0
        self.bin = np.where(good, np.floor((np.where(good, self.r, 0.0) - self.lo) / (2 * E)), -1).astype(np.int64)
        found, count = np.unique(self.bin[good], return_counts=True)
        order = np.lexsort((found, -count))
        self.bins, self.count = found[order], count[order]

    def estimate(self, bits):
        return 2.0**bits * self.size + self.n * bits / 8 + (self.n - int(self.count[: (1 << bits) - 1].sum())) * self.size

    def auto(self):
        return min(range(1, 17), key=lambda b: (self.estimate(b), b))

    def sizes(self, bits, block_bytes=1 << 20):
        none = (1 << bits) - 1
        rank = {b: i for i, b in enumerate(self.bins[:none].tolist())}
        centre = self.lo + (self.bin + 0.5) * (2 * E)
        if self.size == 4:
            centre = centre.astype(np.float32).astype(np.float64)
        full = np.full(int(self.pos[-1]) + 1, none)
        for p, b, r, c in zip(self.pos.tolist(), self.bin.tolist(), self.r.tolist(), centre.tolist(), strict=True):
            if b in rank and (self.size == 8 or abs(r - c) <= E):
                full[p] = rank[b]
        width = block_bytes * 8 // bits
        raw = [pack(full[a : a + width].tolist(), bits) for a in range(0, len(full), width)]
        index = sum(len(zlib.compress(x, 6)) for x in raw)
        out = {"bits": bits, "n": self.n, "n_exact": int((full == none).sum()), "index_bytes": index, "raw_index_bytes": sum(map(len, raw)), "centre_bytes": min(none, len(self.bins)) * self.size}
        out["stored_bytes"] = out["centre_bytes"] + index + out["n_exact"] * self.size + 12 * len(raw)
        return out | {"cr": self.n * self.size / out["stored_bytes"], "zlib_ratio": out["raw_index_bytes"] / index, "blocks": len(raw)}


@pytest.fixture(scope="module")
def steps(values):
    return {name: {s: Step(all_[s - 1], all_[s], ELEM_BYTES[name]) for s in sorted(all_) if s > min(all_) and s - 1 in all_} for name, all_ in values.items()}


def near(a, b):
    assert a == pytest.approx(b, rel=1e-5, abs=1e-6)


def test_ratio_of_every_step_and_series(run, steps):
    got = {(r["var"], r["step"]): r for r in run("w_cr_by_step")}
    assert set(got) == {(n, s) for n in SIX for s in steps[n]}
    for (name, s), r in got.items():
        want = steps[name][s].sizes(steps[name][s].auto())
        assert (r["n"], r["bits"]) == (want["n"], want["bits"]), (name, s)
        near((r["cr"], r["zlib_ratio"]), (want["cr"], want["zlib_ratio"]))


@pytest.mark.parametrize("name", ["c_compression_ratio", "c_zlib_ratio", "c_space_breakdown", "w_predicted_cr"])
def test_sizes(run, steps, name):
    for r in run(name):
        step = steps[r["var"]][r["step"]]
        want = step.sizes(step.auto())
        want |= {"exact_bytes": want["n_exact"] * step.size, "offset_bytes": 12 * want["blocks"], "index_share": want["index_bytes"] / want["stored_bytes"]}
        want["predicted"] = 64 / (want["bits"] / want["zlib_ratio"] + want["n_exact"] / want["n"] * 64)
        for column in set(r.asDict()) - {"var", "step"}:
            near(r[column], want[column])


def test_fixed_lengths_and_every_fifth_step(run, steps, values):
    for r in run("w_cr_fixed_bits"):
        step = steps["customer_balance"][r["step"]]
        near(r["cr"], step.sizes(4 if r["run"] == "fixed" else step.auto())["cr"])
    kept = values["customer_balance"]
    rows = {r["step"]: r for r in run("w_every_fifth_cr")}
    assert set(rows) == {s for s in range(1, max(kept) // 5 + 1)}
    for s, r in rows.items():
        step = Step(kept[5 * s - 5], kept[5 * s], 8)
        assert r["bits"] == step.auto()
        near(r["cr"], step.sizes(r["bits"])["cr"])


def test_sweep_over_lengths(run, steps):
    zlib_sums, cr_sums = {}, {}
    for r in run("w_bits_sweep_actual"):
        want = steps[r["var"]][r["step"]]
        if ELEM_BYTES[r["var"]] == 8:  # the sweep doesn't round centres to floats
            sizes = want.sizes(r["bits"])
            assert r["stored_bytes"] == sizes["stored_bytes"]
            near((r["cr"], r["est_bytes"]), (sizes["cr"], want.estimate(r["bits"])))
            zlib_sums.setdefault((r["var"], r["bits"]), []).append(sizes["zlib_ratio"])
            cr_sums.setdefault((r["var"], r["bits"]), []).append(sizes["cr"])
    table = {r["var"]: r for r in run("w_zlib_by_bits")}
    assert set(table) == {"part_volume", "embedding_field", "customer_balance", "user_activity"}
    for (name, bits), ratios_ in zlib_sums.items():
        near(table[name][str(bits)], np.mean(ratios_))
    means = {(r["var"], r["bits"]): r["mean_cr"] for r in run("w_cr_by_bits")}
    for key, crs in cr_sums.items():
        near(means[key], np.mean(crs))
    for r in run("w_bits_regret"):
        step = steps[r["var"]][r["step"]]
        assert r["auto_bits"] == step.auto() and r["regret"] >= 1
        if r["var"] == "customer_balance" and r["step"] % 20 == 0:
            stored = {b: step.sizes(b)["stored_bytes"] for b in range(1, 17)}
            near(r["regret"], stored[r["auto_bits"]] / min(stored.values()))
    for r in run("m_choose_bits_measured"):
        if r["step"] % 9 == 0:
            step = steps["part_volume"][r["step"]]
            assert r["bits"] == min(range(1, 17), key=lambda b: (step.sizes(b)["stored_bytes"], b))


def test_blocks_groups_and_pooled_centres(run, steps):
    per = {}
    for r in run("m_blocks"):
        per.setdefault(r["step"], []).append(r)
    for s, blocks in per.items():
        step = steps["part_volume"][s]
        want = step.sizes(step.auto(), 256)
        assert (len(blocks), sum(b["stored"] for b in blocks), sum(b["n_exact"] for b in blocks)) == (want["blocks"], want["index_bytes"], want["n_exact"])
    for r in run("w_cr_group_bits"):
        step = steps["customer_balance"][r["step"]]  # 150 positions are one group here
        assert (r["groups"], r["least_bits"], r["most_bits"]) == (1, step.auto(), step.auto())
        near(r["cr"], step.sizes(step.auto())["cr"])
    pooled = run("m_pooled_centres")
    assert len({r["bits"] for r in pooled}) == 1 and [r["step"] for r in pooled if r["n_centres"]] == [min(r["step"] for r in pooled)]
    bits = {r["step"]: r["bits"] for r in run("c_zlib_ratio")}
    assert all(r["bits"] == bits[r["step"]] and (r["first_centre"] is None) == (r["n_centres"] < 1) for r in run("m_centre_map"))
    assert all(r["max_value_error"] <= E * (1 + 1e-6) for r in run("m_value_bound") if r["bound"] == "value" and r["max_value_error"] is not None)


def test_lossless_sizes(run, values):
    chunk = lambda cells: np.array([cells[p] for p in sorted(cells)], dtype="<f8").tobytes()
    for r in run("b_lossless"):
        raw = chunk(values["part_volume"][r["step"]])
        assert (r["raw_bytes"], r["stored_bytes"]) == (len(raw), len(zlib.compress(raw, 6)))
    rows = run("m_anchors")
    assert {r["step"] for r in rows} == set(range(0, max(values["customer_balance"]) + 1, 20))
    assert all(r["stored_bytes"] == len(zlib.compress(chunk(values["customer_balance"][r["step"]]), 6)) for r in rows)


def coded(cells, size, coder):
    x = np.array([cells[p] for p in sorted(cells)], dtype=float)
    if coder == "sorted_fit":
        return x, *baselines.sorted_fit_encode(x, E, elem_bytes=size)
    return x, *baselines.predictive_encode(x, abs(x.mean()) * E, size)


def test_comparison_coders(run, steps, values):
    for name, coder in (("b_sorted_fit", "sorted_fit"), ("b_predictive", "predictive")):
        for r in run(name):
            x, size, hat = coded(values["part_volume"][r["step"]], 8, coder)
            assert (r["n"], r["stored_bytes"]) == (len(x), size)
            near(r["mean_error"], np.mean(np.abs(x - hat)[x != 0] / np.abs(x[x != 0])))
    got = {(r["var"], r["coder"]): r for r in run("w_cr_compare")}
    assert len(got) == 18
    for (name, coder), r in got.items():
        size = ELEM_BYTES[name]
        if coder == "ratio_bin":
            crs = [s.sizes(s.auto())["cr"] for _, s in sorted(steps[name].items())]
        else:
            crs = [len(c) * size / coded(c, size, coder)[1] for s, c in sorted(values[name].items()) if s > 0]
        assert r["steps"] == len(crs)
        near((r["mean_cr"], r["last_cr"]), (np.mean(crs), crs[-1]))


def test_strategies(run, steps):
    stored = {(r["strategy"], r["step"]): r for r in run("b_strategies_fixed")}
    for s, step in steps["part_volume"].items():
        assert len({stored[x, s]["n"] for x in ("topk", "equal", "log", "kmeans", "optimal")}) == 1
        near(stored["topk", s]["cr"], step.sizes(6)["cr"])
        assert stored["optimal", s]["n_exact_stored"] <= min(stored[x, s]["n_exact_stored"] for x in ("topk", "equal", "log", "kmeans")) + 1
    centres = {}
    for r in run("m_kmeans"):
        centres.setdefault(r["step"], []).append(r["centre"])
    for s, step in steps["supplier_month"].items():
        x = np.sort(step.r[~np.isnan(step.r)])
        if len(x):
            cell = np.floor(x / (2 * E / 16))
            found, weight = np.unique(cell, return_counts=True)
            means = np.array([x[cell == c].mean() for c in found])
            near(sorted(centres[s]), lloyd(means, weight.astype(float), 15, 20).tolist())
    assert len(run("m_kmeans_ml")) == 7
    for r in run("m_log_scale_centres"):
        assert np.isfinite(r["centre"])


@pytest.mark.parametrize("name, series", [("w_coverage_customer_balance", "customer_balance"), ("w_coverage_part_volume", "part_volume"), ("w_coverage_embedding", "embedding_field"), ("w_coverage_supplier_month", None)])
def test_coverage(run, steps, name, series):
    rows = {}
    for r in run(name):
        rows.setdefault((r["step"], r["bits"]), {})[r["strategy"]] = r
    for (s, bits), by in rows.items():
        assert len(by) == 5 and len({r["n"] for r in by.values()}) == 1
        best = by["optimal"]["covered"]
        assert all(r["covered"] <= best + 1e-9 * r["n"] + (x != "topk") for x, r in by.items()) and 2 * by["topk"]["covered"] >= best
        if series:
            r = steps[series][s].r
            r = r[np.abs(r) > E]  # NaN is left out as well
            assert by["topk"]["n"] == len(r)
            cell, count = np.unique(np.floor((r - r.min()) / (2 * E)), return_counts=True)
            assert by["topk"]["covered"] == np.sort(count)[::-1][: (1 << bits) - 1].sum()
            k = (1 << bits) - 1
            width = (r.max() - r.min()) / k
            slot = np.minimum(np.floor((r - r.min()) / width), k - 1) if width else np.zeros(len(r))
            assert abs(by["equal"]["covered"] - (np.abs(r - (r.min() + (slot + 0.5) * width)) <= E).sum()) <= 1


def test_partial_decoding_and_closed_loop(run, values):
    for r in run("w_partial_decode"):
        n = len(values[r["var"]][r["step"]])
        assert r["points"] == max(1, n * r["share"] // 100) and (r["var"] != "customer_balance" or r["blocks"] == 1)
    hat = {(r["step"], r["pos"]): r["value_hat"] for r in run("m_decode_closed_loop")}
    for s, cells in values["drift_field"].items():
        for p, v in cells.items():
            assert hat[s, p] == v if s == 0 else abs(hat[s, p] - v) <= E * abs(hat[s - 1, p]) * (1 + 1e-6)


def test_sketches_and_samples(run, steps):
    top = {}
    for r in run("o_approx_top_k"):
        top.setdefault(r["step"], []).append(r["cnt"])
    assert all(max(top[s]) >= step.count[0] for s, step in steps["part_volume"].items() if len(step.count))
    for r in run("o_sketches"):
        step = steps["embedding_field"][r["step"]]
        assert r["occupied"] == pytest.approx(len(step.bins), rel=0.05) and abs((step.r[~np.isnan(step.r)] <= r["median"]).mean() - 0.5) < 0.03
    for r in run("m_choose_bits_sampled"):
        assert r["bits_all"] == steps["drift_field"][r["step"]].auto() and 0 < r["n_sample"] < steps["drift_field"][r["step"]].n
    frozen = {r["step"]: r for r in run("s_frozen_centres")}
    assert set(frozen) == {0, 1, 2, 3} and frozen[0]["n_exact"] == frozen[0]["n"] and frozen[1]["n_exact"] <= 0.05 * frozen[1]["n"]
