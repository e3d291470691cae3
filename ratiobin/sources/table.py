"""The compressed store as a table of decoded values: spark.read.format("ratiobin").load(folder).

A partition is a run of positions of one variable.  It reads those blocks of each step that hold the run, and decodes them
step after step in one array, so nothing is shuffled and no step is read beyond the run.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import pyarrow.dataset as ds
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ratiobin.functions.bits import unpack_bits
from ratiobin.sources.ncfile import file_system

#: Positions of a partition unless the option `points` tells another number.
POINTS = 1 << 20
STEPS = pa.schema([("var", pa.string()), ("step", pa.int32())])


class _Run(InputPartition):
    def __init__(self, var: str, start: int, stop: int, steps: list[dict]):
        self.var, self.start, self.stop, self.steps = var, start, stop, steps


class _Reader(DataSourceReader):
    """Options: step (that one alone is returned), start and stop (positions), points (of a partition)."""

    def __init__(self, options: dict):
        self.folder = options["path"]
        self.step = int(options["step"]) if "step" in options else None
        self.start, self.stop = int(options.get("start", 0)), int(options.get("stop", 1 << 62))
        self.points = int(options.get("points", POINTS))

    def _table(self, name: str, by_step: bool = True) -> ds.Dataset:
        fs, folder = file_system(self.folder)
        return ds.dataset(f"{folder}/{name}", format="parquet", filesystem=fs, partitioning=ds.partitioning(STEPS, flavor="hive") if by_step else None)

    def partitions(self) -> list[InputPartition]:
        rows = self._table("header", by_step=False).to_table(columns=["var", "step", "bits", "indices_per_block", "n_blocks", "centres_step"]).to_pylist()  # one row a step
        ends = {}
        anchored = self._table("anchors").scanner(columns=["var", "pos"]).to_reader()
        for batch in anchored:
            for var in batch.column("var").unique().to_pylist():
                pos = batch.filter(pc.equal(batch.column("var"), var)).column("pos")
                ends[var] = max(ends.get(var, 0), pc.max(pos).as_py() + 1)
        out = []
        for var in ends:
            steps = sorted((r for r in rows if r["var"] == var and (self.step is None or r["step"] <= self.step)), key=lambda r: r["step"])
            last = max([ends[var], *(r["indices_per_block"] * r["n_blocks"] for r in steps)])
            for a in range(self.start, min(self.stop, last), self.points):
                out.append(_Run(var, a, min(a + self.points, self.stop, last), steps))
        return out

    def read(self, run: _Run) -> Iterator[pa.RecordBatch]:
        var, a, b = run.var, run.start, run.stop
        now, gone = np.zeros(b - a), np.ones(b - a, dtype=bool)
        kept = self._table("anchors").to_table(columns=["step", "pos", "value"], filter=(ds.field("var") == var) & (ds.field("pos") >= a) & (ds.field("pos") < b))
        told = {r["step"]: r for r in run.steps}
        blocks, centres = self._table("blocks"), self._table("centres")
        tables: dict[int, np.ndarray] = {}
        for step in sorted({*told, *pc.unique(kept.column("step")).to_pylist()}):
            if self.step is not None and step > self.step:
                break
            here = np.zeros(b - a, dtype=bool)
            mine = kept.filter(pc.equal(kept.column("step"), step))
            if mine.num_rows:
                at, value = mine.column("pos").to_numpy() - a, mine.column("value").combine_chunks()
                here[at], gone[at], now[at] = True, value.is_null().to_numpy(zero_copy_only=False), value.fill_null(0.0).to_numpy()
            if step in told:
                r = told[step]
                if r["centres_step"] not in tables:
                    rows = centres.to_table(columns=["idx", "centre"], filter=(ds.field("var") == var) & (ds.field("step") == r["centres_step"])).sort_by("idx")
                    tables = {r["centres_step"]: np.append(rows.column("centre").to_numpy().astype(np.float64), 0.0)}
                width, none = r["indices_per_block"], (1 << r["bits"]) - 1
                wanted = (ds.field("var") == var) & (ds.field("step") == step) & (ds.field("block_id") >= a // width) & (ds.field("block_id") <= (b - 1) // width)
                for row in blocks.to_table(columns=["first_pos", "n", "payload", "exact"], filter=wanted).to_batches():
                    for i in range(row.num_rows):
                        first, n = row.column(0)[i].as_py(), row.column(1)[i].as_py()
                        idx = unpack_bits(zlib.decompress(row.column(2)[i].as_buffer()), r["bits"], n)
                        exact = row.column(3)[i].values
                        is_exact = idx == none
                        rank = np.cumsum(is_exact) - 1
                        lo, hi = max(a - first, 0), min(b - first, n)
                        cut = slice(lo, hi)
                        at = slice(first + lo - a, first + hi - a)
                        table = tables[r["centres_step"]]
                        value = exact.cast(pa.float64()).fill_null(0.0).to_numpy()
                        null = exact.is_null().to_numpy(zero_copy_only=False)
                        value, null = (np.append(x, 0) for x in (value, null))
                        place = np.where(is_exact, rank, -1)[cut]
                        with np.errstate(all="ignore"):
                            now[at] = np.where(is_exact[cut], value[place], now[at] * (1 + table[np.minimum(idx[cut], len(table) - 1)]))
                        gone[at] = np.where(is_exact[cut], null[place].astype(bool), gone[at])
                        here[at] = True
            if self.step is None or step == self.step:
                at = np.flatnonzero(here & ~gone)
                yield pa.RecordBatch.from_arrays(
                    [pa.repeat(pa.scalar(var), len(at)), pa.array(np.full(len(at), step, dtype=np.int32)), pa.array(at + a), pa.array(now[at])], ["var", "step", "pos", "value_hat"]
                )


class Store(DataSource):
    @classmethod
    def name(cls) -> str:
        return "ratiobin"

    def schema(self) -> str:
        return "var string, step int, pos long, value_hat double"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(dict(self.options))


def read_decoded(spark: SparkSession, path: str, **options) -> DataFrame:
    """Decoded values of a store that write_compressed() wrote."""
    spark.dataSource.register(Store)
    return spark.read.format("ratiobin").options(**options).load(path)
