"""Array files: compressed steps as self-describing classic array files, with a data source that writes and reads them.

A file holds one step and a run of blocks of all its variables: attributes with the number of points and of indices in a
block, then for each variable the arrays bin centres, block offsets, exact-value offsets, index bytes, exact values and their
validity (so NaN and null stay apart).  Arrays of a file with several variables have the variable's name and a slash before
their own.  Steps stored without loss are files of values and validity.  Values are doubles, or floats where the payload is.
The layout is the public classic format with 64-bit offsets (signature CDF 2), written without any library.

Files are written by tasks under other names and get their own when the job commits, on any file system that Arrow knows.
"""

from __future__ import annotations

import posixpath
import struct
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceWriter, InputPartition, WriterCommitMessage

from ratiobin.session import join_spread

#: Blocks of a variable in one file, and points of a lossless step in one file.
FILE_BLOCKS = 64
FILE_POINTS = 1 << 20

# Fixed values of the public file format: tags and type codes.
NC_DIMENSION, NC_VARIABLE, NC_ATTRIBUTE = 10, 11, 12
TYPES = {"i1": 1, "S1": 2, "i4": 4, "f4": 5, "f8": 6}
CODES = {v: k for k, v in TYPES.items()}


def _padded(data: bytes) -> bytes:
    return data + b"\0" * (-len(data) % 4)


def _name(text: str) -> bytes:
    raw = text.encode()
    return struct.pack(">i", len(raw)) + _padded(raw)


def _attributes(values: dict) -> bytes:
    if not values:
        return struct.pack(">ii", 0, 0)
    out = struct.pack(">ii", NC_ATTRIBUTE, len(values))
    for name, value in values.items():
        if isinstance(value, str):
            raw = value.encode()
            out += _name(name) + struct.pack(">ii", TYPES["S1"], len(raw)) + _padded(raw)
        else:
            kind = "i4" if isinstance(value, int) and abs(value) < 1 << 31 else "f8"
            out += _name(name) + struct.pack(">ii", TYPES[kind], 1) + _padded(np.array([value], dtype=f">{kind}").tobytes())
    return out


def encode_file(arrays: dict[str, np.ndarray], attributes: dict) -> bytes:
    """One file of one-dimensional arrays, a dimension for each, with global attributes."""
    dims = b"".join(_name(f"{n}_dim") + struct.pack(">i", len(a)) for n, a in arrays.items())
    head = b"CDF\x02" + struct.pack(">i", 0) + struct.pack(">ii", NC_DIMENSION, len(arrays)) + dims + _attributes(attributes)
    kinds = {n: a.dtype.str.lstrip("<>|=") for n, a in arrays.items()}
    bodies = {n: _padded(a.astype(f">{kinds[n]}").tobytes()) for n, a in arrays.items()}

    def variables(begin: dict[str, int]) -> bytes:
        out = struct.pack(">ii", NC_VARIABLE, len(arrays))
        for i, n in enumerate(arrays):
            out += _name(n) + struct.pack(">ii", 1, i) + _attributes({}) + struct.pack(">iiq", TYPES[kinds[n]], min(len(bodies[n]), (1 << 31) - 4), begin[n])
        return out

    at = len(head) + len(variables(dict.fromkeys(arrays, 0)))
    begin = {}
    for n in arrays:
        begin[n] = at
        at += len(bodies[n])
    return head + variables(begin) + b"".join(bodies.values())


def decode_file(data: bytes) -> tuple[dict[str, np.ndarray], dict]:
    if data[:4] != b"CDF\x02":
        raise ValueError("not an array file")
    at = 8

    def ints(n: int) -> tuple[int, ...]:
        nonlocal at
        at += 4 * n
        return struct.unpack(f">{n}i", data[at - 4 * n : at])

    def name() -> str:
        nonlocal at
        (n,) = ints(1)
        text = data[at : at + n].decode()
        at += n + (-n % 4)
        return text

    def attributes() -> dict:
        nonlocal at
        _, count = ints(2)
        out = {}
        for _ in range(count):
            key = name()
            kind, n = ints(2)
            size = n * np.dtype(CODES[kind]).itemsize
            raw = data[at : at + size]
            at += size + (-size % 4)
            out[key] = raw.decode() if CODES[kind] == "S1" else np.frombuffer(raw, dtype=f">{CODES[kind]}")[0].item()
        return out

    _, n_dims = ints(2)
    dims = [(name(), ints(1)[0]) for _ in range(n_dims)]
    attrs = attributes()
    _, n_vars = ints(2)
    arrays = {}
    for _ in range(n_vars):
        key = name()
        (rank,) = ints(1)
        (dim,) = ints(rank)
        attributes()
        kind, _ = ints(2)
        (begin,) = struct.unpack(">q", data[at : at + 8])
        at += 8
        arrays[key] = np.frombuffer(data, dtype=f">{CODES[kind]}", count=dims[dim][1], offset=begin)
    return arrays, attrs


def file_system(path: str):
    """(file system, path on it) of a folder given as a path or URI."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(path)


class _Written(WriterCommitMessage):
    def __init__(self, files: list[tuple[str, str]]):
        self.files = files


class _Writer(DataSourceWriter):
    """Rows (name, body) to files; they get their names at commit, so a repeated task leaves nothing behind."""

    def __init__(self, folder: str):
        self.folder = folder

    def write(self, iterator) -> WriterCommitMessage:
        fs, folder = file_system(self.folder)
        files = []
        for row in iterator:
            part = posixpath.join(folder, f".{row['name']}.{uuid.uuid4().hex}")
            with fs.open_output_stream(part) as out:
                out.write(bytes(row["body"]))
            files.append((part, posixpath.join(folder, row["name"])))
        return _Written(files)

    def commit(self, messages) -> None:
        fs, _ = file_system(self.folder)
        for message in messages:
            for part, name in message.files if message else []:
                fs.move(part, name)

    def abort(self, messages) -> None:
        fs, _ = file_system(self.folder)
        for message in messages:
            for part, _ in message.files if message else []:
                fs.delete_file(part)


def _delta_file(frame: pa.Table) -> tuple[str, bytes]:
    rows = frame.sort_by([("var", "ascending"), ("block_id", "ascending")])
    variables = pc.unique(rows.column("var")).to_pylist()
    arrays, attributes = {}, {"step": rows.column("step")[0].as_py()}
    for v in variables:
        mine = rows.filter(pc.equal(rows.column("var"), v))
        name = f"{v}/" if len(variables) > 1 else ""
        kind = "f4" if mine.column("elem_bytes")[0].as_py() == 4 else "f8"
        exact = mine.column("exact").combine_chunks()
        values = exact.flatten()
        sizes, counts = pc.binary_length(mine.column("payload")).to_numpy(), pc.list_value_length(mine.column("exact")).to_numpy()
        centres = mine.column("centres")[0].as_py() or []
        arrays |= {
            f"{name}bin_centers": np.array(centres, dtype=kind), f"{name}block_points": mine.column("n").to_numpy().astype(np.int32), f"{name}block_ids": mine.column("block_id").to_numpy().astype(np.int32),
            f"{name}index_table_offset": (np.cumsum(sizes) - sizes).astype(np.float64), f"{name}exact_table_offset": (np.cumsum(counts) - counts).astype(np.float64),
            f"{name}index_table": np.frombuffer(b"".join(mine.column("payload").to_pylist()), dtype=np.int8), f"{name}exact_table": values.cast(pa.float64()).fill_null(0.0).to_numpy().astype(kind),
            f"{name}exact_valid": values.is_valid().to_numpy(zero_copy_only=False).astype(np.int8),
        }
        told = {"total_data_num": "n_points", "elements_per_block": "indices_per_block", "bits": "bits", "error_bound": "error_bound", "elem_bytes": "elem_bytes"}
        attributes |= {f"{name}{a}": mine.column(c)[0].as_py() for a, c in told.items()}
    attributes |= {"var": variables[0]} if len(variables) == 1 else {"variables": "\n".join(variables)}
    return f"step-{attributes['step']:06d}-part-{rows.column('part')[0].as_py():06d}.nc", encode_file(arrays, attributes)


def write_array_files(blocks: DataFrame, header: DataFrame, centres: DataFrame, path: str, anchors: DataFrame | None = None) -> DataFrame:
    """One file for each step and run of FILE_BLOCKS blocks of its variables; anchors in files of FILE_POINTS points of a variable.

    Returns (file, bytes), written already.  path is a folder that all executors reach.
    """
    lists = centres.groupBy("var", "step").agg(F.transform(F.array_sort(F.collect_list(F.struct("idx", "centre"))), lambda c: c["centre"]).alias("centres"))
    told = header.select("var", "step", F.col("n").alias("n_points"), "bits", "indices_per_block", "error_bound", "elem_bytes").join(lists, ["var", "step"], "left")
    spark = blocks.sparkSession
    fs, folder = file_system(path)
    fs.create_dir(folder, recursive=True)
    parted = blocks.select("var", "step", "block_id", "n", "payload", "exact").withColumn("part", F.floor(F.col("block_id") / FILE_BLOCKS))

    def delta(frame: pa.Table) -> pa.Table:
        name, body = _delta_file(frame)
        return pa.table({"name": [name], "body": pa.array([body], pa.binary())})

    files = join_spread(parted, told, ["var", "step"], "block_id", "inner").groupBy("step", "part").applyInArrow(delta, "name string, body binary")
    if anchors is not None:

        def whole(frame: pa.Table) -> pa.Table:
            frame = frame.sort_by("pos")
            value = frame.column("value").combine_chunks()
            var, step, part = (frame.column(c)[0].as_py() for c in ("var", "step", "part"))
            valid = value.is_valid().to_numpy(zero_copy_only=False).astype(np.int8)
            arrays = {"anchor_position": (frame.column("pos").to_numpy() - part * FILE_POINTS).astype(np.int32), "anchor_value": value.fill_null(0.0).to_numpy(), "anchor_valid": valid}
            body = encode_file(arrays, {"var": var, "step": step, "first_pos": float(part * FILE_POINTS)})
            tag = "".join(c if c.isalnum() else f"%{ord(c):x}" for c in var)
            return pa.table({"name": [f"step-{step:06d}-anchor-{tag}-{part:06d}.nc"], "body": pa.array([body], pa.binary())})

        stored = anchors.select("var", "step", "pos", "value").withColumn("part", F.floor(F.col("pos") / FILE_POINTS))
        files = files.unionByName(stored.groupBy("var", "step", "part").applyInArrow(whole, "name string, body binary"))
    spark.dataSource.register(ArrayFiles)
    files.write.format("ratiobin_nc").mode("append").save(path)
    return spark.createDataFrame([(f.path, f.size) for f in _listed(path)], "file string, bytes long")


def _listed(path: str) -> list:
    from pyarrow import fs as arrow_fs

    fs, folder = file_system(path)
    return sorted((f for f in fs.get_file_info(arrow_fs.FileSelector(folder)) if f.base_name.endswith(".nc") and not f.base_name.startswith(".")), key=lambda f: f.path)


class _File(InputPartition):
    def __init__(self, path: str):
        self.path = path


class _Reader(DataSourceReader):
    """One partition a file; the options first_step, last_step, first_block and last_block leave out files by their names."""

    def __init__(self, options: dict):
        self.folder = options["path"]
        self.steps = int(options.get("first_step", -1)), int(options.get("last_step", 1 << 62))
        self.blocks = int(options.get("first_block", 0)), int(options.get("last_block", 1 << 62))
        self.anchors = str(options.get("anchors", "false")).lower() == "true"

    def partitions(self) -> list[InputPartition]:
        out = []
        for f in _listed(self.folder):
            words = f.base_name.removesuffix(".nc").split("-")
            step, part = int(words[1]), int(words[-1])
            if self.steps[0] <= step <= self.steps[1] and (words[2] == "anchor") == self.anchors:
                if self.anchors or (part + 1) * FILE_BLOCKS > self.blocks[0] and part * FILE_BLOCKS <= self.blocks[1]:
                    out.append(_File(f.path))
        return out

    def read(self, partition: _File) -> Iterator[tuple]:
        fs, _ = file_system(self.folder)
        with fs.open_input_stream(partition.path) as f:
            arrays, attrs = decode_file(f.read())
        if self.anchors:
            for at, value, valid in zip(arrays["anchor_position"].tolist(), arrays["anchor_value"].tolist(), arrays["anchor_valid"].tolist(), strict=True):
                yield (attrs["var"], attrs["step"], None, int(attrs["first_pos"]) + at, None, None, None, None, None, None, [value if valid else None])
            return
        variables = [attrs["var"]] if "var" in attrs else attrs["variables"].split("\n")
        for v in variables:
            name = f"{v}/" if len(variables) > 1 else ""
            mine = {k.removeprefix(name): a for k, a in arrays.items() if k.startswith(name)}
            index, offsets, exact_at = mine["index_table"].astype(np.int8).tobytes(), mine["index_table_offset"].astype(np.int64), mine["exact_table_offset"].astype(np.int64)
            values, valid = mine["exact_table"].astype(float), mine["exact_valid"].astype(bool)
            centres, width, bits, size = mine["bin_centers"].astype(float).tolist(), attrs[f"{name}elements_per_block"], attrs[f"{name}bits"], attrs[f"{name}elem_bytes"]
            ends, exact_ends = [*offsets[1:].tolist(), len(index)], [*exact_at[1:].tolist(), len(values)]
            for i, block in enumerate(mine["block_ids"].tolist()):
                if self.blocks[0] <= block <= self.blocks[1]:
                    exact = [x if ok else None for x, ok in zip(values[exact_at[i] : exact_ends[i]].tolist(), valid[exact_at[i] : exact_ends[i]].tolist(), strict=True)]
                    first = block == 0 or i == 0
                    yield (v, attrs["step"], block, block * width, int(mine["block_points"][i]), index[offsets[i] : ends[i]], bits, width, size, centres if first else None, exact)


class ArrayFiles(DataSource):
    """spark.read.format('ratiobin_nc').load(folder): blocks of the array files in a folder, or the points of lossless steps
    with option anchors; centres come with the first block of a file.  write: rows (name, body)."""

    @classmethod
    def name(cls) -> str:
        return "ratiobin_nc"

    def schema(self) -> str:
        return "var string, step int, block_id int, first_pos long, n int, payload binary, bits int, indices_per_block int, elem_bytes int, centres array<double>, exact array<double>"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(dict(self.options))

    def writer(self, schema, overwrite: bool) -> DataSourceWriter:
        return _Writer(self.options["path"])


def read_array_files(spark: SparkSession, path: str, **options) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(blocks, header, centres) of a folder of array files; options as the reader takes them."""
    spark.dataSource.register(ArrayFiles)
    rows = spark.read.format("ratiobin_nc").options(**options).load(path)
    first = rows.where("centres IS NOT NULL").groupBy("var", "step").agg(F.max("bits").alias("bits"), F.max("indices_per_block").alias("indices_per_block"), F.max("elem_bytes").alias("elem_bytes"), F.first("centres").alias("centres"))
    centres = first.select("var", "step", F.posexplode("centres").alias("idx", "centre"))
    return rows.drop("bits", "indices_per_block", "elem_bytes", "centres"), first.drop("centres"), centres


def read_anchors(spark: SparkSession, path: str, **options) -> DataFrame:
    """(var, step, pos, value) of the steps stored without loss in a folder of array files."""
    spark.dataSource.register(ArrayFiles)
    rows = spark.read.format("ratiobin_nc").options(anchors="true", **options).load(path)
    return rows.select("var", "step", F.col("first_pos").alias("pos"), F.col("exact")[0].alias("value"))
