"""Readers and writers of users' fields, graphs and volumes, and a Python data source of generated fields."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from fieldseg.functions.grid import GridSpec
from fieldseg.model import EDGE, VERTEX


def read_field(spark: SparkSession, path: str, kind: str = "parquet", **options) -> DataFrame:
    """(id, f) from parquet, orc, csv or json with a declared schema."""
    return spark.read.schema(VERTEX).options(**options).format(kind).load(path).select("id", "f")


def read_edges(spark: SparkSession, path: str, kind: str = "csv", **options) -> DataFrame:
    return spark.read.schema(EDGE).options(**options).format(kind).load(path)


def read_cells(spark: SparkSession, path: str, kind: str = "json") -> DataFrame:
    return spark.read.schema("cell_id long, verts array<long>").format(kind).load(path)


def read_volume(spark: SparkSession, path: str, spec: GridSpec, scale: float = 1.0) -> DataFrame:
    """(id, f) of raw float32 slabs: files of whole layers, named so that their order is that of the last axis.

    Every file is one row of bytes that one task decodes; the first id of a file is the sum of the sizes before it.
    """
    files = spark.read.format("binaryFile").load(path)
    sizes = sorted((r.path, r.length) for r in files.select("path", "length").collect())
    at, first = 0, []
    for p, n in sizes:
        first.append((p, at // 4))
        at += n
    if at != 4 * spec.n:
        raise ValueError(f"{at} bytes for {spec.n} vertices")
    starts = spark.createDataFrame(first, "path string, first long")

    def decode(batches):
        for rb in batches:
            for blob, base in zip(rb.column(0), rb.column(1).to_pylist()):
                v = np.frombuffer(blob.as_buffer(), "<f4")
                for a in range(0, len(v), 1 << 18):
                    part = v[a : a + (1 << 18)].astype(float)
                    yield pa.RecordBatch.from_arrays([pa.array(base + a + np.arange(len(part))), pa.array(np.round(part * scale).astype(np.int64))], ["id", "f"])

    return files.join(F.broadcast(starts), "path").select("content", "first").mapInArrow(decode, "id long, f long")


def write_by_block(df: DataFrame, path: str, block, kind: str = "parquet") -> None:
    """Results in one folder a block, ids sorted, so that boxes prune to their files."""
    df.withColumn("block", block).repartition("block").sortWithinPartitions("id").write.partitionBy("block").format(kind).save(path)


class NoiseSource(DataSource):
    """`spark.read.format("noise_grid").option("dims", "64,64,64")`: gradient noise, one partition a slab of ids."""

    @classmethod
    def name(cls) -> str:
        return "noise_grid"

    def schema(self) -> str:
        return "id long, f long"

    def reader(self, schema):
        return _NoiseReader(self.options)


class _Slab(InputPartition):
    def __init__(self, a: int, z: int):
        self.a, self.z = a, z


class _NoiseReader(DataSourceReader):
    def __init__(self, options):
        self.dims = tuple(int(x) for x in options.get("dims", "16,16").split(","))
        self.frequency, self.slabs, self.seed = float(options.get("frequency", 0.1)), int(options.get("slabs", 8)), int(options.get("seed", 42))

    def partitions(self):
        n = int(np.prod(self.dims))
        cuts = np.linspace(0, n, self.slabs + 1).astype(int).tolist()
        return [_Slab(a, z) for a, z in zip(cuts, cuts[1:]) if z > a]

    def read(self, slab):
        for a in range(slab.a, slab.z, 1 << 16):
            ids = np.arange(a, min(slab.z, a + (1 << 16)), dtype=np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(gradient_noise(ids, self.dims, self.frequency, self.seed))], ["id", "f"])


def gradient_noise(ids: np.ndarray, dims: tuple[int, ...], frequency: float, seed: int, scale: int = 1_000_000) -> np.ndarray:
    """The same kind of noise in NumPy, with a corner hash of its own."""
    from itertools import product

    coords, rest = [], ids
    for a, n in enumerate(dims):
        coords.append(rest % n if a < len(dims) - 1 else rest)
        rest = rest // n
    at = [c * frequency for c in coords]
    cell = [np.floor(x).astype(np.int64) for x in at]
    t = [x - c for x, c in zip(at, cell)]
    total = np.zeros(len(ids))
    for corner in product((0, 1), repeat=len(dims)):
        h = np.full(len(ids), seed, np.uint64)
        for c, k in zip(cell, corner):
            h = (h ^ (c + k).astype(np.uint64)) * np.uint64(0x9E3779B97F4A7C15)
            h ^= h >> np.uint64(29)
        pick, weight, step = (h >> np.uint64(7)) % np.uint64(2 * len(dims)), np.ones(len(ids)), np.zeros(len(ids))
        for i, (x, k) in enumerate(zip(t, corner)):
            fade = x**3 * (x * (x * 6 - 15) + 10)
            weight *= fade if k else 1 - fade
            step += np.where(pick == 2 * i, x - k, 0) + np.where(pick == 2 * i + 1, k - x, 0)
        total += weight * step
    return np.round(total * scale).astype(np.int64)
