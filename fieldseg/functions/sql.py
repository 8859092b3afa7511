"""Table functions for SQL users."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from fieldseg.functions.grid import GridSpec


@udtf(returnType="neighbour: bigint")
class Stencil:
    """stencil(id, nx, ny, nz): the neighbours of a vertex on a grid (an extent of 1 drops an axis)."""

    def eval(self, vertex: int, nx: int, ny: int, nz: int):
        from itertools import product

        dims = [n for n in (nx, ny, nz) if n > 1] or [1]
        at, rest = [], vertex
        for n in dims[:-1]:
            at.append(rest % n)
            rest //= n
        at.append(rest)
        for step in product((-1, 0, 1), repeat=len(dims)):
            if any(step) and (min(step) >= 0 or max(step) <= 0) and all(0 <= c + s < n for c, s, n in zip(at, step, dims)):
                out, stride = 0, 1
                for c, s, n in zip(at, step, dims):
                    out += (c + s) * stride
                    stride *= n
                yield (out,)


@udtf(returnType="id: bigint, x: int, y: int, z: int")
class GridCells:
    """grid_cells(nx, ny, nz): all vertices of a (small) grid with their coordinates."""

    def eval(self, nx: int, ny: int, nz: int):
        for i in range(nx * ny * nz):
            yield i, i % nx, i // nx % ny, i // (nx * ny)


def register(spark: SparkSession) -> None:
    """Register the table functions and the generated-field source on a session."""
    from fieldseg.runtime import ship
    from fieldseg.sources.files import NoiseSource

    ship(spark)
    spark.udtf.register("stencil", Stencil)
    spark.udtf.register("grid_cells", GridCells)
    spark.dataSource.register(NoiseSource)


__all__ = ["GridCells", "GridSpec", "Stencil", "register"]
