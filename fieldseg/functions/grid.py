"""Structured grids: ids, neighbours and blocks by arithmetic on columns, no edge table."""

from __future__ import annotations

from dataclasses import dataclass
from itertools import product
from math import ceil, prod

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

AXES = ("x", "y", "z")
#: Bytes that a block may take in one task, and that a vertex takes of them (the kernel's observed peak and the input table).
BLOCK_BYTES = 512 << 20
VERTEX_BYTES = 192


@dataclass(frozen=True)
class GridSpec:
    """Extents of a grid of 1 to 3 dimensions; ids are `x + nx * (y + ny * z)`.

    `simplicial` neighbours are those of the standard subdivision into simplices (all steps in {0, 1}, or all in {0, -1}), `axis`
    those one step along an axis, `full` all around.
    """

    dims: tuple[int, ...]
    connectivity: str = "simplicial"

    def __post_init__(self):
        if not 1 <= len(self.dims) <= 3 or any(n < 1 for n in self.dims):
            raise ValueError(f"bad extents {self.dims}")
        if self.connectivity not in ("simplicial", "axis", "full"):
            raise ValueError(f"unknown connectivity {self.connectivity}")

    @property
    def n(self) -> int:
        return prod(self.dims)

    @property
    def d(self) -> int:
        return len(self.dims)

    def stencil(self) -> list[tuple[int, ...]]:
        """Steps to the neighbours, in lexicographic order."""
        steps = [s for s in product((-1, 0, 1), repeat=self.d) if any(s)]
        if self.connectivity == "axis":
            return [s for s in steps if sum(map(abs, s)) == 1]
        if self.connectivity == "simplicial":
            return [s for s in steps if min(s) >= 0 or max(s) <= 0]
        return steps

    def coord(self, axis: int, vertex: Column | str = "id") -> Column:
        c = F.col(vertex) if isinstance(vertex, str) else vertex
        stride = prod(self.dims[:axis])
        inner = F.call_function("div", c, F.lit(stride)) if stride > 1 else c
        return F.pmod(inner, F.lit(self.dims[axis])) if axis < self.d - 1 else inner

    def with_coords(self, df: DataFrame, vertex: str = "id") -> DataFrame:
        return df.withColumns({AXES[a]: self.coord(a, vertex) for a in range(self.d)})

    def offset(self, step: tuple[int, ...]) -> int:
        return sum(s * prod(self.dims[:a]) for a, s in enumerate(step))

    def inside(self, step: tuple[int, ...], vertex: Column | str = "id") -> Column:
        """Whether the step from a vertex stays on the grid."""
        ok = F.lit(True)
        for a, s in enumerate(step):
            if s:
                c = self.coord(a, vertex)
                ok &= (c >= 1) if s < 0 else (c <= self.dims[a] - 2)
        return ok

    def neighbours(self, vertex: str = "id", closed: bool = False) -> Column:
        """Array of the ids of the neighbours on the grid (and of the vertex itself, if closed)."""
        c = F.col(vertex)
        each = [F.when(self.inside(s, vertex), c + F.lit(self.offset(s))) for s in self.stencil()]
        return F.array_compact(F.array(*([c] if closed else []), *each))

    def edges(self, df: DataFrame) -> DataFrame:
        """(src, dst) of the pairs of neighbours that are both in `df` (id), both directions."""
        out = df.select(F.col("id").alias("src"), F.explode(self.neighbours()).alias("dst"))
        return out.join(df.select(F.col("id").alias("dst")), "dst", "left_semi").select("src", "dst")

    def cells(self) -> list[tuple[tuple[int, ...], ...]]:
        """Simplices of one unit cube as corner steps: paths from the lowest to the highest corner, one axis at a time."""
        from itertools import permutations

        out = []
        for order in permutations(range(self.d)):
            at, path = [0] * self.d, [tuple([0] * self.d)]
            for a in order:
                at[a] = 1
                path.append(tuple(at))
            out.append(tuple(path))
        return out


@dataclass(frozen=True)
class Blocks:
    """A tiling of a grid: `counts[a]` blocks along axis a, block `x * k div n` along each."""

    spec: GridSpec
    counts: tuple[int, ...]

    @staticmethod
    def about(spec: GridSpec, n_blocks: int) -> "Blocks":
        """A tiling of about n_blocks blocks, as cubic as powers of two allow."""
        counts, left = [1] * spec.d, n_blocks
        while left > 1:
            a = max(range(spec.d), key=lambda i: spec.dims[i] / counts[i])
            if counts[a] * 2 > spec.dims[a]:
                break
            counts[a] *= 2
            left = -(-left // 2)
        return Blocks(spec, tuple(counts))

    @staticmethod
    def for_memory(spec: GridSpec, bytes_per_block: int | None = None, bytes_per_vertex: int = VERTEX_BYTES) -> "Blocks":
        """As few blocks as fit in memory: fewer, larger blocks have fewer ghosts."""
        return Blocks.about(spec, max(1, ceil(spec.n * bytes_per_vertex / (bytes_per_block or BLOCK_BYTES))))

    @staticmethod
    def of(spec: GridSpec, blocks: "Blocks | int | None") -> "Blocks":
        """The tiling that is given, one of about so many blocks, or by default the one that memory asks for."""
        if isinstance(blocks, Blocks):
            return blocks
        return Blocks.for_memory(spec) if blocks is None else Blocks.about(spec, blocks)

    @property
    def n(self) -> int:
        return prod(self.counts)

    def _of(self, coords: list[Column]) -> Column:
        out, stride = F.lit(0).cast("long"), 1
        for a, c in enumerate(coords):
            out = out + F.call_function("div", c * F.lit(self.counts[a]), F.lit(self.spec.dims[a])) * F.lit(stride)
            stride *= self.counts[a]
        return out

    def block(self, vertex: Column | str = "id") -> Column:
        return self._of([self.spec.coord(a, vertex) for a in range(self.spec.d)])

    def needed_by(self, vertex: str = "id") -> Column:
        """Array of the blocks that own the vertex or one of its neighbours (the owner first)."""
        own = [self.spec.coord(a, vertex) for a in range(self.spec.d)]
        each = [F.when(self.spec.inside(s, vertex), self._of([c + F.lit(x) for c, x in zip(own, s)])) for s in self.spec.stencil()]
        return F.array_distinct(F.array_compact(F.array(self._of(own), *each)))

    def halo(self, df: DataFrame) -> DataFrame:
        """`df` (id, ...) repeated for each block that holds the vertex, with `block` and `is_ghost`."""
        if self.n == 1:
            return df.withColumns({"block": F.lit(0).cast("long"), "is_ghost": F.lit(False)})
        out = df.withColumn("block", F.explode(self.needed_by()))
        return out.withColumn("is_ghost", F.col("block") != self.block())

    def requests(self, df: DataFrame) -> DataFrame:
        """(id, owner, needed_by): what each block asks for from the owners, known by arithmetic."""
        h = self.halo(df.select("id")).where("is_ghost")
        return h.select("id", self.block().alias("owner"), F.col("block").alias("needed_by"))

    def supply(self, df: DataFrame) -> DataFrame:
        """(id, owner, needed_by array): the same from the owners' side, who can tell on a grid without being asked."""
        rows = df.select("id", self.block().alias("owner"), self.needed_by().alias("all"))
        return rows.where(F.size("all") > 1).select("id", "owner", F.array_except("all", F.array("owner")).alias("needed_by"))
