"""A field with what its methods share: computed once, kept while a pipeline of methods runs over it."""

from __future__ import annotations

from functools import cached_property

from pyspark.sql import Column, DataFrame

from fieldseg.functions.grid import Blocks, GridSpec
from fieldseg.operators import components, critical, extremum_graph, segment
from fieldseg.operators.order import order_field
from fieldseg.operators.pointers import steepest
from fieldseg.runtime import cut


class FieldFrame:
    """`df` (id, f) on a grid; the order field, both segmentations and the pointers are made on first use and kept."""

    def __init__(self, df: DataFrame, spec: GridSpec, blocks: Blocks | int | None = None):
        self.spec = spec
        self.blocks = Blocks.for_memory(spec) if blocks is None else blocks
        self.df = cut(df.select("id", "f"))

    @cached_property
    def ords(self) -> DataFrame:
        return order_field(self.df)

    @cached_property
    def ends(self) -> DataFrame:
        return cut(segment.blockwise(self.df, self.spec, self.blocks))

    @cached_property
    def pointers(self) -> tuple[DataFrame, DataFrame]:
        return tuple(cut(steepest(self.df, spec=self.spec, direction=d)) for d in ("up", "down"))

    def mask(self, predicate: str | Column | None = None, **how) -> DataFrame:
        return components.mask(self.df, predicate, **how)

    def components(self, predicate: str | Column | None = None, **how) -> DataFrame:
        return components.connected(self.mask(predicate, **how), self.spec, blocks=self.blocks)

    def critical(self) -> DataFrame:
        return critical.classify(self.df, self.spec)

    def separatrices(self) -> DataFrame:
        return critical.separatrices(self.df, self.spec, *self.pointers)

    def extremum_graph(self, side: str = "max_id") -> DataFrame:
        return extremum_graph.build(self.ends, self.ords, self.spec, side)
