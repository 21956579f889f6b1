"""Functions for SQL users: widths by shape, and a table function that deals values to blocks."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from .. import shapes
from ..hypergraph import Hypergraph
from ..widths import mm_width


def shape_of(name: str, k: int) -> Hypergraph:
    made = {"clique": shapes.clique, "cycle": shapes.cycle, "pyramid": shapes.pyramid, "path": shapes.path, "star": shapes.star}
    if name == "triangle":
        return shapes.triangle()
    if name == "double_triangle":
        return shapes.double_triangle()
    if name == "two_column_triangle":
        return shapes.two_column_triangle()
    return made[name](k)


@udtf(returnType="block int, value long")
class ExpandBlocks:
    """The block copies of a value: expand_blocks(value, blocks)."""

    def eval(self, value: int, blocks: int):
        for b in range(blocks):
            yield b, value


def register(spark: SparkSession) -> None:
    """mm_width_sql(shape, k, omega) as text, and expand_blocks(value, blocks)."""
    spark.udf.register("mm_width_sql", lambda shape, k, omega: str(mm_width(shape_of(shape, k), omega)), "string")
    spark.udtf.register("expand_blocks", ExpandBlocks)
