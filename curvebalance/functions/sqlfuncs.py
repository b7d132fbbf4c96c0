"""The engine's functions for SQL users, registered as temporary SQL functions (expressions, not UDFs) and table functions."""

from __future__ import annotations

from pyspark.sql import SparkSession


def _spread_sql(x: str, bits: int, d: int, at: int) -> str:
    return " | ".join(f"shiftleft(shiftright({x}, {k}) & 1L, {k * d + d - 1 - at})" for k in range(bits))


def register(spark: SparkSession, bits: int = 16) -> None:
    """morton_key(x, y), gray_key(x, y), slice_of(prefix, total, parts), owner_of(idx, n, parts), and the table function box_to_key_ranges."""
    m = f"({_spread_sql('x', bits, 2, 0)}) | ({_spread_sql('y', bits, 2, 1)})"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION morton_key(x BIGINT, y BIGINT) RETURNS BIGINT RETURN {m}")
    inner = "array(morton_key(x, y))"
    for i in range((2 * bits - 1).bit_length()):
        inner = f"transform({inner}, k -> k ^ shiftrightunsigned(k, {1 << i}))"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION gray_key(x BIGINT, y BIGINT) RETURNS BIGINT RETURN element_at({inner}, 1)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION slice_of(prefix BIGINT, total BIGINT, parts INT) RETURNS INT RETURN least(parts - 1, CAST((prefix * parts) div total AS INT))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION owner_of(idx BIGINT, n BIGINT, parts INT) RETURNS INT RETURN CAST((idx * parts) div n AS INT)")
    from .tablefuncs import BoxToKeyRanges, ExpandCutoff, PointToNeighbours

    spark.udtf.register("box_to_key_ranges", BoxToKeyRanges)
    spark.udtf.register("expand_cutoff", ExpandCutoff)
    spark.udtf.register("point_to_neighbours", PointToNeighbours)
