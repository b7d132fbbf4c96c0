"""Table functions: a box to its key ranges, a bucket to its neighbours along the curve, a cell to its face neighbours."""

from __future__ import annotations

from pyspark.sql.functions import udtf

from curvebalance.operators.ranges import key_ranges


@udtf(returnType="lo: bigint, hi: bigint")
class BoxToKeyRanges:
    def eval(self, x0: int, y0: int, x1: int, y1: int, bits: int):
        yield from key_ranges([x0, y0], [x1, y1], bits)


@udtf(returnType="bucket: bigint")
class ExpandCutoff:
    def eval(self, bucket: int, cutoff: int):
        for b in range(max(0, bucket - cutoff), bucket + cutoff + 1):
            yield (b,)


@udtf(returnType="x: bigint, y: bigint, z: bigint")
class PointToNeighbours:
    def eval(self, x: int, y: int, z: int):
        for d in (-1, 1):
            yield x + d, y, z
            yield x, y + d, z
            yield x, y, z + d
