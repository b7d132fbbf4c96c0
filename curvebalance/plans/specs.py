"""What a point set is and how a tree is built: plain, validated descriptions that operators turn into plans."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, types as T

NUMERIC = (T.ByteType, T.ShortType, T.IntegerType, T.LongType, T.FloatType, T.DoubleType, T.DecimalType)


@dataclass(frozen=True)
class PointSpec:
    """Columns of a point table: a unique id, coordinates and a weight (1, if none is named)."""

    uid: str
    coords: tuple[str, ...]
    weight: str | None = None

    def check(self, df: DataFrame) -> PointSpec:
        fields = {f.name: f.dataType for f in df.schema}
        for c in (self.uid, *self.coords, *([self.weight] if self.weight else [])):
            if c not in fields:
                raise ValueError(f"no column {c}")
        for c in self.coords:
            if not isinstance(fields[c], NUMERIC + (T.DateType, T.TimestampType, T.TimestampNTZType)):
                raise ValueError(f"column {c} is not a coordinate: {fields[c].simpleString()}")
        if self.weight and not isinstance(fields[self.weight], NUMERIC):
            raise ValueError(f"column {self.weight} is not a weight")
        return self

    @property
    def dims(self) -> int:
        return len(self.coords)


SPLITTERS = ("midpoint", "median_sort", "median_sample_sort", "median_sample_select")


@dataclass(frozen=True)
class TreeConfig:
    """bucket_size: most points of a leaf. upper and lower: splitters above and from `switch_level`. dim_rule: widest or cyclic. box:
    tight or cell. curve: morton or hilbert. k1: top cells wanted, k2: second-level cells of one top cell. sample_frac: for sampled medians."""

    bucket_size: int = 32
    upper: str = "midpoint"
    lower: str = "midpoint"
    switch_level: int = 0
    dim_rule: str = "widest"
    box: str = "tight"
    curve: str = "morton"
    k1: int = 64
    k2: int = 8
    sample_frac: float = 0.01
    max_depth: int = 62
    top_mode: str = "exact"

    def __post_init__(self):
        if self.upper not in SPLITTERS or self.lower not in SPLITTERS:
            raise ValueError("unknown splitter")
        if self.dim_rule not in ("widest", "cyclic") or self.box not in ("tight", "cell"):
            raise ValueError("unknown rule")
        if self.top_mode not in ("exact", "histogram", "sample"):
            raise ValueError("unknown top mode")
        if self.bucket_size < 1 or not 1 <= self.max_depth <= 62:
            raise ValueError("bucket_size is 1 at least, max_depth 1 to 62")

    def splitter(self, depth: int) -> str:
        return self.upper if depth < self.switch_level else self.lower

    @classmethod
    def of(cls, splitter: str, **more) -> TreeConfig:
        return cls(upper=splitter, lower=splitter, **more)

    @classmethod
    def for_clustered(cls, parts: int, k1: int = 8, k2: int = 8, **more) -> TreeConfig:
        """Medians on the top k1 * k2 * parts cells, midpoints below: for archived data that clusters."""
        return cls(upper="median_sort", lower="midpoint", switch_level=max(1, (k1 * k2 * parts - 1).bit_length()), k1=k1 * parts, k2=k2, **more)

    def with_(self, **more) -> TreeConfig:
        return replace(self, **more)
