"""Box queries: a box becomes a few key ranges, which sorted files prune, and a residual test."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F


def key_ranges(lo: list[int], hi: list[int], bits: int, most: int = 64) -> list[tuple[int, int]]:
    """Morton key ranges that cover a box of cells (inclusive), at most about `most`: cells of the implied tree that lie inside are whole ranges,
    others are opened, largest first, while the limit allows."""
    d = len(lo)
    todo, done = [(0, 0, [0] * d)], []
    while todo:
        todo.sort(key=lambda t: t[0])
        level, key, at = todo.pop(0)
        size = 1 << bits - level
        a, b = [x * size for x in at], [(x + 1) * size - 1 for x in at]
        if any(y < p or x > q for x, y, p, q in zip(a, b, lo, hi)):
            continue
        span = (key << d * (bits - level), (key + 1 << d * (bits - level)) - 1)
        inside = all(x >= p and y <= q for x, y, p, q in zip(a, b, lo, hi))
        if inside or level == bits or len(todo) + len(done) >= most:
            done.append(span)
            continue
        for c in range(1 << d):
            todo.append((level + 1, key << d | c, [x << 1 | c >> d - 1 - i & 1 for i, x in enumerate(at)]))
    done.sort()
    out: list[tuple[int, int]] = []
    for a, b in done:
        if out and a <= out[-1][1] + 1:
            out[-1] = (out[-1][0], max(b, out[-1][1]))
        else:
            out.append((a, b))
    return out


def _cell(v: float, lo: float, hi: float, bits: int) -> int:
    if hi <= lo:
        return 0
    return min((1 << bits) - 1, max(0, int((v - lo) / (hi - lo) * float(1 << bits) // 1)))


def box_filter(lo: list[float], hi: list[float], box, bits: int, most: int = 64) -> Column:
    """A condition on key and coordinates that holds exactly inside the box."""
    spans = key_ranges([_cell(v, *b, bits) for v, b in zip(lo, box)], [_cell(v, *b, bits) for v, b in zip(hi, box)], bits, most)
    keys = F.lit(False)
    for a, b in spans:
        keys = keys | F.col("key").between(a, b)
    inside = F.lit(True)
    for i, (a, b) in enumerate(zip(lo, hi)):
        inside = inside & F.col(f"c{i}").between(F.lit(a), F.lit(b))
    return keys & inside


def box_query(keyed: DataFrame, boxes: dict[int, tuple[list[float], list[float]]], box, bits: int, most: int = 64) -> DataFrame:
    """box_id, uid of the points (uid, c0.., key) in each box. A null coordinate range is a partial-match query."""
    out = None
    for i, (lo, hi) in boxes.items():
        lo = [box[k][0] if v is None else v for k, v in enumerate(lo)]
        hi = [box[k][1] if v is None else v for k, v in enumerate(hi)]
        rows = keyed.where(box_filter(lo, hi, box, bits, most)).select(F.lit(i).cast("int").alias("box_id"), "uid")
        out = rows if out is None else out.unionByName(rows)
    return out
