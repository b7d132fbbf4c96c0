"""Space-filling curve keys on grids, as column expressions: Morton, Gray-code and Hilbert, with their inverses."""

from __future__ import annotations

from functools import lru_cache, reduce

from pyspark.sql import Column, DataFrame, functions as F

#: Masks that spread 32 bits to every second and 21 bits to every third place (fixed values).
SPREAD2 = ((16, 0x0000FFFF0000FFFF), (8, 0x00FF00FF00FF00FF), (4, 0x0F0F0F0F0F0F0F0F), (2, 0x3333333333333333), (1, 0x5555555555555555))
SPREAD3 = ((32, 0x001F00000000FFFF), (16, 0x001F0000FF0000FF), (8, 0x100F00F00F00F00F), (4, 0x10C30C30C30C30C3), (2, 0x1249249249249249))


def _or(xs: list[Column]) -> Column:
    return reduce(lambda a, b: a.bitwiseOR(b), xs)


def _spread(c: Column, steps) -> Column:
    for k, mask in steps:
        c = c.bitwiseOR(F.shiftleft(c, k)).bitwiseAND(F.lit(mask))
    return c


def interleave(cells: list[Column], bits: int) -> Column:
    """The bits of all cells, highest first, dimension 0 first within each group. At most 63 bits together."""
    d = len(cells)
    if d * bits > 63:
        raise ValueError("more than 63 bits; use wide_key")
    cells = [c.cast("long") for c in cells]
    if d == 1:
        return cells[0]
    if d in (2, 3):
        parts = [_spread(c, SPREAD2 if d == 2 else SPREAD3) for c in cells]
        return _or([F.shiftleft(p, d - 1 - i) if i < d - 1 else p for i, p in enumerate(parts)])
    one = F.lit(1).cast("long")
    return _or([F.shiftleft(F.shiftright(c, k).bitwiseAND(one), k * d + d - 1 - i) for i, c in enumerate(cells) for k in range(bits)])


morton_key = interleave


def wide_key(cells: list[Column], bits: int) -> Column:
    """A Morton key of any width as big-endian binary, which sorts like the number: interleaved in slices of 63 // d bits."""
    d = len(cells)
    per = 62 // d if d <= 62 else 0
    if not per:
        raise ValueError("too many dimensions")
    out, top = [], bits
    while top > 0:
        low = max(0, top - per)
        part = interleave([F.shiftright(c.cast("long"), low).bitwiseAND(F.lit((1 << top - low) - 1)) for c in cells], top - low)
        out.append(F.unhex(F.lpad(F.hex(part), 16, "0")))
        top = low
    return F.concat(*out)


def gray_key(cells: list[Column], bits: int) -> Column:
    """Position of the interleaved bits in the reflected Gray code: prefix xor of the bits, by doubling shifts."""
    k = interleave(cells, bits)
    s = 1
    while s < len(cells) * bits:
        k = k.bitwiseXOR(F.shiftrightunsigned(k, s))
        s *= 2
    return k


def _compact(key: Column, d: int, i: int, bits: int) -> Column:
    one = F.lit(1).cast("long")
    return _or([F.shiftleft(F.shiftright(key, k * d + d - 1 - i).bitwiseAND(one), k) for k in range(bits)])


def morton_cell(key: Column, dims: int, bits: int) -> list[Column]:
    """Inverse of the Morton key."""
    return [_compact(key, dims, i, bits) for i in range(dims)]


def _folded_key(cells: list[Column], bits: int) -> Column:
    """Hilbert key in any number of dimensions, by the published transform of transposed coordinates: one fold over (bit,
    dimension) undoes the rotations, then a Gray decoding. Built-in functions only."""
    d = len(cells)
    if d == 1:
        return cells[0].cast("long")
    x = F.array(*[c.cast("long") for c in cells])
    steps = F.array(*[F.struct(F.lit(1 << q).cast("long").alias("q"), F.lit(i).alias("i")) for q in range(bits - 1, 0, -1) for i in range(d)]) if bits > 1 else None

    def turn(a: Column, s: Column) -> Column:
        p = s["q"] - 1
        first, own = F.element_at(a, 1), F.element_at(a, s["i"] + 1)
        up = own.bitwiseAND(s["q"]) != 0
        swap = first.bitwiseXOR(own).bitwiseAND(p)
        return F.transform(a, lambda v, k: F.when(up, F.when(k == 0, v.bitwiseXOR(p)).otherwise(v)).otherwise(F.when((k == 0) | (k == s["i"]), F.when(s["i"] == 0, v).otherwise(v.bitwiseXOR(swap))).otherwise(v)))

    if steps is not None:
        x = F.aggregate(steps, x, turn)
    # Gray encoding across dimensions, then the carry of the last one
    g = F.aggregate(F.sequence(F.lit(2), F.lit(d)), F.struct(x.alias("x"), F.array(F.element_at(x, 1)).alias("g")), lambda a, i: F.struct(a["x"].alias("x"), F.concat(a["g"], F.array(F.element_at(a["g"], -1).bitwiseXOR(F.element_at(a["x"], i)))).alias("g")))["g"]
    qs = F.array(*[F.lit(1 << q).cast("long") for q in range(bits - 1, 0, -1)]) if bits > 1 else F.array().cast("array<long>")
    res = F.transform(F.array(F.struct(g.alias("g"))), lambda s: F.struct(s["g"].alias("g"), F.aggregate(qs, F.lit(0).cast("long"), lambda t, q: F.when(F.element_at(s["g"], -1).bitwiseAND(q) != 0, t.bitwiseXOR(q - 1)).otherwise(t)).alias("t")))
    # (bit, dimension) pairs, highest first
    places = F.array(*[F.struct(F.lit(k).alias("k"), F.lit(i + 1).alias("i")) for k in range(bits - 1, -1, -1) for i in range(d)])
    one = F.lit(1).cast("long")
    keyed = F.transform(res, lambda s: F.aggregate(places, F.lit(0).cast("long"), lambda a, p: F.shiftleft(a, 1).bitwiseOR(F.call_function("shiftright", F.element_at(s["g"], p["i"]).bitwiseXOR(s["t"]), p["k"]).bitwiseAND(one))))
    return F.element_at(keyed, 1)


#: Entries of a step's table; as many levels are taken in one step as its table can hold.
TABLE = 4096
#: Dimensions up to which Hilbert keys come from tables of states; above, from a fold over arrays.
TABLE_DIMS = 4


def _plane_step(state: tuple, bits: list[int]) -> tuple[list[int], tuple]:
    """One level of the two-dimensional curve. State: whether the axes are swapped, and whether bits are complemented."""
    swapped, flipped = state
    p, q = (b ^ flipped for b in (reversed(bits) if swapped else bits))
    digit = 3 * p ^ q
    return [digit >> 1, digit & 1], (swapped ^ (not q), flipped ^ (p and not q))


def _space_step(state: tuple, bits: list[int]) -> tuple[list[int], tuple]:
    """One level in more dimensions. State: which axis each place has, whether it is complemented, and the carry of the last place."""
    axis, flip, carry = list(state[0]), list(state[1]), state[2]
    own = [bits[a] ^ f for a, f in zip(axis, flip)]
    for i, up in enumerate(own):  # how the levels below are turned
        if up:
            flip[0] ^= 1
        else:
            axis[0], axis[i], flip[0], flip[i] = axis[i], axis[0], flip[i], flip[0]
    seen, out = 0, []
    for v in own:
        seen ^= v
        out.append(seen ^ carry)
    return out, (tuple(axis), tuple(flip), carry ^ seen)


@lru_cache(None)
def machine(d: int) -> tuple[list[list[int]], list[list[int]]]:
    """The curve as a machine: for each state and Morton digit, the Hilbert digit and the next state. State 0 is the start."""
    step, first = (_plane_step, (0, 0)) if d == 2 else (_space_step, (tuple(range(d)), (0,) * d, 0))
    states, digits, nexts, i = [first], [], [], 0
    while i < len(states):
        row, to = [], []
        for m in range(1 << d):
            out, new = step(states[i], [m >> d - 1 - k & 1 for k in range(d)])
            new = tuple(int(v) if isinstance(v, bool) else v for v in new)
            if new not in states:
                states.append(new)
            row.append(reduce(lambda a, b: a << 1 | int(b), out, 0))
            to.append(states.index(new))
        digits.append(row)
        nexts.append(to)
        i += 1
    return digits, nexts


@lru_cache(None)
def _table(d: int, levels: int, inverse: bool) -> list[int]:
    """Digits of several levels and the state after them (digits << 16 | state), by state << d * levels | digits."""
    digits, nexts = machine(d)
    if inverse:
        back = [sorted(range(1 << d), key=row.__getitem__) for row in digits]
        digits, nexts = back, [[to[m] for m in row] for to, row in zip(nexts, back)]
    out = []
    for s in range(len(digits)):
        for m in range(1 << d * levels):
            at, v = s, 0
            for k in range(levels - 1, -1, -1):
                one = m >> d * k & (1 << d) - 1
                v, at = v << d | digits[at][one], nexts[at][one]
            out.append(v << 16 | at)
    return out


def _constant(numbers: list[int]) -> Column:
    """A constant array, folded by the optimizer: one expression however long it is."""
    return F.split(F.lit(",".join(map(str, numbers))), ",").cast("array<int>")


def _by_table(code: Column, d: int, bits: int, inverse: bool) -> Column:
    """Runs the machine over a code, highest digits first: a fold of few steps, each one lookup in a constant array for several levels."""
    states = len(machine(d)[0])
    per = max(k for k in range(1, bits + 1) if k == 1 or states << d * k <= TABLE)
    first, long = bits % per or per, "long"
    steps = (bits - first) // per

    def step(rest: Column, state: Column, key: Column, levels: int) -> Column:
        """`rest` has its next digits on top."""
        at = F.shiftleft(state, d * levels).bitwiseOR(F.shiftrightunsigned(rest, d * (bits - levels)).bitwiseAND(F.lit((1 << d * levels) - 1)).cast("int"))
        e = F.get(_constant(_table(d, levels, inverse)), at)
        below = F.shiftleft(rest, d * levels).bitwiseAND(F.lit((1 << d * bits) - 1))
        return F.struct(below.alias("rest"), e.bitwiseAND(F.lit(0xFFFF)).alias("state"), F.shiftleft(key, d * levels).bitwiseOR(F.shiftright(e, 16).cast(long)).alias("key"))

    start = step(code, F.lit(0), F.lit(0).cast(long), first)
    return F.aggregate(F.array(*[F.lit(i) for i in range(steps)]).cast("array<int>"), start, lambda a, _: step(a["rest"], a["state"], a["key"], per), lambda a: a["key"])


def with_hilbert(df: DataFrame, code: str, d: int, bits: int, out: str = "key") -> DataFrame:
    """Adds the Hilbert key of interleaved bits. Each step of the machine is a column of its own, used twice, so the steps stay apart in the plan and
    run one after another in generated code."""
    states = len(machine(d)[0])
    per = max(k for k in range(1, bits + 1) if k == 1 or states << d * k <= TABLE)
    left, parts, state = bits, [], F.lit(0)
    for k, levels in enumerate([bits % per] * (bits % per > 0) + [per] * (bits // per)):
        left -= levels
        digits = F.shiftrightunsigned(F.col(code), d * left).bitwiseAND(F.lit((1 << d * levels) - 1)).cast("int")
        df = df.withColumn(f"_step{k}", F.get(_constant(_table(d, levels, False)), F.shiftleft(state, d * levels).bitwiseOR(digits)))
        state = F.col(f"_step{k}").bitwiseAND(F.lit(0xFFFF))
        parts.append(F.shiftleft(F.shiftright(F.col(f"_step{k}"), 16).cast("long"), d * left))
    return df.withColumn(out, _or(parts)).drop(*[f"_step{k}" for k in range(len(parts))])


def hilbert_key(cells: list[Column], bits: int) -> Column:
    """Hilbert key of a cell. In two to four dimensions by tables of states, several levels a step; above by a fold over bits and arrays."""
    d = len(cells)
    if d == 1:
        return cells[0].cast("long")
    return _by_table(interleave(cells, bits), d, bits, False) if d <= TABLE_DIMS else _folded_key(cells, bits)


def hilbert_cell(key: Column, dims: int, bits: int) -> list[Column]:
    """Inverse of the Hilbert key, in up to four dimensions."""
    if dims > TABLE_DIMS:
        raise ValueError("the inverse has tables for four dimensions at most")
    return [key] if dims == 1 else morton_cell(_by_table(key, dims, bits, True), dims, bits)


def gray_cell(key: Column, dims: int, bits: int) -> list[Column]:
    """Inverse of the Gray key."""
    return morton_cell(key.bitwiseXOR(F.shiftrightunsigned(key, 1)), dims, bits)


def hilbert_key_2d(x: Column, y: Column, bits: int) -> Column:
    """The two-dimensional Hilbert key by a fold over the bits, highest first, without tables. State: 0 and 1 keep or swap
    the axes, 2 and 3 do so on complemented bits."""
    levels = F.array(*[F.lit(k) for k in range(bits - 1, -1, -1)])
    one = F.lit(1).cast("long")

    def step(a: Column, k: Column) -> Column:
        u = F.call_function("shiftright", a["x"], k).bitwiseAND(one)
        v = F.call_function("shiftright", a["y"], k).bitwiseAND(one)
        flip = F.when(a["f"], one).otherwise(F.lit(0).cast("long"))
        p = F.when(a["s"], v).otherwise(u).bitwiseXOR(flip)
        q = F.when(a["s"], u).otherwise(v).bitwiseXOR(flip)
        digit = (p * 3).bitwiseXOR(q)
        low = q == 0
        return F.struct(a["x"].alias("x"), a["y"].alias("y"), (F.shiftleft(a["key"], 2) + digit).alias("key"), F.when(low, ~a["s"]).otherwise(a["s"]).alias("s"), F.when(low & (p == 1), ~a["f"]).otherwise(a["f"]).alias("f"))

    zero = F.struct(x.cast("long").alias("x"), y.cast("long").alias("y"), F.lit(0).cast("long").alias("key"), F.lit(False).alias("s"), F.lit(False).alias("f"))
    return F.aggregate(levels, zero, step)["key"]


def key_of(cells: list[Column], bits: int, curve: str) -> Column:
    if curve == "morton":
        return interleave(cells, bits)
    if curve == "gray":
        return gray_key(cells, bits)
    if curve == "hilbert":
        return hilbert_key(cells, bits)
    raise ValueError(f"unknown curve: {curve}")


def keyed(points: DataFrame, dims: int, bits: int = 16, curve: str = "morton", box=None) -> DataFrame:
    """Adds `key` to a point table, on the grid of its box: no Python, one aggregate for the box."""
    from .geometry import bounding_box, quantise

    box = box or bounding_box(points, dims)
    if curve == "hilbert" and 2 <= dims <= TABLE_DIMS:  # the interleaved bits are a column of their own, made by generated code
        return with_hilbert(points.withColumn("_code", interleave(quantise(points, dims, box, bits), bits)), "_code", dims, bits).drop("_code")
    return points.withColumn("key", key_of(quantise(points, dims, box, bits), bits, curve))
