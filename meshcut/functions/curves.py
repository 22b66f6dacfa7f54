"""Space-filling-curve indices as column expressions: no Python per row."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def _long(x) -> Column:
    return (F.col(x) if isinstance(x, str) else x).cast("long")


def bit(x: Column, b: Column) -> Column:
    return F.call_function("shiftright", x, b).bitwiseAND(1)


def quantize(points: DataFrame, dims: list[str], bits: int = 16, names: list[str] | None = None) -> DataFrame:
    """Adds integer cells gx, gy(, gz) on a 2**bits grid over the bounding box; a flat axis gives cell 0."""
    names = names or [f"g{d}" for d in dims]
    box = points.agg(*(f(d).cast("double").alias(f"{n}_{d}") for d in dims for n, f in (("lo", F.min), ("hi", F.max))))
    out = points.crossJoin(F.broadcast(box))  # one row
    side = float(1 << bits)
    cells = {}
    for d, n in zip(dims, names):
        lo, hi = F.col(f"lo_{d}"), F.col(f"hi_{d}")
        share = F.floor((F.col(d) - lo) / (hi - lo) * side).cast("long")
        cells[n] = F.when(hi > lo, F.least(share, F.lit((1 << bits) - 1))).otherwise(F.lit(0).cast("long"))
    return out.withColumns(cells).drop(*box.columns)


def hilbert2d(gx, gy, bits: int) -> Column:
    """Position of cell (gx, gy) on the Hilbert curve of order `bits`, as one fold over the bit levels."""
    top = F.lit((1 << bits) - 1).cast("long")

    def level(a, b):
        rx, ry = bit(a["x"], b), bit(a["y"], b)
        turned_x = F.when(ry == 1, a["x"]).when(rx == 1, top - a["y"]).otherwise(a["y"])
        turned_y = F.when(ry == 1, a["y"]).when(rx == 1, top - a["x"]).otherwise(a["x"])
        digit = (rx * 3).bitwiseXOR(ry)
        return F.struct(turned_x.alias("x"), turned_y.alias("y"), (a["key"] * 4 + digit).alias("key"))

    start = F.struct(_long(gx).alias("x"), _long(gy).alias("y"), F.lit(0).cast("long").alias("key"))
    return F.aggregate(F.sequence(F.lit(bits - 1), F.lit(0), F.lit(-1)), start, level, lambda a: a["key"])


def hilbert3d(gx, gy, gz, bits: int) -> Column:
    """Position of a cell on the three-dimensional Hilbert curve (public transpose form: undo excess work, Gray decode)."""

    def undo(a, b):
        q = F.call_function("shiftleft", F.lit(1).cast("long"), b)
        low = q - 1
        x, y, z = a["x"], a["y"], a["z"]
        x = F.when(x.bitwiseAND(q) != 0, x.bitwiseXOR(low)).otherwise(x)
        t = x.bitwiseXOR(y).bitwiseAND(low)
        on = y.bitwiseAND(q) != 0
        x, y = F.when(on, x.bitwiseXOR(low)).otherwise(x.bitwiseXOR(t)), F.when(on, y).otherwise(y.bitwiseXOR(t))
        t = x.bitwiseXOR(z).bitwiseAND(low)
        on = z.bitwiseAND(q) != 0
        x, z = F.when(on, x.bitwiseXOR(low)).otherwise(x.bitwiseXOR(t)), F.when(on, z).otherwise(z.bitwiseXOR(t))
        return F.struct(x.alias("x"), y.alias("y"), z.alias("z"))

    levels = F.sequence(F.lit(bits - 1), F.lit(1), F.lit(-1)) if bits > 1 else F.array().cast("array<int>")
    start = F.struct(_long(gx).alias("x"), _long(gy).alias("y"), _long(gz).alias("z"))

    def gray(a):
        y = a["y"].bitwiseXOR(a["x"])
        z = a["z"].bitwiseXOR(y)
        flip = F.aggregate(levels, F.lit(0).cast("long"), lambda t, b: F.when(bit(z, b) == 1, t.bitwiseXOR(F.call_function("shiftleft", F.lit(1).cast("long"), b) - 1)).otherwise(t))
        return F.struct(a["x"].bitwiseXOR(flip).alias("x"), y.bitwiseXOR(flip).alias("y"), z.bitwiseXOR(flip).alias("z"))

    def pack(a):
        every = F.sequence(F.lit(bits - 1), F.lit(0), F.lit(-1))
        return F.aggregate(every, F.lit(0).cast("long"), lambda k, b: k * 8 + bit(a["x"], b) * 4 + bit(a["y"], b) * 2 + bit(a["z"], b))

    # one-element transforms name the intermediate structs, so each is evaluated once
    state = F.aggregate(levels, start, undo)
    return F.get(F.transform(F.transform(F.array(state), gray), pack), F.lit(0))


def morton(cells: list, bits: int) -> Column:
    """Z-order index: the bits of the cells interleaved, the first axis highest."""
    axes = [_long(c) for c in cells]

    def level(k, b):
        for axis in axes:
            k = k * 2 + bit(axis, b)
        return k

    return F.aggregate(F.sequence(F.lit(bits - 1), F.lit(0), F.lit(-1)), F.lit(0).cast("long"), level)


def curve_key(cells: list[str], bits: int, curve: str = "hilbert") -> Column:
    if curve == "morton":
        return morton(cells, bits)
    return hilbert2d(*cells, bits) if len(cells) == 2 else hilbert3d(*cells, bits)
