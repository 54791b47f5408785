"""The Hilbert curve: encoding in columns, decoding and boxes of intervals on a node's scale.

Orientation: on the first order (0,0), (0,1), (1,1), (1,0) come in turn. Two bits of state say whether the
axes are swapped and both directions flipped within the current quadrant.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def encode(x: Column, y: Column, order: int) -> Column:
    """Position on the curve of cell (x, y) of a 2**order square grid."""
    one = F.lit(1).cast("long")
    zero = F.struct(F.lit(0).cast("long").alias("swap"), F.lit(0).cast("long").alias("flip"), F.lit(0).cast("long").alias("at"))

    def step(s: Column, k: Column) -> Column:
        a = F.call_function("shiftright", x, k).bitwiseAND(one).bitwiseXOR(s["flip"])
        b = F.call_function("shiftright", y, k).bitwiseAND(one).bitwiseXOR(s["flip"])
        rx, ry = F.when(s["swap"] == 1, b).otherwise(a), F.when(s["swap"] == 1, a).otherwise(b)
        digit = (3 * rx).bitwiseXOR(ry)
        return F.struct(s["swap"].bitwiseXOR(1 - ry).alias("swap"), s["flip"].bitwiseXOR(rx.bitwiseAND(1 - ry)).alias("flip"), (4 * s["at"] + digit).alias("at"))

    return F.aggregate(F.sequence(F.lit(order - 1), F.lit(0), F.lit(-1)), zero, step)["at"]


def point(v: int, order: int) -> tuple[int, int]:
    """The cell at position v."""
    x = y = swap = flip = 0
    for k in range(order - 1, -1, -1):
        digit = (v >> (2 * k)) & 3
        rx = digit >> 1
        ry = digit ^ (3 * rx)
        a, b = (ry, rx) if swap else (rx, ry)
        x, y = 2 * x + (a ^ flip), 2 * y + (b ^ flip)
        swap, flip = swap ^ (1 - ry), flip ^ (rx & (1 - ry))
    return x, y


def blocks(lo: int, hi: int) -> list[tuple[int, int]]:
    """[lo, hi) as aligned runs (start, k) of length 4**k; each is a square of side 2**k."""
    out = []
    while lo < hi:
        k = 0
        while lo % 4 ** (k + 1) == 0 and lo + 4 ** (k + 1) <= hi:
            k += 1
        out.append((lo, k))
        lo += 4**k
    return out


def interval_box(lo: int, hi: int, order: int) -> tuple[int, int, int, int] | None:
    """The least box of cells (x0, x1, y0, y1), ends exclusive, around the curve's interval."""
    boxes = []
    for start, k in blocks(max(0, lo), min(hi, 4**order)):
        x, y = point(start, order)
        side = 1 << k
        x, y = x // side * side, y // side * side
        boxes.append((x, x + side, y, y + side))
    if not boxes:
        return None
    return min(b[0] for b in boxes), max(b[1] for b in boxes), min(b[2] for b in boxes), max(b[3] for b in boxes)
