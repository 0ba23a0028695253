"""Z-order codes of two 26-bit coordinates in a long, and the code ranges that cover a box."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

BITS = 26
# Shifts and masks that spread 32 bits to every second bit.
SPREAD = ((16, 0x0000FFFF0000FFFF), (8, 0x00FF00FF00FF00FF), (4, 0x0F0F0F0F0F0F0F0F), (2, 0x3333333333333333), (1, 0x5555555555555555))


def spread(c: Column) -> Column:
    for shift, mask in SPREAD:
        c = c.bitwiseOR(F.shiftleft(c, shift)).bitwiseAND(F.lit(mask))
    return c


def encode(x: Column, y: Column) -> Column:
    """x in the even bits, y in the odd ones; both from 0 to 2 ** 26 - 1."""
    return spread(x).bitwiseOR(F.shiftleft(spread(y), 1))


def gather(c: Column) -> Column:
    c = c.bitwiseAND(F.lit(SPREAD[-1][1]))
    masks = [m for _, m in SPREAD[:-1]][::-1] + [0x00000000FFFFFFFF]
    for shift, mask in zip((1, 2, 4, 8, 16), masks, strict=True):
        c = c.bitwiseOR(F.shiftrightunsigned(c, shift)).bitwiseAND(F.lit(mask))
    return c


def decode(z: Column) -> tuple[Column, Column]:
    return gather(z), gather(F.shiftrightunsigned(z, 1))


def ranges(x0: int, y0: int, x1: int, y1: int, most: int = 64, bits: int = BITS) -> list[tuple[int, int]]:
    """Sorted, closed ranges of codes that cover the box, exact unless more than ``most`` are needed: then neighbours with
    the least gaps between them are joined, so that ranges stay a superset."""
    out: list[tuple[int, int]] = []
    stack = [(0, 0, bits, 0)]  # corner, bits of the square's side, code of its corner
    while stack:
        cx, cy, b, z = stack.pop()
        side = (1 << b) - 1
        if cx > x1 or cy > y1 or cx + side < x0 or cy + side < y0:
            continue
        if x0 <= cx and cx + side <= x1 and y0 <= cy and cy + side <= y1 or b == 0 or (len(out) + len(stack) > 4 * most and b < bits // 2):
            out.append((z, z + (1 << 2 * b) - 1))
            continue
        h, q = 1 << (b - 1), 1 << (2 * b - 2)
        stack += [(cx + h, cy + h, b - 1, z + 3 * q), (cx, cy + h, b - 1, z + 2 * q), (cx + h, cy, b - 1, z + q), (cx, cy, b - 1, z)]
    out.sort()
    joined: list[tuple[int, int]] = []
    for a, b_ in out:
        if joined and a <= joined[-1][1] + 1:
            joined[-1] = (joined[-1][0], max(joined[-1][1], b_))
        else:
            joined.append((a, b_))
    return bridged(joined, most)


def bridged(found: list[tuple[int, int]], most: int) -> list[tuple[int, int]]:
    """``found``, sorted and apart, as at most ``most`` ranges: those with the least gaps between them are joined, the first of equals
    first. Joining two leaves all other gaps as they are, so the widest are found by one sort."""
    if len(found) <= most:
        return found
    kept = sorted(sorted(range(1, len(found)), key=lambda k: (found[k][0] - found[k - 1][1], k))[len(found) - max(1, most) :])
    return [(found[a][0], found[b - 1][1]) for a, b in zip([0, *kept], [*kept, len(found)], strict=True)]


def next_in_box(z: int, x0: int, y0: int, x1: int, y1: int, bits: int = BITS) -> int | None:
    """The least code at or after ``z`` of a point in the box, for scans that jump over gaps."""
    return next((max(z, a) for a, b in ranges(x0, y0, x1, y1, most=1 << 30, bits=bits) if b >= z), None)
