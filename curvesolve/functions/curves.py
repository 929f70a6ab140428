"""Keys along space-filling curves as Column expressions, and the same keys on arrays.

Coordinates begin at 0 here. A key of d coordinates of ``bits`` bits is a long while d * bits <= 62,
and beyond that a binary of big-endian digits, which Spark orders byte by byte.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

CURVES = ("hilbert", "lebesgue", "gray", "lex", "snake", "moore", "peano")


def _bit(x: Column, b: int) -> Column:
    return F.shiftright(x, b).bitwiseAND(F.lit(1).cast("long"))


def _let(values: list[Column], body) -> Column:
    """body(values) with the values computed once: as fields of a struct bound by a lambda."""
    row = F.struct(*[v.cast("long").alias(f"x{i}") for i, v in enumerate(values)])
    return F.element_at(F.transform(F.array(row), lambda r: body([r[f"x{i}"] for i in range(len(values))])), 1)


def hilbert_axes(coords: list[Column], bits: int) -> Column:
    """Struct x0..x(d-1): the transposed Hilbert index, bit by bit over the axes."""
    d = len(coords)
    names = [f"x{i}" for i in range(d)]
    masks = F.array(*[F.lit(1 << b).cast("long") for b in range(bits - 1, 0, -1)]) if bits > 1 else F.array().cast("array<long>")
    start = F.struct(*[c.cast("long").alias(n) for c, n in zip(coords, names)])

    def level(acc: Column, q: Column) -> Column:
        # Each axis binds its struct, so that expressions stay as long as the axes are many.
        out = acc
        for i in range(d):
            out = _axis_step(out, q, i, names)
        return out

    turned = F.aggregate(masks, start, level)

    def gray(r: Column) -> Column:
        xs = [r[names[0]]]
        for i in range(1, d):
            xs.append(r[names[i]].bitwiseXOR(xs[i - 1]))
        if bits > 1:
            t = F.aggregate(masks, F.lit(0).cast("long"), lambda acc, q: F.when(xs[-1].bitwiseAND(q) != 0, acc.bitwiseXOR(q - 1)).otherwise(acc))
            xs = [x.bitwiseXOR(t) for x in xs]
        return F.struct(*[x.alias(n) for x, n in zip(xs, names)])

    return F.element_at(F.transform(F.array(turned), gray), 1)


def _axis_step(row: Column, q: Column, i: int, names: list[str]) -> Column:
    def body(r: Column) -> Column:
        on = r[names[i]].bitwiseAND(q) != 0
        swap = r[names[0]].bitwiseXOR(r[names[i]]).bitwiseAND(q - 1)
        new0 = F.when(on, r[names[0]].bitwiseXOR(q - 1)).otherwise(r[names[0]].bitwiseXOR(swap) if i else r[names[0]])
        cols = []
        for k, n in enumerate(names):
            if k == 0:
                cols.append(new0.alias(n))
            elif k == i:
                cols.append(F.when(on, r[n]).otherwise(r[n].bitwiseXOR(swap)).alias(n))
            else:
                cols.append(r[n].alias(n))
        return F.struct(*cols)
    return F.element_at(F.transform(F.array(row), body), 1)


def interleave(axes: list[Column], bits: int) -> Column:
    """Key whose digits are the axes' bits, most significant level first, first axis first."""
    d = len(axes)
    if d * bits <= 62:
        out = F.lit(0).cast("long")
        for b in range(bits - 1, -1, -1):
            for x in axes:
                out = F.shiftleft(out, 1).bitwiseOR(_bit(x.cast("long"), b))
        return out
    text = F.concat(*[_bit(x.cast("long"), b).cast("string") for b in range(bits - 1, -1, -1) for x in axes])
    return F.unhex(F.concat(*[F.lpad(F.conv(F.substring(text, at + 1, 8), 2, 16), 2, "0") for at in range(0, d * bits, 8)]))


def hilbert_key(coords: list[Column], bits: int) -> Column:
    if len(coords) == 1:
        return coords[0].cast("long")
    d = len(coords)
    return F.element_at(F.transform(F.array(hilbert_axes(coords, bits)), lambda r: interleave([r[f"x{i}"] for i in range(d)], bits)), 1)


def lebesgue_key(coords: list[Column], bits: int) -> Column:
    return interleave(coords, bits)


def gray_key(coords: list[Column], bits: int) -> Column:
    """Rank of the interleaved bits read as a Gray code: successive cells differ in one bit."""
    code = interleave(coords, bits)
    if len(coords) * bits > 62:
        raise ValueError("the Gray order is kept to keys of at most 62 bits")
    shift = 1
    while shift < len(coords) * bits:
        code = _gray_fold(code, shift)
        shift *= 2
    return code


def _gray_fold(code: Column, shift: int) -> Column:
    return _let([code], lambda v: v[0].bitwiseXOR(F.shiftright(v[0], shift)))


def lex_key(coords: list[Column], bits: int) -> Column:
    out = F.lit(0).cast("long")
    for c in coords:
        out = F.shiftleft(out, bits).bitwiseOR(c.cast("long"))
    return out


def snake_key(coords: list[Column], bits: int) -> Column:
    """Lexicographic with every other line reversed."""
    out, turn, top = F.lit(0).cast("long"), F.lit(0).cast("long"), (1 << bits) - 1
    for c in coords:
        out = F.shiftleft(out, bits).bitwiseOR(F.when(turn % 2 == 0, c.cast("long")).otherwise(F.lit(top) - c.cast("long")))
        turn = turn + c.cast("long")
    return out


def moore_key(coords: list[Column], bits: int) -> Column:
    """Closed curve in the plane: four Hilbert curves on the quadrants, turned to meet end to end."""
    if len(coords) != 2:
        raise ValueError("the closed order is defined in two dimensions")
    if bits == 1:
        x, y = coords
        return F.when(x == 0, y.cast("long")).otherwise(3 - y.cast("long"))
    half = 1 << (bits - 1)
    x, y = (c.cast("long") for c in coords)
    right, up = x >= half, y >= half
    lx, ly = x % half, y % half
    # In a quadrant the curve runs along the outer or inner side: up on the left, down on the right.
    a = F.when(right, F.lit(half - 1) - ly).otherwise(ly)
    b = F.when(right, lx).otherwise(F.lit(half - 1) - lx)
    quadrant = F.when(~right & ~up, 0).when(~right & up, 1).when(right & up, 2).otherwise(3)
    return F.shiftleft(quadrant.cast("long"), 2 * (bits - 1)).bitwiseOR(hilbert_key([a, b], bits - 1))


def peano_key(coords: list[Column], trits: int) -> Column:
    """Threefold refinement with reflection: a digit is mirrored by the parity of the other axes' earlier digits."""
    d = len(coords)
    out = F.lit(0).cast("long")
    parity: list[Column] = [F.lit(0).cast("long")] * d
    for t in range(trits - 1, -1, -1):
        digits = [F.floor(c.cast("long") / F.lit(3**t)).cast("long") % 3 for c in coords]
        for i, g in enumerate(digits):
            flip = parity[0] * 0
            for j in range(d):
                if j != i:
                    flip = flip + parity[j]
            seen = F.when(flip % 2 == 1, 2 - g).otherwise(g)
            out = out * 3 + seen
            parity[i] = parity[i] + g
    return out


def key(curve: str, coords: list[Column], bits: int) -> Column:
    if curve not in CURVES:
        raise ValueError(f"unknown curve {curve!r}")
    if curve == "peano":
        trits = 1
        while 3**trits < 1 << bits:
            trits += 1
        return peano_key(coords, trits)
    return {"hilbert": hilbert_key, "lebesgue": lebesgue_key, "gray": gray_key, "lex": lex_key, "snake": snake_key, "moore": moore_key}[curve](coords, bits)


def deinterleave(k: Column, d: int, bits: int) -> list[Column]:
    out = []
    for i in range(d):
        x = F.lit(0).cast("long")
        for b in range(bits - 1, -1, -1):
            x = F.shiftleft(x, 1).bitwiseOR(_bit(k, b * d + d - 1 - i))
        out.append(x)
    return out


lebesgue_cell = deinterleave


def hilbert_cell(k: Column, d: int, bits: int) -> Column:
    """Struct x0..x(d-1) of the cell with a Hilbert key."""
    names = [f"x{i}" for i in range(d)]
    if d == 1:
        return F.struct(k.cast("long").alias("x0"))
    start = F.struct(*[x.alias(n) for x, n in zip(deinterleave(k, d, bits), names)])

    def ungray(r: Column) -> Column:
        xs = [r[n] for n in names]
        first = xs[0].bitwiseXOR(F.shiftright(xs[-1], 1))
        return F.struct(first.alias(names[0]), *[xs[i].bitwiseXOR(xs[i - 1]).alias(names[i]) for i in range(1, d)])

    masks = F.array(*[F.lit(1 << b).cast("long") for b in range(1, bits)]) if bits > 1 else F.array().cast("array<long>")

    def level(acc: Column, q: Column) -> Column:
        for i in range(d - 1, -1, -1):
            acc = _axis_step(acc, q, i, names)
        return acc

    return F.aggregate(masks, F.element_at(F.transform(F.array(start), ungray), 1), level)


def precedes(a: list[Column], b: list[Column], bits: int) -> Column:
    """Whether cell a comes before cell b in bit-interleaved order, from the first differing level alone."""
    diff = [x.cast("long").bitwiseXOR(y.cast("long")) for x, y in zip(a, b)]
    # The axis whose difference has the highest bit decides; an earlier axis wins a tie.
    top, before = diff[0], a[0] < b[0]
    for d, x, y in zip(diff[1:], a[1:], b[1:]):
        higher = (top < d) & (top < top.bitwiseXOR(d))
        before = F.when(higher, x < y).otherwise(before)
        top = F.when(higher, d).otherwise(top)
    return before


def hilbert_array(coords: np.ndarray, bits: int) -> np.ndarray:
    """Hilbert keys of an (n, d) array of coordinates; Python integers beyond 62 bits."""
    x = [coords[:, i].astype(np.int64).copy() for i in range(coords.shape[1])]
    d = len(x)
    if d == 1:
        return x[0]
    for b in range(bits - 1, 0, -1):
        q, p = 1 << b, (1 << b) - 1
        for i in range(d):
            on = (x[i] & q) != 0
            swap = np.where(on, 0, (x[0] ^ x[i]) & p)
            x[0] = np.where(on, x[0] ^ p, x[0] ^ swap)
            if i:
                x[i] ^= swap
    for i in range(1, d):
        x[i] ^= x[i - 1]
    t = np.zeros_like(x[0])
    for b in range(bits - 1, 0, -1):
        t = np.where(x[-1] & (1 << b), t ^ ((1 << b) - 1), t)
    x = [v ^ t for v in x]
    wide = d * bits > 62
    out = np.zeros(len(coords), object if wide else np.int64)
    for b in range(bits - 1, -1, -1):
        for v in x:
            bit = (v >> b) & 1
            out = out * 2 + (bit.astype(object) if wide else bit)
    return out


def box_ranges(lo: tuple[int, ...], hi: tuple[int, ...], bits: int, most: int = 64) -> list[tuple[int, int]]:
    """Key ranges of bit-interleaved order that cover a box (inclusive); at most ``most``, merged by smallest gap."""
    d, found = len(lo), []
    todo = [(0, (0,) * d, bits)]
    while todo:
        prefix, corner, left = todo.pop()
        side = 1 << left
        if any(c > h or c + side - 1 < a for c, a, h in zip(corner, lo, hi)):
            continue
        if left == 0 or all(a <= c and c + side - 1 <= h for c, a, h in zip(corner, lo, hi)):
            found.append((prefix << (d * left), ((prefix + 1) << (d * left)) - 1))
            continue
        for o in range(1 << d):
            part = tuple(c + (o >> (d - 1 - j) & 1) * side // 2 for j, c in enumerate(corner))
            todo.append((prefix << d | o, part, left - 1))
    found.sort()
    while len(found) > 1:
        gaps = [found[i + 1][0] - found[i][1] for i in range(len(found) - 1)]
        i = min(range(len(gaps)), key=gaps.__getitem__)
        if gaps[i] > 1 and len(found) <= most:
            break
        found[i:i + 2] = [(found[i][0], found[i + 1][1])]
    return found
