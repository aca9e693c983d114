"""Hash families: register number, raw draw, seed draws, offsets.

``w`` is an unsigned integer of ``spec.bits`` bits; small w stands for a large draw, so a register
keeps MIN(w), exactly. Portable draws are digits of md5, the register from digits that the draw does
not use; fast ones are xxhash64 under two seeds.
"""

from __future__ import annotations

import zlib

from pyspark.sql import Column
from pyspark.sql import functions as F

from evsketch.spec import SketchSpec


def _hex(text: Column, start: int, digits: int) -> Column:
    return F.conv(F.substring(text, start, digits), 16, 10).cast("long")


def _seeded(spec: SketchSpec, what: str, item: Column) -> Column:
    """64-bit fast hash of an item for one purpose."""
    return F.xxhash64(F.lit(zlib.crc32(f"{spec.seed}{what}".encode())), item)


def _digest(spec: SketchSpec, item: Column, tag: str = "") -> Column:
    return F.md5(F.concat(F.lit(f"{spec.seed}{tag}:"), item.cast("string")).cast("binary"))


def draw(spec: SketchSpec, item: Column, tag: str = "") -> Column:
    """w of an item."""
    if spec.family == "portable":
        return _hex(_digest(spec, item, tag), 1, 13)
    return F.shiftrightunsigned(_seeded(spec, f"#draw{tag}", item), 1)


def register(spec: SketchSpec, item: Column) -> Column:
    """The register (0..k-1) of an item, independent of its draw."""
    if spec.family == "portable":
        return F.pmod(_hex(_digest(spec, item), 17, 8), F.lit(spec.k)).cast("int")
    return F.pmod(_seeded(spec, "#reg", item), F.lit(spec.k)).cast("int")


def full_draw(spec: SketchSpec, item: Column, i: Column | int, mode: str = "rehash") -> Column:
    """w of an item for register i of a full sketch: a hash of its own (``rehash``), or ``linear``:
    two hashes of the item combined as h1 + (i + 1) * h2."""
    number = F.lit(i) if isinstance(i, int) else i
    if mode == "linear":
        if spec.family == "portable":  # 52-bit steps; products stay below 2**63 for k up to 2047
            d = _digest(spec, item)
            return F.pmod(_hex(d, 1, 13) + (number + 1).cast("long") * _hex(d, 14, 13), F.lit(1 << 52))
        one, step = F.shiftrightunsigned(_seeded(spec, "#one", item), 2), F.shiftrightunsigned(_seeded(spec, "#two", item), 2)
        i_, low31, low62 = (number + 1).cast("long"), F.lit((1 << 31) - 1), F.lit((1 << 62) - 1)
        high = F.shiftleft((i_ * F.shiftright(step, 31)).bitwiseAND(low31), 31)  # 62-bit product by halves
        product = (high + i_ * step.bitwiseAND(low31)).bitwiseAND(low62)
        return F.shiftleft((one + product).bitwiseAND(low62), 1)
    if spec.family == "portable":
        return _hex(F.md5(F.concat(F.lit(f"{spec.seed}/"), number.cast("string"), F.lit(":"), item.cast("string")).cast("binary")), 1, 13)
    return F.shiftrightunsigned(F.xxhash64(_seeded(spec, "#full", item), number), 1)


def seed_draw(spec: SketchSpec, reg: Column) -> Column:
    """The draw a seeded register starts with: a function of (seed, register), so merging repeats it harmlessly."""
    if spec.family == "portable":
        return _hex(_digest(spec, reg, "#reg"), 1, 13)
    return F.shiftrightunsigned(_seeded(spec, "#start", reg), 1)


def offset(spec: SketchSpec, reg: Column) -> Column:
    """The shift c in [0, 1) of a register; recomputed, never stored."""
    if spec.family == "portable":
        return _hex(_digest(spec, reg, "#off"), 1, 13) / F.lit(float(1 << 52))
    return F.pmod(_seeded(spec, "#off", reg), F.lit(1 << 52)) / F.lit(float(1 << 52))
