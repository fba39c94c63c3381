"""Packed node entries: two flags, a 22-bit child-group pointer and a 40-bit payload in one long."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

IN_BUFFER, HAS_BRICK = 1, 2
POINTER_BITS, PAYLOAD_BITS, ADDRESS_BITS = 22, 40, 32
USED, REQUESTED = 1, 2


def payload_bits(channels: int) -> int:
    """Bits of the payload that each channel's average gets."""
    return PAYLOAD_BITS // channels


def lost_bits(channels: int, dtype_bits: int = 16) -> int:
    return max(0, dtype_bits - payload_bits(channels))


def pack_averages(averages: list[Column], dtype_bits: int = 16) -> Column:
    width, drop = payload_bits(len(averages)), lost_bits(len(averages), dtype_bits)
    out = F.lit(0).cast("long")
    for i, a in enumerate(averages):
        out = out.bitwiseOR(F.shiftleft(F.shiftright(a.cast("long"), drop), width * i))
    return out


def unpack_average(payload: Column, channel: int, channels: int, dtype_bits: int = 16) -> Column:
    width, drop = payload_bits(channels), lost_bits(channels, dtype_bits)
    return F.shiftleft(F.shiftright(payload, width * channel).bitwiseAND(F.lit((1 << width) - 1)), drop)


def encode_node(in_buffer: Column, has_brick: Column, child_group: Column, payload: Column) -> Column:
    """The node word; ``child_group`` 0 means no children, else the parent's breadth-first number plus one.

    The fields are added.  A group beyond ``POINTER_BITS`` (trees of more than nine levels) carries into the payload: such
    words still follow from their node and tell versions apart, but cannot be decoded; ``encode_wide`` has eight bits more.
    """
    flags = F.when(in_buffer, IN_BUFFER).otherwise(0).bitwiseOR(F.when(has_brick, HAS_BRICK).otherwise(0)).cast("long")
    return flags + F.shiftleft(child_group.cast("long"), 2) + F.shiftleft(payload, 2 + POINTER_BITS)


def decode_node(word: Column) -> dict[str, Column]:
    return {
        "in_buffer": word.bitwiseAND(F.lit(IN_BUFFER).cast("long")),
        "has_brick": F.shiftright(word.bitwiseAND(F.lit(HAS_BRICK).cast("long")), 1),
        "child_group": F.shiftright(word, 2).bitwiseAND(F.lit((1 << POINTER_BITS) - 1).cast("long")),
        "payload": F.shiftrightunsigned(word, 2 + POINTER_BITS),
    }


def brick_address(payload: Column) -> Column:
    return payload.bitwiseAND(F.lit((1 << ADDRESS_BITS) - 1))


def encode_wide(in_buffer: Column, has_brick: Column, child_group: Column, averages: list[Column]) -> Column:
    """A 128-bit entry for more than four channels or fractional averages: ``lo`` holds flags and pointer, and four
    bytes of the payload; ``hi`` the other eight.

    The twelve bytes are dealt out equally; averages of up to three channels are kept as 32-bit floats.
    """
    if len(averages) <= 3:
        parts = [(_float_bits(a), 32) for a in averages]
    else:
        width = 96 // len(averages)
        parts = [(a.cast("long").bitwiseAND(F.lit((1 << min(width, 62)) - 1).cast("long")), width) for a in averages]
    lo = encode_node(in_buffer, has_brick, child_group, F.lit(0).cast("long"))
    hi, at = F.lit(0).cast("long"), 0
    for value, width in parts:
        # bits 0..31 of the payload lie in the upper half of ``lo``, the others in ``hi``
        if at < 32:
            lo = lo.bitwiseOR(F.shiftleft(value, 32 + at))
        if at + width > 32:
            hi = hi.bitwiseOR(F.shiftleft(value, at - 32) if at >= 32 else F.shiftrightunsigned(value, 32 - at))
        at += width
    return F.struct(lo.alias("lo"), hi.alias("hi"))


def decode_wide(entry: Column, channels: int) -> list[Column]:
    """The averages of a 128-bit entry: floats for up to three channels, else integers."""
    lo, hi = entry["lo"], entry["hi"]
    width = 32 if channels <= 3 else 96 // channels
    out = []
    for c in range(channels):
        at = width * c
        bits = F.lit(0).cast("long")
        if at < 32:
            bits = F.shiftrightunsigned(lo, 32 + at)
        if at + width > 32:
            bits = bits.bitwiseOR(F.shiftrightunsigned(hi, at - 32) if at >= 32 else F.shiftleft(hi, 32 - at))
        bits = bits.bitwiseAND(F.lit((1 << min(width, 62)) - 1).cast("long"))
        out.append(_bits_float(bits) if channels <= 3 else bits)
    return out


def _float_bits(value: Column) -> Column:
    """Bits of a non-negative fraction as a 32-bit float: 8 bits of exponent, 23 of fraction; 0 stays 0."""
    v = value.cast("float").cast("double")
    exponent = F.floor(F.log2(v))
    whole = F.shiftleft((exponent + 127).cast("long"), 23)
    fraction = F.round((v / F.pow(F.lit(2.0), exponent) - 1) * (1 << 23)).cast("long")
    return F.when(v > 0, whole + fraction).otherwise(F.lit(0).cast("long"))


def _bits_float(bits: Column) -> Column:
    exponent = F.shiftright(bits, 23).cast("int") - 127
    return F.when(bits == 0, 0.0).otherwise((1 + bits.bitwiseAND(F.lit((1 << 23) - 1).cast("long")) / (1 << 23)) * F.pow(F.lit(2.0), exponent))
