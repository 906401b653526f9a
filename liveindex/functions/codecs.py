"""Codecs in numpy: byte code, paired code, interpolative code, blocks of bit-packed integers.

All work on whole arrays. A byte-code number ends with the byte whose top bit is set, so zeros that fill the rest of
a block belong to no number.
"""

from __future__ import annotations

import numpy as np

_LIMITS = np.array([1 << (7 * k) for k in range(1, 9)], np.int64)


def vbyte_lens(x: np.ndarray) -> np.ndarray:
    return np.searchsorted(_LIMITS, x, side="right") + 1


def vbyte_encode(x: np.ndarray) -> np.ndarray:
    """Bytes of all numbers, one after the other."""
    x = np.asarray(x, np.int64)
    sizes = vbyte_lens(x)
    ends = np.cumsum(sizes)
    number = np.repeat(np.arange(x.size), sizes)
    at = np.arange(ends[-1] if x.size else 0) - (ends - sizes)[number]
    out = ((x[number] >> (7 * at)) & 0x7F).astype(np.uint8)
    out[ends - 1] |= 0x80
    return out


def vbyte_decode(data: np.ndarray) -> np.ndarray:
    data = np.asarray(data, np.uint8)
    ends = np.flatnonzero(data & 0x80)
    if not ends.size:
        return np.zeros(0, np.int64)
    starts = np.concatenate(([0], ends[:-1] + 1))
    data = data[: ends[-1] + 1]
    at = np.arange(data.size) - np.repeat(starts, ends - starts + 1)
    return np.add.reduceat((data & 0x7F).astype(np.int64) << (7 * at), starts)


def pair_numbers(a: np.ndarray, b: np.ndarray, f: int) -> tuple[np.ndarray, np.ndarray]:
    """The numbers that say the pairs, and how many each pair takes (1 or 2)."""
    a, b = np.asarray(a, np.int64), np.asarray(b, np.int64)
    two = b >= f
    count = 1 + two.astype(np.int64)
    at = np.cumsum(count) - count
    out = np.empty(int(count.sum()), np.int64)
    out[at] = np.where(two, a * f, (a - 1) * f + b)
    out[at[two] + 1] = b[two] - f + 1
    return out, count


def pair_lens(a: np.ndarray, b: np.ndarray, f: int) -> np.ndarray:
    a, b = np.asarray(a, np.int64), np.asarray(b, np.int64)
    two = b >= f
    return vbyte_lens(np.where(two, a * f, (a - 1) * f + b)) + np.where(two, vbyte_lens(np.maximum(b - f + 1, 0)), 0)


def pair_encode(a: np.ndarray, b: np.ndarray, f: int) -> np.ndarray:
    return vbyte_encode(pair_numbers(a, b, f)[0])


def pair_decode(data: np.ndarray, f: int) -> tuple[np.ndarray, np.ndarray]:
    """Pairs of a payload. What a number is depends on the one before: a number that F divides has a second one
    behind it - unless it is itself such a second one. Runs of divisible numbers settle that by their parity."""
    x = vbyte_decode(data)
    whole = x % f == 0
    index = np.arange(x.size)
    run = index - np.maximum.accumulate(np.where(whole, -1, index))  # how far into a run of divisible numbers
    head = whole & (run % 2 == 1)
    second = np.zeros(x.size, bool)
    second[1:] = head[:-1]
    first = x[~second]
    two = head[~second]
    a, b = np.where(two, first // f, first // f + 1), first % f
    b[two] = x[second] + f - 1
    return a, b


def bits_of(x: np.ndarray) -> np.ndarray:
    """Bits of the largest set bit; 0 for 0."""
    return np.where(x > 0, np.floor(np.log2(np.maximum(x, 1).astype(np.float64))).astype(np.int64) + 1, 0)


def bp_encode(x: np.ndarray, block: int = 128) -> bytes:
    """Blocks of `block` numbers, each block a width byte and the numbers in that many bits; what remains in byte code."""
    x = np.asarray(x, np.int64)
    full = x.size // block
    out = [np.array([full & 0xFF, full >> 8 & 0xFF, full >> 16 & 0xFF, full >> 24], np.uint8)]
    for part in x[: full * block].reshape(full, block):
        width = int(bits_of(part.max(keepdims=True))[0])
        out.append(np.array([width], np.uint8))
        if width:
            out.append(np.packbits((part[:, None] >> np.arange(width)) & 1, bitorder="little"))
    out.append(vbyte_encode(x[full * block :]))
    return np.concatenate(out).astype(np.uint8).tobytes()


def bp_decode(data: bytes, block: int = 128) -> np.ndarray:
    raw = np.frombuffer(data, np.uint8)
    full, at, out = int.from_bytes(data[:4], "little"), 4, []
    for _ in range(full):
        width = int(raw[at])
        size = block * width // 8
        bits = np.unpackbits(raw[at + 1 : at + 1 + size], bitorder="little").reshape(block, width).astype(np.int64)
        out.append(bits @ (np.int64(1) << np.arange(width)) if width else np.zeros(block, np.int64))
        at += 1 + size
    return np.concatenate([*out, vbyte_decode(raw[at:])])


def _centres(low: int, high: int, count: int):
    """(index, least, most) in the order in which interpolative coding says the numbers: middles of ever smaller ranges.

    A generator: the caller sends the number at the index back, which bounds the ranges on both sides of it."""
    waiting = [(0, count, low, high)]
    while waiting:
        first, n, lo, hi = waiting.pop()
        if not n:
            continue
        half = n // 2
        value = yield first + half, lo + half, hi - (n - 1 - half)
        waiting.append((first + half + 1, n - half - 1, value + 1, hi))
        waiting.append((first, half, lo, value - 1))


def interp_encode(x: list[int], low: int, high: int) -> list[tuple[int, int]]:
    """(value, bits) of strictly ascending numbers within [low, high]; a number that has one possible value takes none.

    Bits are of the truncated binary code: short codes for the first values of a range."""
    out, walk = [], _centres(low, high, len(x))
    try:
        at = next(walk)
        while True:
            index, least, most = at
            size, value = most - least + 1, x[index] - least
            width = (size - 1).bit_length()
            spare = (1 << width) - size
            out.append((value, width - 1) if value < spare else (value + spare, width))
            at = walk.send(x[index])
    except StopIteration:
        return out


def interp_bits(x: list[int], low: int, high: int) -> int:
    return sum(bits for _, bits in interp_encode(x, low, high))


def interp_decode(codes: list[tuple[int, int]], count: int, low: int, high: int) -> list[int]:
    """Numbers from the codes' bit string, read from the front."""
    text = "".join(format(v, f"0{n}b") if n else "" for v, n in codes)
    out, at, walk = [0] * count, 0, _centres(low, high, count)
    try:
        step = next(walk)
        while True:
            index, least, most = step
            size = most - least + 1
            width = (size - 1).bit_length()
            spare, value = (1 << width) - size, 0
            if width:
                value = int(text[at : at + width - 1] or "0", 2)
                at += width - 1
                if value >= spare:
                    value = value * 2 + int(text[at]) - spare
                    at += 1
            out[index] = least + value
            step = walk.send(out[index])
    except StopIteration:
        return out
