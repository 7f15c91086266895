"""Counter-based uniform integers below 2**52: equal on Spark, in Python and in SQL, and unchanged by retries."""

from __future__ import annotations

import hashlib
from collections.abc import Sequence
from math import floor, sin

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

BITS = 52


def _hex_int(text: Column, digits: int) -> Column:
    return F.conv(F.substring(F.md5(text), 1, digits), 16, 10).cast("long")


def u52(*parts: Column | str | int) -> Column:
    """Uniform integer in [0, 2**52) of the parts; strings are constants, columns vary."""
    cols = [p.cast("string") if isinstance(p, Column) else F.lit(str(p)) for p in parts]
    return _hex_int(F.concat_ws(":", *cols), 13)


def hash60(*parts: Column) -> Column:
    """Integer of 60 bits of the md5 of the parts, for surrogate keys."""
    return _hex_int(F.concat_ws(":", *[p.cast("string") for p in parts]), 15)


def u52_py(*parts: object) -> int:
    return int(hashlib.md5(":".join(map(str, parts)).encode()).hexdigest()[:13], 16)


def u52_many(parts: Sequence[object], last: Sequence[str]) -> np.ndarray:
    """The integers of many last parts behind common ones."""
    common, out = hashlib.md5("".join(f"{p}:" for p in parts).encode()), []
    for text in last:
        each = common.copy()
        each.update(text.encode())
        out.append(each.digest())
    return (np.frombuffer(b"".join(out), ">u8")[::2] >> np.uint64(64 - BITS)).astype(np.int64)


#: Steps of the digest: rotations, constants, and the word of the message that each takes.
_TURN = [t for four in ((7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21)) for t in four * 4]
_SINE = [floor(abs(sin(i + 1)) * (1 << 32)) for i in range(64)]
_WORD = [*range(16), *((5 * i + 1) % 16 for i in range(16)), *((3 * i + 5) % 16 for i in range(16)), *((7 * i) % 16 for i in range(16))]
_START = (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)
#: Digits of the largest id, and the least ids of two digits and more.
_DIGITS, _POWERS = 19, 10 ** np.arange(1, 19)
#: Longest message of one block of the digest, and messages that go through the steps together.
_LONGEST, _LANES = 55, 10_000


def spell(ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Integers that are not negative: rows of decimal characters, each closed by the mark that ends a message, and numbers of digits."""
    text, high = np.empty((_DIGITS, len(ids)), np.uint8), ids
    for last in range(_DIGITS, 0, -9):  # nine digits at a time, as short integers
        over = high // 10**9
        rest, high = (high - over * 10**9).astype(np.uint32), over
        for j in range(last - 1, max(last - 10, -1), -1):
            less = rest // np.uint32(10)
            text[j] = rest - np.uint32(10) * less + np.uint32(ord("0"))
            rest = less
    text, length = np.ascontiguousarray(text.T), np.searchsorted(_POWERS, ids, side="right") + 1
    out = np.zeros((len(ids), _DIGITS + 1), np.uint8)
    for n in np.unique(length).tolist():
        at = np.flatnonzero(length == n)
        out[at, :n] = text[at, _DIGITS - n :]
        out[at, n] = 0x80
    return out, length


def _digest(words: list, n: int) -> np.ndarray:
    """The first 64 bits of md5 of n messages of one block; a word is a number where all messages share it."""
    a, b, c, d = (np.full(n, x, np.uint32) for x in _START)
    t, u = np.empty(n, np.uint32), np.empty(n, np.uint32)
    for i in range(64):
        if i < 16:
            np.bitwise_xor(c, d, out=t)
            t &= b
            t ^= d
        elif i < 32:
            np.bitwise_xor(b, c, out=t)
            t &= d
            t ^= c
        elif i < 48:
            np.bitwise_xor(b, c, out=t)
            t ^= d
        else:
            np.invert(d, out=t)
            t |= b
            t ^= c
        t += a
        word = words[_WORD[i]]
        if isinstance(word, int):
            t += np.uint32((_SINE[i] + word) & 0xFFFFFFFF)
        else:
            t += word
            t += np.uint32(_SINE[i])
        np.left_shift(t, np.uint32(_TURN[i]), out=u)
        t >>= np.uint32(32 - _TURN[i])
        t |= u
        t += b
        a, b, c, d, t = d, t, b, c, a
    high, low = ((x + np.uint32(s)).byteswap().astype(np.uint64) for x, s in ((a, _START[0]), (b, _START[1])))
    return high << np.uint64(32) | low


def u52_spelled(parts: Sequence[object], spelled: tuple[np.ndarray, np.ndarray]) -> np.ndarray:
    """``u52_many`` of ids that ``spell`` has taken apart, many messages a step of the digest."""
    common = "".join(f"{p}:" for p in parts).encode()
    text, length = spelled
    if not len(text):
        return np.empty(0, np.int64)
    widest = int(length.max())
    if len(common) + widest > _LONGEST:
        return u52_many(parts, [bytes(row[:n]).decode() for row, n in zip(text, length, strict=True)])
    first, last, out = len(common) // 4, (len(common) + widest) // 4, []
    head = len(common) - 4 * first
    fixed = [int.from_bytes(common[4 * i : 4 * i + 4], "little") for i in range(first)]
    for low in range(0, len(text), _LANES):
        few = text[low : low + _LANES, : widest + 1]
        laid = np.zeros((len(few), 4 * (last + 1 - first)), np.uint8)
        laid[:, :head] = np.frombuffer(common[4 * first :], np.uint8)
        laid[:, head : head + widest + 1] = few
        words = [*fixed, *np.ascontiguousarray(laid.view("<u4").T.astype(np.uint32)), *[0] * (15 - last)]
        words[14] = (8 * (len(common) + length[low : low + _LANES])).astype(np.uint32)
        out.append(_digest(words, len(few)) >> np.uint64(64 - BITS))
    return np.concatenate(out).astype(np.int64)


def u52_sql(*parts: str) -> str:
    """The same in DuckDB; parts are SQL expressions."""
    return f"CAST('0x' || substr(md5(concat_ws(':', {', '.join(parts)})), 1, 13) AS BIGINT)"


def place_of(key: Column) -> Column:
    """Place of a key in [0, 2**52): a hash that orders rows; the same at any number of partitions."""
    return _hex_int(key.cast("string"), 13)


def place_sql(key: str) -> str:
    return f"CAST('0x' || substr(md5(CAST({key} AS VARCHAR)), 1, 13) AS BIGINT)"


def bucket_of(key: Column, buckets: int) -> Column:
    """Hash bucket of a key; the same at any number of partitions."""
    return F.pmod(_hex_int(key.cast("string"), 8), F.lit(buckets)).cast("int")
