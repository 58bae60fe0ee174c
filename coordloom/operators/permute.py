"""Orders over bucket numbers as computed keys: md5, a Feistel bijection, an affine map. None builds a list of all numbers."""

from __future__ import annotations

import hashlib
import math

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

ORDERS = ("md5", "feistel", "affine", "none")
ROUNDS = 4
PRIME = 2**31 - 1
MULT = 48271


def _constants(n: int, epoch: int, seed: int) -> tuple[int, list[tuple[int, int]]]:
    m = max(1, math.isqrt(max(0, n - 1)) + 1)
    out = []
    for r in range(ROUNDS):
        d = hashlib.md5(f"{r}:{epoch}:{seed}".encode()).digest()
        out.append((1 + int.from_bytes(d[:4], "big") % (PRIME - 1), int.from_bytes(d[4:8], "big") % PRIME))
    return m, out


def feistel(x: np.ndarray, n: int, epoch: int, seed: int) -> np.ndarray:
    """A bijection of 0..n-1, by rounds on (x div m, x mod m) with m near the root of n; values of n or more walk on."""
    m, constants = _constants(n, epoch, seed)

    def once(v):
        left, right = v // m, v % m
        for a, c in constants:
            left, right = right, (left + (((right * a + c) % PRIME) * MULT % PRIME) % m) % m
        return left * m + right

    out = once(np.asarray(x, dtype=np.int64))
    while (far := out >= n).any():
        out = np.where(far, once(out), out)
    return out


WALKS = 24


def feistel_col(x: Column, n: int, epoch: int, seed: int) -> Column:
    """The same bijection in column arithmetic; m * m is at most (root + 1)^2, so walks are short: each leaves n with a chance of about 2 / root(n)."""
    m, constants = _constants(n, epoch, seed)

    def turn(a: int, c: int):
        return lambda p: F.struct(p["r"].alias("l"), ((p["l"] + (((p["r"] * a + c) % PRIME) * MULT % PRIME) % m) % m).alias("r"))

    def once(v: Column) -> Column:
        pair = F.struct(F.floor(v / m).cast("long").alias("l"), (v % m).alias("r"))
        for a, c in constants:  # through a one-element array, so that each half is computed once and used twice
            pair = F.transform(F.array(pair), turn(a, c))[0]
        return F.transform(F.array(pair), lambda p: p["l"] * m + p["r"])[0]

    steps = F.sequence(F.lit(1), F.lit(WALKS))
    return F.aggregate(steps, once(x.cast("long")), lambda acc, _: F.when(acc >= n, once(acc)).otherwise(acc))


def affine_constants(n: int, epoch: int, seed: int) -> tuple[int, int]:
    """(a, c) with a prime to n."""
    a = 1 + (7919 * (epoch + 1) + 104729 * seed) % max(1, n)
    while math.gcd(a, n) != 1:
        a += 1
    return a, (31 * (epoch + 1) + seed) % max(1, n)


def key(number: Column, epoch: int, seed: int, order: str, n: int) -> Column:
    """A sort key for the epoch. ``affine`` and ``feistel`` keys are ranks themselves."""
    if order == "md5":
        return F.md5(F.concat_ws(":", number.cast("string"), F.lit(str(epoch)), F.lit(str(seed))))
    if order == "feistel":
        return feistel_col(number, n, epoch, seed)
    if order == "affine":
        a, c = affine_constants(n, epoch, seed)
        return (number * a + c) % n
    if order == "none":
        return number
    raise ValueError(f"unknown order {order!r}")


def keys_of(numbers: np.ndarray, epoch: int, seed: int, order: str, n: int) -> list:
    """The keys of ``key`` in numpy and Python."""
    if order == "md5":
        return [hashlib.md5(f"{k}:{epoch}:{seed}".encode()).hexdigest() for k in numbers.tolist()]
    if order == "feistel":
        return feistel(numbers, n, epoch, seed).tolist()
    if order == "affine":
        a, c = affine_constants(n, epoch, seed)
        return [(k * a + c) % n for k in numbers.tolist()]
    return numbers.tolist()


_TURNS = np.array([7, 12, 17, 22, 5, 9, 14, 20, 4, 11, 16, 23, 6, 10, 15, 21]).reshape(4, 4)
_SINES = [int(abs(math.sin(k + 1)) * 2**32) for k in range(64)]
_START = (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)
#: Numbers hashed at a time, so that the work stays in cache.
_AT_ONCE = 1 << 13


def _md5_block(words: list) -> np.ndarray:
    """The digests (rows of 4 little-endian words) of messages of one block; a word is an array, or an integer that all share."""
    a, b, c, d = (np.uint32(x) for x in _START)
    for k in range(64):
        if k < 16:
            f, g = d ^ (b & (c ^ d)), k
        elif k < 32:
            f, g = c ^ (d & (b ^ c)), (5 * k + 1) % 16
        elif k < 48:
            f, g = b ^ c ^ d, (3 * k + 5) % 16
        else:
            f, g = c ^ (b | ~d), 7 * k % 16
        word, turn = words[g], int(_TURNS[k // 16, k % 4])
        x = np.add(a, f)
        x = x + np.uint32((word + _SINES[k]) & 0xFFFFFFFF) if isinstance(word, int) else x + word + np.uint32(_SINES[k])
        a, d, c, b = d, c, b, b + ((x << np.uint32(turn)) | (x >> np.uint32(32 - turn)))
    return np.stack([x + np.uint32(s) for x, s in zip((a, b, c, d), _START, strict=True)], axis=1)


def md5_columns(numbers: np.ndarray, tail: bytes) -> tuple[np.ndarray, np.ndarray]:
    """The md5 of each number (0 or more) in decimal digits with ``tail`` behind, as two big-endian halves; as hashlib gives it, without work by number."""
    numbers = np.asarray(numbers, dtype=np.int64)
    if not len(numbers):
        return np.empty(0, np.uint64), np.empty(0, np.uint64)
    if numbers.min() < 0 or len(tail) > 36:  # 19 digits and the tail fill one block
        out = np.frombuffer(b"".join([hashlib.md5(b"%d%b" % (k, tail)).digest() for k in numbers.tolist()]), dtype=">u8").astype(np.uint64).reshape(-1, 2)
        return out[:, 0], out[:, 1]
    out = np.empty((len(numbers), 2), np.uint64)
    digits = np.searchsorted(10 ** np.arange(1, 19, dtype=np.int64), numbers, side="right") + 1
    for size in np.unique(digits).tolist():
        places = np.flatnonzero(digits == size)
        message = np.zeros(64, np.uint8)
        message[size : size + len(tail)] = np.frombuffer(tail, np.uint8)
        message[size + len(tail)] = 0x80
        message[56:] = np.frombuffer((8 * (size + len(tail))).to_bytes(8, "little"), np.uint8)
        fixed = message.view("<u4").tolist()
        for lo in range(0, len(places), _AT_ONCE):
            now = places[lo : lo + _AT_ONCE]
            left, words = numbers[now], list(fixed)
            for k in range(size - 1, -1, -1):
                left, digit = np.divmod(left, 10)
                words[k // 4] = words[k // 4] + ((digit + 48).astype(np.uint32) << np.uint32(8 * (k % 4)))
            with np.errstate(over="ignore"):
                out[now] = _md5_block(words).view(">u8")
    return out[:, 0], out[:, 1]


def key_columns(numbers: np.ndarray, epoch: int, seed: int, order: str, n: int) -> tuple[np.ndarray, ...]:
    """``keys_of`` as columns of integers that sort in the same way, the leading one first."""
    if order == "md5":
        return md5_columns(numbers, f":{epoch}:{seed}".encode())
    return (np.asarray(keys_of(numbers, epoch, seed, order, n), dtype=np.int64),)


def inside_rows(bids: np.ndarray, sizes: np.ndarray, seed: int) -> np.ndarray:
    """A drawn order of the examples inside each row: places in the rows laid end to end, row after row."""
    row = np.repeat(np.arange(len(bids)), sizes)
    place = np.arange(len(row)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
    x = np.asarray(bids).astype(np.uint64)[row] * np.uint64(0x9E3779B97F4A7C15) + place.astype(np.uint64) * np.uint64(0xD1B54A32D192ED03) + np.uint64((seed * 0x2545F4914F6CDD1D) % (1 << 64))
    for shift, factor in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
        x = (x ^ (x >> np.uint64(shift))) * np.uint64(factor)
    return np.lexsort((x ^ (x >> np.uint64(31)), row))
