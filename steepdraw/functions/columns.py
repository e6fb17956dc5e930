"""Column expressions: hash uniforms, vectors, losses, slopes and gradient lengths."""

from __future__ import annotations

import hashlib
import math
from functools import cache

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

SPAN = float(1 << 48)


def hash_uniform(*parts: Column | str | int) -> Column:
    """Uniform in (0, 1) from the MD5 of the parts joined by colons: the same in every engine."""
    text = F.concat_ws(":", *[p.cast("string") if isinstance(p, Column) else F.lit(str(p)) for p in parts])
    return (F.conv(F.substring(F.md5(text), 1, 12), 16, 10).cast("long") + F.lit(0.5)) / F.lit(SPAN)


def py_uniform(*parts: object) -> float:
    """The same number without Spark."""
    return (int.from_bytes(hashlib.md5(":".join(map(str, parts)).encode()).digest()[:6], "big") + 0.5) / SPAN


def py_uniforms(seed: int, step: int, count: int) -> list[float]:
    """py_uniform(seed, step, j) for j below count."""
    begun = hashlib.md5(f"{seed}:{step}:".encode())
    out = []
    for j in range(count):
        own = begun.copy()
        own.update(b"%d" % j)
        out.append((int.from_bytes(own.digest()[:6], "big") + 0.5) / SPAN)
    return out


@cache
def _md5_plan() -> tuple[list, list, list]:
    """Added constant, word and turn of each of MD5's 64 rounds."""
    word = [k for k in range(16)] + [(5 * k + 1) % 16 for k in range(16)] + [(3 * k + 5) % 16 for k in range(16)] + [7 * k % 16 for k in range(16)]
    turn = [t for four in ((7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21)) for t in four * 4]
    return [int(abs(math.sin(k + 1)) * 2**32) for k in range(64)], word, turn


def _md5_heads(words: list[np.ndarray | int], shape: tuple[int, int]) -> tuple[np.ndarray, np.ndarray]:
    """First two words of the MD5 of messages of one block each."""
    add, word, turn = _md5_plan()
    start = (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)
    a, b, c, d = (np.full(shape, v, np.uint32) for v in start)
    f, low = np.empty(shape, np.uint32), np.empty(shape, np.uint32)
    for k in range(64):
        if k < 16:
            np.bitwise_xor(c, d, out=f)
            f &= b
            f ^= d
        elif k < 32:
            np.bitwise_xor(b, c, out=f)
            f &= d
            f ^= c
        elif k < 48:
            np.bitwise_xor(b, c, out=f)
            f ^= d
        else:
            np.invert(d, out=f)
            f |= b
            f ^= c
        own = words[word[k]]
        f += a
        if isinstance(own, int):
            f += np.uint32((own + add[k]) & 0xFFFFFFFF)
        else:
            f += own
            f += np.uint32(add[k])
        np.right_shift(f, np.uint32(32 - turn[k]), out=low)
        np.left_shift(f, np.uint32(turn[k]), out=f)
        f |= low
        f += b
        a, b, c, d, f = d, f, b, c, a
    return a + np.uint32(start[0]), b + np.uint32(start[1])


CHUNK = 1 << 16  # messages hashed together: many for a call, few for the caches


def head_uniforms(heads: list[bytes], count: int) -> np.ndarray:
    """Uniforms of the MD5 of each head (rows) followed by each j below count, all messages of a length at once."""
    out = np.empty((len(heads), count))
    sizes = np.fromiter(map(len, heads), np.int64, len(heads))
    for length in np.unique(sizes).tolist():
        own = np.flatnonzero(sizes == length)
        j = 0
        while j < count:
            width = len(str(j))
            upto = min(count, 10**width)
            size = length + width
            if size > 55:  # beyond one block
                for i in own.tolist():
                    out[i, j:upto] = [(int.from_bytes(hashlib.md5(heads[i] + b"%d" % k).digest()[:6], "big") + 0.5) / SPAN for k in range(j, upto)]
                j = upto
                continue
            right = np.zeros((upto - j, 64), np.uint8)
            right[:, length:size] = np.frombuffer(b"".join(b"%d" % i for i in range(j, upto)), np.uint8).reshape(-1, width)
            right[:, size] = 0x80
            right = right.view("<u4")
            many = max(1, CHUNK // (upto - j))
            for at in range(0, len(own), many):
                some = own[at : at + many]
                left = np.zeros((len(some), 64), np.uint8)
                left[:, :length] = np.frombuffer(b"".join([heads[i] for i in some.tolist()]), np.uint8).reshape(len(some), -1)
                left = left.view("<u4")
                words: list = [left[:, k, None] | right[None, :, k] if 4 * k <= size else 0 for k in range(16)]
                words[14] = 8 * size
                a, b = _md5_heads(words, (len(some), upto - j))
                high, low = a.byteswap().astype(np.int64), b.byteswap().astype(np.int64)
                out[some, j:upto] = ((high << 16 | low >> 16) + 0.5) / SPAN
            j = upto
    return out


def block_uniforms(seed: object, first: int, steps: int, count: int) -> np.ndarray:
    """py_uniform(seed, t, j) for `steps` steps from `first` on (rows) and j below count."""
    return head_uniforms([f"{seed}:{t}:".encode() for t in range(first, first + steps)], count)


def dot(xs: list[Column], ws: list[float]) -> Column:
    """Unrolled product with a constant vector: stays inside generated code."""
    out = F.lit(0.0)
    for x, w in zip(xs, ws, strict=True):
        out = out + x * F.lit(float(w))
    return out


def sq_norm(xs: list[Column]) -> Column:
    out = F.lit(0.0)
    for x in xs:
        out = out + x * x
    return out


def array_dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, v: s + v)


def loss(kind: str, score: Column, label: Column) -> Column:
    margin = score * label
    if kind == "squared":
        return (score - label) * (score - label)
    if kind == "hinge":
        return F.greatest(F.lit(0.0), 1.0 - margin)
    if kind == "logistic":  # the exponent never overflows
        return F.log1p(F.exp(-F.abs(margin))) + F.greatest(-margin, F.lit(0.0))
    if kind == "zero_one":
        return F.when(F.when(score >= 0, 1.0).otherwise(-1.0) == label, 0.0).otherwise(1.0)
    raise ValueError(kind)


def slope(kind: str, score: Column, label: Column) -> Column:
    """Derivative of the loss in the score."""
    margin = score * label
    if kind == "squared":
        return 2.0 * (score - label)
    if kind == "hinge":
        return F.when(margin < 1.0, -label).otherwise(0.0)
    if kind == "logistic":
        return -label * sigmoid(-margin)
    raise ValueError(kind)


def sigmoid(z: Column) -> Column:
    small = F.exp(-F.abs(z))
    return F.when(z >= 0, 1.0 / (1.0 + small)).otherwise(small / (1.0 + small))


def length(kind: str, score: Column, label: Column, squared_norm: Column) -> Column:
    """Length of a row's loss gradient for linear models: |slope| times the row's norm."""
    return F.abs(slope(kind, score, label)) * F.sqrt(squared_norm)


def probability(score: Column, label: Column) -> Column:
    return sigmoid(score * label)


def entropy(p: Column) -> Column:
    term = lambda q: F.when(q > 0, -q * F.log(q)).otherwise(0.0)
    return term(p) + term(1.0 - p)
