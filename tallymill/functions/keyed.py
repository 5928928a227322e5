"""Uniforms that are functions of a seed and a record's identity, so retries redraw the same."""

from __future__ import annotations

from hashlib import md5
from math import sin

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column
from pyspark.sql import functions as F

SCALE = float(1 << 52)


def uniform(*parts: Column | str | int) -> Column:
    """From 0 to 1, exclusive: 13 hexadecimal digits of the md5 of the parts joined by bars."""
    cols = [x if isinstance(x, Column) else F.lit(str(x)) for x in parts]
    digest = F.md5(F.concat_ws("|", *[c.cast("string") for c in cols]).cast("binary"))
    return F.conv(F.substring(digest, 1, 13), 16, 10).cast("long") / F.lit(SCALE)


def uniform_sql(*parts: str) -> str:
    """The same in DuckDB; parts are SQL expressions."""
    return f"(('0x' || substr(md5(concat_ws('|', {', '.join(parts)})), 1, 13))::BIGINT / {SCALE!r})"


def uniform_py(*parts: object) -> float:
    return int(md5("|".join(map(str, parts)).encode()).hexdigest()[:13], 16) / SCALE


#: Additions and rotations of MD5's 64 steps.
_ADDED = [int(abs(sin(i + 1)) * (1 << 32)) for i in range(64)]
_TURNED = [x for four in ((7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21)) for x in four * 4]
#: Messages hashed at once: few enough for a core's cache, enough to outweigh numpy's calls.
_AT_ONCE = 1 << 15


def _digest_start(words: np.ndarray, fixed: dict[int, int]) -> np.ndarray:
    """First 52 bits of the MD5 of messages of one block each: words[j] has the j-th word of every
    message, fixed those further words that are the same in all and not zero."""
    state = [np.full(words.shape[1], x, np.uint32) for x in (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)]
    first, second = state[0][0], state[1][0]
    a, b, c, d = state
    f = np.empty_like(a)
    for i in range(64):
        if i < 16:
            j = i
            np.bitwise_xor(c, d, out=f)
            f &= b
            f ^= d
        elif i < 32:
            j = (5 * i + 1) % 16
            np.bitwise_xor(b, c, out=f)
            f &= d
            f ^= c
        elif i < 48:
            j = (3 * i + 5) % 16
            np.bitwise_xor(b, c, out=f)
            f ^= d
        else:
            j = 7 * i % 16
            np.bitwise_not(d, out=f)
            f |= b
            f ^= c
        a += f
        a += np.uint32((_ADDED[i] + fixed.get(j, 0)) & 0xFFFFFFFF)
        if j < len(words):
            a += words[j]
        np.left_shift(a, np.uint32(_TURNED[i]), out=f)
        a >>= np.uint32(32 - _TURNED[i])
        a |= f
        a += b
        a, b, c, d = d, a, b, c
    a += first
    b += second
    return (a.byteswap().astype(np.int64) << 20) | (b.byteswap() >> np.uint32(12))


def uniforms_np(docs: np.ndarray, sizes: np.ndarray, *parts: object) -> np.ndarray:
    """uniform_py(*parts, doc, pos) for the positions 0 to size - 1 of each document, one after another."""
    heads = [("|".join(map(str, [*parts, d])) + "|").encode() for d in docs.tolist()]
    long = np.array([len(h) for h in heads], np.int64)
    doc = np.repeat(np.arange(len(sizes)), sizes)
    pos = np.arange(len(doc)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
    out = np.empty(len(doc))
    if not len(doc):
        return out
    if long.max() > 45:  # with the position and the end mark, no longer one block
        return np.array([uniform_py(*parts, docs[d], p) for d, p in zip(doc.tolist(), pos.tolist())])
    base = np.frombuffer(b"".join(h.ljust(64, b"\0") for h in heads), np.uint8).reshape(-1, 64)
    digits = np.searchsorted(10 ** np.arange(1, 10), pos, "right") + 1
    kind = long[doc] * 16 + digits
    for k in np.flatnonzero(np.bincount(kind)).tolist():
        at, n, m = k // 16, k % 16, k // 16 + k % 16
        every = np.flatnonzero(kind == k)
        for a in range(0, len(every), _AT_ONCE):
            own = every[a : a + _AT_ONCE]
            text, p = base[doc[own], : m // 4 * 4 + 4], pos[own].astype(np.uint32)
            for j in range(n - 1, -1, -1):
                q = p // np.uint32(10)
                text[:, at + j] = p - q * np.uint32(10) + 48
                p = q
            text[:, m] = 0x80
            words = np.ascontiguousarray(text.view("<u4").T).astype(np.uint32, copy=False)
            out[own] = _digest_start(words, {14: 8 * m}) / SCALE
    return out


def uniforms_text(head: str, ids: pa.Array, tails: list[str]) -> list[np.ndarray]:
    """For each tail, the draws that uniform() makes of the texts head + id + tail, which hold its bars; no id is null."""
    head_, tails_, out = head.encode(), [t.encode() for t in tails], [np.empty(len(ids)) for _ in tails]
    for a in range(0, len(ids), _AT_ONCE):
        own = ids.slice(a, _AT_ONCE)
        long = pc.binary_length(own).to_numpy(zero_copy_only=False).astype(np.int64)
        most, start = int(long.max()), len(head_)
        if start + most + max(map(len, tails_)) > 55:  # with the end mark and the length, no longer one block
            for tail, u in zip(tails, out):
                u[a : a + len(own)] = [int(md5(f"{head}{x}{tail}".encode()).hexdigest()[:13], 16) / SCALE for x in own.to_pylist()]
            continue
        text = np.zeros((len(own), 64), np.uint8)
        text[:, :start] = np.frombuffer(head_, np.uint8)
        text[:, start : start + most][np.arange(most) < long[:, None]] = np.frombuffer(b"".join(own.cast(pa.binary()).to_pylist()), np.uint8)
        rows = np.arange(len(own))
        for tail, u in zip(tails_, out):
            for j, x in enumerate([*tail, 0x80]):
                text[rows, start + long + j] = x
            words = np.ascontiguousarray(text.view("<u4").T).astype(np.uint32, copy=False)
            words[14] = 8 * (start + long + len(tail))
            u[a : a + len(own)] = _digest_start(words[:15], {}) / SCALE
            # what a shorter tail would leave
            for j in range(len(tail) + 1):
                text[rows, start + long + j] = 0
    return out


def mixed(seed: int, *ids: np.ndarray | int) -> np.ndarray:
    """A vectorised stream of its own: 53-bit uniforms in (0, 1) of a 64-bit mixer."""
    with np.errstate(over="ignore"):
        h = np.uint64(seed) * np.uint64(0x9E3779B97F4A7C15)
        for x in ids:
            h = (h ^ np.asarray(x).astype(np.int64).view(np.uint64)) * np.uint64(0xBF58476D1CE4E5B9)
            h = (h ^ (h >> np.uint64(29))) * np.uint64(0x94D049BB133111EB)
            h = h ^ (h >> np.uint64(32))
    return ((h >> np.uint64(11)).astype(np.float64) + 0.5) / float(1 << 53)


def sample(fraction: float, seed: int, *key: str) -> Column:
    """A keyed Bernoulli draw of rows."""
    return uniform("tr", seed, *[F.col(k) for k in key]) < fraction


def draw(weights: Column, u: Column) -> Column:
    """Least index whose running sum of weights exceeds u times the total; the last if none does."""
    # the bound is a field of the start: inside the function it would be taken anew for every weight
    total = F.aggregate(weights, F.lit(0.0), lambda s, x: s + x)
    start = F.struct(F.lit(0.0).alias("sum"), F.lit(0).alias("k"), F.lit(-1).alias("hit"), (u * total).alias("bound"))
    return F.aggregate(
        weights,
        start,
        lambda s, x: F.struct(
            (s["sum"] + x).alias("sum"),
            (s["k"] + 1).alias("k"),
            F.when((s["hit"] < 0) & (s["sum"] + x > s["bound"]), s["k"]).otherwise(s["hit"]).alias("hit"),
            s["bound"].alias("bound"),
        ),
        lambda s: F.when(s["hit"] < 0, s["k"] - 1).otherwise(s["hit"]),
    )
