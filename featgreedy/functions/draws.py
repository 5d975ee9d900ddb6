"""Seeded draws as functions of a text key, equal in Spark, DuckDB and Python.

``unif(key)`` is the first 32 bits of the key's md5 plus one half, over 2^32. Other laws are built from it.
"""

from __future__ import annotations

import hashlib
import math

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from featgreedy.session import ship


def key(seed: str, role: str, *parts) -> Column:
    cols = [F.lit(f"{seed}|{role}")] + [p.cast("string") if isinstance(p, Column) else F.lit(str(p)) for p in parts]
    return F.concat_ws("|", *cols)


def unif(k: Column) -> Column:
    return (F.conv(F.substring(F.md5(k), 1, 8), 16, 10).cast("double") + 0.5) / F.lit(float(2**32))


def norm(k: Column) -> Column:
    """Standard normal by the polar pair of two uniforms."""
    return F.sqrt(-2 * F.ln(unif(F.concat(k, F.lit("a"))))) * F.cos(2 * math.pi * unif(F.concat(k, F.lit("b"))))


def chi2(k: Column, m: int) -> Column:
    """Chi-square with ``m`` degrees of freedom."""
    out = F.lit(0.0)
    for i in range(m // 2):
        out = out - 2 * F.ln(unif(F.concat(k, F.lit(f"c{i}"))))
    return out + F.pow(norm(F.concat(k, F.lit("o"))), 2) if m % 2 else out


def t_draw(k: Column, m: int = 5) -> Column:
    return norm(k) / F.sqrt(chi2(k, m) / m)


def poisson(k: Column, mean: Column, cap: float = 50.0) -> Column:
    """Inverse distribution function at ``unif(k)``; the mean is capped."""
    lam = F.least(mean, F.lit(cap))
    u = unif(k)
    step = lambda acc, i: F.when(
        acc["s"] >= u, acc
    ).otherwise(F.struct((acc["i"] + 1).alias("i"), (acc["p"] * lam / i).alias("p"), (acc["s"] + acc["p"] * lam / i).alias("s")))
    start = F.struct(F.lit(0).alias("i"), F.exp(-lam).alias("p"), F.exp(-lam).alias("s"))
    return F.aggregate(F.sequence(F.lit(1), F.lit(200)), start, step)["i"]


# the same laws in Python, for truths and noise made on the driver or in Arrow batches


def py_unif(k: str) -> float:
    return (int(hashlib.md5(k.encode()).hexdigest()[:8], 16) + 0.5) / 2**32


def py_norm(k: str) -> float:
    return math.sqrt(-2 * math.log(py_unif(k + "a"))) * math.cos(2 * math.pi * py_unif(k + "b"))


def py_t(k: str, m: int = 5) -> float:
    c = -2 * sum(math.log(py_unif(f"{k}c{i}")) for i in range(m // 2))
    if m % 2:
        c += py_norm(k + "o") ** 2
    return py_norm(k) / math.sqrt(c / m)


def orthonormal(seed: str, rows: int, cols: int) -> np.ndarray:
    """Orthonormal columns from the decomposition of a normal matrix, diagonal made positive."""
    x = np.array([[py_norm(f"{seed}|{i}|{k}") for k in range(cols)] for i in range(rows)])
    q, r = np.linalg.qr(x)
    return q * np.sign(np.diag(r))


# the normal draws of many keys at once: one md5 for whole arrays of short messages

_MD5_ADD = tuple(int(abs(math.sin(i + 1)) * 2**32) & 0xFFFFFFFF for i in range(64))
_MD5_TURN = ((7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21))
#: Messages hashed at a time, which stay in a core's cache.
_PIECE = 1 << 15


def _md5_units(words: dict, n: int) -> np.ndarray:
    """Uniforms of ``n`` messages of one md5 block; ``words``: its 32-bit words, arrays or numbers, zero where absent."""
    u = np.uint32
    a, b, c, d = (np.full(n, v, u) for v in (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476))
    f, g = np.empty(n, u), np.empty(n, u)
    for i in range(64):
        if i < 16:
            np.bitwise_and(np.bitwise_xor(c, d, out=f), b, out=f)
            f ^= d
            k = i
        elif i < 32:
            np.bitwise_and(np.bitwise_xor(b, c, out=f), d, out=f)
            f ^= c
            k = (5 * i + 1) % 16
        elif i < 48:
            np.bitwise_xor(np.bitwise_xor(b, c, out=f), d, out=f)
            k = (3 * i + 5) % 16
        else:
            np.bitwise_or(np.invert(d, out=f), b, out=f)
            f ^= c
            k = 7 * i % 16
        f += a
        w = words.get(k, 0)
        if isinstance(w, np.ndarray):
            f += w
            f += u(_MD5_ADD[i])
        else:
            f += u((_MD5_ADD[i] + int(w)) & 0xFFFFFFFF)
        turn = _MD5_TURN[i // 16][i % 4]
        np.left_shift(f, u(turn), out=g)
        np.right_shift(f, u(32 - turn), out=f)
        f |= g
        f += b
        a, b, c, d, f = d, f, b, c, a
    a += u(0x67452301)
    return (a.byteswap() + 0.5) / 2**32


def _digits(x: np.ndarray, k: int) -> np.ndarray:
    """The last ``k`` decimal digits as text bytes, one row a number."""
    return (x[:, None] // 10 ** np.arange(k - 1, -1, -1) % 10 + 48).astype(np.uint8)


def _by_length(lo: int, hi: int):
    """``lo..hi`` in ranges of numbers of equally many digits."""
    while lo < hi:
        end = min(hi, 10 ** len(str(lo)))
        yield lo, end, len(str(lo))
        lo = end


def normals(seed: str, rows: range, columns: int) -> np.ndarray:
    """``py_norm(f"{seed}|{t}|{c}")`` for ``t`` in ``rows`` and ``c`` in 0 to ``columns``, to the last bits of log and cosine."""
    out = np.empty((len(rows), columns))
    head = np.frombuffer(f"{seed}|".encode(), np.uint8)
    for t0, t1, tk in _by_length(rows.start, rows.stop):
        t_text = _digits(np.arange(t0, t1), tk)
        for c0, c1, ck in _by_length(0, columns):
            size = len(head) + tk + ck + 2
            if size > 55:
                raise ValueError("the key exceeds one md5 block")
            step = max(1, _PIECE // (t1 - t0))
            for c in range(c0, c1, step):
                e = min(c + step, c1)
                raw = np.zeros((e - c, t1 - t0, 4 * (size // 4 + 1)), np.uint8)
                at = len(head)
                raw[:, :, :at] = head
                raw[:, :, at : at + tk] = t_text
                raw[:, :, at + tk] = ord("|")
                raw[:, :, at + tk + 1 : size - 1] = _digits(np.arange(c, e), ck)[:, None]
                raw[:, :, size] = 0x80
                flat = raw.reshape(-1, raw.shape[2])
                u = []
                words = {}
                for last in (b"a", b"b"):
                    flat[:, size - 1] = last[0]
                    both = flat.view("<u4")
                    words = {k: words[k] if k in words and k != (size - 1) // 4 else np.ascontiguousarray(both[:, k]) for k in range(both.shape[1])}
                    u.append(_md5_units({**words, 14: 8 * size}, len(flat)))
                z = np.sqrt(-2 * np.log(u[0])) * np.cos(2 * math.pi * u[1])
                out[t0 - rows.start : t1 - rows.start, c:e] = z.reshape(e - c, -1).T
    return out


ship(__name__)
