"""Counter-based random numbers: pure functions of keys, so retries, partitions and engines agree."""

from __future__ import annotations

import hashlib
from math import ceil

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

SCALE = 2.0**32


def coin(*keys: Column | str | int, kind: str = "md5") -> Column:
    """Uniform number in [0, 1) of the keys.

    md5 has the same value in every engine (its key text joins the keys with ``|``); xxhash64 is for
    large runs, where it stays inside generated code.
    """
    cols = [k if isinstance(k, Column) else F.lit(k) for k in keys]
    if kind == "md5":
        text = F.concat_ws("|", *(c.cast("string") for c in cols))
        return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long") / F.lit(SCALE)
    return F.shiftrightunsigned(F.xxhash64(*cols), 32).cast("double") / F.lit(SCALE)


def coin_below(share: float, *keys: Column | str | int, kind: str = "md5") -> Column:
    """Whether the coin of the keys is less than ``share`` (below 1); md5 digits are compared as text, which takes no number of them."""
    if kind != "md5":
        return coin(*keys, kind=kind) < share
    text = F.concat_ws("|", *((k if isinstance(k, Column) else F.lit(k)).cast("string") for k in keys))
    return F.md5(text) < F.lit(f"{ceil(share * SCALE):08x}")


def coin_sql(*keys: str) -> str:
    """The md5 coin as DuckDB SQL."""
    return f"(('0x' || substr(md5(concat_ws('|', {', '.join(keys)})), 1, 8))::BIGINT / 4294967296.0)"


def md5_coin(*keys: object) -> float:
    return int(hashlib.md5("|".join(map(str, keys)).encode()).hexdigest()[:8], 16) / SCALE


MD5_BLOCK = 1 << 16  # messages that are hashed side by side, so that their state stays in cache
MD5_FEWEST = 3000  # of them that are; fewer are hashed one after another
_SHIFTS = np.repeat([[7, 12, 17, 22], [5, 9, 14, 20], [4, 11, 16, 23], [6, 10, 15, 21]], 4, axis=0).reshape(4, 4, 4).reshape(64)
_SINES = np.floor(np.abs(np.sin(np.arange(1, 65))) * SCALE).astype(np.uint64)
_PLACES = np.concatenate([np.arange(16), (5 * np.arange(16) + 1) % 16, (3 * np.arange(16) + 5) % 16, 7 * np.arange(16) % 16])
_START = (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)


def _md5_heads(words: list[np.ndarray | int], n: int) -> np.ndarray:
    """First 32 bits of the md5 digests of n messages of one block each; a word that all share is a number."""
    state = [np.full(n, v, np.uint32) for v in _START]
    a, b, c, d = state
    f, t = np.empty(n, np.uint32), np.empty(n, np.uint32)
    for i in range(61):  # the last three steps do not touch the first word
        if i < 16 or 16 <= i < 32:
            x, y, z = (b, c, d) if i < 16 else (d, b, c)
            np.bitwise_xor(y, z, out=f)
            np.bitwise_and(f, x, out=f)
            np.bitwise_xor(f, z, out=f)
        elif i < 48:
            np.bitwise_xor(b, c, out=f)
            np.bitwise_xor(f, d, out=f)
        else:
            np.bitwise_not(d, out=f)
            np.bitwise_or(f, b, out=f)
            np.bitwise_xor(f, c, out=f)
        word = words[_PLACES[i]]
        shared = isinstance(word, int)
        np.add(f, a, out=f)
        np.add(f, np.uint32((int(_SINES[i]) + (word if shared else 0)) & 0xFFFFFFFF), out=f)
        if not shared:
            np.add(f, word, out=f)
        s = int(_SHIFTS[i])
        np.left_shift(f, np.uint32(s), out=t)
        np.right_shift(f, np.uint32(32 - s), out=f)
        np.bitwise_or(f, t, out=f)
        np.add(f, b, out=a)
        a, b, c, d = d, a, b, c
    return (b + np.uint32(_START[0])).byteswap()


def md5_coins(prefix: str, last: np.ndarray) -> np.ndarray:
    """md5 coins of one prefix and many last keys, hashed side by side where a message is one block."""
    head, out = f"{prefix}|".encode(), np.empty(len(last))
    last = np.asarray(last, np.int64)
    if len(last) < MD5_FEWEST or len(head) + 20 > 55:
        base = hashlib.md5(head)
        for i, k in enumerate(last.tolist()):
            h = base.copy()
            h.update(str(k).encode())
            out[i] = int(h.hexdigest()[:8], 16)
        return out / SCALE
    for i in range(0, len(last), MD5_BLOCK):
        keys = last[i : i + MD5_BLOCK]
        size = np.where(keys < 0, -1, 1) * (1 + np.searchsorted(_TENS, _magnitude(keys), "right"))
        part = np.empty(len(keys))
        for signed in np.unique(size).tolist():
            some = np.flatnonzero(size == signed)
            part[some] = _md5_heads(_one_block(head + b"-" * (signed < 0), _magnitude(keys[some]), abs(signed)), len(some))
        out[i : i + MD5_BLOCK] = part
    return out / SCALE


_TENS = np.uint64(10) ** np.arange(1, 20, dtype=np.uint64)


def _magnitude(keys: np.ndarray) -> np.ndarray:
    return np.where(keys < 0, np.uint64(0) - keys.view(np.uint64), keys.view(np.uint64))


def _one_block(head: bytes, numbers: np.ndarray, digits: int) -> list[np.ndarray | int]:
    """The sixteen words of the padded messages head + number, where every number has so many digits."""
    numbers = numbers.astype(np.uint32) if digits < 10 else numbers
    size = len(head) + digits
    fixed = bytearray(head + bytes(digits) + b"\x80" + bytes(55 - size) + (8 * size).to_bytes(8, "little"))
    words: list[np.ndarray | int] = [int.from_bytes(fixed[4 * j : 4 * j + 4], "little") for j in range(16)]
    for at in range(size - 1, len(head) - 1, -1):
        rest = numbers // numbers.dtype.type(10)
        byte = (numbers - rest * numbers.dtype.type(10)).astype(np.uint32) + np.uint32(48)
        words[at // 4] = (byte << np.uint32(8 * (at % 4))) + (np.uint32(words[at // 4]) if isinstance(words[at // 4], int) else words[at // 4])
        numbers = rest
    return words


def _mix(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


def key_of(*keys: int | str) -> np.uint64:
    """64-bit key of a few values."""
    return np.uint64(int.from_bytes(hashlib.blake2b("|".join(map(str, keys)).encode(), digest_size=8).digest(), "little"))


def mixed_coins(key: np.uint64, counters: np.ndarray) -> np.ndarray:
    """Vectorised coins of a key and counters, for the in-memory engine's large runs."""
    with np.errstate(over="ignore"):
        return (_mix(_mix(counters.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) + key)) >> np.uint64(11)) / 2.0**53


def bernoulli_words(key: np.uint64, counters: np.ndarray, p: np.ndarray, words: np.ndarray) -> np.ndarray:
    """uint64[counters, words]: each bit is set with the counter's probability (to 32 binary places).

    The bits of 64 uniform numbers are drawn a place at a time and compared with those of p; a lane
    is settled where they first differ, so a word takes about nine mixes and not 64.
    """
    target = np.ceil(p * SCALE).astype(np.uint64)
    with np.errstate(over="ignore"):
        base = _mix(_mix(counters.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) + key)[:, None] + (words.astype(np.uint64) + np.uint64(1)) * np.uint64(0xD1B54A32D192ED03))
        live, open_ = np.zeros_like(base), np.full_like(base, 0xFFFFFFFFFFFFFFFF)
        sure = target > np.uint64(0xFFFFFFFF)
        live[sure], open_[sure] = np.uint64(0xFFFFFFFFFFFFFFFF), np.uint64(0)
        shape, live, open_, base = base.shape, live.ravel(), open_.ravel(), base.ravel()
        target = np.repeat(target, shape[1])
        at = None  # places still open, once they are few
        for place in range(31, -1, -1):
            if place < 24:
                left = np.flatnonzero(open_) if at is None else at[open_[at] != 0]
                if not len(left):
                    break
                at = left
            some = slice(None) if at is None else at
            want = np.uint64(0) - (target[some] >> np.uint64(place) & np.uint64(1))  # all ones where p has this bit
            r = _mix(base[some] + np.uint64((32 - place) * 0xA0761D6478BD642F & 0xFFFFFFFFFFFFFFFF))
            undecided = open_[some]
            live[some] |= undecided & want & ~r
            open_[some] = undecided & ~(r ^ want)
    return live.reshape(shape)
