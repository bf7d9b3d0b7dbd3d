"""The draws of hashing.draw for numbered keys, many at once, in an Arrow map: md5 over arrays of single-block messages."""

from __future__ import annotations

from collections.abc import Iterator
from hashlib import md5

import numpy as np
import pandas as pd

#: md5's sines and rotations (RFC 1321).
_SINES = [np.uint32(int(abs(np.sin(i + 1)) * 2**32)) for i in range(64)]
_TURNS = [(7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21)]
_AT_ONCE = 16_384  # messages whose state stays in the cache
_ROOM = 55  # bytes of a message of one block
_TOGETHER = 500  # texts whose words are drawn at once


def _first_words(blocks: np.ndarray) -> np.ndarray:
    """The first 32 bits of the digests of padded blocks (n, 16), as the hex digits read."""
    x = np.ascontiguousarray(blocks.T)
    a0 = np.uint32(0x67452301)
    a, b, c, d = (np.full(len(blocks), v, dtype=np.uint32) for v in (a0, 0xEFCDAB89, 0x98BADCFE, 0x10325476))
    for i in range(64):
        kind = i // 16
        if kind == 0:
            f, g = d ^ (b & (c ^ d)), i
        elif kind == 1:
            f, g = c ^ (d & (b ^ c)), (5 * i + 1) % 16
        elif kind == 2:
            f, g = b ^ c ^ d, (3 * i + 5) % 16
        else:
            f, g = c ^ (b | ~d), 7 * i % 16
        f += a
        f += x[g]
        f += _SINES[i]
        turn = _TURNS[kind][i % 4]
        a, d, c, b = d, c, b, b + ((f << np.uint32(turn)) | (f >> np.uint32(32 - turn)))
    return (a + a0).byteswap()


def numbered_draws(prefixes: list[bytes], counts: np.ndarray) -> np.ndarray:
    """draw(prefix, i) for i from 0 to count - 1 of each prefix in turn; a prefix ends with the separator."""
    longest = max(map(len, prefixes), default=0) + len(str(max(counts, default=0)))
    if longest > _ROOM:
        return np.array([int.from_bytes(md5(p + b"%d" % i).digest()[:4], "big") for p, n in zip(prefixes, counts, strict=True) for i in range(n)], dtype=np.uint32)
    heads = np.frombuffer(b"".join(p.ljust(64, b"\0") for p in prefixes), dtype=np.uint8).reshape(-1, 64)
    lengths = np.array([len(p) for p in prefixes], dtype=np.int64)
    of = np.repeat(np.arange(len(prefixes)), counts)
    number = np.arange(len(of)) - np.repeat(np.cumsum(counts) - counts, counts)
    out = np.empty(len(of), dtype=np.uint32)
    for at in range(0, len(of), _AT_ONCE):
        mine, i = of[at : at + _AT_ONCE], number[at : at + _AT_ONCE]
        blocks, end, rows = heads[mine], lengths[mine], np.arange(len(mine))
        digits = np.ones(len(i), dtype=np.int64)
        power = 10
        while (more := i >= power).any():
            digits += more
            power *= 10
        rest, place = i.copy(), digits - 1
        while (on := place >= 0).any():
            blocks[rows[on], (end + place)[on]] = 48 + rest[on] % 10
            rest //= 10
            place -= 1
        end = end + digits
        blocks[rows, end] = 0x80
        blocks[:, 56:58] = (8 * end).astype("<u2").view(np.uint8).reshape(-1, 2)
        out[at : at + _AT_ONCE] = _first_words(blocks.view("<u4"))
    return out


def drawn_together(texts: pd.Series, keys: pd.Series, seeds: list[bytes]) -> Iterator[list[tuple[list[bytes] | None, list[np.ndarray]]]]:
    """Some texts at a time: a text's words, and for each seed their draws by seed, key and place; no words and no draws for a null text. A null key is left out, as in SQL."""
    for at in range(0, len(texts), _TOGETHER):
        words = [None if t is None else t.encode("utf-8", "surrogatepass").split() for t in texts.iloc[at : at + _TOGETHER]]
        own = [b"" if k is None else k.encode() + b"|" for k in keys.iloc[at : at + _TOGETHER]]
        prefixes = [s + b"|" + k for k, ws in zip(own, words, strict=True) if ws is not None for s in seeds]
        counts = np.array([len(ws) for ws in words if ws is not None for _ in seeds], dtype=np.int64)
        drawn = iter(np.split(numbered_draws(prefixes, counts), np.cumsum(counts)[:-1])) if prefixes else iter(())
        yield [(ws, [] if ws is None else [next(drawn) for _ in seeds]) for ws in words]
