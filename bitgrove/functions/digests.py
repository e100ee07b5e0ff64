"""MD5 of many short keys at once, by numpy: the same digests that Spark and other SQL engines give, for tasks that hold whole sets."""

from __future__ import annotations

import hashlib
import math
from functools import cache

import numpy as np

#: Keys that are hashed together, so that their words stay in a core's cache; and the longest key that fits one block.
AT_ONCE, LONGEST = 1 << 14, 55
#: Keys that hashlib takes sooner.
FEW = 256
#: Numbers that are counted up and hashed together, and how many of their last digits are listed beforehand.
COUNTED, LISTED = 20_000, 5
_ADD = [np.uint32(int(abs(math.sin(i + 1)) * 2**32)) for i in range(64)]
_TURN = [[7, 12, 17, 22], [5, 9, 14, 20], [4, 11, 16, 23], [6, 10, 15, 21]]
_WORD = [[i for i in range(16)], [(5 * i + 1) % 16 for i in range(16)], [(3 * i + 5) % 16 for i in range(16)], [7 * i % 16 for i in range(16)]]
_START = [np.uint32(v) for v in (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)]


def _block(words: list, n: int, first: bool = False) -> list:
    """The four words of the digests of one-block messages; words are arrays of n, or numbers where all messages agree. first: the
    first of them only, which is known sooner."""
    a, b, c, d = (np.full(n, v, np.uint32) for v in _START)
    f, g = np.empty(n, np.uint32), np.empty(n, np.uint32)
    with np.errstate(over="ignore"):
        for i in range(61 if first else 64):
            kind = i // 16
            if kind == 0:
                np.bitwise_xor(c, d, out=f)
                f &= b
                f ^= d
            elif kind == 1:
                np.bitwise_xor(b, c, out=f)
                f &= d
                f ^= c
            elif kind == 2:
                np.bitwise_xor(b, c, out=f)
                f ^= d
            else:
                np.bitwise_not(d, out=f)
                f |= b
                f ^= c
            f += a
            word = words[_WORD[kind][i % 16]]
            if isinstance(word, np.ndarray):
                f += word
                f += _ADD[i]
            else:
                f += np.uint32((int(word) + int(_ADD[i])) & 0xFFFFFFFF)
            turn = _TURN[kind][i % 4]
            np.left_shift(f, np.uint32(turn), out=g)
            f >>= np.uint32(32 - turn)
            f |= g
            f += b
            a, d, c, b, f = d, c, b, f, a
        if first:
            return [b + _START[0]]
        return [x + s for x, s in zip((a, b, c, d), _START, strict=True)]


def _widths(x: np.ndarray) -> np.ndarray:
    """How many digits non-negative numbers have."""
    return np.searchsorted(np.array([10**i for i in range(1, 19)]), x, side="right") + 1


def heads(*parts: str | np.ndarray) -> np.ndarray:
    """The first 64 bits of the MD5 of keys whose parts are joined by colons, as unsigned numbers in the order of the hex texts. Parts
    are texts, or arrays of non-negative whole numbers, one at least."""
    arrays = [p for p in parts if isinstance(p, np.ndarray)]
    n, out = len(arrays[0]), np.empty(len(arrays[0]), np.uint64)
    wide = [_widths(p) for p in arrays]
    kinds = wide[0].astype(np.int64)
    for w in wide[1:]:
        kinds = kinds * 20 + w
    for kind in np.unique(kinds):
        same = np.flatnonzero(kinds == kind)
        for low in range(0, len(same), AT_ONCE):
            rows = same[low : low + AT_ONCE]
            out[rows] = _same_width([p[rows] if isinstance(p, np.ndarray) else p for p in parts], [int(w[rows[0]]) for w in wide])
    return out


def _same_width(parts: list, widths: list[int]) -> np.ndarray:
    n, at, laid, moving = len(next(p for p in parts if isinstance(p, np.ndarray))), 0, bytearray(), []
    for i, p in enumerate(parts):
        laid += b":" if i else b""
        if isinstance(p, np.ndarray):
            width = widths[len(moving)]
            moving.append((p, len(laid), width))
            laid += b"0" * width
        else:
            laid += p.encode()
    if len(laid) > LONGEST or n < FEW:
        keys = zip(*(p.tolist() if isinstance(p, np.ndarray) else [p] * n for p in parts), strict=True)
        return np.array([int.from_bytes(hashlib.md5(":".join(map(str, k)).encode()).digest()[:8], "big") for k in keys], np.uint64)
    length = len(laid)
    laid += b"\x80" + bytes(55 - length) + (8 * length).to_bytes(8, "little")
    words: list = [int.from_bytes(laid[i : i + 4], "little") for i in range(0, 64, 4)]
    for p, at, width in moving:
        left = p
        for place in range(at + width - 1, at - 1, -1):
            left, digit = left // 10, left
            digit = (digit - left * 10).astype(np.uint32) << np.uint32(8 * (place % 4))
            word = words[place // 4]
            words[place // 4] = (word if isinstance(word, np.ndarray) else np.uint32(word)) + digit
    a, b, _, _ = _block(words, n)
    return a.byteswap().astype(np.uint64) << np.uint64(32) | b.byteswap()


def coins(*parts: str | np.ndarray) -> np.ndarray:
    """descent.coin of keys; the first part is the seed."""
    return (heads(*parts) >> np.uint64(32)).astype(np.float64) / 4294967296.0


@cache
def _last_digits(at: int) -> list[np.ndarray]:
    """What the last LISTED digits of all numbers add to zeros in the word that has the first of them at this byte, and in the next."""
    x, out = np.arange(10**LISTED, dtype=np.uint32), [np.zeros(10**LISTED, np.uint32) for _ in range(2)]
    for place in range(LISTED):
        digit = x // np.uint32(10 ** (LISTED - 1 - place)) % np.uint32(10)
        out[(at + place) // 4] += digit << np.uint32(8 * ((at + place) % 4))
    return out


def coins_counted(head: str, low: int, tails: list[str], which: np.ndarray | None = None) -> np.ndarray:
    """coins of the texts head, number, tails[which], put together, for the numbers low, low + 1, ... COUNTED of them. low is a multiple
    of COUNTED and has more than LISTED digits, so numbers agree in all digits but those."""
    head += str(low // 10**LISTED)
    texts = [(head + "0" * LISTED + t).encode() for t in tails]
    if max(map(len, texts)) > LONGEST:
        of, shown = [0] * COUNTED if which is None else which.tolist(), low % 10**LISTED
        keys = (f"{head}{shown + i:0{LISTED}}{tails[t]}" for i, t in enumerate(of))
        return np.array([int.from_bytes(hashlib.md5(k.encode()).digest()[:4], "big") for k in keys]) / 4294967296.0
    blocks = np.array([np.frombuffer(t + b"\x80" + bytes(55 - len(t)) + (8 * len(t)).to_bytes(8, "little"), "<u4") for t in texts])
    words: list = [c[which] if (c != c[0]).any() else c[0] for c in blocks.T]
    at = len(head.encode())
    for i, digits in enumerate(_last_digits(at % 4)):
        words[at // 4 + i] = words[at // 4 + i] + digits[low % 10**LISTED :][:COUNTED]
    return _block(words, COUNTED, first=True)[0].byteswap() / 4294967296.0


def by_digest(x: np.ndarray, *parts: str, also: np.ndarray | None = None) -> np.ndarray:
    """Indexes that sort x, all different, by `also`, then by the MD5 of parts:x, then by x."""
    keys = heads(*parts, x)
    order = np.argsort(keys, kind="stable") if also is None else np.lexsort((keys, also))
    tied = np.flatnonzero(keys[order][1:] == keys[order][:-1])
    if len(tied):
        whole = lambda i: (0 if also is None else int(also[i]), hashlib.md5(":".join([*parts, str(x[i])]).encode()).hexdigest(), int(x[i]))
        order = np.array(sorted(range(len(x)), key=whole))
    return order


def ranked(x: np.ndarray, ranks: np.ndarray, *parts: str, keys: np.ndarray | None = None):
    """A function from some of `ranks` (from 0, distinct) to the indexes of x that have them by the order of by_digest. x is not sorted
    as a whole. keys: the heads of parts:x, if they are known."""
    keys = heads(*parts, x) if keys is None else keys
    order = np.argpartition(keys, ranks)
    if any(np.count_nonzero(keys == keys[order[r]]) > 1 for r in ranks):
        order = by_digest(x, *parts)
    return lambda wanted: order[wanted]
