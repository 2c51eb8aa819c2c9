"""Portable randomness: coins and 3-wise independent hashes as plain column expressions.

Every random choice is a hash of (seed, repetition, tag, ids), never of a partition, so retries and other engines see the
same coins. A coin is the first 32 bits of an md5 digest.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Prime field of the polynomial hash; products of two residues stay below 2^63.
PRIME = 2**31 - 1
#: Prime field for vertex ids of 31 bits and more; products need DECIMAL(38, 0).
PRIME61 = 2**61 - 1


def digits(*parts: Column | str | int) -> Column:
    """The first eight hex digits of the digest of the given literals and columns; strings name columns."""
    cols = [F.col(p).cast("string") if isinstance(p, str) else p.cast("string") if isinstance(p, Column) else F.lit(str(p)) for p in parts]
    return F.substring(F.md5(F.concat_ws(":", *cols)), 1, 8)


def coin(*parts: Column | str | int) -> Column:
    """32 random bits (0 to 2^32 - 1) of the given literals and columns; strings name columns."""
    return F.conv(digits(*parts), 16, 10).cast("long")


def falls(limit: int, *parts: Column | str | int) -> Column:
    """Whether the coin is below the limit, compared as hex digits and so without a number made of each."""
    return digits(*parts) < (f"{limit:08x}" if limit < 2**32 else "g")


def tag(name: str) -> Column:
    return F.lit(name)


def below(probability: float) -> int:
    """The threshold under which a coin falls with that probability."""
    return int(min(1.0, max(0.0, probability)) * 2**32)


#: Shifts and constants of md5 (RFC 1321), up to the last step that the digest's first word needs.
STEPS, SHIFTS = 61, ((7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21))
#: Pairs whose digests are made together: their words stay in a core's cache.
AT_ONCE = 1 << 16


def first_words(words: list):
    """First 32 bits, as read from the digest, of md5 of one block of sixteen words, each an array or a number; the arrays broadcast to one shape."""
    import math

    import numpy as np

    start = [np.uint32(x) for x in (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)]
    shape = np.broadcast_shapes(*(np.shape(w) for w in words))
    a, b, c, d = (np.full(shape, x) for x in start)
    f, g = np.empty(shape, np.uint32), np.empty(shape, np.uint32)
    for i in range(STEPS):
        at = (i, 5 * i + 1, 3 * i + 5, 7 * i)[i // 16] % 16
        more, turn = words[at] + np.uint32(int(abs(math.sin(i + 1)) * 2**32)), SHIFTS[i // 16][i % 4]
        if i < 32:
            p, q, r = (b, c, d) if i < 16 else (d, b, c)
            np.bitwise_xor(q, r, out=f)
            np.bitwise_and(f, p, out=f)
            np.bitwise_xor(f, r, out=f)
        elif i < 48:
            np.bitwise_xor(b, c, out=f)
            np.bitwise_xor(f, d, out=f)
        else:
            np.invert(d, out=f)
            np.bitwise_or(f, b, out=f)
            np.bitwise_xor(f, c, out=f)
        np.add(a, f, out=a)
        np.add(a, more, out=a)
        np.left_shift(a, np.uint32(turn), out=g)
        np.right_shift(a, np.uint32(32 - turn), out=a)
        np.bitwise_or(a, g, out=a)
        np.add(a, b, out=a)
        a, b, c, d = d, a, b, c
    return (b + start[0]).byteswap()


def by_length(texts: list[bytes]):
    """(length, places, bytes as a matrix) for the texts of each length."""
    import numpy as np

    sizes = np.array([len(t) for t in texts])
    for n in np.unique(sizes):
        places = np.flatnonzero(sizes == n)
        yield int(n), places, np.frombuffer(b"".join(texts[i] for i in places), np.uint8).reshape(len(places), n)


def in_block(chars, at: int):
    """The sixteen words of each row of characters put into an empty block."""
    import numpy as np

    block = np.zeros((len(chars), 64), np.uint8)
    block[:, at : at + chars.shape[1]] = chars
    return block.view("<u4")


def pair_coins(seed: int, x, y):
    """Matrix of coin(seed, x[i], y[j]) for integers, the digests of many pairs made at once; no text of a seed and two 64-bit ids is beyond a block."""
    import numpy as np

    out = np.empty((len(x), len(y)), np.uint32)
    ends = [(n, at, chars) for n, at, chars in by_length([b"%d\x80" % v for v in y])]
    for n, rows, chars in by_length([b"%d:%d:" % (seed, u) for u in x]):
        left = in_block(chars, 0)
        for m, columns, tail in ends:
            right = in_block(tail, n)
            right[:, 14] = 8 * (n + m - 1)
            step = max(1, AT_ONCE // len(columns))
            for i in range(0, len(rows), step):
                words = []
                for k in range(16):
                    l, r = left[i : i + step, k, None], right[None, :, k]
                    # most words are the same for all rows, for all columns or for both
                    words.append(r[0, 0] if k >= 14 or not (l.any() or r.any()) else r if not l.any() else l if not r.any() else l | r)
                out[np.ix_(rows[i : i + step], columns)] = np.broadcast_to(first_words(words), (len(rows[i : i + step]), len(columns)))
    return out


def pair_hits(seed: int, x, y, limit: int = 2**31):
    """Matrix of coin(seed, smaller, larger) < limit for two sorted arrays of ids; no id falls with itself."""
    import numpy as np

    out = np.zeros((len(x), len(y)), bool)
    step = max(1, AT_ONCE // max(1, len(y)))
    for i in range(0, len(x), step):
        part = x[i : i + step]
        low, high = np.searchsorted(y, part[0], "right"), np.searchsorted(y, part[-1], "left")
        low, high = min(low, high), max(low, high)
        out[i : i + step, high:] = pair_coins(seed, part, y[high:]) < limit
        out[i : i + step, :low] = (pair_coins(seed, y[:low], part) < limit).T
        if low < high:
            between = y[low:high]
            up, down = pair_coins(seed, part, between), pair_coins(seed, between, part).T
            out[i : i + step, low:high] = np.where(part[:, None] < between, up, down) < limit
    return out & (x[:, None] != y)


def coefficient(seed: int, rep: int, node: str, k: int) -> Column:
    return F.pmod(coin(seed, rep, tag("h"), node, k), F.lit(PRIME))


def poly_hash(x: Column | str, c0: str, c1: str, c2: str, buckets: int) -> Column:
    """Degree-2 polynomial over the prime field, reduced to buckets."""
    v = F.pmod(F.col(x) if isinstance(x, str) else x, F.lit(PRIME))
    inner = (F.col(c2) * v + F.col(c1)) % PRIME
    return ((inner * v + F.col(c0)) % PRIME) % buckets


def poly_hash61(x: str, c0: str, c1: str, c2: str, buckets: int) -> Column:
    """The same over the 61-bit field, exact in DECIMAL(38, 0)."""
    d = lambda c: F.col(c).cast("decimal(19,0)")
    p = F.lit(PRIME61).cast("decimal(19,0)")
    inner = ((d(c2) * d(x)).cast("decimal(38,0)") % p + d(c1)) % p
    return (((inner.cast("decimal(19,0)") * d(x)).cast("decimal(38,0)") % p + d(c0)) % p % F.lit(buckets)).cast("long")


def sql_coin(*parts: str | int) -> str:
    """The same coin for DuckDB; strings are SQL expressions (quote literals)."""
    return f"('0x' || substr(md5(concat_ws(':', {', '.join(f'{p!r}' if isinstance(p, int) else f'({p})::VARCHAR' for p in parts)})), 1, 8))::BIGINT"


def sql_coefficient(seed: int, rep: int, node: str, k: int) -> str:
    return f"({sql_coin(seed, rep, repr('h'), node, k)} % {PRIME})"


def sql_poly_hash(x: str, c0: str, c1: str, c2: str, buckets: int) -> str:
    v = f"({x} % {PRIME})"
    return f"((((({c2} * {v} + {c1}) % {PRIME}) * {v} + {c0}) % {PRIME}) % {buckets})"
