"""Hashes that are the same in Spark SQL, DuckDB and numpy.

Boundary hash: the bytes under a position as one big-endian integer, through three modular steps whose products stay below
2^63. Block digest: md5, cut into a section selector (32 bits) and two 48-bit numbers for double hashing. Two families of the
same shape know no SQL twin: "fast" takes a 128-bit hash of each block, "vector" hashes all blocks of an array at once.
"""

from __future__ import annotations

import functools
import math

try:
    from _md5 import md5  # the interpreter's own: short inputs take three fifths of the time
except ImportError:
    from hashlib import md5

import numpy as np
import xxhash
from pyspark.sql import Column
from pyspark.sql import functions as F

PRIME = (1 << 31) - 1
#: Multiplier and constant of the first step, constant's step by instance, multiplier and constant of the last.
STEP_A, STEP_B, STEP_I, STEP_C, STEP_D = 1103515245, 12345, 7919, 16807, 7
POS = 1 << 31


def _fold(x: np.ndarray, spare: np.ndarray) -> None:
    """One step of reduction modulo the Mersenne prime, in place: bits from 31 on are added to the lower ones."""
    np.right_shift(x, 31, out=spare)
    np.bitwise_and(x, PRIME, out=x)
    np.add(x, spare, out=x)


def boundary_hash(data: np.ndarray, width: int = 5, instance: int = 0) -> np.ndarray:
    """Of each position of the byte array with `width` bytes from it on. Reductions are only as complete as the next
    product needs; the last one is."""
    n = max(0, len(data) - width + 1)
    x, spare = np.zeros(n, np.int64), np.empty(n, np.int64)
    for i in range(width):
        if i >= 5:  # more than 40 bits would not fit: folded as it grows
            _fold(x, spare)
        np.left_shift(x, 8, out=x)
        np.add(x, data[i : i + n], out=x)
    _fold(x, spare)
    np.multiply(x, STEP_A, out=x)
    np.add(x, STEP_B + STEP_I * instance, out=x)
    _fold(x, spare)
    _fold(x, spare)
    np.multiply(x, x, out=spare)
    np.add(x, spare, out=x)
    _fold(x, spare)
    _fold(x, spare)
    np.multiply(x, STEP_C, out=x)
    np.add(x, STEP_D, out=x)
    _fold(x, spare)
    np.subtract(x, PRIME, out=x, where=x >= PRIME)
    return x


def boundary_hash_column(value: Column, instance: int = 0) -> Column:
    x = F.pmod(F.pmod(value, F.lit(PRIME)) * STEP_A + (STEP_B + STEP_I * instance), F.lit(PRIME))
    x = F.pmod(x * x + x, F.lit(PRIME))
    return F.pmod(x * STEP_C + STEP_D, F.lit(PRIME))


def md5_parts(digests: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Selector and the two numbers of concatenated 16-byte digests."""
    d = np.frombuffer(digests, np.uint8).reshape(-1, 16).astype(np.int64)
    part = lambda a, b: sum(d[:, i] << (8 * (b - 1 - i)) for i in range(a, b))
    return part(0, 4), part(4, 10), part(10, 16)


def digests(blocks: list[bytes], suffix: bytes = b"", family: str = "portable", salt: str = "") -> bytes:
    """16 bytes of each block with the salt before and the suffix after it."""
    head = salt.encode()
    if family == "portable":
        return b"".join([md5(head + b + suffix).digest() for b in blocks]) if head else b"".join([md5(b + suffix).digest() for b in blocks])
    xxh = xxhash.xxh3_128_digest
    return b"".join([xxh(head + b + suffix) for b in blocks])


#: md5 of many pairs at once: constants, rotations and words of its 64 steps, and the state it begins with.
MD5_K = [np.uint32(int(abs(math.sin(i + 1)) * 2**32)) for i in range(64)]
MD5_S = [s for four in ((7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21)) for _ in range(4) for s in four]
MD5_G = [(i, 5 * i + 1, 3 * i + 5, 7 * i)[i // 16] % 16 for i in range(64)]
MD5_IV = (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)
#: Pairs that go through the steps together: their state and words stay in the cache.
MD5_AT_ONCE = 1 << 14


def _md5_steps(state: list[np.ndarray], words: list[np.ndarray | None], first: int = 0, last: int = 64) -> list[np.ndarray]:
    """The state (changed in place) after these steps over 16 words of each message; a word that is zero everywhere is None."""
    a, b, c, d = state
    f = np.empty_like(a)
    for i in range(first, last):
        if i < 16:
            np.bitwise_xor(c, d, out=f)
            np.bitwise_and(f, b, out=f)
            np.bitwise_xor(f, d, out=f)
        elif i < 32:
            np.bitwise_xor(b, c, out=f)
            np.bitwise_and(f, d, out=f)
            np.bitwise_xor(f, c, out=f)
        elif i < 48:
            np.bitwise_xor(b, c, out=f)
            np.bitwise_xor(f, d, out=f)
        else:
            np.invert(d, out=f)
            np.bitwise_or(f, b, out=f)
            np.bitwise_xor(f, c, out=f)
        np.add(a, f, out=a)
        np.add(a, MD5_K[i], out=a)
        if words[MD5_G[i]] is not None:
            np.add(a, words[MD5_G[i]], out=a)
        np.left_shift(a, np.uint32(MD5_S[i]), out=f)
        np.right_shift(a, np.uint32(32 - MD5_S[i]), out=a)
        np.bitwise_or(a, f, out=a)
        np.add(a, b, out=a)
        a, b, c, d = d, a, b, c
    return [a, b, c, d]


def _rows_of_words(rows: list[bytes], width: int) -> np.ndarray:
    """[word, row] of rows padded with zeros to `width` words."""
    return np.ascontiguousarray(np.frombuffer(b"".join([r.ljust(4 * width, b"\0") for r in rows]), "<u4").reshape(len(rows), width).T)


class Tails:
    """What heads are continued with: as words, for each place in a word that a tail may begin at."""

    def __init__(self, tails: list[bytes]):
        self.bytes = tails
        self.size = np.fromiter(map(len, tails), np.int64, len(tails))
        width = (int(self.size.max(initial=0)) + 7) // 4
        self.words = [_rows_of_words([b"\0" * shift + t + b"\x80" for t in tails], width) for shift in range(4)]


class Heads:
    """md5 of pairs (head, tail), the bytes of one after the other, for arrays of pairs at a time. What depends on a head alone is done
    once: its whole 64 bytes, and the first steps of what is left."""

    def __init__(self, heads: list[bytes]):
        self.bytes = heads
        self.size = np.fromiter(map(len, heads), np.int64, len(heads))
        self.rest = (self.size % 64).astype(np.uint8)
        self.words = _rows_of_words([h[len(h) // 64 * 64 :] for h in heads], 16)
        self.state = [np.full(len(heads), x, np.uint32) for x in MD5_IV]
        for j in range(int(self.size.max(initial=0)) // 64):
            some = np.flatnonzero(self.size // 64 > j)
            before = [x[some] for x in self.state]
            after = _md5_steps([x.copy() for x in before], list(_rows_of_words([heads[i][64 * j : 64 * j + 64] for i in some.tolist()], 16)))
            for x, y, z in zip(self.state, before, after, strict=True):
                x[some] = y + z
        self.begun = [x.copy() for x in self.state]
        for step in range(15):
            some = np.flatnonzero(self.rest // 4 > step)
            after = _md5_steps([x[some] for x in self.begun], [w[some] for w in self.words], step, step + 1)
            for x, y in zip(self.begun, after, strict=True):
                x[some] = y

    def parts(self, which: np.ndarray, tails: Tails, of: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Selector and the two numbers of heads[which] continued with tails[of]."""
        out = np.empty((4, len(which)), np.uint32)
        rest = self.rest[which]
        need = rest + tails.size[of] + 9
        kind = rest * np.uint8(2) + (need > 64)
        kind[need > 128] = 255
        many = np.bincount(kind, minlength=256)
        order, ends = np.argsort(kind, kind="stable"), np.cumsum(many)
        for k in np.flatnonzero(many).tolist():
            for a in range(int(ends[k] - many[k]), int(ends[k]), MD5_AT_ONCE):
                at = order[a : min(a + MD5_AT_ONCE, int(ends[k]))]
                if k < 255:
                    out[:, at] = self._same(k // 2, 1 + k % 2, which[at], tails, of[at])
                else:
                    every = [md5(self.bytes[h] + tails.bytes[t]).digest() for h, t in zip(which[at].tolist(), of[at].tolist(), strict=True)]
                    out[:, at] = np.frombuffer(b"".join(every), "<u4").reshape(-1, 4).T
        a, b, c, d = out.byteswap().astype(np.int64)
        return a, b << 16 | c >> 16, (c & 0xFFFF) << 32 | d

    def _same(self, rest: int, blocks: int, which: np.ndarray, tails: Tails, of: np.ndarray) -> list[np.ndarray]:
        """State of pairs whose heads all leave `rest` bytes, and which end in so many blocks."""
        first, words = rest // 4, [None] * (16 * blocks)
        for i in range(-(-rest // 4)):
            words[i] = self.words[i][which]
        for i, w in enumerate(tails.words[rest % 4], first):
            if i < 16 * blocks - 2:
                words[i] = w[of] if words[i] is None else words[i] | w[of]
        words[-2] = (8 * (self.size[which] + tails.size[of])).astype(np.uint32)
        state = [x[which] for x in self.state]
        state = [x + y for x, y in zip(state, _md5_steps([x[which] for x in self.begun], words[:16], first), strict=True)]
        if blocks == 2:
            state = [x + y for x, y in zip(state, _md5_steps([x.copy() for x in state], words[16:]), strict=True)]
        return state


#: The vector family: multiplier of a block's positions, its inverse modulo 2^64, and the span that is summed at a time.
VECTOR_K = 0x9E3779B97F4A7C15
VECTOR_INVERSE = pow(VECTOR_K, -1, 1 << 64)
VECTOR_SPAN = 1 << 16


def _mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


@functools.cache
def _vector_tables() -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """A number for each byte; powers of the multiplier and of its inverse."""
    byte = _mixed(np.arange(1, 257, dtype=np.uint64) * np.uint64(VECTOR_K))
    power = lambda k: np.cumprod(np.concatenate([[np.uint64(1)], np.full(2 * VECTOR_SPAN, k, np.uint64)]), dtype=np.uint64)
    return byte, power(VECTOR_K), power(VECTOR_INVERSE)


def vector_hashes(data: np.ndarray, start: np.ndarray, end: np.ndarray, salt: str = "") -> np.ndarray:
    """64 bits of data[start:end] for each pair (in the order of start, no longer than VECTOR_SPAN): a sum of byte numbers by powers of
    their place, from running sums, mixed with the length. Equal bytes give equal hashes wherever they stand."""
    byte, power, inverse = _vector_tables()
    out = np.empty(len(start), np.uint64)
    at = 0
    while at < len(start):
        base = int(start[at])
        to = int(np.searchsorted(start, base + VECTOR_SPAN))
        last = int(end[at:to].max())
        run = np.zeros(last - base + 1, np.uint64)
        np.cumsum(byte[data[base:last]] * power[: last - base], out=run[1:])
        a, b = start[at:to] - base, end[at:to] - base
        out[at:to] = (run[b] - run[a]) * inverse[a] + (b - a).astype(np.uint64) * np.uint64(VECTOR_K)
        at = to
    return _mixed(out ^ np.uint64(xxhash.xxh3_64_intdigest(salt.encode()))) if salt else _mixed(out)


def flow_number(flow_key: str) -> int:
    """What binds the vector family's hashes to a flow."""
    return xxhash.xxh3_64_intdigest(flow_suffix(flow_key)) | 1


def bound_hashes(hashes: np.ndarray, flow: np.ndarray | np.uint64) -> np.ndarray:
    return _mixed(hashes + flow)


def hash_parts(hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Selector and the two numbers of 64-bit hashes."""
    g1 = _mixed(hashes + np.uint64(VECTOR_K))
    g2 = _mixed(g1 + np.uint64(VECTOR_K))
    return (hashes >> np.uint64(32)).astype(np.int64), (g1 >> np.uint64(16)).astype(np.int64), (g2 >> np.uint64(16)).astype(np.int64)


class Hashed:
    """The digests of a list of blocks, of any family: of their content, and bound to flows."""

    def __init__(self, blocks: list[bytes], family: str = "portable", salt: str = ""):
        self.blocks, self.family, self.salt = blocks, family, salt
        if family == "vector":
            size = np.array([len(b) for b in blocks], np.int64)
            end = np.cumsum(size)
            self.hashes = vector_hashes(np.frombuffer(b"".join(blocks), np.uint8), end - size, end, salt)

    def content(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        return hash_parts(self.hashes) if self.family == "vector" else md5_parts(digests(self.blocks, b"", self.family, self.salt))

    @functools.cached_property
    def heads(self) -> Heads:
        head = self.salt.encode()
        return Heads([head + b for b in self.blocks] if head else self.blocks)

    def binding(self, flows: list[str]):
        """These flows in the form that `bound` takes."""
        if self.family == "vector":
            return np.array([flow_number(f) for f in flows], np.uint64)
        tails = [flow_suffix(f) for f in flows]
        return Tails(tails) if self.family == "portable" else tails

    def bound(self, which: np.ndarray, flows, of: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Of the blocks with these numbers, each bound to the flow `of` it. flows: what `binding` gave."""
        if self.family == "vector":
            return hash_parts(bound_hashes(self.hashes[which], flows[of]))
        if self.family == "portable":
            return self.heads.parts(which, flows, of)
        return md5_parts(digests([self.blocks[i] + flows[f] for i, f in zip(which.tolist(), of.tolist(), strict=True)], b"", self.family, self.salt))


def flow_suffix(flow_key: str) -> bytes:
    return b"|" + flow_key.encode("utf-8", "replace")


def block_digest(block: Column, salt: str = "") -> Column:
    """Hexadecimal digest of block content, the portable family."""
    return F.md5(F.concat(F.lit(salt.encode()), block)) if salt else F.md5(block)


def flow_digest(block: Column, flow_key: Column, salt: str = "") -> Column:
    """Hexadecimal digest of block content bound to its flow."""
    return block_digest(F.concat(block, F.encode(F.concat(F.lit("|"), flow_key), "UTF-8")), salt)


def section_of(digest: Column, sections: int) -> Column:
    return F.pmod(F.conv(F.substring(digest, 1, 8), 16, 10).cast("bigint"), F.lit(sections)).cast("int")


def position_of(digest: Column, r, m_sub: int | Column) -> Column:
    """The r-th bit position inside a section of m_sub bits."""
    g1, g2 = (F.conv(F.substring(digest, a, 12), 16, 10).cast("bigint") for a in (9, 21))
    return F.pmod(g1 + (r if isinstance(r, Column) else F.lit(r)) * g2, m_sub if isinstance(m_sub, Column) else F.lit(m_sub))
