"""First words of many md5 digests at once, to look at far more portable uniforms than can be made one by one."""

from __future__ import annotations

import math

import numpy as np

_ADDED = [int(abs(math.sin(i + 1)) * 2**32) for i in range(64)]
_TURNS = [t for four in ((7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21)) for t in four * 4]
_WORD = [i if i < 16 else (5 * i + 1) % 16 if i < 32 else (3 * i + 5) % 16 if i < 48 else 7 * i % 16 for i in range(64)]
_START = (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)
MOST = 55  # bytes of a message of one block


def first_word(words: list, n: int, room: list[np.ndarray]) -> np.ndarray:
    """The digest's first four bytes as a big-endian number, for ``n`` messages of one block.

    ``words``: the block's 16 little-endian words, each a number that all share or an array of uint32; ``room``: seven arrays of
    ``n`` uint32, one of them returned. The first word is settled three steps before the end.
    """
    u, full = np.uint32, 0xFFFFFFFF
    a, b, c, d = _START
    f, t, *ring = room
    i = 0
    while i < 16 and not isinstance(words[i], np.ndarray):  # steps that all messages share
        x = (a + ((b & c) | (~b & d)) + _ADDED[i] + words[i]) & full
        a, b, c, d = d, (b + ((x << _TURNS[i]) | (x >> (32 - _TURNS[i])))) & full, b, c
        i += 1
    for r, v in zip(ring, (a, b, c, d)):
        r[:] = v
    a, b, c, d, spare = ring
    for i in range(i, 61):
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
        np.add(f, a, out=f)
        w = words[_WORD[i]]
        if isinstance(w, np.ndarray):
            np.add(f, w, out=f)
            w = 0
        np.add(f, u((_ADDED[i] + w) & full), out=f)
        np.right_shift(f, u(32 - _TURNS[i]), out=t)
        np.left_shift(f, u(_TURNS[i]), out=f)
        np.bitwise_or(f, t, out=f)
        np.add(f, b, out=spare)
        a, b, c, d, spare = d, spare, b, c, a
    np.add(b, u(_START[0]), out=b)
    return b.byteswap(inplace=True)


class Tails:
    """Ends of messages of one length, to be put after any beginning."""

    def __init__(self, ends: list[bytes]):
        self.length = len(ends[0])
        self.raw = np.frombuffer(b"".join(ends), np.uint8).reshape(len(ends), self.length)
        self.shifted: dict[int, list[np.ndarray]] = {}

    def _words(self, shift: int) -> list[np.ndarray]:
        """The ends and the mark after them as words, with ``shift`` bytes left free before."""
        if shift not in self.shifted:
            wide = np.zeros((len(self.raw), -(-(shift + self.length + 1) // 4) * 4), np.uint8)
            wide[:, shift : shift + self.length] = self.raw
            wide[:, shift + self.length] = 0x80
            self.shifted[shift] = list(np.ascontiguousarray(wide.view("<u4").T))
        return self.shifted[shift]

    def first_words(self, start: bytes, i: int, j: int, room: list[np.ndarray]) -> np.ndarray:
        """``first_word`` of ``start`` and each of the ends i to j."""
        size = len(start) + self.length
        if size > MOST:
            raise ValueError(f"{size} bytes do not fit one block")
        whole, n = len(start) // 4, j - i
        ends = [w[i:j] for w in self._words(len(start) % 4)]
        if len(start) % 4:
            ends[0] = ends[0] | np.uint32(int.from_bytes(start[whole * 4 :], "little"))
        words = [int.from_bytes(start[k * 4 : k * 4 + 4], "little") for k in range(whole)] + ends
        words += [0] * (14 - len(words)) + [size * 8, 0]
        return first_word(words, n, [r[:n] for r in room])
