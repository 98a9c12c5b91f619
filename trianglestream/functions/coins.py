"""Portable coins of many ranks at once: md5 of ``seed:trial:worker:rank`` in arrays.

A reservoir takes in few of the edges it considers, so nearly all coins say no. Ranks of
a block differ in their last digits only: the rest of the text is constant, and the
steps of the hash run over arrays that stay in the cache. The last three steps run for
those ranks alone whose leading 32 bits may say yes.
"""

from __future__ import annotations

import hashlib

import numpy as np

from .hashing import DIGITS, RANGE

#: Ranks below SMALL are hashed one by one, those below LARGE in blocks of 10⁴, later ones in blocks of 10⁵.
SMALL, LARGE = 1000, 100_000
_TURNS = [(7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21)]
_SINES = [int(abs(np.sin(i + 1.0)) * 2**32) for i in range(64)]
_START = (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)
_MASK = 0xFFFFFFFF


def _word(i: int) -> int:
    """Word of the text that step i takes."""
    return (i, 5 * i + 1, 3 * i + 5, 7 * i)[i // 16] % 16


def _mixed(i: int, b, c, d):
    if i < 16:
        return d ^ (b & (c ^ d))
    if i < 32:
        return c ^ (d & (b ^ c))
    if i < 48:
        return b ^ c ^ d
    return c ^ (b | (d ^ _MASK))


class Blocks:
    """Hashes of blocks of ranks that differ in their last ``low`` digits."""

    def __init__(self, low: int):
        self.low, self.size = low, 10**low
        self.buffers = [np.empty(self.size, np.uint32) for _ in range(5)]
        self.turns = [[(np.array(t, np.uint32), np.array(32 - t, np.uint32)) for t in row] for row in _TURNS]
        digits = (np.arange(self.size)[:, None] // 10 ** np.arange(low)[::-1] % 10 + ord("0")).astype(np.uint32)
        self.tails = []  # by the place of the first such digit in its word: the words these digits touch
        for at in range(4):
            words = [np.zeros(self.size, np.uint32) for _ in range((at + low + 3) // 4)]
            for j in range(low):
                words[(at + j) // 4] |= digits[:, j] << np.uint32(8 * ((at + j) % 4))
            self.tails.append(words)

    def leading(self, prefix: bytes, first: int):
        """State after 61 steps of all texts ``prefix`` + rank, for the block of ``first``, and the words of the texts. A block
        that begins at zero has ranks of so many digits from a tenth of its size on; those before are void."""
        head = prefix + (str(first // self.size).encode() if first else b"")
        length = len(head) + self.low
        if length > 55:
            raise ValueError("the text of a coin must fit one block of the hash")
        text = bytearray(64)
        text[: len(head)] = head
        text[length] = 0x80
        text[56:64] = (8 * length).to_bytes(8, "little")
        words = [int.from_bytes(text[4 * i : 4 * i + 4], "little") for i in range(16)]
        at = len(head) // 4
        for j, tail in enumerate(self.tails[len(head) % 4]):
            words[at + j] = tail | np.uint32(words[at + j])
        a, b, c, d = _START
        for i in range(at):
            a, b, c, d = d, b + self._turned((a + _mixed(i, b, c, d) + _SINES[i] + words[i]) & _MASK, i) & _MASK, b, c
        a, b, c, d, x = (self._filled(buffer, value) for buffer, value in zip(self.buffers, (a, b, c, d, 0)))
        added = np.zeros((), np.uint32)
        for i in range(at, 61):
            if i < 16:
                np.bitwise_xor(c, d, x)
                np.bitwise_and(x, b, x)
                np.bitwise_xor(x, d, x)
            elif i < 32:
                np.bitwise_xor(b, c, x)
                np.bitwise_and(x, d, x)
                np.bitwise_xor(x, c, x)
            elif i < 48:
                np.bitwise_xor(b, c, x)
                np.bitwise_xor(x, d, x)
            else:
                np.invert(d, x)
                np.bitwise_or(x, b, x)
                np.bitwise_xor(x, c, x)
            np.add(a, x, a)
            word, (left, right) = words[_word(i)], self.turns[i // 16][i % 4]
            if isinstance(word, int):
                added[...] = (word + _SINES[i]) & _MASK
            else:
                np.add(a, word, a)
                added[...] = _SINES[i]
            np.add(a, added, a)
            np.left_shift(a, left, x)
            np.right_shift(a, right, a)
            np.bitwise_or(a, x, a)
            np.add(a, b, a)
            a, b, c, d = d, a, b, c
        return a, b, c, d, words

    @staticmethod
    def _turned(x, i: int):
        turn = _TURNS[i // 16][i % 4]
        return ((x << turn) | (x >> (32 - turn))) & _MASK

    @staticmethod
    def _filled(buffer, value):
        buffer.fill(value)
        return buffer

    def within(self, prefix: bytes, first: int, most: int) -> tuple[np.ndarray, np.ndarray]:
        """(rank, slot) of the block's ranks whose uniform slot of rank, from 1, is at most ``most``."""
        a, b, c, d, words = self.leading(prefix, first)
        lead = (b + np.uint32(_START[0])).byteswap()  # after step 60 the newest word is the last but three: it ends as the first
        low = max(first, self.size // 10)
        bound = min(_MASK, most * 2**32 // low + 1)
        at = np.flatnonzero(lead <= np.uint32(bound))
        if not first:
            at = at[at >= low]
        lead = lead[at].astype(np.int64)
        a, b, c, d = (x[at].astype(np.int64) for x in (a, b, c, d))
        for i in range(61, 64):
            word = words[_word(i)]
            word = word if isinstance(word, int) else word[at].astype(np.int64)
            a, b, c, d = d, (b + self._turned((a + _mixed(i, b, c, d) + _SINES[i] + word) & _MASK, i)) & _MASK, b, c
        second = ((b + _START[1]) & _MASK).astype(np.uint32).byteswap().astype(np.int64)
        rank = first + at
        slot = np.floor(((lead << 20) | (second >> 12)) / RANGE * rank).astype(np.int64) + 1
        kept = slot <= most
        return rank[kept], slot[kept]


class Coins:
    """Uniform reservoir slots by portable coins; holds the buffers."""

    def __init__(self):
        self.blocks = {}

    def slots_within(self, prefix: str, low: int, high: int, most: int) -> tuple[np.ndarray, np.ndarray]:
        """(rank, slot), in order, of the ranks from ``low`` to below ``high`` whose uniform slot, by the coin of ``prefix`` + rank,
        is at most ``most``."""
        text, ranks = prefix.encode(), np.arange(low, max(low, min(high, SMALL)), dtype=np.int64)
        coins = np.array([int(hashlib.md5(text + str(r).encode()).hexdigest()[:DIGITS], 16) / RANGE for r in ranks.tolist()], np.float64)
        slots = np.floor(coins * ranks).astype(np.int64) + 1
        found = [(ranks[slots <= most], slots[slots <= most])]
        for digits, begin, end in ((4, max(low, SMALL), min(high, LARGE)), (5, max(low, LARGE), high)):
            if begin < end and digits not in self.blocks:
                self.blocks[digits] = Blocks(digits)
            for first in range(begin // 10**digits * 10**digits, end, 10**digits) if begin < end else ():
                blocks = self.blocks[digits]
                rank, slot = blocks.within(text, first, most)
                mine = (rank >= begin) & (rank < end)
                found.append((rank[mine], slot[mine]))
        return tuple(np.concatenate(x) for x in zip(*found))
