"""MD5 over many texts at once: what the planted words are drawn from, worked out in numpy."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa

#: Steps of RFC 1321: rotations of each round, constants, and the start.
_TURNS = ((7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21))
_SINES = [int(abs(math.sin(i + 1)) * 2**32) for i in range(64)]
_START = (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)


def _block(state: list[np.ndarray], words: list) -> list[np.ndarray]:
    """One block of 16 words, each an array or, where all texts have the same bytes, a number."""
    a, b, c, d = state
    t, turned = np.empty_like(a), np.empty_like(a)
    a, b, c, d = a.copy(), b.copy(), c.copy(), d.copy()
    for i in range(64):
        if i < 16:
            g = i
            np.bitwise_xor(c, d, out=t)
            np.bitwise_and(t, b, out=t)
            np.bitwise_xor(t, d, out=t)
        elif i < 32:
            g = (5 * i + 1) % 16
            np.bitwise_xor(b, c, out=t)
            np.bitwise_and(t, d, out=t)
            np.bitwise_xor(t, c, out=t)
        elif i < 48:
            g = (3 * i + 5) % 16
            np.bitwise_xor(b, c, out=t)
            np.bitwise_xor(t, d, out=t)
        else:
            g = 7 * i % 16
            np.invert(d, out=t)
            np.bitwise_or(t, b, out=t)
            np.bitwise_xor(t, c, out=t)
        np.add(t, a, out=t)
        if isinstance(words[g], int):
            np.add(t, np.uint32((_SINES[i] + words[g]) % 2**32), out=t)
        else:
            np.add(t, words[g], out=t)
            np.add(t, np.uint32(_SINES[i]), out=t)
        by = _TURNS[i // 16][i % 4]
        np.right_shift(t, np.uint32(32 - by), out=turned)
        np.left_shift(t, np.uint32(by), out=t)
        np.bitwise_or(t, turned, out=t)
        np.add(t, b, out=a)  # the register that drops out takes the new value
        a, b, c, d = d, a, b, c
    return [x + y for x, y in zip(state, (a, b, c, d))]


class Draws:
    """Draws of [0, 1) in thousandths from texts ``key/rest``, for the keys given and any ``rest``.

    A draw is the number of the first seven digits of the text's MD5 value, modulo 1000.
    """

    def __init__(self, keys: pa.Array):
        keys = keys.cast(pa.large_binary())
        at, data = np.frombuffer(keys.buffers()[1], np.int64)[keys.offset : keys.offset + len(keys) + 1], keys.buffers()[2]
        held = np.frombuffer(data, np.uint8) if data is not None else np.empty(0, np.uint8)
        lengths = np.diff(at)
        self.n, self.groups = len(keys), []
        for n in np.unique(lengths):
            rows = np.flatnonzero(lengths == n)
            self.groups.append((rows, held[at[rows][:, None] + np.arange(n)]))

    def __call__(self, rest: str, where: np.ndarray | None = None) -> np.ndarray:
        """One draw for each key; without a draw (0) where ``where`` is false."""
        out = np.zeros(self.n)
        for rows, key in self.groups:
            if where is not None:
                chosen = where[rows]
                rows, key = rows[chosen], key[chosen]
            if len(rows):
                out[rows] = self._thousandths(key, b"/" + rest.encode()) / 1000.0
        return out

    @staticmethod
    def _thousandths(key: np.ndarray, rest: bytes) -> np.ndarray:
        n, own = len(key), key.shape[1]
        length = own + len(rest)
        fixed = rest + b"\x80" + bytes((55 - length) % 64) + (8 * length).to_bytes(8, "little")
        shared = -own % 4  # bytes behind the key that complete its last word
        head = np.concatenate([key, np.broadcast_to(np.frombuffer(fixed[:shared], np.uint8), (n, shared))], axis=1)
        varied = np.ascontiguousarray(np.ascontiguousarray(head).view("<u4").T)
        words = [*varied, *(int.from_bytes(fixed[i : i + 4], "little") for i in range(shared, len(fixed), 4))]
        state = [np.full(n, x, np.uint32) for x in _START]
        for i in range(0, len(words), 16):
            state = _block(state, words[i : i + 16])
        return (state[0].byteswap() >> np.uint32(4)) % 1000
