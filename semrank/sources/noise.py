"""The simulator's noise for many lists at once: MD5 of one block, on arrays."""

from __future__ import annotations

import math

import numpy as np

#: Bytes of a message that fits one block, before the mark of its end and its length.
BLOCK = 55
_TURNS = ((7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21))
_SINES = [int(abs(math.sin(i + 1)) * 2**32) for i in range(64)]
_START = (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)
_WORD = [i if i < 16 else (5 * i + 1) % 16 if i < 32 else (3 * i + 5) % 16 if i < 48 else 7 * i % 16 for i in range(64)]


def _steps(state: list[np.ndarray], words: list[np.ndarray | int], first: int, last: int) -> list[np.ndarray]:
    """Steps ``first`` to ``last`` - 1 of a block whose 16 words are arrays, or numbers where all messages have the same."""
    a, b, c, d = state
    f, g = np.empty_like(a), np.empty_like(a)
    for i in range(first, last):
        if i < 16:
            np.bitwise_xor(c, d, out=f)
            f &= b
            f ^= d
        elif i < 32:
            np.bitwise_xor(b, c, out=f)
            f &= d
            f ^= c
        elif i < 48:
            np.bitwise_xor(b, c, out=f)
            f ^= d
        else:
            np.invert(d, out=f)
            f |= b
            f ^= c
        w = words[_WORD[i]]
        f += a
        if isinstance(w, int):
            f += np.uint32((_SINES[i] + w) & 0xFFFFFFFF)
        else:
            f += w
            f += np.uint32(_SINES[i])
        turn = _TURNS[i // 16][i % 4]
        np.right_shift(f, np.uint32(32 - turn), out=g)
        f <<= np.uint32(turn)
        f |= g
        f += b
        # the array of a is free for the next step
        a, b, c, d, f = d, f, b, c, a
    return [a, b, c, d]


def first_digits(words: list[np.ndarray | int], n: int, same: int, times: int) -> np.ndarray:
    """The first 8 hex digits, as numbers, of MD5 of messages of one block: ``times`` for each of ``n`` columns.

    ``words`` are numbers, rows (for all messages of a column alike, as the first ``same`` are) or tables of a row for each message.
    """
    state = _steps([np.full(n, x, dtype=np.uint32) for x in _START], words, 0, same)
    state = [np.broadcast_to(x, (times, n)).copy() for x in state]
    # what is added to the first word of the state is made by the step 60
    return (_steps(state, words, same, 61)[1] + np.uint32(_START[0])).byteswap()


class ListNoise:
    """Noise of the keys of a list: md5 of ``prefix``, the sorted ids joined by '-', '|' and the key's id. Ids are given by their rank."""

    def __init__(self, prefix: bytes, ids: np.ndarray, amplitude: int):
        """``ids``: in order, none negative and none of more than seven digits (see ``fits``)."""
        text = np.char.mod("%d", ids).astype("S8")
        self.width = np.char.str_len(text).astype(np.uint64)
        # digits as a little-endian number, the first one lowest
        self.digits = np.frombuffer(text.tobytes(), dtype="<u8").astype(np.uint64)
        self.prefix, self.amplitude = prefix, amplitude

    @staticmethod
    def fits(prefix: bytes, ids: np.ndarray, m: int) -> bool:
        if not len(ids) or ids.min() < 0 or ids.max() >= 10**7:
            return False
        return len(prefix) + (m + 1) * (len(str(ids.max())) + 1) - 1 <= BLOCK

    @staticmethod
    def _put(words: list, piece: np.ndarray, at: np.ndarray) -> None:
        """``piece``'s up to 8 bytes from the byte ``at`` on."""
        word, shift = at >> np.uint64(3), (at & np.uint64(7)) << np.uint64(3)
        low, high = piece << shift, (piece >> np.uint64(1)) >> (np.uint64(63) - shift)
        least, most = int(word.min()), int(word.max())
        for q in range(least, most + 1):
            here = word == q
            x, y = (low, high) if least == most else (low * here, high * here)
            for to, bits in ((q, x), (q + 1, y)):
                if to < 8:
                    words[to] = bits if words[to] is None else words[to] | bits

    @staticmethod
    def _halves(words: list, fixed: list[int]) -> list[np.ndarray | int]:
        """32-bit words, numbers where no array has been put."""
        out: list[np.ndarray | int] = []
        for x, c in zip(words, fixed, strict=True):
            if x is None:
                out += [c & 0xFFFFFFFF, c >> 32]
            else:
                x = x | np.uint64(c)
                out += [x.astype(np.uint32), (x >> np.uint64(32)).astype(np.uint32)]
        return out

    def of(self, by_id: np.ndarray) -> np.ndarray:
        """Noise of the keys in each column, which are in the order of their ids."""
        m, n = by_id.shape
        digits, width = self.digits[by_id], self.width[by_id]
        begin = self.prefix.ljust(64, b"\0")
        fixed = [int.from_bytes(begin[i : i + 8], "little") for i in range(0, 64, 8)]
        words: list[np.ndarray | None] = [None] * 8
        at = np.full(n, len(self.prefix), dtype=np.uint64)
        for i in range(m):
            sign = np.uint64(ord("-" if i + 1 < m else "|"))
            self._put(words, digits[i] | sign << (width[i] << np.uint64(3)), at)
            at = at + width[i] + np.uint64(1)
        begun = int(at.min()) >> 3
        # each key's own id, the mark of the end and the length; words before them are a row for all
        at = np.broadcast_to(at, (m, n))
        own: list[np.ndarray | None] = [x if q < begun or x is None else np.broadcast_to(x, (m, n)) for q, x in enumerate(words)]
        self._put(own, digits | np.uint64(0x80) << (width << np.uint64(3)), at)
        size = (at + width) << np.uint64(3)
        own[7] = size if own[7] is None else own[7] | size
        got = first_digits(self._halves(own, fixed), n, 2 * begun, m)
        span = np.uint32(2 * self.amplitude + 1)
        got -= got // span * span
        return got.astype(np.int64) - self.amplitude
