"""MD5 of many short texts at once, in NumPy: the digests that order ties."""

from __future__ import annotations

from hashlib import md5

import numpy as np
import pyarrow as pa

_SINES = [int(abs(np.sin(i + 1)) * 2**32) for i in range(64)]
_TURNS = (7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21)
_FIRST = 0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476
#: Texts that are worked on together, so that their words stay near the processor.
TOGETHER = 1 << 13
#: Texts of more bytes are digested one by one.
LONG = 200


def _rounds(state: list[np.ndarray], words: np.ndarray) -> None:
    """Adds a block of 16 words (one row each) of every text to its state."""
    a, b, c, d = (x.copy() for x in state)
    f, t = np.empty_like(a), np.empty_like(a)
    for i in range(64):
        part = i // 16
        if part == 0:
            np.bitwise_xor(c, d, out=f)
            f &= b
            f ^= d
            g = i
        elif part == 1:
            np.bitwise_xor(b, c, out=f)
            f &= d
            f ^= c
            g = (5 * i + 1) % 16
        elif part == 2:
            np.bitwise_xor(b, c, out=f)
            f ^= d
            g = (3 * i + 5) % 16
        else:
            np.bitwise_not(d, out=f)
            f |= b
            f ^= c
            g = 7 * i % 16
        a += f
        a += np.uint32(_SINES[i])
        a += words[g]
        turn = _TURNS[part][i % 4]
        np.left_shift(a, np.uint32(turn), out=t)
        a >>= np.uint32(32 - turn)
        a |= t
        a += b
        a, b, c, d = d, a, b, c
    for x, y in zip(state, (a, b, c, d)):
        x += y


class Ties:
    """Texts of rows, whose digests under a name order ties: MD5 of ``name:text``, of ``name`` alone for null texts."""

    def __init__(self, texts: pa.Array):
        self.texts, self._ready = texts, None

    def __len__(self) -> int:
        return len(self.texts)

    def _lay_out(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """A colon, the text and the end mark of every row, zeros behind; their sizes; which texts are longer than ``LONG``."""
        n = len(self.texts)
        offsets = np.frombuffer(self.texts.buffers()[1], np.int32, n + 1, self.texts.offset * 4).astype(np.int64)
        sizes = np.diff(offsets)
        null = np.asarray(self.texts.is_null())
        long = sizes > LONG
        sizes[long] = 0
        wide = int(sizes.max())
        used = np.frombuffer(self.texts.buffers()[2] or b"", np.uint8)[: offsets[-1]]
        data = np.concatenate([used, np.zeros(wide + 1, np.uint8)])
        m = np.zeros((n, wide + 2), np.uint8)
        m[:, 0] = ord(":")
        if wide:
            m[:, 1 : wide + 1] = np.lib.stride_tricks.sliding_window_view(data, wide)[offsets[:-1]]
            m[:, 1 : wide + 1] *= np.arange(wide, dtype=np.uint8) < sizes.astype(np.uint8)[:, None]
        sizes += 1
        m[null], sizes[null] = 0, 0
        m[np.arange(n), sizes] = 0x80
        return m, sizes, long

    def digests(self, name: str, at: np.ndarray) -> np.ndarray:
        """Two unsigned 64-bit numbers for each of these rows, in the order of the digests."""
        out = np.empty((len(at), 2), np.uint64)
        if not len(at):
            return out
        if self._ready is None:
            self._ready = self._lay_out()
        m, sizes, long = self._ready
        start = np.frombuffer(name.encode(), np.uint8)
        p = len(start)
        size = sizes[at] + p
        count = (size + 8) // 64 + 1  # blocks of 64 bytes, with the end mark and the length
        for blocks in np.unique(count).tolist():
            these = np.flatnonzero(count == blocks)
            message = np.zeros((min(len(these), TOGETHER), 64 * blocks), np.uint8)
            message[:, :p] = start
            room = min(m.shape[1], 64 * blocks - 8 - p)
            for k in range(0, len(these), TOGETHER):
                own = these[k : k + TOGETHER]
                some = message[: len(own)]
                some[:, p : p + room] = m[at[own], :room]
                some[:, -8:] = (size[own].astype("<u8") * 8).view(np.uint8).reshape(-1, 8)
                words = np.ascontiguousarray(some.view("<u4").T)
                state = [np.full(len(own), x, np.uint32) for x in _FIRST]
                for b in range(blocks):
                    _rounds(state, words[16 * b : 16 * b + 16])
                a, b, c, d = (x.byteswap().astype(np.uint64) for x in state)
                out[own, 0], out[own, 1] = a << np.uint64(32) | b, c << np.uint64(32) | d
        for k in np.flatnonzero(long[at]).tolist():
            found = md5(f"{name}:{self.texts[int(at[k])].as_py()}".encode()).digest()
            out[k] = int.from_bytes(found[:8], "big"), int.from_bytes(found[8:], "big")
        return out
