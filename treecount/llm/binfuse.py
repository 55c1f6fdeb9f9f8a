"""Static binary-fuse filters with 8-bit fingerprints: about nine bits a key, no false negatives."""

from __future__ import annotations

import math
import struct

import numpy as np

U = np.uint64


def mix(keys: np.ndarray, seed: int) -> np.ndarray:
    """A 64-bit finaliser over key plus seed."""
    h = keys + U(seed)
    for shift, factor in ((33, 0xFF51AFD7ED558CCD), (33, 0xC4CEB9FE1A85EC53)):
        h = (h ^ (h >> U(shift))) * U(factor)
    return h ^ (h >> U(33))


class BinaryFuse:
    """Built once from a set of 64-bit keys; a key has three slots in neighbouring segments whose fingerprints xor to its own."""

    def __init__(self, seed: int, segment: int, segments: int, slots: np.ndarray):
        self.seed, self.segment, self.segments, self.slots = seed, segment, segments, slots

    @staticmethod
    def places(h: np.ndarray, segment: int, segments: int) -> np.ndarray:
        span = U(segment * segments)
        low = U(0xFFFFFFFF)
        first = ((h >> U(32)) * span + (((h & low) * span) >> U(32))) >> U(32)
        mask = U(segment - 1)
        second = (first + U(segment)) ^ ((h >> U(18)) & mask)
        third = (first + U(2 * segment)) ^ (h & mask)
        return np.stack([first, second, third]).astype(np.int64)

    @staticmethod
    def prints(h: np.ndarray) -> np.ndarray:
        return (h ^ (h >> U(32))).astype(np.uint8)

    @classmethod
    def build(cls, keys: np.ndarray) -> BinaryFuse:
        keys = np.unique(np.asarray(keys).astype(np.int64).view(np.uint64))
        n = len(keys)
        segment = 1 << max(2, min(18, math.floor(math.log(max(n, 2)) / math.log(3.33) + 2.25)))
        factor = max(1.125, 0.875 + 0.25 * math.log(1e6) / math.log(max(n, 2)))
        segments = max(1, -(-round(n * factor) // segment) - 2)
        if n == 0:
            return cls(0, segment, 0, np.zeros(0, np.uint8))
        for seed in range(1, 1000):
            h = mix(keys, seed * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF)
            at = cls.places(h, segment, segments)
            order = cls.peel(at, segment * (segments + 2))
            if order is not None:
                slots = np.zeros(segment * (segments + 2), np.uint8)
                want = cls.prints(h)
                for who, where in reversed(order):
                    # A slot of its own is still zero, so the xor of all three leaves the other two.
                    slots[where] = want[who] ^ slots[at[0, who]] ^ slots[at[1, who]] ^ slots[at[2, who]]
                return cls(seed, segment, segments, slots)
        raise RuntimeError("no seed fits")

    @staticmethod
    def peel(at: np.ndarray, size: int):
        """Rounds of (keys, slots): each key is alone in its slot once all earlier rounds are gone. None if some stay."""
        n = at.shape[1]
        flat = at.ravel()
        count = np.bincount(flat, minlength=size)
        total = np.zeros(size, np.int64)
        np.add.at(total, flat, np.tile(np.arange(n), 3))
        alone, rounds, done = np.flatnonzero(count == 1), [], 0
        while len(alone):
            who, first = np.unique(total[alone], return_index=True)
            rounds.append((who, alone[first]))
            done += len(who)
            gone = at[:, who].ravel()
            np.subtract.at(count, gone, 1)
            np.subtract.at(total, gone, np.tile(who, 3))
            gone = np.unique(gone)
            alone = gone[count[gone] == 1]
        return rounds if done == n else None

    def contains(self, keys: np.ndarray) -> np.ndarray:
        keys = np.asarray(keys).astype(np.int64).view(np.uint64)
        if not self.segments:
            return np.zeros(len(keys), bool)
        h = mix(keys, self.seed * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF)
        at = self.places(h, self.segment, self.segments)
        return (self.slots[at[0]] ^ self.slots[at[1]] ^ self.slots[at[2]]) == self.prints(h)

    def to_bytes(self) -> bytes:
        return struct.pack("<III", self.seed, self.segment, self.segments) + self.slots.tobytes()

    @classmethod
    def from_bytes(cls, raw: bytes) -> BinaryFuse:
        return cls(*struct.unpack_from("<III", raw), np.frombuffer(raw, np.uint8, offset=12))
