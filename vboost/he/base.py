"""What a backend must offer, with operation counters, and two backends without encryption."""

from __future__ import annotations

from abc import ABC, abstractmethod
from collections import Counter

import numpy as np


def to_bytes(x: int, width: int) -> bytes:
    return x.to_bytes(width, "big")


_LOW, _HALF = np.uint64((1 << 32) - 1), np.uint64(32)


class Backend(ABC):
    """Additive ciphers over non-negative integers below 2^iota, as fixed-width big-endian bytes."""

    iota: int
    width: int

    def __init__(self) -> None:
        self.counts: Counter[str] = Counter()

    @abstractmethod
    def encrypt(self, m: int) -> bytes: ...

    @abstractmethod
    def decrypt(self, c: bytes) -> int: ...

    @abstractmethod
    def add(self, a: bytes, b: bytes) -> bytes: ...

    @abstractmethod
    def scale(self, c: bytes, k: int) -> bytes: ...

    @abstractmethod
    def sub(self, a: bytes, b: bytes) -> bytes: ...

    def sub_all(self, a: list[bytes], b: list[bytes]) -> list[bytes]:
        return [self.sub(x, y) for x, y in zip(a, b)]

    def fold(self, ciphers: list[bytes]) -> bytes:
        acc = ciphers[0]
        for c in ciphers[1:]:
            acc = self.add(acc, c)
        return acc

    def encrypt_fields(self, values: np.ndarray, shifts: list[int]) -> np.ndarray:
        """Ciphers as rows of bytes: of each row of non-negative 64-bit integers, moved up by `shifts` bits and added."""
        ints = [sum(int(v) << s for v, s in zip(row, shifts)) for row in values]
        return np.frombuffer(b"".join(map(self.encrypt, ints)), np.uint8).reshape(len(values), self.width)

    def fold_by(self, at: np.ndarray, ciphers: np.ndarray) -> dict[int, bytes]:
        """The sum of the ciphers (rows of bytes) at each place that occurs in `at`."""
        out: dict[int, bytes] = {}
        for k, row in zip(at.tolist(), ciphers):
            c = row.tobytes()
            out[k] = self.add(out[k], c) if k in out else c
        return out

    def shift(self, c: bytes, bits: int) -> bytes:
        self.counts["shifts"] += 1
        return self.scale(c, 1 << bits)

    def public(self) -> "Backend":
        """The backend as a passive party holds it."""
        return self


class Mock(Backend):
    """Transparent integers in the cipher's place: the same code path and counts, without the arithmetic's price."""

    def __init__(self, iota: int = 1023) -> None:
        super().__init__()
        self.iota, self.width = iota, (iota + 9) // 8

    def encrypt(self, m: int) -> bytes:
        self.counts["enc"] += 1
        if not 0 <= m < 1 << self.iota:
            raise OverflowError("plaintext outside the cipher's space")
        return to_bytes(m, self.width)

    def encrypt_fields(self, values: np.ndarray, shifts: list[int]) -> np.ndarray:
        """The same by arrays of 32-bit limbs, the lowest first."""
        if max(shifts) + 64 > min(self.iota, 8 * self.width):
            return super().encrypt_fields(values, shifts)
        self.counts["enc"] += len(values)
        limbs = np.zeros((max(shifts) // 32 + 4, len(values)), np.uint64)
        for v, s in zip(values.T.astype(np.uint64), shifts):
            k, bits = divmod(s, 32)
            for i, half in enumerate((v & _LOW, v >> _HALF)):
                moved = half << np.uint64(bits)
                limbs[k + i] += moved & _LOW
                limbs[k + i + 1] += moved >> _HALF
        for k in range(len(limbs) - 1):
            limbs[k + 1] += limbs[k] >> _HALF
            limbs[k] &= _LOW
        low = np.ascontiguousarray(limbs[::-1].T.astype(">u4")).view(np.uint8).reshape(len(values), -1)[:, -self.width :]
        out = np.zeros((len(values), self.width), np.uint8)
        out[:, self.width - low.shape[1] :] = low
        return out

    def fold_by(self, at: np.ndarray, ciphers: np.ndarray) -> dict[int, bytes]:
        """The same by sums of 16-bit limbs, which doubles hold exactly; leading zeros are not summed."""
        places, at = np.unique(at, return_inverse=True)
        n = len(ciphers)
        used = self.width - int(np.argmax(ciphers.any(axis=0))) if n else 0
        used = min(used + used % 2, self.width)
        raw = np.zeros((n, used + used % 2), np.uint8)
        raw[:, raw.shape[1] - used :] = ciphers[:, self.width - used :]
        sums = [np.bincount(at, weights=limb, minlength=len(places)) for limb in raw.view(">u2").T]
        self.counts["adds"] += n - len(places)
        out = {}
        for k, limbs in zip(places.tolist(), zip(*(s.astype(np.int64).tolist() for s in sums))):
            total = 0
            for x in limbs:
                total = (total << 16) + x
            out[k] = to_bytes(total, self.width)
        return out

    def decrypt(self, c: bytes) -> int:
        self.counts["dec"] += 1
        return int.from_bytes(c, "big")

    def add(self, a: bytes, b: bytes) -> bytes:
        self.counts["adds"] += 1
        return to_bytes(int.from_bytes(a, "big") + int.from_bytes(b, "big"), self.width)

    def scale(self, c: bytes, k: int) -> bytes:
        return to_bytes(int.from_bytes(c, "big") * k, self.width)

    def sub(self, a: bytes, b: bytes) -> bytes:
        self.counts["inversions"] += 1
        return to_bytes(int.from_bytes(a, "big") - int.from_bytes(b, "big"), self.width)
