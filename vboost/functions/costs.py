"""The cost model: cipher computation, encryption with decryption, and communication of one tree."""

from __future__ import annotations

from dataclasses import dataclass

#: Measured microseconds of a 1024-bit operation in pure Python.
PRICES = {"enc": 10_201.0, "dec": 2_999.0, "add": 11.0, "shift": 1_369.0, "inverse": 288.0}


@dataclass(frozen=True)
class Cost:
    computation: float
    endecryption: float
    communication: float


def estimate(n: int, features: int, depth: int = 5, bins: int = 32, optimised: bool = False, slots: int = 6, literal: bool = False) -> Cost:
    """The rough model. `literal` leaves the feature number out of the histogram term, as one printed form has it."""
    nodes = 2**depth
    cells = nodes * features * bins
    if not optimised:
        return Cost(2.0 * n * depth * (1 if literal else features) + 2 * cells, 2.0 * n + 2 * cells, 2.0 * n + 2 * cells)
    return Cost(0.5 * n * depth * features + cells, n + cells / slots, n + cells / slots)


def reduction(n: int, features: int, depth: int = 5, bins: int = 32, slots: int = 6) -> dict[str, float]:
    a, b = (estimate(n, features, depth, bins, o, slots) for o in (False, True))
    return {k: 1 - getattr(b, k) / getattr(a, k) for k in ("computation", "endecryption", "communication")}


def exact(n: int, features: int, depth: int, bins: int, ciphers: int = 1, slots: int | None = None, small: list[int] | None = None) -> dict[str, int]:
    """Closed counts for a complete tree of one passive party.

    ciphers: for each row (1 packed, 2 apart, n_k multi-class). small: summed rows of the built children at layers
    1, 2, ... with histogram subtraction; None builds every layer whole. slots: members of a package, None without.
    """
    splits = (2**depth - 1) * features * (bins - 1)
    rows = n * depth if small is None else n + sum(small)
    infos = splits * ciphers if slots is None else (2**depth - 1) * -(-features * (bins - 1) // slots)
    return {"adds": ciphers * features * rows, "prefix": ciphers * splits, "enc": ciphers * n, "dec": infos, "shifts": 0 if slots is None else splits - infos, "items": ciphers * n + infos}


def price(counts: dict[str, int], prices: dict[str, float] = PRICES) -> float:
    """Seconds that the counted operations take."""
    return sum(counts.get(k, 0) * prices[p] for k, p in (("enc", "enc"), ("dec", "dec"), ("adds", "add"), ("prefix", "add"), ("shifts", "shift"), ("inversions", "inverse"))) / 1e6
