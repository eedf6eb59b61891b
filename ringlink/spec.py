"""Parameters that the parties agree on, and the closed forms behind them."""

from __future__ import annotations

import math
from dataclasses import dataclass

ENCODINGS = ("shared", "weighted_shared", "sampled")
SCHEMES = ("independent", "double")


def fit_length(length: int, parties: int, strict: bool = False) -> int:
    """The filter length rounded up to a multiple of the number of parties; strict raises instead."""
    if strict and length % parties:
        raise ValueError(f"length {length} is no multiple of {parties}")
    return parties * -(-length // parties)


def optimal_hashes(length: int, grams: float) -> float:
    return length / grams * math.log(2)


def false_positive_rate(length: int, grams: float, hashes: float | None = None) -> float:
    """At the optimum number of hashes, or for the number given."""
    if hashes is None:
        return (1 / 2 ** math.log(2)) ** (length / grams)
    return (1 - math.exp(-hashes * grams / length)) ** hashes


def expected_fill(length: int, grams: float, hashes: float) -> float:
    return 1 - math.exp(-hashes * grams / length)


@dataclass(frozen=True)
class LinkageSpec:
    """Thresholds are fractions (numerator, denominator), so that ties at a threshold compare as integers.

    `weights` (one per QID) share out the hashes (weighted_shared) or the record bits (sampled); empty: equal weights.
    """

    parties: int = 3
    length: int = 500
    hashes: int = 20
    q: int = 2
    pad: str = ""
    threshold: tuple[int, int] = (4, 5)
    seg_threshold: tuple[int, int] | None = None
    block_keys: tuple[str, ...] = ("surname",)
    block_fn: str = "soundex"
    qids: tuple[str, ...] = ("given", "surname", "suburb", "postcode")
    secret: str = ""
    encoding: str = "shared"
    scheme: str = "independent"
    weights: tuple[int, ...] = ()

    def __post_init__(self) -> None:
        problems = {
            "three parties or more are needed": self.parties < 3,
            "length, hashes and q are 1 or more": min(self.length, self.hashes, self.q) < 1,
            "a threshold lies between 0 and 1": any(not 0 <= n <= d or d < 1 for n, d in (self.threshold, self.prune)),
            "encoding is one of " + ", ".join(ENCODINGS): self.encoding not in ENCODINGS,
            "scheme is one of " + ", ".join(SCHEMES): self.scheme not in SCHEMES,
            "one weight above 0 for each QID": bool(self.weights) and (len(self.weights) != len(self.qids) or min(self.weights) <= 0),
            "pad is one sign": len(self.pad) > 1,
        }
        if bad := [text for text, wrong in problems.items() if wrong]:
            raise ValueError("; ".join(bad))

    @property
    def bits(self) -> int:
        return fit_length(self.length, self.parties)

    @property
    def width(self) -> int:
        """Bits of one piece."""
        return self.bits // self.parties

    @property
    def words(self) -> int:
        """Longs of 63 payload bits that one piece takes."""
        return -(-self.width // 63)

    @property
    def prune(self) -> tuple[int, int]:
        return self.threshold if self.seg_threshold is None else self.seg_threshold

    def _shares(self, total: int) -> tuple[int, ...]:
        """`total` dealt by weight: whole parts, the rest one by one from the first attribute on."""
        w = self.weights or (1,) * len(self.qids)
        base = [total * x // sum(w) for x in w]
        left = total - sum(base)
        return tuple(b + (i < left) for i, b in enumerate(base))

    @property
    def hashes_by_qid(self) -> tuple[int, ...]:
        """Hashes of each attribute: `hashes` on average, one at least; all alike unless weighted_shared."""
        if self.encoding != "weighted_shared":
            return (self.hashes,) * len(self.qids)
        return tuple(max(1, n) for n in self._shares(self.hashes * len(self.qids)))

    @property
    def bits_by_qid(self) -> tuple[int, ...]:
        """Record bits that a sampled encoding draws from each attribute's filter."""
        return self._shares(self.bits)
