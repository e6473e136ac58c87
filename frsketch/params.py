"""Sketch parameters."""

from __future__ import annotations

from dataclasses import dataclass, replace

DIGEST_BITS = {"md5": 128, "sha1": 160, "sha256": 256, "xx": 128}


@dataclass(frozen=True)
class FrsParams:
    """p: log2 of the buckets; q: log2 of the exponent window; r: mantissa bits.

    hash: md5, sha1, sha256 (portable) or xx (two 64-bit hashes, bulk). mantissa: ``independent`` bit
    ranges or ``contiguous`` bits after the leading one. tail: ``capped`` exponents 1..2^q or
    ``overflow`` 1..2^q + 1."""

    p: int = 6
    q: int = 4
    r: int = 4
    hash: str = "md5"
    mantissa: str = "independent"
    tail: str = "capped"
    seed: int = 0

    def __post_init__(self) -> None:
        if self.hash not in DIGEST_BITS:
            raise ValueError(f"hash {self.hash!r} is none of {sorted(DIGEST_BITS)}")
        if self.mantissa not in ("independent", "contiguous") or self.tail not in ("capped", "overflow"):
            raise ValueError(f"mantissa {self.mantissa!r}, tail {self.tail!r}")
        if not (0 <= self.p <= 26 and 0 <= self.q <= 6 and 0 <= self.r <= 24):
            raise ValueError(f"p, q, r = {self.p}, {self.q}, {self.r} are out of range")
        if self.mantissa == "contiguous" and (self.hash == "xx" or self.p + self.zeros + self.r > DIGEST_BITS[self.hash]):
            raise ValueError(f"{self.p + self.zeros + self.r} bits do not fit {self.hash}")
        if self.hash != "xx" and self.mantissa == "independent" and self.zeros > 64:
            raise ValueError(f"a window of {self.zeros} bits does not fit")
        if self.hash == "xx" and self.zeros > 63:
            raise ValueError("bulk hashing has windows of 63 bits at most")

    @property
    def k(self) -> int:
        return 1 << self.p

    @property
    def window(self) -> int:
        return 1 << self.q

    @property
    def scale(self) -> int:
        return 1 << self.r

    @property
    def zeros(self) -> int:
        """Window bits looked at; all zero: the last exponent."""
        return self.window - 1 if self.tail == "capped" else self.window

    @property
    def last(self) -> int:
        """The largest exponent."""
        return self.zeros + 1

    def with_(self, **kw) -> "FrsParams":
        return replace(self, **kw)

    def tag(self) -> dict[str, str]:
        return {n: str(getattr(self, n)) for n in ("p", "q", "r", "hash", "mantissa", "tail", "seed")}


SMALL = FrsParams(6, 4, 4)
MEDIUM = FrsParams(10, 4, 8)
LARGE = FrsParams(15, 6, 10)
