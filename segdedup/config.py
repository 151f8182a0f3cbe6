"""The frozen rule of an index generation."""

from __future__ import annotations

import hashlib
import json
import random
from dataclasses import asdict, dataclass

PRIME = 2**31 - 1


@dataclass(frozen=True)
class DedupConfig:
    """normalise: ascii (lower A-Z, ASCII white space collapsed) or none; k words a shingle; p
    signature positions in B bands; family portable31 (same values in any SQL engine) or xx64.
    A band's keys fall into 2^shard_bits ranges, each a row of a segment (for 5e9 keys a band, 16
    bits make rows of 600 KB); a segment has `buckets` files."""

    normalise: str = "ascii"
    k: int = 5
    p: int = 128
    bands: int = 16
    family: str = "xx64"
    key_bits: int = 64
    fanout: int = 4
    shard_bits: int = 4
    buckets: int = 4
    seed: int = 7

    def __post_init__(self):
        if self.p % self.bands:
            raise ValueError(f"{self.p} positions do not split into {self.bands} bands")

    @property
    def rows(self) -> int:
        return self.p // self.bands

    @property
    def digest(self) -> str:
        return hashlib.sha256(json.dumps(asdict(self), sort_keys=True).encode()).hexdigest()[:16]

    def coefficients(self) -> list[tuple[int, int]]:
        draw = random.Random(self.seed)
        return [(draw.randrange(1, PRIME), draw.randrange(0, PRIME)) for _ in range(self.p)]


PORTABLE = DedupConfig(p=32, bands=8, family="portable31")
