"""Settings that both parties agree on before they encode."""

from __future__ import annotations

import hashlib
from dataclasses import dataclass

WORD_BITS = 60  # bits in a filter word; the sign bit of a BIGINT is never set
WORDS = 5
LEXICON = 500


@dataclass(frozen=True)
class Linkage:
    """Options of encoding, blocking, noise and classification; all hashable, all public."""

    seed: int = 7
    secret: str = "shared"
    n_bits: int = 300
    k_hash: int = 10
    q: int = 2
    label_bits: int = 12
    label_tables: int = 5
    threshold: float = 0.8
    sensitivity: float = 1.0
    eps: float = 1.0
    flip: float = 0.4
    fill: float = 0.5

    def label_positions(self, table: int) -> list[int]:
        """Filter positions of a table's label: the first ones in order of a keyed digest."""
        order = sorted(range(self.n_bits), key=lambda p: hashlib.md5(f"{self.seed}|label|{table}|{p}".encode()).hexdigest())
        return order[: self.label_bits]


DEFAULT = Linkage()
