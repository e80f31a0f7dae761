"""Parameters of the index."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class IndexSpec:
    """``b`` bits to a mask and ``h`` levels; a tree holds b ** h records."""

    b: int = 32
    h: int = 3

    def __post_init__(self):
        if self.b not in (2, 4, 8, 16, 32, 64) or self.h < 1:
            raise ValueError("b must be a power of two from 2 to 64, h at least 1")

    @property
    def tree(self) -> int:
        return self.b**self.h

    def span(self, level: int) -> int:
        """Records below one node of a level (0 = leaf masks)."""
        return self.b ** (level + 1)


PAPER = IndexSpec(32, 3)
SMALL = IndexSpec(8, 3)
