"""Hierarchical machines: how many elements each level has."""

from __future__ import annotations

from dataclasses import dataclass


def ceil_lg(x: int) -> int:
    """ceil(log2 x) in integers; 0 up to 1."""
    return (x - 1).bit_length() if x > 1 else 0


@dataclass(frozen=True)
class MachineModel:
    """levels: elements of each level, the first is the whole machine (1)."""

    levels: tuple[int, ...] = (1, 5, 25)
    word_bits: int = 64

    def model_bits(self, n: int, ids: int | None = None) -> int:
        """Intra parts of ``ids`` identifiers (default n) in the bottom elements, inter parts once an element of levels 2..N-1."""
        bottom = self.levels[-1]
        return (n if ids is None else ids) * ceil_lg(-(-n // bottom)) + sum(h * ceil_lg(h) for h in self.levels[1:-1])

    def physical_bits(self, n: int, ids: int | None = None) -> int:
        """As the model, with the bottom level's inter parts, which decoding needs."""
        return self.model_bits(n, ids) + self.levels[-1] * ceil_lg(self.levels[-1])
