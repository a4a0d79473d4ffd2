"""Parameters of the twin-slot layout and of the tile plan."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class Config:
    """``segment_j``: a segment has 127 * 2^j transaction ids. ``slot_bits``: 8 packs seven
    element bits and the indicator; 16 and 32 store more and lower the floor on ranges.
    ``slack``: ranges within it of the critical load are doubled (0: the plain rule).
    ``max_rounds`` of placement, then the rest is repaired relationally. A tile holds
    about ``tile_items`` maps and ``tile_bytes`` bytes a side. ``distribution``: ``tiles`` ships maps
    to the tiles of their segment, ``segments`` ships each segment's maps to one task, which sends
    counts on; ``auto`` makes tiles of up to ``pairs.GROWTH`` times the items while the cores have enough.
    """

    segment_j: int = 9
    slot_bits: int = 8
    slack: float = 0.15
    max_rounds: int = 30
    seed: int = 20_240_601
    tile_items: int = 512
    tile_bytes: int = 16 << 20
    slice_bytes: int = 256 << 10
    bucket_elements: int = 500_000
    sort_by_width: bool = True
    triangle: bool = True
    distribution: str = "auto"

    def __post_init__(self):
        if self.slot_bits not in (8, 16, 32):
            raise ValueError("slot_bits must be 8, 16 or 32")
        if not 0 <= self.segment_j <= 13:
            raise ValueError("segment_j must be from 0 to 13")
        if self.distribution not in ("auto", "tiles", "segments"):
            raise ValueError("distribution must be auto, tiles or segments")

    @property
    def segment(self) -> int:
        """Transaction ids in a segment."""
        return 127 << self.segment_j

    @property
    def shift(self) -> int:
        """Low bits of a code that its position stands for: smallest s with codes that fit, zero being kept for vacancy."""
        s = 0
        while ((self.segment - 1) >> s) + 1 > (1 << (self.slot_bits - 1)) - 1:
            s += 1
        return s

    @property
    def r0_bits(self) -> int:
        """Interleave unit of the three tables."""
        return max(self.shift, 6)

    @property
    def cap_bits(self) -> int:
        """From this range on every element has slots of its own."""
        return (self.segment - 1).bit_length()
