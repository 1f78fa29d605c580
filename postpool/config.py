"""Parameters of an index."""

from __future__ import annotations

from dataclasses import dataclass

LAYOUTS = ("linked", "capped", "contiguous")


@dataclass(frozen=True)
class IndexConfig:
    """block: postings of a segment (at most 256); cap_log2: buffers grow to 2**cap_log2 blocks (0: linked list of
    single segments); df_threshold: rarer terms are dropped; n_shards: document ranges with an index each; pos_bits:
    positions are numbers of so many bits, and what a longer document does: overflow 'truncate' (its later words are
    left out) or 'drop' (all of them are)."""

    block: int = 128
    cap_log2: int = 5
    df_threshold: int = 10
    positional: bool = True
    layout: str = "capped"
    n_shards: int = 1
    threshold_scope: str = "global"
    pos_bits: int = 32
    overflow: str = "truncate"

    def __post_init__(self):
        if not 1 <= self.block <= 256 or self.cap_log2 < 0 or self.layout not in LAYOUTS or self.n_shards < 1:
            raise ValueError(f"bad index parameters: {self}")
        if self.threshold_scope not in ("global", "shard"):
            raise ValueError(self.threshold_scope)
        if not 1 <= self.pos_bits <= 32 or self.overflow not in ("truncate", "drop"):
            raise ValueError(f"bad positions: {self.pos_bits}, {self.overflow}")

    @property
    def cap(self) -> int:
        return 0 if self.layout == "linked" else self.cap_log2
