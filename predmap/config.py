"""Parameters of every map, stored with it."""

from __future__ import annotations

from dataclasses import asdict, dataclass


@dataclass(frozen=True)
class MapConfig:
    ribbon_width: int = 64  # bits of a row's band; small stores take less
    bucket: int = 512  # start positions that share a bump threshold, over the number of instances, 128 at least
    threshold_levels: int = 16  # classes by which a bucket can bump
    load: float = 0.96  # slots over equations of a layer that may bump
    max_layers: int = 4
    last_slack: float = 1.03  # slots over equations of the closing layer
    coder: str = "shannon"  # shannon, huffman, fixed
    filter: str = "all"  # all, root, none: which decisions have a filter
    r_mode: str = "integer"  # integer, randomised
    r_cap: int = 24
    prob_bits: int = 24
    fast_head: bool = True
    layout: str = "interleaved"  # interleaved, per_bit_key, per_position
    shard_keys: int = 1 << 17
    broadcast_bytes: int = 64 << 20
    seed: int = 0x5EED

    def as_dict(self) -> dict:
        return asdict(self)
