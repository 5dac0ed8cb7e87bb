"""Settings of a blocking run."""

from __future__ import annotations

from dataclasses import dataclass, replace


@dataclass(frozen=True)
class BlockingConfig:
    """block_cap: most records of a block that is compared exhaustively. key_cap: most over-size keys with which
    a record goes into an intersection. shrink_ratio: a child block may have at most this part of its smaller
    parent's records; it is applied in thousandths, so that equality is exact.

    counting: 'exact' counts all postings by a shuffle of partial counts; 'sketch' lets a count-min sketch
    settle most keys first, or 'buckets', its form as a table, where the sketch would pass sketch_bytes; 'pivot'
    collects the ids of every key; 'auto' takes the sketch where it pays and stays within sketch_bytes, else 'exact'.
    membership: how over-counted keys are told from duplicates, 'join' or 'bloom'. shrink_on: whether the
    shrink test sees the exact size or the sketch's estimate. survivor_store: 'broadcast', 'join', 'auto', or 'sketch', which
    sends a sketch of the survivors' sizes: keys that it takes for survivors go on too, with an estimate of their size.
    pair_dedup: 'shuffle' groups pairs, 'propagate' decides inside blocks, 'auto' by the keys per record.
    hash: how keys are made: 'md5', 'xx128', or, for an index whose keys are 64-bit hashes already, 'h64', which is meant for
    counts: among some 10 million keys two meet by chance about once in 300,000 runs.
    salvage: what becomes of over-size blocks' members that no other over-size block holds: 'none', as published, leaves
    them uncompared; 'windows' cuts them, in the order of their ids, into blocks of block_cap.
    """

    block_cap: int = 500
    key_cap: int = 80
    shrink_ratio: float = 0.9
    counting: str = "auto"
    sketch_eps: float | None = None
    sketch_confidence: float = 0.999
    sketch_seed: int = 42
    sketch_bytes: int = 256 * 2**20
    membership: str = "join"
    bloom_fpp: float = 1e-8
    shrink_on: str = "exact"
    survivor_store: str = "auto"
    pair_dedup: str = "auto"
    salvage: str = "none"
    hash: str = "md5"
    max_rounds: int = 64
    checkpoint_dir: str | None = None
    null_as_value: bool = False
    broadcast_keys: int = 2_000_000

    def __post_init__(self) -> None:
        choices = {"counting": ("auto", "sketch", "buckets", "exact", "pivot"), "salvage": ("none", "windows"), "membership": ("join", "bloom"), "shrink_on": ("exact", "estimate"), "survivor_store": ("auto", "broadcast", "join", "sketch"), "pair_dedup": ("auto", "propagate", "shuffle"), "hash": ("md5", "xx128", "h64")}
        for name, allowed in choices.items():
            if getattr(self, name) not in allowed:
                raise ValueError(f"{name} must be one of {allowed}")
        if self.block_cap < 2 or self.key_cap < 2 or not 0 < self.shrink_ratio <= 1 or self.max_rounds < 1:
            raise ValueError("block_cap and key_cap must be at least 2, shrink_ratio in (0, 1], max_rounds positive")

    @property
    def shrink_thousandths(self) -> int:
        return round(self.shrink_ratio * 1000)

    def but(self, **changes) -> BlockingConfig:
        return replace(self, **changes)


#: As published: sketch and Bloom filter, estimate in the shrink test, survivors broadcast, pairs shuffled.
AS_PUBLISHED = BlockingConfig(counting="sketch", membership="bloom", shrink_on="estimate", survivor_store="broadcast", pair_dedup="shuffle")
