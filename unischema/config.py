"""All parameters of the integration in one frozen object."""

from __future__ import annotations

from dataclasses import dataclass, replace


@dataclass(frozen=True)
class Config:
    """Thresholds and variants; every open reading of the method is a field here."""

    eps_t: int = 1
    gamma: int = 3
    q: int = 2
    bound: str = "max"  # or "self": the bound from one word's length only
    verify: str = "edit"  # or "count": trust the count filter
    anchor: str = "nearest"  # or "any"
    expand_plan: str = "frontier"  # or "binary", "meet"
    max_degree: int | None = None
    beta: float = 1.5
    resolve: str = "overlap"  # or "cover", "dense", "none"
    max_parts: int = 1000
    max_members: int = 1000
    distance: str = "path"  # or "energy" (sum of squared path lengths), "literal": what resolving goes by
    halo_policy: str = "ball"  # or "top_degree", "none"
    halo_cap: int = 16
    halo_rule: str = "combined"  # or "subtract"
    absorb: bool = True
    literal: bool = True
    semantic: bool = True
    verify_stage: str = "before"  # or "after"
    hash_seed: int = 13
    bucket_length: int = 10_000
    bucket_base: int = 1_000_000

    def but(self, **changes) -> Config:
        return replace(self, **changes)


DEFAULT = Config()
