"""What to build: the parameters of a band filter."""

from __future__ import annotations

from dataclasses import dataclass, replace

WIDTHS = (16, 32, 64, 128)
VARIANTS = ("standard", "homogeneous", "balanced")
LAYOUTS = ("icm", "row", "column")
SHARDINGS = ("hash", "fixed_bytes", "until_failure", "soft")


@dataclass(frozen=True)
class FilterSpec:
    """variant, band width w, result bits r (may be fractional), eps = (m-n)/n (None: recommended), edge inflation.

    retry: what a segment does when its system has no solution, "reseed" or "grow" (m by (w+1)/w).
    free_rule: how empty rows are filled: zero, odd_multiple, xxhash, or auto (zero; xxhash for homogeneous).
    layout: how the solution is stored and probed: interleaved column-major words, rows, or columns.
    sharding: "hash" segments of about segment_keys keys; "fixed_bytes", segments of one size whose result width follows from
    their keys; "until_failure", ranges of a hash that end with the first key that does not fit shard_rows rows;
    "soft", ranges of one system, each with a seed of its own. shard_rows: w^2/4 if None.
    step: sizes m are rounded up to powers of it, so that many systems share a size (1: not).
    redundant: what a static or standard build does with equations that say nothing new, "ignore" or "fail".
    """

    variant: str = "homogeneous"
    w: int = 64
    r: float = 7.0
    eps: float | None = None
    edge: int = 1
    layout: str = "icm"
    seeds: int = 16
    segment_keys: int = 1 << 16
    max_fail: float = 0.05
    retry: str = "reseed"
    free_rule: str = "auto"
    alpha: float | None = None
    sharding: str = "hash"
    shard_rows: int | None = None
    redundant: str = "ignore"
    step: float = 1.0

    def __post_init__(self):
        if self.variant not in VARIANTS or self.w not in WIDTHS:
            raise ValueError(f"variant is one of {VARIANTS}, w one of {WIDTHS}")
        if not 1 <= self.r <= 62:
            raise ValueError("r is 1 to 62")
        if self.retry not in ("reseed", "grow") or self.free_rule not in ("auto", "zero", "odd_multiple", "xxhash") or self.redundant not in ("ignore", "fail"):
            raise ValueError("unknown retry, free_rule or redundant")
        if self.layout not in LAYOUTS or self.sharding not in SHARDINGS:
            raise ValueError(f"layout is one of {LAYOUTS}, sharding one of {SHARDINGS}")
        if self.sharding in ("until_failure", "soft") and self.variant != "standard":
            raise ValueError("shards that end or re-seed on failure need the standard variant, the one that can fail and is not tiered")
        if self.sharding == "fixed_bytes" and self.variant == "balanced":
            raise ValueError("fixed_bytes is for the standard and homogeneous variants")
        if self.segment_keys < 1 or self.seeds < 1 or self.edge < 0 or self.shard_rows is not None and self.shard_rows < 2 * self.w:
            raise ValueError("segment_keys and seeds are positive, edge is not negative, shard_rows is at least 2 w")

    @property
    def r_lo(self) -> int:
        return int(self.r)

    @property
    def r_hi(self) -> int:
        return int(-(-self.r // 1))

    @property
    def free(self) -> str:
        return ("xxhash" if self.variant == "homogeneous" else "zero") if self.free_rule == "auto" else self.free_rule

    def but(self, **changes) -> FilterSpec:
        return replace(self, **changes)
