"""Settings of an index."""

from __future__ import annotations

from dataclasses import asdict, dataclass

WHEN = ("full_data", "just_full")
SEARCHES = ("restricted", "exhaustive", "flat", "rescan")
POLICIES = ("adaptive", "binary", "binary_rr", "fullary", "dynseg")
PACKINGS = ("demotion", "none", "size", "sorted")


@dataclass(frozen=True)
class BuildParams:
    """w, bits: of the words.  th: most series in a leaf.  f_low, f_high: fan-outs aim at
    leaves that are between f_low and f_high times th full.  alpha: weight of balance in the
    score.  rho: most demoted bits of a pack, as a part of the split's.  r: children of at
    most r * th series are packed.  f: width of the border, as a part of a cell, within
    which series are copied to neighbours.  local_limit: words above which a node is split
    by aggregates over the cluster.  when: "full_data", or "just_full" to decide from the
    first th + 1 series.  search: "restricted", "exhaustive", "flat" or "rescan".
    sample: part of the words that decide.  pack_bytes: most bytes of raw values in a data
    file; leaves that are neighbours share one, and a row group of it.  levels: most splits
    from the root to a leaf (0: any number); leaves there stay over capacity.
    """

    w: int = 16
    bits: int = 8
    th: int = 10_000
    policy: str = "adaptive"
    alpha: float = 0.2
    f_low: float = 0.5
    f_high: float = 3.0
    packing: str = "demotion"
    rho: float = 0.5
    r: float = 1.0
    seed: int = 0
    f: float = 0.0
    max_copies: int = 3
    normalize: bool = True
    when: str = "full_data"
    search: str = "restricted"
    sample: float = 1.0
    skip_degenerate: bool = False
    local_limit: int = 5_000_000
    pack_bytes: int = 128 << 20
    levels: int = 0

    def __post_init__(self):
        if self.policy not in POLICIES:
            raise ValueError(f"policy: one of {POLICIES}")
        if self.packing not in PACKINGS:
            raise ValueError(f"packing: one of {PACKINGS}")
        if self.when not in WHEN:
            raise ValueError(f"when: one of {WHEN}")
        if self.search not in SEARCHES:
            raise ValueError(f"search: one of {SEARCHES}")
        if not (0 < self.f_low <= self.f_high and 0 <= self.rho <= 1 and 0 < self.r <= 1 and 0 <= self.f < 1 and self.alpha >= 0 and 0 < self.sample <= 1):
            raise ValueError("0 < f_low <= f_high; rho in [0, 1]; r and sample in (0, 1]; f in [0, 1); alpha at least 0")
        if self.max_copies < 0 or self.local_limit < 1 or self.pack_bytes < 1:
            raise ValueError("max_copies: at least 0; local_limit and pack_bytes: at least 1")
        if self.levels < 0 or self.levels and (self.policy == "dynseg" or self.packing == "sorted"):
            raise ValueError("levels: at least 0, and 0 for trees that do not split on words")
        if self.packing == "sorted" and (self.policy != "adaptive" or self.f):
            raise ValueError("the sorted packing cuts words in their order: it has no splits, so no policy and no copies")
        if not (1 <= self.w <= 20 and 1 <= self.bits <= 8 and self.th >= 1):
            raise ValueError("w: 1 to 20, bits: 1 to 8, th: at least 1")

    def asdict(self) -> dict:
        return asdict(self)
