"""Settings of a search, all in one frozen record."""

from __future__ import annotations

from dataclasses import dataclass, replace

MAX_SIDES = 8
#: The road class of a bridge block is its number of vertices.
BRIDGE_KIND = 2


@dataclass(frozen=True)
class SearchParams:
    """k answers at most, score threshold theta, community radius (milli-units)."""

    k: int = 10
    theta: float = 0.6
    radius: int = 1000
    max_sides: int = MAX_SIDES
    normalize: bool = True
    n_mode: str = "query"  # kinds counted in the mean: of the query, or the whole 'catalog'
    denominator: str = "query"  # 'query': by the query's blocks of a kind; 'pairs': by both sides
    bound: str = "safe"  # none, printed, safe, tight
    bound_basis: str = "unit"  # largest 'unit' vectors, or largest 'count' vectors (looser)
    count_scope: str = "block"  # candidate threshold: block or global maximum count
    use_candidates: bool = True
    use_distance_stop: bool = True
    use_tree: bool = False
    exclude_home: bool = False
    distinct_sets: bool = False  # of homes with equal block sets, the nearest alone answers
    connected: bool = False  # communities keep the blocks that hang together with their home
    reach: str = "boundary"  # corridor: distance to a block's 'boundary' and interior, or to its 'vertex' set
    anchor_xy: tuple[int, int] | None = None
    anchor: str = "fixed"  # corridor: fixed, start, mid, or the 'moving' centre
    fanout: int = 16
    packing: str = "zorder"  # or 'str', slices and runs of equal counts

    def __post_init__(self):
        if self.k < 1:
            raise ValueError("k must be 1 at least")
        if self.theta < 0:
            raise ValueError("theta must not be negative")
        if self.radius <= 0:
            raise ValueError("radius must be positive")
        if self.anchor == "moving" and self.anchor_xy is not None:
            raise ValueError("distances are measured from anchor_xy or from the moving centre")
        for name, allowed in (("n_mode", ("query", "catalog")), ("denominator", ("query", "pairs")), ("bound", ("none", "printed", "safe", "tight")), ("bound_basis", ("unit", "count")), ("count_scope", ("block", "global")), ("reach", ("boundary", "vertex")), ("anchor", ("fixed", "start", "mid", "moving")), ("fanout", (4, 16, 64, 256)), ("packing", ("zorder", "str"))):
            if getattr(self, name) not in allowed:
                raise ValueError(f"{name} must be one of {allowed}")

    @property
    def fanout_bits(self) -> int:
        return self.fanout.bit_length() - 1

    @property
    def kinds(self) -> list[int]:
        return list(range(BRIDGE_KIND, self.max_sides + 2))

    def but(self, **changes) -> SearchParams:
        return replace(self, **changes)
