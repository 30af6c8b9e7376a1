"""All parameters of the mappers in one place."""

from __future__ import annotations

from dataclasses import dataclass, replace


@dataclass(frozen=True)
class Config:
    """Defaults are the published settings where there are any; the others are ours and say so.

    eps is num / den, so that bounds are exact integers.
    """

    eps_num: int = 3
    eps_den: int = 100
    seed: int = 0
    # coarsening
    coarsest_factor: int = 8
    match_target: float = 0.75
    match_rounds: int = 8  # ours: skewed vertex weights need dozens of rounds otherwise
    least_shrink: float = 0.05  # ours: a level that shrinks less ends the coarsening
    rating: str = "squared_over_product"
    levels: int = 40  # ours
    coarsening: str = "matching"  # "cluster": clusters in place of pairs, for graphs without structure
    cluster_rounds: int = 6  # ours
    cluster_share: int = 4  # ours: a cluster weighs at most this part of a block's bound, one over it
    # refinement
    patience: int = 12
    phi: float = 0.999
    max_weak: int = 2
    passes: int = 1
    rounds: int = 200  # ours: cap of all rounds of a refinement
    local_search: str = "none"  # "fm": the kernel's gain-ordered local search follows each refinement
    filter_mode: str = "nonnegative"
    relaxed_c: float = 0.25  # ours: the value is not published
    rebalance_objective: str = "cut"
    sigma_gap: int = 100
    sigma_mode: str = "scaled"  # "absolute" is the published one; bounds below the gap need "scaled"
    heavy_num: int = 3  # too heavy to move: more than 3/2 of the block's excess over the average
    heavy_den: int = 2
    # multisection
    adaptive: bool = True
    # initial mapping
    initial: str = "direct"
    restarts: int = 1  # ours
    # below so many directed edges a level is finished by the small-graph kernel, in one task
    small_edges: int = 400_000

    def but(self, **changes) -> Config:
        return replace(self, **changes)


#: The deep variants repeat the whole refinement so often.
DEEP_PASSES = 18
