"""Settings of a partitioning run, and the presets of the method and its rivals."""

from __future__ import annotations

from dataclasses import dataclass, replace


@dataclass(frozen=True)
class PartitionConfig:
    """Defaults are the full pipeline's."""

    preset: str = "full"
    #: cluster (label propagation), matching, or auto (matching for meshes).
    coarsening: str = "cluster"
    sequential_lp: bool = False
    quota: bool = False
    cluster_factor: int = 5
    coarsest_min: int = 100
    coarsest_per_block: int = 20
    min_shrink: float = 0.05
    max_levels: int = 40
    lp_rounds_coarsen: int = 10
    lp_rounds_refine: int = 25
    sub_rounds: int = 4
    stay_on_tie: bool = True
    packet: int | None = None
    trials: int = 4
    growth_starts: int = 4
    #: Starts are polished by flows between blocks; ``flow`` does so on every level too.
    flow_start: bool = False
    flow: bool = False
    #: lp+mts, lp, mts, fm, hill or greedy.
    refiner: str = "lp+mts"
    global_rounds: int = 3
    alpha: float = 0.10
    nested: bool = True
    stop_a: float = 1.0
    stop_b: float | None = None
    mark: str = "on_move"
    gain_mode: str = "recompute"
    store: str = "dict"
    ball_radius: int = 2
    max_steps_per_pe: int = 0
    replay_limit: int = 1_000_000
    two_hop: bool = False
    match_rounds: int = 6
    #: auto, local or distributed; auto takes the kernels below local_arc_limit arcs.
    execution_mode: str = "auto"
    local_arc_limit: int = 2_000_000
    #: Phases that use p PEs; the others use one.
    parallel: frozenset[str] = frozenset({"coarsen", "init", "refine"})


PRESETS: dict[str, PartitionConfig] = {
    "full": PartitionConfig(sub_rounds=16, growth_starts=8, flow_start=True),
    "seq_lp": PartitionConfig(preset="seq_lp", sequential_lp=True, refiner="lp", parallel=frozenset()),
    "dist_lp": PartitionConfig(preset="dist_lp", quota=True, lp_rounds_coarsen=3, lp_rounds_refine=6, refiner="lp"),
    "matching": PartitionConfig(preset="matching", coarsening="matching", refiner="hill"),
    "matching_greedy": PartitionConfig(preset="matching_greedy", coarsening="matching", refiner="greedy"),
}


def config(preset: str = "full", **changes) -> PartitionConfig:
    if preset not in PRESETS:
        raise ValueError(f"no preset {preset}; there are {', '.join(PRESETS)}")
    return replace(PRESETS[preset], **changes)
