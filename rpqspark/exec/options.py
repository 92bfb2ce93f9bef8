"""Options and counters of an evaluation."""

from __future__ import annotations

from dataclasses import dataclass, field


@dataclass(frozen=True)
class RpqOptions:
    #: auto, kernel (one job over a broadcast edge table of checked size), frontier (one job a round), joins,
    #: ring (one job over a broadcast shard of the cyclic index, of checked size).
    executor: str = "auto"
    #: States in one word of a mask, and bits of a chunk of the transition tables.
    mask_bits: int = 63
    chunk_bits: int = 8
    #: Edges that the kernel, or a shard of the index, takes at most; they are sent to every task.
    kernel_edges: int = 2_000_000
    #: Parts into which the origins of two open ends are dealt, each with frontier rounds of its
    #: own; 0: as many as keep origins x nodes of a part under ``most_state``.
    origin_chunks: int = 0
    most_state: int = 20_000_000_000
    #: Rows of a frontier that are sent to the edges at most; a larger one is shuffled with them.
    broadcast_rows: int = 100_000
    #: The ring beyond one shard: on the index all the same, of the labels of the path, and if that is over
    #: one shard too, in rounds over many. If not set, the planner picks another executor.
    index_only: bool = False
    limit: int | None = None
    timeout_s: float | None = None
    #: auto, forward (from s), backward (from o).
    direction: str = "auto"
    #: The sequence of visits in a task of the kernel: bfs or dfs. The answers are the same.
    visit: str = "bfs"
    #: v-to-v on the frontier: split at a label that has so many times fewer edges than the ends; 0: never.
    rare_times: int = 4
    #: v-to-v: objects or subjects are looked up first.
    order: str = "subjects"
    #: v-to-v: phase two only enters what phase one marked.
    prune: bool = True
    #: c-to-c: both ends at once.
    bidirectional: bool = False
    #: Constants that are no node of the graph: no answer, or the empty path.
    zero_length_unknown: str = "empty"
    # Ablations.
    fast_paths: bool = True
    label_pruning: bool = True
    merge_states: bool = True
    visited_pruning: bool = True
    range_start: bool = True
    #: Rounds at most; a traversal ends by itself after the longest product path.
    most_rounds: int = 100_000


@dataclass
class RunStats:
    """Work of one evaluation."""

    rounds: int = 0
    frontier_rows: int = 0
    candidate_rows: int = 0
    states: int = 0
    edges: int = 0
    labels_read: int = 0
    labels_pruned: int = 0
    fast_path: str = ""
    extra: dict = field(default_factory=dict)

    @property
    def states_per_visit(self) -> float:
        return self.states / max(1, self.frontier_rows)
