"""Options of a search."""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass, replace


@dataclass(frozen=True)
class Options:
    """How a width search runs; the defaults are exact and make use of every exact reduction that pays.

    clique      vertices that are never removed: 'max' (the lexicographically first maximum
                clique), 'greedy', 'none', or a tuple of vertices
    clique_on   'input', or 'augmented': the clique is looked for again in the graph with the
                forced edges of each k
    augment     add forced edges for each k (pairs with more than k disjoint paths)
    early_stop  stop when k + 1 vertices remain
    k0          'clique' (clique size - 1) or a number
    k_max       last k that is tried, or None
    dedup       'exact', 'bloom' or 'none' (at most 9 vertices)
    bloom_bits, bloom_hashes   size of the Bloom filter per item, and its hash functions
    combine     fold repeats inside a task before the shuffle
    mmw         'off', 'min' or 'second': drop states by the contraction bound
    mmw_impl    'explicit' (a copy of the remaining graph) or 'implicit' (degrees and disjoint sets)
    capacity    most states of a level; the surplus is dropped by hash order, the same for every run
    kernel      'prefix', 'remove', 'parts', 'search' or 'expr'
    adjacency   'literal' (in the task's code), 'broadcast' or 'join' (as a column)
    local_limit states up to which a level runs on the driver; no result depends on it
    task_limit  states of a level up to which a graph is searched inside one task; beyond it the graph gets a walk of its own
    batch_rows  states per kernel block, None: by the number of vertices
    partitions  shuffle partitions of a level, None: the session's
    """

    clique: str | tuple[int, ...] = "max"
    clique_on: str = "input"
    augment: bool = False
    early_stop: bool = True
    k0: str | int = "clique"
    k_max: int | None = None
    dedup: str = "exact"
    bloom_bits: int = 24
    bloom_hashes: int = 17
    combine: bool = True
    mmw: str = "off"
    mmw_impl: str = "explicit"
    capacity: int | None = None
    kernel: str = "prefix"
    adjacency: str = "literal"
    local_limit: int = 2_000_000
    task_limit: int = 1_000_000
    batch_rows: int | None = None
    partitions: int | None = None

    def block(self, n: int) -> int:
        """States per kernel block: as many as keep a block's masks in a core's cache."""
        return self.batch_rows or (2048 if n > 32 and self.kernel != "prefix" else 8192)

    def json(self) -> str:
        return json.dumps(asdict(self), sort_keys=True)

    def but(self, **changes) -> Options:
        return replace(self, **changes)
