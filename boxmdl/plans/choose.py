"""Which plan to use for a step, from counts that are known when it starts.

The limits keep what is collected or broadcast bounded: beyond them the
distributed plans run, with the same results.
"""

from __future__ import annotations

#: Cells whose neighbours are found by a plain join of all pairs, with one side broadcast.
ALL_PAIRS_CELLS = 2_000
#: Bytes of cell positions that are sent to every task at once when neighbours are looked for; more are sent block by block.
NEIGHBOR_BLOCK_BYTES = 64 << 20
#: Patterns up to which mining rounds run on the driver (their boxes take some 110 MB in five attributes), and their number times that of the attributes.
LOCAL_PATTERNS, LOCAL_SIDES = 1_200_000, 12_800_000
#: Candidate pairs that the local kernel may hold (8 bytes each at rest, some 100 while a round sorts them); more stay in tasks.
LOCAL_CANDIDATES = 1_500_000
#: Edges left in a matching on DataFrames from which the driver goes on (some 100 bytes each).
MATCHING_LOCAL = 100_000
#: Cells up to which every pair may be a candidate.
EVERY_PAIR_CELLS = 10_000
#: Patterns up to which the driver itself looks for pruning candidates; beyond, tasks do.
PRUNE_LOCAL = 1_000
#: Pairs that a search for pruning candidates keeps for the next ones (16 bytes each), if `top_n` is not more.
PRUNE_PAIRS = 50_000
#: Patterns above which pruning is left out, with a warning, for who sets it; by default it never is.
PRUNE_PATTERNS: int | None = None


def knn_plan(n_cells: int) -> str:
    """'broadcast' for few cells, else 'tiled'; both exact.  The approximate plan runs by name only."""
    return "broadcast" if n_cells <= ALL_PAIRS_CELLS else "tiled"


def unpruned(n_patterns: int) -> bool:
    return PRUNE_PATTERNS is not None and n_patterns > PRUNE_PATTERNS


def most_pairs(n_patterns: int) -> int:
    return n_patterns * (n_patterns - 1) // 2


def rounds_plan(n_patterns: int, n_edges: int, scope: str = "inherited", requeue: bool = False, n_attrs: int = 1) -> str:
    """'local' (patterns and candidates on the driver), 'tasks' (only the patterns) or 'distributed' (neither)."""
    if n_patterns > min(LOCAL_PATTERNS, LOCAL_SIDES // n_attrs):
        return "distributed"
    if n_edges <= LOCAL_CANDIDATES and (scope != "all" or most_pairs(n_patterns) <= LOCAL_CANDIDATES):
        return "local"
    return "distributed" if scope == "all" and requeue else "tasks"
