"""Choice of strategy from sizes, and how it is explained."""

from __future__ import annotations

from dataclasses import dataclass

#: Pairs of voxels and atoms up to which a nested-loop join is chosen; it scores
#: pair by pair, and broadcasts the atoms, which are no more than this many.
JOIN_PAIRS = 100_000
#: Rank up to which the normal operator goes through a kernel per cell.
KERNEL_RANK = 24
#: Grid edge up to which iterations run as plans of joins, and beyond which a
#: slice is too large for one task.
RELATIONAL_EDGE, TASK_EDGE = 16, 4096
#: Sequence length up to which the Gram matrix is made by sums of pairs.
SQL_GRAM = 64


@dataclass(frozen=True)
class Plan:
    matching: str
    normal: str
    reconstruction: str
    gram: str

    def explain(self) -> str:
        return f"matching: {self.matching}\nnormal operator: {self.normal}\nreconstruction: {self.reconstruction}\nGram matrix: {self.gram}"


def choose(voxels: int, atoms: int, rank: int, edge: int, length: int, accelerate: bool = False) -> Plan:
    """Strategies for a problem of this size.

    A dictionary goes to all tasks only while it is one: its size is that of the
    parameter grid, which the caller states here.
    """
    if voxels * atoms <= JOIN_PAIRS:
        matching = "nested-loop join"
    else:
        matching = "group search" if accelerate else "blocked products"
    reconstruction = "joins" if edge <= RELATIONAL_EDGE else "one task per slice" if edge <= TASK_EDGE else "tiles"
    return Plan(matching, "kernel per cell" if rank <= KERNEL_RANK else "mask times basis", reconstruction, "sums of pairs" if length <= SQL_GRAM else "packed rows")


def match(voxels, atoms, score: str = "modulus", interleaved: bool = False, accelerate: bool = False):
    """Matching by the chosen strategy; both sides are counted, not assumed."""
    from ..operators import matching as m

    n, k = voxels.count(), atoms.count()
    width = len(atoms.first()["x"]) if k else 0
    plan = choose(n, k, width, 0, width, accelerate)
    if plan.matching == "nested-loop join":
        return m.exhaustive_join(voxels, atoms, score)
    if plan.matching == "group search":
        return m.group(voxels, atoms)
    return m.exhaustive_blocks(voxels, atoms, score, interleaved)
