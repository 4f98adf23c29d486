"""Options of the clustering engines."""

from __future__ import annotations

from dataclasses import dataclass, replace
from fractions import Fraction

DEFAULT_PHI = (Fraction(3, 4),) * 4 + (Fraction(1, 4),) * 2


@dataclass(frozen=True)
class Options:
    """phi holds one temperature per pass. Graphs of up to kernel_limit stored edges run in one process, larger ones of up to
    state_limit vertices over blocks of edges (the vertex state is in the driver and sent out), all others on DataFrames."""

    phi: tuple = DEFAULT_PHI
    eps: tuple = (1, 10)
    symmetry: str = "replay"  # replay, none, min_label, batch, async_batches, async_min_label
    mlh_passes: str | int = "odd"  # odd, even, or n for every n-th pass
    batching: str = "degree"  # degree, color1, color2, partition
    batches: int = 4
    prune: bool = False
    kernel: str = "split"  # split, fused, fused_large_moves
    patch_threshold: float = 0.05
    salt_degree: int | None = None  # vertices of this degree and more are summed in two stages
    salt: int = 16
    gather: bool = False
    uncoarsen: bool = True
    move_at_top: bool = False
    refine_mode: str = "forest"  # forest, racy, greedy
    strict_method: str = "pairs"  # pairs, prefix
    seed: int = 0
    kernel_limit: int = 200_000
    state_limit: int = 3_000_000
    cap: int = 10_000  # movers up to which the strict move goes pair by pair; above it prefix sums
    max_levels: int = 64
    redraw_limit: int = 8

    def but(self, **changes) -> Options:
        return replace(self, **changes)

    def mlh_active(self, i: int) -> bool:
        """Whether the minimum-label rule holds in pass i (from 0)."""
        if isinstance(self.mlh_passes, int):
            return i % self.mlh_passes == self.mlh_passes - 1
        return i % 2 == (self.mlh_passes == "even")

    def batching_in_effect(self) -> str | None:
        """How a pass is cut into batches; asynchronous updates are emulated by hashed ones. None: all at once."""
        return {"batch": self.batching, "async_batches": "partition", "async_min_label": "partition"}.get(self.symmetry)


ZERO_PHI = (Fraction(0),) * 6
ABLATIONS = {
    "default": Options(),
    "one_way": Options(uncoarsen=False),
    "one_way_double": Options(uncoarsen=False, phi=(Fraction(3, 4),) * 8 + (Fraction(1, 4),) * 4),
    "no_symmetry": Options(symmetry="none", phi=ZERO_PHI),
    "no_annealing": Options(phi=ZERO_PHI),
    "min_label": Options(symmetry="min_label", phi=ZERO_PHI),
    "fused_large_moves": Options(kernel="fused_large_moves", patch_threshold=0.03),
    "fused": Options(kernel="fused"),
    "gathered": Options(gather=True),
}
