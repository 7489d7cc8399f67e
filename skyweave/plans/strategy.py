"""Choice of execution strategy from stated sizes."""

from __future__ import annotations

from dataclasses import dataclass

BROADCAST_BUDGET = 256 << 20


@dataclass(frozen=True)
class Strategy:
    """How map vectors meet the sample blocks."""

    kind: str
    bytes_needed: int
    budget: int

    def explain(self) -> str:
        way = "vectors on the driver, broadcast per product" if self.kind == "broadcast" else "vectors as tables, joined to the blocks' pixel lists"
        return f"{self.kind}: {way}; {self.bytes_needed} bytes against a budget of {self.budget}"


def choose(n_pix: int, nstokes: int, rank: int = 0, budget: int = BROADCAST_BUDGET) -> Strategy:
    need = n_pix * nstokes * 8 * (2 + rank)
    return Strategy("broadcast" if need <= budget else "shuffle", need, budget)


def halo_overhead(length: int, lambda_: int) -> float:
    """Share of samples read twice when intervals are cut into chunks of ``length`` with a halo of ``lambda_`` on both sides."""
    return 2.0 * lambda_ / max(1, length)
